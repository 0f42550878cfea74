"""Byte-level BPE encoding and decoding by merge ranks.

A text is split by the vocabulary's pattern. Each piece is either a token itself or is merged pair by pair: a
segment tree over its byte positions holds, for the token that starts at a position, the rank of its pair with
the next token; the root is the leftmost pair of minimum rank. A merge touches three leaves (the pair, the
token swallowed and the live left neighbour), each a logarithmic update, so a piece of n bytes costs O(n log n)
however long it is.

Trees of equal size are worked on together: the pieces of a slice that the worker does not know yet lie in one array, a row
each, and every round merges the root's pair of every row and updates the paths above the leaves it changed. Long or
rare sizes go one by one. Encoded pieces are kept in two generations of bounded size, as natural words recur: what is met
again moves from the old one to the young one.

Decoding concatenates the vocabulary's byte strings, and thus restores the text exactly.

Defined cases: a null text counts as empty and gives no tokens; bytes that are not UTF-8 are read as U+FFFD; special
tokens' strings are ordinary text; ids of repeated rows are given each; an empty table gives an empty result;
other columns are carried only if asked for. A vocabulary without all 256 single bytes is refused.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from .arrow import slices, text_bytes
from .store import ship

#: Pieces that a generation of a worker's memory holds, and the longest piece remembered.
MEMORY_PIECES = 200_000
MEMORY_PIECE_CHARS = 64
#: Pieces handled at a time.
BLOCK_PIECES = 1 << 18
#: Leaves of the trees that are worked on together, the widest such tree, and the fewest rows worth an array.
BLOCK_LEAVES = 1 << 17
WIDEST_TREE = 256
FEWEST_ROWS = 12
#: Ids that are decoded at a time.
BLOCK_IDS = 1 << 18
_NONE = 1 << 62


def merge_piece(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Token ids of one piece."""
    whole = ranks.get(piece)
    if whole is not None:
        return [whole]
    n = len(piece)
    get = ranks.get
    none = 1 << 62
    size = 1
    while size < n:
        size *= 2
    tree = [none] * (2 * size)
    for i in range(n - 1):
        r = get(piece[i : i + 2])
        if r is not None:
            tree[size + i] = r * n + i
    for at in range(size - 1, 0, -1):
        a, b = tree[2 * at], tree[2 * at + 1]
        tree[at] = a if a < b else b
    nxt = list(range(1, n + 1))  # where the token after the one that starts here starts
    prv = list(range(-1, n))
    while (top := tree[1]) != none:
        i = top % n
        j = nxt[i]
        end = nxt[j]
        nxt[i] = end
        prv[end] = i
        p = prv[i]
        changed = [(j, none)]
        if end < n:
            r = get(piece[i : nxt[end]])
            changed.append((i, none if r is None else r * n + i))
        else:
            changed.append((i, none))
        if p >= 0:
            r = get(piece[p:end])
            changed.append((p, none if r is None else r * n + p))
        for leaf, key in changed:
            at = size + leaf
            if tree[at] == key:
                continue
            tree[at] = key
            at >>= 1
            while at:
                a, b = tree[2 * at], tree[2 * at + 1]
                if b < a:
                    a = b
                if tree[at] == a:
                    break
                tree[at] = a
                at >>= 1
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : nxt[i]]])
        i = nxt[i]
    return out


def read_ranks(data: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, data.splitlines())}


class PairTable:
    """Rank of each pair of tokens whose bytes together are a token; a token's id is its rank."""

    def __init__(self, ranks: dict[bytes, int]):
        get = ranks.get
        self.byte_ids = np.array([get(bytes([b]), -1) for b in range(256)], dtype=np.int64)
        if (self.byte_ids < 0).any():
            raise ValueError("the vocabulary lacks single bytes")
        self.top = max(ranks.values()) + 1
        keys, merged = [], []
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left, right = get(token[:cut]), get(token[cut:])
                if left is not None and right is not None:
                    keys.append(left * self.top + right)
                    merged.append(rank)
        order = np.argsort(np.array(keys, dtype=np.int64))
        self.keys = np.append(np.array(keys, dtype=np.int64)[order], _NONE)
        self.merged = np.append(np.array(merged, dtype=np.int64)[order], -1)
        self.of_bytes = self.rank(np.repeat(self.byte_ids, 256), np.tile(self.byte_ids, 256)).reshape(256, 256)

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """-1 where the two don't make a token."""
        key = left * self.top + right
        at = np.searchsorted(self.keys, key)
        return np.where(self.keys[at] == key, self.merged[at], -1)


def merge_rows(pieces: list[bytes], size: int, table: PairTable) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all pieces, one after another, and how many each has. ``size``, a power of two, is no less than any piece's length."""
    n, rows, shift = np.fromiter(map(len, pieces), dtype=np.int64, count=len(pieces)), len(pieces), size.bit_length() - 1
    place = np.arange(size)
    live = place < n[:, None]
    raw = np.zeros((rows, size), np.uint8)
    raw[live] = np.frombuffer(b"".join(pieces), dtype=np.uint8)
    first = table.of_bytes[raw[:, :-1], raw[:, 1:]]
    tree = np.full((rows, 2 * size), _NONE, np.int64)
    tree[:, size:-1] = np.where((first >= 0) & live[:, 1:], (first << shift) | place[:-1], _NONE)
    width = size
    while width > 1:
        tree[:, width // 2 : width] = np.minimum(tree[:, width : 2 * width : 2], tree[:, width + 1 : 2 * width : 2])
        width //= 2
    root = tree[:, 1].copy()
    tree, token, live = tree.ravel(), table.byte_ids[raw].ravel(), live.ravel()
    following, before = (np.tile(place + k, rows) for k in (1, -1))  # starts of the neighbouring tokens
    row = np.flatnonzero(root != _NONE)
    while len(row):
        top = tree[row * 2 * size + 1]
        i, rank, base = top & (size - 1), top >> shift, row * size
        j = following[base + i]
        end = following[base + j]
        token[base + i], following[base + i], live[base + j] = rank, end, False
        right, p = end < n[row], before[base + i]
        before[(base + end)[right]] = i[right]
        left = p >= 0
        p = np.where(left, p, i)
        # ranks of the new pairs to the right and to the left
        beside = np.concatenate([token[base + np.where(right, end, i)], token[base + p]])
        both = table.rank(np.concatenate([rank, beside[len(row) :]]), np.concatenate([beside[: len(row)], rank]))
        after, ahead = both[: len(row)], both[len(row) :]
        trunk = row * 2 * size
        tree[trunk + size + j] = _NONE
        tree[trunk + size + i] = np.where(right & (after >= 0), (after << shift) | i, _NONE)
        tree[(trunk + size + p)[left]] = np.where(ahead >= 0, (ahead << shift) | p, _NONE)[left]
        at, trunk = size + np.concatenate([j, i, p]), np.tile(trunk, 3)
        for _ in range(shift):
            at >>= 1
            below = trunk + 2 * at
            tree[trunk + at] = np.minimum(tree[below], tree[below + 1])
        row = row[tree[row * 2 * size + 1] != _NONE]
    return token[live], live.reshape(rows, size).sum(axis=1)


class Coder:
    """Encoder and decoder for one vocabulary."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.table = ranks, PairTable(ranks)
        split = regex.compile(pattern)
        self.each = split.finditer
        self.split = (lambda text: [m.group() for m in split.finditer(text)]) if split.groups else split.findall
        self.young: dict[str, bytes] = {}  # piece -> packed ids (little-endian, 32 bits)
        self.old: dict[str, bytes] = {}
        by_id = [b""] * self.table.top
        for token, i in ranks.items():
            by_id[i] = token
        self.lengths = np.array([len(t) for t in by_id], dtype=np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths
        self.bytes = np.frombuffer(b"".join(by_id), dtype=np.uint8)

    def merge(self, pieces: list[bytes]) -> list[bytes]:
        """Packed ids of each piece."""
        out = [b""] * len(pieces)
        classes: dict[int, list[int]] = {}
        pack = lambda ids: np.array(ids, dtype="<u4").tobytes()
        for k, piece in enumerate(pieces):
            whole = self.ranks.get(piece)
            if whole is not None:
                out[k] = whole.to_bytes(4, "little")
            else:
                classes.setdefault(1 << (len(piece) - 1).bit_length(), []).append(k)
        for size, members in classes.items():
            if size > WIDEST_TREE or len(members) < FEWEST_ROWS:
                for k in members:
                    out[k] = pack(merge_piece(pieces[k], self.ranks))
                continue
            step = max(BLOCK_LEAVES // size, 1)
            for at in range(0, len(members), step):
                part = members[at : at + step]
                ids, counts = merge_rows([pieces[k] for k in part], size, self.table)
                packed, ends = pack(ids), (4 * np.cumsum(counts)).tolist()
                for k, a, b in zip(part, [0, *ends], ends, strict=False):
                    out[k] = packed[a:b]
        return out

    def packed(self, pieces: list[str]) -> list[bytes]:
        found = list(map(self.young.get, pieces))
        missing = [i for i, ids in enumerate(found) if ids is None]
        if missing:
            known = {piece: self.old.get(piece) for piece in {pieces[i] for i in missing}}
            fresh = [piece for piece, ids in known.items() if ids is None]
            known.update(zip(fresh, self.merge([piece.encode("utf-8", "replace") for piece in fresh]), strict=True))
            for i in missing:
                found[i] = known[pieces[i]]
            if len(self.young) + len(known) > MEMORY_PIECES:
                self.old, self.young = self.young, {}
            self.young.update((piece, ids) for piece, ids in known.items() if len(piece) <= MEMORY_PIECE_CHARS)
        return found

    def batch(self, texts: list[str]) -> list[bytes]:
        """Packed ids of each text; long texts are worked on in blocks."""
        out: list[bytes] = []
        pieces: list[str] = []
        ends: list[int] = []

        def settle() -> None:
            found = self.packed(pieces)
            out.extend(b"".join(found[a:b]) for a, b in zip([0, *ends], ends, strict=False))
            pieces.clear()
            ends.clear()

        for text in texts:
            if len(text) > BLOCK_PIECES:
                settle()
                each = (m.group() for m in self.each(text))
                parts = []
                while block := list(islice(each, BLOCK_PIECES)):
                    parts.append(b"".join(self.packed(block)))
                out.append(b"".join(parts))
                continue
            pieces += self.split(text)
            ends.append(len(pieces))
            if len(pieces) >= BLOCK_PIECES:
                settle()
        settle()
        return out

    def encode(self, text: str) -> np.ndarray:
        return np.frombuffer(self.batch([text])[0], dtype="<u4")

    def decode(self, ids: np.ndarray) -> bytes:
        parts = []
        for at in range(0, len(ids), BLOCK_IDS):
            block = ids[at : at + BLOCK_IDS]
            lengths = self.lengths[block]
            ends = np.cumsum(lengths)
            parts.append(self.bytes[np.repeat(self.starts[block] - (ends - lengths), lengths) + np.arange(ends[-1])].tobytes())
        return b"".join(parts)

    def decode_batch(self, packed: list[bytes]) -> list[bytes]:
        """The bytes that each list of packed ids stands for."""
        ids = np.frombuffer(b"".join(packed), dtype="<u4")
        whole, ends = self.decode(ids), np.concatenate([[0], np.cumsum(self.lengths[ids])])
        cuts = ends[np.cumsum([0, *[len(p) // 4 for p in packed]])].tolist()
        return [whole[a:b] for a, b in zip(cuts, cuts[1:], strict=False)]


_coders: dict[str, Coder] = {}


def coder_of(data: bytes, pattern: str) -> Coder:
    """The worker's coder for these ranks; made once per worker."""
    key = hashlib.md5(data + pattern.encode()).hexdigest()
    if key not in _coders:
        _coders[key] = Coder(read_ranks(data), pattern)
    return _coders[key]


def ranks_and_pattern(spark: SparkSession, ranks_path: str, pattern: str | None):
    """The rank file's bytes, read on the driver and broadcast: its size is fixed by the vocabulary."""
    if pattern is None:
        import public_tokenizers

        pattern = public_tokenizers.PATTERN
    ship(spark)
    with open(ranks_path, "rb") as f:
        return spark.sparkContext.broadcast(f.read()), pattern


#: What an encoder can return for each text, with the types.
OUTPUTS = {
    "n_tokens": (T.LongType(), pa.int64()),
    "ids": (T.ArrayType(T.IntegerType()), pa.list_(pa.int32())),
    "ids_sha256": (T.StringType(), pa.string()),
    "decoded": (T.BinaryType(), pa.binary()),
    "decoded_sha256": (T.StringType(), pa.string()),
}


def encode_texts(
    docs: DataFrame, ranks_path: str, pattern: str | None = None, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",),
    outputs: tuple[str, ...] = ("n_tokens", "ids"),
) -> DataFrame:
    """The kept columns and what ``outputs`` names, per row; decoded forms come from the ids, not from the text."""
    spark = docs.sparkSession
    ranks, pattern = ranks_and_pattern(spark, ranks_path, pattern)
    rows = docs.select(*keep, docs[text_col].alias("_text"))
    schema = T.StructType([*[rows.schema[c] for c in keep], *[T.StructField(o, OUTPUTS[o][0]) for o in outputs]])
    decodes = any(o.startswith("decoded") for o in outputs)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = coder_of(ranks.value, pattern)
        sha256 = lambda parts: [hashlib.sha256(p).hexdigest() for p in parts]
        for whole in batches:
            for batch in slices(whole, "_text"):
                packed = coder.batch([(raw or b"").decode("utf-8", "replace") for raw in text_bytes(batch.column("_text")).to_pylist()])
                plain = coder.decode_batch(packed) if decodes else []
                make = {
                    "n_tokens": lambda packed=packed: [len(p) // 4 for p in packed],
                    "ids": lambda packed=packed: [np.frombuffer(p, dtype="<i4") for p in packed],
                    "ids_sha256": lambda packed=packed: sha256(packed),
                    "decoded": lambda plain=plain: plain,
                    "decoded_sha256": lambda plain=plain: sha256(plain),
                }
                yield pa.RecordBatch.from_arrays(
                    [*[batch.column(c) for c in keep], *[pa.array(make[o](), type=OUTPUTS[o][1]) for o in outputs]], names=[*keep, *outputs]
                )

    return rows.mapInArrow(work, schema)


def decode_ids(
    rows: DataFrame, ranks_path: str, ids_col: str = "ids", keep: tuple[str, ...] = ("doc_id",), out_col: str = "decoded", pattern: str | None = None,
) -> DataFrame:
    """The kept columns and the bytes that each row's ids stand for; null ids give empty bytes."""
    ranks, pattern = ranks_and_pattern(rows.sparkSession, ranks_path, pattern)
    rows = rows.select(*keep, rows[ids_col].alias("_ids"))
    schema = T.StructType([*[rows.schema[c] for c in keep], T.StructField(out_col, T.BinaryType())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = coder_of(ranks.value, pattern)
        for batch in batches:
            plain = [coder.decode(np.array(x.as_py() or [], dtype=np.int64)) for x in batch.column("_ids")]
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], pa.array(plain, type=pa.binary())], names=[*keep, out_col])

    return rows.mapInArrow(work, schema)


def op4_byte_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return encode_texts(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), outputs=("n_tokens", "ids_sha256", "decoded_sha256"))
