"""Substring dedup by fixed-block anchors.

A repeat is a window of ``window`` words that also starts in a document with a smaller id. Any such window holds a
whole aligned block of half its length, so it is enough to index each document's non-overlapping blocks and to probe the
index with every rolling block of every document:

1. Blocks and probes are dealt out by hash, packed per slice of documents (5 bytes of hash and about one of the
   document's number each). In a bucket the index comes first and is reduced to one entry per block, with its least
   document and whether another has it; probes then stream past it. A block that two documents have is an anchor.
2. Documents with anchors are read again, in the order of their ids. Windows around anchors are hashed to 128 bits and
   dealt out by the least blocks of their two halves. Neighbours mostly share these, so they stay together, but the
   windows at the edges of a common passage, which differ in every document, are spread by what stands beside it. In a bucket
   windows arrive in document order, so the first document that shows a window is the least. Every later document's window is
   a repeat, and runs of repeats extend to the maximal ones.

   Before anything is dealt out, each slice settles what its own documents share: only the first of them goes on.
3. The runs of each document are merged and cut out of its text.

Memory in a bucket follows the number of distinct blocks or windows, not of their copies: a passage that a third of all
documents share is one entry, past which one row per slice streams. There are ``BUCKETS`` buckets per shuffle partition.

Defined cases: a null or empty text has no words; documents with a null id neither lose words nor count as earlier ones;
rows with the same id are told apart by their texts, each loses what an id smaller than its own has, and neither counts as
earlier than the other; an empty table gives an empty result; other columns are carried as they are. Ids are integers.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow import slices, text_bytes
from .store import materialise, ship
from .words import buffer_of, mix, rolling, word_hashes, word_places

WINDOW = 50
BUCKETS = 8
_LOW = np.uint64((1 << 40) - 1)


def block_words(window: int) -> int:
    """The longest block of which every window holds an aligned one."""
    return (window + 1) // 2


def _narrow(x: np.ndarray) -> tuple[int, bytes]:
    """Width and bytes of non-negative integers in the least width that holds them."""
    top = int(x.max()) if len(x) else 0
    width = next(w for w in (1, 2, 4, 8) if top < 1 << (8 * w) or w == 8)
    return width, x.astype(f"<u{width}").tobytes()


def _wide(data: bytes, width: int) -> np.ndarray:
    return np.frombuffer(data, dtype=f"<u{width}")


def _pack_ids(ids: np.ndarray) -> bytes:
    """Ascending ids: the first one, then steps."""
    width, steps = _narrow(np.diff(ids))
    return int(ids[0]).to_bytes(8, "little", signed=True) + bytes([width]) + steps


def _unpack_ids(data: bytes) -> np.ndarray:
    first = int.from_bytes(data[:8], "little", signed=True)
    steps = _wide(data[9:], data[8])
    out = np.empty(len(steps) + 1, np.int64)
    out[0] = 0
    np.cumsum(steps, dtype=np.int64, out=out[1:])
    return out + first


def _pack_hashes(h: np.ndarray) -> bytes:
    low = h & _LOW
    return low.astype("<u4").tobytes() + (low >> np.uint64(32)).astype(np.uint8).tobytes()


def _unpack_hashes(data: bytes) -> np.ndarray:
    n = len(data) // 5
    return np.frombuffer(data, dtype="<u4", count=n).astype(np.uint64) | (np.frombuffer(data, dtype=np.uint8, offset=4 * n).astype(np.uint64) << np.uint64(32))


def _bucket(h: np.ndarray, buckets: int) -> np.ndarray:
    return ((h >> np.uint64(40)) % np.uint64(buckets)).astype(np.int64)


class _Doc:
    """Word hashes of a slice's texts with ids, ordered by id."""

    def __init__(self, ids: pa.Array, texts: pa.Array, families: tuple[int, ...]):
        self.ids = ids.cast(pa.int64()).to_numpy(zero_copy_only=False)
        buf, offsets = buffer_of(texts)
        starts, ends, owner = word_places(buf, offsets)
        self.hashes = [word_hashes(buf, starts, ends, f) for f in families]
        self.owner = owner
        counts = np.bincount(owner, minlength=len(self.ids))
        self.first = np.cumsum(counts) - counts
        self.place = np.arange(len(owner)) - self.first[owner] if len(owner) else owner

    def blocks(self, block: int) -> tuple[np.ndarray, np.ndarray]:
        """Block hash at each word where one starts, and those words' numbers."""
        h = rolling(self.hashes[0], block)
        at = np.flatnonzero(self.owner[: len(h)] == self.owner[block - 1 :]) if len(h) else np.zeros(0, np.int64)
        return h[at], at


_BLOBS = T.StructType([T.StructField("bucket", T.IntegerType()), T.StructField("kind", T.IntegerType()), T.StructField("ids", T.BinaryType()), T.StructField("hashes", T.BinaryType())])


def _anchor_blobs(rows: DataFrame, window: int, buckets: int) -> DataFrame:
    block = block_words(window)

    def parts(h: np.ndarray, ids: np.ndarray, kind: int, out: list, b: np.ndarray | None = None) -> None:
        if not len(h):
            return
        b = _bucket(h, buckets) if b is None else b
        order = np.lexsort((h & _LOW, ids, b))
        h, ids, b = h[order], ids[order], b[order]
        cuts = np.flatnonzero(np.diff(b)) + 1
        for i, k in zip([0, *cuts], [*cuts, len(h)], strict=True):
            out.append((int(b[i]), kind, _pack_ids(ids[i:k]), _pack_hashes(h[i:k])))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "_text"):
                d = _Doc(batch.column("_id"), text_bytes(batch.column("_text")), (0,))
                h, at = d.blocks(block)
                if not len(h):
                    continue
                owner = d.owner[at]
                long = np.bincount(d.owner, minlength=len(d.ids))[owner] >= window
                h, at, owner = h[long], at[long], owner[long]
                ids, aligned = d.ids[owner], d.place[at] % block == 0
                # one row per block and document, with whether it is aligned anywhere in it
                order = np.lexsort((~aligned, ids, h))
                h, ids, aligned = h[order], ids[order], aligned[order]
                keep = np.ones(len(h), bool)
                keep[1:] = (h[1:] != h[:-1]) | (ids[1:] != ids[:-1])
                h, ids, aligned = h[keep], ids[keep], aligned[keep]
                head = np.ones(len(h), bool)
                head[1:] = h[1:] != h[:-1]
                first = np.flatnonzero(head)
                many = np.diff(np.append(first, len(h)))
                shared = np.repeat(many > 1, many)
                out: list[tuple] = []
                # blocks that documents of this slice share are anchors already: two of these are indexed for the others
                two, last = first[many > 1], (first + many - 1)[many > 1]
                alone = ~shared & aligned
                parts(np.concatenate([h[two], h[last], h[alone]]), np.concatenate([ids[two], ids[last], ids[alone]]), 0, out)
                parts(h[~shared], ids[~shared], 1, out)
                known = np.full(int(shared.sum()), int(mix(ids[:1].astype(np.uint64))[0] % np.uint64(buckets)) if len(ids) else 0)
                parts(h[shared], ids[shared], 2, out, known)
                if out:
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(c, type=t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)], names=_BLOBS.names
                    )

    return rows.where("_id is not null").mapInArrow(work, _BLOBS)


def _anchors(blobs: DataFrame) -> DataFrame:
    """(id, h): the 40-bit hashes of a document's anchors."""
    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("h", T.LongType())])

    class Index:
        """Blocks of a bucket with their least and largest document; parts are merged before they grow large."""

        def __init__(self):
            self.parts, self.held, self.h = [], 0, None

        def add(self, ids, h):
            self.parts.append((h, ids, ids))
            self.held += len(h)
            if self.held > 1 << 20:
                self._merge()

        def _merge(self):
            h, low, high = (np.concatenate([p[k] for p in self.parts]) for k in range(3)) if self.parts else (np.zeros(0, np.uint64), *[np.zeros(0, np.int64)] * 2)
            order = np.argsort(h, kind="stable")
            h, low, high = h[order], low[order], high[order]
            at = np.flatnonzero(np.append(True, h[1:] != h[:-1])) if len(h) else np.zeros(0, np.int64)
            self.parts = [(h[at], np.minimum.reduceat(low, at), np.maximum.reduceat(high, at))] if len(h) else []
            self.held = len(at)

        def close(self):
            self._merge()
            self.h, self.least, high = self.parts[0] if self.parts else (np.zeros(0, np.uint64), *[np.zeros(0, np.int64)] * 2)
            self.many, self.told, self.parts = high != self.least, np.zeros(len(self.h), bool), []

        def probe(self, ids, h):
            if not len(self.h):
                return ids[:0], h[:0]
            at = np.minimum(np.searchsorted(self.h, h), len(self.h) - 1)
            hit = (self.h[at] == h) & (self.many[at] | (self.least[at] != ids))
            at = at[hit]
            owner = np.unique(at[~self.many[at] & ~self.told[at]])
            self.told[owner] = True
            return np.concatenate([ids[hit], self.least[owner]]), np.concatenate([h[hit], self.h[owner]])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, index = None, Index()
        for batch in batches:
            found = []
            for b, kind, ids, h in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3), strict=True):
                if b != now:
                    now, index = b, Index()
                ids, h = _unpack_ids(ids.as_py()), _unpack_hashes(h.as_py())
                if kind == 0:
                    index.add(ids, h)
                    continue
                if kind == 2:
                    found.append((ids, h))
                    continue
                if index.h is None:
                    index.close()
                found.append(index.probe(ids, h))
            if found:
                ids, h = (np.concatenate([f[k] for f in found]) for k in (0, 1))
                if len(ids):
                    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(h.astype(np.int64))], names=["id", "h"])

    return blobs.repartition("bucket").sortWithinPartitions("bucket", "kind").mapInArrow(work, schema)


_WINDOWS = T.StructType([
    T.StructField("bucket", T.IntegerType()), T.StructField("first", T.LongType()), T.StructField("ids", T.BinaryType()), T.StructField("keys", T.BinaryType()),
    T.StructField("counts", T.BinaryType()), T.StructField("places", T.BinaryType()), T.StructField("hashes", T.BinaryType()),
])
_WINDOWS_ARROW = (pa.int32(), pa.int64(), *[pa.binary()] * 5)


def _runs(rows: np.ndarray, places: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, start, length) of the runs of consecutive places, ordered by row."""
    order = np.lexsort((places, rows))
    rows, places = rows[order], places[order]
    head = np.ones(len(rows), bool)
    head[1:] = (rows[1:] != rows[:-1]) | (places[1:] > places[:-1] + 1)
    at = np.flatnonzero(head)
    ends = np.append(at[1:], len(rows)) - 1
    return rows[at], places[at], places[ends] - places[at] + 1


def _window_blobs(candidates: DataFrame, window: int, buckets: int) -> DataFrame:
    """Windows that hold an anchor, packed per bucket; batches come in the order of ids."""
    block = block_words(window)
    reach = window - block + 1

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "_text"):
                d = _Doc(batch.column("_id"), text_bytes(batch.column("_text")), (0, 1))
                keys = batch.column("_key").to_numpy()
                h, at = d.blocks(block)
                if not len(h):
                    continue
                # anchors of the same document, by (document, hash)
                known = batch.column("anchors")
                counts = pa.compute.list_value_length(known).to_numpy(zero_copy_only=False)
                key = np.repeat(np.arange(len(d.ids)), counts).astype(np.uint64)
                values = known.flatten().to_numpy(zero_copy_only=False).astype(np.uint64)
                want = np.unique(mix(values + (key << np.uint64(41))))
                have = mix((h & _LOW) + (d.owner[at].astype(np.uint64) << np.uint64(41)))
                spot = np.minimum(np.searchsorted(want, have), len(want) - 1)
                anchored = np.zeros(len(d.owner) + reach, np.int64)
                anchored[at[want[spot] == have] + 1] = 1
                anchored = np.cumsum(anchored)  # anchors before each word
                w0, w1 = rolling(d.hashes[0], window, 0), rolling(d.hashes[1], window, 1)
                start = np.flatnonzero((d.owner[: len(w0)] == d.owner[window - 1 :]) & (anchored[reach : reach + len(w0)] > anchored[: len(w0)])) if len(w0) else np.zeros(0, np.int64)
                if not len(start):
                    continue
                value = np.full(len(d.owner) + reach, np.uint64(2**64 - 1))
                value[at] = mix(h)
                half = (reach + 1) // 2
                least = np.lib.stride_tricks.sliding_window_view(value, half).min(axis=1)
                b = _bucket(mix(least[start] + mix(least[start + reach - half])), buckets)
                row, place = d.owner[start], d.place[start]
                # what an earlier document of this slice has is a repeat already
                order = np.lexsort((d.ids[row], w1[start], w0[start]))
                same = np.zeros(len(order), bool)
                same[1:] = (w0[start][order][1:] == w0[start][order][:-1]) & (w1[start][order][1:] == w1[start][order][:-1])
                group = np.cumsum(~same) - 1
                least_id = d.ids[row[order]][np.flatnonzero(~same)][group]
                late = np.zeros(len(order), bool)
                late[order] = d.ids[row[order]] > least_id
                out = []

                def pack(bucket: int, rows: np.ndarray, places: np.ndarray, hashes: bytes | None, d=d, keys=keys, out=out) -> None:
                    head = np.flatnonzero(np.append(True, rows[1:] != rows[:-1]))
                    docs, counts = rows[head], np.diff(np.append(head, len(rows)))
                    out.append((bucket, int(d.ids[docs[0]]), _pack_ids(d.ids[docs]), keys[docs].tobytes(), counts.astype("<u4").tobytes(), places.astype("<u4").tobytes(), hashes))

                if late.any():
                    run_row, run_start, run_n = _runs(row[late], place[late])
                    pack(int(mix(d.ids[run_row[:1]].astype(np.uint64))[0] % np.uint64(buckets)), run_row, np.concatenate([run_start, run_n]), None)
                b, row, place, start = b[~late], row[~late], place[~late], start[~late]
                order = np.lexsort((place, row, b))
                b, row, place, start = b[order], row[order], place[order], start[order]
                cuts = np.flatnonzero(np.diff(b)) + 1
                for i, k in zip([0, *cuts], [*cuts, len(b)], strict=True):
                    pack(int(b[i]), row[i:k], place[i:k], np.stack([w0[start[i:k]], w1[start[i:k]]], axis=1).tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(c, type=t) for c, t in zip(zip(*out, strict=True), _WINDOWS_ARROW, strict=True)], names=_WINDOWS.names)

    return candidates.mapInArrow(work, _WINDOWS)


def _repeats(blobs: DataFrame) -> DataFrame:
    """(id, key, start, windows): runs of windows that a document with a smaller id has too."""
    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("key", T.LongType()), T.StructField("start", T.IntegerType()), T.StructField("windows", T.IntegerType())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, seen = None, {}
        for batch in batches:
            found = []
            for b, ids, keys, counts, places, pairs in zip(batch.column(0).to_pylist(), *[batch.column(c).to_pylist() for c in range(2, 7)], strict=True):
                if b != now:
                    now, seen = b, {}
                ids, keys, counts = _unpack_ids(ids), np.frombuffer(keys, dtype="<i8"), np.frombuffer(counts, dtype="<u4")
                places, row = np.frombuffer(places, dtype="<u4").astype(np.int64), np.repeat(np.arange(len(ids)), counts)
                if pairs is None:  # runs that the slice knew
                    found.append((ids[row], keys[row], places[: len(row)], places[len(row) :]))
                    continue
                set_first = seen.setdefault
                first = np.fromiter((set_first(pairs[16 * i : 16 * i + 16], d) for i, d in enumerate(ids[row].tolist())), dtype=np.int64, count=len(row))
                late = first < ids[row]
                if late.any():
                    run_row, start, n = _runs(row[late], places[late])
                    found.append((ids[run_row], keys[run_row], start, n))
            if found:
                cols = [np.concatenate([f[k] for f in found]) for k in range(4)]
                yield pa.RecordBatch.from_arrays([pa.array(c.astype(t)) for c, t in zip(cols, (np.int64, np.int64, np.int32, np.int32), strict=True)], names=schema.names)

    return blobs.repartition("bucket").sortWithinPartitions("bucket", "first").mapInArrow(work, schema)


def text_key(text: str) -> Column:
    """Tells texts of one id apart."""
    return F.xxhash64(F.col(text))


def repeated_runs(docs: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, key, runs): per document with repeats, its runs of repeated windows as structs (start word, number of windows). The key
    is ``text_key`` of its text."""
    spark = docs.sparkSession
    ship(spark)
    buckets = BUCKETS * int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = docs.select(docs[id_col].cast("long").alias("_id"), docs[text_col].alias("_text"))
    rows = rows.withColumn("_key", text_key("_text"))
    anchors = materialise(
        _anchors(_anchor_blobs(rows, window, buckets)).groupBy(F.col("id").alias("_aid")).agg(F.collect_list("h").alias("anchors")), "dedup-anchors"
    )
    # by sorting at every size: both sides grow with the corpus
    candidates = materialise(rows.join(anchors.hint("merge"), F.col("_id") == F.col("_aid")).drop("_aid"), "dedup-candidates")
    ordered = candidates.repartitionByRange("_id", "_key").sortWithinPartitions("_id", "_key")
    return materialise(
        _repeats(_window_blobs(ordered, window, buckets)).groupBy("id", "key").agg(F.collect_list(F.struct("start", "windows")).alias("runs")), "dedup-runs"
    )


def _covered(runs: list[dict], window: int, n: int) -> np.ndarray:
    """Which of n words the runs cover."""
    step = np.zeros(n + 1, np.int32)
    for r in runs:
        step[r["start"]] += 1
        step[r["start"] + r["windows"] + window - 1] -= 1
    return np.cumsum(step[:n]) > 0


#: What a row can be given; ``text`` is the document without its repeats, ``spans`` their words as (start, end).
OUTPUTS = {
    "n_words": (T.LongType(), pa.int64()),
    "n_removed": (T.LongType(), pa.int64()),
    "kept_sha256": (T.StringType(), pa.string()),
    "kept_text": (T.StringType(), pa.string()),
    "spans": (T.ArrayType(T.ArrayType(T.LongType())), pa.list_(pa.list_(pa.int64()))),
}


def remove_repeats(
    docs: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ("doc_id",),
    outputs: tuple[str, ...] = ("n_words", "n_removed", "kept_text", "spans"),
) -> DataFrame:
    """The kept columns and the outputs, per row. A cut text loses what stands from a removed word to the next kept one;
    one without repeats stays as it is (null stays null)."""
    runs = repeated_runs(docs, window, id_col, text_col).select(F.col("id").alias("_rid"), F.col("key").alias("_rkey"), "runs")
    rows = docs.select(*keep, docs[text_col].alias("_text"), docs[id_col].cast("long").alias("_id"))
    rows = rows.withColumn("_key", text_key("_text"))
    rows = rows.join(runs.hint("merge"), (F.col("_id") == F.col("_rid")) & (F.col("_key") == F.col("_rkey")), "left").drop("_rid", "_rkey", "_id", "_key")
    schema = T.StructType([*[rows.schema[c] for c in keep], *[T.StructField(o, OUTPUTS[o][0]) for o in outputs]])

    def one(raw: bytes | None, runs: list[dict] | None) -> dict:
        words = (raw or b"").split()
        if not runs:
            got = {"n_words": len(words), "n_removed": 0, "kept_text": None if raw is None else raw.decode("utf-8", "replace"), "spans": []}
            if "kept_sha256" in outputs:
                got["kept_sha256"] = hashlib.sha256(b" ".join(words)).hexdigest()
            return got
        gone = _covered(runs, window, len(words))
        kept = [w for w, g in zip(words, gone.tolist(), strict=True) if not g]
        got = {"n_words": len(words), "n_removed": int(gone.sum()), "kept_sha256": hashlib.sha256(b" ".join(kept)).hexdigest()}
        edge = np.flatnonzero(np.diff(np.concatenate([[0], gone.view(np.int8), [0]])))
        spans = list(zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True))
        got["spans"] = [list(s) for s in spans]
        if "kept_text" in outputs:
            starts, _, _ = word_places(np.frombuffer(raw, dtype=np.uint8), np.array([0, len(raw)]))
            at, parts = 0, []
            for a, b in spans:
                parts.append(raw[at : starts[a]])
                at = int(starts[b]) if b < len(starts) else len(raw)
            got["kept_text"] = b"".join([*parts, raw[at:]]).decode("utf-8", "replace")
        return got

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "_text"):
                found = [one(t.as_py(), r) for t, r in zip(text_bytes(batch.column("_text")), batch.column("runs").to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [*[batch.column(c) for c in keep], *[pa.array([f[o] for f in found], type=OUTPUTS[o][1]) for o in outputs]], names=[*keep, *outputs]
                )

    return rows.mapInArrow(work, schema)


def op7_substring_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"), outputs=("n_words", "n_removed", "kept_sha256"))


OP7_SQL = """
with d as materialized (
  select row_number() over () as rid, doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') as ws from documents
), win as materialized (
  select rid, doc_id, p, sha256(array_to_string(list_slice(ws, p, p + 49), ' ')) as h
  from (select rid, doc_id, ws, unnest(range(1, len(ws) - 48)) as p from d where len(ws) >= 50 and doc_id is not null)
), least as (select h, min(doc_id) as m from win group by h),
gone as materialized (select distinct rid, p + j as i from win join least using (h), range(50) r(j) where m < doc_id),
kept as (
  select w.rid, string_agg(w.word, ' ' order by w.i) as words
  from (select rid, unnest(ws) as word, unnest(range(1, len(ws) + 1)) as i from d) w anti join gone on gone.rid = w.rid and gone.i = w.i group by w.rid
), n as (select rid, count(*) as n from gone group by rid)
select doc_id, len(ws)::BIGINT as n_words, coalesce(n.n, 0)::BIGINT as n_removed, sha256(coalesce(kept.words, '')) as kept_sha256
from d left join kept on kept.rid = d.rid left join n on n.rid = d.rid
"""
