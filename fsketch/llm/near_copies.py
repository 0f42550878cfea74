"""Near copies by similarity: texts whose sets of 5-word shingles have a Jaccard similarity of 0.8 or more.

A SimHash of 64 bits puts such pairs at up to 11 bits or so, which no affordable ball reaches. So candidates come from two
sides: fingerprints within ``radius`` bits, as in ``simhash``, and bands of minima. A text has ``BANDS`` band values, each of
``BAND_ROWS`` minima of its hashed shingles; two texts of similarity s agree in one at least with probability
1 - (1 - s^4)^16, that is 0.9998 at 0.8 and more above it. Texts that agree in a band are compared with the band's hub, a
member drawn by hash, so that the bands of a large group have different hubs; bands of few texts have two hubs. Every
candidate pair is verified by its exact similarity, and components are formed of verified pairs only.

What bands and hubs miss is found by an exact filter. All shingles have one fixed order; two texts of similarity 0.8 share a
shingle among the first n - ceil(0.8 n) + 1 of their n ones. So each text deals out these, and texts of different components that share
one and whose sizes allow it are verified too. Links within a component change nothing and are not looked for: a large
group costs its rows there, not its pairs. The order puts shingles first that a sample of the texts (one in ``COMMON_PART``, ``COMMON_TEXTS`` at
least) doesn't show to be common; it decides how many pairs are looked at, never which are found. Of these pairs, texts meet only where the
parities of their shingles' hashes allow the similarity: two sets differ in no fewer shingles than such parities.

Equal texts are one text from the start. Work beyond the rows is that of pairs of different components that share a rare shingle.

Defined cases: words are those of ``simhash`` (A-Z lower-cased, ASCII white space separates); null, empty and blank texts are
equal; texts of fewer words than a shingle are similar to equal ones only; repeated rows get one row each; null ids count
for a component only if no other id is there; an empty table gives an empty result; other columns are not returned.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow import text_bytes
from .components import connected_components, join_labels
from .simhash import SEED, fingerprint, links
from .store import materialise, ship

SHINGLE = 5
LEAST_SIMILARITY = 0.8
BANDS = 16
BAND_ROWS = 4
#: Bands of at most so many texts have a second hub.
SMALL_BAND = 64
#: Shingles whose minima are taken at a time.
BLOCK = 1 << 9
#: Texts looked at for common shingles, how often such a shingle is there at least, and the most that are told apart.
COMMON_TEXTS, COMMON_LEAST, COMMON_MOST = 4096, 3, 1 << 16
#: One in so many texts is looked at in a large table: a fixed number of them would let the pairs grow with the square of the table.
COMMON_PART = 8
#: Parity bits of a text at least; longer texts have one or two for each shingle.
LEAST_BITS = 512
#: Buckets per shuffle partition that shingles are dealt to, and pairs of a bucket held at a time.
BUCKETS, HELD_PAIRS = 8, 1 << 20

_draw = np.random.default_rng(SEED)
_MASKS = _draw.integers(0, 1 << 64, BANDS * BAND_ROWS, dtype=np.uint64)
_FACTORS = _draw.integers(0, 1 << 64, BANDS * BAND_ROWS, dtype=np.uint64) | np.uint64(1)


def words_of(text: bytes | None) -> list[bytes]:
    return (text or b"").lower().split()


def text_key(words: list[bytes]) -> str:
    """Name of all texts with these words."""
    return xxhash.xxh3_128_hexdigest(b" ".join(words), SEED)


def shingles(words: list[bytes], width: int = SHINGLE) -> set[bytes]:
    if len(words) < width:
        return {b" ".join(words)} if words else set()
    return set(map(b" ".join, zip(*[words[i:] for i in range(width)], strict=False)))


def similarity(a: set[bytes], b: set[bytes]) -> float:
    return len(a & b) / len(a | b) if a or b else 1.0


def _hashes(words: list[bytes]) -> np.ndarray:
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(s, SEED) for s in shingles(words)), dtype=np.uint64)


def band_values(found: np.ndarray) -> list[int]:
    """A signed 64-bit value per band, of the shingles' hashes."""
    least = np.full(len(_MASKS), np.iinfo(np.uint64).max, dtype=np.uint64)
    for at in range(0, len(found), BLOCK):
        mixed = (found[at : at + BLOCK, None] ^ _MASKS) * _FACTORS
        np.minimum(least, mixed.min(axis=0), out=least)
    return [xxhash.xxh64_intdigest(row.tobytes(), i) - (1 << 63) for i, row in enumerate(least.reshape(BANDS, BAND_ROWS))]


def parities(found: np.ndarray) -> bytes:
    """How many of the hashes fall into each bin, as even or odd; the number of bins is a power of two."""
    size = max(LEAST_BITS, 1 << max(len(found) - 1, 0).bit_length())
    odd = np.bincount((found % np.uint64(size)).astype(np.int64), minlength=size) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def may_be_similar(n_x: int, x: bytes, n_y: int, y: bytes) -> bool:
    """False only for sets of n_x and n_y shingles whose similarity is below 0.8: such of 0.8 or more differ in a ninth of n_x + n_y at most, and
    each shingle in which they differ turns one parity."""
    if len(x) < len(y):
        x, y = y, x
    bits, size = int.from_bytes(x, "little"), 8 * len(x)
    while size > 8 * len(y):  # the parities of half as many bins
        size //= 2
        bits = (bits >> size) ^ (bits & ((1 << size) - 1))
    return 9 * (bits ^ int.from_bytes(y, "little")).bit_count() <= n_x + n_y


def keys(docs: DataFrame, keep: tuple[str, ...], text_col: str = "text") -> DataFrame:
    """The kept columns and ``key``, the text's name."""
    ship(docs.sparkSession)
    rows = docs.select(*[docs[c] for c in keep], docs[text_col].alias("_text"))
    schema = T.StructType([*[rows.schema[c] for c in keep], T.StructField("key", T.StringType())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            named = pa.array([text_key(words_of(x.as_py())) for x in text_bytes(batch.column("_text"))], pa.string())
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], named], names=[*keep, "key"])

    return rows.mapInArrow(work, schema)


def prints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, key, fp, b0, b1, ..., size, bits) per row: the text's name, its SimHash, its band values, its number of shingles and their parities."""
    ship(docs.sparkSession)
    rows = docs.select(docs[id_col].alias(id_col), docs[text_col].alias("_text"))
    longs = ["fp", *[f"b{i}" for i in range(BANDS)]]
    schema = T.StructType([rows.schema[id_col], T.StructField("key", T.StringType()), *[T.StructField(c, T.LongType()) for c in (*longs, "size")], T.StructField("bits", T.BinaryType())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            named, sizes, bits, values = [], [], [], np.empty((len(longs), batch.num_rows), dtype=np.int64)
            for at, x in enumerate(text_bytes(batch.column("_text"))):
                text = x.as_py() or b""
                words = words_of(text)
                named.append(text_key(words))
                values[0, at] = np.uint64(fingerprint(text)).astype(np.int64)
                found = _hashes(words)
                values[1:, at] = band_values(found)
                sizes.append(len(found))
                bits.append(parities(found))
            columns = [batch.column(id_col), pa.array(named, pa.string()), *map(pa.array, values), pa.array(sizes, pa.int64()), pa.array(bits, pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, names=[id_col, "key", *longs, "size", "bits"])

    return rows.mapInArrow(work, schema)


def _paired(a: str, b: str) -> list:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def candidates(texts: DataFrame, radius: int = 2) -> DataFrame:
    """(a, b): keys of different texts, a < b, that may be similar. Texts are (key, fp, b0, b1, ...), once each."""
    hubs = materialise(texts.groupBy("fp").agg(F.min("key").alias("hub")), "near-hubs")
    equal = texts.join(hubs.hint("merge"), "fp").select(*_paired("key", "hub"))
    near = links(hubs.select("fp"), radius)
    for side in ("a", "b"):
        near = near.join(hubs.select(F.col("fp").alias(side), F.col("hub").alias(f"hub_{side}")).hint("merge"), side)
    bands = texts.select("key", F.explode(F.array(*[f"b{i}" for i in range(BANDS)])).alias("band"))
    drawn = F.struct(F.xxhash64("key", "band").alias("h"), F.col("key").alias("key"))
    met = bands.groupBy("band").agg(F.count(F.lit(1)).alias("n"), F.min(drawn)["key"].alias("lo"), F.max(drawn)["key"].alias("hi"))
    met = materialise(met.where("n > 1"), "near-met")
    ends = F.when(F.col("n") <= SMALL_BAND, F.array("lo", "hi")).otherwise(F.array("lo"))
    banded = bands.join(met.hint("merge"), "band").select("key", F.explode(ends).alias("hub")).select(*_paired("key", "hub"))
    return equal.unionByName(near.select(*_paired("hub_a", "hub_b"))).unionByName(banded).where("a <> b").distinct()


def verified(pairs: DataFrame, texts: DataFrame, least: float = LEAST_SIMILARITY) -> DataFrame:
    """The pairs (a, b) whose exact similarity is ``least`` or more. Texts are (key, text), once each."""
    for side in ("a", "b"):
        pairs = pairs.join(texts.select(F.col("key").alias(side), F.col("text").alias(f"text_{side}")).hint("merge"), side)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, kept = None, set()
        for batch in batches:
            held = []
            for b, x, y in zip(batch.column("b").to_pylist(), text_bytes(batch.column("text_a")), text_bytes(batch.column("text_b")), strict=True):
                if b != last:  # rows come in order of b
                    last, kept = b, shingles(words_of(y.as_py()))
                held.append(similarity(shingles(words_of(x.as_py())), kept) >= least)
            yield batch.select(["a", "b"]).filter(pa.array(held, pa.bool_()))

    return pairs.select("a", "b", "text_a", "text_b").mapInArrow(work, "a string, b string")


def common_shingles(held: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes, in order, of shingles that are common in a sample of the texts, and in how many of its texts each is."""
    share = min(1.0, max(COMMON_TEXTS / max(n, 1), 1 / COMMON_PART))
    few = held if share == 1 else held.where(F.col("key") < f"{int(share * (1 << 64)):016x}")  # keys are hashes

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in text_bytes(batch.column("text")):
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(_hashes(words_of(x.as_py()))).view(np.int64))], names=["h"])

    counts = few.select("text").mapInArrow(work, "h long").groupBy("h").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= COMMON_LEAST)
    found = counts.orderBy(F.col("n").desc(), "h").limit(COMMON_MOST).collect()
    h, often = np.array([r.h for r in found], np.int64).view(np.uint64), np.array([r.n for r in found], np.int64)
    order = np.argsort(h)
    return h[order], often[order]


def prefix(h: np.ndarray, common: np.ndarray, often: np.ndarray) -> np.ndarray:
    """The first shingles in the order of all, so many that a text of similarity 0.8 or more has one of them among its own."""
    level = np.zeros(len(h), np.int64)
    if len(common):
        at = np.minimum(np.searchsorted(common, h), len(common) - 1)
        level = np.where(common[at] == h, often[at], 0)
    return h[np.lexsort((h, level))[: len(h) - (4 * len(h) + 4) // 5 + 1]]


def _pairs_of(token: np.ndarray, node: np.ndarray, component: np.ndarray, n: np.ndarray) -> Iterator[np.ndarray]:
    """Pairs of nodes that share a token, have different components and sizes that allow the similarity; in parts, which may repeat pairs."""
    order = np.lexsort((n, token))
    token, node, component, n = token[order], node[order], component[order], n[order]
    begin = np.flatnonzero(np.r_[True, token[1:] != token[:-1]])
    mixed = np.minimum.reduceat(component, begin) != np.maximum.reduceat(component, begin)
    parts, size = [], 0
    for lo, hi in zip(begin[mixed], np.r_[begin[1:], len(token)][mixed], strict=True):
        last = lo + np.searchsorted(4 * n[lo:hi], 5 * n[lo:hi], side="right")
        for i in range(lo, hi - 1):
            others = node[i + 1 : last[i - lo]][component[i + 1 : last[i - lo]] != component[i]]
            parts.append(np.stack([np.minimum(others, node[i]), np.maximum(others, node[i])], axis=1))
            size += len(others)
            if size >= HELD_PAIRS:
                yield np.unique(np.concatenate(parts), axis=0)
                parts, size = [], 0
    if size:
        yield np.unique(np.concatenate(parts), axis=0)


def _may_be(pairs: DataFrame) -> DataFrame:
    """(key_x, key_y) of the pairs (key, size and bits of x and y) whose parities allow the similarity."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = [batch.column(c).to_pylist() for c in ("size_x", "bits_x", "size_y", "bits_y")]
            yield batch.select(["key_x", "key_y"]).filter(pa.array([may_be_similar(*row) for row in zip(*columns, strict=True)], pa.bool_()))

    return pairs.select(*[f"{c}_{side}" for side in ("x", "y") for c in ("key", "size", "bits")]).mapInArrow(work, "key_x string, key_y string")


def apart(held: DataFrame, member: DataFrame, n: int) -> DataFrame:
    """(a, b): keys of all texts of different components, a < b, that may be similar. Texts are (key, text), members (key, component,
    size, bits)."""
    spark = held.sparkSession
    ship(spark)
    common, often = common_shingles(held, n)
    buckets = BUCKETS * int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = held.join(member.select("key", "component").hint("merge"), "key").select(F.xxhash64("key").alias("node"), F.xxhash64("component").alias("component"), "text")

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found, sizes = [], []
            for x in text_bytes(batch.column("text")):
                h = _hashes(words_of(x.as_py()))
                found.append(prefix(h, common, often) if len(h) else h)
                sizes.append(len(h))
            counts = np.array([len(f) for f in found], np.int64)
            token = np.concatenate([np.zeros(0, np.uint64), *found])
            bucket = ((token >> np.uint64(20)) % np.uint64(buckets)).astype(np.int32)
            order = np.argsort(bucket, kind="stable")
            columns = [token[order], *[np.repeat(np.asarray(c, np.int64), counts)[order] for c in (batch.column("node").to_numpy(), batch.column("component").to_numpy(), np.array(sizes, np.int64))]]
            begin = np.flatnonzero(np.r_[True, np.diff(bucket[order]) != 0]) if len(token) else np.zeros(0, np.int64)
            ends = np.r_[begin[1:], len(token)] if len(token) else begin
            blobs = [pa.array([c[lo:hi].tobytes() for lo, hi in zip(begin, ends, strict=True)], pa.binary()) for c in columns]
            yield pa.RecordBatch.from_arrays([pa.array(bucket[order][begin]), *blobs], names=["bucket", "token", "node", "component", "n"])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def close(parts: list[list[bytes]]) -> Iterator[pa.RecordBatch]:
            columns = [np.frombuffer(b"".join(p), t) for p, t in zip(zip(*parts, strict=True), (np.uint64, np.int64, np.int64, np.int64), strict=True)]
            for pairs in _pairs_of(*columns):
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["x", "y"])

        last, parts = None, []
        for batch in batches:
            for bucket, *blobs in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if bucket != last and parts:
                    yield from close(parts)
                    parts = []
                last = bucket
                parts.append(blobs)
        if parts:
            yield from close(parts)

    dealt = rows.mapInArrow(deal, "bucket int, token binary, node binary, component binary, n binary")
    met = materialise(dealt.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(meet, "x long, y long").distinct(), "near-apart")
    for side in ("x", "y"):
        of = member.select(F.xxhash64("key").alias(side), *[F.col(c).alias(f"{c}_{side}") for c in ("key", "size", "bits")])
        met = met.join(of.hint("merge"), side)
    return _may_be(met).select(*_paired("key_x", "key_y")).where("a <> b").distinct()


def _joined(links: DataFrame, member: DataFrame) -> DataFrame:
    """The members after links (a, b) between texts of different components."""
    for side in ("a", "b"):
        links = links.join(member.select(F.col("key").alias(side), F.col("component").alias(f"of_{side}")).hint("merge"), side)
    moved = connected_components(links.select("of_a", "of_b"), "of_a", "of_b").select(F.col("node").alias("component"), F.col("component").alias("_now"))
    return member.join(moved, "component", "left").withColumn("component", F.coalesce("_now", "component")).drop("_now")


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, key, component, component_id, stays): one row per document; the component is the least key that similar pairs lead to, and
    component_id the least id of its rows (components of other texts may have it too, where an id repeats). ``stays`` says
    whether the row has that id and, of the texts with it, the one of least key."""
    rows = materialise(prints(docs, id_col, text_col), "near-prints")
    longs = [c for c in rows.columns if c not in (id_col, "key", "size", "bits")]
    found = [F.min(id_col).alias("least"), F.count(F.lit(1)).alias("n"), *[F.min(c).alias(c) for c in (*longs, "size", "bits")]]
    texts = materialise(rows.groupBy("key").agg(*found), "near-texts")
    pairs = materialise(candidates(texts.select("key", *longs)), "near-pairs")
    # one text per key before keys meet, so that copies don't travel to one task
    held = keys(docs.select(docs[text_col].alias("text")), keep=("text",)).groupBy("key").agg(F.min("text").alias("text"))
    held = materialise(held, "near-held")
    nodes = connected_components(materialise(verified(pairs, held), "near-links"))
    member = texts.select("key", "least", "n", "size", "bits").join(nodes.withColumnRenamed("node", "key"), "key", "left")
    member = materialise(member.withColumn("component", F.coalesce("component", "key")), "near-members")
    missed = materialise(verified(materialise(apart(held, member, texts.count()), "near-rest"), held), "near-missed")
    if not missed.isEmpty():
        member = materialise(_joined(missed, member), "near-joined")
    first = F.min(F.when(F.col("least").isNotNull(), F.struct("least", "key")))
    roots = materialise(member.groupBy("component").agg(first.alias("first"), F.count(F.lit(1)).alias("texts")), "near-roots")
    labels = join_labels(member.select("key", "component", "n"), roots, "component", "texts")
    labels = materialise(labels.select("key", "component", "first", "n"), "near-labels")
    least = F.col("first")["least"]
    stays = F.coalesce((F.col(id_col) == least) & (F.col("key") == F.col("first")["key"]), F.lit(False))
    out = join_labels(rows.select(id_col, "key"), labels, "key")
    return out.select(id_col, "key", "component", least.alias("component_id"), stays.alias("stays"))
