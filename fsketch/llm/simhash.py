"""SimHash near-duplicates by meeting in the middle.

A document's fingerprint has bit i set if more than half of its shingles' hashes have. Two fingerprints that differ in
at most r bits have a common neighbour within r/2 bits of both, so every distinct fingerprint emits all variants
within r/2 bits and the variants are shuffled. A variant collects at most as many fingerprints as it has neighbours
itself (65 for r = 2), and all of them are within r bits of each other: linking each to the least loses no component.
Colliding pairs are deduplicated and verified. Copies never meet: they share one fingerprint.

Defined cases: null, empty and blank texts have fingerprint zero and link like any other; shorter texts than a
shingle are hashed whole; repeated rows get one row each; null ids get a fingerprint and count for the component only if
no other id is there (it is null then); an empty table gives an empty result; other columns are not returned.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow import text_bytes
from .components import connected_components
from .store import materialise, ship

SEED = 42
BITS = 64
#: Shingles whose bits are counted at a time.
BLOCK = 1 << 14


def fingerprint(text: bytes, width: int = 3, seed: int = SEED) -> int:
    """Unsigned 64-bit fingerprint of a text in UTF-8; A-Z are lower-cased and ASCII white space separates words."""
    words = text.lower().split()
    if not words:
        return 0
    digest = xxhash.xxh64_digest
    if len(words) < width:
        return int.from_bytes(digest(b" ".join(words), seed), "big")
    n = len(words) - width + 1
    counts = np.zeros(BITS, dtype=np.int64)
    for at in range(0, n, BLOCK):
        part = words[at : min(at + BLOCK, n) + width - 1]
        joined = map(b" ".join, zip(*[part[i:] for i in range(width)], strict=False))
        hashes = b"".join([digest(s, seed) for s in joined])
        counts += np.unpackbits(np.frombuffer(hashes, dtype=np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, seed: int = SEED) -> DataFrame:
    """(id, fp): the fingerprint as a signed long, per row."""
    ship(docs.sparkSession)
    rows = docs.select(docs[id_col].alias(id_col), docs[text_col].alias("_text"))
    schema = T.StructType([rows.schema[id_col], T.StructField("fp", T.LongType())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.fromiter((fingerprint(x.as_py() or b"", width, seed) for x in text_bytes(batch.column("_text"))), dtype=np.uint64, count=batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(id_col), pa.array(found.view(np.int64))], names=[id_col, "fp"])

    return rows.mapInArrow(work, schema)


def ball(radius: int) -> list[int]:
    """Masks, as signed longs, that turn a fingerprint into all those within the radius."""
    masks = [sum(1 << b for b in bits) for k in range(radius + 1) for bits in combinations(range(BITS), k)]
    return np.array(masks, dtype=np.uint64).view(np.int64).tolist()


def links(distinct: DataFrame, radius: int = 2) -> DataFrame:
    """(a, b): verified links between distinct fingerprints (column fp) that hold every component together."""
    if radius % 2 or radius < 0:
        raise ValueError("the radius must be even: both sides emit variants within half of it")
    masks = F.array(*[F.lit(m) for m in ball(radius // 2)])
    fp = F.col("fp")
    variants = distinct.select(fp, F.explode(masks).alias("m")).select(fp, fp.bitwiseXOR(F.col("m")).alias("variant"))
    met = variants.repartition("variant").groupBy("variant").agg(F.min("fp").alias("a"), F.max("fp").alias("b"), F.count(F.lit(1)).alias("n"))
    met = materialise(met.where("n > 1"), "simhash-met")
    # where more than two met, the others are among the variant's own neighbours
    more = met.where("n > 2").select("a", "variant", F.explode(masks).alias("m")).select("a", F.col("variant").bitwiseXOR(F.col("m")).alias("b"))
    more = more.join(distinct.select(F.col("fp").alias("b")), "b").select("a", "b")
    pairs = met.select("a", "b").unionByName(more).where("a <> b").distinct()
    return pairs.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius)


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, radius: int = 2, seed: int = SEED) -> DataFrame:
    """(id, fp, component_id): one row per document; the component is the least id that can be reached by links."""
    prints = materialise(fingerprints(docs, id_col, text_col, width, seed), "simhash-prints")
    distinct = materialise(prints.groupBy("fp").agg(F.min(id_col).alias("least")), "simhash-distinct")
    nodes = connected_components(links(distinct.select("fp"), radius))
    member = distinct.join(nodes.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("component", "fp"))
    roots = member.groupBy("root").agg(F.min("least").alias("component_id"))
    labels = materialise(member.join(roots, "root").select("fp", "component_id"), "simhash-labels")
    return prints.join(labels, "fp").select(id_col, "fp", "component_id")


def op10_simhash(spark, sf_dir: str) -> DataFrame:
    out = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
