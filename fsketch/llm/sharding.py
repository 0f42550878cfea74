"""Proportional stratified interleaving into shards (native: DataFrame functions only).

Rows get a seeded pseudo-random order inside their source. A row of rank r among n rows has the fractional rank
(r - u) / n, where u in (0, 1) is drawn per source, so that sources of the same size don't fall on the same places; sorted by
it, each stretch of rows holds the sources in their overall proportions. The sorted sequence is cut into shards whose row counts differ by one at most (law ``rows``).

No rank is taken over a whole source or table by one task: rows are ranked in hash buckets of some thousands
and get the number of rows in earlier buckets as an offset, so one source with a third of all rows is spread like
any other.

Defined cases: a null source is a source of its own; null ids are ordered first; a null text counts as
empty; equal rows get neighbouring places; equal texts are not kept together (the mixture comes first);
an empty table gives an empty result; other columns are neither read nor returned.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .store import materialise

#: Rows that one bucket holds on average.
BUCKET_ROWS = 4096
#: Hash bits used to order the rows of a source.
KEY_BITS = 60
GROUP = 1024


def _before(counts: DataFrame, part: list[str], by: str) -> DataFrame:
    """Adds to the counts ``n`` per bucket the rows in earlier buckets of the same part, by groups of buckets first."""
    counts = counts.withColumn("_group", F.expr(f"{by} div {GROUP}"))
    groups = counts.groupBy(*part, "_group").agg(F.sum("n").alias("_gn"))
    over = Window.partitionBy(*part) if part else Window.partitionBy(F.lit(0))
    start = F.coalesce(F.sum("_gn").over(over.orderBy("_group").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    groups = groups.select(*[F.col(c).alias(f"_g_{c}") for c in part], F.col("_group").alias("_g_group"), start.alias("_start"))
    same = F.col("_group") == F.col("_g_group")
    for c in part:
        same = same & F.col(c).eqNullSafe(F.col(f"_g_{c}"))
    inner = Window.partitionBy(*part, "_group").orderBy(by).rowsBetween(Window.unboundedPreceding, -1)
    return counts.join(groups, same).select(
        *part, by, (F.col("_start") + F.coalesce(F.sum("n").over(inner), F.lit(0))).alias("_before")
    )


def assign_shards(
    docs: DataFrame, n_shards: int = 40, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text",
    seed: int = 17, bucket_rows: int = BUCKET_ROWS,
) -> DataFrame:
    """One row per input row: id, source, size (UTF-8 bytes + 16), text_crc32, shard and slot (gapless from 0)."""
    if n_shards < 1:
        raise ValueError("n_shards must be positive")
    text = F.coalesce(F.col(text_col), F.lit(""))
    # the text takes part, so that rows which share an id, or have none, are spread too
    md5 = F.md5(F.concat(F.lit(f"{seed}|"), F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.lit("|"), F.crc32(text).cast("string")))
    rows = materialise(
        docs.select(
            F.col(id_col).alias("id"), F.col(source_col).alias("source"),
            (F.octet_length(text).cast("long") + 16).alias("size"), F.crc32(text).alias("text_crc32"),
            F.conv(F.substring(md5, 1, KEY_BITS // 4), 16, 10).cast("long").alias("key"),
        ),
        "shard-rows",
    )
    sources = materialise(
        rows.groupBy("source").agg(F.count(F.lit(1)).alias("n_source"))
        .select(F.col("source").alias("s_source"), "n_source", F.expr(f"(n_source + {bucket_rows - 1}) div {bucket_rows}").alias("n_buckets")),
        "shard-sources",
    )
    total = sources.agg(F.coalesce(F.sum("n_source"), F.lit(0))).first()[0]
    with_n = rows.join(sources, F.col("source").eqNullSafe(F.col("s_source"))).drop("s_source").withColumn(
        "bucket", F.shiftrightunsigned(F.shiftrightunsigned("key", KEY_BITS - 31) * F.col("n_buckets"), 31)
    )
    order = ["key", "id", "text_crc32", "size"]
    offsets = materialise(_before(with_n.groupBy("source", "bucket").agg(F.count(F.lit(1)).alias("n")), ["source"], "bucket"), "shard-offsets")
    offsets = offsets.select(F.col("source").alias("o_source"), F.col("bucket").alias("o_bucket"), "_before")
    local = F.row_number().over(Window.partitionBy("source", "bucket").orderBy(*order))
    ranked = with_n.withColumn("_local", local).join(
        offsets, F.col("source").eqNullSafe(F.col("o_source")) & (F.col("bucket") == F.col("o_bucket"))
    )
    drawn = F.md5(F.concat(F.lit(f"{seed}|source|"), F.coalesce(F.col("source").cast("string"), F.lit(""))))
    offset = (F.conv(F.substring(drawn, 1, 12), 16, 10).cast("double") + 0.5) / F.lit(float(1 << 48))
    fraction = ((F.col("_local") + F.col("_before")).cast("double") - offset) / F.col("n_source").cast("double")
    strips = max(1, -(-total // bucket_rows))
    placed = materialise(
        ranked.select("id", "source", "size", "text_crc32", "key", fraction.alias("fraction"))
        .withColumn("strip", F.least(F.floor(F.col("fraction") * strips), F.lit(strips - 1))),
        "shard-ranked",
    )
    starts = materialise(_before(placed.groupBy("strip").agg(F.count(F.lit(1)).alias("n")), [], "strip"), "shard-starts")
    starts = starts.select(F.col("strip").alias("o_strip"), "_before")
    local = F.row_number().over(Window.partitionBy("strip").orderBy("fraction", "source", *order)) - 1
    whole = max(total, 1)
    return (
        placed.withColumn("_local", local).join(starts, F.col("strip") == F.col("o_strip"))
        .withColumn("place", F.col("_local") + F.col("_before"))
        .withColumn("shard", F.expr(f"place * {n_shards} div {whole}"))
        .select(
            F.col("id").alias(id_col), F.col("source").alias(source_col), "size", "text_crc32",
            F.col("shard").cast("int").alias("shard"),
            (F.col("place") - F.expr(f"(shard * {whole} + {n_shards - 1}) div {n_shards}")).alias("slot"),
        )
    )


def write_shards(docs: DataFrame, assigned: DataFrame, path: str, id_col: str = "doc_id") -> None:
    """Write whole rows into one folder per shard, each in slot order; ids must be unique here."""
    places = assigned.select(F.col(id_col).alias("_id"), F.col("shard").alias("_shard"), F.col("slot").alias("_slot"))
    rows = docs.join(places, F.col(id_col) == F.col("_id")).drop("_id")
    rows.repartitionByRange("_shard", "_slot").sortWithinPartitions("_shard", "_slot").write.partitionBy("_shard").parquet(path)


def op9_sharding(spark, sf_dir: str) -> DataFrame:
    out = assign_shards(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source"
    )


#: The CRC in SQL: one step per byte over the reflected polynomial's table, which is itself computed.
OP9_SQL = """
with recursive bits(i, v, k) as (
  select i::BIGINT, i::BIGINT, 0 from range(256) r(i)
  union all
  select i, case when v % 2 = 1 then xor(v // 2, 3988292384) else v // 2 end, k + 1 from bits where k < 8
), tab as (select list(v order by i) t from bits where k = 8
), summed as (
  select doc_id, source, strlen(coalesce(text, ''))::BIGINT + 16 as size,
    xor(list_reduce(list_prepend(4294967295::BIGINT, list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'),
      lambda x: ('0x' || x)::BIGINT)),
      lambda a, b: xor(a // 256, t[1 + xor(a % 256, b)])), 4294967295)::BIGINT as text_crc32
  from documents, tab
), base as (
  select *, ('0x' || substr(md5('17|' || coalesce(doc_id::VARCHAR, '') || '|' || text_crc32), 1, 15))::BIGINT as key from summed
), ranked as (
  select *, row_number() over (partition by source order by key, doc_id, text_crc32, size) as r, count(*) over (partition by source) as n from base
), placed as (
  select *, row_number() over (order by (r::DOUBLE - (('0x' || substr(md5('17|source|' || coalesce(source, '')), 1, 12))::BIGINT::DOUBLE + 0.5) / 281474976710656::DOUBLE) / n::DOUBLE, source nulls first, key, doc_id, text_crc32, size) - 1 as place, count(*) over () as total
  from ranked
)
select doc_id, size, text_crc32, 'rows' as law, (place * 40 // total)::INTEGER as shard,
  (place - ((place * 40 // total) * total + 39) // 40)::BIGINT as slot, null::INTEGER as grown_shard, source
from placed
"""
