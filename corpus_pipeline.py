"""The corpus pipeline: classify, drop near copies, cut repeats, decontaminate, encode.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes every stage's result as Parquet to the shared
folder and reads it back as the next one's documents. All but the last return the columns of the documents they got, whatever
these are; rows travel as one struct, so that no column of theirs can clash with what a stage adds.

Documents with a null id are classified, cut, decontaminated and encoded like others; as near copies they cannot be told
apart by id and all stay. Of rows that repeat one id and text, one stays (by the row's digest, where other columns differ); rows of one id and different texts are different
documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fsketch.llm.bpe import encode_texts
from fsketch.llm.decontamination import mark_leaks
from fsketch.llm.near_copies import keys, near_copies
from fsketch.llm.quality_classifier import THRESHOLD, fit_classifier, score_rows
from fsketch.llm.store import materialise
from fsketch.llm.substring_dedup import remove_repeats

VOCABULARY = "byte_bpe_multi_50k.tiktoken"


def _quoted(name: str) -> Column:
    return F.col(f"`{name}`")


def _packed(docs: DataFrame) -> DataFrame:
    return docs.select(F.struct(*[_quoted(c) for c in docs.columns]).alias("row"), "doc_id", "text")


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier scores below its threshold go."""
    model = fit_classifier(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score_rows(_packed(docs), model, keep=("row",)).where(F.col("score") >= THRESHOLD).select("row.*")


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (5-word similarity of 0.8 or more) stays: the one with the least id, and of several
    texts with that id the one with the least key."""
    groups = materialise(near_copies(docs).where("doc_id is not null"), "pipeline-groups")
    gone = groups.where(~F.col("stays")).select(F.col("doc_id").alias("_gone"), F.col("key").alias("_gone_key")).distinct()
    named = keys(_packed(docs), keep=("row", "doc_id"))
    kept = named.join(materialise(gone, "pipeline-gone"), (F.col("doc_id") == F.col("_gone")) & (F.col("key") == F.col("_gone_key")), "left_anti")
    n, stay = groups.count(), groups.select("doc_id", "key").distinct().count()
    if n != stay:
        order = F.md5(F.to_json("row"))
        one = kept.where("doc_id is not null").groupBy("doc_id", "key").agg(F.min_by("row", order).alias("row"))
        kept = one.select("row").unionByName(kept.where("doc_id is null").select("row"))
    return kept.select("row.*")


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated windows are cut out of the texts; n_chars follows."""
    cut = remove_repeats(_packed(docs), keep=("row",), outputs=("n_removed", "kept_text"))
    changed = F.col("n_removed") > 0
    out = {c: F.col("row")[c] for c in docs.columns}
    out["text"] = F.when(changed, F.col("kept_text")).otherwise(out["text"])
    if "n_chars" in out:
        out["n_chars"] = F.when(changed, F.length("kept_text").cast(docs.schema["n_chars"].dataType)).otherwise(out["n_chars"])
    return cut.select(*[v.alias(c) for c, v in out.items()])


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark text go."""
    marked = mark_leaks(_packed(docs), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), keep=("row",))
    return marked.where(F.size("leaks") == 0).select("row.*")


def byte_level_bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each text, and the digest of what they decode to."""
    import public_tokenizers

    return encode_texts(docs, public_tokenizers.path(VOCABULARY), outputs=("n_tokens", "ids", "ids_sha256", "decoded_sha256"))


STAGES = [
    ("quality classifier", quality_classifier),
    ("SimHash near-dedup", simhash_near_dedup),
    ("substring dedup", substring_dedup),
    ("benchmark decontamination", benchmark_decontamination),
    ("byte-level BPE encoding and decoding", byte_level_bpe),
]

#: SQL can express neither the fitted stages nor the hash; the tests compare each stage with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (_, stage) in enumerate(STAGES):
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{i + 1}")
    return docs
