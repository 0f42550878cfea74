"""Quality rules with adaptive thresholds (native: DataFrame functions only).

Each document gets a few counts over its whole text. Instead of fixed cutoffs, every measure is compared with
fences taken from quantile sketches per (language, source): quartiles widened by ``reach`` times the interquartile
range. The KLL sketches are mergeable: a group with fewer than ``least_rows`` documents uses the merged sketch of its
language, and that of the whole table where the language is small too. Thresholds come back as a table with one narrow
row per (language, source), which is joined to the counts.

Defined cases: a null or empty text has no words and fails the base rule; null languages and sources are groups
of their own; repeated rows are judged each; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .store import materialise

#: What separates words, and the characters counted as symbols.
SPACES = "[\\x20\\x09-\\x0D]+"
NOT_SPACE = "[^\\x20\\x09-\\x0D]"
SYMBOLS = "[#*$%&|<>]"
WINDOW = 5

#: Measure, sides judged, and the least interquartile range it is given (a measure that is mostly constant has none).
MEASURES = {
    "symbol_share": ("upper", 0.02),
    "repeat_share": ("upper", 0.05),
    "dup_lines_per_word": ("upper", 0.02),
    "mean_word_chars": ("both", 1.0),
}
SKETCH_K = 2048
LEAST_ROWS = 50
REACH = 3.0


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACES), "")


def _covered(positions: Column) -> Column:
    """Number of places that windows at these ascending positions cover together."""
    zero = F.struct(F.lit(0).alias("n"), F.lit(0).alias("end"))

    def add(acc: Column, p: Column) -> Column:
        end = p + WINDOW
        return F.struct((acc["n"] + end - F.greatest(acc["end"], p)).cast("int").alias("n"), end.cast("int").alias("end"))

    return F.aggregate(positions, zero, add, lambda acc: acc["n"])


def document_counts(docs: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("doc_id", "lang", "source")) -> DataFrame:
    """The kept columns and n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (all long)."""
    text = F.coalesce(F.col("_text"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(NOT_SPACE))
    step = docs.select(*keep, F.col(text_col).alias("_text")).withColumn("_words", words_of(F.col("_text"))).withColumn("_lines", lines)
    step = step.select(
        *keep,
        F.size("_words").alias("n_words"),
        F.length(F.array_join("_words", "")).alias("word_chars"),
        (F.length(text) - F.length(F.regexp_replace(text, SYMBOLS, ""))).alias("n_symbols"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).alias("n_dup_lines"),
        F.transform("_words", lambda w: F.xxhash64(w)).alias("_h"),
    )
    starts = F.when(F.col("n_words") >= WINDOW, F.sequence(F.lit(0), F.col("n_words") - WINDOW)).otherwise(F.array().cast("array<int>"))
    step = step.withColumn("_w", F.transform(starts, lambda i: F.xxhash64(*[F.get(F.col("_h"), i + j) for j in range(WINDOW)])))
    step = step.withColumn("_twice", F.size(F.array_distinct("_w")) < F.size("_w")).drop("_h")
    pairs = F.when(F.col("_twice"), F.array_sort(F.transform("_w", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))
    step = step.withColumn("_p", pairs).drop("_w")
    same = F.filter(
        "_p", lambda x, j: (F.get(F.col("_p"), j - 1)["h"] == x["h"]) | F.coalesce(F.get(F.col("_p"), j + 1)["h"] == x["h"], F.lit(False))
    )
    found = _covered(F.array_sort(F.transform(same, lambda x: x["i"])))
    return step.select(
        *keep,
        *[F.col(c).cast("long").alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines")],
        F.when(F.col("_twice"), found).otherwise(0).cast("long").alias("n_repeat_words"),
    )


def measures(counts: DataFrame) -> DataFrame:
    words, chars = F.greatest(F.col("n_words"), F.lit(1)).cast("double"), F.greatest(F.col("word_chars"), F.lit(1)).cast("double")
    return counts.withColumns({
        "symbol_share": F.col("n_symbols") / chars,
        "repeat_share": F.col("n_repeat_words") / words,
        "dup_lines_per_word": F.col("n_dup_lines") / words,
        "mean_word_chars": F.col("word_chars") / words,
    })


def sketches(rows: DataFrame, by: tuple[str, str], k: int = SKETCH_K) -> DataFrame:
    """One mergeable sketch per measure and group, and the group's row count."""
    return rows.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), *[F.kll_sketch_agg_double(m, F.lit(k)).alias(m) for m in MEASURES])


def thresholds(parts: DataFrame, lang_col: str, source_col: str, k: int = SKETCH_K, least_rows: int = LEAST_ROWS, reach: float = REACH) -> DataFrame:
    """Fences per (language, source) from the group's sketches, or from merged ones where the group is small."""
    merged = [F.kll_merge_agg_double(m, F.lit(k)).alias(m) for m in MEASURES]

    def fences(rows: DataFrame, prefix: str) -> list[Column]:
        out = []
        for m, (_, least) in MEASURES.items():
            low, high = F.kll_sketch_get_quantile_double(m, F.lit(0.25)), F.kll_sketch_get_quantile_double(m, F.lit(0.75))
            spread = F.greatest(high - low, F.lit(least))
            out += [(low - reach * spread).alias(f"{prefix}{m}_low"), (high + reach * spread).alias(f"{prefix}{m}_high")]
        return out

    own = parts.select(F.col(lang_col), F.col(source_col), F.col("n").alias("own_n"), *fences(parts, "own_"))
    by_lang = parts.groupBy(lang_col).agg(F.sum("n").alias("n"), *merged)
    lang = by_lang.select(F.col(lang_col).alias("_lang"), F.col("n").alias("lang_n"), *fences(by_lang, "lang_"))
    everything = by_lang.agg(*merged)
    whole = everything.select(*fences(everything, "all_"))
    names = [f"{m}_{side}" for m in MEASURES for side in ("low", "high")]
    choice = {
        n: F.when(F.col("own_n") >= least_rows, F.col(f"own_{n}")).when(F.col("lang_n") >= least_rows, F.col(f"lang_{n}")).otherwise(F.col(f"all_{n}"))
        for n in names
    }
    # the last side is always a single row
    joined = own.join(lang, F.col(lang_col).eqNullSafe(F.col("_lang"))).crossJoin(F.broadcast(whole))
    return joined.select(F.col(lang_col).alias("_t_lang"), F.col(source_col).alias("_t_source"), *[v.alias(f"_t_{n}") for n, v in choice.items()])


def judge(docs: DataFrame, id_col: str = "doc_id", lang_col: str = "lang", source_col: str = "source", text_col: str = "text",
          k: int = SKETCH_K, least_rows: int = LEAST_ROWS, reach: float = REACH) -> DataFrame:
    """Counts, measures, base_failed, kept and the names of the measures outside their fences, per document."""
    rows = materialise(measures(document_counts(docs, text_col, (id_col, lang_col, source_col))), "quality-counts")
    parts = materialise(sketches(rows, (lang_col, source_col), k), "quality-sketches")
    fences = materialise(thresholds(parts, lang_col, source_col, k, least_rows, reach), "quality-fences")
    joined = rows.join(fences, F.col(lang_col).eqNullSafe(F.col("_t_lang")) & F.col(source_col).eqNullSafe(F.col("_t_source")))
    outside = []
    for m, (sides, _) in MEASURES.items():
        bad = F.col(m) > F.col(f"_t_{m}_high")
        if sides == "both":
            bad = bad | (F.col(m) < F.col(f"_t_{m}_low"))
        outside.append(F.when(bad, F.lit(m)))
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return (
        joined.withColumn("outside", F.array_compact(F.array(*outside)))
        .withColumn("base_failed", failed)
        .withColumn("kept", ~F.col("base_failed") & (F.size("outside") == 0))
        .drop("_t_lang", "_t_source", *[f"_t_{m}_{s}" for m in MEASURES for s in ("low", "high")])
    )


def op1_quality_rules(spark, sf_dir: str) -> DataFrame:
    out = judge(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.array_join("outside", ",").alias("outside"))


def _fence_sql(level: str, by: str) -> str:
    picks = []
    for m, (_, least) in MEASURES.items():
        low, high = (f"list_sort(list({m}))[greatest(1, ceil({r} * count(*)))::BIGINT]" for r in (0.25, 0.75))
        spread = f"greatest({high} - {low}, {least}::DOUBLE)"
        picks.append(f"{low} - {REACH}::DOUBLE * {spread} as {m}_low, {high} + {REACH}::DOUBLE * {spread} as {m}_high")
    return f"{level} as (select {by + ',' if by else ''} count(*) as n, {', '.join(picks)} from m {'group by ' + by if by else ''})"


def _op1_sql() -> str:
    """The same result with exact quantiles: a sketch of up to SKETCH_K values is exact."""
    pick = lambda n: f"case when o.n >= {LEAST_ROWS} then o.{n} when l.n >= {LEAST_ROWS} then l.{n} else a.{n} end"
    bad = []
    for m, (sides, _) in MEASURES.items():
        cond = f"m.{m} > {pick(m + '_high')}" + (f" or m.{m} < {pick(m + '_low')}" if sides == "both" else "")
        bad.append(f"case when {cond} then '{m}' end")
    return f"""
with d as (
  select row_number() over () as rid, doc_id, lang, source, coalesce(text, '') as t,
    list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') as ws,
    list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) as ls
  from documents
), win as (
  select rid, p, w, count(*) over (partition by rid, w) as c from (
    select rid, unnest(range(1, len(ws) - 3)) as p, unnest(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(list_slice(ws, i, i + 4), ' '))) as w
    from d where len(ws) >= 5)
), rep as (
  select rid, count(*) as n from (select distinct rid, p + j as q from win, range(5) r(j) where c >= 2) group by rid
), c as (
  select d.rid, doc_id, lang, source, len(ws)::BIGINT as n_words, length(array_to_string(ws, ''))::BIGINT as word_chars,
    length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT as n_symbols,
    (len(ls) - len(list_distinct(ls)))::BIGINT as n_dup_lines, coalesce(rep.n, 0)::BIGINT as n_repeat_words
  from d left join rep on rep.rid = d.rid
), m as (
  select *, n_symbols / greatest(word_chars, 1)::DOUBLE as symbol_share, n_repeat_words / greatest(n_words, 1)::DOUBLE as repeat_share,
    n_dup_lines / greatest(n_words, 1)::DOUBLE as dup_lines_per_word, word_chars / greatest(n_words, 1)::DOUBLE as mean_word_chars
  from c
), {_fence_sql("own", "lang, source")}, {_fence_sql("lng", "lang")}, {_fence_sql("al", "")}
, j as (
  select m.*, array_to_string(list_filter([{', '.join(bad)}], lambda x: x is not null), ',') as outside,
    n_words < 10 or 100 * n_repeat_words > 20 * n_words as base_failed
  from m join own o on o.lang is not distinct from m.lang and o.source is not distinct from m.source
    join lng l on l.lang is not distinct from m.lang cross join al a
)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and outside = '' as kept, outside from j
"""


OP1_SQL = _op1_sql()
