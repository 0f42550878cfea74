"""Token counts by section: each document is encoded once, whole, and its tokens are attributed to sections by offset.

Tokens and sections are both intervals of a text, so attribution is an interval join of two sorted lists, done
by binary search over the documents of a slice laid end to end. Counting sections one by one would give other tokens at their edges; here the
counts of a document's sections and of the text outside them add up to the document's count. A token that crosses a
boundary goes by an explicit rule:

- ``start``: to the section of its first character;
- ``largest``: to the section with most of its characters, the earlier one on a tie;
- ``proportional``: to every section in proportion to its characters there (counts are then fractions).

A token may begin or end inside a character (byte-level vocabularies): such a character is counted as the token's.

Sections are spans [start, end) in characters; they come from a column, from several text fields
that are joined, or from splitting at a separator, which then belongs to the section that it ends.

Defined cases: a null or empty text has one empty section (if split) with no tokens; sections of no length get none.
Given sections may come in any order; a character that several of them hold is the first one's (by start, then end, then
place in the array); what lies outside the text counts as cut off, and a section that ends before it starts as empty; null
sections and those with a null bound get no row, but the others keep their numbers. Repeated rows are counted each; an
empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow import slices, text_bytes
from .bpe import coder_of, ranks_and_pattern

RULES = ("start", "largest", "proportional")


def token_spans(coder, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First character and end (exclusive) of each token of the texts laid end to end, and the tokens of each text."""
    packed = coder.batch(texts)
    ids = np.frombuffer(b"".join(packed), dtype="<u4")
    many = np.array([len(p) // 4 for p in packed], dtype=np.int64)
    ends = np.cumsum(coder.lengths[ids])
    starts = ends - coder.lengths[ids]
    raw = "".join(texts).encode()
    if len(raw) == sum(map(len, texts)):
        return starts, ends, many
    # characters begun before each byte offset
    begun = np.zeros(len(raw) + 1, np.int32 if len(raw) < 1 << 31 else np.int64)
    np.cumsum((np.frombuffer(raw, dtype=np.uint8) & 0xC0) != 0x80, out=begun[1:])
    return (begun[starts + 1] - 1).astype(np.int64), begun[ends].astype(np.int64), many


def attribute(first: np.ndarray, last: np.ndarray, starts: np.ndarray, ends: np.ndarray, rule: str) -> np.ndarray:
    """Tokens per section; sections are sorted and disjoint. ``last`` is exclusive."""
    n = len(starts)
    counts = np.zeros(n + 1, dtype=np.float64 if rule == "proportional" else np.int64)
    if not len(first):
        return counts[:n]
    if rule == "start":
        at = np.searchsorted(starts, first, side="right") - 1
        # among sections that start at the same place only the last one has a length
        inside = (at >= 0) & (first < ends[np.maximum(at, 0)]) if n else np.zeros(len(first), bool)
        counts += np.bincount(np.where(inside, at, n), minlength=n + 1)
        return counts[:n]
    # sections met by each token: the ones that end after its start and start before its end
    low, high = np.searchsorted(ends, first, side="right"), np.searchsorted(starts, last, side="left")
    many = np.maximum(high - low, 0)
    token = np.repeat(np.arange(len(first)), many)
    section = np.arange(len(token)) - np.repeat(np.cumsum(many) - many, many) + np.repeat(low, many)
    shared = np.minimum(last[token], ends[section]) - np.maximum(first[token], starts[section])
    token, section, shared = token[shared > 0], section[shared > 0], shared[shared > 0]
    if rule == "proportional":
        share = shared / (last - first)[token]
        counts += np.bincount(section, weights=share, minlength=n + 1)
        return counts[:n]
    order = np.lexsort((section, -shared, token))
    token, section = token[order], section[order]
    head = np.ones(len(token), bool)
    head[1:] = token[1:] != token[:-1]
    counts += np.bincount(section[head], minlength=n + 1)
    return counts[:n]


def split_spans(texts: list[str], separator: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text, start and end of each section; offsets are those of the texts laid end to end."""
    lengths: list[int] = []
    many = []
    for text in texts:
        parts = text.split(separator)
        lengths += map(len, parts)
        many.append(len(parts))
    width, many = np.array(lengths, dtype=np.int64) + len(separator), np.array(many, dtype=np.int64)
    width[np.cumsum(many) - 1] -= len(separator)
    ends = np.cumsum(width)
    return np.repeat(np.arange(len(texts)), many), ends - width, ends


def given_spans(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Text, number in the text's array, start and end of each section that is not null."""
    many = pa.compute.fill_null(pa.compute.list_value_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    start, end = column.flatten().flatten()[:2]
    known = pa.compute.and_(start.is_valid(), end.is_valid()).to_numpy(zero_copy_only=False)
    bound = lambda x: pa.compute.fill_null(x, 0).cast(pa.int64()).to_numpy(zero_copy_only=False)[known]
    owner = np.repeat(np.arange(len(column)), many)
    return owner[known], (np.arange(len(owner)) - (np.cumsum(many) - many)[owner])[known], bound(start), bound(end)


def disjoint(owner: np.ndarray, starts: np.ndarray, ends: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """An order of the sections, and their starts and ends in it, laid end to end: within their texts (of ``size`` characters) and
    each without what earlier ones hold."""
    base = np.cumsum(size) - size
    starts, ends = (np.clip(x, 0, size[owner]) + base[owner] for x in (starts, ends))
    ends = np.maximum(starts, ends)
    order = np.lexsort((ends, starts, owner))
    starts, ends = starts[order], ends[order]
    held = np.maximum.accumulate(np.append(0, ends))[:-1]
    starts = np.maximum(starts, held)
    return order, starts, np.maximum(starts, ends)


def count_tokens(
    docs: DataFrame, ranks_path: str, pattern: str | None = None, id_col: str = "doc_id", text_col: str = "text",
    sections_col: str | None = None, separator: str = "\n", rule: str = "start",
) -> DataFrame:
    """One row per document and section: id, section (from 0; -1 for the rest outside, where there is one), char_start,
    char_end, n_tokens (double under ``proportional``). ``sections_col`` is an array of structs (start, end)."""
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    ranks, pattern = ranks_and_pattern(docs.sparkSession, ranks_path, pattern)
    rows = docs.select(docs[id_col].alias("_id"), docs[text_col].alias("_text"), *([docs[sections_col].alias("_sections")] if sections_col else []))
    kind, arrow = (T.DoubleType(), pa.float64()) if rule == "proportional" else (T.LongType(), pa.int64())
    schema = T.StructType([
        T.StructField(id_col, rows.schema["_id"].dataType), T.StructField("section", T.IntegerType()),
        T.StructField("char_start", T.LongType()), T.StructField("char_end", T.LongType()), T.StructField("n_tokens", kind),
    ])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, kinds = coder_of(ranks.value, pattern), (pa.int32(), pa.int64(), pa.int64(), arrow)
        for whole in batches:
            for batch in slices(whole, "_text"):
                texts = [(raw or b"").decode("utf-8", "replace") for raw in text_bytes(batch.column("_text")).to_pylist()]
                size = np.array([len(t) for t in texts], dtype=np.int64)
                first, last, many = token_spans(coder, texts)
                if sections_col:
                    owner, label, begin, end = given_spans(batch.column("_sections"))
                    order, starts, ends = disjoint(owner, begin, end, size)
                    counts = np.zeros(len(owner), np.float64 if rule == "proportional" else np.int64)
                    counts[order] = attribute(first, last, starts, ends, rule)
                    rest = many - np.bincount(owner, weights=counts, minlength=len(texts))
                    more = np.flatnonzero(rest > 1e-6)
                    owner, label, begin = np.append(owner, more), np.append(label, np.full(len(more), -1)), np.append(begin, np.zeros(len(more), np.int64))
                    end, counts = np.append(end, size[more]), np.append(counts, rest[more].astype(counts.dtype))
                else:
                    owner, starts, ends = split_spans(texts, separator)
                    counts = attribute(first, last, starts, ends, rule)
                    base, head = (np.cumsum(size) - size)[owner], np.searchsorted(owner, owner)
                    label, begin, end = np.arange(len(owner)) - head, starts - base, ends - base
                ids = batch.column("_id").take(pa.array(owner))
                yield pa.RecordBatch.from_arrays([ids, *[pa.array(c).cast(k) for c, k in zip((label, begin, end, counts), kinds, strict=True)]], names=schema.names)

    return rows.mapInArrow(work, schema)


def count_fields(docs: DataFrame, ranks_path: str, fields: list[str], joiner: str = "\n\n", id_col: str = "doc_id", pattern: str | None = None, rule: str = "start") -> DataFrame:
    """Tokens of each of several text columns within the text that they make together, in the order given."""
    texts = [F.coalesce(docs[f], F.lit("")) for f in fields]
    spans, start = [], F.lit(0)
    for i, t in enumerate(texts):
        spans.append(F.struct(start.alias("start"), (start + F.length(t)).alias("end")))
        start = start + F.length(t) + (len(joiner) if i + 1 < len(texts) else 0)
    joined = docs.select(docs[id_col].alias(id_col), F.concat_ws(joiner, *texts).alias("_joined"), F.array(*spans).alias("_spans"))
    out = count_tokens(joined, ranks_path, pattern, id_col, "_joined", "_spans", rule=rule)
    names = F.array(*[F.lit(f) for f in fields])
    return out.withColumn("field", F.get(names, F.col("section")))


def op2_token_counts(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return count_tokens(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
