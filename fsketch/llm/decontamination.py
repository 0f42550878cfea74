"""Benchmark decontamination by latent semantic retrieval, for copies and paraphrases.

1. Benchmark texts are cut into passages, which are dealt into blocks by hash. Their words get inverse document frequencies from
   all documents of the corpus, in one pass for all blocks (words in over half of them tell nothing, unless a passage has hardly
   any others), and the TF-IDF matrix of a block's passages a randomised SVD: its rows stay distributed, partitions multiply
   them with the current basis and send sums whose size is (words of the block) x (rank), over some power rounds. The rank
   is half of a block's passages, so the latent space is narrower than the passages whatever the size of the benchmark; a
   passage that would keep less than ``LEAST_HELD`` of its length there gets a direction of its own.
2. Every window of every document is folded into the latent spaces, where words that no passage has weigh nothing, and
   compared with all passages by cosine. Windows overlap by half.
3. Around each candidate the longest common subsequence of words decides: a large part of the passage in order is a copy; half of
   it is a paraphrase if the answer is there in order too, or if the item has no answer.

The benchmark is the stated query set. It stays a table; the driver holds one block of it at a time, and one part of its
words. A pass of the corpus takes a group of blocks, whose vectors are broadcast and have a fixed bound; further groups follow
in the same stage, so the corpus is read twice in all. Nothing of it is sampled or cut.

Words are runs of bytes other than ASCII white space and punctuation, with A-Z and the Latin-1 capitals lower-cased.

Defined cases: null and empty texts, and benchmark texts without words, never match; a null answer, or one without words, is
none; null ids are carried; repeated rows of documents are reported each and those of the benchmark once; empty tables give an
empty result; other columns are ignored. Benchmark ids are integers.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow import slices, text_bytes
from .store import materialise, ship
from .words import buffer_of, word_hashes, word_places

#: ASCII punctuation separates words here, like white space.
_PUNCTUATION = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
FOLD = np.arange(256, dtype=np.uint8)
FOLD[0x41:0x5B] += 32
SEPARATES = np.zeros(256, dtype=bool)
SEPARATES[[0x20, *range(0x09, 0x0E), *_PUNCTUATION]] = True

WINDOW_WORDS = 32
PASSAGE_WORDS = 96
#: Passages of a block, on average, and dimensions of its latent space.
BLOCK_PASSAGES = 256
RANK = 128
OVERSAMPLE = 16
POWER_ROUNDS = 2
#: Blocks that a pass of the corpus takes (some MB each), and words whose documents are counted at a time.
GROUP_BLOCKS = 64
PART_WORDS = 1 << 22
LEAST_HELD = 0.5
LEAST_COSINE = 0.7
COPY_SHARE = 0.8
PARAPHRASE_SHARE = 0.5
ANSWER_SHARE = 0.75
#: Documents without any benchmark word that are added to the corpus's counts: frequencies in a few documents say little.
PSEUDO_DOCS = 20


def folded_words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hash and text number of each word of a binary column."""
    buf, offsets = buffer_of(texts)
    buf = FOLD[buf]
    # capitals of the Latin-1 letters: second bytes 80-9E but for the sign at 97
    at = np.flatnonzero(buf[:-1] == 0xC3) + 1
    at = at[(buf[at] >= 0x80) & (buf[at] <= 0x9E) & (buf[at] != 0x97)]
    buf[at] += 0x20
    starts, ends, owner = word_places(buf, offsets, SEPARATES)
    return word_hashes(buf, starts, ends), owner


def common_subsequence(a: list[int], places: dict[int, int], n: int) -> int:
    """Length of the longest common subsequence of ``a`` and a sequence of n words with these bit masks of their places."""
    full = (1 << n) - 1
    row = full
    for w in a:
        hit = places.get(w)
        if hit:
            both = row & hit
            row = ((row + both) | (row - both)) & full
    return n - row.bit_count()


def _masks(words: list[int]) -> dict[int, int]:
    out: dict[int, int] = {}
    for i, w in enumerate(words):
        out[w] = out.get(w, 0) | (1 << i)
    return out


def passages(benchmark: DataFrame, id_col: str, text_col: str, answer_col: str | None, most: int = PASSAGE_WORDS) -> DataFrame:
    """(item, part, words, answer): word hashes of each passage, and of the item's answer; long texts give several that overlap by half."""
    ship(benchmark.sparkSession)
    rows = benchmark.select(F.col(id_col).cast("long").alias("item"), F.col(text_col).alias("_text"), (F.col(answer_col) if answer_col else F.lit(None)).cast("string").alias("_answer"))
    rows = rows.distinct()
    schema = T.StructType([T.StructField("item", T.LongType()), T.StructField("part", T.IntegerType()), T.StructField("words", T.ArrayType(T.LongType())), T.StructField("answer", T.ArrayType(T.LongType()))])

    def split(column: pa.Array) -> list[list[int]]:
        h, owner = folded_words(text_bytes(column))
        cuts = np.searchsorted(owner, np.arange(len(column) + 1))
        return [h[a:b].view(np.int64).tolist() for a, b in zip(cuts, cuts[1:], strict=False)]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for item, words, answer in zip(batch.column("item").to_pylist(), split(batch.column("_text")), split(batch.column("_answer")), strict=True):
                for part, at in enumerate(range(0, max(len(words) - most // 2, 1), most // 2)):
                    if words[at : at + most]:
                        out.append({"item": item, "part": part, "words": words[at : at + most], "answer": answer})
            yield pa.RecordBatch.from_pylist(out, schema=_PASSAGES)

    return rows.mapInArrow(work, schema)


_PASSAGES = pa.schema([("item", pa.int64()), ("part", pa.int32()), ("words", pa.list_(pa.int64())), ("answer", pa.list_(pa.int64()))])


def document_frequencies(docs: DataFrame, vocabulary: np.ndarray, text_col: str = "text") -> tuple[int, np.ndarray]:
    """Number of documents, and of those that hold each word of the (sorted) vocabulary."""
    ship(docs.sparkSession)
    known = docs.sparkSession.sparkContext.broadcast(vocabulary)  # PART_WORDS or so at most

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = known.value
        total, n = np.zeros(len(v), np.int64), 0
        for whole in batches:
            n += whole.num_rows
            for batch in slices(whole, "_text"):
                h, owner = folded_words(text_bytes(batch.column("_text")))
                at = np.minimum(np.searchsorted(v, h), len(v) - 1)
                hit = v[at] == h
                key = np.unique(owner[hit] * len(v) + at[hit])
                total += np.bincount(key % len(v), minlength=len(v))
        yield pa.RecordBatch.from_arrays([pa.array(np.append(np.flatnonzero(total), -1)), pa.array(np.append(total[total > 0], n))], names=["word", "n"])

    counts = docs.select(F.col(text_col).alias("_text")).mapInArrow(work, "word long, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
    out, n_docs = np.zeros(len(vocabulary), np.int64), 0
    for r in counts:
        if r.word < 0:
            n_docs = r.n
        else:
            out[r.word] = r.n
    return n_docs, out


def telling(block: list, vocabulary: np.ndarray, n_docs: int, df: np.ndarray, least: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """The words that take part in the retrieval, with their weights: those in at most half of the documents, and all
    words of passages that have fewer than ``least`` of these."""
    n_docs += PSEUDO_DOCS
    keep = 2 * df <= n_docs
    for _, words, _ in block:
        at = np.unique(np.searchsorted(vocabulary, np.array(words, dtype=np.int64).view(np.uint64)))
        if keep[at].sum() < least:
            keep[at] = True
    return vocabulary[keep], np.log((1 + n_docs) / (1 + df[keep])) + 1e-3


def tfidf_row(words: np.ndarray, vocabulary: np.ndarray, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Columns and weights (of length 1) of a passage."""
    at = np.minimum(np.searchsorted(vocabulary, words), len(vocabulary) - 1)
    cols, counts = np.unique(at[vocabulary[at] == words], return_counts=True)
    weights = counts * idf[cols]
    return cols, weights / np.linalg.norm(weights)


def randomised_svd(rows: DataFrame, vocabulary: np.ndarray, idf: np.ndarray, rank: int = RANK, oversample: int = OVERSAMPLE, rounds: int = POWER_ROUNDS, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """Right singular vectors (words x rank) and singular values of the TF-IDF matrix of passages (column words)."""
    width = max(1, min(rank + oversample, len(vocabulary)))
    sc = rows.sparkSession.sparkContext
    fixed = sc.broadcast((vocabulary, idf))

    def products(basis: np.ndarray, inner: bool) -> np.ndarray:
        """Sum over passages of x (x basis), or of (x basis) (x basis) if inner."""
        sent = sc.broadcast(basis)

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            (v, w), q = fixed.value, sent.value
            total = np.zeros((q.shape[1] if inner else q.shape[0], q.shape[1]))
            for batch in batches:
                for words in batch.column("words"):
                    cols, weights = tfidf_row(np.array(words.as_py(), dtype=np.int64).view(np.uint64), v, w)
                    y = weights @ q[cols]
                    if inner:
                        total += np.outer(y, y)
                    else:
                        total[cols] += np.outer(weights, y)
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()])], names=["sums"])

        parts = rows.select("words").mapInArrow(work, "sums binary").toLocalIterator()
        return sum((np.frombuffer(p[0]).reshape(-1, basis.shape[1]) for p in parts), np.zeros((basis.shape[1] if inner else basis.shape[0], basis.shape[1])))

    basis = np.random.Generator(np.random.PCG64(seed)).standard_normal((len(vocabulary), width))
    for _ in range(rounds + 1):
        basis, _ = np.linalg.qr(products(basis, inner=False))
    values, vectors = np.linalg.eigh(products(basis, inner=True))
    order = np.argsort(values)[::-1][:rank]
    order = order[values[order] > 1e-12]
    return basis @ vectors[:, order], np.sqrt(np.maximum(values[order], 0))


def completed(loadings: np.ndarray, items: list, vocabulary: np.ndarray, idf: np.ndarray, least: float = LEAST_HELD) -> np.ndarray:
    """The basis with what it lacks of the passages that it holds badly."""
    rest = []
    for _, words, _ in items:
        cols, weights = tfidf_row(np.array(words, dtype=np.int64).view(np.uint64), vocabulary, idf)
        inside = weights @ loadings[cols]
        if np.linalg.norm(inside) < least:
            own = -loadings @ inside
            own[cols] += weights
            rest.append(own)
    if not rest:
        return loadings
    more, sizes = np.linalg.qr(np.array(rest).T)
    return np.concatenate([loadings, more[:, np.abs(np.diag(sizes)) > 1e-9]], axis=1)


class Searcher:
    """Compares the windows of texts with the passages of one block."""

    def __init__(self, items: list[tuple[int, list[int], list[int]]], vocabulary: np.ndarray, idf: np.ndarray, loadings: np.ndarray, least_cosine: float):
        self.vocabulary, self.least = vocabulary, least_cosine
        self.weighted = (loadings * idf[:, None]).astype(np.float32)
        self.items = [(item, words, _masks(words), answer, _masks(answer)) for item, words, answer in items]
        # which of all the block's words a passage has; the last column is for others
        self.words = np.unique(np.concatenate([np.array(w, dtype=np.int64) for _, w, _ in items]))
        self.lengths = np.array([len(w) for _, w, _ in items])
        self.member = np.zeros((len(items), len(self.words) + 1), bool)
        for k, (_, words, _) in enumerate(items):
            self.member[k, np.searchsorted(self.words, np.array(words, dtype=np.int64))] = True
        rows = []
        for _, words, *_ in self.items:
            cols, weights = tfidf_row(np.array(words, dtype=np.int64).view(np.uint64), vocabulary, idf)
            rows.append(weights @ loadings[cols])
        latent = np.array(rows, dtype=np.float32).reshape(len(rows), -1)
        self.latent = latent / np.maximum(np.linalg.norm(latent, axis=1, keepdims=True), 1e-12)

    def candidates(self, h: np.ndarray, owner: np.ndarray, n_texts: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(text, first word in the text, passage, cosine) of windows that are close to a passage, in parts."""
        half = WINDOW_WORDS // 2
        counts = np.bincount(owner, minlength=n_texts)
        first = np.cumsum(counts) - counts
        blocks = -(-counts // half)
        block_first = np.cumsum(blocks) - blocks
        at = np.minimum(np.searchsorted(self.vocabulary, h), len(self.vocabulary) - 1)
        hit = np.flatnonzero(self.vocabulary[at] == h)
        if not len(hit):
            return
        block = block_first[owner[hit]] + (hit - first[owner[hit]]) // half
        cuts = np.flatnonzero(np.append(True, block[1:] != block[:-1]))
        total = int(blocks.sum())
        text = np.repeat(np.arange(n_texts), blocks)
        sums = np.zeros((total + 1, self.weighted.shape[1]), np.float32)
        for i in range(0, len(cuts), 4096):
            part = cuts[i : i + 4097]
            end = int(part[4096]) if len(part) > 4096 else len(hit)
            part = part[:4096]
            sums[block[part]] = np.add.reduceat(self.weighted[at[hit[part[0] : end]]], part - part[0], axis=0)
        pair = sums[:total].copy()
        joined = np.flatnonzero(text[1:] == text[:-1])
        pair[joined] += sums[joined + 1]
        pair /= np.maximum(np.linalg.norm(pair, axis=1, keepdims=True), 1e-12)
        for i in range(0, total, 4096):
            close = pair[i : i + 4096] @ self.latent.T
            w, p = np.nonzero(close >= self.least)
            yield text[i + w], (i + w - block_first[text[i + w]]) * half, p, close[w, p]

    def leaks(self, h: np.ndarray, owner: np.ndarray, n_texts: int) -> dict[tuple[int, int], tuple[int, float, float, float | None]]:
        """(text, item) -> first word of the place, cosine, shares of the passage and of the answer found, for the best place."""
        counts = np.bincount(owner, minlength=n_texts)
        first = np.cumsum(counts) - counts
        signed = h.view(np.int64)
        at = np.minimum(np.searchsorted(self.words, signed), len(self.words) - 1)
        at = np.where(self.words[at] == signed, at, len(self.words))
        found: dict[tuple[int, int], tuple[int, float, float, float | None]] = {}
        for text, start, p, cosine in self.candidates(h, owner, n_texts):
            for k in range(0, len(text), 2048):
                self._settle(found, signed, at, counts, first, *(x[k : k + 2048] for x in (text, start, p, cosine)))
        return found

    def _settle(self, found, signed, at, counts, first, text, start, p, cosine) -> None:
        m = self.lengths[p]
        low, high = np.maximum(0, start - m), np.minimum(counts[text], start + WINDOW_WORDS + m)
        # no more words can be common in order than are common at all
        size = high - low
        ends = np.cumsum(size)
        place = np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(first[text] + low - (ends - size), size)
        common = np.add.reduceat(self.member[np.repeat(p, size), at[place]], ends - size, dtype=np.int64) if len(place) else size
        for k in np.flatnonzero(common >= PARAPHRASE_SHARE * m).tolist():
            item, _, masks, answer, answer_masks = self.items[p[k]]
            n, begin = int(m[k]), int(first[text[k]])
            region = signed[begin + int(low[k]) : begin + int(high[k])].tolist()
            if sum(masks[w].bit_count() for w in masks.keys() & set(region)) < PARAPHRASE_SHARE * n:
                continue
            share = common_subsequence(region, masks, n) / n
            if share < PARAPHRASE_SHARE:
                continue
            told = common_subsequence(region, answer_masks, len(answer)) / len(answer) if answer else None
            if share < COPY_SHARE and told is not None and told < ANSWER_SHARE:
                continue
            key = (int(text[k]), item)
            if key not in found or share > found[key][2]:
                found[key] = (int(low[k]), float(cosine[k]), share, told)


LEAK = T.StructType([
    T.StructField("item", T.LongType()), T.StructField("first_word", T.LongType()), T.StructField("cosine", T.DoubleType()),
    T.StructField("lcs_share", T.DoubleType()), T.StructField("answer_share", T.DoubleType()),
])
_LEAKS = pa.list_(pa.struct([("item", pa.int64()), ("first_word", pa.int64()), ("cosine", pa.float64()), ("lcs_share", pa.float64()), ("answer_share", pa.float64())]))


def word_frequencies(docs: DataFrame, table: DataFrame, text_col: str = "text") -> tuple[int, DataFrame]:
    """Number of documents, and (word, n): those that hold each word of the passages. One pass per ``PART_WORDS`` words."""
    words = materialise(table.select(F.explode("words").alias("word")).distinct(), "leak-words")
    parts = max(1, -(-words.count() // PART_WORDS))
    n_docs, out = 0, []
    for part in range(parts):
        mine = words.where(F.pmod(F.xxhash64("word"), F.lit(parts)) == part)
        vocabulary = np.sort(np.fromiter((r.word for r in mine.toLocalIterator()), dtype=np.int64).view(np.uint64))
        if len(vocabulary):
            n_docs, df = document_frequencies(docs, vocabulary, text_col)
            frame = pa.table({"word": vocabulary.view(np.int64), "n": df})
            out.append(materialise(docs.sparkSession.createDataFrame(frame), "leak-frequencies"))
    return n_docs, reduce(DataFrame.unionByName, out) if out else words.withColumn("n", F.lit(0).cast("long"))


def prepared(docs: DataFrame, table: DataFrame, text_col: str, rank: int, block_passages: int) -> Iterator[tuple]:
    """(items, vocabulary, weights, loadings) of each block of passages; one is held at a time."""
    blocks = max(1, -(-table.count() // block_passages))
    table = materialise(table.withColumn("block", F.pmod(F.xxhash64("item", "part"), F.lit(blocks))), "leak-blocks")
    n_docs, frequencies = word_frequencies(docs, table, text_col)
    for block in range(blocks):
        rows = table.where(F.col("block") == block)
        items = [(r.item, list(r.words), list(r.answer or [])) for r in rows.orderBy("item", "part").toLocalIterator()]
        if not items:
            continue
        mine = rows.select(F.explode("words").alias("word")).distinct().join(frequencies, "word").toLocalIterator()
        known = np.array(sorted((r.word & (2**64 - 1), r.n) for r in mine), dtype=np.uint64).reshape(-1, 2)
        vocabulary, idf = telling(items, known[:, 0], n_docs, known[:, 1].astype(np.int64))
        loadings, _ = randomised_svd(rows.repartition(4), vocabulary, idf, rank)
        yield items, vocabulary, idf, completed(loadings, items, vocabulary, idf).astype(np.float32)


def mark_leaks(
    docs: DataFrame, benchmark: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",), item_col: str = "item_id", item_text_col: str = "text",
    answer_col: str | None = None, rank: int = RANK, least_cosine: float = LEAST_COSINE, block_passages: int = BLOCK_PASSAGES,
) -> DataFrame:
    """The kept columns and ``leaks``, an array of structs with one entry per benchmark item that the row's text holds."""
    spark = docs.sparkSession
    table = materialise(passages(benchmark, item_col, item_text_col, answer_col), "leak-passages")
    out = docs.select(*keep, docs[text_col].alias("_text"), F.array().cast(T.ArrayType(LEAK)).alias("leaks"))
    names, schema = out.columns, T.StructType([T.StructField(f.name, f.dataType) for f in out.schema.fields])
    each = prepared(docs, table, text_col, rank, block_passages)
    while group := list(islice(each, GROUP_BLOCKS)):
        sent = spark.sparkContext.broadcast(group)

        def work(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            searchers = [Searcher(*block, least_cosine) for block in sent.value]
            for whole in batches:
                for batch in slices(whole, "_text"):
                    h, owner = folded_words(text_bytes(batch.column("_text")))
                    leaks = batch.column("leaks").to_pylist()
                    for searcher in searchers:
                        for (text, item), (place, cosine, share, told) in searcher.leaks(h, owner, batch.num_rows).items():
                            same = [x for x in leaks[text] if x["item"] == item]
                            if same and same[0]["lcs_share"] >= share:
                                continue
                            leaks[text] = [x for x in leaks[text] if x["item"] != item] + [{"item": item, "first_word": place, "cosine": cosine, "lcs_share": share, "answer_share": told}]
                    columns = [*[batch.column(c) for c in names[:-1]], pa.array(leaks, type=_LEAKS)]
                    yield pa.RecordBatch.from_arrays(columns, names=names)

        out = out.mapInArrow(work, schema)
    return out.select(*keep, "leaks")


def find_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", item_col: str = "item_id", **settings) -> DataFrame:
    """(id, item, first_word, cosine, lcs_share, answer_share): one row per document and benchmark item found in it."""
    marked = mark_leaks(docs, benchmark, keep=(id_col,), item_col=item_col, **settings)
    found = marked.select(id_col, F.explode("leaks").alias("leak"))
    return found.select(id_col, F.col("leak.item").alias(item_col), *[F.col(f"leak.{c}").alias(c) for c in LEAK.names[1:]])


def op6_decontamination(spark, sf_dir: str) -> DataFrame:
    docs, benchmark = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    return find_leaks(docs, benchmark)
