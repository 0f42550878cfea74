"""BPE, token counts, SimHash, substring dedup and decontamination against brute force."""

import base64
import hashlib
import random
import re
from collections import Counter

import duckdb
import numpy as np
import pyarrow as pa
import pytest
import public_tokenizers
import tiktoken
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from fsketch.llm import bpe, components, decontamination, simhash, substring_dedup, token_counts, words

from .conftest import prose, rows

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


@pytest.fixture(scope="module")
def coder():
    with open(RANKS, "rb") as f:
        return bpe.coder_of(f.read(), public_tokenizers.PATTERN)


@pytest.fixture(scope="module")
def encoding():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


@given(st.text(max_size=60))
@settings(max_examples=300, deadline=None)
def test_bpe_is_tiktoken(coder, encoding, text):
    ids = coder.encode(text)
    assert ids.tolist() == encoding.encode_ordinary(text) and coder.decode(ids) == text.encode()


@pytest.mark.parametrize("text", ["a" * 5000, "ab" * 4000, " " * 999 + "x", "日本語" * 300, "<|endoftext|>", "\x1c\x85 　"])
def test_bpe_long_pieces(coder, encoding, text):
    assert coder.encode(text).tolist() == encoding.encode_ordinary(text)


def test_bpe_blocks_and_memory(coder, encoding, monkeypatch):
    text = prose(3, 500)
    monkeypatch.setattr(bpe, "BLOCK_PIECES", 50)
    monkeypatch.setattr(bpe, "MEMORY_PIECES", 20)
    assert coder.encode(text).tolist() == encoding.encode_ordinary(text)


def test_bpe_tables(spark, docs, empty, encoding):
    got = bpe.encode_texts(docs, RANKS, outputs=("n_tokens", "ids", "ids_sha256", "decoded", "decoded_sha256"))
    back = {r.doc_id: bytes(r.decoded) for r in bpe.decode_ids(got, RANKS).collect()}
    texts = {r[0]: r[1] for r in rows()}
    for r in got.where("doc_id is not null").collect():
        text = texts[r.doc_id] or ""
        want = encoding.encode_ordinary(text)
        assert r.ids == want and r.n_tokens == len(want) and bytes(r.decoded) == back[r.doc_id] == text.encode()
        assert r.ids_sha256 == hashlib.sha256(np.array(want, "<u4").tobytes()).hexdigest() and r.decoded_sha256 == hashlib.sha256(text.encode()).hexdigest()
    assert got.count() == docs.count() and bpe.encode_texts(empty, RANKS).count() == 0


def spans_by_tiktoken(encoding, text):
    ids = encoding.encode_ordinary(text)
    out, at = [], 0
    raw = text.encode()
    begun = np.concatenate([[0], np.cumsum([(b & 0xC0) != 0x80 for b in raw])]) if raw else np.zeros(1, int)
    for i in ids:
        n = len(encoding.decode_single_token_bytes(i))
        out.append((int(begun[at + 1]) - 1, int(begun[at + n])))
        at += n
    return out


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_token_counts(docs, empty, encoding, rule):
    texts = {r[0]: r[1] or "" for r in rows()}
    got = {}
    for r in token_counts.count_tokens(docs, RANKS, rule=rule).where("doc_id is not null and doc_id <> 1").collect():
        got.setdefault(r.doc_id, []).append(r)
    assert set(got) == set(texts) - {1, None}
    for i, sections in got.items():
        spans = spans_by_tiktoken(encoding, texts[i])
        assert abs(sum(s.n_tokens for s in sections) - len(spans)) < 1e-6
        want = [0.0] * len(sections)
        bounds = [(s.char_start, s.char_end) for s in sorted(sections, key=lambda s: s.section)]
        assert [texts[i][a:b] for a, b in bounds] == re.findall(r"[^\n]*\n|[^\n]+$", texts[i]) + ([""] if not texts[i] or texts[i].endswith("\n") else [])
        for a, b in spans:
            share = [max(0, min(b, e) - max(a, s)) for s, e in bounds]
            if rule == "start":
                want[next(k for k, (s, e) in enumerate(bounds) if s <= a < e)] += 1
            elif rule == "largest":
                want[int(np.argmax(share))] += 1
            else:
                want = [w + x / (b - a) for w, x in zip(want, share, strict=True)]
        assert np.allclose(want, [s.n_tokens for s in sorted(sections, key=lambda s: s.section)])
    assert token_counts.count_tokens(empty, RANKS, rule=rule).count() == 0


def test_token_fields(spark, encoding):
    df = spark.createDataFrame([(1, "A title", "and a body, longer"), (2, None, "x")], "doc_id long, title string, body string")
    got = {(r.doc_id, r.field): r.n_tokens for r in token_counts.count_fields(df, RANKS, ["title", "body"]).collect()}
    total = len(encoding.encode_ordinary("A title\n\nand a body, longer"))
    assert got[1, "title"] + got[1, "body"] + got.get((1, None), 0) == total and got[2, "title"] == 0
    with pytest.raises(ValueError):
        token_counts.count_tokens(df, RANKS, text_col="body", rule="none")


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_given_sections(spark, encoding, rule):
    """Unsorted, overlapping, null, empty, inverted and outlying sections: every character is the first section's that holds it."""
    rng, text = random.Random(8), "hello world, " * 4 + "日本語 ñandú é\n" * 3
    spans = {1: [(6, 11), (0, 6)], 2: [(0, 8), (4, 12), None, (12, 12), (20, 15), (60, 500)], 3: None, 4: [], 5: [(None, 4), (-5, 3)], 6: [(0, 30), (5, 9), (5, 40)]}
    for i in range(7, 40):
        spans[i] = [(a, a + rng.randrange(0, 25)) for a in (rng.randrange(0, len(text)) for _ in range(rng.randrange(1, 7)))]
    texts = {i: ("hello world" if i == 1 else text) for i in spans} | {99: None}
    df = spark.createDataFrame([(i, t, spans.get(i, [(0, 4)])) for i, t in texts.items()], "doc_id long, text string, s array<struct<start:int,end:int>>")
    got = {}
    for r in token_counts.count_tokens(df, RANKS, sections_col="s", rule=rule).collect():
        got.setdefault(r.doc_id, {})[r.section] = r
    for i, given in spans.items():
        mine = {k: s for k, s in enumerate(given or []) if s is not None and None not in s}
        owner = [-1] * len(texts[i])
        cut = {k: [min(max(x, 0), len(owner)) for x in s] for k, s in mine.items()}
        held = sorted(cut, key=lambda k: (cut[k][0], max(cut[k]), k))
        for k in reversed(held):
            a, b = cut[k]
            owner[a:b] = [k] * max(b - a, 0) if b > a else owner[a:b]
        want = Counter()
        for a, b in spans_by_tiktoken(encoding, texts[i]):
            if rule == "start":
                want[owner[a]] += 1
                continue
            share = Counter(owner[a:b])
            if rule == "proportional":
                for k, n in share.items():
                    want[k] += n / (b - a)
            else:
                inside = {k: n for k, n in share.items() if k >= 0}
                want[max(inside, key=lambda k: (inside[k], -held.index(k))) if inside else -1] += 1
        rows_of = got.get(i, {})
        assert set(rows_of) == set(mine) | ({-1} if want[-1] > 1e-9 else set())
        assert all(abs(rows_of[k].n_tokens - want[k]) < 1e-6 for k in rows_of), (i, want, rows_of)
        assert all((rows_of[k].char_start, rows_of[k].char_end) == s for k, s in mine.items())
    assert got[99][0].n_tokens == 0


def test_pieces_across_sizes(coder, encoding, monkeypatch):
    """Many unknown pieces at once, of all tree sizes, with a memory that overflows."""
    rng = random.Random(5)
    monkeypatch.setattr(bpe, "MEMORY_PIECES", 100)
    texts = [" ".join("".join(rng.choice("abcdeéßñ日") for _ in range(min(int(rng.expovariate(0.12)) + 1, 300))) for _ in range(rng.randrange(0, 60))) for _ in range(80)]
    texts += ["", "x" * 700, prose(4, 900)]
    packed = coder.batch(texts)
    for text, ids in zip(texts, packed, strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == encoding.encode_ordinary(text)
    assert coder.decode_batch(packed) == [t.encode() for t in texts]
    assert coder.merge([]) == [] and len(coder.young) <= 100 + 60 * 80
    with pytest.raises(ValueError):
        bpe.PairTable({b"a": 0})


def plain_fingerprint(text):
    text = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else ([" ".join(w)] if w else [])
    h = [xxhash.xxh64(x.encode(), seed=42).intdigest() for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash(docs, empty):
    got = simhash.near_duplicates(docs).collect()
    texts = {(r[0], r[1]) for r in rows()}
    prints = {}
    for i, t in texts:
        prints.setdefault(i, set()).add(plain_fingerprint(t))
    assert len(got) == docs.count()
    every = sorted({f for s in prints.values() for f in s})
    parent = {f: f for f in every}

    def root(f):
        while parent[f] != f:
            f = parent[f]
        return f

    for a in every:
        for b in every:
            if (a ^ b).bit_count() <= 2:
                parent[root(a)] = root(b)
    least = {}
    for i, fs in prints.items():
        for f in fs:
            if i is not None:
                least[root(f)] = min(least.get(root(f), i), i)
    for r in got:
        f = r.fp & (2**64 - 1)
        assert f in prints[r.doc_id] and r.component_id == least.get(root(f))
    assert simhash.near_duplicates(empty).count() == 0
    with pytest.raises(ValueError):
        simhash.links(docs.select(F.lit(1).alias("fp")), 3)


def test_simhash_links_and_chains(spark):
    rng = random.Random(5)
    prints = [rng.getrandbits(64)]
    for _ in range(60):  # a chain of single steps of one or two bits, and a ball that shares variants
        prints.append(prints[-1] ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)))
    prints += [prints[0] ^ (1 << b) for b in range(30)] + [rng.getrandbits(64) for _ in range(50)]
    signed = np.unique(np.array(prints, dtype=np.uint64)).view(np.int64)
    df = spark.createDataFrame([(int(x),) for x in signed], "fp long")
    for radius in (0, 2, 4):
        found = components.connected_components(simhash.links(df, radius)).collect()
        got = {}
        for r in found:
            got.setdefault(r.component, set()).add(r.node)
        u = signed.view(np.uint64)
        near = np.bitwise_count(u[:, None] ^ u[None, :]) <= radius
        reach = near.copy()
        for _ in range(8):
            reach = (reach.astype(int) @ reach.astype(int)) > 0
        want = {frozenset(signed[row].tolist()) for row in reach if row.sum() > 1}
        assert {frozenset(v) for v in got.values()} == want


@given(st.lists(st.tuples(st.integers(0, 25), st.integers(0, 25)), max_size=30))
@settings(max_examples=4, deadline=None)
def test_components(spark, pairs):
    got = {r.node: r.component for r in components.connected_components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    label = {x: x for p in pairs if p[0] != p[1] for x in p}
    for _ in label:
        for a, b in pairs:
            if a != b:
                label[a] = label[b] = min(label[a], label[b])
    assert got == label


def brute_repeats(docs, window):
    first = {}
    for i, t in sorted((d for d in docs if d[0] is not None), key=lambda d: d[0]):
        w = (t or "").encode().split()
        for p in range(len(w) - window + 1):
            first.setdefault(b" ".join(w[p : p + window]), i)
    out = {}
    for i, t in docs:
        w = (t or "").encode().split()
        gone = [False] * len(w)
        if i is not None:
            for p in range(len(w) - window + 1):
                if first[b" ".join(w[p : p + window])] < i:
                    gone[p : p + window] = [True] * window
        out[i] = (len(w), sum(gone), b" ".join(x for x, g in zip(w, gone, strict=True) if not g))
    return out


@pytest.mark.parametrize("window", [50, 7, 1])
def test_substring_dedup(docs, empty, window):
    want = brute_repeats([(r[0], r[1]) for r in rows() if r[0] is not None], window)
    got = substring_dedup.remove_repeats(docs, window, outputs=("n_words", "n_removed", "kept_sha256", "kept_text", "spans")).collect()
    assert len(got) == docs.count()
    for r in got:
        if r.doc_id is None:
            assert r.n_removed == 0
            continue
        n, gone, kept = want[r.doc_id]
        assert (r.n_words, r.n_removed, r.kept_sha256) == (n, gone, hashlib.sha256(kept).hexdigest())
        assert b" ".join((r.kept_text or "").encode().split()) == kept and sum(b - a for a, b in r.spans) == gone
    assert substring_dedup.remove_repeats(empty, window).count() == 0


def test_substring_dedup_ids_on_several_texts(spark):
    """Rows of one id and different texts lose what smaller ids have, each its own words; positions may be beyond the other's end."""
    passage, alone = prose(7, 90), prose(70, 400)
    data = [(1, passage), (2, alone + " " + passage), (2, "short text"), (2, passage), (2, passage), (3, alone), (3, alone), (3, alone + " x"), (None, passage), (2, None)]
    data += [(4, " ".join(["same"] * 80)), (4, " ".join(["same"] * 70)), (5, prose(70, 400)[: 1500])]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    got = substring_dedup.remove_repeats(df, outputs=("n_words", "n_removed", "kept_sha256")).toPandas()
    con = duckdb.connect()
    con.register("documents", df.toPandas().astype({"doc_id": "Int64"}))
    want = con.execute(substring_dedup.OP7_SQL).df()
    plain = lambda t: sorted(map(str, t[["doc_id", "n_words", "n_removed", "kept_sha256"]].astype(object).values.tolist()))
    assert [x.replace("<NA>", "nan") for x in plain(want.astype({"doc_id": "float"}))] == plain(got.astype({"doc_id": "float"}))
    assert got.n_removed.sum() == 90 * 3 + 400 * 3 + (want[want.doc_id == 5].n_removed.sum())


def test_substring_dedup_many_copies(spark, monkeypatch):
    """Passages at shifted places in many documents, over several slices."""
    monkeypatch.setattr(substring_dedup, "WINDOW", 12)
    rng, passage = random.Random(2), prose(7, 40).split()
    texts = []
    for i in range(60):
        a = rng.randrange(0, 20)
        texts.append((i * 3, " ".join([prose(100 + i, rng.randrange(1, 30)), *passage[a : a + 20], prose(300 + i, 9)])))
    texts.append((500, " ".join(["same"] * 200)))
    texts.append((501, " ".join(["same"] * 100)))
    rng.shuffle(texts)
    df = spark.createDataFrame(texts, "doc_id long, text string").repartition(5)
    want = brute_repeats(texts, 12)
    for r in substring_dedup.remove_repeats(df, 12, outputs=("n_words", "n_removed", "kept_sha256")).collect():
        assert (r.n_removed, r.kept_sha256) == (want[r.doc_id][1], hashlib.sha256(want[r.doc_id][2]).hexdigest())


@given(st.lists(st.text(alphabet="ab \n\té日", max_size=30), min_size=1, max_size=6))
@settings(max_examples=100, deadline=None)
def test_word_places(texts):
    buf, offsets = words.buffer_of(pa.array([t.encode() for t in texts]))
    starts, ends, owner = words.word_places(buf, offsets)
    got = [(int(o), buf[s:e].tobytes()) for s, e, o in zip(starts, ends, owner, strict=True)]
    assert got == [(i, w) for i, t in enumerate(texts) for w in t.encode().split()]
    h = words.word_hashes(buf, starts, ends)
    assert len(set(h.tolist())) == len({w for _, w in got})
    two = words.rolling(h, 2)
    assert len(set(two.tolist())) == len({(a, b) for (_, a), (_, b) in zip(got, got[1:], strict=False)})


def slow_lcs(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        new = [0]
        for j, y in enumerate(b):
            new.append(max(new[-1], row[j + 1], row[j] + (x == y)))
        row = new
    return row[-1]


@given(st.lists(st.integers(0, 4), max_size=20), st.lists(st.integers(0, 4), min_size=1, max_size=12))
@settings(max_examples=200, deadline=None)
def test_common_subsequence(a, b):
    assert decontamination.common_subsequence(a, decontamination._masks(b), len(b)) == slow_lcs(a, b)


def test_leaks(spark, benchmark, empty):
    one, two = prose(500, 40), prose(501, 25)
    other = one.split()
    other[5:9], other[20] = ["changed"] * 4, "too"
    texts = [
        (1, prose(1, 200)), (2, prose(2, 90) + " " + one + " " + prose(3, 90)), (3, two.upper() + "!"), (4, prose(4, 33) + " " + " ".join(other) + " " + prose(5, 50)), (5, None), (6, ""),
        (7, ". ".join(one.split()[:10])), (None, two), (2, prose(2, 90) + " " + one + " " + prose(3, 90)),
    ]
    df = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    got = decontamination.find_leaks(df, benchmark).collect()
    assert sorted((r.doc_id or -1, r.item_id) for r in got) == [(-1, 2), (2, 1), (2, 1), (2, 5), (2, 5), (3, 2), (4, 1), (4, 5)]
    blocks = decontamination.find_leaks(df, benchmark, block_passages=1).collect()
    assert sorted((r.doc_id or -1, r.item_id) for r in blocks) == sorted((r.doc_id or -1, r.item_id) for r in got)
    assert decontamination.find_leaks(df.limit(0), benchmark).count() == 0
    assert decontamination.find_leaks(df, benchmark.limit(0)).count() == 0


def test_answers_decide_on_paraphrases(spark):
    item = prose(700, 40).split()
    loose = item.copy()
    loose[::3] = [f"new{i}" for i in range(len(loose[::3]))]  # two thirds are left
    df = spark.createDataFrame([(1, " ".join([prose(9, 40), *loose, prose(10, 40)]))], "doc_id long, text string")
    bench = lambda answer: spark.createDataFrame([(1, " ".join(item), answer)], "item_id long, text string, answer string")
    kept = " ".join(w for w in loose if not w.startswith("new"))
    found = [decontamination.find_leaks(df, bench(a), answer_col="answer", least_cosine=0.3).count() for a in (kept, "not at all there")]
    assert found == [1, 0]
    # without an answer half of the passage in order is enough
    assert [decontamination.find_leaks(df, bench(a), answer_col="answer").count() for a in (None, " .,")] == [1, 1]
    assert decontamination.find_leaks(df, bench("not at all there")).count() == 1


def test_randomised_svd(spark):
    rng = np.random.default_rng(0)
    passages = [[int(x) for x in rng.integers(0, 60, 12)] for _ in range(30)]
    vocabulary = np.unique(np.concatenate(passages)).astype(np.uint64)
    idf = rng.uniform(0.5, 2, len(vocabulary))
    dense = np.zeros((30, len(vocabulary)))
    for i, p in enumerate(passages):
        cols, weights = decontamination.tfidf_row(np.array(p, dtype=np.uint64), vocabulary, idf)
        dense[i, cols] = weights
    loadings, values = decontamination.randomised_svd(spark.createDataFrame([(p,) for p in passages], "words array<long>"), vocabulary, idf, rank=10, rounds=6)
    want = np.linalg.svd(dense, compute_uv=False)[:10]
    assert np.allclose(values, want, rtol=0.02) and np.allclose(loadings.T @ loadings, np.eye(10), atol=1e-8)
