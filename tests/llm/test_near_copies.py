"""Near copies by similarity and the pipeline's stage, against brute force."""

import random
from itertools import combinations

import pytest

import corpus_pipeline
from fsketch.llm import near_copies, simhash
from fsketch.llm.components import HOT_SHARE, join_labels

from .conftest import SCHEMA, prose


def edited(seed: int, base: str, n: int) -> str:
    rng, words = random.Random(seed), base.split()
    for at in rng.sample(range(len(words)), n):
        words[at] = f"new{seed}at{at}"
    return " ".join(words)


def texts():
    """30 texts with two edited copies each, some near copies and some not, and a group of 150 edited copies of one text."""
    out = {}
    for i in range(30):
        base = prose(1000 + i, 150 + 10 * i)
        out |= {i: base, 100 + i: edited(i, base, 1 + i % 6), 200 + i: edited(50 + i, base, 2 + i % 9)}
    common = prose(3000, 400)
    return out | {1000 + i: edited(100 + i, common, 3) for i in range(150)}


def components(data):
    """Least id of each id's component, over all pairs."""
    sets = {i: near_copies.shingles(near_copies.words_of(t.encode())) for i, t in data.items()}
    least = {i: i for i in data}

    def root(i):
        while least[i] != i:
            i = least[i]
        return i

    pairs = [(a, b) for a, b in combinations(sorted(data), 2) if near_copies.similarity(sets[a], sets[b]) >= 0.8]
    for a, b in pairs:
        a, b = sorted((root(a), root(b)))
        least[b] = a
    return pairs, {i: root(i) for i in data}


@pytest.mark.parametrize("stage", [False, True])
def test_near_copies_at_similarity(spark, stage):
    data = texts()
    pairs, want = components(data)
    prints = {i: simhash.fingerprint(t.encode()) for i, t in data.items()}
    far = [p for p in pairs if (prints[p[0]] ^ prints[p[1]]).bit_count() > 2]
    assert len(far) > len(pairs) / 2 and len(set(want.values())) > 30
    docs = spark.createDataFrame([(i, t, *[None] * 8) for i, t in data.items()], SCHEMA).repartition(4)
    if stage:
        kept = corpus_pipeline.simhash_near_dedup(spark, docs, "")
        assert sorted(r.doc_id for r in kept.collect()) == sorted(set(want.values()))
    else:
        got = near_copies.near_copies(docs).collect()
        assert {r.doc_id: r.component_id for r in got} == want and len(got) == len(data)


def test_near_copies_edges(spark, docs, empty):
    got = near_copies.near_copies(docs).collect()
    assert len(got) == docs.count() and near_copies.near_copies(empty).count() == 0
    found = {r.doc_id: r.component_id for r in got if r.doc_id is not None}
    assert [found[i] for i in (1, 2, 3, 4, 5, 7, 17)] == [1, 1, 3, 3, 3, 7, 7]
    assert all(found[i] == i for i in (6, 8, 9, 10, 11, 12, 13, 14, 15, 16))


def test_stage_drops_rows_not_ids(spark):
    """An id on rows of different texts: only the row that is a near copy goes, and the other text keeps its document."""
    base, other, third = prose(1, 100), prose(2, 100), prose(3, 100)
    rows = [(1, base), (5, edited(7, base, 1)), (5, other), (8, other), (9, third), (9, prose(4, 100)), (9, third), (None, base)]
    docs = spark.createDataFrame([(i, t, *[None] * 8) for i, t in rows], SCHEMA).repartition(3)
    kept = corpus_pipeline.simhash_near_dedup(spark, docs, "")
    found = sorted(((r.doc_id or 0, r.text) for r in kept.collect()), key=str)
    assert kept.columns == docs.columns and found == sorted([(0, base), (1, base), (5, other), (9, third), (9, prose(4, 100))], key=str)


def test_labels_of_hot_keys(spark):
    """A third of the rows bear one key: the result is that of a plain join, and only rows of other keys are shuffled."""
    keys = ["hot"] * 2000 + ["warm"] * 3 + [f"k{i}" for i in range(4000)] + ["unknown", None]
    rows = spark.createDataFrame(list(enumerate(keys)), "id long, key string")
    counts = {k: keys.count(k) for k in set(keys) - {"unknown", None}}
    labels = spark.createDataFrame([(k, f"of {k}", n) for k, n in counts.items()], "key string, label string, n long")
    got = [(r.id, r.key, r.label) for r in join_labels(rows, labels, "key").collect()]
    assert sorted(got) == [(i, k, f"of {k}") for i, k in enumerate(keys) if k in counts]
    assert sum(n * HOT_SHARE >= len(keys) for n in counts.values()) == 1
    assert join_labels(rows.limit(0), labels.limit(0), "key").count() == 0


def test_pairs_that_bands_and_hubs_miss(spark, monkeypatch):
    """Without any candidate of the bands and fingerprints, the filter still leads to every component."""
    whole = near_copies.candidates
    monkeypatch.setattr(near_copies, "candidates", lambda texts: whole(texts).limit(0))
    data = {i: t for i, t in texts().items() if i < 1020} | {5000: "a b c d e f", 5001: "a b c d e f g", 5002: "one two", 5003: ""}
    pairs, want = components(data)
    assert len(pairs) > 60 and len(set(want.values())) > 30
    docs = spark.createDataFrame([(i, t, *[None] * 8) for i, t in data.items()], SCHEMA).repartition(4)
    assert {r.doc_id: r.component_id for r in near_copies.near_copies(docs).collect()} == want


def test_parities_never_rule_out_a_similar_pair():
    """Also where one text has twice the bins of the other."""
    rng = random.Random(5)
    seen = {True: 0, False: 0}
    for n in (1, 3, 40, 500, 511, 513, 700, 1024, 1030, 4000):
        base = prose(n, n + 4).split()
        for share in (0.0, 0.01, 0.02, 0.03, 0.1, 0.5, 1.0):
            other = [f"new{i}" if rng.random() < share else w for i, w in enumerate(base)] + prose(n + 1, n // 40).split()
            x, y = ([w.encode() for w in words] for words in (base, other))
            a, b = near_copies._hashes(x), near_copies._hashes(y)
            said = near_copies.may_be_similar(len(a), near_copies.parities(a), len(b), near_copies.parities(b))
            similar = near_copies.similarity(near_copies.shingles(x), near_copies.shingles(y)) >= 0.8
            assert said or not similar
            seen[similar] += not said
    assert seen[True] == 0 and seen[False] > 30


def test_texts_of_pairs_that_cannot_be_similar_stay(spark, monkeypatch):
    """60 texts with one passage in common: their pairs meet in its shingles, but no text travels for them."""
    passage, given, whole = prose(7, 60), [], near_copies.verified

    def noted(pairs, texts):
        given.append(pairs.count())
        return whole(pairs, texts)

    monkeypatch.setattr(near_copies, "verified", noted)
    monkeypatch.setattr(near_copies, "COMMON_MOST", 1)
    data = {i: prose(7000 + i, 150 + 15 * i) + " " + passage + " " + prose(8000 + i, 30) for i in range(60)}
    data |= {100: edited(1, data[5], 2)}
    docs = spark.createDataFrame([(i, t, *[None] * 8) for i, t in data.items()], SCHEMA).repartition(4)
    got = {r.doc_id: r.component_id for r in near_copies.near_copies(docs).collect()}
    assert got == {i: 5 if i == 100 else i for i in data} and given[1] < 10


def test_common_shingles_are_told_in_a_share_of_the_texts(spark, monkeypatch):
    """A passage in a quarter of the texts is found common, however small the least sample."""
    monkeypatch.setattr(near_copies, "COMMON_TEXTS", 4)
    passage = prose(7, 40)
    texts = [prose(9000 + i, 60) + (" " + passage if i % 4 == 0 else "") for i in range(800)]
    held = spark.createDataFrame([(near_copies.text_key(near_copies.words_of(t.encode())), t) for t in texts], "key string, text string")
    common, _ = near_copies.common_shingles(held, len(texts))
    assert set(near_copies._hashes(near_copies.words_of(passage.encode()))) <= set(common)
