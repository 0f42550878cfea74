"""Recall of the decontamination where the benchmark has more passages than the rank, for copies and paraphrases."""

import random

import pytest

from fsketch.llm import decontamination


def test_no_copy_is_lost_beyond_the_rank(spark, monkeypatch):
    blocks, svd = [], decontamination.randomised_svd
    monkeypatch.setattr(decontamination, "randomised_svd", lambda rows, v, w, rank: blocks.append((rows.count(), rank)) or svd(rows, v, w, rank))
    rng = random.Random(5)
    words = ["".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(3, 8))) for _ in range(1500)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    around = lambda: " ".join(rng.choice(words) if rng.random() < 0.15 else f"other{rng.randint(0, 999)}" for _ in range(rng.randint(20, 50)))
    items = [(i, text(rng.randint(10, 14))) for i in range(320)]
    docs = [(i, f"{around()} {t} {around()}") for i, t in items]
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    df = spark.createDataFrame(docs, "doc_id long, text string")
    held = {(d, i) for d, t in docs for i, x in items if f" {x} " in t}
    found = decontamination.find_leaks(df, benchmark, rank=64)
    lost = held - {(r.doc_id, r.item_id) for r in found.collect()}
    assert len(held) >= 320 and not lost, len(lost)
    assert sum(n for n, _ in blocks) == len(items) and len(blocks) == 2 and all(n > rank for n, rank in blocks)


@pytest.mark.parametrize("rate", [0.0, 0.15, 0.3, 0.4])
def test_paraphrases_by_brute_force(spark, rate):
    """Items with words replaced at random, against the longest common subsequence at every place of every document."""
    rng = random.Random(17)
    words = [w for w in {"".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(2, 8))) for _ in range(900)} if w]
    often = words[:20]
    some = lambda: rng.choice(often) if rng.random() < 0.3 else rng.choice(words)
    items = [(i, [some() for _ in range(rng.randint(15, 60))]) for i in range(300)]
    docs = []
    for i, text in items[::3]:
        loose = [some() if rng.random() < rate else w for w in text]
        docs.append((i, [some() for _ in range(rng.randint(0, 120))] + loose + [some() for _ in range(rng.randint(0, 120))]))
    benchmark = spark.createDataFrame([(i, " ".join(t)) for i, t in items], "item_id long, text string")
    df = spark.createDataFrame([(i, " ".join(t)) for i, t in docs], "doc_id long, text string").repartition(3)
    got = {(r.doc_id, r.item_id) for r in decontamination.find_leaks(df, benchmark).collect()}
    want = set()
    for i, text in items:
        masks, m = decontamination._masks(text), len(text)
        wide = 2 * m + decontamination.WINDOW_WORDS
        for d, doc in docs:
            if 2 * sum(w in masks for w in doc) < m:
                continue
            starts = range(0, max(len(doc) - wide, 0) + 1, 4)
            if any(2 * decontamination.common_subsequence(doc[a : a + wide], masks, m) >= m for a in starts):
                want.add((d, i))
    assert len(want) >= 80
    if rate <= 0.3:
        assert len(want & {(i, i) for i, _ in docs}) >= 97
    assert len(got & want) >= 0.9 * len(want), (len(got), len(want))
    # what is found beyond it lies between the places that were tried
    assert len(got - want) <= 0.05 * len(want)
    if rate == 0:
        assert got >= {(i, i) for i, _ in docs}
