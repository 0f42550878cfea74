import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, runs string, n_words int, leaks string, `_text2` string"


def prose(seed: int, n: int) -> str:
    rng = random.Random(seed)
    words = ["".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(2, 9))) for _ in range(400)]
    return " ".join(rng.choice(words) for _ in range(n))


def rows():
    """Nulls in any column, empty, blank and very long texts, repeated rows, copies, shared passages, clashing column names."""
    shared = prose(99, 120)
    texts = {
        1: prose(1, 80), 2: prose(1, 80), 3: None, 4: "", 5: "  \n\t ", 6: prose(6, 60) + "\n" + shared + "\n" + prose(66, 30), 7: shared, 8: prose(8, 30) + " " + shared,
        9: "one", 10: "one two", 11: "x " * 300, 12: "y", 13: prose(13, 6000), 14: "É ñ – 日本語 🎉 " * 20, 15: "a\n" * 50, 16: "!!! *** ### $$$ " * 30, 17: shared.replace(" ", "  "),
    }
    out = [(i, t, ["en", "fr", None][i % 3], ["s1", None][i % 2], None if t is None else len(t), 0.5, "r", 1, "l", "z") for i, t in texts.items()]
    out += [out[0], (None, prose(1, 80), None, None, None, None, None, None, None, None), (None, None, None, None, None, None, None, None, None, None)]
    return out


@pytest.fixture(scope="session")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3).cache()


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, 0) for i in range(1, 18)] + [(None, 1, 0), (3, None, None), (1, 1, 0), (2, 7, 1)], "doc_id long, quality int, toxic int")


@pytest.fixture(scope="session")
def benchmark(spark):
    return spark.createDataFrame([(1, prose(500, 40)), (2, prose(501, 25)), (3, ""), (4, None), (5, prose(500, 40))], "item_id long, text string")
