import random

import pytest

EXTRA = ["fp", "size", "score", "row", "start", "bucket", "block", "fingerprint", "component_id", "k_text", "s_parts", "m_pass", "cell", "label", "x", "ka", "kt", "chosen", "taken", "sid", "passes", "word_from", "failed", "parts", "tokens"]
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, " + ", ".join(f"{c} string" for c in EXTRA)


def word(rng):
    return "".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7)))


def prose(rng, n):
    return " ".join(word(rng) for _ in range(n))


@pytest.fixture(scope="session")
def odd_rows():
    """Nulls everywhere, empty, blank and long texts, ties, repeated rows, near copies, foreign letters."""
    rng = random.Random(11)
    base = prose(rng, 400)
    words = base.split()
    words[200] = "changed"
    near = " ".join(words)
    long = prose(rng, 60_000)
    rows = [
        (1, base, "en", "a", len(base)), (2, base, "en", "a", len(base)), (3, near, "en", "b", len(near)), (4, long, "de", None, len(long)), (5, None, None, "a", None), (6, "", "en", "c", 0), (7, " \n\t ", "en", "c", 4),
        (None, base, "en", "a", 1), (None, None, None, None, None), (8, "a", "en", "b", 1), (8, "a", "en", "b", 1), (9, "one two three", "fr", "é", 13), (10, "Zeile\n" * 90, "de", "b", 540), (11, "x y z   \U0001f600 é" * 30, "en", "a", 9), (12, prose(rng, 300), "es", "", 9), (13, prose(rng, 80), "es", "b", 9), (13, prose(rng, 80), "es", "b", 9),
        (14, prose(rng, 60) + ' token = "04dbebab91ab85687d33eeaaf9ac699e1188f962" ' + prose(rng, 60), "en", "a", 9), (15, "Licensd under the Apach License, Version 2.0 " + prose(rng, 70), "en", "a", 9), (2**62, prose(rng, 55), "en", "a", 9), (-5, prose(rng, 70), "en", "a", 9),
    ]
    return [(*r, *["7"] * len(EXTRA)) for r in rows]


@pytest.fixture(scope="session")
def odd_docs(spark, odd_rows):
    return spark.createDataFrame(odd_rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def docs(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


@pytest.fixture(scope="session")
def labels(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/labels.parquet")
