import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, fp long"


def make(spark, texts, ids=None):
    """Documents with columns whose names clash with the operators' own."""
    ids = range(len(texts)) if ids is None else ids
    return spark.createDataFrame([(i, t, "en", "s", 0, True, 5) for i, t in zip(ids, texts)], SCHEMA)


@pytest.fixture
def documents(spark):
    return lambda texts, ids=None: make(spark, texts, ids)


@pytest.fixture(scope="session")
def prose():
    """Random texts with copies, near copies, shared lines and passages, blanks and nulls."""
    rng = random.Random(11)
    word = lambda: "".join(rng.choice(["an", "er", "th", "é", "ß", "on", "ing"]) for _ in range(rng.randrange(1, 4)))
    text = lambda n: " ".join(word() + ("\n" if rng.random() < 0.1 else "") for _ in range(n))
    texts = [text(rng.randrange(1, 90)) for _ in range(120)]
    passage, line = text(40).replace("\n", ""), "This Line appears in several documents"
    for i in range(0, 120, 9):
        texts[i] = texts[i] + "\n" + line + "\n" + passage
    texts += texts[:20] + [t + " end" for t in texts[20:40]] + [None, "", " \t\n", "x", passage, line, line + "\n" + line.upper(), "one " * 300]
    return texts
