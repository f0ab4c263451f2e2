import random

import pytest

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, part int, bucket int, shard int, node bigint"


def sentence(rng, n):
    return " ".join("".join(rng.choice(["an", "the", "er", "on", "ti", "re", "st", "ing", "éa", "ou"]) for _ in range(rng.randint(1, 4))) for _ in range(n))


def tricky_rows():
    """Nulls, empty, blank, tiny, long and repeated texts, near copies, shared passages, clashing columns."""
    rng = random.Random(5)
    passage = sentence(rng, 40)
    base = sentence(rng, 120)
    texts = [None, "", "   ", "\t\n", "one", "One two", "a" * 49, "b" * 50, "b" * 50, "b" * 120, "日本語のテキスト 😀 é", "x" * 3000, "ab " * 4000, base, base, base + " tail words here", base.replace("the", "The", 1), passage, "start " + passage, passage + " end", sentence(rng, 30) + " " + passage + " " + sentence(rng, 20), sentence(rng, 9000), "!!! 123 ???"]
    texts += [sentence(rng, rng.randint(1, 90)) for _ in range(60)]
    for i in range(12):
        words = base.split(" ")
        words[i * 7] = f"w{i}"
        texts.append(" ".join(words))
    rows = [(i * 3 + 1, t, ["en", "de", None][i % 3], f"s{i % 2}", None if t is None else len(t), 7, 7, 7, 7) for i, t in enumerate(texts)]
    return rows


@pytest.fixture(scope="session")
def tricky(spark):
    return spark.createDataFrame(tricky_rows(), DOCS).repartition(3)


@pytest.fixture(scope="session")
def rows():
    return [(r[0], r[1]) for r in tricky_rows()]


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="session")
def repeated(spark):
    """Rows that repeat an id, with equal and with other texts, and null ids."""
    r = [(5, "same text of some length that is over fifty bytes long, really", "en"), (5, "same text of some length that is over fifty bytes long, really", "en"), (5, "another text", "en"), (None, "same text of some length that is over fifty bytes long, really", None), (None, None, None), (2, "another text", "de")]
    return spark.createDataFrame([(a, b, c, "s", 1, 0, 0, 0, 0) for a, b, c in r], DOCS)
