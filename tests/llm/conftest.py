import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id int, g string, blob int, n_words string, kept_text int, bucket string"


def prose(rng, n):
    return " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 6))) for _ in range(n))


@pytest.fixture(scope="session")
def rows():
    """Copies, near copies, shared passages, nulls, empty, long and repeated rows, ids out of order."""
    rng = random.Random(3)
    passage, base = prose(rng, 40), prose(rng, 120)
    texts = [prose(rng, rng.randint(1, 80)) for _ in range(20)]
    texts += [base, base, f"{base} end", base.replace("a", "A"), f"x {passage} y", f"{prose(rng, 30)} {passage}", passage, f"{passage} {passage}"]
    texts += [None, "", "   \n\t ", "one", "one", "two words", "a " * 60, "é ü ß " * 30, prose(rng, 3000), "\x00\x01 odd \x7f bytes", "Stop Stop"]
    near = base.split()
    for k in range(6):
        changed = list(near)
        changed[7 * k] = "zz"
        texts.append(" ".join(changed))
    ids = list(range(len(texts)))
    rng.shuffle(ids)
    out = [(i, t, rng.choice(["en", "fr", None]), rng.choice(["s0", "s0", "s1", None]), len(t or "")) for i, t in zip(ids, texts, strict=True)]
    rng.shuffle(out)
    return out


@pytest.fixture(scope="session")
def docs(spark, rows):
    """The rows with columns whose names clash with the operators' own."""
    return spark.createDataFrame([(*r, 1, "g", 2, "n", 3, "b") for r in rows], SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def odd(spark, rows):
    """The rows with null ids, and rows that repeat an id with the same and with another text."""
    more = [(None, rows[0][1], "en", "s0", 1), (None, None, None, None, None), rows[1], rows[1], (rows[2][0], "quite another text " * 10, "en", "s1", 5)]
    return spark.createDataFrame([(*r, 1, "g", 2, "n", 3, "b") for r in [*rows, *more]], SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def empty(docs):
    return docs.limit(0)
