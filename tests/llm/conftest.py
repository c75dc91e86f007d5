import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size int, Shard string"


@pytest.fixture(scope="session")
def corpus():
    """Texts with copies, near copies, repeats, nulls, empties and one long text; extra columns with clashing names."""
    r = random.Random(4)
    vocabulary = ["".join(r.choice("abcdefgé") for _ in range(r.randint(1, 7))) for _ in range(400)]
    prose = lambda n: " ".join(r.choice(vocabulary) for _ in range(n))
    rows = []
    for i in range(60):
        rows.append(prose(r.randint(1, 120)))
    for i in range(30):
        base = r.choice(rows).split(" ")
        for _ in range(r.randint(0, 3)):
            base[r.randrange(len(base))] = r.choice(vocabulary)
        rows.append(" ".join(base))
    passage = prose(60)
    rows += [f"{prose(10)} {passage} {prose(9)}\n{prose(30)}" for _ in range(4)]
    rows += [None, "", " \n\t", "one", "One", None, prose(6000), "x " * 40]
    out = [(i * 3, t, r.choice(["en", None]), r.choice(["a", "b", None]), None, 1, "s") for i, t in enumerate(rows)]
    return [*out, out[0], (None, "no id " + prose(30), "en", "a", None, 1, "s")]


@pytest.fixture(scope="session")
def docs(spark, corpus):
    return spark.createDataFrame(corpus, SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], SCHEMA)
