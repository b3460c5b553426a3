import random

import pytest

CLASH = ["fp", "key", "uid", "size", "score", "component_id", "found", "words", "copies", "t", "label", "u", "hi"]


@pytest.fixture(scope="session")
def edge_rows():
    """Nulls, blanks, ties, repeated rows, copies, a very long text."""
    rng = random.Random(5)
    vocab = [f"w{i}" for i in range(400)] + ["the", "of", "and", "to", "in"] * 20
    prose = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    base = prose(120)
    long = prose(30_000)
    rows = [(i, prose(rng.randint(1, 150)), "en", f"src{i % 4}") for i in range(40)]
    rows += [
        (100, None, "en", "src0"), (101, "", None, None), (102, " \t\n ", "de", "src1"), (103, "one", "de", "src1"), (104, "Two Words", "de", "src1"),
        (105, base, "en", "src2"), (106, base.upper(), "en", "src2"), (107, base + " tail", "en", "src2"), (107, base + " tail", "en", "src2"),
        (None, base + " other tail here", "en", None), (None, None, None, None), (108, long, "en", "src0"), (109, "a " * 200, "en", "src3"),
        (110, long[:4000] + " é ß 漢字 👍 " + prose(30), "fr", "src3"), (111, "a " * 36, "en", "src3"),
    ]
    return rows


@pytest.fixture(scope="session")
def edge_docs(spark, edge_rows):
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{c} string" for c in CLASH)
    rows = [(*r, len(r[1] or ""), *(["x"] * len(CLASH))) for r in edge_rows]
    return spark.createDataFrame(rows, schema).repartition(3)


@pytest.fixture(scope="session")
def empty_docs(spark, edge_docs):
    return spark.createDataFrame([], edge_docs.schema)
