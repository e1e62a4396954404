import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept string, _b string, spans string"


@pytest.fixture(scope="session")
def texts():
    """Odd rows on purpose: null, empty, blank and very long texts, repeats, null ids, repeated ids and rows, ties."""
    r = random.Random(11)
    word = lambda: "".join(r.choice("abcdeéñ") for _ in range(r.randint(1, 9)))
    prose = lambda n: " ".join(word() for _ in range(n))
    base, passage = prose(120), prose(160)
    near = base.split(" ")
    near[60] = "changed"
    rows = [
        (1, base), (2, base), (3, " ".join(near)), (4, "".join(c.upper() if c.isascii() else c for c in base)), (5, None), (6, ""), (7, " \n\t "), (8, "one"), (9, "one two three four"), (10, "one two three four"),
        (11, prose(30) + " " + passage + " " + prose(20)), (12, prose(25) + " " + passage + " " + prose(10)), (13, passage), (14, "z" * 3000), (15, prose(20000)),
        (None, prose(40)), (None, None), (16, prose(50)), (16, prose(50)), (17, "twin rows " * 60), (17, "twin rows " * 60), (18, "Released under the MIT License.\n" + prose(20)), (19, "<|endoftext|> x<|endoftext|>"),
    ]
    return rows + [(100 + k, prose(r.randint(5, 90))) for k in range(40)]


@pytest.fixture(scope="session")
def docs(spark, texts):
    sources = ["b", "a", None, "c", "é"]
    rows = [(i, t, "xx", sources[k % 5], len(t) if t else 0, "clash", "clash", "clash") for k, (i, t) in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA).repartition(3).persist()


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], SCHEMA)
