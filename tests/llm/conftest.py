import random

import pytest
from pyspark.sql import functions as F

#: Names that operators use inside themselves.
CLASHING = ("body", "key", "chunk", "label", "part", "c0", "_id", "_stay", "lines", "rest", "fp", "w", "h", "size", "tag", "bucket")

LONG = " ".join(random.Random(1).choice(["alpha", "beta", "gamma", "delta", "eps"]) + str(i) for i in range(30_000))


@pytest.fixture(scope="session")
def edge(spark):
    """Null, empty, blank, tied, repeated and very long texts, a null id, and extra columns with clashing names."""
    line = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty"
    passage = "\n".join(["the first line here", "the second line here", "the third line here"])
    rows = [
        (1, f"{line} tail"), (2, None), (3, ""), (4, " \t\n  "), (5, f"{line} other"), (5, f"{line} other"), (6, f"{line.upper()} TAIL"),
        (7, passage), (8, f"head\n{passage}\nend"), (9, LONG), (10, "one\x0btwo\x0cthree four"), (11, "ÉCOLE école \U0001F642 é"), (None, "a text without an id"), (12, passage),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    return df.withColumns({c: F.lit("x") for c in CLASHING})


@pytest.fixture(scope="session")
def empty(edge):
    return edge.limit(0)
