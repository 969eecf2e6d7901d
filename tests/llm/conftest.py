import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def rows_of(texts, lang="en"):
    return [(i, t, lang, "s", len(t or "")) for i, t in enumerate(texts)]


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty and very long texts, repeated rows, copies, one null id, and columns with clashing names."""
    rnd = random.Random(5)
    words = [f"word{i}" for i in range(300)]
    long = " ".join(rnd.choice(words) for _ in range(30_000))
    base = " ".join(rnd.choice(words) for _ in range(120))
    near = base.split()
    near[60] = "changed"
    texts = ["", None, base, base, " ".join(near), long, "one", "a b", "\n \n", "é漢字 ñ" * 9, "x" * 5000]
    rows = rows_of(texts) + [(2, base, "en", "s", len(base)), (None, "no id here", None, None, None)]
    df = spark.createDataFrame(rows, SCHEMA)
    for name in ("node", "part", "key", "shard", "region", "size", "gone_id", "cell", "label", "score"):
        df = df.selectExpr("*", f"'clash' AS {name}")
    return df


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def tiny(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet")
