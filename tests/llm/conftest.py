import pytest
from pyspark.sql import types as T

WORDS = "the of and cat sat on a mat while dogs bark at night under bright moon beside old river stones".split()


def long_text(seed, n):
    import random

    r = random.Random(seed)
    return " ".join(r.choice(WORDS) for _ in range(n))


@pytest.fixture(scope="session")
def edge(spark):
    """Nulls everywhere, empty and long texts, ties, repeated rows, and extra columns with names that operators use inside."""
    passage = long_text(99, 60)
    rows = [
        (1, None, "en", "a"), (2, "", "en", None), (3, "   \n\t", None, "a"), (4, "One line\nTwo line\none LINE \n", "en", "b"),
        (5, long_text(1, 4000), "en", "a"), (6, long_text(1, 4000).upper(), "en", "b"), (7, passage + " x", "de", "c"), (8, "y " + passage, "de", "c"),
        (9, "Ünïcode Ä ä — text <|endoftext|> \x1c    end", "xx", "d"), (9, "Ünïcode Ä ä — text <|endoftext|> \x1c    end", "xx", "d"),
        (None, "no id", "en", "a"), (None, None, None, None), (10, "ab" * 300, "en", "b"), (11, "'ll  it's 123 45,6\r\n\r\n", "en", "b"), (12, "short", "en", "a"), (12, "other text, same id", "en", "a"),
    ]
    schema = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType())])
    df = spark.createDataFrame(rows, schema)
    from pyspark.sql import functions as F

    for name in ("row", "tie", "word", "_h", "size", "fp", "shard", "key", "line", "held_out", "n_chars", "Times"):
        df = df.withColumn(name, F.lit(None).cast("long"))
    return df


@pytest.fixture(scope="session")
def empty(edge):
    return edge.filter("1 = 0")
