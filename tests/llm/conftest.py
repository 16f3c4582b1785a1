import pytest
from pyspark.sql import functions as F


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls in any column, empty and wordless texts, ties, repeated rows, and columns whose names could clash."""
    long = " ".join(f"word{i % 97} and the of" for i in range(3000))
    rows = [
        (1, "The cat and the dog of the house", "en", "a"), (1, "The cat and the dog of the house", "en", "a"), (2, None, None, None), (3, "", "en", "b"), (4, " \n\t ", "de", None),
        (5, long, "en", "a"), (6, long + " tail", "en", "b"), (None, "no id here but some text of the kind", "en", "a"), (7, "Der Hund und die Katze sind in dem Haus", "de", "b"), (8, "%%% 123", None, "b"),
        (9, "x " * 200, "en", "a"), (10, "password = hunter2hunter2 é", "en", "a"),
    ]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string")
    return df.withColumns({"n_chars": F.length("text").cast("long"), "size": F.lit(1), "shard": F.lit("x"), "kept": F.lit(True), "__mix_size": F.lit(3), "fp": F.lit(4), "d": F.lit("q")})


@pytest.fixture(scope="session")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")
