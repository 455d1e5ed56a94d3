import pytest
from pyspark.sql import SparkSession


@pytest.fixture(scope="session")
def spark():
    session = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    return session


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty texts, repeated rows, a long text and an extra column with a clashing name."""
    rows = [
        (1, "one two three four five six seven eight nine ten", "x"),
        (1, "one two three four five six seven eight nine ten", "x"),
        (2, None, "y"),
        (3, "", None),
        (4, " \n\t ", "z"),
        (5, "again and again and " * 400, "z"),
        (None, "a text without an id of its own", "z"),
        (6, "é ü 漢字 ok\nline one here\nline one here\nlast #*$", "q"),
        (7, "w%d " * 3 % (1, 2, 3) + " ".join(f"word{i}" for i in range(3000)), "q"),
    ]
    return spark.createDataFrame(rows, "doc_id bigint, text string, score string")
