import pytest
from pyspark.sql import SparkSession


@pytest.fixture(scope="session")
def spark():
    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "4g").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def odd(spark):
    """Rows with nulls, empty and long texts, repeated rows and an extra column."""
    passage = " ".join(f"word{i}" for i in range(40))
    rows = [
        (1, None, None, None, None), (2, "", "en", "src0", 0), (3, passage, "en", "src0", 5), (3, passage, "en", "src0", 5), (3, "other text under the same id.\nagain", "en", None, 5),
        (None, "a row without an id " + passage, "de", "src1", 3), (7, "x", "fr", "src1", 1), (8, "before. " + passage + " after", "en", "src0", 9), (9, " ".join(["the"] * 5000), "en", "src2", 9), (10, "  \t\n ", None, "src2", 5),
    ]
    return spark.createDataFrame([(*r, "extra") for r in rows], DOCS + ", _extra string")
