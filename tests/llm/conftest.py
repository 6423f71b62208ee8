import pytest
from pyspark.sql import functions as F

from hopframe.exec.importing import importable


@pytest.fixture(autouse=True)
def _path(spark):
    importable(spark)


@pytest.fixture(scope="session")
def docs_of(spark):
    """A documents table with clashing further columns, from (doc_id, text) pairs."""

    def make(rows):
        df = spark.createDataFrame(rows, "doc_id long, text string")
        for name in ("n", "rep", "band", "key", "part", "run", "digest", "mini", "bands", "kept", "score", "component_id", "length", "row_id", "lang", "source"):
            df = df.withColumn(name, F.lit("x"))
        return df.withColumn("n_chars", F.length("text").cast("long"))

    return make


@pytest.fixture(scope="session")
def documents(spark):
    return spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
