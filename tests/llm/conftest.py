import pytest


@pytest.fixture(scope="session")
def make(spark):
    """A documents table of (doc_id, text) rows."""

    def documents(rows):
        return spark.createDataFrame(rows, "doc_id long, text string")

    return documents


@pytest.fixture(scope="session")
def docs(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet")
