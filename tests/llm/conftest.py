import pytest
from pyspark.sql import types as T

DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())])


@pytest.fixture(scope="session")
def docs_of(spark):
    """Documents from (doc_id, text[, source]) rows."""

    def make(rows):
        return spark.createDataFrame([(r[0], r[1], "en", r[2] if len(r) > 2 else "s", len(r[1] or "")) for r in rows], DOCS)

    return make


@pytest.fixture(scope="session")
def table_dir(spark, tmp_path_factory):
    """A folder with the given tables as Parquet."""

    def make(**frames):
        path = tmp_path_factory.mktemp("tables")
        for name, frame in frames.items():
            frame.coalesce(2).write.parquet(str(path / f"{name}.parquet"))
        return str(path)

    return make
