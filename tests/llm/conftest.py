import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def docs(spark):
    """Builds a documents table; a row is (doc_id, text) or (doc_id, text, lang, source)."""

    def make(rows, extra=None):
        full = [(r[0], r[1], *(r[2:] or ("en", "s0")), len(r[1]) if r[1] is not None else None) for r in rows]
        frame = spark.createDataFrame(full, SCHEMA)
        from pyspark.sql import functions as F

        for name in extra or ():
            frame = frame.withColumn(name, F.lit("x"))
        return frame

    return make
