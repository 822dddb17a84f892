import pytest


@pytest.fixture(scope="session")
def docs_of(spark):
    def make(rows, extra=True):
        """documents with columns of clashing names: row, label, set, n, value, part, length, spans, base, text_ and more."""
        df = spark.createDataFrame([(i, t) for i, t in rows], "doc_id long, text string")
        if not extra:
            return df
        from pyspark.sql import functions as F

        names = ["lang", "source", "n_chars", "row", "label", "set", "n", "value", "part", "length", "spans", "base", "ids", "counts", "hashes", "host", "held_out", "n_words"]
        return df.withColumns({k: F.length("text").cast("long") if k == "n_chars" else F.lit("x") for k in names})

    return make


SF = "/root/testdata/sf0.001"
