"""The corpus pipeline: each stage on its predecessor's rows."""

import hashlib

from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"


def test_pipeline(spark, docs_of):
    import corpus_pipeline as cp
    from joincluster.llm import common, decontam, ngram_join, toxicity

    names = [n for n, _ in cp.STAGES]
    assert names == ["toxicity", "ngram_join", "decontamination", "pii", "packing"] and cp.ORACLE_SQL is None
    docs = common.table(spark, SF, "documents")
    kept = docs
    for name, stage in cp.STAGES[:-1]:
        new = common.written(stage(spark, kept, SF))
        assert new.columns == docs.columns and dict(new.dtypes) == dict(docs.dtypes)
        gone = kept.join(new.select("doc_id"), "doc_id", "left_anti").select("doc_id")
        if name == "toxicity":
            bad = toxicity.score(kept, common.table(spark, SF, "labels")).where("predicted = 1").select("doc_id")
            assert sorted(gone.collect()) == sorted(bad.collect())
        if name == "ngram_join":
            found = ngram_join.near_copies(kept, cp.SHINGLE, cp.PERCENT)
            assert sorted(gone.collect()) == sorted(found.where("component_id != doc_id").select("doc_id").collect())
        if name == "decontamination":
            bad = decontam.decontaminate(kept, common.table(spark, SF, "benchmark")).where("contaminated").select("doc_id")
            assert sorted(gone.collect()) == sorted(bad.collect())
        if name == "pii":
            assert gone.count() == 0 and new.where(F.col("text").rlike(r"[\w.]+@mail\d\.example\.com")).count() == 0
        kept = new
    packed = cp.STAGES[-1][1](spark, kept, SF)
    assert packed.select("doc_id").distinct().count() == kept.count()


def test_queries_are_registered():
    from joincluster.llm import queries

    got = queries.queries()
    assert [n for n in got if n.startswith("op")] == [n for n in got if n.split("_")[0] in {f"op{i}" for i in range(1, 11)}] and len(got) == 11
    assert set(queries.oracle_sql()) <= set(got)
    assert hashlib.sha256(b"").hexdigest()[:4] == "e3b0"
