import pytest

pipeline = pytest.importorskip("corpus_pipeline")

from prefix_credit.llm.common import staged  # noqa: E402
from tests.llm.test_operators import brute_components  # noqa: E402

SF = "/root/testdata/sf0.01"


def test_stages_against_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels = {r["doc_id"]: r for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    bench = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    assert [n for n, _ in pipeline.STAGES] == ["toxicity", "near_dedup", "decontamination", "packing"]
    kept = docs
    for name, stage in pipeline.STAGES:
        before = {r["doc_id"]: r["text"] for r in kept.collect()}
        kept = staged(stage(spark, kept, SF))
        after = {r["doc_id"] for r in kept.collect()}
        assert after <= set(before)
        gone = set(before) - after
        if name != "packing":
            assert kept.columns == docs.columns
        if name == "toxicity":
            clean = [k for k in before if k in labels and labels[k]["toxic"] == 0]
            toxic = [k for k in before if k in labels and labels[k]["toxic"] == 1]
            assert sum(k in gone for k in clean) <= 0.01 * len(clean) and sum(k in gone for k in toxic) >= 0.6 * len(toxic)
        elif name == "near_dedup":
            want = brute_components(before, 5, 80, 100)
            assert after == {k for k, (_, c) in want.items() if c == k}
        elif name == "decontamination":
            assert gone == {k for k, t in before.items() if any(b in t for b in bench)} | gone
            assert all(any(sum(w in t for w in b.split()) > 0.6 * len(b.split()) for b in bench) for k, t in before.items() if k in gone)
        else:
            assert not gone


def test_odd_documents_pass_through(spark, tmp_path):
    kind = "doc_id long, text string, lang string, source string, n_chars long, bucket int"
    docs = spark.createDataFrame([(1, None, None, None, None, 1), (2, "", "en", "s", 0, 1), (None, "null id text", "en", "s", 9, 1), (4, "w " * 50_000, "en", "s", 1, 1), (5, "twice the same", "en", "s", 1, 1), (5, "twice the same", "en", "s", 1, 1)], kind)
    for table in ("labels", "benchmark"):
        spark.read.parquet(f"{SF}/{table}.parquet").write.parquet(f"{tmp_path}/{table}.parquet")
    spark.read.parquet(f"{SF}/documents.parquet").filter("doc_id > 10").unionByName(docs, allowMissingColumns=True).write.parquet(f"{tmp_path}/documents.parquet")
    rows = pipeline.run(spark, str(tmp_path)).collect()
    ids = [r["doc_id"] for r in rows]
    assert {1, 2, None, 4, 5} <= set(ids) and ids.count(5) == 2
    empty = spark.read.parquet(f"{tmp_path}/documents.parquet").limit(0)
    for _, stage in pipeline.STAGES[:3]:
        empty = stage(spark, empty, str(tmp_path))
    assert empty.count() == 0
