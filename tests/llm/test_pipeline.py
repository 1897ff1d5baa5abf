"""The pipeline on a small table with planted cases."""

import corpus_pipeline
from relcodec.llm import common


def test_stages(spark, tmp_path):
    docs = common.documents(spark, "/root/testdata/sf0.001")
    bench = common.table(spark, "/root/testdata/sf0.001", "benchmark").first()
    base = docs.orderBy("doc_id").first()["text"] or "some words"
    extra = [(9001, "1234 !!! ###", "en", "x", 12), (9002, base, "en", "x", 1), (9003, "Lead in words here. " + bench["text"] + " And out.", "en", "x", 1), (9004, None, "en", "x", None)]
    docs = docs.unionByName(spark.createDataFrame(extra, docs.schema))
    seen = [{r["doc_id"] for r in docs.select("doc_id").collect()}]
    for name, stage in corpus_pipeline.STAGES:
        docs = common.materialise(stage(spark, docs, "/root/testdata/sf0.001"))
        seen.append({r["doc_id"] for r in docs.select("doc_id").collect()})
        if name != "packing":
            assert tuple(docs.columns) == corpus_pipeline.COLUMNS
    assert {9001, 9004} <= seen[0] - seen[1] and 9002 in seen[1] - seen[2] and 9003 in seen[2] - seen[3] and seen[3] == seen[4] == seen[5]


def test_null_and_shared_ids(spark):
    sf = "/root/testdata/sf0.001"
    bench = common.table(spark, sf, "benchmark").first()["text"]
    texts = [" ".join(f"w{(i * 37 + k * k) % 997}" for k in range(90)) for i in range(4)]
    rows = [(None, texts[0]), (None, texts[1]), (None, texts[1]), (5, texts[1]), (7, texts[2]), (7, texts[3]), (None, "Lead in words here. " + bench + " And out.")]
    docs = spark.createDataFrame([(i, t, "en", "x", len(t)) for i, t in rows], common.documents(spark, sf).schema)
    left = common.materialise(corpus_pipeline.near_duplicates(spark, docs, sf))
    assert sorted(map(str, ((r["doc_id"], r["text"]) for r in left.collect()))) == sorted(map(str, [rows[0], *rows[3:]]))
    clean = corpus_pipeline.benchmark_leaks(spark, left, sf)
    assert sorted(map(str, ((r["doc_id"], r["text"]) for r in clean.collect()))) == sorted(map(str, [rows[0], *rows[3:6]]))


def test_empty_and_odd_tables(spark):
    sf = "/root/testdata/sf0.001"
    schema = common.documents(spark, sf).schema
    empty = spark.createDataFrame([], schema)
    long_text = " ".join(f"the{i % 977} and{i % 1009}" for i in range(60_000))
    odd = spark.createDataFrame([(1, "", None, None, 0), (2, None, "en", "x", None), (3, long_text, "en", "x", 1), (3, long_text, "en", "x", 1), (4, long_text, None, "y", 2)], schema)
    odd = odd.selectExpr("*", "1 AS _key", "2 AS class_id", "3 AS bands", "4 AS h")
    for name, stage in corpus_pipeline.STAGES:
        assert common.materialise(stage(spark, empty, sf)).count() == 0
        out = stage(spark, odd, sf)
        ids = {r["doc_id"] for r in out.collect()}
        assert ids == {"language": ids, "near_duplicates": {1, 2, 3}}.get(name, {1, 2, 3, 4}), name
        if name != "packing":
            assert tuple(out.columns) == corpus_pipeline.COLUMNS
