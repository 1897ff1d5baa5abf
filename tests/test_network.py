"""Structure search, fitted networks and archives on small tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from relcodec import archive as archives
from relcodec import stats
from relcodec.measures import chain_bits, clustered_bits, closeness
from relcodec.network import Structure, brute_force_structure, learn_structure, score_local
from relcodec.schema import infer_spec
from relcodec.sources.tables import scratch


def test_formulas():
    assert round(chain_bits(1000, 4, 2 / 3), 2) == 1447.17
    assert round(clustered_bits(100, 0.2), 2) == 73.19


def test_search_finds_copies_and_leaves_noise_alone():
    rng = np.random.default_rng(0)
    a = rng.integers(0, 8, 3000)
    symbols = {"a": a, "copy": (a * 3) % 8, "noise": rng.integers(0, 2, 3000)}
    s = learn_structure(symbols, {"a": 8, "copy": 8, "noise": 2})
    assert ("a", "copy") in s.edges or ("copy", "a") in s.edges
    assert not [e for e in s.edges if "noise" in e]


def test_search_against_all_orders():
    rng = np.random.default_rng(1)
    a, b = rng.integers(0, 4, 2000), rng.integers(0, 4, 2000)
    symbols = {"a": a, "b": b, "c": (a + b) % 4, "d": a // 2}
    domains = {"a": 4, "b": 4, "c": 4, "d": 2}
    best, _ = brute_force_structure(symbols, domains)
    s = learn_structure(symbols, domains, lookahead=2)
    total = 0.0
    for child, parents in s.parents.items():
        config = np.zeros(2000, np.int64)
        for p in parents:
            config = config * domains[p] + symbols[p]
        total += score_local(symbols[child], config, domains[child])
    assert total <= best * 1.25


def test_cycles_are_refused():
    with pytest.raises(ValueError):
        Structure.from_edges(["a", "b"], [("a", "b"), ("b", "a")])
    assert Structure.from_edges(["a", "b"], [("b", "a")]).coding_order == ["b", "a"]


def frame(spark):
    rows = [(i, f"id{i:06d}", "xy"[i % 2], None if i % 7 == 0 else i / 4, f"täxt {i} 😀" if i % 3 else "", -1.5e-9 * i) for i in range(400)]
    return spark.createDataFrame(rows, "k long, name string, flag string, part double, words string, tiny double")


@pytest.mark.parametrize("delta", [False, True])
def test_round_trip(spark, delta):
    df = frame(spark)
    path = scratch(spark)
    archives.compress(df, path, archives.Options(delta=delta, block_rows=100, structure="empty" if delta else "learn"))
    back = archives.decompress(spark, path)
    assert df.exceptAll(back).count() == 0 and back.exceptAll(df).count() == 0
    if not delta:
        some = archives.decompress(spark, path, ["flag", "name"])
        assert some.columns == ["name", "flag"] and some.distinct().count() == 400


def test_empty_and_single_rows(spark):
    for rows in ([], [(1, "a", None)], [(5, "c", 1.0)] * 50):
        df = spark.createDataFrame(rows, "k long, s string, x double")
        path = scratch(spark)
        archives.compress(df, path)
        back = archives.decompress(spark, path)
        assert sorted(map(tuple, back.collect()), key=str) == sorted(rows, key=str)


def test_lookup(spark):
    df = spark.range(1000).select("id", (F.col("id") * 3 % 17).alias("m"))
    path = scratch(spark)
    archive = archives.compress(df.coalesce(1), path, archives.Options(block_rows=300))
    blocks = [r["block_id"] for r in archive.blocks(spark).orderBy("block_id").collect()]
    got = {tuple(r) for r in archives.lookup(spark, path, [(blocks[0], 5), (blocks[2], 299), (blocks[3], 0)]).collect()}
    assert got == {(5, 15), (899, 899 * 3 % 17), (900, 900 * 3 % 17)}


def test_tolerance_holds(spark):
    df = spark.range(500).select("id", (F.sin("id") * 100).alias("x"))
    spec = infer_spec(df).with_tolerance(0.5, ["x"])
    path = scratch(spark)
    archives.compress(df, path, archives.Options(structure="empty"), spec)
    report = {r["attribute"]: r for r in closeness(df, archives.decompress(spark, path), "id", spec).collect()}
    assert report["x"]["violations"] == 0 and report["x"]["max_error"] > 0.1 and report["id"]["max_error"] == 0


def test_objectives_agree(spark):
    df = spark.range(600).select((F.col("id") % 5).cast("string").alias("a"), (F.col("id") % 5 % 2).cast("string").alias("b"))
    spec = infer_spec(df)
    out = {r["node"]: r for r in stats.node_objectives(spec.images(df), spec, Structure.from_edges(["a", "b"], [("a", "b")])).collect()}
    assert out["b"]["data_bits"] == pytest.approx(0) and out["a"]["data_bits"] == pytest.approx(600 * np.log2(5))
