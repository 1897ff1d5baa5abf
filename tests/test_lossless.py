"""Archives give back every value of every type, late misfits and NULLs included."""

import datetime
import decimal

import pytest
from pyspark.sql import functions as F

from relcodec import archive, measures
from relcodec.schema import infer_spec


def back(spark, df, tmp_path, **options):
    archive.compress(df, str(tmp_path / "a"), archive.Options(**({"structure": "empty"} | options)))
    return archive.decompress(spark, str(tmp_path / "a"))


def same(spark, df, tmp_path, **options):
    got = back(spark, df, tmp_path, **options)
    assert got.schema.simpleString() == df.schema.simpleString()
    as_text = lambda d: sorted(map(repr, d.collect()))
    assert as_text(got) == as_text(df)


def rows_with_late_misfits(good, odd, n=260):
    """n usual values, more than the probe looks at, then odd ones and a NULL."""
    return [(good(i),) for i in range(n)] + [(x,) for x in odd] + [(None,)]


CASES = {
    "array<float>": (lambda i: [i / 4, i * 1.5], [[], [1.0], [1.0, None], [float("nan"), 2.0], [-0.0, 1.0], [1.0, 2.0, 3.0]]),
    "array<double>": (lambda i: [i / 3, 0.1 * i], [[0.1, 0.333], [1e308, 5e-324], [float("inf"), 0.0], [], None]),
    "array<bigint>": (lambda i: [i, i * i], [[2**62 + 1, -(2**63)], [None, 1], []]),
    "array<string>": (lambda i: [f"a{i}", "b"], [[], [None], ["", "ä"]]),
    "struct<a:bigint,b:string>": (lambda i: (i, f"x{i}"), [(None, None), (1, None)]),
    "map<string,double>": (lambda i: {"k": i / 2}, [{}, {"k": None}, {"a b": 0.1}]),
    "decimal(9,2)": (lambda i: decimal.Decimal(i) / 4, [decimal.Decimal("-9999999.99"), decimal.Decimal("9999999.99")]),
    "decimal(18,6)": (lambda i: decimal.Decimal(i) / 8, [decimal.Decimal("999999999999.999999"), decimal.Decimal("-0.000001")]),
    "decimal(38,10)": (lambda i: decimal.Decimal(i) / 16, [decimal.Decimal("1234567890123456789012345678.0123456789")]),
    "bigint": (lambda i: i * 10**12, [2**63 - 1, -(2**63)]),
    "double": (lambda i: i / 7, [float("nan"), float("inf"), -float("inf"), -0.0, 5e-324, 1e308]),
    "float": (lambda i: i / 8, [1e38, -1e-30, 3.25]),
    "binary": (lambda i: bytearray([i % 256, 255, 0]), [bytearray(), bytearray(b"\xff\xfe")]),
    "boolean": (lambda i: i % 2 == 0, []),
    "date": (lambda i: datetime.date(1990, 1, 1) + datetime.timedelta(days=i * 3), [datetime.date(1, 1, 1), datetime.date(9999, 12, 31)]),
    "timestamp_ntz": (lambda i: datetime.datetime(2000, 1, 1) + datetime.timedelta(seconds=i * 61), [datetime.datetime(1950, 5, 5, 1, 2, 3, 456789)]),
    "string": (lambda i: f"Item#{i:06d}", ["", "Item#1", "Item#0000001", "ß\U0001f600", "nothing alike"]),
}


@pytest.mark.parametrize("dtype", CASES)
def test_round_trip_of_every_type(spark, tmp_path, dtype):
    good, odd = CASES[dtype]
    df = spark.createDataFrame(rows_with_late_misfits(good, odd), f"v {dtype}").coalesce(1)
    same(spark, df, tmp_path)


@pytest.mark.parametrize("texts", [['{"k": %d}', '{"k": 1.5}', '{"k": 7, "z": 1}', "{}", "[]", "no json"], ["https://h%d.org/a/%d", "ftp://x", "https://h.org/a/007", "://", "x"], ["Customer#%09d", "Customer#12345678901234567890", "customer"]])
def test_round_trip_of_codecs(spark, tmp_path, texts):
    rows = [(texts[0].replace("%09d", f"{i:09d}").replace("%d", str(i)),) for i in range(300)] + [(t,) for t in texts[1:]] + [(None,)] * 3
    same(spark, spark.createDataFrame(rows, "v string").coalesce(1), tmp_path)


def test_all_null_and_empty_tables(spark, tmp_path):
    df = spark.createDataFrame([(None, None, None)] * 5, "a bigint, b string, c array<double>")
    same(spark, df, tmp_path / "n")
    same(spark, df.limit(0), tmp_path / "e")


def test_types_without_an_exact_form_are_refused(spark, tmp_path):
    with pytest.raises(TypeError, match="column i"):
        infer_spec(spark.sql("SELECT INTERVAL 3 DAYS AS i"))
    with pytest.raises(TypeError, match="column m"):
        archive.compress(spark.sql("SELECT map(1, 2) AS m"), str(tmp_path / "m"))


def test_decimals_within_a_tolerance(spark, tmp_path):
    df = spark.range(1000).select("id", (F.col("id") * F.lit(decimal.Decimal("1.37"))).cast("decimal(12,2)").alias("v"))
    spec = infer_spec(df).with_tolerance(0.5, ["v"])
    archive.compress(df, str(tmp_path / "a"), archive.Options(structure="empty"), spec)
    worst = {r["attribute"]: r for r in measures.closeness(df, archive.decompress(spark, str(tmp_path / "a")), "id", spec).collect()}
    assert 0 < worst["v"]["max_error"] <= 0.5 and worst["v"]["violations"] == 0 == worst["id"]["max_error"]


def test_closeness_sees_lost_rows(spark):
    df = spark.range(10).select("id", (F.col("id") * 2).alias("v"))
    spec = infer_spec(df)
    seen = {r["attribute"]: (r["violations"], r["lost"]) for r in measures.closeness(df, df.filter("id <> 3"), "id", spec).collect()}
    assert seen["v"] == (1, 1)


def test_a_named_number_of_few_values_has_its_tolerance(spark):
    df = spark.range(4000).selectExpr("id", "case when id % 50 = 0 then null else round((id % 40) * 2.5D, 1) end as price", "id % 3 as part")
    spec = infer_spec(df)
    assert [spec[n].kind for n in ("price", "part")] == ["categorical"] * 2
    near = spec.with_tolerance_pct(5.0, ["price"])
    assert [near[n].kind for n in ("price", "part")] == ["decimal", "categorical"]
    assert near["price"].tolerance == pytest.approx(97.5 * 0.05)
    got = near.quantise(df)
    rows = df.join(got.withColumnRenamed("price", "back"), "id").collect()
    assert all((r["back"] is None) == (r["price"] is None) for r in rows)
    errors = [abs(r["back"] - r["price"]) for r in rows if r["price"] is not None]
    assert 0 < max(errors) <= near["price"].tolerance + 1e-9
    # Without names, and at a tolerance of nothing, categories stay exact.
    assert spec.with_tolerance_pct(5.0)["price"].kind == spec.with_tolerance(0.0, ["price"])["price"].kind == "categorical"
