"""Scalar expressions used by codecs and interpreters, and the function surface (vectorised, grouped, table-valued)."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from relcodec.plans.workloads import query
from relcodec.sources.tables import table

#: Interpreters: views of a value as a predictor for other attributes.
INTERPRETERS = {
    "bucket": lambda c, lo, hi, n: F.width_bucket(c, F.lit(lo), F.lit(hi), F.lit(n)),
    "length": lambda c: F.length(c),
    "prefix": lambda c, n: F.substring(c, 1, n),
    "hour": lambda c: F.hour(c),
    "weekday": lambda c: F.dayofweek(c),
    "sign": lambda c: F.signum(c).cast("int"),
    "member": lambda c, path: F.get_json_object(c, path),
}


def unary(n: Column) -> Column:
    """n ones and a zero."""
    return F.concat(F.repeat(F.lit("1"), n), F.lit("0"))


@query("fn_string", "SELECT c_custkey, length(c_name)::BIGINT AS n, substr(c_name, 10, 9) AS digits, upper(c_mktsegment) AS up, lpad(c_custkey::VARCHAR, 9, '0') AS padded, replace(c_name, '#', '-') AS dashed FROM customer")
def fn_string(spark, sf_dir):
    return table(spark, sf_dir, "customer").select("c_custkey", F.length("c_name").cast("long").alias("n"), F.substring("c_name", 10, 9).alias("digits"), F.upper("c_mktsegment").alias("up"), F.lpad(F.col("c_custkey").cast("string"), 9, "0").alias("padded"), F.replace("c_name", F.lit("#"), F.lit("-")).alias("dashed"))


@query("fn_unary", "SELECT n_regionkey, repeat('1', n_regionkey) || '0' AS code FROM nation")
def fn_unary(spark, sf_dir):
    return table(spark, sf_dir, "nation").select("n_regionkey", unary(F.col("n_regionkey")).alias("code"))


@query("fn_url_parts", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages")
def fn_url_parts(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", F.parse_url("url", F.lit("PROTOCOL")).alias("scheme"), F.parse_url("url", F.lit("HOST")).alias("host"))


@query("fn_bits", "SELECT n_nationkey, bin(n_nationkey) AS bits, bit_count(n_nationkey)::BIGINT AS ones, (n_nationkey::BIGINT << 3) AS up, xor(n_nationkey, 21)::BIGINT AS flipped FROM nation")
def fn_bits(spark, sf_dir):
    k = F.col("n_nationkey")
    return table(spark, sf_dir, "nation").select("n_nationkey", F.bin(k.cast("long")).alias("bits"), F.bit_count(k).cast("long").alias("ones"), F.shiftleft(k.cast("long"), 3).alias("up"), k.bitwiseXOR(F.lit(21)).cast("long").alias("flipped"))


@query("fn_math", "SELECT p_partkey, round(log2(p_size), 6) AS l, ceil(p_retailprice)::BIGINT AS up, (p_partkey % 7)::BIGINT AS m, round(exp(-p_size / 10.0), 6) AS e, greatest(p_size, 25)::BIGINT AS g FROM part")
def fn_math(spark, sf_dir):
    return table(spark, sf_dir, "part").select("p_partkey", F.round(F.log2(F.col("p_size").cast("double")), 6).alias("l"), F.ceil("p_retailprice").alias("up"), F.pmod(F.col("p_partkey"), F.lit(7)).cast("long").alias("m"), F.round(F.exp(-F.col("p_size") / 10.0), 6).alias("e"), F.greatest("p_size", F.lit(25)).cast("long").alias("g"))


@query("fn_datetime", "SELECT o_orderkey, epoch_us(o_orderdate)::BIGINT AS us, datediff('day', TIMESTAMP '1970-01-01', o_orderdate)::BIGINT AS days, dayofweek(o_orderdate)::BIGINT + 1 AS weekday FROM orders")
def fn_datetime(spark, sf_dir):
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.unix_micros(d.cast("timestamp")).alias("us"), F.unix_date(d.cast("date")).cast("long").alias("days"), F.dayofweek(d).cast("long").alias("weekday"))


@query("fn_array", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS positive FROM embeddings")
def fn_array(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@query("interval_fold", "SELECT l_linenumber, (l_linenumber * 4096 + l_linenumber * 64 + l_linenumber)::BIGINT AS folded FROM (SELECT DISTINCT l_linenumber FROM lineitem)")
def interval_fold(spark, sf_dir):
    """A product of nested choices as a fold."""
    d = table(spark, sf_dir, "lineitem").select("l_linenumber").distinct()
    steps = F.array_repeat(F.col("l_linenumber").cast("long"), 3)
    return d.select("l_linenumber", F.aggregate(steps, F.lit(0).cast("long"), lambda a, x: a * 64 + x).alias("folded"))


@query("fn_map", "SELECT r_regionkey, r_name AS name, (r_regionkey * 2)::BIGINT AS twice FROM region")
def fn_map(spark, sf_dir):
    m = table(spark, sf_dir, "region").select("r_regionkey", F.map_from_arrays(F.array(F.lit("name")), F.array("r_name")).alias("a"), F.transform_values(F.create_map(F.lit("twice"), F.col("r_regionkey")), lambda k, v: v * 2).alias("b"))
    return m.select("r_regionkey", F.element_at("a", "name").alias("name"), F.element_at("b", "twice").cast("long").alias("twice"))


@query("fn_json_props", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")
def fn_json_props(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("fn_conditional", "SELECT doc_id, coalesce(quality, -1)::BIGINT AS q, nullif(toxic, 0)::BIGINT AS t, CASE WHEN quality = 1 THEN 'good' WHEN quality = 0 THEN 'bad' ELSE 'none' END AS word FROM documents LEFT JOIN labels USING (doc_id)")
def fn_conditional(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    return d.select("doc_id", F.coalesce("quality", F.lit(-1)).cast("long").alias("q"), F.nullif("toxic", F.lit(0)).cast("long").alias("t"), F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "bad").otherwise("none").alias("word"))


@query("fn_hash", "SELECT n_nationkey, sha256(n_name) AS digest FROM nation")
def fn_hash(spark, sf_dir):
    return table(spark, sf_dir, "nation").select("n_nationkey", F.sha2("n_name", 256).alias("digest"))


@query("udf_expected_bits", "SELECT p_partkey, round(p_size * 0.5, 4) AS bits FROM part")
def udf_expected_bits(spark, sf_dir):
    """The vectorised form of a cost function, registered for SQL."""
    def bits(size: pd.Series) -> pd.Series:
        return size * 0.5

    spark.udf.register("expected_bits", F.pandas_udf(bits, "double"))
    table(spark, sf_dir, "part").createOrReplaceTempView("_part_for_bits")
    return spark.sql("SELECT p_partkey, round(expected_bits(p_size), 4) AS bits FROM _part_for_bits")


@query("udf_huffman_bits")
def udf_huffman_bits(spark, sf_dir):
    """Bits a row of a prefix code, and the entropy that it is within one bit of."""
    from relcodec import stats
    from relcodec.baselines import huffman_bits

    p = table(spark, sf_dir, "part")
    return spark.createDataFrame([(huffman_bits(p, "p_brand") / p.count(), stats.entropy(p, ["p_brand"]).first()["bits"])], "huffman_bits double, entropy_bits double")


@query("udtf_tree_steps", "SELECT p_size, s::BIGINT AS step FROM (SELECT DISTINCT p_size FROM part), range(1, 51) AS t(s) WHERE s <= p_size AND p_size <= 5")
def udtf_tree_steps(spark, sf_dir):
    """The steps that a value takes down an endless tree, as a table function."""
    class TreeSteps:
        def eval(self, value: int):
            for s in range(1, value + 1):
                yield (s,)

    spark.udtf.register("tree_steps", F.udtf(TreeSteps, returnType="step bigint"))
    table(spark, sf_dir, "part").select("p_size").distinct().filter("p_size <= 5").createOrReplaceTempView("_sizes_for_steps")
    return spark.sql("SELECT p_size, step FROM _sizes_for_steps, LATERAL tree_steps(p_size)")


