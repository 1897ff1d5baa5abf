"""Scans, filters, joins, aggregations, windows, sorts and set operations that archives are used with."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec import stats
from relcodec.plans.workloads import query
from relcodec.sources.tables import scratch, star, table


@query("scan_parquet_pruned", "SELECT l_orderkey, l_extendedprice FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'")
def scan_parquet_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").filter((F.col("l_quantity") >= 45) & (F.col("l_returnflag") == "R")).select("l_orderkey", "l_extendedprice")


@query("json_roundtrip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def json_roundtrip(spark, sf_dir):
    n, path = table(spark, sf_dir, "nation"), scratch(spark)
    n.write.json(path)
    return spark.read.schema(n.schema).json(path).select("n_nationkey", "n_name", "n_regionkey")


@query("csv_roundtrip", "SELECT s_suppkey, s_name, s_nationkey, s_acctbal FROM supplier")
def csv_roundtrip(spark, sf_dir):
    s, path = table(spark, sf_dir, "supplier"), scratch(spark)
    s.write.option("header", "true").csv(path)
    return spark.read.schema(s.schema).option("header", "true").csv(path).select("s_suppkey", "s_name", "s_nationkey", "s_acctbal")


@query("partition_pruned_scan", "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderstatus = 'F'")
def partition_pruned_scan(spark, sf_dir):
    path = scratch(spark)
    table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).filter("o_orderstatus = 'F'").select("o_orderkey", "o_orderpriority")


@query("archive_source_scan", "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders WHERE o_orderkey < 500")
def archive_source_scan(spark, sf_dir):
    """The archive through the data source, blocks chosen by zone maps."""
    from relcodec import archive as archives
    from relcodec.sources import datasource

    path = scratch(spark)
    archives.compress(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus"), path, archives.Options(structure="empty", zones=("o_orderkey",), block_rows=2048))
    return datasource.read(spark, path).filter("o_orderkey < 500")


@query("filter_predicates", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_name LIKE '%a%' AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#13') AND NOT regexp_matches(p_type, '^Z')")
def filter_predicates(spark, sf_dir):
    return table(spark, sf_dir, "part").filter(F.col("p_size").between(10, 20) & F.col("p_name").like("%a%") & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13") & ~F.col("p_type").rlike("^Z")).select("p_partkey")


@query("filter_null_logic", "SELECT doc_id, quality IS NULL AS unlabelled FROM documents LEFT JOIN labels USING (doc_id) WHERE quality IS NULL OR NOT (toxic = 1 AND quality = 0)")
def filter_null_logic(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    return d.filter(F.col("quality").isNull() | ~((F.col("toxic") == 1) & (F.col("quality") == 0))).select("doc_id", F.col("quality").isNull().alias("unlabelled"))


LOSSY = "((round(o_totalprice * 100)::BIGINT - lo) // 2001 * 2001 + lo + 1000) / 100.0"


def lossy_prices(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select("o_orderkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("c"))
    lo = o.agg(F.min("c").alias("lo"))
    return o.crossJoin(F.broadcast(lo)).select("o_orderkey", (F.expr("(c - lo) div 2001 * 2001 + lo + 1000") / 100.0).alias("x"))


@query("filter_surely", f"SELECT o_orderkey FROM orders, (SELECT min(round(o_totalprice * 100))::BIGINT AS lo FROM orders) WHERE {LOSSY} > 100000 + 10")
def filter_surely(spark, sf_dir):
    """Rows whose original surely exceeds the bound, whatever the tolerance hid."""
    return lossy_prices(spark, sf_dir).filter(F.col("x") > 100000 + 10).select("o_orderkey")


@query("filter_maybe", f"SELECT o_orderkey FROM orders, (SELECT min(round(o_totalprice * 100))::BIGINT AS lo FROM orders) WHERE {LOSSY} > 100000 - 10")
def filter_maybe(spark, sf_dir):
    return lossy_prices(spark, sf_dir).filter(F.col("x") > 100000 - 10).select("o_orderkey")


@query("join_masses_bits", "WITH c AS (SELECT p_brand, count(*) AS n, sum(count(*)) OVER () AS t FROM part GROUP BY 1) SELECT p_partkey, round(-log2(n / t), 6) AS bits FROM part JOIN c USING (p_brand)")
def join_masses_bits(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    c = p.groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"))
    total = c.agg(F.sum("n").alias("t"))
    return p.join(F.broadcast(c.crossJoin(total)), "p_brand").select("p_partkey", F.round(-F.log2(F.col("n") / F.col("t")), 6).alias("bits"))


@query("star_join", "SELECT r_name, count(*)::BIGINT AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def star_join(spark, sf_dir):
    return star(spark, sf_dir).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@query("join_hinted", "SELECT o_orderpriority, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def join_hinted(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.sum("l_quantity").alias("q"))


@query("left_join_labels", "SELECT doc_id, lang, quality, toxic FROM documents LEFT JOIN labels USING (doc_id)")
def left_join_labels(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id", "left")


@query("full_join_labels", "SELECT doc_id, item_id FROM (SELECT doc_id FROM labels) FULL JOIN (SELECT item_id FROM benchmark) ON doc_id = item_id")
def full_join_labels(spark, sf_dir):
    return table(spark, sf_dir, "labels").select("doc_id").join(table(spark, sf_dir, "benchmark").select("item_id"), F.col("doc_id") == F.col("item_id"), "full")


@query("anti_orders_without_lines", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def anti_orders_without_lines(spark, sf_dir):
    return table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").select("o_orderkey")


@query("semi_labelled_docs", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def semi_labelled_docs(spark, sf_dir):
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id", "left_semi").select("doc_id")


@query("cross_representatives", "WITH r AS (SELECT p_brand, p_type, p_size FROM part WHERE p_partkey <= 4), m AS (SELECT p.p_partkey, max((p.p_brand = r.p_brand)::INT + (p.p_type = r.p_type)::INT + (p.p_size = r.p_size)::INT) AS best FROM part p, r GROUP BY 1) SELECT best::BIGINT AS best, count(*)::BIGINT AS n FROM m GROUP BY 1")
def cross_representatives(spark, sf_dir):
    """Best match of every row with a handful of representative rows."""
    p = table(spark, sf_dir, "part")
    reps = p.filter("p_partkey <= 4").select(F.struct("p_brand", "p_type", "p_size").alias("r"))
    same = sum((F.col(c) == F.col(f"r.{c}")).cast("int") for c in ("p_brand", "p_type", "p_size"))
    return p.crossJoin(F.broadcast(reps)).groupBy("p_partkey").agg(F.max(same).alias("best")).groupBy(F.col("best").cast("long").alias("best")).agg(F.count(F.lit(1)).alias("n"))


@query("range_join_buckets", "SELECT b, count(*)::BIGINT AS n FROM events JOIN (SELECT i AS b, i * 50.0 AS lo, i * 50.0 + 50 AS hi FROM range(0, 10) AS t(i)) ON value >= lo AND value < hi GROUP BY 1")
def range_join_buckets(spark, sf_dir):
    b = spark.range(10).select(F.col("id").alias("b"), (F.col("id") * 50.0).alias("lo"), (F.col("id") * 50.0 + 50).alias("hi"))
    e = table(spark, sf_dir, "events")
    return e.join(F.broadcast(b), (e.value >= b.lo) & (e.value < b.hi)).groupBy("b").agg(F.count(F.lit(1)).alias("n"))


@query("asof_model_version", "WITH m AS (SELECT i AS version, TIMESTAMP '2024-01-01' + to_days(5 * i::INT) AS since FROM range(0, 6) AS t(i)) SELECT version, count(*)::BIGINT AS n FROM (SELECT event_id, max(version) AS version FROM events JOIN m ON since <= ts GROUP BY 1) GROUP BY 1")
def asof_model_version(spark, sf_dir):
    """The model version valid at each event: the latest one that is not newer."""
    m = spark.range(6).select(F.col("id").alias("version"), F.expr("TIMESTAMP_NTZ '2024-01-01' + make_interval(0, 0, 0, cast(5 * id as int))").alias("since"))
    e = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp_ntz").alias("ts"))
    return e.join(F.broadcast(m), F.col("since") <= F.col("ts")).groupBy("event_id").agg(F.max("version").alias("version")).groupBy("version").agg(F.count(F.lit(1)).alias("n"))


@query("contingency_counts", "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS cnt FROM lineitem GROUP BY 1, 2")
def contingency_counts(spark, sf_dir):
    return stats.counts(table(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"])


@query("contingency_grouping_sets", "SELECT l_returnflag, l_linestatus, l_linenumber, count(*)::BIGINT AS cnt, grouping(l_returnflag)::BIGINT AS no_flag FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linenumber), ())")
def contingency_grouping_sets(spark, sf_dir):
    """All candidate tables of a round of the search from one scan."""
    l = table(spark, sf_dir, "lineitem")  # noqa: E741
    cols = [F.col("l_returnflag"), F.col("l_linestatus"), F.col("l_linenumber")]
    return l.groupingSets([cols[:2], cols[2:], []], *cols).agg(F.count(F.lit(1)).alias("cnt"), F.grouping("l_returnflag").cast("long").alias("no_flag"))


@query("contingency_cube", "SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS cnt FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def contingency_cube(spark, sf_dir):
    return table(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("cnt"))


@query("contingency_rollup", "SELECT n_regionkey, n_name, count(*)::BIGINT AS cnt FROM nation GROUP BY ROLLUP (n_regionkey, n_name)")
def contingency_rollup(spark, sf_dir):
    return table(spark, sf_dir, "nation").rollup("n_regionkey", "n_name").agg(F.count(F.lit(1)).alias("cnt"))


@query("domain_sizes", "SELECT count(DISTINCT l_partkey)::BIGINT AS parts, count(DISTINCT l_suppkey)::BIGINT AS suppliers, count(DISTINCT l_quantity)::BIGINT AS quantities FROM lineitem")
def domain_sizes(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_quantity").alias("quantities"))


@query("domain_sizes_approx")
def domain_sizes_approx(spark, sf_dir):
    """Sketched and exact domain size; the sketch's standard error is one percent."""
    return table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.01).alias("approximate"), F.count_distinct("l_partkey").alias("exact"))


@query("agg_collect", "SELECT n_regionkey, array_to_string(list_sort(list(n_name)), ',') AS names FROM nation GROUP BY 1")
def agg_collect(spark, sf_dir):
    return table(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


@query("moments_numeric", "SELECT count(*)::BIGINT AS n, round(avg(value), 4) AS mean, round(stddev_pop(value), 4) AS deviation, round(min(value), 2) AS lo, round(max(value), 2) AS hi FROM events")
def moments_numeric(spark, sf_dir):
    return table(spark, sf_dir, "events").agg(F.count("value").alias("n"), F.round(F.avg("value"), 4).alias("mean"), F.round(F.stddev_pop("value"), 4).alias("deviation"), F.round(F.min("value"), 2).alias("lo"), F.round(F.max("value"), 2).alias("hi"))


@query("linear_fit", "SELECT round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 2) AS intercept, round(corr(l_quantity, l_extendedprice), 6) AS correlation FROM lineitem")
def linear_fit(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").agg(F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.regr_intercept("l_extendedprice", "l_quantity"), 2).alias("intercept"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("correlation"))


@query("quantiles_exact", "SELECT round(quantile_cont(value, 0.25), 4) AS q1, round(median(value), 4) AS q2, round(quantile_cont(value, 0.75), 4) AS q3 FROM events")
def quantiles_exact(spark, sf_dir):
    return table(spark, sf_dir, "events").agg(F.round(F.percentile("value", F.lit(0.25)), 4).alias("q1"), F.round(F.median("value"), 4).alias("q2"), F.round(F.percentile("value", F.lit(0.75)), 4).alias("q3"))


@query("mode_per_group", "SELECT c_nationkey, c_mktsegment FROM (SELECT c_nationkey, c_mktsegment, row_number() OVER (PARTITION BY c_nationkey ORDER BY count(*) DESC, c_mktsegment) AS r FROM customer GROUP BY 1, 2) WHERE r = 1")
def mode_per_group(spark, sf_dir):
    n = table(spark, sf_dir, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    return n.groupBy("c_nationkey").agg(F.min(F.struct(-F.col("n"), "c_mktsegment"))["c_mktsegment"].alias("c_mktsegment"))


@query("count_if_checks", "SELECT count(*) FILTER (l_discount > 0.05)::BIGINT AS high, count(*) FILTER (l_tax = 0)::BIGINT AS untaxed, bit_xor(l_orderkey)::BIGINT AS keys FROM lineitem")
def count_if_checks(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").agg(F.count_if(F.col("l_discount") > 0.05).alias("high"), F.count_if(F.col("l_tax") == 0).alias("untaxed"), F.bit_xor("l_orderkey").alias("keys"))


@query("histogram_cells", "SELECT floor(c_acctbal / 500)::BIGINT AS cell, count(*)::BIGINT AS n FROM customer GROUP BY 1")
def histogram_cells(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupBy(F.floor(F.col("c_acctbal") / 500).alias("cell")).agg(F.count(F.lit(1)).alias("n"))


@query("pivot_orders", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F')::BIGINT AS F, count(*) FILTER (o_orderstatus = 'O')::BIGINT AS O, count(*) FILTER (o_orderstatus = 'P')::BIGINT AS P FROM orders GROUP BY 1")
def pivot_orders(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)


@query("unpivot_lineitem", "SELECT measure, round(sum(x), 2) AS total FROM (UNPIVOT (SELECT l_quantity, l_tax FROM lineitem) ON l_quantity, l_tax INTO NAME measure VALUE x) GROUP BY 1")
def unpivot_lineitem(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select("l_quantity", "l_tax").unpivot([], ["l_quantity", "l_tax"], "measure", "x").groupBy("measure").agg(F.round(F.sum("x"), 2).alias("total"))


@query("rank_domain_values", "SELECT p_brand, (row_number() OVER (ORDER BY count(*) DESC, p_brand))::BIGINT AS rank, count(*)::BIGINT AS n FROM part GROUP BY 1")
def rank_domain_values(spark, sf_dir):
    n = table(spark, sf_dir, "part").groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("rank", F.row_number().over(W.orderBy(F.desc("n"), "p_brand")).cast("long"))


@query("ntile_buckets", "SELECT c_nationkey, b::BIGINT AS b, count(*)::BIGINT AS n FROM (SELECT c_nationkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS b FROM customer) GROUP BY 1, 2")
def ntile_buckets(spark, sf_dir):
    t = table(spark, sf_dir, "customer").withColumn("b", F.ntile(4).over(W.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).cast("long"))
    return t.groupBy("c_nationkey", "b").agg(F.count(F.lit(1)).alias("n"))


@query("lead_event_gap", "SELECT event_id, epoch_us(lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) - epoch_us(ts) AS gap FROM events")
def lead_event_gap(spark, sf_dir):
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return table(spark, sf_dir, "events").select("event_id", (F.lead(us).over(W.partitionBy("user_id").orderBy("ts", "event_id")) - us).alias("gap"))


@query("bit_offsets", "SELECT n_nationkey, sum(length(n_name) * 8) OVER (ORDER BY n_nationkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)::BIGINT AS starts FROM nation")
def bit_offsets(spark, sf_dir):
    return table(spark, sf_dir, "nation").select("n_nationkey", F.sum(F.length("n_name").cast("long") * 8).over(W.orderBy("n_nationkey").rowsBetween(W.unboundedPreceding, -1)).alias("starts"))


@query("rolling_bits_range", "SELECT event_id, (sum(length(props)) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW))::BIGINT AS chars FROM events")
def rolling_bits_range(spark, sf_dir):
    s = F.expr("unix_micros(cast(ts as timestamp)) div 1000000")
    return table(spark, sf_dir, "events").withColumn("s", s).select("event_id", F.sum(F.length("props").cast("long")).over(W.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("chars"))


@query("config_totals", "SELECT DISTINCT l_returnflag, l_linenumber, count(*) OVER (PARTITION BY l_returnflag)::BIGINT AS config, count(*) OVER (PARTITION BY l_returnflag, l_linenumber)::BIGINT AS cell FROM lineitem")
def config_totals(spark, sf_dir):
    c = stats.counts(table(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linenumber"])
    return c.select("l_returnflag", "l_linenumber", F.sum("cnt").over(W.partitionBy("l_returnflag")).alias("config"), F.col("cnt").alias("cell"))


@query("first_2000", "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey LIMIT 2000")
def first_2000(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").limit(2000).select("l_orderkey", "l_linenumber", "l_partkey")


@query("topk_per_attribute", "SELECT o_orderpriority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def topk_per_attribute(spark, sf_dir):
    r = F.row_number().over(W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return table(spark, sf_dir, "orders").withColumn("r", r).filter("r <= 3").select("o_orderpriority", "o_orderkey")


@query("union_all_attributes", "SELECT 'c' AS kind, c_nationkey AS nation, c_acctbal AS balance FROM customer UNION ALL SELECT 's', s_nationkey, s_acctbal FROM supplier")
def union_all_attributes(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select(F.lit("c").alias("kind"), F.col("c_nationkey").alias("nation"), F.col("c_acctbal").alias("balance"))
    return c.unionByName(table(spark, sf_dir, "supplier").select(F.col("s_acctbal").alias("balance"), F.lit("s").alias("kind"), F.col("s_nationkey").alias("nation")))


@query("intersect_keys", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def intersect_keys(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(spark, sf_dir, "supplier").select("s_nationkey"))


@query("exceptall_multiset", "SELECT l_linenumber AS k FROM lineitem EXCEPT ALL SELECT p_size FROM part")
def exceptall_multiset(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select(F.col("l_linenumber").alias("k")).exceptAll(table(spark, sf_dir, "part").select("p_size"))
