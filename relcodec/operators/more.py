"""Operators around archives that the workloads do not use themselves, each with the SQL it is compared with."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec import archive as archives
from relcodec import stats
from relcodec.plans.workloads import CODES_SQL, NODES, PAIRS, query, short_codes
from relcodec.sources.tables import STAR, STAR_SQL, scratch, star, table


@query("literal_intervals", "SELECT letter, low::DOUBLE AS low, high::DOUBLE AS high, count(l_orderkey)::BIGINT AS n FROM (VALUES ('A', 0.0, 0.4), ('N', 0.4, 0.6), ('R', 0.6, 1.0)) AS t(letter, low, high) LEFT JOIN lineitem ON l_returnflag = letter GROUP BY ALL")
def literal_intervals(spark, sf_dir):
    """Intervals given as literals, and how many rows of lineitem each one codes."""
    t = spark.sql("SELECT letter, cast(low AS double) AS low, cast(high AS double) AS high FROM VALUES ('A', 0.0, 0.4), ('N', 0.4, 0.6), ('R', 0.6, 1.0) AS t(letter, low, high)")
    n = table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("letter")).agg(F.count("l_orderkey").alias("n"))
    return t.join(n, "letter", "left").select("letter", "low", "high", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


@query("symbols_lineitem", """WITH s AS (SELECT min(round(l_extendedprice * 100))::BIGINT AS lo FROM lineitem)
SELECT l_returnflag, l_linenumber::BIGINT AS line, ((round(l_extendedprice * 100)::BIGINT - lo) // 10001)::BIGINT AS cell, count(*)::BIGINT AS n FROM lineitem, s GROUP BY ALL""")
def symbols_lineitem(spark, sf_dir):
    """Projected, renamed and cast columns, and the cell of a price."""
    t = table(spark, sf_dir, "lineitem")
    lo = t.agg(F.min(F.round(F.col("l_extendedprice") * 100)).cast("long").alias("lo"))
    cells = t.join(F.broadcast(lo)).select("l_returnflag", F.col("l_linenumber").cast("long").alias("line"), F.expr("(cast(round(l_extendedprice * 100) as bigint) - lo) div 10001").alias("cell"))
    return cells.groupBy("l_returnflag", "line", "cell").agg(F.count(F.lit(1)).alias("n"))


@query("filter_on_leaf", """WITH s AS (SELECT min(round(o_totalprice * 100))::BIGINT AS lo FROM orders)
SELECT count(*)::BIGINT AS n, sum((round(o_totalprice * 100)::BIGINT - lo) // 2001)::BIGINT AS leaves FROM orders, s WHERE (round(o_totalprice * 100)::BIGINT - lo) // 2001 >= (20000000 - lo + 2000) // 2001""")
def filter_on_leaf(spark, sf_dir):
    """A price filter on leaf numbers, before any value is restored."""
    from relcodec.schema import infer_spec

    df = table(spark, sf_dir, "orders").select("o_totalprice")
    spec = infer_spec(df).with_tolerance(10.0, ["o_totalprice"])
    a = spec["o_totalprice"]
    path = scratch(spark)
    made = archives.compress(df, path, archives.Options(structure="empty"), spec)
    images = archives.decode(made.blocks(spark), made.network)
    # The first leaf whose cents all lie at 200,000.00 or more.
    first = -(-(20_000_000 - a.image_lo) // a.step)
    return images.filter(F.col("o_totalprice") >= first).agg(F.count(F.lit(1)).alias("n"), F.sum("o_totalprice").alias("leaves"))


@query("pairwise_counts", """WITH l AS (UNPIVOT (SELECT l_orderkey, l_linenumber, l_returnflag AS f, l_linestatus AS s, l_linenumber::VARCHAR AS n FROM lineitem) ON f, s, n INTO NAME attribute VALUE value)
SELECT a.attribute AS one, a.value AS x, b.attribute AS other, b.value AS y, count(*)::BIGINT AS n FROM l a JOIN l b USING (l_orderkey, l_linenumber) WHERE a.attribute < b.attribute GROUP BY ALL""")
def pairwise_counts(spark, sf_dir):
    """Joint counts of all attribute pairs: columns are stacked and joined to themselves on the row's key."""
    t = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s"), F.col("l_linenumber").cast("string").alias("n"))
    long = t.unpivot(["l_orderkey", "l_linenumber"], ["f", "s", "n"], "attribute", "value")
    a, b = long.withColumnsRenamed({"attribute": "one", "value": "x"}), long.withColumnsRenamed({"attribute": "other", "value": "y"})
    return a.join(b, ["l_orderkey", "l_linenumber"]).filter("one < other").groupBy("one", "x", "other", "y").agg(F.count(F.lit(1)).alias("n"))


@query("lateral_tree_steps", "SELECT p_partkey, s::BIGINT AS step, s = p_size AS stops FROM part, range(1, 51) AS t(s) WHERE s <= p_size")
def lateral_tree_steps(spark, sf_dir):
    """The steps that a value takes down an endless tree, one row each."""
    return table(spark, sf_dir, "part").select("p_partkey", "p_size", F.explode(F.sequence(F.lit(1), "p_size")).alias("step")).select(
        "p_partkey", F.col("step").cast("long").alias("step"), (F.col("step") == F.col("p_size")).alias("stops"))


_XLOG = "(SELECT sum(n * log2(n)) FROM (SELECT count(*) AS n FROM src GROUP BY {0}))"


@query("entropy_columns", f"WITH src AS ({STAR_SQL}), t AS (SELECT count(*) AS n FROM src) " + " UNION ALL ".join(
    f"SELECT '{c}' AS attribute, round(log2(n) - {_XLOG.format(c)} / n, 5) + 0.0 AS bits FROM t" for c in STAR))
def entropy_columns(spark, sf_dir):
    return stats.entropies(star(spark, sf_dir), STAR).select("attribute", (F.round("bits", 5) + 0.0).alias("bits"))


@query("mutual_information_pairs", f"WITH src AS ({STAR_SQL}), t AS (SELECT count(*) AS n FROM src) " + " UNION ALL ".join(
    f"SELECT '{p}' AS parent, '{c}' AS child, round(log2(n) - ({_XLOG.format(c)} + {_XLOG.format(p)} - {_XLOG.format(f'{p}, {c}')}) / n, 5) + 0.0 AS bits FROM t" for p, c in PAIRS))
def mutual_information_pairs(spark, sf_dir):
    """What pairs of attributes tell about each other: the weights that columns are grouped by."""
    return stats.conditional_entropies(star(spark, sf_dir), PAIRS).select("parent", "child", (F.round("mutual_information", 5) + 0.0).alias("bits"))


def partition_columns(df, columns: list[str], largest: int, least_bits: float = 0.05) -> list[list[str]]:
    """Columns in groups of at most `largest` that share information: pairs are merged from the most to the least."""
    pairs = [(a, b) for i, a in enumerate(columns) for b in columns[i + 1:]]
    found = sorted(((r["mutual_information"], r["parent"], r["child"]) for r in stats.conditional_entropies(df, pairs).collect()), reverse=True)
    group = {c: [c] for c in columns}
    for bits, a, b in found:
        if bits >= least_bits and group[a] is not group[b] and len(group[a]) + len(group[b]) <= largest:
            joined = group[a] + group[b]
            for c in joined:
                group[c] = joined
    return [list(g) for g in {id(g): sorted(g, key=columns.index) for g in group.values()}.values()]


@query("column_groups_star")
def column_groups_star(spark, sf_dir):
    """Groups of columns that a very wide table would be archived by."""
    columns = ["c_nationkey", "n_name", "n_regionkey", "r_name", "p_brand", "p_type", "l_returnflag", "l_linestatus", "s_nationkey", "s_name"]
    groups = partition_columns(star(spark, sf_dir), columns, 4)
    return spark.createDataFrame([(i, c) for i, g in enumerate(groups) for c in g], "group_id long, attribute string")


@query("quantiles_approx")
def quantiles_approx(spark, sf_dir):
    """Sketched split points of a number beside the exact ones."""
    q = F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))
    return table(spark, sf_dir, "events").agg(F.percentile_approx("value", q, 10000).alias("approximate"), F.percentile("value", q).alias("exact"))


@query("sort_codes", CODES_SQL + " SELECT code::BIGINT AS code, nbits::BIGINT AS nbits, n::BIGINT AS n, row_number() OVER (ORDER BY code / (1::BIGINT << nbits::INT)::DOUBLE, nbits)::BIGINT AS place FROM codes")
def sort_codes(spark, sf_dir):
    """Codes in the order of the numbers between 0 and 1 that they begin: a range partitioning sorted within."""
    c = short_codes(spark, sf_dir).select("code", F.col("nbits").cast("long").alias("nbits"), F.col("n").cast("long").alias("n")).withColumn("at", F.col("code") / F.pow(F.lit(2.0), F.col("nbits")))
    sorted_codes = c.repartitionByRange(4, "at", "nbits").sortWithinPartitions("at", "nbits")
    return sorted_codes.withColumn("place", F.row_number().over(W.orderBy("at", "nbits")).cast("long")).select("code", "nbits", "n", "place")


@query("lag_code_gap", CODES_SQL + """, p AS (SELECT code * (1::BIGINT << (48 - nbits)::INT) AS start, nbits FROM codes)
SELECT start::BIGINT AS start, (start - coalesce(lag(start) OVER (ORDER BY start, nbits), 0))::BIGINT AS gap FROM p""")
def lag_code_gap(spark, sf_dir):
    """Gaps between sorted codes, each code as a number of 48 bits."""
    c = short_codes(spark, sf_dir).select(F.expr("code * shiftleft(1L, cast(48 - nbits as int))").alias("start"), "nbits")
    return c.select("start", (F.col("start") - F.coalesce(F.lag("start").over(W.orderBy("start", "nbits")), F.lit(0))).alias("gap"))


@query("topk_costly_rows", """WITH t AS (SELECT count(*) AS n FROM orders), p AS (SELECT o_orderpriority, count(*) AS n FROM orders GROUP BY 1), s AS (SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY 1)
SELECT o_orderkey, round(2 * log2(t.n) - log2(p.n) - log2(s.n), 6) AS bits FROM orders JOIN p USING (o_orderpriority) JOIN s USING (o_orderstatus), t ORDER BY bits DESC, o_orderkey LIMIT 20""")
def topk_costly_rows(spark, sf_dir):
    """The rows that independent columns code longest: each task keeps its own top rows."""
    o = table(spark, sf_dir, "orders")
    t = o.agg(F.count(F.lit(1)).alias("t"))
    p = o.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("p"))
    s = o.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("s"))
    rows = o.join(F.broadcast(p), "o_orderpriority").join(F.broadcast(s), "o_orderstatus").join(F.broadcast(t))
    bits = F.round(2 * F.log2(F.col("t").cast("double")) - F.log2(F.col("p").cast("double")) - F.log2(F.col("s").cast("double")), 6)
    return rows.select("o_orderkey", bits.alias("bits")).orderBy(F.desc("bits"), "o_orderkey").limit(20)


@query("archive_block_index", "SELECT count(*)::BIGINT AS nrows, min(o_orderkey)::BIGINT AS lo, max(o_orderkey)::BIGINT AS hi FROM orders")
def archive_block_index(spark, sf_dir):
    """Rows and key range by the zones of an archive's blocks, without decoding."""
    path = scratch(spark)
    made = archives.compress(table(spark, sf_dir, "orders"), path, archives.Options(zones=("o_orderkey",), keys=False))
    lowest = made.network.spec["o_orderkey"].image_lo
    zone = F.element_at("zone", "o_orderkey")
    return made.blocks(spark).agg(F.sum("nrows").alias("nrows"), (F.min(zone["lo"]) + lowest).alias("lo"), (F.max(zone["hi"]) + lowest).alias("hi"))


@query("csv_raw_bytes", "SELECT sum(strlen(concat_ws(',', r_regionkey::VARCHAR, r_name)) + 1)::BIGINT AS bytes FROM region")
def csv_raw_bytes(spark, sf_dir):
    """Bytes of the text form, by writing it."""
    path = scratch(spark)
    table(spark, sf_dir, "region").coalesce(1).write.csv(path)
    return spark.read.format("binaryFile").load(f"{path}/*.csv").agg(F.sum("length").alias("bytes"))


@query("compare_archives", "SELECT n_regionkey, count(*)::BIGINT AS one_side, count(*)::BIGINT AS other_side, 0::BIGINT AS only_one FROM nation GROUP BY 1")
def compare_archives(spark, sf_dir):
    """Two archives of a table, one of them delta-coded, compared group by group."""
    import pandas as pd

    sides = []
    for options in (archives.Options(structure="empty"), archives.Options(structure="empty", delta=True)):
        path = scratch(spark)
        archives.compress(table(spark, sf_dir, "nation"), path, options)
        sides.append(archives.decompress(spark, path))

    def compared(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        differ = set(map(tuple, a.to_numpy().tolist())) ^ set(map(tuple, b.to_numpy().tolist()))
        return pd.DataFrame({"n_regionkey": [key[0]], "one_side": [len(a)], "other_side": [len(b)], "only_one": [len(differ)]})

    schema = f"n_regionkey {dict(sides[0].dtypes)['n_regionkey']}, one_side long, other_side long, only_one long"
    return sides[0].groupBy("n_regionkey").cogroup(sides[1].groupBy("n_regionkey")).applyInPandas(compared, schema)
