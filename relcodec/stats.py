"""Entropies, contingency tables, objectives, masses and moments as DataFrame aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec.network import Structure, contingency, domain_of
from relcodec.schema import TableSpec, quoted


def counts(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.groupBy(*[F.col(quoted(c)) for c in columns]).agg(F.count(F.lit(1)).alias("cnt"))


def entropy(df: DataFrame, columns: list[str]) -> DataFrame:
    """One row: n, distinct, bits per row of the joint distribution of columns."""
    c = F.col("cnt").cast("double")
    return counts(df, columns).agg(F.sum("cnt").alias("n"), F.count(F.lit(1)).alias("distinct_values"), F.sum(c * F.log2(c)).alias("s")).select(
        "n", "distinct_values", (F.log2(F.col("n").cast("double")) - F.col("s") / F.col("n")).alias("bits"))


def entropies(df: DataFrame, columns: list[str]) -> DataFrame:
    """attribute, n, distinct_values, bits: all columns from one scan."""
    long = df.select(F.explode(F.array(*[F.struct(F.lit(c).alias("attribute"), F.col(quoted(c)).cast("string").alias("value")) for c in columns])).alias("p"))
    c = F.col("cnt").cast("double")
    return long.groupBy("p.attribute", "p.value").agg(F.count(F.lit(1)).alias("cnt")).groupBy("attribute").agg(
        F.sum("cnt").alias("n"), F.count(F.lit(1)).alias("distinct_values"), F.sum(c * F.log2(c)).alias("s")).select(
        "attribute", "n", "distinct_values", (F.log2(F.col("n").cast("double")) - F.col("s") / F.col("n")).alias("bits"))


def conditional_entropies(df: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """parent, child, bits of the child given the parent, bits of the child alone, and their difference; one scan."""
    rows = F.array(*[F.struct(F.lit(p).alias("parent"), F.lit(c).alias("child"), F.col(quoted(p)).cast("string").alias("g"), F.col(quoted(c)).cast("string").alias("v")) for p, c in pairs])
    cells = df.select(F.explode(rows).alias("r")).groupBy("r.parent", "r.child", "r.g", "r.v").agg(F.count(F.lit(1)).alias("cnt"))
    xlog = lambda c: F.sum(F.col(c).cast("double") * F.log2(F.col(c).cast("double")))
    joint = cells.groupBy("parent", "child").agg(F.sum("cnt").alias("n"), xlog("cnt").alias("s_pair"))
    by_g = cells.groupBy("parent", "child", "g").agg(F.sum("cnt").alias("cg")).groupBy("parent", "child").agg(xlog("cg").alias("s_g"))
    by_v = cells.groupBy("parent", "child", "v").agg(F.sum("cnt").alias("cv")).groupBy("parent", "child").agg(xlog("cv").alias("s_v"))
    out = joint.join(by_g, ["parent", "child"]).join(by_v, ["parent", "child"])
    given, alone = (F.col("s_g") - F.col("s_pair")) / F.col("n"), F.log2(F.col("n").cast("double")) - F.col("s_v") / F.col("n")
    return out.select("parent", "child", given.alias("bits_given"), alone.alias("bits_alone"), (alone - given).alias("mutual_information"))


def node_objectives(images: DataFrame, spec: TableSpec, structure: Structure, accounting: str = "sparse") -> DataFrame:
    """node, model_bits, data_bits, objective of every node of a structure, on all rows, in one scan."""
    cells = contingency(images, spec, structure)
    n = F.col("cnt").cast("double")
    per = cells.groupBy("node", "config").agg(F.sum("cnt").alias("cg"), F.count(F.lit(1)).alias("cells"), F.sum(n * F.log2(n)).alias("s"))
    g = F.col("cg").cast("double")
    out = per.groupBy("node").agg(F.sum("cells").alias("cells"), F.count(F.lit(1)).alias("configs"), F.sum(g * F.log2(g) - F.col("s")).alias("data_bits"))
    sizes = F.create_map(*[x for a in spec.attributes for x in (F.lit(a.name), F.lit(domain_of(a)))])
    domain = F.greatest(sizes[F.col("node")], F.lit(2))
    if accounting == "sparse":
        bits = F.col("cells") * (F.ceil(F.log2(domain)) + 16) + 16 * F.col("configs")
    else:
        bits = F.col("configs") * (domain - 1) * (32 if accounting == "dense" else 8)
    return out.select("node", bits.cast("double").alias("model_bits"), "data_bits", (bits + F.col("data_bits")).alias("objective"))


def masses(cells: DataFrame, by: list[str], value: str) -> DataFrame:
    """by, value, cnt, mass, low: integer masses of 2^16 per group of `by`, at least one each; what rounding leaves goes
    to the most frequent value (of equal ones the smallest)."""
    g = W.partitionBy(*by) if by else W.partitionBy(F.lit(0))
    base = cells.withColumns({"n": F.sum("cnt").over(g), "k": F.count(F.lit(1)).over(g)})
    base = base.withColumn("m0", F.expr("1 + (cnt * (65536 - k)) div n"))
    order = g.orderBy(F.desc("cnt"), F.col(value))
    base = base.withColumns({"rank": F.row_number().over(order), "given": F.sum("m0").over(g)})
    base = base.withColumn("mass", F.col("m0") + F.when(F.col("rank") == 1, 65536 - F.col("given")).otherwise(0))
    lows = g.orderBy(value).rowsBetween(W.unboundedPreceding, -1)
    return base.select(*by, value, "cnt", F.col("mass").cast("long").alias("mass"), F.coalesce(F.sum("mass").over(lows), F.lit(0)).cast("long").alias("low"))


def functional_dependencies(df: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """parent, child of the pairs where one parent value always has one child value."""
    c = conditional_entropies(df, pairs)
    return c.filter(F.col("bits_given") < 1e-9).select("parent", "child")


def moments(df: DataFrame, columns: list[str]) -> DataFrame:
    """attribute, n, mean, deviation, lo, hi, median, deviation from the median: what the density families need."""
    long = df.select(F.explode(F.array(*[F.struct(F.lit(c).alias("attribute"), F.col(quoted(c)).cast("double").alias("x")) for c in columns])).alias("p")).select("p.*").filter("x is not null")
    first = long.groupBy("attribute").agg(F.count("x").alias("n"), F.avg("x").alias("mean"), F.stddev_pop("x").alias("deviation"), F.min("x").alias("lo"), F.max("x").alias("hi"), F.percentile("x", F.lit(0.5)).alias("median"))
    spread = long.join(F.broadcast(first.select("attribute", "median")), "attribute").groupBy("attribute").agg(F.avg(F.abs(F.col("x") - F.col("median"))).alias("absolute"))
    return first.join(spread, "attribute")


def leaf_index(x: Column, lo: float, width: float, leaves: int) -> Column:
    """Cell of an equal-width grid: (lo, lo + width] is 0, and lo itself too."""
    return F.least(F.greatest(F.ceil((x - F.lit(lo)) / F.lit(width)).cast("long") - 1, F.lit(0).cast("long")), F.lit(leaves - 1).cast("long"))


def leaf_mid(leaf: Column, lo: float, width: float) -> Column:
    return F.lit(lo) + (leaf + 0.5) * F.lit(width)
