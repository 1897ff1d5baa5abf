"""Quality by hierarchical empirical Bayes: a document's own evidence with what its site and path are like.

Evidence: structural features are cut into bins; each bin's log-odds between labels come from grouped counts with
add-one smoothing, their sum is made a log-likelihood ratio by a one-variable logistic fit on binned sums. Sites:
every document counts towards its path and host with its label, or else its expected label. A host's rate is shrunk
towards the corpus' rate and a path's towards its host's, with prior strengths fitted by the method of moments, so a
sparse site says little and a large one much; a document's own share is taken out of its site before the site judges
it. The posterior adds evidence and the path's log-odds.

Everything is DataFrame aggregation over narrow rows (no text leaves its scan), partial before each shuffle, so one
host with a third of all rows is a few partial sums. The site table joins back by broadcast only when counted to be
at most `MAX_BROADCAST` rows.

Defined cases: null text has the features of an empty one; null host or path is a site of its own; without labels of
both classes evidence is 0 and every rate the prior 1/2; repeated rows count each; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec.llm import common

MAX_BROADCAST = 200_000
HELD_OUT_MODULUS, HELD_OUT_REMAINDER = 5, 0
#: Features and the upper ends of their bins (per mille, but for counts and lengths).
BINS = {
    "symbols": (0, 20, 50, 100, 200, 400, 800),
    "shouts": (0, 20, 50, 100, 300, 600),
    "bars": (0, 10, 50, 100, 300),
    "capitals": (5, 20, 40, 80, 150, 300, 600),
    "distinct": (50, 100, 200, 350, 500, 700, 850),
    "mean_word": (2000, 3000, 4000, 5000, 6000, 8000, 12000),
    "repeated_lines": (0, 100, 300, 500),
    "words": (10, 30, 100, 300, 1000, 3000),
    "neighbours": (0, 20, 50, 100, 300, 600),
}


def features(text: Column) -> dict[str, Column]:
    """Per-mille ratios of a text, by name; words are `common.words`."""
    body = F.coalesce(text, F.lit(""))
    n = F.greatest(F.size("_words"), F.lit(1))
    chars = F.greatest(F.length(body), F.lit(1))
    gone = lambda letters: F.length(body) - F.length(F.translate(body, letters, ""))
    lines = F.split(body, "\n")
    return {
        "symbols": gone("#*$%&<>@{}=") * 1000 / n,
        "shouts": gone("!") * 1000 / n,
        "bars": gone("|") * 1000 / n,
        "capitals": (chars - F.length(F.translate(body, "ABCDEFGHIJKLMNOPQRSTUVWXYZÄÖÜÉÈÊÀÇÑÓÍÁÚ", ""))) * 1000 / chars,
        "distinct": F.size(F.array_distinct("_words")) * 1000 / n,
        "mean_word": F.length(F.array_join("_words", "")) * 1000 / n,
        "repeated_lines": (F.size(lines) - F.size(F.array_distinct(lines))) * 1000 / F.size(lines),
        "words": F.size("_words").cast("double"),
        # Words equal to the one before them.
        "neighbours": F.size(F.filter(F.zip_with("_words", F.slice("_words", 2, 1 << 30), lambda a, b: a.eqNullSafe(b)), lambda x: x)) * 1000 / n,
    }


def binned(value: Column, ends: tuple[int, ...]) -> Column:
    out = F.lit(len(ends))
    for i in range(len(ends) - 1, -1, -1):
        out = F.when(value <= ends[i], i).otherwise(out)
    return out


def featurise(docs: DataFrame, id_col: str, text_col: str, host: Column, path: Column) -> DataFrame:
    """doc_id, host, path, b_<feature>: narrow rows, written once."""
    cut = docs.select(F.col(id_col).cast("long").alias("doc_id"), host.alias("host"), path.alias("path"), F.col(text_col).alias("_text"), common.words(F.col(text_col)).alias("_words"))
    wide = cut.select("doc_id", "host", "path", *[v.alias(k) for k, v in features(F.col("_text")).items()])
    return common.materialise(wide.select("doc_id", "host", "path", *[binned(F.col(k), ends).alias(f"b_{k}") for k, ends in BINS.items()]))


def evidence_table(rows: DataFrame) -> dict[str, list[float]]:
    """feature -> log-odds per bin, from rows with b_<feature> and label; at most a few hundred counts reach the driver."""
    pairs = F.explode(F.array(*[F.struct(F.lit(k).alias("feature"), F.col(f"b_{k}").alias("bin")) for k in BINS]))
    counts = rows.select("label", pairs.alias("p")).groupBy("p.feature", "p.bin", "label").count().collect()
    n = {(r["feature"], r["bin"], r["label"]): r["count"] for r in counts}
    total = {label: sum(c for (f, _, y), c in n.items() if y == label and f == next(iter(BINS))) for label in (0, 1)}
    if not total[0] or not total[1]:
        return {k: [0.0] * (len(e) + 1) for k, e in BINS.items()}
    return {k: [float(np.log((n.get((k, i, 1), 0) + 1) / (total[1] + len(e) + 1)) - np.log((n.get((k, i, 0), 0) + 1) / (total[0] + len(e) + 1))) for i in range(len(e) + 1)] for k, e in BINS.items()}


def summed(table: dict[str, list[float]]) -> Column:
    terms = [F.element_at(F.array(*[F.lit(x) for x in v]), F.col(f"b_{k}") + 1) for k, v in table.items()]
    out = terms[0]
    for t in terms[1:]:
        out = out + t
    return out


def calibration(rows: DataFrame) -> tuple[float, float]:
    """(slope, intercept) of the log-odds of label 1 on `raw`, fitted on counts per bin of raw."""
    bins = rows.groupBy(F.round(F.col("raw") * 4).alias("x"), "label").count().toPandas()
    if bins["label"].nunique() < 2:
        return 1.0, 0.0
    x, y, w = bins["x"].to_numpy(float) / 4, bins["label"].to_numpy(float), bins["count"].to_numpy(float)
    a = np.column_stack([x, np.ones(len(x))])
    beta = np.zeros(2)
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(a @ beta, -30, 30)))
        v = np.maximum(w * p * (1 - p), 1e-9)
        step = np.linalg.solve((a * v[:, None]).T @ a + 1e-2 * np.eye(2), a.T @ (w * (p - y)) + 1e-2 * beta)
        beta -= step * min(1.0, 3.0 / max(float(np.abs(step).max()), 1e-9))
        if np.abs(step).max() < 1e-9:
            break
    return float(beta[0]), float(beta[1])


def strength(groups: DataFrame, rate: Column, centre: Column) -> float:
    """Prior strength of rates around their centres: binomial variance over excess variance, between 1 and 10^4."""
    sums = groups.filter("n >= 2").agg(
        F.sum(F.col("n") * (rate - centre) ** 2).alias("between"), F.sum(centre * (1 - centre)).alias("within"), F.sum(F.col("n") * centre * (1 - centre)).alias("spread"), F.sum("n").alias("n")).first()
    if not sums["n"] or not sums["spread"]:
        return 10.0
    excess = (sums["between"] - sums["within"]) / sums["n"]
    mean = sums["spread"] / sums["n"]
    return float(min(1e4, max(1.0, mean / excess - 1 if excess > 0 else 1e4)))


def classify(docs: DataFrame, labels: DataFrame, host: Column, path: Column, label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, evidence, host_rate, path_rate, score (posterior probability of label 1) for every row of docs."""
    rows = featurise(docs, id_col, text_col, host, path)
    known = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("label")).filter("label in (0, 1)").dropDuplicates(["doc_id"])
    rows = common.materialise(rows.join(known, "doc_id", "left"))
    labelled = rows.filter("label is not null")
    raw = summed(evidence_table(labelled))
    slope, intercept = calibration(labelled.withColumn("raw", raw))
    base = labelled.agg(F.avg("label")).first()[0]
    base = min(1 - 1e-6, max(1e-6, base if base is not None else 0.5))
    prior = float(np.log(base / (1 - base)))
    # The calibrated log-odds hold the base rate; without it they are a likelihood ratio.
    rows = rows.withColumn("evidence", F.lit(slope) * raw + F.lit(intercept - prior))
    rows = rows.withColumn("q", F.coalesce(F.col("label").cast("double"), 1 / (1 + F.exp(-(F.col("evidence") + prior)))))
    paths = common.materialise(rows.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n"), F.sum("q").alias("good")))
    hosts = paths.groupBy("host").agg(F.sum("n").alias("n"), F.sum("good").alias("good"))
    centre = hosts.agg(F.sum("good") / F.sum("n")).first()[0]
    centre = min(1 - 1e-6, max(1e-6, centre if centre is not None else 0.5))
    k_host = strength(hosts, F.col("good") / F.col("n"), F.lit(centre))
    hosts = hosts.select(F.col("host").alias("_host"), ((F.col("good") + k_host * centre) / (F.col("n") + k_host)).alias("host_rate"))
    sites = common.materialise(paths.join(hosts, F.col("host").eqNullSafe(F.col("_host"))).drop("_host"))
    k_path = strength(sites, F.col("good") / F.col("n"), F.col("host_rate"))
    sites = sites.select(F.col("host").alias("_host"), F.col("path").alias("_path"), "n", "good", "host_rate")
    joined = rows.join(common.small_side(sites, sites.count(), MAX_BROADCAST), F.col("host").eqNullSafe(F.col("_host")) & F.col("path").eqNullSafe(F.col("_path")))
    rate = (F.col("good") - F.col("q") + k_path * F.col("host_rate")) / (F.col("n") - 1 + k_path)
    rate = F.least(F.greatest(rate, F.lit(1e-6)), F.lit(1 - 1e-6))
    return joined.withColumn("path_rate", rate).select(
        "doc_id", "evidence", "host_rate", "path_rate", (1 / (1 + F.exp(-(F.col("evidence") + F.log(F.col("path_rate") / (1 - F.col("path_rate"))))))).alias("score"))


def op1_site_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    fold = common.fold(F.col("doc_id"), HELD_OUT_MODULUS)
    labels = common.table(spark, sf_dir, "labels").filter(fold != HELD_OUT_REMAINDER)
    out = classify(common.documents(spark, sf_dir), labels, F.col("source"), F.concat_ws("/", "source", "lang"))
    return out.select("doc_id", (fold == HELD_OUT_REMAINDER).alias("held_out"), "evidence", "host_rate", "path_rate", "score", (F.col("score") >= 0.5).alias("kept"))
