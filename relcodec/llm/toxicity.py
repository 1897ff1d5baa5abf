"""Toxicity by maximum-scoring segments.

Token log-odds between toxic and other texts come from counts with an informative Dirichlet prior (the prior of a
token is its share of all counted tokens, times `prior_tokens`); a token enters the lexicon if its log-odds are
`min_z` standard deviations from zero. A linear scan then finds every maximal scoring segment of a text, tokens
outside the lexicon costing a constant. The number of toxic passages and the best passage are judged by extreme-value
statistics: with scores drawn at background rates, E = K n exp(-lambda S) passages of score S or more are expected in
n tokens. Both constants come from the training sample's other texts: lambda solves sum p exp(lambda s) = 1 over the
rates p at which their tokens occur, and K is the maximum-likelihood value given the best passage of each of them,
m / sum n exp(-lambda S). A logistic curve over -log E, fitted on counts per bin, makes it a
probability; the summed score of all maximal segments is its second input, so that many weak passages count too.

The training sample is bounded (`max_per_class` labelled rows of each class, in the order of a hash of the id); the
lexicon is bounded by `max_lexicon` (largest |z| first). Both bounds hold at any corpus size, so the join with labels
broadcasts only ids of the sample, and scoring is map-only over whole texts.

Defined cases: null and empty texts have no passage and get the lowest score; without labels of both classes every
score is the share of label 1 (0 without labels); repeated rows score alike; very long texts are scanned whole; of
equally clear tokens at the lexicon's bound the first by alphabet stay; further columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec.llm import common

MAX_PER_CLASS = 8000
MAX_LEXICON = 50_000
PRIOR_TOKENS = 50_000.0
MIN_Z = 2.0
HELD_OUT_MODULUS, HELD_OUT_REMAINDER = 5, 0

_word = re.compile(r"[^\W\d_]+")


def tokens(text: str | None) -> list[str]:
    return _word.findall(text.lower()) if text else []


def segments(scores: list[float], places: list[int], gap_cost: float) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (first, last token, score), given the places of scored tokens; each token between
    costs `gap_cost`. One pass with a stack of candidates, each pushed and popped once."""
    found: list[tuple[int, int, float, float]] = []  # first, last, sum before, sum at the end
    total, last = 0.0, -1
    for place, score in zip(places, scores, strict=True):
        total -= gap_cost * (place - last - 1)
        before = total
        total += score
        last = place
        if score <= 0:
            continue
        new = (place, place, before, total)
        while True:
            j = len(found) - 1
            while j >= 0 and found[j][2] >= new[2]:
                j -= 1
            if j < 0 or found[j][3] >= new[3]:
                found.append(new)
                break
            new = (found[j][0], new[1], found[j][2], new[3])
            del found[j:]
    return [(a, b, end - start) for a, b, start, end in found]


class Model:
    """Lexicon, background statistics and the final logistic curve."""

    def __init__(self, lexicon: dict[str, float], gap_cost: float, lam: float, log_k: float, curve: tuple[float, ...], base_rate: float):
        self.lexicon, self.gap_cost, self.lam, self.log_k, self.curve, self.base_rate = lexicon, gap_cost, lam, log_k, curve, base_rate

    def passages(self, words: list[str]) -> list[tuple[int, int, float]]:
        get = self.lexicon.get
        hits = [(i, s) for i, s in enumerate(map(get, words)) if s is not None]
        if not hits:
            return []
        return segments([s for _, s in hits], [i for i, _ in hits], self.gap_cost)

    def evidence(self, words: list[str]) -> tuple[float, float, list[tuple[int, int, float]], float]:
        """(-log E summed over significant passages, summed score of all passages, the significant ones, best score):
        the larger, the less by chance."""
        found = self.passages(words)
        size = math.log(max(len(words), 1))
        worth = [self.lam * s - self.log_k - size for _, _, s in found]
        best = max((s for _, _, s in found), default=0.0)
        good = [w for w in worth if w > 0]
        return (sum(good) if good else max(worth, default=-self.log_k - size), sum(s for _, _, s in found), [f for f, w in zip(found, worth, strict=True) if w > 0], best)

    def score(self, evidence: float, total: float) -> float:
        if not self.lexicon:
            return self.base_rate
        x = self.curve[0] * clip(evidence) + self.curve[1] * clip(total) + self.curve[2]
        return 1.0 / (1.0 + math.exp(-max(-30.0, min(30.0, x))))


def clip(x: float) -> float:
    return max(-40.0, min(100.0, x))


def training_sample(docs: DataFrame, labels: DataFrame, label_col: str, max_per_class: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(label, text, weight) of at most max_per_class documents of each class; weight restores the class's share."""
    spark = docs.sparkSession
    known = labels.select(F.col(id_col).alias("doc_id"), F.col(label_col).cast("int").alias("label")).filter("doc_id is not null and label in (0, 1)")
    totals = {r["label"]: r["n"] for r in known.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    picked = None
    for label, n in sorted(totals.items()):
        share = min(1.0, 2.0 * max_per_class / n)
        near = known.filter((F.col("label") == label) & (F.xxhash64("doc_id").cast("double") / 2.0**64 + 0.5 <= share))
        part = near.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_per_class).withColumn("weight", F.lit(max(1.0, n / max_per_class)))
        picked = part if picked is None else picked.unionByName(part)
    if picked is None:
        return spark.createDataFrame([], "label int, text string, weight double")
    # At most 2 * max_per_class ids: a proven bound for the broadcast.
    texts = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    return texts.join(F.broadcast(picked), "doc_id").select("label", "text", "weight")


def fit(sample: DataFrame, max_lexicon: int = MAX_LEXICON, prior_tokens: float = PRIOR_TOKENS, min_z: float = MIN_Z) -> Model:
    sample = common.materialise(sample)

    def counted(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            sums, often = {0: Counter(), 1: Counter()}, Counter()
            for label, text in zip(frame["label"], frame["text"], strict=True):
                words = tokens(text)
                sums[label].update(set(words))
                if label == 0:
                    often.update(words)
            rows = [(w, c, 0, often[w]) for w, c in sums[0].items()] + [(w, 0, c, 0) for w, c in sums[1].items()]
            yield pd.DataFrame(rows, columns=["word", "n0", "n1", "often"])

    counts = sample.mapInPandas(counted, "word string, n0 long, n1 long, often long").groupBy("word").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"), F.sum("often").alias("often"))
    counts = common.materialise(counts)
    total = counts.agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"), F.sum("often").alias("often")).first()
    share = sample.groupBy().agg(F.sum(F.when(F.col("label") == 1, F.col("weight"))).alias("w1"), F.sum("weight").alias("w")).first()
    base_rate = (share["w1"] or 0.0) / share["w"] if share["w"] else 0.0
    if not total["n0"] or not total["n1"]:
        return Model({}, 1.0, 1.0, 0.0, (1.0, 0.0, 0.0), base_rate)
    n0, n1, occurring = float(total["n0"]), float(total["n1"]), float(total["often"])
    prior = (F.col("n0") + F.col("n1")) / (n0 + n1) * prior_tokens
    odds = lambda n, all_n: F.log((F.col(n) + prior) / (all_n + prior_tokens - F.col(n) - prior))
    delta = odds("n1", n1) - odds("n0", n0)
    z = delta / F.sqrt(1 / (F.col("n1") + prior) + 1 / (F.col("n0") + prior))
    # Bounded by max_lexicon: the clearest tokens of either sign.
    rows = counts.select("word", delta.alias("delta"), z.alias("z"), (F.col("often") / occurring).alias("p0")).filter((F.abs("z") >= min_z) & (F.abs("delta") > 1.0)).orderBy(F.desc(F.abs("z")), "word").limit(max_lexicon).collect()
    lexicon = {r["word"]: float(r["delta"]) for r in rows}
    gap = 0.02
    positive = [(max(r["p0"], 0.1 / occurring), lexicon[r["word"]]) for r in rows]
    if not any(s > 0 for _, s in positive):
        return Model({}, 1.0, 1.0, 0.0, (1.0, 0.0, 0.0), base_rate)
    rest = 1.0 - sum(p for p, _ in positive)
    # The mean score must be negative for extreme-value statistics to hold.
    mean = sum(p * s for p, s in positive)
    gap = max(gap, 2.0 * mean / max(rest, 1e-9))

    def excess(lam: float) -> float:
        return sum(p * math.exp(min(lam * s, 700)) for p, s in positive) + rest * math.exp(-lam * gap) - 1.0

    low, high = 1e-6, 1.0
    while excess(high) < 0 and high < 64:
        high *= 2
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if excess(mid) < 0 else (low, mid)
    lam = (low + high) / 2
    model = Model(lexicon, gap, lam, 0.0, (1.0, 0.0, 0.0), base_rate)

    def chances(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = [(len(w), max((s for _, _, s in model.passages(w)), default=0.0)) for w in map(tokens, frame["text"]) if w]
            yield pd.DataFrame({"texts": [len(rows)], "expected": [sum(n * math.exp(-lam * best) for n, best in rows)]})

    background = sample.filter("label = 0").select("text").mapInPandas(chances, "texts long, expected double").agg(F.sum("texts"), F.sum("expected")).first()
    model.log_k = math.log((background[0] or 1) / max(background[1] or 1.0, 1e-300))

    def judged(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            bins = Counter()
            for label, text, weight in zip(frame["label"], frame["text"], frame["weight"], strict=True):
                x, total, _, _ = model.evidence(tokens(text))
                bins[(int(label), round(clip(x) * 2), round(clip(total) * 2))] += weight
            yield pd.DataFrame([(*k, w) for k, w in bins.items()], columns=["label", "x", "total", "weight"])

    bins = sample.mapInPandas(judged, "label int, x int, total int, weight double").groupBy("label", "x", "total").agg(F.sum("weight").alias("weight")).toPandas()
    model.curve = logistic(bins[["x", "total"]].to_numpy(float) / 2, bins["label"].to_numpy(float), bins["weight"].to_numpy(float))
    return model


def logistic(x: np.ndarray, y: np.ndarray, w: np.ndarray, ridge: float = 1e-2) -> tuple[float, ...]:
    """Slopes and intercept by Newton's method on binned counts."""
    scale = np.maximum(np.abs(x).max(axis=0), 1.0)
    x = np.column_stack([x / scale, np.ones(len(x))])
    beta, keep = np.zeros(x.shape[1]), ridge * np.eye(x.shape[1])
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        v = np.maximum(w * p * (1 - p), 1e-9)
        step = np.linalg.solve((x * v[:, None]).T @ x + keep, x.T @ (w * (p - y)) + ridge * beta)
        beta -= step * min(1.0, 5.0 / max(float(np.abs(step).max()), 1e-9))
        if np.abs(step).max() < 1e-8:
            break
    return tuple((beta / np.append(scale, 1.0)).tolist())


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score, evidence, passages (first token, last token and score of every significant one), best_score."""
    shared = docs.sparkSession.sparkContext.broadcast(model.__dict__)

    def scored(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own = Model(**{k: v for k, v in shared.value.items()})
        for frame in frames:
            rows = []
            for text in frame["text"]:
                words = tokens(text)
                evidence, total, found, best = own.evidence(words)
                rows.append((own.score(evidence, total), evidence, [{"first": a, "last": b, "score": s} for a, b, s in found], best))
            out = pd.DataFrame(rows, columns=["score", "evidence", "passages", "best_score"])
            out.insert(0, "doc_id", frame["doc_id"].to_numpy())
            yield out

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInPandas(
        scored, "doc_id long, score double, evidence double, passages array<struct<first:int,last:int,score:double>>, best_score double")


def op4_segment_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = common.documents(spark, sf_dir), common.table(spark, sf_dir, "labels")
    fold = common.fold(F.col("doc_id"), HELD_OUT_MODULUS)
    model = fit(training_sample(docs, labels.filter(fold != HELD_OUT_REMAINDER), "toxic", MAX_PER_CLASS))
    return score(docs, model).select("doc_id", (fold == HELD_OUT_REMAINDER).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.size("passages").alias("n_passages"), "best_score")
