"""Language identification as mixture inference.

A text is a bag of character n-grams drawn from a mixture of languages. Expectation-maximisation estimates the
proportions of the languages in the set; the set grows by the language that raises the likelihood most, for as long
as the gain exceeds a penalty per language (half the logarithm of the number of n-grams, times `penalty`).

Models are one table of log-probabilities per language over a fixed number of hashed n-gram buckets, so what is
broadcast is (languages x buckets) numbers at any corpus size. They are fitted on a bounded sample of labelled texts
(`sample_per_language`, taken in the order of a hash of the id, so alike for any layout of the files) by a grouped
aggregation; scoring is map-only.

Defined cases: null text, or one without letters, gives `und` with score 0; a table without labelled rows gives `und`
everywhere; very long texts are counted whole; repeated rows are scored alike; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relcodec.llm import common

UNDETERMINED = "und"
BUCKETS = 1 << 15
SAMPLE_PER_LANGUAGE = 2000
#: More labelled languages than this are an error, never dropped: models are BUCKETS numbers each.
MAX_LANGUAGES = 512
HELD_OUT_MODULUS, HELD_OUT_REMAINDER = 4, 2


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)


def letters(points: np.ndarray) -> np.ndarray:
    """Letters as they are, everything else as one blank; ASCII by range, the rest by Unicode's own classes."""
    is_letter = (points >= 97) & (points <= 122)
    other = points > 127
    if other.any():
        distinct, place = np.unique(points[other], return_inverse=True)
        is_letter[other] = np.array([chr(p).isalpha() for p in distinct])[place]
    return np.where(is_letter, points, np.uint64(32))


def grams(text: str) -> np.ndarray:
    """Buckets of the text's letter n-grams of length 1 to 3; runs of non-letters count as one word boundary."""
    points = letters(code_points(f" {text} "))
    points = points[~((points == 32) & (np.roll(points, 1) == 32))] if len(points) > 1 else points
    if len(points) < 2:
        return np.zeros(0, np.int64)
    mixed = [points[points != 32] * np.uint64(0x9E3779B97F4A7C15)]
    two = points[:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + points[1:] * np.uint64(0x165667B19E3779F9)
    mixed.append(two)
    if len(points) > 2:
        mixed.append(two[:-1] * np.uint64(0x9E3779B185EBCA87) + points[2:] * np.uint64(0x27D4EB2F165667C5))
    return (np.concatenate(mixed) >> np.uint64(64 - 15)).astype(np.int64) if BUCKETS == 1 << 15 else (np.concatenate(mixed) % np.uint64(BUCKETS)).astype(np.int64)


def fit(docs: DataFrame, sample_per_language: int = SAMPLE_PER_LANGUAGE, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> tuple[list[str], np.ndarray]:
    """(languages, log-probabilities by language and bucket), add-half smoothed, from labelled rows."""
    labelled = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).filter("lang is not null and text is not null")
    # The bounded sample: per language the ids with the smallest hashes, found on narrow rows before any text moves.
    keys = labelled.select("lang", F.xxhash64("doc_id").alias("h"))
    totals = {r["lang"]: r["n"] for r in keys.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "lang").limit(MAX_LANGUAGES + 1).collect()}
    if len(totals) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages are labelled: their models would not fit a broadcast")
    if not totals:
        return [], np.zeros((0, BUCKETS))
    # A uniform hash threshold leaves about four samples' worth of rows per language; ranks decide among those.
    share = F.create_map(*[x for lang, n in totals.items() for x in (F.lit(lang), F.lit(min(1.0, 4.0 * sample_per_language / n)))])
    near = labelled.withColumn("h", F.xxhash64("doc_id")).filter(((F.col("h").cast("double") / 2.0**64 + 0.5) <= share[F.col("lang")]))
    rank = F.row_number().over(W.partitionBy("lang").orderBy("h", "doc_id"))
    sample = near.withColumn("rank", rank).filter(F.col("rank") <= sample_per_language).select("lang", "text")

    def counted(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sums: dict[str, np.ndarray] = {}
        for frame in frames:
            for lang, text in zip(frame["lang"], frame["text"], strict=True):
                sums.setdefault(lang, np.zeros(BUCKETS, np.int64))
                sums[lang] += np.bincount(grams(text), minlength=BUCKETS)
        for lang, c in sums.items():
            some = np.flatnonzero(c)
            yield pd.DataFrame({"lang": lang, "bucket": some, "n": c[some]})

    counts = sample.mapInPandas(counted, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(counts["lang"].unique())
    table = np.full((len(langs), BUCKETS), 0.5)
    table[counts["lang"].map({x: i for i, x in enumerate(langs)}).to_numpy(int), counts["bucket"].to_numpy(int)] += counts["n"].to_numpy(float)
    return langs, np.log(table / table.sum(axis=1, keepdims=True))


def proportions(counts: np.ndarray, log_probs: np.ndarray, rounds: int = 12) -> tuple[np.ndarray, float]:
    """EM over the given languages: (proportions, log-likelihood) of n-gram counts under their mixture."""
    top = log_probs.max(axis=0)
    like = np.exp(log_probs - top)
    share = np.full(len(like), 1.0 / len(like))
    total = counts.sum()
    for _ in range(rounds):
        joint = share[:, None] * like
        new = (joint * (counts / joint.sum(axis=0))).sum(axis=1) / total
        done = np.abs(new - share).max() < 1e-4
        share = new
        if done:
            break
    return share, float((counts * (np.log((share[:, None] * like).sum(axis=0)) + top)).sum())


def infer(text: str | None, log_probs: np.ndarray, penalty: float = 8.0) -> list[tuple[int, float]]:
    """Languages of a text with their proportions, largest first; empty if it has no letters."""
    found = grams(text) if text else np.zeros(0, np.int64)
    if not len(found) or not len(log_probs):
        return []
    bag = np.bincount(found, minlength=BUCKETS)
    some = np.flatnonzero(bag)
    counts, probs = bag[some].astype(float), log_probs[:, some]
    alone = probs @ counts
    chosen = [int(alone.argmax())]
    share, best = np.ones(1), float(alone.max())
    cost = penalty * 0.5 * np.log(counts.sum())
    while len(chosen) < len(probs):
        # The best addition is the language whose n-grams the present mixture explains worst.
        mixed = np.log((share[:, None] * np.exp(probs[chosen] - probs.max(axis=0))).sum(axis=0)) + probs.max(axis=0)
        gain = (counts * np.maximum(probs - mixed, 0)).sum(axis=1)
        gain[chosen] = -np.inf
        extra = int(gain.argmax())
        if gain[extra] <= cost:
            break
        new_share, like = proportions(counts, probs[[*chosen, extra]])
        if like - best <= cost:
            break
        chosen, share, best = [*chosen, extra], new_share, like
    order = np.argsort(-share, kind="stable")
    return [(chosen[i], float(share[i])) for i in order]


def identify(docs: DataFrame, model: tuple[list[str], np.ndarray], penalty: float = 8.0, id_col: str = "doc_id", text_col: str = "text",
             passthrough: tuple[str, ...] = ()) -> DataFrame:
    """doc_id (or the columns named to pass through), lang_pred, score (share of the main language), mixture."""
    langs, log_probs = model
    shared = docs.sparkSession.sparkContext.broadcast(log_probs)

    def predicted(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        probs = shared.value
        for frame in frames:
            rows = [infer(t, probs, penalty) for t in frame["text"]]
            out = pd.DataFrame({
                "lang_pred": [langs[r[0][0]] if r else UNDETERMINED for r in rows],
                "score": [min(1.0, max(0.0, r[0][1])) if r else 0.0 for r in rows],
                "n_langs": [len(r) for r in rows],
                "mixture": [",".join(f"{langs[i]}:{p:.3f}" for i, p in r) for r in rows],
            })
            yield pd.concat([frame[kept].reset_index(drop=True), out], axis=1)

    kept = list(passthrough) or ["doc_id"]
    docs = docs.select(*passthrough) if passthrough else docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    schema = T.StructType([docs.schema[c] for c in kept])
    for field, kind in (("lang_pred", "string"), ("score", "double"), ("n_langs", "integer"), ("mixture", "string")):
        schema = schema.add(field, kind)
    return docs.mapInPandas(predicted, schema)


def op2_mixture_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    remainder = common.fold(F.col("doc_id"), HELD_OUT_MODULUS)
    model = fit(docs.filter(remainder != HELD_OUT_REMAINDER))
    out = identify(docs, model)
    return out.select("doc_id", (common.fold(F.col("doc_id"), HELD_OUT_MODULUS) == HELD_OUT_REMAINDER).alias("held_out"), "lang_pred", "score", "n_langs", "mixture")
