"""Quality rules: a threshold table compiled into one projection.

Each rule compares `numerator * 1000` with `threshold * denominator` in whole numbers, so results are the same on
every engine. Metrics are plain columns over the text (lengths, symbols, stop words, lines, repeated 8-word
windows); no user function, no shuffle, one scan.

Defined cases: null text counts as no words (all metrics 0, base_failed true); empty and blank texts likewise; very
long texts cost linear time but for sorting the windows of those with repeats; repeated rows give repeated rows;
an empty table gives an empty result; other columns are neither read nor returned.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec.llm import common

WINDOW = 8
#: Frequent function words of the corpus languages.
STOP_WORDS = ("a", "and", "as", "de", "der", "die", "el", "en", "in", "is", "it", "la", "le", "of", "on", "que", "the", "to", "und", "von")


@dataclass(frozen=True)
class Rule:
    """Keeps a text when 1000 * numerator >= / <= per_mille * denominator."""

    name: str
    numerator: str
    keeps: str
    per_mille: int
    denominator: str = "one"

    def passes(self) -> Column:
        left, right = F.col(self.numerator) * 1000, F.col(self.denominator) * self.per_mille
        return left >= right if self.keeps == ">=" else left <= right


#: The production threshold table.
RULES = (
    Rule("most_words", "n_words", "<=", 200_000_000),
    Rule("longest_mean_word", "word_chars", "<=", 20_000, "n_words"),
    Rule("shortest_mean_word", "word_chars", ">=", 2_000, "n_words"),
    Rule("symbols_to_words", "n_symbols", "<=", 400, "n_words"),
    Rule("duplicate_lines", "n_dup_lines", "<=", 500, "n_lines"),
    Rule("stop_words", "n_stop_words", ">=", 10, "n_counted"),
    Rule("shouted_words", "n_shouts", "<=", 400, "n_words"),
)


def metrics(text: Column) -> dict[str, Column]:
    body = F.coalesce(text, F.lit(""))
    return {"body": body, "words": common.words(text), "lines": F.filter(F.split(body, "\n"), lambda line: F.length(F.translate(line, " \t\n\x0b\x0c\r", "")) > 0)}


def repeat_words(windows: Column) -> Column:
    """Words covered by windows found at least twice, given the window hashes in order."""

    def covered(h: Column) -> Column:
        # Equal windows meet after sorting; what differs from both neighbours is found once.
        ordered = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        starts = common.let(ordered, lambda o: F.sort_array(F.transform(
            F.filter(o, lambda e, k: (F.get(o, k - 1)["h"] == e["h"]) | (F.get(o, k + 1)["h"] == e["h"])), lambda e: e["i"])))
        return F.aggregate(starts, F.struct(F.lit(0).alias("sum"), F.lit(-WINDOW).alias("last")), lambda acc, i: F.struct(
            (acc["sum"] + F.least(i - acc["last"], F.lit(WINDOW))).alias("sum"), i.alias("last")), lambda acc: acc["sum"])

    return common.let(windows, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(covered(h)))


def assess(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per text: the metrics, base_failed, the rules it broke and the verdict."""
    part = metrics(F.col(text_col))
    cut = docs.select(F.col(id_col).alias("doc_id"), part["body"].alias("body"), part["words"].alias("words"), part["lines"].alias("lines"))
    cut = cut.withColumn("joined", F.array_join("words", ""))
    measured = cut.select(
        "doc_id",
        F.lit(1).cast("long").alias("one"),
        F.size("words").cast("long").alias("n_words"),
        F.length("joined").cast("long").alias("word_chars"),
        (F.length("body") - F.length(F.translate("body", "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        repeat_words(common.window_hashes(F.col("words"), WINDOW)).cast("long").alias("n_repeat_words"),
        F.size(F.filter("words", lambda w: w.isin(*STOP_WORDS))).cast("long").alias("n_stop_words"),
        (F.length("body") - F.length(F.translate("body", "!", ""))).cast("long").alias("n_shouts"),
    )
    # Short texts may do without stop words.
    measured = measured.withColumn("n_counted", F.when(F.col("n_words") >= 100, F.col("n_words")).otherwise(F.lit(0).cast("long")))
    base_failed = (F.col("n_words") < 20) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 30)
    broken = F.array_compact(F.array(*[F.when(~rule.passes(), F.lit(rule.name)) for rule in rules]))
    return measured.withColumns({"base_failed": base_failed, "broken": broken}).withColumn("kept", ~F.col("base_failed") & (F.size("broken") == 0)).drop("one", "n_counted")


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assess(common.documents(spark, sf_dir)).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept",
        "n_lines", "n_stop_words", "n_shouts")


_IN_SQL = {"one": "1", "n_counted": "(CASE WHEN n_words >= 100 THEN n_words ELSE 0 END)"}

ORACLE = """
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS body,
         regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS words,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines
  FROM documents
), win AS (
  SELECT doc_id, i, list_slice(words, i, i + 7) AS w
  FROM (SELECT doc_id, words, unnest(range(1, len(words) - 6)) AS i FROM d WHERE len(words) >= 8)
), rep AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w) AS n FROM win) WHERE n > 1
), cov AS (
  SELECT doc_id, count(DISTINCT i + k) AS n FROM rep, range(8) AS t(k) GROUP BY doc_id
), m AS (
  SELECT doc_id, len(words)::BIGINT AS n_words, length(array_to_string(words, ''))::BIGINT AS word_chars,
         (length(body) - length(regexp_replace(body, '[#*$%%&|<>]', '', 'g')))::BIGINT AS n_symbols,
         len(lines)::BIGINT AS n_lines, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
         coalesce(cov.n, 0)::BIGINT AS n_repeat_words,
         len(list_filter(words, lambda x: x IN (%s)))::BIGINT AS n_stop_words,
         (length(body) - length(replace(body, '!', '')))::BIGINT AS n_shouts
  FROM d LEFT JOIN cov USING (doc_id)
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (n_words < 20 OR n_repeat_words * 100 > n_words * 30) AS base_failed,
       NOT (n_words < 20 OR n_repeat_words * 100 > n_words * 30) AND %s AS kept,
       n_lines, n_stop_words, n_shouts
FROM m
""" % (", ".join(f"'{w}'" for w in STOP_WORDS), " AND ".join(f"{r.numerator}::BIGINT * 1000 {r.keeps} {r.per_mille}::BIGINT * {_IN_SQL.get(r.denominator, r.denominator)}" for r in RULES))
