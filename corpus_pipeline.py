"""Corpus pipeline: language, near duplicates, benchmark leaks, personal data, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows it is given; run() writes a stage's rows as Parquet in the
shared scratch folder and reads them again for the next one.

Defined cases, for every stage: rows whose ids are null or shared are told apart by a key of id and text (`keyed`); null
and empty texts have no language, so they go in the first stage (alone, later stages keep them); rows equal in id and
text are one document from the second stage on; of equally near copies the smallest id stays; very long texts are read
whole; columns beyond those of documents are dropped; an empty table goes through all stages and stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec.llm import common, decontamination, language_id, near_dup, packing, pii

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: A text is rejected without letters, or if no language explains at least this share of it.
LEAST_SHARE = 0.3


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with a main language; the models learn from the labelled rows of the given documents."""
    verdict = language_id.identify(docs, language_id.fit(docs), passthrough=COLUMNS)
    return verdict.filter((F.col("lang_pred") != language_id.UNDETERMINED) & (F.col("score") >= LEAST_SHARE)).select(*COLUMNS)


def keyed(docs: DataFrame) -> DataFrame:
    """docs with a row key `_key`: the id where it tells texts apart, else (null, or shared by unlike texts) a hash of id
    and text above all usual ids. Rows equal in both are one document."""
    text = F.xxhash64("text")
    shared = docs.filter("doc_id is not null").groupBy("doc_id").agg(F.min(text).alias("low"), F.max(text).alias("high")).filter("low <> high").select("doc_id", F.lit(True).alias("_shared"))
    own = F.xxhash64("doc_id", "text").bitwiseAND(F.lit((1 << 62) - 1)).bitwiseOR(F.lit(1 << 62))
    by_id = F.col("doc_id").isNotNull() & F.col("_shared").isNull()
    return docs.join(common.materialise(shared), "doc_id", "left").withColumn("_key", F.when(by_id, F.col("doc_id").cast("long")).otherwise(own)).drop("_shared")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class, whatever its id: the one with the smallest, null and shared ids last."""
    docs = keyed(docs)
    keep = near_dup.classes(docs, id_col="_key").filter("doc_id = class_id").select(F.col("doc_id").alias("_key")).distinct()
    return docs.join(common.materialise(keep), "_key", "left_semi").dropDuplicates(["_key"]).select(*COLUMNS)


def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without occurrences of benchmark items, whatever their ids."""
    docs = keyed(docs)
    hits = decontamination.contaminated(docs.select(F.col("_key").alias("doc_id"), "text"), common.table(spark, sf_dir, "benchmark")).select(F.col("doc_id").alias("_key"))
    return docs.join(common.materialise(hits), "_key", "left_anti").select(*COLUMNS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with surrogates in place of personal data; n_chars is that of the new text."""
    return pii.replace(docs.select(*COLUMNS), pii.DEMO_KEY).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in sequences of at most 2048 tokens."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"))


STAGES = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("benchmark_leaks", benchmark_leaks),
    ("personal_data", personal_data),
    ("packing", packed),
]

#: Signatures, mixtures and token ids are beyond SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    for _, stage in STAGES:
        docs = common.materialise(stage(spark, docs, sf_dir))
    return docs
