"""Shared pieces of the training-data operators: words, scratch tables, sized broadcasts."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Word separators of every word-based operator: space and U+0009 to U+000D.
SEPARATORS = r"[\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text: Column) -> Column:
    """Maximal runs of non-separator characters; an empty array for null and for blank texts."""
    trimmed = F.regexp_replace(F.coalesce(text, F.lit("")), r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "")
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SEPARATORS))


def fold(doc_id: Column, modulus: int) -> Column:
    """crc32 of the decimal id, modulo: the fold a document belongs to. A null id folds like an empty string."""
    return F.crc32(F.encode(F.coalesce(doc_id.cast("string"), F.lit("")), "UTF-8")) % modulus


def let(value: Column, body) -> Column:
    """body(value) with value computed once: higher-order functions have no shared subexpressions."""
    return F.transform(F.array(value), body)[0]


def window_hashes(tokens: Column, size: int) -> Column:
    """One 64-bit hash per run of `size` adjacent tokens, in order; empty when there are fewer tokens.

    Doubling keeps the work per token constant in `size`: hashes of 2^k tokens come from two of 2^(k-1).
    """
    def paired(by: int):
        # The last `by` entries pair with nothing; they are cut off below.
        return lambda h: F.zip_with(h, F.slice(h, by + 1, 1 << 30), lambda a, b: F.xxhash64(a, b))

    span, hashed = 1, F.transform(tokens, lambda t: F.xxhash64(t))
    while span < size:
        step = min(span, size - span)
        hashed = let(hashed, paired(step))
        span += step
    return F.slice(hashed, F.lit(1), F.greatest(F.size(tokens) - (size - 1), F.lit(0)))


def scratch_dir(spark: SparkSession) -> str:
    """A new folder under the cluster's shared checkpoint folder; where none is set, one of this machine if it is all
    there is (a local master), else an error."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not root and not spark.sparkContext.master.split("[")[0] == "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not root:
        root = tempfile.mkdtemp(prefix="relcodec-")
    return f"{root.rstrip('/')}/relcodec-{uuid.uuid4().hex}"


def materialise(df: DataFrame, partition_by: list[str] | None = None) -> DataFrame:
    """Write to a shared scratch table and read it back: lineage is cut and a lost executor costs no recomputation."""
    path = scratch_dir(df.sparkSession)
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path) if not partition_by else df.sparkSession.read.parquet(path)


def small_side(df: DataFrame, rows: int, max_rows: int) -> DataFrame:
    """Broadcast hint only below a checked row count; beyond it the join shuffles."""
    return F.broadcast(df) if rows <= max_rows else df
