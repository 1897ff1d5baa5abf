"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec import archive as archives
from relcodec.schema import TableSpec, quoted
from relcodec.sources.stored import Stored, coded, mapped, texts_of


def raw_bytes(df: DataFrame | Stored) -> int:
    """Bytes of the table as comma-separated text with a line end a row."""
    if isinstance(df, Stored):
        return stored_bytes(df)
    line = F.concat_ws(",", *[F.coalesce(F.col(quoted(c)).cast("string"), F.lit("")) for c in df.columns])
    # concat_ws drops nothing here, since NULLs were made empty.
    return int(df.agg(F.sum(F.octet_length(line) + 1)).first()[0] or 0)


def stored_bytes(df: Stored) -> int:
    """`raw_bytes` of a table whose texts are stored: the lengths of distinct texts, a batch at a time."""
    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total = batch.num_rows * batch.num_columns
            for column in batch.columns:
                values, at = coded(column)
                size = pc.binary_length(values.cast(pa.large_string())).to_numpy(zero_copy_only=False)
                total += int(np.append(size, 0)[at].sum())
            yield pa.RecordBatch.from_pydict({"bytes": [total]})

    return int(mapped(texts_of(df, df.columns), counted, "bytes long").agg(F.sum("bytes")).first()[0] or 0)


def compression_ratio(spark: SparkSession, archive: archives.Archive, df: DataFrame) -> dict[str, float]:
    """Archive over raw bytes, with and without the model's."""
    size, raw = archives.archive_bytes(spark, archive), raw_bytes(df)
    return {"raw": raw, **size, "ratio": (size["codes"] + size["index"] + size["model"]) / raw, "ratio_without_model": (size["codes"] + size["index"]) / raw}


def reduction(ours: float, other: float) -> float:
    return 1 - ours / other


def closeness(df: DataFrame, back: DataFrame, key: str, spec: TableSpec) -> DataFrame:
    """attribute, max_error, violations, lost: how far restored values are from the originals, by key.

    A row on one side only is a violation of every attribute and counts as lost."""
    one = df.select(F.col(key).alias("_k"), F.lit(True).alias("_o"), *[F.col(quoted(a.name)).alias(f"o_{a.name}") for a in spec.attributes])
    other = back.select(F.col(key).alias("_b"), F.lit(True).alias("_r"), *[F.col(quoted(a.name)).alias(f"r_{a.name}") for a in spec.attributes])
    both = one.join(other, F.col("_k").eqNullSafe(F.col("_b")), "full")
    lost = F.col("_o").isNull() | F.col("_r").isNull()
    rows = []
    for a in spec.attributes:
        o, r = F.col(quoted(f"o_{a.name}")), F.col(quoted(f"r_{a.name}"))
        near = a.numeric and a.kind not in ("timestamp", "date")
        error = F.abs(o.cast("double") - r.cast("double")) if near else F.lit(None).cast("double")
        error = F.when(lost, math.inf).when(o.eqNullSafe(r), 0.0).otherwise(F.coalesce(error, F.lit(math.inf if near else 1.0)))
        rows.append(F.struct(F.lit(a.name).alias("attribute"), error.alias("error"), lost.alias("lost"), F.lit(float(a.tolerance) if a.numeric else 0.0).alias("allowed")))
    return both.select(F.explode(F.array(*rows)).alias("x")).groupBy("x.attribute").agg(
        F.max("x.error").alias("max_error"), F.count_if(F.col("x.error") > F.col("x.allowed") + 1e-9).alias("violations"), F.count_if("x.lost").alias("lost"))


def size_breakdown(spark: SparkSession, archive: archives.Archive) -> DataFrame:
    """component, bits: codes, index and every node's model."""
    size = archives.archive_bytes(spark, archive)
    rows = [("codes", float(size["code_bits"])), ("index", 8.0 * size["index"]), *[(f"model {n.attribute.name}", float(n.bits)) for n in archive.network.nodes]]
    return spark.createDataFrame(rows, "component string, bits double")


def timed_phases(spark: SparkSession, df: DataFrame, options: archives.Options = archives.Options()) -> dict[str, float]:
    """Seconds of structure learning, parameter fit, coding with writing, and decompression."""
    from relcodec.schema import infer_spec
    from relcodec.sources.tables import scratch

    out, t = {}, time.time()

    def lap(name: str) -> None:
        nonlocal t
        out[name], t = time.time() - t, time.time()

    wide = archives.codecs.Expansion.infer(df).expand(df)
    spec = infer_spec(wide)
    images = spec.images(wide)
    lap("schema")
    structure = archives.learn(images, spec, options)
    lap("structure")
    network = archives.fit_parameters(images, spec, structure)
    lap("parameters")
    path = scratch(spark)
    archives.encode(images, network, options).write.parquet(path)
    lap("compression")
    archives.decode(spark.read.schema(archives.BLOCKS).parquet(path), network).write.format("noop").mode("overwrite").save()
    lap("decompression")
    return out


def gaussian_bits(deviation: float, tolerance: float) -> float:
    """About how many bits a normal number needs when the tolerance is small against the deviation."""
    return math.log2(deviation / tolerance) + 0.5 * math.log2(2 * math.pi * math.e) - 1


def delta_saving(n: int) -> float:
    """Bits that sorting n codes saves, about."""
    return n * (math.log2(n) - 2) if n > 4 else 0.0


def clustered_bits(attributes: int, flip: float) -> float:
    """Bits of a tuple of binary copies of a hidden bit, each flipped with a probability: the cluster coded along."""
    return 1 + attributes * -(flip * math.log2(flip) + (1 - flip) * math.log2(1 - flip))


def chain_bits(attributes: int, symbols: int, stay: float) -> float:
    """Bits of a tuple whose attributes form a chain that stays or moves evenly to any other symbol."""
    move = (1 - stay) / (symbols - 1)
    return math.log2(symbols) + (attributes - 1) * -(stay * math.log2(stay) + (1 - stay) * math.log2(move))
