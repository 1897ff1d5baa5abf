"""Named queries over archives and statistics, and the DuckDB SQL each is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from relcodec import archive as archives
from relcodec.functions import scalars  # noqa: F401  (registers its queries)
from relcodec.operators import more, relational  # noqa: F401
from relcodec.plans import studies  # noqa: F401
from relcodec.plans.workloads import ORACLES, QUERIES
from relcodec.sources.tables import scratch, table
from relcodec.streaming import streams  # noqa: F401

__all__ = ["ORACLES", "QUERIES", "flagship"]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem through an archive and back."""
    path = scratch(spark)
    archives.compress(table(spark, sf_dir, "lineitem"), path)
    return archives.decompress(spark, path)
