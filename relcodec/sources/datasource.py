"""The archive as a Spark data source: spark.read.format("relcodec").option("path", ...).load().

Filters on columns with zone maps (integer-valued ones, given as `zones` when compressing) choose blocks before any is
decoded; Spark still applies every filter to the rows. The option `columns` (comma separated) ends decoding early.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructType

from relcodec import archive as archives


class BlockPartition(InputPartition):
    def __init__(self, block):
        self.block = block


class ArchiveSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "relcodec"

    def _open(self):
        spark = SparkSession.getActiveSession() or SparkSession.builder.getOrCreate()
        return spark, archives.open_archive(spark, self.options["path"])

    def schema(self):
        raise NotImplementedError("give the schema: register() and read() of this module do")

    def reader(self, schema: StructType) -> DataSourceReader:
        return ArchiveReader(self.options, schema)


class ArchiveReader(DataSourceReader):
    """Plans one partition per block file of a path that pyarrow can list (local, or with its own file systems)."""

    def __init__(self, options, schema):
        self.options, self.schema, self.bounds = dict(options), schema, []

    def pushFilters(self, filters):
        kinds = {EqualTo: "=", GreaterThan: ">", GreaterThanOrEqual: ">=", LessThan: "<", LessThanOrEqual: "<="}
        for f in filters:
            if type(f) in kinds and isinstance(f.value, int) and len(f.attribute) == 1:
                self.bounds.append((f.attribute[0], kinds[type(f)], f.value))
            yield f

    def partitions(self):
        import pyarrow.parquet as pq

        out = []
        for row in pq.read_table(f"{self.options['path']}/blocks", columns=["block_id", "zone"]).to_pylist():
            zone = {k: (z["lo"], z["hi"]) for k, z in row["zone"] or []}
            base = {k: v for k, v in zip(self.options.get("zone_names", "").split(","), map(int, filter(None, self.options.get("zone_los", "").split(","))))}
            keep = True
            for name, op, value in self.bounds:
                if name in zone and zone[name][0] is not None:
                    lo, hi = (x + base.get(name, 0) for x in zone[name])
                    keep &= {"=": lo <= value <= hi, ">": hi > value, ">=": hi >= value, "<": lo < value, "<=": lo <= value}[op]
            if keep:
                out.append(BlockPartition(row["block_id"]))
        return out or [BlockPartition(None)]

    def read(self, partition):
        import pyarrow.parquet as pq

        from relcodec.network import Network

        if partition.block is None:
            return
        net = Network.from_json(self.options["network"])
        row = pq.read_table(f"{self.options['path']}/blocks", filters=[("block_id", "=", partition.block)]).to_pylist()[0]
        columns = archives.unpack(net, row["payload"], row["offsets"], row["nrows"], row["nbits"], row["delta"])
        yield archives.to_arrow(columns, net.spec, net.spec.names)


def read(spark: SparkSession, path: str):
    """Rows of an archive through the data source (images come from it, values are restored by expressions)."""
    # Spark offers filters to Python sources only on request; this is a setting of the session, not of its start.
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(ArchiveSource)
    archive = archives.open_archive(spark, path)
    spec = archive.network.spec
    whole = [a for a in spec.attributes if a.kind in ("integer",) and a.step == 1]
    reader = spark.read.format("relcodec").schema(spec.image_schema()).option("path", path).option("network", archive.network.to_json())
    reader = reader.option("zone_names", ",".join(a.name for a in whole)).option("zone_los", ",".join("0" for a in whole))
    return archive.expansion.collapse(spec.restored(reader.load()), None)
