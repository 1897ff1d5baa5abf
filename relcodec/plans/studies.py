"""Studies of whole archives: sizes by treatment, tolerance, sample and baseline, and what access and estimates cost.

Archive sizes have no SQL form, so most of these queries are compared with thresholds in the tests.
"""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec import archive as archives
from relcodec import baselines, measures
from relcodec.network import CELL_BITS, Network, Structure, family_bits, fit_parameters
from relcodec.plans.workloads import CODES_SQL, NODES, query, short_codes
from relcodec.schema import Attribute, TableSpec, quoted
from relcodec.sources.stored import Stored, derived, stored_spec, text_columns, with_texts
from relcodec.sources.tables import clustered100, scratch, star, table


#: Rows of a file of a study's table: small ones let all cores read it, however few tasks wrote it.
FILE_ROWS = 65_536


def written(df: DataFrame) -> DataFrame:
    """df as a scratch table, so that a study's many passes don't repeat its joins."""
    path = scratch(df.sparkSession)
    df.write.option("maxRecordsPerFile", FILE_ROWS).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class Subject:
    """A table made ready once: its codecs, attributes and text size, for archives under several options."""

    def __init__(self, df: DataFrame, spec: TableSpec | None = None, texts: bool = False):
        """texts: the texts of columns are stored with them, so that tasks read them too."""
        made = written(with_texts(df) if texts else df)
        self.df = made.select(*[F.col(quoted(c)) for c in df.columns])
        self.stored = Stored(made, {c: c for c in df.columns}, text_columns(df)) if texts else None
        self.expansion = archives.codecs.Expansion.infer(self.df) if spec is None else archives.codecs.Expansion.none(self.df)
        self.wide = self.expansion.expand(self.df)
        self.raw, self.rows = measures.raw_bytes(self.df if self.stored is None else self.stored), self.df.count()
        self.spec = spec or stored_spec(self.df, self.expansion, self.rows)

    @functools.cached_property
    def images(self) -> Stored:
        """The table's images as a scratch table, for archives that are made in the same scans."""
        return Stored(written(self.spec.images(self.wide)))

    def images_under(self, specs: list[TableSpec]) -> list[Stored]:
        """The table's images under several specs: made by the tasks that read the table, or else all in one scratch table that
        has equal ones once."""
        if self.stored is not None and (made := derived(self.stored, self.expansion, specs)):
            return made
        place: dict[Attribute, str] = {}
        columns = [{a.name: place.setdefault(a, f"image{len(place)}") for a in spec.attributes} for spec in specs]
        table = written(self.wide.select(*[a.image().alias(c) for a, c in place.items()]))
        return [Stored(table, own) for own in columns]

    def plain_spec(self) -> TableSpec:
        """`infer_spec` of the table whose columns are not taken apart: of those that no codec takes apart it is known."""
        whole = [c[0] for c in self.expansion.columns if c[2] is None]
        apart = [c[0] for c in self.expansion.columns if c[2] is not None]
        known = {n: self.spec[n] for n in whole}
        if apart:
            table = self.df.select(*[F.col(quoted(n)) for n in apart])
            known |= {a.name: a for a in stored_spec(table, archives.codecs.Expansion.none(table), self.rows).attributes}
        return TableSpec(tuple(known[n] for n in self.df.columns))

    def archive(self, options: archives.Options = archives.Options(), spec: TableSpec | None = None) -> archives.Archive:
        """An archive of the table in scratch (codes only pass through executors)."""
        spec = spec or self.spec
        images = spec.images(self.wide)
        network = fit_parameters(images, spec, archives.learn(images, spec, options), string_order=options.string_order)
        path = scratch(self.df.sparkSession)
        archives.encode(images, network, options).write.option("compression", "none").parquet(f"{path}/blocks")
        return archives.Archive(path, network, self.expansion)

    def bytes(self, archive: archives.Archive) -> dict[str, int]:
        return archives.archive_bytes(self.df.sparkSession, archive)

    def total(self, archive: archives.Archive) -> int:
        size = self.bytes(archive)
        return size["codes"] + size["index"] + size["model"]


def archived(images: Stored, spec: TableSpec, options: list[archives.Options], rows: int) -> list[tuple[Network, int]]:
    """(network, bytes of codes, index and model) under several options: all archives are made in the same scans."""
    networks = archives.fit_all(images, spec, options, rows)
    return [(network, size["codes"] + size["index"] + size["model"]) for network, size in zip(networks, archives.encoded_bytes(images, networks, options), strict=True)]


def sizes_of(subject: Subject, options: dict[str, archives.Options]) -> list[tuple]:
    """(name, code bits a row, bytes of model, ratio) by name of options: all archives are made in the same scans.

    Tasks read the images' files themselves, so blocks are those of files in order, a run of them a task."""
    chosen = list(options.values())
    sizes = archives.encoded_bytes(subject.images, archives.fit_all(subject.images, subject.spec, chosen, subject.rows), chosen)
    return [(name, size["code_bits"] / max(subject.rows, 1), size["model"], (size["codes"] + size["index"] + size["model"]) / subject.raw) for name, size in zip(options, sizes, strict=True)]


SIZES = "treatment string, code_bits_per_row double, model_bytes long, ratio double"
EMPTY = archives.Options(structure="empty")


@query("dependence_gain_star")
def dependence_gain_star(spark, sf_dir):
    """The star view under learned dependences and as independent columns: sizes with models."""
    return spark.createDataFrame(sizes_of(Subject(star(spark, sf_dir)), {"learned": archives.Options(), "columns": EMPTY}), SIZES)


@query("sensitivity_five_samples")
def sensitivity_five_samples(spark, sf_dir):
    """The star view under structures learned from five random samples."""
    return spark.createDataFrame(sizes_of(Subject(star(spark, sf_dir)), {f"sample {i}": archives.Options(seed=i) for i in range(5)}), SIZES)


@query("sensitivity_sample_size")
def sensitivity_sample_size(spark, sf_dir):
    """The star view under structures learned from more and more rows."""
    return spark.createDataFrame(sizes_of(Subject(star(spark, sf_dir)), {str(n): archives.Options(sample_rows=n) for n in (1000, 2000, 5000)}), SIZES)


@query("scores_star")
def scores_star(spark, sf_dir):
    """The star view under structures by each score, and under a random one."""
    s = Subject(star(spark, sf_dir))
    options = {score: archives.Options(score=score, keys=False) for score in ("mdl_scaled", "mdl", "bic", "nll")}
    return spark.createDataFrame(sizes_of(s, options | {"random": archives.Options(structure=Structure.random(s.spec.names, 0))}), SIZES)


@query("ratio_vs_tolerance_mixed")
def ratio_vs_tolerance_mixed(spark, sf_dir):
    """Archives of a table of numbers and categories by tolerance (a share of each number's range), beside compressed text
    of the same rounded values."""
    s = Subject(table(spark, sf_dir, "lineitem").drop("l_orderkey"))
    prices = [a.name for a in s.spec.attributes if a.kind in ("decimal", "real") and a.name in s.df.columns]
    rows = []
    for percent in (0.0, 0.5, 1.0, 5.0, 10.0):
        spec = s.spec.with_tolerance_pct(percent, prices) if percent else s.spec
        size = s.bytes(s.archive(spec=spec))
        rounded = baselines.universal_size(s.expansion.collapse(spec.quantise(s.wide), None))
        rows.append((percent, size["code_bits"] / max(s.rows, 1), (size["codes"] + size["index"] + size["model"]) / s.raw, rounded / s.raw))
    return spark.createDataFrame(rows, "percent double, code_bits_per_row double, ratio double, text_ratio double")


def treatments(subject: Subject, percent: float = 1.0) -> list[tuple]:
    """(method, bytes, ratio) of every baseline on a table, its columns alone, the full archive, and a lossy one."""
    df, spec = subject.df, subject.spec
    stored = df if subject.stored is None else subject.stored
    plain = [f.name for f in df.schema.fields if not f.dataType.typeName() in ("array", "map", "struct")]
    numbers = [a.name for a in spec.attributes if a.kind in ("decimal", "real", "integer") and a.name in plain]
    lossy = spec.with_tolerance_pct(percent)
    images, near_images = subject.images_under([spec, lossy])
    (full, full_bytes), (_, columns_bytes) = archived(images, spec, [archives.Options(), EMPTY], subject.rows)
    rows = [("gzip", baselines.universal_size(stored)), ("gzip of columns", baselines.gzip_columns(stored))]
    if len(plain) == len(df.columns):
        domain = {r["attribute"]: r["bits"] for r in baselines.domain_code_bits(stored, plain).collect()}
        names = [a.name for a in spec.attributes if a.kind == "categorical" and a.name in plain]
        own = {c: tuple(p for p in full.structure.parents[c] if p in names) for c in names}
        rest = sum(b for c, b in domain.items() if c not in names) * subject.rows
        rows += [("domain code", sum(domain.values()) * subject.rows / 8), ("column prefix code, sorted deltas", baselines.column_huffman_delta_bits(stored, plain) / 8),
                 ("network with prefix codes", (baselines.network_huffman_bits(images, own, spec) + rest) / 8)]
        near = subject.plain_spec().with_tolerance_pct(percent)
        bits, squeezed = baselines.representative_rows(stored, near)
        rows += [("representative rows, lossy", bits / 8), ("representative rows and gzip, lossy", squeezed)]
        if len(numbers) > 1:
            predicted = {n: baselines.tree_predictor_bits(stored, near, n, [x for x in numbers if x != n]) for n in numbers[:1]}
            rows.append(("tree predictor of one number, lossy", (sum(b for c, b in domain.items() if c not in predicted) * subject.rows + sum(predicted.values())) / 8))
    (_, near_bytes), = archived(near_images, lossy, [archives.Options()], subject.rows)
    rows += [("archive of columns", columns_bytes), ("archive", full_bytes), ("archive, lossy", near_bytes)]
    return [(method, float(size), float(size) / subject.raw) for method, size in rows]


def baseline_table(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = star(spark, sf_dir) if name == "star" else table(spark, sf_dir, name)
        return spark.createDataFrame(treatments(Subject(df, texts=True)), "method string, bytes double, ratio double")
    return run


for _t in ("lineitem", "orders", "star", "embeddings"):
    query(f"baselines_{_t}")(baseline_table(_t))


@query("numeric_treatments_embeddings")
def numeric_treatments_embeddings(spark, sf_dir):
    """Vectors as 32-bit floats, on a fixed grid, as skew-aware columns, with correlations, and within a wider tolerance."""
    s = Subject(table(spark, sf_dir, "embeddings").select("embedding"))
    fine, coarse = s.spec.with_tolerance_pct(1e-5), s.spec.with_tolerance_pct(1e-2)
    per = lambda archive: s.bytes(archive)["code_bits"] / max(s.rows, 1)
    numbers = [a for a in fine.attributes if a.numeric]
    rows = [("float", 32.0 * len(numbers)), ("grid", float(sum(a.depth for a in numbers))), ("columns", per(s.archive(EMPTY, fine))),
            ("full", per(s.archive(archives.Options(max_parents=1), fine))), ("lossy", per(s.archive(EMPTY, coarse)))]
    return spark.createDataFrame(rows, "treatment string, bits_per_row double")


def optional_orders(spark: SparkSession, sf_dir: str, most: int = 8) -> DataFrame:
    """A row per customer with columns for each of its first orders, NULL from where there are no more."""
    o = table(spark, sf_dir, "orders").withColumn("k", F.row_number().over(W.partitionBy("o_custkey").orderBy("o_orderkey"))).filter(F.col("k") <= most)
    per = o.groupBy(F.col("o_custkey").alias("c_custkey")).agg(*[
        F.max(F.when(F.col("k") == k, F.col(c))).alias(f"{a}_{k}") for k in range(1, most + 1) for a, c in (("status", "o_orderstatus"), ("priority", "o_orderpriority"), ("price", "o_totalprice"))])
    return table(spark, sf_dir, "customer").join(per, "c_custkey", "left")


@query("lossless_ratio_wide_optional")
def lossless_ratio_wide_optional(spark, sf_dir):
    """A wide table of optional attributes with a network made by hand (each order's columns hang on its status, the
    status on the one before), beside independent columns and compressed text."""
    s = Subject(optional_orders(spark, sf_dir))
    known = set(s.spec.names)
    edges = [(f"status_{k}", f"{c}_{k}") for k in range(1, 9) for c in ("priority", "price")] + [(f"status_{k}", f"status_{k + 1}") for k in range(1, 8)]
    hand = Structure.from_edges(s.spec.names, [(p, c) for p, c in edges if {p, c} <= known])
    rows = sizes_of(s, {"by hand": archives.Options(structure=hand), "columns": EMPTY})
    return spark.createDataFrame([*rows, ("gzip", 8.0 * baselines.universal_size(s.df) / max(s.rows, 1), 0, baselines.universal_size(s.df) / s.raw)], SIZES)


def add_cluster_attribute(df: DataFrame, columns: list[str], k: int, seed: int = 0, sample_rows: int = 20_000) -> DataFrame:
    """df with `cluster`, a column that every other one is to depend on: k-means on a bounded sample, assigned by rows.

    The label is coded with the rows, so decoding needs no clustering."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    vectors = VectorAssembler(inputCols=columns, outputCol="_x").transform(df)
    sample = vectors.withColumn("_o", F.rand(seed)).orderBy("_o").limit(sample_rows)
    model = KMeans(k=k, seed=seed, featuresCol="_x", predictionCol="cluster").fit(sample)
    return model.transform(vectors).drop("_x")


@query("clustered_archive_bits")
def clustered_archive_bits(spark, sf_dir):
    """100 binary copies of a hidden bit in archives: with a cluster attribute, and as independent columns."""
    wide = clustered100(spark, sf_dir).groupBy("o_orderkey").pivot("i", list(range(1, 101))).agg(F.first("a"))
    columns = [f"a{i}" for i in range(1, 101)]
    wide = written(wide.select(*[F.col(str(i)).cast("int").alias(f"a{i}") for i in range(1, 101)]))
    s = Subject(add_cluster_attribute(wide, columns, 2).select("cluster", *columns))
    structure = Structure.from_edges(["cluster", *columns], [("cluster", c) for c in columns])
    return spark.createDataFrame(sizes_of(s, {"cluster attribute": archives.Options(structure=structure), "columns": EMPTY}), SIZES)


@query("estimate_error_lineitem")
def estimate_error_lineitem(spark, sf_dir):
    """Bits that the counts of a learned network promise, and the bits its codes have."""
    s = Subject(table(spark, sf_dir, "lineitem"))
    archive = s.archive()
    net = archive.network
    families = list(net.structure.parents.items())
    counted = sum(family_bits(s.spec.images(s.wide), s.spec, families, with_model=False))
    low = sum(max(0, a.depth - CELL_BITS) for a in s.spec.attributes if a.numeric) * s.rows
    actual = s.bytes(archive)["code_bits"]
    return spark.createDataFrame([(float(counted + low), float(actual), float(counted + low) / max(actual, 1) - 1)], "estimated_bits double, code_bits double, relative_error double")


@query("entropy_bound_lineitem", CODES_SQL + """, h AS (SELECT sum(n) AS n, sum(n) * log2(sum(n)) - sum(n * log2(n)) AS joint FROM codes)
SELECT round(joint, 2) AS entropy_bits, (SELECT sum(n * nbits) FROM codes)::BIGINT AS code_bits, round(joint + 4 * n + 32 * 3 * 7, 2) AS bound_bits, (SELECT sum(n * nbits) FROM codes) <= joint + 4 * n + 32 * 3 * 7 AS within FROM h""")
def entropy_bound_lineitem(spark, sf_dir):
    """Code bits of three attributes against their joint entropy, four bits a row, and the model's numbers."""
    c = short_codes(spark, sf_dir)
    n = F.col("n").cast("double")
    r = c.agg(F.sum("n").alias("rows"), (F.sum(n) * F.log2(F.sum(n)) - F.sum(n * F.log2(n))).alias("joint"), F.sum(F.col("n") * F.col("nbits")).alias("code_bits"))
    bound = F.col("joint") + 4 * F.col("rows") + 32 * len(NODES) * 7
    return r.select(F.round("joint", 2).alias("entropy_bits"), "code_bits", F.round(bound, 2).alias("bound_bits"), (F.col("code_bits") <= bound).alias("within"))


@query("access_cost_orders")
def access_cost_orders(spark, sf_dir):
    """What a look-up of a few rows touches: blocks read and codes decoded, against all of them."""
    s = Subject(table(spark, sf_dir, "orders"))
    archive = s.archive()
    blocks = archive.blocks(spark).select("block_id", "nrows", F.octet_length("payload").alias("bytes"), F.ascii(F.substring("offsets", 1, 1).cast("string")).alias("every")).collect()
    rows = []
    for asked in (1, 10, 100):
        places = [(blocks[i % len(blocks)], (i * 97) % blocks[i % len(blocks)]["nrows"]) for i in range(asked)]
        runs = {(b["block_id"], at // archives.INDEX_EVERY) for b, at in places}
        touched = {b["block_id"]: b["bytes"] for b, _ in places}
        rows.append((asked, len(touched), len(blocks), sum(touched.values()) / sum(b["bytes"] for b in blocks), len(runs) * archives.INDEX_EVERY, s.rows))
    return spark.createDataFrame(rows, "asked long, blocks_read long, blocks long, share_of_bytes double, codes_decoded long, codes long")


@query("archive_vs_gzip_lineitem")
def archive_vs_gzip_lineitem(spark, sf_dir):
    """Codes, index and model of all columns together, against compressed text and fixed-width codes."""
    s = Subject(table(spark, sf_dir, "lineitem"))
    domain = sum(r["bits"] for r in baselines.domain_code_bits(s.df, s.df.columns).collect()) * s.rows / 8
    return spark.createDataFrame([(s.total(s.archive()), baselines.universal_size(s.df), int(domain), s.raw)], "archive_bytes long, gzip_bytes long, domain_code_bytes long, raw_bytes long")
