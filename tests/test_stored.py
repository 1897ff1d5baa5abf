"""Tables whose files tasks read themselves, and codes that are measured but not kept."""

import numpy as np
from pyspark.sql import functions as F

from relcodec import archive, network
from relcodec.codecs import Expansion
from relcodec.network import Structure
from relcodec.plans import studies
from relcodec.schema import infer_spec
from relcodec.sources import stored
from relcodec.sources.tables import star

SF = "/root/testdata/sf0.001"


def odd(spark):
    """Numbers that images don't hold, NULLs, texts of a template and others, many values and one."""
    df = spark.range(0, 20_000, 1, 3).withColumn("r", F.rand(1))
    return df.select(
        "id", (F.col("id") % 7).cast("int").alias("few"), F.when(F.col("id") % 5 > 0, F.col("id") % 300).alias("holes"), F.lit(None).cast("string").alias("none"),
        F.when(F.col("id") == 9, float("nan")).otherwise(F.col("id") % 9 / 4).alias("nan"), F.when(F.col("id") == 19_999, -0.0).otherwise(F.col("id") % 2 * 1.0).alias("zero"),
        (F.col("id") % 50 / 100).alias("cents"), "r", F.when(F.col("r") < 0.01, "-7 #").otherwise(F.format_string("No#%03d", F.col("id") % 900)).alias("name"),
        F.format_string("é %d", F.col("id") % 40).alias("text"), F.lit("x").alias("`a`.b"), (F.col("id") % 3).cast("decimal(9,2)").alias("money"), F.timestamp_seconds(F.col("id") % 11).alias("at"), (F.col("id") % 2 == 0).alias("flag"))


def test_kinds_found_through_values_are_those_of_all_rows(spark, monkeypatch):
    # 100: most columns are looked at in full.
    for table, most in ((odd(spark), stored.MOST_VALUES), (odd(spark), 100), (star(spark, SF), stored.MOST_VALUES), (odd(spark).limit(0), stored.MOST_VALUES)):
        df = studies.written(table)
        expansion = Expansion.infer(df)
        monkeypatch.setattr(stored, "MOST_VALUES", most)
        assert stored.stored_spec(df, expansion, df.count()) == infer_spec(expansion.expand(df))


def test_tasks_read_the_files_themselves(spark, tmp_path):
    path = f"{tmp_path}/with space % and é"
    odd(spark).select("id", "few", "holes", "name", "r").write.option("maxRecordsPerFile", 1000).parquet(path)
    df = spark.read.parquet(path)
    spec = infer_spec(df)
    images = studies.written(spec.images(df))
    many = stored.Stored(df)
    assert len(many.files) >= 20 and many.openable() and many.mapInArrow(lambda x: x, df.schema).exceptAll(df).count() == 0
    families = [("few", ("holes",)), ("name", ()), ("id", ("few",))]
    own, spark_read = (network.cells(x, spec, families) for x in (stored.Stored(images), images))
    assert "Scan parquet" in spark_read._jdf.queryExecution().toString() and "Scan parquet" not in own._jdf.queryExecution().toString()
    assert sorted(own.collect()) == sorted(spark_read.collect())
    # Where pyarrow can't find the files, Spark reads them.
    lost = stored.Stored(images)
    lost.files = ["nowhere://x/y"]
    assert not lost.openable() and sorted(network.cells(lost, spec, families).collect()) == sorted(spark_read.collect())


def test_sizes_are_those_of_the_codes(spark, monkeypatch):
    df = odd(spark).drop("`a`.b")
    expansion = Expansion.infer(df)
    wide = expansion.expand(df)
    spec = infer_spec(wide)
    images = spec.images(wide)
    names = spec.names
    structures = [Structure.empty(names), Structure.from_edges(names, [("few", "holes"), ("holes", "cents"), ("id", "r"), ("nan", "text")]), Structure.random(names, 3), Structure.empty(names)]
    nets = network.fit_networks(images, spec, structures)
    rows = images.filter("id < 5000").coalesce(1).toArrow()
    columns = {a.name: network.image_values(rows.column(a.name), a) for a in spec.attributes}
    # Rows of the second kind are unlike those that the network saw: symbols escape.
    nets += network.fit_networks(images.filter("id < 3"), spec, structures[:3])
    calls = []
    encode = network.Node.encode
    monkeypatch.setattr(network.Node, "encode", lambda node, *x: calls.append(node) or encode(node, *x))
    sizes = network.code_sizes([n.nodes for n in nets], columns, rows.num_rows)
    # Nodes of several networks are looked at once, but for texts, whose codes depend on the state.
    plain = [id(node) for node in calls if not node.chars]
    assert len(plain) == len(set(plain)) < sum(not node.chars for n in nets for node in n.nodes)
    for net, own in zip(nets, sizes, strict=True):
        assert (own == net.encoder(columns, rows.num_rows).packed()[1]).all()


def test_networks_with_the_same_nodes_are_coded_once(spark):
    s = studies.Subject(star(spark, SF))
    delta = archive.Options(structure="empty", delta=True)
    options = {"one": studies.EMPTY, "again": studies.EMPTY, "sorted": delta, "random": archive.Options(structure=Structure.random(s.spec.names, 0))}
    found = {name: rest for name, *rest in studies.sizes_of(s, options)}
    assert found["one"] == found["again"] != found["random"]
    for name, o in options.items():
        size = s.bytes(s.archive(o))
        assert found[name] == [size["code_bits"] / s.rows, size["model"], (size["codes"] + size["index"] + size["model"]) / s.raw], name


def test_last_cell_of_a_state_is_found_at_once():
    from relcodec.interval import HALF, STATE_BITS, WHOLE, finish, shared_bits

    rng = np.random.default_rng(0)
    low = np.concatenate([rng.integers(0, WHOLE - 1, 2000), HALF - (np.int64(1) << rng.integers(0, 47, 2000)), [0, 0, HALF]])
    high = np.concatenate([np.minimum(low[:2000] + (np.int64(1) << rng.integers(0, 48, 2000)), WHOLE), HALF + (np.int64(1) << rng.integers(0, 48, 2000)), [WHOLE, 1, WHOLE]])
    k, value = finish(low, high)
    for lo, hi, bits, m, same in zip(low.tolist(), high.tolist(), k.tolist(), value.tolist(), shared_bits(low, high).tolist(), strict=True):
        cells = ((n, -(-lo // (WHOLE >> n))) for n in range(STATE_BITS + 1))
        assert (bits, m) == next((n, m) for n, m in cells if (m + 1) * (WHOLE >> n) <= hi)
        assert same == STATE_BITS - (lo ^ (hi - 1)).bit_length()
