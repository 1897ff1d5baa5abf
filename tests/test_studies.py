"""Thresholds of the studies that have no SQL, and faults that rows with SQL would show."""

from relcodec import archive, baselines, measures
from relcodec.network import Structure, near_functions
from relcodec.plans import studies
from relcodec.queries import QUERIES
from relcodec.schema import infer_spec
from relcodec.sources.tables import scratch, star, table

SF = "/root/testdata/sf0.001"


def by(rows, key):
    return {r[key]: r for r in rows}


def test_learned_archives_of_the_star_view(spark):
    s = studies.Subject(star(spark, SF))
    learned = s.archive()
    sizes = by(studies.sizes_of(s, {"columns": studies.EMPTY, "other sample": archive.Options(seed=3)}), 0)
    ratio = s.total(learned) / s.raw
    assert ratio < 0.7 * sizes["columns"][3] and abs(sizes["other sample"][3] / ratio - 1) < 0.05
    assert ratio < 0.5 * baselines.universal_size(s.df) / s.raw
    # A key's attributes hang on it, or it on them.
    edges = {frozenset(e) for e in learned.network.structure.edges}
    assert any({"o_custkey", x} in map(set, edges) for x in s.spec.names if x.startswith("c_name"))


def test_archive_beats_text_and_the_representative_rows(spark):
    rows = {m: b for m, b, _ in studies.treatments(studies.Subject(table(spark, SF, "customer")))}
    assert {"gzip", "gzip of columns", "domain code", "representative rows and gzip, lossy", "archive of columns", "archive", "archive, lossy"} <= set(rows)
    assert rows["archive, lossy"] < rows["archive"]


def test_estimates_are_near_the_codes(spark):
    r = QUERIES["estimate_error_lineitem"](spark, SF).first()
    assert abs(r["relative_error"]) < 0.05


def test_near_functions_of_a_sample():
    import numpy as np

    rng = np.random.default_rng(0)
    key = rng.integers(0, 900, 2000)
    symbols = {"key": key, "name": key * 7 % 901, "free": rng.integers(0, 5, 2000)}
    assert set(near_functions(symbols, {"key": 900, "name": 901, "free": 5})) == {("key", "name"), ("name", "key")}


def test_random_access_shows_a_wrong_place(spark):
    df = table(spark, SF, "orders").orderBy("o_orderkey")
    path = scratch(spark)
    made = archive.compress(df, path, archive.Options(structure="empty"))
    first = made.blocks(spark).agg({"block_id": "min"}).first()[0]
    keys = [r["o_orderkey"] for r in df.limit(60).collect()]
    got = sorted(r["o_orderkey"] for r in archive.lookup(spark, path, [(first, i) for i in (0, 17, 59)]).collect())
    assert got == [keys[0], keys[17], keys[59]] and got != [keys[1], keys[17], keys[59]]


def test_a_value_outside_the_fitted_range_is_an_error(spark):
    import pytest

    df = spark.range(5000).selectExpr("id * 3 as v")
    images, network, _ = archive.fit(df, archive.Options(structure="empty"), infer_spec(df))
    strange = network.spec.images(spark.range(1).selectExpr("cast(-5 as long) as v"))
    with pytest.raises(Exception, match="not in the attribute's domain"):
        archive.encode(strange, network).collect()


def test_raw_bytes_of_text(spark):
    assert measures.raw_bytes(table(spark, SF, "region")) == QUERIES["csv_raw_bytes"](spark, SF).first()["bytes"]


def test_hand_made_structure_orders_itself():
    s = Structure.from_edges(["a", "b", "c"], [("c", "a"), ("b", "c")])
    assert s.coding_order == ["b", "c", "a"] and s.depends_on("a") == {"b", "c"}
