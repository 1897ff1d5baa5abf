"""Sizes of what archives are compared with, against plainer ways to reckon them."""

import numpy as np

from relcodec import baselines


def test_prefix_codes_by_how_often_counts_occur():
    rng = np.random.default_rng(0)
    for size in (1, 2, 3, 5, 17, 200):
        for top in (1, 3, 1000):
            counts = dict(enumerate(rng.integers(1, top + 1, size).tolist()))
            lengths = baselines.huffman_lengths(counts)
            often = [(n, 1) for n in counts.values()]
            some, many = np.unique(list(counts.values()), return_counts=True)
            want = sum(n * lengths[k] for k, n in counts.items())
            assert baselines.huffman_cost(often) == baselines.huffman_cost(zip(some.tolist(), many.tolist(), strict=True)) == want
    assert baselines.huffman_cost([]) == 0


def test_prefix_codes_of_many_values(spark):
    # A code per value was made anew for each value before: 20,000 of them never ended.
    df = spark.range(20_000).selectExpr("id as key", "cast(id % 7 as string) as a", "case when id % 11 = 0 then null else id % 5 end as b")
    counts = {k: 1 for k in range(20_000)}
    assert baselines.huffman_bits(df, "key") == sum(baselines.huffman_lengths(counts).values())
    groups = {}
    for r in df.collect():
        group = groups.setdefault(r["b"], {})
        group[r["a"]] = group.get(r["a"], 0) + 1
    want = 0
    for group in groups.values():
        lengths = baselines.huffman_lengths(group)
        want += sum(n * lengths[k] for k, n in group.items())
    assert baselines.huffman_bits(df, "a", ("b",)) == want
    assert baselines.huffman_bits(df.limit(0), "a") == baselines.huffman_bits(df.limit(0), "a", ("b",)) == 0


def test_representative_rows_by_hand(spark):
    import datetime
    import math

    from relcodec.schema import infer_spec

    # Ties between groups went to whichever came first out of a shuffle before.
    rows = [(i, None if i % 13 == 0 else float(i % 90) / 4, "xyz"[i % 3], datetime.datetime(2020, 1, 1 + i % 9)) for i in range(900)]
    df = spark.createDataFrame(rows, "id long, x double, s string, t timestamp").repartition(5, "id")
    spec = infer_spec(df).with_tolerance_pct(10.0, ["id", "x"])
    found = set()
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for parts in ("1", "3", "7"):
            spark.conf.set("spark.sql.shuffle.partitions", parts)
            found.add(baselines.representative_rows(df, spec))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert len(found) == 1
    assert baselines.representative_rows(df.limit(0), spec) == (0.0, 0)
    # With one round the representatives are given rows, so all can be reckoned by hand.
    bits, _ = baselines.representative_rows(df, spec, k=900, rounds=1)
    assert bits == 900 * (math.log2(900) + 4)
    near = lambda a, b, t: a is None and b is None or a is not None and b is not None and abs(a - b) <= t
    one = df.selectExpr("*", "xxhash64(0, id, x, s, t) as h").orderBy("h").limit(1).collect()[0]
    sizes = {r["attribute"]: r["bits"] for r in baselines.domain_code_bits(df, df.columns).collect()}
    want = 900 * (1 + 4)
    for i, x, s, t in rows:
        want += sizes["id"] * (not near(i, one["id"], spec["id"].tolerance)) + sizes["x"] * (not near(x, one["x"], spec["x"].tolerance))
        want += sizes["s"] * (s != one["s"]) + sizes["t"] * (t != one["t"])
    assert baselines.representative_rows(df, spec, k=1, rounds=1)[0] == want


def test_text_sizes_are_those_of_each_group_alone(spark):
    import zlib

    df = spark.range(3000).coalesce(1).selectExpr("id", "case when id % 3 = 0 then null else concat('t', id % 17) end as t")
    rows = df.collect()
    texts = [[f"{r['id']},{r['t'] or ''}" for r in rows], [str(r["id"]) for r in rows], [r["t"] or "" for r in rows]]
    plain = []
    for lines in texts:
        squeeze = zlib.compressobj(6, zlib.DEFLATED, 31)
        plain.append(len(squeeze.compress(("\n".join(lines) + "\n").encode())) + len(squeeze.flush()))
    assert baselines.text_sizes(df, [["id", "t"], ["id"], ["t"]]) == plain
    assert (baselines.universal_size(df), baselines.gzip_columns(df)) == (plain[0], plain[1] + plain[2])
    assert baselines.universal_size(df.limit(0)) == 0


def test_columns_are_counted_in_one_scan(spark):
    import math

    # Each column was grouped by itself before.
    df = spark.range(4000).selectExpr(*[f"id % {k} as a{k}" for k in range(1, 9)], "case when id % 3 = 0 then null else concat('t', id % 50) end as t", "case when id % 2 = 0 then double('NaN') else id end as x", "id")
    columns = df.columns
    spark.sparkContext.setJobGroup("columns", "")
    try:
        bits = baselines.column_huffman_delta_bits(df, columns)
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("columns")) <= 4
    assert bits == sum(baselines.huffman_bits(df, c) for c in columns) - 4000 * (math.log2(4000) - 2)
    found = {r["attribute"]: (r["distinct_values"], r["bits"]) for r in baselines.domain_code_bits(df, columns).collect()}
    assert found == {c: (n, math.ceil(math.log2(n))) for c, n in ((c, df.select(c).distinct().count()) for c in columns)}
    assert baselines.domain_code_bits(df.limit(0), columns).count() == 0


def odd_table(spark):
    """Values of all types, with NULLs, odd numbers, repeated and rare ones."""
    return spark.range(5000).selectExpr(
        "id", "cast(id % 13 as double) / 8 as x", "case when id % 5 = 0 then null else id * 37 % 1000 end as n", "case when id % 7 = 0 then double('NaN') when id % 11 = 0 then 0d else -0d end as odd",
        "concat('é', id % 60) as s", "cast(null as string) as none", "timestamp_micros(id * 1000003) as t", "date_from_unix_date(cast(id % 40 as int)) as d", "cast(id % 90 as decimal(9, 2)) as m",
        "cast(id % 90 as decimal(30, 2)) as wide", "id % 2 = 0 as flag", "cast(id as float) / 3 as f", "cast(id % 3 as string) as `a.b`", "cast(concat('b', id % 4) as binary) as raw")


def test_stored_tables_have_the_baselines_of_plain_ones(spark):
    from relcodec import measures
    from relcodec.plans import studies
    from relcodec.schema import infer_spec

    s = studies.Subject(odd_table(spark).repartition(4, "id"), texts=True)
    assert s.stored.openable() and s.stored.df.exceptAll(s.df).count() == 0
    assert s.raw == measures.raw_bytes(s.df)
    assert baselines.how_often(s.stored, s.df.columns).keys() == set(s.df.columns)
    assert {c: sorted(x) for c, x in baselines.how_often(s.stored, s.df.columns).items()} == {c: sorted(x) for c, x in baselines.how_often(s.df, s.df.columns).items()}
    one = studies.Subject(odd_table(spark).coalesce(1), texts=True)
    assert baselines.text_sizes(one.stored, [one.df.columns, ["x"], ["t", "s"]]) == baselines.text_sizes(one.df.coalesce(1), [one.df.columns, ["x"], ["t", "s"]])
    plain = one.df.drop("raw")
    near = infer_spec(plain).with_tolerance_pct(1.0)
    assert baselines.representative_rows(one.stored, near) == baselines.representative_rows(plain.coalesce(1), near)
    assert s.plain_spec() == infer_spec(s.df)
    spec = s.spec
    names = [a.name for a in spec.attributes if a.kind == "categorical"]
    own = {c: tuple(names[max(0, i - 2): i]) for i, c in enumerate(names)}
    images, again = s.images_under([spec, spec.with_tolerance_pct(5.0)])
    assert baselines.network_huffman_bits(images, own, spec) == baselines.network_huffman_bits(s.wide, own)
    assert again.df.exceptAll(spec.with_tolerance_pct(5.0).images(s.wide)).count() == 0


def test_points_keep_ranks(monkeypatch):
    import pyarrow as pa

    from relcodec.baselines import held

    monkeypatch.setattr(held, "POINTS", 50)
    rng = np.random.default_rng(0)
    rep = np.sort(rng.integers(0, 3, 6000)).astype(np.int32)
    value, n = rng.permutation(6000), rng.integers(1, 4, 6000)
    # One value is as frequent as a third of its group.
    n[100] = 1000
    table = pa.table({"rep": rep, "value": value, "n": n})
    few = held.points(table)
    assert few.num_rows < 3 * 3 * 50 and sum(few["n"].to_pylist()) == n.sum()
    for r in range(3):
        full = np.repeat(value[rep == r], n[rep == r])
        mine = [np.array(few[c])[np.array(few["rep"]) == r] for c in ("value", "n")]
        for share in (0.1, 0.37, 0.5, 0.9):
            rank = int(np.ceil(share * len(full)))
            found = mine[0][np.searchsorted(np.cumsum(mine[1]), rank)]
            assert (full < found).sum() - len(full) * 2 / 50 < rank <= (full <= found).sum() + len(full) * 2 / 50


def test_images_made_in_tasks_are_those_of_spark(spark):
    from relcodec.plans import studies

    table = odd_table(spark).select("id", "n", "x", "s", "m", "flag", "odd", "none", "d", "`a.b`").selectExpr("*", "case when id % 3 = 0 then null when id % 100 = 1 then 'No#x' else concat('No#', id) end as name", "id / 100d as cents")
    s = studies.Subject(table.repartition(3, "id"), texts=True)
    assert [c[2] for c in s.expansion.columns if c[0] in ("s", "name")] == ["template", "template"] and {a.kind for a in s.spec.attributes} == {"categorical", "integer", "decimal"}
    specs = [s.spec, s.spec.with_tolerance_pct(1.0)]
    made = studies.derived(s.stored, s.expansion, specs)
    written = [studies.Stored(studies.written(spec.images(s.wide))) for spec in specs]
    for spec, own, plain in zip(specs, made, written, strict=True):
        rows = own.mapInArrow(lambda batches: batches, spec.image_schema())
        assert rows.exceptAll(plain.df).count() == 0 and plain.df.exceptAll(rows).count() == 0 and rows.count() == s.rows
        drawn = studies.archives.samples_random(own, {0: 300, 1: 200}, s.rows)
        assert [len(x) for x in drawn.values()] == [300, 200] and set(drawn[0][0].asDict()) >= set(spec.names)
    # A type whose images only Spark makes: one scratch table for all specs.
    timed = studies.Subject(odd_table(spark).select("id", "t", "s"), texts=True)
    assert studies.derived(timed.stored, timed.expansion, [timed.spec]) is None
    assert timed.images_under([timed.spec])[0].df.exceptAll(timed.spec.images(timed.wide)).count() == 0
