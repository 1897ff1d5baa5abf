"""Archives under several options made in the same scans are those that are made one by one."""

import numpy as np

from relcodec import archive, network
from relcodec.network import Structure
from relcodec.plans import studies
from relcodec.sources.tables import star

SF = "/root/testdata/sf0.001"


def jobs(spark, call):
    """What a call gives, and how many times Spark ran over tables for it."""
    spark.sparkContext.setJobGroup("counted", "")
    try:
        out = call()
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    return out, len(spark.sparkContext.statusTracker().getJobIdsForGroup("counted"))


def test_archives_made_together_have_the_sizes_of_single_ones(spark):
    s = studies.Subject(star(spark, SF))
    options = {f"sample {i}": archive.Options(seed=i) for i in range(2)} | {score: archive.Options(score=score, keys=False) for score in ("mdl_scaled", "nll")}
    options["random"] = archive.Options(structure=Structure.random(s.spec.names, 0))
    together, runs = jobs(spark, lambda: studies.sizes_of(s, options))
    for (name, bits, model, ratio), o in zip(together, options.values(), strict=True):
        size = s.bytes(s.archive(o))
        assert (bits, model, ratio) == (size["code_bits"] / s.rows, size["model"], (size["codes"] + size["index"] + size["model"]) / s.raw), name
    _, fewer = jobs(spark, lambda: studies.sizes_of(s, {"sample 0": options["sample 0"]}))
    assert runs <= fewer + 2 * len(options)


def test_budget_is_kept_without_counting_what_goes_over_it_by_far(spark, monkeypatch):
    rng = np.random.default_rng(0)
    df = spark.createDataFrame([(int(a), int(b), int(c), int(a) % 7) for a, b, c in rng.integers(0, 200, (60_000, 3))], "a long, b long, c long, d long").repartition(3)
    spec = archive.infer_spec(df)
    images = spec.images(df)
    s = Structure.from_edges(["a", "b", "c", "d"], [("a", "c"), ("b", "c"), ("a", "d")])
    counted = []
    cells = network.cells
    monkeypatch.setattr(network, "cells", lambda i, p, f, drawn=frozenset(): counted.append([x for k, x in enumerate(f) if k not in drawn]) or cells(i, p, f, drawn))
    # c has about 60,000 cells, d about 200: over a budget of 20,000 c goes, without a full count of its cells.
    net = network.fit_parameters(images, spec, s, max_cells=20_000)
    assert net.structure.parents == {"a": (), "b": (), "c": (), "d": ("a",)} and not any(x[0] == "c" and x[1] for f in counted for x in f)
    # Near the budget they are counted.
    exact = images.select("a", "b", "c").distinct().count() + images.select("a", "d").distinct().count() + 400
    for budget, parents in ((exact, ("a", "b")), (exact - 1, ())):
        assert network.fit_parameters(images, spec, s, max_cells=budget).structure.parents["c"] == parents


def test_packed_codes_are_the_bits(spark):
    rng = np.random.default_rng(1)
    from relcodec.coder import Encoder, put_uniform

    for n in (0, 1, 500):
        enc = Encoder(n)
        for bits in (0, 3, 40, 62):
            put_uniform(enc, rng.integers(0, 1 << bits, n), bits)
        enc.put(rng.integers(0, 100, n), rng.integers(101, 60_000, n))
        bits, sizes = enc.codes()
        payload, same = enc.packed()
        assert payload == np.packbits(bits).tobytes() and (sizes == same).all()


def test_five_samples_of_one_scan_are_the_single_ones(spark):
    s = studies.Subject(star(spark, SF))
    images = s.spec.images(s.wide)
    found = archive.samples_random(images, {seed: 500 for seed in range(5)}, s.rows)
    for seed, rows in found.items():
        assert [tuple(r)[: len(images.columns)] for r in rows] == [tuple(r) for r in archive.sample_random(images, 500, seed).collect()], seed
    # A wrong number of rows makes no sample smaller.
    assert len(archive.samples_random(images, {0: 500}, 100 * s.rows)[0]) == 500
