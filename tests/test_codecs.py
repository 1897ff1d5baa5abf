"""Arrays that the probe of a codec does not foresee."""

import random

from relcodec import archive
from relcodec.sources.tables import scratch


def test_arrays_past_the_probe_come_back(spark):
    rng = random.Random(1)
    vector = lambda n: [rng.randrange(-511, 511) / 512 for _ in range(n)]
    rows = [(i, vector(3), vector(3), [i, 1]) for i in range(240)]
    odd = [None, [], vector(2), vector(5), [0.5, None, 0.25], [0.1, 0.7, -0.0]]
    rows += [(240 + i, v, v if i < 5 else [0.1, 1e-300, 1 / 3], [2**53 + 1, 2**62 + 1]) for i, v in enumerate(odd)]
    df = spark.createDataFrame(rows, "i long, f array<float>, d array<double>, n array<bigint>").coalesce(1)
    path = scratch(spark)
    archive.compress(df, path, archive.Options(structure="empty"))
    assert sorted(map(str, archive.decompress(spark, path).collect())) == sorted(map(str, df.collect()))
