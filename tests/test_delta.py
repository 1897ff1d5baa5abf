"""Delta-coded blocks with few distinct codes."""

import numpy as np
import pytest

from relcodec import archive as archives


def test_repeats():
    bits = np.array([0, 1, 1] * 9 + [0, 1, 0, 0, 1, 1], np.uint8)
    pattern = np.array([0, 1, 1], np.uint8)
    assert archives.repeats(bits, 0, pattern, 99) == 9
    assert archives.repeats(bits, 0, pattern, 4) == 4
    assert archives.repeats(bits, 27, pattern, 99) == 0
    assert archives.repeats(bits, 30, pattern, 99) == 1
    assert archives.repeats(bits, len(bits), pattern, 99) == 0


@pytest.mark.parametrize("delta_rows", [1, 7, 2000])
def test_equal_codes_are_decoded_once(spark, delta_rows):
    df = spark.createDataFrame([(k % 3, "ab"[k % 7 == 0]) for k in range(delta_rows)], "n int, s string").coalesce(1)
    images, net, _ = archives.fit(df, archives.Options(structure="empty"))
    block = archives.encode(images, net, archives.Options(structure="empty", delta=True)).first()
    calls = []

    class Counting:
        def decode(self, *args):
            calls.append(args)
            return net.decode(*args)

    columns = archives.delta_decode(Counting(), bytes(block["payload"]), block["nbits"], block["nrows"])
    got = sorted(zip(columns[net.spec.names[0]].tolist(), columns[net.spec.names[1]].tolist(), strict=True), key=str)
    assert got == sorted(zip(*(archives.unpack(net, bytes(p["payload"]), bytes(p["offsets"]), p["nrows"], p["nbits"], False)[n].tolist() for p in [archives.encode(images, net, archives.Options(structure="empty")).first()] for n in net.spec.names), strict=True), key=str)
    assert len(calls) <= 6
