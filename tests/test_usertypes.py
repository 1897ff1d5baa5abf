"""Types given by walks and models, coded end to end."""

import numpy as np
import pytest

from relcodec import archive
from relcodec.coder import Decoder, Encoder
from relcodec.schema import infer_spec
from relcodec.usertypes import Sequence, StepTree, WalkCoder


def test_step_tree_codes_near_its_entropy():
    rng = np.random.default_rng(0)
    steps = rng.geometric(0.1, 4000)
    coder = WalkCoder(StepTree.finish([{"stops": len(steps), "goes": int((steps - 1).sum())}]))
    values = np.array([*map(str, steps), None], object)[:-1]
    enc = Encoder(len(values))
    coder.encode(enc, values, np.arange(len(values)))
    bits, sizes = enc.codes()
    p = len(steps) / steps.sum()
    information = -(np.log2(p) + (steps - 1) * np.log2(1 - p))
    assert (sizes <= information + 2.1).all() and abs(sizes.sum() - information.sum()) < 2.1 * len(steps)
    dec = Decoder(np.packbits(bits).tobytes(), np.cumsum(sizes) - sizes)
    assert coder.decode(dec, np.arange(len(values)), None).tolist() == values.tolist()
    assert (dec.ends() == np.cumsum(sizes)).all()


def test_user_types_in_an_archive(spark, tmp_path):
    rows = [(i, None if i % 50 == 3 else i * i % 23 + 1, None if i % 40 == 7 else "ACGT"[i % 4] * (i % 5) + "GA" * (i % 3)) for i in range(400)]
    df = spark.createDataFrame(rows, "id int, steps int, genome string")
    spec = infer_spec(df).with_model("steps", StepTree).with_model("genome", Sequence)
    made = archive.compress(df, str(tmp_path / "a"), archive.Options(), spec)
    assert sorted(map(tuple, archive.decompress(spark, str(tmp_path / "a")).collect())) == rows
    assert {n.attribute.name for n in made.network.nodes if n.bits > 0} >= {"steps", "genome"}
    assert [tuple(r) for r in archive.decompress(spark, str(tmp_path / "a"), ["genome"]).filter("genome = 'GA'").limit(1).collect()] == [("GA",)]


def test_a_value_without_a_branch_is_an_error(spark):
    coder = WalkCoder(Sequence.finish([{"a": "", "b": "A", "n": 1}, {"a": "A", "b": "", "n": 1}]))
    with pytest.raises(ValueError, match="no branch"):
        coder.encode(Encoder(1), np.array(["AZ", None], object)[:1], np.arange(1))
