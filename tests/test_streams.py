"""Sinks of streams."""

from relcodec.streaming.streams import stream_sessions

SF = "/root/testdata/sf0.001"


def test_whole_results_lie_in_files(spark):
    """A result of complete mode is a table in scratch, not rows in the driver's memory."""
    df = stream_sessions(spark, SF)
    assert df.inputFiles() and df.count() > 0
