"""Streams: what they give lies in files of the shared folder, and equals the batch form."""

from bspflow.graphs import table
from bspflow.streaming import streams


def test_rows_of_an_append_stream_are_files(spark, sf):
    got = streams.s_dedup(spark, sf)
    assert got.inputFiles()  # rows kept in the driver's memory have none
    want = table(spark, sf, "events").select("event_id", "user_id")
    assert got.count() == want.count() and not want.exceptAll(got).count()


def test_rows_of_a_complete_stream_are_files_of_its_last_batch(spark, sf):
    got = streams.s_session(spark, sf)
    assert got.inputFiles()
    assert sum(r.n for r in got.collect()) == table(spark, sf, "events").count()
    assert got.select("start_us", "user_id").distinct().count() == got.count()
