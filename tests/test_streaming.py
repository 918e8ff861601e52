"""Streams that stop and start again."""

from sketchfit.operators.maps import identity_map
from sketchfit.sources.tables import event_stream, load_table
from sketchfit.streaming import queries
from sketchfit.streaming.sketches import SketchStore, drained


def rows(spark, lo, hi):
    return spark.range(lo, hi).selectExpr("array(cast(id as double)) as features")


def total(store):
    return store.state().first().n


def test_a_new_store_goes_on_from_the_written_total(spark, tmp_path):
    path = f"file://{tmp_path}/totals"
    SketchStore(spark, identity_map(1), path).update(rows(spark, 0, 10), 0)
    again = SketchStore(spark, identity_map(1), path)
    assert total(again) == 10
    again.update(rows(spark, 0, 10), 0)  # the batch that the lost driver had applied
    assert total(again) == 10
    again.update(rows(spark, 10, 15), 1)
    (tmp_path / "totals" / "v2").mkdir()  # a version whose writer was lost
    third = SketchStore(spark, identity_map(1), path)
    assert third.version == 1 and total(third) == 15


def test_a_stream_restarts_with_its_checkpoint(spark, tmp_path):
    source, path = f"file://{tmp_path}/in", f"file://{tmp_path}/totals"
    for lo, hi in ((0, 7), (7, 20)):
        rows(spark, lo, hi).write.mode("append").parquet(source)
        store = SketchStore(spark, identity_map(1), path)
        store.run(spark.readStream.schema("features array<double>").parquet(source))
        assert total(store) == hi


def test_results_of_complete_and_update_streams_are_files(spark, sf):
    e = event_stream(spark, sf).groupBy("event_type").count()
    want = {r.event_type: r["count"] for r in load_table(spark, sf, "events").groupBy("event_type").count().collect()}
    for mode in ("complete", "update"):
        got = drained(e, mode)
        assert got.inputFiles()  # not a table in the driver's memory
        assert {r.event_type: r["count"] for r in got.collect()} == want


def test_a_stream_without_rows_gives_an_empty_result(spark, sf, tmp_path):
    load_table(spark, sf, "events").where("false").write.parquet(f"{tmp_path}/events.parquet")
    for mode in ("append", "complete", "update"):
        e = event_stream(spark, str(tmp_path)).select("event_id") if mode == "append" else event_stream(spark, str(tmp_path)).groupBy("event_type").count()
        assert drained(e, mode).count() == 0


def test_sessions_keep_their_state_off_the_heap(spark, sf, monkeypatch):
    key, seen = "spark.sql.streaming.stateStore.providerClass", []
    before = spark.conf.get(key, None)

    def spy(df, mode):
        seen.append(spark.conf.get(key, None))
        return drained(df, mode)

    monkeypatch.setattr(queries, "drained", spy)
    queries.R.queries["stream_session"](spark, sf).count()
    assert "RocksDB" in seen[0] and spark.conf.get(key, None) == before
