"""Fan-out against a set per row, costs from an event log, formats, functions of one's own."""

import json
import random

import pytest
from pyspark.sql import functions as F

from relanom import cost, extensions, sources, sqlfn, streaming, views


def test_distinct_within_counts_like_a_set(spark):
    draw = random.Random(3)
    rows = [(i, draw.choice([1, 1, 1, 2, None]), draw.choice([5, 6, 7, 8, None]), draw.randrange(40) * 500_000) for i in range(400)]
    got = views.distinct_within(spark.createDataFrame(rows, "id long, u int, m int, us long"), "u", "m", 4, "n")
    assert got.columns == ["id", "u", "m", "us", "n"]
    want = {i: len({m2 for _, u2, m2, t2 in rows if u2 == u and m2 is not None and t - 4_000_000 <= t2 < t}) for i, u, m, t in rows}
    assert {r["id"]: r["n"] for r in got.collect()} == want


def test_distinct_within_empty(spark):
    assert views.distinct_within(spark.createDataFrame([], "u int, m int, us long"), "u", "m", 4, "n").count() == 0


def test_event_log_stages(spark, tmp_path):
    def end(stage, run, wrote, failed=False):
        return json.dumps({"Event": "SparkListenerTaskEnd", "Stage ID": stage, "Task Info": {"Failed": failed}, "Task Metrics": {"Executor Run Time": run, "Peak Execution Memory": run * 2, "Disk Bytes Spilled": 7, "Shuffle Write Metrics": {"Shuffle Bytes Written": wrote}}})

    log = [json.dumps({"Event": "SparkListenerApplicationStart", "App Name": "a"}), end(0, 10, 100), end(0, 30, 50), end(1, 5, 0, True)]
    (tmp_path / "log").write_text("\n".join(log))
    got = {r["stage"]: r for r in cost.stages(spark, str(tmp_path / "log")).collect()}
    assert (got[0]["tasks"], got[0]["run_ms"], got[0]["shuffle_write"], got[0]["spilled"], got[0]["peak_bytes"], got[0]["skew"]) == (2, 40, 150, 14, 60, 1.5)
    assert (got[1]["failed"], got[1]["shuffle_read"]) == (1, 0)


@pytest.mark.parametrize("form", sources.FORMATS)
def test_formats_round_trip(spark, tmp_path, form):
    rows = spark.createDataFrame([(1, "a"), (2, None)], "k long, v string")
    sources.save(rows, str(tmp_path / form), form=form)
    assert sorted(map(tuple, sources.read(spark, str(tmp_path / form), form, "k long, v string").collect())) == [(1, "a"), (2, None)]


def test_text_formats_need_a_schema(spark, tmp_path):
    with pytest.raises(ValueError):
        sources.read(spark, str(tmp_path), "csv")


def test_functions_of_ones_own(spark):
    sqlfn.register(spark)
    assert spark.sql("SELECT * FROM rule_conditions(NULL)").count() == 0
    rows = spark.createDataFrame([(0.1, 0), (0.1, 1), (0.9, 1)], "s double, y int")
    assert rows.agg(sqlfn.group_auroc("s", "y").alias("a")).first()["a"] == 0.75
    assert rows.filter("y = 1").agg(sqlfn.group_auroc("s", "y").alias("a")).first()["a"] is None


def test_aggregators_refuse_unknown(spark):
    e = spark.createDataFrame([("r", 1, 2)], "rel string, src long, dst long")
    h = spark.createDataFrame([(1, [1.0])], "nid long, h array<double>")
    with pytest.raises(ValueError):
        extensions.messages(e, h, 1, "median")
    with pytest.raises(ValueError):
        extensions.messages(e, h, 1, "attention")
    assert extensions.messages(e, h, 1, "sum").first()["m"] == [1.0]


def test_stream_join_drops_repeated_events(spark, tmp_path):
    rows = [(1, 7, "click", "2024-01-01 00:00:00"), (1, 7, "click", "2024-01-01 00:00:00"), (2, 7, "signup", "2024-01-01 00:05:00"), (3, 7, "signup", "2024-01-01 00:30:00"), (4, 8, "signup", "2024-01-01 00:01:00")]
    events = spark.createDataFrame(rows, "event_id long, user_id long, event_type string, t string").select("event_id", F.col("t").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", F.lit(1.0).alias("value"), F.lit("{}").alias("props"))
    events.coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    stream = spark.readStream.schema(streaming.EVENTS).parquet(str(tmp_path / "events.parquet")).withColumn("ts", F.col("ts").cast("timestamp"))
    got = streaming.finished(streaming.joined_logs(stream, 10), "append", spark)
    assert [tuple(r) for r in got.collect()] == [(2, 1)]


@pytest.mark.parametrize("mode", ["append", "complete"])
def test_stream_results_are_files_and_not_rows_of_the_driver(spark, mode):
    events = streaming.source(spark, "/root/testdata/sf0.001")
    got = streaming.finished(events.select("event_id") if mode == "append" else streaming.windows(events, "session"), mode, spark)
    assert got.inputFiles()
    assert got.count() == spark.read.parquet("/root/testdata/sf0.001/events.parquet").count() if mode == "append" else got.count() > 0


def test_stream_without_events_is_an_empty_table(spark, tmp_path):
    (tmp_path / "nothing").mkdir()
    events = spark.readStream.schema(streaming.EVENTS).parquet(str(tmp_path / "nothing"))
    assert streaming.finished(events.select("event_id"), "append", spark).count() == 0


def test_rows_that_tie_for_the_top_give_the_smallest_key(spark, tmp_path):
    from relanom import registry

    rows = [("A", 30.0, 7.0, 5), ("A", 30.0, 9.0, 2), ("A", 10.0, 9.0, 8), ("A", 10.0, None, 1), ("B", 1.0, None, 3)]
    spark.createDataFrame(rows, "l_returnflag string, l_quantity double, l_extendedprice double, l_orderkey long").coalesce(1).write.parquet(str(tmp_path / "lineitem.parquet"))
    got = registry.queries()["agg_conditional"](spark, str(tmp_path)).orderBy("flag").collect()
    assert [(r.flag, r.many, r.top, r.best) for r in got] == [("A", 2, 9.0, 2), ("B", 0, None, None)]
