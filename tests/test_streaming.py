from pyspark.sql import functions as F

from nudgegraph.sources.networks import table
from nudgegraph.streaming import online


def test_late_rows_are_dropped(spark, sf):
    events = table(spark, sf, "events")
    path = online.split_by_time(spark, events, 3, late=True)
    rows, reports = online.drain(online.tumbling(online.stream_actions(spark, path), "1 hour"), "update")
    kept = online.latest(rows, "start").agg(F.sum("n")).first()[0]
    first = events.agg(F.min("ts")).first()[0]
    late = events.where(F.col("ts") < F.lit(first) + F.expr("interval 1 hour")).count()
    assert late > 0 and kept == events.count() - late and reports


def test_batch_and_stream_agree(spark, sf):
    events = table(spark, sf, "events")
    path = online.split_by_time(spark, events, 2)
    rows, _ = online.drain(online.first_seen(online.stream_actions(spark, path)))
    batch = online.first_actions(online.as_actions(spark.read.schema(online.ACTION).parquet(path)))
    assert rows.exceptAll(batch.select(rows.columns)).isEmpty() and rows.count() == batch.count()


def test_pairs_are_forgotten_after_a_while(spark, tmp_path):
    import datetime as dt

    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    at = lambda hours: dt.datetime(2024, 1, 1) + dt.timedelta(hours=hours)
    # one file a batch: the same pair at once, soon, and long after the watermark passed its time
    for i, hours in enumerate((0, 1, 30, 31, 60)):
        spark.createDataFrame([(i, at(hours), 1 if hours not in (30, 31) else 2, "buy", 1.0, "{}")], schema).coalesce(1).write.mode("append").parquet(str(tmp_path))
    found = {}
    for keep in (None, 3600):
        rows, _ = online.drain(online.first_seen(online.stream_actions(spark, str(tmp_path), "1 hour"), keep))
        found[keep] = sorted((r.actor, r.ts) for r in rows.collect())
    assert found[None] == [(1, at(0)), (2, at(30))] and (1, at(0)) in found[3600] and (1, at(60)) in found[3600]


def test_join_meets_slices_of_time_only(spark, sf):
    """The join's key has the slice of time; windows of hours and of days give what the plain condition gives."""
    from pyspark.sql import functions as F

    actions = online.as_actions(table(spark, sf, "events"))
    for window in ("6 hours", "3 days"):
        met = online.hits(actions, actions, window)
        assert "slice_u" in met._jdf.queryExecution().optimizedPlan().toString()
        u, v = actions.toDF("ts_u", "src", "action"), actions.toDF("at", "dst", "action")
        plain = u.join(v, "action").where(F.expr(f"src <> dst and at > ts_u and at <= ts_u + interval {window}")).select(met.columns)
        assert met.exceptAll(plain).isEmpty() and plain.exceptAll(met).isEmpty() and not met.isEmpty()


def test_first_rows_without_a_call_for_each_pair(spark, tmp_path):
    """Several rows of a pair in one trigger give the earliest; a later trigger adds none."""
    import datetime as dt

    at = lambda hours: dt.datetime(2024, 1, 1) + dt.timedelta(hours=hours)
    for batch in (((5, 1), (3, 1), (4, 2), (9, None)), ((6, 1), (7, 2), (8, 3), (10, None))):
        rows = [(i, at(i), actor, "buy", 1.0, "{}") for i, actor in batch]
        spark.createDataFrame(rows, online.ACTION).coalesce(1).write.mode("append").parquet(str(tmp_path))
    seen = online.first_seen(online.stream_actions(spark, str(tmp_path)))
    assert "FlatMapGroups" not in seen._jdf.queryExecution().analyzed().toString()
    rows = online.drain(seen)[0].collect()
    assert sorted((r.actor or 0, r.ts) for r in rows) == [(0, at(9)), (1, at(3)), (2, at(4)), (3, at(8))]
