"""Streaming forms against batch forms, and the SQL surface."""

from pyspark.sql import functions as F

from stratamatch.operators.effects import stratified_effect
from stratamatch.operators.strata import overlapping, summarize
from stratamatch.plans.spec import UnitSpec
from stratamatch.sources.catalog import READINGS, read_as, write_bucketed, write_partitioned
from stratamatch.sqlapi import grouped_metric, register
from stratamatch.streaming.live import current_effect, join_streams, live_strata, running_counts, running_differences, windowed_traffic

SPEC = UnitSpec("uid", "t", ("x",), ("y",))


def _units(spark):
    return spark.createDataFrame([(i, i % 3 % 2, i % 5, i) for i in range(60)], "uid long, t int, x int, y long")


def test_live_strata_equal_batch(spark, tmp_path):
    units = _units(spark)
    src = str(tmp_path / "in")
    units.where("uid < 30").coalesce(1).write.parquet(src)
    stream = lambda: spark.readStream.schema(units.schema).parquet(src)
    sink, check = str(tmp_path / "cells"), str(tmp_path / "check")
    live_strata(stream(), SPEC, sink, check).awaitTermination()
    units.where("uid >= 30").coalesce(1).write.mode("append").parquet(src)
    live_strata(stream(), SPEC, sink, check).awaitTermination()
    assert len(list((tmp_path / "cells").glob("batch=*"))) == 2
    got = current_effect(spark.read.parquet(sink), SPEC).first()
    assert got == stratified_effect(overlapping(summarize(units, SPEC)), ("y",)).first()


def test_running_counts_in_complete_mode(spark, tmp_path):
    units = _units(spark)
    units.write.parquet(str(tmp_path / "in"))
    q = running_counts(spark.readStream.schema(units.schema).parquet(str(tmp_path / "in")), SPEC).writeStream.outputMode("complete").format("memory").queryName("counts").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("counts").agg(F.sum("n1") + F.sum("n0")).first()[0] == 60


def test_running_differences_end_at_the_batch_result(spark, tmp_path):
    units, seen = _units(spark), {}
    for part in (units.where("uid < 20"), units.where("uid >= 20")):
        part.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        q = running_differences(spark.readStream.schema(units.schema).parquet(str(tmp_path / "in")), SPEC, "y").writeStream.outputMode("update")
        q = q.foreachBatch(lambda df, _: seen.update({r.x: r for r in df.collect()})).option("checkpointLocation", str(tmp_path / "check")).trigger(availableNow=True).start()
        q.awaitTermination()
    for r in summarize(units, SPEC).collect():
        assert (seen[r.x].n1, seen[r.x].n0) == (r.n1, r.n0)
        assert abs(seen[r.x].difference - (r.sum1_y / r.n1 - r.sum0_y / r.n0)) < 1e-9


def _events(spark, rows):
    return spark.createDataFrame(rows, "event_id long, at string, site int").select("event_id", F.col("at").cast("timestamp").alias("ts"), "site")


def test_late_rows_past_the_watermark_are_left_out(spark, tmp_path):
    src = str(tmp_path / "in")
    (tmp_path / "in").mkdir()
    stream = spark.readStream.schema("event_id long, ts timestamp, site int").option("maxFilesPerTrigger", 1).parquet(src)
    batches = [[(1, "2024-01-01 00:10", 1), (2, "2024-01-01 00:20", 1)], [(3, "2024-01-01 09:00", 1)], [(4, "2024-01-01 00:30", 1), (5, "2024-01-01 08:30", 1)], [(6, "2024-01-01 20:00", 1)]]
    counts = {}
    for n, rows in enumerate(batches):
        _events(spark, rows).coalesce(1).write.mode("append").parquet(src)
        q = windowed_traffic(stream, ["site"], late="1 hour").writeStream.outputMode("append").foreachBatch(lambda df, _: counts.update({str(r.start): r.n for r in df.collect()}))
        q.option("checkpointLocation", str(tmp_path / "check")).trigger(availableNow=True).start().awaitTermination()
    assert counts["2024-01-01 00:00:00"] == 2  # the row of 00:30 came after its window had closed
    assert counts["2024-01-01 08:00:00"] == 1


def test_stream_join_equals_batch(spark, tmp_path):
    trips = _events(spark, [(1, "2024-01-01 01:00", 1), (2, "2024-01-01 05:00", 1)])
    readings = _events(spark, [(11, "2024-01-01 00:30", 1), (12, "2024-01-01 00:30", 2), (13, "2024-01-01 06:00", 1)])
    for name, df in (("t", trips), ("r", readings)):
        df.write.parquet(str(tmp_path / name))
    t, r = (spark.readStream.schema(trips.schema).parquet(str(tmp_path / n)) for n in "tr")
    q = join_streams(t, r, "site", "ts").writeStream.format("memory").queryName("joined").trigger(availableNow=True).start()
    q.awaitTermination()
    assert [(x.t_event_id, x.r_event_id) for x in spark.table("joined").collect()] == [(1, 11)]


def test_sources_round_trip(spark, tmp_path, small):
    whole_seconds = F.expr("timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(0, 0, 0, event_id)")
    events = spark.read.parquet(f"{small}/events.parquet").where("event_id < 50").withColumn("ts", whole_seconds)
    for kind in ("csv", "json", "orc"):
        events.write.format(kind).save(str(tmp_path / kind))
        assert sorted(map(tuple, read_as(spark, kind, str(tmp_path / kind), READINGS).collect())) == sorted(map(tuple, events.collect()))
    write_partitioned(events, str(tmp_path / "parts"), ["event_type"], ["ts"])
    assert spark.read.parquet(str(tmp_path / "parts")).count() == 50


def test_database_tables_are_read_in_ranges(spark, tmp_path):
    """Against the embedded database that Spark itself carries."""
    from stratamatch.sources.catalog import read_jdbc

    url = f"jdbc:derby:{tmp_path}/db;create=true"
    rows = [(i, i * 10) for i in range(40)]
    spark.createDataFrame(rows, "K int, V int").write.format("jdbc").options(url=url, dbtable="UNITS_T").save()
    back = read_jdbc(spark, url, "UNITS_T", "K", 0, 40, 4)
    assert back.rdd.getNumPartitions() == 4 and sorted(map(tuple, back.collect())) == rows


def test_bucketed_tables_need_no_exchange(spark):
    units = _units(spark)
    write_bucketed(units, "bucketed_units", 4, ["x"])
    plan = spark.table("bucketed_units").groupBy("x").count()._jdf.queryExecution().executedPlan().toString()
    spark.sql("DROP TABLE bucketed_units")
    assert "Exchange" not in plan


def test_sql_surface(spark):
    import pandas as pd

    register(spark, _units(spark), SPEC)
    assert spark.sql("SELECT count(*) FROM match_matched").first()[0] == 60
    assert spark.sql("SELECT count(*) FROM match_strata").first()[0] == 5
    assert [tuple(r) for r in spark.sql("SELECT * FROM cut_points(0D, 4D, 2)").collect()] == [(1, 0.0, 2.0), (2, 2.0, 4.0)]
    metric = grouped_metric(lambda p: pd.DataFrame({"x": [p.x.iloc[0]], "gap": [p.y[p.t == 1].mean() - p.y[p.t == 0].mean()]}), "x int, gap double")
    assert metric(_units(spark), ["x"]).count() == 5
