"""Streams equal their batch results; SQL, ML and source surfaces."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from gridhub.config import Grid, TileParams
from gridhub.functions import ml, sql
from gridhub.operators.agglomerate import agglomerate, tile_clusters
from gridhub.operators.contract import count_tiles
from gridhub.operators.project import with_tile
from gridhub.plans import advisor
from gridhub.sources import tables
from gridhub.sources.hubs import HubSource, e7_grid, hub_points
from gridhub.streaming import tiles as S

GRID = Grid(("x", "y"), scale=1.0)


@pytest.fixture()
def folder(spark, tmp_path):
    rows = [(i, dt.datetime(2024, 1, 1 + i // 10, i % 10), i % 3 + 0.5, 0.5) for i in range(40)]
    df = spark.createDataFrame(rows, "event_id bigint, ts timestamp, x double, y double")
    for k in range(4):
        df.where(f"event_id div 10 = {k}").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    return df, f"{tmp_path}"


def read(spark, path, files=1):
    return spark.readStream.schema("event_id bigint, ts timestamp, x double, y double").option("maxFilesPerTrigger", files).parquet(f"{path}/in")


def test_running_and_windowed_counts(spark, folder):
    df, path = folder
    got = S.run_once(S.stream_counts(read(spark, path), GRID), "a")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, count_tiles(df, GRID).collect()))
    win = S.run_once(S.stream_counts(read(spark, path), GRID, "1 day"), "b")
    assert win.agg(F.sum("n")).first()[0] == 40 and win.select("start").distinct().count() == 4
    panes = S.sliding_from_panes(win, 2, 86400)
    slide = S.run_once(S.stream_counts(read(spark, path), GRID, "2 days", "1 day"), "c")
    assert sorted(map(tuple, panes.select("start", "tx", "ty", "n").collect())) == sorted(map(tuple, slide.select("start", "tx", "ty", "n").collect()))


def test_restart_goes_on_from_its_checkpoint(spark, folder):
    df, path = folder
    first = S.stream_counts(read(spark, path), GRID)
    S.run_once(first, "r1", checkpoint=f"{path}/ck")
    df.limit(5).withColumn("x", F.lit(77.5)).coalesce(1).write.mode("append").parquet(f"{path}/in")
    again = S.run_once(S.stream_counts(read(spark, path), GRID), "r2", checkpoint=f"{path}/ck")
    assert again.agg(F.sum("n")).first()[0] == 45


def test_late_rows_are_dropped_and_counted(spark, folder):
    _, path = folder
    query = S.stream_counts(read(spark, path), GRID, "1 day", watermark="1 hour").writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{path}/late").start()
    query.awaitTermination()
    spark.createDataFrame([(99, dt.datetime(2023, 12, 1), 0.5, 0.5)], "event_id bigint, ts timestamp, x double, y double").coalesce(1).write.mode("append").parquet(f"{path}/in")
    query = S.stream_counts(read(spark, path), GRID, "1 day", watermark="1 hour").writeStream.format("noop").outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{path}/late").start()
    query.awaitTermination()
    assert sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"]) == 1


def test_clusters_per_trigger_and_their_fate(spark, folder):
    df, path = folder
    query = S.stream_clusters(S.stream_counts(read(spark, path), GRID), f"{path}/out", f"{path}/ck2", TileParams(3, 1))
    query.awaitTermination()
    last = spark.read.parquet(f"{path}/out/batch=3")
    want = tile_clusters(df, GRID, TileParams(3, 1))
    assert sorted(map(tuple, last.select(*want.columns).collect())) == sorted(map(tuple, want.collect()))
    windows = S.stream_counts(read(spark, path), GRID, "6 hours")
    S.stream_clusters(windows, f"{path}/win", f"{path}/ck4", TileParams(1, 1)).awaitTermination()
    got = spark.read.parquet(f"{path}/win/batch=3").select("start", "r_tx", "r_ty", "tx", "ty", "n")
    tiled = with_tile(df, GRID).groupBy(F.window("ts", "6 hours").start.alias("start"), "tx", "ty").agg(F.count("*").alias("n"))
    want = None
    for r in tiled.select("start").distinct().collect():
        one = agglomerate(tiled.where(F.col("start") == F.lit(r.start)).select("tx", "ty", "n")).select(F.lit(r.start).alias("start"), "r_tx", "r_ty", "tx", "ty", "n")
        want = one if want is None else want.unionByName(one)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    a = agglomerate(spark.createDataFrame([(0, 0, 9), (1, 0, 9), (50, 0, 9), (60, 0, 9), (62, 0, 9)], "tx bigint, ty bigint, n bigint"))
    b = agglomerate(spark.createDataFrame([(0, 0, 9), (1, 0, 9), (60, 0, 9), (61, 0, 9), (62, 0, 9), (90, 0, 9)], "tx bigint, ty bigint, n bigint"))
    fates = {(r.cluster[0], r.fate) for r in S.evolution(a, b).collect()}
    assert fates == {(0, "kept"), (50, "died"), (60, "merged"), (90, "born")}
    assert {(r.cluster[0], r.fate) for r in S.evolution(b, a).collect()} >= {(60, "split")}


def test_dedup_sessions_labels_joins(spark, folder):
    df, path = folder
    df.limit(3).coalesce(1).write.mode("append").parquet(f"{path}/in")
    assert S.run_once(S.stream_dedup(read(spark, path)), "d", "append").count() == 40
    stays = S.run_once(S.stream_sessions(read(spark, path).withColumn("user_id", F.lit(1)), GRID, "4 hours"), "e")
    assert stays.agg(F.sum("n")).first()[0] == 40  # the repeated rows come after the watermark
    clusters = tile_clusters(df, GRID, TileParams(3, 1))
    assert S.run_once(S.label_stream(read(spark, path), clusters, GRID), "f", "append").where("r_tx is not null").count() == 43
    met = S.near_in_time(read(spark, path), read(spark, path), "event_id", "ts", "1 hour").select("a.event_id")
    assert S.run_once(met, "g", "append").count() >= 40


def test_decayed_counts(spark, folder):
    df, path = folder
    pytest.importorskip("google.protobuf", reason="the stateful Python worker needs protobuf")
    out = S.decayed_counts(read(spark, path, 4), GRID, 3600.0)
    query = out.writeStream.format("memory").queryName("decay").outputMode("update").trigger(availableNow=True).option("checkpointLocation", f"{path}/ck3").start()
    query.awaitTermination()
    got = {r.tx: r.weight for r in spark.sql("select tx, max_by(weight, at_s) weight from decay group by tx").collect()}
    for tx in range(3):
        times = sorted(r.ts.timestamp() for r in df.where(F.floor("x") == tx).collect())
        assert got[tx] == pytest.approx(sum(0.5 ** ((times[-1] - t) / 3600) for t in times), rel=1e-6)


def test_sql_surface(spark):
    sql.register_functions(spark)
    spark.createDataFrame([(0, 0, 1), (1, 0, 2), (5, 5, 3)], "tx bigint, ty bigint, n bigint").createOrReplaceTempView("t")
    assert spark.sql("select tile_of(0.29D, 10D)").first()[0] == 2
    assert spark.sql("select * from tile_neighbors(0, 0, 'manhattan', 1)").count() == 4
    assert spark.sql("select n.* from t, lateral tile_neighbors(tx, ty, 'chebyshev', 1) n").count() == 24
    got = spark.sql("select * from tile_components(TABLE(t) WITH SINGLE PARTITION)").collect()
    assert sorted((r.r_tx, r.tx) for r in got) == [(0, 0), (0, 1), (5, 5)]
    assert spark.table("t").agg(sql.tile_entropy(F.col("n").cast("double"))).first()[0] == pytest.approx(1.459, abs=1e-3)
    inside = sql.point_in_polygon([(0.0, 0.0), (2.0, 0.0), (2.0, 2.0), (0.0, 2.0)])
    assert spark.table("t").where(inside(F.col("tx") + 0.5, F.col("ty") + 0.5)).count() == 2
    assert sql.map_side_counts(spark.table("t"), ("tx", "ty")).count() == 3
    assert sql.map_side_counts(spark.table("t").where("tx < 0"), ("tx", "ty")).count() == 0
    assert spark.createDataFrame([('{"k": 4}',)], "p string").select(sql.props_number(F.col("p"))).first()[0] == 4


def test_estimator_round_trip(spark, tiny, tmp_path):
    pts = hub_points(spark, tiny).select("hub", "lon", "lat")
    model = ml.TileClusterer(precision=3.5, tau=5, mu=4).fit(pts)
    out = model.transform(pts)
    assert out.where("prediction >= 0").select("prediction").distinct().count() == 10 and out.columns == ["hub", "lon", "lat", "prediction"]
    model.save(f"file://{tmp_path}/m")
    again = ml.TileClusterModel.load(spark, f"file://{tmp_path}/m")
    assert again.transform(pts).exceptAll(out).count() == 0


def test_sources_and_sinks(spark, tmp_path):
    spark.dataSource.register(HubSource)
    made = spark.read.format("hubgen").option("hubs", 6).option("points", 20).load()
    assert made.count() == 120 and made.select("hub").distinct().count() == 6
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    again = spark.read.format("hubgen").option("hubs", 6).option("points", 20).option("pushdown", "true").load()
    assert again.where("hub = 4").count() == 20 and again.where("hub = 9").count() == 0
    spark.conf.unset("spark.sql.python.filterPushdown.enabled")
    counts = count_tiles(made, e7_grid("3"))
    for kind in ("parquet", "orc", "json", "csv"):
        tables.write_counts(counts, f"{tmp_path}/{kind}", kind)
        assert tables.read_counts(spark, f"{tmp_path}/{kind}", kind).exceptAll(counts).count() == 0
    (tmp_path / "p.csv").write_text("lon,lat\n1.0,2.0\nbroken,3\n")
    rows = tables.points_csv(spark, str(tmp_path / "p.csv")).collect()
    assert [r.lon for r in rows] == [1.0, None] and rows[1]["_malformed"] == "broken,3"
    (tmp_path / "p.json").write_text('{"lon": 1.0, "lat": 2.0}\n{bad\n')
    assert sorted(r["_malformed"] is None for r in tables.points_json(spark, str(tmp_path / "p.json")).collect()) == [False, True]


def test_advice(spark, tiny):
    pts = hub_points(spark, tiny).cache()
    good = lambda found: found.select("r_tx", "r_ty").distinct().count() == 10
    assert advisor.lowest_precision(pts, [e7_grid(v) for v in ("5", "4", "35", "3")], good).cell == e7_grid("35").cell
    assert advisor.engine_for(10) == "driver" and advisor.engine_for(10**9) == "blocks" and advisor.partitions_for(pts, e7_grid("4")) == 1
