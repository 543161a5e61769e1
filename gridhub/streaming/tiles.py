"""The stream form: tile counts per window, clusters per trigger, decay, evolution."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.query import StreamingQuery

from gridhub.config import Grid, Neighborhood, TileParams
from gridhub.operators.agglomerate import agglomerate, keep_clusters
from gridhub.operators.contract import significant
from gridhub.operators.metrics import overlap
from gridhub.operators.neighbors import tile_keys
from gridhub.operators.project import with_tile
from gridhub.plans.staging import shared_root


def timed_points(stream: DataFrame, at: str = "ts") -> DataFrame:
    """Event time as TIMESTAMP; a watermark does not take the zoneless type."""
    return stream.withColumn(at, F.col(at).cast("timestamp"))


def stream_counts(stream: DataFrame, grid: Grid, window: str | None = None, slide: str | None = None, at: str = "ts", watermark: str | None = "1 day") -> DataFrame:
    """Counts per tile, or per window and tile.

    Without a window the state holds every tile ever seen, bounded by the canvas.  With
    one, rows later than the watermark are dropped and old windows leave the state.
    """
    tiled = with_tile(stream, grid)
    if window is None:
        return tiled.groupBy(*grid.keys).agg(F.count("*").cast("bigint").alias("n"))
    if watermark:
        tiled = tiled.withWatermark(at, watermark)
    span = F.window(at, window, slide) if slide else F.window(at, window)
    return tiled.groupBy(span.alias("w"), *grid.keys).agg(F.count("*").cast("bigint").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *grid.keys, "n")


def sliding_from_panes(panes: DataFrame, panes_per_window: int, pane_seconds: int) -> DataFrame:
    """Sliding windows summed in batch from the counts of tumbling panes."""
    keys = tile_keys(panes)
    steps = F.sequence(F.lit(0), F.lit(panes_per_window - 1))
    moved = panes.withColumn("_i", F.explode(steps)).withColumn("start", F.timestamp_seconds(F.unix_timestamp("start") - F.col("_i") * pane_seconds))
    out = moved.groupBy("start", *keys).agg(F.sum("n").cast("bigint").alias("n"))
    return out.withColumn("end", F.timestamp_seconds(F.unix_timestamp("start") + panes_per_window * pane_seconds)).select("start", "end", *keys, "n")


def stream_sessions(stream: DataFrame, grid: Grid, gap: str, vehicle: str = "user_id", at: str = "ts", watermark: str = "1 day") -> DataFrame:
    """Stays of a vehicle on a tile: session windows."""
    tiled = with_tile(stream, grid).withWatermark(at, watermark)
    return tiled.groupBy(F.session_window(at, gap).alias("w"), F.col(vehicle).alias("vehicle"), *grid.keys).agg(F.count("*").cast("bigint").alias("n")).select("vehicle", F.col("w.start").alias("arrive"), F.col("w.end").alias("leave"), *grid.keys, "n")


def stream_dedup(stream: DataFrame, key: str = "event_id", at: str = "ts", watermark: str = "1 day") -> DataFrame:
    return stream.withWatermark(at, watermark).dropDuplicatesWithinWatermark([key])


def label_stream(stream: DataFrame, clusters: DataFrame, grid: Grid) -> DataFrame:
    """Arriving points against the last published clusters: a stream-static join."""
    keys = list(grid.keys)
    return with_tile(stream, grid).join(clusters.select(*keys, *[f"r_{k}" for k in keys]), keys, "left")


def near_in_time(left: DataFrame, right: DataFrame, key: str, at: str, within: str, watermark: str = "1 day") -> DataFrame:
    """Rows of two streams with one key whose times differ by ``within`` at most."""
    a = left.withWatermark(at, watermark).alias("a")
    b = right.withWatermark(at, watermark).alias("b")
    return a.join(b, F.expr(f"a.{key} = b.{key} AND b.{at} BETWEEN a.{at} - interval {within} AND a.{at} + interval {within}"))


class DecayedCount(StatefulProcessor):
    """Per tile, a count that halves every ``half_life`` seconds; light tiles expire.

    For ``transformWithStateInPandas`` in update mode.  Input columns: tile keys and
    ``at_s``, event time in seconds.
    """

    def __init__(self, half_life: float, floor: float = 0.01):
        self.half_life, self.floor = half_life, floor

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.state = handle.getValueState("decayed", "weight double, at_s double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        weight, at = (self.state.get() if self.state.exists() else (0.0, None)) or (0.0, None)
        for pdf in rows:
            for t in sorted(pdf["at_s"]):
                if at is not None and t >= at:
                    weight *= 0.5 ** ((t - at) / self.half_life)
                    at = t
                elif at is None:
                    at = t
                weight += 1.0 if t >= at else 0.5 ** ((at - t) / self.half_life)
        if weight < self.floor:
            self.state.clear()
        else:
            self.state.update((float(weight), float(at)))
        yield pd.DataFrame({"tx": [key[0]], "ty": [key[1]], "weight": [weight], "at_s": [at]})

    def close(self) -> None:
        pass


def decayed_counts(stream: DataFrame, grid: Grid, half_life: float, at: str = "ts", floor: float = 0.01) -> DataFrame:
    """Exponentially decayed counts per tile; needs the RocksDB state store provider."""
    rows = with_tile(stream, grid).select(*grid.keys, F.col(at).cast("double").alias("at_s"))
    return rows.groupBy(*grid.keys).transformWithStateInPandas(statefulProcessor=DecayedCount(half_life, floor), outputStructType="tx bigint, ty bigint, weight double, at_s double", outputMode="Update", timeMode="None")


def window_clusters(counts: DataFrame, params: TileParams | None = None) -> DataFrame:
    """Clusters of every window of ``start, tx, ty, n`` in one plan: ``start, r_tx, r_ty, tx, ty, n``.

    The window's start is one more axis, along which no tile has a neighbour.
    """
    params = params or TileParams()
    within = Neighborhood(offsets=tuple((0, *o) for o in params.near.all_offsets(2)))
    tiles = counts.select(F.unix_micros("start").alias("t0"), F.col("tx").alias("t1"), F.col("ty").alias("t2"), "n")
    found = keep_clusters(agglomerate(significant(tiles, params.tau), within), params.mu)
    return found.select(F.timestamp_micros("t0").alias("start"), F.col("r_t1").alias("r_tx"), F.col("r_t2").alias("r_ty"), F.col("t1").alias("tx"), F.col("t2").alias("ty"), "n")


def stream_clusters(counts: DataFrame, path: str, checkpoint: str, params: TileParams | None = None, output_mode: str = "complete", **trigger) -> StreamingQuery:
    """Clusters of every trigger, published as one folder per batch id.

    A batch that runs again after a failure writes its own folder anew, so the snapshots
    are the same as without the failure.
    """
    params = params or TileParams()
    windowed = "start" in counts.columns

    def publish(batch: DataFrame, batch_id: int) -> None:
        if windowed:
            out = window_clusters(batch, params)
        else:
            out = keep_clusters(agglomerate(significant(batch, params.tau), params.near), params.mu)
        out.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return counts.writeStream.outputMode(output_mode).option("checkpointLocation", checkpoint).foreachBatch(publish).trigger(**(trigger or {"availableNow": True})).start()


def evolution(before: DataFrame, after: DataFrame, share: float = 0.0) -> DataFrame:
    """What became of clusters between two snapshots: born, died, merged, split or kept."""
    met = overlap(before, after).where(F.col("jaccard") > share)
    old, new = met.groupBy("a").agg(F.count("*").alias("heirs")), met.groupBy("b").agg(F.count("*").alias("parents"))
    roots_a = before.select(F.struct(*[c for c in before.columns if c.startswith("r_")]).alias("a")).distinct()
    roots_b = after.select(F.struct(*[c for c in after.columns if c.startswith("r_")]).alias("b")).distinct()
    died = roots_a.join(old, "a", "left_anti").select(F.col("a").alias("cluster"), F.lit("died").alias("fate"))
    born = roots_b.join(new, "b", "left_anti").select(F.col("b").alias("cluster"), F.lit("born").alias("fate"))
    merged = new.where("parents > 1").select(F.col("b").alias("cluster"), F.lit("merged").alias("fate"))
    split = old.where("heirs > 1").select(F.col("a").alias("cluster"), F.lit("split").alias("fate"))
    kept = met.join(old.where("heirs = 1"), "a", "left_semi").join(new.where("parents = 1"), "b", "left_semi").select(F.col("b").alias("cluster"), F.lit("kept").alias("fate"))
    return died.unionByName(born).unionByName(merged).unionByName(split).unionByName(kept)


def run_once(frame: DataFrame, name: str = "drained", mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Drains a stream with ``availableNow`` into a staged table and returns that.

    In complete mode the last batch is the result, in append mode all batches are.
    """
    spark = frame.sparkSession
    path = f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(path if mode == "complete" else f"{path}/batch={batch_id}")

    spark.createDataFrame([], frame.schema).write.parquet(path if mode == "complete" else f"{path}/batch=-1")
    query = frame.writeStream.outputMode(mode).option("checkpointLocation", checkpoint or f"{path}-state").foreachBatch(put).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(frame.schema).option("basePath", path).parquet(path)
