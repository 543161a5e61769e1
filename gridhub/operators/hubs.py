"""The hub problem: what clusters are, who visits them, and the network between them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridhub.config import Grid
from gridhub.functions.geo import degrees_to_metres, haversine
from gridhub.operators.components import star_components
from gridhub.operators.neighbors import tile_keys
from gridhub.operators.project import tile_center
from gridhub.operators.variants import label_points, retain_points


def hubs(clusters: DataFrame, grid: Grid, degrees: float = 1.0) -> DataFrame:
    """A summary row per cluster: weighted centre, box, tiles, points, densest tile, area.

    ``degrees`` is the size in degrees of one unit of the axes (1e-7 for e7 integers).
    """
    keys = tile_keys(clusters)
    roots = [f"r_{k}" for k in keys]
    x, y = grid.axes
    placed = tile_center(clusters, grid)
    out = placed.groupBy(*roots).agg(
        (F.sum(F.col("n") * F.col(x)) / F.sum("n")).alias("x"), (F.sum(F.col("n") * F.col(y)) / F.sum("n")).alias("y"),
        F.min("tx").alias("tx_min"), F.max("tx").alias("tx_max"), F.min("ty").alias("ty_min"), F.max("ty").alias("ty_max"),
        F.count("*").cast("bigint").alias("tiles"), F.sum("n").cast("bigint").alias("points"), F.max_by(F.struct("tx", "ty"), F.struct("n", "tx", "ty")).alias("densest"),
    )
    per_x, per_y = degrees_to_metres(F.col("y") * degrees)
    tile_area = F.lit(degrees**2 / abs(grid.scales[0] * grid.scales[1]))
    return out.withColumn("area_m2", F.col("tiles") * tile_area * per_x * per_y)


def filter_area(found: DataFrame, low_m2: float = 0.0, high_m2: float = float("inf")) -> DataFrame:
    return found.where(F.col("area_m2").between(low_m2, high_m2))


def near_hubs(found: DataFrame, min_m: float, degrees: float = 1.0) -> DataFrame:
    """Pairs of hubs closer than ``min_m``, by buckets of that size and an exact distance."""
    roots = [c for c in found.columns if c.startswith("r_")]
    lon, lat = F.col("x") * degrees, F.col("y") * degrees
    per = 111_000.0
    # one bucket is at least min_m wide everywhere between 85 degrees south and north
    b = found.select(F.struct(*roots).alias("hub"), lon.alias("lon"), lat.alias("lat"), F.floor(lon / (min_m / per / 0.087)).alias("bx"), F.floor(lat / (min_m / per)).alias("by"))
    around = b.withColumn("i", F.explode(F.array(*[F.lit(i) for i in range(9)]))).select(F.col("hub").alias("other"), F.col("lon").alias("lon2"), F.col("lat").alias("lat2"), (F.col("bx") + F.col("i") % 3 - 1).alias("bx"), (F.col("by") + F.floor(F.col("i") / 3) - 1).alias("by"))
    met = b.join(around, ["bx", "by"]).where("hub < other").withColumn("metres", haversine(F.col("lon"), F.col("lat"), F.col("lon2"), F.col("lat2")))
    return met.where(F.col("metres") < min_m).select("hub", "other", "metres")


def merge_near_hubs(clusters: DataFrame, pairs: DataFrame) -> DataFrame:
    """Clusters whose hubs are suspiciously close become one, under the least root."""
    keys = tile_keys(clusters)
    roots = [f"r_{k}" for k in keys]
    to = star_components(pairs, "hub", "other").select(*[F.col(f"node.{r}").alias(r) for r in roots], F.col("root").alias("_to"))
    joined = clusters.join(to, roots, "left")
    return joined.select(*[F.coalesce(F.col(f"_to.{r}"), F.col(r)).alias(r) for r in roots], *[c for c in clusters.columns if c not in roots])


def hub_vehicles(points: DataFrame, clusters: DataFrame, grid: Grid, vehicle: str = "vehicle", names: bool = False) -> DataFrame:
    """Vehicles and points per hub; ``names`` adds the vehicles themselves, sorted."""
    roots = [f"r_{k}" for k in grid.keys]
    rows = retain_points(points, clusters, grid)
    extra = [F.array_sort(F.collect_set(vehicle)).alias("vehicle_ids")] if names else []
    return rows.groupBy(*roots).agg(F.countDistinct(vehicle).alias("vehicles"), F.approx_count_distinct(vehicle).alias("vehicles_approx"), F.count("*").alias("points"), *extra)


def visits(points: DataFrame, clusters: DataFrame, grid: Grid, gap: str = "7 days", vehicle: str = "vehicle", at: str = "at") -> DataFrame:
    """Runs of a vehicle's rows at one hub with no pause over ``gap``.

    Rows at the same instant are ordered by hub and place, so the result does not depend
    on the input's order.  Returns ``vehicle, visit, r_*, arrive, leave, rows``.
    """
    roots = [f"r_{k}" for k in grid.keys]
    rows = retain_points(points, clusters, grid).select(F.col(vehicle).alias("vehicle"), F.col(at).alias("at"), *roots, *grid.axes)
    order = Window.partitionBy("vehicle").orderBy("at", *roots, *grid.axes)
    same = F.lit(True)
    for r in roots:
        same = same & (F.lag(r).over(order) == F.col(r))
    near = F.col("at") <= F.lag("at").over(order) + F.expr(f"interval {gap}")
    marked = rows.withColumn("opens", (~F.coalesce(same & near, F.lit(False))).cast("int"))
    numbered = marked.withColumn("visit", F.sum("opens").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy("vehicle", "visit", *roots).agg(F.min("at").alias("arrive"), F.max("at").alias("leave"), F.count("*").alias("rows"))


def hub_network(found: DataFrame) -> DataFrame:
    """Trips between hubs: from each visit to the vehicle's next visit elsewhere."""
    roots = [c for c in found.columns if c.startswith("r_")]
    order = Window.partitionBy("vehicle").orderBy("visit")
    nxt = found.select(F.struct(*roots).alias("src"), F.lead(F.struct(*roots)).over(order).alias("dst"), F.col("leave"), F.lead("arrive").over(order).alias("arrive"))
    return nxt.where("dst is not null and src <> dst").groupBy("src", "dst").agg(F.count("*").alias("trips"), F.avg(F.unix_timestamp("arrive") - F.unix_timestamp("leave")).alias("mean_seconds"))


def usage_profile(found: DataFrame, by: tuple[str, ...] = ("hour", "weekday"), shape: str = "cube") -> DataFrame:
    """Visits by parts of the arrival time and hub: ``cube``, ``rollup`` or plain groups."""
    roots = [c for c in found.columns if c.startswith("r_")]
    parts = {"hour": F.hour("arrive"), "weekday": F.dayofweek("arrive"), "month": F.month("arrive"), "year": F.year("arrive")}
    timed = found.withColumns({b: parts[b] for b in by})
    keys = [*roots, *by]
    grouped = {"cube": timed.cube, "rollup": timed.rollup, "plain": timed.groupBy}[shape](*keys)
    marks = [F.grouping_id().alias("grouping")] if shape != "plain" else []
    return grouped.agg(*marks, F.count("*").alias("visits"), F.countDistinct("vehicle").alias("vehicles"))


def usage_pivot(found: DataFrame, by: str = "weekday") -> DataFrame:
    """One row per hub, one column per weekday."""
    roots = [c for c in found.columns if c.startswith("r_")]
    return found.withColumn("weekday", F.dayofweek("arrive")).groupBy(*roots).pivot("weekday", list(range(1, 8))).agg(F.count(F.lit(1)))


def reduction(points: DataFrame, clusters: DataFrame) -> DataFrame:
    """How much smaller the answer is than the input."""
    return points.agg(F.count("*").alias("points")).crossJoin(clusters.agg(F.count("*").alias("tiles"))).withColumn("ratio", F.col("points") / F.nullif(F.col("tiles"), F.lit(0)))


def as_of_visit(events: DataFrame, found: DataFrame, vehicle: str = "vehicle", at: str = "at") -> DataFrame:
    """The last visit that began at or before each event: union and a running last value."""
    roots = [c for c in found.columns if c.startswith("r_")]
    left = events.select(F.col(vehicle).alias("vehicle"), F.col(at).alias("at"), F.lit(1).alias("kind"), F.lit(None).cast("bigint").alias("visit"), *[F.lit(None).cast("bigint").alias(r) for r in roots])
    right = found.select("vehicle", F.col("arrive").alias("at"), F.lit(0).alias("kind"), F.col("visit").cast("bigint").alias("visit"), *roots)
    order = Window.partitionBy("vehicle").orderBy("at", "kind", F.col("visit")).rowsBetween(Window.unboundedPreceding, 0)
    filled = left.unionByName(right).withColumns({c: F.last(c, ignorenulls=True).over(order) for c in ("visit", *roots)})
    return filled.where("kind = 1").drop("kind")


def events_in_visits(events: DataFrame, found: DataFrame, vehicle: str = "vehicle", at: str = "at") -> DataFrame:
    """Events inside visit intervals: an equi-join on vehicle and day, then the exact test."""
    days = found.withColumn("day", F.explode(F.sequence(F.to_date("arrive"), F.to_date("leave"))))
    left = events.select(F.col(vehicle).alias("vehicle"), F.col(at).alias("at"), F.to_date(at).alias("day"))
    return left.join(days, ["vehicle", "day"]).where(F.col("at").between(F.col("arrive"), F.col("leave"))).drop("day")


def top_tiles(clusters: DataFrame, many: int = 3) -> DataFrame:
    """The densest tiles of every cluster, ties by place."""
    roots = [f"r_{k}" for k in tile_keys(clusters)]
    rank = F.row_number().over(Window.partitionBy(*roots).orderBy(F.desc("n"), *tile_keys(clusters)))
    return clusters.withColumn("place", rank).where(F.col("place") <= many)


__all__ = ["as_of_visit", "events_in_visits", "filter_area", "hub_network", "hub_vehicles", "hubs", "label_points", "merge_near_hubs", "near_hubs", "reduction", "top_tiles", "usage_pivot", "usage_profile", "visits"]
