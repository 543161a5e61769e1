"""Point sets: hubs and noise derived from the tables, generated hubs, natural axes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition

from gridhub.config import Grid
from gridhub.sources.tables import table

E7 = 10_000_000
#: Divisors of e7 coordinates for the precisions of the sweep.
CELL = {"3": 10000.0, "35": 3162.2776601683795, "4": 1000.0, "5": 100.0}


def e7_grid(level: str = "35", mode: str = "floor", offset: float | tuple[float, ...] = 0.0) -> Grid:
    """A grid on the integer coordinates, exact in any engine that divides doubles."""
    return Grid(("lon_e7", "lat_e7"), cell=CELL[level], mode=mode, offset=offset)


def hub_points(spark: SparkSession, folder: str, trips: bool = False) -> DataFrame:
    """Points around one hub per supplier, from ``lineitem``; integer arithmetic only.

    With ``trips`` the vehicle is the order's customer and ``at`` the ship date.
    """
    line = table(spark, folder, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber", "l_suppkey", "l_shipdate")
    o, p, n, s = (F.col(c).cast("bigint") for c in ("l_orderkey", "l_partkey", "l_linenumber", "l_suppkey"))
    a = (o * 1103515245 + p * 12345 + n * 7919) % 2003
    b = (o * 69069 + p * 362437 + n * 104729) % 2011
    half = 3500 + ((s * 31) % 5) * 500
    rows = line.select(
        s.alias("hub"), F.col("l_orderkey"), F.col("l_shipdate").alias("at"),
        ((s % 40) * 100000 + 50000 + ((s * 7919) % 97) * 200).alias("cx"), (F.floor(s / 40) * 100000 + 50000 + ((s * 104729) % 89) * 200).alias("cy"),
        ((a - 1001) * half).alias("dx"), ((b - 1005) * half).alias("dy"),
    ).select("hub", "l_orderkey", "at", F.expr("cx + dx div 1000").alias("lon_e7"), F.expr("cy + dy div 1000").alias("lat_e7"))
    coordinates = ["lon_e7", "lat_e7", (F.col("lon_e7") / 1e7).alias("lon"), (F.col("lat_e7") / 1e7).alias("lat")]
    if not trips:
        return rows.select("hub", *coordinates)
    orders = table(spark, folder, "orders").select("o_orderkey", F.col("o_custkey").alias("vehicle"))
    return rows.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("hub", "vehicle", F.col("at").cast("timestamp").alias("at"), *coordinates)


def noise_points(spark: SparkSession, folder: str) -> DataFrame:
    """Background over the same canvas, from ``orders``."""
    rows = F.broadcast(table(spark, folder, "lineitem").agg((F.floor(F.max("l_suppkey") / 40) + 1).alias("rows")))
    o, c = F.col("o_orderkey"), F.col("o_custkey")
    made = table(spark, folder, "orders").crossJoin(rows).select(F.lit(-1).cast("bigint").alias("hub"), ((o * 1103515245 + c * 12345) % 4000037).alias("lon_e7"), ((o * 69069 + c * 362437) % (F.col("rows") * 100000)).alias("lat_e7"))
    return made.select("hub", "lon_e7", "lat_e7", (F.col("lon_e7") / 1e7).alias("lon"), (F.col("lat_e7") / 1e7).alias("lat"))


def replicas(points: DataFrame, copies: int) -> DataFrame:
    """Shifted copies of an e7 point set, each a whole degree further; hubs stay apart."""
    shifted = points.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    return shifted.select((F.col("hub") + F.col("copy") * 1_000_000).alias("hub"), (F.col("lon_e7") + F.col("copy") * E7).alias("lon_e7"), "lat_e7")


def hub_grid(spark: SparkSession, hubs: int, points: int = 500, seed: int = 1, layout: str = "grid", partitions: int | None = None) -> DataFrame:
    """Generated hubs: ``hub, lon_e7, lat_e7``, made by arithmetic on ``spark.range``.

    ``grid`` cuts the canvas into boxes with a centre in each; ``random`` scatters centres
    and keeps those with no earlier centre in their own or a neighbouring box.
    """
    side = max(1, round(hubs**0.5))
    word = lambda x, k: F.pmod(F.xxhash64(x, F.lit(seed), F.lit(k)), F.lit(1_000_003))
    base = spark.range(hubs, numPartitions=partitions).withColumnRenamed("id", "hub")
    if layout == "grid":
        at = base.select("hub", ((F.col("hub") % side) * 100_000 + 30_000 + word("hub", 1) * 40_000 / 1_000_003).cast("bigint").alias("cx"), (F.floor(F.col("hub") / side) * 100_000 + 30_000 + word("hub", 2) * 40_000 / 1_000_003).cast("bigint").alias("cy"))
    elif layout == "random":
        span = side * 200_000
        drawn = base.select("hub", (word("hub", 1) * span / 1_000_003).cast("bigint").alias("cx"), (word("hub", 2) * span / 1_000_003).cast("bigint").alias("cy"))
        boxed = drawn.withColumns({"bx": F.floor(F.col("cx") / 20_000), "by": F.floor(F.col("cy") / 20_000)})
        around = boxed.withColumn("i", F.explode(F.array(*[F.lit(i) for i in range(9)]))).select(F.col("hub").alias("other"), (F.col("bx") + F.col("i") % 3 - 1).alias("bx"), (F.col("by") + F.floor(F.col("i") / 3) - 1).alias("by"))
        crowded = boxed.join(around, ["bx", "by"]).where("other < hub").select("hub").distinct()
        at = drawn.join(crowded, "hub", "left_anti")
    else:
        raise ValueError("layout is grid or random")
    half = 3500 + (F.col("hub") % 5) * 500
    spread = at.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(points - 1))))
    off = lambda k: ((F.pmod(F.xxhash64("hub", "i", F.lit(seed), F.lit(k)), F.lit(2001)) - 1000) * half / 1000).cast("bigint")
    return spread.select("hub", (F.col("cx") + off(3)).alias("lon_e7"), (F.col("cy") + off(4)).alias("lat_e7"))


class _HubRange(InputPartition):
    def __init__(self, low: int, high: int):
        super().__init__((low, high))


class _HubReader(DataSourceReader):
    def __init__(self, options: dict):
        self.hubs, self.points = int(options.get("hubs", 10)), int(options.get("points", 500))
        self.parts, self.seed = int(options.get("parts", 4)), int(options.get("seed", 1))
        self.only = None

    def partitions(self):
        if self.only is not None:
            return [_HubRange(self.only, self.only + 1)] if 0 <= self.only < self.hubs else [_HubRange(0, 0)]
        return [_HubRange(self.hubs * i // self.parts, self.hubs * (i + 1) // self.parts) for i in range(self.parts)]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        low, high = partition.value
        side = max(1, round(self.hubs**0.5))
        for hub in range(low, high):
            rng = np.random.default_rng([self.seed, hub])
            half = 3500 + hub % 5 * 500
            offs = rng.integers(-half, half + 1, (2, self.points))
            yield pa.RecordBatch.from_pydict({"hub": pa.array(np.full(self.points, hub)), "lon_e7": pa.array((hub % side) * 100_000 + 50_000 + offs[0]), "lat_e7": pa.array((hub // side) * 100_000 + 50_000 + offs[1])})


class _PushingReader(_HubReader):
    """Also prunes hubs; Spark refuses such a reader while its pushdown setting is off."""

    def pushFilters(self, filters):
        """Takes equality on ``hub``; needs spark.sql.python.filterPushdown.enabled."""
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("hub",) and self.only is None:
                self.only = f.value
            else:
                yield f


class HubSource(DataSource):
    """``spark.read.format('hubgen').option('hubs', n)``: generated hubs as a source.

    With the option ``pushdown`` and spark.sql.python.filterPushdown.enabled, equality on
    ``hub`` is answered by the source.
    """

    @classmethod
    def name(cls) -> str:
        return "hubgen"

    def schema(self) -> str:
        return "hub bigint, lon_e7 bigint, lat_e7 bigint"

    def reader(self, schema) -> DataSourceReader:
        return (_PushingReader if self.options.get("pushdown") == "true" else _HubReader)(self.options)


#: Natural point sets: table, axes as SQL over it, threshold.
NATURAL = {
    "events": ("events", "datediff(ts, date'2024-01-01')", "cast(floor(value / 10) as bigint)", 5),
    "orders": ("orders", "cast(floor(datediff(o_orderdate, date'1992-01-01') / 30) as bigint)", "cast(floor(o_totalprice / 10000) as bigint)", 5),
    "parts": ("part", "cast(p_size as bigint)", "cast(floor(p_retailprice / 5) as bigint)", 2),
    "docs": ("documents", "cast(floor(n_chars / 200) as bigint)", "cast(length(source) as bigint)", 3),
    "pages": ("pages", "cast(floor(length(html) / 500) as bigint)", "cast(floor((length(html) - length(replace(html, '<', ''))) / 20) as bigint)", 2),
    "conversations": ("conversations", "cast(turn as bigint)", "cast(floor(length(text) / 50) as bigint)", 3),
    "customers": ("customer", "cast(c_nationkey as bigint)", "cast(floor(c_acctbal / 500) as bigint)", 2),
    "benchmark": ("benchmark", "cast(floor(length(text) / 20) as bigint)", "cast(floor((length(text) - length(replace(text, ' ', ''))) / 5) as bigint)", 1),
}


def natural_points(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """``x, y`` integers from one of the NATURAL sets."""
    source, x, y, _ = NATURAL[name]
    return table(spark, folder, source).select(F.expr(x).cast("bigint").alias("x"), F.expr(y).cast("bigint").alias("y"))
