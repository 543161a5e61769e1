"""Contract queries over the given tables, and the same results in DuckDB's SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridhub import baselines
from gridhub.config import Grid, Neighborhood, TileParams
from gridhub.functions import sql as Q
from gridhub.functions.shape import covariance_ellipse, least_ellipse
from gridhub.operators import analytics as A
from gridhub.operators import hubs as H
from gridhub.operators import metrics as M
from gridhub.operators import variants as V
from gridhub.operators.agglomerate import agglomerate, keep_clusters, tile_clusters
from gridhub.operators.contract import count_chunks, count_tiles, significant, tau_candidates, tile_sketch
from gridhub.operators.project import clean_points, dropped_rows, vector_axes
from gridhub.operators.sliced import slice_clusters
from gridhub.plans.staging import stage
from gridhub.sources.hubs import CELL, NATURAL, e7_grid, hub_points, natural_points, noise_points
from gridhub.sources.tables import table
from gridhub.streaming import tiles as S

TAU, MU = 5, 4
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def _add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql is not None:
        SQL[name] = sql


# ---------------------------------------------------------------- point sets in SQL

_HALF = "(3500 + ((l_suppkey * 31) % 5) * 500)"
_LON = f"((l_suppkey % 40) * 100000 + 50000 + ((l_suppkey * 7919) % 97) * 200 + ((((l_orderkey * 1103515245 + l_partkey * 12345 + l_linenumber * 7919) % 2003) - 1001) * {_HALF}) // 1000)::BIGINT"
_LAT = f"((l_suppkey // 40) * 100000 + 50000 + ((l_suppkey * 104729) % 89) * 200 + ((((l_orderkey * 69069 + l_partkey * 362437 + l_linenumber * 104729) % 2011) - 1005) * {_HALF}) // 1000)::BIGINT"
_HUBS = f"pts AS (SELECT l_suppkey AS hub, {_LON} AS lon_e7, {_LAT} AS lat_e7 FROM lineitem)"
_TRIPS = f"trips AS (SELECT l_suppkey AS hub, o_custkey AS vehicle, l_shipdate::TIMESTAMP AS tm, {_LON} AS lon_e7, {_LAT} AS lat_e7 FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"
_NOISE = "noise AS (SELECT -1::BIGINT AS hub, ((o_orderkey * 1103515245 + o_custkey * 12345) % 4000037)::BIGINT AS lon_e7, ((o_orderkey * 69069 + o_custkey * 362437) % (((SELECT max(l_suppkey) FROM lineitem) // 40 + 1) * 100000))::BIGINT AS lat_e7 FROM orders)"


def _tiles(level: str, source: str = "pts", name: str = "counts") -> str:
    c = f"{CELL[level]!r}e0"
    return f"{name} AS (SELECT floor(lon_e7 / {c})::BIGINT AS tx, floor(lat_e7 / {c})::BIGINT AS ty, count(*)::BIGINT AS n FROM {source} GROUP BY 1, 2)"


_CHEB1 = "abs(a.tx - b.tx) <= 1 AND abs(a.ty - b.ty) <= 1"


def _walk(keys: tuple[str, ...] = ("tx", "ty"), near: str = _CHEB1, sig: str = "sig", mu: int = MU, tag: str = "") -> str:
    """Reachable pairs by a recursive union, least tile as root, groups of mu or more."""
    a = ", ".join(f"a.{k} AS a_{k}" for k in keys)
    b = ", ".join(f"b.{k} AS b_{k}" for k in keys)
    both = ", ".join([f"a_{k}" for k in keys] + [f"b_{k}" for k in keys])
    start = ", ".join(list(keys) + list(keys))
    step = ", ".join([f"r.a_{k}" for k in keys] + [f"e.b_{k}" for k in keys])
    on = " AND ".join(f"r.b_{k} = e.a_{k}" for k in keys)
    pack = ", ".join(f"{k} := b_{k}" for k in keys)
    out = ", ".join([f"l.root.{k} AS r_{k}" for k in keys] + [f"s.{k}" for k in keys])
    join = " AND ".join(f"l.a_{k} = s.{k}" for k in keys)
    group = ", ".join(f"a_{k}" for k in keys)
    return f"""edges{tag} AS (SELECT {a}, {b} FROM {sig} a JOIN {sig} b ON {near}),
reach{tag}({both}) AS (SELECT {start} FROM {sig} UNION SELECT {step} FROM reach{tag} r JOIN edges{tag} e ON {on}),
lab{tag} AS (SELECT {group}, min(struct_pack({pack})) AS root FROM reach{tag} GROUP BY {group}),
every{tag} AS (SELECT {out}, s.n, count(*) OVER (PARTITION BY l.root) AS size FROM {sig} s JOIN lab{tag} l ON {join}),
clusters{tag} AS (SELECT * EXCLUDE (size) FROM every{tag} WHERE size >= {mu})"""


def _base_sql(level: str = "35", near: str = _CHEB1, tau: int = TAU, source: str = "pts", more: str = "") -> str:
    return f"WITH RECURSIVE {_HUBS}, {more}{_tiles(level, source)}, sig AS (SELECT * FROM counts WHERE n >= {tau}), {_walk(near=near)}"


_ROWS = " SELECT r_tx, r_ty, tx, ty, n FROM clusters"


def _significant(spark: SparkSession, d: str, level: str = "35") -> DataFrame:
    return significant(count_tiles(hub_points(spark, d), e7_grid(level)), TAU)


def _clusters(spark: SparkSession, d: str, level: str = "35", engine: str = "auto", near: Neighborhood | None = None) -> DataFrame:
    return tile_clusters(hub_points(spark, d), e7_grid(level), TileParams(TAU, MU, near or Neighborhood()), engine)


def _staged_clusters(spark: SparkSession, d: str) -> DataFrame:
    return stage(_clusters(spark, d), "clusters")


def base_clusters(spark: SparkSession, d: str) -> DataFrame:
    """The flagship: clusters of tiles of the derived hubs."""
    return _clusters(spark, d)


# ---------------------------------------------------------------- points, tiles

_add("hub_points", lambda s, d: hub_points(s, d).select("hub", "lon_e7", "lat_e7"), f"WITH {_HUBS} SELECT hub, lon_e7, lat_e7 FROM pts")
_add("noise_points", lambda s, d: noise_points(s, d).select("hub", "lon_e7", "lat_e7"), f"WITH {_NOISE} SELECT hub, lon_e7, lat_e7 FROM noise")
for _level in CELL:
    _add(f"tile_counts_p{_level}", lambda s, d, v=_level: count_tiles(hub_points(s, d), e7_grid(v)), f"WITH {_HUBS}, {_tiles(_level)} SELECT tx, ty, n FROM counts")

_CUST = "SELECT c_nationkey::BIGINT AS tx, {0} AS ty, count(*)::BIGINT AS n FROM customer GROUP BY 1, 2"


def _customer(mode: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda s, d: count_tiles(table(s, d, "customer").select("c_nationkey", "c_acctbal"), Grid(("c_nationkey", "c_acctbal"), scale=(1.0, 0.002), mode=mode))


_add("tile_counts_floor", _customer("floor"), _CUST.format("floor(c_acctbal * 0.002e0)::BIGINT"))
_add("tile_counts_trunc", _customer("trunc"), _CUST.format("trunc(c_acctbal * 0.002e0)::BIGINT"))
_add("tile_counts_round", _customer("round"), _CUST.format("round(c_acctbal * 0.002e0)::BIGINT"))
_add(
    "tile_counts_decimal",
    lambda s, d: count_tiles(hub_points(s, d).select((F.col("lon_e7").cast("decimal(17,0)") * F.expr("0.0000001BD")).alias("lon"), (F.col("lat_e7").cast("decimal(17,0)") * F.expr("0.0000001BD")).alias("lat")), Grid(precision=4, exact=True)),
    f"WITH {_HUBS} SELECT floor(lon_e7 / 1000e0)::BIGINT AS tx, floor(lat_e7 / 1000e0)::BIGINT AS ty, count(*)::BIGINT AS n FROM pts GROUP BY 1, 2",
)
_add(
    "tile_counts_double",
    lambda s, d: count_tiles(hub_points(s, d), Grid(precision=4)),
    f"WITH {_HUBS} SELECT floor((lon_e7 / 1e7) * 10000e0)::BIGINT AS tx, floor((lat_e7 / 1e7) * 10000e0)::BIGINT AS ty, count(*)::BIGINT AS n FROM pts GROUP BY 1, 2",
)
_add(
    "tile_counts_shifted",
    lambda s, d: count_tiles(hub_points(s, d), e7_grid("35", offset=(1500.0, 700.0))),
    f"WITH {_HUBS} SELECT floor((lon_e7 + 1500e0) / {CELL['35']!r}e0)::BIGINT AS tx, floor((lat_e7 + 700e0) / {CELL['35']!r}e0)::BIGINT AS ty, count(*)::BIGINT AS n FROM pts GROUP BY 1, 2",
)
for _scale in (2000, 2500, 5000):
    _add(
        f"tile_counts_scale{_scale}",
        lambda s, d, v=_scale: count_tiles(hub_points(s, d), Grid(scale=float(v))),
        f"WITH {_HUBS} SELECT floor((lon_e7 / 1e7) * {_scale}e0)::BIGINT AS tx, floor((lat_e7 / 1e7) * {_scale}e0)::BIGINT AS ty, count(*)::BIGINT AS n FROM pts GROUP BY 1, 2",
    )
_add(
    "tile_counts_negative_scale",
    lambda s, d: count_tiles(hub_points(s, d), Grid(scale=(-2500.0, 2500.0))),
    f"WITH {_HUBS} SELECT floor((lon_e7 / 1e7) * -2500e0)::BIGINT AS tx, floor((lat_e7 / 1e7) * 2500e0)::BIGINT AS ty, count(*)::BIGINT AS n FROM pts GROUP BY 1, 2",
)

_NATURAL_SQL = {
    "events": ("events", "datediff('day', DATE '2024-01-01', ts::DATE)", "floor(value / 10e0)"),
    "orders": ("orders", "floor(datediff('day', DATE '1992-01-01', o_orderdate::DATE) / 30e0)", "floor(o_totalprice / 10000e0)"),
    "parts": ("part", "p_size", "floor(p_retailprice / 5e0)"),
    "docs": ("documents", "floor(n_chars / 200e0)", "length(source)"),
    "pages": ("pages", "floor(length(html) / 500e0)", "floor((length(html) - length(replace(html, '<', ''))) / 20e0)"),
    "conversations": ("conversations", "turn", "floor(length(text) / 50e0)"),
    "customers": ("customer", "c_nationkey", "floor(c_acctbal / 500e0)"),
    "benchmark": ("benchmark", "floor(length(text) / 20e0)", "floor((length(text) - length(replace(text, ' ', ''))) / 5e0)"),
}
for _name, (_table, _x, _y) in _NATURAL_SQL.items():
    _tau = NATURAL[_name][3]
    _add(f"significant_{_name}", lambda s, d, v=_name, t=_tau: significant(count_tiles(natural_points(s, d, v), Grid(("x", "y"), scale=1.0)), t), f"SELECT ({_x})::BIGINT AS tx, ({_y})::BIGINT AS ty, count(*)::BIGINT AS n FROM {_table} WHERE ({_x}) IS NOT NULL AND ({_y}) IS NOT NULL GROUP BY 1, 2 HAVING count(*) >= {_tau}")
_add("significant_tiles", lambda s, d: _significant(s, d), f"WITH {_HUBS}, {_tiles('35')} SELECT tx, ty, n FROM counts WHERE n >= {TAU}")
_add("dropped_rows", lambda s, d: dropped_rows(table(s, d, "events").select("value", F.col("user_id").alias("u")), Grid(("u", "value"), scale=1.0)), "SELECT count(*)::BIGINT AS rows, count(*) FILTER (WHERE value IS NOT NULL AND user_id IS NOT NULL AND isfinite(value))::BIGINT AS kept, count(*) FILTER (WHERE value IS NULL OR user_id IS NULL OR NOT isfinite(value))::BIGINT AS dropped FROM events")
_add(
    "counts_chunked",
    lambda s, d: count_chunks([hub_points(s, d).where(F.pmod(F.col("hub"), F.lit(10)) == i) for i in (3, 1, 4, 0, 5, 9, 2, 6, 8, 7)], e7_grid("4")),
    f"WITH {_HUBS}, {_tiles('4')} SELECT tx, ty, n FROM counts",
)
_add("counts_shuffled", lambda s, d: count_tiles(hub_points(s, d).orderBy(F.rand(5)), e7_grid("4")), f"WITH {_HUBS}, {_tiles('4')} SELECT tx, ty, n FROM counts")
_add("sketch_m", lambda s, d: tile_sketch(hub_points(s, d), e7_grid("4")))
_add("tau_candidates", lambda s, d: tau_candidates(count_tiles(hub_points(s, d), e7_grid("35"))))

# ---------------------------------------------------------------- clusters

_add("clusters_base", base_clusters, _base_sql() + _ROWS)
for _level in ("3", "4", "5"):
    _add(f"clusters_p{_level}", lambda s, d, v=_level: _clusters(s, d, v), _base_sql(_level) + _ROWS)
_NEAR = {
    "manhattan1": (Neighborhood("manhattan", 1), "abs(a.tx - b.tx) + abs(a.ty - b.ty) <= 1"),
    "manhattan2": (Neighborhood("manhattan", 2), "abs(a.tx - b.tx) + abs(a.ty - b.ty) <= 2"),
    "chebyshev2": (Neighborhood("chebyshev", 2), "abs(a.tx - b.tx) <= 2 AND abs(a.ty - b.ty) <= 2"),
    "offsets": (Neighborhood(offsets=((1, 0), (0, 2))), "(a.tx = b.tx AND abs(a.ty - b.ty) IN (0, 2)) OR (a.ty = b.ty AND abs(a.tx - b.tx) = 1)"),
}
for _name, (_nbh, _near) in _NEAR.items():
    _add(f"clusters_{_name}", lambda s, d, n=_nbh: _clusters(s, d, "4", near=n), _base_sql("4", _near) + _ROWS)
for _engine in ("driver", "star", "propagate", "blocks", "recursive"):
    _add(f"clusters_{_engine}", lambda s, d, e=_engine: _clusters(s, d, engine=e), _base_sql() + _ROWS)
_SLICED = {
    "sliced2": {"slices": 2}, "sliced4": {"slices": 4}, "sliced8": {"slices": 8}, "sliced16": {"slices": 16},
    "minmax": {"slices": 8, "slicing": "minmax"}, "domain": {"slices": 8, "slicing": "domain", "domain": (0, 4000)},
    "balanced_points": {"slices": 8, "by": "points"}, "sweep": {"slices": 8, "join": "sweep"}, "tree": {"slices": 8, "join": "tree"},
}
for _name, _how in _SLICED.items():
    _add(f"clusters_{_name}", lambda s, d, h=_how: slice_clusters(_significant(s, d, "4"), Neighborhood(), mu=MU, **h), _base_sql("4") + _ROWS)
_ALL = f"{_NOISE}, everyone AS (SELECT hub, lon_e7, lat_e7 FROM pts UNION ALL SELECT * FROM noise), "


def _with_noise(s: SparkSession, d: str) -> DataFrame:
    return hub_points(s, d).select("hub", "lon_e7", "lat_e7").unionByName(noise_points(s, d).select("hub", "lon_e7", "lat_e7"))


_add("clusters_noise", lambda s, d: tile_clusters(_with_noise(s, d), e7_grid("35"), TileParams(TAU, MU)), _base_sql(source="everyone", more=_ALL) + _ROWS)

_EV = "counts AS (SELECT datediff('day', DATE '2024-01-01', ts::DATE)::BIGINT AS tx, floor(value / 10e0)::BIGINT AS ty, count(*)::BIGINT AS n FROM events GROUP BY 1, 2), sig AS (SELECT * FROM counts WHERE n >= 5)"
_add("clusters_events", lambda s, d: tile_clusters(natural_points(s, d, "events"), Grid(("x", "y"), scale=1.0), TileParams(5, 4)), f"WITH RECURSIVE {_EV}, {_walk()}" + _ROWS)


def _vector_clusters(dim: int, tau: int, metric: str) -> tuple[Callable[[SparkSession, str], DataFrame], str]:
    grid = Grid(tuple(f"v{i}" for i in range(dim)), scale=5.0)

    def run(s: SparkSession, d: str) -> DataFrame:
        points = clean_points(vector_axes(table(s, d, "embeddings"), "embedding", dim), grid)
        return tile_clusters(points, grid, TileParams(tau, 2, Neighborhood(metric, 1)), "star")

    keys = grid.keys
    cols = ", ".join(f"floor(embedding[{i + 1}]::DOUBLE * 5e0)::BIGINT AS {k}" for i, k in enumerate(keys))
    steps = [f"abs(a.{k} - b.{k})" for k in keys]
    near = " + ".join(steps) + " <= 1" if metric == "manhattan" else " AND ".join(f"{x} <= 1" for x in steps)
    sql = f"WITH RECURSIVE sig AS (SELECT {cols}, count(*)::BIGINT AS n FROM embeddings GROUP BY {', '.join(str(i + 1) for i in range(dim))} HAVING count(*) >= {tau}), {_walk(keys, near, mu=2)} SELECT * FROM clusters"
    return run, sql


_add("clusters_3d", *_vector_clusters(3, 3, "chebyshev"))
_add("clusters_emb4", *_vector_clusters(4, 2, "manhattan"))
_add("clusters_emb5", *_vector_clusters(5, 2, "chebyshev"))

# ---------------------------------------------------------------- points with clusters

_ON = f"floor(p.lon_e7 / {CELL['35']!r}e0)::BIGINT = c.tx AND floor(p.lat_e7 / {CELL['35']!r}e0)::BIGINT = c.ty"


def _retained(retain: str, nested: bool = False) -> Callable[[SparkSession, str], DataFrame]:
    def run(s: SparkSession, d: str) -> DataFrame:
        rows = V.tile_clusters_points(hub_points(s, d).select("hub", "lon_e7", "lat_e7"), e7_grid("35"), TileParams(TAU, MU), retain, nested)
        if nested:
            return rows.select("r_tx", "r_ty", "tx", "ty", F.size("points").cast("bigint").alias("held"), F.element_at("points", 1)["lon_e7"].alias("first_lon"))
        return rows.select("r_tx", "r_ty", "tx", "ty", "lon_e7", "lat_e7")
    return run


_DISTINCT = f"WITH RECURSIVE {_HUBS}, once AS (SELECT DISTINCT lon_e7, lat_e7 FROM pts), {_tiles('35', 'once')}, sig AS (SELECT * FROM counts WHERE n >= {TAU}), {_walk()}"
_add("retained_points_all", _retained("all"), _base_sql() + f" SELECT r_tx, r_ty, tx, ty, p.lon_e7, p.lat_e7 FROM pts p JOIN clusters c ON {_ON}")
_add("retained_points_distinct", _retained("distinct"), _DISTINCT + f" SELECT r_tx, r_ty, tx, ty, p.lon_e7, p.lat_e7 FROM once p JOIN clusters c ON {_ON}")
_add("retained_points_nested", _retained("all", True), _base_sql() + f" SELECT r_tx, r_ty, tx, ty, count(*)::BIGINT AS held, min(p.lon_e7) AS first_lon FROM pts p JOIN clusters c ON {_ON} GROUP BY ALL")
_add("retained_points_sliced", lambda s, d: V.sliced_clusters_points(hub_points(s, d).select("lon_e7", "lat_e7"), e7_grid("35"), TileParams(TAU, MU), 8).select("r_tx", "r_ty", "tx", "ty", "lon_e7", "lat_e7"), SQL["retained_points_all"])


def _labelled(s: SparkSession, d: str) -> DataFrame:
    points = _with_noise(s, d)
    return V.label_points(points, stage(tile_clusters(points, e7_grid("35"), TileParams(TAU, MU)), "clusters"), e7_grid("35"))


_LABEL = _base_sql(source="everyone", more=_ALL) + f", labelled AS (SELECT p.hub, c.r_tx, c.r_ty, p.lon_e7, p.lat_e7 FROM everyone p LEFT JOIN clusters c ON {_ON})"
_add("labels_points", lambda s, d: _labelled(s, d).groupBy("hub", F.coalesce("r_tx", F.lit(-1)).alias("r_tx"), F.coalesce("r_ty", F.lit(-1)).alias("r_ty")).agg(F.count("*").alias("points")), _LABEL + " SELECT hub, coalesce(r_tx, -1) AS r_tx, coalesce(r_ty, -1) AS r_ty, count(*)::BIGINT AS points FROM labelled GROUP BY ALL")
_add("noise_share", lambda s, d: M.noise_share(_labelled(s, d), F.col("r_tx")), _LABEL + " SELECT count(*)::BIGINT AS points, count(*) FILTER (WHERE r_tx IS NULL)::BIGINT AS noise, round(count(*) FILTER (WHERE r_tx IS NULL) / count(*), 6) AS share FROM labelled")

# ---------------------------------------------------------------- variants

_WINDOWS = "windows AS (SELECT tx - dx AS wx, ty - dy AS wy, n, n >= {tau} AS dense FROM counts, (VALUES (0), (1)) x(dx), (VALUES (0), (1)) y(dy)), good AS (SELECT wx, wy FROM windows GROUP BY 1, 2 HAVING sum(n) >= {tau} {missed}), held AS (SELECT wx + dx AS tx, wy + dy AS ty FROM good, (VALUES (0), (1)) x(dx), (VALUES (0), (1)) y(dy) UNION SELECT tx, ty FROM counts WHERE n >= {tau})"
for _scope, _missed in (("all", ""), ("missed", "AND NOT bool_or(dense)")):
    _sql = f"WITH RECURSIVE {_HUBS}, {_tiles('4')}, " + _WINDOWS.format(tau=TAU, missed=_missed) + f", sig AS (SELECT counts.* FROM counts SEMI JOIN held USING (tx, ty)), {_walk()}" + _ROWS
    _add(f"rescue_{_scope}", lambda s, d, v=_scope: keep_clusters(agglomerate(V.rescue_windows(stage(count_tiles(hub_points(s, d), e7_grid("4")), "counts"), TAU, v)), MU), _sql)
_add(
    "relax_eps",
    lambda s, d: V.relax(stage(count_tiles(hub_points(s, d), e7_grid("4")), "counts"), TAU, 2, 3),
    f"WITH {_HUBS}, {_tiles('4')}, sig AS (SELECT * FROM counts WHERE n >= {TAU}) SELECT * FROM sig UNION ALL SELECT c.* FROM counts c WHERE n < {TAU} AND n >= {TAU - 2} AND (SELECT count(*) FROM sig b WHERE abs(c.tx - b.tx) <= 1 AND abs(c.ty - b.ty) <= 1) >= 3",
)
_add(
    "adaptive_delta",
    lambda s, d: keep_clusters(V.agglomerate_adaptive(_significant(s, d, "4"), lambda n: F.when(n < 8, 2).otherwise(1), 2), MU),
    _base_sql("4", "abs(a.tx - b.tx) <= greatest(CASE WHEN a.n < 8 THEN 2 ELSE 1 END, CASE WHEN b.n < 8 THEN 2 ELSE 1 END) AND abs(a.ty - b.ty) <= greatest(CASE WHEN a.n < 8 THEN 2 ELSE 1 END, CASE WHEN b.n < 8 THEN 2 ELSE 1 END)") + _ROWS,
)
_add(
    "multi_precision",
    lambda s, d: V.multi_precision(hub_points(s, d), {"p3": e7_grid("3"), "p35": e7_grid("35"), "p4": e7_grid("4")}, TileParams(TAU, MU)).select("level", "r_tx", "r_ty", "tx", "ty", "n"),
    f"WITH RECURSIVE {_HUBS}, " + ", ".join(f"{_tiles(v, name='counts' + v)}, sig{v} AS (SELECT * FROM counts{v} WHERE n >= {TAU}), {_walk(sig='sig' + v, tag=v)}" for v in ("3", "35", "4")) + " " + " UNION ALL ".join(f"SELECT 'p{v}' AS level, r_tx, r_ty, tx, ty, n FROM clusters{v}" for v in ("3", "35", "4")),
)
_add(
    "refine_dense",
    lambda s, d: V.refine(hub_points(s, d).select("lon_e7", "lat_e7"), Grid(("lon_e7", "lat_e7"), scale=0.0001), 100, 2, 2),
    f"""WITH {_HUBS}, l0 AS (SELECT *, floor(lon_e7 * 0.0001e0)::BIGINT AS tx, floor(lat_e7 * 0.0001e0)::BIGINT AS ty FROM pts), c0 AS (SELECT tx, ty, count(*)::BIGINT AS n FROM l0 GROUP BY 1, 2),
l1 AS (SELECT lon_e7, lat_e7, floor(lon_e7 * 0.0002e0)::BIGINT AS tx, floor(lat_e7 * 0.0002e0)::BIGINT AS ty FROM l0 SEMI JOIN (SELECT tx, ty FROM c0 WHERE n > 100) h USING (tx, ty)), c1 AS (SELECT tx, ty, count(*)::BIGINT AS n FROM l1 GROUP BY 1, 2),
l2 AS (SELECT floor(lon_e7 * 0.0004e0)::BIGINT AS tx, floor(lat_e7 * 0.0004e0)::BIGINT AS ty FROM l1 SEMI JOIN (SELECT tx, ty FROM c1 WHERE n > 100) h USING (tx, ty)), c2 AS (SELECT tx, ty, count(*)::BIGINT AS n FROM l2 GROUP BY 1, 2)
SELECT 0 AS level, tx, ty, n FROM c0 WHERE n <= 100 UNION ALL SELECT 1, tx, ty, n FROM c1 WHERE n <= 100 UNION ALL SELECT 2, tx, ty, n FROM c2""",
)
_add(
    "coarsen_sparse",
    lambda s, d: V.coarsen(stage(count_tiles(hub_points(s, d), e7_grid("4")), "counts"), TAU, 2),
    f"WITH {_HUBS}, {_tiles('4')} SELECT 0 AS level, tx, ty, n FROM counts WHERE n >= {TAU} UNION ALL SELECT 1, floor(tx / 2e0)::BIGINT, floor(ty / 2e0)::BIGINT, sum(n)::BIGINT FROM counts WHERE n < {TAU} GROUP BY 2, 3 HAVING sum(n) >= {TAU}",
)
_add(
    "shade_levels",
    lambda s, d: V.shade(_clusters(s, d), 4).select("r_tx", "r_ty", "tx", "ty", "n", "shade"),
    _base_sql() + " SELECT r_tx, r_ty, tx, ty, n, (least(CASE WHEN max(n) OVER w > min(n) OVER w THEN floor((n - min(n) OVER w) * 4 / (max(n) OVER w - min(n) OVER w)) ELSE 0 END, 3) + 1)::INTEGER AS shade FROM clusters WINDOW w AS (PARTITION BY r_tx, r_ty)",
)
_add(
    "ellipse_cov",
    lambda s, d: covariance_ellipse(_clusters(s, d)).select("r_tx", "r_ty", "points", F.round("cx", 4).alias("cx"), F.round("cy", 4).alias("cy"), F.round("major", 3).alias("major"), F.round("minor", 3).alias("minor")),
    _base_sql() + ", m AS (SELECT r_tx, r_ty, sum(n)::BIGINT AS points, sum(n * tx) / sum(n) AS cx, sum(n * ty) / sum(n) AS cy, sum(n * tx * tx) / sum(n) - pow(sum(n * tx) / sum(n), 2) AS vx, sum(n * ty * ty) / sum(n) - pow(sum(n * ty) / sum(n), 2) AS vy, sum(n * tx * ty) / sum(n) - (sum(n * tx) / sum(n)) * (sum(n * ty) / sum(n)) AS vxy FROM clusters GROUP BY 1, 2) SELECT r_tx, r_ty, points, round(cx, 4) AS cx, round(cy, 4) AS cy, round(2 * sqrt(greatest((vx + vy) / 2 + sqrt(pow((vx - vy) / 2, 2) + vxy * vxy), 0)), 3) AS major, round(2 * sqrt(greatest((vx + vy) / 2 - sqrt(pow((vx - vy) / 2, 2) + vxy * vxy), 0)), 3) AS minor FROM m",
)
_add("ellipse_least", lambda s, d: least_ellipse(_clusters(s, d), e7_grid("35")))
_add("ellipse_least_points", lambda s, d: least_ellipse(V.tile_clusters_points(hub_points(s, d).select("lon_e7", "lat_e7"), e7_grid("35"), TileParams(TAU, MU)), e7_grid("35"), "points"))

# ---------------------------------------------------------------- the hub problem

_add(
    "hubs",
    lambda s, d: H.hubs(_clusters(s, d), e7_grid("35"), 1e-7).select("r_tx", "r_ty", "tiles", "points", F.round("x", 2).alias("x"), F.round("y", 2).alias("y"), "tx_min", "tx_max", "ty_min", "ty_max", F.col("densest.tx").alias("dense_tx"), F.col("densest.ty").alias("dense_ty")),
    _base_sql() + f" SELECT r_tx, r_ty, count(*)::BIGINT AS tiles, sum(n)::BIGINT AS points, round(sum(n * ((tx + 0.5e0) / (1e0 / {CELL['35']!r}e0))) / sum(n), 2) AS x, round(sum(n * ((ty + 0.5e0) / (1e0 / {CELL['35']!r}e0))) / sum(n), 2) AS y, min(tx) AS tx_min, max(tx) AS tx_max, min(ty) AS ty_min, max(ty) AS ty_max, arg_max(tx, struct_pack(n := n, a := tx, b := ty)) AS dense_tx, arg_max(ty, struct_pack(n := n, a := tx, b := ty)) AS dense_ty FROM clusters GROUP BY 1, 2",
)
_CENTRES = f"h AS (SELECT r_tx AS tx, r_ty AS ty, count(*) AS n, sum(n * ((tx + 0.5e0) * {CELL['35']!r}e0)) / sum(n) * 1e-7 AS lon, sum(n * ((ty + 0.5e0) * {CELL['35']!r}e0)) / sum(n) * 1e-7 AS lat FROM clusters GROUP BY 1, 2)"
_METRES = "2 * 6371008.8 * asin(least(1.0, sqrt(pow(sin(radians(b.lat - a.lat) / 2), 2) + cos(radians(a.lat)) * cos(radians(b.lat)) * pow(sin(radians(b.lon - a.lon) / 2), 2))))"
_add("near_hubs", lambda s, d: H.near_hubs(stage(H.hubs(_clusters(s, d), e7_grid("35"), 1e-7), "hubs"), 1000.0, 1e-7).select("hub.r_tx", "hub.r_ty", F.col("other.r_tx").alias("o_tx"), F.col("other.r_ty").alias("o_ty"), F.round("metres", 3).alias("metres")), _base_sql() + f", {_CENTRES} SELECT a.tx AS r_tx, a.ty AS r_ty, b.tx AS o_tx, b.ty AS o_ty, round({_METRES}, 3) AS metres FROM h a JOIN h b ON (a.tx, a.ty) < (b.tx, b.ty) AND {_METRES} < 1000")


def _merged(s: SparkSession, d: str) -> DataFrame:
    clusters = _staged_clusters(s, d)
    pairs = H.near_hubs(stage(H.hubs(clusters, e7_grid("35"), 1e-7), "hubs"), 1000.0, 1e-7)
    return H.merge_near_hubs(clusters, stage(pairs, "pairs"))


_add("merge_near_hubs", _merged, _base_sql() + f", {_CENTRES}, {_walk(near=_METRES + ' < 1000', sig='h', mu=1, tag='m')} SELECT m.r_tx, m.r_ty, c.tx, c.ty, c.n FROM clusters c JOIN clustersm m ON c.r_tx = m.tx AND c.r_ty = m.ty")
_TRIP_ROWS = f"WITH RECURSIVE {_HUBS}, {_TRIPS}, {_tiles('35')}, sig AS (SELECT * FROM counts WHERE n >= {TAU}), {_walk()}, met AS (SELECT p.*, c.r_tx, c.r_ty FROM trips p JOIN clusters c ON {_ON})"
_add(
    "hub_vehicles",
    lambda s, d: H.hub_vehicles(hub_points(s, d, trips=True), _staged_clusters(s, d), e7_grid("35")).select("r_tx", "r_ty", "vehicles", "points"),
    _TRIP_ROWS + " SELECT r_tx, r_ty, count(DISTINCT vehicle)::BIGINT AS vehicles, count(*)::BIGINT AS points FROM met GROUP BY 1, 2",
)


def _visits(s: SparkSession, d: str) -> DataFrame:
    return H.visits(hub_points(s, d, trips=True), _staged_clusters(s, d), e7_grid("35"), "30 days")


_VISITS = (
    _TRIP_ROWS
    + """, marked AS (SELECT *, CASE WHEN lag(r_tx) OVER w = r_tx AND lag(r_ty) OVER w = r_ty AND tm <= lag(tm) OVER w + INTERVAL 30 DAY THEN 0 ELSE 1 END AS opens
FROM met WINDOW w AS (PARTITION BY vehicle ORDER BY tm, r_tx, r_ty, lon_e7, lat_e7)),
numbered AS (SELECT *, sum(opens) OVER (PARTITION BY vehicle ORDER BY tm, r_tx, r_ty, lon_e7, lat_e7 ROWS UNBOUNDED PRECEDING)::BIGINT AS visit FROM marked),
visits AS (SELECT vehicle, visit, r_tx, r_ty, min(tm) AS arrive, max(tm) AS leave, count(*)::BIGINT AS rows FROM numbered GROUP BY ALL)"""
)
_SECONDS = "epoch({0})::BIGINT"
_add("visits", lambda s, d: _visits(s, d).select("vehicle", "visit", "r_tx", "r_ty", F.unix_timestamp("arrive").alias("arrive_s"), F.unix_timestamp("leave").alias("leave_s"), "rows"), _VISITS + f" SELECT vehicle, visit, r_tx, r_ty, {_SECONDS.format('arrive')} AS arrive_s, {_SECONDS.format('leave')} AS leave_s, rows FROM visits")
_add(
    "hub_network",
    lambda s, d: H.hub_network(_visits(s, d)).select(F.col("src.r_tx").alias("s_tx"), F.col("src.r_ty").alias("s_ty"), F.col("dst.r_tx").alias("d_tx"), F.col("dst.r_ty").alias("d_ty"), "trips"),
    _VISITS + ", nxt AS (SELECT r_tx AS s_tx, r_ty AS s_ty, lead(r_tx) OVER w AS d_tx, lead(r_ty) OVER w AS d_ty FROM visits WINDOW w AS (PARTITION BY vehicle ORDER BY visit)) SELECT *, count(*)::BIGINT AS trips FROM nxt WHERE d_tx IS NOT NULL AND (s_tx, s_ty) <> (d_tx, d_ty) GROUP BY ALL",
)
_PART = "year(arrive)::INTEGER AS year, (dayofweek(arrive) + 1)::INTEGER AS weekday"
for _shape in ("cube", "rollup"):
    _add(
        f"usage_{_shape}",
        lambda s, d, v=_shape: H.usage_profile(_visits(s, d).select("vehicle", "arrive", F.col("r_ty")), ("year", "weekday"), v).select("r_ty", "year", "weekday", F.col("grouping").cast("bigint").alias("grouping"), "visits", "vehicles").withColumnRenamed("r_ty", "hub_row"),
        _VISITS + f", t AS (SELECT vehicle, r_ty AS hub_row, {_PART} FROM visits) SELECT hub_row, year, weekday, grouping(hub_row, year, weekday)::BIGINT AS grouping, count(*)::BIGINT AS visits, count(DISTINCT vehicle)::BIGINT AS vehicles FROM t GROUP BY {_shape.upper()} (hub_row, year, weekday)",
    )
_add(
    "usage_pivot",
    lambda s, d: H.usage_pivot(_visits(s, d)).select("r_tx", "r_ty", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"d{i}") for i in range(1, 8)]),
    _VISITS + " SELECT r_tx, r_ty, " + ", ".join(f"count(*) FILTER (WHERE dayofweek(arrive) + 1 = {i})::BIGINT AS d{i}" for i in range(1, 8)) + " FROM visits GROUP BY 1, 2",
)


def _orders_as_events(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").select(F.col("o_custkey").alias("vehicle"), F.col("o_orderdate").cast("timestamp").alias("at"))


_add(
    "asof_visit",
    lambda s, d: H.as_of_visit(_orders_as_events(s, d), stage(_visits(s, d), "visits")).where("visit is not null").groupBy("vehicle", "visit", "r_tx", "r_ty").agg(F.count("*").alias("events")),
    _VISITS + ", ev AS (SELECT o_custkey AS vehicle, o_orderdate::TIMESTAMP AS tm FROM orders), best AS (SELECT e.vehicle, e.tm, v.visit, v.r_tx, v.r_ty FROM ev e ASOF JOIN (SELECT * FROM visits QUALIFY row_number() OVER (PARTITION BY vehicle, arrive ORDER BY visit DESC) = 1) v ON e.vehicle = v.vehicle AND e.tm >= v.arrive) SELECT vehicle, visit, r_tx, r_ty, count(*)::BIGINT AS events FROM best GROUP BY ALL",
)
_add(
    "interval_events",
    lambda s, d: H.events_in_visits(_orders_as_events(s, d), stage(_visits(s, d), "visits")).groupBy("vehicle", "visit").agg(F.count("*").alias("events")),
    _VISITS + ", ev AS (SELECT o_custkey AS vehicle, o_orderdate::TIMESTAMP AS tm FROM orders) SELECT v.vehicle, v.visit, count(*)::BIGINT AS events FROM ev e JOIN visits v ON e.vehicle = v.vehicle AND e.tm BETWEEN v.arrive AND v.leave GROUP BY ALL",
)
_add("top_tiles", lambda s, d: H.top_tiles(_clusters(s, d), 2).select("r_tx", "r_ty", "tx", "ty", "n", "place"), _base_sql() + " SELECT r_tx, r_ty, tx, ty, n, row_number() OVER (PARTITION BY r_tx, r_ty ORDER BY n DESC, tx, ty)::INTEGER AS place FROM clusters QUALIFY place <= 2")


def _lateral_top(s: SparkSession, d: str) -> DataFrame:
    hub_points(s, d).groupBy("hub").agg(F.count("*").alias("n")).createOrReplaceTempView("_hub_sizes")
    table(s, d, "supplier").createOrReplaceTempView("_supplier")
    table(s, d, "nation").createOrReplaceTempView("_nation")
    return s.sql("SELECT n_name, t.hub, t.n FROM _nation, LATERAL (SELECT hub, n FROM _hub_sizes JOIN _supplier ON hub = s_suppkey WHERE s_nationkey = n_nationkey ORDER BY n DESC, hub LIMIT 2) t")


_add("lateral_top_hubs", _lateral_top, f"WITH {_HUBS}, sizes AS (SELECT hub, count(*)::BIGINT AS n FROM pts GROUP BY 1) SELECT n_name, hub, n FROM sizes JOIN supplier ON hub = s_suppkey JOIN nation ON s_nationkey = n_nationkey QUALIFY row_number() OVER (PARTITION BY n_nationkey ORDER BY n DESC, hub) <= 2")
_add(
    "region_rollup",
    lambda s, d: hub_points(s, d).groupBy("hub").agg(F.count("*").alias("n")).join(table(s, d, "supplier"), F.col("hub") == F.col("s_suppkey")).join(F.broadcast(table(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("hubs"), F.sum("n").alias("points")),
    f"WITH {_HUBS}, sizes AS (SELECT hub, count(*) AS n FROM pts GROUP BY 1) SELECT r_name, n_name, count(*)::BIGINT AS hubs, sum(n)::BIGINT AS points FROM sizes JOIN supplier ON hub = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
)


def _day_tiles(s: SparkSession, d: str, day: int) -> DataFrame:
    return table(s, d, "events").where(F.dayofmonth("ts") == day).select((F.floor(F.col("user_id") / 10)).alias("tx"), F.floor(F.col("value") / 10).alias("ty"))


_add("set_ops_days", lambda s, d: _day_tiles(s, d, 3).intersect(_day_tiles(s, d, 4)).withColumn("kind", F.lit("both")).unionByName(_day_tiles(s, d, 3).exceptAll(_day_tiles(s, d, 4)).withColumn("kind", F.lit("more"))), "WITH t AS (SELECT dayofmonth(ts) AS day, floor(user_id / 10e0)::BIGINT AS tx, floor(value / 10e0)::BIGINT AS ty FROM events) SELECT *, 'both' AS kind FROM (SELECT tx, ty FROM t WHERE day = 3 INTERSECT SELECT tx, ty FROM t WHERE day = 4) UNION ALL SELECT *, 'more' FROM (SELECT tx, ty FROM t WHERE day = 3 EXCEPT ALL SELECT tx, ty FROM t WHERE day = 4)")

_COUNTS4 = f"WITH {_HUBS}, {_tiles('4')}"


def _counts4(s: SparkSession, d: str) -> DataFrame:
    return count_tiles(hub_points(s, d), e7_grid("4"))


_add("tau_sweep", lambda s, d: A.tau_sweep(_counts4(s, d), [1, 3, 5, 8, 12]), _COUNTS4 + " SELECT tau, count(*)::BIGINT AS tiles, sum(n)::BIGINT AS points FROM counts, (VALUES (1), (3), (5), (8), (12)) t(tau) WHERE n >= tau GROUP BY 1")
_add("parameter_grid", lambda s, d: A.parameter_grid(s, _counts4(s, d), [5, 10], [1, 2, 3]), _COUNTS4 + ", c AS (SELECT tau, factor, floor(tx / factor)::BIGINT AS tx, floor(ty / factor)::BIGINT AS ty, sum(n) AS n FROM counts, (VALUES (5), (10)) t(tau), (VALUES (1), (2), (3)) f(factor) GROUP BY 1, 2, 3, 4 HAVING sum(n) >= tau) SELECT tau, factor, count(*)::BIGINT AS tiles, sum(n)::BIGINT AS points FROM c GROUP BY 1, 2")
_DAILY = "SELECT datediff('day', DATE '2024-01-01', ts::DATE)::INTEGER AS day, floor(user_id / 50e0)::BIGINT AS tx, floor(value / 50e0)::BIGINT AS ty, count(*)::BIGINT AS n FROM events GROUP BY 1, 2, 3"
_add(
    "moving_counts",
    lambda s, d: A.moving_counts(table(s, d, "events").select(F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("day"), F.floor(F.col("user_id") / 50).alias("tx"), F.floor(F.col("value") / 50).alias("ty")).groupBy("day", "tx", "ty").agg(F.count("*").alias("n")), 7),
    f"WITH c AS ({_DAILY}) SELECT *, (sum(n) OVER (PARTITION BY tx, ty ORDER BY day RANGE BETWEEN 6 PRECEDING AND CURRENT ROW))::BIGINT AS moving FROM c",
)
_add(
    "rank_tiles",
    lambda s, d: A.rank_tiles(_clusters(s, d)),
    _base_sql() + " SELECT r_tx, r_ty, tx, ty, n, (rank() OVER b)::INTEGER AS rank, (dense_rank() OVER b)::INTEGER AS dense_rank, (row_number() OVER k)::INTEGER AS row_number, (ntile(4) OVER k)::INTEGER AS quarter, round(percent_rank() OVER b, 6) AS percent_rank, first_value(n) OVER k AS top, nth_value(n, 2) OVER w AS second FROM clusters WINDOW b AS (PARTITION BY r_tx, r_ty ORDER BY n DESC), k AS (PARTITION BY r_tx, r_ty ORDER BY n DESC, tx, ty), w AS (PARTITION BY r_tx, r_ty ORDER BY n DESC, tx, ty ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
)
_add(
    "compare_counts",
    lambda s, d: A.compare_counts(_counts4(s, d), count_tiles(hub_points(s, d), Grid(precision=4))),
    _COUNTS4 + ", other AS (SELECT floor((lon_e7 / 1e7) * 10000e0)::BIGINT AS tx, floor((lat_e7 / 1e7) * 10000e0)::BIGINT AS ty, count(*)::BIGINT AS n FROM pts GROUP BY 1, 2) SELECT tx, ty, coalesce(a.n, 0) AS n_a, coalesce(b.n, 0) AS n_b FROM counts a FULL JOIN other b USING (tx, ty) WHERE coalesce(a.n, 0) <> coalesce(b.n, 0)",
)
_add("noise_tiles", lambda s, d: A.noise_tiles(_counts4(s, d), _clusters(s, d, "4")), _base_sql("4") + " SELECT counts.* FROM counts ANTI JOIN clusters USING (tx, ty)")
_add("densest_tiles", lambda s, d: A.densest(_counts4(s, d), 25), _COUNTS4 + " SELECT tx, ty, n FROM counts ORDER BY n DESC, tx, ty LIMIT 25")
_add("column_profile", lambda s, d: A.column_profile(_counts4(s, d)), _COUNTS4 + ", c AS (SELECT tx, sum(n)::BIGINT AS n, count(*)::BIGINT AS tiles FROM counts GROUP BY 1) SELECT *, (sum(n) OVER (ORDER BY tx))::BIGINT AS upto FROM c")
_add("vehicle_sketches", lambda s, d: A.vehicle_sketches(hub_points(s, d, trips=True), ["hub"], "vehicle"))
_add("heavy_tiles", lambda s, d: A.heavy_tiles(hub_points(s, d).select(F.floor(F.col("lon_e7") / 10000).alias("tx"), F.floor(F.col("lat_e7") / 10000).alias("ty")), ["tx", "ty"], 0.004).select("tx", "ty", "n"), f"WITH {_HUBS}, {_tiles('3')} SELECT tx, ty, n FROM counts WHERE n >= 0.004 * (SELECT count(*) FROM pts)")
_add("by_type_and_day", lambda s, d: A.by_type_and_day(table(s, d, "events")).select("event_type", F.date_format("day", "yyyy-MM-dd").alias("day"), "level", "n"), "SELECT event_type, strftime(ts::DATE, '%Y-%m-%d') AS day, grouping(event_type, ts::DATE)::BIGINT AS level, count(*)::BIGINT AS n FROM events GROUP BY GROUPING SETS ((event_type), (ts::DATE), ())")
_add(
    "usage_long",
    lambda s, d: A.long_profile(H.usage_pivot(_visits(s, d)).select("r_tx", "r_ty", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"d{i}") for i in range(1, 8)]), ["r_tx", "r_ty"], [f"d{i}" for i in range(1, 8)]),
    _VISITS + ", days AS (SELECT 'd' || k AS part, k FROM range(1, 8) r(k)) SELECT r_tx, r_ty, part, count(*) FILTER (WHERE dayofweek(arrive) + 1 = k)::BIGINT AS visits FROM visits, days GROUP BY 1, 2, 3",
)
_add("props_by_tile", lambda s, d: table(s, d, "events").select(F.floor(F.col("user_id") / 10).alias("tx"), Q.props_number(F.col("props")).alias("k")).groupBy("tx").agg(F.sum("k").alias("total"), F.max("k").alias("most")), "SELECT floor(user_id / 10e0)::BIGINT AS tx, sum((props::JSON ->> 'k')::INTEGER)::BIGINT AS total, max((props::JSON ->> 'k')::INTEGER) AS most FROM events GROUP BY 1")

# ---------------------------------------------------------------- measures


def _hub_labels(s: SparkSession, d: str, level: str = "35") -> DataFrame:
    points = hub_points(s, d).select("hub", "lon_e7", "lat_e7")
    return V.label_points(points, stage(_clusters(s, d, level), "clusters"), e7_grid(level))


def _found(s: SparkSession, d: str, level: str) -> DataFrame:
    return M.found_ratio(_clusters(s, d, level), table(s, d, "supplier").count())


for _level in CELL:
    _cell = f"{CELL[_level]!r}e0"
    _at = f"floor(p.lon_e7 / {_cell})::BIGINT = c.tx AND floor(p.lat_e7 / {_cell})::BIGINT = c.ty"
    _add(f"found_ratio_p{_level}", lambda s, d, v=_level: _found(s, d, v), _base_sql(_level) + " SELECT count(*)::BIGINT AS found, round(count(*) * 100.0 / (SELECT count(*) FROM supplier), 6)::DOUBLE AS percent FROM (SELECT DISTINCT r_tx, r_ty FROM clusters)")
    _add(
        f"matched_ratio_p{_level}",
        lambda s, d, v=_level: M.matched_ratio(_hub_labels(s, d, v)),
        _base_sql(_level) + f", pairs AS (SELECT DISTINCT p.hub, c.r_tx, c.r_ty FROM pts p JOIN clusters c ON {_at}), one AS (SELECT min(hub) AS hub FROM pairs GROUP BY r_tx, r_ty HAVING count(*) = 1), single AS (SELECT hub FROM pairs GROUP BY hub HAVING count(*) = 1), total AS (SELECT count(DISTINCT hub)::BIGINT AS hubs FROM pts) SELECT (SELECT count(*) FROM one SEMI JOIN single USING (hub))::BIGINT AS matched, hubs, round((SELECT count(*) FROM one SEMI JOIN single USING (hub)) * 100.0 / hubs, 6)::DOUBLE AS percent FROM total",
    )
_LAB = _base_sql() + f", l AS (SELECT p.hub, c.r_tx * 1000000 + c.r_ty AS label, p.lon_e7 / 1e4 AS x, p.lat_e7 / 1e4 AS y FROM pts p JOIN clusters c ON {_ON})"


def _numbered(s: SparkSession, d: str) -> DataFrame:
    return _hub_labels(s, d).select("hub", (F.col("r_tx") * 1000000 + F.col("r_ty")).alias("label"), (F.col("lon_e7") / 1e4).alias("x"), (F.col("lat_e7") / 1e4).alias("y"))


_add(
    "silhouette_sq",
    lambda s, d: M.silhouette_fast(_numbered(s, d), ("x", "y"), "label").select(F.round("silhouette", 4).alias("silhouette"), "points"),
    _LAB + ", st AS (SELECT label AS k, count(*) AS m, sum(x) AS sx, sum(y) AS sy, sum(x * x + y * y) AS q FROM l GROUP BY 1), d AS (SELECT l.label, x, y, k, m, greatest(x * x + y * y + q / m - 2 * (x * sx + y * sy) / m, 0) AS d FROM (SELECT DISTINCT label, x, y FROM l) l, st), ab AS (SELECT label, x, y, max(d * m / (m - 1)) FILTER (WHERE k = label AND m > 1) AS a, min(d) FILTER (WHERE k <> label) AS b FROM d GROUP BY 1, 2, 3) SELECT round(sum(CASE WHEN a IS NULL OR b IS NULL OR greatest(a, b) = 0 THEN 0 ELSE (b - a) / greatest(a, b) END) / count(*), 4) AS silhouette, count(*)::BIGINT AS points FROM l JOIN ab USING (label, x, y)",
)
_add(
    "silhouette_exact",
    lambda s, d: M.silhouette(_numbered(s, d), ("x", "y"), "label").select(F.round("silhouette", 4).alias("silhouette"), "points"),
    # b(i) is sought among the clusters whose centre is no farther than the least root mean square
    _LAB + """, st AS (SELECT label AS k, count(*) AS m, avg(x) AS cx, avg(y) AS cy, var_pop(x) + var_pop(y) AS v FROM l GROUP BY 1),
    place AS (SELECT label, x, y, count(*) AS w FROM l GROUP BY 1, 2, 3),
    near AS (SELECT label, x, y, w, k, m, sqrt((x - cx) ** 2 + (y - cy) ** 2) AS low, min(CASE WHEN k <> label THEN sqrt((x - cx) ** 2 + (y - cy) ** 2 + v) END) OVER (PARTITION BY label, x, y) AS high FROM place, st),
    met AS (SELECT n.label, n.x, n.y, n.w, n.k, n.m, sum(o.w * sqrt((n.x - o.x) ** 2 + (n.y - o.y) ** 2)) AS total FROM near n JOIN place o ON o.label = n.k WHERE n.k = n.label OR n.low <= n.high * (1 + 1e-9) GROUP BY ALL),
    ab AS (SELECT label, x, y, w, max(total / (m - 1)) FILTER (WHERE k = label AND m > 1) AS a, min(total / m) FILTER (WHERE k <> label) AS b FROM met GROUP BY 1, 2, 3, 4)
    SELECT round(sum(w * CASE WHEN a IS NULL OR b IS NULL OR greatest(a, b) = 0 THEN 0 ELSE (b - a) / greatest(a, b) END) / sum(w), 4) AS silhouette, sum(w)::BIGINT AS points FROM ab""",
)
_add(
    "pair_scores",
    lambda s, d: M.pair_scores(_numbered(s, d), "hub", "label"),
    _LAB + ", c AS (SELECT hub, label, count(*)::DOUBLE AS n FROM l GROUP BY 1, 2), h AS (SELECT sum(n) AS n FROM c GROUP BY hub), g AS (SELECT sum(n) AS n, max(n) AS top FROM c GROUP BY label), v AS (SELECT (SELECT sum(n * (n - 1) / 2) FROM c) AS s, (SELECT sum(n * (n - 1) / 2) FROM h) AS sh, (SELECT sum(n * (n - 1) / 2) FROM g) AS sg, (SELECT sum(top) FROM g) AS top, (SELECT sum(n) FROM c) AS n) SELECT round((s - sh * sg / (n * (n - 1) / 2)) / ((sh + sg) / 2 - sh * sg / (n * (n - 1) / 2)), 6) AS ari, round(top / n, 6) AS purity, n::BIGINT AS points FROM v",
)
_add("reduction", lambda s, d: H.reduction(hub_points(s, d), _clusters(s, d)).select("points", "tiles", F.round("ratio", 6).alias("ratio")), _base_sql() + " SELECT (SELECT count(*) FROM pts)::BIGINT AS points, count(*)::BIGINT AS tiles, round((SELECT count(*) FROM pts) / count(*), 6) AS ratio FROM clusters")
_add("memory_report", lambda s, d: M.memory_report(count_tiles(hub_points(s, d), e7_grid("4"))), f"WITH {_HUBS}, {_tiles('4')} SELECT count(*)::BIGINT AS tiles, (count(*) * 24)::BIGINT AS bytes, sum(n)::BIGINT AS points FROM counts")
_add("overlap_precisions", lambda s, d: M.overlap(stage(V.roll_up(_clusters(s, d, "4").select("tx", "ty", "n"), 1).join(_clusters(s, d, "4").select("r_tx", "r_ty", "tx", "ty"), ["tx", "ty"]), "a"), stage(_clusters(s, d, "4", near=Neighborhood("manhattan", 1)), "b")).select(F.col("a.r_tx").alias("a_tx"), F.col("a.r_ty").alias("a_ty"), F.col("b.r_tx").alias("b_tx"), F.col("b.r_ty").alias("b_ty"), "shared", F.round("jaccard", 6).alias("jaccard")), f"WITH RECURSIVE {_HUBS}, {_tiles('4')}, sig AS (SELECT * FROM counts WHERE n >= {TAU}), {_walk()}, {_walk(near='abs(a.tx - b.tx) + abs(a.ty - b.ty) <= 1', tag='2')}, na AS (SELECT r_tx, r_ty, count(*) AS n FROM clusters GROUP BY 1, 2), nb AS (SELECT r_tx, r_ty, count(*) AS n FROM clusters2 GROUP BY 1, 2), met AS (SELECT a.r_tx AS a_tx, a.r_ty AS a_ty, b.r_tx AS b_tx, b.r_ty AS b_ty, count(*)::BIGINT AS shared FROM clusters a JOIN clusters2 b USING (tx, ty) GROUP BY 1, 2, 3, 4) SELECT a_tx, a_ty, b_tx, b_ty, shared, round(shared / (na.n + nb.n - shared), 6) AS jaccard FROM met JOIN na ON na.r_tx = a_tx AND na.r_ty = a_ty JOIN nb ON nb.r_tx = b_tx AND nb.r_ty = b_ty")

# ---------------------------------------------------------------- baselines (statistics or sets; no SQL)

_AXES = ("x", "y")


def _plane(s: SparkSession, d: str) -> DataFrame:
    return hub_points(s, d).select("hub", (F.col("lon_e7") / 1e4).alias("x"), (F.col("lat_e7") / 1e4).alias("y"))


def _scored(run: Callable[[DataFrame, int], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    def query(s: SparkSession, d: str) -> DataFrame:
        hubs = table(s, d, "supplier").count()
        labelled = stage(run(_plane(s, d), hubs).select("hub", "label"), "baseline")
        return M.matched_ratio(labelled, "hub", ["label"]).withColumn("status", F.lit("computed"))
    return query


_BASELINES: dict[str, Callable[[DataFrame, int], DataFrame]] = {
    "kmeans": lambda p, k: baselines.kmeans(p, _AXES, k),
    "minibatch_kmeans": lambda p, k: baselines.minibatch_kmeans(p, _AXES, k),
    "gaussian_mixture": lambda p, k: baselines.gaussian_mixture(p, _AXES, k),
    "mean_shift": lambda p, k: baselines.mean_shift(p, _AXES, 1.0),
    "dbscan": lambda p, k: baselines.dbscan(p, _AXES, 0.2, 5),
    "dbscan_pairs": lambda p, k: baselines.dbscan(p, _AXES, 0.2, 5, "pairs"),
    "dbscan_cells": lambda p, k: baselines.dbscan(p, _AXES, 0.2, 5, "cells"),
    "dbscan_multi": lambda p, k: baselines.dbscan_multi(p, _AXES, [0.1, 0.2], 5),
    "birch": lambda p, k: baselines.birch(p, _AXES, 0.3, 50, k),
}
for _name, _run in _BASELINES.items():
    _add(f"baseline_{_name}", _scored(_run))


def _capped(run: Callable[[DataFrame, int], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    """A quadratic method either scores or says by its status which size it refuses."""
    def query(s: SparkSession, d: str) -> DataFrame:
        try:
            return _scored(run)(s, d)
        except baselines.BaselineTooLarge as e:
            hubs = table(s, d, "supplier").count()
            return s.createDataFrame([(None, hubs, None, f"refused: {e}")], "matched bigint, hubs bigint, percent double, status string")
    return query


for _link in ("average", "single", "complete"):
    _add(f"baseline_linkage_{_link}", _capped(lambda p, k, v=_link: baselines.linkage_by_parts(p, _AXES, k, v, 0.4)))
_add("baseline_linkage_ward", _capped(lambda p, k: baselines.ward(p, _AXES, k)))
_add("baseline_single_linkage", _capped(lambda p, k: baselines.single_linkage(p, _AXES, k, 0.1)))
_add("baseline_spectral", _capped(lambda p, k: baselines.spectral(p, _AXES, k)))
_add("baseline_affinity", _capped(lambda p, k: baselines.affinity_propagation(p, _AXES)))


def _clique_sql(xi: int, density: float) -> str:
    return f"""WITH RECURSIVE {_HUBS}, p AS (SELECT lon_e7 / 1e4 AS x, lat_e7 / 1e4 AS y FROM pts), ends AS (SELECT min(x) AS lx, (max(x) - min(x)) / {xi} AS wx, min(y) AS ly, (max(y) - min(y)) / {xi} AS wy, count(*) AS rows FROM p),
u AS (SELECT least(floor((x - lx) / wx), {xi - 1})::BIGINT AS tx, least(floor((y - ly) / wy), {xi - 1})::BIGINT AS ty, rows FROM p, ends), d1 AS (SELECT tx FROM u GROUP BY tx HAVING count(*) >= {density} * any_value(rows)), d2 AS (SELECT ty FROM u GROUP BY ty HAVING count(*) >= {density} * any_value(rows)),
sig AS (SELECT tx, ty, count(*)::BIGINT AS n FROM u WHERE tx IN (SELECT tx FROM d1) AND ty IN (SELECT ty FROM d2) GROUP BY 1, 2 HAVING count(*) >= {density} * any_value(rows))"""


_add("clique_units", lambda s, d: baselines.full_units(_plane(s, d), _AXES, 300, 0.0002).select(F.col("u0").alias("tx"), F.col("u1").alias("ty"), "n"), _clique_sql(300, 0.0002) + " SELECT tx, ty, n FROM sig")
_add("clique_clusters", lambda s, d: baselines.clique(_plane(s, d), _AXES, 300, 0.0002), _clique_sql(300, 0.0002) + ", " + _walk(near="abs(a.tx - b.tx) + abs(a.ty - b.ty) <= 1", mu=1) + _ROWS)

# ---------------------------------------------------------------- streams


def _event_stream(s: SparkSession, d: str) -> DataFrame:
    path = f"{d}/events.parquet"
    schema = s.read.parquet(path).schema
    return S.timed_points(s.readStream.schema(schema).option("maxFilesPerTrigger", 4).parquet(path.replace("events.parquet", "events.parque[t]"))).withColumns({"x": F.floor(F.col("user_id") / 10), "y": F.floor(F.col("value") / 10)})


_XY = Grid(("x", "y"), scale=1.0)
_EXY = "floor(user_id / 10e0)::BIGINT AS tx, floor(value / 10e0)::BIGINT AS ty"
_add("stream_running", lambda s, d: S.run_once(S.stream_counts(_event_stream(s, d), _XY)), f"SELECT {_EXY}, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
_add("stream_daily", lambda s, d: S.run_once(S.stream_counts(_event_stream(s, d), _XY, "1 day")).select(F.unix_timestamp("start").alias("start_s"), "tx", "ty", "n"), f"SELECT (epoch(date_trunc('day', ts)))::BIGINT AS start_s, {_EXY}, count(*)::BIGINT AS n FROM events GROUP BY 1, 2, 3")
_SLIDE = f"SELECT (epoch(date_trunc('day', ts)) - k * 86400)::BIGINT AS start_s, {_EXY}, count(*)::BIGINT AS n FROM events, range(0, 7) r(k) GROUP BY 1, 2, 3"
_add("stream_sliding", lambda s, d: S.run_once(S.stream_counts(_event_stream(s, d), _XY, "7 days", "1 day")).select(F.unix_timestamp("start").alias("start_s"), "tx", "ty", "n"), _SLIDE)
_add("sliding_from_panes", lambda s, d: S.sliding_from_panes(S.run_once(S.stream_counts(_event_stream(s, d), _XY, "1 day")), 7, 86400).select(F.unix_timestamp("start").alias("start_s"), "tx", "ty", "n"), _SLIDE)
_add(
    "stream_session",
    lambda s, d: S.run_once(S.stream_sessions(_event_stream(s, d), _XY, "12 hours")).groupBy("vehicle", "tx", "ty").agg(F.count("*").alias("stays"), F.sum("n").alias("rows")),
    f"WITH e AS (SELECT user_id AS vehicle, {_EXY}, ts FROM events), m AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY vehicle, tx, ty ORDER BY ts) + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS opens FROM e) SELECT vehicle, tx, ty, sum(opens)::BIGINT AS stays, count(*)::BIGINT AS rows FROM m GROUP BY 1, 2, 3",
)
_add("stream_dedup", lambda s, d: S.run_once(S.stream_dedup(_event_stream(s, d)), mode="append").groupBy(F.col("x").alias("tx"), F.col("y").alias("ty")).agg(F.countDistinct("event_id").alias("n")), f"SELECT {_EXY}, count(DISTINCT event_id)::BIGINT AS n FROM events GROUP BY 1, 2")
_add("stream_labelled", lambda s, d: S.run_once(S.label_stream(_event_stream(s, d), stage(tile_clusters(table(s, d, "events").withColumns({"x": F.floor(F.col("user_id") / 10), "y": F.floor(F.col("value") / 10)}), _XY, TileParams(5, 4)), "clusters"), _XY), mode="append").groupBy("tx", "ty").agg(F.count("r_tx").alias("labelled"), F.count("*").alias("rows")), f"WITH RECURSIVE counts AS (SELECT {_EXY}, count(*)::BIGINT AS n FROM events GROUP BY 1, 2), sig AS (SELECT * FROM counts WHERE n >= 5), {_walk()} SELECT tx, ty, (CASE WHEN c.r_tx IS NULL THEN 0 ELSE k.n END)::BIGINT AS labelled, k.n AS rows FROM counts k LEFT JOIN clusters c USING (tx, ty)")
_add(
    "stream_window_clusters",
    lambda s, d: S.window_clusters(S.run_once(S.stream_counts(_event_stream(s, d), _XY, "30 days")), TileParams(2, 2)).select(F.unix_timestamp("start").alias("start_s"), "r_tx", "r_ty", "tx", "ty", "n"),
    f"WITH RECURSIVE sig AS (SELECT (epoch(ts)::BIGINT // 2592000 * 2592000)::BIGINT AS start_s, {_EXY}, count(*)::BIGINT AS n FROM events GROUP BY 1, 2, 3 HAVING count(*) >= 2), {_walk(('start_s', 'tx', 'ty'), 'a.start_s = b.start_s AND ' + _CHEB1, mu=2)} SELECT start_s, r_tx, r_ty, tx, ty, n FROM clusters",
)
