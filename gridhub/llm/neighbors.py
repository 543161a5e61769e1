"""Exact top-k by inner product: a Voronoi join of queries and data.

Data and queries fall into the cells of a few pivots.  Per cell, the driver keeps counts,
radii and the smallest distances to the pivot, which bound from below how good the k-th
partner of every query of a group must be.  A data row is sent to a group only if it could
reach that bound there; each group is cut into as many slices of bounded size as the rows
that came to it need, each slice is solved with one matrix product, and the partial lists
are merged.  A cell of many queries is several groups, so no task holds more than
GROUP_QUERIES queries, on average, and SLICE_ROWS rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridhub.llm.arrow import column
from gridhub.plans.staging import stage

#: Least and largest number of pivots, a quarter of the root of the rows between them, and
#: the rows that are drawn to place each.
PIVOTS, MOST_PIVOTS, PIVOT_SAMPLE = 64, 4096, 64
#: Queries of one group, and data rows of one slice that a group is solved against.
GROUP_QUERIES, SLICE_ROWS = 2048, 32768
UNIT = 1024


def quantised(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", unit: int = UNIT) -> DataFrame:
    """``vec_id, v``: components as floor(unit * x), up to the ends of a long.

    Rows with a null id or vector, or with null or non-finite components, take no part.
    """
    bad = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
    rows = vectors.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(embedding).cast("array<double>").alias("e")).where(F.col("e").isNotNull() & ~F.exists("e", bad) & F.col("vec_id").isNotNull())
    return rows.select("vec_id", F.transform("e", lambda x: F.floor(x * F.lit(float(unit))).cast("long")).alias("v"))


def _matrix(lists: pa.Array, dim: int) -> np.ndarray:
    """Rows of an array column, padded with zeros on the right."""
    sizes = lists.value_lengths().to_numpy(zero_copy_only=False)
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    out = np.zeros((len(lists), dim), np.int64)
    out[np.arange(dim) < sizes[:, None]] = flat
    return out


def _pivots(sample: np.ndarray, many: int, rounds: int = 6) -> np.ndarray:
    """A few rounds of k-means over a bounded sample."""
    rng = np.random.default_rng(3)
    unique = np.unique(sample, axis=0)
    centres = unique[rng.choice(len(unique), min(many, len(unique)), replace=False)].astype(np.float64)
    for _ in range(rounds):
        cell = _nearest(sample, centres)[0]
        many_in = np.bincount(cell, minlength=len(centres))
        sums = np.stack([np.bincount(cell, sample[:, j], len(centres)) for j in range(sample.shape[1])], 1)
        centres = np.where(many_in[:, None] > 0, sums / np.maximum(many_in, 1)[:, None], centres)
    return centres


def _nearest(x: np.ndarray, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    x = x.astype(np.float64)
    d2 = (x * x).sum(1)[:, None] - 2 * x @ centres.T + (centres * centres).sum(1)
    cell = d2.argmin(1)
    return cell, np.sqrt(np.maximum(((x - centres[cell]) ** 2).sum(1), 0))


def _scores(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer inner products of all rows of two integer matrices, ending at those of a long.

    Rows with components so large that products could pass 64 bits go through unbounded
    integers, and only those.
    """
    if not a.size or not b.size:
        return np.zeros((len(a), len(b)), np.int64)
    top_a, top_b = (np.abs(m.astype(np.float64)).max(1) for m in (a, b))
    limit = (2.0**62 / a.shape[1]) ** 0.5
    if float(top_a.max()) * float(top_b.max()) * a.shape[1] < 2**53:
        return (a.astype(np.float64) @ b.astype(np.float64).T).astype(np.int64)
    large_a, large_b = np.flatnonzero(top_a > limit), np.flatnonzero(top_b > limit)
    with np.errstate(over="ignore"):
        out = a @ b.T
    ends = np.iinfo(np.int64)
    for rows, cols in ((large_a, np.arange(len(b))), (np.arange(len(a)), large_b)):
        if len(rows) and len(cols):
            whole = a[rows].astype(object) @ b[cols].astype(object).T
            out[np.ix_(rows, cols)] = np.clip(whole, ends.min, ends.max).astype(np.int64)
    return out


def _neighbouring(centres: np.ndarray) -> np.ndarray:
    """An order of the pivots in which near ones stand together: median cuts of the widest axis."""
    out, stack = [], [np.arange(len(centres))]
    while stack:
        some = stack.pop()
        if len(some) < 3:
            out.extend(some.tolist())
            continue
        axis = int(np.ptp(centres[some], axis=0).argmax())
        some = some[np.argsort(centres[some, axis], kind="stable")]
        stack += [some[len(some) // 2 :], some[: len(some) // 2]]
    return np.array(out, np.int64)


class Groups:
    """Query cells in groups of about GROUP_QUERIES queries; a larger cell is several groups.

    ``cells`` lists the cells with queries, group by group; group ``i`` begins at
    ``starts[i]`` of them and is the ``parts[i]`` numbers from ``first[i]`` on.
    """

    def __init__(self, order: np.ndarray, load: dict[int, int], size: int):
        lists, held = [], size
        for c in (int(c) for c in order if int(c) in load):
            if held + load[c] > size:
                lists.append([])
                held = 0
            lists[-1].append(c)
            held += load[c]
        self.cells = np.array([c for g in lists for c in g], np.int64)
        self.starts = np.cumsum([0, *map(len, lists)])[:-1]
        self.parts = np.array([-(-sum(load[c] for c in g) // size) for g in lists], np.int64)
        self.first = np.cumsum(self.parts) - self.parts
        self.of_cell = [(c, int(self.first[i]), int(self.parts[i])) for i, g in enumerate(lists) for c in g]


def top_k(queries: DataFrame, data: DataFrame, k: int = 10) -> DataFrame:
    """The ``k`` best rows of ``data`` for each query, itself aside.

    Both sides are ``vec_id, v`` with integer arrays; a shorter array counts as padded with
    zeros.  Rows that share a query's id are taken for the query.  Ties go to the smaller
    id; scores beyond the ends of a long end there.  Returns ``query_id, rank, vec_id,
    score``, fewer than ``k`` rows where there are fewer partners; an empty side gives an
    empty result.
    """
    spark = data.sparkSession
    schema = "query_id long, rank int, vec_id long, score long"
    data, queries = stage(data, "vec"), stage(queries.dropDuplicates(["vec_id", "v"]), "query")
    facts = data.agg(F.max(F.size("v")), F.count("*")).first()
    asked = queries.agg(F.max(F.size("v")), F.count("*")).first()
    dim = max(facts[0] or 0, asked[0] or 0)
    if not facts[1] or not asked[1] or not dim:
        return spark.createDataFrame([], schema)
    many = int(min(MOST_PIVOTS, max(PIVOTS, facts[1] ** 0.5 / 4)))
    drawn = data.orderBy(F.xxhash64("vec_id", F.lit(7)), "vec_id").limit(many * PIVOT_SAMPLE).select("v").toArrow()
    centres = _pivots(_matrix(drawn["v"].combine_chunks(), dim), many)
    lengths = np.linalg.norm(centres, axis=1)

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _matrix(column(b, "v"), dim)
            cell, far = _nearest(x, centres)
            yield pa.RecordBatch.from_pydict({"vec_id": column(b, "vec_id"), "cell": pa.array(cell, pa.int32()), "far": pa.array(far), "norm": pa.array(np.sqrt((x.astype(np.float64) ** 2).sum(1))), "x": pa.array([r.tobytes() for r in x], pa.binary())})

    shape = "vec_id long, cell int, far double, norm double, x binary"
    placed = stage(data.mapInArrow(assign, shape), "cell")
    asking = stage(queries.mapInArrow(assign, shape), "ask")

    # distances to the pivot of the k + 1 nearest ids of each cell, a bounded number of rows
    rank = F.row_number().over(Window.partitionBy("cell").orderBy("far", "vec_id"))
    ids = placed.groupBy("cell", "vec_id").agg(F.min("far").alias("far"))
    near = ids.withColumn("r", rank).where(F.col("r") <= k + 1).select("cell", "vec_id", "far").toArrow()
    near_cell, near_id, near_far = (near[c].to_numpy() for c in ("cell", "vec_id", "far"))
    load = {r["cell"]: r for r in asking.groupBy("cell").agg(F.count("*").alias("n"), F.max("far").alias("far")).collect()}
    groups = Groups(_neighbouring(centres), {c: r["n"] for c, r in load.items()}, GROUP_QUERIES)

    slack = 1e-6
    bound = np.full(len(groups.cells), -np.inf)  # score that the k-th partner of any query of a cell reaches
    radii = np.array([load[c]["far"] for c in groups.cells.tolist()])
    for at, c in enumerate(groups.cells.tolist()):
        base = centres @ centres[c] - radii[at] * lengths
        lows = base[near_cell] - (lengths[c] + radii[at]) * near_far
        order = np.argsort(-lows, kind="stable")
        # by id, as rows of the query's own id are no partners
        best = np.sort(np.unique(near_id[order], return_index=True)[1])[: k + 1]
        if len(best) > k:
            low = lows[order[best[k]]]
            bound[at] = low - slack * (1 + abs(low))

    def needed(b: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        """(row, group number) of every group that a row of the batch could matter to."""
        x = np.frombuffer(b"".join(column(b, "x").to_pylist()), "<i8").reshape(-1, dim).astype(np.float64)
        best = x @ centres[groups.cells].T + column(b, "norm").to_numpy()[:, None] * radii
        best += slack * (1 + np.abs(best))
        row, group = np.nonzero(np.logical_or.reduceat(best >= bound, groups.starts, axis=1))
        parts = groups.parts[group]
        part = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
        return np.repeat(row, parts), np.repeat(groups.first[group], parts) + part

    def portions(batches: Iterator[pa.RecordBatch], size: int = 1024) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, size):
                yield b.slice(i, size)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(int(groups.parts.sum()), np.int64)
        for b in portions(batches):
            total += np.bincount(needed(b)[1], minlength=len(total))
        yield pa.RecordBatch.from_pydict({"g": pa.array(np.arange(len(total)), pa.int32()), "n": pa.array(total)})

    def replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in portions(batches):
            row, g = needed(b)
            part = b.take(pa.array(row))
            yield pa.RecordBatch.from_pydict({"g": pa.array(g, pa.int32()), "vec_id": column(part, "vec_id"), "x": column(part, "x")})

    rows_in = placed.select("x", "norm").mapInArrow(count, "g int, n long").groupBy("g").agg(F.sum("n").alias("n"))
    slices = F.broadcast(stage(rows_in.select("g", F.greatest(F.lit(1), F.ceil(F.col("n") / SLICE_ROWS)).cast("int").alias("slices")), "slices"))  # a row a group
    sent = placed.mapInArrow(replicate, "g int, vec_id long, x binary").join(slices, "g")
    sent = sent.withColumn("s", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.col("slices")).cast("int")).drop("slices")
    cells = F.broadcast(spark.createDataFrame(groups.of_cell, "cell int, first int, parts int"))  # a row a pivot
    grouped = asking.join(cells, "cell").withColumn("g", (F.col("first") + F.pmod(F.xxhash64("vec_id", F.lit(2)), F.col("parts"))).cast("int")).join(slices, "g")
    wanted = grouped.select("g", F.explode(F.sequence(F.lit(0), F.col("slices") - 1)).alias("s"), F.col("vec_id").alias("query_id"), F.col("x").alias("q"))

    def solve(left: pa.Table, right: pa.Table) -> pa.Table:
        out = {"query_id": [np.zeros(0, np.int64)], "vec_id": [np.zeros(0, np.int64)], "score": [np.zeros(0, np.int64)]}
        if left.num_rows and right.num_rows:
            q_ids, ids = left["query_id"].to_numpy(), right["vec_id"].to_numpy()
            by_id = np.argsort(ids, kind="stable")
            ids = ids[by_id]
            x = np.frombuffer(b"".join(right["x"].to_pylist()), "<i8").reshape(-1, dim)[by_id]
            q = np.frombuffer(b"".join(left["q"].to_pylist()), "<i8").reshape(-1, dim)
            for i in range(0, len(q), 128):
                found = _scores(q[i : i + 128], x)
                for row, qid in zip(found, q_ids[i : i + 128]):
                    other = np.flatnonzero(ids != qid)
                    mine = row[other]
                    if len(mine) > k:
                        floor = np.partition(mine, len(mine) - k)[len(mine) - k]
                        kept = np.flatnonzero(mine >= floor)
                        kept = kept[np.lexsort((ids[other[kept]], ~mine[kept]))[:k]]
                    else:
                        kept = np.arange(len(mine))
                    out["query_id"].append(np.full(len(kept), qid))
                    out["vec_id"].append(ids[other[kept]])
                    out["score"].append(mine[kept])
        return pa.table({n: pa.array(np.concatenate(v)) for n, v in out.items()})

    partial = wanted.groupBy("g", "s").cogroup(sent.groupBy("g", "s")).applyInArrow(solve, "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return partial.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op10_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten best partners of every hundredth row of ``embeddings`` among all rows."""
    rows = quantised(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
    return top_k(rows.where(F.col("vec_id") % 100 == 0), rows)


OP10_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)::BIGINT) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, d.vec_id, list_sum(list_transform(list_zip(q.v, d.v), lambda z: z[1] * z[2]))::BIGINT AS score
  FROM v q JOIN v d ON q.vec_id <> d.vec_id WHERE q.vec_id % 100 = 0
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM scored
)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 10
"""
