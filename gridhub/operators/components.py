"""Connected components of an edge table, without any driver-side graph."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridhub.operators.unionfind import label_components
from gridhub.plans.staging import release, stage

#: Edges between integer nodes, 16 bytes each, up to which one task solves the whole graph.
TASK_EDGES = 1_000_000


def _ends(edges: DataFrame, lower: Column, upper: Column) -> DataFrame:
    return edges.select(lower.alias("a"), upper.alias("b"))


def _attach_to_larger(edges: DataFrame) -> DataFrame:
    """Every node hands its least neighbour to all larger neighbours."""
    both = _ends(edges, F.col("a"), F.col("b")).unionByName(_ends(edges, F.col("b"), F.col("a")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.join(least, "a").where("b > a").select(F.col("m").alias("a"), "b").where("a < b").distinct()


def _attach_to_smaller(edges: DataFrame) -> DataFrame:
    """Every node hangs itself and its smaller neighbours under the least of them."""
    least = edges.groupBy("b").agg(F.min("a").alias("m"))
    moved = edges.join(least, "b").where("a > m").select(F.col("m").alias("a"), F.col("a").alias("b"))
    return moved.unionByName(least.select(F.col("m").alias("a"), "b")).distinct()


def _fingerprint(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
    return row[0], row[1]


def _one_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    ends = [(b.column("a").to_numpy(), b.column("b").to_numpy()) for b in batches]
    if ends:
        a, b = (np.concatenate(side) for side in zip(*ends))
        nodes, at = np.unique(np.r_[a, b], return_inverse=True)
        roots = nodes[label_components(len(nodes), at[: len(a)], at[len(a) :])]
        yield pa.RecordBatch.from_pydict({"node": pa.array(nodes), "root": pa.array(roots)})


def star_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """Label every node of ``edges`` with the least node of its component.

    Alternating star contraction: each round is two grouped minima and two equi-joins,
    ending in one staged table; the driver reads a count and a hash per round.  Rounds
    are logarithmic in practice.  Up to TASK_EDGES edges of integer nodes, once counted,
    are solved by one task instead.  Self loops give a component of one node; rows with a
    null end are ignored.  Node ids are any ordered type.

    Returns ``(node, root)``, one row per node that occurs in an edge.
    """
    clean = edges.select(F.col(src).alias("s"), F.col(dst).alias("d")).where("s is not null and d is not null")
    loops = clean.where("s = d").select(F.col("s").alias("node")).distinct()
    now = stage(clean.where("s <> d").select(F.least("s", "d").alias("a"), F.greatest("s", "d").alias("b")).distinct(), "cc")
    mark = _fingerprint(now)
    if 0 < mark[0] <= TASK_EDGES and dict(now.dtypes)["a"] == "bigint":
        solved = stage(now.repartition(1).mapInArrow(_one_task, "node bigint, root bigint"), "cc")
        release(now)
        return solved.unionByName(loops.join(solved, "node", "left_anti").select("node", F.col("node").alias("root")))
    for _ in range(max_rounds):
        if not mark[0]:
            break
        after = stage(_attach_to_smaller(_attach_to_larger(now)), "cc")
        release(now)
        now, before, mark = after, mark, _fingerprint(after)
        if mark == before:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    under = now.select(F.col("b").alias("node"), F.col("a").alias("root"))
    roots = now.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct()
    alone = loops.join(under, "node", "left_anti").join(roots, "node", "left_anti")
    return under.unionByName(roots).unionByName(alone.select("node", F.col("node").alias("root")))
