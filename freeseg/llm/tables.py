"""Intermediate tables in the shared folder, joins with a checked broadcast, and connected components."""

from __future__ import annotations

import uuid

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shipping import work_dir

#: Rows of a few numbers each that may be broadcast; more are joined by a shuffle.
BROADCAST_ROWS = 500_000
#: Edges whose components one task finds.
AT_ONCE = 300_000


def keep(df: DataFrame) -> DataFrame:
    """df as a Parquet table in the application's part of the shared folder, with its lineage cut; see `freeseg.shipping.release`."""
    to = f"{work_dir(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(to)
    return df.sparkSession.read.schema(df.schema).parquet(to)


def hinted(kept: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """A kept table of short rows, marked for broadcast if it has `most` rows at most."""
    return F.broadcast(kept) if kept.count() <= most else kept


def _joined(batches):
    """Components of all edges of a task by union-find."""
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while (up := root.setdefault(x, x)) != x:
            root[x] = root[up]
            x = up
        return x

    for batch in batches:
        for u, v in zip(batch.column("u").to_pylist(), batch.column("v").to_pylist(), strict=True):
            a, b = find(u), find(v)
            root[max(a, b)] = min(a, b)
    nodes = list(root)
    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([find(x) for x in nodes], pa.int64())], ["node", "component"])


def components(edges: DataFrame, rounds: int = 100, at_once: int = AT_ONCE) -> DataFrame:
    """node, component of the nodes of edges (a, b): component is the smallest node that can be reached.

    Up to `at_once` edges, a checked and fixed bound, are solved by one task; more in rounds, with the same result.
    Alternating large and small stars: every round points each node's neighbours at its smallest neighbour, until only
    stars are left, after about the logarithm of the longest path. A round is two aggregations and two joins; the
    edges stay distributed. Edges with a null end or of a node with itself are left out.
    """
    now = keep(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    mark = lambda t: tuple(t.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
    before = mark(now)
    if before[0] <= at_once:
        return now.coalesce(1).mapInArrow(_joined, "node long, component long")
    for _ in range(rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = keep(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        after = mark(now)
        if after == before:
            break
        before = after
    roots = now.select("v").distinct().select(F.col("v").alias("node"), F.col("v").alias("component"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
