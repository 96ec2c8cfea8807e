"""Model compression: weak vertices and edges are dropped, relative to the largest count around them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import model

LEVELS = (0.0, 0.0001, 0.001, 0.01, 0.1)


def vertex_limits(vertices: DataFrame, scope: str = "rank") -> DataFrame:
    """lang, n, vmax: the largest count of the rank, or ("global") of the language."""
    most = model.vertex_max(vertices).select("lang", "n", "vmax")
    if scope == "rank":
        return most
    return most.join(F.broadcast(most.groupBy("lang").agg(F.max("vmax").alias("g"))), "lang").select("lang", "n", F.col("g").alias("vmax"))


def prune_vertices(vertices: DataFrame, theta: float, scope: str = "rank") -> DataFrame:
    """Vertices of at least theta times the largest count. The limits are a row for each language and rank."""
    return vertices.join(F.broadcast(vertex_limits(vertices, scope)), ["lang", "n"]).where(F.col("cnt") >= theta * F.col("vmax")).drop("vmax")


def with_edge_max(edges: DataFrame) -> DataFrame:
    """Edges with emax, that of the gram's strongest edge in the same direction."""
    most = edges.groupBy(*model.KEYS, "dir").agg(F.max("cnt").alias("emax"))
    return edges.join(most, [*model.KEYS, "dir"])


def prune_edges(edges: DataFrame, theta: float) -> DataFrame:
    """Edges of at least theta times the gram's strongest in the same direction."""
    return with_edge_max(edges).where(F.col("cnt") >= theta * F.col("emax")).drop("emax")


def prune(vertices: DataFrame, edges: DataFrame, theta: float, scope: str = "rank", prune_targets: bool = False) -> tuple[DataFrame, DataFrame]:
    """Both pruned; edges of dropped grams go too, and with prune_targets edges to dropped symbols."""
    kept = prune_vertices(vertices, theta, scope)
    left = prune_edges(edges, theta).join(kept.select(*model.KEYS), list(model.KEYS), "left_semi")
    if prune_targets:
        symbols = kept.where("n = 1").select("lang", F.col("gram").alias("nbr"))
        left = left.join(symbols, ["lang", "nbr"], "left_semi").select(*edges.columns)
    return kept, left


def rated(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """Edges with emax, the gram's count as vcnt, and vmax: all that any level needs, in one shuffle by gram."""
    own = vertices.join(F.broadcast(vertex_limits(vertices)), ["lang", "n"]).select(*model.KEYS, F.col("cnt").alias("vcnt"), "vmax")
    return with_edge_max(edges).join(own, list(model.KEYS))


def holds(theta) -> F.Column:
    """Whether a rated edge is kept at a level."""
    return (F.col("cnt") >= theta * F.col("emax")) & (F.col("vcnt") >= theta * F.col("vmax"))


def freedom_wide(vertices: DataFrame, edges: DataFrame, levels=LEVELS) -> DataFrame:
    """lang, n, gram, dir, t0, t1 and so on: the freedom at every level from one pass over the rated edges."""
    counts = [F.count_if(holds(F.lit(t))).alias(f"t{k}") for k, t in enumerate(levels)]
    return rated(vertices, edges).groupBy(*model.KEYS, "dir").agg(*counts)


def freedom_levels(vertices: DataFrame, edges: DataFrame, levels=LEVELS) -> DataFrame:
    """lang, n, gram, dir, theta, tf, where it is above 0."""
    each = F.array(*(F.struct(F.lit(t).alias("theta"), F.col(f"t{k}").alias("tf")) for k, t in enumerate(levels)))
    return freedom_wide(vertices, edges, levels).select(*model.KEYS, "dir", F.inline(each)).where("tf > 0")


def parameter_count(vertices: DataFrame, edges: DataFrame, levels=LEVELS) -> DataFrame:
    """lang, n, theta, part, params: how many counts the model holds at each level, vertices and edges of each direction apart."""
    v = vertices.join(F.broadcast(vertex_limits(vertices)), ["lang", "n"])
    v = v.groupBy("lang", "n", F.lit("v").alias("part")).agg(*(F.count_if(F.col("cnt") >= F.lit(t) * F.col("vmax")).alias(f"t{k}") for k, t in enumerate(levels)))
    e = rated(vertices, edges).groupBy("lang", "n", F.col("dir").alias("part")).agg(*(F.count_if(holds(F.lit(t))).alias(f"t{k}") for k, t in enumerate(levels)))
    each = F.array(*(F.struct(F.lit(t).alias("theta"), F.col(f"t{k}").alias("params")) for k, t in enumerate(levels)))
    return v.unionByName(e).select("lang", "n", "part", F.inline(each))
