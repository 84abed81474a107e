"""Breadth-first and shortest-path searches from many sources at once: one join a round, whatever the number of sources."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import cut, drop
from . import reach


def label_naive(edges: DataFrame, roots: DataFrame, max_depth: int | None = None) -> DataFrame:
    """Distances (v, hub, dist) from every root (hub) over unweighted edges (u, v); a graph that workers can hold is searched in tasks."""
    if (graph := reach.hold(edges, roots.select(F.col("hub").alias("v")), both=True)) is not None:
        return cut(reach.searches(edges.sparkSession, graph, reach.places(graph, roots, "hub"), max_depth), "bfs")
    seen = front = cut(roots.select(F.col("hub").alias("v"), "hub", F.lit(0).alias("dist")).distinct(), "bfs")
    d = 0
    while max_depth is None or d < max_depth:
        d += 1
        nxt = front.withColumnRenamed("v", "u").join(edges.select("u", "v"), "u").select("v", "hub").distinct().join(seen.select("v", "hub"), ["v", "hub"], "left_anti")
        nxt = cut(nxt.select("v", "hub", F.lit(d).alias("dist")), "bfs")
        if nxt.isEmpty():
            break
        seen, front = seen.unionByName(nxt), nxt
    return seen


def label_naive_weighted(edges: DataFrame, roots: DataFrame) -> DataFrame:
    """Least weight sums (v, hub, dist) from every root: improvements spread until none is left."""
    best = front = cut(roots.select(F.col("hub").alias("v"), "hub", F.lit(0).cast("long").alias("dist")).distinct(), "sp")
    while not front.isEmpty():
        step = front.withColumnRenamed("v", "u").join(edges, "u").groupBy("v", "hub").agg(F.min(F.col("dist") + F.col("w")).alias("dist"))
        old = best.withColumnRenamed("dist", "old")
        front = cut(step.join(old, ["v", "hub"], "left").where("old is null or dist < old").select("v", "hub", "dist"), "sp")
        nxt = cut(best.unionByName(front).groupBy("v", "hub").agg(F.min("dist").alias("dist")), "sp")
        drop(best)
        best = nxt
    return best


def bfs_pairs(edges: DataFrame, pairs: DataFrame, max_depth: int | None = None) -> DataFrame:
    """(qid, s, t, dist) by one search per distinct s; a source stops once all its targets are met. Null: no path."""
    want = cut(pairs.select(F.col("s").alias("hub"), F.col("t").alias("v")).distinct(), "want")
    seen = front = cut(want.select(F.col("hub").alias("v"), "hub", F.lit(0).alias("dist")).distinct(), "bfs")
    d = 0
    while max_depth is None or d < max_depth:
        open_ = want.join(seen.select("v", "hub"), ["v", "hub"], "left_anti").select("hub").distinct()
        d += 1
        nxt = front.join(open_, "hub", "left_semi").withColumnRenamed("v", "u").join(edges.select("u", "v"), "u").select("v", "hub").distinct().join(seen.select("v", "hub"), ["v", "hub"], "left_anti")
        nxt = cut(nxt.select("v", "hub", F.lit(d).alias("dist")), "bfs")
        if nxt.isEmpty():
            break
        seen, front = seen.unionByName(nxt), nxt
    return pairs.join(seen.select(F.col("hub").alias("s"), F.col("v").alias("t"), "dist"), ["s", "t"], "left").select("qid", "s", "t", "dist")


def apsp(edges: DataFrame, vertices: DataFrame, limit: int = 20_000, weighted: bool = False) -> DataFrame:
    """All pairs (s, t, dist) that have a path. Rows of a graph that workers can hold go straight from the searches to the reader; by rounds, whose tables are quadratic, more than ``limit`` vertices are refused."""
    if not weighted and (graph := reach.hold(edges, vertices.select(F.col("vid").alias("v")), both=True)) is not None:
        got = reach.searches(edges.sparkSession, graph, reach.places(graph, vertices, "vid"))
        return got.select(F.col("hub").alias("s"), F.col("v").alias("t"), "dist")
    if vertices.count() > limit:
        raise ValueError("too many vertices for the table of all pairs")
    roots = vertices.select(F.col("vid").alias("hub"))
    got = label_naive_weighted(edges, roots) if weighted else label_naive(edges, roots)
    return got.select(F.col("hub").alias("s"), F.col("v").alias("t"), "dist")


def components(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """(vid, comp) with the smallest vid reached: minima spread, and each vertex also takes its minimum's minimum, so rounds are logarithmic on most graphs."""
    comp = cut(vertices.select("vid", F.col("vid").alias("comp")), "comp")
    while True:
        near = comp.withColumnRenamed("vid", "u").join(edges.select("u", "v"), "u").groupBy(F.col("v").alias("vid")).agg(F.min("comp").alias("c"))
        low = comp.join(near, "vid", "left").select("vid", F.col("comp").alias("old"), F.least("comp", F.coalesce("c", "comp")).alias("comp"))
        jump = comp.select(F.col("vid").alias("comp"), F.col("comp").alias("far"))
        nxt = cut(low.join(jump, "comp").select("vid", "old", F.least("comp", "far").alias("comp")), "comp")
        done = nxt.where("comp <> old").isEmpty()
        comp = nxt.select("vid", "comp")
        if done:
            return comp
