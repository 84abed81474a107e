"""Two-hop labels: built for all roots at once, a distance at a time.

In round d every vertex hears from its neighbours which hubs they gained in round
d - 1. It keeps a hub that ranks before itself unless labels known so far already
explain the distance d by way of an earlier hub. Such a hub lies strictly between
the two, so both of its legs are shorter than d and known: the result is the index
that one pruned search per root in rank order would give, in as many rounds as the
longest label distance. A graph that workers can hold gets the same index from
searches inside tasks (``reach``), without the shuffles of the rounds. All tables are
in rank space: v, hub and neighbours are ranks.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import cut, drop
from . import reach


def _union(parts: list[DataFrame]) -> DataFrame:
    """All rounds as one scan over their directories."""
    spark = parts[0].sparkSession
    return spark.read.schema(parts[0].schema).parquet(*[p._scratch_path for p in parts])


def explained(cand: DataFrame, hub_side: DataFrame, own_side: DataFrame, d) -> DataFrame:
    """Candidates (v, hub) for which an earlier common hub gives a sum of at most d."""
    a = hub_side.select(F.col("v").alias("hub"), F.col("hub").alias("h2"), F.col("dist").alias("da"))
    b = own_side.select("v", F.col("hub").alias("h2"), F.col("dist").alias("db"))
    return cand.join(a, "hub").join(b, ["v", "h2"]).where((F.col("h2") < F.col("hub")) & (F.col("da") + F.col("db") <= d)).select("v", "hub").distinct()


def label_pruned(edges: DataFrame, vertices: DataFrame, hubs_below: int | None = None, with_parent: bool = False, prefilter: Callable[[DataFrame, int], DataFrame] | None = None, skip: DataFrame | None = None, max_round: int | None = None) -> DataFrame:
    """Labels (v, hub, dist[, parent]) over unweighted undirected edges (u, v); vertices: (v).

    ``hubs_below``: the first searches only. ``prefilter`` drops candidates another
    index explains, one that gives the exact distance of each pair with a shortest path
    through ``skip`` (v), which are no hubs. ``parent``: the smallest neighbour that
    delivered the hub.
    """
    if not with_parent and (skip is None) == (prefilter is None) and (graph := reach.hold(edges, vertices)) is not None:
        roots, first = reach.places(graph, vertices, "v"), None
        if hubs_below is not None:
            roots = roots[graph.ids[roots] < hubs_below]
        if skip is not None:
            first = np.isin(graph.ids, reach.columns(skip.select("v"))[0])
            roots = roots[~first[roots]]
        return cut(reach.labels(edges.sparkSession, graph, roots, first, max_round), "labels")
    seed = vertices.select("v", F.col("v").alias("hub"), F.lit(0).alias("dist"))
    if hubs_below is not None:
        seed = seed.where(F.col("hub") < hubs_below)
    if skip is not None:
        seed = seed.join(skip, "v", "left_anti")
    if with_parent:
        seed = seed.withColumn("parent", F.lit(None).cast("long"))
    rounds = [cut(seed, "round")]
    d = 0
    while max_round is None or d < max_round:
        d += 1
        known = _union(rounds)
        step = rounds[-1].select(F.col("v").alias("u"), "hub").join(edges.select("u", "v"), "u").where("hub < v")
        cand = step.groupBy("v", "hub").agg(F.min("u").alias("parent")) if with_parent else step.select("v", "hub").distinct()
        cand = cand.join(known.select("v", "hub"), ["v", "hub"], "left_anti")
        if prefilter is not None:
            cand = prefilter(cand, d)
        cand = cut(cand, "cand")
        bad = explained(cand.select("v", "hub"), known, known, F.lit(d))
        kept = cand.join(bad, ["v", "hub"], "left_anti").select("v", "hub", F.lit(d).alias("dist"), *(["parent"] if with_parent else []))
        kept = cut(kept, "round")
        drop(cand)
        if kept.isEmpty():
            return known
        rounds.append(kept)
    return _union(rounds)


def label_closed_form(dist: DataFrame) -> DataFrame:
    """The index read off all-pairs distances (s, t, dist) in rank space: s is a hub of t unless an earlier vertex lies on a shortest path between them."""
    pair = dist.where("s <= t")
    a = dist.select("s", F.col("t").alias("x"), F.col("dist").alias("da"))
    b = dist.select(F.col("s").alias("x"), "t", F.col("dist").alias("db"))
    bad = pair.join(a, "s").where("x < s").join(b, ["x", "t"]).where(F.col("da") + F.col("db") == F.col("dist")).select("s", "t").distinct()
    return pair.join(bad, ["s", "t"], "left_anti").select(F.col("t").alias("v"), F.col("s").alias("hub"), "dist")


def label_correcting(edges: DataFrame, vertices: DataFrame, hubs: tuple[int, int] | None = None, known: tuple[DataFrame, DataFrame] | None = None) -> tuple[DataFrame, DataFrame]:
    """(labels_out, labels_in) over directed edges (u, v, w) with positive integer weights.

    Labels improve until none does, pruned by what is known; a last pass removes
    entries that an earlier hub on both sides explains. labels_out of x holds hubs
    that x reaches, labels_in those that reach x.
    """
    if not edges.where("w is null or w <= 0").isEmpty():
        raise ValueError("weights must be positive integers")
    both = edges.select(F.lit("in").alias("side"), "u", "v", "w").unionByName(edges.select(F.lit("out").alias("side"), F.col("v").alias("u"), F.col("u").alias("v"), "w"))
    seed = vertices.select("v", F.col("v").alias("hub"), F.lit(0).cast("long").alias("dist"))
    if hubs is not None:
        seed = seed.where((F.col("hub") >= hubs[0]) & (F.col("hub") < hubs[1]))
    seed = seed.select(F.explode(F.array(F.lit("in"), F.lit("out"))).alias("side"), "v", "hub", "dist")
    if known is not None:
        old = known[0].withColumn("side", F.lit("out")).unionByName(known[1].withColumn("side", F.lit("in")))
        best = cut(old.select("side", "v", "hub", "dist").unionByName(seed), "labels")
    else:
        best = cut(seed, "labels")
    front = cut(seed, "front")
    while not front.isEmpty():
        step = front.withColumnRenamed("v", "u").join(both, ["side", "u"]).where("hub < v").groupBy("side", "v", "hub").agg(F.min(F.col("dist") + F.col("w")).alias("dist"))
        better = step.join(best.withColumnRenamed("dist", "old"), ["side", "v", "hub"], "left").where("old is null or dist < old").select("side", "v", "hub", "dist")
        better = cut(better, "cand")
        bad = _explained_sides(better, best, strict=False)
        nxt = cut(better.join(bad, ["side", "v", "hub"], "left_anti"), "front")
        whole = cut(best.unionByName(nxt).groupBy("side", "v", "hub").agg(F.min("dist").alias("dist")), "labels")
        for x in (better, best, front):
            drop(x)
        best, front = whole, nxt
    clean = cut(best.join(_explained_sides(best.where("v <> hub"), best, strict=False), ["side", "v", "hub"], "left_anti"), "labels")
    return clean.where("side = 'out'").drop("side"), clean.where("side = 'in'").drop("side")


def _explained_sides(cand: DataFrame, best: DataFrame, strict: bool) -> DataFrame:
    """An entry hub -> v (in) is explained by out(hub) and in(v), v -> hub (out) by out(v) and in(hub)."""
    flip = F.when(F.col("side") == "in", "out").otherwise("in")
    a = best.select(flip.alias("side"), F.col("v").alias("hub"), F.col("hub").alias("h2"), F.col("dist").alias("da"))
    b = best.select("side", "v", F.col("hub").alias("h2"), F.col("dist").alias("db"))
    return cand.join(a, ["side", "hub"]).where("h2 < hub").join(b, ["side", "v", "h2"]).where(F.col("da") + F.col("db") <= F.col("dist")).select("side", "v", "hub").distinct()


def label_pruned_directed(edges: DataFrame, vertices: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Hop distances along directed edges."""
    if (graph := reach.hold(edges, vertices, both=True)) is not None:
        roots = reach.places(graph, vertices, "v")
        sides = [cut(reach.labels(edges.sparkSession, g, roots).withColumn("dist", F.col("dist").cast("long")), "labels") for g in (graph.turned(), graph)]
        return sides[0], sides[1]
    return label_correcting(edges.select("u", "v", F.lit(1).cast("long").alias("w")), vertices)


def label_pruned_weighted(edges: DataFrame, vertices: DataFrame, bit_parallel: int = 0) -> DataFrame:
    """Labels of an undirected weighted graph; bit-parallel roots need unit weights and are refused."""
    if bit_parallel:
        raise ValueError("bit-parallel labels need an unweighted graph")
    return label_correcting(edges, vertices)[1]


def label_pruned_batched(edges: DataFrame, vertices: DataFrame, batch: int) -> DataFrame:
    """Roots in batches of ranks, each batch pruned by all before it: fewer rounds wait for one another on graphs of long diameter."""
    n = vertices.count()
    w = edges.select("u", "v", F.lit(1).cast("long").alias("w"))
    known = None
    for lo in range(0, n, batch):
        known = label_correcting(w, vertices, (lo, lo + batch), known)
    return known[1].select("v", "hub", F.col("dist").cast("int").alias("dist"))


def label_reference(near: dict[int, list[int]], order: list[int], limit: int = 5000) -> tuple[dict[int, dict[int, int]], dict[int, tuple[int, int]]]:
    """One pruned search per root in the given order, for small graphs and tests: labels per vertex, and (visited, labelled) per root."""
    if len(order) > limit:
        raise ValueError("the reference engine is for small graphs")
    labels: dict[int, dict[int, int]] = {v: {} for v in order}
    counts = {}
    for root in order:
        dist, queue, kept = {root: 0}, deque([root]), 0
        while queue:
            x = queue.popleft()
            if any(labels[root].get(h, 1 << 60) + k <= dist[x] for h, k in labels[x].items()):
                continue
            labels[x][root] = dist[x]
            kept += 1
            for y in near.get(x, ()):
                if y not in dist:
                    dist[y] = dist[x] + 1
                    queue.append(y)
        counts[root] = len(dist), kept
    return labels, counts
