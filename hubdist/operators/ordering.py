"""Vertex orders: the index is exact under each, but its size depends on it. All give (vid, rnk), dense and total; ties go to the smaller vid."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ids import dense_ids


def rank_random(vertices: DataFrame, seed: int = 1) -> DataFrame:
    """By a hash of the id: the same on any partitioning."""
    return dense_ids(vertices.select("vid", F.xxhash64("vid", F.lit(seed)).alias("h")), ["h", "vid"], "rnk").select("vid", "rnk")


def rank_arithmetic(vertices: DataFrame, factor: int = 7919, modulus: int = 10007) -> DataFrame:
    """A scattered order that any engine can repeat: by vid * factor mod modulus."""
    return dense_ids(vertices.select("vid", (F.col("vid") * factor % modulus).alias("h")), ["h", "vid"], "rnk").select("vid", "rnk")


def rank_degree(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Vertices with more neighbours first."""
    deg = edges.groupBy(F.col("src").alias("vid")).count()
    full = vertices.select("vid").join(deg, "vid", "left").select("vid", F.coalesce("count", F.lit(0)).alias("deg"))
    return dense_ids(full, [F.desc("deg"), F.asc("vid")], "rnk").select("vid", "rnk")


def rank_closeness(edges: DataFrame, vertices: DataFrame, samples: DataFrame) -> DataFrame:
    """By distance to sampled sources (vid): more of them reached first, then the smaller sum."""
    from .search import label_naive

    dist = label_naive(edges.select(F.col("src").alias("u"), F.col("dst").alias("v")), samples.select(F.col("vid").alias("hub")))
    agg = dist.groupBy(F.col("v").alias("vid")).agg(F.count("*").alias("n"), F.sum("dist").alias("s"))
    full = vertices.select("vid").join(agg, "vid", "left").na.fill(0)
    return dense_ids(full, [F.desc("n"), F.asc("s"), F.asc("vid")], "rnk").select("vid", "rnk")


def rank_given(order: DataFrame) -> DataFrame:
    """A user's order (vid, rnk), checked to be a permutation."""
    n, d, hi, k = order.agg(F.count("*"), F.count_distinct("rnk"), F.max("rnk"), F.count_distinct("vid")).first()
    if n and not (n == d == k == hi + 1):
        raise ValueError("ranks must be a permutation of 0..n-1")
    return order.select("vid", F.col("rnk").cast("long").alias("rnk"))


def rank_centroid(edges: DataFrame, comps: DataFrame, limit: int = 2_000_000) -> DataFrame:
    """Order for forests: centroids by level of a centroid cut, so every label has at most log2(n) + 1 entries. One task per tree of at most ``limit`` vertices."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        if len(part) > limit:
            raise ValueError("a tree is larger than the limit")
        near: dict[int, list[int]] = {}
        for a, b in zip(part["src"].tolist(), part["dst"].tolist(), strict=True):
            near.setdefault(a, []).append(b)
        level, gone, todo = {}, set(), [(next(iter(near)), 0)]
        while todo:
            root, depth = todo.pop()
            seen, up = [root], {root: -1}
            for x in seen:
                for y in near[x]:
                    if y not in gone and y != up[x]:
                        if y in up:
                            raise ValueError("not a forest")
                        up[y] = x
                        seen.append(y)
            size = dict.fromkeys(seen, 1)
            for x in reversed(seen[1:]):
                size[up[x]] += size[x]
            half = len(seen) / 2
            c = min((x for x in seen if size[x] >= half), key=lambda x: (size[x], x))
            level[c] = depth
            gone.add(c)
            todo += [(y, depth + 1) for y in near[c] if y not in gone]
        return pd.DataFrame({"vid": list(level), "lvl": list(level.values())})

    rows = edges.join(comps.select(F.col("vid").alias("src"), "comp"), "src").select("comp", "src", "dst")
    got = rows.groupBy("comp").applyInPandas(run, "vid long, lvl long")
    return dense_ids(got, ["lvl", "vid"], "rnk").select("vid", "rnk")
