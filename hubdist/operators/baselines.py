"""What the index is compared with: landmark bounds, hierarchical labels by greedy cover, and a tree-decomposition index."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import reach
from .search import label_naive

#: Vertices up to which the table of all distances is held for the greedy cover, on the driver twice and by each worker once (1 byte a pair; 2 or 4 on long graphs).
HELD_TABLE = 12_000


def landmark_table(edges: DataFrame, vertices: DataFrame, k: int) -> DataFrame:
    """Distances (v, hub, dist) from the first k vertices by rank."""
    return label_naive(edges, vertices.where(F.col("v") < k).select(F.col("v").alias("hub")))


def landmark_estimate(table: DataFrame, pairs: DataFrame) -> DataFrame:
    """(qid, s, t, lower, upper): triangle bounds over shared landmarks; null without one."""
    a = table.select(F.col("v").alias("s"), "hub", F.col("dist").alias("da"))
    b = table.select(F.col("v").alias("t"), "hub", F.col("dist").alias("db"))
    got = pairs.join(a, "s").join(b, ["t", "hub"]).groupBy("qid").agg(F.max(F.abs(F.col("da") - F.col("db"))).alias("lower"), F.min(F.col("da") + F.col("db")).alias("upper"))
    return pairs.join(got, "qid", "left").select("qid", "s", "t", "lower", "upper")


def hierarchical_order(dist: DataFrame, limit: int = 300) -> list[int]:
    """Greedy order: next comes the vertex on shortest paths of most pairs not yet covered. For small graphs."""
    rows = dist.collect() if dist.select("s").distinct().count() <= limit else None
    if rows is None:
        raise ValueError("the greedy cover is for small graphs")
    d = {(r["s"], r["t"]): r["dist"] for r in rows}
    verts = sorted({s for s, _ in d})
    on = {v: {(s, t) for (s, t), k in d.items() if s <= t and d.get((s, v), 1 << 30) + d.get((v, t), 1 << 30) == k} for v in verts}
    out, left = [], {p for p in d if p[0] <= p[1]}
    while verts:
        v = max(verts, key=lambda x: (len(on[x] & left), -x))
        out.append(v)
        verts.remove(v)
        left -= on[v]
    return out


def table(graph: reach.Held) -> tuple[np.ndarray, int]:
    """(distances between all places, the mark for none), in the smallest type that holds the sum of two of either."""
    n = len(graph.ids)
    for kind, none in ((np.uint8, 100), (np.uint16, 32_000), (np.int32, 1 << 29)):
        dist = np.empty((n, n), kind)
        try:
            for lo in range(0, n, reach.WIDTH):
                dist[lo : lo + reach.WIDTH] = graph.matrix(np.arange(lo, min(n, lo + reach.WIDTH)), kind, none)
        except OverflowError:
            continue
        if 2 * max((int(row.max(where=row < none, initial=0)) for row in dist), default=0) < none:
            break
    return dist, none


def on_paths(dist: np.ndarray, s: np.ndarray, t: np.ndarray) -> np.ndarray:
    """On shortest paths of how many of the connected pairs (s, t) each vertex lies."""
    out = np.zeros(len(dist), np.int64)
    for lo in range(0, len(s), 128):
        a, b = s[lo : lo + 128], t[lo : lo + 128]
        total = dist[a]
        total += dist[b]
        out += np.add.reduce((total == dist[a, b][:, None]).view(np.uint8), axis=0, dtype=np.uint8)
    return out


def greedy_cover(dist: np.ndarray, none: int, counts: np.ndarray) -> list[int]:
    """Places in the order of the greedy cover. ``counts``: on shortest paths of how many pairs s <= t each lies.

    A pair is taken off the counts of the vertices on its paths when it is covered,
    which happens once, so no count is ever made anew. Pairs not covered are found in
    their table at first and in a list when few are left.
    """
    n, done = len(dist), np.iinfo(dist.dtype).max  # no sum is as large
    counts, left, out = counts.copy(), dist.copy(), []
    left[left == none] = done
    for s in range(n):
        left[s, :s] = done
    size, pairs = sum(int(np.count_nonzero(row != done)) for row in left), None
    for _ in range(n):
        v = int(np.argmax(counts))  # the smallest of the best
        out.append(v)
        counts[v] = -(1 << 62)
        if pairs is None and 32 * size <= n * n:
            s, t = np.nonzero(left != done)
            pairs, left = (s.astype(np.int32), t.astype(np.int32), dist[s, t]), None
        if pairs is not None:
            s, t, d = pairs
            hit = dist[v][s] + dist[v][t] == d
            counts -= on_paths(dist, s[hit], t[hit])
            pairs = s[~hit], t[~hit], d[~hit]
            continue
        for lo in range(0, n, 64):
            part = left[lo : lo + 64, lo:]
            s, t = np.nonzero(dist[lo : lo + 64, v, None] + dist[v, lo:] == part)
            part[s, t] = done
            counts -= on_paths(dist, s + lo, t + lo)
            size -= len(s)
    return out


def hierarchical_order_held(edges: DataFrame, vertices: DataFrame) -> list[int] | None:
    """``hierarchical_order`` of an undirected graph whose table of all distances can be held, with the first counts made in tasks; None for a larger one."""
    if vertices.count() > HELD_TABLE or (graph := reach.hold(edges, vertices)) is None:
        return None
    n, spark = len(graph.ids), edges.sparkSession
    pieces = max(1, min(n, 4 * spark.sparkContext.defaultParallelism))

    def count(g: reach.Held, k: int) -> Iterator[tuple]:
        if not hasattr(g, "table"):  # once a worker
            g.table = table(g)
        dist, none = g.table
        total = np.zeros(n, np.int64)
        for s in range(k, n, pieces):
            t = s + np.flatnonzero(dist[s, s:] != none)
            total += on_paths(dist, np.full(len(t), s), t)
        yield np.arange(n), total

    v, c = reach.columns(reach.dealt(spark, graph, pieces, count, "v long, c long"))
    counts = np.zeros(n, np.int64)
    np.add.at(counts, v, c)
    return graph.ids[greedy_cover(*table(graph), counts)].tolist()


def tree_index(edges: DataFrame, width: int, limit: int = 200_000) -> tuple[dict[int, list[tuple[int, int]]], dict[int, dict[int, int]], dict[int, int]]:
    """Min-degree elimination up to ``width``: bags (vertex: neighbours and weights when it left), core distances, and the order.

    For graphs of at most ``limit`` edges, on the driver, as a baseline.
    """
    cols = ["u", "v", "w"] if "w" in edges.columns else ["u", "v"]
    if edges.count() > limit:
        raise ValueError("the tree baseline is for small graphs")
    near: dict[int, dict[int, int]] = {}
    for r in edges.select(*cols).collect():
        near.setdefault(r[0], {})[r[1]] = r[2] if len(cols) == 3 else 1
    heap = [(len(n), v) for v, n in near.items()]
    heapq.heapify(heap)
    bags: dict[int, list[tuple[int, int]]] = {}
    order: dict[int, int] = {}
    while heap:
        deg, v = heapq.heappop(heap)
        if v in order or deg != len(near[v]):
            continue
        if deg > width:
            break
        order[v] = len(order)
        own = near.pop(v)
        bags[v] = sorted(own.items())
        for a, wa in own.items():
            del near[a][v]
            for b, wb in own.items():
                if a != b and near[a].get(b, 1 << 60) > wa + wb:
                    near[a][b] = wa + wb
            heapq.heappush(heap, (len(near[a]), a))
    core = {}
    for s in near:
        dist, queue = {s: 0}, [(0, s)]
        while queue:
            d, x = heapq.heappop(queue)
            if d == dist[x]:
                for y, w in near[x].items():
                    if d + w < dist.get(y, 1 << 60):
                        dist[y] = d + w
                        heapq.heappush(queue, (d + w, y))
        core[s] = dist
    return bags, core, order


def tree_query(index: tuple, s: int, t: int) -> int | None:
    """Distance by climbing the bags of both ends to common ancestors or the core."""
    bags, core, order = index

    def climb(x: int) -> dict[int, int]:
        dist, queue = {x: 0}, [(order.get(x, 1 << 60), x)]
        done = set()
        while queue:
            _, v = heapq.heappop(queue)
            if v in done:
                continue
            done.add(v)
            for y, w in bags.get(v, ()):
                if dist[v] + w < dist.get(y, 1 << 60):
                    dist[y] = dist[v] + w
                heapq.heappush(queue, (order.get(y, 1 << 60), y))
        return dist

    a, b = climb(s), climb(t)
    best = min((a[x] + b[x] for x in a.keys() & b.keys()), default=1 << 60)
    for x in a.keys() & core.keys():
        for y in b.keys() & core[x].keys():
            best = min(best, a[x] + core[x][y] + b[y])
    return None if best == 1 << 60 else best
