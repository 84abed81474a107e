"""Exact set-overlap search: occurrence counting with long lists set aside, over tasks of bounded size.

Whoever calls names, for each key that items share, the smallest item under it,
its hub; any two items that may link have a hub in common or are hub and item. The
search has two passes:

1. Every item meets its hubs, all overlaps of a task counted at once. A group of n
   near copies has few hubs and is joined here by a few comparisons an item.
2. Other items of one hub that still lie in different components meet each other;
   hubs whose items are joined are done. At a hub too large for a task, all others
   meet the largest component chunk by chunk, so its members travel once for each
   chunk of the others, never for each chunk of their own.

Inside a task, an item of n tokens needs T of them in a partner. Its longest
inverted lists are left out, up to T - 1 of them; the short ones are merged, and
an item found in enough of these is looked up in the long ones by binary probes.
What reaches the overlap is checked against the exact ratio. Only links that join
two groups not yet joined inside the task are returned, so no connection is lost.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import cut, drop
from .graph import components

LONG = 64  # a list of at most so many items is merged, never set aside
CELLS = 1 << 17  # values that are sorted at once, so that they stay in a core's cache
HEAP = 512  # up to so many places are merged by a heap, more by a merge sort whose runs are the lists


class Sets:
    """Union-find over 0..n-1 with path halving."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.find(x), self.find(y)
        if x == y:
            return False
        if x > y:
            x, y = y, x
        self.up[y] = x
        return True


def merged(posts: np.ndarray, start: np.ndarray, lens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Items of several sorted lists and how many of the lists hold each."""
    total = int(lens.sum())
    if total <= HEAP:
        runs = [iter(posts[a : a + n].tolist()) for a, n in zip(start.tolist(), lens.tolist(), strict=True)]
        heap = [(next(r), k) for k, r in enumerate(runs)]
        heapq.heapify(heap)
        items: list[int] = []
        counts: list[int] = []
        while heap:
            item, k = heap[0]
            if items and items[-1] == item:
                counts[-1] += 1
            else:
                items.append(item)
                counts.append(1)
            nxt = next(runs[k], None)
            if nxt is None:
                heapq.heappop(heap)
            else:
                heapq.heapreplace(heap, (nxt, k))
        return np.array(items, np.int64), np.array(counts, np.int64)
    heads = np.cumsum(lens) - lens
    every = np.sort(posts[np.repeat(start - heads, lens) + np.arange(total)], kind="stable")
    edge = np.flatnonzero(np.concatenate([[True], every[1:] != every[:-1]]))
    return every[edge], np.diff(np.append(edge, total))


def links(block: np.ndarray, side: np.ndarray, sizes: np.ndarray, tokens: np.ndarray, num: int, den: int) -> Iterator[tuple[int, int]]:
    """Spanning links (i, j) among items with den * overlap >= num * union in the same block.

    ``side``: 0 or 1; if both occur only pairs across sides are compared. Otherwise
    items of side 3 belong together already and are only found, not searched from.
    ``tokens`` holds the distinct tokens of all items one after another.
    """
    n = len(sizes)
    owner = np.repeat(np.arange(n), sizes)
    code, uniq = pd.factorize(tokens)
    name, names = pd.factorize(block)
    if len(names) > 1:  # lists never leave a block
        code, uniq = pd.factorize(name[owner] * len(uniq) + code)
    df = np.bincount(code, minlength=len(uniq))
    live = df[code] > 1
    owner, code = owner[live], code[live]
    order = np.argsort(code, kind="stable")
    posts, start = owner[order], np.concatenate([[0], np.cumsum(np.bincount(code, minlength=len(uniq)))])
    probe = code[order] * n + posts  # all lists end to end, sorted: one binary search serves any list
    at = np.searchsorted(owner, np.arange(n + 1))
    enough = np.diff(at) >= -(-num * sizes // den)  # a partner of any size shares so many at least
    mixed = bool((side == 0).any() and (side == 1).any())
    joined = Sets(n)
    for x in np.flatnonzero(enough & (sizes > 0) & (side != 3) & ~(mixed & (side == 1))).tolist():
        size = int(sizes[x])
        need = -(-num * size // den)
        own = code[at[x] : at[x + 1]]
        lens = start[own + 1] - start[own]
        longest = int(lens.max())
        long = np.zeros(0, np.int64)
        if longest > LONG:
            by = np.argsort(lens, kind="stable")
            own, lens = own[by], lens[by]
            aside = min(need - 1, int((lens > LONG).sum()), int(need / (0.1 * math.log2(longest) + 1)))
            if aside:
                own, lens, long = own[:-aside], lens[:-aside], own[-aside:]
        if not len(own):
            continue
        found, counts = merged(posts, start[own], lens)
        enough_here = counts >= max(1, need - len(long))
        if not mixed:
            enough_here &= (found > x) | (side[found] == 3)
        found, counts = found[enough_here], counts[enough_here]
        if not len(found):
            continue
        fits = (den * sizes[found] >= num * size) & (num * sizes[found] <= den * size)
        if mixed:
            fits &= side[found] == 1
        root = joined.find(x)
        fits[fits] = [joined.find(y) != root for y in found[fits].tolist()]
        found, total = found[fits], counts[fits]
        if not len(found):
            continue
        if len(long):
            want = long[:, None] * n + found[None, :]
            k = np.minimum(np.searchsorted(probe, want), len(probe) - 1)
            total = total + (probe[k] == want).sum(axis=0)
        good = found[den * total >= num * (size + sizes[found] - total)]
        for y in good.tolist():
            if joined.join(x, y):
                yield x, y


def centre_links(block: np.ndarray, side: np.ndarray, sizes: np.ndarray, tokens: np.ndarray, num: int, den: int) -> Iterator[tuple[int, int]]:
    """Links (i, j) from the one item of side 0 in each block to those of side 1: a block's tokens are sought in its sorted hub, all at once."""
    start = np.cumsum(sizes) - sizes
    name, names = pd.factorize(block)
    centre = np.zeros(len(names), np.int64)
    centre[name[side == 0]] = np.flatnonzero(side == 0)
    size = sizes[centre[name]]
    live = np.flatnonzero((side == 1) & (sizes > 0) & (den * np.minimum(sizes, size) >= num * np.maximum(sizes, size)) & (size > 0))
    live = live[np.argsort(name[live], kind="stable")]
    if not len(live):
        return
    at = name[live]
    for own in np.split(live, np.flatnonzero(at[1:] != at[:-1]) + 1):
        c = int(centre[name[own[0]]])
        held = np.sort(tokens[start[c] : start[c] + sizes[c]])
        n = sizes[own]
        x = np.concatenate([tokens[i : i + k] for i, k in zip(start[own].tolist(), n.tolist(), strict=True)])
        k = np.searchsorted(held, x)
        k[k == len(held)] = 0
        shared = np.add.reduceat(held[k] == x, np.cumsum(n) - n, dtype=np.int64)
        for j in own[den * shared >= num * (n + len(held) - shared)].tolist():
            yield c, j


def _tasks(groups: DataFrame, key: str, budget: int) -> tuple[DataFrame, int]:
    """Groups (key, total) with the number of chunks ``c`` each needs, and how many tasks the small ones share."""
    small = groups.where(F.col("total") <= budget).agg(F.sum("total")).first()[0] or 0
    return groups.withColumn("c", F.ceil(F.col("total") / F.lit(budget)).cast("int")), max(1, math.ceil(small / budget))


def _shared(key: str, n: int):
    return F.concat_ws("/", F.lit("s"), F.pmod(F.xxhash64(key), F.lit(n)).cast("string"))


def centre_places(own: DataFrame, hubs: DataFrame, budget: int) -> DataFrame:
    """(task, block, side, item): every item of ``own`` (p, item, weight) with its hub p; side 0 is the hub, an item of ``hubs`` (p, item)."""
    groups = cut(own.groupBy("p").agg(F.sum("weight").cast("long").alias("total")), "groups")
    groups, n = _tasks(groups, "p", budget)
    task = F.when(F.col("c") > 1, F.concat_ws("/", F.lit("p"), F.col("p").cast("string"), F.col("chunk").cast("string"))).otherwise(_shared("p", n))
    members = own.join(groups, "p").withColumn("chunk", F.pmod(F.xxhash64("item", F.lit(7)), F.col("c")).cast("int")).withColumn("side", F.lit(1))
    centres = hubs.join(groups, "p").withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("c") - 1))).withColumn("side", F.lit(0))
    return members.select("p", "c", "chunk", "side", "item").unionByName(centres.select("p", "c", "chunk", "side", "item")).select(task.alias("task"), F.xxhash64("p", "chunk").alias("block"), "side", "item")


def block_places(placed: DataFrame, comps: DataFrame, budget: int) -> DataFrame:
    """(task, block, side, item) of the blocks in ``placed`` (block, item, weight) that ``comps`` (node, comp) leaves in several components.

    Small blocks share a task and
    compare all their items but those of its largest component. In a larger one, chunks of its largest component meet
    chunks of the rest, and chunks of the rest meet each other.
    """
    cls = placed.join(comps.withColumnRenamed("node", "item"), "item", "left").select("block", "item", "weight", F.coalesce("comp", "item").alias("cls"))
    cls = cut(cls, "classes")
    per = cls.groupBy("block", "cls").agg(F.sum("weight").cast("long").alias("w"))
    blocks = per.groupBy("block").agg(F.count("*").alias("k"), F.sum("w").alias("total"), F.max(F.struct("w", "cls")).alias("big")).where("k > 1")
    blocks = cut(blocks.select("block", "total", F.col("big.cls").alias("big"), F.col("big.w").alias("bw")), "blocks")
    blocks, n = _tasks(blocks, "block", budget)
    at = cls.join(blocks, "block")
    small = at.where("c = 1").select(_shared("block", n).alias("task"), "block", F.when(F.col("cls") == F.col("big"), 3).otherwise(2).alias("side"), "item")
    large = at.where("c > 1").withColumn("cl", F.greatest(F.ceil(F.col("bw") / F.lit(budget)), F.lit(1)).cast("int")).withColumn("co", F.greatest(F.ceil((F.col("total") - F.col("bw")) / F.lit(budget)), F.lit(1)).cast("int"))
    h = F.xxhash64("item", F.lit(7))
    chunk = F.when(F.col("cls") == F.col("big"), F.pmod(h, F.col("cl"))).otherwise(F.pmod(h, F.col("co"))).cast("int")
    large = large.withColumn("chunk", chunk).withColumn("id", F.xxhash64("block").cast("string"))
    name = lambda kind, i, j: F.concat_ws("/", F.lit(kind), F.col("id"), i.cast("string"), j.cast("string"))
    each = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
    big = large.where("cls = big").withColumn("j", each("co")).select(name("l", F.col("chunk"), F.col("j")).alias("task"), "block", F.lit(1).alias("side"), "item")
    rest = large.where("cls <> big")
    across = rest.withColumn("j", each("cl")).select(name("l", F.col("j"), F.col("chunk")).alias("task"), "block", F.lit(0).alias("side"), "item")
    side = F.when(F.col("chunk") > F.col("j"), 1).when(F.col("chunk") < F.col("j"), 0).otherwise(2)
    among = rest.withColumn("j", each("co")).select(name("o", F.least("chunk", "j"), F.greatest("chunk", "j")).alias("task"), "block", side.alias("side"), "item")
    return small.unionByName(big).unionByName(across).unionByName(among)


def verified(dealt: DataFrame, sets: Callable[[pa.Table], tuple[np.ndarray, np.ndarray, np.ndarray]], num: int, den: int) -> DataFrame:
    """Exact links (a, b) of dealt items within blocks.

    ``sets`` turns a task's rows into distinct tokens end to end, their
    offsets, and the rows that take part. Repeated (block, item) rows count once,
    with a column ``mark`` once for each value of it; empty sets link with nothing.
    """
    kind = dealt.schema["item"].dataType.simpleString()

    def run(table: pa.Table) -> pa.Table:
        seen, keep = set(), []
        marks = table["mark"].to_pylist() if "mark" in table.column_names else [0] * table.num_rows
        for k, v in enumerate(zip(table["block"].to_pylist(), map(str, table["item"].to_pylist()), marks, strict=True)):
            if v not in seen:
                seen.add(v)
                keep.append(k)
        table = table.take(keep)
        tokens, off, rows = sets(table)
        block, side = table["block"].to_numpy()[rows], table["side"].to_numpy()[rows]
        alone = len(rows) and side.max() == 1 and side.min() == 0 and len(np.unique(block)) == len(np.unique(block[side == 0])) == (side == 0).sum()
        pairs = list((centre_links if alone else links)(block, side, np.diff(off), tokens, num, den))
        items = table["item"].combine_chunks().take(pa.array(rows))
        a, b = (pa.array([p[k] for p in pairs], pa.int64()) for k in (0, 1))
        return pa.table({"a": items.take(a), "b": items.take(b)})

    return dealt.groupBy("task").applyInArrow(run, f"a {kind}, b {kind}")


def linked_items(near: DataFrame, items: DataFrame, texts: DataFrame, sets: Callable[[pa.Table], tuple[np.ndarray, np.ndarray, np.ndarray]], num: int, den: int, budget: int = 1_000_000) -> DataFrame:
    """(node, comp): components of the exact links among ``items`` (node, item, weight); an item without links has no row.

    ``near`` (a, b): node b is the smallest node under a key of node a, once. ``texts``
    (item, what ``sets`` needs); texts travel, not tokens, as they are several times
    smaller.
    """
    own = cut(near.select(F.col("a").alias("node"), F.col("b").alias("p")).join(items, "node").select("p", "item", "weight"), "own")
    hubs = near.select(F.col("b").alias("p")).distinct().join(items.withColumnRenamed("node", "p"), "p").select("p", "item")
    every = own.select("item").unionByName(hubs.select("item")).distinct()
    texts = cut(texts.join(every, "item", "left_semi"), "texts")
    first = components(verified(centre_places(own, hubs, budget).join(texts, "item"), sets, num, den))
    rest = verified(block_places(own.withColumnRenamed("p", "block"), first, budget).join(texts, "item"), sets, num, den)
    rest = cut(rest, "found")
    if rest.isEmpty():
        return first
    out = components(first.select(F.col("node").alias("a"), F.col("comp").alias("b")).unionByName(rest))
    drop(texts)
    return out


def distinct(x: np.ndarray, owner: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of each of n owners end to end in any order, and their offsets.

    Owners of about one size are the rows of a small matrix, each filled up with its
    last value and sorted by itself.
    """
    if (owner[1:] < owner[:-1]).any():
        order = np.argsort(owner, kind="stable")
        x, owner = x[order], owner[order]
    size = np.bincount(owner, minlength=n)
    start = np.cumsum(size) - size
    rows = np.argsort(size, kind="stable")
    rows = rows[size[rows] > 0]
    width, count = size[rows], np.zeros(n, np.int64)
    parts, i = [x[:0]], 0
    while i < len(rows):
        j = int(np.searchsorted(width, width[i] + width[i] // 8, "right"))
        j = min(j, i + max(1, CELLS // int(width[j - 1])))
        own = rows[i:j]
        m = x[start[own][:, None] + np.minimum(np.arange(width[j - 1]), size[own][:, None] - 1)]
        m.sort(axis=1)
        keep = np.ones(m.shape, bool)
        np.not_equal(m[:, 1:], m[:, :-1], out=keep[:, 1:])
        parts.append(m[keep])
        count[own] = keep.sum(axis=1)
        i = j
    off = np.concatenate([[0], np.cumsum(count)])
    first = np.zeros(n, np.int64)
    first[rows] = np.cumsum(count[rows]) - count[rows]
    return np.concatenate(parts)[np.repeat(first - off[:-1], count) + np.arange(off[-1])], off
