"""Searches inside tasks: the graph goes to every worker once and the roots are dealt out, so that no candidate is shuffled.

An entry (v, hub) stays in the index just if no earlier vertex lies on any shortest
path between the two. A search can see that by itself: it carries a mark from every
vertex that ranks before its root, and ends once each vertex of its last level is
marked. 64 roots search together, a bit of a word each.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Edge entries up to which a graph is held by every worker (4 bytes each); larger ones go through rounds of joins.
HELD_EDGES = 10_000_000
#: The same for the entries of an index (12 bytes each).
HELD_LABELS = 20_000_000
#: The same for asked pairs (24 bytes each).
HELD_PAIRS = 5_000_000
#: Rows of a batch that a task hands on.
ROWS = 1 << 17
WIDTH = 64


def columns(df: DataFrame) -> list[np.ndarray]:
    """The columns of a bounded table of numbers, on the driver."""
    table = df.toArrow()
    return [table.column(c).to_numpy() for c in df.columns]


def csr(n: int, key: np.ndarray, *values: np.ndarray) -> tuple[np.ndarray, ...]:
    """(first row of each key, values in order of key)."""
    order = np.argsort(key, kind="stable")
    return np.concatenate([[0], np.cumsum(np.bincount(key, minlength=n))]), *(v[order] for v in values)


def spread(ptr: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(rows of the keys ``at`` one after another, how many of each)."""
    deg = ptr[at + 1] - ptr[at]
    return np.repeat(ptr[at] - (np.cumsum(deg) - deg), deg) + np.arange(deg.sum()), deg


class Held:
    """A graph as workers get it: vertices by place in the order of their ranks, edges forth and back."""

    def __init__(self, ids: np.ndarray, u: np.ndarray, v: np.ndarray, both: bool):
        self.ids, n = ids, len(ids)
        a, b = np.searchsorted(ids, u).astype(np.int32), np.searchsorted(ids, v).astype(np.int32)
        self.forth = csr(n, a, b)
        self.back = csr(n, b, a) if both else self.forth

    def turned(self) -> Held:
        out = object.__new__(Held)
        out.ids, out.forth, out.back = self.ids, self.back, self.forth
        return out

    def levels(self, roots: np.ndarray, first: np.ndarray | None = None, marks: bool = True, depth: int | None = None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(d, places, words) of at most 64 ascending roots: whom each finds at distance d, unmarked if ``marks``; what is ``first`` marks like an earlier vertex."""
        (ptr, nbr), (rptr, rnbr) = self.forth, self.back
        n, m = len(self.ids), len(nbr)
        low = np.array([(1 << 64) - (1 << c) for c in range(65)], np.uint64)  # bits of the roots from the c-th on
        has = np.flatnonzero(rptr[1:] > rptr[:-1])
        seen = np.zeros(n, np.uint64)
        at, word = roots, np.uint64(1) << np.arange(len(roots), dtype=np.uint64)
        mark, d = np.zeros(len(roots), np.uint64), 0
        seen[at] = word
        yield d, at, word
        while depth is None or d < depth:
            d += 1
            if 16 * int((ptr[at + 1] - ptr[at]).sum()) < m:
                rows, deg = spread(ptr, at)
                to = nbr[rows]
                order = np.argsort(to, kind="stable")
                to = to[order]
                cuts = np.flatnonzero(np.concatenate([[True], to[1:] != to[:-1]])) if len(to) else np.zeros(0, np.int64)
                to, got = to[cuts], [np.bitwise_or.reduceat(np.repeat(x, deg)[order], cuts) if len(cuts) else x[:0] for x in ((word, mark) if marks else (word,))]
            else:
                to, got = has, []
                for x in (word, mark) if marks else (word,):
                    full = np.zeros(n, np.uint64)
                    full[at] = x
                    got.append(np.bitwise_or.reduceat(full[rnbr], rptr[has]))
            new = got[0] & ~seen[to]
            hit = np.flatnonzero(new)
            at, word = to[hit], new[hit]
            if marks:
                mark = got[1][hit] | low[np.searchsorted(roots, at, side="right")]
                if first is not None:
                    mark[first[at]] = low[0]
                mark &= word
                clean = word & ~mark
                alive = np.bitwise_or.reduce(clean) if len(clean) else np.uint64(0)
                keep = np.flatnonzero(word & alive)
                at, word, mark, clean = at[keep], word[keep] & alive, mark[keep] & alive, clean[keep]
            else:
                mark, clean = np.zeros(len(at), np.uint64), word
            if not len(at):
                return
            seen[at] |= word
            yield d, at, clean

    def rows(self, roots: np.ndarray, **how) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(place, root's number among ``roots``, d) of every find."""
        for d, at, word in self.levels(roots, **how):
            r, c = np.nonzero(np.unpackbits(word.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
            yield at[r], c, np.full(len(r), d, np.int32)

    def matrix(self, roots: np.ndarray, kind: type = np.int32, none: int = -1) -> np.ndarray:
        """Distances from each root to all; ``none`` where there is no path."""
        out = np.full((len(self.ids), len(roots)), none, kind)
        for d, at, word in self.levels(roots, marks=False):
            if none > 0 and d >= none:
                raise OverflowError("a distance is as large as the mark for none")
            found = np.unpackbits(word.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")[:, : len(roots)]
            out[at] ^= found * kind(none ^ d)  # each is found once
        return np.ascontiguousarray(out.T)


class Entries:
    """An index as workers get it: places of an undirected graph, entries by hub, those of hubs with many as packed rows of distances to all vertices.

    ``far`` stands for no entry: larger than any sum of two distances, and can be
    added to a distance.
    """

    #: Bytes of the rows of hubs with many entries, unpacked.
    WIDE = 1 << 27

    def __init__(self, n: int, key: np.ndarray, top: int):
        """``key``: (hub * n + v) * top + distance of every entry, distances below ``top``; is sorted in place."""
        self.n, self.kind, self.far = n, *((np.uint8, 128) if top <= 64 else (np.int32, 1 << 29))
        key.sort()
        ends = np.searchsorted(key, np.arange(n + 1) * (n * top))
        many = np.diff(ends)
        wide = np.argsort(-many, kind="stable")[: self.WIDE // (max(1, n) * np.dtype(self.kind).itemsize)]
        self.wide = np.sort(wide[many[wide] > n // 32])  # below that a list is read faster than a row
        self.packed, rest = [], np.ones(len(key), bool)
        for h in self.wide:
            own = key[ends[h] : ends[h + 1]]
            row = np.full(n, self.far, self.kind)
            row[own // top % n] = own % top
            self.packed.append(pa.compress(row.tobytes(), codec="zstd", asbytes=True))
            rest[ends[h] : ends[h + 1]] = False
        key = key[rest]
        self.v, self.d = (key // top % n).astype(np.int32), (key % top).astype(self.kind)
        many[self.wide] = 0
        self.ptr = np.concatenate([[0], np.cumsum(many)])
        self.rows = None

    def unpack(self) -> Entries:
        """Once a worker: rows, and the lists by vertex."""
        if self.rows is None:
            size = self.n * np.dtype(self.kind).itemsize
            self.rows = np.empty((len(self.wide), self.n), self.kind)
            for row, x in zip(self.rows, self.packed, strict=True):
                row[:] = np.frombuffer(pa.decompress(x, size, codec="zstd"), self.kind)
            self.own = csr(self.n, self.v, np.repeat(np.arange(self.n, dtype=np.int32), np.diff(self.ptr)), self.d)
        return self

    def sums(self, lo: int, hi: int) -> Iterator[tuple[int, Iterator[tuple[int, object, np.ndarray]]]]:
        """For each source from ``lo`` to below ``hi``: (hub, places counted from the source on, sums there) of its hubs in order; sums of a row hold for a moment only."""
        near, buf = np.ascontiguousarray(self.rows[:, lo:hi].T), np.empty(self.n, self.kind)
        ptr, hubs, dists = self.own

        def of(s: int) -> Iterator[tuple[int, object, np.ndarray]]:
            has = np.flatnonzero(near[s - lo] < self.far)
            own = slice(ptr[s], ptr[s + 1])
            every = np.concatenate([self.wide[has], hubs[own]])
            which = np.concatenate([has, np.full(ptr[s + 1] - ptr[s], -1)])
            das = np.concatenate([near[s - lo, has], dists[own]])
            for i in np.argsort(every, kind="stable"):
                h, da = int(every[i]), das[i]
                if which[i] >= 0:
                    yield h, slice(None), np.add(self.rows[which[i], s:], da, out=buf[s:])
                else:
                    at = self.v[self.ptr[h] : self.ptr[h + 1]]
                    first = np.searchsorted(at, s)
                    yield h, at[first:] - s, self.d[self.ptr[h] + first : self.ptr[h + 1]] + da

        for s in range(lo, hi):
            yield s, of(s)


def hold(edges: DataFrame, vertices: DataFrame, both: bool = False, limit: int | None = None) -> Held | None:
    """The graph of edges (u, v) and vertices (v); None above the limit. ``both``: edges have a direction."""
    edges = edges.select("u", "v")
    if edges.count() > (HELD_EDGES if limit is None else limit):
        return None
    u, v = columns(edges)
    return Held(np.unique(np.concatenate([*columns(vertices.select("v")), u, v])), u, v, both)


def batched(parts: Iterator[tuple], names: list[str]) -> Iterator[pa.RecordBatch]:
    """Arrays as batches of some size."""
    kept, size = [], 0
    for x in parts:
        kept.append(x)
        size += len(x[0])
        if size >= ROWS:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*kept, strict=True)], names)
            kept, size = [], 0
    if size:
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*kept, strict=True)], names)


def dealt(spark, what: object, count: int, run: Callable[[object, int], Iterator[tuple]], schema: str) -> DataFrame:
    """What ``run`` gives for each of ``count`` pieces of work, which are dealt out in turn; ``what`` goes to every worker once."""
    tasks = max(1, min(count, 4 * max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))))
    sent = spark.sparkContext.broadcast(what)
    names = [x.split()[0] for x in schema.split(", ")]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in b.column(0).to_pylist():
                yield from batched((x for k in range(i, count, tasks) for x in run(sent.value, k)), names)

    return spark.range(0, tasks, 1, tasks).mapInArrow(work, schema)


def places(graph: Held, roots: DataFrame, col: str) -> np.ndarray:
    return np.searchsorted(graph.ids, np.unique(columns(roots.select(col))[0]))


def split(graph: Held, roots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(roots with a later neighbour, the others, whose only entry is themselves)."""
    ptr, nbr = graph.forth
    has = np.flatnonzero(ptr[1:] > ptr[:-1])
    latest = np.full(len(graph.ids), -1, np.int64)
    if len(has):
        latest[has] = np.maximum.reduceat(nbr, ptr[has])
    return roots[latest[roots] > roots], roots[latest[roots] <= roots]


def labels(spark, graph: Held, roots: np.ndarray, first: np.ndarray | None = None, depth: int | None = None) -> DataFrame:
    """Index entries (v, hub, dist) of the roots. Only roots with a later neighbour search; the others have themselves."""
    wide, alone = split(graph, roots)
    one = 1 << 16
    n = -(-len(wide) // WIDTH)

    def run(x: tuple, k: int) -> Iterator[tuple]:
        g, wide, alone, first = x
        if k >= n:
            own = g.ids[alone[(k - n) * one : (k - n + 1) * one]]
            yield own, own, np.zeros(len(own), np.int32)
            return
        some = wide[k * WIDTH : (k + 1) * WIDTH]
        for v, c, d in g.rows(some, first=first, depth=depth):
            yield g.ids[v], g.ids[some[c]], d

    return dealt(spark, (graph, wide, alone, first), n - (-len(alone) // one), run, "v long, hub long, dist int")


def searches(spark, graph: Held, roots: np.ndarray, depth: int | None = None) -> DataFrame:
    """Distances (v, hub, dist) from every root to all it reaches."""

    def run(x: tuple, k: int) -> Iterator[tuple]:
        g, roots = x
        some = roots[k * WIDTH : (k + 1) * WIDTH]
        for v, c, d in g.rows(some, marks=False, depth=depth):
            yield g.ids[v], g.ids[some[c]], d

    return dealt(spark, (graph, roots), -(-len(roots) // WIDTH), run, "v long, hub long, dist int")


def answers(spark, graph: Held, roots: np.ndarray, qid: np.ndarray, s: np.ndarray, t: np.ndarray) -> DataFrame:
    """(qid, dist, first): least sum and first hub with it of the pairs of places (s, t), over the index of the roots, which is not written.

    The two entries of a pair under one hub come from the hub's own search, so each
    task joins them hub by hub and hands on its best of every pair; a pair may have
    a row from every task. Pairs without a shared hub have none.
    """
    wide, alone = split(graph, roots)
    tasks = max(1, min(-(-len(wide) // WIDTH), 2 * spark.sparkContext.defaultParallelism))
    none = np.iinfo(np.int64).max

    def run(x: tuple, task: int) -> Iterator[tuple]:
        g, wide, alone, (ptr, own, qid, t) = x
        n, far = len(g.ids), 1 << 30
        best = np.full(len(t), none)  # sum, then place of the hub
        if not task:
            same = np.flatnonzero((own == t) & np.isin(t, alone))
            best[same] = t[same]
        dist = np.full(n, far, np.int64)
        for lo in range(task * WIDTH, len(wide), tasks * WIDTH):
            some = wide[lo : lo + WIDTH]
            found = [(d, at, word, np.bitwise_or.reduce(word)) for d, at, word in g.levels(some)]
            for c, hub in enumerate(some):
                bit = np.uint64(1 << c)
                levels = [(at[(word & bit) != 0], d) for d, at, word, every in found if every & bit]
                v = np.concatenate([at for at, _ in levels])
                dist[v] = np.repeat([d for _, d in levels], [len(at) for at, _ in levels])
                rows, deg = spread(ptr, v)
                total = np.repeat(dist[v], deg) + dist[t[rows]]
                met = total < far
                rows = rows[met]
                best[rows] = np.minimum(best[rows], (total[met] << 32) | int(hub))
                dist[v] = far
        for lo in range(0, len(best), ROWS):
            at = lo + np.flatnonzero(best[lo : lo + ROWS] != none)
            yield qid[at], (best[at] >> 32).astype(np.int32), g.ids[best[at] & 0xFFFFFFFF]

    asked = csr(len(graph.ids), s, s, qid, t)
    got = dealt(spark, (graph, wide, alone, asked), tasks, run, "qid long, dist int, first long")
    return got.groupBy("qid").agg(F.min(F.struct("dist", "first")).alias("m")).select("qid", "m.dist", "m.first")
