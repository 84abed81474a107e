"""Measures of an index and of graphs: sizes, searches, coverage, distances, errors, times."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import reach
from .query import query_labels


def timed(name: str, build: Callable[[], DataFrame], reps: int = 1) -> tuple[str, float, int]:
    """Best wall seconds of a full evaluation, and the rows."""
    best = float("inf")
    for _ in range(reps):
        t = time.time()
        df = build()
        df.write.format("noop").mode("overwrite").save()
        best = min(best, time.time() - t)
    return name, best, df.count()


def index_bytes(labels: DataFrame, bp: DataFrame | None = None) -> DataFrame:
    """(part, rows, model_bytes): 5 bytes an entry, 17 a vertex and slot."""
    out = labels.agg(F.lit("labels").alias("part"), F.count("*").alias("rows"), (F.count("*") * 5).alias("model_bytes"))
    return out if bp is None else out.unionByName(bp.agg(F.lit("bit_parallel").alias("part"), F.count("*").alias("rows"), (F.count("*") * 17).alias("model_bytes")))


def label_sizes(labels: DataFrame, vertices: DataFrame) -> DataFrame:
    """(v, size) for every vertex."""
    return vertices.select("v").join(labels.groupBy("v").agg(F.count("*").alias("size")), "v", "left").select("v", F.coalesce("size", F.lit(0)).alias("size"))


def label_size_summary(sizes: DataFrame) -> DataFrame:
    return sizes.agg(F.avg("size").alias("mean"), F.max("size").alias("max"), F.percentile_approx("size", 0.5).alias("p50"), F.percentile_approx("size", 0.99).alias("p99"))


def size_histogram(sizes: DataFrame) -> DataFrame:
    return sizes.groupBy("size").agg(F.count("*").alias("vertices"))


def labels_per_search(labels: DataFrame) -> DataFrame:
    """(hub, added) per search."""
    return labels.groupBy("hub").agg(F.count("*").alias("added"))


def running(df: DataFrame, key: str, value: str, name: str, width: int = 4096) -> DataFrame:
    """``df`` with a running sum in order of an integer key: within blocks of the key, plus the sums of earlier blocks."""
    b = df.withColumn("_b", F.floor(F.col(key) / F.lit(width)))
    before = b.groupBy("_b").agg(F.sum(value).alias("_s")).select("_b", F.coalesce(F.sum("_s").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_s"))
    w = Window.partitionBy("_b").orderBy(key).rowsBetween(Window.unboundedPreceding, 0)
    return b.withColumn("_r", F.sum(value).over(w)).join(before, "_b").select(*df.columns, (F.col("_r") + F.col("_s")).alias(name))


def coverage_steps(labels: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, dist, first): per connected pair of ``truth`` (qid, s, t, dist) the first search whose hub gives the exact distance; one pass serves every step."""
    a = labels.select(F.col("v").alias("s"), "hub", F.col("dist").alias("da"))
    b = labels.select(F.col("v").alias("t"), "hub", F.col("dist").alias("db"))
    pairs = truth.where("dist is not null")
    return pairs.join(a, "s").join(b, ["t", "hub"]).where("da + db = dist").groupBy("qid", "dist").agg(F.min("hub").alias("first"))


def query_steps(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """``coverage_steps`` of pairs (qid, s, t) whose distance is the index's own, in one pass: least sum, then least hub."""
    a = labels.select(F.col("v").alias("s"), "hub", F.col("dist").alias("da"))
    b = labels.select(F.col("v").alias("t"), "hub", F.col("dist").alias("db"))
    got = pairs.join(a, "s").join(b, ["t", "hub"]).groupBy("qid").agg(F.min(F.struct((F.col("da") + F.col("db")).alias("dist"), "hub")).alias("m"))
    return got.select("qid", "m.dist", F.col("m.hub").alias("first"))


def search_answers(edges: DataFrame, vertices: DataFrame, pairs: DataFrame) -> DataFrame | None:
    """``query_steps`` of the pruned index of all vertices, joined where its entries are found and so never written or shuffled. None if the graph is too large to be held or the pairs too many."""
    if pairs.count() > reach.HELD_PAIRS or (graph := reach.hold(edges, vertices)) is None:
        return None
    qid, s, t = reach.columns(pairs.select("qid", "s", "t").dropna())
    known = np.isin(s, graph.ids) & np.isin(t, graph.ids)
    s, t = (np.searchsorted(graph.ids, x[known]).astype(np.int32) for x in (s, t))
    return reach.answers(edges.sparkSession, graph, reach.places(graph, vertices, "v"), qid[known], s, t)


def index_sums(edges: DataFrame, vertices: DataFrame, labels: DataFrame) -> tuple | None:
    """(work, run, pieces): an undirected graph and an index as workers get them, and for each piece of work the sources with (distances to the vertices from the source on, the sums that each of its hubs gives them); None if either is too large.

    Only half of the ordered pairs are gone through, as both directions of a pair
    have the same distance, hubs and sums. A distance of ``far`` means no path.
    """
    size, top = labels.agg(F.count("*"), F.coalesce(F.max("dist"), F.lit(0)) + 1).first()
    if size > reach.HELD_LABELS or (graph := reach.hold(edges, vertices)) is None:
        return None
    n, top = len(graph.ids), int(top)
    if not n or graph.ids[-1] == n - 1:  # ids are places
        (key,) = reach.columns(labels.select(((F.col("hub").cast("long") * n + F.col("v")) * top + F.col("dist")).alias("key")))
        key = key.copy() if not key.flags.writeable else key
    else:
        v, hub, dist = reach.columns(labels.select("v", "hub", "dist"))
        key = (np.searchsorted(graph.ids, hub) * n + np.searchsorted(graph.ids, v)) * top + dist
    entries = reach.Entries(n, key, top)

    def run(x: tuple, k: int) -> Iterator[tuple]:
        graph, entries = x
        lo, hi = k * reach.WIDTH, min(n, (k + 1) * reach.WIDTH)
        far, kind = entries.far, entries.kind
        try:
            true = graph.matrix(np.arange(lo, hi), kind, far)
        except OverflowError:  # only if the index lacks pairs: distances beyond twice its largest
            far, kind = 1 << 29, np.int32
            true = graph.matrix(np.arange(lo, hi), kind, far)
        for s, sums in entries.unpack().sums(lo, hi):
            yield s, true[s - lo, s:], far, sums

    return (graph, entries), run, -(-n // reach.WIDTH)


def first_counts(edges: DataFrame, vertices: DataFrame, labels: DataFrame) -> DataFrame | None:
    """(dist, first, pairs): over all ordered pairs, as ``coverage_steps`` finds them one by one."""
    if (held := index_sums(edges, vertices, labels)) is None:
        return None
    work, run, pieces = held

    def count(x: tuple, k: int) -> Iterator[tuple]:
        entries, ids, got = x[1], x[0].ids, {}
        for _, true, _, sums in run(x, k):
            left = true.copy()
            left[left >= entries.far] = done = np.iinfo(left.dtype).max  # no path, or farther than any sum; no sum is as large
            for h, at, total in sums:
                met = np.flatnonzero(total == left[at])
                if not len(met):
                    continue
                met = met if isinstance(at, slice) else at[met]
                dists, pairs = np.unique(left[met], return_counts=True) if left.itemsize > 1 else _small_counts(left[met])
                own = got.setdefault(h, {})
                for d, c in zip(dists.tolist(), pairs.tolist(), strict=True):
                    own[d] = own.get(d, 0) + (2 * c if d else c)  # both directions, but a vertex and itself once
                left[met] = done
        rows = [(d, h, c) for h, own in got.items() for d, c in own.items()]
        if rows:
            d, h, c = (np.array(x, np.int64) for x in zip(*rows, strict=True))
            yield d.astype(np.int32), ids[h], c

    return reach.dealt(edges.sparkSession, work, pieces, count, "dist int, first long, pairs long")


def _small_counts(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    every = np.bincount(x)
    at = np.flatnonzero(every)
    return at, every[at]


def coverage(first: DataFrame, steps: list[int], by_distance: bool = False) -> DataFrame:
    """(k[, dist], covered, total): pairs that the first k searches answer exactly; ``first`` has a row for each pair, or for each number of ``pairs``."""
    pairs = F.col("pairs") if "pairs" in first.columns else F.lit(1)
    sums = [F.sum(F.when(F.col("first") < k, pairs).otherwise(0).cast("long")).alias(f"k{k}") for k in steps]
    agg = first.groupBy(*(["dist"] if by_distance else [])).agg(F.sum(pairs).cast("long").alias("total"), *sums)
    each = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"k{k}").alias("covered")) for k in steps])).alias("x")
    return agg.select(*(["dist"] if by_distance else []), "total", each).select("x.k", *(["dist"] if by_distance else []), "x.covered", "total")


def degree_ccdf(edges: DataFrame) -> DataFrame:
    """(degree, vertices_ge) over vertices with an edge."""
    hist = edges.groupBy("u").count().groupBy(F.col("count").alias("degree")).agg(F.count("*").alias("n"))
    neg = running(hist.withColumn("neg", -F.col("degree")), "neg", "n", "vertices_ge")
    return neg.select("degree", "vertices_ge")


def ccdf_slope(ccdf: DataFrame) -> DataFrame:
    return ccdf.agg(F.expr("regr_slope(ln(vertices_ge), ln(degree))").alias("slope"))


def distance_histogram(answers: DataFrame) -> DataFrame:
    """(dist, pairs); null distance: no path."""
    return answers.groupBy("dist").agg(F.count("*").alias("pairs"))


def search_space(labels: DataFrame, edges: DataFrame) -> DataFrame:
    """(hub, visited, labelled, pruned): a search visits its labelled vertices and their neighbours of later or equal standing reach."""
    own = labels.select("hub", "v")
    seen = own.unionByName(own.select("hub", F.col("v").alias("u")).join(edges.select("u", "v"), "u").select("hub", "v")).distinct()
    got = seen.groupBy("hub").agg(F.count("*").alias("visited")).join(own.groupBy("hub").agg(F.count("*").alias("labelled")), "hub")
    return got.select("hub", "visited", "labelled", (F.col("visited") - F.col("labelled")).alias("pruned"))


def estimate_error(estimate: DataFrame, truth: DataFrame) -> DataFrame:
    """(dist, n, exact, sum_abs_err, sum_rel_err) of upper bounds, per distance above 0; null dist: over all."""
    both = estimate.join(truth.where("dist > 0").select("qid", "dist"), "qid").where("upper is not null")
    err = F.col("upper") - F.col("dist")
    return both.rollup("dist").agg(F.count("*").alias("n"), F.sum((err == 0).cast("long")).alias("exact"), F.sum(err).alias("sum_abs_err"), F.sum(err / F.col("dist")).alias("sum_rel_err"))


def landmark_bound(labels: DataFrame, first: DataFrame, k: int) -> DataFrame:
    """(beyond, uncovered): entries of searches from k on never exceed the pairs not covered by the first k."""
    return labels.where(F.col("hub") >= k).agg(F.count("*").alias("beyond")).crossJoin(first.where(F.col("first") >= k).agg(F.count("*").alias("uncovered")))


def speedups(report: DataFrame, metric: str, base: str) -> DataFrame:
    """Ratios of a metric of the base method to every method's, per graph."""
    r = report.where(F.col("metric") == metric)
    b = r.where(F.col("method") == base).select("graph", F.col("value").alias("base"))
    return r.join(b, "graph").select("graph", "method", (F.col("base") / F.col("value")).alias("ratio"))


def audit_minimal(labels: DataFrame) -> DataFrame:
    """Entries that could go without changing any distance: must be empty."""
    cand = labels.where("v <> hub")
    a = labels.select(F.col("v").alias("hub"), F.col("hub").alias("h2"), F.col("dist").alias("da"))
    b = labels.select("v", F.col("hub").alias("h2"), F.col("dist").alias("db"))
    return cand.join(a, "hub").where("h2 <> hub").join(b, ["v", "h2"]).where("da + db <= dist").select("v", "hub").distinct()


def audit_cover(labels: DataFrame, truth: DataFrame) -> DataFrame:
    """Pairs whose label distance is not the true one: must be empty."""
    got = query_labels(labels, truth.select("qid", "s", "t"))
    return got.join(truth.select("qid", F.col("dist").alias("true")), "qid").where(~F.col("dist").eqNullSafe(F.col("true")))


def audit_cover_all(edges: DataFrame, vertices: DataFrame, labels: DataFrame) -> DataFrame | None:
    """``audit_cover`` over all ordered pairs, with true distances from searches: (s, t, dist, true) where they differ, null for none. None if the graph or index is too large to be held."""
    if (held := index_sums(edges, vertices, labels)) is None:
        return None
    work, run, pieces = held

    def wrong(x: tuple, k: int) -> Iterator[tuple]:
        entries, ids = x[1], x[0].ids
        for s, true, far, sums in run(x, k):
            least = np.full(len(true), entries.far, entries.kind)
            for _, at, total in sums:
                if isinstance(at, slice):
                    np.minimum(least, total, out=least)
                else:
                    least[at] = np.minimum(least[at], total)
            least = least.astype(true.dtype)
            least[least >= entries.far] = far
            bad = np.flatnonzero(least != true)
            if len(bad):
                a, b, got, want = np.full(len(bad), ids[s]), ids[bad + s], *(np.where(x[bad] == far, -1, x[bad].astype(np.int32)).astype(np.int32) for x in (least, true))
                yield a, b, got, want
                back = bad > 0
                yield b[back], a[back], got[back], want[back]

    got = reach.dealt(edges.sparkSession, work, pieces, wrong, "s long, t long, dist int, true int")
    return got.select("s", "t", *(F.when(F.col(c) >= 0, F.col(c)).alias(c) for c in ("dist", "true")))


def audit_prefix(pruned: DataFrame, naive: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """Pairs that the first k pruned searches answer otherwise than k full ones: must be empty."""
    a = query_labels(pruned.where(F.col("hub") < k), pairs)
    b = query_labels(naive.where(F.col("hub") < k), pairs).select("qid", F.col("dist").alias("full"))
    return a.join(b, "qid").where(~F.col("dist").eqNullSafe(F.col("full")))


def prefix_steps(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """(qid, k, dist): every step k at which the answer from the first k + 1 searches improves, and the answer from there on."""
    a = labels.select(F.col("v").alias("s"), "hub", F.col("dist").alias("da"))
    b = labels.select(F.col("v").alias("t"), "hub", F.col("dist").alias("db"))
    sums = pairs.join(a, "s").join(b, ["t", "hub"]).select("qid", F.col("hub").alias("k"), (F.col("da") + F.col("db")).alias("dist"))
    before = F.min("dist").over(Window.partitionBy("qid").orderBy("k").rowsBetween(Window.unboundedPreceding, -1))
    return sums.withColumn("before", before).where("before is null or dist < before").drop("before")


def search_steps(edges: DataFrame, vertices: DataFrame, pairs: DataFrame) -> DataFrame | None:
    """``prefix_steps`` of full searches from every vertex, without their table: the distances of both ends to all vertices. None if the graph is too large to be held."""
    if (graph := reach.hold(edges, vertices)) is None:
        return None
    qid, s, t = reach.columns(pairs.select("qid", "s", "t"))
    known = np.isin(s, graph.ids) & np.isin(t, graph.ids)
    qid, s, t = qid[known], np.searchsorted(graph.ids, s[known]), np.searchsorted(graph.ids, t[known])

    def run(x: tuple, k: int) -> Iterator[tuple]:
        graph, qid, s, t = x
        own = slice(k * reach.WIDTH, (k + 1) * reach.WIDTH)
        (a, i), (b, j) = np.unique(s[own], return_inverse=True), np.unique(t[own], return_inverse=True)
        for q, x, y in zip(qid[own], graph.matrix(a)[i], graph.matrix(b)[j], strict=True):
            total = np.where((x < 0) | (y < 0), 1 << 30, x + y)
            before = np.minimum.accumulate(np.concatenate([[1 << 30], total[:-1]]))
            at = np.flatnonzero(total < before)
            yield np.full(len(at), q), graph.ids[at], total[at].astype(np.int32)

    return reach.dealt(edges.sparkSession, (graph, qid, s, t), -(-len(qid) // reach.WIDTH), run, "qid long, k long, dist int")


def audit_prefix_all(pruned: DataFrame, naive: DataFrame, pairs: DataFrame) -> DataFrame:
    """(steps, violations): improvements of the full searches over all k, and those the pruned ones lack or have besides: none."""
    return compare_steps(prefix_steps(naive, pairs), prefix_steps(pruned, pairs))


def compare_steps(full: DataFrame, own: DataFrame) -> DataFrame:
    """``audit_prefix_all`` of improvements that are at hand."""
    a, b = full.withColumn("full", F.lit(1)), own.withColumn("own", F.lit(1))
    return a.join(b, ["qid", "k", "dist"], "full").agg(F.count("full").alias("steps"), F.sum((F.col("full").isNull() | F.col("own").isNull()).cast("long")).alias("violations"))
