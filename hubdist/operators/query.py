"""Distance and path queries over an index, in batches; null means no path."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bitparallel import query_bitparallel


def query_labels(labels: DataFrame, pairs: DataFrame, labels_in: DataFrame | None = None) -> DataFrame:
    """(qid, s, t, dist): least sum over shared hubs. With ``labels_in`` the graph is directed and ``labels`` are the outgoing ones."""
    a = labels.select(F.col("v").alias("s"), "hub", F.col("dist").alias("da"))
    b = (labels if labels_in is None else labels_in).select(F.col("v").alias("t"), "hub", F.col("dist").alias("db"))
    got = pairs.join(a, "s").join(b, ["t", "hub"]).groupBy("qid").agg(F.min(F.col("da") + F.col("db")).alias("dist"))
    return pairs.join(got, "qid", "left").select("qid", "s", "t", "dist")


def query_directed(labels_out: DataFrame, labels_in: DataFrame, pairs: DataFrame) -> DataFrame:
    return query_labels(labels_out, pairs, labels_in)


def pack(labels: DataFrame) -> DataFrame:
    """(v, hubs, dists): parallel arrays sorted by hub."""
    got = labels.groupBy("v").agg(F.array_sort(F.collect_list(F.struct("hub", "dist"))).alias("l"))
    return got.select("v", F.col("l.hub").alias("hubs"), F.col("l.dist").alias("dists"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("v", F.explode(F.arrays_zip("hubs", "dists")).alias("x")).select("v", F.col("x.hubs").alias("hub"), F.col("x.dists").alias("dist"))


def packed_distance(ha, da, hb, db) -> F.Column:
    """Least sum over the hubs that two packed labels share: the shared hubs once, then a place in each array for every one of them."""
    at = lambda hubs, dists, h: F.element_at(dists, F.array_position(hubs, h).cast("int"))
    return F.array_min(F.transform(F.array_intersect(ha, hb), lambda h: at(ha, da, h) + at(hb, db, h)))


def query_packed(packed: DataFrame, pairs: DataFrame) -> DataFrame:
    """As ``query_labels``, but one row per pair moves, not one per label entry."""
    a = packed.select(F.col("v").alias("s"), F.col("hubs").alias("ha"), F.col("dists").alias("da"))
    b = packed.select(F.col("v").alias("t"), F.col("hubs").alias("hb"), F.col("dists").alias("db"))
    got = pairs.join(a, "s", "left").join(b, "t", "left")
    return got.select("qid", "s", "t", F.when(F.col("ha").isNotNull() & F.col("hb").isNotNull(), packed_distance(F.col("ha"), F.col("da"), F.col("hb"), F.col("db"))).alias("dist"))


def query_combined(bp: DataFrame, labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """The smaller of the bit-parallel and the label distance."""
    x = query_bitparallel(bp, pairs).select("qid", F.col("dist").alias("x"))
    return query_labels(labels, pairs).join(x, "qid").select("qid", "s", "t", F.least("dist", "x").alias("dist"))


def query_one(labels: DataFrame, s: int, t: int) -> DataFrame:
    """A single pair; on an index clustered by vertex the filters read the files of two vertices."""
    a = labels.where(F.col("v") == s).select("hub", F.col("dist").alias("da"))
    b = labels.where(F.col("v") == t).select("hub", F.col("dist").alias("db"))
    return a.join(b, "hub").agg(F.min(F.col("da") + F.col("db")).alias("dist")).select(F.lit(s).alias("s"), F.lit(t).alias("t"), "dist")


def resolve(pairs: DataFrame, ranks: DataFrame) -> DataFrame:
    """Pairs of vids as pairs of ranks, kept beside them as s_vid and t_vid."""
    a, b = ranks.select(F.col("vid").alias("s_vid"), F.col("rnk").alias("s")), ranks.select(F.col("vid").alias("t_vid"), F.col("rnk").alias("t"))
    return pairs.select("qid", F.col("s").alias("s_vid"), F.col("t").alias("t_vid")).join(a, "s_vid").join(b, "t_vid").select("qid", "s", "t", "s_vid", "t_vid")


def paths(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """(qid, step, v): a shortest path of every pair that has one, by walking parents from both ends to the best shared hub."""
    a = labels.select(F.col("v").alias("s"), "hub", F.col("dist").alias("da"))
    b = labels.select(F.col("v").alias("t"), "hub", F.col("dist").alias("db"))
    best = pairs.join(a, "s").join(b, ["t", "hub"]).groupBy("qid", "s", "t").agg(F.min(F.struct((F.col("da") + F.col("db")).alias("d"), "hub", "da")).alias("m"))
    walk = best.select("qid", F.lit(0).alias("half"), F.col("s").alias("v"), F.col("m.hub").alias("hub"), F.lit(0).alias("step"), F.col("m.d").alias("d"))
    walk = walk.unionByName(best.select("qid", F.lit(1).alias("half"), F.col("t").alias("v"), F.col("m.hub").alias("hub"), F.lit(0).alias("step"), F.col("m.d").alias("d")))
    from ..plans.scratch import cut

    up = labels.select("v", "hub", "parent")
    parts, now = [], cut(walk, "walk")
    while not now.isEmpty():
        parts.append(now)
        now = cut(now.where("v <> hub").join(up, ["v", "hub"]).select("qid", "half", F.col("parent").alias("v"), "hub", (F.col("step") + 1).alias("step"), "d"), "walk")
    if not parts:
        return walk.select("qid", "step", "v")
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    return every.where("half = 0 or v <> hub").select("qid", F.when(F.col("half") == 0, F.col("step")).otherwise(F.col("d") - F.col("step")).alias("step"), "v")


def outlier_vertices(labels: DataFrame, threshold: int) -> DataFrame:
    """Vertices with more label entries than the threshold."""
    return labels.groupBy("v").count().where(F.col("count") > threshold).select("v")


def precompute_rows(edges: DataFrame, outliers: DataFrame) -> DataFrame:
    """Full distance rows (s, t, dist) of the outliers."""
    from .search import label_naive

    return label_naive(edges, outliers.select(F.col("v").alias("hub"))).select(F.col("hub").alias("s"), F.col("v").alias("t"), "dist")


def query_with_rows(labels: DataFrame, rows: DataFrame, pairs: DataFrame) -> DataFrame:
    """Pairs with an end among the outliers are read off; the rest use labels."""
    both = rows.unionByName(rows.select(F.col("t").alias("s"), F.col("s").alias("t"), "dist")).distinct()
    own = rows.select("s").distinct()
    heavy = pairs.join(own, "s", "left_semi").unionByName(pairs.join(own, "s", "left_anti").join(own.withColumnRenamed("s", "t"), "t", "left_semi").select(*pairs.columns))
    read = heavy.join(both, ["s", "t"], "left").select("qid", "s", "t", "dist")
    return read.unionByName(query_labels(labels, pairs.join(heavy.select("qid"), "qid", "left_anti")))
