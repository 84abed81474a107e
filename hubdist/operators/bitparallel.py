"""Bit-parallel labels: one search covers a root and up to 64 of its neighbours.

Per vertex and slot: the distance to the root, and two words that tell which set
members are one closer and which are equally far. All slots advance together.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import cut
from . import labels as lb


def choose_bp_roots(edges: DataFrame, t: int, b: int = 64, window: int = 50_000) -> list[tuple[int, list[int]]]:
    """Greedy choice in rank order: the first unused vertex is a root, its first unused neighbours its members.

    Only neighbours of the top-ranked vertices reach the driver, the first of each
    root's list that could be needed (at most t * (b + 1) used vertices come before).
    """
    from pyspark.sql import Window

    if not 1 <= b <= 64:
        raise ValueError("a word holds 1 to 64 members")
    heads = t * (b + 1)
    w = Window.partitionBy("u").orderBy("v")
    rows = edges.where(F.col("u") < heads).withColumn("k", F.row_number().over(w)).where(F.col("k") <= heads + b).where(F.col("u") <= min(heads, window)).select("u", "v").collect()
    near: dict[int, list[int]] = {}
    for u, v in sorted(map(tuple, rows)):
        near.setdefault(u, []).append(v)
    used: set[int] = set()
    out = []
    for u in sorted(near):
        if len(out) == t:
            break
        if u in used:
            continue
        members = [v for v in near[u] if v not in used][:b]
        used |= {u, *members}
        out.append((u, members))
    return out


def _word(bit: int) -> int:
    return (1 << bit) - (1 << 64 if bit == 63 else 0)


def label_bitparallel(edges: DataFrame, roots: list[tuple[int, list[int]]]) -> DataFrame:
    """(v, slot, dist, s_minus, s_zero) for every vertex that a root reaches. A member counts as equally far only if it is not closer."""
    spark = edges.sparkSession
    seed = [(root, slot, 0, 0, 0) for slot, (root, _) in enumerate(roots)]
    member = [(m, slot, 1, _word(i), 0) for slot, (_, ms) in enumerate(roots) for i, m in enumerate(ms)]
    kind = "v long, slot int, dist int, s_minus long, s_zero long"
    members = spark.createDataFrame(member, kind)
    level = cut(spark.createDataFrame(seed, kind), "bp")
    done = None
    e = edges.select("u", "v")
    d = 0
    while True:
        # equally far: what a neighbour on the same level is closer to
        other = level.select(F.col("v").alias("u"), "slot", F.col("s_minus").alias("m"))
        same = other.join(e, "u").join(level.select("v", "slot"), ["v", "slot"], "left_semi").groupBy("v", "slot").agg(F.bit_or("m").alias("m"))
        now = level.join(same, ["v", "slot"], "left").select("v", "slot", "dist", "s_minus", ((F.col("s_zero").bitwiseOR(F.coalesce("m", F.lit(0)))).bitwiseAND(F.bitwise_not("s_minus"))).alias("s_zero"))
        now = cut(now, "bp")
        done = now if done is None else done.unionByName(now)
        d += 1
        step = now.select(F.col("v").alias("u"), "slot", "s_minus", "s_zero").join(e, "u").join(done.select("v", "slot"), ["v", "slot"], "left_anti").select("v", "slot", F.lit(d).alias("dist"), "s_minus", "s_zero")
        if d == 1:
            step = step.unionByName(members)
        level = cut(step.groupBy("v", "slot").agg(F.min("dist").alias("dist"), F.bit_or("s_minus").alias("s_minus"), F.bit_or("s_zero").alias("s_zero")).select("v", "slot", "dist", "s_minus", "s_zero"), "bp")
        if level.isEmpty():
            return done


def bp_sum() -> F.Column:
    """Distance by way of one slot from columns dist, s_minus, s_zero of both ends (prefixed a_, b_)."""
    minus = F.col("a_m").bitwiseAND(F.col("b_m")) != 0
    zero = F.col("a_z").bitwiseAND(F.col("b_m")).bitwiseOR(F.col("a_m").bitwiseAND(F.col("b_z"))) != 0
    return F.col("a_d") + F.col("b_d") - F.when(minus, 2).when(zero, 1).otherwise(0)


def bp_side(bp: DataFrame, key: str, p: str) -> DataFrame:
    return bp.select(F.col("v").alias(key), "slot", F.col("dist").alias(f"{p}_d"), F.col("s_minus").alias(f"{p}_m"), F.col("s_zero").alias(f"{p}_z"))


def query_bitparallel(bp: DataFrame, pairs: DataFrame) -> DataFrame:
    """(qid, s, t, dist): the least distance by way of any root or member; null if no root reaches both."""
    got = pairs.join(bp_side(bp, "s", "a"), "s").join(bp_side(bp, "t", "b"), ["t", "slot"]).groupBy("qid").agg(F.min(bp_sum()).alias("dist"))
    return pairs.join(got, "qid", "left").select("qid", "s", "t", "dist")


def bp_expand(bp: DataFrame, roots: list[tuple[int, list[int]]]) -> DataFrame:
    """Distances (source, v, dist) from each root and each member, spelled out."""
    root = bp.sparkSession.createDataFrame([(slot, r) for slot, (r, _) in enumerate(roots)], "slot int, source long")
    bits = bp.sparkSession.createDataFrame([(slot, m, _word(i)) for slot, (_, ms) in enumerate(roots) for i, m in enumerate(ms)], "slot int, source long, bit long")
    each = bp.join(bits, "slot")
    d = F.col("dist") + F.when(F.col("s_minus").bitwiseAND(F.col("bit")) != 0, -1).when(F.col("s_zero").bitwiseAND(F.col("bit")) != 0, 0).otherwise(1)
    return bp.join(root, "slot").select("source", "v", "dist").unionByName(each.select("source", "v", d.alias("dist")))


def label_combined(edges: DataFrame, vertices: DataFrame, t: int, b: int = 64) -> tuple[DataFrame, DataFrame, list]:
    """(bp_labels, labels, roots): t bit-parallel roots first, then pruned labels that both indexes prune. t = 0 is plain pruning."""
    roots = choose_bp_roots(edges, t, b) if t else []
    bp = cut(label_bitparallel(edges, roots), "bp_labels")
    if not roots:
        return bp, lb.label_pruned(edges, vertices), roots
    used = edges.sparkSession.createDataFrame([(x,) for r, ms in roots for x in (r, *ms)], "v long")  # at most t * (b + 1) rows

    def prefilter(cand: DataFrame, d: int) -> DataFrame:
        best = cand.join(bp_side(bp, "hub", "a"), "hub").join(bp_side(bp, "v", "b"), ["v", "slot"]).groupBy("v", "hub").agg(F.min(bp_sum()).alias("x")).where(F.col("x") <= d)
        return cand.join(best, ["v", "hub"], "left_anti")

    return bp, lb.label_pruned(edges, vertices, prefilter=prefilter, skip=used), roots
