"""Exact top-k by inner product: tiled matrix products, partial selection per tile, tree merging."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .ann import matrix, vectors

SHARD, BLOCK, FAN = 16_384, 1024, 16


def quantise(x: np.ndarray) -> np.ndarray:
    return np.floor(256.0 * x)


def products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact integer inner products: in doubles while every partial sum is an exact integer, else in Python integers kept within a long."""
    top = lambda m: float(np.abs(m).max(initial=0.0))
    if top(q) * top(x) * max(1, q.shape[1]) < 2.0**53:
        return (q @ x.T).astype(np.int64)
    big = np.vectorize(int, otypes=[object])
    out = big(q).dot(big(x).T)
    return np.clip(out, -(2**63), 2**63 - 1).astype(np.int64)


def tile_best(q: np.ndarray, qid: np.ndarray, x: np.ndarray, xid: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best rows of a tile for each query: only what reaches the k-th score is sorted."""
    out_q, out_x, out_s = [], [], []
    for i in range(0, len(q), 256):
        s = products(q[i : i + 256], x)
        s = np.where(qid[i : i + 256, None] == xid[None, :], np.iinfo(np.int64).min, s)
        n = s.shape[1]
        kth = np.partition(s, max(0, n - k), axis=1)[:, max(0, n - k)]
        for j, floor in enumerate(kth):
            c = np.flatnonzero((s[j] >= floor) & (xid != qid[i + j]))
            by = c[np.lexsort((xid[c], -s[j, c]))[:k]]
            out_q.append(np.full(len(by), qid[i + j]))
            out_x.append(xid[by])
            out_s.append(s[j, by])
    join = lambda v: np.concatenate(v) if v else np.zeros(0, np.int64)
    return join(out_q), join(out_x), join(out_s)


def search(table: DataFrame, queries: DataFrame, k: int = 5, shard: int = SHARD, block: int = BLOCK) -> DataFrame:
    """(query_id, rank, vec_id, score): for each query the k highest integer products, ties to smaller vec_id.

    Vectors that are null or hold null or non-finite components take no part; zero
    vectors do. Vectors of several lengths meet only their like. Rows that repeat a
    vec_id count once (the smallest vector). Fewer rows than k: all of them.
    """
    live = vectors(table).groupBy("vec_id").agg(F.min("v").alias("v"))
    asked = vectors(queries).groupBy("vec_id").agg(F.min("v").alias("v"))
    n, m = table.count(), queries.count()
    shards, blocks = max(1, -(-n // shard)), max(1, -(-m // block))
    x = live.withColumn("s", F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int")).withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("ask", F.lit(False))
    q = asked.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")).withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(shards - 1)))).withColumn("ask", F.lit(True))

    def run(part: pa.Table) -> pa.Table:
        ask, ids, v = part["ask"].to_numpy(), part["vec_id"].to_numpy(), quantise(matrix(part["v"]))
        if not ask.any() or ask.all():
            a = b = c = np.zeros(0, np.int64)
        else:
            a, b, c = tile_best(v[ask], ids[ask], v[~ask], ids[~ask], k)
        return pa.table({"s": np.full(len(a), part["s"][0].as_py(), np.int32), "query_id": a, "vec_id": b, "score": c})

    tops = x.unionByName(q).withColumn("d", F.size("v")).groupBy("s", "b", "d").applyInArrow(run, "s int, query_id long, vec_id long, score long")
    while True:
        shards = -(-shards // FAN)
        tops = tops.withColumn("s", F.floor(F.col("s") / F.lit(FAN)).cast("int"))
        w = Window.partitionBy("query_id", "s").orderBy(F.desc("score"), "vec_id")
        tops = tops.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
        if shards == 1:
            return tops.select("query_id", "rank", "vec_id", "score")
        tops = tops.drop("rank")


def search_sql(k: int = 5, every: int = 50) -> str:
    """The registered query for DuckDB by brute force."""
    return (
        "with v as (select vec_id::bigint vec_id, list_transform(embedding, lambda x: floor(256 * x::double)) q from embeddings where embedding is not null and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0), "
        "s as (select a.vec_id query_id, b.vec_id, list_inner_product(a.q, b.q)::bigint score from v a, v b where a.vec_id % " + str(every) + " = 0 and a.vec_id <> b.vec_id), "
        "r as (select *, row_number() over (partition by query_id order by score desc, vec_id) rank from s) select query_id, rank::int rank, vec_id, score from r where rank <= " + str(k)
    )
