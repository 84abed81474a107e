"""Graphs over the star-schema, event, page and embedding tables, each with its SQL twin.

``links`` gives (ka, a, kb, b, w): kinds and keys of the ends and a positive
integer weight. ``build`` turns them into dense vertex ids and clean edges.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.ids import dense_ids
from ..plans.scratch import cut


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, form: str = "csv", sep: str = "\t", weighted: bool = False) -> DataFrame:
    """Links from a plain list (csv, json, orc or parquet); lines that start with # are comments, loops and repeats go when the graph is built."""
    schema = "a string, b string" + (", w long" if weighted else "")
    reader = spark.read.schema(schema)
    raw = reader.csv(path, sep=sep, comment="#") if form == "csv" else reader.format(form).load(path)
    return raw.where("a is not null and b is not null").select(F.lit(0).alias("ka"), "a", F.lit(0).alias("kb"), "b", (F.col("w") if weighted else F.lit(1)).cast("long").alias("w"))


@dataclass(frozen=True)
class Graph:
    name: str
    links: Callable[[SparkSession, str], DataFrame]
    sql: str
    directed: bool = False


def _pair(df: DataFrame, ka: int, a: str, kb: int, b: str, w=None) -> DataFrame:
    return df.select(F.lit(ka).alias("ka"), F.col(a).cast("string").alias("a"), F.lit(kb).alias("kb"), F.col(b).cast("string").alias("b"), (F.lit(1) if w is None else w).cast("long").alias("w"))


def _lines(where: str, other: str):
    def links(spark, d):
        lines = read(spark, d, "lineitem").where(where).select("l_orderkey", other)
        orders = read(spark, d, "orders").select("o_orderkey", "o_custkey")
        return _pair(lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")), 0, "o_custkey", 1, other)

    sql = f"select 0 ka, o_custkey::varchar a, 1 kb, {other}::varchar b, 1::bigint w from lineitem join orders on l_orderkey = o_orderkey where {where}"
    return links, sql


def _supply(spark, d):
    return _pair(read(spark, d, "lineitem").where("l_quantity >= 48").select("l_partkey", "l_suppkey"), 0, "l_partkey", 1, "l_suppkey")


def _web(spark, d):
    hrefs = F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))
    return _pair(read(spark, d, "pages").select("page_id", F.explode(hrefs).alias("href")), 0, "page_id", 1, "href")


def _handoff(event: str | None, gap: int):
    cond = f"event_type = '{event}'" if event else "true"

    def links(spark, d):
        ev = read(spark, d, "events").where(cond).select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
        # days are ordered within themselves; a day's last event meets the first of the next day that has any
        ev = ev.withColumn("day", F.floor(F.col("us") / 86_400_000_000))
        w = Window.partitionBy("day").orderBy("us", "event_id")
        first = ev.groupBy("day").agg(F.min(F.struct("us", "event_id", "user_id")).alias("f"))
        after = first.select("day", F.lead("f").over(Window.orderBy("day")).alias("f"))  # a row for each day
        nxt = ev.withColumn("n", F.lead("user_id").over(w)).withColumn("m", F.lead("us").over(w)).join(after, "day")
        nxt = nxt.withColumn("n", F.coalesce("n", "f.user_id")).withColumn("gap", F.coalesce("m", "f.us") - F.col("us"))
        return _pair(nxt.where(f"n is not null and gap <= {gap} and n <> user_id"), 0, "user_id", 0, "n", 1 + F.floor(F.col("gap") / 1000000))

    sql = (
        f"select 0 ka, user_id::varchar a, 0 kb, n::varchar b, (1 + gap // 1000000)::bigint w from (select user_id, lead(user_id) over o n, lead(epoch_us(ts)) over o - epoch_us(ts) gap from events where {cond} "
        f"window o as (order by ts, event_id)) where n is not null and gap <= {gap} and n <> user_id"
    )
    return links, sql


def _tree(orders: bool):
    def links(spark, d):
        out = _pair(read(spark, d, "nation"), 1, "n_nationkey", 0, "n_regionkey").unionByName(_pair(read(spark, d, "customer"), 2, "c_custkey", 1, "c_nationkey"))
        return out.unionByName(_pair(read(spark, d, "orders"), 3, "o_orderkey", 2, "o_custkey")) if orders else out

    part = lambda ka, a, kb, b, t: f"select {ka} ka, {a}::varchar a, {kb} kb, {b}::varchar b, 1::bigint w from {t}"
    sql = part(1, "n_nationkey", 0, "n_regionkey", "nation") + " union all " + part(2, "c_custkey", 1, "c_nationkey", "customer")
    return links, sql + (" union all " + part(3, "o_orderkey", 2, "o_custkey", "orders") if orders else "")


def _knn(spark, d, k: int = 5):
    """The k nearest by cosine; products of blocks of rows, each against all others in blocks."""
    import numpy as np
    import pandas as pd

    vecs = read(spark, d, "embeddings").where("embedding is not null").select("vec_id", "embedding")
    n = max(1, vecs.count() // 2000 + 1)
    part = F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    rows = vecs.withColumn("q", part).withColumn("x", every).withColumn("ask", F.lit(True)).unionByName(vecs.withColumn("x", part).withColumn("q", every).withColumn("ask", F.lit(False)))

    def near(p: pd.DataFrame) -> pd.DataFrame:
        m = np.vstack(p["embedding"].to_numpy()).astype(float)
        m /= np.maximum(np.sqrt((m * m).sum(axis=1, keepdims=True)), 1e-300)
        a, b = p["ask"].to_numpy(), ~p["ask"].to_numpy()
        ids = p["vec_id"].to_numpy()
        s = m[a] @ m[b].T
        s[ids[a][:, None] == ids[b][None, :]] = -9
        top = np.argsort(-s, axis=1, kind="stable")[:, :k]
        return pd.DataFrame({"a": np.repeat(ids[a], top.shape[1]), "b": ids[b][top].ravel(), "s": np.take_along_axis(s, top, 1).ravel()})

    got = rows.groupBy("q", "x").applyInPandas(near, "a long, b long, s double").where("s > -5")
    got = got.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("s"), "b"))).where(F.col("r") <= k)
    return _pair(got, 0, "a", 0, "b")


GRAPHS: dict[str, Graph] = {}
for _name, (_l, _s), _d in (
    ("trade", _lines("l_returnflag = 'R' and l_quantity >= 45", "l_suppkey"), False),
    ("trade_full", _lines("true", "l_suppkey"), False),
    ("supply", (_supply, "select 0 ka, l_partkey::varchar a, 1 kb, l_suppkey::varchar b, 1::bigint w from lineitem where l_quantity >= 48"), False),
    ("basket", _lines("l_returnflag = 'R' and l_quantity >= 45", "l_partkey"), False),
    ("web", (_web, "select 0 ka, page_id::varchar a, 1 kb, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) b, 1::bigint w from pages"), False),
    ("handoff", _handoff("purchase", 300_000_000), True),
    ("handoff_all", _handoff(None, 60_000_000), True),
    ("tree", _tree(True), False),
    ("tree_rnc", _tree(False), False),
    ("knn", (_knn, ""), False),
):
    GRAPHS[_name] = Graph(_name, _l, _s, _d)


def build(links: DataFrame, directed: bool = False) -> tuple[DataFrame, DataFrame]:
    """(vertices, edges): vertices (vid, kind, key) dense in order of kind and key; edges (src, dst, w) without loops, repeats keep the least weight, both ways unless directed."""
    ends = links.select(F.col("ka").alias("kind"), F.col("a").alias("key")).unionByName(links.select(F.col("kb").alias("kind"), F.col("b").alias("key"))).distinct()
    vertices = dense_ids(ends, ["kind", "key"], "vid")
    va, vb = vertices.toDF("vid_a", "ka", "a"), vertices.toDF("vid_b", "kb", "b")
    e = links.join(va, ["ka", "a"]).join(vb, ["kb", "b"]).select(F.col("vid_a").alias("src"), F.col("vid_b").alias("dst"), "w")
    if not directed:
        e = e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return vertices, cut(e.where("src <> dst").groupBy("src", "dst").agg(F.min("w").alias("w")), "edges")


def graph_sql(name: str, directed: bool = False) -> str:
    """CTEs l, vx(vid, kind, key) and e(src, dst, w) for DuckDB; to be followed by more CTEs or a select."""
    both = "" if directed else " union all select dst, src, w from e0"
    return (
        f"l as ({GRAPHS[name].sql}), vx as (select (row_number() over (order by kind, key) - 1)::bigint vid, kind, key from (select ka kind, a as key from l union select kb, b from l)), "
        "e0 as (select p.vid src, q.vid dst, w from l join vx p on l.ka = p.kind and l.a = p.key join vx q on l.kb = q.kind and l.b = q.key), "
        f"e as (select src, dst, min(w) w from (select * from e0{both}) where src <> dst group by src, dst)"
    )
