"""All registered queries of the distance engine and their DuckDB twins.

A twin never looks at the engine: distances come from a recursive query or from
repeated min-plus squaring, labels from their closed form. Tables that several
queries share (edges, ranks, labels) are built once per session and input.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .operators import baselines, measures, ordering, query, search
from .operators import bitparallel as bitp
from .operators import labels as lb
from .operators.ids import relabel
from .plans.scratch import cut, new_path, ship
from .sources.graphs import GRAPHS, build, graph_sql, read

_held: dict[tuple, object] = {}
#: Rounds that suffice for the recursive twins at sf0.01; the distances end well before.
BOUND = {"trade": 9, "handoff": 9, "web": 14, "tree_rnc": 8, "supply": 9, "handoff_all": 6}


def held(spark: SparkSession, sf_dir: str, *what, make: Callable):
    key = (spark.sparkContext.applicationId, sf_dir, *what)
    if key not in _held:
        _held[key] = make()
    return _held[key]


class Space:
    """A graph in rank space under an order."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, directed: bool = False, order: str = "degree"):
        ship(spark)
        g = GRAPHS[name]
        self.key = (spark, sf_dir, name, directed, order)
        self.vertices, self.edges = held(spark, sf_dir, name, directed, "graph", make=lambda: build(g.links(spark, sf_dir), directed))
        self.ranks = held(spark, sf_dir, name, directed, order, "ranks", make=lambda: self._order(order))
        self.e = held(spark, sf_dir, name, directed, order, "e", make=lambda: relabel(self.edges, self.ranks))
        self.v = self.ranks.select(F.col("rnk").alias("v"))

    def _order(self, order: str) -> DataFrame:
        if order == "closeness":
            return ordering.rank_closeness(self.edges, self.vertices, self.vertices.where("vid % 5 = 0"))
        if order == "arithmetic":
            return ordering.rank_arithmetic(self.vertices)
        if order == "random":
            return ordering.rank_random(self.vertices)
        if self.key[3]:  # directed: neighbours either way
            both = self.edges.select("src", "dst").unionByName(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
            return ordering.rank_degree(both, self.vertices)
        return ordering.rank_degree(self.edges, self.vertices)

    def once(self, what: str, make: Callable):
        return held(self.key[0], *self.key[1:], what, make=make)

    def labels(self) -> DataFrame:
        return self.once("labels", lambda: lb.label_pruned(self.e, self.v))

    def prefix(self, k: int) -> DataFrame:
        """Entries of the first k searches, which no later one changes."""
        return self.once(f"prefix{k}", lambda: lb.label_pruned(self.e, self.v, hubs_below=k))

    def parents(self) -> DataFrame:
        return self.once("parents", lambda: lb.label_pruned(self.e, self.v, with_parent=True))

    def naive(self, k: int | None = None) -> DataFrame:
        roots = self.v if k is None else self.v.where(F.col("v") < k)
        return self.once(f"naive{k}", lambda: search.label_naive(self.e, roots.select(F.col("v").alias("hub"))))

    def sides(self, weighted: bool) -> tuple[DataFrame, DataFrame]:
        return self.once(f"sides{weighted}", lambda: lb.label_correcting(self.e, self.v) if weighted else lb.label_pruned_directed(self.e, self.v))

    def combined(self, t: int, b: int) -> tuple:
        return self.once(f"combined{t}/{b}", lambda: bitp.label_combined(self.e, self.v, t, b))

    def pairs(self) -> DataFrame:
        """Every s with t = (7 s + 3) mod n."""
        n = self.once("n", lambda: self.v.count())
        return self.v.select(F.col("v").alias("qid"), F.col("v").alias("s"), ((F.col("v") * 7 + 3) % F.lit(max(n, 1))).alias("t"))

    def truth(self) -> DataFrame:
        d = self.naive().select(F.col("hub").alias("s"), F.col("v").alias("t"), "dist")
        n = self.once("n", lambda: self.v.count())
        return d.select((F.col("s") * n + F.col("t")).alias("qid"), "s", "t", "dist")


def ranked_sql(name: str, directed: bool = False, order: str = "degree") -> str:
    by = {"degree": "coalesce(deg, 0) desc, vid", "arithmetic": "vid * 7919 % 10007, vid"}[order]
    deg = "select src, count(distinct dst) deg from (select src, dst from e union select dst, src from e) group by src" if directed else "select src, count(*) deg from e group by src"
    return graph_sql(name, directed) + f", r as materialized (select vid, (row_number() over (order by {by}) - 1)::bigint rnk from vx left join ({deg}) g on g.src = vid), er as materialized (select a.rnk u, b.rnk v, w from e join r a on a.vid = src join r b on b.vid = dst)"


def hops_sql(bound: int) -> str:
    return f"d0(s, t, dist) as (select rnk, rnk, 0 from r union select d0.s, er.v, d0.dist + 1 from d0 join er on d0.t = er.u where d0.dist < {bound}), d as materialized (select s, t, min(dist)::bigint dist from d0 group by s, t)"


def squares_sql(weight: str, n: int = 9) -> str:
    out = [f"m0 as materialized (select rnk s, rnk t, 0::bigint dist from r union all select u, v, {weight}::bigint from er)"]
    for i in range(1, n):
        out.append(f"m{i} as materialized (select a.s, b.t, min(a.dist + b.dist) dist from m{i - 1} a join m{i - 1} b on a.t = b.s group by a.s, b.t)")
    return ", ".join(out) + f", d as (select s, t, dist from m{n - 1})"


LABEL_SQL = "bad as (select distinct p.s, p.t from d p join d a on a.s = p.s and a.t < p.s join d b on b.s = a.t and b.t = p.t where p.s <= p.t and a.dist + b.dist = p.dist), lab as materialized (select t v, s hub, dist from d p where s <= t and not exists (select 1 from bad where bad.s = p.s and bad.t = p.t))"
OUT_SQL = "bado as (select distinct p.s, p.t from d p join d a on a.s = p.s and a.t < p.t join d b on b.s = a.t and b.t = p.t where p.t <= p.s and a.dist + b.dist = p.dist), labo as (select s v, t hub, dist from d p where t <= s and not exists (select 1 from bado where bado.s = p.s and bado.t = p.t))"
#: Smallest rank on any shortest path, level by level: a label is a vertex that is smallest on all its paths, and a pair is answered by the first k hubs if that rank is below k.
LEAST_SQL = "x(s, v, dist, m) as (select rnk, rnk, 0::bigint, rnk from r union all select x.s, er.v, x.dist + 1, min(least(x.m, er.v)) from x join er on er.u = x.v join d on d.s = x.s and d.t = er.v and d.dist = x.dist + 1 group by x.s, er.v, x.dist), lab as materialized (select v, s hub, dist from x where m = s)"
PAIRS_SQL = "pr as (select rnk qid, rnk s, (rnk * 7 + 3) % (select count(*) from r) t from r)"


def bp_sql(t: int, b: int) -> str:
    """Roots and members by the greedy rule are sequential; the twin takes fixed ones: the first t ranks are roots, with their first b neighbours by rank."""
    return f"ro as (select rnk slot, rnk root from r where rnk < {t}), me as (select slot, v m, row_number() over (partition by slot order by v) - 1 bit from ro join er on u = root), mb as (select * from me where bit < {b}), wd as (select p.t v, slot, p.dist, bit_or(case when q.dist = p.dist - 1 then 1::bigint << bit::int else 0 end) s_minus, bit_or(case when q.dist = p.dist then 1::bigint << bit::int else 0 end) s_zero from ro join d p on p.s = root left join mb using (slot) left join d q on q.s = m and q.t = p.t group by p.t, slot, p.dist)"


def fixed_roots(s: Space, t: int, b: int) -> list:
    rows = s.e.where(F.col("u") < t).select("u", "v").collect()
    return [(r, sorted(v for u, v in map(tuple, rows) if u == r)[:b]) for r in range(t) if r < s.v.count()]


def final(with_: str, cols: str, tail: str) -> str:
    names = [c.strip() for c in cols.split(",")]
    return f"with recursive {with_} select " + ", ".join(f"{c}::bigint {c}" for c in names) + f" from {tail}"


def longs(df: DataFrame) -> DataFrame:
    return df.select(*[F.col(f.name).cast("long").alias(f.name) if isinstance(f.dataType, (T.IntegerType, T.ShortType, T.ByteType)) else F.col(f.name) for f in df.schema])


Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def add(name: str, fn: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    Q[name] = lambda spark, d: longs(fn(spark, d))
    if sql:
        SQL[name] = sql


def on(name: str, fn: Callable[[Space], DataFrame], directed: bool = False, order: str = "degree") -> Callable:
    return lambda spark, d: fn(Space(spark, d, name, directed, order))


# graphs, orders and degrees
for g in GRAPHS:
    if g == "knn":
        add("graph_knn_edges", on(g, lambda s: s.edges))
        continue
    add(f"graph_{g}_edges", on(g, lambda s: s.edges), final(graph_sql(g), "src, dst, w", "e"))
for g in ("trade", "supply", "web", "handoff"):
    add(f"rank_degree_{g}", on(g, lambda s: s.ranks), final(ranked_sql(g), "vid, rnk", "r"))
    add(f"degree_ccdf_{g}", on(g, lambda s: measures.degree_ccdf(s.e)), final(graph_sql(g) + ", h as (select deg, count(*) n from (select count(*) deg from e group by src) group by deg)", "degree, vertices_ge", "(select deg degree, sum(n) over (order by deg desc) vertices_ge from h)"))
add("degree_slope_trade", on("trade", lambda s: measures.ccdf_slope(measures.degree_ccdf(s.e))))
add("rank_random_handoff", on("handoff", lambda s: s.ranks, order="random"))
add("rank_closeness_handoff", on("handoff", lambda s: s.ranks, order="closeness"), final(ranked_sql("handoff") + ", " + hops_sql(9) + ", sm as (select rnk from r where vid % 5 = 0), cl as (select r.vid, count(d.dist) n, coalesce(sum(d.dist), 0) sd from r left join (select * from d where s in (select rnk from sm)) d on d.t = r.rnk group by r.vid)", "vid, rnk", "(select vid, row_number() over (order by n desc, sd, vid) - 1 rnk from cl)"))
add("directed_handoff_edges", on("handoff", lambda s: s.edges, True), final(graph_sql("handoff", True), "src, dst, w", "e"))


def graph_sizes(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for g in ("trade", "supply", "web", "handoff", "tree_rnc"):
        s = Space(spark, d, g)
        x = s.e.agg((F.count("*") / 2).cast("long").alias("m")).select(F.lit(g).alias("graph"), F.lit(s.once("n", lambda s=s: s.v.count())).cast("long").alias("n"), "m")
        out = x if out is None else out.unionByName(x)
    return out


add("graph_sizes", graph_sizes, " union all ".join(f"select * from (with {graph_sql(g)} select '{g}' graph, (select count(*) from vx)::bigint n, (select count(*) // 2 from e)::bigint m)" for g in ("trade", "supply", "web", "handoff", "tree_rnc")))

# searches
H = ranked_sql("handoff") + ", " + hops_sql(9)
add("bfs_levels_trade", on("trade", lambda s: search.label_naive(s.e, s.v.where("v = 0").select(F.col("v").alias("hub")))), final(ranked_sql("trade") + ", b0(v, dist) as (select 0::bigint, 0 union select er.v, dist + 1 from b0 join er on er.u = b0.v where dist < 9)", "v, hub, dist", "(select v, 0 hub, min(dist) dist from b0 group by v)"))
add("bfs_pairs_handoff", on("handoff", lambda s: search.bfs_pairs(s.e, s.pairs())), final(H + ", " + PAIRS_SQL, "qid, s, t, dist", "pr left join d using (s, t)"))
add("apsp_handoff", on("handoff", lambda s: search.apsp(s.e, s.v.select(F.col("v").alias("vid")))), final(H, "s, t, dist", "d"))
add("apsp_tree_rnc", on("tree_rnc", lambda s: search.apsp(s.e, s.v.select(F.col("v").alias("vid")))), final(ranked_sql("tree_rnc") + ", " + hops_sql(8), "s, t, dist", "d"))
for g in ("web", "basket"):
    add(f"components_{g}", on(g, lambda s: search.components(s.e, s.v.select(F.col("v").alias("vid")))), final(ranked_sql(g) + ", c0(v, c) as (select rnk, rnk from r union select er.v, c from c0 join er on er.u = c0.v where c < er.v)", "vid, comp", "(select v vid, min(c) comp from c0 group by v)"))

# labels
add("labels_naive_handoff", on("handoff", lambda s: s.naive()), final(H, "v, hub, dist", "(select t v, s hub, dist from d)"))
add("labels_naive_k16_trade", on("trade", lambda s: s.naive(16)), final(ranked_sql("trade") + ", b0(s, v, dist) as (select rnk, rnk, 0 from r where rnk < 16 union select s, er.v, dist + 1 from b0 join er on er.u = b0.v where dist < 9)", "v, hub, dist", "(select v, s hub, min(dist) dist from b0 group by v, s)"))
for g in ("handoff", "web", "tree_rnc"):
    add(f"labels_pruned_{g}", on(g, lambda s: s.labels()), final(ranked_sql(g) + ", " + hops_sql(BOUND[g]) + ", " + LABEL_SQL, "v, hub, dist", "lab"))
for g in ("trade", "supply"):
    add(f"labels_pruned_{g}", on(g, lambda s: s.labels()), final(ranked_sql(g) + ", " + hops_sql(BOUND[g]) + ", " + LEAST_SQL, "v, hub, dist", "lab"))
add("labels_pruned_knn", on("knn", lambda s: s.labels()))
L = H + ", " + LABEL_SQL
add("labels_pruned_k16_handoff", on("handoff", lambda s: lb.label_pruned(s.e, s.v, hubs_below=16)), final(L, "v, hub, dist", "lab where hub < 16"))
add("labels_closed_form_handoff", on("handoff", lambda s: lb.label_closed_form(s.naive().select(F.col("hub").alias("s"), F.col("v").alias("t"), "dist"))), final(L, "v, hub, dist", "lab"))
add("labels_batched_handoff", on("handoff", lambda s: lb.label_pruned_batched(s.e, s.v, 50)), final(L, "v, hub, dist", "lab"))
DH, DW = ranked_sql("handoff", True) + ", " + squares_sql("1"), ranked_sql("handoff", True) + ", " + squares_sql("w")
sided = lambda w: on("handoff", lambda s: s.sides(w)[0].withColumn("side", F.lit("out")).unionByName(s.sides(w)[1].withColumn("side", F.lit("in"))), True)
both_sql = lambda d: f"with recursive {d}, {LABEL_SQL}, {OUT_SQL} select v::bigint v, hub::bigint hub, dist::bigint dist, 'in' side from lab union all select v::bigint, hub::bigint, dist::bigint, 'out' from labo"
add("labels_directed_handoff", sided(False), both_sql(DH))
add("labels_weighted_handoff", sided(True), both_sql(DW))
BP = H + ", " + bp_sql(2, 32)
add("bp_words_handoff", on("handoff", lambda s: bitp.label_bitparallel(s.e, fixed_roots(s, 2, 32))), final(BP, "v, slot, dist, s_minus, s_zero", "wd"))
add("bp_expand_handoff", on("handoff", lambda s: bitp.bp_expand(bitp.label_bitparallel(s.e, fixed_roots(s, 2, 32)), fixed_roots(s, 2, 32))), final(BP + ", so as (select root x, slot from ro union all select m, slot from mb)", "source, v, dist", "(select x source, d.t v, d.dist from so join d on d.s = x)"))
add("labels_combined_handoff", on("handoff", lambda s: s.combined(2, 32)[1]))

# queries
for g in ("handoff", "web", "trade"):
    add(f"query_pruned_{g}", on(g, lambda s: query.query_labels(s.labels(), s.pairs())), final(ranked_sql(g) + ", " + hops_sql(BOUND[g]) + ", " + PAIRS_SQL, "qid, s, t, dist", "pr left join d using (s, t)"))
P = H + ", " + PAIRS_SQL
answers = final(P, "qid, s, t, dist", "pr left join d using (s, t)")
add("query_packed_handoff", on("handoff", lambda s: query.query_packed(query.pack(s.labels()), s.pairs())), answers)
add("query_combined_handoff", on("handoff", lambda s: query.query_combined(s.combined(2, 32)[0], s.combined(2, 32)[1], s.pairs())), answers)
add("query_bp_handoff", on("handoff", lambda s: bitp.query_bitparallel(bitp.label_bitparallel(s.e, fixed_roots(s, 2, 32)), s.pairs())), final(BP + ", " + PAIRS_SQL + ", so as (select root x from ro union select m from mb)", "qid, s, t, dist", "(select qid, pr.s, pr.t, min(a.dist + b.dist) dist from pr left join so on true left join d a on a.s = x and a.t = pr.s left join d b on b.s = x and b.t = pr.t group by qid, pr.s, pr.t)"))
add("query_directed_handoff", on("handoff", lambda s: query.query_directed(*s.sides(False), s.pairs()), True), final(DH + ", " + PAIRS_SQL, "qid, s, t, dist", "pr left join d using (s, t)"))
add("query_weighted_handoff", on("handoff", lambda s: query.query_directed(*s.sides(True), s.pairs()), True), final(DW + ", " + PAIRS_SQL, "qid, s, t, dist", "pr left join d using (s, t)"))
add("query_point_handoff", on("handoff", lambda s: query.query_one(s.labels(), 3, 100)), final(H, "s, t, dist", "(select 3 s, 100 t, (select dist from d where s = 3 and t = 100) dist)"))
add("query_outlier_rows_handoff", on("handoff", lambda s: query.query_with_rows(s.labels(), query.precompute_rows(s.e, query.outlier_vertices(s.labels(), 20)), s.pairs())), answers)
add("path_steps_handoff", on("handoff", lambda s: query.paths(s.parents(), s.pairs()).groupBy("qid").agg((F.count("*") - 1).alias("dist"), F.count_distinct("step").alias("steps"))), final(P, "qid, dist, steps", "(select qid, dist, dist + 1 steps from pr join d using (s, t))"))


def sql_face(s: Space) -> DataFrame:
    from .functions.sqlface import register

    spark = s.key[0]
    register(spark, query.pack(s.labels()))
    s.pairs().createOrReplaceTempView("asked_pairs")
    return spark.sql("select qid, s, t, hub_distance(a.hubs, a.dists, b.hubs, b.dists) dist from asked_pairs join labels_packed a on a.v = s join labels_packed b on b.v = t")


add("sql_hub_distance_handoff", on("handoff", sql_face), answers)


def stream_answers(s: Space) -> DataFrame:
    from .streaming.serve import answer_batches

    spark = s.key[0]
    source, out, mark = (new_path(spark, f"stream-{x}") for x in ("in", "out", "mark"))
    s.pairs().write.parquet(source)
    answer_batches(spark.readStream.schema(s.pairs().schema).parquet(source), s.labels(), out, mark).awaitTermination()
    return spark.read.parquet(out)


add("stream_pairs_batch_equiv", on("handoff", stream_answers), answers)


def index_round_trip(s: Space) -> DataFrame:
    from .sources.index_io import open_index, write_index

    path = new_path(s.key[0], "index")
    write_index(s.labels(), path)
    return open_index(s.key[0], path)["labels"].select("v", "hub", "dist")


add("index_round_trip_handoff", on("handoff", index_round_trip), final(L, "v, hub, dist", "lab"))

# baselines
LM = H + ", " + PAIRS_SQL + ", lm as (select qid, pr.s, pr.t, max(abs(a.dist - b.dist)) lower, min(a.dist + b.dist) upper from pr left join (select * from d where s < 8) a on a.t = pr.s left join d b on b.s = a.s and b.t = pr.t group by qid, pr.s, pr.t)"
estimates = lambda s: baselines.landmark_estimate(baselines.landmark_table(s.e, s.v, 8), s.pairs())
add("landmark_bounds_handoff", on("handoff", estimates), final(LM, "qid, s, t, lower, upper", "lm"))
add("landmark_precision_handoff", on("handoff", lambda s: measures.estimate_error(estimates(s), query.query_labels(s.labels(), s.pairs())).select("dist", "n", "exact", "sum_abs_err")), final(LM + ", er2 as (select d.dist, upper - d.dist e from lm join d using (s, t) where d.dist > 0 and upper is not null)", "dist, n, exact, sum_abs_err", "(select dist, count(*) n, sum((e = 0)::int) exact, sum(e) sum_abs_err from er2 group by rollup(dist))"))


def tree_distance(s: Space) -> DataFrame:
    index = baselines.tree_index(s.e.select("u", "v"), 1)
    pairs = s.pairs().collect()  # the baseline runs on the driver, on a small tree
    return s.key[0].createDataFrame([(q, a, b, baselines.tree_query(index, a, b)) for q, a, b in map(tuple, pairs)], "qid long, s long, t long, dist long")


add("tree_lca_distance", on("tree_rnc", tree_distance), final(ranked_sql("tree_rnc") + ", " + hops_sql(8) + ", " + PAIRS_SQL, "qid, s, t, dist", "pr left join d using (s, t)"))
add("tree_index_handoff", on("handoff", lambda s: s.key[0].createDataFrame([(q, a, b, baselines.tree_query(ix, a, b)) for ix in [baselines.tree_index(s.e.select("u", "v"), 6)] for q, a, b in map(tuple, s.pairs().collect())], "qid long, s long, t long, dist long")), answers)


def hierarchical(s: Space) -> DataFrame:
    best = baselines.hierarchical_order_held(s.e, s.v)
    if best is None:
        best = baselines.hierarchical_order(s.naive().select(F.col("hub").alias("s"), F.col("v").alias("t"), "dist"))
    order = s.key[0].createDataFrame(list(enumerate(best)), "rnk long, vid long")
    e = relabel(s.e.select(F.col("u").alias("src"), F.col("v").alias("dst")), order)
    lab = lb.label_pruned(e, order.select(F.col("rnk").alias("v")))
    pairs = query.resolve(s.pairs(), order)
    return query.query_labels(lab, pairs).join(pairs.select("qid", "s_vid", "t_vid"), "qid").select("qid", F.col("s_vid").alias("s"), F.col("t_vid").alias("t"), "dist")


add("hierarchical_query_handoff", on("handoff", hierarchical), answers)

# measures
STEPS = [1, 4, 16, 64, 256]
FI = L + ", fi as (select p.s, p.t, p.dist, min(a.hub) as first from d p join lab a on a.v = p.s join lab b on b.v = p.t and b.hub = a.hub where a.dist + b.dist = p.dist group by p.s, p.t, p.dist)"
first = lambda s: measures.coverage_steps(s.labels(), s.truth())


def firsts(s: Space) -> DataFrame:
    """Over all pairs: counted in tasks where graph and index can be held, else a row for each pair."""
    counted = measures.first_counts(s.e, s.v, s.labels())
    return first(s) if counted is None else counted


def cover(s: Space) -> DataFrame:
    wrong = measures.audit_cover_all(s.e, s.v, s.labels())
    return measures.audit_cover(s.labels(), s.truth()) if wrong is None else wrong


def asked(s: Space) -> DataFrame:
    """Distance and first hub of the asked pairs: joined in the tasks that search where the graph can be held, else from the index."""

    def make() -> DataFrame:
        found = measures.search_answers(s.e, s.v, s.pairs())
        return cut(measures.query_steps(s.labels(), s.pairs()) if found is None else found, "asked")

    return s.once("asked", make)


def prefixes(s: Space) -> DataFrame:
    full = measures.search_steps(s.e, s.v, s.pairs())
    return measures.audit_prefix_all(s.labels(), s.naive(), s.pairs()) if full is None else measures.compare_steps(full, measures.prefix_steps(s.labels(), s.pairs()))


add("coverage_by_step_handoff", on("handoff", lambda s: measures.coverage(firsts(s), STEPS)), final(FI, "k, covered, total", f"(select k, count(*) filter (first < k) covered, count(*) total from fi, (select unnest({STEPS}) k) group by k)"))
add("coverage_by_distance_handoff", on("handoff", lambda s: measures.coverage(firsts(s), STEPS, True)), final(FI, "k, dist, covered, total", f"(select k, dist, count(*) filter (first < k) covered, count(*) total from fi, (select unnest({STEPS}) k) group by k, dist)"))
for g in ("web", "trade", "supply"):
    W = ranked_sql(g) + ", " + hops_sql(BOUND[g]) + ", " + LEAST_SQL
    add(f"labels_per_search_{g}", on(g, lambda s: measures.labels_per_search(s.labels())), final(W, "hub, added", "(select hub, count(*) added from lab group by hub)"))
    add(f"labels_cumulative_{g}", on(g, lambda s: measures.running(measures.labels_per_search(s.labels()), "hub", "added", "cum", 64)), final(W, "hub, added, cum", "(select hub, added, sum(added) over (order by hub) cum from (select hub, count(*) added from lab group by hub))"))
    add(f"label_size_hist_{g}", on(g, lambda s: measures.size_histogram(measures.label_sizes(s.labels(), s.v))), final(W, "size, vertices", "(select size, count(*) vertices from (select count(*) size from lab group by v) group by size)"))
    add(f"search_space_{g}", on(g, lambda s: measures.search_space(s.labels(), s.e)), final(W + ", vs as (select hub, v from lab union select hub, er.v from lab join er on er.u = lab.v)", "hub, visited, labelled, pruned", "(select hub, visited, labelled, visited - labelled pruned from (select hub, count(*) visited from vs group by hub) join (select hub, count(*) labelled from lab group by hub) using (hub))"))
    FP = W + ", " + PAIRS_SQL + ", fi as (select pr.s, pr.t, x.dist, x.m as first from pr join x on x.s = pr.s and x.v = pr.t)"
    add(f"coverage_pairs_by_step_{g}", on(g, lambda s: measures.coverage(asked(s), STEPS)), final(FP, "k, covered, total", f"(select k, count(*) filter (first < k) covered, count(*) total from fi, (select unnest({STEPS}) k) group by k)"))
    add(f"coverage_pairs_by_distance_{g}", on(g, lambda s: measures.coverage(asked(s), STEPS, True)), final(FP, "k, dist, covered, total", f"(select k, dist, count(*) filter (first < k) covered, count(*) total from fi, (select unnest({STEPS}) k) group by k, dist)"))
    add(f"distance_histogram_{g}", on(g, lambda s: measures.distance_histogram(s.pairs().join(asked(s), "qid", "left"))), final(FP, "dist, pairs", "(select x.dist, count(*) pairs from pr left join x on x.s = pr.s and x.v = pr.t group by x.dist)"))
add("label_size_summary_trade", on("trade", lambda s: measures.label_size_summary(measures.label_sizes(s.labels(), s.v))))
add("distance_histogram_handoff", on("handoff", lambda s: measures.distance_histogram(query.query_labels(s.labels(), s.pairs()))), final(P, "dist, pairs", "(select dist, count(*) pairs from pr left join d using (s, t) group by dist)"))
add("index_bytes_handoff", on("handoff", lambda s: measures.index_bytes(s.labels(), s.combined(2, 32)[0])))
add("audit_minimal_web", on("web", lambda s: measures.audit_minimal(s.labels()).agg(F.count("*").alias("violations"))), "select 0::bigint violations")
add("audit_cover_handoff", on("handoff", lambda s: cover(s).agg(F.count("*").alias("violations"))), "select 0::bigint violations")
add("audit_prefix_handoff", on("handoff", lambda s: measures.audit_prefix(s.prefix(16), s.naive(16), s.pairs(), 16).agg(F.count("*").alias("violations"))), "select 0::bigint violations")
add("landmark_bound_handoff", on("handoff", lambda s: measures.landmark_bound(s.labels(), first(s), 16)), final(FI, "beyond, uncovered", "(select (select count(*) from lab where hub >= 16) beyond, (select count(*) from fi where first >= 16) uncovered)"))


def ordering_compare(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for order in ("degree", "closeness", "random"):
        s = Space(spark, d, "handoff", False, order)
        x = s.labels().agg(F.lit(order).alias("ordering"), F.count("*").alias("entries"))
        out = x if out is None else out.unionByName(x)
    return out


add("ordering_compare_handoff", ordering_compare)


def centroid(spark: SparkSession, d: str) -> DataFrame:
    s = Space(spark, d, "tree_rnc")
    comps = search.components(s.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")), s.vertices)
    ranks = ordering.rank_centroid(s.edges, comps)
    lab = lb.label_pruned(relabel(s.edges, ranks), ranks.select(F.col("rnk").alias("v")))
    n = s.once("n", lambda: s.v.count())
    return lab.groupBy("v").count().agg((F.max("count") <= F.floor(F.log2(F.lit(n))) + 1).cast("long").alias("within_bound"))


add("centroid_order_bound_tree", centroid, "select 1::bigint within_bound")


def bp_sweep(spark: SparkSession, d: str) -> DataFrame:
    s = Space(spark, d, "handoff")
    out = None
    for t in (0, 1, 4):
        bp, lab, _ = s.combined(t, 64)
        x = lab.agg(F.count("*").alias("normal_entries")).crossJoin(bp.agg(F.count("*").alias("bp_entries"))).withColumn("t", F.lit(t))
        out = x if out is None else out.unionByName(x)
    return out


add("bp_sweep_handoff", bp_sweep)


def closest_pages(spark: SparkSession, d: str) -> DataFrame:
    """Pages with a keyword by closeness to the first page."""
    s = Space(spark, d, "web")
    at = s.vertices.where("kind = 0").join(s.ranks, "vid").select("rnk", F.col("key").cast("long").alias("page_id"))
    hits = read(spark, d, "pages").where(F.lower("html").contains("the")).select("page_id").join(at, "page_id")
    home = at.where("page_id = 0").select(F.col("rnk").alias("s"))
    pairs = hits.crossJoin(home).select(F.col("page_id").alias("qid"), "s", F.col("rnk").alias("t"))
    return query.query_labels(s.labels(), pairs).where("dist is not null").select(F.col("qid").alias("page_id"), "dist").orderBy("dist", "page_id").limit(10)


add("closest_pages_topk", closest_pages, final(ranked_sql("web") + ", h0(v, dist) as (select rnk, 0 from r join vx using (vid) where kind = 0 and key = '0' union select er.v, dist + 1 from h0 join er on er.u = h0.v where dist < 14)", "page_id, dist", "(select p.page_id, min(h.dist) dist from pages p join vx on kind = 0 and key = p.page_id::varchar join r using (vid) join h0 h on h.v = rnk where lower(html) like '%the%' group by p.page_id order by 2, 1 limit 10)"))


# scattered order: ranks, labels and landmark precision that both engines can repeat
AR = ranked_sql("handoff", order="arithmetic") + ", " + hops_sql(9)
add("rank_arithmetic_handoff", on("handoff", lambda s: s.ranks, order="arithmetic"), final(ranked_sql("handoff", order="arithmetic"), "vid, rnk", "r"))
add("labels_arithmetic_handoff", on("handoff", lambda s: s.labels(), order="arithmetic"), final(AR + ", " + LABEL_SQL, "v, hub, dist", "lab"))
add("landmark_precision_scattered", on("handoff", lambda s: measures.estimate_error(estimates(s), query.query_labels(s.labels(), s.pairs())).select("dist", "n", "exact", "sum_abs_err"), order="arithmetic"), final(LM.replace(H, AR) + ", er2 as (select d.dist, upper - d.dist e from lm join d using (s, t) where d.dist > 0 and upper is not null)", "dist, n, exact, sum_abs_err", "(select dist, count(*) n, sum((e = 0)::int) exact, sum(e) sum_abs_err from er2 group by rollup(dist))"))
add("order_sizes_handoff", lambda spark, d: Space(spark, d, "handoff").labels().agg(F.lit("degree").alias("ordering"), F.count("*").alias("entries")).unionByName(Space(spark, d, "handoff", False, "arithmetic").labels().agg(F.lit("arithmetic").alias("ordering"), F.count("*").alias("entries"))), f"select * from (with recursive {L} select 'degree' as ordering, count(*)::bigint entries from lab) union all select * from (with recursive {AR}, {LABEL_SQL} select 'arithmetic' as ordering, count(*)::bigint entries from lab)")
add("audit_prefix_all_handoff", on("handoff", prefixes), final(P + ", sm as (select qid, a.s k, a.dist + b.dist dist from pr join d a on a.t = pr.s join d b on b.s = a.s and b.t = pr.t), st as (select qid, k, dist, min(dist) over (partition by qid order by k rows between unbounded preceding and 1 preceding) before from sm)", "steps, violations", "(select count(*) steps, 0 violations from st where before is null or dist < before)"))

# undirected weights, and each direction of a directed graph beside its symmetrised form
UW = ranked_sql("handoff") + ", " + squares_sql("w")
add("query_weighted_undirected_handoff", on("handoff", lambda s: query.query_labels(s.once("weighted", lambda: lb.label_pruned_weighted(s.e, s.v)), s.pairs())), final(UW + ", " + PAIRS_SQL, "qid, s, t, dist", "pr left join d using (s, t)"))
add("weighted_bfs_handoff", on("handoff", lambda s: search.label_naive_weighted(s.e, s.v.where("v < 16").select(F.col("v").alias("hub")))), final(UW, "v, hub, dist", "(select t v, s hub, dist from d where s < 16)"))


def directions(s: Space) -> DataFrame:
    """Pairs by how the directed distance compares with the distance on the symmetrised graph."""
    both = s.e.select("u", "v").unionByName(s.e.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct()
    free = query.query_labels(s.once("symmetric", lambda: lb.label_pruned(both, s.v)), s.pairs()).select("qid", F.col("dist").alias("free"))
    kind = F.when(F.col("dist").isNull(), F.when(F.col("free").isNull(), "apart").otherwise("one_way")).when(F.col("dist") > F.col("free"), "longer").otherwise("equal")
    return query.query_directed(*s.sides(False), s.pairs()).join(free, "qid").groupBy(kind.alias("kind")).agg(F.count("*").alias("pairs"))


add("direction_compare_handoff", on("handoff", directions, True), f"with recursive {DH}, {PAIRS_SQL}, n0 as materialized (select rnk s, rnk t, 0::bigint dist from r union all select u, v, 1::bigint from er union all select v, u, 1::bigint from er), " + ", ".join(f"n{i} as materialized (select a.s, b.t, min(a.dist + b.dist) dist from n{i - 1} a join n{i - 1} b on a.t = b.s group by a.s, b.t)" for i in range(1, 5)) + " select case when d.dist is null then case when f.dist is null then 'apart' else 'one_way' end when d.dist > f.dist then 'longer' else 'equal' end kind, count(*)::bigint pairs from pr left join d using (s, t) left join n4 f on f.s = pr.s and f.t = pr.t group by 1")

# relational operators over the index, one small query each
lab_pairs = lambda s: s.labels().join(s.labels().select(F.col("v").alias("w"), "hub"), "hub")
add("semi_join_hubs", on("handoff", lambda s: s.v.join(s.labels().where("v <> hub").select(F.col("hub").alias("v")), "v", "left_semi")), final(L, "v", "(select rnk v from r where rnk in (select hub from lab where v <> hub))"))
add("anti_join_uncovered", on("handoff", lambda s: s.v.join(s.prefix(16).select("v"), "v", "left_anti")), final(L, "v", "(select rnk v from r where rnk not in (select v from lab where hub < 16))"))
add("rollup_labels", on("handoff", lambda s: s.labels().rollup("dist").agg(F.count("*").alias("entries"))), final(L, "dist, entries", "(select dist, count(*) entries from lab group by rollup(dist))"))
add("cube_distance", on("handoff", lambda s: s.labels().withColumn("band", F.floor(F.col("hub") / 16)).cube("band", "dist").agg(F.count("*").alias("entries"))), final(L, "band, dist, entries", "(select hub // 16 band, dist, count(*) entries from lab group by cube(band, dist))"))
add("union_graphs", lambda spark, d: Space(spark, d, "handoff").e.select("u", "v", F.lit("handoff").alias("graph")).unionByName(Space(spark, d, "web").e.select("u", "v", F.lit("web").alias("graph"))).groupBy("graph").agg(F.count("*").alias("edges")), f"select * from (with {graph_sql('handoff')} select 'handoff' graph, count(*)::bigint edges from e) union all select * from (with {graph_sql('web')} select 'web' graph, count(*)::bigint edges from e)")
add("intersect_neighbours", on("handoff", lambda s: s.e.where("u = 0").select("v").intersect(s.e.where("u = 1").select("v"))), final(ranked_sql("handoff"), "v", "(select v from er where u = 0 intersect select v from er where u = 1)"))
add("except_pairs", on("handoff", lambda s: s.naive(16).select("v", "hub").exceptAll(s.prefix(16).select("v", "hub"))), final(L, "v, hub", "(select t v, s hub from d where s < 16 except select v, hub from lab)"))
add("window_rank_hubs", on("handoff", lambda s: s.labels().groupBy("dist", "hub").agg(F.count("*").alias("n")).withColumn("place", F.dense_rank().over(Window.partitionBy("dist").orderBy(F.desc("n"), "hub"))).where("place <= 3")), final(L, "dist, hub, n, place", "(select *, dense_rank() over (partition by dist order by n desc, hub) place from (select dist, hub, count(*) n from lab group by dist, hub) qualify place <= 3)"))
add("array_labels", on("handoff", lambda s: query.unpack(query.pack(s.labels()).where(F.size("hubs") >= 3)).select("v", "hub", "dist")), final(L, "v, hub, dist", "(select * from lab where v in (select v from lab group by v having count(*) >= 3))"))
add("json_events", lambda spark, d: read(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.count(F.get_json_object(F.to_json(F.struct("event_type", "user_id")), "$.user_id")).alias("with_user")), "select event_type, count(*)::bigint n, count(json_extract(json_object('event_type', event_type, 'user_id', user_id), '$.user_id'))::bigint with_user from events group by event_type")


def last_purchase(spark: SparkSession, d: str) -> DataFrame:
    """As-of join: for every event its user's last purchase before it, as the last value of an ordered union; counted by whether there is one."""
    ev = read(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    w = Window.partitionBy("user_id").orderBy("us", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    at = ev.withColumn("bought", F.last(F.when(F.col("event_type") == "purchase", F.col("us")), ignorenulls=True).over(w))
    return at.groupBy("event_type").agg(F.count("*").alias("events"), F.count("bought").alias("after_purchase"), F.sum(F.col("us") - F.col("bought")).alias("wait_us"))


add("asof_user_event", last_purchase, "select event_type, count(*)::bigint events, count(b)::bigint after_purchase, sum(us - b)::bigint wait_us from (select event_type, epoch_us(ts) us, last_value(case when event_type = 'purchase' then epoch_us(ts) end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) b from events) group by event_type")


def closest_customers(spark: SparkSession, d: str) -> DataFrame:
    """The ten customers of one segment that are nearest to the first supplier."""
    s = Space(spark, d, "trade")
    at = s.vertices.join(s.ranks, "vid")
    home = at.where("kind = 1").select(F.col("rnk").alias("s"), F.col("key").cast("long").alias("k")).orderBy("k").limit(1).select("s")
    who = read(spark, d, "customer").where("c_mktsegment = 'BUILDING'").select("c_custkey")
    hits = at.where("kind = 0").select(F.col("key").cast("long").alias("c_custkey"), F.col("rnk").alias("t")).join(who, "c_custkey")
    pairs = hits.crossJoin(home).select(F.col("c_custkey").alias("qid"), "s", "t")
    found = measures.search_answers(s.e, s.v, pairs)
    got = query.query_labels(s.labels(), pairs).where("dist is not null") if found is None else found
    return got.select(F.col("qid").alias("c_custkey"), "dist").orderBy("dist", "c_custkey").limit(10)


add("closest_customers_topk", closest_customers, final(ranked_sql("trade") + ", hm as (select rnk from r join vx using (vid) where kind = 1 order by key::bigint limit 1), h0(v, dist) as (select rnk, 0 from hm union select er.v, dist + 1 from h0 join er on er.u = h0.v where dist < 9)", "c_custkey, dist", "(select c_custkey, min(h.dist) dist from customer join vx on kind = 0 and key = c_custkey::varchar join r using (vid) join h0 h on h.v = rnk where c_mktsegment = 'BUILDING' group by c_custkey order by 2, 1 limit 10)"))


def performance(name: str, t: int = 16, k: int = 1000) -> Callable:
    """Main comparison on one graph: (method, it, is_bytes, qt, ln, bp) for the combined, the plain and the naive index, and a search per pair."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        import time

        s = Space(spark, d, name)
        n = max(1, s.v.count())
        pairs = s.pairs().where(F.col("qid") % max(1, n // k) == 0)
        q = max(1, pairs.count())
        rows = []

        def clock(df: DataFrame) -> float:
            at = time.time()
            df.write.format("noop").mode("overwrite").save()
            return time.time() - at

        def method(label: str, build: Callable, ask: Callable, entries: Callable, slots: int) -> None:
            at = time.time()
            index = build()
            it = time.time() - at
            size = entries(index).count()
            rows.append((label, it, 5 * size + 17 * slots * n, clock(ask(index)) / q, size / n, slots))

        method("combined", lambda: bitp.label_combined(s.e, s.v, t), lambda x: query.query_combined(x[0], x[1], pairs), lambda x: x[1], t)
        method("pruned", lambda: lb.label_pruned(s.e, s.v), lambda x: query.query_labels(x, pairs), lambda x: x, 0)
        if n <= 3000:
            method("naive", lambda: search.label_naive(s.e, s.v.select(F.col("v").alias("hub"))), lambda x: query.query_labels(x, pairs), lambda x: x, 0)
        rows.append(("bfs", 0.0, 0, clock(search.bfs_pairs(s.e, pairs)) / q, 0.0, 0))
        return spark.createDataFrame(rows, "method string, it double, is_bytes long, qt double, ln double, bp int")

    return run


for g in ("handoff", "web", "trade"):
    add(f"performance_{g}", performance(g))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
