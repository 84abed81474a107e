"""Exactness on micro graphs and random graphs, and DuckDB twins on the smallest tables."""

import itertools
import random

import duckdb
import pytest

from hubdist import registry
from hubdist.operators import baselines, measures, query, search
from hubdist.operators import bitparallel as bitp
from hubdist.operators import labels as lb

MICRO = {
    "path5": ([(0, 1), (1, 2), (2, 3), (3, 4)], [1, 2, 3, 0, 4]),
    "star4": ([(0, i) for i in range(1, 5)], [0, 1, 2, 3, 4]),
    "clique4": (list(itertools.combinations(range(4), 2)), [0, 1, 2, 3]),
    "cycle6": ([(i, (i + 1) % 6) for i in range(6)], list(range(6))),
    "two_comp": ([(0, 1), (1, 2), (3, 4)], [1, 0, 2, 3, 4, 5]),
    "single": ([], [0]),
}
EXPECTED = {"path5": 12, "star4": 9, "clique4": 10, "cycle6": 18, "two_comp": 9, "single": 1}


def frames(spark, edges, order):
    rank = {v: k for k, v in enumerate(order)}
    both = {(rank[a], rank[b]) for a, b in edges} | {(rank[b], rank[a]) for a, b in edges}
    e = spark.createDataFrame(sorted(both), "u long, v long")
    return e, spark.createDataFrame([(k,) for k in range(len(order))], "v long"), both


def near(both):
    out = {}
    for a, b in both:
        out.setdefault(a, []).append(b)
    return out


def distances(both, n):
    d = {}
    for s in range(n):
        d[s, s], todo = 0, [s]
        for x in todo:
            for y in near(both).get(x, []):
                if (s, y) not in d:
                    d[s, y] = d[s, x] + 1
                    todo.append(y)
    return d


@pytest.mark.parametrize("name", MICRO)
def test_micro_labels_equal_sequential_search(spark, name):
    edges, order = MICRO[name]
    e, v, both = frames(spark, edges, order)
    got = {tuple(r) for r in lb.label_pruned(e, v).collect()}
    want, counts = lb.label_reference(near(both), list(range(len(order))))
    assert got == {(x, h, d) for x, l in want.items() for h, d in l.items()}
    assert len(got) == EXPECTED[name]
    if edges:
        space = {r["hub"]: (r["visited"], r["labelled"]) for r in measures.search_space(lb.label_pruned(e, v), e).collect()}
        assert space == counts


def test_random_graphs_are_exact_and_minimal(spark):
    rng = random.Random(3)
    for n in (9, 17):
        edges = [(a, b) for a, b in itertools.combinations(range(n), 2) if rng.random() < 0.2]
        order = rng.sample(range(n), n)
        e, v, both = frames(spark, edges, order)
        lab = lb.label_pruned(e, v)
        d = distances(both, n)
        pairs = spark.createDataFrame([(s * n + t, s, t) for s in range(n) for t in range(n)], "qid long, s long, t long")
        for answer in (query.query_labels(lab, pairs), query.query_packed(query.pack(lab), pairs)):
            assert {(r.s, r.t): r.dist for r in answer.collect() if r.dist is not None} == d
        assert measures.audit_minimal(lab).isEmpty()
        index = baselines.tree_index(e, 3)
        assert all(baselines.tree_query(index, s, t) == d.get((s, t)) for s in range(n) for t in range(n))


def test_bit_parallel_words_and_sign_bit(spark):
    star = [(0, i) for i in range(1, 66)] + [(64, 66), (65, 66), (1, 2)]
    e, v, both = frames(spark, star, list(range(67)))
    roots = bitp.choose_bp_roots(e, 1, 64)
    assert roots == [(0, list(range(1, 65)))]
    d = distances(both, 67)
    for r in bitp.label_bitparallel(e, roots).collect():
        for bit, m in enumerate(roots[0][1]):
            assert (r.s_minus >> bit & 1) == (d[m, r.v] == r.dist - 1)
            assert (r.s_zero >> bit & 1) == (d[m, r.v] == r.dist)
    pairs = spark.createDataFrame([(s * 67 + t, s, t) for s in range(60, 67) for t in range(60, 67)], "qid long, s long, t long")
    bp, lab, _ = bitp.label_combined(e, v, 1, 64)
    assert all(r.dist == d[r.s, r.t] for r in query.query_combined(bp, lab, pairs).collect())


def test_superset_slip_is_masked(spark):
    e, _, _ = frames(spark, [(0, 1), (1, 2), (1, 3), (2, 3)], [0, 1, 2, 3])
    rows = {r.v: (r.s_minus, r.s_zero) for r in bitp.label_bitparallel(e, [(0, [1])]).collect()}
    assert rows[2] == rows[3] == (1, 0)


def test_directed_and_weighted(spark):
    v = spark.createDataFrame([(k,) for k in range(3)], "v long")
    ring = spark.createDataFrame([(0, 1, 1), (1, 2, 1), (2, 0, 1)], "u long, v long, w long")
    pairs = spark.createDataFrame([(0, 0, 1), (1, 1, 0)], "qid long, s long, t long")
    assert {r.qid: r.dist for r in query.query_directed(*lb.label_pruned_directed(ring, v), pairs).collect()} == {0: 1, 1: 2}
    tri = spark.createDataFrame([(0, 1, 1), (1, 0, 1), (1, 2, 1), (2, 1, 1), (0, 2, 3), (2, 0, 3)], "u long, v long, w long")
    far = spark.createDataFrame([(0, 0, 2)], "qid long, s long, t long")
    assert query.query_labels(lb.label_pruned_weighted(tri, v), far).first().dist == 2
    with pytest.raises(ValueError):
        lb.label_pruned_weighted(tri, v, bit_parallel=1)
    with pytest.raises(ValueError):
        lb.label_correcting(tri.selectExpr("u", "v", "0L as w"), v)


def test_paths_follow_edges(spark):
    e, v, both = frames(spark, MICRO["cycle6"][0], MICRO["cycle6"][1])
    pairs = spark.createDataFrame([(0, 0, 3), (1, 2, 2), (2, 5, 1)], "qid long, s long, t long")
    steps = {}
    for r in query.paths(lb.label_pruned(e, v, with_parent=True), pairs).collect():
        steps.setdefault(r.qid, {})[r.step] = r.v
    for qid, s, t in ((0, 0, 3), (1, 2, 2), (2, 5, 1)):
        walk = [steps[qid][k] for k in sorted(steps[qid])]
        assert walk[0] == s and walk[-1] == t and all((a, b) in both for a, b in zip(walk, walk[1:]))
        assert len(walk) - 1 == distances(both, 6)[s, t]


def test_components(spark):
    e, v, _ = frames(spark, *MICRO["two_comp"])
    got = {r.vid: r.comp for r in search.components(e, v.withColumnRenamed("v", "vid")).collect()}
    assert got == {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 5}


TWINS = ["graph_trade_edges", "graph_web_edges", "graph_handoff_edges", "rank_degree_trade", "degree_ccdf_web", "labels_pruned_handoff", "labels_pruned_trade", "search_space_supply", "coverage_pairs_by_distance_supply", "query_pruned_trade", "landmark_bounds_handoff", "coverage_by_step_handoff", "path_steps_handoff", "audit_prefix_all_handoff", "cube_distance", "asof_user_event", "closest_customers_topk"]


@pytest.mark.parametrize("name", TWINS)
def test_twin(spark, name):
    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "pages", "embeddings"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    df = registry.queries()[name](spark, d)
    cols = sorted(df.columns)
    want = con.execute(f"select {', '.join(cols)} from ({registry.oracle_sql()[name]})").fetchall()
    assert sorted(map(str, (tuple(r) for r in df.select(*cols).collect()))) == sorted(map(str, want))


def test_streams_and_sql_face(spark, tmp_path):
    from hubdist.functions import sqlface
    from hubdist.streaming import serve

    e, v, _ = frames(spark, *MICRO["path5"])
    packed = query.pack(lb.label_pruned(e, v))
    asked = spark.createDataFrame([(0, 0, 3), (1, 2, 2), (2, 0, 77)], "qid long, s long, t long")
    asked.write.parquet(str(tmp_path / "asked"))
    stream = spark.readStream.schema(asked.schema).parquet(str(tmp_path / "asked"))
    serve.answer_stream(stream, packed).writeStream.format("memory").queryName("answers").trigger(availableNow=True).start().awaitTermination()
    want = {0: query.query_labels(lb.label_pruned(e, v), asked.where("qid = 0")).first().dist, 1: 0, 2: None}
    assert {r.qid: r.dist for r in spark.table("answers").collect()} == want
    sqlface.register(spark, packed)
    asked.createOrReplaceTempView("asked_here")
    got = spark.sql("select qid, hub_distance(a.hubs, a.dists, b.hubs, b.dists) dist from asked_here left join labels_packed a on a.v = s left join labels_packed b on b.v = t")
    assert {r.qid: r.dist for r in got.collect()} == want
    assert spark.sql("select count(*) n from labels_packed, lateral label_entries(hubs, dists)").first().n == EXPECTED["path5"]
    events = [(1, 10, 0), (1, 11, 100), (1, 11, 150), (1, 12, 10_000), (2, 10, 50), (1, 10, 10_100)]
    spark.createDataFrame(events, "key long, user_id long, us long").coalesce(1).write.parquet(str(tmp_path / "events"))
    found = serve.handoffs(spark.readStream.schema("key long, user_id long, us long").parquet(str(tmp_path / "events")), 1000)
    found.writeStream.format("memory").queryName("moves").trigger(availableNow=True).start().awaitTermination()
    assert sorted(map(tuple, spark.table("moves").collect())) == [(10, 11, 100), (12, 10, 10_100)]
    root = str(tmp_path / "root")
    first = serve.swap_index(lambda p: asked.write.parquet(p), root, spark)
    second = serve.swap_index(lambda p: asked.write.parquet(p), root, spark)
    assert first != second == serve.current_index(spark, root) and spark.read.parquet(first).count() == 3
