"""Worked examples, exact baselines and invariants of the linking methods."""

import itertools
import math
import random

import duckdb
import pytest
from pyspark.sql import functions as F

from tracelink.functions import columns as C
from tracelink.operators import linking as L
from tracelink.operators import metrics as M
from tracelink.operators import prepare as P
from tracelink.operators import protect, refine, sigtree, spaces
from tracelink.operators import reduce as R
from tracelink.operators import weights as W
from tracelink.plans import relational, workloads
from tracelink.sources import traces as S
from tracelink.streaming import streams

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def data(spark):
    trace = P.interleaved(S.habit(S.read(spark, SF, "events"))).cache()
    sig = W.spatial(trace, 5).cache()
    return trace, sig, *L.sides(sig), S.locations(trace).cache()


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def same(a, b):
    return rows(a.withColumn("s", F.round("sim", 9)), "qid", "oid", "s", "rnk") == rows(b.withColumn("s", F.round("sim", 9)), "qid", "oid", "s", "rnk")


QUICK = ["p_split_random", "s_tfidf_own", "s_tfidf_union", "r_cut", "s_qgram2", "w_repr_temp_4h", "r_lsh_bits", "w_link_l2ap", "w_link_tree", "w_sm_pairs", "w_closure_r2", "w_unique_2", "rel_as_of", "rel_windows", "st_counts", "st_sessions"]


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_its_sql_twin(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = workloads.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted(str(tuple(r)) for r in df.select(*cols).collect())
    want = sorted(str(tuple(r)) for r in con.sql(f"SELECT {', '.join(chr(34) + c + chr(34) for c in cols)} FROM ({workloads.ORACLES[name]})").fetchall())
    assert got == want


@pytest.mark.parametrize("name", ["rel_join_inner", "rel_join_left", "rel_join_right", "rel_join_full", "p_snap"])
def test_whole_tables_equal_their_sql_twin(spark, name):
    test_query_equals_its_sql_twin(spark, name)
    if name.startswith("rel"):
        df = workloads.QUERIES[name](spark, SF)
        assert df.where("o_orderkey is not null").count() == S.read(spark, SF, "orders").count()
        want = 0 if "inner" in name else S.read(spark, SF, "customer").count()
        assert not want or df.select("c_custkey").distinct().count() == want
    else:
        points = S.raw(S.read(spark, SF, "events")).select("oid", "t", "x", "y").distinct()
        place = {r["pid"]: (r["x"], r["y"]) for r in S.locations(S.habit(S.read(spark, SF, "events"))).collect()}
        near = {(p["oid"], p["t"], p["x"], p["y"]): min(((p["x"] - x) ** 2 + (p["y"] - y) ** 2, i) for i, (x, y) in place.items()) for p in points.collect()}
        got = {(r["oid"], r["t"], r["x"], r["y"]): r["pid"] for r in workloads.QUERIES[name](spark, SF).collect()}
        assert got == {k: i for k, (d2, i) in near.items() if d2 <= 16}


@pytest.mark.parametrize("name", ["w_days_both_2", "w_tree_m3_k1"])
def test_registered_members_equal_their_sql_twin(spark, name):
    assert {f"w_days_{x}_{n}" for x in ("query", "both") for n in range(1, 16)} | {f"w_tree_m{m}_k{k}" for m in (3, 5, 10) for k in range(1, 6)} <= set(workloads.QUERIES)
    test_query_equals_its_sql_twin(spark, name)


def test_registry_is_complete():
    assert {relational, streams} and len(workloads.QUERIES) > 200 and set(workloads.ORACLES) <= set(workloads.QUERIES)


def transport(a, b, hours):
    """Brute force: move unit masses between bins at circular cost."""
    bins = 24 // hours
    left = [i for i, n in enumerate(a) for _ in range(n)]
    right = [i for i, n in enumerate(b) for _ in range(n)]
    cost = lambda i, j: min(abs(i - j), bins - abs(i - j)) * hours / 12
    return min(sum(cost(i, j) for i, j in zip(left, p, strict=True)) for p in itertools.permutations(right)) / len(left)


def test_circular_transport_cost(spark):
    random.seed(3)
    cases = []
    for hours in (4, 6, 8, 12):
        bins = 24 // hours
        for _ in range(5):
            a, b = [0] * bins, [0] * bins
            for _ in range(5):
                a[random.randrange(bins)] += 1
                b[random.randrange(bins)] += 1
            cases.append((hours, a, b))
    for hours, a, b in cases:
        df = spark.createDataFrame([([x / 5 for x in a], [x / 5 for x in b])], "a array<double>, b array<double>")
        got = df.select(C.emd_circular(F.col("a"), F.col("b"), hours)).first()[0]
        assert got == pytest.approx(transport(a, b, hours), abs=1e-9)
    one = [0.0] * 24
    x, y = one.copy(), one.copy()
    x[1], y[23] = 1.0, 1.0
    df = spark.createDataFrame([(x, y)], "a array<double>, b array<double>")
    assert df.select(C.emd_circular(F.col("a"), F.col("b"), 1)).first()[0] == pytest.approx(1 / 6)


def test_one_grams_are_places(spark, data):
    trace, *_ = data
    a = W.sequential(trace, 1, ["t", "pid", "x", "y"]).select("side", "oid", F.col("fid").cast("long").alias("fid"), F.round("w", 9).alias("w"))
    b = W.spatial(trace).select("side", "oid", "fid", F.round("w", 9).alias("w"))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_cut_is_nested_and_of_unit_length(spark, data):
    trace, *_ = data
    keys = {m: set(rows(W.spatial(trace, m), "side", "oid", "fid")) for m in (2, 4, None)}
    assert keys[2] < keys[4] < keys[None]
    norms = W.spatial(trace, 4).groupBy("side", "oid").agg(F.sum(F.col("w") ** 2).alias("n")).select(F.max(F.abs(F.col("n") - 1))).first()[0]
    assert norms < 1e-9


def test_feature_of_all_objects_has_no_weight(spark):
    trace = spark.createDataFrame([("Q", o, p) for o, p in [(1, 7), (1, 8), (2, 7), (2, 9)]], "side string, oid long, pid long")
    assert {r["fid"] for r in W.spatial(trace).collect()} == {8, 9}


def test_short_traces_have_no_grams(spark):
    trace = spark.createDataFrame([("Q", 1, 1, 5), ("Q", 1, 2, 6)], "side string, oid long, t int, pid long")
    assert W.qgrams(trace, 3, ["t"]).isEmpty()


def test_exact_searches_agree(spark, data):
    trace, sig, q, d, place = data
    want = L.inverted(q, d, 3).cache()
    box = L.boxes(sig, place)
    assert same(L.linear(q, d, 3), want)
    assert same(L.euclid(q, d, 3), want)
    assert same(L.mbr_range(q, d, box, 3), want)
    assert same(L.threshold_knn(q, d, 3, 0.2), want)
    for criterion in ("spatial", "common"):
        tree = sigtree.build(d, place, 4, criterion)
        for mbr, bound in itertools.product((True, False), repeat=2):
            assert same(sigtree.knn_join(q, tree, 3, place, mbr, bound), want)
            assert same(sigtree.search_local(q, tree, 3, place, mbr, bound), want)


@pytest.mark.parametrize("bound", ["maxweight", "minsize", "length", "l2"])
@pytest.mark.parametrize("theta", [0.1, 0.5, 0.8])
def test_threshold_joins_are_exact(spark, data, bound, theta):
    _, _, q, d, _ = data
    want = L.dot_pairs(q, d).where(F.round("sim", 9) >= theta)
    assert rows(L.threshold(q, d, theta, bound), "qid", "oid") == rows(want, "qid", "oid")


def test_tree_invariants_and_updates(spark, data):
    _, _, q, d, place = data
    tree = sigtree.build(d.where("oid % 4 <> 0"), place, 4)
    grown = sigtree.insert(tree, d.where("oid % 4 = 0"), place)
    for t in (tree, grown):
        for low, high in itertools.pairwise(t.levels):
            kids = [r["child"] for r in high.members.collect()]
            assert len(kids) == len(set(kids)) == low.nodes.count()
            want = sigtree.aggregate(high.members, low.sigs)
            assert rows(high.sigs, "nid", "fid", F.round("w", 9)) == rows(want, "nid", "fid", F.round("w", 9))
            assert rows(high.nodes, "nid", *sigtree.BOX) == rows(sigtree.aggregate_boxes(high.members, low.nodes), "nid", *sigtree.BOX)
    assert tree.levels[1].members.groupBy("nid").count().agg(F.max("count")).first()[0] <= 4
    assert same(sigtree.knn_join(q, grown, 3, place), L.inverted(q, d, 3))


def test_largest_weight_rule(spark):
    members = spark.createDataFrame([(3, 1), (3, 2)], "nid long, child long")
    sigs = spark.createDataFrame([(1, 8, 0.3), (2, 8, 0.5)], "nid long, fid long, w double")
    assert rows(sigtree.aggregate(members, sigs), "nid", "fid", "w") == [(3, 8, 0.5)]


def test_merging_by_common_features():
    features = {1: {1, 2}, 2: {9}, 3: {1, 2, 3}, 4: {9, 8}, 5: {7}}
    assert sigtree.merge_by_common([1, 2, 3, 4, 5], features, 2) == [[1, 3], [2, 4], [5]]
    assert sigtree.merge_by_common([1, 2, 3], features, 4) == [[1, 3, 2]]
    assert sigtree.enlargement({1, 2}, {2, 3, 4}) == 2 and sigtree.enlargement({2, 3, 4}, {1, 2}) == 1
    near, far = (0, 0, 1, 1), (9, 9, 9, 9)
    same = {i: {1} for i in range(1, 5)}
    assert sigtree.merge_by_common([1, 2, 3, 4], same, 2, {1: near, 2: far, 3: near, 4: far}) == [[1, 3], [2, 4]]
    # equal growth: the node that is closed already decides by overlap
    boxes = {1: (0, 0, 4, 4), 2: (0, 0, 4, 4), 3: (6, 0, 6, 4), 4: (2, 0, 6, 4), 5: (6, 0, 10, 4)}
    assert sigtree.merge_by_common([1, 2, 3, 4, 5], {1: {1}, 2: {1}, 3: {2}, 4: {2}, 5: {2}}, 2, boxes) == [[1, 2], [3, 5], [4]]


def test_tree_grown_by_insertion_finds_the_same():
    random.seed(1)
    objects = []
    for o in range(60):
        pts = {random.randrange(40): random.random() for _ in range(4)}
        objects.append((o, (min(pts), 0, max(pts), 0), pts))
    root = sigtree.build_by_insert(objects, 4)
    for _, box, sig in objects[:10]:
        want = sorted(((round(sum(w * s.get(f, 0) for f, w in sig.items()), 9), o) for o, _, s in objects), key=lambda e: (-e[0], e[1]))[:5]
        assert sigtree.best_first(root, sig, box, 5)[0] == [x for x in want if x[0] > 0]


def test_touching_boxes_overlap(spark):
    df = spark.createDataFrame([(0.0, 0.0, 1.0, 1.0, 1.0, 1.0, 2.0, 2.0), (0.0, 0.0, 1.0, 1.0, 1.5, 0.0, 2.0, 2.0)], "ax1 double, ay1 double, ax2 double, ay2 double, bx1 double, by1 double, bx2 double, by2 double")
    assert [r[0] for r in df.select(C.boxes_overlap("a", "b")).collect()] == [True, False]


def test_dense_indices_agree(spark):
    vectors = S.read(spark, SF, "embeddings")
    want = rows(L.dense_knn(vectors, 3), "qid", "oid", "rnk")
    for kind in ("kdtree", "rtree", "hbtree"):
        assert rows(spaces.knn(vectors, 3, kind), "qid", "oid", "rnk") == want


def test_dense_indices_take_the_smallest_ids_among_copies(spark):
    random.seed(5)
    one = [random.gauss(0, 1) for _ in range(6)]
    near = [one[0] * (1 + 1e-5), *one[1:]]  # rounds to the same similarity, a little way off
    data = [(i, one) for i in range(60, 10, -1)] + [(i, near) for i in range(10)] + [(i, [random.gauss(0, 1) for _ in range(6)]) for i in range(400, 100, -1)]
    vectors = spark.createDataFrame(data, "vec_id long, embedding array<double>").coalesce(1)
    want = rows(L.dense_knn(vectors, 3), "qid", "oid", "rnk")
    for kind in ("kdtree", "rtree", "hbtree"):
        assert rows(spaces.knn(vectors, 3, kind), "qid", "oid", "rnk") == want


def greedy(edges):
    taken_q, taken_d, out = set(), set(), set()
    for q, o, _ in sorted(edges, key=lambda e: (-e[2], e[0], e[1])):
        if q not in taken_q and o not in taken_d:
            out.add((q, o))
            taken_q.add(q)
            taken_d.add(o)
    return out


@pytest.mark.parametrize("small", [0, refine.SMALL])
def test_stable_matching(spark, monkeypatch, small):
    monkeypatch.setattr(refine, "SMALL", small)
    random.seed(1)
    edges = [(q, o, random.choice([0.1, 0.2, 0.3, 0.4, 0.5])) for q in range(25) for o in random.sample(range(18), 4)]
    df = spark.createDataFrame(edges, "qid long, oid long, sim double")
    got = refine.stable_match(df)
    matched = set(rows(got.where("stage = 'matched'"), "qid", "oid"))
    assert matched == greedy(edges)
    assert rows(got, "qid") == [(q,) for q in range(25)]
    assert set(rows(refine.stable_match(df.repartition(7), leftover="none"), "qid", "oid")) == matched


def test_stable_matching_of_ties_takes_few_rounds(spark, monkeypatch):
    written = []
    monkeypatch.setattr(refine, "SMALL", 0)
    monkeypatch.setattr(refine, "materialise", lambda df, name, f=refine.materialise: written.append(name) or f(df, name))
    block = [(q, o, 0.5) for q in range(30) for o in range(100, 125)]
    open_block = [(q, o, 0.5) for q in range(40, 44) for o in range(140, 144)] + [(50, 140, 0.9), (51, 141, 0.5), (51, 160, 0.7), (52, 160, 0.8)]
    edges = block + open_block
    got = refine.stable_match(spark.createDataFrame(edges, "qid long, oid long, sim double").repartition(5), leftover="none")
    assert set(rows(got, "qid", "oid")) == greedy(edges) and got.count() == len(greedy(edges))
    assert len(written) < 20


def test_stable_matching_of_a_long_chain_is_whole(spark, monkeypatch):
    monkeypatch.setattr(refine, "SMALL", 0)
    monkeypatch.setattr(refine, "SOON", 3)
    edges = [(i // 2, (i + 1) // 2, 1 - i * 1e-5) for i in range(2100)]
    got = refine.stable_match(spark.createDataFrame(edges, "qid long, oid long, sim double"), leftover="none")
    assert set(rows(got, "qid", "oid")) == greedy(edges)


def test_contested_partner_and_exhausted_list():
    own = [(1, 10, 0.9), (1, 11, 0.2), (2, 10, 0.8), (2, 11, 0.7), (3, 10, 0.5)]
    other = [(10, 1, 0.9), (10, 2, 0.8), (10, 3, 0.5), (11, 2, 0.7), (11, 1, 0.2)]
    assert set(refine.sequential_match(own, other)) == {(1, 10, "matched"), (2, 11, "matched"), (3, 10, "leftover")}


def test_rerank_permutes_and_matches_full_order(spark, data):
    trace, _, q, d, _ = data
    knn = L.inverted(q, d, 4)
    full = L.sides(W.spatial(trace))
    again = refine.rerank(knn, *full)
    assert rows(again, "qid", "oid") == rows(knn, "qid", "oid")
    order = again.join(L.dot_pairs(*full).withColumnRenamed("sim", "f"), ["qid", "oid"])
    assert order.where(F.abs(F.col("sim") - F.col("f")) > 1e-9).isEmpty()


def test_closure_shrinks_and_suppresses(spark, data):
    trace = data[0].drop("side")
    last = 1.0
    for before, after in protect.closure(trace, 3, 3):
        kept = M.data_remaining(trace, after).first()[0]
        assert 0 <= kept < last
        last = kept
        heavy = W.cut(W.weigh(W.counts(before.withColumn("side", F.lit("A")))), 3, False).select("oid", F.col("fid").alias("pid"))
        assert after.join(heavy, ["oid", "pid"], "left_semi").isEmpty()
    assert M.mbr_retained(trace, trace).first()[0] == 1.0 and M.grid_coverage(trace, trace, 5.0).first()[0] == 1.0


def test_splits_cover_the_trace(spark, data):
    trace = data[0].drop("side")
    n = trace.count()
    for split in (P.interleaved, P.random_days, P.serial, P.weekend):
        sides = split(trace)
        assert sides.count() == n
        days = {r["side"]: r["d"] for r in sides.groupBy("side").agg(F.count_distinct(P.day(F.col("t"))).alias("d")).collect()}
        assert days == ({"Q": 8, "D": 22} if split is P.weekend else {"Q": 15, "D": 15})


def test_planted_accuracy_at_known_hits(spark):
    trace = P.interleaved(S.habit(S.read(spark, "/root/testdata/sf0.01", "events")))
    for m, hits in ((3, 135), (5, 147), (10, 150)):
        acc = workloads.accuracy(trace, workloads.link(trace, m)).collect()
        assert [r["hits"] for r in acc if r["k"] == 1] == [hits]


def test_pca_methods_agree(spark, data):
    sig = data[1]
    mass = [R.pca(sig, 5, *how).select(F.sum(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))).first()[0] for how in (("gram",), ("randomized", 5))]
    assert 0.95 * mass[0] <= mass[1] <= mass[0] * (1 + 1e-6)


def test_hash_recall_rises_with_bits(spark, data):
    _, sig, q, d, _ = data
    exact = L.inverted(q, d, 1)
    got = [M.recall_at(L.lsh(q, d, L.lsh_bits(sig, m), m // 4, m, 1), exact, 1).first()["recall"] for m in (8, 64)]
    assert got[0] <= got[1] and got[1] > 0.5


def test_empty_sides(spark, data):
    trace = data[0].where("side = 'Q'")
    assert workloads.accuracy(trace, workloads.link(trace, 3)).first()["hits"] == 0
    assert L.inverted(*L.sides(W.spatial(trace, 3)), 3).isEmpty()


def test_plans_have_the_wanted_shape(spark, data):
    trace = P.interleaved(S.habit(S.read(spark, SF, "events")))
    q, d = L.sides(W.spatial(trace, 3))
    plan = L.inverted(q, d, 3)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan and "Cartesian" not in plan and "Python" not in plan
    assert "value:double" not in plan


def test_haversine(spark):
    one = spark.range(1).select(C.haversine(F.lit(0.0), F.lit(0.0), F.lit(1.0), F.lit(0.0))).first()[0]
    assert one == pytest.approx(6371008.8 * math.pi / 180)
