"""Streams cut anyhow, reductions against linear algebra, tuned hashing, divided and stored trees, space partitions, the pipeline object."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from tracelink.functions import tables
from tracelink.operators import linking as L
from tracelink.operators import metrics as M
from tracelink.operators import prepare as P
from tracelink.operators import reduce as R
from tracelink.operators import sigtree, spaces
from tracelink.operators import weights as W
from tracelink.pipeline import LinkPipeline, SignatureEstimator
from tracelink.sources import generated
from tracelink.sources import traces as S
from tracelink.streaming import streams

SF = "/root/testdata/sf0.001"


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


@pytest.fixture(scope="module")
def data(spark):
    trace = P.interleaved(S.habit_of_size(spark, 120, 40)).cache()
    sig = W.spatial(trace, 5).cache()
    return trace, sig, *L.sides(sig), S.locations(trace).cache()


# --- streams -----------------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("cuts", [1, 3, 10])
def test_stream_in_any_cut_equals_the_batch(spark, tmp_path, cuts):
    events = S.read(spark, SF, "events")
    for i in range(cuts):
        events.where(F.col("event_id") % cuts == i).coalesce(1).write.parquet(str(tmp_path / f"in/events_{i}.parquet"))
    stream = streams.event_stream(spark, str(tmp_path / "in")).where(F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")) % 2 == 0)
    trace = P.interleaved(S.habit(events))
    stored = trace.where("side = 'D'").drop("side")
    got = streams.link_arrivals(stream, stored, 2, str(tmp_path / "out"))
    want = L.inverted(*L.sides(W.spatial(trace, None, scope="candidate")), 2)
    assert rows(got, "qid", "oid", "rnk", F.round("sim", 9)) == rows(want, "qid", "oid", "rnk", F.round("sim", 9))
    assert spark.read.parquet(str(tmp_path / "out/linked")).select("batch").distinct().count() == cuts


def test_batches_of_a_linked_stream_leave_only_their_results(spark, tmp_path, monkeypatch):
    """However many batches, candidates are prepared once and what a batch writes on its way is gone."""
    from tracelink import session

    kept = tmp_path / "kept"
    monkeypatch.setattr(session, "shared_folder", lambda spark: str(kept))
    for limit in ("JOINED", "JOINED_TIMES"):
        monkeypatch.setattr(L, limit, 0)
    events = S.read(spark, SF, "events")
    for i in range(3):
        events.where(F.col("event_id") % 3 == i).coalesce(1).write.parquet(str(tmp_path / f"in/events_{i}.parquet"))
    stored = P.interleaved(S.habit(events)).where("side = 'D'").drop("side")
    streams.link_arrivals(streams.event_stream(spark, str(tmp_path / "in")), stored, 2, str(tmp_path / "out"))
    assert sorted(p.name.split("-")[0] for p in kept.iterdir()) == ["blocks", "candidates", "dealt", "rarity"]
    assert sorted(p.name for p in (tmp_path / "out").iterdir()) == ["checkpoint", "counts", "linked"]


def test_a_batch_run_again_counts_once(spark, tmp_path):
    store = streams.ObjectStore(spark, str(tmp_path / "store"))
    delta = spark.createDataFrame([(1, 7, 2), (2, 8, 1)], "oid long, fid long, n long")
    assert rows(store.merged(delta, 0), "oid", "fid", "n") == [(1, 7, 2), (2, 8, 1)]
    more = spark.createDataFrame([(1, 7, 3)], "oid long, fid long, n long")
    for _ in range(2):
        assert rows(store.merged(more, 1), "oid", "fid", "n") == [(1, 7, 5)]


# --- reductions --------------------------------------------------------------------------------------------------------------------


def test_components_span_the_leading_subspace(spark, data):
    """Both methods against a singular value decomposition: variances, and angles of the spanned subspace."""
    sig = data[1]
    frame = sig.toPandas()
    names = sorted(set(zip(frame["side"], frame["oid"], strict=True)))
    at = {x: i for i, x in enumerate(names)}
    fids = {f: i for i, f in enumerate(sorted(set(frame["fid"])))}
    x = np.zeros((len(names), len(fids)))
    for s, o, f, w in frame[["side", "oid", "fid", "w"]].itertuples(index=False):
        x[at[s, o], fids[f]] = w
    u, value, _ = np.linalg.svd(x - x.mean(axis=0), full_matrices=False)
    m = 6
    for method, close in (("gram", 1e-6), ("randomized", 0.05)):
        got = R.pca(sig, m, method).toPandas()
        points = np.zeros((len(names), m))
        for s, o, v in got[["side", "oid", "v"]].itertuples(index=False):
            points[at[s, o]] = v
        assert np.allclose(np.sort((points**2).sum(axis=0))[::-1], value[:m] ** 2, rtol=max(close, 1e-6))
        basis, _ = np.linalg.qr(points)
        # every found direction lies in the span of few more leading ones, whatever ties there are
        assert np.linalg.norm(u[:, : 4 * m].T @ basis, axis=0).min() > 1 - close


def test_dense_components_against_linear_algebra(spark):
    vectors = S.read(spark, SF, "embeddings")
    x = np.array([r["embedding"] for r in vectors.orderBy("vec_id").collect()], dtype=float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    value = np.linalg.svd(x - x.mean(axis=0), compute_uv=False)
    got = np.array([r["v"] for r in R.pca_dense(vectors, 5).orderBy("id").collect()])
    assert np.allclose(np.sort((got**2).sum(axis=0))[::-1], value[:5] ** 2)


def test_super_bits_are_orthogonal(spark, data):
    """Signatures that are single places show the directions themselves: in a batch their signs come from an orthogonal basis."""
    vocabulary = [r["fid"] for r in data[1].select("fid").distinct().orderBy("fid").collect()]
    signs = np.array([[r[f"p{j}"] for j in range(8)] for r in spark.createDataFrame([(f,) for f in vocabulary], "fid long").select("fid", *[L._sign(F.col("fid"), j).alias(f"p{j}") for j in range(8)]).orderBy("fid").collect()])
    gram = signs.T @ signs
    turned = signs @ np.linalg.inv(np.linalg.cholesky(gram)).T
    assert np.allclose(turned.T @ turned, np.eye(8), atol=1e-6)
    one = spark.createDataFrame([("D", f, f, 1.0) for f in vocabulary], "side string, oid long, fid long, w double")
    bits = np.array([r["bits"] for r in L.lsh_bits(one, 8, superbit=8).orderBy("oid").collect()])
    assert (bits == (np.round(turned, 9) >= 0)).mean() > 0.999


@pytest.mark.parametrize("family", ["sign", "gauss"])
def test_tuned_hashing_reaches_its_recall(spark, data, family):
    _, sig, q, d, _ = data
    bands, recall = L.lsh_tune(q, d, sig, 0.9, family=family, m=48)
    found = L.lsh(q, d, L.lsh_bits(sig, 48, family), bands, 48, 1)
    assert recall >= 0.9 and M.recall_at(found, L.inverted(q, d, 1), 1).first()["recall"] >= 0.9


def test_estimated_cosine_of_more_bits_is_closer(spark, data):
    _, sig, q, d, _ = data
    exact = L.dot_pairs(q, d)
    errors = []
    for m in (16, 128):
        near = L.lsh_scan(L.lsh_bits(sig, m, "gauss"), m, 1 << 20).select("qid", "oid", F.col("sim").alias("e"))
        errors.append(exact.join(near, ["qid", "oid"]).agg(F.avg(F.abs(F.col("sim") - F.col("e")))).first()[0])
    assert errors[1] < 0.6 * errors[0]


# --- tree --------------------------------------------------------------------------------------------------------------------------


def naive_merge(ids, features, capacity, boxes):
    free, nodes, closed = list(ids), [], []
    united = lambda a, b: (min(a[0], b[0]), min(a[1], b[1]), max(a[2], b[2]), max(a[3], b[3]))
    area = lambda b: (b[2] - b[0]) * (b[3] - b[1])
    shared = lambda a, b: max(0.0, min(a[2], b[2]) - max(a[0], b[0])) * max(0.0, min(a[3], b[3]) - max(a[1], b[1]))
    while free:
        node = [free.pop(0)]
        have, box = set(features[node[0]]), boxes[node[0]]
        while len(node) < capacity and free:
            some = [i for i in free if features[i] & have]
            some = some or free[:capacity]
            best = min(some, key=lambda i: (-len(features[i] & have), round(area(united(box, boxes[i])) - area(box), 9), round(sum(shared(united(box, boxes[i]), c) for c in closed), 9), ids.index(i)))
            free.remove(best)
            node.append(best)
            have |= features[best]
            box = united(box, boxes[best])
        nodes.append(node)
        closed.append(box)
    return nodes


def test_merging_against_a_naive_form():
    rng = random.Random(4)
    for _ in range(20):
        n = rng.randint(1, 30)
        ids = rng.sample(range(100), n)
        features = {i: set(rng.sample(range(25), rng.randint(1, 4))) for i in ids}
        boxes = {i: (x := rng.randint(0, 9), y := rng.randint(0, 9), x + rng.randint(0, 4), y + rng.randint(0, 4)) for i in ids}
        assert sigtree.merge_by_common(ids, features, 4, boxes) == naive_merge(ids, features, 4, boxes)


def check_invariants(tree, most=None):
    for low, high in itertools.pairwise(tree.levels):
        kids = [r["child"] for r in high.members.collect()]
        assert len(kids) == len(set(kids)) == low.nodes.count()
        assert set(kids) == {r["nid"] for r in low.nodes.collect()}
        assert rows(high.sigs, "nid", "fid", F.round("w", 9)) == rows(sigtree.aggregate(high.members, low.sigs), "nid", "fid", F.round("w", 9))
        assert rows(high.nodes, "nid", *sigtree.BOX) == rows(sigtree.aggregate_boxes(high.members, low.nodes), "nid", *sigtree.BOX)
        if most:
            assert high.members.groupBy("nid").count().agg(F.max("count")).first()[0] <= most
    assert tree.levels[-1].nodes.count() == 1


def test_divided_tree(spark, data, criterion="common"):
    _, _, q, d, place = data
    tree = sigtree.build(d.where("oid % 3 = 0"), place, 4, criterion)
    for part in (1, 2):
        tree = sigtree.insert(tree, d.where(f"oid % 3 = {part}"), place, criterion, "split")
    check_invariants(tree, 4)
    want = rows(L.inverted(q, d, 3), "qid", "oid", "rnk")
    assert rows(sigtree.knn_join(q, tree, 3, place), "qid", "oid", "rnk") == want
    assert rows(sigtree.knn(q, tree, 3, place), "qid", "oid", "rnk") == want


def test_large_levels_by_joins_equal_small_ones(spark, data, monkeypatch, tmp_path):
    """Nothing local, nothing broadcast: the same leaves and neighbours; a stored tree comes back whole."""
    _, _, q, d, place = data
    few = sigtree.build(d, place, 4)
    monkeypatch.setattr(sigtree, "LOCAL_NODES", 0)
    monkeypatch.setattr(sigtree, "BROADCAST_ROWS", 0)
    many = sigtree.build(d, place, 4)
    check_invariants(many, 4)
    assert [rows(lv.members, "nid", "child") for lv in few.levels] == [rows(lv.members, "nid", "child") for lv in many.levels]
    want = rows(L.inverted(q, d, 3), "qid", "oid", "rnk")
    for mbr, bound in ((True, True), (False, False)):
        assert rows(sigtree.knn_join(q, many, 3, place, mbr, bound), "qid", "oid", "rnk") == want
    sigtree.save(many, str(tmp_path / "tree"))
    back = sigtree.load(spark, str(tmp_path / "tree"))
    assert back.capacity == 4 and rows(sigtree.knn_join(q, back, 3, place), "qid", "oid", "rnk") == want


def test_routing_by_overlap_growth(spark):
    """Two children hold the object in their boxes' growth alike; the one that would come to overlap its sibling more is avoided."""
    place = spark.createDataFrame([(1, 0.0, 0.0), (2, 4.0, 4.0), (3, 10.0, 0.0), (4, 14.0, 4.0), (5, 7.0, 0.0), (6, 7.0, 4.0), (7, 5.0, 2.0), (8, 9.0, 6.0)], "pid long, x double, y double")
    objects = spark.createDataFrame([(o, f, 0.5) for o, fs in {1: (1, 2), 2: (1, 2), 3: (3, 4), 4: (3, 4), 5: (7, 8), 6: (7, 8)}.items() for f in fs], "oid long, fid long, wd double")
    tree = sigtree.build(objects, place, 2, "spatial")
    fresh = spark.createDataFrame([(9, 5, 0.5), (9, 6, 0.5)], "oid long, fid long, wd double")
    grown = sigtree.insert(tree, fresh, place, "spatial")
    check_invariants(grown)
    local = sigtree.local(tree)
    # the same choice by hand, level by level
    box, node = (7.0, 0.0, 7.0, 4.0), local
    while node.level > 1:
        grow = {c.nid: round(sigtree._area(sigtree._united(c.box, box)) - sigtree._area(c.box), 9) for c in node.children}
        over = {c.nid: round(sum(sigtree._shared_area(sigtree._united(c.box, box), s.box) - sigtree._shared_area(c.box, s.box) for s in node.children if s is not c), 9) for c in node.children}
        node = min(node.children, key=lambda c: (grow[c.nid], over[c.nid], c.nid))
    assert [r["nid"] for r in grown.levels[1].members.where("child = 9").collect()] == [node.nid]


# --- dense partitions ----------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("kind", spaces.KINDS)
def test_partitions_meet_every_point_of_a_ball(kind):
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(size=(300, 3)), rng.normal(size=(300, 3)) * 0.1 + 2])
    cut = spaces.KINDS[kind](x[::2], 24)
    cell = cut.assign(x)
    names = np.unique(cell)
    cut.bounded(names, np.stack([x[cell == c].min(axis=0) for c in names]), np.stack([x[cell == c].max(axis=0) for c in names]))
    assert len(names) > 8
    for i in range(0, 600, 25):
        for radius in (0.05, 0.4, 1.5):
            met = cut.meets(x[i], radius)
            inside = set(cell[np.linalg.norm(x - x[i], axis=1) <= radius].tolist())
            assert inside <= set(met) and len(met) == len(set(met))
    assert len(cut.meets(x[0], 0.05)) < len(names)


def test_holey_bricks_have_holes():
    x = np.random.default_rng(1).normal(size=(2000, 4))
    cut = spaces.HoleyBricks(x, 32)
    sizes = np.bincount(cut.assign(x))
    assert cut.root.holes and max(sizes) <= 2 * len(x) / 32 and min(sizes) >= len(x) / 32 / 4


# --- surroundings --------------------------------------------------------------------------------------------------------------------


def test_pipeline_object(spark, data):
    trace = data[0].drop("side")
    want = None
    for search in ("inverted", "euclid", "mbr", "tree"):
        out = LinkPipeline(m=5, k=3, search=search).run(trace)
        got = rows(out.knn, "qid", "oid", "rnk")
        want = want or got
        assert got == want and out.match is None
    whole = LinkPipeline(m=5, k=3, rerank=None, match=True).run(data[0].where("side = 'Q'").drop("side"), data[0].where("side = 'D'").drop("side"))
    assert whole.match.select("qid").distinct().count() == whole.match.count() and whole.metrics.count() == 3


def test_estimator_freezes_rarity(spark, data):
    d = data[0].where("side = 'D'").drop("side")
    model = SignatureEstimator(None).fit(d)
    assert rows(model.transform(d), "oid", "fid", F.round("w", 9)) == rows(W.spatial(d.withColumn("side", F.lit("Q"))), "oid", "fid", F.round("w", 9))
    assert model.transform(d.where("oid = 1")).select("oid").distinct().count() == 1


def test_generated_source_equals_generated_events(spark):
    generated.register(spark)
    events = spark.read.format("tracegen").option("objects", 30).option("points", 20).option("parts", 3).load()
    assert rows(S.habit(events), "oid", "t", "pid") == rows(S.habit_of_size(spark, 30, 20), "oid", "t", "pid")


def test_table_functions_equal_their_native_forms(spark):
    tables.register(spark)
    df = spark.createDataFrame([(1, ["a", "b", "c"]), (2, ["a"]), (3, None)], "i int, w array<string>")
    df.createOrReplaceTempView("some_words")
    assert rows(spark.sql("SELECT i, g.at, g.gram FROM some_words, LATERAL grams(w, 2) g"), "i", "at", "gram") == rows(tables.grams(df, "w", 2), "i", "at", "gram") == [(1, 0, "a_b"), (1, 1, "b_c")]


def test_pivot_index_is_exact(spark, data, monkeypatch):
    trace = data[0]
    hist = L.temporal(trace, 2).cache()
    want = rows(L.histogram_knn(hist, 2, 3), "qid", "oid", "rnk")
    monkeypatch.setattr(L, "HIST_CELL", 8)
    assert rows(L.histogram_index(hist, 2, 3), "qid", "oid", "rnk") == want
    assert L.histogram_index(hist.where("side = 'Q'"), 2, 3).isEmpty()
