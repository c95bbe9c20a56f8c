"""Searches that meet in blocks: the same neighbours as every pair compared one by one, and no relation of pairs in the plan."""

import numpy as np
import pytest
from pyspark.sql import functions as F
from tracelink.functions import columns as C
from tracelink.operators import blocks
from tracelink.operators import linking as L

PAIRS = ("CartesianProduct", "BroadcastNestedLoopJoin")


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def rows(df, *names) -> list[tuple]:
    return sorted(tuple(r) for r in df.select(*names).collect())


def in_blocks(df) -> bool:
    """Whether pairs are compared in blocks."""
    return "MapInArrow" in plan_of(df)


def first(sim: np.ndarray, k: int, own: bool = True) -> list[tuple]:
    """``qid, oid, rnk`` of all pairs by rounded similarity, then by id."""
    out = []
    for q, s in enumerate(np.round(sim, 9)):
        order = [int(o) for o in np.lexsort((np.arange(len(s)), -s)) if own or o != q][:k]
        out += [(q, o, i + 1) for i, o in enumerate(order)]
    return sorted(out)


def vectors(n: int, copies: int) -> np.ndarray:
    v = np.random.default_rng(7).integers(-3, 4, size=(n, 5)).astype(float)
    v[:, 0] += 4.5  # no vector of length 0
    v[:copies] = v[0]
    return v


def test_dense_linear_in_blocks(spark, monkeypatch):
    v = vectors(90, 40)
    df = spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(v)], "vec_id long, embedding array<double>")
    unit = v / np.sqrt((v * v).sum(axis=1))[:, None]
    monkeypatch.setattr(blocks, "ROWS", 16)
    got = L.dense_knn(df, 3)
    assert in_blocks(got)
    assert rows(got, "qid", "oid", "rnk") == first(unit @ unit.T, 3, own=False)


@pytest.mark.parametrize("how", ["chi2", "correlation", "bhattacharyya", "intersection", "lp"])
def test_histograms_in_blocks(spark, how, monkeypatch):
    h = np.random.default_rng(3).integers(0, 4, size=(60, 6)).astype(float)
    h[:, 2] += 1
    h[20:40] = h[20]
    h /= h.sum(axis=1)[:, None]
    h[50] = 1 / 6  # no spread
    df = spark.createDataFrame([(s, i, [float(x) for x in r]) for s in "QD" for i, r in enumerate(h)], "side string, oid long, h array<double>")
    q, d = df.where("side = 'Q'").select(F.col("oid").alias("qid"), F.col("h").alias("a")), df.where("side = 'D'").select("oid", F.col("h").alias("b"))
    sim = C.histogram_distance(F.col("a"), F.col("b"), how)
    want = rows(L.top_k(q.crossJoin(d).select("qid", "oid", (sim if how in ("correlation", "intersection") else -sim).alias("sim")), 2).withColumn("s", F.round("sim", 6)), "qid", "rnk", "s")
    monkeypatch.setattr(blocks, "ROWS", 16)
    got = L.histogram_knn(df, 4, 2, how)
    assert in_blocks(got)
    assert rows(got.withColumn("s", F.round("sim", 6)), "qid", "rnk", "s") == want


def test_signs_in_blocks(spark, monkeypatch):
    m, bits = 16, np.random.default_rng(5).integers(0, 2, size=(50, 16))
    bits[10:30] = bits[10]
    df = spark.createDataFrame([(s, i, [int(x) for x in r]) for s in "QD" for i, r in enumerate(bits)], "side string, oid long, bits array<int>")
    apart = (bits[:, None, :] != bits[None, :, :]).sum(axis=2)
    monkeypatch.setattr(blocks, "ROWS", 8)
    got = L.lsh_scan(df, m, 2)
    assert in_blocks(got)
    assert rows(got, "qid", "oid", "rnk") == first(np.cos(np.pi * apart / m), 2)
    assert len(rows(L.lsh_scan(df, m, 1 << 20), "qid", "oid")) == 2500


def signatures(spark, n: int = 70):
    """Both sides' signatures of up to six of 12 places, and the boxes of these."""
    rng = np.random.default_rng(11)
    held = [(s, i, int(f), float(rng.integers(1, 5)) / 4) for s in "QD" for i in range(n) for f in rng.choice(12, size=1 + i % 6, replace=False)]
    df = spark.createDataFrame(held, "side string, oid long, fid long, w double")
    place = df.select(F.col("fid").alias("pid"), (F.col("fid") % 4).cast("double").alias("x"), F.expr("double(fid div 4)").alias("y")).distinct()
    return *L.sides(df), L.boxes(df, place)


def searched(spark, monkeypatch, search):
    q, d, box = signatures(spark)
    for name, n in (("OBJECTS", 16), ("ENTRIES", 40), ("EXPANDED", 64)):
        monkeypatch.setattr(blocks, name, n)
    for name in ("JOINED", "JOINED_TIMES"):
        monkeypatch.setattr(L, name, 0, raising=False)
    got = search(q, d, box)
    assert in_blocks(got)
    show = lambda df: rows(df.withColumn("s", F.round("sim", 9)), "qid", "oid", "rnk", "s")
    assert show(got) == show(L.top_k(L.dot_pairs(q, d), 3))


def test_inverted_in_blocks(spark, monkeypatch):
    searched(spark, monkeypatch, lambda q, d, box: L.inverted(q, d, 3))


def test_linear_in_blocks(spark, monkeypatch):
    searched(spark, monkeypatch, lambda q, d, box: L.linear(q, d, 3))


@pytest.mark.parametrize("pairs", [0, 1 << 40])
def test_products_leave_out_what_is_under_the_floor(pairs, monkeypatch):
    """Whether sums are held for all pairs or sorted by pair."""
    monkeypatch.setattr(blocks, "SPARSE_PAIRS", pairs, raising=False)
    rng = np.random.default_rng(2)
    held = [rng.random((20, 9)) * (rng.random((20, 9)) < 0.4) for _ in "qd"]
    q, d = ({"ids": np.arange(20), "row": np.nonzero(x)[0], "fid": np.nonzero(x)[1], "w": x[x > 0]} for x in held)
    want = held[0] @ held[1].T
    for floor in (np.zeros(20), np.linspace(0.0, 1.0, 20)):
        row, column, total = blocks.products(q, d, floor)
        there = want >= np.maximum(floor, np.finfo(float).tiny)[:, None]
        assert sorted(zip(row, column, strict=True)) == list(zip(*np.nonzero(there), strict=True))
        assert np.allclose(total, want[row, column])


def test_boxes_in_blocks(spark, monkeypatch):
    searched(spark, monkeypatch, lambda q, d, box: L.mbr_range(q, d, box, 3))


def test_buckets_in_blocks(spark, monkeypatch):
    q, d, _ = signatures(spark)
    sig = q.select(F.lit("Q").alias("side"), F.col("qid").alias("oid"), "fid", F.col("wq").alias("w")).union(d.select(F.lit("D"), "oid", "fid", "wd"))
    find = lambda: L.lsh(q, d, L.lsh_bits(sig, 12), 3, 12, 3)
    want = rows(find(), "qid", "oid", "rnk")
    for name in ("JOINED", "JOINED_TIMES"):
        monkeypatch.setattr(L, name, 0, raising=False)
    assert in_blocks(find())
    assert rows(find(), "qid", "oid", "rnk") == want


def test_recursion_reads_a_table(spark):
    import __spark_entry__

    df = __spark_entry__.queries()["rel_recursive"](spark, "/root/testdata/sf0.001")
    assert any("lineitem" in f for f in df.inputFiles())
    lines = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet").count()
    got = df.collect()
    assert sum(r["lines"] for r in got if r["n"] == 1) == lines
    assert max(r["f"] for r in got) == 479001600


def test_generated_events_read_a_table(spark):
    import __spark_entry__

    df = __spark_entry__.queries()["src_generated"](spark, "/root/testdata/sf0.001")
    assert any("events" in f for f in df.inputFiles())
    assert df.first()["points"] == spark.read.parquet("/root/testdata/sf0.001/events.parquet").count()


def test_range_join_pairs_rows_of_alike_parts(spark, tmp_path, monkeypatch):
    from tracelink.plans import relational

    price = [900.0, 905.0, 905.0, 905.0, 905.0, 905.0, 910.0, 910.1, 899.9999999999999, 894.9999999999999, float("nan"), None]
    part = [(i, i % 2 if 6 < i < 9 else 1, p) for i, p in enumerate(price)] + [(3, 1, 905.0), (40, None, 905.0)]
    spark.createDataFrame(part, "p_partkey long, p_size int, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    want = [(a, z) for a, m, x in part for z, n, y in part if a < z and m == n and m is not None and None not in (x, y) and abs(x - y) <= 5]
    monkeypatch.setattr(relational, "RANGE_CHUNK", 2, raising=False)
    monkeypatch.setattr(relational, "RANGE_TASK", 4, raising=False)
    got = relational._range_join(spark, str(tmp_path))
    assert rows(got, "a", "z") == sorted(want)
    assert got.rdd.getNumPartitions() > 4  # as many tasks as the pairs ask for, however small the table


#: Queries that search by postings.
POSTED = [
    "w_ablate_tfidf_full",
    "w_ablate_idf_full",
    "w_reduce_cut_m50",
    "w_link_raw",
    "w_ablate_tf_full",
    "st_link",
]


@pytest.mark.parametrize("name", POSTED)
def test_queries_by_postings_meet_in_blocks(spark, name, monkeypatch):
    import __spark_entry__

    def find() -> list[tuple]:
        df = __spark_entry__.queries()[name](spark, "/root/testdata/sf0.001")
        return rows(df, *df.columns)

    want, met, multiply = find(), [], blocks.multiply
    for limit in ("JOINED", "JOINED_TIMES"):
        monkeypatch.setattr(L, limit, 0, raising=False)
    monkeypatch.setattr(blocks, "multiply", lambda *a: met.append(1) or multiply(*a))
    assert find() == want and met


def test_tree_matches_children_by_feature(spark, monkeypatch):
    from tracelink.operators import sigtree

    q, d, _ = signatures(spark)
    place = q.select(F.col("fid").alias("pid")).union(d.select("fid")).distinct().select("pid", (F.col("pid") % 4).cast("double").alias("x"), F.expr("double(pid div 4)").alias("y"))
    tree = sigtree.build(d, place, 4)
    show = lambda df: rows(df.withColumn("s", F.round("sim", 9)), "qid", "oid", "rnk", "s")
    want = show(L.top_k(L.dot_pairs(q, d), 3))
    for joined in (1 << 40, 0):  # by node and feature, by the postings of whole levels
        counted = []
        monkeypatch.setattr(sigtree, "JOINED", joined, raising=False)
        monkeypatch.setattr(sigtree, "shared", lambda *a: counted.append(1) or 0, raising=False)
        for mbr, bound in ((True, True), (False, True), (True, False)):
            got = sigtree.knn_join(q, tree, 3, place, mbr, bound)
            assert show(got) == want
        assert bool(counted) == (not joined)


@pytest.mark.parametrize(("label", "place"), [("suppliers", "l_suppkey"), ("parts", "l_partkey")])
def test_visits_are_joined_once(spark, label, place):
    import __spark_entry__
    from tracelink.plans import workloads as K

    d = "/root/testdata/sf0.001"
    got = __spark_entry__.queries()[f"w_link_customers_{label}"](spark, d)
    assert not any("lineitem" in f for f in got.inputFiles())
    t = K.S.customers(K.S.read(spark, d, "orders"), K.S.read(spark, d, "lineitem"), place)
    assert rows(got, *got.columns) == rows(K.accuracy(t, K.link(t, 10)), *got.columns)
