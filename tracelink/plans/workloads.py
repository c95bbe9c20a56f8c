"""The experiments and operators as registered queries, each with its SQL twin where SQL can express it.

A query takes (spark, sf_dir). Traces are the planted habits over the events table unless named otherwise; m = 3 or 5 features stand for
the short signatures, since half a trace has about 33 points here.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import columns as C
from ..operators import linking as L
from ..operators import metrics as M
from ..operators import prepare as P
from ..operators import protect, refine, sigtree
from ..operators import reduce as R
from ..operators import spaces
from ..operators import weights as W
from ..session import materialise
from ..sources import traces as S
from . import sqltext as Q

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
KS = [1, 2, 3, 4, 5]
TIES = ["pid", "x", "y"]


def add(name: str, run: Query, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql is not None:
        ORACLES[name] = sql


def habit(spark: SparkSession, d: str) -> DataFrame:
    return S.habit(S.read(spark, d, "events"))


def split(spark: SparkSession, d: str) -> DataFrame:
    return P.interleaved(habit(spark, d))


def queries_of(trace: DataFrame) -> DataFrame:
    return trace.where("side = 'Q'").select(F.col("oid").alias("qid"))


def accuracy(trace: DataFrame, knn: DataFrame, ks: list[int] = KS) -> DataFrame:
    return M.acc_at(knn, queries_of(trace), ks)


def link(trace: DataFrame, m: int | None, k: int = 5, scheme: str = "tfidf") -> DataFrame:
    return L.inverted(*L.sides(W.spatial(trace, m, scheme)), k)


def shown(knn: DataFrame) -> DataFrame:
    return knn.select("qid", "oid", F.round("sim", 6).alias("sim"), "rnk")


SHOWN = "SELECT qid, oid, round(sim, 6) AS sim, rnk::INT AS rnk FROM "
SIG = "SELECT side, oid, fid, round(w, 6) AS w FROM "


def sized(m: int | None) -> str:
    return "full" if m is None else f"m{m}"


# --- preparation -------------------------------------------------------------------------------------------------------------------

add("p_assemble", lambda s, d: P.assemble(S.suppliers(S.read(s, d, "lineitem"), S.read(s, d, "part")), TIES).groupBy("oid").agg(F.max("seq").alias("points"), F.min_by("pid", "seq").alias("first_pid"), F.max_by("pid", "seq").alias("last_pid")),
    """WITH t AS (SELECT l_suppkey AS oid, l_shipdate AS t, l_partkey AS pid, p_size::DOUBLE AS x, p_retailprice AS y FROM lineitem JOIN part ON l_partkey = p_partkey),
    n AS (SELECT *, row_number() OVER (PARTITION BY oid ORDER BY t, pid, x, y) AS seq FROM t)
    SELECT oid, max(seq)::INT AS points, min_by(pid, seq) AS first_pid, max_by(pid, seq) AS last_pid FROM n GROUP BY oid""")  # fmt: skip
add("p_min_points", lambda s, d: P.min_points(habit(s, d), 68).groupBy("oid").agg(F.count(F.lit(1)).alias("points")),
    f"WITH {Q.HABIT} SELECT oid, count(*) AS points FROM habit GROUP BY oid HAVING count(*) >= 68")


def _snap(s: SparkSession, d: str) -> DataFrame:
    return P.snap(S.raw(S.read(s, d, "events")).select("oid", "t", "x", "y"), S.locations(habit(s, d)), 4.0).select("oid", "t", "x", "y", "pid", F.round("d2", 6).alias("d2"))


add("p_snap", _snap, f"""WITH {Q.HABIT}, {Q.RAW}, a AS (SELECT pid, min(x) AS ax, min(y) AS ay FROM habit GROUP BY pid),
    c AS (SELECT DISTINCT r.oid, r.t, r.x, r.y, a.pid, (x - ax) ** 2 + (y - ay) ** 2 AS d2 FROM raw r JOIN a ON abs(x - ax) <= 4 AND abs(y - ay) <= 4)
    SELECT oid, t, x, y, pid, round(d2, 6) AS d2 FROM (SELECT *, row_number() OVER (PARTITION BY oid, t, x, y ORDER BY d2, pid) AS r FROM c WHERE d2 <= 16) WHERE r = 1""")  # fmt: skip
GRID = "least({0} - 1, greatest(0, floor(x / (100.0 / {0}))::BIGINT)) * {0} + least({0} - 1, greatest(0, floor(y / (100.0 / {0}))::BIGINT))"
for r in (10, 100):
    add(f"p_grid_{r}", lambda s, d, r=r: P.to_grid(habit(s, d), r).groupBy("pid").agg(F.count(F.lit(1)).alias("points")),
        f"WITH {Q.HABIT} SELECT {GRID.format(r)} AS pid, count(*) AS points FROM habit GROUP BY 1")
BIN = "floor((hour(t) * 3600 + minute(t) * 60 + second(t)) / ({0} * 3600.0))::INT"
add("p_time_bin", lambda s, d: habit(s, d).groupBy(P.time_bin(F.col("t"), 2).alias("bin")).agg(F.count(F.lit(1)).alias("points")),
    f"WITH {Q.HABIT} SELECT {BIN.format(2)} AS bin, count(*) AS points FROM habit GROUP BY 1")
SAMPLE = "drawn AS (SELECT oid FROM (SELECT DISTINCT oid FROM {0}) ORDER BY " + Q.int_hash("oid", 0) + ", oid LIMIT {1})"
add("p_sample", lambda s, d: P.sample_objects(habit(s, d), 40).groupBy("oid").agg(F.count(F.lit(1)).alias("points")),
    f"WITH {Q.HABIT}, {SAMPLE.format('habit', 40)} SELECT oid, count(*) AS points FROM habit WHERE oid IN (SELECT oid FROM drawn) GROUP BY oid")

SPLITS: dict[str, tuple[Callable[[DataFrame], DataFrame], str]] = {
    "inter": (P.interleaved, Q.INTERLEAVED),
    "random": (P.random_days, f"dd AS (SELECT dy, row_number() OVER (ORDER BY {Q.int_hash('dy', 1)}, dy) AS r FROM (SELECT DISTINCT {Q.DAY} AS dy FROM habit)), split AS (SELECT h.*, CASE WHEN r <= 15 THEN 'Q' ELSE 'D' END AS side FROM habit h JOIN dd ON {Q.DAY} = dy)"),
    "serial": (P.serial, f"dd AS (SELECT dy, row_number() OVER (ORDER BY dy) AS r FROM (SELECT DISTINCT {Q.DAY} AS dy FROM habit)), split AS (SELECT h.*, CASE WHEN r <= 15 THEN 'Q' ELSE 'D' END AS side FROM habit h JOIN dd ON {Q.DAY} = dy)"),
    "weekend": (P.weekend, "split AS (SELECT *, CASE WHEN isodow(t) >= 6 THEN 'Q' ELSE 'D' END AS side FROM habit)"),
}
for name, (cutter, text) in SPLITS.items():
    add(f"p_split_{name}", lambda s, d, f=cutter: f(habit(s, d)).groupBy("side").agg(F.count(F.lit(1)).alias("points"), F.count_distinct(P.day(F.col("t"))).alias("days")),
        f"WITH {Q.HABIT}, {text} SELECT side, count(*) AS points, count(DISTINCT {Q.DAY}) AS days FROM split GROUP BY side")
    for m in (3, None):
        add(f"w_split_{name}_{sized(m)}", lambda s, d, f=cutter, m=m: accuracy(t := f(habit(s, d)), link(t, m)),
            f"WITH {Q.HABIT}, {text}, {Q.sig('split', 'sg', m)}, {Q.knn('sg', 5)} {Q.acc('knn')}")


def limited(n: int, both: bool, seed: int = 3, name: str = "split") -> str:
    keep = f"r <= {n}" + ("" if both else " OR side = 'D'")
    return f"""full_split AS (SELECT *, CASE WHEN {Q.DAY} % 2 = 0 THEN 'Q' ELSE 'D' END AS side FROM habit), lim AS (SELECT side, dy FROM (SELECT side, dy,
    row_number() OVER (PARTITION BY side ORDER BY {Q.int_hash('dy', seed)}, dy) AS r FROM (SELECT DISTINCT side, {Q.DAY} AS dy FROM full_split)) WHERE {keep}),
    {name} AS (SELECT f.* FROM full_split f JOIN lim ON f.side = lim.side AND {Q.DAY} = dy)"""


DRAWS = (3, 4, 5)


def _mean_days(s: SparkSession, d: str, n: int, both: bool) -> DataFrame:
    """Accuracy with n days, mean over several draws of the days; the draws are one plan."""
    parts = [accuracy(t := split(s, d), link(P.limit_days(t, n, ["Q", "D"] if both else ["Q"], seed), 3)) for seed in DRAWS]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out.groupBy("k").agg(F.count(F.lit(1)).alias("draws"), F.sum("hits").alias("hits"), F.round(F.sum("hits") / F.sum("queries"), 6).alias("acc"))


def mean_days(n: int, both: bool) -> str:
    parts = [f"{limited(n, both, seed, f'split{seed}').replace('full_split', f'full{seed}').replace('lim ', f'lim{seed} ').replace('lim.', f'lim{seed}.')}, {Q.sig(f'split{seed}', f'sg{seed}', 3)}, {Q.knn(f'sg{seed}', 5, f'knn{seed}')}, acc{seed} AS ({Q.acc(f'knn{seed}', f'full{seed}')})" for seed in DRAWS]
    every = " UNION ALL ".join(f"SELECT * FROM acc{seed}" for seed in DRAWS)
    return f"WITH {Q.HABIT}, {', '.join(parts)} SELECT k, count(*) AS draws, sum(hits)::BIGINT AS hits, round(sum(hits) / sum(queries), 6) AS acc FROM ({every}) GROUP BY k"


for n in range(1, 16):
    for label, both in (("query", False), ("both", True)):
        add(f"w_days_{label}_{n}", lambda s, d, n=n, both=both: accuracy(split(s, d), link(P.limit_days(split(s, d), n, ["Q", "D"] if both else ["Q"]), 3)),
            f"WITH {Q.HABIT}, {limited(n, both)}, {Q.sig('split', 'sg', 3)}, {Q.knn('sg', 5)} {Q.acc('knn', 'full_split')}")
        if n % 2:
            add(f"w_days_mean_{label}_{n}", lambda s, d, n=n, both=both: _mean_days(s, d, n, both), mean_days(n, both))
add("p_two_sources", lambda s, d: P.two_sources(habit(s, d), S.raw(S.read(s, d, "events"))).groupBy("side").agg(F.count(F.lit(1)).alias("points"), F.sum("pid").alias("pids")),
    f"WITH {Q.HABIT}, {Q.RAW} SELECT 'Q' AS side, count(*) AS points, sum(pid)::BIGINT AS pids FROM habit UNION ALL SELECT 'D', count(*), sum(pid)::BIGINT FROM raw")

# --- signatures --------------------------------------------------------------------------------------------------------------------

add("s_tf", lambda s, d: W.tf(W.counts(split(s, d))).select("side", "oid", "fid", F.round("tf", 6).alias("w")),
    f"WITH {Q.BASE}, {Q.sig('split', 'sg')} SELECT side, oid, fid, round(tf, 6) AS w FROM sg_t")
add("s_idf", lambda s, d: W.idf(W.counts(split(s, d))).select("side", "fid", F.round("idf", 6).alias("w")),
    f"WITH {Q.BASE}, {Q.sig('split', 'sg')} SELECT side, fid, round(ln(objects / df), 6) AS w FROM sg_f JOIN sg_o USING (side)")
for scope in ("own", "candidate", "union"):
    add(f"s_tfidf_{scope}", lambda s, d, c=scope: W.weigh(W.counts(split(s, d)), "tfidf", c).select("side", "oid", "fid", F.round("w", 6).alias("w")),
        f"WITH {Q.BASE}, {Q.sig('split', 'sg', scope=scope)} {SIG} sg")
add("r_cut", lambda s, d: W.spatial(split(s, d), 3).select("side", "oid", "fid", F.round("w", 6).alias("w")), f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3)} {SIG} sg")
GRAMS = """grams_{0} AS (SELECT side, oid, fid FROM (SELECT side, oid, {1} AS fid FROM split WINDOW w AS (PARTITION BY side, oid ORDER BY t, pid, x, y)) WHERE fid IS NOT NULL)"""


def grams(q: int) -> str:
    parts = ["pid::VARCHAR", *[f"lead(pid, {i}) OVER w::VARCHAR" for i in range(1, q)]]
    return GRAMS.format(q, " || '_' || ".join(f"({p})" for p in parts))


add("s_qgram2", lambda s, d: W.sequential(split(s, d), 2, ["t", *TIES]).select("side", "oid", "fid", F.round("w", 6).alias("w")), f"WITH {Q.BASE}, {grams(2)}, {Q.sig('grams_2', 'sg', feature='fid')} {SIG} sg")
for q in range(1, 6):
    add(f"w_repr_seq_q{q}", lambda s, d, q=q: accuracy(t := split(s, d), L.inverted(*L.sides(W.sequential(t, q, ["t", *TIES])), 5)),
        f"WITH {Q.BASE}, {grams(q)}, {Q.sig(f'grams_{q}', 'sg', feature='fid')}, {Q.knn('sg', 5)} {Q.acc('knn')}")
add("w_repr_spatial", lambda s, d: accuracy(t := split(s, d), link(t, None)), f"WITH {Q.BASE}, {Q.sig('split', 'sg')}, {Q.knn('sg', 5)} {Q.acc('knn')}")
for r in (10, 20, 50, 100, 200, 300):
    cells = f"cells AS (SELECT side, oid, ({GRID.format(r)}) * 24 + {BIN.format(1)} AS pid FROM split)"
    add(f"w_repr_st_{r}", lambda s, d, r=r: accuracy(t := split(s, d), L.inverted(*L.sides(W.spatiotemporal(t, r)), 5)),
        f"WITH {Q.BASE}, {cells}, {Q.sig('cells', 'sg')}, {Q.knn('sg', 5)} {Q.acc('knn')}")


def hist(hours: int) -> str:
    bins = 24 // hours
    return f"hist AS (SELECT side, oid, [{', '.join(f'count(*) FILTER ({BIN.format(hours)} = {b}) / count(*)' for b in range(bins))}] AS h FROM split GROUP BY side, oid)"


def emd(hours: int) -> str:
    bins = 24 // hours
    run = f"list_transform(range(1, {bins} + 1), lambda i: list_sum(list_transform(range(1, i + 1), lambda z: a[z] - b[z])))"
    return f"""hp AS (SELECT q.oid AS qid, d.oid AS oid, q.h AS a, d.h AS b FROM hist q, hist d WHERE q.side = 'Q' AND d.side = 'D'), hr AS (SELECT qid, oid, {run} AS run FROM hp),
    hm AS (SELECT qid, oid, run, (list_sort(run)[{(bins + 1) // 2}] + list_sort(run)[{bins // 2 + 1}]) / 2 AS mid FROM hr),
    hs AS (SELECT qid, oid, 1 - list_sum(list_transform(run, lambda v: abs(v - mid))) * {hours / 12.0} AS sim FROM hm)"""


for hours in (1, 2, 3, 4, 6, 8, 12):
    add(f"w_repr_temp_{hours}h", lambda s, d, h=hours: accuracy(t := split(s, d), L.histogram_knn(L.temporal(t, h), h, 5)),
        f"WITH {Q.BASE}, {hist(hours)}, {emd(hours)}, {Q.ranked('hs', 'knn', 5)} {Q.acc('knn')}")
    add(f"w_repr_temp_index_{hours}h", lambda s, d, h=hours: accuracy(t := split(s, d), L.histogram_index(L.temporal(t, h), h, 5)),
        f"WITH {Q.BASE}, {hist(hours)}, {emd(hours)}, {Q.ranked('hs', 'knn', 5)} {Q.acc('knn')}")
add("s_histogram", lambda s, d: L.temporal(split(s, d), 4).select("side", "oid", *[F.round(F.get("h", F.lit(i)), 6).alias(f"h{i}") for i in range(6)]),
    f"WITH {Q.BASE}, {hist(4)} SELECT side, oid, {', '.join(f'round(h[{i + 1}], 6) AS h{i}' for i in range(6))} FROM hist")
MEAN = "(list_sum({0}) / len({0}))"
HIST_SQL = {
    "intersection": "list_sum(list_transform(range(1, 7), lambda i: least(a[i], b[i])))",
    "chi2": "-list_sum(list_transform(range(1, 7), lambda i: CASE WHEN a[i] + b[i] > 0 THEN (a[i] - b[i]) ** 2 / (a[i] + b[i]) ELSE 0 END))",
    "bhattacharyya": "-sqrt(greatest(0, 1 - list_sum(list_transform(range(1, 7), lambda i: sqrt(a[i] * b[i])))))",
    "kl": "-list_sum(list_transform(range(1, 7), lambda i: (a[i] + 1e-6) * ln((a[i] + 1e-6) / (b[i] + 1e-6))))",
    "lp": "-sqrt(list_sum(list_transform(range(1, 7), lambda i: abs(a[i] - b[i]) ** 2)))",
    "correlation": f"""CASE WHEN list_sum(list_transform(a, lambda v: (v - {MEAN.format('a')}) ** 2)) > 0 AND list_sum(list_transform(b, lambda v: (v - {MEAN.format('b')}) ** 2)) > 0
      THEN list_sum(list_transform(range(1, 7), lambda i: (a[i] - {MEAN.format('a')}) * (b[i] - {MEAN.format('b')}))) / sqrt(list_sum(list_transform(a, lambda v: (v - {MEAN.format('a')}) ** 2)) * list_sum(list_transform(b, lambda v: (v - {MEAN.format('b')}) ** 2))) ELSE 0 END""",
}
for how, text in HIST_SQL.items():
    add(f"s_hist_{how}", lambda s, d, how=how: shown(L.histogram_knn(L.temporal(split(s, d), 4), 4, 1, how)).select("qid", "sim"),
        f"WITH {Q.BASE}, {hist(4)}, hs AS (SELECT q.oid AS qid, max({text.replace('a[', 'q.h[').replace('b[', 'd.h[').replace('(a,', '(q.h,').replace('(b,', '(d.h,').replace('(a)', '(q.h)').replace('(b)', '(d.h)')}) AS sim FROM hist q, hist d WHERE q.side = 'Q' AND d.side = 'D' GROUP BY q.oid) SELECT qid, round(sim, 6) AS sim FROM hs")
add("w_powerlaw", lambda s, d: W.weight_curve(W.spatial(split(s, d)), [1, 3, 5, 10, 20]),
    f"""WITH {Q.BASE}, {Q.sig('split', 'sg')}, pl AS (SELECT *, row_number() OVER (PARTITION BY side, oid ORDER BY round(w, 12) DESC, fid) AS r FROM sg),
    ps AS (SELECT side, oid, p.r AS r, sum(CASE WHEN pl.r <= p.r THEN w * w ELSE 0 END) / sum(w * w) AS s FROM pl, (VALUES (1), (3), (5), (10), (20)) p(r) GROUP BY ALL) SELECT r, round(avg(s), 6) AS share FROM ps GROUP BY r""")  # fmt: skip
add("s_cosine_pairs", lambda s, d: L.dot_pairs(*L.sides(W.spatial(split(s, d), 5))).select("qid", "oid", F.round("sim", 6).alias("sim")), f"WITH {Q.BASE}, {Q.sig('split', 'sg', 5)}, {Q.pairs('sg')} SELECT qid, oid, round(sim, 6) AS sim FROM pairs")

# --- ablation, reduction, size -----------------------------------------------------------------------------------------------------

for scheme in ("tf", "idf", "tfidf"):
    for m in (3, None):
        add(f"w_ablate_{scheme}_{sized(m)}", lambda s, d, c=scheme, m=m: accuracy(t := split(s, d), link(t, m, scheme=c)),
            f"WITH {Q.BASE}, {Q.sig('split', 'sg', m, scheme)}, {Q.knn('sg', 5)} {Q.acc('knn')}")
for m in (3, 5, 10, 50, None):
    add(f"w_reduce_cut_{sized(m)}", lambda s, d, m=m: accuracy(t := split(s, d), link(t, m)), f"WITH {Q.BASE}, {Q.sig('split', 'sg', m)}, {Q.knn('sg', 5)} {Q.acc('knn')}")
SIGN = "CASE WHEN (((((fid % 1000003 + 1) * (7919 + 104729 * (j + 1)) + 1299709 * (j + 1)) % 2147483647) * 48271) % 2147483647) % 1048576 < 524288 THEN 1.0 ELSE -1.0 END"


def bits(m: int) -> str:
    return f"""pj AS (SELECT side, oid, j, round(sum(w * {SIGN}), 9) >= 0 AS bit FROM sg, range(0, {m}) t(j) GROUP BY side, oid, j),
    bits AS (SELECT side, oid, list(bit::INT ORDER BY j) AS b FROM pj GROUP BY side, oid)"""


add("r_lsh_bits", lambda s, d: L.lsh_bits(W.spatial(split(s, d), 10), 32).select("side", "oid", F.array_join(F.transform("bits", lambda b: b.cast("string")), "").alias("bits")),
    f"WITH {Q.BASE}, {Q.sig('split', 'sg', 10)}, {bits(32)} SELECT side, oid, array_to_string(b, '') AS bits FROM bits")
for m in (16, 64, 128):
    add(f"w_reduce_lsh_m{m}", lambda s, d, m=m: accuracy(t := split(s, d), L.lsh_scan(L.lsh_bits(W.spatial(t), m), m, 5)),
        f"""WITH {Q.BASE}, {Q.sig('split', 'sg')}, {bits(m)}, hs AS (SELECT q.oid AS qid, d.oid AS oid, cos(pi() * list_sum(list_transform(range(1, {m} + 1), lambda i: abs(q.b[i] - d.b[i]))) / {m}) AS sim
        FROM bits q, bits d WHERE q.side = 'Q' AND d.side = 'D'), {Q.ranked('hs', 'knn', 5)} {Q.acc('knn')}""")  # fmt: skip
add("w_reduce_lsh_superbit_m64", lambda s, d: accuracy(t := split(s, d), L.lsh_scan(L.lsh_bits(W.spatial(t), 64, superbit=8), 64, 5)))
add("w_reduce_lsh_gauss_m64", lambda s, d: accuracy(t := split(s, d), L.lsh_scan(L.lsh_bits(W.spatial(t), 64, family="gauss"), 64, 5)))
for m in (3, 10, 50):
    add(f"w_reduce_pca_m{m}", lambda s, d, m=m: accuracy(t := split(s, d), R.projected_knn(R.pca(W.spatial(t), m), 5)))
add("w_reduce_pca_randomized_m10", lambda s, d: accuracy(t := split(s, d), R.projected_knn(R.pca(W.spatial(t), 10, "randomized"), 5)))
for share in (25, 50, 75, 100):
    n_sql = f"(SELECT count(DISTINCT oid) * {share} // 100 FROM habit)"

    def _sized(s: SparkSession, d: str, share: int = share) -> DataFrame:
        trace = habit(s, d)
        n = trace.select("oid").distinct().count() * share // 100
        kept = P.interleaved(P.sample_objects(trace, n))
        return accuracy(kept, link(kept, 3))

    add(f"w_size_{share}", _sized, f"WITH {Q.HABIT}, {SAMPLE.format('habit', n_sql)}, split AS (SELECT *, CASE WHEN {Q.DAY} % 2 = 0 THEN 'Q' ELSE 'D' END AS side FROM habit WHERE oid IN (SELECT oid FROM drawn)), {Q.sig('split', 'sg', 3)}, {Q.knn('sg', 5)} {Q.acc('knn')}")

# --- searches ----------------------------------------------------------------------------------------------------------------------


def sig_of(s: SparkSession, d: str, m: int | None = 3) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Trace, queries, candidates, places."""
    trace = split(s, d)
    sig = W.spatial(trace, m)
    return trace, *L.sides(sig), S.locations(trace)


KNN3 = f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3)}, {Q.knn('sg', 5)} "
add("w_link_inverted", lambda s, d: shown(L.inverted(*sig_of(s, d)[1:3], 5)), KNN3 + SHOWN + "knn")
add("w_link_linear", lambda s, d: shown(L.linear(*sig_of(s, d)[1:3], 5)), KNN3 + SHOWN + "knn")
add("w_link_euclid", lambda s, d: L.euclid(*sig_of(s, d)[1:3], 5).select("qid", "oid", F.round("dist", 6).alias("dist"), "rnk"), KNN3 + "SELECT qid, oid, round(sqrt(greatest(0.0, 2 - 2 * sim)), 6) AS dist, rnk::INT AS rnk FROM knn")
THETA = 0.4
for label, bound in (("allpairs", "maxweight"), ("apt", "minsize"), ("mmjoin", "length"), ("l2ap", "l2")):
    add(f"w_link_{label}", lambda s, d, b=bound: L.threshold(*sig_of(s, d, 10)[1:3], THETA, b).select("qid", "oid", F.round("sim", 6).alias("sim")),
        f"WITH {Q.BASE}, {Q.sig('split', 'sg', 10)}, {Q.pairs('sg')} SELECT qid, oid, round(sim, 6) AS sim FROM pairs WHERE round(sim, 9) >= {THETA}")


def _l2ap_knn(s: SparkSession, d: str) -> DataFrame:
    _, q, c, _ = sig_of(s, d)
    return shown(L.threshold_knn(q, c, 5, max(0.05, L.calibrate_theta(L.inverted(q, c, 5), 5))))


add("w_link_l2ap_knn", _l2ap_knn, KNN3 + SHOWN + "knn")


def _mbr(s: SparkSession, d: str) -> DataFrame:
    t, q, c, place = sig_of(s, d)
    return shown(L.mbr_range(q, c, L.boxes(W.spatial(t, 3), place), 5))


add("w_link_mbr", _mbr, KNN3 + SHOWN + "knn")
add("w_link_lsh", lambda s, d: accuracy(t := split(s, d), L.lsh(*L.sides(g := W.spatial(t, 3)), L.lsh_bits(g, 64), 16, 64, 5)))


def _tree(s: SparkSession, d: str, m: int = 3, k: int = 5, criterion: str = "common", mbr: bool = True, bound: bool = True, capacity: int = 16) -> DataFrame:
    _, q, c, place = sig_of(s, d, m)
    return sigtree.knn_join(q, sigtree.build(c, place, capacity, criterion), k, place, mbr, bound)


add("w_link_tree", lambda s, d: shown(_tree(s, d)), KNN3 + SHOWN + "knn")
add("w_link_tree_spatial", lambda s, d: shown(_tree(s, d, criterion="spatial")), KNN3 + SHOWN + "knn")
add("w_link_tree_no_mbr", lambda s, d: shown(_tree(s, d, mbr=False)), KNN3 + SHOWN + "knn")
add("w_link_rtree", lambda s, d: shown(_tree(s, d, criterion="spatial", bound=False)), KNN3 + SHOWN + "knn")
for m in (3, 5, 10):
    for k in KS:
        add(f"w_tree_m{m}_k{k}", lambda s, d, m=m, k=k: shown(_tree(s, d, m, k)), f"WITH {Q.BASE}, {Q.sig('split', 'sg', m)}, {Q.knn('sg', k)} {SHOWN} knn")


def _local(s: SparkSession, d: str) -> DataFrame:
    _, q, c, place = sig_of(s, d)
    return shown(sigtree.search_local(q, sigtree.build(c, place, 8), 5, place))


add("w_link_tree_local", _local, KNN3 + SHOWN + "knn")


def _auto(s: SparkSession, d: str) -> DataFrame:
    _, q, c, place = sig_of(s, d)
    return shown(sigtree.knn(q, sigtree.build(c, place), 5, place))


add("w_link_tree_auto", _auto, KNN3 + SHOWN + "knn")


def _customer_signatures(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Customers that visit parts, m = 10: signature relation, queries, candidates, places."""
    t = S.customers(S.read(s, d, "orders"), S.read(s, d, "lineitem"), "l_partkey")
    sig = W.spatial(t, 10)
    return sig, *L.sides(sig), S.locations(t)


CUSTOMER_KNN = f"WITH {Q.customers('l_partkey')}, {Q.sig('split', 'sg', 10)}, {Q.knn('sg', 1)} {SHOWN} knn"
CUSTOMER_SEARCHES: dict[str, Callable] = {
    "inverted": lambda sig, q, c, p: L.inverted(q, c, 1),
    "linear": lambda sig, q, c, p: L.linear(q, c, 1),
    "l2ap": lambda sig, q, c, p: L.threshold_knn(q, c, 1, 0.3),
    "mbr": lambda sig, q, c, p: L.mbr_range(q, c, L.boxes(sig, p), 1),
    "tree": lambda sig, q, c, p: sigtree.knn_join(q, sigtree.build(c, p, 16), 1, p),
}
for label, search in CUSTOMER_SEARCHES.items():
    add(f"w_link_customers_{label}_k1", lambda s, d, f=search: shown(f(*_customer_signatures(s, d))), CUSTOMER_KNN)


def _customers_linked(s: SparkSession, d: str, place: str) -> DataFrame:
    """Accuracy at m = 10; visits are joined and counted once for both sides' signatures and for the number of queries."""
    counted = materialise(W.counts(S.customers(S.read(s, d, "orders"), S.read(s, d, "lineitem"), place)), "visits")
    return accuracy(counted, L.inverted(*L.sides(W.cut(W.weigh(counted), 10)), 5))


for place, label in (("l_suppkey", "suppliers"), ("l_partkey", "parts")):
    add(f"w_link_customers_{label}", lambda s, d, p=place: _customers_linked(s, d, p),
        f"WITH {Q.customers(place)}, {Q.sig('split', 'sg', 10)}, {Q.knn('sg', 5)} {Q.acc('knn')}")
add("w_link_raw", lambda s, d: accuracy(t := P.interleaved(S.raw(S.read(s, d, "events"))), link(t, 10)),
    f"WITH {Q.RAW}, {Q.INTERLEAVED.replace('FROM habit', 'FROM raw')}, {Q.sig('split', 'sg', 10)}, {Q.knn('sg', 5)} {Q.acc('knn')}")
DOC = """words AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS w FROM documents),
    split AS (SELECT CASE WHEN i % 2 = 1 THEN 'Q' ELSE 'D' END AS side, doc_id AS oid, w[i] AS pid FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM words))"""
add("w_repr_second_documents", lambda s, d: accuracy(t := S.documents(S.read(s, d, "documents")), link(t, 10)), f"WITH {DOC}, {Q.sig('split', 'sg', 10)}, {Q.knn('sg', 5)} {Q.acc('knn')}")
CONV = """words AS (SELECT conv_id, role, list_filter(string_split_regex(lower(coalesce(text, '')), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS w FROM conversations),
    split AS (SELECT CASE WHEN role = 'user' THEN 'Q' ELSE 'D' END AS side, conv_id AS oid, unnest(w) AS pid FROM words)"""
add("w_repr_second_conversations", lambda s, d: accuracy(t := S.conversations(S.read(s, d, "conversations")), link(t, 10)), f"WITH {CONV}, {Q.sig('split', 'sg', 10)}, {Q.knn('sg', 5)} {Q.acc('knn')}")
PAGE = """parts AS (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, list_filter(string_split(regexp_extract(url, '^[a-z]+://[^/?#]+/([^?#]*)', 1), '/'), lambda w: w <> '') AS w FROM pages),
    split AS (SELECT CASE WHEN page_id % 2 = 1 THEN 'Q' ELSE 'D' END AS side, host AS oid, unnest(w) AS pid FROM parts)"""
add("w_repr_second_hosts", lambda s, d: accuracy(t := S.pages(S.read(s, d, "pages")), link(t, 10)), f"WITH {PAGE}, {Q.sig('split', 'sg', 10)}, {Q.knn('sg', 5)} {Q.acc('knn')}")


SUPPLIERS = f"""supp AS (SELECT l_suppkey AS oid, l_shipdate AS t, l_partkey AS pid, p_size::DOUBLE AS x, p_retailprice AS y FROM lineitem JOIN part ON l_partkey = p_partkey)"""
SUPP_SPLIT = f"split AS (SELECT *, CASE WHEN {Q.DAY} % 2 = 0 THEN 'Q' ELSE 'D' END AS side FROM supp)"


def supplier_trace(s: SparkSession, d: str) -> DataFrame:
    return S.suppliers(S.read(s, d, "lineitem"), S.read(s, d, "part"))


#: Times are midnights there, so a time bin tells nothing; the extent of places is fixed (sizes 1 to 50, prices 900 to 2100).
SUPP_GRID = "least({0} - 1, greatest(0, floor((x - 1.0) / (49.0 / {0}))::BIGINT)) * {0} + least({0} - 1, greatest(0, floor((y - 900.0) / (1200.0 / {0}))::BIGINT))"
SUPP_BOX = (1.0, 900.0, 50.0, 2100.0)
for m in (10, None):
    add(f"w_repr_suppliers_spatial_{sized(m)}", lambda s, d, m=m: accuracy(t := P.interleaved(supplier_trace(s, d)), link(t, m)),
        f"WITH {SUPPLIERS}, {SUPP_SPLIT}, {Q.sig('split', 'sg', m)}, {Q.knn('sg', 5)} {Q.acc('knn')}")
for q in range(1, 6):
    add(f"w_repr_suppliers_seq_q{q}", lambda s, d, q=q: accuracy(t := P.interleaved(supplier_trace(s, d)), L.inverted(*L.sides(W.sequential(t, q, ["t", *TIES])), 5)),
        f"WITH {SUPPLIERS}, {SUPP_SPLIT}, {grams(q)}, {Q.sig(f'grams_{q}', 'sg', feature='fid')}, {Q.knn('sg', 5)} {Q.acc('knn')}")
for r in (100, 200, 300):
    cells = f"cells AS (SELECT side, oid, {SUPP_GRID.format(r)} AS pid FROM split)"
    add(f"w_repr_suppliers_grid_{r}", lambda s, d, r=r: accuracy(t := P.interleaved(supplier_trace(s, d)), link(P.to_grid(t, r, SUPP_BOX), None)),
        f"WITH {SUPPLIERS}, {SUPP_SPLIT}, {cells}, {Q.sig('cells', 'sg')}, {Q.knn('sg', 5)} {Q.acc('knn')}")
DOC_GRAMS = """grams_{0} AS (SELECT side, oid, {1} AS fid FROM (SELECT CASE WHEN i % 2 = 1 THEN 'Q' ELSE 'D' END AS side, doc_id AS oid, i, w[i] AS pid FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM words)) WINDOW v AS (PARTITION BY side, oid ORDER BY i))"""
for q in range(2, 6):
    parts = " || '_' || ".join(["pid", *[f"lead(pid, {i}) OVER v" for i in range(1, q)]])
    add(f"w_repr_second_documents_q{q}", lambda s, d, q=q: accuracy(t := S.documents(S.read(s, d, "documents")), L.inverted(*L.sides(W.sequential(t, q, ["seq"])), 5)),
        f"WITH {DOC}, {DOC_GRAMS.format(q, parts)}, {Q.sig(f'grams_{q}', 'sg', feature='fid')}, {Q.knn('sg', 5)} {Q.acc('knn')}")
for n in (3000, 6000, 9000, 12000):
    for place, label in (("l_suppkey", "suppliers"), ("l_partkey", "parts")):
        add(f"w_size_customers_{label}_{n}", lambda s, d, n=n, p=place: accuracy(t := S.customers(S.read(s, d, "orders"), S.read(s, d, "lineitem"), p, n), link(t, 10)),
            f"WITH {Q.customers(place)[:-1]} AND o_custkey < {n}), {Q.sig('split', 'sg', 10)}, {Q.knn('sg', 5)} {Q.acc('knn')}")
CURVE = "ps AS (SELECT side, oid, p.r AS r, sum(CASE WHEN pl.r <= p.r THEN w * w ELSE 0 END) / sum(w * w) AS s FROM pl, (VALUES (1), (3), (5), (10), (20)) p(r) GROUP BY ALL) SELECT r, round(avg(s), 6) AS share FROM ps GROUP BY r"
RANKED = "pl AS (SELECT *, row_number() OVER (PARTITION BY side, oid ORDER BY round(w, 12) DESC, fid) AS r FROM sg)"
for label, run, text in (
    ("suppliers", lambda s, d: P.interleaved(supplier_trace(s, d)), f"{SUPPLIERS}, {SUPP_SPLIT}"),
    ("customers", lambda s, d: S.customers(S.read(s, d, "orders"), S.read(s, d, "lineitem"), "l_partkey"), Q.customers("l_partkey")),
    ("documents", lambda s, d: S.documents(S.read(s, d, "documents")), DOC),
    ("raw", lambda s, d: P.interleaved(S.raw(S.read(s, d, "events"))), f"{Q.RAW}, {Q.INTERLEAVED.replace('FROM habit', 'FROM raw')}"),
):
    add(f"w_powerlaw_{label}", lambda s, d, run=run: W.weight_curve(W.spatial(run(s, d)), [1, 3, 5, 10, 20]), f"WITH {text}, {Q.sig('split', 'sg')}, {RANKED}, {CURVE}")


def _accounts(s: SparkSession, d: str) -> DataFrame:
    """Two ids of one person: benchmark items against documents by word 5-grams."""
    words = lambda c: F.filter(F.split(F.coalesce(c, F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    def grams_of(df: DataFrame, key: str, side: str) -> DataFrame:
        w = df.select(F.lit(side).alias("side"), F.col(key).alias("oid"), words(F.col("text")).alias("w")).where(F.size("w") >= 5)
        return w.select("side", "oid", F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.array_join(F.slice("w", i, 5), " "))).alias("pid"))
    trace = grams_of(S.read(s, d, "benchmark"), "item_id", "Q").union(grams_of(S.read(s, d, "documents"), "doc_id", "D"))
    return shown(L.inverted(*L.sides(W.weigh(W.counts(trace))), 3))


ACC = """bw AS (SELECT 'Q' AS side, item_id AS oid, list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS w FROM benchmark
    UNION ALL SELECT 'D', doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') FROM documents),
    split AS (SELECT side, oid, array_to_string(w[i:i+4], ' ') AS pid FROM (SELECT side, oid, w, unnest(range(1, len(w) - 3)) AS i FROM bw WHERE len(w) >= 5))"""
add("w_scenario_accounts", _accounts, f"WITH {ACC}, {Q.sig('split', 'sg')}, {Q.knn('sg', 3)} {SHOWN} knn")

# --- dense vectors -----------------------------------------------------------------------------------------------------------------

DENSE = """u AS (SELECT vec_id AS id, list_transform(embedding, lambda x: x::DOUBLE / sqrt(list_sum(list_transform(embedding, lambda z: z::DOUBLE * z::DOUBLE)))) AS v FROM embeddings),
    dp AS (SELECT a.id AS qid, b.id AS oid, list_dot_product(a.v, b.v) AS sim FROM u a, u b WHERE a.id <> b.id)"""
DENSE_SQL = f"WITH {DENSE}, {Q.ranked('dp', 'knn', 3)} SELECT qid, oid, round(sim, 5) AS sim, rnk::INT AS rnk FROM knn"
dense_shown = lambda df: df.select("qid", "oid", F.round("sim", 5).alias("sim"), "rnk")
add("b_dense_linear", lambda s, d: dense_shown(L.dense_knn(S.read(s, d, "embeddings"), 3)), DENSE_SQL)
for kind in ("kdtree", "rtree", "hbtree"):
    add(f"b_{kind}", lambda s, d, kind=kind: dense_shown(spaces.knn(S.read(s, d, "embeddings"), 3, kind)), DENSE_SQL)



def _labels(knn: DataFrame, vectors: DataFrame) -> DataFrame:
    """Vectors whose nearest neighbour has their label."""
    label = vectors.select(F.col("vec_id").alias("v_id"), "label")
    one = knn.where("rnk = 1").join(label, F.col("qid") == F.col("v_id")).select("oid", F.col("label").alias("own"))
    one = one.join(label, F.col("oid") == F.col("v_id"))
    return one.agg(F.count(F.lit(1)).alias("vectors"), F.count(F.when(F.col("own") == F.col("label"), 1)).alias("same_label"))


add("w_reduce_embeddings_full", lambda s, d: _labels(spaces.knn(v := S.read(s, d, "embeddings"), 1), v), f"""WITH {DENSE}, {Q.ranked('dp', 'knn', 1)}
    SELECT count(*) AS vectors, count(*) FILTER (a.label = b.label) AS same_label FROM knn JOIN embeddings a ON a.vec_id = qid JOIN embeddings b ON b.vec_id = oid""")  # fmt: skip
for m in (5, 10, 50):
    add(f"w_reduce_embeddings_pca_m{m}", lambda s, d, m=m: _labels(spaces.knn(R.pca_dense(v := S.read(s, d, "embeddings"), m), 1, id_column="id", column="v"), v))


def _dense_bits(s: SparkSession, d: str, m: int) -> DataFrame:
    """Nearest neighbours of embeddings by the Hamming distance of m hashed signs, over all vectors."""
    vectors = S.read(s, d, "embeddings")
    rows = L.unit_vectors(vectors).select(F.explode(F.array(F.lit("Q"), F.lit("D"))).alias("side"), F.col("id").alias("oid"), F.posexplode("v").alias("fid", "w"))
    pairs = L.lsh_scan(L.lsh_bits(rows, m), m, 2)
    return _labels(L.top_k(pairs.where("qid <> oid"), 1), vectors)


for m in (16, 64):
    add(f"w_reduce_embeddings_lsh_m{m}", lambda s, d, m=m: _dense_bits(s, d, m))

# --- tree parts --------------------------------------------------------------------------------------------------------------------

BOXES = f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3)}, {Q.boxes('sg', 'split')} "
add("x_boxes", lambda s, d: L.boxes(W.spatial(t := split(s, d), 3), S.locations(t)), BOXES + "SELECT side, oid, x1, y1, x2, y2 FROM box")
for m in (3, 5, 10, None):
    add(f"w_shrink_{sized(m)}", lambda s, d, m=m: L.overlap_ratio(L.boxes(W.spatial(t := split(s, d), m), S.locations(t))),
        f"""WITH {Q.BASE}, {Q.sig('split', 'sg', m)}, {Q.boxes('sg', 'split')}, o AS (SELECT count(*) FILTER (q.x1 <= d.x2 AND d.x1 <= q.x2 AND q.y1 <= d.y2 AND d.y1 <= q.y2) AS overlapping, count(*) AS pairs
        FROM box q, box d WHERE q.side = 'Q' AND d.side = 'D') SELECT overlapping, pairs, round(overlapping / pairs, 6) AS ratio FROM o""")  # fmt: skip


def _disjoint(s: SparkSession, d: str) -> DataFrame:
    """Pairs of positive similarity, and those of them whose boxes do not meet (there must be none)."""
    t, q, c, place = sig_of(s, d, 5)
    pairs = L.dot_pairs(q, c)
    met = L.overlapping(L.boxes(W.spatial(t, 5), place)).withColumn("met", F.lit(1))
    return pairs.join(met, ["qid", "oid"], "left").agg(F.count(F.lit(1)).alias("pairs"), F.count(F.when(F.col("met").isNull(), 1)).alias("violations"))


add("x_prune_mbr", _disjoint, f"""WITH {Q.BASE}, {Q.sig('split', 'sg', 5)}, {Q.boxes('sg', 'split')}, {Q.pairs('sg')}
    SELECT count(*) AS pairs, count(*) FILTER (NOT (q.x1 <= d.x2 AND d.x1 <= q.x2 AND q.y1 <= d.y2 AND d.y1 <= q.y2)) AS violations
    FROM pairs p JOIN box q ON q.side = 'Q' AND q.oid = p.qid JOIN box d ON d.side = 'D' AND d.oid = p.oid""")  # fmt: skip


def _bound(s: SparkSession, d: str) -> DataFrame:
    """Pairs of a query and a node that has a member alike, the nodes' bounds, and those below a member's similarity (there must be none)."""
    _, q, c, place = sig_of(s, d, 5)
    lv = sigtree.build(c, place, 8, "spatial").levels[1]
    bounds = L.dot_pairs(q, lv.sigs.select(F.col("nid").alias("oid"), "fid", F.col("w").alias("wd"))).select("qid", F.col("oid").alias("nid"), F.col("sim").alias("bound"))
    members = L.dot_pairs(q, c).join(lv.members.select("nid", F.col("child").alias("oid")), "oid").groupBy("qid", "nid").agg(F.max("sim").alias("best"))
    out = members.join(bounds, ["qid", "nid"], "left")
    return out.agg(F.count(F.lit(1)).alias("visits"), F.round(F.sum("bound"), 6).alias("bounds"), F.round(F.sum("best"), 6).alias("best"), F.count(F.when(F.coalesce("bound", F.lit(0.0)) < F.col("best") - 1e-9, 1)).alias("violations"))


def _leaves(s: SparkSession, d: str, criterion: str) -> sigtree.Tree:
    _, _, c, place = sig_of(s, d)
    return sigtree.build(c, place, 8, criterion)


STR = f"""{BOXES}, b AS (SELECT oid, (x1 + x2) / 2 AS cx, (y1 + y2) / 2 AS cy FROM box WHERE side = 'D'), n AS (SELECT count(*) AS n FROM b),
    z AS (SELECT greatest(8, ceil(n / sqrt(ceil(n / 8.0))))::BIGINT AS slab FROM n), r AS (SELECT *, row_number() OVER (ORDER BY cx, cy, oid) - 1 AS r FROM b),
    y AS (SELECT *, r // slab AS sl FROM r, z), o AS (SELECT *, row_number() OVER (PARTITION BY sl ORDER BY cy, cx, oid) - 1 AS s FROM y)
    SELECT sl * ceil(slab / 8.0)::BIGINT + s // 8 AS nid, oid AS child FROM o"""
STR5 = STR.replace(BOXES, f"WITH {Q.BASE}, {Q.sig('split', 'sg', 5)}, {Q.boxes('sg', 'split')} ")
add("x_prune_bound", _bound, f"""WITH st AS MATERIALIZED ({STR5}), {Q.BASE}, {Q.sig('split', 'sg', 5)}, {Q.pairs('sg')}, ag AS (SELECT nid, fid, max(w) AS w FROM st JOIN sg ON side = 'D' AND oid = child GROUP BY nid, fid),
    b AS (SELECT q.oid AS qid, nid, sum(q.w * ag.w) AS bound FROM sg q JOIN ag USING (fid) WHERE q.side = 'Q' GROUP BY q.oid, nid), m AS (SELECT qid, nid, max(sim) AS best FROM pairs JOIN st ON oid = child GROUP BY qid, nid)
    SELECT count(*) AS visits, round(sum(bound), 6) AS bounds, round(sum(best), 6) AS best, count(*) FILTER (coalesce(bound, 0) < best - 1e-9) AS violations FROM m LEFT JOIN b USING (qid, nid)""")  # fmt: skip
add("x_str_leaves", lambda s, d: _leaves(s, d, "spatial").levels[1].members, STR)
add("x_aggregate", lambda s, d: _leaves(s, d, "spatial").levels[1].sigs.select("nid", "fid", F.round("w", 6).alias("w")),
    f"WITH st AS ({STR}), ag AS ({BOXES} SELECT * FROM sg WHERE side = 'D') SELECT st.nid, ag.fid, round(max(ag.w), 6) AS w FROM st JOIN ag ON st.child = ag.oid GROUP BY st.nid, ag.fid")
for criterion in ("spatial", "common"):
    add(f"w_tree_build_{criterion}", lambda s, d, c=criterion: sigtree.size(_leaves(s, d, c)))
add("x_tree_sizes", lambda s, d: sigtree.size(_leaves(s, d, "spatial")).where("level <= 1"),
    f"""WITH st AS ({STR}), ag AS ({BOXES} SELECT * FROM sg WHERE side = 'D') SELECT 0 AS level, count(DISTINCT oid) AS nodes, count(*) AS entries FROM ag
    UNION ALL SELECT 1, count(DISTINCT nid), count(DISTINCT (nid, fid)) FROM st JOIN ag ON child = oid""")  # fmt: skip


def _grown_locally(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, sigtree.LocalNode]:
    """Queries, places, and a tree grown one object at a time on the driver (refused beyond a bound of entries)."""
    _, q, c, place = sig_of(s, d)
    return q, place, sigtree.build_by_insert(sigtree.objects_of(c, place), 16)


add("w_tree_build_insert", lambda s, d: s.createDataFrame(sigtree.local_size(_grown_locally(s, d)[2]), "level int, nodes long, entries long"))
add("w_link_tree_insert", lambda s, d: shown(sigtree.search_local(*(x := _grown_locally(s, d))[:1], x[2], 5, x[1])), KNN3 + SHOWN + "knn")


def _work(s: SparkSession, d: str, how: str) -> DataFrame:
    """Mean work of a query in best-first search: nodes taken from the queue, children scored, cut by box, cut by bound."""
    _, q, c, place = sig_of(s, d)
    tree = sigtree.build_by_insert(sigtree.objects_of(c, place), 16) if how == "insert" else sigtree.build(c, place, 16, how)
    kinds = ["popped", "scored", "cut_by_box", "cut_by_bound"]
    one = sigtree.search_local(q, tree, 1, place).groupBy("qid").agg(*[F.max(x).alias(x) for x in kinds])
    return one.agg(F.count(F.lit(1)).alias("queries"), *[F.round(F.avg(x), 3).alias(x) for x in kinds])


for how in ("spatial", "common", "insert"):
    add(f"w_work_{how}", lambda s, d, how=how: _work(s, d, how))


def _frontier(s: SparkSession, d: str, mbr: bool, bound: bool) -> DataFrame:
    """Rows that stay at each level of the batch search."""
    _, q, c, place = sig_of(s, d)
    work: list = []
    sigtree.knn_join(q, sigtree.build(c, place, 16), 5, place, mbr, bound, work)
    return s.createDataFrame(work, "level int, rows long")


for label, mbr, bound in (("both", True, True), ("box", True, False), ("bound", False, True)):
    add(f"w_frontier_{label}", lambda s, d, a=mbr, b=bound: _frontier(s, d, a, b))


STEPS = 6


def _grown(s: SparkSession, d: str, criterion: str, overflow: str = "grow", growth: float | None = None) -> DataFrame:
    """Build on three quarters of the objects, insert the rest in six steps (rebuild a degraded tree if asked), search."""
    _, q, c, place = sig_of(s, d)
    h = P.int_hash(F.col("oid"), 9) % (4 * STEPS)
    tree = sigtree.build(c.where(h >= STEPS), place, 16, "common" if criterion == "common" else "spatial")
    for part in range(STEPS):
        tree = sigtree.insert(tree, c.where(h == part), place, criterion, overflow)
        if growth is not None:
            tree = sigtree.maintain(tree, place, growth)
    return shown(sigtree.knn_join(q, tree, 5, place))


for criterion in ("spatial", "common"):
    add(f"w_tree_update_{criterion}", lambda s, d, c=criterion: _grown(s, d, c), KNN3 + SHOWN + "knn")
add("w_tree_update_split", lambda s, d: _grown(s, d, "common", "split"), KNN3 + SHOWN + "knn")
add("w_tree_update_rebuilt", lambda s, d: _grown(s, d, "common", growth=1.25), KNN3 + SHOWN + "knn")

# --- refinement --------------------------------------------------------------------------------------------------------------------


def _lists(s: SparkSession, d: str, k: int = 5) -> tuple[DataFrame, DataFrame, DataFrame]:
    t = split(s, d)
    q, c = L.sides(W.spatial(t, 3))
    back = L.top_k(L.dot_pairs(q, c).select(F.col("oid").alias("qid"), F.col("qid").alias("oid"), "sim"), k)
    return t, L.inverted(q, c, k), back


BACK = Q.ranked("(SELECT oid AS qid, qid AS oid, sim FROM knn_p)", "knn_back", 5)
for m in (5, 10, None):
    add(f"w_rr_{sized(m)}", lambda s, d, m=m: accuracy((x := _lists(s, d))[0], refine.rerank(x[1], *L.sides(W.spatial(x[0], m)))),
        f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3)}, {Q.knn('sg', 5)}, {Q.sig('split', 'lg', m)}, {Q.rerank('knn', 'lg', 'rr')} {Q.acc('rr')}")


def _sm(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    t, mine, theirs = _lists(s, d)
    return t, mine, refine.stable_match(refine.both_lists(mine, theirs), mine)


SM = f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3)}, {Q.knn('sg', 5)}, {BACK}, {Q.edges('knn', 'knn_back', 'ed')}, {Q.match('ed', 'knn', 'mt')}"
add("w_sm_pairs", lambda s, d: _sm(s, d)[2].select("qid", "oid", F.round("sim", 6).alias("sim"), "stage"), SM + " SELECT qid, oid, round(sim, 6) AS sim, stage FROM mt")
add("w_sm", lambda s, d: accuracy((x := _sm(s, d))[0], refine.match_ranking(x[1], x[2])), f"{SM}, {Q.match_ranking('knn', 'mt', 'mr')} {Q.acc('mr')}")


def _rr_sm(s: SparkSession, d: str, m: int | None) -> DataFrame:
    t, mine, theirs = _lists(s, d)
    q, c = L.sides(W.spatial(t, m))
    mine = refine.rerank(mine, q, c)
    theirs = refine.rerank(theirs.select(F.col("oid").alias("qid"), F.col("qid").alias("oid")), q, c).select(F.col("oid").alias("qid"), F.col("qid").alias("oid"), "sim")
    match = refine.stable_match(refine.both_lists(mine, theirs), mine)
    return accuracy(t, refine.match_ranking(mine, match))


for m in (5, 10, None):
    rr_sm = f"""WITH {Q.BASE}, {Q.sig('split', 'sg', 3)}, {Q.knn('sg', 5)}, {BACK}, {Q.sig('split', 'lg', m)}, {Q.rerank('knn', 'lg', 'rr')},
    turned AS (SELECT oid AS qid, qid AS oid FROM knn_back), {Q.rerank('turned', 'lg', 'rb')}, back AS (SELECT oid AS qid, qid AS oid, sim FROM rb),
    {Q.edges('rr', 'back', 'ed')}, {Q.match('ed', 'rr', 'mt')}, {Q.match_ranking('rr', 'mt', 'mr')} {Q.acc('mr')}"""
    add(f"w_rr_sm_{sized(m)}", lambda s, d, m=m: _rr_sm(s, d, m), rr_sm)


def _full_marriage(s: SparkSession, d: str) -> DataFrame:
    q, c = L.sides(W.spatial(split(s, d), 3))
    return refine.stable_match(L.dot_pairs(q, c), leftover="none").select("qid", "oid", F.round("sim", 6).alias("sim"))


add("w_sm_full_lists", _full_marriage, f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3)}, {Q.pairs('sg')}, {Q.ranked('pairs', 'knn', 1)}, {Q.match('pairs', 'knn', 'mt', 20)} SELECT qid, oid, round(sim, 6) AS sim FROM mt_all")
add("w_sm_ranked", lambda s, d: refine.ranked_match(*_lists(s, d)[1:]).groupBy("stage").agg(F.count(F.lit(1)).alias("pairs")))

# --- linkability -------------------------------------------------------------------------------------------------------------------


def closed(rounds: int, m: int = 3, source: str = Q.HABIT, first: str = "habit") -> str:
    """Traces t0 .. t<rounds> of the suppression."""
    parts = [source, f"t0 AS (SELECT * FROM {first})"]
    for i in range(rounds):
        parts.append(Q.sig(f"(SELECT 'A' AS side, * FROM t{i})", f"c{i}").replace(f"c{i} AS (SELECT * FROM c{i}_u)", f"c{i} AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY side, oid ORDER BY round(w, 12) DESC, fid) AS rr FROM c{i}_u) WHERE rr <= {m})"))
        parts.append(f"t{i + 1} AS MATERIALIZED (SELECT * FROM t{i} t WHERE NOT EXISTS (SELECT 1 FROM c{i} c WHERE c.oid = t.oid AND c.fid = t.pid))")
    return "WITH " + ", ".join(parts)


def _round(whole: DataFrame, r: int, m: int = 3, cells: tuple[float, float] = (10.0, 2.0)) -> DataFrame:
    """Accuracy before the r-th removal and utility after it."""
    before, after = protect.closure(whole, m, r)[-1]
    sides = P.interleaved(before)
    hits = accuracy(P.interleaved(whole), link(sides, m), [1]).select(F.col("hits").alias("hits_at_1"))
    cover = [M.grid_coverage(whole, after, c).withColumnRenamed("coverage", n) for c, n in zip(cells, ("coverage_large", "coverage_small"), strict=True)]
    out = hits
    for p in (M.data_remaining(whole, after), M.mbr_retained(whole, after), *cover):
        out = out.crossJoin(p)  # single rows
    return out


def utility(r: int, m: int = 3, cells: tuple[float, float] = (10.0, 2.0), source: str = Q.HABIT, first: str = "habit") -> str:
    grid = lambda t, c: f"(SELECT oid, count(DISTINCT (floor(x / {c}), floor(y / {c}))) AS n FROM {t} GROUP BY oid)"
    cover = lambda c: f"(SELECT round(avg(coalesce(b.n, 0) / a.n), 6) FROM {grid('t0', c)} a LEFT JOIN {grid(f't{r}', c)} b USING (oid))"
    area = lambda t: f"(SELECT oid, (max(x) - min(x)) * (max(y) - min(y)) AS a FROM {t} GROUP BY oid)"
    return f"""{closed(r, m, source, first)}, split AS (SELECT *, CASE WHEN {Q.DAY} % 2 = 0 THEN 'Q' ELSE 'D' END AS side FROM t{r - 1}), {Q.sig('split', 'sg', m)}, {Q.knn('sg', 5)}
    SELECT (SELECT count(*) FROM knn WHERE qid = oid AND rnk = 1) AS hits_at_1,
    (SELECT round(avg(coalesce(b.n, 0) / a.n), 6) FROM (SELECT oid, count(*) AS n FROM t0 GROUP BY oid) a LEFT JOIN (SELECT oid, count(*) AS n FROM t{r} GROUP BY oid) b USING (oid)) AS data_remaining,
    (SELECT round(avg(CASE WHEN b.a IS NULL THEN 0 WHEN a.a = 0 THEN 1 ELSE b.a / a.a END), 6) FROM {area('t0')} a LEFT JOIN {area(f't{r}')} b USING (oid)) AS mbr_overlap,
    {cover(cells[0])} AS coverage_large, {cover(cells[1])} AS coverage_small"""


def _repaired(t: DataFrame, m: int, longer: int | None) -> DataFrame:
    """Ranking after re-ranking by longer signatures and matching over the lists of both sides."""
    q, c = L.sides(W.spatial(t, m))
    pairs = L.dot_pairs(q, c)
    long_q, long_c = L.sides(W.spatial(t, longer))
    mine = refine.rerank(L.top_k(pairs, 5), long_q, long_c)
    theirs = L.top_k(pairs.select(F.col("oid").alias("qid"), F.col("qid").alias("oid"), "sim"), 5)
    theirs = refine.rerank(theirs.select(F.col("oid").alias("qid"), F.col("qid").alias("oid")), long_q, long_c).select(F.col("oid").alias("qid"), F.col("qid").alias("oid"), "sim")
    return refine.match_ranking(mine, refine.stable_match(refine.both_lists(mine, theirs), mine))


def _best5(whole: DataFrame, r: int, m: int = 3) -> DataFrame:
    """Acc@1..5 after re-ranking and matching, on the traces that the r-th round begins with."""
    t = P.interleaved(protect.closure(whole, m, r - 1)[-1][1] if r > 1 else whole)
    return accuracy(P.interleaved(whole), _repaired(t, m, None))


def best5(r: int, m: int = 3, source: str = Q.HABIT, first: str = "habit") -> str:
    return f"""{closed(r - 1, m, source, first)}, whole AS (SELECT *, CASE WHEN {Q.DAY} % 2 = 0 THEN 'Q' ELSE 'D' END AS side FROM t0), split AS (SELECT *, CASE WHEN {Q.DAY} % 2 = 0 THEN 'Q' ELSE 'D' END AS side FROM t{r - 1}),
    {Q.sig('split', 'sg', m)}, {Q.knn('sg', 5)}, {BACK}, {Q.sig('split', 'lg')}, {Q.rerank('knn', 'lg', 'rr')},
    turned AS (SELECT oid AS qid, qid AS oid FROM knn_back), {Q.rerank('turned', 'lg', 'rb')}, back AS (SELECT oid AS qid, qid AS oid, sim FROM rb),
    {Q.edges('rr', 'back', 'ed')}, {Q.match('ed', 'rr', 'mt', 20)}, {Q.match_ranking('rr', 'mt', 'mr')} {Q.acc('mr', 'whole')}"""


for r in range(1, 6):
    add(f"w_closure_r{r}", lambda s, d, r=r: _round(habit(s, d), r), utility(r))
    add(f"w_closure_m10_r{r}", lambda s, d, r=r: _round(habit(s, d), r, 10), utility(r, 10))
    add(f"w_closure_suppliers_r{r}", lambda s, d, r=r: _round(supplier_trace(s, d), r, 10, (10.0, 2.0)), utility(r, 10, (10.0, 2.0), SUPPLIERS, "supp"))
    add(f"w_closure_best5_r{r}", lambda s, d, r=r: _best5(habit(s, d), r), best5(r))


def _half(s: SparkSession, d: str) -> DataFrame:
    """One round in which each half of a trace loses its own signature."""
    trace = habit(s, d)
    return M.data_remaining(trace, protect.closure(trace, 3, 1, "half")[-1][1])


add("w_closure_half", _half, f"""WITH {Q.BASE}, {Q.sig('split', 'sg')}, hv AS (SELECT DISTINCT oid, fid FROM (SELECT *, row_number() OVER (PARTITION BY side, oid ORDER BY round(w, 12) DESC, fid) AS rr FROM sg) WHERE rr <= 3),
    k AS (SELECT oid, count(*) AS n FROM habit h WHERE NOT EXISTS (SELECT 1 FROM hv WHERE hv.oid = h.oid AND hv.fid = h.pid) GROUP BY oid)
    SELECT round(avg(coalesce(k.n, 0) / a.n), 6) AS data_remaining FROM (SELECT oid, count(*) AS n FROM habit GROUP BY oid) a LEFT JOIN k USING (oid)""")  # fmt: skip
UNICITY = """i AS (SELECT c.side, c.oid, avg(ln(objects / df)) AS mi, max((df = 1)::INT) AS alone FROM sg_c c JOIN sg_f USING (side, fid) JOIN sg_o USING (side) GROUP BY c.side, c.oid)
    SELECT round(avg(mi), 6) AS mean_idf, round(avg(alone), 6) AS own_place FROM i"""
for r in range(1, 6):
    add(f"w_unicity_after_r{r}", lambda s, d, r=r: M.unicity(P.interleaved(protect.closure(habit(s, d), 3, r)[-1][1])),
        f"{closed(r)}, split AS (SELECT *, CASE WHEN {Q.DAY} % 2 = 0 THEN 'Q' ELSE 'D' END AS side FROM t{r}), {Q.sig('split', 'sg')}, {UNICITY}")
add("w_unicity", lambda s, d: M.unicity(split(s, d)), f"""WITH {Q.BASE}, {Q.sig('split', 'sg')}, i AS (SELECT c.side, c.oid, avg(ln(objects / df)) AS mi, max((df = 1)::INT) AS alone FROM sg_c c JOIN sg_f USING (side, fid) JOIN sg_o USING (side) GROUP BY c.side, c.oid)
    SELECT round(avg(mi), 6) AS mean_idf, round(avg(alone), 6) AS own_place FROM i""")  # fmt: skip
add("w_crowd", lambda s, d: M.k_of_point(habit(s, d)).groupBy("objects").agg(F.count(F.lit(1)).alias("places")), f"WITH {Q.HABIT} SELECT objects, count(*) AS places FROM (SELECT pid, count(DISTINCT oid) AS objects FROM habit GROUP BY pid) GROUP BY objects")


def _generalised(s: SparkSession, d: str) -> DataFrame:
    trace = habit(s, d)
    heavy = W.cut(W.weigh(W.counts(trace.withColumn("side", F.lit("A")))), 3, False).select("oid", F.col("fid").alias("pid"))
    return protect.release(trace, heavy, "generalize").groupBy("oid").agg(F.count(F.lit(1)).alias("points"), F.count_distinct("pid").alias("places"))


add("w_release_generalised", _generalised, f"""{closed(1)}, g AS (SELECT t.oid, CASE WHEN c.fid IS NULL THEN t.pid ELSE -(floor(x / 10) * 100000 + floor(y / 10) + 1)::BIGINT END AS pid FROM t0 t LEFT JOIN c0 c ON c.oid = t.oid AND c.fid = t.pid)
    SELECT oid, count(*) AS points, count(DISTINCT pid) AS places FROM g GROUP BY oid""")  # fmt: skip
for p in (1, 2, 3, 4):
    add(f"w_unique_{p}", lambda s, d, p=p: protect.point_uniqueness(habit(s, d), p, 20),
        f"""WITH {Q.HABIT}, v AS (SELECT DISTINCT oid, ({GRID.format(20)}) * 1000000 + floor(epoch(t) / 86400)::BIGINT % 1000000 AS v FROM habit),
        dr AS (SELECT oid AS qid, v FROM (SELECT *, row_number() OVER (PARTITION BY oid ORDER BY {Q.int_hash('(v + oid)', 5)}, v) AS r FROM v) WHERE r <= {p}),
        h AS (SELECT qid, oid, count(*) AS n FROM dr JOIN v USING (v) GROUP BY qid, oid), f AS (SELECT qid, count(*) AS drawn FROM dr GROUP BY qid),
        c AS (SELECT qid, count(*) AS crowd FROM h JOIN f USING (qid) WHERE n = drawn GROUP BY qid) SELECT count(*) AS objects, count(*) FILTER (crowd = 1) AS "unique" FROM c""")  # fmt: skip


def _tuned(s: SparkSession, d: str) -> DataFrame:
    """Recall over all queries of hashing whose bands were tuned to find nine of ten first neighbours."""
    g = W.spatial(split(s, d), 3)
    q, c = L.sides(g)
    bands, _ = L.lsh_tune(q, c, g, 0.95)
    return M.recall_at(L.lsh(q, c, L.lsh_bits(g, 96), bands, 96, 1), L.inverted(q, c, 1), 1).withColumn("bands", F.lit(bands))


add("w_link_lsh_tuned", _tuned)
add("m_recall_lsh", lambda s, d: M.recall_at(L.lsh(*L.sides(g := W.spatial(split(s, d), 3)), L.lsh_bits(g, 64), 16, 64, 5), L.inverted(*L.sides(g), 5), 1))


def _api(s: SparkSession, d: str) -> DataFrame:
    """The whole way through the pipeline object: search on the tree, re-ranking by whole signatures, matching."""
    from ..pipeline import LinkPipeline

    return LinkPipeline(m=3, search="tree", rerank=None, match=True).run(habit(s, d)).metrics


add("api_pipeline", _api, f"""WITH {Q.BASE}, {Q.sig('split', 'sg', 3)}, {Q.knn('sg', 5)}, {Q.sig('split', 'lg')}, {Q.rerank('knn', 'lg', 'rr')},
    ed AS (SELECT qid, oid, sim FROM rr), {Q.match('ed', 'rr', 'mt', 20)}, {Q.match_ranking('rr', 'mt', 'mr')} {Q.acc('mr')}""")  # fmt: skip


def _estimated(s: SparkSession, d: str) -> DataFrame:
    """Signatures of the queries by the rarity that an estimator learned from the candidates."""
    from ..pipeline import SignatureEstimator

    trace = split(s, d)
    model = SignatureEstimator(3).fit(trace.where("side = 'D'").drop("side"))
    return model.transform(trace.where("side = 'Q'")).select("oid", "fid", F.round("w", 6).alias("w"))


add("api_estimator", _estimated, f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3, scope='candidate')} SELECT oid, fid, round(w, 6) AS w FROM sg WHERE side = 'Q'")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Acc@1..5 of spatial signatures cut to three places, searched on the tree."""
    t, q, c, place = sig_of(spark, d)
    return accuracy(t, sigtree.knn_join(q, sigtree.build(c, place), 5, place))



