"""Repair of neighbour lists: re-ranking with longer signatures and stable matching."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import materialise
from .linking import top_k, verify

#: Rounds of a stable matching before a rest of few edges is matched in one task, and that many edges; edges that go to one task at once.
SOON, FEW, SMALL = 16, 2_000_000, 200_000


def rerank(knn: DataFrame, q_long: DataFrame, d_long: DataFrame) -> DataFrame:
    """Reorder each query's neighbours by longer signatures; only listed pairs are scored, a pair without common features scores 0."""
    pairs = knn.select("qid", "oid")
    scored = pairs.join(verify(pairs, q_long, d_long), ["qid", "oid"], "left").select("qid", "oid", F.coalesce("sim", F.lit(0.0)).alias("sim"))
    return top_k(scored, 1 << 30)


def _mutual(edges: DataFrame) -> DataFrame:
    """Edges that are the best of both ends: best by (similarity, smaller qid, smaller oid)."""
    order = [F.round("sim", 9).desc(), F.col("qid"), F.col("oid")]
    ranked = edges.withColumn("rq", F.row_number().over(Window.partitionBy("qid").orderBy(*order))).withColumn("rd", F.row_number().over(Window.partitionBy("oid").orderBy(*order)))
    return ranked.where("rq = 1 and rd = 1").select("qid", "oid", "sim")


def _tied_blocks(edges: DataFrame) -> DataFrame:
    """Edges of the matching in blocks of ties: queries and candidates whose best edges are all those between them, equal in similarity.

    Taking such a block's edges by (qid, oid) gives its i-th query its i-th candidate. A block is known by the sets of ends its members
    see (count and two hash sums). Every end seen must be a member, so an end whose best is elsewhere leaves the block to ``_mutual``.
    """
    best = edges.withColumn("s", F.round("sim", 9))
    best = best.withColumn("bq", F.max("s").over(Window.partitionBy("qid"))).withColumn("bd", F.max("s").over(Window.partitionBy("oid")))

    def seen(end: str, other: str, top: str, x: str) -> DataFrame:
        hashes = [F.sum(F.xxhash64(F.lit(i), other).cast("decimal(38,0)")).alias(f"h{i}{x}") for i in (1, 2)]
        return best.where(F.col("s") == F.col(top)).groupBy(end).agg(F.count(F.lit(1)).alias(f"n{x}"), *hashes)

    tied = best.where("s = bq and s = bd").join(seen("qid", "oid", "bq", "q"), "qid").join(seen("oid", "qid", "bd", "d"), "oid")
    block = ["s", "nq", "h1q", "h2q", "nd", "h1d", "h2d"]
    qs, ds = (tied.groupBy(*block, end).agg(F.count(F.lit(1)).alias("met")) for end in ("qid", "oid"))
    sizes = (x.groupBy(*block).agg(F.count(F.lit(1)).alias(f"c{e}"), F.min("met").alias(f"m{e}")) for x, e in ((qs, "q"), (ds, "d")))
    whole = next(sizes).join(next(sizes), block).where("cq = nd and cd = nq and mq = nq and md = nd").select(*block)
    placed = (x.join(whole, block, "left_semi").withColumn("i", F.row_number().over(Window.partitionBy(*block).orderBy(end))).drop("met") for x, end in ((qs, "qid"), (ds, "oid")))
    pairs = next(placed).join(next(placed), [*block, "i"]).select("qid", "oid")
    return tied.join(pairs, ["qid", "oid"], "left_semi").select("qid", "oid", "sim")


def _in_order(edges: pd.DataFrame) -> pd.DataFrame:
    """The matching of a bounded number of edges, one after another in their order."""
    edges = edges.sort_values(["s", "qid", "oid"], ascending=[False, True, True])
    free_q, free_d, rows = set(edges["qid"]), set(edges["oid"]), []
    for i, (q, o) in enumerate(zip(edges["qid"], edges["oid"], strict=True)):
        if q in free_q and o in free_d:
            free_q.remove(q)
            free_d.remove(o)
            rows.append(i)
    return edges.iloc[rows][["qid", "oid", "sim"]]


def stable_match(edges: DataFrame, knn: DataFrame | None = None, leftover: str = "top1") -> DataFrame:
    """``qid, oid, sim, stage``: the stable matching of ``edges(qid, oid, sim)``.

    Both sides rank by the same similarity, so edges that are best for both ends are in the one stable matching; taking them, removing
    their ends and going on until no edge is left gives all of it. Blocks of ties go at once. A falling chain gives one pair a round, so
    after ``SOON`` rounds a rest of ``FEW`` edges at most is matched in one task; a larger rest takes more rounds, however many. A rest of
    ``SMALL`` edges is matched in one task in any round, which gives the same pairs sooner than another round. Queries
    without partner get their first neighbour of ``knn`` (stage 'leftover') unless ``leftover`` is 'none'.
    """
    rest = materialise(edges.select("qid", "oid", "sim"), "edges")
    taken, rounds = None, 0
    while not rest.isEmpty():
        last = rest.count() <= (FEW if rounds >= SOON else SMALL)
        if last:
            now = rest.withColumn("s", F.round("sim", 9)).groupBy(F.lit(1).alias("one")).applyInPandas(_in_order, rest.schema)
        else:
            now = _mutual(rest) if rounds % 4 else _mutual(rest).union(_tied_blocks(rest)).distinct()
        now = materialise(now, "matched")
        taken = now if taken is None else taken.union(now)
        if last:
            break
        rounds += 1
        if rounds % SOON == 0:  # one table instead of a plan that grows with the rounds
            taken = materialise(taken, "matched")
        rest = materialise(rest.join(now.select("qid"), "qid", "left_anti").join(now.select("oid"), "oid", "left_anti").select("qid", "oid", "sim"), "edges")
    matched = (taken if taken is not None else rest).withColumn("stage", F.lit("matched"))
    if leftover == "none":
        return matched
    first = (knn if knn is not None else top_k(edges, 1)).where("rnk = 1").select("qid", "oid", "sim", F.lit("leftover").alias("stage"))
    return matched.union(first.join(matched.select("qid"), "qid", "left_anti").select("qid", "oid", "sim", "stage"))


def both_lists(knn_q: DataFrame, knn_d: DataFrame) -> DataFrame:
    """Edges of the lists of both sides; ``knn_d`` has candidates as qid."""
    turned = knn_d.select(F.col("oid").alias("qid"), F.col("qid").alias("oid"), F.round("sim", 9).alias("sim"))
    return knn_q.select("qid", "oid", F.round("sim", 9).alias("sim")).union(turned).groupBy("qid", "oid").agg(F.max("sim").alias("sim"))


def match_ranking(knn: DataFrame, match: DataFrame) -> DataFrame:
    """Lists with the matched partner first, then by similarity, and partners of others last."""
    own = match.select("qid", "oid", F.lit(1).alias("own"))
    taken = match.where("stage = 'matched'").select("oid", F.lit(1).alias("taken")).distinct()
    merged = knn.select("qid", "oid", "sim").join(own, ["qid", "oid"], "full").join(taken, "oid", "left")
    place = F.when(F.col("own") == 1, 0).when(F.col("taken").isNull(), 1).otherwise(2)
    order = Window.partitionBy("qid").orderBy(place, F.round("sim", 9).desc_nulls_last(), "oid")
    return merged.select("qid", "oid", "sim", F.row_number().over(order).alias("rnk"))


def sequential_match(own: list[tuple], other: list[tuple]) -> list[tuple]:
    """Proposals on truncated lists, one after another in order of qid (reference, and the work of one component).

    ``own`` is (qid, oid, sim) of the proposers' lists, ``other`` of the receivers' (oid, qid, sim). A receiver keeps the proposer that
    stands higher on its own list, one not listed stands below all; of two unlisted ones the first stays.
    """
    lists: dict = {}
    for q, o, s in sorted(own, key=lambda e: (e[0], -round(e[2], 9), e[1])):
        lists.setdefault(q, []).append(o)
    rank = {(o, q): s for o, q, s in other}
    queue, at, held = sorted(lists), dict.fromkeys(lists, 0), {}
    lost = []
    while queue:
        q = queue.pop(0)
        o = lists[q][at[q]]
        at[q] += 1
        loser = None
        if o not in held:
            held[o] = q
        elif rank.get((o, q), -1.0) > rank.get((o, held[o]), -1.0):
            loser, held[o] = held[o], q
        else:
            loser = q
        if loser is not None:
            (queue if at[loser] < len(lists[loser]) else lost).append(loser)
    return [(q, o, "matched") for o, q in held.items()] + [(q, lists[q][0], "leftover") for q in lost]


def ranked_match(knn_q: DataFrame, knn_d: DataFrame, most_edges: int = 2_000_000) -> DataFrame:
    """The order-dependent proposals on whole lists, in one task; refuses more edges than ``most_edges`` (use ``stable_match`` there)."""
    edges = knn_q.select(F.lit(0).alias("kind"), F.col("qid").alias("a"), F.col("oid").alias("b"), "sim").union(knn_d.select(F.lit(1).alias("kind"), F.col("qid").alias("a"), F.col("oid").alias("b"), "sim"))
    if edges.limit(most_edges + 1).count() > most_edges:
        raise ValueError(f"more than {most_edges} edges: the ranked mode is sequential")

    def run(group: pd.DataFrame) -> pd.DataFrame:
        rows = {k: list(g[["a", "b", "sim"]].itertuples(index=False, name=None)) for k, g in group.groupby("kind")}
        return pd.DataFrame(sequential_match(rows.get(0, []), rows.get(1, [])), columns=["qid", "oid", "stage"])

    return edges.groupBy(F.lit(1).alias("one")).applyInPandas(run, "qid long, oid long, stage string")
