"""Efficiency experiments: build, search, refinement and insertion timed apart on generated traces, with growth in the number of objects.

``python experiments.py [n ...]`` prints Markdown rows. Signatures are written and read back before anything is timed, so a time is that of
the step named alone. EXPERIMENT_CPUS chooses the cores, EXPERIMENT_M the places kept of a signature; a search that took over EXPERIMENT_SECONDS is left out for larger n.
"""

from __future__ import annotations

import os
import sys
import tempfile
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

POINTS, M, CAPACITY = 66, int(os.environ.get("EXPERIMENT_M", "3")), 16
MOST_SECONDS = float(os.environ.get("EXPERIMENT_SECONDS", "90"))


def main(sizes: list[int]) -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from tracelink.operators import linking as L
    from tracelink.operators import metrics as MT
    from tracelink.operators import prepare as P
    from tracelink.operators import refine, sigtree
    from tracelink.operators import weights as W
    from tracelink.session import materialise
    from tracelink.sources import traces as S

    cpus = os.environ.get("EXPERIMENT_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("experiments").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "16g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="experiments-")).getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    slow: set[str] = set()

    def timed(label: str, run, n: int, note: str = "", extra: str = ""):
        if label in slow:
            return None
        start = time.time()
        out = run()
        if hasattr(out, "write"):
            out = materialise(out, "timed")
        took = time.time() - start
        if took > MOST_SECONDS:
            slow.add(label)
        print(f"| {label} | {took:.2f} | n={n}, m={M}{note} | {extra(out) if callable(extra) else extra} |", flush=True)
        return out

    # compile and start workers outside the figures
    sizes = [int(os.environ.get("EXPERIMENT_WARM", "200")), *sizes]
    for n in sizes:
        trace = materialise(P.interleaved(S.habit_of_size(spark, n, POINTS)), "trace")
        whole = materialise(W.spatial(trace), "whole")
        sig = materialise(W.cut(whole, M), "sig")
        place = materialise(S.locations(trace), "places")
        q, d = L.sides(sig)
        queries = q.select("qid").distinct()
        hits = lambda knn: f"Acc@1 {MT.acc_at(knn, queries, [1]).first()['acc']:.3f}"  # noqa: E731, B023
        posting = L.dot_pairs(q, d).count()
        print(f"| pairs that share a place | {posting} | n={n}, m={M} | of {n * n} |", flush=True)
        box = materialise(L.boxes(sig, place), "boxes")
        bands, recall = L.lsh_tune(q, d, sig, 0.9)
        bits = materialise(L.lsh_bits(sig, 96), "bits")
        timed("link: inverted join", lambda: L.inverted(q, d, 1), n, ", k=1", hits)
        timed("link: linear", lambda: L.linear(q, d, 1), n, ", k=1", hits)
        timed("link: l2ap", lambda: L.threshold_knn(q, d, 1, 0.3), n, ", k=1", hits)
        timed("link: hashing", lambda: L.lsh(q, d, bits, bands, 96, 1), n, f", k=1, {bands} bands of 96 bits, recall {recall:.2f} in tuning", hits)
        timed("link: box range", lambda: L.mbr_range(q, d, box, 1), n, ", k=1", hits)
        spatial = timed("build: spatial", lambda: sigtree.build(d, place, CAPACITY, "spatial"), n, f", c={CAPACITY}", lambda t: f"{t.entries} entries")
        common = timed("build: common", lambda: sigtree.build(d, place, CAPACITY, "common"), n, f", c={CAPACITY}", lambda t: f"{t.entries} entries")
        grown = timed("build: one by one", lambda: sigtree.build_by_insert(sigtree.objects_of(d, place), CAPACITY), n, f", c={CAPACITY}", lambda t: f"{sum(x[2] for x in sigtree.local_size(t))} entries")
        for k in (1, 5):
            timed(f"link: tree, joins, k={k}", lambda k=k: sigtree.knn_join(q, common, k, place), n, "", hits)
        for label, tree in (("spatial", spatial), ("common", common), ("one by one", grown)):
            work = timed(f"link: tree, best first, {label}", lambda t=tree: sigtree.search_local(q, t, 1, place), n, ", k=1", hits)
            if work is not None:
                row = work.where("rnk = 1").agg(F.avg("popped").alias("a"), F.avg("scored").alias("b")).first()
                print(f"| work: best first, {label} | {row['a'] or 0:.1f} / {row['b'] or 0:.1f} | n={n}, m={M}, k=1 | nodes taken / children scored a query |", flush=True)
        knn = materialise(L.inverted(q, d, 5), "knn")
        back = materialise(L.top_k(L.dot_pairs(q, d).select(F.col("oid").alias("qid"), F.col("qid").alias("oid"), "sim"), 5), "back")
        for longer in (20, None):
            timed(f"extra: re-rank {longer or 'full'}", lambda x=longer: refine.rerank(knn, *L.sides(W.cut(whole, x))), n, ", k=5", hits)
        timed("extra: stable matching", lambda: refine.match_ranking(knn, refine.stable_match(refine.both_lists(knn, back), knn)), n, ", k=5", hits)
        part = P.int_hash(F.col("oid"), 9) % 24
        for criterion in ("spatial", "common"):
            tree = sigtree.build(d.where(part >= 6), place, CAPACITY, criterion)
            for step in (0, 1):
                fresh = d.where(part == step)
                many = fresh.select("oid").distinct().count()
                start = time.time()
                tree = sigtree.insert(tree, fresh, place, criterion, "split")
                print(f"| insert: {criterion} | {(time.time() - start) / max(1, many):.4f} an object | n={n}, m={M}, batch {step + 1} of {many} | grown from three quarters |", flush=True)
            timed(f"link: grown tree, {criterion}", lambda t=tree: sigtree.knn_join(q, t, 1, place), n, ", k=1", hits)
    spark.stop()


if __name__ == "__main__":
    main([int(x) for x in sys.argv[1:]] or [1501, 3001, 6001, 12001])
