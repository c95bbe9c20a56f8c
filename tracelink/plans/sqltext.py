"""DuckDB text of traces, signatures, searches and measures: the independent twin that the queries are compared with.

Every function returns one or more common table expressions without the leading WITH.
"""

from __future__ import annotations

DAY = "date_diff('day', DATE '2024-01-01', t::DATE)"

HABIT = """ev AS (SELECT *, (event_id * 7919 + 104729) % 10 AS h, (event_id // 7) % 8 AS j, regexp_extract(props, '[0-9]+')::BIGINT AS k,
  CASE event_type WHEN 'view' THEN 0 WHEN 'click' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS et FROM events),
lattice AS (SELECT user_id AS oid, ts AS t, event_id,
  CASE WHEN h < 4 THEN ((37 * user_id) % 97 + (5 * j + user_id) % 7) % 100 ELSE (13 * k + 17 * event_id) % 100 END AS gx,
  CASE WHEN h < 4 THEN ((91 * user_id) % 89 + (3 * j + 3 * user_id) % 7) % 100 ELSE (23 * et + 29 * event_id + k) % 100 END AS gy FROM ev),
habit AS (SELECT oid, t, gx * 1000 + gy AS pid, gx::DOUBLE AS x, gy::DOUBLE AS y FROM lattice)"""

RAW = """raw AS (SELECT user_id AS oid, ts AS t, regexp_extract(props, '[0-9]+')::BIGINT * 100000 + floor(coalesce(value, 0.0) / 25)::BIGINT AS pid,
  regexp_extract(props, '[0-9]+')::DOUBLE AS x, floor(coalesce(value, 0.0) / 25)::DOUBLE AS y FROM events)"""

INTERLEAVED = f"split AS (SELECT *, CASE WHEN {DAY} % 2 = 0 THEN 'Q' ELSE 'D' END AS side FROM habit)"

BASE = f"{HABIT}, {INTERLEAVED}"


def customers(place: str = "l_suppkey") -> str:
    return f"""split AS (SELECT CASE WHEN o_orderkey % 2 = 1 THEN 'Q' ELSE 'D' END AS side, o_custkey AS oid, o_orderdate AS t, {place} AS pid,
  ({place} % 40)::DOUBLE AS x, ({place} // 40)::DOUBLE AS y FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"""


def int_hash(c: str, seed: int) -> str:
    return f"((({c} + 1) * 48271 + {seed} * 11) % 2147483647 * 48271 % 2147483647)"


def sig(src: str, name: str, m: int | None = None, scheme: str = "tfidf", feature: str = "pid", scope: str = "own") -> str:
    """``name(side, oid, fid, w)`` from a relation with side, oid and the feature."""
    n = name
    w = {"tf": "tf", "idf": "ln(objects / df)", "tfidf": "tf * ln(objects / df)"}[scheme]
    keep = "" if scheme == "tf" else "WHERE objects > df"
    base = {"own": f"{n}_c", "candidate": f"(SELECT * FROM {n}_c WHERE side = 'D')", "union": f"{n}_c"}[scope]
    key, on = ("side, ", "USING (side, fid)") if scope == "own" else ("", "USING (fid)")
    objects = f"SELECT side, count(DISTINCT oid) AS objects FROM {n}_c GROUP BY side" if scope == "own" else f"SELECT count(*) AS objects FROM (SELECT DISTINCT side, oid FROM {base})"
    join_objects = f"JOIN {n}_o USING (side)" if scope == "own" else f"CROSS JOIN {n}_o"
    text = f"""{n}_c AS (SELECT side, oid, {feature} AS fid, count(*) AS n FROM {src} WHERE {feature} IS NOT NULL GROUP BY ALL),
{n}_o AS ({objects}), {n}_f AS (SELECT {key}fid, count(*) AS df FROM {base} GROUP BY ALL),
{n}_t AS (SELECT *, n / sum(n) OVER (PARTITION BY side, oid) AS tf FROM {n}_c),
{n}_w AS (SELECT side, oid, fid, {w} AS w FROM {n}_t JOIN {n}_f {on} {join_objects} {keep}),
{n}_u AS (SELECT side, oid, fid, w / sqrt(sum(w * w) OVER (PARTITION BY side, oid)) AS w FROM {n}_w)"""
    return text + ", " + (f"{n} AS (SELECT * FROM {n}_u)" if m is None else cut(f"{n}_u", n, m))


def cut(src: str, name: str, m: int) -> str:
    return f"""{name}_k AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY side, oid ORDER BY round(w, 12) DESC, fid) AS rr FROM {src}) WHERE rr <= {m}),
{name} AS (SELECT side, oid, fid, w / sqrt(sum(w * w) OVER (PARTITION BY side, oid)) AS w FROM {name}_k)"""


def pairs(sig_name: str, name: str = "pairs") -> str:
    return f"""{name} AS (SELECT q.oid AS qid, d.oid AS oid, sum(q.w * d.w) AS sim FROM {sig_name} q JOIN {sig_name} d ON q.fid = d.fid
  WHERE q.side = 'Q' AND d.side = 'D' GROUP BY q.oid, d.oid)"""


def ranked(src: str, name: str, k: int) -> str:
    return f"{name} AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(sim, 9) DESC, oid) AS rnk FROM {src}) WHERE rnk <= {k})"


def knn(sig_name: str, k: int, name: str = "knn") -> str:
    return pairs(sig_name, f"{name}_p") + ", " + ranked(f"{name}_p", name, k)


def acc(knn_name: str, split: str = "split", most: int = 5) -> str:
    """Final SELECT: k, hits, queries, acc."""
    return f"""SELECT k, hits, queries, round(hits / queries, 6) AS acc FROM (SELECT k, (SELECT count(*) FROM {knn_name} WHERE qid = oid AND rnk <= k) AS hits,
  (SELECT count(DISTINCT oid) FROM {split} WHERE side = 'Q') AS queries FROM (SELECT unnest(range(1, {most + 1}))::INT AS k))"""


def rerank(knn_name: str, sig_name: str, name: str) -> str:
    return f"""{name}_s AS (SELECT k.qid, k.oid, coalesce(sum(q.w * d.w), 0.0) AS sim FROM {knn_name} k LEFT JOIN {sig_name} q ON q.side = 'Q' AND q.oid = k.qid
  LEFT JOIN {sig_name} d ON d.side = 'D' AND d.oid = k.oid AND d.fid = q.fid GROUP BY k.qid, k.oid), {ranked(f"{name}_s", name, 1 << 30)}"""


def edges(knn_q: str, knn_d: str, name: str) -> str:
    return f"""{name} AS (SELECT qid, oid, max(sim) AS sim FROM (SELECT qid, oid, round(sim, 9) AS sim FROM {knn_q} UNION ALL SELECT oid, qid, round(sim, 9) FROM {knn_d}) GROUP BY qid, oid)"""


def match(edge: str, first: str, name: str, rounds: int = 12) -> str:
    """Stable matching by unrolled rounds of mutually best edges, leftovers from ``first`` (rnk 1)."""
    parts, rest = [], edge
    for i in range(rounds):
        parts.append(f"""{name}_m{i} AS MATERIALIZED (SELECT qid, oid, sim FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(sim, 9) DESC, qid, oid) AS a,
  row_number() OVER (PARTITION BY oid ORDER BY round(sim, 9) DESC, qid, oid) AS b FROM {rest}) WHERE a = 1 AND b = 1)""")
        parts.append(f"{name}_r{i} AS MATERIALIZED (SELECT * FROM {rest} WHERE qid NOT IN (SELECT qid FROM {name}_m{i}) AND oid NOT IN (SELECT oid FROM {name}_m{i}))")
        rest = f"{name}_r{i}"
    every = " UNION ALL ".join(f"SELECT * FROM {name}_m{i}" for i in range(rounds))
    parts.append(f"{name}_all AS ({every})")
    parts.append(f"{name} AS (SELECT qid, oid, sim, 'matched' AS stage FROM {name}_all UNION ALL SELECT qid, oid, sim, 'leftover' FROM {first} WHERE rnk = 1 AND qid NOT IN (SELECT qid FROM {name}_all))")
    return ", ".join(parts)


def match_ranking(knn_name: str, match_name: str, name: str) -> str:
    return f"""{name} AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY CASE WHEN own THEN 0 WHEN NOT taken THEN 1 ELSE 2 END, round(sim, 9) DESC NULLS LAST, oid) AS rnk
  FROM (SELECT coalesce(k.qid, m.qid) AS qid, coalesce(k.oid, m.oid) AS oid, k.sim, m.qid IS NOT NULL AS own,
    coalesce(k.oid, m.oid) IN (SELECT oid FROM {match_name} WHERE stage = 'matched') AS taken FROM {knn_name} k FULL JOIN {match_name} m ON k.qid = m.qid AND k.oid = m.oid))"""


def boxes(sig_name: str, src: str, name: str = "box") -> str:
    return f"""{name}_l AS (SELECT pid, min(x) AS x, min(y) AS y FROM {src} GROUP BY pid),
{name} AS (SELECT side, oid, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM {sig_name} s JOIN {name}_l l ON s.fid = l.pid GROUP BY side, oid)"""
