"""Relational operators and scalar functions around the methods, as registered queries with their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import columns as C
from ..functions import tables
from ..operators.prepare import int_hash
from ..session import materialise, shuffle_width
from ..sources import traces as S
from .workloads import QUERIES, add, habit, sig_of
from . import sqltext as Q


def events(s: SparkSession, d: str) -> DataFrame:
    return S.read(s, d, "events")


add("rel_filter", lambda s, d: events(s, d).where("value between 10 and 50 and event_type in ('view', 'click') and event_type like 'v%' and not (user_id <=> null)").select("event_id", "user_id", F.when(F.col("value") > 30, "high").otherwise("low").alias("level")),
    "SELECT event_id, user_id, CASE WHEN value > 30 THEN 'high' ELSE 'low' END AS level FROM events WHERE value BETWEEN 10 AND 50 AND event_type IN ('view', 'click') AND event_type LIKE 'v%' AND user_id IS NOT NULL")

JOINS = {"inner": "JOIN", "left": "LEFT JOIN", "right": "RIGHT JOIN", "full": "FULL JOIN"}
for how, text in JOINS.items():
    # orders stand on the left of the right join, so that customers without orders are its unmatched rows
    first, second = ("orders", "customer") if how == "right" else ("customer", "orders")
    add(f"rel_join_{how}", lambda s, d, how=how, a=first, b=second: S.read(s, d, a).join(S.read(s, d, b), F.col("c_custkey") == F.col("o_custkey"), how).select("c_custkey", "o_orderkey"),
        f"SELECT c_custkey, o_orderkey FROM {first} {text} {second} ON c_custkey = o_custkey")
for hint in ("broadcast", "merge", "shuffle_hash"):
    add(f"rel_hint_{hint}", lambda s, d, h=hint: S.read(s, d, "nation").join(S.read(s, d, "region").hint(h), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name"),
        "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
add("rel_semi", lambda s, d: S.read(s, d, "customer").join(S.read(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
add("rel_anti", lambda s, d: S.read(s, d, "documents").join(S.read(s, d, "labels"), "doc_id", "left_anti").select("doc_id"), "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
add("rel_theta", lambda s, d: (lambda n: n.alias("a").join(n.alias("b"), F.expr("a.n_nationkey < b.n_nationkey and abs(a.n_regionkey - b.n_regionkey) <= 1")).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b")))(S.read(s, d, "nation")),
    "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND abs(a.n_regionkey - b.n_regionkey) <= 1")


#: Parts of one size and price that are held as one row, and pairs aimed at for a task, of the range join.
RANGE_CHUNK, RANGE_TASK = 1024, 8_000_000


def _range_join(s: SparkSession, d: str) -> DataFrame:
    """Pairs of parts of one size whose price is within 5.

    Parts of one size and price meet others alike, so they meet as rows of up to RANGE_CHUNK keys: an equi-join on the price bucket and the
    next one, each two rows once. The keys of two rows are paired last, in as many tasks as the counted pairs ask for.
    """
    p = S.read(s, d, "part").select("p_partkey", "p_size", F.col("p_retailprice").alias("price")).dropna()
    place = F.row_number().over(Window.partitionBy("p_size", "price").orderBy("p_partkey")) - 1
    alike = p.withColumn("chunk", F.floor(place / RANGE_CHUNK)).groupBy("p_size", "price", "chunk").agg(F.collect_list("p_partkey").alias("keys"))
    # buckets wider than 5, so that no rounding of the quotient takes a pair apart
    alike = materialise(alike.withColumn("b", F.floor(F.col("price") / 6)), "alike")
    left = alike.select("p_size", F.col("price").alias("pa"), F.col("chunk").alias("ca"), F.col("keys").alias("ka"), F.explode(F.array(F.col("b"), F.col("b") + 1)).alias("b"))
    right = alike.select("p_size", F.col("price").alias("pz"), F.col("chunk").alias("cz"), F.col("keys").alias("kz"), "b")
    met = left.join(right, ["p_size", "b"]).where("abs(pa - pz) <= 5 and (pa < pz or pa = pz and ca <= cz)")
    pairs = met.agg(F.sum(F.size("ka").cast("long") * F.size("kz"))).first()[0] or 0
    dealt = met.withColumn("own", F.expr("pa = pz and ca = cz")).repartition(max(shuffle_width(s), -(-pairs // RANGE_TASK)), "p_size", "pa", "ca", "pz", "cz")
    both = dealt.select(F.explode("ka").alias("x"), "kz", "own").select("x", F.explode("kz").alias("y"), "own")
    return both.where("x < y or x > y and not own").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("z"))


add("rel_range_join", _range_join, "SELECT a.p_partkey AS a, z.p_partkey AS z FROM part a JOIN part z ON a.p_size = z.p_size AND a.p_partkey < z.p_partkey AND abs(a.p_retailprice - z.p_retailprice) <= 5")


def _as_of(s: SparkSession, d: str) -> DataFrame:
    """Last place of a user before each purchase: one union and one window, no range join."""
    e = events(s, d).select("user_id", "ts", "event_id", F.when(F.col("event_type") == "view", F.struct("event_id", "ts")).alias("seen"), "event_type")
    w = Window.partitionBy("user_id").orderBy("ts").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("last", F.last("seen", ignorenulls=True).over(w)).where("event_type = 'purchase' and last is not null").select("event_id", F.col("last.event_id").alias("last_view"))


add("rel_as_of", _as_of, """SELECT p.event_id, v.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts > v.ts""")


def _interval(s: SparkSession, d: str) -> DataFrame:
    """Events of different users at one lattice row within ten minutes: equi-join on time buckets and exact residual."""
    e = habit(s, d).select("oid", "t", F.expr("pid div 1000").alias("gx"), F.floor(F.unix_timestamp(F.col("t").cast("timestamp")) / 600).alias("b"))
    left = e.select(F.col("oid").alias("a"), F.col("t").alias("ta"), "gx", F.explode(F.array(F.col("b") - 1, F.col("b"), F.col("b") + 1)).alias("b"))
    right = e.select(F.col("oid").alias("z"), F.col("t").alias("tz"), "gx", "b")
    gap = F.abs(F.unix_timestamp(F.col("ta").cast("timestamp")) - F.unix_timestamp(F.col("tz").cast("timestamp")))
    return left.join(right, ["gx", "b"]).where((F.col("a") < F.col("z")) & (gap <= 600)).groupBy("a", "z").agg(F.count(F.lit(1)).alias("meetings"))


add("rel_interval_join", _interval, f"WITH {Q.HABIT} SELECT a.oid AS a, z.oid AS z, count(*) AS meetings FROM habit a JOIN habit z ON a.oid < z.oid AND a.pid // 1000 = z.pid // 1000 AND abs(floor(epoch(a.t)) - floor(epoch(z.t))) <= 600 GROUP BY a.oid, z.oid")
add("rel_aggregate", lambda s, d: S.read(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_extendedprice"), 2).alias("total"), F.round(F.avg("l_quantity"), 6).alias("mean"), F.count(F.lit(1)).alias("n"), F.count_distinct("l_suppkey").alias("suppliers"), F.max_by("l_partkey", F.struct("l_extendedprice", "l_partkey")).alias("dearest")),
    "SELECT l_returnflag, l_linestatus, round(sum(l_extendedprice), 2) AS total, round(avg(l_quantity), 6) AS mean, count(*) AS n, count(DISTINCT l_suppkey) AS suppliers, max_by(l_partkey, (l_extendedprice, l_partkey)) AS dearest FROM lineitem GROUP BY ALL")
add("rel_sketches", lambda s, d: S.read(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts_hll"), F.percentile_approx("l_quantity", 0.5).alias("median")))
NATIONS = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _nations(s: SparkSession, d: str) -> DataFrame:
    return S.read(s, d, "customer").join(S.read(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(S.read(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))


add("rel_rollup", lambda s, d: _nations(s, d).rollup("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")), f"SELECT r_name, c_mktsegment, count(*) AS n FROM {NATIONS} GROUP BY ROLLUP (r_name, c_mktsegment)")
add("rel_cube", lambda s, d: _nations(s, d).cube("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")), f"SELECT r_name, c_mktsegment, count(*) AS n FROM {NATIONS} GROUP BY CUBE (r_name, c_mktsegment)")
add("rel_grouping_sets", lambda s, d: _nations(s, d).groupingSets([["r_name"], ["c_mktsegment"]], "r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")), f"SELECT r_name, c_mktsegment, count(*) AS n FROM {NATIONS} GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")
add("rel_pivot", lambda s, d: events(s, d).groupBy("user_id").pivot("event_type", ["view", "click"]).agg(F.count(F.lit(1))).select("user_id", F.coalesce("view", F.lit(0)).alias("views"), F.coalesce("click", F.lit(0)).alias("clicks")),
    "SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (event_type = 'click') AS clicks FROM events GROUP BY user_id")


def _windows(s: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts")
    e = events(s, d)
    run = w.rowsBetween(-2, 0)
    return e.select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"),
        F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.round(F.sum("value").over(run), 4).alias("run"))


add("rel_windows", _windows, """SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr,
    lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS run FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)""")
add("rel_top_k", lambda s, d: S.read(s, d, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
add("rel_top_k_group", lambda s, d: events(s, d).withColumn("r", F.row_number().over(Window.partitionBy("user_id").orderBy(F.col("value").desc(), "event_id"))).where("r <= 2").select("user_id", "event_id", "r"),
    "SELECT user_id, event_id, r FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM events) WHERE r <= 2")
SETS = {"union": "UNION ALL", "intersect": "INTERSECT", "except": "EXCEPT", "intersect_all": "INTERSECT ALL", "except_all": "EXCEPT ALL"}
METHODS = {"union": "unionByName", "intersect": "intersect", "except": "subtract", "intersect_all": "intersectAll", "except_all": "exceptAll"}
for name, text in SETS.items():
    add(f"rel_{name}", lambda s, d, n=name: getattr(events(s, d).where("value > 40").select("user_id", "event_type"), METHODS[n])(events(s, d).where("value < 60").select("user_id", "event_type")),
        f"SELECT user_id, event_type FROM events WHERE value > 40 {text} SELECT user_id, event_type FROM events WHERE value < 60")


def _subqueries(s: SparkSession, d: str) -> DataFrame:
    for t in ("orders", "customer"):
        S.read(s, d, t).createOrReplaceTempView(f"v_{t}")
    return s.sql("""WITH big AS (SELECT o_custkey, o_totalprice FROM v_orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM v_orders))
        SELECT c_custkey, count(*) AS n FROM v_customer JOIN big ON c_custkey = o_custkey WHERE EXISTS (SELECT 1 FROM v_orders o WHERE o.o_custkey = c_custkey AND o.o_orderstatus = 'F') GROUP BY c_custkey""")


add("rel_subqueries", _subqueries, """WITH big AS (SELECT o_custkey, o_totalprice FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders))
    SELECT c_custkey, count(*) AS n FROM customer JOIN big ON c_custkey = o_custkey WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c_custkey AND o.o_orderstatus = 'F') GROUP BY c_custkey""")
def _recursive(s: SparkSession, d: str) -> DataFrame:
    """Running factorials up to each quantity of the lines (12 at most), and the lines of that quantity, by recursion from one row a quantity."""
    S.read(s, d, "lineitem").createOrReplaceTempView("v_lineitem")
    return s.sql("""WITH RECURSIVE r(q, lines, n, f) AS (SELECT CAST(l_quantity AS INT), count(*), 1, 1L FROM v_lineitem GROUP BY 1
        UNION ALL SELECT q, lines, n + 1, f * (n + 1) FROM r WHERE n < least(q, 12)) SELECT q, lines, n, f FROM r""")


add("rel_recursive", _recursive, """WITH RECURSIVE r(q, lines, n, f) AS (SELECT l_quantity::INT, count(*), 1, 1::BIGINT FROM lineitem GROUP BY 1
    UNION ALL SELECT q, lines, n + 1, f * (n + 1) FROM r WHERE n < least(q, 12)) SELECT q, lines, n, f FROM r""")

# --- functions ---------------------------------------------------------------------------------------------------------------------

add("f_strings", lambda s, d: S.read(s, d, "pages").select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1).alias("host"), F.length("url").alias("n"), F.lower(F.substring("url", 1, 5)).alias("head"), F.levenshtein(F.substring("url", 1, 12), F.lit("https://www.")).alias("dist"), F.translate(F.substring("url", 9, 8), ".", "_").alias("t")),
    "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, length(url)::INT AS n, lower(substr(url, 1, 5)) AS head, levenshtein(substr(url, 1, 12), 'https://www.')::INT AS dist, translate(substr(url, 9, 8), '.', '_') AS t FROM pages")
add("f_dates", lambda s, d: events(s, d).select("event_id", F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("dy"), F.hour("ts").alias("h"), F.weekday("ts").alias("wd"), F.date_trunc("month", "ts").cast("date").cast("string").alias("m")),
    "SELECT event_id, date_diff('day', DATE '2024-01-01', ts::DATE)::INT AS dy, hour(ts)::INT AS h, (isodow(ts) - 1)::INT AS wd, date_trunc('month', ts)::DATE::VARCHAR AS m FROM events")
add("f_math", lambda s, d: events(s, d).select("event_id", F.round(F.log(F.col("value") + 1), 6).alias("l"), F.round(F.sqrt("value"), 6).alias("q"), F.pmod(-F.col("event_id"), F.lit(7)).alias("p"), F.greatest(F.col("event_id"), F.col("user_id")).alias("g"), F.round(F.cos("value"), 6).alias("c")),
    "SELECT event_id, round(ln(value + 1), 6) AS l, round(sqrt(value), 6) AS q, ((-event_id) % 7 + 7) % 7 AS p, greatest(event_id, user_id) AS g, round(cos(value), 6) AS c FROM events")
add("f_json", lambda s, d: events(s, d).select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object("props", "$.k").alias("text")),
    "SELECT event_id, regexp_extract(props, '[0-9]+')::INT AS k, regexp_extract(props, '[0-9]+') AS text FROM events")
add("f_bits", lambda s, d: events(s, d).select("event_id", F.bit_count(F.col("event_id").bitwiseXOR(F.col("user_id"))).alias("b"), F.shiftleft("event_id", 3).alias("sl")),
    "SELECT event_id, bit_count(xor(event_id, user_id))::INT AS b, event_id << 3 AS sl FROM events")
add("f_morton", lambda s, d: habit(s, d).select("pid", C.morton(F.col("x"), F.col("y"), 7).alias("z")).distinct(),
    f"WITH {Q.HABIT} SELECT DISTINCT pid, {' + '.join(f'(((x::BIGINT >> {i}) & 1) << {2 * i}) + (((y::BIGINT >> {i}) & 1) << {2 * i + 1})' for i in range(7))} AS z FROM habit")


def _sparse_sql(s: SparkSession, d: str) -> DataFrame:
    """Similarity through the registered SQL function over packed signatures."""
    C.register_sql(s)
    _, q, c, _ = sig_of(s, d, 3)
    q.groupBy("qid").agg(F.collect_list(F.struct("fid", F.col("wq").alias("w"))).alias("a")).createOrReplaceTempView("v_q")
    c.groupBy("oid").agg(F.collect_list(F.struct("fid", F.col("wd").alias("w"))).alias("b")).createOrReplaceTempView("v_d")
    return s.sql("SELECT qid, oid, round(sparse_dot(a, b), 6) AS sim FROM v_q JOIN v_d ON qid = oid")


add("f_sql_sparse_dot", _sparse_sql, f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3)}, {Q.pairs('sg')} SELECT o.oid AS qid, o.oid, round(coalesce(p.sim, 0.0), 6) AS sim FROM (SELECT DISTINCT oid FROM sg WHERE side = 'Q' INTERSECT SELECT DISTINCT oid FROM sg WHERE side = 'D') o LEFT JOIN pairs p ON p.qid = o.oid AND p.oid = o.oid")
assert QUERIES


def _grams_by_udtf(s: SparkSession, d: str) -> DataFrame:
    """Pairs of consecutive words of the benchmark by the registered table function."""
    tables.register(s)
    S.read(s, d, "benchmark").select("item_id", F.split("text", " ").alias("w")).createOrReplaceTempView("benchmark_words")
    return s.sql("SELECT item_id, g.at, g.gram FROM benchmark_words, LATERAL grams(w, 2) g")


GRAM_SQL = "SELECT item_id, i::INT AS at, w[i + 1] || '_' || w[i + 2] AS gram FROM (SELECT item_id, w, unnest(range(0, len(w) - 1)) AS i FROM (SELECT item_id, string_split(text, ' ') AS w FROM benchmark))"
add("f_udtf_grams", _grams_by_udtf, GRAM_SQL)
add("f_grams", lambda s, d: tables.grams(S.read(s, d, "benchmark").select("item_id", F.split("text", " ").alias("w")), "w", 2).select("item_id", "at", "gram"), GRAM_SQL)


def _cells(s: SparkSession, d: str, native: bool) -> DataFrame:
    box = habit(s, d).groupBy("oid").agg(*[f(c).alias(n) for c, f, n in (("x", F.min, "x1"), ("y", F.min, "y1"), ("x", F.max, "x2"), ("y", F.max, "y2"))])
    if native:
        return tables.box_cells(box, 25.0).select("oid", "cx", "cy")
    tables.register(s)
    box.createOrReplaceTempView("trace_boxes")
    return s.sql("SELECT oid, c.cx, c.cy FROM trace_boxes, LATERAL box_cells(x1, y1, x2, y2, 25.0D) c")


CELL_SQL = f"WITH {Q.HABIT}, b AS (SELECT oid, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM habit GROUP BY oid), c AS (SELECT *, unnest(range(floor(x1 / 25)::BIGINT, floor(x2 / 25)::BIGINT + 1)) AS cx FROM b) SELECT oid, cx, unnest(range(floor(y1 / 25)::BIGINT, floor(y2 / 25)::BIGINT + 1)) AS cy FROM c"
add("f_udtf_box_cells", lambda s, d: _cells(s, d, False), CELL_SQL)
add("f_box_cells", lambda s, d: _cells(s, d, True), CELL_SQL)
add("f_mbr_of", lambda s, d: habit(s, d).groupBy("oid").agg(tables.mbr_of().alias("b")).select("oid", *[F.get("b", F.lit(i)).alias(n) for i, n in enumerate(("x1", "y1", "x2", "y2"))]),
    f"WITH {Q.HABIT} SELECT oid, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM habit GROUP BY oid")


def _generated(s: SparkSession, d: str) -> DataFrame:
    """Generated events, one for each number of the events table: points, objects and places of 500 objects."""
    from ..sources import generated

    return S.habit(generated.from_events(events(s, d), 500)).agg(F.count(F.lit(1)).alias("points"), F.count_distinct("oid").alias("objects"), F.sum("pid").alias("pids"))


add("src_generated", _generated, f"""WITH made AS (SELECT i AS event_id, to_timestamp(1704067200 + i * 7907 % 2592000) AS ts, i % 500 AS user_id, 'view' AS event_type, (i * 37 % 1000) / 10.0 AS value, '{{"k": ' || (i * 31 % 100) || '}}' AS props FROM (SELECT event_id AS i FROM events WHERE event_id IS NOT NULL)),
    {Q.HABIT.replace('FROM events', 'FROM made')} SELECT count(*) AS points, count(DISTINCT oid) AS objects, sum(pid)::BIGINT AS pids FROM habit""")  # fmt: skip

# --- sampling, sketches with their error, salting ------------------------------------------------------------------------------------

SHARES = {"view": 100, "click": 300, "purchase": 1000}


def _stratified(s: SparkSession, d: str) -> DataFrame:
    """A sample by integer hash with a share (in thousandths) for each kind of event: the same rows in every run and engine."""
    share = F.create_map(*[F.lit(x) for kv in SHARES.items() for x in kv])[F.col("event_type")]
    return events(s, d).where(int_hash(F.col("event_id"), 7) % 1000 < F.coalesce(share, F.lit(0))).select("event_id", "event_type")


CASES = " ".join(f"WHEN '{k}' THEN {v}" for k, v in SHARES.items())
add("rel_sample_by", _stratified, f"SELECT event_id, event_type FROM events WHERE {Q.int_hash('event_id', 7)} % 1000 < CASE event_type {CASES} ELSE 0 END")
add("rel_quantiles", lambda s, d: S.read(s, d, "lineitem").agg(*[F.round(F.percentile("l_extendedprice", p / 4), 4).alias(f"q{p}") for p in (1, 2, 3)]),
    "SELECT " + ", ".join(f"round(quantile_cont(l_extendedprice, {p / 4}), 4) AS q{p}" for p in (1, 2, 3)) + " FROM lineitem")


def _sketch_error(s: SparkSession, d: str) -> DataFrame:
    """Distinct parts by merged sketches of every supplier's lines: the exact number, and whether estimates are within five percent."""
    lines = S.read(s, d, "lineitem")
    per = lines.groupBy("l_suppkey").agg(F.hll_sketch_agg("l_partkey", F.lit(12)).alias("h"))
    near = lambda c: F.abs(F.col(c) / F.col("parts") - 1) < 0.05
    merged = per.agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("by_parts"))
    whole = lines.agg(F.count_distinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.01).alias("hll"))
    return whole.crossJoin(merged).select("parts", near("hll").alias("whole_near"), near("by_parts").alias("merged_near"))  # single rows


add("rel_sketch_error", _sketch_error, "SELECT count(DISTINCT l_partkey) AS parts, true AS whole_near, true AS merged_near FROM lineitem")
SALTS = 16


def _salted(s: SparkSession, d: str) -> DataFrame:
    """A join and a sum on a key of few values, dealt to SALTS parts of each: the large side by a hash of its rows, the small one to every part."""
    orders = S.read(s, d, "orders").withColumn("salt", F.pmod(F.xxhash64("o_orderkey"), F.lit(SALTS)).cast("int"))
    kinds = S.read(s, d, "orders").select("o_orderstatus").distinct().withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    parts = orders.join(kinds, ["o_orderstatus", "salt"]).groupBy("o_orderstatus", "salt").agg(F.count(F.lit(1)).alias("n"), F.sum("o_totalprice").alias("price"))
    return parts.groupBy("o_orderstatus").agg(F.sum("n").alias("orders"), F.round(F.sum("price"), 2).alias("price"))


add("rel_salted", _salted, "SELECT o_orderstatus, count(*)::BIGINT AS orders, round(sum(o_totalprice), 2) AS price FROM orders GROUP BY o_orderstatus")
