"""MinHash near-dedup by an inverted join over signature coordinates.

Texts become sets of word shingles; documents of equal sets are one class. Each class has a MinHash signature of K coordinates, and is
posted under its coordinate-value pairs. A pair whose sets are at least as alike as asked matches in at least T coordinates but for a
documented chance, so only the rarest K - T + 1 pairs of each signature need posting (prefix); pairs that nobody else has are skipped.
Collisions are counted over whole signatures, pairs below T are dropped, the others are confirmed on the full sets of the texts.

No posting list is expanded into all its pairs. First every member meets two pivots of its list: a verified star joins most of a group.
Then members of lists that still hold several components are searched exactly across components, by prefixes of their full sets; links
inside a component change nothing, so none is lost.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from math import comb

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, give_back, in_chunks, materialise, mix64, run_hash, table, unused

SHINGLE_WORDS, COORDINATES, MISS = 5, 32, 1e-6
CHUNK_BYTES = 1 << 20
#: Bits of the filter on ids (8 MB at any size of the input), and of one block of it.
FILTER_BITS, BLOCK_BITS = 1 << 26, 1 << 16
_SEEDS = mix64(np.arange(1, 4097, dtype=np.uint64))
_FACTORS = mix64(np.arange(5001, 9097, dtype=np.uint64)) | np.uint64(1)


def match_threshold(percent: int, coordinates: int = COORDINATES, miss: float = MISS) -> int:
    """Largest T for which a pair of resemblance ``percent`` has fewer than T matching coordinates with a chance of ``miss`` at most."""
    j, below, t = percent / 100, 0.0, 0
    while t < coordinates and (below := below + comb(coordinates, t) * j**t * (1 - j) ** (coordinates - t)) <= miss:
        t += 1
    return max(1, t)


def _shingles(words: Words, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes of all texts and the text each is from; a text of fewer words has one."""
    counts = np.diff(words.first)
    full = np.maximum(counts - (size - 1), 0)
    take = np.where(full > 0, full, np.minimum(counts, 1))
    text = np.repeat(np.arange(len(take)), take)
    at = np.arange(take.sum()) - np.repeat(np.cumsum(take) - take, take) + words.first[:-1][text]
    runs = run_hash(words.hash, size, 3)
    out = runs[np.minimum(at, max(len(runs) - 1, 0))] if len(runs) else np.zeros(len(at), dtype=np.uint64)
    for i in np.flatnonzero(full[text] == 0).tolist():
        d = text[i]
        n = int(counts[d])
        out[i] = run_hash(words.hash[words.first[d] : words.first[d + 1]], n, 100 + n)[0]
    return out, text


def _raw(texts: pa.Array, part: slice) -> list[bytes]:
    """UTF-8 of some texts, null as empty; only this part of the batch is copied."""
    return [t or b"" for t in texts.slice(part.start, part.stop - part.start).cast(pa.binary()).to_pylist()]


def _signer(size: int, k: int):
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("s1", pa.int64()), ("s2", pa.int64()), ("sig", pa.list_(pa.int32()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in in_chunks(batch, pc.binary_length(batch.column(1)).fill_null(0).to_pylist(), CHUNK_BYTES):
                words = Words(_raw(batch.column(1), part), lower=True)
                hashes, text = _shingles(words, size)
                n = part.stop - part.start
                order = np.lexsort((hashes, text))
                h, t = hashes[order], text[order]
                fresh = np.ones(len(h), dtype=bool)
                fresh[1:] = (h[1:] != h[:-1]) | (t[1:] != t[:-1])
                h, t = h[fresh], t[fresh]
                held = np.bincount(t, minlength=n)
                full = np.flatnonzero(held)
                heads = (np.cumsum(held) - held)[full]
                sums = np.zeros((2, n), dtype=np.uint64)
                sig = np.zeros((len(full), k), dtype=np.uint64)
                if len(h):
                    for i in range(2):
                        sums[i, full] = np.add.reduceat(mix64(h + np.uint64(i)), heads)
                    for i in range(k):
                        sig[:, i] = np.minimum.reduceat((h ^ _SEEDS[i]) * _FACTORS[i], heads)
                ends = np.zeros(n + 1, dtype=np.int32)
                ends[1:] = np.cumsum(np.where(held > 0, k, 0))
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array((sig.ravel() >> np.uint64(32)).astype(np.uint32).view(np.int32)))
                ids = batch.column(0).slice(part.start, n)
                yield pa.RecordBatch.from_arrays([ids, pa.array(held.astype(np.int64)), pa.array(sums[0].view(np.int64)), pa.array(sums[1].view(np.int64)), lists], schema=schema)
        give_back()

    return run


def signatures(docs: DataFrame, text: str = "text", size: int = SHINGLE_WORDS, k: int = COORDINATES) -> DataFrame:
    """``doc_id, n_shingles, s1, s2, sig``: set size, 128-bit digest of the set and its MinHash signature (upper halves of 64-bit minima; empty without words)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(f"`{text}`").cast("string").alias("text"))
    return rows.mapInArrow(_signer(size, k), "doc_id long, n_shingles long, s1 long, s2 long, sig array<int>")


def shingle_set(text: str | None, size: int = SHINGLE_WORDS) -> set[tuple[bytes, ...]]:
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if len(words) < size:
        return {tuple(words)} if words else set()
    return set(zip(*[words[i:] for i in range(size)], strict=False))


def _confirmer(size: int, percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, held = None, set()
        for batch in batches:
            sizes = pc.add(pc.binary_length(batch.column(2)).fill_null(0), pc.binary_length(batch.column(3)).fill_null(0)).to_pylist()
            for part in in_chunks(batch, sizes, CHUNK_BYTES):
                rows = batch.slice(part.start, part.stop - part.start)
                kept = []
                for i, (a, y) in enumerate(zip(rows.column(0).to_pylist(), rows.column(3).to_pylist(), strict=True)):
                    if a != last:
                        last, held = a, shingle_set(rows.column(2)[i].as_py(), size)
                    other = shingle_set(y, size)
                    both = len(held & other)
                    kept.append(100 * both >= percent * (len(held) + len(other) - both))
                yield rows.filter(pa.array(kept)).select(["a", "b"])
        give_back()

    return run


def components(edges: DataFrame) -> DataFrame:
    """``node, component``: smallest node reachable, for every node of ``edges(a, b)``.

    Alternates two steps that hang every neighbour on the smallest known node until nothing changes; each round is written to the shared
    folder. Only a count and a checksum of a round reach the driver.
    """

    def distinct(df: DataFrame) -> DataFrame:
        return df.where("u > v").distinct()

    def state(df: DataFrame):
        return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    now = materialise(distinct(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))), "edges")
    before, mark = None, state(now)
    while mark != before and mark[0]:
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy(F.col("u").alias("x")).agg(F.min("v").alias("m")).select("x", F.least("x", "m").alias("m"))
        large = distinct(both.join(low, F.col("u") == F.col("x")).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")))
        low = large.groupBy(F.col("u").alias("x")).agg(F.min("v").alias("m"))
        hung = large.join(low, F.col("u") == F.col("x")).select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e"))
        now = materialise(distinct(hung.select("e.u", "e.v")), "edges")
        before, mark = mark, state(now)
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select("v", "v").distinct())


def _postings(classes: DataFrame, k: int, need: int) -> DataFrame:
    """``token, node, n, weight``: prefix of each signature, rarest first, without tokens nobody else has."""
    tokens = classes.select(F.col("doc_id").alias("node"), F.col("n_shingles").alias("n"), F.posexplode("sig").alias("i", "v"))
    tokens = tokens.select("node", "n", F.xxhash64("i", "v").alias("token"))
    shared = tokens.groupBy(F.col("token").alias("t")).agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    # written, so that both sides of the join are exchanges of their own and Spark can split a popular token
    held = tokens.join(materialise(shared, "shared"), F.col("token") == F.col("t"))
    # at most k rows a node: the whole list of a node is bounded
    lists = held.groupBy("node", "n").agg(F.sort_array(F.collect_list(F.struct("df", "token"))).alias("ts"), F.sum("df").alias("weight"))
    # pairs that only this class has come first in the order and use up the prefix
    lists = lists.withColumn("room", F.size("ts") - (need - 1)).where("room > 0")
    return lists.select(F.explode(F.slice("ts", F.lit(1), F.col("room"))).alias("p"), "node", "n", "weight").select("p.token", "node", "n", "weight")


def _hasher(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in in_chunks(batch, pc.binary_length(batch.column(2)).fill_null(0).to_pylist(), CHUNK_BYTES):
                hashes, text = _shingles(Words(_raw(batch.column(2), part), lower=True), size)
                n = part.stop - part.start
                sets = [np.unique(x).view(np.int64) for x in np.split(hashes, np.cumsum(np.bincount(text, minlength=n))[:-1])]
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum([len(x) for x in sets])]).astype(np.int32)), pa.array(np.concatenate(sets)))
                yield pa.RecordBatch.from_arrays([batch.column(i).slice(part.start, n) for i in (0, 1)] + [lists], names=["node", "c", "hs"])

    return run


def _pairs_across(unsettled: DataFrame, texts: DataFrame, percent: int, size: int) -> DataFrame:
    """``a, b``: pairs of nodes in different components that may be linked, found exactly.

    Works on the full sets of the nodes whose posting lists hold several components. Of two sets that alike, the smaller one shares one of
    its rarest ``n - 2p/(100+p) n + 1`` shingles with the rarest ``n - p/100 n + 1`` of the larger one. Shingles that no other node has use
    up that prefix and bound the intersection, so copies with many edits of their own are posted nowhere and meet nobody.
    """
    rows = unsettled.join(texts, F.col("node") == F.col("t_id")).select("node", "c", "t_text")
    sets = materialise(rows.mapInArrow(_hasher(size), "node long, c long, hs array<long>"), "sets")
    held = sets.select("node", "c", F.size("hs").cast("long").alias("n"), F.explode("hs").alias("h"))
    shared = held.groupBy(F.col("h").alias("x")).agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    # a text's shingles: as many as it has words
    lists = held.join(shared, F.col("h") == F.col("x")).groupBy("node", "c", "n").agg(F.sort_array(F.collect_list(F.struct("df", "h"))).alias("ts"))
    alone = F.col("n") - F.size("ts")
    lists = lists.withColumn("most", F.size("ts").cast("long"))
    room_small = (F.col("n") - F.ceil(2 * percent * F.col("n") / (100 + percent)) + 1 - alone).cast("int")
    room_large = (F.col("n") - F.ceil(percent * F.col("n") / 100) + 1 - alone).cast("int")
    lists = materialise(lists.withColumn("small", F.slice("ts.h", F.lit(1), F.greatest(F.lit(0), room_small))).withColumn("large", F.slice("ts.h", F.lit(1), F.greatest(F.lit(0), room_large))).drop("ts").where(F.size("large") > 0), "prefixes")
    x, y = (lists.select(F.posexplode(side).alias(f"at_{v}", "h"), *[F.col(k).alias(f"{k}_{v}") for k in ("node", "c", "n", "most")]) for side, v in (("small", "x"), ("large", "y")))
    order = (F.col("n_x") < F.col("n_y")) | ((F.col("n_x") == F.col("n_y")) & (F.col("node_x") < F.col("node_y")))
    # all sets have one order of shingles: before a pair's first common one there is none, so all are in what is left from there on
    left = F.least(F.col("most_x") - F.col("at_x"), F.col("most_y") - F.col("at_y"))
    may = order & (F.col("c_x") != F.col("c_y")) & (100 * left >= percent * (F.col("n_x") + F.col("n_y") - left))
    return x.join(y, "h").where(may).select(F.least("node_x", "node_y").alias("a"), F.greatest("node_x", "node_y").alias("b")).distinct()


def _sieved(texts: DataFrame, ids: DataFrame) -> DataFrame:
    """``t_id, t_text`` of rows that a hash filter of fixed size takes for one of ``ids(p_node)``: all of those, and a few others.

    It only spares the following exact join most rows' shuffle; its share of wrong passes is at most the ids per bit.
    """

    def place(c: str):
        return F.pmod(F.xxhash64(c), F.lit(FILTER_BITS))

    def pack(rows: pd.DataFrame) -> pd.DataFrame:
        bits = np.zeros(BLOCK_BITS, dtype=bool)
        bits[rows["at"].to_numpy()] = True
        return pd.DataFrame({"block": rows["block"].iloc[:1], "packed": [zlib.compress(np.packbits(bits).tobytes(), 1)]})

    blocks = ids.select(place("p_node").alias("p")).distinct().select(F.floor(F.col("p") / BLOCK_BITS).alias("block"), (F.col("p") % BLOCK_BITS).alias("at"))
    whole = np.zeros(FILTER_BITS // 8, dtype=np.uint8)
    size = BLOCK_BITS // 8
    for block, packed in blocks.groupBy("block").applyInPandas(pack, "block long, packed binary").collect():  # FILTER_BITS / BLOCK_BITS rows at most
        whole[block * size : (block + 1) * size] = np.frombuffer(zlib.decompress(packed), dtype=np.uint8)
    held = texts.sparkSession.sparkContext.broadcast(whole)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.column(2).to_numpy()
            kept = batch.filter(pa.array((held.value[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 == 1))
            yield kept.select(["t_id", "t_text"])

    return texts.where("t_id is not null").withColumn("at", place("t_id")).mapInArrow(run, "t_id long, t_text string")


def near_dups(docs: DataFrame, text: str = "text", percent: int = 80, size: int = SHINGLE_WORDS, k: int = COORDINATES, miss: float = MISS) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept`` for every row of ``docs``.

    Documents are linked if 100 * |A and B| >= percent * |A or B| for their sets of lower-cased (A-Z) word shingles; fewer words than a
    shingle are one shingle. ``component_id`` is the smallest doc_id reachable over links, ``kept`` marks the document of that id. Texts
    without words (null, empty, blank) are linked with nothing. Rows that repeat a doc_id count as one node with every text it has; rows
    without doc_id are kept and linked with nothing (null component). An empty table gives no rows. A link is lost only if its pair
    matches in fewer coordinates than ``match_threshold``: a chance of ``miss`` for a pair just at the limit, less for closer ones.
    """
    need = match_threshold(percent, k, miss)
    signed = materialise(signatures(docs, text, size, k), "signatures")
    known = signed.where("n_shingles > 0 and doc_id is not null")
    # written, so that both sides of the join are exchanges of their own and Spark can split a set that very many documents have
    classes = materialise(known.groupBy("s1", "s2", "n_shingles").agg(F.min("doc_id").alias("node")), "sets")
    member = classes.select(F.col("s1").alias("c1"), F.col("s2").alias("c2"), F.col("n_shingles").alias("cn"), "node")
    same = (F.col("s1") == F.col("c1")) & (F.col("s2") == F.col("c2")) & (F.col("n_shingles") == F.col("cn"))
    noded = materialise(signed.join(member, same & F.col("doc_id").isNotNull(), "left").select(*signed.columns, F.coalesce("node", "doc_id").alias("node")), "classes")
    leaders = noded.where("doc_id = node and n_shingles > 0").dropDuplicates(["doc_id", "s1", "s2"])
    posted = materialise(_postings(leaders, k, need), "postings")
    if posted.isEmpty():  # nobody shares a coordinate with anybody
        return noded.select("doc_id", "n_shingles", F.col("node").alias("component_id"), F.coalesce(F.col("doc_id") == F.col("node"), F.lit(True)).alias("kept"))
    in_reach = posted.select(F.col("node").alias("p_node")).distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("t_id"), F.col(f"`{text}`").cast("string").alias("t_text"))
    texts = materialise(_sieved(texts, in_reach).join(in_reach, F.col("t_id") == F.col("p_node"), "left_semi").distinct(), "texts")
    sigs = materialise(leaders.join(in_reach, F.col("doc_id") == F.col("p_node"), "left_semi").select(F.col("doc_id").alias("g_id"), "sig"), "sigs")

    def confirmed(pairs: DataFrame) -> DataFrame:
        left, right = (sigs.select(F.col("g_id").alias(f"g_{x}"), F.col("sig").alias(f"sig_{x}")) for x in "ab")
        matches = F.size(F.filter(F.zip_with("sig_a", "sig_b", lambda x, y: x == y), lambda m: m))
        alike = pairs.join(left, F.col("a") == F.col("g_a")).join(right, F.col("b") == F.col("g_b")).where(matches >= need).select("a", "b")
        # written, so that pairs of a popular pivot can be split in the joins with texts
        alike = materialise(alike.distinct(), "alike")
        left, right = (texts.select(F.col("t_id").alias(f"i_{x}"), F.col("t_text").alias(f"text_{x}")) for x in "ab")
        full = alike.join(right, F.col("b") == F.col("i_b")).select("a", "b", "text_b").join(left, F.col("a") == F.col("i_a")).select("a", "b", "text_a", "text_b")
        return full.mapInArrow(_confirmer(size, percent), "a long, b long")

    pivots = posted.groupBy(F.col("token").alias("t")).agg(F.min("node").alias("least"), F.max(F.struct("weight", F.col("node"))).alias("top"))
    star = posted.join(materialise(pivots, "pivots"), F.col("token") == F.col("t")).select("node", F.explode(F.array("least", "top.node")).alias("pivot")).where("node <> pivot")
    tried = materialise(star.select(F.least("node", "pivot").alias("a"), F.greatest("node", "pivot").alias("b")).distinct(), "pairs")
    links = materialise(confirmed(tried), "links")
    labels = materialise(components(links), "components")
    placed = posted.join(labels.select(F.col("node").alias("l_node"), "component"), F.col("node") == F.col("l_node"), "left").select("token", "node", F.coalesce("component", "node").alias("c"))
    split = placed.groupBy("token").agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low <> high").select("token")
    unsettled = materialise(placed.join(materialise(split, "split"), "token", "left_semi").groupBy("node").agg(F.min("c").alias("c")), "open")
    if not unsettled.isEmpty():
        more = materialise(confirmed(_pairs_across(unsettled, texts, percent, size).join(tried, ["a", "b"], "left_anti")), "links")
        if not more.isEmpty():
            labels = materialise(components(links.union(more)), "components")
    final = labels.select(F.col("node").alias("l_node"), F.col("component").alias("l_component"))
    out = noded.join(final, F.col("node") == F.col("l_node"), "left").withColumn("component_id", F.coalesce("l_component", "node"))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def deduplicated(docs: DataFrame, text: str = "text", percent: int = 80) -> DataFrame:
    """One document of each group of near duplicates: the one with the smallest doc_id, with all its columns.

    Where ids repeat, every row is a document of its own: rows of one id are dropped only as near duplicates, and of those with the
    smallest id the one of the smallest text hash stays. Rows without doc_id, and texts without words, all stay.
    """
    identified = docs.where("doc_id is not null")
    if identified.groupBy(F.col("doc_id").cast("long").alias("id")).count().where("count > 1").isEmpty():
        (k_id,) = unused(docs, "k_id")
        kept = near_dups(identified, text, percent).where("kept").select(F.col("doc_id").alias(k_id))
        out = identified.join(materialise(kept, "kept"), F.col("doc_id").cast("long") == F.col(k_id), "left_semi")
        return out.union(docs.where("doc_id is null"))
    rows = identified.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.monotonically_increasing_id().alias("at"))
    rows = materialise(rows, "rows")
    found = near_dups(rows.select(F.col("at").alias("doc_id"), F.col("row")[text].alias("text")), "text", percent).select(F.col("doc_id").alias("f_at"), "component_id")
    place = F.struct(F.col("row.doc_id").cast("long"), F.xxhash64(F.col("row")[text]), "at")
    first = rows.select("at", place.alias("place")).join(found, F.col("at") == F.col("f_at")).groupBy("component_id").agg(F.min("place").alias("least")).select(F.col("least.at").alias("k_at"))
    out = rows.join(materialise(first, "kept"), F.col("at") == F.col("k_at"), "left_semi").select("row.*")
    return out.union(docs.where("doc_id is null"))


def brute_force(docs: list[tuple[int, str | None]], percent: int, size: int = SHINGLE_WORDS) -> dict[int, tuple[int, int]]:
    """Reference for tests: doc_id -> set size, component."""
    sets = {i: shingle_set(t, size) for i, t in docs}
    root = {i: i for i in sets}

    def find(i: int) -> int:
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for n, i in enumerate(ids):
        for j in ids[n + 1 :]:
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {i: (len(sets[i]), find(i)) for i in ids}


def op7_near_dups(spark, sf_dir: str) -> DataFrame:
    return near_dups(table(spark, sf_dir, "documents").select("doc_id", "text"), percent=85)


def components_sql(docs: str, percent: int, prefix: str = "nd") -> str:
    """DuckDB text: ``{prefix}_comp(doc_id, n, comp)`` by full sets and min-label walks (a recursive CTE)."""
    return f"""
{prefix}_words AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS w FROM {docs}),
{prefix}_sets AS (SELECT doc_id, list_sort(list_distinct(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: md5_number(array_to_string(w[i:i+4], ' '))) WHEN len(w) > 0 THEN [md5_number(array_to_string(w, ' '))] ELSE [] END)) AS s FROM {prefix}_words),
{prefix}_class AS (SELECT s, min(doc_id) AS node, len(s) AS n FROM {prefix}_sets WHERE len(s) > 0 GROUP BY s),
{prefix}_post AS (SELECT node, n, unnest(s) AS h FROM {prefix}_class),
{prefix}_links AS (SELECT a.node AS a, b.node AS b FROM {prefix}_post a JOIN {prefix}_post b ON a.h = b.h AND a.node < b.node AND 100 * least(a.n, b.n) >= {percent} * greatest(a.n, b.n)
  GROUP BY a.node, b.node, a.n, b.n HAVING 100 * count(*) >= {percent} * (a.n + b.n - count(*))),
{prefix}_sym AS (SELECT a, b FROM {prefix}_links UNION ALL SELECT b, a FROM {prefix}_links),
{prefix}_walk(node, low) AS (SELECT node, node FROM {prefix}_class UNION SELECT s.b, w.low FROM {prefix}_walk w JOIN {prefix}_sym s ON s.a = w.node WHERE w.low < s.b),
{prefix}_low AS (SELECT node, min(low) AS low FROM {prefix}_walk GROUP BY node),
{prefix}_comp AS (SELECT s.doc_id, len(s.s) AS n, coalesce(l.low, s.doc_id) AS comp FROM {prefix}_sets s LEFT JOIN {prefix}_class c ON s.s = c.s AND len(s.s) > 0 LEFT JOIN {prefix}_low l ON l.node = c.node)"""


OP7_SQL = "WITH RECURSIVE " + components_sql("documents", 85) + " SELECT doc_id, n AS n_shingles, comp AS component_id, doc_id = comp AS kept FROM nd_comp"
