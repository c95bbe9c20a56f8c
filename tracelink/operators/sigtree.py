"""Max-weight signature tree: a bulk-loaded tree of boxes whose nodes also store the largest weight of each feature below them.

A tree is a list of levels of three relations: ``members(nid, child)``, ``nodes(nid, x1, y1, x2, y2)`` and ``sigs(nid, fid, w)``. Level 0
holds the objects (nid = oid), the last level one root.

Lower levels are built and searched by joins. Levels whose rows were counted and found few are finished on the driver, and are broadcast in
a search, so that the few nodes near the root are no hot join keys.
"""

from __future__ import annotations

import heapq
import json
import math
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import box_area, boxes_overlap, overlap_area, union_area
from ..session import global_rank, materialise
from .linking import boxes, dot_pairs, shared, top_k, verify

BOX = ["x1", "y1", "x2", "y2"]
#: Slabs are no larger than this, whatever the number of objects: greedy merging is quadratic in a slab.
SLAB_LIMIT = 20_000
#: Levels of so many nodes and (feature, weight) entries at most are built on the driver from there on.
LOCAL_NODES, LOCAL_ENTRIES = 4096, 1_000_000
#: A relation of a level with so many rows at most is sent to every executor in a search.
BROADCAST_ROWS = 500_000
#: Rows of frontier nodes beside their queries' features that are always joined; beyond, a level's postings are, if these make fewer rows.
JOINED = 2_000_000
#: Trees of so many entries, over all levels, may be searched best first from one copy in every worker.
COPIED_ENTRIES = 2_000_000


@dataclass
class Level:
    members: DataFrame
    nodes: DataFrame
    sigs: DataFrame
    #: rows of ``nodes`` and ``sigs``, counted when they are first asked for
    counted: dict = field(default_factory=dict)

    def rows(self, name: str) -> int:
        if name not in self.counted:
            self.counted[name] = getattr(self, name).count()
        return self.counted[name]

    def small(self, name: str) -> DataFrame:
        """A relation of the level, to be broadcast if it is known to be small."""
        df = getattr(self, name)
        return F.broadcast(df) if self.rows(name) <= BROADCAST_ROWS else df


@dataclass
class Tree:
    levels: list[Level]
    capacity: int
    criterion: str

    @property
    def height(self) -> int:
        return len(self.levels) - 1

    @property
    def entries(self) -> int:
        return sum(lv.rows("sigs") for lv in self.levels)


def aggregate(members: DataFrame, sigs: DataFrame) -> DataFrame:
    """Feature-wise maximum over the members of each node."""
    below = sigs.select(F.col("nid").alias("child"), "fid", "w")
    return members.join(below, "child").groupBy("nid", "fid").agg(F.max("w").alias("w"))


def aggregate_boxes(members: DataFrame, nodes: DataFrame) -> DataFrame:
    below = nodes.select(F.col("nid").alias("child"), *BOX)
    return members.join(below, "child").groupBy("nid").agg(F.min("x1").alias("x1"), F.min("y1").alias("y1"), F.max("x2").alias("x2"), F.max("y2").alias("y2"))


def enlargement(a: set, b: set) -> int:
    """Features that a node of ``a`` gains when ``b`` joins it: those of ``b`` that ``a`` lacks."""
    return len(b - a)


def _united(a: tuple, b: tuple) -> tuple:
    return min(a[0], b[0]), min(a[1], b[1]), max(a[2], b[2]), max(a[3], b[3])


def _area(b: tuple) -> float:
    return (b[2] - b[0]) * (b[3] - b[1])


def _shared_area(a: tuple, b: tuple) -> float:
    return max(0.0, min(a[2], b[2]) - max(a[0], b[0])) * max(0.0, min(a[3], b[3]) - max(a[1], b[1]))


def merge_by_common(ids: list, features: dict, capacity: int, boxes: dict | None = None) -> list[list]:
    """Greedy nodes over spatially ordered elements.

    A node starts with the first free element. The next one is the element that shares most features with the node so far (its aggregate
    grows least); of several, the one that makes the node's box grow least, then the one by which the box overlaps the nodes made before
    least, then the first in order. Where nobody shares a feature, the next ``capacity`` free elements in order compete by area.
    """
    holders: dict = {}
    for i in ids:
        for f in features[i]:
            holders.setdefault(f, []).append(i)
    place = {i: n for n, i in enumerate(ids)}
    free = dict.fromkeys(ids)
    nodes: list[list] = []
    closed: list[tuple] = []
    while free:
        seed = next(iter(free))
        del free[seed]
        node, have = [seed], set()
        box = boxes[seed] if boxes else None
        common: Counter = Counter()
        fresh = features[seed]
        while len(node) < capacity and free:
            for f in fresh - have:
                for i in holders[f]:
                    if i in free:
                        common[i] += 1
            have |= fresh
            rivals = [i for i in common if i in free]
            if rivals:
                most = max(common[i] for i in rivals)
                rivals = [i for i in rivals if common[i] == most]
            else:
                rivals = [i for _, i in zip(range(capacity), free, strict=False)]
            if boxes and len(rivals) > 1:
                growth = {i: round(_area(_united(box, boxes[i])) - _area(box), 9) for i in rivals}
                least = min(growth.values())
                rivals = [i for i in rivals if growth[i] == least]
                if len(rivals) > 1:
                    over = {i: round(sum(_shared_area(_united(box, boxes[i]), c) for c in closed), 9) for i in rivals}
                    least = min(over.values())
                    rivals = [i for i in rivals if over[i] == least]
            best = min(rivals, key=place.__getitem__)
            del free[best]
            node.append(best)
            fresh = features[best]
            box = _united(box, boxes[best]) if boxes else None
        nodes.append(node)
        closed.append(box)
    return nodes


def _slabs(n: int, capacity: int) -> int:
    leaves = math.ceil(n / capacity)
    return min(max(capacity, math.ceil(n / math.sqrt(leaves))), max(capacity, SLAB_LIMIT))


def _merged(group: pd.DataFrame, capacity: int, per: int) -> pd.DataFrame:
    """Nodes of one slab (``slab, s, child, fids``, box) by common features."""
    group = group.sort_values("s")
    held = {c: set(f) if f is not None else set() for c, f in zip(group["child"], group["fids"], strict=True)}
    box = dict(zip(group["child"], group[BOX].itertuples(index=False, name=None), strict=True))
    made = merge_by_common(group["child"].tolist(), held, capacity, box)
    base = int(group["slab"].iloc[0]) * per
    return pd.DataFrame([(base + i, c) for i, node in enumerate(made) for c in node], columns=["nid", "child"])


def _assign(nodes: DataFrame, sigs: DataFrame, n: int, capacity: int, criterion: str) -> DataFrame:
    """``nid, child`` of the next level: slabs along x, then along y, nodes of ``capacity`` inside a slab."""
    slab = _slabs(n, capacity)
    per = math.ceil(slab / capacity)
    centred = nodes.select(F.col("nid").alias("child"), ((F.col("x1") + F.col("x2")) / 2).alias("cx"), ((F.col("y1") + F.col("y2")) / 2).alias("cy"), *BOX)
    ranked = global_rank(centred, "cx", ["cy", "child"], "r").withColumn("slab", F.expr(f"r div {slab}"))
    ordered = ranked.withColumn("s", F.row_number().over(Window.partitionBy("slab").orderBy("cy", "cx", "child")) - 1)
    if criterion == "spatial":
        return ordered.select((F.col("slab") * per + F.expr(f"s div {capacity}")).alias("nid"), "child")
    # a slab has SLAB_LIMIT nodes at most
    features = sigs.groupBy(F.col("nid").alias("child")).agg(F.sort_array(F.collect_list("fid")).alias("fids"))
    joined = ordered.select("slab", "s", "child", *BOX).join(features, "child", "left")
    return joined.groupBy("slab").applyInPandas(lambda group: _merged(group, capacity, per), "nid long, child long")


def _assign_local(nodes: pd.DataFrame, sigs: pd.DataFrame, capacity: int, criterion: str) -> pd.DataFrame:
    """``_assign`` for few nodes."""
    slab = _slabs(len(nodes), capacity)
    per = math.ceil(slab / capacity)
    rows = nodes.rename(columns={"nid": "child"}).assign(cx=(nodes["x1"] + nodes["x2"]) / 2, cy=(nodes["y1"] + nodes["y2"]) / 2)
    rows = rows.sort_values(["cx", "cy", "child"])
    rows["slab"] = np.arange(len(rows)) // slab
    rows = rows.sort_values(["slab", "cy", "cx", "child"])
    rows["s"] = rows.groupby("slab").cumcount()
    if criterion == "spatial":
        return pd.DataFrame({"nid": rows["slab"] * per + rows["s"] // capacity, "child": rows["child"]})
    fids = sigs.groupby("nid")["fid"].agg(list)
    rows["fids"] = [fids.get(c) for c in rows["child"]]
    return pd.concat([_merged(g, capacity, per) for _, g in rows.groupby("slab")])


def _finish_local(nodes: DataFrame, sigs: DataFrame, capacity: int, criterion: str) -> list[Level]:
    """The levels above a level of few nodes and entries, made on the driver."""
    spark, n, w = nodes.sparkSession, nodes.toPandas(), sigs.toPandas()
    fid_type = sigs.schema["fid"].dataType.simpleString()
    out = []
    while len(n) > 1:
        members = _assign_local(n, w, capacity, criterion).astype("int64")
        w = members.merge(w.rename(columns={"nid": "child"}), on="child").groupby(["nid", "fid"], as_index=False)["w"].max()
        n = members.merge(n.rename(columns={"nid": "child"}), on="child").groupby("nid", as_index=False).agg(x1=("x1", "min"), y1=("y1", "min"), x2=("x2", "max"), y2=("y2", "max"))
        frames = [spark.createDataFrame(members, "nid long, child long"), spark.createDataFrame(n, "nid long, x1 double, y1 double, x2 double, y2 double"), spark.createDataFrame(w, f"nid long, fid {fid_type}, w double")]
        out.append(Level(*frames, {"members": len(members), "nodes": len(n), "sigs": len(w)}))
    return out


def build(d: DataFrame, place: DataFrame, capacity: int = 16, criterion: str = "common") -> Tree:
    """Bulk load over candidates ``d(oid, fid, wd)`` with places (pid, x, y).

    'spatial' cuts slabs into runs of ``capacity``; 'common' fills nodes by common features, area and overlap. Every level is written to the
    shared folder, but the last ones, of LOCAL_NODES nodes and LOCAL_ENTRIES entries at most. Objects without features are not indexed.
    """
    sigs = materialise(d.select(F.col("oid").alias("nid"), "fid", F.col("wd").alias("w")), "tree-sigs")
    flat = boxes(sigs.select(F.lit("D").alias("side"), F.col("nid").alias("oid"), "fid", "w"), place)
    nodes = materialise(flat.select(F.col("oid").alias("nid"), *BOX), "tree-nodes")
    levels = [Level(nodes.select("nid", F.col("nid").alias("child")), nodes, sigs)]
    while (n := levels[-1].rows("nodes")) > 1:
        if n <= LOCAL_NODES and levels[-1].rows("sigs") <= LOCAL_ENTRIES:
            levels += _finish_local(nodes, sigs, capacity, criterion)
            break
        members = materialise(_assign(nodes, sigs, n, capacity, criterion), "tree-members")
        sigs, nodes = materialise(aggregate(members, sigs), "tree-sigs"), materialise(aggregate_boxes(members, nodes), "tree-nodes")
        levels.append(Level(members, nodes, sigs))
    return Tree(levels, capacity, criterion)


def save(tree: Tree, path: str) -> None:
    """Write the relations of every level and a manifest of one row (capacity, criterion, height)."""
    for i, lv in enumerate(tree.levels):
        for name in ("members", "nodes", "sigs"):
            getattr(lv, name).write.mode("overwrite").parquet(f"{path}/{name}/level={i}")
    row = json.dumps({"capacity": tree.capacity, "criterion": tree.criterion, "height": tree.height})
    tree.levels[0].nodes.sparkSession.createDataFrame([(row,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def load(spark, path: str) -> Tree:
    known = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    levels = [Level(*[spark.read.parquet(f"{path}/{name}/level={i}") for name in ("members", "nodes", "sigs")]) for i in range(known["height"] + 1)]
    return Tree(levels, known["capacity"], known["criterion"])


def size(tree: Tree) -> DataFrame:
    """``level, nodes, entries``: stored nodes and (feature, weight) entries."""
    parts = [lv.nodes.agg(F.count(F.lit(1)).alias("nodes")).crossJoin(lv.sigs.agg(F.count(F.lit(1)).alias("entries"))).select(F.lit(i).alias("level"), "nodes", "entries") for i, lv in enumerate(tree.levels)]  # single rows
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


def knn_join(q: DataFrame, tree: Tree, k: int, place: DataFrame, use_mbr: bool = True, use_bound: bool = True, work: list | None = None) -> DataFrame:
    """k nearest neighbours of all queries at once, level by level.

    Each query first goes greedily down to its best leaf node; the k-th similarity there is a floor of its answer. Then the tree is
    walked from the root: a child stays if its box meets the query's box and its bound (dot product with the node's largest weights)
    reaches the floor. Objects that stay are scored exactly. Queries are dealt by qid once. Frontier nodes are joined with their children's
    entries by node and feature, so that only children with a feature of the query come up; where that would make more rows than the
    postings of the whole level, all its bounds are summed, and of those that reach the floor the children of frontier nodes are kept. Rows
    kept at each level go to ``work`` if given.
    """
    top = tree.height
    if not top:
        return top_k(dot_pairs(q, tree.levels[0].sigs.select(F.col("nid").alias("oid"), "fid", F.col("w").alias("wd"))), k)
    box = boxes(q.select(F.lit("Q").alias("side"), F.col("qid").alias("oid"), "fid", F.col("wq").alias("w")), place).select(F.col("oid").alias("qid"), *[F.col(c).alias(f"q_{c}") for c in BOX])
    q = materialise(q.select("qid", "fid", "wq").join(box, "qid"), "queries").repartition("qid")
    box = q.select("qid", *[f"q_{c}" for c in BOX]).distinct()
    features = q.select("fid").distinct()
    queries = box.count()
    per_query = q.count() / max(1, queries)

    def entries(level: int) -> DataFrame:
        """Weights of a level's nodes; of a large level only those of features that some query has."""
        below = tree.levels[level]
        return below.small("sigs") if below.rows("sigs") <= BROADCAST_ROWS else below.sigs.join(features, "fid", "left_semi")

    sizes: dict = {}

    def size_of(level: int) -> int:
        """Rows that the postings of a level make."""
        if level not in sizes:
            sizes[level] = shared(q, entries(level), ["fid"])
        return sizes[level]

    def reaching(bounds: DataFrame, floor: DataFrame | None) -> DataFrame:
        return bounds if floor is None else bounds.join(floor, "qid", "left").where(F.col("bound") >= F.coalesce("floor", F.lit(0.0)) - 1e-9).drop("floor")

    def scored(frontier: DataFrame, level: int, bound: bool = True, floor: DataFrame | None = None, rows: int | None = None) -> DataFrame:
        """Children of frontier nodes (of level + 1; ``rows`` of them) that pass, with their bounds."""
        above, below = tree.levels[level + 1], tree.levels[level]
        kids = above.members.select(F.col("nid").alias("parent"), F.col("child").alias("nid"))
        kids = F.broadcast(kids) if above.rows("members") <= BROADCAST_ROWS else kids
        held = frontier.select("qid", F.col("nid").alias("parent"))

        def met(step: DataFrame) -> DataFrame:
            if not use_mbr:
                return step
            return step.join(box, "qid").join(below.small("nodes").select("nid", *BOX), "nid").where(boxes_overlap("q_", "")).select(*step.columns)

        if not bound:
            return met(held.join(kids, "parent").select("qid", "nid")).withColumn("bound", F.lit(1e9))
        posted = entries(level).join(kids, "nid").select("parent", "nid", "fid", "w")
        posted = F.broadcast(posted) if below.rows("sigs") <= BROADCAST_ROWS else posted
        total = F.sum(F.col("wq") * F.col("w")).alias("bound")
        if rows is None or rows * per_query <= JOINED or rows * per_query <= size_of(level):
            pairs = held.join(q.select("qid", "fid", "wq"), "qid").join(posted, ["parent", "fid"])
            return met(reaching(pairs.groupBy("qid", "nid").agg(total), floor))
        pairs = q.select("qid", "fid", "wq").join(posted, "fid").select("qid", "parent", "nid", "wq", "w").repartition("qid")
        kept = reaching(pairs.groupBy("qid", "parent", "nid").agg(total), floor)
        return met(kept.join(held, ["qid", "parent"], "left_semi").select("qid", "nid", "bound"))

    start = box.select("qid").crossJoin(F.broadcast(tree.levels[top].nodes.select("nid")))  # one root
    floor = None
    if use_bound:
        best = start
        for level in range(top - 1, 0, -1):
            best = top_k(scored(best, level).select("qid", F.col("nid").alias("oid"), F.col("bound").alias("sim")), 1).select("qid", F.col("oid").alias("nid"))
        seen = top_k(scored(best, 0).select("qid", F.col("nid").alias("oid"), F.col("bound").alias("sim")), k)
        floor = materialise(seen.where(F.col("rnk") == k).select("qid", F.round("sim", 9).alias("floor")), "floor")
    frontier, rows = start, queries
    for level in range(top - 1, -1, -1):
        bounded = use_bound or level == 0
        frontier = scored(frontier, level, bounded, floor, rows).select("qid", "nid", "bound")
        if level or work is not None:
            frontier = materialise(frontier, "frontier")
            rows = frontier.count()
        if work is not None:
            work.append((level, rows))
    return top_k(frontier.select("qid", F.col("nid").alias("oid"), F.col("bound").alias("sim")), k)


def knn(q: DataFrame, tree: Tree, k: int, place: DataFrame) -> DataFrame:
    """The search that fits the tree: best first on a copy in every worker if its counted entries are few, else by joins; same neighbours."""
    if tree.height and tree.entries <= COPIED_ENTRIES:
        return search_local(q, tree, k, place).select("qid", "oid", "sim", "rnk")
    return knn_join(q, tree, k, place)


# --- local form: small trees, counters, reference ----------------------------------------------------------------------------------


@dataclass
class LocalNode:
    nid: int
    box: tuple
    sig: dict
    children: list
    level: int


def local(tree: Tree, most_entries: int = 4 * COPIED_ENTRIES) -> LocalNode:
    """The tree on the driver; refuses trees of more entries than ``most_entries``."""
    if tree.entries > most_entries:
        raise ValueError("the tree is too large for a local copy")
    below: dict = {}
    for i, lv in enumerate(tree.levels):
        held, kids = {}, {}
        frame = lv.sigs.toPandas()
        for n, f, w in zip(frame["nid"].tolist(), frame["fid"].tolist(), frame["w"].tolist(), strict=True):
            held.setdefault(n, {})[f] = w
        if i:
            frame = lv.members.toPandas()
            for n, c in zip(frame["nid"].tolist(), frame["child"].tolist(), strict=True):
                kids.setdefault(n, []).append(below[c])
        below = {n: LocalNode(n, tuple(b), held.get(n, {}), sorted(kids.get(n, []), key=lambda c: c.nid), i) for n, *b in lv.nodes.select("nid", *BOX).toPandas().itertuples(index=False, name=None)}
    return next(iter(below.values()))


def _meets(a: tuple, b: tuple) -> bool:
    return a[0] <= b[2] and b[0] <= a[2] and a[1] <= b[3] and b[1] <= a[3]


def best_first(root: LocalNode, sig: dict, box: tuple, k: int, use_mbr: bool = True, use_bound: bool = True) -> tuple[list[tuple[float, int]], dict]:
    """Neighbours of one query by a priority queue over bounds, with counters of the work."""
    work = {"popped": 0, "scored": 0, "cut_by_box": 0, "cut_by_bound": 0}
    found: list[tuple[float, int]] = []
    queue = [(-float("inf"), 0, 0, root)]
    tick, kth = 0, 0.0
    while queue:
        minus, _, _, node = heapq.heappop(queue)
        if use_bound and len(found) >= k and round(-minus, 9) < kth:
            break
        work["popped"] += 1
        if not node.level:
            if round(-minus, 9) > 0:
                found.append((round(-minus, 9), node.nid))
                kth = heapq.nlargest(k, (f[0] for f in found))[-1] if len(found) >= k else 0.0
            continue
        for c in node.children:
            if use_mbr and not _meets(c.box, box):
                work["cut_by_box"] += 1
                continue
            work["scored"] += 1
            bound = sum(w * c.sig.get(f, 0.0) for f, w in sig.items())
            if use_bound and round(bound, 9) < (kth if len(found) >= k else 1e-9):
                work["cut_by_bound"] += 1
                continue
            tick += 1
            heapq.heappush(queue, (-bound if use_bound or not c.level else -1e9, c.level, tick, c))
    return sorted(found, key=lambda e: (-e[0], e[1]))[:k], work


def search_local(q: DataFrame, tree: Tree | LocalNode, k: int, place: DataFrame, use_mbr: bool = True, use_bound: bool = True) -> DataFrame:
    """Best-first search of every query on a broadcast copy of a small tree; also returns counters a query."""
    held = q.sparkSession.sparkContext.broadcast(local(tree) if isinstance(tree, Tree) else tree)  # refused beyond a bound of entries
    box = boxes(q.select(F.lit("Q").alias("side"), F.col("qid").alias("oid"), "fid", F.col("wq").alias("w")), place)
    packed = q.groupBy("qid").agg(F.collect_list(F.struct("fid", "wq")).alias("s")).join(box.select(F.col("oid").alias("qid"), *BOX), "qid")
    packed = packed.select("qid", F.col("s.fid").alias("fids"), F.col("s.wq").alias("ws"), *BOX)

    def run(batches):
        for batch in batches:
            rows = []
            for r in batch.itertuples(index=False):
                near, work = best_first(held.value, dict(zip(r.fids.tolist(), r.ws.tolist(), strict=True)), (r.x1, r.y1, r.x2, r.y2), k, use_mbr, use_bound)
                rows += [(r.qid, o, s, i + 1, work["popped"], work["scored"], work["cut_by_box"], work["cut_by_bound"]) for i, (s, o) in enumerate(near)]
            yield pd.DataFrame(rows, columns=["qid", "oid", "sim", "rnk", "popped", "scored", "cut_by_box", "cut_by_bound"])

    return packed.mapInPandas(run, "qid long, oid long, sim double, rnk int, popped long, scored long, cut_by_box long, cut_by_bound long")


# --- updates -----------------------------------------------------------------------------------------------------------------------


def _routes(tree: Tree, sigs: DataFrame, nodes: DataFrame, criterion: str) -> dict[int, DataFrame]:
    """``o, at``: the node of each level that a new object goes to, by level."""
    mine = nodes.select(F.col("nid").alias("o"), *[F.col(c).alias(f"o_{c}") for c in BOX])
    where = mine.select("o").crossJoin(F.broadcast(tree.levels[-1].nodes.select(F.col("nid").alias("at"))))  # one root
    paths = {tree.height: where}
    for level in range(tree.height - 1, 0, -1):
        lv = tree.levels[level]
        kids = tree.levels[level + 1].small("members").select(F.col("nid").alias("at"), F.col("child").alias("c"))
        if tree.levels[level + 1].rows("members") <= BROADCAST_ROWS:
            kids = F.broadcast(kids)
        boxed = lv.small("nodes").select(F.col("nid").alias("c"), *[F.col(x).alias(f"c_{x}") for x in BOX])
        options = where.join(kids, "at").join(boxed, "c").join(mine, "o")
        growth = F.round(union_area("c_", "o_") - box_area("c_"), 9)
        if criterion == "common":
            met = where.join(kids, "at").join(sigs.select(F.col("nid").alias("o"), "fid"), "o").join(lv.small("sigs").select(F.col("nid").alias("c"), "fid"), ["c", "fid"])
            options = options.join(met.groupBy("o", "c").agg(F.count(F.lit(1)).alias("common")), ["o", "c"], "left")
            options = options.withColumn("rating", F.struct((-F.coalesce("common", F.lit(0))).alias("a"), growth.alias("b")))
        else:
            options = options.withColumn("rating", F.struct(F.lit(0).alias("a"), growth.alias("b")))
        own = Window.partitionBy("o")
        options = options.withColumn("best", F.min("rating").over(own)).where("rating = best").withColumn("ties", F.count(F.lit(1)).over(own))
        options = materialise(options.select("o", "at", "c", "ties", *[f"o_{x}" for x in BOX], *[f"c_{x}" for x in BOX]), "options")
        # overlap with siblings decides among children that are equal so far
        grown = [f(F.col(f"c_{x}"), F.col(f"o_{x}")).alias(f"u_{x}") for x, f in zip(BOX, (F.least, F.least, F.greatest, F.greatest), strict=True)]
        tied = options.where("ties > 1").select("o", "at", "c", *[f"c_{x}" for x in BOX], *grown)
        siblings = kids.select("at", F.col("c").alias("s")).join(lv.small("nodes").select(F.col("nid").alias("s"), *[F.col(x).alias(f"s_{x}") for x in BOX]), "s")
        over = tied.join(siblings, "at").where("c <> s").groupBy("o", "c").agg(F.round(F.sum(overlap_area("u_", "s_") - overlap_area("c_", "s_")), 9).alias("more"))
        rated = options.select("o", "c").join(over, ["o", "c"], "left").select("o", F.struct(F.coalesce("more", F.lit(0.0)).alias("l"), F.col("c").alias("n")).alias("rating"))
        where = materialise(rated.groupBy("o").agg(F.min("rating").alias("r")).select("o", F.col("r.n").alias("at")), "route")
        paths[level] = where
    return paths


def _split(members: DataFrame, nodes: DataFrame, sigs: DataFrame, below: Level, capacity: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame | None]:
    """Divide nodes of more than ``capacity`` members along the longer side of their box into even parts; also ``nid, fresh`` of the new nodes."""
    over = materialise(members.groupBy("nid").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > capacity), "overfull")
    if over.isEmpty():
        return members, nodes, sigs, None
    stride = int(nodes.agg(F.max("nid")).first()[0]) + 1
    wide = nodes.join(over, "nid").select("nid", "n", ((F.col("x2") - F.col("x1")) >= (F.col("y2") - F.col("y1"))).alias("by_x"))
    kids = members.join(wide, "nid").join(below.nodes.select(F.col("nid").alias("child"), *BOX), "child")
    centre = F.when(F.col("by_x"), F.col("x1") + F.col("x2")).otherwise(F.col("y1") + F.col("y2"))
    parts = F.ceil(F.col("n") / capacity)
    rank = F.row_number().over(Window.partitionBy("nid").orderBy("centre", "child")) - 1  # a node's members: its capacity and what came
    dealt = kids.withColumn("centre", centre).withColumn("part", F.floor(rank * parts / F.col("n")))
    dealt = materialise(dealt.select(F.col("nid").alias("old"), (F.col("nid") + F.col("part") * stride).alias("nid"), "child"), "divided")
    moved = dealt.select("nid", "child")
    members = materialise(members.join(over.select("nid"), "nid", "left_anti").select("nid", "child").union(moved), "tree-members")
    nodes = materialise(nodes.join(over.select("nid"), "nid", "left_anti").union(aggregate_boxes(moved, below.nodes)), "tree-nodes")
    sigs = materialise(sigs.join(over.select("nid"), "nid", "left_anti").union(aggregate(moved, below.sigs).select("nid", "fid", "w")), "tree-sigs")
    return members, nodes, sigs, dealt.where("nid <> old").select(F.col("old").alias("nid"), F.col("nid").alias("fresh")).distinct()


def insert(tree: Tree, d: DataFrame, place: DataFrame, criterion: str = "common", overflow: str = "grow") -> Tree:
    """Add objects ``d(oid, fid, wd)``: each goes down to the most attractive child, nodes on its path grow.

    'common' prefers the child with most common features, then least growth of area, then least growth of the overlap with its siblings,
    then the lowest node; 'spatial' leaves out the first. All objects of a batch are routed over the tree as it was. With 'grow' nodes may
    exceed the capacity (rebuild when ``degraded``), with 'split' overfull nodes are divided on every level up to a new root.
    """
    sigs = materialise(d.select(F.col("oid").alias("nid"), "fid", F.col("wd").alias("w")), "new-sigs")
    nodes = boxes(sigs.select(F.lit("D").alias("side"), F.col("nid").alias("oid"), "fid", "w"), place)
    nodes = materialise(nodes.select(F.col("oid").alias("nid"), *BOX), "new-nodes")
    paths = _routes(tree, sigs, nodes, criterion)
    levels = [Level(tree.levels[0].members.union(nodes.select("nid", F.col("nid").alias("child"))), tree.levels[0].nodes.union(nodes), tree.levels[0].sigs.union(sigs))]
    fresh = None
    for level in range(1, tree.height + 1):
        lv, path = tree.levels[level], paths[level].select(F.col("at").alias("nid"), F.col("o").alias("child"))
        members = lv.members.union(path.select("nid", "child")) if level == 1 else lv.members
        if fresh is not None:
            members = members.union(lv.members.join(fresh.select(F.col("nid").alias("child"), "fresh"), "child").select("nid", F.col("fresh").alias("child")))
        grown = lv.sigs.union(aggregate(path, sigs).select("nid", "fid", "w")).groupBy("nid", "fid").agg(F.max("w").alias("w"))
        wide = lv.nodes.union(aggregate_boxes(path, nodes)).groupBy("nid").agg(F.min("x1").alias("x1"), F.min("y1").alias("y1"), F.max("x2").alias("x2"), F.max("y2").alias("y2"))
        parts = materialise(members, "tree-members"), materialise(wide, "tree-nodes"), materialise(grown, "tree-sigs")
        fresh = None
        if overflow == "split":
            *parts, fresh = _split(*parts, levels[-1], tree.capacity)
        levels.append(Level(*parts))
    while levels[-1].rows("nodes") > 1:  # the root was divided
        last = levels[-1]
        ids = last.nodes.select(F.floor((F.row_number().over(Window.orderBy("x1", "y1", "nid")) - 1) / tree.capacity).alias("nid"), F.col("nid").alias("child"))  # parts of one root
        members = materialise(ids, "tree-members")
        levels.append(Level(members, materialise(aggregate_boxes(members, last.nodes), "tree-nodes"), materialise(aggregate(members, last.sigs), "tree-sigs")))
    return Tree(levels, tree.capacity, tree.criterion)


def degraded(tree: Tree, most_growth: float = 1.5) -> bool:
    """Whether a leaf node holds more than ``most_growth`` times the capacity: time for a bulk rebuild."""
    fullest = tree.levels[1].members.groupBy("nid").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] if tree.height else 0
    return (fullest or 0) > most_growth * tree.capacity


def maintain(tree: Tree, place: DataFrame, most_growth: float = 1.5) -> Tree:
    """The tree, bulk loaded anew if degraded."""
    if not degraded(tree, most_growth):
        return tree
    return build(tree.levels[0].sigs.select(F.col("nid").alias("oid"), "fid", F.col("w").alias("wd")), place, tree.capacity, tree.criterion)


def build_by_insert(objects: list[tuple[int, tuple, dict]], capacity: int) -> LocalNode:
    """Yardstick: a tree grown one object at a time on the driver; full nodes split along the longer side of their centres."""
    root = LocalNode(0, (math.inf, math.inf, -math.inf, -math.inf), {}, [], 1)
    numbers = iter(range(1, 1 << 62))

    def grow(node: LocalNode, box: tuple, sig: dict) -> None:
        node.box = _united(node.box, box)
        for f, w in sig.items():
            node.sig[f] = max(node.sig.get(f, 0.0), w)

    def remade(children: list, level: int) -> LocalNode:
        node = LocalNode(next(numbers), (math.inf, math.inf, -math.inf, -math.inf), {}, children, level)
        for c in children:
            grow(node, c.box, c.sig)
        return node

    def attractive(node: LocalNode, box: tuple, sig: dict) -> LocalNode:
        rated = [(-len(c.sig.keys() & sig.keys()), round(_area(_united(c.box, box)) - _area(c.box), 9), c) for c in node.children]
        best = min(r[:2] for r in rated)
        tied = [c for *r, c in rated if tuple(r) == best]
        if len(tied) == 1:
            return tied[0]
        more = lambda c: round(sum(_shared_area(_united(c.box, box), s.box) - _shared_area(c.box, s.box) for s in node.children if s is not c), 9)
        return min(tied, key=lambda c: (more(c), c.nid))

    for oid, box, sig in objects:
        leaf = LocalNode(oid, box, dict(sig), [], 0)
        path, node = [root], root
        grow(root, box, sig)
        while node.level > 1:
            node = attractive(node, box, sig)
            grow(node, box, sig)
            path.append(node)
        node.children.append(leaf)
        for i in range(len(path) - 1, -1, -1):
            node = path[i]
            if len(node.children) <= capacity:
                break
            axis = 0 if node.box[2] - node.box[0] >= node.box[3] - node.box[1] else 1
            ordered = sorted(node.children, key=lambda c: (c.box[axis] + c.box[axis + 2], c.nid))  # noqa: B023
            half = len(ordered) // 2
            a, b = remade(ordered[:half], node.level), remade(ordered[half:], node.level)
            if i:
                path[i - 1].children.remove(node)
                path[i - 1].children += [a, b]
            else:
                root = remade([a, b], node.level + 1)
    return root


def objects_of(d: DataFrame, place: DataFrame, most_entries: int = COPIED_ENTRIES) -> list[tuple[int, tuple, dict]]:
    """Objects ``(oid, box, signature)`` on the driver in order of id; refuses more entries than ``most_entries``."""
    if d.limit(most_entries + 1).count() > most_entries:
        raise ValueError("too many entries for a tree that grows on the driver")
    sigs: dict = {}
    for o, f, w in d.select("oid", "fid", "wd").toPandas().itertuples(index=False, name=None):
        sigs.setdefault(o, {})[f] = w
    box = boxes(d.select(F.lit("D").alias("side"), "oid", "fid", F.col("wd").alias("w")), place).toPandas()
    return [(o, b, sigs[o]) for o, b in sorted((int(r[0]), tuple(r[1:])) for r in box[["oid", *BOX]].itertuples(index=False, name=None))]


def local_size(root: LocalNode) -> list[tuple[int, int, int]]:
    """``level, nodes, entries`` of a tree on the driver, from the objects up."""
    found: dict[int, list[int]] = {}
    todo = [root]
    while todo:
        node = todo.pop()
        held = found.setdefault(node.level, [0, 0])
        held[0] += 1
        held[1] += len(node.sig)
        todo += node.children
    return [(level, *found[level]) for level in sorted(found)]


def verify_knn(knn: DataFrame, q: DataFrame, d: DataFrame) -> DataFrame:
    """Similarities of a list recomputed from the signatures."""
    return verify(knn.select("qid", "oid"), q, d)
