"""Descending the tree for many filters at once, a level at a time; and reconstruction, the pruned sweep."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.theory import estimate_overlap, estimate_size, overlap_status
from ..plans.tree import Tree
from ..sources.scratch import stored
from .filters import BROADCAST_BYTES, check_pairs, ones
from .whole import all_of, dense, parts_for, positives, spread

#: Weight that "floored" gives to a live branch whose estimate is lower.
FLOOR = 0.5
#: What a tree's word takes in a broadcast, at most; and the deepest leaves that a set lists as bits beside what it holds.
WORD_BYTES, MOST_BITS = 64, 10
#: Nodes that a job may look at for each level it takes besides the first, and the most levels it takes.
BLOCK_ROWS, MOST_LEVELS = 200_000, 5


def start_level(tree: Tree, fill: float = 0.95) -> int:
    """First level whose nodes are not nearly full by formula: above it an AND tells nothing."""
    spec, level = tree.spec, 0
    while level < tree.depth and 1 - (1 - 1 / spec.m) ** (spec.k * tree.domain / 2**level) > fill:
        level += 1
    return level


@dataclass(frozen=True)
class Live:
    """marks: set_id, level, idx, both, weight, for every node reached with a live branch above; live tells if it is one."""

    start: int
    marks: DataFrame
    sizes: DataFrame


def _weighed(rows: DataFrame, tree: Tree, weights: str, tau: float | None) -> DataFrame:
    args = F.col("node_ones"), F.col("ones"), F.col("both")
    estimate = estimate_overlap(*args, tree.spec.m, tree.spec.k)
    status = overlap_status(*args, tree.spec.m)
    prior = F.coalesce(F.col("n_hat"), F.lit(1.0)) * F.col("occupied") / F.lit(float(tree.domain))
    value = F.when(status.isin("saturated", "undefined"), prior).otherwise(estimate)
    touched = F.col("both") >= 1
    if weights == "prior":
        return rows.withColumn("weight", prior).withColumn("live", touched)
    if weights == "floored":
        return rows.withColumn("weight", F.greatest(value, F.lit(FLOOR))).withColumn("live", touched)
    keep = touched if tau is None else touched & (status.isin("saturated", "undefined") | (value >= tau))
    return rows.withColumn("weight", F.greatest(value, F.lit(0.0))).withColumn("live", keep)


def _block(frontier: int, left: int) -> int:
    """How many levels to look at in one job: more while few nodes are live."""
    levels = 1
    while levels < min(left, MOST_LEVELS) and frontier << (levels + 1) <= BLOCK_ROWS:
        levels += 1
    return levels


def mark(words: DataFrame, tree: Tree, weights: str = "floored", tau: float | None = None, start: int | None = None) -> Live:
    """Live nodes per set and level. A node is entered if its parent is live; a node without a common bit is never live, which
    loses no member. tau: nodes with a smaller estimate are not live either, which may.

    A job takes several levels while the frontier is thin. Nodes looked at meet their set's words first and the tree's words by
    (level, node, word) then, so neither the root nor any other node is a key that all sets share. Where most nodes of these levels
    are looked at, the tree's words go to the sets' words instead, and bits are counted before anything moves. Nodes below a dead
    one of the same job are dropped at its end."""
    start = 0 if start is None else min(start, tree.depth)
    sizes = stored(ones(words).withColumn("n_hat", estimate_size(F.col("ones"), tree.spec.m, tree.spec.k)), "sizes")
    frontier, out = sizes.select("set_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit((1 << start) - 1).cast("long"))).alias("idx")), None
    held = sizes.count()
    asked, many = words.withColumnRenamed("bits", "asked"), held << start
    level = start
    while level <= tree.depth:
        last = min(tree.depth, level + _block(many, tree.depth - level + 1) - 1)
        # Nodes below a frontier node, numbered as in a heap: 1 is the node itself.
        below = F.explode(F.sequence(F.lit(1), F.lit((1 << (last - level + 1)) - 1)))
        depth = F.floor(F.log2("heap") + 1e-9).cast("int")
        seen = frontier.withColumnRenamed("idx", "top").withColumn("heap", below).withColumn("down", depth)
        seen = seen.select("set_id", "top", "heap", (F.lit(level) + F.col("down")).alias("level"), (F.call_function("shiftleft", F.col("top"), F.col("down")) + F.col("heap") - F.call_function("shiftleft", F.lit(1), F.col("down"))).alias("idx"))
        node = tree.nodes.filter(F.col("level").between(level, last)).select("level", "idx", F.col("ones").alias("node_ones"), "occupied")
        seen = seen.join(node, ["level", "idx"])
        at = tree.words.filter(F.col("level").between(level, last)).select("level", "idx", "word_no", "bits")
        few = node.count()
        if few * held <= 4 * many << (last - level + 1) and few * tree.spec.words * WORD_BYTES <= BROADCAST_BYTES:
            near = asked.join(F.broadcast(at), "word_no")
        else:
            near = seen.select("set_id", "level", "idx").join(asked, "set_id").join(at, ["level", "idx", "word_no"])
        shared = near.groupBy("set_id", "level", "idx").agg(F.sum(F.bit_count(F.col("bits").bitwiseAND(F.col("asked")))).cast("long").alias("both"))
        full = seen.join(shared, ["set_id", "level", "idx"], "left").fillna(0, ["both"]).join(sizes, "set_id")
        weighed = _weighed(full, tree, weights, tau)
        if last > level:
            # A node is reached if no node above it in its heap is dead or missing.
            of = weighed.groupBy("set_id", "top").agg(F.collect_list(F.when(F.col("live"), F.col("heap"))).alias("_alive"), F.collect_list(F.struct("heap", "level", "idx", "both", "occupied", "weight", "live")).alias("_nodes"))
            ups = lambda h: F.transform(F.sequence(F.lit(1), F.greatest(F.floor(F.log2(h) + 1e-9).cast("int"), F.lit(1))), lambda d: F.call_function("shiftright", h, d))
            reached = F.filter("_nodes", lambda x: (x["heap"] == 1) | F.forall(ups(x["heap"]), lambda h: F.array_contains("_alive", h)))
            weighed = of.select("set_id", F.explode(reached).alias("n")).select("set_id", "n.level", "n.idx", "n.both", "n.occupied", "n.weight", "n.live")
        marked = stored(weighed.select("set_id", F.col("level").cast("int").alias("level"), "idx", "both", "occupied", "weight", "live"), f"level{level}")
        out = marked if out is None else out.unionByName(marked)
        alive = marked.filter(F.col("live") & (F.col("level") == last))
        frontier = alive.select("set_id", F.explode(F.array(F.col("idx") * 2, F.col("idx") * 2 + 1)).alias("idx"))
        level = last + 1
        many = 2 * alive.count() if level <= tree.depth else 0
    return Live(start, out, sizes)


def held_leaves(live: Live, tree: Tree, words: DataFrame) -> DataFrame:
    """(set_id, r, leaves): what each filter answers yes for among all ids, as r of one period, and bits of the set's live leaves."""
    leaves = live.marks.filter((F.col("level") == tree.depth) & F.col("live"))
    bits = leaves.groupBy("set_id", F.shiftright("idx", 6).alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("idx") % 64).cast("int"))).alias("b"))
    listed = bits.groupBy("set_id").agg(F.map_from_entries(F.collect_list(F.struct("w", "b"))).alias("m"))
    every = F.sequence(F.lit(0).cast("long"), F.lit(((1 << tree.depth) - 1) >> 6).cast("long"))
    listed = listed.select("set_id", F.transform(every, lambda w: F.coalesce(F.try_element_at("m", w), F.lit(0).cast("long"))).alias("leaves"))
    filters = stored(dense(words, tree.spec).join(listed, "set_id"), "filters")
    return stored(positives(filters.repartition(parts_for(filters.count()), "set_id"), tree.spec, tree.domain), "held")


def in_live_leaves(held: DataFrame, tree: Tree) -> DataFrame:
    """(set_id, x, idx) of held_leaves."""
    listed = spread(held, tree.spec, tree.domain).withColumn("idx", tree.leaf_of(F.col("x")))
    return listed.filter(F.getbit(F.get("leaves", F.shiftright("idx", 6).cast("int")), (F.col("idx") % 64).cast("int")) == 1).select("set_id", "x", "idx")


def probe_leaves(live: Live, tree: Tree, words: DataFrame, ids: DataFrame | None) -> DataFrame:
    """(set_id, x, idx): ids in live leaves for which the filter answers yes. ids: those in use, or None for all of the domain."""
    if ids is None and tree.depth <= MOST_BITS:
        return in_live_leaves(held_leaves(live, tree, words), tree)
    ids = all_of(words.sparkSession, tree.domain) if ids is None else ids
    leaves = live.marks.filter((F.col("level") == tree.depth) & F.col("live")).select("set_id", "idx")
    return check_pairs(ids.select("x", tree.leaf_of(F.col("x")).alias("idx")).join(leaves, "idx"), words, tree.spec)


def recover(words: DataFrame, tree: Tree, ids: DataFrame | None, tau: float | None = None, start: int | None = None) -> DataFrame:
    """(set_id, x) of all ids that each filter answers yes for. Without tau exactly what a probe of all ids finds; with tau
    branches of small estimates are given up. Leaves are disjoint, so nothing is found twice."""
    live = mark(words, tree, "floored" if tau is None else "paper", tau, start_level(tree) if start is None else start)
    return probe_leaves(live, tree, words, ids).select("set_id", "x")


def recover_counted(words: DataFrame, tree: Tree, truth: DataFrame, tau: float | None = None, start: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(set_id, n_found) and (set_id, n_both) of recover over all ids against truth (set_id, x), distinct: members are tried one by
    one, so that what is found is counted where it is and not joined."""
    live = mark(words, tree, "floored" if tau is None else "paper", tau, start_level(tree) if start is None else start)
    found = probe_leaves(live, tree, words, None).groupBy("set_id").agg(F.count("*").alias("n_found"))
    leaves = live.marks.filter((F.col("level") == tree.depth) & F.col("live")).select("set_id", "idx")
    members = truth.filter(F.col("x").between(0, tree.domain - 1)).select("set_id", "x", tree.leaf_of(F.col("x")).alias("idx")).join(leaves, ["set_id", "idx"])
    return found, check_pairs(members, words, tree.spec).groupBy("set_id").agg(F.count("*").alias("n_both"))


def recover_ops(live: Live, tree: Tree) -> DataFrame:
    """Per set: intersections (one per node reached below the start), memberships (ids of live leaves), nodes and leaves."""
    leaf = (F.col("level") == tree.depth) & F.col("live")
    total: list[Column] = [
        F.count_if(F.col("level") > live.start).alias("intersections"),
        F.coalesce(F.sum(F.when(leaf, F.col("occupied"))), F.lit(0)).cast("long").alias("memberships"),
        F.count_if("live").alias("nodes_visited"),
        F.count_if(leaf).alias("leaves_probed"),
    ]
    return live.marks.groupBy("set_id").agg(*total)
