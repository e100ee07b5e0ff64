"""The range-filter tree: level by level, every node a filter of the ids in its range.

Node (level, idx) covers the ids x with (x << level) div M = idx; its parent is idx div 2. Only leaves hash ids; each level
above is the OR of pairs below. A range without an id has no rows, so the tree of an occupied domain is the same plan over the
occupied ids, and growing a tree is an OR with the tree of the new ids.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import MAX_LONG, Spec, positions
from ..functions.theory import choose_depth
from ..operators.filters import same_spec, words_by
from ..sources.scratch import stored


def node_of(x: Column, level: int, domain: int, cut: str = "even") -> Column:
    """Number of the node of this level that covers x. cut 'even' splits 0..domain-1 into even parts, 'pow2' halves the next
    power of two, by shifts alone."""
    if cut == "pow2":
        return F.shiftright(x, max(0, (domain - 1).bit_length() - level)).cast("long")
    if domain << level > MAX_LONG:
        raise ValueError("domain and depth overflow 64 bits; use cut='pow2'")
    return F.call_function("div", F.shiftleft(x, level), F.lit(domain).cast("long"))


@dataclass(frozen=True)
class Tree:
    """words: level, idx, word_no, bits. nodes: level, idx, occupied, ones."""

    spec: Spec
    domain: int
    depth: int
    words: DataFrame
    nodes: DataFrame
    cut: str = "even"

    def level(self, at: int) -> DataFrame:
        return self.words.filter(F.col("level") == at).select("idx", "word_no", "bits")

    def leaf_of(self, x: Column) -> Column:
        return node_of(x, self.depth, self.domain, self.cut)


#: Levels that one shuffle rolls up. Words of a level go to their ancestors on this many levels at once and are OR-ed before
#: they move; the next shuffle starts from the topmost of these.
AT_ONCE = 4


def rolled(leaves: DataFrame, depth: int, keys: list[str], aggs: list[Column]) -> DataFrame:
    """All levels from the leaves (idx, keys, values) up, a few levels a shuffle, with ever fewer rows."""
    out = level = leaves
    for top in range(depth, 0, -AT_ONCE):
        ups = F.sequence(F.lit(max(0, top - AT_ONCE)), F.lit(top - 1))
        above = level.withColumn("level", F.explode(ups)).withColumn("idx", F.call_function("shiftright", F.col("idx"), F.lit(top) - F.col("level")))
        above = above.groupBy("level", "idx", *keys).agg(*aggs)
        out = out.unionByName(above)
        level = above.filter(F.col("level") == max(0, top - AT_ONCE))
    return out


def _range_size(idx: Column, level: Column, domain: int, cut: str) -> Column:
    """How many ids of 0..domain-1 a node covers."""
    if cut == "pow2":
        shift = F.lit((domain - 1).bit_length()) - level
        low, high = F.call_function("shiftleft", idx, shift), F.call_function("shiftleft", idx + 1, shift)
    else:
        two = F.call_function("shiftleft", F.lit(1).cast("long"), level)
        first = lambda i: F.call_function("div", i * domain + two - 1, two)
        low, high = first(idx), first(idx + 1)
    return F.greatest(F.least(high, F.lit(domain).cast("long")) - F.least(low, F.lit(domain).cast("long")), F.lit(0).cast("long"))


def build_tree(ids: DataFrame, spec: Spec, domain: int, depth: int, cut: str = "even", complete: bool = False) -> Tree:
    """Tree of the ids (x) of a domain 0..domain-1: all of them (complete, as the caller says), or those in use. Repeated and null
    ids change nothing."""
    placed = ids.filter("x is not null").select("x", node_of(F.col("x"), depth, domain, cut).alias("idx"))
    leaves = stored(words_by(placed, ["idx"], spec).withColumn("level", F.lit(depth)), "leaves")
    words = stored(rolled(leaves, depth, ["word_no"], [F.bit_or("bits").alias("bits")]), "tree")
    set_bits = words.groupBy("level", "idx").agg(F.sum(F.bit_count("bits")).cast("long").alias("ones"))
    if complete:
        nodes = set_bits.withColumn("occupied", _range_size(F.col("idx"), F.col("level"), domain, cut))
    else:
        held = placed.distinct().groupBy("idx").agg(F.count("*").alias("occupied")).withColumn("level", F.lit(depth))
        nodes = rolled(held, depth, [], [F.sum("occupied").alias("occupied")]).join(set_bits, ["level", "idx"])
    return Tree(spec, domain, depth, words, stored(nodes.select("level", "idx", "occupied", "ones"), "nodes"), cut)


def complete_tree(spark: SparkSession, spec: Spec, domain: int, depth: int, cut: str = "even") -> Tree:
    return build_tree(spark.range(domain).select(F.col("id").alias("x")), spec, domain, depth, cut, complete=True)


def one_pass_words(ids: DataFrame, spec: Spec, domain: int, depth: int) -> DataFrame:
    """All levels in one shuffle: each id's bits go to all its ancestors. For shallow trees."""
    nodes = F.transform(F.sequence(F.lit(0), F.lit(depth)), lambda level: F.struct(level.alias("level"), F.call_function("shiftright", node_of(F.col("x"), depth, domain), F.lit(depth) - level).alias("idx")))
    spread = ids.filter("x is not null").select("x", F.explode(nodes).alias("n")).select("x", "n.level", "n.idx")
    return words_by(spread, ["level", "idx"], spec)


def grow(tree: Tree, new_ids: DataFrame) -> Tree:
    """The tree with more ids in it; ids that are there already change the filters not at all, but count in `occupied` only if
    new_ids leaves them out."""
    delta = build_tree(new_ids, tree.spec, tree.domain, tree.depth, tree.cut)
    same_spec(tree.spec, delta.spec)
    words = stored(tree.words.unionByName(delta.words).groupBy("level", "idx", "word_no").agg(F.bit_or("bits").alias("bits")), "tree")
    set_bits = words.groupBy("level", "idx").agg(F.sum(F.bit_count("bits")).cast("long").alias("ones"))
    held = tree.nodes.unionByName(delta.nodes).groupBy("level", "idx").agg(F.sum("occupied").alias("occupied"))
    return replace(tree, words=words, nodes=stored(held.join(set_bits, ["level", "idx"]).select("level", "idx", "occupied", "ones"), "nodes"))


def rebuild_range(tree: Tree, ids: DataFrame, low: int, high: int) -> Tree:
    """After deletions among low..high-1: leaves that the range touches are made anew from the ids left, and all levels above."""
    idx = lambda v: (v << tree.depth) // tree.domain if tree.cut == "even" else v >> max(0, (tree.domain - 1).bit_length() - tree.depth)
    first, last = idx(low), idx(max(low, high - 1))
    leaf = tree.leaf_of(F.col("x"))
    redone = words_by(ids.filter("x is not null").withColumn("idx", leaf).filter(F.col("idx").between(first, last)), ["idx"], tree.spec)
    kept = tree.level(tree.depth).filter(~F.col("idx").between(first, last))
    leaves = stored(kept.unionByName(redone).withColumn("level", F.lit(tree.depth)), "leaves")
    words = stored(rolled(leaves, tree.depth, ["word_no"], [F.bit_or("bits").alias("bits")]), "tree")
    held = ids.filter("x is not null").distinct().groupBy(leaf.alias("idx")).agg(F.count("*").alias("occupied")).withColumn("level", F.lit(tree.depth))
    set_bits = words.groupBy("level", "idx").agg(F.sum(F.bit_count("bits")).cast("long").alias("ones"))
    occupied = rolled(held, tree.depth, [], [F.sum("occupied").alias("occupied")])
    return replace(tree, words=words, nodes=stored(occupied.join(set_bits, ["level", "idx"]).select("level", "idx", "occupied", "ones"), "nodes"))


def truncated(tree: Tree, depth: int) -> Tree:
    """The tree cut at a level where probing is cheaper."""
    return replace(tree, depth=min(depth, tree.depth), words=tree.words.filter(F.col("level") <= depth), nodes=tree.nodes.filter(F.col("level") <= depth))


def leaf_depth(domain: int, spec: Spec, leaf: str | int = "cost", ratio: float = 120.0, n: float = 1000) -> int:
    """Depth by leaf size: 'cost' (intersection over membership cost), 'critical' (false branches die out), or a number of ids."""
    if leaf == "cost":
        return choose_depth(domain, ratio)
    size = max(1.0, spec.m * math.log(2) / (spec.k**2 * n)) if leaf == "critical" else float(leaf)
    return max(0, math.ceil(math.log2(domain / size)))


def calibrate_costs(spark: SparkSession, spec: Spec, rounds: int = 200_000) -> tuple[float, float]:
    """Seconds of one intersection of two filters and of one membership query, by timed jobs over made-up words of this length.
    Their ratio is what leaf_depth takes."""
    import time

    def timed(df: DataFrame) -> float:
        df.agg(F.max("v")).collect()
        began = time.perf_counter()
        df.agg(F.max("v")).collect()
        return time.perf_counter() - began

    pair = F.xxhash64(F.lit(0), "id").bitwiseAND(F.xxhash64(F.lit(1), "id"))
    words = max(rounds, 10 * spec.words)
    idle = timed(spark.range(1).select(F.col("id").alias("v")))
    ands = timed(spark.range(words).select(F.bit_count(pair).cast("long").alias("v")))
    hit = F.lit(0).cast("long")
    for pos in positions(F.col("id"), spec):
        hit = hit + F.call_function("shiftright", F.lit(0x5555555555555555).cast("long"), (pos % 64).cast("int")).bitwiseAND(F.lit(1))
    probes = timed(spark.range(words).select(hit.alias("v")))
    floor = 1e-9
    return max(ands - idle, floor * words) / words * spec.words, max(probes - idle, floor * words) / words


def tree_memory(tree: Tree) -> DataFrame:
    """Per level: nodes, bytes of dense filters, bytes of the word rows that are kept."""
    sparse = tree.words.groupBy("level").agg(F.count("*").alias("word_rows"))
    dense = F.col("n_nodes") * F.lit(tree.spec.words * 8)
    return tree.nodes.groupBy("level").agg(F.count("*").alias("n_nodes")).join(sparse, "level").select(F.col("level").cast("long").alias("level"), "n_nodes", dense.cast("long").alias("dense_bytes"), "word_rows")
