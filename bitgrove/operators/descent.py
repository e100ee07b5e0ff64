"""Sampling with the tree: guided descent for many filters and draws at once, without recursion.

A recursion that turns to the sibling when a branch yields nothing ends where a descent ends that turns away from branches
without a reachable positive beforehand. So: mark live nodes, probe live leaves, carry upwards which nodes can yield and what a
vain visit of them costs, then draw downwards with coins fixed per (draw, node). The cost of a raw choice of a barren branch is
added as the recursion would have paid it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.digests import by_digest, coins
from ..functions.hashing import period
from ..plans.tree import Tree
from ..sources.scratch import stored
from . import held as H
from .filters import BROADCAST_BYTES, as_arrays
from .measures import distance_of_leaves
from .sweep import MOST_BITS, Live, held_leaves, in_live_leaves, mark, probe_leaves
from .whole import HANDED, LEAST_PARTS, MOST_PARTS, _blocks, by_set, dense, looked_up, parts_for, positives, probed, spread, turns

#: What a row of live nodes takes in a broadcast, at most.
NODE_BYTES = 512
#: Draws that a task lists at a time.
DRAW_RUN = 20_000
#: Draws of a set that one task walks, and how many of them at once.
WALK_RUN, WALK_STEP = 1 << 23, 1 << 17
#: Sets of which one task takes whole ones, at least.
FEW_SETS = 256


def coin(seed: int, *parts: Column | str) -> Column:
    """A number in 0..1 from the digest of its key: the same on every retry and in every partitioning."""
    key = F.concat_ws(":", F.lit(str(seed)), *(F.col(p).cast("string") if isinstance(p, str) else p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("double") / 4294967296.0


def random_key(seed: int, *parts: Column | str) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *(F.col(p).cast("string") if isinstance(p, str) else p.cast("string") for p in parts)))


def viability(live: Live, tree: Tree, found: DataFrame, printed: bool = False) -> DataFrame:
    """Live nodes with: positives below, and the cost of exploring them in vain (intersections, memberships).

    printed: after a vain visit the sibling is entered even if it shares no bit; that costs its two intersections, or the probes
    of a leaf, and never finds anything."""
    nodes = live.marks.filter("live").select("set_id", "level", "idx", "weight", "occupied")
    hits = found.groupBy("set_id", "idx").agg(F.count("*").alias("positives")).withColumn("level", F.lit(tree.depth))
    own = nodes.join(hits, ["set_id", "level", "idx"], "left")
    at_leaf = F.col("level") == tree.depth
    if printed:
        key = ["set_id", "level", "parent"]
        reached = live.marks.filter(F.col("level") > live.start).withColumn("parent", F.shiftright("idx", 1))
        alone = reached.groupBy(*key).agg(F.count_if("live").alias("alive"), F.sum(F.when(~F.col("live"), F.col("occupied"))).alias("dead_ids"), F.count_if(~F.col("live")).alias("dead")).filter("alive = 1 and dead = 1")
        extra = alone.select("set_id", (F.col("level") - 1).alias("level"), F.col("parent").alias("idx"), F.when(at_leaf, 0).otherwise(2).alias("more_ands"), F.when(at_leaf, F.col("dead_ids")).otherwise(0).alias("more_probes"))
        own = own.join(extra, ["set_id", "level", "idx"], "left").fillna(0, ["more_ands", "more_probes"])
    else:
        own = own.withColumns({"more_ands": F.lit(0), "more_probes": F.lit(0)})
    # One row per node and ancestor, summed in one shuffle.
    up = own.select("set_id", "idx", F.coalesce("positives", F.lit(0)).alias("positives"), (F.when(at_leaf, 0).otherwise(2) + F.col("more_ands")).alias("ands"), (F.when(at_leaf, F.col("occupied")).otherwise(0) + F.col("more_probes")).alias("probes"), "level", F.explode(F.sequence(F.lit(live.start), "level")).alias("to"))
    sums = up.groupBy("set_id", F.col("to").alias("level"), F.call_function("shiftright", F.col("idx"), F.col("level") - F.col("to")).alias("idx")).agg(*(F.sum(c).alias(c) for c in ("positives", "ands", "probes")))
    return stored(nodes.join(sums, ["set_id", "level", "idx"]).select("set_id", "level", "idx", "weight", "positives", "ands", "probes"), "viability")


def _children(nodes: DataFrame) -> DataFrame:
    """One row per parent: weight, positives, ands, probes of both live children; level is the children's."""
    left = F.col("idx") % 2 == 0
    sides = [F.max(F.when(left if side == "l" else ~left, F.col(c))).alias(f"{side}_{c}") for side in "lr" for c in ("weight", "positives", "ands", "probes")]
    return stored(nodes.filter("level > 0").groupBy("set_id", "level", F.shiftright("idx", 1).alias("parent")).agg(*sides), "children")


def _small(rows: DataFrame) -> DataFrame:
    """rows for a join: sent to every task if they are few, by a count; else left to the join's own way, which splits hot keys."""
    return F.broadcast(rows) if rows.count() * NODE_BYTES <= BROADCAST_BYTES else rows


def _numbered(sets: DataFrame) -> DataFrame:
    """(set_id, draw) of (set_id, draws): many draws are listed in runs, which are dealt to tasks before they are listed."""
    runs = sets.select("set_id", "draws", F.explode(F.sequence(F.lit(0).cast("long"), F.col("draws") - 1, F.lit(DRAW_RUN).cast("long"))).alias("low"))
    if (sets.agg(F.sum("draws")).first()[0] or 0) > DRAW_RUN:
        runs = runs.repartition(LEAST_PARTS, "set_id", "low")
    return runs.select("set_id", F.explode(F.sequence(F.col("low").cast("int"), (F.least(F.col("low") + DRAW_RUN, F.col("draws")) - 1).cast("int"))).alias("draw"))


def descend(nodes: DataFrame, live: Live, tree: Tree, draws: int | DataFrame, seed: int, weights: str, keep: bool = True) -> DataFrame:
    """(set_id, draw, idx, intersections, memberships, positives): the leaf that each draw ends in and how many ids it offers; idx is
    null if the set has none. draws: a number for all sets, or a table (set_id, draws).

    All draws of a set meet at its root. While the live nodes are few they are sent to the draws, so that no level shuffles; else
    each level joins by (set, node). keep=False: paths are not stored at their end, for callers that read them once."""
    exact = weights == "exact"
    if live.start:
        raise ValueError("a descent starts at the root")
    root = nodes.filter("level = 0").select("set_id", "positives", "ands", "probes")
    sets = live.sizes.select("set_id")
    sets = sets.withColumn("draws", F.lit(draws).cast("long")) if isinstance(draws, int) else sets.join(draws.select("set_id", F.col("draws").cast("long").alias("draws")), "set_id")
    wanted = _numbered(sets.filter("draws > 0"))
    every = wanted.join(_small(root), "set_id", "left").select("set_id", "draw", F.when(F.col("positives") > 0, F.lit(0).cast("long")).alias("idx"), F.when(F.coalesce("positives", F.lit(0)) > 0, F.lit(0)).otherwise(F.coalesce("ands", F.lit(0))).cast("long").alias("intersections"), F.when(F.coalesce("positives", F.lit(0)) > 0, F.lit(0)).otherwise(F.coalesce("probes", F.lit(0))).cast("long").alias("memberships"))
    paths, children = every, _children(nodes)
    few = children.count() * NODE_BYTES <= BROADCAST_BYTES
    for level in range(tree.depth):
        if level % 6 == 5:
            paths = stored(paths, f"paths{level}")
        of = children.filter(F.col("level") == level + 1).drop("level").withColumnRenamed("parent", "idx")
        both = paths.join(F.broadcast(of) if few else of, ["set_id", "idx"], "left")
        w = {s: F.coalesce(F.col(f"{s}_positives" if exact else f"{s}_weight"), F.lit(0)).cast("double") for s in "lr"}
        alive = {s: F.col(f"{s}_weight").isNotNull() for s in "lr"}
        share = F.when(alive["l"] & ~alive["r"], 1.0).when(~alive["l"], 0.0).when(w["l"] + w["r"] > 0, w["l"] / (w["l"] + w["r"])).otherwise(0.5)
        both = both.withColumn("raw", coin(seed, "set_id", "draw", F.lit(level), "idx") < share)
        raw_left = F.col("raw")
        yields = {s: F.coalesce(F.col(f"{s}_positives"), F.lit(0)) > 0 for s in "lr"}
        left = F.when(raw_left, yields["l"]).otherwise(~yields["r"])
        vain = lambda c: F.when(raw_left & ~yields["l"], F.coalesce(F.col(f"l_{c}"), F.lit(0))).when(~raw_left & ~yields["r"], F.coalesce(F.col(f"r_{c}"), F.lit(0))).otherwise(F.lit(0))  # noqa: B023, E731
        going = F.col("idx").isNotNull()
        paths = both.select("set_id", "draw", F.when(going, F.col("idx") * 2 + F.when(left, 0).otherwise(1)).alias("idx"), (F.col("intersections") + F.when(going, 2 + vain("ands")).otherwise(0)).alias("intersections"), (F.col("memberships") + F.when(going, vain("probes")).otherwise(0)).alias("memberships"))
    leaf = nodes.filter(F.col("level") == tree.depth).select("set_id", "idx", "probes", "positives")
    done = (stored(paths, "paths") if keep else paths).join(_small(leaf), ["set_id", "idx"], "left")
    return done.select("set_id", "draw", "idx", "intersections", (F.col("memberships") + F.coalesce("probes", F.lit(0))).alias("memberships"), "positives")


def _leaf_ranks(found: DataFrame, seed: int) -> DataFrame:
    return found.withColumn("rank", F.row_number().over(Window.partitionBy("set_id", "idx").orderBy(random_key(seed, F.lit("leaf"), "set_id", "x"), "x")))


def _found(live: Live, tree: Tree, words: DataFrame, ids: DataFrame | None) -> tuple[DataFrame, DataFrame]:
    """(set_id, x, idx) of probe_leaves twice: as stored, and dealt so that a set's rows are ranked where they are. Of all ids only
    those of one period are stored."""
    if ids is not None or tree.depth > MOST_BITS:
        found = stored(probe_leaves(live, tree, words, ids), "positives")
        return found, found
    held, sets = held_leaves(live, tree, words), live.sizes.count()
    # A few sets would leave most tasks idle: their rows are dealt by leaf.
    return in_live_leaves(held, tree), in_live_leaves(held.repartition(parts_for(sets), "set_id") if sets >= FEW_SETS else held, tree)


def sample_sets(words: DataFrame, tree: Tree, ids: DataFrame | None, draws: int | DataFrame = 1, seed: int = 1, weights: str = "floored", tau: float | None = None, replace: bool = True, printed: bool = False) -> DataFrame:
    """(set_id, draw, x, idx, intersections, memberships): `draws` ids of each filter, x null if it holds none.

    weights: 'paper' (estimated overlap, nodes under tau are not entered), 'floored' (the estimate, FLOOR at least, only nodes
    without a common bit are left out), 'prior' (the share of ids in use, whatever the bits say of live nodes), 'exact' (true numbers of positives below; uniform over what the filter answers yes for).
    printed: counts the work of the printed control flow, which enters dead siblings too; the draws are the same.
    ids: those in use, or None for all of the domain.
    replace=False: ids of a set differ; draws that meet in a leaf with too few ids take unused ones of the set, or none.
    """
    if _held(tree, ids, draws):
        return H.drawn(dense(words, tree.spec), tree, draws, seed, weights, tau, replace, printed)
    words = by_set(words)
    live = mark(words, tree, weights if weights in ("paper", "prior") else "floored", tau)
    found, dealt = _found(live, tree, words, ids)
    nodes = viability(live, tree, found, printed)
    paths = descend(nodes, live, tree, draws, seed, weights)
    ranks = lambda rows: _leaf_ranks(rows, seed)
    if ids is None and isinstance(draws, int):
        meet = lambda wanted: looked_up(wanted, dealt, ["set_id", "idx"], ranks)
    else:
        meet = lambda wanted: wanted.join(ranks(dealt), ["set_id", "idx", "rank"], "left")
    if replace:
        # A draw names the rank it wants, so it meets one id of its leaf and not all of them.
        wanted = paths.withColumn("rank", F.floor(coin(seed, F.lit("pick"), "set_id", "draw") * F.col("positives")).cast("int") + 1)
        return meet(wanted).select("set_id", "draw", "x", "idx", "intersections", "memberships")
    ranked = paths.withColumn("rank", F.row_number().over(Window.partitionBy("set_id", "idx").orderBy("draw")))
    first = stored(meet(ranked).select("set_id", "draw", "x", "idx", "intersections", "memberships"), "drawn")
    missing = stored(first.filter("x is null").select("set_id").distinct(), "missing")
    if missing.isEmpty():
        return first
    unused = found.select("set_id", "x").join(_small(missing), "set_id", "left_semi").join(first.filter("x is not null").select("set_id", "x"), ["set_id", "x"], "left_anti")
    spare = unused.withColumn("rank", F.row_number().over(Window.partitionBy("set_id").orderBy(random_key(seed, F.lit("spare"), "set_id", "x"), "x"))).withColumnRenamed("x", "y")
    short = first.filter("x is null").withColumn("rank", F.row_number().over(Window.partitionBy("set_id").orderBy("draw")))
    filled = short.join(spare, ["set_id", "rank"], "left").select("set_id", "draw", F.col("y").alias("x"), "idx", "intersections", "memberships")
    return first.filter("x is not null").unionByName(filled)


def _held(tree: Tree, ids: DataFrame | None, draws: int | DataFrame = 1) -> bool:
    """Whether a set's task can do all of its work: for all ids of the domain, a tree that fits a broadcast, and not too many draws."""
    return ids is None and isinstance(draws, int) and 0 < draws <= H.MOST_DRAWS and H.fits(tree)


def sample_work(words: DataFrame, tree: Tree, draws: int, seed: int = 1, weights: str = "floored") -> DataFrame:
    """(set_id, draw, intersections, memberships) of sample_sets over all ids, for which no id has to be looked up."""
    if _held(tree, None, draws):
        got = H.drawn(dense(words, tree.spec), tree, draws, seed, weights, None, True, False, look_up=False)
    else:
        got = sample_sets(words, tree, None, draws, seed, weights)
    return got.select("set_id", "draw", "intersections", "memberships")


def sample_counts(words: DataFrame, tree: Tree, draws: int | DataFrame, seed: int = 1, weights: str = "floored", tau: float | None = None, among: DataFrame | None = None) -> DataFrame:
    """(set_id, x, times): how often sample_sets, with replacement over all ids, draws each id. Draws that name the same rank of a leaf
    are counted before they meet its id. among: (set_id, x), distinct, for callers that want to know of these ids alone."""
    if H.fits(tree):
        sets = as_arrays(words, tree.spec)
        sets = sets.withColumn("draws", F.lit(draws).cast("long")) if isinstance(draws, int) else sets.join(draws.select("set_id", F.col("draws").cast("long").alias("draws")), "set_id")
        if among is not None:
            sets = sets.join(among.groupBy("set_id").agg(F.collect_list("x").alias("xs")), "set_id")
        return H.times_drawn(sets, tree, seed, weights, tau, among is not None)
    if among is not None:
        return sample_counts(words, tree, draws, seed, weights, tau).join(among, ["set_id", "x"], "left_semi")
    words = by_set(words)
    live = mark(words, tree, weights if weights in ("paper", "prior") else "floored", tau)
    found, dealt = _found(live, tree, words, None)
    nodes = viability(live, tree, found)
    if period(tree.spec) is not None and tree.depth <= MOST_BITS:
        return _walked(nodes, live, tree, words, draws, seed, weights)
    paths = descend(nodes, live, tree, draws, seed, weights, keep=False)
    rank = F.floor(coin(seed, F.lit("pick"), "set_id", "draw") * F.col("positives")).cast("int") + 1
    aimed = paths.filter("idx is not null").select("set_id", "idx", rank.alias("rank")).groupBy("set_id", "idx", "rank").agg(F.count("*").alias("times"))
    return aimed.join(_leaf_ranks(dealt, seed), ["set_id", "idx", "rank"]).select("set_id", "x", "times")


def _walked(nodes: DataFrame, live: Live, tree: Tree, words: DataFrame, draws: int | DataFrame, seed: int, weights: str) -> DataFrame:
    """sample_counts in tasks that hold a set's filter and its live nodes: draws walk down there, and only ids with how often they
    were drawn leave them. Sets of many draws are dealt in runs, whose numbers are added up."""
    spec, domain, depth, cut = tree.spec, tree.domain, tree.depth, tree.cut
    w = {s: F.coalesce(F.col(f"{s}_positives" if weights == "exact" else f"{s}_weight"), F.lit(0)).cast("double") for s in "lr"}
    alive = {s: F.col(f"{s}_weight").isNotNull() for s in "lr"}
    share = F.when(alive["l"] & ~alive["r"], 1.0).when(~alive["l"], 0.0).when(w["l"] + w["r"] > 0, w["l"] / (w["l"] + w["r"])).otherwise(0.5)
    yields = [(F.coalesce(F.col(f"{s}_positives"), F.lit(0)) > 0).alias(s) for s in "lr"]
    turns_of = _children(nodes).groupBy("set_id").agg(F.collect_list(F.struct((F.col("level") - 1).alias("level"), F.col("parent").alias("idx"), share.alias("share"), *yields)).alias("turns"))
    leaves = nodes.filter((F.col("level") == depth) & (F.col("positives") > 0)).groupBy("set_id").agg(F.collect_list("idx").alias("leaves"))
    sets = live.sizes.select("set_id")
    sets = sets.withColumn("draws", F.lit(draws).cast("long")) if isinstance(draws, int) else sets.join(draws.select("set_id", F.col("draws").cast("long").alias("draws")), "set_id")
    runs = sets.filter("draws > 0").select("set_id", "draws", F.explode(F.sequence(F.lit(0).cast("long"), F.col("draws") - 1, F.lit(WALK_RUN).cast("long"))).alias("low"))
    held = stored(leaves.join(turns_of, "set_id", "left").join(as_arrays(words, spec), "set_id").join(runs, "set_id"), "walks")
    names = ["set_id", "draws", "low", "leaves", "turns", "filter"]

    def walked(batches):
        import numpy as np
        import pyarrow as pa

        blocks = _blocks(spec, turns(spec, domain))
        for row in (r for batch in batches for r in batch.select(names).to_pylist()):
            set_id, at_leaf = row["set_id"], np.zeros(1 << depth, bool)
            at_leaf[row["leaves"]] = True
            x = probed(np.array(row["filter"], np.int64), blocks, spec, domain)
            leaf = x >> max(0, (domain - 1).bit_length() - depth) if cut == "pow2" else (x << depth) // domain
            x, leaf = x[at_leaf[leaf]], leaf[at_leaf[leaf]]
            x = x[by_digest(x, str(seed), "leaf", set_id, also=leaf)]
            positives = np.bincount(leaf, minlength=1 << depth)
            first, times = np.cumsum(positives) - positives, np.zeros(len(x), np.int64)
            # Nodes of all levels as in a heap: 1 is the root.
            shares, lefts, rights = np.zeros(1 << depth), np.zeros(1 << depth, bool), np.zeros(1 << depth, bool)
            for t in row["turns"] or ():
                node = (1 << t["level"]) + t["idx"]
                shares[node], lefts[node], rights[node] = t["share"], t["l"], t["r"]
            end = min(row["draws"], row["low"] + WALK_RUN)
            for low in range(row["low"], end, WALK_STEP):
                draw = np.arange(low, min(low + WALK_STEP, end), dtype=np.int64)
                node = np.ones(len(draw), np.int64)
                for level in range(depth):
                    raw = coins(str(seed), set_id, draw, str(level), node - (1 << level)) < shares[node]
                    node = 2 * node + ~np.where(raw, lefts[node], ~rights[node])
                at = node - (1 << depth)
                rank = np.floor(coins(str(seed), "pick", set_id, draw) * positives[at]).astype(np.int64)
                times += np.bincount(first[at] + rank, minlength=len(x))
            hit = np.flatnonzero(times)
            for i in range(0, len(hit), HANDED):
                part = hit[i : i + HANDED]
                yield pa.RecordBatch.from_arrays([pa.array([set_id] * len(part)), pa.array(x[part]), pa.array(times[part])], names=["set_id", "x", "times"])

    drawn = held.repartition(max(1, min(MOST_PARTS, held.count()))).mapInArrow(walked, "set_id string, x long, times long")
    most = sets.agg(F.max("draws")).first()[0] or 0
    return drawn if most <= WALK_RUN else drawn.groupBy("set_id", "x").agg(F.sum("times").alias("times"))


def leaf_probabilities(words: DataFrame, tree: Tree, ids: DataFrame | None, weights: str = "floored", tau: float | None = None) -> DataFrame:
    """(set_id, idx, n, probability): leaves that hold positives, how many, and the exact chance of each of them in one draw."""
    live = mark(words, tree, weights if weights in ("paper", "prior") else "floored", tau)
    return _chances(live, tree, _found(live, tree, words, ids)[0], weights)


def distances(words: DataFrame, tree: Tree, kinds: list[tuple[str, float | None]]) -> DataFrame:
    """measures.distance_to_uniform over all ids for several kinds of weights (name, tau), with a column weights."""
    if _held(tree, None):
        got = H.distances(dense(words, tree.spec), tree, kinds)
        names = F.array(*(F.lit(name) for name, _ in kinds))
        return got.select(F.get(names, F.col("kind")).alias("weights"), "set_id", "n", "reachable", "total_variation", "max_ratio")
    words, out = by_set(words), None
    found = spread(positives(dense(words, tree.spec), tree.spec, tree.domain), tree.spec, tree.domain)
    found = stored(found.groupBy("set_id", tree.leaf_of(F.col("x")).alias("idx")).agg(F.count("*").alias("n")), "found")
    for name, tau in kinds:
        one = distance_of_leaves(leaf_probabilities(words, tree, None, name, tau), found).select(F.lit(name).alias("weights"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def _chances(live: Live, tree: Tree, found: DataFrame, weights: str) -> DataFrame:
    nodes = viability(live, tree, found).filter("positives > 0")
    weight = F.col("positives").cast("double") if weights == "exact" else F.col("weight")
    chance = nodes.filter("level = 0").select("set_id", "idx", F.lit(1.0).alias("probability"))
    for level in range(1, tree.depth + 1):
        at = nodes.filter(F.col("level") == level).select("set_id", "idx", F.shiftright("idx", 1).alias("parent"), weight.alias("w"))
        total, many = F.sum("w").over(Window.partitionBy("set_id", "parent")), F.count("*").over(Window.partitionBy("set_id", "parent"))
        shared = at.withColumn("share", F.when(total > 0, F.col("w") / total).otherwise(1 / many))
        up = chance.select("set_id", F.col("idx").alias("parent"), "probability")
        chance = shared.join(up, ["set_id", "parent"]).select("set_id", "idx", (F.col("probability") * F.col("share")).alias("probability"))
    leaf = nodes.filter(F.col("level") == tree.depth).select("set_id", "idx", F.col("positives").alias("n"))
    return chance.join(leaf, ["set_id", "idx"]).select("set_id", "idx", "n", (F.col("probability") / F.col("n")).alias("probability"))


def path_probabilities(words: DataFrame, tree: Tree, ids: DataFrame | None, weights: str = "floored", tau: float | None = None) -> DataFrame:
    """(set_id, x, probability): the exact chance that one draw returns each positive; no sampling noise."""
    live = mark(words, tree, weights if weights in ("paper", "prior") else "floored", tau)
    found = _found(live, tree, words, ids)[0]
    return found.join(_chances(live, tree, found, weights), ["set_id", "idx"]).select("set_id", "x", "probability")


def rejected_to_uniform(words: DataFrame, tree: Tree, ids: DataFrame | None, draws: int, seed: int, weights: str = "floored") -> DataFrame:
    """(set_id, draw, x): draws by descents with these weights, each kept with a chance that makes those kept uniform: the least
    probability of a positive of the set over its own. Positives of a leaf share one probability."""
    if _held(tree, ids, draws):
        return H.kept_uniform(dense(words, tree.spec), tree, draws, seed, weights)
    words = by_set(words)
    chances = stored(leaf_probabilities(words, tree, ids, weights), "chances")
    least = chances.groupBy("set_id").agg(F.min("probability").alias("least"))
    tried = sample_sets(words, tree, ids, draws, seed, weights).filter("x is not null").select("set_id", "draw", "x", "idx")
    known = tried.join(chances, ["set_id", "idx"]).join(_small(least), "set_id")
    return known.filter(coin(seed, "set_id", "draw", F.lit("keep")) < F.col("least") / F.col("probability")).select("set_id", "draw", "x")
