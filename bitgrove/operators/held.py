"""Marking, recovering and drawing in the task that holds a set's filter: of its live nodes, what it answers yes for and its draws
nothing but results leaves the task. The tree's words go to all tasks; so this is for trees that fit a broadcast."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.digests import COUNTED, LISTED, by_digest, coins, coins_counted, heads, ranked
from ..functions.hashing import Spec, period
from ..plans.tree import Tree
from ..sources.scratch import stored
from .filters import BROADCAST_BYTES
from .sweep import FLOOR, MOST_BITS, recover, start_level
from .whole import HANDED, MOST_PARTS, _blocks, _filters_of, _placed, _yes, dense, probed, turns

#: Draws of a set that its task lists at once.
MOST_DRAWS = 1 << 17
#: Draws of a set that one task counts.
RUN_DRAWS = 400 * COUNTED
#: What a draw is in a result.
DRAWN = "set_id string, draw int, x long, idx long, intersections long, memberships long"


@dataclass(frozen=True)
class Nodes:
    """A tree's nodes as arrays, numbered as in a heap: 1 is the root, 2 and 3 are its children."""

    spec: Spec
    domain: int
    depth: int
    cut: str
    words: object
    ones: object
    occupied: object
    there: object

    def leaf_of(self, x):
        return x >> max(0, (self.domain - 1).bit_length() - self.depth) if self.cut == "pow2" else (x << self.depth) // self.domain


def fits(tree: Tree) -> bool:
    return period(tree.spec) is not None and tree.depth <= MOST_BITS and (2 << tree.depth) * tree.spec.words * 8 <= BROADCAST_BYTES


def nodes_of(tree: Tree) -> Nodes:
    import numpy as np

    heap = 2 << tree.depth
    words, ones, occupied, there = np.zeros((heap, tree.spec.words), np.uint64), np.zeros(heap, np.int64), np.zeros(heap, np.int64), np.zeros(heap, bool)
    w, n = tree.words.filter(f"level <= {tree.depth}").select("level", "idx", "word_no", "bits").toArrow(), tree.nodes.filter(f"level <= {tree.depth}").select("level", "idx", "ones", "occupied").toArrow()
    place = lambda t: (1 << t["level"].to_numpy().astype(np.int64)) + t["idx"].to_numpy()
    words[place(w), w["word_no"].to_numpy()] = w["bits"].to_numpy().view(np.uint64)
    ones[place(n)], occupied[place(n)], there[place(n)] = n["ones"].to_numpy(), n["occupied"].to_numpy(), True
    return Nodes(tree.spec, tree.domain, tree.depth, tree.cut, words, ones, occupied, there)


def marked(held, nodes: Nodes, weights: str, tau: float | None = None, start: int = 0):
    """sweep.mark of some filters (arrays of words): (weight, live, reached), a row per filter and a column per node."""
    import numpy as np

    m, k, n = nodes.spec.m, nodes.spec.k, len(nodes.there)
    held = held.view(np.uint64)
    own = np.bitwise_count(held).sum(axis=1, dtype=np.int64)[:, None]
    both = np.stack([np.bitwise_count(held & w).sum(axis=1, dtype=np.int64) for w in nodes.words], axis=1)
    log = k * math.log(1 - 1 / m)
    with np.errstate(divide="ignore", invalid="ignore"):
        below = float(m) * (m - nodes.ones - own + both)
        arg = np.where(below != 0, 1 - (float(m) * both - nodes.ones * own.astype(np.float64)) / below, -1.0)
        unknown = (nodes.ones >= m) | (own >= m) | (arg <= 0)
        size = np.where(own < m, np.log((float(m) - own) / float(m)) / log, 1.0)
        prior = size * nodes.occupied / float(nodes.domain)
        value = np.where(unknown, prior, np.log(np.where(unknown, 1.0, arg)) / log)
    live = both >= 1
    if weights == "prior":
        weight = prior
    elif weights == "paper":
        weight = np.maximum(value, 0.0)
        live = live if tau is None else live & (unknown | (value >= tau))
    else:
        weight = np.maximum(value, FLOOR)
    reached, start = np.zeros(live.shape, bool), min(start, nodes.depth)
    reached[:, 1 << start : 2 << start] = nodes.there[1 << start : 2 << start]
    live[:, : 1 << start] = False
    for at in range(1 << start, n):
        if at >= 2 << start:
            reached[:, at] = live[:, at >> 1] & nodes.there[at]
        live[:, at] &= reached[:, at]
    return weight, live, reached


def _mark_kind(weights: str) -> str:
    return weights if weights in ("paper", "prior") else "floored"


def _in_leaves(filter_, live, nodes: Nodes, blocks):
    """Ids in live leaves that a filter answers yes for, in order, and how many are in each leaf."""
    import numpy as np

    x = np.sort(probed(filter_, blocks, nodes.spec, nodes.domain))
    leaf = nodes.leaf_of(x)
    kept = live[(1 << nodes.depth) + leaf]
    return x[kept], np.bincount(leaf[kept], minlength=1 << nodes.depth)


def _upwards(live, reached, positives, nodes: Nodes, printed: bool):
    """descent.viability of one set: positives below each live node, and what it costs to explore it in vain."""
    import numpy as np

    low, n = 1 << nodes.depth, len(live)
    hits, ands, probes = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, np.int64)
    hits[low:], ands[1:low], probes[low:] = positives, 2, nodes.occupied[low:]
    if printed:
        left, right = np.arange(2, n, 2), np.arange(3, n, 2)
        # One child is live, and the other is reached and dead: it is entered after a vain visit.
        alone = np.flatnonzero((live[left] != live[right]) & reached[left] & reached[right]) + 1
        dead = np.where(live[2 * alone], 2 * alone + 1, 2 * alone)
        at_leaf = 2 * alone >= low
        ands[alone] += np.where(at_leaf, 0, 2)
        probes[alone] += np.where(at_leaf, nodes.occupied[dead], 0)
    sums = [np.where(live, v, 0) for v in (hits, ands, probes)]
    for level in range(nodes.depth - 1, -1, -1):
        a, b = 1 << level, 2 << level
        for v in sums:
            v[a:b] += np.where(live[a:b], v[b : 2 * b : 2] + v[b + 1 : 2 * b : 2], 0)
    return sums


def _chances(weight, hits, depth: int):
    """The chance of each node with positives in one draw."""
    import numpy as np

    yields = hits > 0
    chance = np.zeros(len(hits))
    chance[1] = 1.0 if yields[1] else 0.0
    w = np.where(yields, weight, 0.0)
    for level in range(depth):
        a, b = 1 << level, 2 << level
        l, r = slice(b, 2 * b, 2), slice(b + 1, 2 * b, 2)
        total, many = w[l] + w[r], yields[l].astype(int) + yields[r]
        for s in (l, r):
            share = np.where(total > 0, w[s] / np.where(total > 0, total, 1.0), 1 / np.maximum(many, 1))
            chance[s] = np.where(yields[s], chance[a:b] * share, 0.0)
    return chance


def _walk(set_id: str, weight, live, sums, nodes: Nodes, draw, seed: int, exact: bool):
    """descent.descend of one set: leaves that draws end in (-1: the set has none), intersections, memberships."""
    import numpy as np

    hits, ands, probes = sums
    if hits[1] <= 0:
        none = np.full(len(draw), -1, np.int64)
        return none, np.full(len(draw), ands[1]), np.full(len(draw), probes[1])
    node, more_ands, more_probes = np.ones(len(draw), np.int64), np.zeros(len(draw), np.int64), np.zeros(len(draw), np.int64)
    w = np.where(live, hits if exact else weight, 0).astype(np.float64)
    for level in range(nodes.depth):
        l, r = 2 * node, 2 * node + 1
        total = w[l] + w[r]
        share = np.where(live[l] & ~live[r], 1.0, np.where(~live[l], 0.0, np.where(total > 0, w[l] / np.where(total > 0, total, 1.0), 0.5)))
        raw = coins(str(seed), set_id, draw, str(level), node - (1 << level)) < share
        chosen = np.where(raw, l, r)
        vain = hits[chosen] <= 0
        more_ands += 2 + np.where(vain, ands[chosen], 0)
        more_probes += np.where(vain, probes[chosen], 0)
        node = np.where(vain, chosen ^ 1, chosen)
    return node - (1 << nodes.depth), more_ands, more_probes + probes[node]


def _counts(set_id: str, x, positives, weight, live, hits, nodes: Nodes, low: int, high: int, seed: int):
    """How often the draws low..high-1 of one set hit each of its ids; x in the order of leaf and digest. The draws are those of _walk,
    counted up, so that their keys are made from lists."""
    import numpy as np

    depth, l = nodes.depth, 2 * np.arange(1 << nodes.depth)
    w, r = np.where(live, weight, 0).astype(np.float64), l + 1
    total = w[l] + w[r]
    share = np.where(live[l] & ~live[r], 1.0, np.where(~live[l], 0.0, np.where(total > 0, w[l] / np.where(total > 0, total, 1.0), 0.5)))
    # Where both coins lead, for each node.
    turn_left, turn_right = np.where(hits[l] > 0, l, r), np.where(hits[r] > 0, r, l)
    first, times = np.cumsum(positives) - positives, np.zeros(len(x), np.int64)
    tails = [[f":{level}:{i}" for i in range(1 << level)] for level in range(depth)]
    for at in range(low, high, COUNTED):
        draw, listed = np.arange(at, at + COUNTED), at >= 10**LISTED
        node = np.ones(COUNTED, np.int64)
        for level in range(depth):
            idx = node - (1 << level)
            coin = coins_counted(f"{seed}:{set_id}:", at, tails[level], idx) if listed else coins(str(seed), set_id, draw, str(level), idx)
            node = np.where(coin < share[node], turn_left[node], turn_right[node])
        leaf = node - (1 << depth)
        pick = coins_counted(f"{seed}:pick:{set_id}:", at, [""]) if listed else coins(str(seed), "pick", set_id, draw)
        hit = first[leaf] + np.floor(pick * positives[leaf]).astype(np.int64)
        times += np.bincount(hit[: high - at], minlength=len(x))
    return times


def _ids_at(set_id: str, x, positives, leaf, rank, seed: int):
    """Ids of these ranks (from 0, by digest) in their leaves; x in order. -1 where a leaf has none of that rank, or leaf is -1."""
    import numpy as np

    out = np.full(len(leaf), -1, np.int64)
    good = (leaf >= 0) & (rank < positives[np.maximum(leaf, 0)])
    if not good.any():
        return out
    first, wanted = np.cumsum(positives) - positives, np.unique(leaf[good])
    lists = [x[first[w] : first[w] + positives[w]] for w in wanted]
    keys, low = heads(str(seed), "leaf", set_id, np.concatenate(lists)), 0
    for w, ids in zip(wanted, lists, strict=True):
        at = np.flatnonzero(good & (leaf == w))
        out[at] = ids[ranked(ids, np.unique(rank[at]), str(seed), "leaf", set_id, keys=keys[low : low + len(ids)])(rank[at])]
        low += len(ids)
    return out


def _without_replacement(set_id: str, x, positives, leaf, draw, seed: int):
    """Ids of draws that take those of their leaf in turn; where a leaf has too few, unused ones of the set, or none."""
    import numpy as np

    order = np.argsort(leaf, kind="stable")
    starts = np.flatnonzero(np.r_[True, leaf[order][1:] != leaf[order][:-1]])
    rank = np.empty(len(leaf), np.int64)
    rank[order] = np.arange(len(leaf)) - np.repeat(starts, np.diff(np.r_[starts, len(leaf)]))
    out = _ids_at(set_id, x, positives, leaf, rank, seed)
    short = np.flatnonzero(out < 0)
    if len(short):
        unused = np.setdiff1d(x, out[out >= 0], assume_unique=True)
        if len(unused):
            spare = unused[by_digest(unused, str(seed), "spare", set_id)][: len(short)]
            out[short[: len(spare)]] = spare
    return out


def _by_set(filters: DataFrame, nodes: Nodes, kinds: list[tuple[str, float | None]], start: int, make: Callable, schema: str, also: tuple[str, ...] = ()) -> DataFrame:
    """make(set_id, filter, blocks, marks, i) gives the columns of a set's rows after set_id; marks has those of every kind of
    weights, i is the set's row in them. also: columns whose values make gets too."""
    words, names = nodes.spec.words, [c.split()[0] for c in schema.split(", ")]

    def done(batches):
        import numpy as np
        import pyarrow as pa

        arrow = {"int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
        blocks, types = _blocks(nodes.spec, turns(nodes.spec, nodes.domain)), [arrow[c.split()[1]] for c in schema.split(", ")[1:]]

        def handed(sets, of, rows):
            named = pa.array(sets, pa.string()).take(pa.array(np.repeat(np.arange(len(sets)), of)))
            columns = [np.concatenate([r[j] for r in rows]) for j in range(len(types))]
            # Ids and numbers of leaves are not negative: what is, is none.
            made = [pa.array(c, t, mask=c < 0) if n in ("x", "idx") else pa.array(c, t) for c, t, n in zip(columns, types, names[1:], strict=True)]
            return pa.RecordBatch.from_arrays([named, *made], names=names)

        for batch in batches:
            held = _filters_of(batch, words)
            marks = [marked(held, nodes, _mark_kind(w), tau, start) for w, tau in kinds]
            sets, of, rows, many = [], [], [], 0
            more = [batch.column(batch.schema.get_field_index(c)) for c in also]
            for i, set_id in enumerate(batch.column(batch.schema.get_field_index("set_id")).to_pylist()):
                got = make(set_id, held[i], blocks, marks, i, *(c[i] for c in more))
                if len(got[0]):
                    sets.append(set_id), of.append(len(got[0])), rows.append(got)
                    many += len(got[0])
                if many >= HANDED:
                    yield handed(sets, of, rows)
                    sets, of, rows, many = [], [], [], 0
            if sets:
                yield handed(sets, of, rows)

    return filters.select("set_id", "filter", *also).mapInArrow(done, schema)


def drawn(filters: DataFrame, tree: Tree, draws: int, seed: int, weights: str, tau: float | None, replace: bool, printed: bool, look_up: bool = True) -> DataFrame:
    """descent.sample_sets over all ids. look_up=False: for callers that want the work only; x is null then."""
    import numpy as np

    nodes, exact = nodes_of(tree), weights == "exact"

    def make(set_id, filter_, blocks, marks, i):
        weight, live, reached = (v[i] for v in marks[0])
        x, positives = _in_leaves(filter_, live, nodes, blocks)
        draw = np.arange(draws, dtype=np.int64)
        leaf, ands, probes = _walk(set_id, weight, live, _upwards(live, reached, positives, nodes, printed), nodes, draw, seed, exact)
        if not look_up:
            got = np.full(draws, -1, np.int64)
        elif replace:
            rank = np.floor(coins(str(seed), "pick", set_id, draw) * positives[leaf]).astype(np.int64)
            got = _ids_at(set_id, x, positives, leaf, rank, seed)
        else:
            got = _without_replacement(set_id, x, positives, leaf, draw, seed)
        return draw, got, leaf, ands, probes

    return _by_set(filters, nodes, [(weights, tau)], 0, make, DRAWN)


def times_drawn(sets: DataFrame, tree: Tree, seed: int, weights: str, tau: float | None, among: bool) -> DataFrame:
    """descent.sample_counts of sets (set_id, filter, draws), or, of sets that list ids xs as well (among), of these ids alone: all draws
    are made, but no others leave the task. Sets of many draws are dealt in runs, whose numbers are added up."""
    import numpy as np

    nodes, exact = nodes_of(tree), weights == "exact"

    def make(set_id, filter_, blocks, marks, i, low, high, xs=None):
        weight, live, reached = (v[i] for v in marks[0])
        x, positives = _in_leaves(filter_, live, nodes, blocks)
        if not len(x):
            return x, x
        hits = _upwards(live, reached, positives, nodes, False)[0]
        x = x[by_digest(x, str(seed), "leaf", set_id, also=nodes.leaf_of(x))]
        times = _counts(set_id, x, positives, hits if exact else weight, live, hits, nodes, low.as_py(), high.as_py(), seed)
        hit = times > 0
        if xs is not None:
            hit &= np.isin(x, xs.values.to_numpy())
        return x[hit], times[hit]

    lows = F.explode(F.sequence(F.lit(0).cast("long"), F.col("draws") - 1, F.lit(RUN_DRAWS).cast("long")))
    runs = sets.filter("draws > 0").withColumn("low", lows).withColumn("high", F.least("draws", F.col("low") + RUN_DRAWS)).drop("draws")
    runs = stored(runs, "runs")
    got = _by_set(runs.repartition(max(1, min(MOST_PARTS, runs.count()))), nodes, [(weights, tau)], 0, make, "set_id string, x long, times long", ("low", "high", *(["xs"] if among else [])))
    return got if runs.filter("low > 0").isEmpty() else got.groupBy("set_id", "x").agg(F.sum("times").alias("times"))


def kept_uniform(filters: DataFrame, tree: Tree, draws: int, seed: int, weights: str) -> DataFrame:
    """descent.rejected_to_uniform over all ids: only draws that are kept meet their ids."""
    import numpy as np

    nodes, exact = nodes_of(tree), weights == "exact"

    def make(set_id, filter_, blocks, marks, i):
        weight, live, reached = (v[i] for v in marks[0])
        x, positives = _in_leaves(filter_, live, nodes, blocks)
        sums, draw = _upwards(live, reached, positives, nodes, False), np.arange(draws, dtype=np.int64)
        if sums[0][1] <= 0:
            return draw[:0], draw[:0]
        leaf = _walk(set_id, weight, live, sums, nodes, draw, seed, exact)[0]
        chance = _chances(sums[0].astype(np.float64) if exact else weight, sums[0], nodes.depth)[1 << nodes.depth :]
        own = chance[positives > 0] / positives[positives > 0]
        keep = coins(str(seed), set_id, draw, "keep") < own.min() / (chance[leaf] / positives[leaf])
        draw, leaf = draw[keep], leaf[keep]
        rank = np.floor(coins(str(seed), "pick", set_id, draw) * positives[leaf]).astype(np.int64) if len(draw) else draw
        return draw, _ids_at(set_id, x, positives, leaf, rank, seed)

    return _by_set(filters, nodes, [(weights, None)], 0, make, "set_id string, draw int, x long")


def distances(filters: DataFrame, tree: Tree, kinds: list[tuple[str, float | None]]) -> DataFrame:
    """measures.distance_of_leaves of descent.leaf_probabilities over all ids, for several kinds of weights (name, tau) at once; kind
    is the number of the kind."""
    import numpy as np

    nodes = nodes_of(tree)
    low = 1 << nodes.depth

    def make(set_id, filter_, blocks, marks, i):
        everywhere = np.ones(2 * low, bool)
        n = _in_leaves(filter_, everywhere, nodes, blocks)[1]
        of, total = n[n > 0], n.sum()
        out = []
        for j, (weights, _) in enumerate(kinds):
            weight, live, reached = (v[i] for v in marks[j])
            sums = _upwards(live, reached, np.where(live[low:], n, 0), nodes, False)
            if total:
                p = _chances(sums[0].astype(np.float64) if weights == "exact" else weight, sums[0], nodes.depth)[low:][n > 0] / of
                u = 1 / total
                out.append((j, total, of[p > 0].sum(), (np.abs(p - u) * of).sum() / 2, (p / u).max()))
        columns = list(zip(*out, strict=True)) or [()] * 5
        return [np.array(c) for c in columns]

    return _by_set(filters, nodes, kinds, 0, make, "set_id string, kind int, n long, reachable long, total_variation double, max_ratio double")


def recover_digest(words: DataFrame, tree: Tree, tau: float | None = None, start: int | None = None) -> DataFrame:
    """(set_id, n, sum_x) of sweep.recover over all ids, summed where it is found; sets without any have no row."""
    import numpy as np

    start = start_level(tree) if start is None else start
    if not fits(tree):
        return recover(words, tree, None, tau, start).groupBy("set_id").agg(F.count("*").alias("n"), F.sum("x").alias("sum_x"))
    nodes = nodes_of(tree)

    def make(set_id, filter_, blocks, marks, i):
        x = _in_leaves(filter_, marks[0][1][i], nodes, blocks)[0]
        return (np.array([len(x)]), np.array([x.sum()])) if len(x) else (x, x)

    return _by_set(dense(words, tree.spec), nodes, [("floored" if tau is None else "paper", tau)], start, make, "set_id string, n long, sum_x long")


def recovered_members(listed: DataFrame, spec: Spec, domain: int, tree: Tree | None = None, tau: float | None = None, start: int = 0) -> DataFrame:
    """(set_id, n_true, n_found, n_both) of sets (set_id, xs), xs their distinct ids: a set's filter is built, swept (without a tree:
    all ids are tried) and compared with its members in one task, so pairs move no second time."""
    if period(spec) is None or tree is not None and not fits(tree):
        raise ValueError("only for affine families, and trees that fit a broadcast")
    nodes = None if tree is None else nodes_of(tree)
    kind = "floored" if tau is None else "paper"

    def tried(batches):
        import numpy as np
        import pyarrow as pa

        blocks, step = _blocks(spec, turns(spec, domain)), period(spec)
        for batch in batches:
            sets, lists = batch.column(batch.schema.get_field_index("set_id")), batch.column(batch.schema.get_field_index("xs"))
            n = np.diff(lists.offsets.to_numpy()).astype(np.int64)
            found, both = np.zeros(len(n), np.int64), np.zeros(len(n), np.int64)
            for i, xs in enumerate(np.split(lists.flatten().to_numpy(), np.cumsum(n)[:-1]) if len(n) else []):
                bits = np.zeros(spec.words * 64, bool)
                for p in _placed(xs, spec):
                    bits[p] = True
                filter_ = np.packbits(bits, bitorder="little").view(np.int64)
                members = xs[(xs >= 0) & (xs < domain)]
                members = members[_yes(bits, _placed(members, spec))]
                if nodes is None:
                    for low, places in blocks():
                        found[i] += ((domain - 1 - (_yes(bits, places) + low)) // step + 1).sum()
                    both[i] = len(members)
                else:
                    live = marked(filter_[None, :], nodes, kind, tau, start)[1][0]
                    found[i] = len(_in_leaves(filter_, live, nodes, blocks)[0])
                    both[i] = live[(1 << nodes.depth) + nodes.leaf_of(members)].sum()
            yield pa.RecordBatch.from_arrays([sets, pa.array(n), pa.array(found), pa.array(both)], names=["set_id", "n_true", "n_found", "n_both"])

    return listed.select("set_id", "xs").mapInArrow(tried, "set_id string, n_true long, n_found long, n_both long")
