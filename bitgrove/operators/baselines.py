"""What the tree is compared with: probing the whole domain, and enumerating the preimages of bits."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.digests import coins, ranked
from ..functions.hashing import Spec, period
from ..sources.scratch import stored
from .descent import coin, random_key
from .filters import BROADCAST_BYTES, as_arrays, check_held, check_pairs, contains, ones, set_bits
from .whole import _blocks, _divider, _filters_of, _taker, by_set, counted, dealt, dense, digest, divided, found_by, listable, looked_up, parts_for, positives, probed, spread, turns, without_unset

#: What a set id takes in a broadcast, at most.
ID_BYTES = 256


def probe_recover(ids: DataFrame, words: DataFrame, spec: Spec, way: str = "auto") -> DataFrame:
    """(set_id, x): every id is tried."""
    return contains(ids, words, spec, way)


def probe_whole(words: DataFrame, spec: Spec, domain: int, way: str = "each") -> DataFrame:
    """(set_id, r): what each filter answers yes for among all ids 0..domain-1, as those of one period of the hash functions; spread
    lists the ids, digest counts them. 'each': a set's task tries its filter; 'division': it divides the set's bits."""
    return divided(words, spec, domain) if way == "division" else positives(dense(words, spec), spec, domain)


def probe_counted(words: DataFrame, spec: Spec, domain: int, truth: DataFrame | None = None, way: str = "each") -> tuple[DataFrame, DataFrame | None]:
    """(set_id, n, sum_x) of a probe of all ids 0..domain-1, and with truth (set_id, x) how many of it are found (set_id, n_both)."""
    if way == "division" and listable(spec):
        held = stored(as_arrays(words, spec), "dense")
        found = found_by(dealt(held), spec, domain, _divider)
    elif way == "division":
        found, held = digest(probe_whole(words, spec, domain, way), spec, domain), None
    else:
        held = stored(as_arrays(words, spec), "dense")
        found = counted(dealt(held), spec, domain)
    if truth is None:
        return found, None
    members = truth.filter(F.col("x").between(0, domain - 1))
    both = check_pairs(members, words, spec) if held is None else check_held(members, held, spec)
    return found, both.groupBy("set_id").agg(F.count("*").alias("n_both"))


def probe_whole_sample(words: DataFrame, spec: Spec, domain: int, draws: int = 1, seed: int = 1) -> DataFrame:
    """probe_sample over all ids 0..domain-1: ranks are counted in the task that holds the set."""
    if period(spec) is not None:
        return _drawn_where_held(dense(words, spec), spec, domain, draws, seed)
    words = by_set(words)
    held = stored(probe_whole(words, spec, domain), "probe")
    n = digest(held, spec, domain).select("set_id", "n")
    listed = spread(held.repartition(parts_for(held.select("set_id").distinct().count()), "set_id"), spec, domain)
    ranks = lambda rows: rows.withColumn("rank", F.row_number().over(Window.partitionBy("set_id").orderBy(random_key(seed, F.lit("probe"), "set_id", "x"), "x")))
    every = words.select("set_id").distinct().join(n, "set_id", "left").select("set_id", "n", F.explode(F.sequence(F.lit(0), F.lit(draws - 1))).alias("draw"))
    aimed = every.withColumn("rank", F.floor(coin(seed, F.lit("probe"), "set_id", "draw") * F.col("n")).cast("int") + 1)
    return looked_up(aimed, listed, ["set_id"], ranks).select("set_id", "draw", "x")


def _drawn_where_held(filters: DataFrame, spec: Spec, domain: int, draws: int, seed: int) -> DataFrame:
    """The same in the memory of one set's positives: nothing but the draws leaves a task."""
    words = spec.words

    def drawn(batches):
        import numpy as np
        import pyarrow as pa

        blocks, draw = _blocks(spec, turns(spec, domain)), np.arange(draws, dtype=np.int64)
        for batch in batches:
            for set_id, filter_ in zip(batch.column(batch.schema.get_field_index("set_id")).to_pylist(), _filters_of(batch, words), strict=True):
                x, got = probed(filter_, blocks, spec, domain), pa.nulls(draws, pa.int64())
                if len(x):
                    rank = np.floor(coins(str(seed), "probe", set_id, draw) * len(x)).astype(np.int64)
                    got = pa.array(x[ranked(x, np.unique(rank), str(seed), "probe", set_id)(rank)])
                yield pa.RecordBatch.from_arrays([pa.array([set_id] * draws), pa.array(draw.astype(np.int32)), got], names=["set_id", "draw", "x"])

    return filters.select("set_id", "filter").mapInArrow(drawn, "set_id string, draw int, x long")


def preimage_unset_whole(words: DataFrame, spec: Spec, domain: int) -> DataFrame:
    """(set_id, n, sum_x) of all ids 0..domain-1 less the preimages of unset bits."""
    if listable(spec):
        return found_by(dense(words, spec), spec, domain, _taker)
    return digest(without_unset(dense(words, spec), spec, domain), spec, domain)


def _ranked(rows: DataFrame, value: str, draws: int, seed: int, what: str) -> DataFrame:
    """(set_id, draw, value): each draw names the rank it wants among the set's rows in the order of a digest, so it meets one
    row and not all of them."""
    placed = stored(rows.withColumn("rank", F.row_number().over(Window.partitionBy("set_id").orderBy(random_key(seed, F.lit(what), "set_id", value), value))), what)
    many = placed.groupBy("set_id").agg(F.max("rank").alias("n"))
    tried = many.select("set_id", "n", F.explode(F.sequence(F.lit(0), F.lit(draws - 1))).alias("draw"))
    aimed = tried.withColumn("rank", F.floor(coin(seed, F.lit(what), "set_id", "draw") * F.col("n")).cast("int") + 1)
    return aimed.join(placed, ["set_id", "rank"]).select("set_id", "draw", value)


def probe_sample(ids: DataFrame, words: DataFrame, spec: Spec, draws: int = 1, seed: int = 1) -> DataFrame:
    """(set_id, draw, x): uniform draws over the positives of a probe of all ids; null if there is none."""
    picked = _ranked(contains(ids, words, spec), "x", draws, seed, "probe")
    every = words.select("set_id").distinct().select("set_id", F.explode(F.sequence(F.lit(0), F.lit(draws - 1))).alias("draw"))
    return every.join(picked, ["set_id", "draw"], "left")


def probe_reservoir(found: DataFrame, seed: int = 1) -> DataFrame:
    """The reservoir of one over (set_id, x): walking the positives in order of id, the (j+1)-th replaces the kept one with chance
    1/(j+1). The last replacement wins, so it is a running count and a maximum. (set_id, x). Coins depend on keys alone."""
    order = Window.partitionBy("set_id").orderBy("x")
    walked = found.select("set_id", "x", F.row_number().over(order).alias("j"))
    replaced = walked.filter(coin(seed, F.lit("reservoir"), "set_id", "x") * F.col("j") < 1)
    return replaced.groupBy("set_id").agg(F.max_by("x", "j").alias("x"))


def preimages(pos: Column, spec: Spec, i: int, domain: int) -> Column:
    """Array of the ids below domain that function i sends to pos."""
    a, b = spec.a[i], spec.b[i]
    if spec.family == "affine_mod_m":
        if math.gcd(a, spec.m) != 1:
            raise ValueError("the multiplier must be prime to the length")
        first = F.pmod((pos - b) * F.lit(pow(a, -1, spec.m)), F.lit(spec.m))
        return F.when(first < domain, F.sequence(first, F.lit(domain - 1).cast("long"), F.lit(spec.m).cast("long"))).otherwise(F.array().cast("array<bigint>"))
    if spec.family == "affine_mod_p":
        inverse = pow(a, -1, spec.p)
        residues = F.transform(F.sequence(pos, F.lit(spec.p - 1).cast("long"), F.lit(spec.m).cast("long")), lambda y: F.pmod(F.pmod(y - b, F.lit(spec.p)) * F.lit(inverse), F.lit(spec.p)))
        if spec.p < domain:
            residues = F.flatten(F.transform(residues, lambda x: F.sequence(x, F.lit(domain - 1).cast("long"), F.lit(spec.p).cast("long"))))
        return F.filter(residues, lambda x: x < domain)
    raise ValueError(f"{spec.family} can't be inverted")


def _listed(bits: DataFrame, spec: Spec, domain: int, functions: str) -> DataFrame:
    """bits (set_id, pos, ...) with a row per id that one of the functions, or the first, sends there."""
    lists = [preimages(F.col("pos"), spec, i, domain) for i in range(spec.k if functions == "all" else 1)]
    return bits.withColumn("x", F.explode(F.concat(*lists) if len(lists) > 1 else lists[0]))


def preimage_sample(words: DataFrame, spec: Spec, domain: int, draws: int = 1, seed: int = 1) -> DataFrame:
    """(set_id, draw, pos, x): a random set bit, then a random one of the ids that map there and pass; null if none does."""
    chosen = _ranked(set_bits(words), "pos", draws, seed, "bit")
    fits = check_pairs(_listed(chosen, spec, domain, "all").distinct(), words, spec)
    picked = fits.groupBy("set_id", "draw").agg(F.min(F.struct(random_key(seed, F.lit("pre"), "set_id", "draw", "x").alias("key"), "x"))["x"].alias("x"))
    return chosen.join(picked, ["set_id", "draw"], "left")


def preimage_recover(words: DataFrame, spec: Spec, domain: int, ids: DataFrame, bits: str = "auto", functions: str = "all", dedup: bool = True) -> DataFrame:
    """(set_id, x). bits 'set': list the ids of every set bit, keep those that pass; 'unset': take from the domain all ids of
    unset bits; 'auto': per set whichever has fewer bits."""
    few = ones(words).select("set_id", (F.col("ones") * 2 <= spec.m).alias("by_set"))
    sides = {"set": few.select("set_id"), "unset": few.select("set_id").limit(0)} if bits == "set" else {"set": few.select("set_id").limit(0), "unset": few.select("set_id")} if bits == "unset" else {"set": few.filter("by_set").select("set_id"), "unset": few.filter("not by_set").select("set_id")}
    listed = _listed(set_bits(words.join(sides["set"], "set_id", "left_semi")), spec, domain, functions).select("set_id", "x")
    by_set = check_pairs(listed.distinct() if dedup else listed, words, spec).select("set_id", "x").distinct()
    absent = _listed(unset_bits(words.join(sides["unset"], "set_id", "left_semi"), spec), spec, domain, "all").select("set_id", "x").distinct()
    # All ids of each such set are what is asked for; only ids of sets of a checked number go to every task.
    wide = sides["unset"] if bits == "set" or sides["unset"].count() * ID_BYTES > BROADCAST_BYTES else F.broadcast(sides["unset"])
    every = ids.select("x").crossJoin(wide)
    return by_set.unionByName(every.join(absent, ["set_id", "x"], "left_anti").select("set_id", "x"))


def unset_bits(words: DataFrame, spec: Spec) -> DataFrame:
    every = words.select("set_id").distinct().select("set_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(spec.m - 1).cast("long"))).alias("pos"))
    return every.join(set_bits(words), ["set_id", "pos"], "left_anti")


def preimage_ops(words: DataFrame, spec: Spec, domain: int) -> DataFrame:
    """Per set: set bits, which side 'auto' takes, ids listed and memberships after repeats are dropped."""
    listed = _listed(set_bits(words), spec, domain, "all").groupBy("set_id").agg(F.count("*").alias("listed"), F.count_distinct("x").alias("memberships"))
    return ones(words).join(listed, "set_id").select("set_id", "ones", F.when(F.col("ones") * 2 <= spec.m, "set").otherwise("unset").alias("side"), "listed", "memberships")
