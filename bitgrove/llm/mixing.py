"""Mixing sources to target weights by weighted fair queueing.

Every shuffled document gets a virtual finish time, its source's cumulative size up to it over the source's target; a source
whose target exceeds its size queues its documents again for a second turn. The queue is range-sorted on the finish time and
cut where the running total reaches the budget. A source's cumulative sizes come from windows over small slices of its
shuffled order plus slice offsets, so a source with a third of all rows is spread over many tasks.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import n_words, stored

#: Documents that a slice of a source's shuffled order, and of the queue, holds on average, at most.
SLICE_ROWS = 20_000


def source_targets(sizes: DataFrame, weights=(5, 2, 1), share: float = 1.5, turns: int = 2) -> DataFrame:
    """(source, size) to one row per source: source_size, weight, target.

    Sources by code point, null last, take the weights in turn and share `share` of all sizes by weight; a target stops at
    `turns` times its source's size and the excess is reshared by weight. The level at which all others stop follows from one
    sort by size per weight.
    """
    by_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    rank = (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights)
    weighed = by_source.withColumn("weight", F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (rank + 1).cast("int")))
    full = weighed.withColumn("cap", turns * F.col("source_size").cast("double")).withColumn("ratio", F.col("cap") / F.col("weight"))
    order = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    every = Window.partitionBy()
    before = full.withColumns({
        "budget": F.sum("source_size").over(every) * F.lit(share),
        "capped": F.sum("cap").over(order) - F.col("cap"),
        "rest": F.sum("weight").over(every) - F.sum("weight").over(order) + F.col("weight"),
    }).withColumn("level", (F.col("budget") - F.col("capped")) / F.col("rest"))
    level = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", "level"))).over(every)["level"]
    return before.withColumn("at", level).select("source", "source_size", "weight", F.least("cap", F.coalesce(F.col("weight") * F.col("at"), F.col("cap"))).alias("target"))


def mix(docs: DataFrame, weights=(5, 2, 1), share: float = 1.5, turns: int = 2, seed: int = 11, carry=()) -> DataFrame:
    """doc_id, size (words), source_size, target, taken and n_taken (whole turns) for each row of docs (doc_id, text, source).

    A null source is a source of its own, the last; null and blank texts have size 0 and are never taken; repeated rows queue
    one after the other; ties in the queue are taken together or not at all; other columns are ignored, but for those named
    in carry. An empty table gives no row. The order depends on seed, doc_id, source and text only, so reruns agree.
    """
    names = {c: f"_carried{i}" for i, c in enumerate(carry)}
    kept = list(names.values())
    key = F.xxhash64(F.lit(seed), "doc_id", "source", "text")
    sized = stored(docs.select("doc_id", "source", *(F.col(c).alias(n) for c, n in names.items()), n_words(F.col("text")).alias("size"), key.alias("key")), "sizes")
    rows = sized.count()
    # Each source gets slices by its rows, all of about one size.
    slice_rows = min(SLICE_ROWS, max(200, rows // 256))
    targets = stored(source_targets(sized, weights, share, turns).join(sized.groupBy(F.col("source").alias("s")).agg(F.ceil(F.count("*") / slice_rows).alias("slices")), F.col("source").eqNullSafe(F.col("s"))).drop("s"), "targets")
    of = targets.select(F.col("source").alias("of"), "slices")
    sliced = sized.join(of, F.col("source").eqNullSafe(F.col("of"))).withColumn("slice", F.pmod(F.shiftrightunsigned("key", 20), F.col("slices"))).drop("of", "slices")
    within = Window.partitionBy("source", "slice").orderBy("key", "doc_id", "size", *kept)
    offsets = sliced.groupBy("source", "slice").agg(F.sum("size").alias("of_slice")).withColumn("before", F.sum("of_slice").over(Window.partitionBy("source").orderBy("slice")) - F.col("of_slice"))
    offsets = offsets.join(targets, offsets.source.eqNullSafe(targets.source)).select(offsets.source, "slice", "before", "source_size", "target")
    queued = sliced.withColumn("upto", F.sum("size").over(within.rowsBetween(Window.unboundedPreceding, 0)))
    at = offsets.select(F.col("source").alias("s"), F.col("slice").alias("p"), "before", "source_size", "target")
    queued = queued.join(at, F.col("source").eqNullSafe(F.col("s")) & (F.col("slice") == F.col("p")))
    finish = [(F.lit(t) * F.col("source_size") + F.col("before") + F.col("upto")) / F.col("target") for t in range(turns)]
    queued = stored(queued.select("doc_id", *kept, "size", "source_size", "target", *(F.when(F.col("size") > 0, f).alias(f"finish{t}") for t, f in enumerate(finish))), "queue")
    cut = _cut(queued, turns, targets.agg(F.sum("source_size")).first()[0] or 0, share, rows)
    taken = sum((F.when(F.col(f"finish{t}") <= F.lit(cut), 1).otherwise(0) for t in range(turns)), F.lit(0))
    return queued.select("doc_id", *(F.col(n).alias(c) for c, n in names.items()), "size", "source_size", "target", (F.col("size") * taken).cast("long").alias("taken"), taken.alias("n_taken"))


def _cut(queued: DataFrame, turns: int, total: int, share: float, rows: int) -> float:
    """The last finish time at which the running total of the range-sorted queue stays within the budget."""
    slices = min(max(1024, rows * turns // SLICE_ROWS), 1 << 20)
    entries = queued.select("size", F.explode(F.array(*(F.col(f"finish{t}") for t in range(turns)))).alias("finish")).filter("finish is not null")
    ranged = entries.withColumn("slice", F.floor(F.least("finish", F.lit(8.0)) * slices))
    sums = ranged.groupBy("slice").agg(F.sum("size").alias("of_slice")).withColumn("upto", F.sum("of_slice").over(Window.orderBy("slice")))
    split = sums.filter(F.col("upto") > total * share).orderBy("slice").first()
    if split is None:
        return math.inf
    inside = ranged.filter(F.col("slice") == split["slice"]).groupBy("finish").agg(F.sum("size").alias("size"))
    upto = inside.withColumn("upto", F.sum("size").over(Window.orderBy("finish")) + (split["upto"] - split["of_slice"]))
    last = upto.filter(F.col("upto") <= total * share).agg(F.max("finish")).first()[0]
    return split["slice"] / slices - 1e-12 if last is None else last
