"""Quality rules with risk-controlled thresholds.

Each rule compares one ratio of a document with a cutoff. Per stratum, labelled good documents that a cutoff would reject are
counted, and a cutoff is allowed if the exact binomial (Clopper-Pearson) upper bound of its false rejection rate stays below
the rule's share of the risk, at a confidence corrected for all rules, cutoffs and strata tried. The strictest allowed cutoff
is taken; a stratum with too few labels gets none. Cutoffs come from a fixed grid, so every label serves as holdout.

The joint way needs fewer labels: all rules go from lenient to strict together, a step of the grid at a time, and the good
documents that any rule would reject are held against the whole risk. The steps are fixed beforehand, nested, and end at the
first that is not allowed, so the confidence is corrected for the strata only.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, stored, words

#: Ratio of a document, and the cutoffs tried, from strict to lenient; a document above the cutoff is rejected.
RULES = {
    "symbols_per_word": ("n_symbols / n_words", (0.05, 0.1, 0.15, 0.2, 0.3, 0.4, 0.6, 0.8, 1.0, 1.5)),
    "repeated_share": ("n_repeat_words / n_words", (0.05, 0.1, 0.15, 0.2, 0.25, 0.3, 0.35, 0.4, 0.45)),
    "duplicate_lines": ("n_dup_lines / n_lines", (0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.8)),
    "word_length": ("word_chars / n_words", (6.0, 6.5, 7.0, 7.5, 8.0, 9.0, 10.0, 12.0, 15.0, 20.0)),
}
#: Bytes that the cutoffs of one stratum take in a broadcast, at most.
STRATUM_BYTES = 512


def measured(docs: DataFrame, carry=()) -> DataFrame:
    """doc_id, carry, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines of each whole text (null: none)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    one = docs.select("doc_id", *carry, text.alias("_t"))
    split = one.select("doc_id", *carry, words(F.col("_t")).alias("_w"), F.filter(F.split("_t", "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("_l"), F.length(F.regexp_replace("_t", "[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"))
    triples = F.transform(F.sequence(F.lit(1), F.size("_w") - 2), lambda i: F.xxhash64(F.element_at("_w", i), F.element_at("_w", i + 1), F.element_at("_w", i + 2)))
    counted = split.select(
        "doc_id", *carry, "n_symbols",
        F.size("_w").cast("long").alias("n_words"),
        F.length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        F.size("_l").cast("long").alias("n_lines"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.when(F.size("_w") >= 3, triples).otherwise(F.array().cast("array<bigint>")).alias("_h"),
    )
    ordered = F.sort_array(F.transform("_h", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    found = counted.withColumn("_s", F.when(F.size(F.array_distinct("_h")) < F.size("_h"), ordered))
    place = F.transform(F.sequence(F.lit(0), F.size("_s") - 1), lambda k: F.when((F.get("_s", k)["h"] == F.get("_s", k - 1)["h"]) | (F.get("_s", k)["h"] == F.get("_s", k + 1)["h"]), F.get("_s", k)["i"]))
    placed = found.withColumn("_p", F.when(F.col("_s").isNotNull(), F.sort_array(F.filter(place, lambda x: x.isNotNull()))))
    reach = F.aggregate(F.sequence(F.lit(1), F.size("_p")), F.lit(0), lambda n, k: n + F.coalesce(F.least(F.lit(3), F.get("_p", k) - F.get("_p", k - 1)), F.lit(3)))
    repeated = F.when(F.size("_p") > 0, reach).otherwise(0)
    return placed.select("doc_id", *carry, "n_words", "word_chars", "n_symbols", "n_dup_lines", F.coalesce(repeated, F.lit(0)).cast("long").alias("n_repeat_words"), "n_lines")


def _ratio(of: str):
    above, below = of.split(" / ")
    return F.try_divide(F.col(above), F.col(below))


def binomial_tail(n: int, p: float, x: int) -> float:
    """P(at most x of n), in exact terms from the largest on until they add nothing: some square roots of n terms."""
    if x >= n:
        return 1.0
    below = x < n * p
    k, end, step = (x, -1, -1) if below else (x + 1, n + 1, 1)
    log = math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1) + k * math.log(p) + (n - k) * math.log1p(-p)
    term = total = 1.0
    for j in range(k, end - step, step):
        term *= j * (1 - p) / ((n - j + 1) * p) if below else (n - j) * p / ((j + 1) * (1 - p))
        total += term
        if term < 1e-18 * total:
            break
    part = math.exp(log) * total
    return min(1.0, part) if below else max(0.0, 1.0 - part)


def allowed(n: int, p: float, level: float) -> int:
    """The most rejections of n good documents for which the exact upper bound at this level is at most p; -1: none."""
    if n == 0 or binomial_tail(n, p, 0) > level:
        return -1
    low, high = 0, n
    while high - low > 1:
        mid = (low + high) // 2
        low, high = (mid, high) if binomial_tail(n, p, mid) <= level else (low, mid)
    return low


def _log_gamma(z: Column) -> Column:
    """Logarithm of the gamma function for z of 1 or more: a series at z + 8, led back."""
    y = z + 8.0
    series = (y - 0.5) * F.log(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y * y * y) + 1 / (1260 * F.pow(y, F.lit(5.0))) - 1 / (1680 * F.pow(y, F.lit(7.0)))
    return series - sum((F.log(z + float(i)) for i in range(1, 8)), F.log(z))


def tail_at_most(n: Column, p: float, x: Column, level: Column | float) -> Column:
    """Whether P(at most x of n) is at most level, which is under a quarter: false from the mean n p on, below it the sum of
    terms from x downwards over ten standard deviations."""
    n, x = n.cast("double"), x.cast("double")
    log = _log_gamma(n + 1) - _log_gamma(x + 1) - _log_gamma(n - x + 1) + x * math.log(p) + (n - x) * math.log1p(-p)
    terms = F.sequence(F.lit(0), F.least(x, F.ceil(10 * F.sqrt(n * (p * (1 - p))) + 60)).cast("int"))

    def add(acc, i):
        k = x - i
        return F.struct((acc["term"] * k * ((1 - p) / p) / (n - k + 1)).alias("term"), (acc["total"] + acc["term"]).alias("total"))

    total = F.aggregate(terms, F.struct(F.lit(1.0).alias("term"), F.lit(0.0).alias("total")), add)["total"]
    return F.when(x < n * p, log + F.log(total) <= F.log(F.lit(level) if isinstance(level, float) else level)).otherwise(F.lit(False))


def _good(features: DataFrame, labels: DataFrame) -> DataFrame:
    good = labels.groupBy("doc_id").agg(F.min("quality").alias("quality")).filter("quality = 1").select("doc_id")
    return features.filter("not base_failed").join(good, "doc_id", "left_semi")


def cutoffs(features: DataFrame, labels: DataFrame, stratum: str = "lang", risk: float = 0.02, level: float = 0.05) -> DataFrame:
    """A row per stratum: stratum, and a column per rule with its cutoff, null for none. labels: doc_id, quality (1: good)."""
    held = _good(features, labels)
    tried = [(rule, c, f"_{r}_{i}") for r, (rule, (_, grid)) in enumerate(RULES.items()) for i, c in enumerate(grid)]
    counts = stored(held.groupBy(F.col(stratum).alias("_stratum")).agg(F.count("*").alias("_n"), *(F.count_if(_ratio(RULES[rule][0]) > c).alias(name) for rule, c, name in tried)), "counts")
    share = level / max(1, len(tried) * counts.count())
    ok = {name: tail_at_most(F.col("_n"), risk / len(RULES), F.col(name), share) for _, _, name in tried}
    return counts.select("_stratum", *(F.least(*(F.when(ok[name], F.lit(c)) for r, c, name in tried if r == rule)).alias(f"_cut_{rule}") for rule in RULES))


def steps() -> list[dict]:
    """Rule to cutoff, from the most lenient to the strictest; a rule with a shorter grid stays at its strictest."""
    return [{rule: grid[max(0, len(grid) - 1 - t)] for rule, (_, grid) in RULES.items()} for t in range(max(len(grid) for _, grid in RULES.values()))]


def least_labels(strata: int, risk: float = 0.02, level: float = 0.05) -> int:
    """Good documents that a stratum needs before the joint way allows a step, if none of them is rejected."""
    return math.ceil(math.log(level / max(1, strata)) / math.log1p(-risk))


def _over(rules: dict) -> Column:
    out = F.lit(False)
    for rule, c in rules.items():
        out = out | F.coalesce(_ratio(RULES[rule][0]) > c, F.lit(False))
    return out


def joint_cutoffs(features: DataFrame, labels: DataFrame, stratum: str = "lang", risk: float = 0.02, level: float = 0.05) -> DataFrame:
    """As cutoffs, by the joint way: the last step before the first that is not allowed."""
    path = steps()
    counts = stored(_good(features, labels).groupBy(F.col(stratum).alias("_stratum")).agg(F.count("*").alias("_n"), *(F.count_if(_over(rules)).alias(f"_step{t}") for t, rules in enumerate(path))), "counts")
    share = level / max(1, counts.count())
    reached = F.lit(0)
    for t in reversed(range(len(path))):
        reached = F.when(tail_at_most(F.col("_n"), risk, F.col(f"_step{t}"), share), 1 + reached).otherwise(0)
    at = counts.select("_stratum", reached.alias("_reached"))
    return at.select("_stratum", *(F.get(F.array(*(F.lit(rules[rule]) for rules in path)), F.col("_reached") - 1).alias(f"_cut_{rule}") for rule in RULES))


def judge(docs: DataFrame, labels: DataFrame, stratum: str = "lang", risk: float = 0.02, level: float = 0.05, carry=(), joint: bool = False) -> DataFrame:
    """Features, base_failed and kept for each row of docs (doc_id, text, stratum); joint: cutoffs by the joint way.

    Null and empty texts have no words and fail the base rules; repeated rows are judged alike; a null stratum is one of its
    own; a ratio without words or lines never rejects; labels may repeat (the lowest counts), be null or name no document.
    Other columns are ignored, but for those named in carry. Empty tables give no row.
    """
    base = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    features = stored(measured(docs, tuple(dict.fromkeys([stratum, *carry]))).withColumn("base_failed", base), "features")
    cuts = stored((joint_cutoffs if joint else cutoffs)(features, labels, stratum, risk, level), "cutoffs")
    n, widest = cuts.agg(F.count("*"), F.max(F.length(F.col("_stratum").cast("string")))).first()
    by = F.broadcast(cuts) if n * (STRATUM_BYTES + 8 * (widest or 0)) <= BROADCAST_BYTES else cuts
    held = features.join(by, features[stratum].eqNullSafe(cuts["_stratum"]), "left")
    return held.select(*(features[c] for c in features.columns), (~F.col("base_failed") & ~_over({rule: F.col(f"_cut_{rule}") for rule in RULES})).alias("kept"))
