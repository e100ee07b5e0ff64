"""Secret scans: fixed patterns, and two character Markov models compared by log-likelihood ratio.

One model is trained on labelled random strings, one on labelled ordinary identifiers. A run of identifier characters is
reported if the random model explains its transitions better by a margin. Training, scoring and span arithmetic are SQL
expressions; the trained table has one number per pair of characters.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# The three base patterns, in the order in which kinds are listed, with the group and length that a match needs.
BASE = (
    ("assign", r"""((?i)password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    ("access", r"AKIA[A-Z0-9]+", 0, 16),
    ("hex", r"[0-9a-f]+", 0, 32),
)
#: Quick tests that any text with a kept match passes.
HINTS = {"assign": r"""((?i)password|passwd|secret|token|api_?key)["']?\x20*[:=]""", "access": "AKIA[A-Z0-9]{12}", "hex": "[0-9a-f]{32}"}
#: For kinds where one match is one whole run, runs too short are not worth listing.
RUNS = {"hex": "[0-9a-f]{32,}", "access": "AKIA[A-Z0-9]{12,}"}
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
TOKEN = r"[A-Za-z0-9+/_=-]{20,}"
KINDS = [*(k for k, *_ in BASE), "markov"]


def spans(text: Column, pattern: str, kind: str, group: int = 0, least: int = 0) -> Column:
    """Array of (start, kind number, end, value) of the matches, in code points: lengths of matches and of what is between add up."""
    between, found, value = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.regexp_extract_all(text, F.lit(pattern), F.lit(group))
    pieces = F.zip_with(between, F.arrays_zip(found.alias("f"), value.alias("v")), lambda b, m: F.struct(F.length(b).alias("gap"), F.coalesce(F.length(m["f"]), F.lit(0)).alias("size"), m["v"].alias("v")))

    def placed(x):
        before = running(F.transform(x, lambda p: p["gap"] + p["size"]))
        return let(F.struct(x.alias("x"), before.alias("before")), lambda s: F.transform(s["x"], lambda p, i: F.struct((F.get(s["before"], i) + p["gap"]).alias("start"), F.lit(KINDS.index(kind)).alias("kind"), (F.get(s["before"], i) + p["gap"] + p["size"]).alias("end"), p["v"].alias("value"))))

    return F.filter(let(pieces, placed), lambda s: F.length(s["value"]) >= least)


def let(value: Column, then) -> Column:
    """then(value) with value evaluated once."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def touches(spans: Column, one: Column) -> Column:
    """Whether one span overlaps any of the spans, which are in order and apart: those that start before its end are counted by
    halving, and the last of them decides."""
    turns = F.ceil(F.log2(F.size(spans) + 1)).cast("int")

    def halve(s, _):
        mid = F.call_function("div", s["low"] + s["high"], F.lit(2)).cast("int")
        return F.when(s["low"] >= s["high"], s).when(F.get(spans, mid)["start"] < one["end"], F.struct((mid + 1).alias("low"), s["high"].alias("high"))).otherwise(F.struct(s["low"].alias("low"), mid.alias("high")))

    n = F.aggregate(F.sequence(F.lit(0), turns), F.struct(F.lit(0).alias("low"), F.size(spans).alias("high")), halve)["low"]
    return (F.size(spans) > 0) & F.coalesce(F.get(spans, n - 1)["end"] > one["start"], F.lit(False))


def running(values: Column, block: int = 128) -> Column:
    """Sum of all values before each place of an array of int. Blocks are summed up by themselves and then moved, so that a text
    with very many matches costs little more per match than one with few."""
    empty = F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out"))
    add = lambda acc, x: F.struct((acc["at"] + x).alias("at"), F.array_append(acc["out"], acc["at"]).alias("out"))

    def of(v):
        firsts = F.when(F.size(v) > 0, F.sequence(F.lit(0), F.size(v) - 1, F.lit(block))).otherwise(F.array().cast("array<int>"))
        blocks = F.transform(firsts, lambda a: F.aggregate(F.transform(F.sequence(a, F.least(a + block, F.size(v)) - 1), lambda i: F.get(v, i)), empty, add))
        moved = lambda b: let(F.struct(b.alias("b"), F.aggregate(b, empty, lambda acc, x: add(acc, x["at"]))["out"].alias("off")), lambda s: F.flatten(F.transform(s["b"], lambda x, k: F.transform(x["out"], lambda o: o + F.get(s["off"], k)))))
        return let(blocks, moved)

    return let(values, of)


def _none() -> Column:
    return F.array().cast("array<struct<start:int,kind:int,end:int,value:string>>")


def _pairs(value: Column) -> Column:
    """Numbers (1-based) of the pairs of neighbouring characters, null outside the alphabet."""
    codes = F.transform(F.split(value, ""), lambda c: F.when(c != "", F.instr(F.lit(ALPHABET), c)))
    number = lambda c, i: let(F.struct(F.get(c, i).alias("a"), F.get(c, i + 1).alias("b")), lambda p: F.when((p["a"] > 0) & (p["b"] > 0), (p["a"] - 1) * len(ALPHABET) + p["b"]))
    return let(codes, lambda c: F.transform(F.when(F.size(c) > 1, F.sequence(F.lit(0), F.size(c) - 2)).otherwise(F.array().cast("array<int>")), lambda i: number(c, i)))


def train(samples: DataFrame, smooth: float = 0.5) -> list[float]:
    """samples: value, random (boolean). One log-likelihood ratio per character pair; the counts collected are bounded by the alphabet."""
    size = len(ALPHABET)
    pairs = samples.select("random", F.explode(_pairs(F.col("value"))).alias("pair")).filter("pair is not null")
    counts = {True: [smooth] * size**2, False: [smooth] * size**2}
    for row in pairs.groupBy("random", "pair").count().collect():
        counts[row["random"]][row["pair"] - 1] += row["count"]
    rows = {k: [sum(v[a * size : a * size + size]) for a in range(size)] for k, v in counts.items()}
    return [round(math.log(counts[True][i] / rows[True][i // size]) - math.log(counts[False][i] / rows[False][i // size]), 6) for i in range(size**2)]


def default_samples(spark: SparkSession, docs: DataFrame, n_random: int = 3000, n_docs: int = 200) -> DataFrame:
    """Labelled samples. Random: digests in hexadecimal, base64 and upper case. Ordinary: the words of the n_docs (a documented
    bound) documents with the smallest key, their whole texts, alone, with underscores, hyphens, capitals and short numbers."""
    seed = F.sha2(F.concat(F.lit("sample:"), F.col("id").cast("string")), 256)
    coded = F.base64(F.unhex(seed))
    forms = F.array(F.substring(seed, 1, 40), F.substring(coded, 1, 32), F.upper(F.substring(F.regexp_replace(coded, "[+/=]", "Z"), 1, 20)), F.translate(F.substring(coded, 1, 40), "+/", "-_"))
    random = spark.range(n_random).select(F.explode(forms).alias("value"), F.lit(True).alias("random"))
    # Few texts, but many strings come from them.
    few = docs.select("text", F.xxhash64("doc_id").alias("k")).filter("text is not null").orderBy("k", F.xxhash64("text")).limit(n_docs).repartition(64)
    flat = few.select(F.filter(F.split("text", "[^A-Za-z]+", -1), lambda w: w.rlike("^[A-Za-z]{2,}$")).alias("w"))
    k = F.lit(3)
    three = F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - k, F.lit(1))), lambda i: F.concat_ws("_", F.get("w", i - 1), F.get("w", i), F.get("w", i + 1)))
    named = flat.filter(F.size("w") > 4).select(F.explode(three).alias("v"))
    ways = F.array("v", F.translate("v", "_", "-"), F.upper("v"), F.regexp_replace(F.initcap(F.translate("v", "_", " ")), " ", ""), F.concat("v", F.lit("_"), (F.length("v") % 20).cast("string")))
    return random.unionByName(named.select(F.explode(ways).alias("value"), F.lit(False).alias("random")))


def scan(docs: DataFrame, table: list[float] | None, margin: float = 12.0, per_pair: float = 0.4, carry=()) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans and n_markov for each row of docs (doc_id, text).

    Null and empty texts have no span; repeated rows are scanned alike; other columns are ignored, but for those in carry.
    table: of train(), None for the base patterns only. A Markov span is a whole run of 20 identifier characters or more with a
    digit in it, whose ratio reaches margin and per_pair on average; shorter runs and runs of letters alone are not scored. It
    must not touch a base span. An empty table gives no row.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    one = docs.select("doc_id", *carry, text.alias("_t"))
    each = [F.when(F.col("_t").rlike(HINTS[k]), spans(F.col("_t"), RUNS.get(k, rx), k, group, least)).otherwise(_none()) for k, rx, group, least in BASE]
    based = one.select("doc_id", *carry, F.when(F.col("_t").rlike(TOKEN), F.col("_t")).alias("_t"), *(x.alias(f"_{k}") for x, (k, *_) in zip(each, BASE, strict=True)))
    joined = based.withColumn("_base", F.sort_array(F.concat(*(F.transform(f"_{k}", lambda s: F.struct(s["start"], s["kind"], s["end"])) for k, *_ in BASE))))
    if table is None:
        extra = _none()
    else:
        ratios = F.split(F.lit(",".join(map(str, table))), ",").cast("array<double>")
        score = lambda v: F.aggregate(_pairs(v), F.lit(0.0), lambda acc, p: acc + F.coalesce(F.get(ratios, p - 1), F.lit(0.0)))
        free = F.filter(spans(F.col("_t"), TOKEN, "markov"), lambda s: s["value"].rlike("[0-9]") & ~(touches(F.col("_assign"), s) | touches(F.col("_access"), s) | touches(F.col("_hex"), s)))
        extra = F.when(F.col("_t").isNotNull(), F.filter(free, lambda s: score(s["value"]) >= F.greatest(F.lit(margin), per_pair * (F.length(s["value"]) - 1)))).otherwise(_none())
    listed = joined.withColumn("_more", F.transform(extra, lambda s: F.struct(s["start"], s["kind"], s["end"])))
    names = F.array(*(F.lit(k) for k in KINDS))
    text_of = lambda a: F.array_join(F.transform(a, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"], s["end"])), ",")
    return listed.select(
        "doc_id", *carry, *(F.size(f"_{k}").cast("long").alias(f"n_{k}") for k, *_ in BASE),
        F.sha2(text_of(F.col("_base")), 256).alias("base_sha256"), text_of(F.sort_array(F.concat("_base", "_more"))).alias("spans"), F.size("_more").cast("long").alias("n_markov"),
    )
