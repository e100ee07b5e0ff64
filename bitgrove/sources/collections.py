"""Set collections (set_id, x) over the given tables, and the domains that they lie in."""

from __future__ import annotations

import hashlib
import random

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SPARSE_DOMAIN = 2147483647


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def domain_of(spark: SparkSession, sf_dir: str, name: str = "orders", key: str = "o_orderkey") -> int:
    """Ids are 0..domain-1; the largest is read from the table's statistics or one aggregate."""
    return (table(spark, sf_dir, name).agg(F.max(key)).first()[0] or 0) + 1


def all_ids(spark: SparkSession, domain: int) -> DataFrame:
    return spark.range(domain).select(F.col("id").alias("x"))


def pairs(rows: DataFrame, set_id: Column | str, x: Column | str) -> DataFrame:
    """Distinct (set_id, x); nulls drop out."""
    s, v = (F.col(c) if isinstance(c, str) else c for c in (set_id, x))
    return rows.select(s.cast("string").alias("set_id"), v.cast("long").alias("x")).filter("x is not null and set_id is not null").distinct()


def orders_by_supplier(spark, sf_dir):
    return pairs(table(spark, sf_dir, "lineitem"), "l_suppkey", "l_orderkey")


def orders_dealt_by_supplier(spark, sf_dir, distinct: bool = True):
    """The same, moved once: a supplier's rows lie in one task, where they are made distinct and its filter is built. For sets of
    like size, none of which is too much for a task. Not distinct: rows as they are, not dealt yet."""
    rows = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").cast("string").alias("set_id"), F.col("l_orderkey").cast("long").alias("x"))
    rows = rows.filter("x is not null and set_id is not null")
    return pairs(rows.repartition("set_id"), "set_id", "x") if distinct else rows


def orders_by_part(spark, sf_dir):
    return pairs(table(spark, sf_dir, "lineitem"), "l_partkey", "l_orderkey")


def orders_by_flag(spark, sf_dir):
    return pairs(table(spark, sf_dir, "lineitem"), "l_returnflag", "l_orderkey")


def orders_by_key_run(spark, sf_dir, sets: int = 5, runs: int = 6, length: int = 100):
    """Clustered sets: runs of consecutive keys whose starts come from digests."""
    domain = domain_of(spark, sf_dir)
    start = F.pmod(F.conv(F.substring(F.md5(F.concat_ws(":", F.col("id").cast("string"), F.col("r").cast("string"))), 1, 8), 16, 10).cast("long"), F.lit(domain - length))
    laid = spark.range(sets).select("id", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("r")).select("id", F.explode(F.sequence(start, start + length - 1)).alias("x"))
    return pairs(laid, "id", "x")


def customers_by_nation(spark, sf_dir):
    return pairs(table(spark, sf_dir, "customer"), "c_nationkey", "c_custkey")


def users_by_type_day(spark, sf_dir):
    day = F.date_format(F.date_trunc("day", F.col("ts")), "yyyy-MM-dd")
    return pairs(table(spark, sf_dir, "events"), F.concat_ws("/", F.col("event_type"), day), "user_id")


def docs_by_token(spark, sf_dir, share: float = 0.05):
    """Words of lower-case ASCII letters that occur in this share of all documents, or more."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    tokens = pairs(docs.select("doc_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("t")).filter("t <> ''"), "t", "doc_id")
    least = docs.count() * share
    often = tokens.groupBy("set_id").count().filter(F.col("count") >= least).select("set_id")
    return tokens.join(often, "set_id", "left_semi")


def docs_by(spark, sf_dir, column: str):
    return pairs(table(spark, sf_dir, "documents"), column, "doc_id")


def pages_by_host(spark, sf_dir):
    return pairs(table(spark, sf_dir, "pages").withColumn("host", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)), "host", "page_id")


def sparse_id(x: Column) -> Column:
    """Scatters dense ids one to one over a domain of 2**31 - 1."""
    return F.pmod(x * 48271 + 11, F.lit(SPARSE_DOMAIN))


def kept_ranges(fraction: float, layout: str, ranges: int = 256) -> list[int]:
    """The ranges of a domain part: those of smallest digest ('uniform'), or drawn as clustered sets are ('clustered')."""
    keep = int(ranges * fraction + 0.5)
    if layout == "clustered":
        return sorted(ClusteredDraws(ranges, 10.0, 42).drawn(keep))
    return sorted(sorted(range(ranges), key=lambda r: hashlib.md5(str(r).encode()).hexdigest())[:keep])


def range_of(x: Column, domain: int = SPARSE_DOMAIN, bits: int = 8) -> Column:
    """Which of the 2**bits equal ranges of the domain holds x."""
    return F.call_function("div", F.shiftleft(x, bits), F.lit(domain).cast("long"))


def domain_part(x: Column, fraction: float, layout: str, domain: int = SPARSE_DOMAIN) -> Column:
    """Whether an id lies in the kept ones of 256 equal ranges."""
    return range_of(x, domain).isin(kept_ranges(fraction, layout))


def uniform_set(spark: SparkSession, domain: int, n: int, seed: int = 42) -> DataFrame:
    """n ids of the domain without replacement: those with the smallest digests."""
    keyed = all_ids(spark, domain).withColumn("key", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("x").cast("string"))))
    return keyed.orderBy("key").limit(n).select(F.lit("u").alias("set_id"), "x")


class ClusteredDraws:
    """Draws without replacement that cluster: a drawn id leaves half of its probability to the nearest undrawn id on each side
    (all of it, if there is one side only); then every id gives p per cent of its probability, which those two share alike.

    Ids that never neighboured a drawn one all have one probability, so only the others are kept: their surplus over it, in a
    tree of partial sums, times a common factor that the p per cent shrink. A draw costs the logarithm of the draws so far,
    whatever the domain."""

    def __init__(self, domain: int, p: float, seed: int):
        self.domain, self.keep, self.rng = domain, 1 - p / 100, random.Random(seed)
        self.base, self.factor, self.n = 1.0, 1.0, 0
        self.ids: list[int] = []
        self.place: dict[int, int] = {}
        self.tree = [0.0, 0.0]
        self.beside = {-1: {}, 1: {}}
        self.gone: set[int] = set()

    def _surplus(self, place: int) -> float:
        """Surplus at a place, before the factor."""
        value, at, low = self.tree[place], place - 1, place - (place & -place)
        while at > low:
            value -= self.tree[at]
            at -= at & -at
        return max(value, 0.0)

    def _add(self, place: int, by: float) -> None:
        while place < len(self.tree):
            self.tree[place] += by
            place += place & -place

    def _grow(self, x: int, by: float) -> None:
        if (at := self.place.get(x)) is None:
            if len(self.ids) + 1 >= len(self.tree):
                old = [self._surplus(i) for i in range(1, len(self.ids) + 1)]
                self._fill(old, 2 * len(self.tree))
            self.ids.append(x)
            at = self.place[x] = len(self.ids)
        self._add(at, by / self.factor)

    def _fill(self, values: list[float], size: int) -> None:
        self.tree = [0.0, *values] + [0.0] * (size - len(values) - 1)
        for i in range(1, size):
            if (up := i + (i & -i)) < size:
                self.tree[up] += self.tree[i]

    def _next(self, x: int, step: int) -> int | None:
        """The nearest undrawn id on one side; walked ways are shortened."""
        skip, way, at = self.beside[step], [], x + step
        while at in self.gone:
            way.append(at)
            at = skip.get(at, at + step)
        for w in way:
            skip[w] = at
        return at if 0 <= at < self.domain else None

    def mass(self, x: int) -> float:
        """Unscaled probability of an id; all add up to the size of the domain."""
        return 0.0 if x in self.gone else self.base + (self._surplus(self.place[x]) * self.factor if x in self.place else 0.0)

    def _pick(self) -> int:
        plain = self.base * (self.domain - len(self.gone))
        extra = self._total() * self.factor
        u = self.rng.random() * (plain + extra)
        if u >= plain and extra > 0:
            u, at, step = (u - plain) / self.factor, 0, len(self.tree) >> 1
            while step:
                if at + step < len(self.tree) and self.tree[at + step] <= u:
                    at += step
                    u -= self.tree[at]
                step >>= 1
            x = self.ids[min(at, len(self.ids) - 1)]
            if x not in self.gone:
                return x
        for _ in range(64):
            if (x := self.rng.randrange(self.domain)) not in self.gone:
                return x
        # Nearly all are drawn: the undrawn ones are few enough to list.
        return self.rng.choice([x for x in range(self.domain) if x not in self.gone])

    def _total(self) -> float:
        total, at = 0.0, len(self.tree) - 1
        while at:
            total += self.tree[at]
            at -= at & -at
        return total

    def take(self, x: int) -> None:
        """Takes x out and moves probabilities."""
        own = self.mass(x)
        if x in self.place:
            self._add(self.place[x], -self._surplus(self.place[x]))
        self.gone.add(x)
        near = [v for v in (self._next(x, -1), self._next(x, 1)) if v is not None]
        for v in near:
            self._grow(v, own / len(near))
        if self.keep < 1 and near:
            self.base *= self.keep
            self.factor *= self.keep
            for v in near:
                self._grow(v, self.domain * (1 - self.keep) / len(near))
            if self.factor < 1e-100:
                values = [self._surplus(i) * self.factor for i in range(1, len(self.ids) + 1)]
                self.factor = 1.0
                self._fill(values, len(self.tree))

    def drawn(self, n: int) -> list[int]:
        out = []
        for _ in range(min(n, self.domain)):
            out.append(self._pick())
            self.take(out[-1])
        return out


def clustered_set(spark: SparkSession, domain: int, n: int, sets: int = 1, p: float = 10.0, seed: int = 42) -> DataFrame:
    """Sets of clustered draws, one task per set, in memory that follows n alone; (set_id, x)."""
    import pandas as pd

    def make(pdf: pd.DataFrame) -> pd.DataFrame:
        s = int(pdf.s[0])
        out = ClusteredDraws(domain, p, seed + s).drawn(n)
        return pd.DataFrame({"set_id": [f"c{s}"] * len(out), "x": out})

    return spark.range(sets).withColumnRenamed("id", "s").groupBy("s").applyInPandas(make, "set_id string, x long")


def clustered_sets(sizes: DataFrame, domain: int, p: float = 10.0, seed: int = 42) -> DataFrame:
    """For each (set_id, n) a set of n clustered draws, (set_id, x): one task per set, with a seed of its own."""
    import pandas as pd

    def make(pdf: pd.DataFrame) -> pd.DataFrame:
        s, n = str(pdf.set_id[0]), int(pdf.n[0])
        own = int(hashlib.md5(f"{seed}:{s}".encode()).hexdigest()[:12], 16)
        out = ClusteredDraws(domain, p, own).drawn(n)
        return pd.DataFrame({"set_id": [s] * len(out), "x": out})

    return sizes.repartition(64, "set_id").groupBy("set_id").applyInPandas(make, "set_id string, x long")
