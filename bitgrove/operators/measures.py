"""Cost, accuracy and uniformity measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def upper_tail(q: Column, df: Column) -> Column:
    """P-value of a chi-squared statistic by the cube-root normal approximation and a logistic form of the normal tail."""
    c = F.lit(2.0) / (F.lit(9.0) * df)
    z = (F.pow(q / df, F.lit(1.0 / 3)) - (F.lit(1.0) - c)) / F.sqrt(c)
    return F.lit(1.0) / (F.lit(1.0) + F.exp(F.lit(1.5976) * z + F.lit(0.07056) * z * z * z))


def _draws(samples: DataFrame) -> Column:
    """Rows of samples are draws, or ids with how many times they were drawn."""
    return F.sum("times") if "times" in samples.columns else F.count("*")


def chi_square(samples: DataFrame, members: DataFrame) -> DataFrame:
    """samples (set_id, x), members (set_id, x), distinct: statistic over the members of each set, those never drawn too, with
    as many draws expected for each as fell on a member on average. set_id, n, draws, q, df, p_value."""
    drawn = samples.filter("x is not null").groupBy("set_id", "x").agg(_draws(samples).alias("o"))
    each = members.join(drawn, ["set_id", "x"], "left").select("set_id", "x", F.coalesce("o", F.lit(0)).alias("o"))
    sums = each.groupBy("set_id").agg(F.count("*").alias("n"), F.sum("o").alias("draws"), F.sum(F.col("o") * F.col("o")).alias("squares"))
    e = F.col("draws") / F.col("n")
    stat = sums.withColumn("q", F.when(F.col("draws") > 0, F.col("squares") / e - F.col("draws"))).withColumn("df", F.col("n") - 1)
    return stat.select("set_id", "n", "draws", "q", "df", F.when(F.col("df") > 0, upper_tail(F.col("q"), F.col("df"))).alias("p_value"))


def chi_square_exact(spark: SparkSession, counts: list[int]) -> tuple[float, float]:
    """Statistic and exact p-value of one set's draw counts (a bounded vector) against uniform."""
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.stat import Statistics

    found = Statistics.chiSqTest(Vectors.dense(counts))
    return found.statistic, found.pValue


def draw_histogram(samples: DataFrame, domain: int, buckets: int = 10) -> DataFrame:
    """Draws per equal part of the domain."""
    return samples.filter("x is not null").groupBy("set_id", F.width_bucket(F.col("x").cast("double"), F.lit(0.0), F.lit(float(domain)), F.lit(buckets)).alias("bucket")).agg(_draws(samples).alias("draws"))


def accuracy(samples: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of the samples that are true members."""
    known = samples.filter("x is not null").join(truth.select("set_id", "x", F.lit(1).alias("member")), ["set_id", "x"], "left")
    if "times" in samples.columns:
        return known.groupBy("set_id").agg(F.sum("times").alias("draws"), (F.sum(F.coalesce("member", F.lit(0)) * F.col("times")) / F.sum("times")).alias("accuracy"))
    return known.groupBy("set_id").agg(F.count("*").alias("draws"), F.avg(F.coalesce("member", F.lit(0))).alias("accuracy"))


def recovery(found: DataFrame, truth: DataFrame) -> DataFrame:
    """set_id, n_true, n_found, n_both, precision, recall."""
    a, b = truth.select("set_id", "x", F.lit(1).alias("t")), found.select("set_id", "x", F.lit(1).alias("f"))
    both = a.join(b, ["set_id", "x"], "full").groupBy("set_id").agg(F.count("t").alias("n_true"), F.count("f").alias("n_found"), F.count_if(F.col("t").isNotNull() & F.col("f").isNotNull()).alias("n_both"))
    return both.select("*", F.try_divide("n_both", "n_found").alias("precision"), F.try_divide("n_both", "n_true").alias("recall"))


def recovery_counted(n_found: DataFrame, n_both: DataFrame, truth: DataFrame) -> DataFrame:
    """recovery from counts per set (set_id, n_found) and (set_id, n_both)."""
    true = truth.groupBy("set_id").agg(F.count("*").alias("n_true"))
    both = true.join(n_found, "set_id", "full").join(n_both, "set_id", "left").fillna(0, ["n_true", "n_found", "n_both"])
    return both.select("set_id", "n_true", "n_found", "n_both", F.try_divide("n_both", "n_found").alias("precision"), F.try_divide("n_both", "n_true").alias("recall"))


def distance_of_leaves(chances: DataFrame, positives: DataFrame) -> DataFrame:
    """distance_to_uniform where the positives of a leaf share one probability: chances (set_id, idx, probability), positives
    (set_id, idx, n)."""
    p = positives.join(chances.select("set_id", "idx", "probability"), ["set_id", "idx"], "left").withColumn("p", F.coalesce("probability", F.lit(0.0)))
    sized = positives.groupBy("set_id").agg(F.sum("n").alias("all"))
    off = p.join(sized, "set_id").withColumn("u", 1 / F.col("all"))
    return off.groupBy("set_id").agg(F.first("all").alias("n"), F.coalesce(F.sum(F.when(F.col("p") > 0, F.col("n"))), F.lit(0)).alias("reachable"), (F.sum(F.abs(F.col("p") - F.col("u")) * F.col("n")) / 2).alias("total_variation"), F.max(F.col("p") / F.col("u")).alias("max_ratio"))


def distance_to_uniform(probabilities: DataFrame, positives: DataFrame) -> DataFrame:
    """set_id, n, reachable, total_variation, max_ratio of exact draw probabilities against uniform over the positives."""
    p = positives.select("set_id", "x").join(probabilities, ["set_id", "x"], "left").withColumn("p", F.coalesce("probability", F.lit(0.0)))
    sized = p.groupBy("set_id").agg(F.count("*").alias("n"))
    off = p.join(sized, "set_id").withColumn("u", 1 / F.col("n"))
    return off.groupBy("set_id").agg(F.first("n").alias("n"), F.count_if(F.col("p") > 0).alias("reachable"), (F.sum(F.abs(F.col("p") - F.col("u"))) / 2).alias("total_variation"), F.max(F.col("p") / F.col("u")).alias("max_ratio"))
