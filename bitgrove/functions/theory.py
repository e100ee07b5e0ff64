"""Closed forms: error rates, sizes, bounds and costs; numbers in Python, and the two estimators as columns too."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def fp_rate(n: float, m: float, k: int) -> float:
    """Probability that a filter of n ids answers yes for another id."""
    return (1 - math.exp(-k * n / m)) ** k


def false_overlap(n1: float, n2: float, m: float, k: int) -> float:
    """Probability that filters of two disjoint sets share a bit."""
    return -math.expm1(k * k * n1 * n2 * math.log1p(-1 / m))


def and_is_exact(only_a: float, only_b: float, m: float, k: int) -> float:
    """Probability that the AND of two filters is the filter of the intersection."""
    return math.exp(k * k * only_a * only_b * math.log1p(-1 / m))


def fp_for(n: float, domain: float, accuracy: float) -> float:
    if not 0 < accuracy < 1:
        raise ValueError("accuracy must lie between 0 and 1: 1 needs an infinite filter")
    return n * (1 - accuracy) / (accuracy * (domain - n))


def size_for(n: float, domain: float, accuracy: float, k: int = 3) -> float:
    """Filter length at which a share `accuracy` of the positives are members."""
    return k * n / -math.log1p(-(fp_for(n, domain, accuracy) ** (1 / k)))


def design_accuracy(n: float, domain: float, fp: float) -> float:
    return n / (n + (domain - n) * fp)


def choose_depth(domain: int, ratio: float) -> int:
    """Smallest depth whose leaf size N keeps N / log2 N within intersection cost over membership cost."""
    depth = 0
    while (leaf := domain / 2**depth) > 2 and leaf / math.log2(leaf) > ratio:
        depth += 1
    return depth


def critical_leaf(m: float, k: int, n: float) -> float:
    """Ids of a node below which a branch without members tends to die out by itself."""
    return m * math.log(2) / (k * k * n)


def critical_depth(domain: float, m: float, k: int, n: float) -> float:
    return math.log2(domain * k * k * n / (m * math.log(2)))


def node_count(depth: int, way: str = "definition") -> int:
    """Nodes of a complete tree; 'tabulated' is the count that fits the published memory table."""
    return 2 ** (depth + 1) - 1 if way == "definition" else max(0, 2**depth - 2)


def memory_mb(depth: int, m: float, way: str = "definition") -> float:
    return node_count(depth, way) * m / 8 / 2**20


def sample_epsilon(m: float, n: float, k: int) -> float:
    return math.sqrt(2 * n * k * (math.log(m) + math.log(math.log(m)) + math.log(n))) / m


def sample_f(m: float, n: float, k: int, depth: int) -> float:
    return 2 * sample_epsilon(m, n, k) * depth


def leaf_bounds(members: float, n: float, eps: float, depth: int) -> tuple[float, float]:
    """Bounds of the probability that a leaf with so many of n members is reached."""
    return members / n * (1 - 2 * eps) ** depth, members / n * (1 + 4 * eps) ** depth


def expected_nodes(domain: float, leaf: float, m: float, k: int, n: float) -> float:
    return math.log2(domain / leaf) + domain * k * k * n / m


def expected_nodes_recover(domain: float, leaf: float, m: float, k: int, n: float) -> float:
    return n * (math.log2(domain / leaf) + leaf * k * k / m)


def false_path_cost(alpha: float, depth: int | None = None) -> float:
    """Nodes visited below a false branch: each child survives with probability alpha; of unbounded depth if alpha < 1/2."""
    if depth is None:
        return alpha / (1 - 2 * alpha) if alpha < 0.5 else math.inf
    cost = 0.0
    for _ in range(depth):
        cost = alpha * (1 + 2 * cost)
    return cost


def zero_tail(eps: float, n: float, k: int, m: float) -> float:
    """Bound of the probability that the zero bits are off their mean by eps m."""
    return 2 * math.exp(-(eps**2) * m**2 / (2 * n * k))


def preimage_cost(m: float, k: int, domain: float) -> float:
    return m + k * domain / m


def estimate_size(ones: Column, m: int, k: int) -> Column:
    """Number of ids in a filter from its set bits; null if all are set."""
    zeros = F.lit(float(m)) - ones
    return F.when(zeros > 0, F.ln(zeros / float(m)) / (k * math.log(1 - 1 / m)))


def overlap_argument(t1: Column, t2: Column, both: Column, m: int) -> Column:
    below = F.lit(float(m)) * (m - t1 - t2 + both)
    return F.when(below != 0, 1 - (F.lit(float(m)) * both - t1 * t2.cast("double")) / below)


def estimate_overlap(t1: Column, t2: Column, both: Column, m: int, k: int) -> Column:
    """Size of the intersection from the set bits of two filters and of their AND; null where undefined."""
    arg = overlap_argument(t1, t2, both, m)
    return F.when((t1 < m) & (t2 < m) & (arg > 0), F.ln(arg) / (k * math.log(1 - 1 / m)))


def overlap_status(t1: Column, t2: Column, both: Column, m: int) -> Column:
    arg = overlap_argument(t1, t2, both, m)
    return F.when((t1 >= m) | (t2 >= m), "saturated").when(arg.isNull() | (arg <= 0), "undefined").when(arg > 1, "negative").otherwise("ok")
