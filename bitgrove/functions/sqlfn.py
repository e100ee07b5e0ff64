"""The closed forms and the hash positions as temporary SQL functions; the analyzer inlines them."""

from __future__ import annotations

import math

from pyspark.sql import SparkSession

from .hashing import Spec


def register(spark: SparkSession, spec: Spec) -> None:
    if spec.family != "affine_mod_p":
        raise ValueError("SQL positions are for affine_mod_p")
    c = spec.k * math.log(1 - 1 / spec.m)
    pos = ", ".join(f"pmod(pmod({a}L * x + {b}L, {spec.p}L), {spec.m}L)" for a, b in zip(spec.a, spec.b, strict=True))
    for name, args, kind, body in (
        ("fp_rate", "n DOUBLE, m DOUBLE, k INT", "DOUBLE", "pow(1 - exp(-k * n / m), k)"),
        ("false_overlap", "n1 DOUBLE, n2 DOUBLE, m DOUBLE, k INT", "DOUBLE", "-expm1(k * k * n1 * n2 * log1p(-1 / m))"),
        ("size_estimate", "ones BIGINT", "DOUBLE", f"CASE WHEN ones < {spec.m} THEN ln(({spec.m}D - ones) / {spec.m}) / ({c!r}D) END"),
        ("overlap_estimate", "t1 BIGINT, t2 BIGINT, t12 BIGINT", "DOUBLE", f"try_divide(ln(nullif(greatest(1 - try_divide({spec.m}D * t12 - double(t1) * t2, {spec.m}D * ({spec.m} - t1 - t2 + t12)), 0D), 0D)), {c!r}D)"),
        ("positions", "x BIGINT", "ARRAY<BIGINT>", f"array({pos})"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
