"""Hash families: identifiers to filter positions, as columns and as text for other SQL engines."""

from __future__ import annotations

import math
import random
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

FAMILIES = ("affine_mod_m", "affine_mod_p", "murmur3", "md5", "xxhash64")
MAX_LONG = 2**63 - 1


def next_prime(n: int) -> int:
    while n < 2 or any(n % d == 0 for d in range(2, math.isqrt(n) + 1)):
        n += 1
    return n


@dataclass(frozen=True)
class Spec:
    """What filters must share to be combined: length m, k functions, family and constants."""

    m: int
    k: int = 3
    family: str = "affine_mod_p"
    a: tuple[int, ...] = ()
    b: tuple[int, ...] = ()
    p: int = 2147483647

    @property
    def words(self) -> int:
        return -(-self.m // 64)

    @property
    def id(self) -> str:
        return f"{self.family}/{self.m}/{self.k}/{self.p}/" + "/".join(map(str, self.a + self.b))


def make_spec(m: int, k: int = 3, family: str = "affine_mod_p", domain: int = 2**31 - 1, seed: int = 20, p: int | None = None) -> Spec:
    """Constants from a seed. affine_mod_p takes a prime of at least the domain; affine_mod_m multipliers prime to m, so that
    they can be inverted. affine_mod_m is literal: ids x and x + m agree in every function, so prefer another family."""
    if family not in FAMILIES:
        raise ValueError(f"family must be one of {FAMILIES}")
    rng = random.Random(seed)
    p = p or (2147483647 if domain > 10**7 else next_prime(domain))
    top = p if family == "affine_mod_p" else m
    a: list[int] = []
    while len(a) < k:
        c = rng.randrange(1, top) if top > 2 else 1
        if math.gcd(c, top) == 1:
            a.append(c)
    b = [rng.randrange(top) for _ in range(k)]
    if family.startswith("affine") and max(a) * min(domain, 2**31) + top > MAX_LONG:
        raise ValueError("constants overflow 64 bits over this domain")
    return Spec(m, k, family, tuple(a), tuple(b), p)


def period(spec: Spec) -> int | None:
    """Ids that differ by a multiple of this agree in every function; None if there is no such number."""
    return {"affine_mod_m": spec.m, "affine_mod_p": spec.p}.get(spec.family)


def positions(x: Column, spec: Spec) -> list[Column]:
    """The k positions of an id. Ids are non-negative longs; string or struct keys go through xxhash64 first."""
    m = F.lit(spec.m)
    if spec.family == "affine_mod_m":
        return [F.pmod(F.lit(a) * x + F.lit(b), m).cast("long") for a, b in zip(spec.a, spec.b, strict=True)]
    if spec.family == "affine_mod_p":
        return [F.pmod(F.pmod(F.lit(a) * x + F.lit(b), F.lit(spec.p)), m).cast("long") for a, b in zip(spec.a, spec.b, strict=True)]
    if spec.family == "murmur3":
        return [F.pmod(F.hash(F.lit(i), x.cast("long")), m).cast("long") for i in range(1, spec.k + 1)]
    if spec.family == "xxhash64":
        return [F.pmod(F.xxhash64(F.lit(i), x), m).cast("long") for i in range(1, spec.k + 1)]
    return [F.pmod(F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(i)), x.cast("string"))), 1, 8), 16, 10).cast("long"), m) for i in range(1, spec.k + 1)]


def sql_positions(spec: Spec, x: str = "x") -> list[str]:
    """The same as text for DuckDB; Murmur3 needs the steps of sql_murmur3."""
    if spec.family == "affine_mod_m":
        return [f"(({a} * {x} + {b}) % {spec.m})" for a, b in zip(spec.a, spec.b, strict=True)]
    if spec.family == "affine_mod_p":
        return [f"((({a} * {x} + {b}) % {spec.p}) % {spec.m})" for a, b in zip(spec.a, spec.b, strict=True)]
    if spec.family == "md5":
        return [f"(('0x' || substr(md5('{i}:' || {x}), 1, 8))::BIGINT % {spec.m})" for i in range(1, spec.k + 1)]
    if spec.family == "murmur3":
        return [f"((((h{i} + 2147483648) % 4294967296 - 2147483648) % {spec.m} + {spec.m}) % {spec.m})" for i in range(1, spec.k + 1)]
    raise ValueError(f"no SQL text for {spec.family}")


#: 32-bit seeds that hash(1), hash(2), hash(3) leave for the second argument.
MURMUR_SEEDS = (3735386339, 1765031574, 2471885347)


def sql_murmur3(source: str) -> str:
    """A query over source (x and other columns) that adds h1..h3, unsigned 32-bit Murmur3 of a non-negative long."""
    low32 = "4294967295"
    turn = lambda e, r: f"((({e}) << {r}) & {low32}) | (({e}) >> {32 - r})"
    steps = f"SELECT *, {', '.join(f'{s}::BIGINT AS h{i + 1}' for i, s in enumerate(MURMUR_SEEDS))} FROM ({source})"
    for word in ("(x & 4294967295)", "(x >> 32)"):
        steps = f"SELECT * REPLACE ({', '.join(f'h{i} AS h{i}' for i in (1, 2, 3))}), (({word}::HUGEINT * 3432918353) % 4294967296)::BIGINT AS w FROM ({steps})"
        steps = f"SELECT * REPLACE ((({turn('w', 15)})::HUGEINT * 461845907 % 4294967296)::BIGINT AS w) FROM ({steps})"
        steps = f"SELECT * REPLACE ({', '.join(f'xor(h{i}, w) AS h{i}' for i in (1, 2, 3))}) FROM ({steps})"
        steps = f"SELECT * EXCLUDE (w) REPLACE ({', '.join(f'((({turn(f"h{i}", 13)})::HUGEINT * 5 + 3864292196) % 4294967296)::BIGINT AS h{i}' for i in (1, 2, 3))}) FROM ({steps})"
    for e in ("xor(h{i}, 8)", "xor(h{i}, h{i} >> 16)", "(h{i}::HUGEINT * 2246822507 % 4294967296)::BIGINT", "xor(h{i}, h{i} >> 13)", "(h{i}::HUGEINT * 3266489909 % 4294967296)::BIGINT", "xor(h{i}, h{i} >> 16)"):
        steps = f"SELECT * REPLACE ({', '.join(e.format(i=i) + f' AS h{i}' for i in (1, 2, 3))}) FROM ({steps})"
    return steps
