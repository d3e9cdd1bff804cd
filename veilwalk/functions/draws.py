"""Draws that depend only on a seed, a purpose and keys: the same on every engine, partitioning and retry.

A draw is a 52-bit number from a digest of its arguments. 'md5' can be replayed in any SQL engine; 'xx' is faster and
stays in Spark. A known seed suits tests; in production the seed must be secret.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 52
SPAN = float(1 << BITS)


def number(seed: str | Column, purpose: str, *keys: Column | str, rng: str = "md5") -> Column:
    """A whole number below 2 to the 52 as long."""
    parts = [F.lit(seed), F.lit(purpose), *[(F.col(k) if isinstance(k, str) else k).cast("string") for k in keys]]
    if rng == "xx":
        return F.shiftrightunsigned(F.xxhash64(F.concat_ws("|", *parts)), 64 - BITS)
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 13), 16, 10).cast("long")


def unit(seed: str, purpose: str, *keys: Column | str, rng: str = "md5") -> Column:
    """Uniform on [0, 1)."""
    return number(seed, purpose, *keys, rng=rng) / F.lit(SPAN)


def laplace(n: Column, scale: float) -> Column:
    """Laplace value of mean zero from a drawn number, by the inverse distribution function."""
    u = (n + F.lit(0.5)) / F.lit(SPAN) - F.lit(0.5)
    return -F.lit(float(scale)) * F.signum(u) * F.log(F.lit(1.0) - F.lit(2.0) * F.abs(u))


def unit_sql(seed: str, purpose: str, *keys: str) -> str:
    """The md5 draw in DuckDB SQL."""
    return f"(('0x' || substr(md5(concat_ws('|', '{seed}', '{purpose}', {', '.join(keys)})), 1, 13))::BIGINT / {SPAN!r})"


def laplace_sql(seed: str, purpose: str, *keys: str, scale: float) -> str:
    u = f"((('0x' || substr(md5(concat_ws('|', '{seed}', '{purpose}', {', '.join(keys)})), 1, 13))::BIGINT + 0.5) / {SPAN!r} - 0.5)"
    return f"(-{float(scale)!r} * sign({u}) * ln(1.0 - 2.0 * abs({u})))"
