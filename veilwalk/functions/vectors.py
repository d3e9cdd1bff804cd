"""Expressions over arrays of numbers, and closed forms, that stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def l1(a: Column, b: Column) -> Column:
    """Sum of absolute differences."""
    return total(F.zip_with(a, b, lambda x, y: F.abs(x - y)))


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def align_cost(a: Column, b: Column, one_sided: bool = False) -> Column:
    """Alignment cost of two row arrays by dynamic programming in array expressions.

    a's rows are taken one by one; the state is the row of least costs of ending at each row of b. one_sided forbids
    the step that leaves the row of a behind while b's stays for a second time, so each row of the longer meets one row.
    """
    inf = F.lit(float("inf"))
    start = F.concat(F.array(F.lit(0.0)), F.transform(b, lambda _: inf))

    def advance(before: Column, row: Column) -> Column:
        costs = F.transform(b, lambda y: l1(row, y))
        steps = F.zip_with(costs, F.zip_with(F.slice(before, 1, F.size(b)), F.slice(before, 2, F.size(b)), lambda p, q: F.least(p, q)), lambda c, m: F.struct(c.alias("c"), m.alias("m")))
        if one_sided:
            return F.concat(F.array(inf), F.transform(steps, lambda s: s["c"] + s["m"]))
        return F.aggregate(steps, F.array(inf), lambda out, s: F.concat(out, F.array(s["c"] + F.least(s["m"], F.element_at(out, -1)))))

    return F.element_at(F.aggregate(a, start, advance), -1)


def messages_protocol(length: Column, p: Column) -> Column:
    """Expected messages between devices of one walk, counting hop by hop; p below 1 or above."""
    n = length.cast("double")
    full = (n - 1) / (1 + p) + p * (1 - F.pow(-p, n - 1)) / F.pow(1 + p, F.lit(2.0))
    return F.when(length <= 1, F.lit(0.0)).otherwise(full)


def messages_published(length: Column, p: Column) -> Column:
    """Expected messages when a jump that ends a walk, or leaves one step, is not charged."""
    n = length.cast("double")
    full = (n - 2) / (1 + p) + (2 * (1 - p) - 1 / (1 + p)) * (1 - F.pow(-p, n - 2)) / (1 + p)
    return F.when(length <= 1, F.lit(0.0)).when(length == 2, F.lit(1.0)).otherwise(full)


def pool_size(c: Column, available: Column, rounding: str = "round") -> Column:
    """A noisy count as a number of vertices, from none to all that are there."""
    n = {"round": F.floor(c + 0.5), "floor": F.floor(c)}[rounding]
    return F.greatest(F.lit(0), F.least(n, available)).cast("long")
