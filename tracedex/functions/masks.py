"""Sets of small numbers as bit words, for queries of any number of pairs or elements."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 62  # of a word; the sign bit stays clear


def words(members: set[int] | frozenset[int], n: int) -> list[int]:
    """The words of a set of numbers below n."""
    out = [0] * max(1, -(-n // BITS))
    for m in members:
        out[m // BITS] |= 1 << (m % BITS)
    return out


def gathered(number: str, n: int) -> list[Column]:
    """Aggregates: the words of all values (below n) of the integer column `number` in a group."""
    bit = F.expr(f"shiftleft(1L, cast({number} % {BITS} as int))")
    if n <= BITS:
        return [F.bit_or(bit).alias("w0")]
    return [F.bit_or(F.when(F.expr(f"{number} div {BITS} = {w}"), bit).otherwise(F.lit(0).cast("long"))).alias(f"w{w}") for w in range(-(-n // BITS))]


def met(hits: list[Column]) -> list[Column]:
    """Aggregates: the words of the numbers of those conditions that some row of a group meets."""
    out = []
    for w in range(0, len(hits), BITS):
        parts = [F.when(h, F.lit(1 << k)).otherwise(F.lit(0)).cast("long") for k, h in enumerate(hits[w : w + BITS])]
        out.append(F.bit_or(reduce(lambda a, b: a.bitwiseOR(b), parts)).alias(f"w{w // BITS}"))
    return out


def holds_all(members: set[int] | frozenset[int], n: int) -> Column:
    """The gathered words hold all the members."""
    tests = [F.col(f"w{w}").bitwiseAND(F.lit(m).cast("long")) == F.lit(m).cast("long") for w, m in enumerate(words(members, n)) if m]
    return reduce(lambda a, b: a & b, tests, F.lit(True))


def holds_any(members: set[int] | frozenset[int], n: int) -> Column:
    """The gathered words hold one of the members."""
    tests = [F.col(f"w{w}").bitwiseAND(F.lit(m).cast("long")) != 0 for w, m in enumerate(words(members, n)) if m]
    return reduce(lambda a, b: a | b, tests, F.lit(False))
