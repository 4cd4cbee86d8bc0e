"""Entropy, cross entropy and divergence of probability vectors in bits, as column expressions.

0 log 0 is 0; a positive probability against a zero of the codebook costs infinitely many
bits. The general forms are higher-order functions for one-off projections; the unrolled
forms compile to straight-line code for the loops, where the number of symbols is known.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

INFINITE = float("inf")


def plogq(p: Column, q: Column) -> Column:
    """-p log2 q with both guards."""
    return F.when(p <= 0, F.lit(0.0)).when(q <= 0, F.lit(INFINITE)).otherwise(-p * F.log2(q))


def _total(parts: Column) -> Column:
    return F.aggregate(parts, F.lit(0.0), lambda s, x: s + x)


def entropy_bits(p: Column | str) -> Column:
    p = F.col(p) if isinstance(p, str) else p
    return _total(F.transform(p, lambda x: plogq(x, x)))


def cross_bits(p: Column | str, q: Column | str) -> Column:
    return _total(F.zip_with(p, q, plogq))


def kl_bits(p: Column | str, q: Column | str) -> Column:
    return cross_bits(p, q) - entropy_bits(p)


def entropy_unrolled(p: Column, n: int) -> Column:
    total = F.lit(0.0)
    for i in range(n):
        total = total + plogq(p[i], p[i])
    return total


def cost_unrolled(p: Column, bits: Column, n: int) -> Column:
    """Bits per symbol of p under code lengths; an infinite length counts only where its symbol occurs."""
    total = F.lit(0.0)
    for i in range(n):
        total = total + F.when(p[i] > 0, p[i] * bits[i]).otherwise(F.lit(0.0))
    return total


def normalised(p: Column) -> Column:
    total = F.aggregate(p, F.lit(0.0), lambda s, x: s + x)
    return F.transform(p, lambda x: x / total)
