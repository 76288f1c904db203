"""Vertex partition functions: a column of block numbers 0..b-1. ``hash`` is the default in production."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

Psi = Callable[[Column, int], Column]

#: An odd multiplier near 2**32 / golden ratio.
MULTIPLIER = 2654435761


def mod(node: Column, b: int) -> Column:
    return F.pmod(node, F.lit(b)).cast("int")


def mult(node: Column, b: int) -> Column:
    x = F.pmod(node, F.lit(1 << 32))
    # the product modulo 2**32 in two halves, since the whole one would not fit a long
    high = x * F.lit(MULTIPLIER >> 16) % F.lit(1 << 16) * F.lit(1 << 16)
    return F.pmod((high + x * F.lit(MULTIPLIER & 0xFFFF)) % F.lit(1 << 32), F.lit(b)).cast("int")


def md5(node: Column, b: int) -> Column:
    head = F.conv(F.substring(F.md5(node.cast("string").cast("binary")), 1, 8), 16, 10).cast("bigint")
    return F.pmod(head, F.lit(b)).cast("int")


def hashed(node: Column, b: int) -> Column:
    return F.pmod(F.xxhash64(node), F.lit(b)).cast("int")


def native(node: Column, b: int) -> Column:
    """Spark's own hash partitioning: what bucketed tables use."""
    return F.pmod(F.hash(node), F.lit(b)).cast("int")


def ranged(width: int) -> Psi:
    """Contiguous blocks of ``width`` ids; ids start at 0. Not random-like: see the cost model's assumption."""
    return lambda node, b: F.least(F.floor(node / F.lit(width)), F.lit(b - 1)).cast("int")


KINDS: dict[str, Psi] = {"mod": mod, "mult": mult, "md5": md5, "hash": hashed, "native": native}


def named(psi: str | Psi) -> Psi:
    return KINDS[psi] if isinstance(psi, str) else psi
