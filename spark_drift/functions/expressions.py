"""Column expressions shared by the operators: portable normals, densities, ranges."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash_unit(text: Column, part: int = 0) -> Column:
    """A number in (0, 1] from eight hex digits of the text's md5 (equal in any engine)."""
    digits = F.conv(F.substring(F.md5(text.cast("binary")), 1 + 8 * part, 8), 16, 10).cast("long")
    return (digits + 1) / F.lit(4294967296.0)


def hash_normal(text: Column, second: bool = False) -> Column:
    """A standard normal deviate from a text, by the polar transform of two units."""
    radius = F.sqrt(-2.0 * F.log(hash_unit(text, 0)))
    angle = 2.0 * math.pi * hash_unit(text, 1)
    return radius * (F.sin(angle) if second else F.cos(angle))


def distance(left: list[Column], right: list[Column]) -> Column:
    """Euclidean distance as one generated expression."""
    total = None
    for a, b in zip(left, right, strict=True):
        square = (a - b) * (a - b)
        total = square if total is None else total + square
    return F.sqrt(total)


def placed(bounds: Column, key: Column) -> Column:
    """How many of the sorted ``bounds``, an array column, lie at or below ``key``, by halving."""
    halves = F.sequence(F.lit(0), F.ceil(F.log2(F.size(bounds) + 1.0)).cast("int"))
    fits = lambda at: (at <= F.size(bounds)) & (F.get(bounds, at - 1) <= key)
    steps = F.transform(F.reverse(halves), lambda k: F.pow(F.lit(2.0), k).cast("int"))
    return F.aggregate(steps, F.lit(0), lambda low, step: F.when(fits(low + step), low + step).otherwise(low))


def fixed(column: Column, digits: int = 6) -> Column:
    """Rounded, without a negative zero."""
    return F.round(column, digits) + F.lit(0.0)
