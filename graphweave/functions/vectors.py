"""Elementwise and reducing functions on array columns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

Pair = Callable[[Column, Column], Column]

#: Elementwise combinations of two operands; the copies take one operand alone.
BINARY: dict[str, Pair] = {
    "add": lambda x, y: x + y,
    "sub": lambda x, y: x - y,
    "mul": lambda x, y: x * y,
    "div": lambda x, y: F.try_divide(x, y),
    "copy_lhs": lambda x, y: x,
    "copy_rhs": lambda x, y: y,
}

REDUCE: dict[str, Callable[[Column], Column]] = {"sum": F.sum, "max": F.max, "min": F.min, "mean": F.avg}


def combine(op: str | Pair, x: Column, y: Column | None) -> Column:
    """The elementwise combination of two vectors; y is ignored by a copy of the left operand."""
    if op == "copy_lhs":
        return x
    if op == "copy_rhs":
        return y
    return F.zip_with(x, y, BINARY[op] if isinstance(op, str) else op)


def dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def norm(x: Column) -> Column:
    return F.sqrt(dot(x, x))


def scale(x: Column, by: Column) -> Column:
    return F.transform(x, lambda v: v * by)


def argmax(x: Column) -> Column:
    """Place (from 0) of the greatest component, the first of equals."""
    return (F.array_position(x, F.array_max(x)) - 1).cast("int")


def part_of(src: Column, dst: Column, parts: int) -> Column:
    """The partition of an edge by an arithmetic hash of its unordered pair of ends."""
    low, high = F.least(src, dst), F.greatest(src, dst)
    return ((low * 7919 + high * 104729) % parts).cast("int")


def hash_order(*keys: Column) -> Column:
    """A well-mixed order of rows that does not follow the ids."""
    return F.xxhash64(*keys)
