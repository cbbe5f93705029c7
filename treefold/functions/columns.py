"""Native column helpers: exact weights, tagged ids, clamped sums, array algebra."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..model import NEG


def cents(column: Column) -> Column:
    """An amount as whole cents, so that sums are exact."""
    return F.round(column * 100).cast("long")


def tagged(node_id: Column, tag: int = 0) -> Column:
    """Binary-tree id of an original vertex (tag 0) or of the helper named after it (tags 1 to 3)."""
    return F.shiftleft(node_id.cast("long"), 2).bitwiseOR(F.lit(tag))


def original_id(node_id: Column) -> Column:
    return F.shiftright(node_id, 2)


def tag_of(node_id: Column) -> Column:
    return node_id.bitwiseAND(F.lit(3))


def clamp_add(a: Column, b: Column) -> Column:
    """Sum in which minus infinity absorbs."""
    return F.greatest(a + b, F.lit(NEG))


def knuth_parent(node_id: Column) -> Column:
    """A scattered parent below the id, the same in any SQL engine."""
    return F.pmod(F.pmod(node_id.cast("long") * F.lit(2654435761), F.lit(4294967296)), node_id.cast("long"))


def max_plus(a: Column, b: Column) -> Column:
    """(max,+) product of two state vectors of equal length: max over positions of the sums."""
    return F.array_max(F.zip_with(a, b, lambda x, y: clamp_add(x, y)))


def min_plus_convolution(a: Column, b: Column) -> Column:
    """(min,+) convolution of two arrays, by array functions alone (blocks; numpy is used for long ones)."""
    n, m = F.size(a), F.size(b)

    def at(k):
        low, high = F.greatest(F.lit(0), k - m + 1), F.least(k, n - 1)
        return F.array_min(F.transform(F.sequence(low, high), lambda i: F.get(a, i) + F.get(b, k - i)))

    return F.when((n > 0) & (m > 0), F.transform(F.sequence(F.lit(0), n + m - 2), at)).otherwise(F.expr("cast(array() as array<bigint>)"))
