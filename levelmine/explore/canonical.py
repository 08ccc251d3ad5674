"""Canonical embeddings as column expressions: of all orders in which a subgraph can be grown, exactly one passes.

An order v1..vk is canonical if v1 is the least, every other vertex is adjacent to one before it, and no vertex comes
after a larger one that was added when the vertex was already adjacent to what stood there.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

LEAST = -(1 << 63)


def first_bit(mask: Column) -> Column:
    """Index of the lowest set bit."""
    return F.bit_count(mask.bitwiseAND(-mask) - F.lit(1))


def suffix_max(path: Column, k: int) -> Column:
    """Array whose entry i is the largest vertex after position i (the least long where none is)."""
    later = [F.array_max(F.slice(path, i + 2, k)) for i in range(k - 1)]
    return F.array(*later, F.lit(LEAST))


def may_follow(path: Column, above: Column, v: Column, mask: Column) -> Column:
    """Whether path + v is canonical, given the positions that v is adjacent to and the path's suffix maxima."""
    return (v > F.element_at(path, 1)) & (v > F.element_at(above, first_bit(mask).cast("int") + 1))


def is_canonical(path: Column, adjacent: Column) -> Column:
    """Of whole paths; adjacent: array of masks, entry j has the earlier positions that vertex j is adjacent to."""
    at = F.sequence(F.lit(1), F.size(path) - 1)

    def fits(j: Column) -> Column:
        v, mask = F.element_at(path, j.cast("int") + 1), F.element_at(adjacent, j.cast("int") + 1)
        first = first_bit(mask).cast("int")
        between = F.slice(path, first + 2, F.greatest(j.cast("int") - first - 1, F.lit(0)))
        return (mask > 0) & (v > F.element_at(path, 1)) & F.forall(between, lambda u: u < v)

    return F.when(F.size(path) == 1, True).otherwise(F.forall(at, fits))
