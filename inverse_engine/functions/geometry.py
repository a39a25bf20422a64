"""Column expressions on points, boxes and query arrays. A query set is an array of structs (q, x: array<double>) in one column."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def coordinates(d: int, prefix: str = "x") -> list[str]:
    return [f"{prefix}{i}" for i in range(d)]


def columns(names: Sequence[str], side: str | None = None) -> list[Column]:
    return [F.col(f"{side}.{n}" if side else n) for n in names]


def at(vector: Column, d: int) -> list[Column]:
    """The first d elements of an array column."""
    return [F.get(vector, F.lit(i)) for i in range(d)]


#: Longer sums and conditions become one array expression: the optimizer's work on a chain grows steeply with its length.
LONGEST_CHAIN = 10


def total(parts: Sequence[Column]) -> Column:
    """Left to right, so that a sum of doubles is the same wherever it is taken."""
    if len(parts) > LONGEST_CHAIN:
        return F.aggregate(F.array(*parts[1:]), parts[0], lambda a, b: a + b)
    return reduce(lambda a, b: a + b, parts)


def dist2(a: Sequence[Column], b: Sequence[Column]) -> Column:
    """Squared Euclidean distance, summed by ascending dimension."""
    if len(a) > LONGEST_CHAIN:
        squares = F.zip_with(F.array(*a), F.array(*b), lambda x, y: (x - y) * (x - y))
        return F.aggregate(squares, F.lit(0.0), lambda s, x: s + x)
    return total([(x - y) * (x - y) for x, y in zip(a, b, strict=True)])


def all_of(parts: Sequence[Column]) -> Column:
    if len(parts) > LONGEST_CHAIN:
        return F.forall(F.array(*parts), lambda x: x)
    return reduce(lambda a, b: a & b, parts)


def any_of(parts: Sequence[Column]) -> Column:
    if len(parts) > LONGEST_CHAIN:
        return F.exists(F.array(*parts), lambda x: x)
    return reduce(lambda a, b: a | b, parts)


def box_min_dist2(low: Sequence[Column], high: Sequence[Column], p: Sequence[Column]) -> Column:
    """Squared distance of a point to the nearest place of a box."""
    gaps = [F.greatest(lo - x, x - hi, F.lit(0.0)) for lo, hi, x in zip(low, high, p, strict=True)]
    return total([g * g for g in gaps])


def box_max_dist2(low: Sequence[Column], high: Sequence[Column], p: Sequence[Column]) -> Column:
    """Squared distance of a point to the farthest place of a box."""
    gaps = [F.greatest(F.abs(x - lo), F.abs(hi - x)) for lo, hi, x in zip(low, high, p, strict=True)]
    return total([g * g for g in gaps])


def box_dominates(low: Sequence[Column], high: Sequence[Column], low2: Sequence[Column], high2: Sequence[Column], q: Sequence[Column]) -> Column:
    """Is every point of box 2 nearer to every point of the box than q is? Each dimension's term is largest at an end of the box."""
    terms = []
    for lo, hi, lo2, hi2, x in zip(low, high, low2, high2, q, strict=True):
        ends = [F.greatest((e - lo2) * (e - lo2), (e - hi2) * (e - hi2)) - (e - x) * (e - x) for e in (lo, hi)]
        terms.append(F.greatest(*ends))
    return total(terms) < 0


def dominates(o: Sequence[Column], q: Sequence[Column], r: Sequence[Column]) -> Column:
    """o is at least as near as q to r in every dimension, and nearer in one."""
    near = [(F.abs(a - c), F.abs(b - c)) for a, b, c in zip(o, q, r, strict=True)]
    return all_of([x <= y for x, y in near]) & any_of([x < y for x, y in near])


def in_pruning_region(q: Sequence[Column], o: Sequence[Column], p: Sequence[Column]) -> Column:
    """Does o keep q out of the dynamic skyline of p? The region reaches from the midpoint of q and o away from q; a dimension
    where they agree does not bound it, and a point that ties in all dimensions is outside."""
    return dominates(o, q, p)


def box_in_pruning_region(q: Sequence[Column], o: Sequence[Column], low: Sequence[Column], high: Sequence[Column]) -> Column:
    """Is the whole box strictly inside in every dimension that bounds the region? Sufficient: the boundary is left to points."""
    sides = [F.when(b > a, lo * 2 > a + b).when(b < a, hi * 2 < a + b).otherwise(F.lit(True)) for a, b, lo, hi in zip(q, o, low, high, strict=True)]
    return all_of(sides) & any_of([a != b for a, b in zip(q, o, strict=True)])


def orthant(p: Sequence[Column], q: Sequence[Column]) -> Column:
    """Bit i is set where p is not below q in dimension i."""
    return total([F.when(a >= b, F.lit(1 << i)).otherwise(F.lit(0)) for i, (a, b) in enumerate(zip(p, q, strict=True))])


def in_box(p: Sequence[Column], low: Sequence[Column], high: Sequence[Column]) -> Column:
    return all_of([(x >= lo) & (x <= hi) for x, lo, hi in zip(p, low, high, strict=True)])


def max_dist2_of_set(p: Sequence[Column], members: Column, d: int) -> Column:
    """Largest squared distance to the members of a query array."""
    return F.array_max(F.transform(members, lambda m: dist2(p, at(m["x"], d))))


def furthest(p: Sequence[Column], members: Column, d: int) -> Column:
    """struct(d2, q): the member that comes last by (squared distance, id)."""
    return F.array_max(F.transform(members, lambda m: F.struct(dist2(p, at(m["x"], d)).alias("d2"), m["q"].alias("q"))))


def bucket(value: Column, cuts: Sequence[float]) -> Column:
    """How many of the ascending cuts the value is at or above: binary search in one literal array."""
    if len(cuts) <= LONGEST_CHAIN:
        return total([(value >= c).cast("int") for c in cuts] or [F.lit(0)])
    array = F.lit(list(cuts))
    widths = F.array(*[F.lit(1 << s) for s in reversed(range(len(cuts).bit_length()))])
    return F.aggregate(widths, F.lit(0), lambda found, w: F.when((found + w <= len(cuts)) & (value >= F.get(array, found + w - 1)), found + w).otherwise(found))


def box_gap2(low: Sequence[Column], high: Sequence[Column], low2: Sequence[Column], high2: Sequence[Column]) -> Column:
    """Squared distance of two boxes at their nearest places."""
    gaps = [F.greatest(a - d, c - b, F.lit(0.0)) for a, b, c, d in zip(low, high, low2, high2, strict=True)]
    return total([g * g for g in gaps])


def morton(cells: Sequence[Column], bits: int) -> Column:
    """Interleaves the low bits of whole-number cell coordinates."""
    d = len(cells)
    return total([F.shiftleft(F.shiftright(c, b).bitwiseAND(F.lit(1)).cast("long"), b * d + i) for b in range(bits) for i, c in enumerate(cells)])


def precedes(d2: Column, id_: Column, limit_d2: Column, limit_id: Column) -> Column:
    """(d2, id) comes before (limit_d2, limit_id)."""
    return (d2 < limit_d2) | ((d2 == limit_d2) & (id_ < limit_id))
