"""Column expressions over packed labels (arrays of (lm, d))."""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def label_upper_bound(ls: Column, lt: Column, matrix: Column) -> Column:
    """Least label-matrix-label sum; ``matrix`` maps a landmark to a map of distances. NULL if there is no way."""
    sums = F.flatten(F.transform(ls, lambda a: F.transform(lt, lambda b: a.d + b.d + F.try_element_at(F.try_element_at(matrix, a.lm), b.lm))))
    return F.array_min(F.filter(sums, lambda x: x.isNotNull()))


def label_overlap(ls: Column, lt: Column) -> Column:
    """Number of landmarks in both labels."""
    return F.size(F.array_intersect(F.transform(ls, lambda e: e.lm), F.transform(lt, lambda e: e.lm)))
