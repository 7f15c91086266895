"""Dense vector expressions that stay inside generated code: constants are literals, rows are columns."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def add(terms: Sequence[Column]) -> Column:
    return reduce(lambda a, b: a + b, terms) if terms else F.lit(0.0)


def dot(cols: Sequence[Column], weights: Sequence[float]) -> Column:
    return add([c * F.lit(float(w)) for c, w in zip(cols, weights, strict=True)])


def sq_dist(cols: Sequence[Column], point: Sequence[float]) -> Column:
    return add([(c - F.lit(float(p))) * (c - F.lit(float(p))) for c, p in zip(cols, point, strict=True)])


def sq_norm_after(cols: Sequence[Column], matrix: np.ndarray) -> Column:
    """Squared length of row times matrix."""
    return add([(t := dot(cols, matrix[:, j])) * t for j in range(matrix.shape[1])])


def array_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def array_sq_dist(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


#: Terms of an expression that is written out; larger ones go over arrays, which keeps generated code small.
WRITTEN_OUT = 512
#: Squared distances that differ by less than this share are a tie: counts lie exactly between centres, and rounding must not choose.
TIE = 1e-9


def nearest(cols: Sequence[Column], centers: np.ndarray) -> Column:
    """struct(d2, cell): the least squared distance, and its centre; ties go to the lowest index. A row with a null has cell 0 and no distance."""
    k = len(centers)
    if k == 1:
        return F.struct(sq_dist(cols, centers[0]).alias("d2"), F.lit(0).alias("cell"))
    if k * k * len(cols) > WRITTEN_OUT:
        points = F.array(*[F.array(*[F.lit(float(x)) for x in c]) for c in centers])
        found = F.transform(points, lambda c: array_sq_dist(F.array(*cols), c))
        # Of an array of one array: a name for the distances, so that they are computed once.
        first = lambda d2: F.struct(F.array_min(d2).alias("d2"), F.array_position(F.transform(d2, lambda x: x <= F.array_min(d2) * (1 + TIE)), True).cast("int").alias("at"))
        best = F.element_at(F.transform(F.array(found), first), 1)
        return F.struct(best["d2"].alias("d2"), F.greatest(F.coalesce(best["at"], F.lit(1)) - 1, F.lit(0)).alias("cell"))
    found = [sq_dist(cols, c) for c in centers]
    least = F.least(*found)
    tied = [F.when(d2 <= least * (1 + TIE), F.lit(i)) for i, d2 in enumerate(found)]
    return F.struct(least.alias("d2"), F.coalesce(F.least(*tied), F.lit(0)).alias("cell"))


def nearest_rows(d2: np.ndarray) -> np.ndarray:
    """The same choice for rows x centres of squared distances."""
    return (d2 <= d2.min(1, keepdims=True) * (1 + TIE)).argmax(1)
