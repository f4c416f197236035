"""Array columns as vectors."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda acc, x: acc + x)


def axpy(scale: Column, x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda a, b: scale * a + b)


def one_hot(label: Column, classes: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(classes - 1)), lambda k: F.when(k == label, F.lit(1.0)).otherwise(F.lit(0.0)))


def argmax(scores: Column) -> Column:
    """0-based place of the greatest element; the first of equals."""
    return (F.array_position(scores, F.array_max(scores)) - 1).cast("int")


def is_clean(x: Column) -> Column:
    """No null and no NaN in the vector."""
    return x.isNotNull() & ~F.exists(x, lambda v: v.isNull() | F.isnan(v.cast("double")))
