"""Small dense vectors as array<double> columns, inside whole-stage expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def total(v: Column) -> Column:
    return F.aggregate(v, F.lit(0.0), lambda a, x: a + x)


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x * y))


def axpy(alpha: Column, x: Column, y: Column) -> Column:
    """alpha * x + y."""
    return F.zip_with(x, y, lambda u, v: alpha * u + v)


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once and use it in ``body``."""
    return F.element_at(F.transform(F.array(value), body), 1)


def softmax(z: Column) -> Column:
    def shifted(v: Column) -> Column:
        e = F.transform(v, lambda x: F.exp(x - F.array_max(v)))
        return let(e, lambda w: F.transform(w, lambda x: x / total(w)))

    return let(z, shifted)


def log_sum_exp(z: Column) -> Column:
    return let(z, lambda v: F.array_max(v) + F.log(total(F.transform(v, lambda x: F.exp(x - F.array_max(v))))))


def argmax(z: Column) -> Column:
    """Position (from 0) of the largest entry, the lowest on ties."""
    return let(z, lambda v: (F.array_position(v, F.array_max(v)) - 1).cast("int"))


def rows(flat: Column, width: int, height: int) -> Column:
    """A flat row-major matrix as an array of rows."""
    return F.transform(
        F.sequence(F.lit(0), F.lit(height - 1)), lambda c: F.slice(flat, c * width + 1, F.lit(width))
    )


def logits(flat: Column, x: Column, width: int, height: int) -> Column:
    return F.transform(rows(flat, width, height), lambda w: dot(w, x))
