"""Vector arithmetic over arrays, as column expressions."""

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Null where either vector is zero."""
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def l2_normalize(a: Column) -> Column:
    """Unit length; a zero vector becomes null."""
    return F.when(norm(a) > 0, F.transform(a, lambda x: x.cast("double") / norm(a)))


def by_place(column: str, dim: int, aggregate) -> Column:
    """One aggregate for each place of a vector column: partial results are one row a group and no vector is exploded."""
    return F.array(*(aggregate(F.col(column)[i].cast("double")) for i in range(dim)))


def mean_vector(column: str, dim: int) -> Column:
    return by_place(column, dim, F.avg)


def weighted_vector(column: str, weight: str, dim: int) -> Column:
    return by_place(column, dim, lambda x: F.sum(x * F.col(weight)) / F.sum(weight))


def max_vector(column: str, dim: int) -> Column:
    return by_place(column, dim, F.max)


def gem_vector(column: str, dim: int, p: float = 3.0, eps: float = 1e-6) -> Column:
    """Generalized mean of the places, clamped to eps from below."""
    return by_place(column, dim, lambda x: F.pow(F.avg(F.pow(F.greatest(x, F.lit(eps)), F.lit(p))), F.lit(1.0 / p)))
