"""Vector arithmetic as Column expressions, in double, and deterministic draws by md5."""

from __future__ import annotations

import math
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F



def total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def doubles(a: Column) -> Column:
    return a.cast("array<double>")


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(doubles(a), doubles(b), lambda x, y: x * y))


def l2_sq(a: Column, b: Column) -> Column:
    return total(F.zip_with(doubles(a), doubles(b), lambda x, y: (x - y) * (x - y)))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2_sq(a, b))


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def inner_product(a: Column, b: Column) -> Column:
    """As a distance: smaller is nearer."""
    return -dot(a, b)


def cosine(a: Column, b: Column) -> Column:
    """1 - cosine similarity; null if either vector is zero."""
    return F.lit(1.0) - dot(a, b) / F.nullif(norm(a) * norm(b), F.lit(0.0))


METRICS = {"l2": l2, "ip": inner_product, "cosine": cosine}


def add(a: Column, b: Column) -> Column:
    return F.zip_with(doubles(a), doubles(b), lambda x, y: x + y)


def sub(a: Column, b: Column) -> Column:
    return F.zip_with(doubles(a), doubles(b), lambda x, y: x - y)


def scale(a: Column, s: float) -> Column:
    return F.transform(doubles(a), lambda x: x * F.lit(s))


def normalize(a: Column) -> Column:
    """Unit length; a zero vector stays as it is."""
    # An array of the length alone, so that it is computed once a vector instead of once a component.
    return F.transform(F.array(norm(a)), lambda n: F.when(n > 0, F.transform(doubles(a), lambda x: x / n)).otherwise(doubles(a)))[0]


def is_valid(a: Column, dim: int | None = None) -> Column:
    """Not null, of length `dim` (if given), every element a finite number."""
    finite = F.forall(a, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    length = F.size(a) == dim if dim is not None else F.size(a) > 0
    return F.coalesce(a.isNotNull() & length & finite, F.lit(False))


def hex_int(text: Column, digits: int = 8) -> Column:
    return F.conv(F.substring(F.md5(text), 1, digits), 16, 10).cast("long")


def level(label: Column, m: int) -> Column:
    """Top layer of a label: floor(-ln(u) / ln(M)) with u from its md5, so that every engine draws the same."""
    u = (hex_int(F.concat(F.lit("lvl:"), label.cast("string"))) + 1) / F.lit(4294967297.0)
    return F.floor(-F.log(u) / F.lit(math.log(m))).cast("int")


def draw(label: Column, seed: int, iteration: int | Column) -> Column:
    """Key for pseudo-random order."""
    it = iteration if isinstance(iteration, Column) else F.lit(iteration)
    return F.md5(F.concat_ws(":", F.lit(str(seed)), it.cast("string"), label.cast("string")))


def rng_prune(candidates: Column, cap: int, alpha: float) -> Column:
    """Relaxed relative-neighbourhood selection as an expression.

    candidates: array<struct<dist double, id long, vec array<double>>>, distances to the centre. Visited by (dist, id); one is
    kept unless a kept one lies, times alpha, strictly nearer to it than the centre; at most `cap`. Returns ids in that order.
    """
    ordered = F.array_sort(candidates)
    empty = F.slice(ordered, 1, 0)
    kept = F.aggregate(ordered, empty, lambda acc, c: F.when((F.size(acc) < cap) & ~F.exists(acc, lambda a: F.lit(alpha) * l2(a["vec"], c["vec"]) < c["dist"]), F.concat(acc, F.array(c))).otherwise(acc))
    return F.transform(kept, lambda c: c["id"])


def nearest(candidates: Column, cap: int) -> Column:
    """Plain selection: the `cap` nearest ids."""
    return F.transform(F.slice(F.array_sort(candidates), 1, cap), lambda c: c["id"])


def centroid(column: str, dim: int) -> Column:
    """Aggregate: the mean of vectors of `dim` elements, element by element, with partial sums before the exchange."""
    return F.array(*(F.avg(F.get(F.col(column), F.lit(k)).cast("double")) for k in range(dim)))


def rounded(x: Column, digits: int) -> Column:
    """round() that keeps the sign of what becomes zero, as SQL engines on IEEE doubles do; Spark's own gives 0.0 for -0.0."""
    r = F.round(x, digits)
    return F.when((r == 0) & (x < 0), F.lit(-0.0)).otherwise(r)


def register(spark: SparkSession) -> None:
    """SQL functions that Catalyst inlines: vec_dot, vec_l2, vec_cosine."""
    body = {
        "vec_dot": "aggregate(zip_with(a, b, (x, y) -> x * y), CAST(0 AS DOUBLE), (s, v) -> s + v)",
        "vec_l2": "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), CAST(0 AS DOUBLE), (s, v) -> s + v))",
        "vec_cosine": "1 - vec_dot(a, b) / nullif(sqrt(vec_dot(a, a)) * sqrt(vec_dot(b, b)), 0)",
    }
    for name, expression in body.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {expression}")
