"""Vectors as array columns: the readable twin of the numpy kernels, used where SQL checks results.

Lambdas on arrays are interpreted per element, so training and large evaluation go through
``operators.kernels`` instead.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .hashing import TWO32, h32


def zero() -> Column:
    return F.lit(0.0).cast("double")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), zero(), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Zero where a vector is zero."""
    size = norm(a) * norm(b)
    return F.when(size > 0, dot(a, b) / size).otherwise(zero())


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def scale(a: Column, by: Column) -> Column:
    return F.transform(a, lambda x: x * by)


def hadamard(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def complex_product(a: Column, b: Column, half: int) -> Column:
    """Elementwise complex product; the first half of an array is real, the second imaginary."""
    ar, ai, br, bi = (F.slice(v, s, half) for v in (a, b) for s in (1, half + 1))
    return F.concat(
        F.zip_with(hadamard(ar, br), hadamard(ai, bi), lambda x, y: x - y),
        F.zip_with(hadamard(ar, bi), hadamard(ai, br), lambda x, y: x + y),
    )


def linear(a: Column, matrix: Column, d: int) -> Column:
    """Matrix (d rows after one another) times vector."""
    return F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: dot(F.slice(matrix, i * d + 1, F.lit(d)), a))


def initial(d: int, spread: float, seed: int, *key) -> Column:
    """The starting vector of a node or relation: small values from hashes of its key."""
    head = F.concat_ws(":", F.lit(str(seed)), *[(k if isinstance(k, Column) else F.lit(k)).cast("string") for k in key])
    return F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: (h32(head, i) / F.lit(float(TWO32)) - F.lit(0.5)) * F.lit(2.0 * spread))


def apply_op(op: str, x: Column, theta: Column | None, d: int) -> Column:
    if op == "identity":
        return x
    if op == "translation":
        return add(x, theta)
    if op == "diagonal":
        return hadamard(x, theta)
    if op == "linear":
        return linear(x, theta, d)
    if op == "complex_diagonal":
        return complex_product(x, theta, d // 2)
    raise ValueError(f"{op} has no column form")


def similarity(sim: str, a: Column, b: Column) -> Column:
    return {"dot": dot, "complex_dot": dot, "cos": cosine}[sim](a, b)
