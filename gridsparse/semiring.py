"""Semirings as pairs of Column functions.

``mul(a, b, k)`` makes a product from the operands' values and the inner index;
``add`` is an aggregate that may be applied to its own results, so partial sums
can be merged anywhere.  ``ufunc`` names the numpy pair for the Arrow kernels.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    name: str
    add: Callable[[Column], Column]
    mul: Callable[[Column, Column, Column], Column]
    zero: object = 0
    ring: bool = False  # additive inverses exist
    ufunc: tuple[str, str] | None = None

    @staticmethod
    def plus_times() -> Semiring:
        return Semiring("plus_times", F.sum, lambda a, b, k: a * b, 0, True, ("add", "multiply"))

    @staticmethod
    def or_and() -> Semiring:
        return Semiring("or_and", F.bool_or, lambda a, b, k: a.cast("boolean") & b.cast("boolean"), False, False, ("logical_or", "logical_and"))

    @staticmethod
    def min_plus() -> Semiring:
        return Semiring("min_plus", F.min, lambda a, b, k: a + b, float("inf"), False, ("minimum", "add"))

    @staticmethod
    def max_plus() -> Semiring:
        return Semiring("max_plus", F.max, lambda a, b, k: a + b, float("-inf"), False, ("maximum", "add"))

    @staticmethod
    def max_min() -> Semiring:
        return Semiring("max_min", F.max, lambda a, b, k: F.least(a, b), float("-inf"), False, ("maximum", "minimum"))

    @staticmethod
    def min_max() -> Semiring:
        return Semiring("min_max", F.min, lambda a, b, k: F.greatest(a, b), float("inf"), False, ("minimum", "maximum"))

    @staticmethod
    def select_first() -> Semiring:
        """Keep the left operand's value: a general matrix times a pattern."""
        return Semiring("select_first", F.sum, lambda a, b, k: a, 0)

    @staticmethod
    def select_second() -> Semiring:
        """Keep the right operand's value: a pattern times a general matrix."""
        return Semiring("select_second", F.sum, lambda a, b, k: b, 0)

    @staticmethod
    def any_pair() -> Semiring:
        return Semiring("any_pair", F.max, lambda a, b, k: F.lit(1).cast("long"), 0)

    @staticmethod
    def count_pairs() -> Semiring:
        return Semiring("count_pairs", F.sum, lambda a, b, k: F.lit(1).cast("long"), 0)

    @staticmethod
    def arg_min_plus() -> Semiring:
        """Least sum with the inner index that reaches it, as a struct (value, via)."""
        return Semiring("arg_min_plus", F.min, lambda a, b, k: F.struct((a + b).alias("value"), k.alias("via")), None)

    @staticmethod
    def custom(add, mul, zero=0, name: str = "custom") -> Semiring:
        """Any pair: an aggregate and a function of two values."""
        return Semiring(name, add, lambda a, b, k: mul(a, b), zero)
