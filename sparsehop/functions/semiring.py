"""Semirings as builders of Column expressions: the product, the sum over a group, the sum of two values."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from typing import Any

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """``mul(matrix value, vector value)``, ``agg`` over a group, ``add`` of two values and its neutral ``zero``.

    ``is_boolean_or`` allows early exit and structure-only products; ``is_idempotent``
    allows duplicates in a frontier. Absent entries are zeros; a stored zero stays stored.
    """

    name: str
    kind: str
    zero: Any
    one: Any
    mul: Callable[[Column, Column], Column]
    agg: Callable[[Column], Column]
    add: Callable[[Column, Column], Column]
    is_boolean_or: bool = False
    is_idempotent: bool = False

    def zero_column(self) -> Column:
        return F.lit(self.zero).cast(self.kind)


OR_AND = Semiring("or_and", "boolean", False, True, lambda a, x: x, F.bool_or, lambda a, b: a | b, True, True)
PLUS_TIMES = Semiring("plus_times", "double", 0.0, 1.0, lambda a, x: a * x, F.sum, lambda a, b: a + b)
COUNT_TIMES = Semiring("count_times", "bigint", 0, 1, lambda a, x: a * x, F.sum, lambda a, b: a + b)
MIN_PLUS = Semiring("min_plus", "double", float("inf"), 0.0, lambda a, x: a + x, F.min, F.least, is_idempotent=True)
MAX_SECOND = Semiring("max_second", "bigint", -(2**63), 0, lambda a, x: x, F.max, F.greatest, is_idempotent=True)
MAX_TIMES = Semiring("max_times", "double", 0.0, 1.0, lambda a, x: a * x, F.max, F.greatest, is_idempotent=True)
MIN_FIRST = Semiring("min_first", "bigint", 2**63 - 1, 0, lambda a, x: x, F.min, F.least, is_idempotent=True)
PLUS_PAIR = Semiring("plus_pair", "bigint", 0, 1, lambda a, x: F.lit(1).cast("bigint"), F.sum, lambda a, b: a + b)
ANY_PAIR = Semiring("any_pair", "boolean", False, True, lambda a, x: F.lit(True), F.any_value, lambda a, b: a | b, True, True)
BITOR_AND = Semiring("bitor_and", "bigint", 0, -1, lambda a, x: x, F.bit_or, lambda a, b: a.bitwiseOR(b), is_idempotent=True)
SEMIRINGS = {s.name: s for s in (OR_AND, PLUS_TIMES, COUNT_TIMES, MIN_PLUS, MAX_SECOND, MAX_TIMES, MIN_FIRST, PLUS_PAIR, ANY_PAIR, BITOR_AND)}


def user_semiring(name: str, kind: str, zero: Any, one: Any, mul, agg, add, *, boolean_or: bool = False, idempotent: bool = False) -> Semiring:
    """A caller's own algebra by Column lambdas; ``agg`` may be a grouped-aggregate pandas UDF."""
    return Semiring(name, kind, zero, one, mul, agg, add, boolean_or, idempotent)
