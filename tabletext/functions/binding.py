"""Names for intermediate values inside one expression.

An expression that is used twice is evaluated twice, and in lambdas once an element.  Bound to the
variable of a one-element transform, it is evaluated once and its tree stays small.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(*values_and_body) -> Column:
    """``let(a, b, lambda a, b: ...)``: the body with each value evaluated once."""
    *values, body = values_and_body
    return _bind(list(values), [], body)


def surplus(found: Column, seen: Column) -> Column:
    """``found`` without as many of each value as ``seen`` has: a difference of bags, in order."""
    count = lambda values, x: F.size(F.filter(values, lambda y: y == x))
    return let(found, seen, lambda found, seen: F.filter(found, lambda x, i: count(F.slice(found, 1, i + 1), x) > count(seen, x)))


def _bind(values: list[Column], bound: list[Column], body: Callable[..., Column]) -> Column:
    if not values:
        return body(*bound)
    return F.element_at(F.transform(F.array(values[0]), lambda x: _bind(values[1:], [*bound, x], body)), 1)
