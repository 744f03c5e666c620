"""Comparisons of the property filters."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_OPS = {
    "=": lambda c, v: c == v,
    "<>": lambda c, v: c != v,
    "<": lambda c, v: c < v,
    "<=": lambda c, v: c <= v,
    ">": lambda c, v: c > v,
    ">=": lambda c, v: c >= v,
    "in": lambda c, v: c.isin(*v) if v else F.lit(False),
    "between": lambda c, v: c.between(*v),
    "like": lambda c, v: c.like(v),
    "exists": lambda c, v: c.isNotNull(),
}


def compare(column: Column, op: str, value=None) -> Column:
    if op not in _OPS:
        raise ValueError(f"{op}: one of {' '.join(_OPS)}")
    return _OPS[op](column, value)
