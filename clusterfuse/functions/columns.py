"""Column helpers."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, body) -> Column:
    """Bind ``value`` to a lambda variable, so that ``body`` may use it many times and it is evaluated once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def struct_of(**parts: Column) -> Column:
    return F.struct(*[c.alias(k) for k, c in parts.items()])
