"""Suffix arrays of single short strings, as arrays in a column."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def suffix_array_col(text: Column) -> Column:
    """ARRAY<INT>: starts of the suffixes in order, the empty one first. Quadratic in the text, so for short ones."""
    each = F.transform(F.sequence(F.lit(0), F.length(text)), lambda i: F.struct(F.substring(text, i + 1, F.length(text)).alias("s"), i.alias("i")))
    return F.transform(F.array_sort(each), lambda x: x["i"])
