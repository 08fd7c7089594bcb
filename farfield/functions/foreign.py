"""Foreign functions of the algorithms: from columns to a column, with the names by which programs call them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def ends(a: Column, b: Column, far: Column) -> Column:
    """An edge seen alike from both ends, and the tree at its far end."""
    return F.struct(F.least(a, b).alias("lo"), F.greatest(a, b).alias("hi"), far.alias("far"))


def edge_key(a: Column, b: Column) -> Column:
    """Orders equal weights by the edge, seen alike from both ends; far is the other end."""
    return F.struct((-F.least(a, b)).alias("lo"), (-F.greatest(a, b)).alias("hi"), b.alias("far"))


FUNCTIONS: dict[str, Callable[..., Column]] = {
    "toss": lambda *xs: F.xxhash64(*xs),
    "second": lambda p: p["_2"],
    "third": lambda p: p["_2"]["far"],
    "far": lambda p: p["_2"]["far"],
    "ends": ends,
    "edge_key": edge_key,
}
