"""Block confidence: 0 impossible, 1 least likely, 2 to 99 graded, 100 certain or nothing known."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def merge_scores(prior: Column, new: Column, *, validator: bool) -> Column:
    """A block validator may exclude (0); a classifier only orders, so its scores count as 1 at least. An excluded
    block stays excluded; otherwise the newer score replaces the older, null leaves it."""
    fresh = new if validator else F.greatest(new, F.lit(1))
    return F.when(prior == 0, 0).otherwise(F.least(F.lit(100), F.coalesce(fresh, prior, F.lit(100))))
