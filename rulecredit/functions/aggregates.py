"""Interestingness of a set of rules: max, sum, avg and the sum of the k best scores."""

from __future__ import annotations

import re

from pyspark.sql import Column
from pyspark.sql import functions as F


def top_k_of(agg: str) -> int | None:
    m = re.fullmatch(r"top(\d+)", agg)
    return int(m[1]) if m else None


def set_aggregate(agg: str, column: str = "score") -> Column:
    """The aggregate expression; per itemset a list holds at most 2**size - 2 scores."""
    k = top_k_of(agg)
    if k:
        best = F.slice(F.sort_array(F.collect_list(column), asc=False), 1, k)
        return F.aggregate(best, F.lit(0.0), lambda acc, x: acc + x)
    return {"max": F.max, "sum": F.sum, "avg": F.avg}[agg](column)
