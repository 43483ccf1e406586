"""Rule scores as column expressions over a rule's counts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def support() -> Column:
    return F.col("cnt") / F.col("n_rows")


def confidence() -> Column:
    return F.col("cnt") / F.col("lhs_cnt")


def lift() -> Column:
    joint = F.col("cnt").cast("double") * F.col("n_rows")
    return joint / (F.col("lhs_cnt").cast("double") * F.col("rhs_cnt"))


NAMED = {
    "support": lambda: F.col("support"),
    "confidence": lambda: F.col("confidence"),
    "lift": lambda: F.col("lift"),
    "is": lambda: F.sqrt(F.col("support") * F.col("lift")),
    "is_product": lambda: F.col("support") * F.col("lift"),
}


def score_column(score: str | Column) -> Column:
    """A named score, a SQL expression, or any column over the rule's measures."""
    if isinstance(score, Column):
        return score
    return NAMED[score]() if score in NAMED else F.expr(score)


#: Scores that treat both sides of a rule alike.
SYMMETRIC = {"support", "lift", "is", "is_product"}
