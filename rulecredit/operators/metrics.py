"""Accuracy of a score list against a reference list, both (elem_id, x)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

DIGITS = 9


def _ranked(scores: DataFrame, name: str) -> DataFrame:
    order = Window.orderBy(F.desc(F.round("x", DIGITS)), "elem_id")
    return scores.select("elem_id", F.row_number().over(order).alias(name))


def precision_at(ref: DataFrame, est: DataFrame, k: int = 10) -> DataFrame:
    """One row ``p``: shared elements of the two top-k lists over k."""
    top = lambda s: s.orderBy(F.desc(F.round("x", DIGITS)), "elem_id").limit(k).select("elem_id")
    return top(ref).join(top(est), "elem_id").agg((F.count("*") / F.lit(float(k))).alias("p"))


def average_precision_at(ref: DataFrame, est: DataFrame, k: int = 10) -> DataFrame:
    """One row ``ap``: mean of the precisions at 1..k."""
    both = _ranked(ref, "a").join(_ranked(est, "b"), "elem_id").select(F.greatest("a", "b").alias("r")).where(F.col("r") <= k)
    # an element within both lists from rank r on counts at r, r+1, ..., k
    gain = F.aggregate(F.sequence(F.col("r"), F.lit(k)), F.lit(0.0), lambda acc, j: acc + 1.0 / j)
    return both.agg((F.coalesce(F.sum(gain), F.lit(0.0)) / k).alias("ap"))


def _average_rank(c: Column) -> Column:
    w = Window.orderBy(F.round(c, DIGITS))
    same = Window.partitionBy(F.round(c, DIGITS))
    return F.rank().over(w) + (F.count("*").over(same) - 1) / 2.0


def _correlation(a: str, b: str) -> Column:
    """Pearson correlation, null where a side does not vary."""
    return F.try_divide(F.covar_pop(a, b), F.stddev_pop(a) * F.stddev_pop(b))


def spearman(ref: DataFrame, est: DataFrame) -> DataFrame:
    """One row ``rho``: Pearson correlation of average ranks."""
    both = ref.select("elem_id", F.col("x").alias("a")).join(est.select("elem_id", F.col("x").alias("b")), "elem_id")
    ranked = both.select(_average_rank(F.col("a")).alias("ra"), _average_rank(F.col("b")).alias("rb"))
    return ranked.agg(_correlation("ra", "rb").alias("rho"))


def score_error(ref: DataFrame, est: DataFrame) -> DataFrame:
    """Largest and mean absolute error, and the largest over the largest absolute reference score."""
    both = ref.select("elem_id", F.col("x").alias("a")).join(est.select("elem_id", F.col("x").alias("b")), "elem_id")
    d = F.abs(F.col("a") - F.col("b"))
    return both.agg(F.max(d).alias("max_error"), F.avg(d).alias("mean_error"), (F.max(d) / F.max(F.abs("a"))).alias("relative_error"))


def mean_ci(df: DataFrame, column: str, by: list[str] | None = None) -> DataFrame:
    """Mean and 95 % interval over instances."""
    half = F.try_divide(1.96 * F.coalesce(F.stddev_samp(column), F.lit(0.0)), F.sqrt(F.count(column)))
    return df.groupBy(*(by or [])).agg(F.avg(column).alias("mean"), (F.avg(column) - half).alias("low"), (F.avg(column) + half).alias("high"))


def quality_by(ref: DataFrame, lists: DataFrame, key: str, k: int = 10) -> DataFrame:
    """(key, p, ap, rho) of many score lists (key, elem_id, x) against one reference, in one plan."""
    return quality_within(ref, lists, [], key, "elem_id", k)


def quality_within(ref: DataFrame, lists: DataFrame, groups: list[str], key: str, elem: str, k: int = 10) -> DataFrame:
    """(groups, key, p, ap, rho) of score lists (groups, key, elem, x) against their group's reference (groups, elem, x)."""
    by = [*groups, key]
    pairs = lists.select(*by, elem, F.col("x").alias("b")).join(ref.select(*groups, elem, F.col("x").alias("a")), [*groups, elem])
    of = lambda c: Window.partitionBy(*by).orderBy(F.desc(F.round(c, DIGITS)), elem)
    mid = lambda c: F.rank().over(Window.partitionBy(*by).orderBy(F.round(c, DIGITS))) + (
        F.count("*").over(Window.partitionBy(*by, F.round(c, DIGITS))) - 1
    ) / 2.0
    both = pairs.select(
        *by, F.greatest(F.row_number().over(of("a")), F.row_number().over(of("b"))).alias("r"), mid("a").alias("ra"), mid("b").alias("rb")
    )
    gain = F.aggregate(
        F.when(F.col("r") <= k, F.sequence(F.col("r"), F.lit(k))).otherwise(F.array().cast("array<int>")), F.lit(0.0), lambda acc, j: acc + 1.0 / j
    )
    return both.groupBy(*by).agg(
        (F.count_if(F.col("r") <= k) / F.lit(float(k))).alias("p"), (F.sum(gain) / k).alias("ap"), _correlation("ra", "rb").alias("rho")
    )
