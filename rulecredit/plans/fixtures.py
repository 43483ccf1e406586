"""The worked example: four rules over six elements of a census table, and the same rule set on the conversations view."""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Elements (id, attribute, value) and rules (lhs, rhs, support, lift, printed score x 100).
ELEMENTS = (
    (1, "relationship", "unmarried"),
    (2, "hours", "40-50"),
    (3, "age", "44-53"),
    (4, "income", ">=50K"),
    (5, "age", "31-44"),
    (6, "income", "<50K"),
)
RULES = (
    ((1, 2, 3), (4,), 0.20, 5.25, 105.0),
    ((2, 3), (4,), 0.25, 4.08, 102.0),
    ((6,), (5,), 0.43, 2.44, 105.0),
    ((6,), (1, 5), 0.21, 3.33, 70.0),
)


RULE_SCHEMA = "rule_id long, lhs array<int>, rhs array<int>, items array<int>, attrs array<int>, size int, support double, lift double, score double"

#: The elements in the example's places on the conversations view: alike in which of them share an attribute.
MEASURED = (
    (1, "role", "user"),
    (2, "nl", "true"),
    (3, "turn", "1"),
    (4, "len", "l"),
    (5, "turn", "0"),
    (6, "len", "s"),
)


def _frame(spark: SparkSession, elements: tuple) -> DataFrame:
    attrs = {a: i for i, a in enumerate(sorted({e[1] for e in elements}))}
    rows = [(e, attrs[a], a, v, 1, 0.0) for e, a, v in elements]
    return spark.createDataFrame(rows, "elem_id int, attr_id int, attr string, val string, freq_cnt long, freq double")


def measured_elements(spark: SparkSession) -> DataFrame:
    return _frame(spark, MEASURED)


def measured_rules(view: DataFrame, score: str = "printed") -> DataFrame:
    """The example's rules over MEASURED, as many as the rows of ``view`` meet, counted in one pass.

    Scores: ``is_product`` (support x lift), ``is`` (its root) or ``printed`` (the product in whole hundredths, x 100).
    """
    attrs = {a: i for i, a in enumerate(sorted({e[1] for e in MEASURED}))}
    of = {e: (a, v) for e, a, v in MEASURED}
    met = lambda items: F.count_if(reduce(and_, [F.col(of[i][0]) == of[i][1] for i in items]))
    counts = [met(s).alias(f"{k}{i}") for i, (lhs, rhs, *_) in enumerate(RULES, 1) for k, s in (("b", lhs + rhs), ("l", lhs), ("r", rhs))]
    got = view.agg(F.count("*").alias("n"), *counts).first()
    rows = []
    for i, (lhs, rhs, *_) in enumerate(RULES, 1):
        both, left, right = got[f"b{i}"], got[f"l{i}"], got[f"r{i}"]
        if not both:
            continue
        items = sorted(lhs + rhs)
        sup, lift = both / got["n"], (both * got["n"]) / (left * right)
        value = {"printed": float(int(100 * (sup * lift) + 0.5)), "is_product": sup * lift, "is": (sup * lift) ** 0.5}[score]
        rows.append((i, list(lhs), list(rhs), items, sorted(attrs[of[x][0]] for x in items), len(items), sup, lift, value))
    return view.sparkSession.createDataFrame(rows, RULE_SCHEMA)


def example_elements(spark: SparkSession) -> DataFrame:
    return _frame(spark, ELEMENTS)


def example_rules(spark: SparkSession, score: str = "printed") -> DataFrame:
    """Scores: ``printed``, ``is_product`` (support x lift) or ``is`` (its root)."""
    attrs = {a: i for i, a in enumerate(sorted({e[1] for e in ELEMENTS}))}
    of = {e: attrs[a] for e, a, _ in ELEMENTS}
    rows = []
    for i, (lhs, rhs, sup, lift, printed) in enumerate(RULES, 1):
        items = sorted(lhs + rhs)
        value = {"printed": printed, "is_product": sup * lift, "is": (sup * lift) ** 0.5}[score]
        rows.append((i, list(lhs), list(rhs), items, sorted(of[x] for x in items), len(items), sup, lift, value))
    return spark.createDataFrame(rows, RULE_SCHEMA)
