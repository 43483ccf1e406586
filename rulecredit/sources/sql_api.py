"""SQL surface: temp views of rules and scores, and table functions for rule splits and contributions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from rulecredit.functions.weights import shapley_weights
from rulecredit.operators.contribution import contribution, itemset_values, rule_elements
from rulecredit.operators.usecases import normalized, rule_importance


@udtf(returnType="lhs array<int>, rhs array<int>")
class RuleSplits:
    """``rule_splits(items)``: every split of an itemset into two non-empty sides."""

    def eval(self, items):
        n = len(items or [])
        for mask in range(1, (1 << n) - 1):
            yield [x for i, x in enumerate(items) if mask >> i & 1], [x for i, x in enumerate(items) if not mask >> i & 1]


@udtf(returnType="elem string, x double")
class ContributionOf:
    """``contribution_of(itemsets)``: scores from an array of structs (items as ``attr=val``, value), n the elements met.

    For small sets in ad-hoc SQL: one call holds its whole argument.
    """

    def eval(self, itemsets):
        sets = [(list(r["items"]), float(r["value"])) for r in itemsets or []]
        attr = lambda e: e.split("=", 1)[0]
        known = sorted({e for items, _ in sets for e in items})
        w = shapley_weights(len(known), max((len(i) for i, _ in sets), default=0))
        at = lambda k: w[k] if k < len(w) else 0.0
        for e in known:
            own = sum(at(len(i) - 1) * v for i, v in sets if e in i)
            yield e, own - sum(at(len(i)) * v for i, v in sets if attr(e) not in map(attr, i))


def register(spark: SparkSession, rules: DataFrame, elements: DataFrame, agg: str = "max", prefix: str = "") -> None:
    """Views ``rules`` (with rx), ``itemset_values``, ``elements``, ``scores`` (with nx), and the functions ``rule_splits`` and ``contribution_of``."""
    values = itemset_values(rules, agg)
    scores = normalized(contribution(rules, elements, agg))
    views = {
        "rules": rule_importance(rules, scores),
        "itemset_values": values,
        "elements": rule_elements(values, elements),
        "scores": scores,
    }
    for name, df in views.items():
        df.createOrReplaceTempView(prefix + name)
    spark.udtf.register("rule_splits", RuleSplits)
    spark.udtf.register("contribution_of", ContributionOf)
