"""What the scores are used for: importance of elements, rules and attributes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rulecredit.functions.weights import lookup, shapley_weights
from rulecredit.operators.contribution import contribution, shape
from rulecredit.operators.mining import element_bands

DIGITS = 9  # scores are ranked after rounding: sums depend on row order, and equal elements must tie


def ranks(scores: DataFrame) -> DataFrame:
    """Adds ``rank_x`` and ``rank_freq``, 1 for the highest; ties share a rank. |E| rows, one task."""
    by_x, by_freq = Window.orderBy(F.desc(F.round("x", DIGITS))), Window.orderBy(F.desc("freq_cnt"))
    return scores.withColumns({"rank_x": F.rank().over(by_x), "rank_freq": F.rank().over(by_freq)})


def normalized(scores: DataFrame) -> DataFrame:
    """Adds ``nx`` = rank by frequency / rank by score; low values mark redundant elements."""
    return ranks(scores).withColumn("nx", F.col("rank_freq") / F.col("rank_x"))


def element_importance(scores: DataFrame, banded: DataFrame, n: int = 3) -> DataFrame:
    """Elements with score, frequency and their rules per score band."""
    return element_bands(banded, scores, n).orderBy(F.desc(F.round("x", DIGITS)), "elem_id")


def _score_map(nx: DataFrame):
    """A literal map elem_id -> nx; as many entries as elements."""
    rows = nx.select("elem_id", "nx").collect()
    if not rows:
        return F.create_map().cast("map<int,double>")
    return F.create_map(*[F.lit(x) for r in rows for x in (r[0], r[1])])


def rule_importance(rules: DataFrame, nx: DataFrame) -> DataFrame:
    """Adds ``rx``, the least nx of the rule's elements, and ``weakest_elem``; no shuffle of rules."""
    score = _score_map(nx)
    low = F.array_min(F.transform("items", lambda e: F.struct(score[e].alias("nx"), e.alias("e"))))
    return rules.withColumn("_low", low).withColumns({"rx": F.col("_low.nx"), "weakest_elem": F.col("_low.e")}).drop("_low")


def filter_redundant(scored: DataFrame, threshold: float) -> tuple[DataFrame, DataFrame]:
    """Rules with rx above the threshold, and the counts (removed, kept, removed_share)."""
    low = F.count_if(F.col("rx") <= threshold)
    report = scored.agg(low.alias("removed"), (F.count("*") - low).alias("kept"), (low / F.greatest(F.count("*"), F.lit(1))).alias("removed_share"))
    return scored.where(F.col("rx") > threshold), report


def redundant_pairs(scored: DataFrame, eps: float = 0.05) -> DataFrame:
    """Rules with a shorter one: the same sides without the weakest element, scoring at least (1 - eps) of it."""
    drop = lambda side: F.filter(side, lambda e: e != F.col("weakest_elem"))
    long = scored.where("size >= 3").select(
        F.col("rule_id").alias("long_id"), "lhs", "rhs", F.col("score").alias("long_score"), "weakest_elem", drop("lhs").alias("l"), drop("rhs").alias("r")
    ).where((F.size("l") > 0) & (F.size("r") > 0))
    short = scored.select(F.col("rule_id").alias("short_id"), F.col("lhs").alias("l"), F.col("rhs").alias("r"), F.col("score").alias("short_score"))
    return long.join(short, ["l", "r"]).where(F.col("short_score") >= (1 - eps) * F.col("long_score"))


def attribute_importance(nx: DataFrame, rules: DataFrame | None = None, denominator: str = "in_rules") -> DataFrame:
    """(attr, ax, n_elems): mean nx of the attribute's elements; ``in_rules`` leaves out those in no rule."""
    rows = nx
    if denominator == "in_rules" and rules is not None:
        met = rules.select(F.explode("items").alias("elem_id")).distinct()
        rows = nx.join(met, "elem_id", "left_semi")
    return rows.groupBy("attr").agg(F.avg("nx").alias("ax"), F.count("*").alias("n_elems"))


def attribute_profile(nx: DataFrame) -> DataFrame:
    """Elements with nx and their share of their attribute's occurrences."""
    total = F.sum("freq_cnt").over(Window.partitionBy("attr"))
    return nx.select("attr", "val", "nx", (F.col("freq_cnt") / total).alias("share"))


def drop_attributes(view: DataFrame, ax: DataFrame, threshold: float) -> DataFrame:
    """The view without the attributes scored below the threshold, to be mined again."""
    low = [r["attr"] for r in ax.where(F.col("ax") < threshold).select("attr").collect()]
    return view.drop(*low)


def drop_elements(rules: DataFrame, scores: DataFrame, eps: float) -> DataFrame:
    """Rules without any element whose score is within ``eps`` of zero."""
    ids = [r[0] for r in scores.where(F.abs("x") <= eps).select("elem_id").collect()]
    return rules.where(F.size(F.array_intersect("items", F.array(*[F.lit(i) for i in ids]))) == 0) if ids else rules


def interaction(rules: DataFrame, elements: DataFrame, elem_id: int, attr: str, agg: str = "max") -> DataFrame:
    """The element's score within the rules that hold each value of another attribute; no row for values it meets in no rule."""
    out = None
    for r in elements.where(F.col("attr") == attr).select("elem_id", "val").orderBy("elem_id").collect():
        part = contribution(rules.where(F.array_contains("items", r["elem_id"])), elements, agg)
        row = part.where(F.col("elem_id") == elem_id).select(F.lit(r["val"]).alias("given"), "x")
        out = row if out is None else out.unionByName(row)
    return out


def subset_importance(scores: DataFrame, elem_ids: list[int]) -> DataFrame:
    """Summed score of a group of elements."""
    return scores.where(F.col("elem_id").isin(elem_ids)).agg(F.sum("x").alias("x"), F.count("*").alias("n_elems"))


def union_importance(values: DataFrame, elements: DataFrame, elem_ids: list[int]) -> DataFrame:
    """One row ``x``: the score of a group of elements of different attributes as one player.

    The group joins a coalition as a whole, so the others and it are n - size + 1 players.
    A coalition is an itemset without the group, or one with no attribute of it.
    """
    own = elements.where(F.col("elem_id").isin(elem_ids)).select("elem_id", "attr_id").collect()
    attrs = {r["attr_id"] for r in own}
    if len(attrs) != len(set(elem_ids)):
        raise ValueError("a group needs elements of different attributes, all of them given")
    n, top = shape(values, elements)
    w = shapley_weights(n - len(attrs) + 1, top)
    ids, held = (F.array(*[F.lit(i) for i in sorted(x)]) for x in (set(elem_ids), attrs))
    inside = F.size(F.array_except(ids, "items")) == 0
    apart = ~F.arrays_overlap(held, "attrs")
    gain = F.when(inside, lookup(w, F.col("size") - len(attrs)) * F.col("value"))
    loss = F.when(apart, lookup(w, F.col("size")) * F.col("value"))
    return values.agg((F.coalesce(F.sum(gain), F.lit(0.0)) - F.coalesce(F.sum(loss), F.lit(0.0))).alias("x"))


def score_correlation(scores: DataFrame) -> DataFrame:
    """Correlation of the scores with the elements' frequencies."""
    return scores.agg(F.corr("x", "freq_cnt").alias("corr"))
