"""The experiments: instances, coalition counts, timings, approximation quality, robustness."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from dataclasses import dataclass
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.functions.aggregates import set_aggregate
from rulecredit.operators import contribution as c
from rulecredit.operators.alternatives import i_top, influence
from rulecredit.operators.approx import ESTIMATORS, approximate
from rulecredit.operators.grouped import (
    far_from_independent,
    grouped_contribution,
    grouped_counts,
    grouped_estimate,
    grouped_influence,
    grouped_itemsets,
    grouped_rules,
    grouped_top,
    grouped_values,
    tuple_texts,
)
from rulecredit.operators.metrics import mean_ci, quality_by, quality_within
from rulecredit.operators.mining import filter_lift, frequent_itemsets, generate_rules, with_score
from rulecredit.operators.prepare import Bins, discretize, sample_rows
from rulecredit.sources.store import TableStore
from rulecredit.sources.views import RAW


@dataclass(frozen=True)
class Instance:
    view: str
    sample_rows: int
    n_bins: int
    min_support: float
    min_lift: float

    @property
    def base(self) -> str:
        return f"{self.view}-r{self.sample_rows}-b{self.n_bins}"

    @property
    def run_id(self) -> str:
        return f"{self.base}-s{self.min_support:g}-l{self.min_lift:g}"


def build_instances(
    views: Iterable[str] = tuple(RAW),
    samples: Iterable[int] = (2000, 10000),
    bins: Iterable[int] = (3, 4, 5),
    supports: Iterable[float] = (0.05, 0.1, 0.2),
    lifts: Iterable[float] = (1.05, 1.2),
) -> list[Instance]:
    """The grid of pipeline knobs."""
    return [Instance(*k) for k in product(views, samples, bins, supports, lifts)]


def sampled(spark: SparkSession, folder: str, view: str, n: int) -> DataFrame:
    raw = RAW[view]
    return sample_rows(raw.frame(spark, folder), n, key=list(raw.key)).drop(*(c for c in raw.key if c not in raw.numeric))


def binned(raw: DataFrame, view: str, bins: int) -> DataFrame:
    spec = {c: Bins.equal_width(bins) for c in RAW[view].numeric} | {p: Bins.keep() for p in RAW[view].plain}
    return discretize(raw, spec, labels="index")


def mine_instance(spark: SparkSession, folder: str, inst: Instance) -> tuple[DataFrame, DataFrame]:
    """(scored rules, frequent elements) of one instance, written once."""
    store = TableStore(spark, f"instance-{inst.run_id}")
    tuples = binned(sampled(spark, folder, inst.view, inst.sample_rows), inst.view, inst.n_bins)
    mined = frequent_itemsets(tuples, inst.min_support, len(tuples.columns), "levelwise", store)
    rules = store.write(with_score(filter_lift(generate_rules(mined), inst.min_lift)), "rules")
    return rules, mined.elements


def grid_rules(spark: SparkSession, folder: str, instances: list[Instance], store: TableStore | None = None) -> DataFrame:
    """Scored rules (g, view, items, lhs, rhs, size, measures, score) of all instances, ``g`` the run id: what
    ``mine_instance`` mines one by one.

    A sample is taken once, binned once for each bin count, and mined once at its lowest support;
    higher supports and lifts select among those rules, whose sides are frequent when the rule is.
    """
    store = store or TableStore(spark, "grid")
    samples, tuples = {}, []
    for view, n, bins in dict.fromkeys((i.view, i.sample_rows, i.n_bins) for i in instances):
        if (view, n) not in samples:
            samples[view, n] = store.write(sampled(spark, folder, view, n), f"{view}-{n}")
        texts = binned(samples[view, n], view, bins).select(tuple_texts([*RAW[view].numeric, *RAW[view].plain]).alias("items"))
        tuples.append(texts.groupBy("items").agg(F.count("*").alias("c")).select(F.lit(f"{view}-r{n}-b{bins}").alias("g"), "items", "c"))
    held = store.write(reduce(DataFrame.unionByName, tuples), "tuples")
    knobs = [(i.base, i.run_id, i.view, str(i.min_support), i.min_lift) for i in instances]
    runs = spark.createDataFrame(knobs, "base string, run string, view string, min_support string, min_lift double")
    runs = store.write(runs.withColumn("min_support", F.col("min_support").cast("decimal(12,10)")), "knobs")
    bases = runs.groupBy(F.col("base").alias("g")).agg(F.min("min_support").alias("min_support"))
    width = max(len(RAW[i.view].numeric + RAW[i.view].plain) for i in instances)
    base_rules = grouped_rules(grouped_itemsets(held, bases, width, store)).withColumnRenamed("g", "base")
    picked = base_rules.join(F.broadcast(runs), "base").where((F.col("cnt") >= F.col("min_support") * F.col("n_rows")) & far_from_independent(F.col("min_lift")))
    return store.write(picked.withColumnRenamed("run", "g").drop("base", "min_support", "min_lift"), "rules")


def grid_properties(rules: DataFrame) -> DataFrame:
    """(g, view, n_rules, avg_length, max_length, n_elements) of every instance that has rules."""
    elements = rules.select("g", F.explode("items").alias("e")).groupBy("g").agg(F.count_distinct("e").alias("n_elements"))
    sizes = rules.groupBy("g", "view").agg(F.count("*").alias("n_rules"), F.avg("size").alias("avg_length"), F.max("size").alias("max_length"))
    return sizes.join(elements, "g")


def properties_by_view(properties: DataFrame) -> DataFrame:
    """Range of every property of a dataset's rule sets."""
    edges = [f(c).alias(f"{n}_{c}") for c in ("n_rules", "avg_length", "n_elements") for n, f in (("min", F.min), ("max", F.max))]
    return properties.groupBy("view").agg(F.count("*").alias("n_sets"), *edges, F.max("max_length").alias("max_length"))


#: Bands of the properties by which counts are averaged.
BANDS = {"n_elements": [10, 20, 30], "n_rules": [100, 1000, 10000], "avg_length": [2.5, 3.0, 3.5, 4.0]}


def grid_coalitions(rules: DataFrame, by: str) -> DataFrame:
    """Average coalition counts of an element by ``view`` or by bands of a property, with the mean of their ratio."""
    counts, properties = grouped_counts(grouped_values(rules)), grid_properties(rules)
    joined = counts.join(F.broadcast(properties), "g").withColumn("ratio", F.col("naive") / F.col("pruned"))
    key = F.col("view")
    if by != "view":
        key = sum(((F.col(by) >= cut).cast("int") for cut in BANDS[by]), F.lit(0)).cast("string")
    means = [F.avg(c).alias(f"avg_{c}") for c in ("naive", "pruned", "ratio")]
    return joined.groupBy(key.alias("band")).agg(F.count("*").alias("n"), *means)


ROBUSTNESS = ("is_max", "confidence_max", "lift_max", "is_sum", "is_top2", "is_top3", "is_avg")


def variant_values(rules: DataFrame) -> DataFrame:
    """(g, variant, items, size, value) under every score and aggregate of ROBUSTNESS, from one shuffle of the rules."""
    column = {"is": "score", "confidence": "confidence", "lift": "lift"}
    split = [v.split("_") for v in ROBUSTNESS]
    all_ = rules.groupBy("g", "items").agg(F.first("size").alias("size"), *[set_aggregate(a, column[s]).alias(f"{s}_{a}") for s, a in split])
    cells = F.array(*[F.struct(F.lit(v).alias("variant"), F.col(v).alias("value")) for v in ROBUSTNESS])
    return all_.select("g", "items", "size", F.explode(cells).alias("c")).select("g", "c.variant", "items", "size", "c.value")


def grid_robustness(rules: DataFrame, top: int, store: TableStore) -> DataFrame:
    """(variant, n_sets, mean, low, high): rank correlation of each variant with IS and max, averaged over the instances."""
    values = variant_values(rules).withColumn("g", F.struct("g", "variant")).drop("variant")
    scores = store.write(grouped_contribution(values, top).select("g.g", "g.variant", "elem", "x"), "variants")
    quality = quality_within(scores.where(F.col("variant") == ROBUSTNESS[0]).drop("variant"), scores.where(F.col("variant") != ROBUSTNESS[0]), ["g"], "variant", "elem")
    means = mean_ci(quality, "rho", ["variant"]).join(quality.groupBy("variant").agg(F.count("rho").alias("n_sets")), "variant")
    return means.select("variant", "n_sets", "mean", "low", "high")


def grid_alternatives(rules: DataFrame, top: int, store: TableStore) -> DataFrame:
    """(method, n_sets, p_at_10, ap_at_10, rank_corr): influence and best rule against the exact scores, means over the instances."""
    exact = store.write(grouped_contribution(grouped_values(rules), top), "exact")
    named = lambda m, df: df.select("g", F.lit(m).alias("method"), "elem", "x")
    lists = named("i_top", grouped_top(rules)).unionByName(named("influence", grouped_influence(rules)))
    return _mean_quality(quality_within(exact, lists, ["g"], "method", "elem"))


def _mean_quality(quality: DataFrame) -> DataFrame:
    return quality.groupBy("method").agg(
        F.count("*").alias("n_sets"), F.avg("p").alias("p_at_10"), F.avg("ap").alias("ap_at_10"), F.avg("rho").alias("rank_corr")
    )


def grid_approximations(rules: DataFrame, top: int, store: TableStore, n_samples: int = 2048, seed: int = 0) -> DataFrame:
    """(method, n_sets, p_at_10, ap_at_10, rank_corr, seconds): alternatives and estimators against the exact scores.

    Quality is averaged over the instances. ``seconds``: wall time of all instances' scores by the
    method, from the itemset values (alternatives: from the rules) to written scores.
    """
    values = store.write(grouped_values(rules), "values")
    exact = store.write(grouped_contribution(values, top), "exact")
    jobs = {"influence": lambda: grouped_influence(rules), "i_top": lambda: grouped_top(rules)}
    jobs |= {m: lambda m=m: grouped_estimate(values, m, n_samples, top, store, seed) for m in ESTIMATORS}
    lists, spent = [], []
    for name, job in jobs.items():
        start = time.perf_counter()
        scores = store.write(job(), f"scores-{name}")
        spent.append((name, time.perf_counter() - start))
        lists.append(scores.select("g", F.lit(name).alias("method"), "elem", "x"))
    quality = quality_within(exact, reduce(DataFrame.unionByName, lists), ["g"], "method", "elem")
    times = rules.sparkSession.createDataFrame(spent, "method string, seconds double")
    return _mean_quality(quality).join(F.broadcast(times), "method")


def rule_set_properties(rules: DataFrame, run_id: str) -> DataFrame:
    """(run_id, n_rules, avg_length, max_length, n_elements) of one rule set."""
    elements = rules.select(F.explode("items").alias("e")).agg(F.count_distinct("e").alias("n")).select("n").scalar()
    return rules.agg(F.count("*").alias("n_rules"), F.avg("size").alias("avg_length"), F.max("size").alias("max_length")).select(
        F.lit(run_id).alias("run_id"), "n_rules", "avg_length", "max_length", elements.alias("n_elements")
    )


def coalition_counts(rules: DataFrame, elements: DataFrame, run_id: str) -> DataFrame:
    """(run_id, elem_id, naive, pruned, bound, ratio) for every element in a rule."""
    values = c.itemset_values(rules)
    scope = c.rule_elements(values, elements)
    pruned = c.count_pruned(values, scope).select("elem_id", "pruned")
    bound = c.count_bound(rules, scope)
    both = c.count_naive(scope).select("elem_id", "naive").join(pruned, "elem_id").join(bound, "elem_id")
    return both.select(F.lit(run_id).alias("run_id"), "elem_id", "naive", "pruned", "bound", (F.col("naive").cast("double") / F.col("pruned")).alias("ratio"))


def timed(job: Callable[[], DataFrame]) -> tuple[float, list]:
    start = time.perf_counter()
    rows = job().collect()
    return time.perf_counter() - start, rows


def bench_multi_vs_sequential(rules: DataFrame, elements: DataFrame) -> dict[str, float]:
    """Seconds of the exact forms for all elements, and their ratios."""
    values = c.itemset_values(rules)
    scope = c.rule_elements(values, elements)
    spent = {name: timed(lambda f=f: f(values, scope))[0] for name, f in c.METHODS.items()}
    return spent | {
        "sequential_over_multi": spent["sequential"] / spent["multi"],
        "multi_over_decomposed": spent["multi"] / spent["decomposed"],
    }


def _stacked(lists: dict[str, Callable[[], DataFrame]], key: str, store: TableStore) -> tuple[DataFrame, list[tuple[str, float]]]:
    """(key, elem_id, x) of the named lists, each written on its own so that plans stay small, and the seconds each took."""
    tables, spent = [], []
    for k, job in lists.items():
        start = time.perf_counter()
        tables.append(store.write(job().select("elem_id", "x"), k).select(F.lit(k).alias(key), "elem_id", "x"))
        spent.append((k, time.perf_counter() - start))
    return reduce(DataFrame.unionByName, tables), spent


def approximation_table(rules: DataFrame, elements: DataFrame, n_samples: int = 2048, seed: int = 0) -> DataFrame:
    """(method, p_at_10, ap_at_10, rank_corr, seconds) of the alternatives and estimators against the exact scores."""
    store = TableStore(rules.sparkSession, "approximation")
    values = store.write(c.itemset_values(rules), "values")
    scope = store.write(c.rule_elements(values, elements), "scope")
    ref = store.write(c.contribution_decomposed(values, scope).select("elem_id", "x"), "exact")
    lists = {"influence": lambda: influence(rules, scope), "i_top": lambda: i_top(rules, scope)}
    lists |= {m: lambda m=m: approximate(values, scope, m, n_samples, seed) for m in ESTIMATORS}
    stacked, spent = _stacked(lists, "method", store)
    times = rules.sparkSession.createDataFrame(spent, "method string, seconds double")
    out = quality_by(ref, stacked, "method").join(F.broadcast(times), "method")
    return out.select("method", F.col("p").alias("p_at_10"), F.col("ap").alias("ap_at_10"), F.col("rho").alias("rank_corr"), "seconds")


def robustness(rules: DataFrame, elements: DataFrame) -> DataFrame:
    """(variant, rank_corr): other scores and aggregates against IS with max."""
    store = TableStore(rules.sparkSession, "robustness")
    scope = store.write(c.rule_elements(c.itemset_values(rules), elements), "scope")
    score = lambda r, agg: c.contribution_decomposed(c.itemset_values(r, agg), scope)
    ref = store.write(score(rules, "max").select("elem_id", "x"), "reference")
    variants = {f"score_{s}": lambda s=s: score(with_score(rules, s), "max") for s in ("confidence", "lift")}
    variants |= {f"agg_{a}": lambda a=a: score(rules, a) for a in ("sum", "top2", "top3", "avg")}
    return quality_by(ref, _stacked(variants, "variant", store)[0], "variant").select("variant", F.col("rho").alias("rank_corr"))
