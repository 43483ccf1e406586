"""Sampling estimators of the contribution.

Two frames. ``index`` draws from the pruned coalitions: a size first, then a set within
the size. An estimate of S is w(|S|) (V(S + e) - V(S)) / q(S), averaged over the draws;
split as in the decomposed form, a draw only touches the elements that extend it to a
mined itemset and the attributes of S. ``permutation`` draws orders of the elements and
looks at the set before each element; only prefixes up to the largest itemset matter. A Sobol
order takes one coordinate a place: it picks among the elements not yet taken.

Estimators: monte_carlo (independent draws, sizes weighted by w), kernel (sizes weighted by
the regression kernel; the two ends counted exactly), antithetic (half the draws, each with
its mirror), stratified (a quota of sets per size, no repeats; exact at a full budget) and
sobol (two-dimensional low-discrepancy draws). ``mode='expectation'`` visits every set
once with its probability, which gives the estimator's expected value.

Draws come from hashes of their number, so retries and repartitioning change nothing.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rulecredit.functions.weights import BITS, DIMENSIONS, kernel_weights, lookup, shapley_weights, sobol_point, uniform
from rulecredit.operators.contribution import contribution_decomposed, pruned_coalitions, shape
from rulecredit.sources.store import TableStore

ESTIMATORS = ("kernel", "monte_carlo", "antithetic", "stratified", "sobol")


#: Coalitions numbered by one task, about.
BUCKET_ROWS = 100_000


def _positions(values: DataFrame) -> DataFrame:
    """(items, k, pos): pruned coalitions numbered within their size, by hash bucket, then item order.

    Buckets are counted first and each numbers its own rows, so that no size has to fit one task.
    """
    store = TableStore(values.sparkSession, "coalitions")
    sets = store.write(pruned_coalitions(values).withColumn("k", F.size("items")), "sets")
    buckets = max(1, sets.count() // BUCKET_ROWS)
    placed = sets.withColumn("bucket", F.pmod(F.xxhash64("items"), F.lit(buckets)))
    before = Window.partitionBy("k").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = placed.groupBy("k", "bucket").agg(F.count("*").alias("n")).select("k", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    own = Window.partitionBy("k", "bucket").orderBy("items")
    return placed.withColumn("nth", F.row_number().over(own) - 1).join(base, ["k", "bucket"]).select("items", "k", (F.col("base") + F.col("nth")).alias("pos"))


def _lowest(numbered: DataFrame, quota: dict[int, int], seed: int) -> DataFrame:
    """The quota[k] sets of each size with the lowest hash.

    A histogram of the hashes tells the last cell that is needed; only rows up to it are ranked.
    """
    cells = 4096
    take = F.create_map(*[F.lit(x) for k in quota for x in (k, quota[k])])[F.col("k")]
    drawn = numbered.withColumn("u", uniform(F.col("k"), F.col("pos"), seed)).withColumn("cell", F.floor(F.col("u") * cells))
    before = Window.partitionBy("k").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    counts = drawn.groupBy("k", "cell").agg(F.count("*").alias("n"))
    needed = counts.withColumn("ahead", F.coalesce(F.sum("n").over(before), F.lit(0))).where(F.col("ahead") < take)
    few = drawn.join(F.broadcast(needed.select("k", "cell")), ["k", "cell"], "left_semi")  # sizes x cells rows at most
    ranked = few.withColumn("r", F.row_number().over(Window.partitionBy("k").orderBy("u", "pos")))
    return ranked.where(F.col("r") <= take).select("items", "k")


def _size_counts(numbered: DataFrame) -> dict[int, int]:
    return {r["k"]: r["n"] for r in numbered.groupBy("k").agg(F.count("*").alias("n")).collect()}


def _draws(numbered: DataFrame, counts: dict[int, int], weight: list[float], m: int, seed: int, how: str) -> DataFrame:
    """(items, k, factor): drawn sets with multiplicity over (draws x probability)."""
    spark = numbered.sparkSession
    mass = {k: counts[k] * weight[k] for k in counts if k < len(weight) and weight[k] > 0}
    total = sum(mass.values())
    if not total:
        return numbered.select("items", "k", F.lit(0.0).alias("factor")).limit(0)
    edges, acc = [], 0.0
    for k in sorted(mass):
        edges.append((acc, k))
        acc += mass[k] / total
    i = F.col("id")
    base = F.floor(i / 2) if how == "antithetic" else i
    if how == "sobol":
        u1, u2 = (sobol_point(i.cast("int"), d, uniform(seed, 7919 + d)) for d in (0, 1))
    else:
        u1, u2 = (uniform(base, seed, d) for d in (1, 2))
        if how == "antithetic":
            top = F.lit(1.0 - 2.0**-53)
            u1, u2 = (F.when(i % 2 == 1, top - u).otherwise(u) for u in (u1, u2))
    size: Column = F.lit(edges[0][1])
    for edge, k in edges[1:]:
        size = F.when(F.col("u1") >= edge, k).otherwise(size)
    number = F.create_map(*[F.lit(x) for k in counts for x in (k, counts[k])])
    drawn = spark.range(m).select(u1.alias("u1"), u2.alias("u2")).select(size.alias("k"), "u2")
    drawn = drawn.withColumn("pos", F.least(F.floor(F.col("u2") * number[F.col("k")]), number[F.col("k")] - 1).cast("long"))
    tally = drawn.groupBy("k", "pos").agg(F.count("*").alias("times"))
    q = lookup([weight[k] / total if k < len(weight) else 0.0 for k in range(max(counts) + 1)], F.col("k"))
    return numbered.join(tally, ["k", "pos"]).select("items", "k", (F.col("times") / (F.lit(float(m)) * q)).alias("factor"))


def _estimate(chosen: DataFrame, values: DataFrame, elements: DataFrame, w: list[float]) -> DataFrame:
    """Scores from (items, k, factor): the sum of factor w(k) (V(S + e) - V(S)).

    Gains: each mined itemset minus one element is looked up among the chosen sets. Losses:
    V(S) counts against every element whose attribute S lacks, by complement.
    """
    drop = F.transform("items", lambda e: F.struct(F.filter("items", lambda x: x != e).alias("s"), e.alias("elem_id")))
    ext = values.select(F.explode(drop).alias("d"), "value").select(F.col("d.s").alias("items"), "d.elem_id", "value")
    weighted = chosen.withColumn("f", F.col("factor") * lookup(w, F.col("k"))).select("items", "f")
    gain = ext.join(weighted, "items").groupBy("elem_id").agg(F.sum(F.col("f") * F.col("value")).alias("gain"))
    lost = values.join(weighted, "items").select("attrs", (F.col("f") * F.col("value")).alias("l"))
    per = lost.select(F.explode(F.concat(F.array(F.lit(-1)), "attrs")).alias("attr_id"), "l").groupBy("attr_id").agg(F.sum("l").alias("l"))
    whole = per.where("attr_id = -1").agg(F.coalesce(F.sum("l"), F.lit(0.0))).scalar()
    joined = elements.join(F.broadcast(gain), "elem_id", "left").join(F.broadcast(per), "attr_id", "left")
    x = F.coalesce("gain", F.lit(0.0)) - (whole - F.coalesce("l", F.lit(0.0)))
    return joined.withColumn("x", x).drop("gain", "l")


def estimate_index(
    values: DataFrame, elements: DataFrame, method: str, n_samples: int, seed: int = 0, mode: str = "sample", alloc: str = "proportional"
) -> DataFrame:
    n, top = shape(values, elements)
    w = shapley_weights(n, top)
    numbered = _positions(values)
    if mode == "expectation":
        return _estimate(numbered.select("items", "k", F.lit(1.0).alias("factor")), values, elements, w)
    counts = _size_counts(numbered)
    if method == "stratified":
        total = sum(counts.values())
        share = {k: (c / total if alloc == "proportional" else 1 / len(counts)) for k, c in counts.items()}
        quota = {k: min(counts[k], max(1, round(n_samples * share[k]))) for k in counts}
        factor = F.create_map(*[F.lit(x) for k in quota for x in (k, counts[k] / quota[k])])[F.col("k")]
        chosen = _lowest(numbered, quota, seed).withColumn("factor", factor) if quota else numbered.select("items", "k", F.lit(0.0).alias("factor"))
        return _estimate(chosen, values, elements, w)
    if method == "kernel":
        ends = numbered.where((F.col("k") == 0) | (F.col("k") == n)).select("items", "k", F.lit(1.0).alias("factor"))
        drawn = _draws(numbered, counts, kernel_weights(n, max(counts, default=0)), n_samples, seed, "independent")
        return _estimate(ends.unionByName(drawn), values, elements, w)
    how = {"monte_carlo": "independent", "antithetic": "antithetic", "sobol": "sobol"}[method]
    return _estimate(_draws(numbered, counts, w, n_samples, seed, how), values, elements, w)


def estimate_poisson(values: DataFrame, elements: DataFrame, n_samples: int, seed: int = 0) -> DataFrame:
    """A map-only scheme for very many coalitions: each set enters on its own hash with
    probability min(1, m q) and counts by its inverse."""
    n, top = shape(values, elements)
    w = shapley_weights(n, top)
    numbered = pruned_coalitions(values).withColumn("k", F.size("items"))
    counts = _size_counts(numbered)
    total = sum(c * w[k] for k, c in counts.items() if k < len(w)) or 1.0
    p = F.least(F.lit(1.0), lookup([n_samples * x / total for x in w], F.col("k")))
    kept = numbered.withColumn("p", p).where(uniform(F.col("items"), seed) < F.col("p"))
    return _estimate(kept.select("items", "k", (1 / F.col("p")).alias("factor")), values, elements, w)


def estimate_permutation(values: DataFrame, elements: DataFrame, method: str, n_samples: int, seed: int = 0) -> DataFrame:
    """Orders of the elements as hashes; (prefix, next element) pairs up to the largest itemset."""
    n, top = shape(values, elements)
    rows = elements.select("elem_id", "attr_id").orderBy("elem_id").collect()
    ids = [r[0] for r in rows]
    attr = F.create_map(*[F.lit(x) for r in rows for x in (r[0], r[1])])
    i, depth = F.col("id"), min(top + 1, n)
    base = F.floor(i / 2) if method == "antithetic" else i
    full = F.array(*[F.lit(e) for e in ids])
    if method == "sobol":
        if depth > DIMENSIONS or n_samples > 1 << BITS:
            raise ValueError(f"Sobol orders have at most {DIMENSIONS} places and {1 << BITS} draws")
        spots = F.array(*[sobol_point(i.cast("int"), d, uniform(seed, 7919 + d)) for d in range(depth)])
        start = F.struct(F.array().cast("array<int>").alias("o"), full.alias("rest"))

        def pick(acc: Column, u: Column) -> Column:
            rest = acc["rest"]
            at = F.least(F.floor(u * F.size(rest)), F.size(rest) - 1).cast("int")
            return F.struct(F.concat(acc["o"], F.array(F.get(rest, at))).alias("o"), F.filter(rest, lambda e, j: j != at).alias("rest"))

        order = F.aggregate(spots, start, pick, lambda acc: acc["o"])
    else:
        key = lambda e: uniform(base, e, seed)
        order = F.transform(F.array_sort(F.transform(full, lambda e: F.struct(key(e).alias("u"), e.alias("e")))), lambda s: s["e"])
    if method == "antithetic":
        order = F.when(i % 2 == 1, F.reverse(order)).otherwise(order)
    spark = values.sparkSession
    drawn = spark.range(n_samples).select("id", F.slice(order, 1, depth).alias("o"))
    steps = drawn.select("o", F.posexplode("o").alias("at", "elem_id")).select(
        F.expr("slice(o, 1, at)").alias("prefix"), "elem_id"
    )
    clash = F.size(F.array_distinct(F.transform("prefix", lambda e: attr[e]))) < F.size("prefix")
    meets = F.exists("prefix", lambda e: attr[e] == attr[F.col("elem_id")])
    live = steps.where(~clash & ~meets).select(F.array_sort("prefix").alias("items"), "elem_id")
    tally = live.groupBy("items", "elem_id").agg(F.count("*").alias("times"))
    v = values.select("items", "value")
    joined = tally.withColumn("j", F.array_sort(F.concat("items", F.array("elem_id"))))
    both = joined.join(v.withColumnRenamed("value", "v0"), "items", "left").join(
        v.select(F.col("items").alias("j"), F.col("value").alias("v1")), "j", "left"
    )
    diff = F.coalesce("v1", F.lit(0.0)) - F.coalesce("v0", F.lit(0.0))
    x = both.groupBy("elem_id").agg((F.sum(F.col("times") * diff) / n_samples).alias("x"))
    return elements.join(x, "elem_id", "left").na.fill(0.0, ["x"])


def approximate(values: DataFrame, elements: DataFrame, method: str, n_samples: int = 4096, seed: int = 0, frame: str = "index", **kw) -> DataFrame:
    if method not in ESTIMATORS:
        raise ValueError(f"unknown estimator {method}")
    if frame == "permutation":
        if method in ("kernel", "stratified"):
            raise ValueError(f"{method} draws sets, not orders: use the index frame")
        return estimate_permutation(values, elements, method, n_samples, seed)
    return estimate_index(values, elements, method, n_samples, seed, **kw)


def exact(values: DataFrame, elements: DataFrame) -> DataFrame:
    return contribution_decomposed(values, elements)
