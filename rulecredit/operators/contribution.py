"""How much each element contributes to the interestingness of a rule set.

With V(T) the aggregate score of the rules whose elements are exactly T, n elements and
w(k) = k!(n-k-1)!/n!, an element's contribution is the weighted sum of V(S + e) - V(S)
over the attribute-disjoint sets S that lack the attribute of e. Five equivalent forms:

* ``naive``      every valid set (guarded: exponential);
* ``single``     only mined itemsets and their one-removed subsets, one element;
* ``sequential`` single, a job for each element after the other (the timing baseline);
* ``multi``      the same sets, shared by all elements in one plan;
* ``decomposed`` (default) no sets at all. V vanishes off the mined itemsets, so
  X(e) = P(e) - (W - A(attr e)) with P(e) = sum of w(|T|-1) V(T) over T with e,
  A(a) = sum of w(|T|) V(T) over T with attribute a, W = the sum over all T.
"""

from __future__ import annotations

from functools import reduce
from math import log10

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulecredit.functions.aggregates import set_aggregate
from rulecredit.functions.weights import lookup, shapley_weights


def itemset_values(rules: DataFrame, agg: str = "max") -> DataFrame:
    """(items, attrs, size, n_rules, value): one row per distinct itemset, one shuffle."""
    return rules.groupBy("items").agg(
        F.first("attrs").alias("attrs"), F.first("size").alias("size"), F.count("*").alias("n_rules"), set_aggregate(agg).alias("value")
    )


def set_interest(rules: DataFrame, agg: str = "max") -> DataFrame:
    """One row: the interestingness of the whole set, 0 for none."""
    return rules.agg(F.coalesce(set_aggregate(agg), F.lit(0.0)).alias("interest"))


def restrict(values: DataFrame, elements: DataFrame) -> DataFrame:
    """Itemsets made of the given elements only. ``elements`` is small: its size is bounded by support."""
    ids = [r[0] for r in elements.select("elem_id").distinct().collect()]
    inside = F.array(*[F.lit(i) for i in ids]) if ids else F.array().cast("array<int>")
    return values.where(F.size(F.array_except("items", inside)) == 0)


def rule_elements(values: DataFrame, elements: DataFrame) -> DataFrame:
    """The elements met in at least one rule."""
    return elements.join(values.select(F.explode("items").alias("elem_id")).distinct(), "elem_id", "left_semi")


def shape(values: DataFrame, elements: DataFrame) -> tuple[int, int]:
    """(number of elements, largest itemset): the two numbers the weights need."""
    return elements.count(), values.agg(F.max("size")).first()[0] or 0


def combine(elements: DataFrame, parts: DataFrame, n: int, top: int) -> DataFrame:
    """Scores from ``parts`` (kind, id, size, v): sums of V by size for each element ('e'),
    attribute ('a') and over all ('w'). Weights enter last, so parts do not depend on n."""
    w = shapley_weights(n, top)
    own = F.sum(lookup(w, F.col("size") - 1) * F.col("v"))
    rest = F.sum(lookup(w, F.col("size")) * F.col("v"))
    p = parts.where("kind = 'e'").groupBy(F.col("id").alias("elem_id")).agg(own.alias("p"))
    a = parts.where("kind = 'a'").groupBy(F.col("id").alias("attr_id")).agg(rest.alias("a"))
    whole = parts.where("kind = 'w'").agg(F.coalesce(rest, F.lit(0.0)).alias("w")).scalar()
    joined = elements.join(F.broadcast(p), "elem_id", "left").join(F.broadcast(a), "attr_id", "left")
    x = F.coalesce("p", F.lit(0.0)) - (whole - F.coalesce("a", F.lit(0.0)))
    return joined.withColumn("x", x).drop("p", "a")


def statistics(values: DataFrame) -> DataFrame:
    """(kind, id, size, v): one pass, one shuffle of at most (elements + attributes + 1) x sizes rows a task."""
    tag = lambda k, c: F.transform(c, lambda i: F.struct(F.lit(k).alias("kind"), i.alias("id")))
    cells = F.concat(tag("e", "items"), tag("a", "attrs"), F.array(F.struct(F.lit("w").alias("kind"), F.lit(-1).alias("id"))))
    return values.select(F.explode(cells).alias("c"), "size", "value").groupBy("c.kind", "c.id", "size").agg(F.sum("value").alias("v"))


def merge_statistics(*parts: DataFrame) -> DataFrame:
    """Statistics of several rule sets, or of a set and signed changes to it, added up."""
    return reduce(DataFrame.unionByName, parts).groupBy("kind", "id", "size").agg(F.sum("v").alias("v"))


def contribution_decomposed(values: DataFrame, elements: DataFrame) -> DataFrame:
    n, top = shape(values, elements)
    return combine(elements, statistics(values), n, top)


def valid_coalitions(elements: DataFrame, elem_id: int, max_coalitions: int = 1_000_000) -> DataFrame:
    """Every attribute-disjoint set without the element's attribute; refused above the limit."""
    rows = elements.select("elem_id", "attr_id").collect()
    attr = {r[0]: r[1] for r in rows}
    groups: dict[int, list[int]] = {}
    for e, a in attr.items():
        if a != attr[elem_id]:
            groups.setdefault(a, []).append(e)
    total = 1
    for g in groups.values():
        total *= len(g) + 1
    if total > max_coalitions:
        raise ValueError(f"{total} coalitions exceed the limit of {max_coalitions}")
    # a coalition is a number in mixed radix: digit 0 leaves the attribute out
    n, items, radix = F.col("id"), [], 1
    for g in groups.values():
        digit = F.floor(n / radix) % (len(g) + 1)
        items.append(F.when(digit > 0, F.get(F.array(*[F.lit(e) for e in g]), (digit - 1).cast("int"))))
        radix *= len(g) + 1
    made = F.array_sort(F.array_compact(F.array(*items))) if items else F.array().cast("array<int>")
    return elements.sparkSession.range(total).select(made.cast("array<int>").alias("items"))


def pruned_coalitions(values: DataFrame) -> DataFrame:
    """(items, attrs): the mined itemsets and their one-removed subsets, each once."""
    drop = lambda c, i: F.filter(c, lambda x, j: j != i)
    spots = F.sequence(F.lit(-1), F.col("size") - 1)
    # items ascend by id, attrs by id of attribute: both are kept as pairs through the drop
    pairs = F.transform(spots, lambda i: F.struct(drop("items", i).alias("items")))
    return values.select(F.explode(pairs).alias("p")).select("p.items").distinct()


def _with_attrs(sets: DataFrame, elements: DataFrame) -> DataFrame:
    """Adds ``attrs`` by a literal map of the (few) elements."""
    pairs = [F.lit(x) for r in elements.select("elem_id", "attr_id").collect() for x in (r[0], r[1])]
    of = F.create_map(*pairs).cast("map<int,int>")
    return sets.withColumn("attrs", F.transform("items", lambda i: of[i]))


def _weighted(rows: DataFrame, values: DataFrame, w: list[float]) -> DataFrame:
    """rows (elem_id, items): adds the weighted utility difference ``d``."""
    v = values.select("items", "value")
    added = F.array_sort(F.concat("items", F.array("elem_id")))
    with_e = v.select(F.col("items").alias("joined"), F.col("value").alias("v1"))
    both = rows.withColumn("joined", added).join(v.withColumnRenamed("value", "v0"), "items", "left").join(with_e, "joined", "left")
    diff = F.coalesce("v1", F.lit(0.0)) - F.coalesce("v0", F.lit(0.0))
    return both.select("elem_id", (lookup(w, F.size("items")) * diff).alias("d"))


def contribution_naive(values: DataFrame, elements: DataFrame, elem_id: int, max_coalitions: int = 1_000_000) -> DataFrame:
    n = elements.count()
    sets = valid_coalitions(elements, elem_id, max_coalitions).withColumn("elem_id", F.lit(elem_id))
    return _weighted(sets, values, shapley_weights(n, n)).groupBy("elem_id").agg(F.sum("d").alias("x"))


def contribution_single(values: DataFrame, elements: DataFrame, elem_id: int) -> DataFrame:
    n, top = shape(values, elements)
    attr = elements.where(F.col("elem_id") == elem_id).first()["attr_id"]
    sets = _with_attrs(pruned_coalitions(values), elements).where(~F.array_contains("attrs", attr))
    rows = sets.select("items", F.lit(elem_id).alias("elem_id"))
    return _weighted(rows, values, shapley_weights(n, top)).groupBy("elem_id").agg(F.sum("d").alias("x"))


def contribution_sequential(values: DataFrame, elements: DataFrame) -> DataFrame:
    """One job per element, each from the itemset values on: the timing baseline, for small rule sets.

    Runs when called; one number an element reaches the driver.
    """
    found = [
        (e, next((r["x"] for r in contribution_single(values, elements, e).collect()), 0.0))
        for e in [r[0] for r in elements.select("elem_id").orderBy("elem_id").collect()]
    ]
    scores = elements.sparkSession.createDataFrame(found, "elem_id int, x double")
    return elements.join(scores, "elem_id", "left").na.fill(0.0, ["x"])


def contribution_multi(values: DataFrame, elements: DataFrame) -> DataFrame:
    """All elements over the shared coalitions: each set meets the elements of the attributes it lacks."""
    n, top = shape(values, elements)
    sets = _with_attrs(pruned_coalitions(values), elements)
    every = F.array(*[F.lit(r[0]) for r in elements.select("attr_id").distinct().collect()]).cast("array<int>")
    lacking = sets.select("items", F.explode(F.array_except(every, "attrs")).alias("attr_id"))
    rows = lacking.join(F.broadcast(elements.select("elem_id", "attr_id")), "attr_id").select("items", "elem_id")
    scores = _weighted(rows, values, shapley_weights(n, top)).groupBy("elem_id").agg(F.sum("d").alias("x"))
    return elements.join(scores, "elem_id", "left").na.fill(0.0, ["x"])


METHODS = {"decomposed": contribution_decomposed, "multi": contribution_multi, "sequential": contribution_sequential}


def contribution(rules: DataFrame, elements: DataFrame, agg: str = "max", method: str = "decomposed", within: DataFrame | None = None) -> DataFrame:
    """Scores ``x`` of the elements of ``within`` (default: those in a rule) from scored rules."""
    values = itemset_values(rules, agg)
    if within is not None:
        values = restrict(values, within)
    scope = within if within is not None else rule_elements(values, elements)
    return METHODS[method](values, scope)


def contribution_context(rules: DataFrame, elements: DataFrame, predicate: str, agg: str = "max") -> DataFrame:
    """Scores from the rules that satisfy a SQL predicate."""
    return contribution(rules.where(predicate), elements, agg)


def count_naive(elements: DataFrame) -> DataFrame:
    """(elem_id, naive, log10_naive): valid coalitions of each element, as a product over the other attributes."""
    sizes = {r[0]: r[1] for r in elements.groupBy("attr_id").count().collect()}
    total = 1
    for s in sizes.values():
        total *= s + 1
    own = F.create_map(*[F.lit(x) for a, s in sizes.items() for x in (a, str(total // (s + 1)))]).cast("map<int,string>")
    exact = own[F.col("attr_id")]
    wide = F.when(F.length(exact) <= 38, exact.cast("decimal(38,0)"))
    return elements.select("elem_id", "attr_id", wide.alias("naive"), (F.length(exact) - 1 + F.log10(F.concat(F.substring(exact, 1, 1), F.lit("."), F.substring(exact, 2, 15)).cast("double"))).alias("log10_naive"))


def count_pruned(values: DataFrame, elements: DataFrame) -> DataFrame:
    """(elem_id, pruned): distinct coalitions without the element's attribute, by complement."""
    sets = _with_attrs(pruned_coalitions(values), elements)
    cells = F.explode(F.concat(F.array(F.lit(-1)), "attrs"))
    per = sets.select(cells.alias("attr_id")).groupBy("attr_id").agg(F.count("*").alias("k"))
    total = per.where("attr_id = -1").select("k").scalar()
    joined = elements.join(F.broadcast(per), "attr_id", "left")
    return joined.select("elem_id", "attr_id", (F.coalesce(total, F.lit(0)) - F.coalesce("k", F.lit(0))).alias("pruned"))


def count_bound(rules: DataFrame, elements: DataFrame) -> DataFrame:
    """(elem_id, bound): rules with the attribute give one coalition, the others their size and one."""
    stats = rules.agg(F.count("*").alias("r"), F.max("size").alias("t")).first()
    r, t = stats["r"], stats["t"] or 0
    have = rules.select(F.explode("attrs").alias("attr_id")).groupBy("attr_id").agg(F.count("*").alias("k"))
    k = F.coalesce("k", F.lit(0))
    return elements.join(F.broadcast(have), "attr_id", "left").select("elem_id", ((r - k) * (t + 1) + k).alias("bound"))


def speedup_bound(n_elements: int, tau: int) -> float:
    """Sequential over shared work: |E| t (t+1) / (|E| (t+1) + t^2)."""
    return n_elements * tau * (tau + 1) / (n_elements * (tau + 1) + tau * tau)


def count_worst(n_rows: int, n_attributes: int) -> float:
    """log10 of the most coalitions an element can have: each of the attributes with as many values as rows."""
    return n_attributes * log10(n_rows) if n_rows else 0.0
