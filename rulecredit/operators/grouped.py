"""Mining and scoring of many row groups (windows, instances) in one pass, the group as a key.

Elements and itemsets are texts ``attr=val`` here: ids would have to be numbered per group.
A group's knobs and row count come from one row of ``groups``; no group is looped over and
nothing is collected.
"""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rulecredit.functions.aggregates import set_aggregate
from rulecredit.functions.scores import score_column
from rulecredit.functions.weights import sobol_point, uniform
from rulecredit.operators.mining import with_measures
from rulecredit.sources.store import TableStore


def attribute_of(e: Column) -> Column:
    return F.substring_index(e, "=", 1)


def tuple_texts(attrs: list[str]) -> Column:
    """The elements of a row, ascending; null cells have none."""
    cells = [F.when(F.col(a).isNotNull(), F.concat(F.lit(f"{a}="), F.col(a).cast("string"))) for a in attrs]
    return F.array_sort(F.array_compact(F.array(*cells)))


def limits(min_support: float) -> Column:
    """A support as an exact decimal, for the ``min_support`` column of ``groups``."""
    return F.lit(Decimal(str(min_support))).cast("decimal(12,10)")


def _frequent(cnt: Column | str) -> Column:
    return F.col(cnt) >= F.col("min_support") * F.col("n_rows")


def grouped_itemsets(tuples: DataFrame, groups: DataFrame, max_len: int, store: TableStore) -> DataFrame:
    """(g, items, size, cnt, n_rows): each group's frequent itemsets, level by level.

    ``tuples`` (g, items, c); ``groups`` (g, min_support). A level extends a group's frequent
    prefixes by the elements that follow in a tuple; the last level is the first empty one.
    """
    sized = store.write(groups.join(tuples.groupBy("g").agg(F.sum("c").alias("n_rows")), "g"), "groups")
    single = tuples.select("g", F.explode("items").alias("e"), "c").groupBy("g", "e").agg(F.sum("c").alias("cnt"))
    known = single.join(sized, "g").where(_frequent("cnt")).groupBy("g").agg(F.collect_list("e").alias("known"))
    rows = tuples.join(store.write(known, "known"), "g").select("g", F.array_intersect("items", "known").alias("rest"), "c")
    live = rows.select("g", F.array().cast("array<string>").alias("items"), "rest", "c")
    found = None
    for k in range(1, max_len + 1):
        grown = live.where(F.size("rest") > 0).select("g", "items", F.posexplode("rest").alias("at", "next"), "rest", "c").select(
            "g",
            F.concat("items", F.array("next")).alias("items"),
            F.expr("slice(rest, at + 2, greatest(size(rest) - at - 1, 0))").alias("rest"),
            "c",
        )
        grown = store.write(grown.groupBy("g", "items", "rest").agg(F.sum("c").alias("c")), f"grown{k}")
        counts = grown.groupBy("g", "items").agg(F.sum("c").alias("cnt")).join(sized, "g").where(_frequent("cnt"))
        level = store.write(counts.select("g", "items", F.lit(k).alias("size"), "cnt", "n_rows"), f"level{k}")
        found = level if found is None else found.unionByName(level)
        if level.isEmpty():
            break
        live = grown.join(level.select("g", "items"), ["g", "items"], "left_semi")
    return store.write(found, "itemsets")


def grouped_rules(itemsets: DataFrame, score: str = "is") -> DataFrame:
    """Scored rules of each group, both sides from the group's own itemsets."""
    splits = itemsets.where("size >= 2").withColumn("mask", F.explode(F.expr("sequence(1, shiftleft(1, size) - 2)")))
    side = lambda bit: F.filter("items", lambda x, i: F.getbit(F.col("mask"), i) == bit)
    split = splits.withColumns({"lhs": side(1), "rhs": side(0)}).drop("mask")
    counts = lambda s: itemsets.select("g", F.col("items").alias(s), F.col("cnt").alias(f"{s}_cnt"))
    return with_measures(split.join(counts("lhs"), ["g", "lhs"]).join(counts("rhs"), ["g", "rhs"])).withColumn("score", score_column(score))


def far_from_independent(min_lift: Column) -> Column:
    return F.greatest(F.col("lift"), 1 / F.col("lift")) >= min_lift


def grouped_values(rules: DataFrame, agg: str = "max") -> DataFrame:
    """(g, items, size, n_rules, value)."""
    return rules.groupBy("g", "items").agg(F.first("size").alias("size"), F.count("*").alias("n_rules"), set_aggregate(agg).alias("value"))


def _weight(n: Column, size: Column, top: int) -> Column:
    """1 / (n C(n - 1, size)) for sizes up to ``top``, 0 from n on."""
    out = F.when(size >= n, F.lit(0.0))
    ways = F.lit(1.0)
    for k in range(top + 1):
        out = out.when(size == k, F.lit(1.0) / (n * ways))
        ways = ways * (n - (k + 1)) / (k + 1)
    return out


def grouped_contribution(values: DataFrame, top: int) -> DataFrame:
    """(g, elem, x) of every element in a rule of its group: the decomposed form, n counted per group."""
    attrs = F.transform("items", attribute_of)
    tag = lambda kind, c: F.transform(c, lambda i: F.struct(F.lit(kind).alias("kind"), i.alias("id")))
    cells = F.concat(tag("e", F.col("items")), tag("a", attrs), F.array(F.struct(F.lit("w").alias("kind"), F.lit("").alias("id"))))
    parts = values.select("g", F.explode(cells).alias("c"), "size", "value").groupBy("g", "c.kind", "c.id", "size").agg(F.sum("value").alias("v"))
    number = parts.where("kind = 'e'").groupBy("g").agg(F.count_distinct("id").alias("n"))
    at = F.col("size") - F.when(F.col("kind") == "e", 1).otherwise(0)
    sums = parts.join(number, "g").groupBy("g", "kind", "id").agg(F.sum(_weight(F.col("n"), at, top) * F.col("v")).alias("s"))
    pick = lambda kind, name, key: sums.where(F.col("kind") == kind).select("g", F.col("id").alias(key), F.col("s").alias(name))
    own = pick("e", "p", "elem").withColumn("attr", attribute_of(F.col("elem")))
    joined = own.join(pick("a", "a", "attr"), ["g", "attr"]).join(pick("w", "w", "_").drop("_"), "g")
    return joined.select("g", "elem", (F.col("p") - (F.col("w") - F.col("a"))).alias("x"))


def grouped_counts(values: DataFrame) -> DataFrame:
    """(g, elem, naive, pruned) of every element in a rule of its group: all valid coalitions without the
    element's attribute, and those among the itemsets and their one-removed subsets."""
    scope = values.select("g", F.explode("items").alias("elem")).distinct().withColumn("attr", attribute_of(F.col("elem")))
    sizes = scope.groupBy("g", "attr").agg((F.count("*") + 1).cast("double").alias("k"))
    total = sizes.groupBy("g").agg(F.aggregate(F.collect_list("k"), F.lit(1.0), lambda acc, k: acc * k).alias("total"))
    drop = F.transform(F.sequence(F.lit(-1), F.col("size") - 1), lambda i: F.filter("items", lambda x, j: j != i))
    sets = values.select("g", F.explode(drop).alias("items")).distinct()
    cells = F.explode(F.concat(F.array(F.lit("")), F.transform("items", attribute_of)))
    per = sets.select("g", cells.alias("attr")).groupBy("g", "attr").agg(F.count("*").alias("n"))
    every = per.where("attr = ''").select("g", F.col("n").alias("sets"))
    joined = scope.join(sizes, ["g", "attr"]).join(total, "g").join(every, "g").join(per, ["g", "attr"], "left")
    return joined.select("g", "elem", (F.col("total") / F.col("k")).alias("naive"), (F.col("sets") - F.coalesce("n", F.lit(0))).alias("pruned"))


def grouped_top(rules: DataFrame) -> DataFrame:
    """(g, elem, x): the best score of a rule with the element."""
    return rules.select("g", F.explode("items").alias("elem"), "score").groupBy("g", "elem").agg(F.max("score").alias("x"))


def grouped_influence(rules: DataFrame) -> DataFrame:
    """(g, elem, x): the group's best score minus that of its rules without the element.

    Only an element of one best rule can matter; the other elements score 0.
    """
    best = rules.groupBy("g").agg(F.max(F.struct("score", "lhs", "rhs", "items")).alias("b"))
    tops = best.select("g", F.col("b.score").alias("top"), F.col("b.items").alias("held"))
    lacking = rules.join(F.broadcast(tops), "g").select("g", F.explode(F.array_except("held", "items")).alias("elem"), "score")
    rest = lacking.groupBy("g", "elem").agg(F.max("score").alias("rest"))
    scope = rules.select("g", F.explode("items").alias("elem")).distinct().join(F.broadcast(tops), "g")
    x = F.when(F.array_contains("held", F.col("elem")), F.col("top") - F.coalesce("rest", F.lit(0.0))).otherwise(0.0)
    return scope.join(rest, ["g", "elem"], "left").select("g", "elem", x.alias("x"))


def _kernel(n: Column, size: Column, top: int) -> Column:
    """(n - 1) / (C(n, size) size (n - size)) for sizes 1 to ``top`` below n, 0 elsewhere."""
    out, ways = F.lit(0.0), F.lit(1.0)
    for k in range(1, top + 1):
        ways = ways * (n - (k - 1)) / k
        out = F.when((size == k) & (size < n), (n - 1) / (ways * k * (n - k))).otherwise(out)
    return out


def grouped_estimate(values: DataFrame, method: str, n_samples: int, top: int, store: TableStore, seed: int = 0) -> DataFrame:
    """(g, elem, x): an estimator of the index frame (see ``approx``) for every group, from the same draws.

    Meant for many small groups: a size of a group is numbered by one task.
    """
    number = values.select("g", F.explode("items").alias("e")).groupBy("g").agg(F.count_distinct("e").alias("n"))
    drop = F.transform(F.sequence(F.lit(-1), F.col("size") - 1), lambda i: F.filter("items", lambda x, j: j != i))
    sets = values.select("g", F.explode(drop).alias("items")).distinct().withColumn("k", F.size("items"))
    numbered = store.write(sets.withColumn("pos", (F.row_number().over(Window.partitionBy("g", "k").orderBy("items")) - 1).cast("long")), f"{method}-sets")
    sizes = numbered.groupBy("g", "k").agg(F.count("*").alias("cnt")).join(number, "g")
    w = _weight(F.col("n"), F.col("k"), top)
    sizes = sizes.withColumn("w", w).withColumn("p", _kernel(F.col("n"), F.col("k"), top) if method == "kernel" else w).where("w is not null")
    if method == "stratified":
        total = F.sum("cnt").over(Window.partitionBy("g"))
        quota = F.least("cnt", F.greatest(F.lit(1), F.round(n_samples * F.col("cnt") / total))).cast("long")
        order = Window.partitionBy("g", "k").orderBy(uniform(F.col("k"), F.col("pos"), seed), "pos")
        ranked = numbered.join(sizes.withColumn("quota", quota), ["g", "k"]).withColumn("r", F.row_number().over(order))
        chosen = ranked.where("r <= quota").select("g", "items", (F.col("w") * F.col("cnt") / F.col("quota")).alias("f"))
    else:
        mass, by_size = F.col("cnt") * F.col("p"), Window.partitionBy("g").orderBy("k")
        edges = sizes.where("p > 0").withColumns({"hi": F.sum(mass).over(by_size), "all": F.sum(mass).over(Window.partitionBy("g"))})
        edges = edges.withColumn("edge", F.struct((F.col("hi") / F.col("all")).alias("hi"), "k", "cnt", (F.col("p") / F.col("all")).alias("q"), "w"))
        drawn = edges.groupBy("g").agg(F.sort_array(F.collect_list("edge")).alias("e")).withColumn("id", F.explode(F.sequence(F.lit(0), F.lit(n_samples - 1))))
        i = F.col("id")
        if method == "sobol":
            u1, u2 = (sobol_point(i, d, uniform(seed, 7919 + d)) for d in (0, 1))
        elif method == "antithetic":
            u1, u2 = (F.when(i % 2 == 1, F.lit(1.0 - 2.0**-53) - uniform(F.floor(i / 2), seed, d)).otherwise(uniform(F.floor(i / 2), seed, d)) for d in (1, 2))
        else:
            u1, u2 = (uniform(i.cast("long"), seed, d) for d in (1, 2))
        drawn = drawn.withColumns({"u1": u1, "u2": u2})
        hit = F.coalesce(F.get(F.filter("e", lambda x: F.col("u1") < x["hi"]), F.lit(0)), F.element_at("e", -1))
        drawn = drawn.withColumn("hit", hit).withColumn("pos", F.least(F.floor(F.col("u2") * F.col("hit.cnt")), F.col("hit.cnt") - 1).cast("long"))
        tally = drawn.groupBy("g", "hit.k", "pos").agg(F.count("*").alias("times"), F.first("hit.q").alias("q"), F.first("hit.w").alias("w"))
        chosen = numbered.join(tally, ["g", "k", "pos"]).select("g", "items", (F.col("w") * F.col("times") / (n_samples * F.col("q"))).alias("f"))
        if method == "kernel":  # the two sizes without a weight count exactly
            ends = numbered.join(sizes, ["g", "k"]).where("k = 0 or k = n").select("g", "items", F.col("w").alias("f"))
            chosen = chosen.unionByName(ends)
    chosen = store.write(chosen, f"{method}-chosen")
    one_less = F.transform("items", lambda e: F.struct(F.filter("items", lambda x: x != e).alias("s"), e.alias("elem")))
    ext = values.select("g", F.explode(one_less).alias("d"), "value").select("g", F.col("d.s").alias("items"), "d.elem", "value")
    gain = ext.join(chosen, ["g", "items"]).groupBy("g", "elem").agg(F.sum(F.col("f") * F.col("value")).alias("gain"))
    lost = values.join(chosen, ["g", "items"]).select("g", F.transform("items", attribute_of).alias("attrs"), (F.col("f") * F.col("value")).alias("l"))
    per = lost.select("g", F.explode(F.concat(F.array(F.lit("")), "attrs")).alias("attr"), "l").groupBy("g", "attr").agg(F.sum("l").alias("l"))
    whole = per.where("attr = ''").select("g", F.col("l").alias("whole"))
    scope = values.select("g", F.explode("items").alias("elem")).distinct().withColumn("attr", attribute_of(F.col("elem")))
    joined = scope.join(gain, ["g", "elem"], "left").join(per, ["g", "attr"], "left").join(whole, "g", "left").na.fill(0.0, ["gain", "l", "whole"])
    return joined.select("g", "elem", (F.col("gain") - (F.col("whole") - F.col("l"))).alias("x"))
