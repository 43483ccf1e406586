"""Elements, frequent itemsets, rules.

Itemsets are ascending arrays of element ids. The ids number the *frequent* elements in
the order of their text ``attr=val``; an attribute has at most 1/min_support of them, so
every element-sized frame is small whatever the data size.
"""

from __future__ import annotations

from dataclasses import dataclass
from decimal import ROUND_CEILING, Decimal
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rulecredit.functions.scores import confidence, lift, score_column, support
from rulecredit.operators.bitmaps import bitmap_itemsets, element_counts, split_methods
from rulecredit.operators.prepare import compress
from rulecredit.sources.store import TableStore


@dataclass
class Mined:
    """n_rows; elements (elem_id, attr_id, attr, val, freq_cnt, freq); itemsets (items, size, cnt)."""

    n_rows: int
    elements: DataFrame
    itemsets: DataFrame


def min_count(min_support: float, n_rows: int) -> int:
    """The least whole count with cnt >= min_support * n_rows, free of binary rounding."""
    return int((Decimal(str(min_support)) * n_rows).to_integral_value(ROUND_CEILING))


def element_frequencies(view: DataFrame, weight: str | None = None) -> DataFrame:
    """(attr, val, freq_cnt) of every element; null cells have none."""
    attrs = [c for c in view.columns if c != weight]
    w = F.col(weight) if weight else F.lit(1).cast("bigint")
    pairs = F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("val")) for a in attrs]))
    return (
        view.select(w.alias("w"), pairs.alias("e"))
        .where("e.val is not null")
        .groupBy("e.attr", "e.val")
        .agg(F.sum("w").alias("freq_cnt"))
    )


def build_elements(view: DataFrame, n_rows: int, least: int = 1, weight: str | None = None) -> DataFrame:
    """Numbered elements met at least ``least`` times; ids are values' ranks, stable under retries."""
    return number_elements(element_frequencies(view, weight).where(F.col("freq_cnt") >= least), n_rows)


def number_elements(named: DataFrame, n_rows: int) -> DataFrame:
    """Elements (attr, val, freq_cnt) with their ids and share of the rows."""
    by_name = Window.orderBy(F.concat("attr", F.lit("="), "val"))
    by_attr = Window.orderBy("attr")
    return named.select(
        (F.row_number().over(by_name) - 1).alias("elem_id"),
        (F.dense_rank().over(by_attr) - 1).alias("attr_id"),
        "attr",
        "val",
        "freq_cnt",
        (F.lit(100.0) * F.col("freq_cnt") / n_rows).alias("freq"),
    )


def _tuple_items(tuples: DataFrame, numbered: list) -> DataFrame:
    """(items, c): each tuple's frequent elements, ascending; equal rows merged.

    The mapping is a literal of the numbered elements, whose count the support bounds.
    """
    ids: dict[str, list[Column]] = {}
    for r in numbered:
        ids.setdefault(r["attr"], []).extend([F.lit(r["val"]), F.lit(r["elem_id"])])
    cells = [F.create_map(*pairs)[F.col(a)] for a, pairs in ids.items()]
    if not cells:
        return tuples.select(F.array().cast("array<int>").alias("items"), "c").limit(0)
    items = F.array_sort(F.array_compact(F.array(*cells)))
    return tuples.select(items.alias("items"), "c").where(F.size("items") > 0).groupBy("items").agg(F.sum("c").alias("c"))


def _levelwise(rows: DataFrame, least: int, max_len: int, store: TableStore) -> DataFrame:
    """Apriori by prefixes: a row carries a frequent prefix and the elements that may follow.

    Each level extends matched prefixes only, sums support with map-side combine, and
    keeps the rows whose new prefix is frequent; rows with equal rest merge again.
    """
    live = rows.select(F.array().cast("array<int>").alias("items"), F.col("items").alias("rest"), "c")
    found = None
    for k in range(1, max_len + 1):
        grown = live.where(F.size("rest") > 0).select(
            "items", F.posexplode("rest").alias("at", "next"), "rest", "c"
        ).select(
            F.concat("items", F.array("next")).alias("items"),
            F.expr("slice(rest, at + 2, greatest(size(rest) - at - 1, 0))").alias("rest"),
            "c",
        )
        grown = store.write(grown.groupBy("items", "rest").agg(F.sum("c").alias("c")), f"grown{k}")
        level = store.write(grown.groupBy("items").agg(F.sum("c").alias("cnt")).where(F.col("cnt") >= least), f"level{k}")
        if level.isEmpty():
            break
        sized = level.select("items", F.lit(k).alias("size"), "cnt")
        found = sized if found is None else found.unionByName(sized)
        live = grown.join(level.select("items"), "items", "left_semi")
    return found if found is not None else rows.select("items", F.lit(0).alias("size"), F.col("c").alias("cnt")).limit(0)


def _cube(rows: DataFrame, least: int, max_len: int) -> DataFrame:
    """All itemsets in one pass: every subset of a tuple up to max_len, summed and cut.

    The same output as grouping sets over the attributes, without their null groups.
    Meant for few attributes: a tuple of m elements makes sum C(m, k) rows before combining.
    """
    subsets = F.lit(None)
    widest = rows.agg(F.max(F.size("items"))).first()[0] or 0
    picks = [list(p) for k in range(1, min(max_len, widest) + 1) for p in combinations(range(widest), k)]
    if not picks:
        return rows.select("items", F.size("items").alias("size"), F.col("c").alias("cnt")).limit(0)
    spots = F.from_json(F.lit(str(picks)), "array<array<int>>")
    subsets = F.transform(
        F.filter(spots, lambda p: F.element_at(p, -1) < F.size("items")), lambda p: F.transform(p, lambda i: F.get("items", i))
    )
    sums = rows.select(F.explode(subsets).alias("items"), "c").groupBy("items").agg(F.sum("c").alias("cnt"))
    return sums.where(F.col("cnt") >= least).select("items", F.size("items").alias("size"), "cnt")


def _fpgrowth(rows: DataFrame, least: int, max_len: int, n_rows: int) -> DataFrame:
    """The same itemsets from the library's FP-growth (rows repeated by their count)."""
    from pyspark.ml.fpm import FPGrowth

    baskets = rows.select("items", F.explode(F.expr("array_repeat(1, cast(c as int))")).alias("one")).select("items")
    model = FPGrowth(itemsCol="items", minSupport=max(least - 0.5, 0) / n_rows, minConfidence=1.0).fit(baskets)
    sets = model.freqItemsets.where((F.size("items") <= max_len) & (F.col("freq") >= least))
    return sets.select(F.array_sort("items").alias("items"), F.size("items").alias("size"), F.col("freq").alias("cnt"))


def frequent_itemsets(
    view: DataFrame, min_support: float, max_len: int = 5, method: str = "levelwise", store: TableStore | None = None, weight: str | None = None
) -> Mined:
    """Mine a wide view (one STRING column per attribute). Methods: levelwise, cube, fpgrowth, bitmap.

    ``weight``: a column with the number of rows a tuple stands for (not for bitmap, whose
    rows are of so many attributes that few are equal: they are not grouped).
    """
    store = store or TableStore(view.sparkSession)
    if method == "bitmap":
        if weight:
            raise ValueError("bitmaps take rows, not weighted tuples")
        n_rows = view.count()
        least = max(1, min_count(min_support, n_rows))
        with split_methods(view.sparkSession):
            counts = store.write(element_counts(view).where(F.col("freq_cnt") >= least), "counts")
        elements = store.write(number_elements(counts, max(n_rows, 1)), "elements")
        sets = bitmap_itemsets(view, elements.orderBy("elem_id").collect(), least, max_len, store)
        return Mined(n_rows, elements, store.write(sets, "itemsets"))
    tuples = store.write(compress(view, weight), "tuples")
    n_rows = tuples.agg(F.sum("c")).first()[0] or 0
    least = max(1, min_count(min_support, n_rows))
    elements = store.write(build_elements(tuples, max(n_rows, 1), least, "c"), "elements")
    rows = store.write(_tuple_items(tuples, elements.collect()), "rows")
    if method == "levelwise":
        sets = _levelwise(rows, least, max_len, store)
    elif method == "cube":
        sets = _cube(rows, least, max_len)
    elif method == "fpgrowth":
        # rows without frequent elements still count
        sets = _fpgrowth(rows, least, max_len, max(rows.agg(F.sum("c")).first()[0] or 1, 1))
    else:
        raise ValueError(f"unknown method {method}")
    return Mined(n_rows, elements, store.write(sets, "itemsets"))


def generate_rules(mined: Mined, min_confidence: float = 0.0) -> DataFrame:
    """Every split of every itemset into two non-empty sides, with counts and measures."""
    sets = mined.itemsets
    splits = sets.where("size >= 2").select(
        "items", "size", "cnt", F.explode(F.expr("sequence(1, shiftleft(1, size) - 2)")).alias("mask")
    )
    side = lambda bit: F.filter("items", lambda x, i: F.getbit(F.col("mask"), i) == bit)
    split = splits.select("items", "size", "cnt", side(1).alias("lhs"), side(0).alias("rhs"))
    counts = lambda s: sets.select(F.col("items").alias(s), F.col("cnt").alias(f"{s}_cnt"))
    rules = split.join(counts("lhs"), "lhs").join(counts("rhs"), "rhs")
    numbers = [F.lit(x) for r in mined.elements.select("elem_id", "attr_id").collect() for x in (r[0], r[1])]
    attr_of = F.create_map(*numbers).cast("map<int,int>")
    rules = rules.withColumn("n_rows", F.lit(mined.n_rows).cast("bigint")).withColumn(
        "attrs", F.array_sort(F.transform("items", lambda i: attr_of[i]))
    )
    out = with_measures(rules).withColumn("rule_id", F.xxhash64("lhs", "rhs"))
    if min_confidence:
        out = out.where(F.col("confidence") >= min_confidence)
    return out.select(
        "rule_id", "lhs", "rhs", "items", "attrs", "size", "cnt", "lhs_cnt", "rhs_cnt", "n_rows", "support", "confidence", "lift"
    )


def with_measures(rules: DataFrame) -> DataFrame:
    return rules.withColumns({"support": support(), "confidence": confidence(), "lift": lift()})


def filter_lift(rules: DataFrame, min_lift: float) -> DataFrame:
    """Keep rules far from independence: lift, or its inverse below 1, at least ``min_lift``."""
    return rules.where(F.greatest(F.col("lift"), 1 / F.col("lift")) >= min_lift)


def with_score(rules: DataFrame, score: str | Column = "is") -> DataFrame:
    return rules.withColumn("score", score_column(score))


def top_rules(rules: DataFrame, m: int) -> DataFrame:
    """The m best rules by score; ties by their sides."""
    return rules.orderBy(F.desc(F.round("score", 9)), "lhs", "rhs").limit(m)


def validate_rules(rules: DataFrame) -> DataFrame:
    """Rules that break the model: an empty side, a shared element, or a repeated attribute."""
    bad = (
        (F.size("lhs") == 0)
        | (F.size("rhs") == 0)
        | (F.size(F.array_intersect("lhs", "rhs")) > 0)
        | (F.size(F.array_distinct("attrs")) < F.size("attrs"))
    )
    return rules.where(bad)


def score_bands(rules: DataFrame, n: int = 3) -> DataFrame:
    """Rules with ``band`` 0..n-1: equal-width bands of the score's range."""
    edges = rules.agg(F.min("score").alias("lo"), F.max("score").alias("hi")).first()
    lo, hi = edges["lo"], edges["hi"]
    if lo is None or lo == hi:
        return rules.withColumn("band", F.lit(0))
    cut = F.floor((F.col("score") - lo) * n / (hi - lo))
    return rules.withColumn("band", F.least(cut, F.lit(n - 1)).cast("int"))


def element_bands(banded: DataFrame, elements: DataFrame, n: int = 3) -> DataFrame:
    """Per element: its rules in each band, and their share of the band's rules."""
    sizes = {r["band"]: r["count"] for r in banded.groupBy("band").count().collect()}
    per = banded.select(F.explode("items").alias("elem_id"), "band").groupBy("elem_id").agg(
        *[F.count_if(F.col("band") == b).alias(f"band{b}") for b in range(n)]
    )
    out = elements.join(per, "elem_id", "left").na.fill(0, [f"band{b}" for b in range(n)])
    return out.withColumns({f"share{b}": F.col(f"band{b}") / F.lit(max(sizes.get(b, 0), 1)) for b in range(n)})
