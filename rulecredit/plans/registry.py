"""Queries of the engine and their SQL counterparts.

Outputs name elements as attr and val, or as text ``attr=val``; itemsets join their
elements by ``|``. Doubles are rounded to 6 digits.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.operators import contribution as c
from rulecredit.operators import evaluation as ev
from rulecredit.operators import metrics as mt
from rulecredit.operators import usecases as us
from rulecredit.operators.alternatives import i_top, influence
from rulecredit.operators.approx import ESTIMATORS, approximate, estimate_poisson
from rulecredit.operators.mining import element_frequencies, frequent_itemsets, score_bands, top_rules, with_score
from rulecredit.operators.prepare import Bins, discretize, sample_rows
from rulecredit.plans import oracles as sql
from rulecredit.plans.fixtures import measured_elements, measured_rules
from rulecredit.plans.workbench import SETTINGS, Bench, Setting, bench, forget, grid
from rulecredit.sources.store import TableStore
from rulecredit.sources.tables import table
from rulecredit.sources.views import RAW, VIEWS
from rulecredit.streaming.windows import contribution_by_window, session, sliding, tumbling, update_statistics, windowed_tuples

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
FLAGSHIP = "conversations"


def add(name: str, query: Query, oracle: str | None = None) -> None:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        forget()
        return query(spark, folder)

    QUERIES[name] = run
    if oracle is not None:
        ORACLES[name] = oracle


def rounded(e: Column | str) -> Column:
    return F.round(e, 6) + F.lit(0.0)


def _names(elements: DataFrame) -> Column:
    """A literal map from element id to ``attr=val``; elements are few."""
    rows = elements.select("elem_id", F.concat("attr", F.lit("="), "val").alias("e")).collect()
    return F.create_map(*[F.lit(x) for r in rows for x in (r[0], r[1])]) if rows else F.create_map().cast("map<int,string>")


def _text(items: str, names: Column) -> Column:
    return F.array_join(F.transform(items, lambda i: names[i]), "|")


def _x(scores: DataFrame, elements: DataFrame) -> DataFrame:
    """attr, val, x of (elem_id, x)."""
    return scores.select("elem_id", "x").join(F.broadcast(elements.select("elem_id", "attr", "val")), "elem_id").select("attr", "val", rounded("x").alias("x"))


def _bench(view: str = FLAGSHIP, setting: Setting | None = None) -> Callable[[SparkSession, str], Bench]:
    return lambda spark, folder: bench(spark, folder, view, setting)


def _values(b: Bench, agg: str = "max") -> DataFrame:
    return c.itemset_values(b.rules, agg)


# --- elements, itemsets, rules

for _v in ("conversations", "documents", "pages"):
    add(f"elements_{_v}", lambda s, d, v=_v: element_frequencies(VIEWS[v](s, d)), sql.elements_sql(_v))


def _itemsets(view: str, setting: Setting | None = None) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view, setting)
        return b.itemsets.select(_text("items", _names(b.elements)).alias("items"), "size", "cnt")

    return run


for _v in ("conversations", "documents", "events", "star"):
    add(f"itemsets_{_v}", _itemsets(_v), sql.itemsets_sql(_v))
for _m in ("levelwise", "fpgrowth"):
    add(f"itemsets_{_m}_conversations", _itemsets("conversations", Setting(0.05, 5, _m)), sql.itemsets_sql("conversations"))


def _rules(view: str, score: str = "is") -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        names = _names(b.elements)
        return with_score(b.rules, score).select(
            _text("lhs", names).alias("lhs"),
            _text("rhs", names).alias("rhs"),
            "cnt",
            "lhs_cnt",
            "rhs_cnt",
            *[rounded(m).alias(m) for m in ("support", "confidence", "lift", "score")],
        )

    return run


for _v in ("conversations", "documents"):
    add(f"rules_{_v}", _rules(_v), sql.rules_sql(_v))
for _s in ("is_product", "confidence", "lift", "support"):
    add(f"rules_score_{_s}", _rules(FLAGSHIP, _s), sql.rules_sql(FLAGSHIP, _s))


def _itemset_values(agg: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, FLAGSHIP)
        return _values(b, agg).select(_text("items", _names(b.elements)).alias("items"), "n_rules", rounded("value").alias("value"))

    return run


for _a in ("max", "sum", "top2", "top3", "avg"):
    add(f"itemset_values_{_a}", _itemset_values(_a), sql.values_sql(FLAGSHIP, _a))

# --- exact contribution


def _contribution(view: str, agg: str = "max", score: str = "is", predicate: str | None = None, method: str = "decomposed") -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        rules = with_score(b.rules, score) if score != "is" else b.rules
        rules = rules.where(predicate) if predicate else rules
        return _x(c.contribution(rules, b.elements, agg, method), b.elements)

    return run


#: Label and all 64 components: SQL over every subset of a row is too slow, so there is none.
WIDE = "embeddings_wide"
for _v in SETTINGS:
    add(f"contribution_{_v}", _contribution(_v), sql.contribution_sql(_v) if _v != WIDE else None)
for _a in ("sum", "top2", "top3", "avg"):
    add(f"contribution_agg_{_a}", _contribution(FLAGSHIP, _a), sql.contribution_sql(FLAGSHIP, agg=_a))
for _s in ("is_product", "confidence", "lift"):
    add(f"contribution_score_{_s}", _contribution(FLAGSHIP, score=_s), sql.contribution_sql(FLAGSHIP, score=_s))
for _m in ("multi", "sequential"):
    add(f"contribution_{_m}", _contribution(FLAGSHIP, method=_m), sql.contribution_sql(FLAGSHIP, "decomposed"))
add("contribution_context", _contribution(FLAGSHIP, predicate="lift >= 1"), sql.contribution_sql(FLAGSHIP, keep="lift >= 1"))


def _one(form: Callable[[DataFrame, DataFrame, int], DataFrame]) -> Query:
    """The element role=user alone."""

    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, FLAGSHIP)
        e = b.scope.where("attr = 'role' and val = 'user'").first()["elem_id"]
        return _x(form(_values(b), b.scope, e), b.elements)

    return run


_USER = " WHERE e = 'role=user'"
add("contribution_single", _one(c.contribution_single), sql.contribution_sql(FLAGSHIP, "decomposed") + _USER)


def _naive(spark: SparkSession, folder: str) -> DataFrame:
    """Every element of the scope over all its valid coalitions."""
    b = bench(spark, folder, FLAGSHIP)
    values = _values(b)
    ids = [r["elem_id"] for r in b.scope.select("elem_id").orderBy("elem_id").collect()]
    none = b.scope.select("elem_id", F.lit(0.0).alias("x")).limit(0)
    return _x(reduce(DataFrame.unionByName, [c.contribution_naive(values, b.scope, e) for e in ids] or [none]), b.elements)


add("contribution_naive", _naive, sql.contribution_sql(FLAGSHIP, "decomposed"))


def _example(score: str, method: str) -> Query:
    """The worked example's rule set as measured on the conversations view."""

    def run(spark: SparkSession, folder: str) -> DataFrame:
        elements, rules = measured_elements(spark), measured_rules(VIEWS[FLAGSHIP](spark, folder), score)
        values = c.itemset_values(rules)
        scope = c.rule_elements(values, elements)
        if method == "naive":
            ids = [r["elem_id"] for r in scope.select("elem_id").orderBy("elem_id").collect()]
            none = scope.select("elem_id", F.lit(0.0).alias("x")).limit(0)
            return _x(reduce(DataFrame.unionByName, [c.contribution_naive(values, scope, e) for e in ids] or [none]), elements)
        return _x(c.METHODS[method](values, scope), elements)

    return run


for _s in ("printed", "is_product", "is"):
    add(f"contribution_example_{_s}", _example(_s, "decomposed"), sql.example_sql(_s))
add("contribution_naive_example", _example("printed", "naive"), sql.example_sql("printed"))


def _statistics(spark: SparkSession, folder: str) -> DataFrame:
    """Incremental: statistics of two halves of the itemsets, merged, give the whole's scores."""
    b = bench(spark, folder, FLAGSHIP)
    values = _values(b)
    half = F.pmod(F.xxhash64("items"), F.lit(2)) == 0
    merged = c.merge_statistics(c.statistics(values.where(half)), c.statistics(values.where(~half)))
    return _x(c.combine(b.scope, merged, *c.shape(values, b.scope)), b.elements)


add("contribution_incremental", _statistics, sql.contribution_sql(FLAGSHIP))

# --- coalition counts


def _count(kind: str, view: str = FLAGSHIP) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        if kind == "naive":
            rows = c.count_naive(b.scope).select("elem_id", F.col("naive").cast("bigint").alias("naive"))
        elif kind == "naive_log10":
            rows = c.count_naive(b.scope).select("elem_id", rounded("log10_naive").alias("log10_naive"))
        elif kind == "pruned":
            rows = c.count_pruned(_values(b), b.scope).select("elem_id", "pruned")
        else:
            rows = c.count_bound(b.rules, b.scope)
        return rows.join(F.broadcast(b.scope.select("elem_id", "attr", "val")), "elem_id").drop("elem_id")

    return run


add("coalitions_naive", _count("naive"), sql.naive_count_sql(FLAGSHIP))
add("coalitions_naive_embeddings", _count("naive", "embeddings"), sql.naive_count_sql("embeddings"))
add("coalitions_pruned", _count("pruned"), sql.pruned_count_sql(FLAGSHIP))
add("coalitions_pruned_embeddings", _count("pruned", "embeddings"), sql.pruned_count_sql("embeddings"))
add(f"coalitions_naive_{WIDE}", _count("naive_log10", WIDE))
add(f"coalitions_pruned_{WIDE}", _count("pruned", WIDE))
add("coalition_bound", _count("bound"), sql.bound_sql(FLAGSHIP))


def _worst(view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        df = VIEWS[view](spark, folder)
        n, width = df.count(), len(df.columns)
        row = (n, width, c.count_worst(n, width))
        out = spark.createDataFrame([row], "n_rows long, n_attributes int, log10_worst double")
        return out.withColumn("log10_worst", rounded("log10_worst"))

    return run


for _v in ("conversations", "documents", "events", "pages", "embeddings", "star"):
    add(f"coalitions_worst_{_v}", _worst(_v), sql.worst_case_sql(_v))


def _speedup(spark: SparkSession, folder: str) -> DataFrame:
    b = bench(spark, folder, FLAGSHIP)
    n, tau = c.shape(_values(b), b.scope)
    return spark.range(1).select(
        F.lit(n).cast("bigint").alias("n_elements"), F.lit(tau).cast("int").alias("tau"), rounded(F.lit(c.speedup_bound(n, tau))).alias("speedup")
    )


add("speedup_bound", _speedup, sql.speedup_sql(FLAGSHIP))

# --- alternatives

add("i_top", lambda s, d: _x(i_top(_bench()(s, d).rules, _bench()(s, d).scope), _bench()(s, d).elements), sql.i_top_sql(FLAGSHIP))
for _a in ("max", "sum", "top2", "top3", "avg"):
    add(
        f"influence_{_a}",
        lambda s, d, a=_a: _x(influence(_bench()(s, d).rules, _bench()(s, d).scope, a), _bench()(s, d).elements),
        sql.influence_sql(FLAGSHIP, _a),
    )

# --- use cases


def _scores(b: Bench) -> DataFrame:
    return c.contribution_decomposed(_values(b), b.scope)


def _nx(b: Bench) -> DataFrame:
    return us.normalized(_scores(b))


def _importance(view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        out = us.element_importance(_scores(b), score_bands(b.rules))
        return out.select(
            "attr", "val", rounded("x").alias("x"), "freq_cnt", *[f"band{i}" for i in range(3)], *[rounded(f"share{i}").alias(f"share{i}") for i in range(3)]
        )

    return run


def _is_bands(view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        return score_bands(bench(spark, folder, view).rules).groupBy("band").agg(
            F.count("*").alias("n_rules"), rounded(F.min("score")).alias("lo"), rounded(F.max("score")).alias("hi")
        )

    return run


def _normalized(view: str) -> Query:
    return lambda spark, folder: _nx(bench(spark, folder, view)).select("attr", "val", "rank_x", "rank_freq", rounded("nx").alias("nx"))


def _scored_rules(b: Bench) -> DataFrame:
    return us.rule_importance(b.rules, _nx(b))


def _rule_importance(view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        names = _names(b.elements)
        return _scored_rules(b).select(
            _text("lhs", names).alias("lhs"), _text("rhs", names).alias("rhs"), rounded("rx").alias("rx"), names[F.col("weakest_elem")].alias("weakest")
        )

    return run


REDUNDANT = 0.21


def _redundant_filter(view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        _, report = us.filter_redundant(_scored_rules(bench(spark, folder, view)), REDUNDANT)
        return report.select("removed", "kept", rounded("removed_share").alias("removed_share"))

    return run


def _redundant_pairs(view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        names = _names(b.elements)
        return us.redundant_pairs(_scored_rules(b), 0.05).select(
            _text("lhs", names).alias("long_lhs"),
            _text("rhs", names).alias("long_rhs"),
            names[F.col("weakest_elem")].alias("weakest"),
            rounded("long_score").alias("long_score"),
            rounded("short_score").alias("short_score"),
        )

    return run


def _attribute_importance(view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        return us.attribute_importance(_nx(b), b.rules).select("attr", rounded("ax").alias("ax"), "n_elems")

    return run


def _attribute_profile(view: str) -> Query:
    return lambda spark, folder: us.attribute_profile(_nx(bench(spark, folder, view))).select("attr", "val", rounded("nx").alias("nx"), rounded("share").alias("share"))


# the case study: both views whose rules carry real associations
for _v, _end in ((FLAGSHIP, ""), ("documents", "_documents")):
    add(f"element_importance{_end}", _importance(_v), sql.importance_sql(_v))
    add(f"is_bands{_end}", _is_bands(_v), sql.is_bands_sql(_v))
    add(f"normalized{_end}", _normalized(_v), sql.normalized_sql(_v))
    add(f"rule_importance{_end}", _rule_importance(_v), sql.rule_importance_sql(_v))
    add(f"redundant_filter{_end}", _redundant_filter(_v), sql.redundant_filter_sql(_v, REDUNDANT))
    add(f"redundant_pairs{_end}", _redundant_pairs(_v), sql.redundant_pairs_sql(_v, 0.05))
    add(f"attribute_importance{_end}", _attribute_importance(_v), sql.attribute_importance_sql(_v))
    add(f"attribute_profile{_end}", _attribute_profile(_v), sql.attribute_profile_sql(_v))


def _top_rules(spark: SparkSession, folder: str) -> DataFrame:
    b = bench(spark, folder, FLAGSHIP)
    names = _names(b.elements)
    return top_rules(b.rules, 20).select(_text("lhs", names).alias("lhs"), _text("rhs", names).alias("rhs"), rounded("score").alias("score"))


DROP_BELOW, NEAR_ZERO = 0.75, 0.002


def _drop_attributes(spark: SparkSession, folder: str) -> DataFrame:
    """The view mined again without its low-scoring attributes."""
    b = bench(spark, folder, FLAGSHIP)
    ax = us.attribute_importance(_nx(b), b.rules)
    setting = SETTINGS[FLAGSHIP]
    mined = frequent_itemsets(us.drop_attributes(VIEWS[FLAGSHIP](spark, folder), ax, DROP_BELOW), setting.min_support, setting.max_len, "levelwise")
    return mined.itemsets.select(_text("items", _names(mined.elements)).alias("items"), "size", "cnt")


def _drop_elements(spark: SparkSession, folder: str) -> DataFrame:
    b = bench(spark, folder, FLAGSHIP)
    names = _names(b.elements)
    left = us.drop_elements(b.rules, _scores(b), NEAR_ZERO)
    return left.select(_text("lhs", names).alias("lhs"), _text("rhs", names).alias("rhs"))


def _within(condition: str) -> Query:
    """Scores within a part of the frequent elements, met in a rule or not."""

    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, FLAGSHIP)
        return _x(c.contribution(b.rules, b.elements, within=b.elements.where(condition)), b.elements)

    return run


def _interaction(spark: SparkSession, folder: str) -> DataFrame:
    b = bench(spark, folder, FLAGSHIP)
    e = b.elements.where("attr = 'role' and val = 'user'").first()["elem_id"]
    return us.interaction(b.rules, b.elements, e, "len").select("given", rounded("x").alias("x"))


GROUP = ["role=user", "len=l"]


def _subset(spark: SparkSession, folder: str) -> DataFrame:
    b = bench(spark, folder, FLAGSHIP)
    ids = [r["elem_id"] for r in b.scope.where(F.concat("attr", F.lit("="), "val").isin(GROUP)).collect()]
    summed = us.subset_importance(_scores(b), ids).select(rounded("x").alias("summed"))
    return summed.crossJoin(us.union_importance(_values(b), b.scope, ids).select(rounded("x").alias("as_one")))  # one row each


def _score_correlation(spark: SparkSession, folder: str) -> DataFrame:
    return us.score_correlation(_scores(bench(spark, folder, FLAGSHIP))).select(rounded("corr").alias("corr"))


def _score_error(spark: SparkSession, folder: str) -> DataFrame:
    b = bench(spark, folder, FLAGSHIP)
    out = mt.score_error(_scores(b), influence(b.rules, b.scope, "sum"))
    return out.select(*[rounded(n).alias(n) for n in out.columns])


add("top_rules", _top_rules, sql.top_rules_sql(FLAGSHIP, 20))
add("drop_attributes", _drop_attributes, sql.drop_attributes_sql(FLAGSHIP, DROP_BELOW))
add("drop_elements", _drop_elements, sql.drop_elements_sql(FLAGSHIP, NEAR_ZERO))
add("contribution_restricted", _within("attr in ('role', 'len', 'nl')"), sql.restricted_sql(FLAGSHIP, "split_part(e, '=', 1) IN ('role', 'len', 'nl')", "pruned"))
add("contribution_all_elements", _within("true"), sql.restricted_sql(FLAGSHIP, "TRUE", "pruned"))
add("interaction", _interaction, sql.interaction_sql(FLAGSHIP, "role=user", "len"))
add("subset_importance", _subset, sql.subset_sql(FLAGSHIP, GROUP))
add("score_correlation", _score_correlation, sql.score_correlation_sql(FLAGSHIP))
add("score_error", _score_error, sql.score_error_sql(FLAGSHIP))

# --- estimators


def _approx(method: str, n_samples: int = 4096, view: str = FLAGSHIP, **kw) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        return _x(approximate(_values(b), b.scope, method, n_samples, 7, **kw), b.elements)

    return run


#: How far an estimate may be off, as a share of the largest exact score.
NEAR = 0.1


def _near(method: str | None, n_samples: int, **kw) -> Query:
    """Exact scores, and whether the estimate (no method: Poisson) from many draws is near."""

    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, FLAGSHIP)
        values = _values(b)
        est = approximate(values, b.scope, method, n_samples, 7, **kw) if method else estimate_poisson(values, b.scope, n_samples, 7)
        exact = _scores(b).select("elem_id", F.col("x").alias("exact"))
        both = est.select("elem_id", "x").join(exact, "elem_id").crossJoin(exact.agg(F.max(F.abs("exact")).alias("most")))  # one row
        both = both.select("elem_id", F.col("exact").alias("x"), (F.abs(F.col("x") - F.col("exact")) <= NEAR * F.col("most")).alias("near"))
        named = both.join(F.broadcast(b.elements.select("elem_id", "attr", "val")), "elem_id")
        return named.select("attr", "val", rounded("x").alias("x"), "near")

    return run


for _m in ESTIMATORS:
    add(f"approx_{_m}", _approx(_m))
    add(f"approx_{_m}_expect", _approx(_m, mode="expectation"), sql.contribution_sql(FLAGSHIP, "decomposed"))
add("approx_stratified_full", _approx("stratified", 1 << 20), sql.contribution_sql(FLAGSHIP))
for _m in ("monte_carlo", "antithetic", "sobol"):
    add(f"approx_permutation_{_m}", _approx(_m, frame="permutation"))
for _m in ("monte_carlo", "antithetic", "sobol"):
    add(f"approx_near_permutation_{_m}", _near(_m, 1 << 16, frame="permutation"), sql.near_sql(FLAGSHIP))
for _m in ESTIMATORS:
    add(f"approx_near_{_m}", _near(_m, 1 << 16), sql.near_sql(FLAGSHIP))
add("approx_near_poisson", _near(None, 1 << 16), sql.near_sql(FLAGSHIP))
add("approx_poisson", lambda s, d: _x(estimate_poisson(_values(_bench()(s, d)), _bench()(s, d).scope, 4096, 7), _bench()(s, d).elements))

# --- accuracy and experiments


def _quality(what: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, FLAGSHIP)
        ref, est = _scores(b), influence(b.rules, b.scope, "sum")
        if what == "p_at_10":
            return mt.precision_at(ref, est).select(rounded("p").alias("p"))
        if what == "ap_at_10":
            return mt.average_precision_at(ref, est).select(rounded("ap").alias("ap"))
        other = est if what == "spearman_influence" else i_top(b.rules, b.scope)
        return mt.spearman(ref, other).select(rounded("rho").alias("rho"))

    return run


for _q in ("p_at_10", "ap_at_10", "spearman_influence", "spearman_itop"):
    add(_q, _quality(_q), sql.quality_sql(FLAGSHIP, _q))


def _table(report: Callable[[DataFrame, DataFrame], DataFrame], view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        b = bench(spark, folder, view)
        out = report(b.rules, b.elements)
        return out.select(*[rounded(n).alias(n) if t == "double" else F.col(n) for n, t in out.dtypes])

    return run


def _rounded_doubles(out: DataFrame) -> DataFrame:
    return out.select(*[rounded(n).alias(n) if t == "double" else F.col(n) for n, t in out.dtypes])


for _v in ("conversations", "documents", "embeddings", WIDE):
    add(f"approximation_table_{_v}", _table(ev.approximation_table, _v))
for _v in SETTINGS:
    add(f"robustness_{_v}", _table(ev.robustness, _v), sql.robustness_sql(_v) if _v != WIDE else None)


def _properties(view: str) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        out = ev.rule_set_properties(bench(spark, folder, view).rules, view)
        return out.select("run_id", "n_rules", rounded("avg_length").alias("avg_length"), "max_length", "n_elements")

    return run


for _v in SETTINGS:
    add(f"rule_set_properties_{_v}", _properties(_v), sql.properties_sql(_v) if _v != WIDE else None)

# the evaluation set: six workloads, all knobs, every instance a key
_INSTANCES = ev.build_instances()
#: The largest number of attributes of a workload.
TOP = max(len(r.numeric) + len(r.plain) for r in RAW.values())


def _grid(report: Callable[[DataFrame, TableStore], DataFrame]) -> Query:
    return lambda spark, folder: _rounded_doubles(report(grid(spark, folder), TableStore(spark, "experiment")))


add("evaluation_properties", _grid(lambda r, _: ev.properties_by_view(ev.grid_properties(r))), sql.grid_properties_sql(_INSTANCES))
for _by in ("view", *ev.BANDS):
    add(f"evaluation_coalitions_by_{_by}", _grid(lambda r, _, by=_by: ev.grid_coalitions(r, by)), sql.grid_coalitions_sql(_INSTANCES, _by))
add("evaluation_robustness", _grid(lambda r, s: ev.grid_robustness(r, TOP, s)), sql.grid_robustness_sql(_INSTANCES))
add("evaluation_alternatives", _grid(lambda r, s: ev.grid_alternatives(r, TOP, s)), sql.grid_alternatives_sql(_INSTANCES))
add("evaluation_approximations", _grid(lambda r, s: ev.grid_approximations(r, TOP, s)))

# --- preparation


def _bins(name: str, column: str, how: Bins, labels: str = "index") -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        out = discretize(table(spark, folder, name).select(column), {column: how}, labels=labels)
        return out.groupBy(F.col(column).alias("bin")).agg(F.count("*").alias("n"))

    return run


add("sample_orders", lambda s, d: sample_rows(table(s, d, "orders"), 500, key=["o_orderkey"]).select("o_orderkey"), sql.sample_sql("orders", "o_orderkey", 500))
add("bins_equal_width", _bins("part", "p_retailprice", Bins.equal_width(5)), sql.equal_width_sql("part", "p_retailprice", 5))
add("bins_equal_depth", _bins("orders", "o_totalprice", Bins.equal_depth(5, exact=True)), sql.equal_depth_sql("orders", "o_totalprice", 5))
add("bins_top_values", _bins("documents", "source", Bins.top_k(5)), sql.top_values_sql("documents", "source", 5))
add("bins_date_part", _bins("orders", "o_orderdate", Bins.part("year")), "SELECT year(o_orderdate)::VARCHAR AS bin, count(*) AS n FROM orders GROUP BY 1")
add(
    "bins_given_cuts",
    _bins("events", "value", Bins.cuts(20, 50)),
    "SELECT ((value >= 20)::INT + (value >= 50)::INT)::VARCHAR AS bin, count(*) AS n FROM events GROUP BY 1",
)

# --- windows

WINDOW_DAYS = 7
WINDOW_SETTING = Setting(0.05, 3, "cube")


def _window_counts(spark: SparkSession, folder: str) -> DataFrame:
    out = windowed_tuples(table(spark, folder, "events"), tumbling(f"{WINDOW_DAYS} days"))
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("start"), *EVENT_NAMES, "c")


EVENT_NAMES = ("et", "h", "dow", "v", "u", "k")
SLIDE_DAYS, GAP_HOURS = 1, 12


def _sliding_counts(spark: SparkSession, folder: str) -> DataFrame:
    out = windowed_tuples(table(spark, folder, "events"), sliding(f"{WINDOW_DAYS} days", f"{SLIDE_DAYS} days"))
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("start"), *EVENT_NAMES, "c")


def _session_counts(spark: SparkSession, folder: str) -> DataFrame:
    out = windowed_tuples(table(spark, folder, "events"), session(f"{GAP_HOURS} hours"))
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), *EVENT_NAMES, "c")


def _after_changes(spark: SparkSession, folder: str) -> DataFrame:
    """Statistics of IS values, then every itemset's value revised to its lift's: the scores by lift."""
    b = bench(spark, folder, FLAGSHIP)
    old, new = _values(b), c.itemset_values(with_score(b.rules, "lift"))
    held = update_statistics(c.statistics(old), c.statistics(old), c.statistics(new))
    return _x(c.combine(b.scope, held, *c.shape(new, b.scope)), b.elements)


def _window_contribution(spark: SparkSession, folder: str) -> DataFrame:
    tuples = windowed_tuples(table(spark, folder, "events"), tumbling(f"{WINDOW_DAYS} days"))
    scores = contribution_by_window(tuples, WINDOW_SETTING.min_support, WINDOW_SETTING.max_len, WINDOW_SETTING.min_lift)
    return scores.select(F.date_format("start", "yyyy-MM-dd").alias("window_start"), "attr", "val", rounded("x").alias("x"))


add("stream_window_counts", _window_counts, sql.window_counts_sql(WINDOW_DAYS))
add("windowed_contribution_events", _window_contribution, sql.windows_contribution_sql(WINDOW_DAYS, WINDOW_SETTING))
add("stream_sliding_counts", _sliding_counts, sql.sliding_sql(WINDOW_DAYS, SLIDE_DAYS))
add("stream_session_counts", _session_counts, sql.session_sql(GAP_HOURS))
add("contribution_after_changes", _after_changes, sql.contribution_sql(FLAGSHIP, score="lift"))
