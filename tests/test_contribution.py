"""Worked example, equivalence of the exact forms, invariants, counts."""

from math import comb

import pytest
from pyspark.sql import functions as F

from rulecredit.functions.weights import BITS, DIMENSIONS, directions, kernel_weights, shapley_weights
from rulecredit.operators import contribution as c
from rulecredit.operators.alternatives import i_top, influence
from rulecredit.operators.approx import ESTIMATORS, approximate
from rulecredit.plans.fixtures import example_elements, example_rules
from rulecredit.plans.workbench import bench

EXPECTED = {
    "printed": (-0.5333, 0.5333, 3.45, 3.45, 4.6667, 4.6667),
    "is_product": (-0.5332e-2, 0.5358e-2, 3.45e-2, 3.45e-2, 4.6628e-2, 4.6628e-2),
    "is": (-0.2889e-2, 0.2902e-2, 3.3911e-2, 3.3911e-2, 4.8081e-2, 4.8081e-2),
}


def by_id(df):
    return {r["elem_id"]: r["x"] for r in df.select("elem_id", "x").collect()}


@pytest.mark.parametrize("score", list(EXPECTED))
def test_example(spark, score):
    e, r = example_elements(spark), example_rules(spark, score)
    values = c.itemset_values(r)
    tol = 1e-4 if score == "printed" else 1e-6
    for form in (c.contribution_decomposed, c.contribution_multi, c.contribution_sequential):
        got = by_id(form(values, e))
        assert all(abs(got[i + 1] - x) < tol for i, x in enumerate(EXPECTED[score])), form
    naive = {i: by_id(c.contribution_naive(values, e, i))[i] for i in (1, 6)}
    assert abs(naive[1] - EXPECTED[score][0]) < tol and abs(naive[6] - EXPECTED[score][5]) < tol


def test_example_counts(spark):
    e, r = example_elements(spark), example_rules(spark)
    values = c.itemset_values(r)
    naive = {x["elem_id"]: int(x["naive"]) for x in c.count_naive(e).collect()}
    pruned = {x["elem_id"]: x["pruned"] for x in c.count_pruned(values, e).collect()}
    bound = {x["elem_id"]: x["bound"] for x in c.count_bound(r, e).collect()}
    assert [naive[i] for i in range(1, 7)] == [18, 18, 12, 12, 12, 12]
    assert [pruned[i] for i in range(1, 7)] == [7, 8, 4, 4, 4, 4]
    assert all(pruned[i] <= bound[i] for i in pruned)
    with pytest.raises(ValueError):
        c.valid_coalitions(e, 1, max_coalitions=5)


def test_example_alternatives(spark):
    e, r = example_elements(spark), example_rules(spark)
    assert set(by_id(i_top(r, e)).values()) == {105.0}
    assert set(by_id(influence(r, e)).values()) == {0.0}


def test_forms_agree(spark, small):
    b = bench(spark, small, "conversations")
    values = c.itemset_values(b.rules)
    ref = by_id(c.contribution_decomposed(values, b.scope))
    assert b.rules.count() == 846 and len(ref) == 13
    assert abs(sum(ref.values()) - 0.129210) < 1e-6
    multi = by_id(c.contribution_multi(values, b.scope))
    assert max(abs(ref[e] - multi[e]) for e in ref) < 1e-9
    for e in list(ref)[:2]:
        assert abs(by_id(c.contribution_naive(values, b.scope, e))[e] - ref[e]) < 1e-9
        assert abs(by_id(c.contribution_single(values, b.scope, e))[e] - ref[e]) < 1e-9


def test_sum_invariant(spark, small):
    b = bench(spark, small, "conversations")
    values = c.itemset_values(b.rules)
    n, top = c.shape(values, b.scope)
    w = shapley_weights(n, top)
    size = {r["attr_id"]: r["count"] for r in b.scope.groupBy("attr_id").count().collect()}
    want = 0.0
    for r in values.collect():
        outside = n - sum(size[a] for a in r["attrs"])
        want += r["value"] * (r["size"] * w[r["size"] - 1] - w[r["size"]] * outside)
    assert abs(sum(by_id(c.contribution_decomposed(values, b.scope)).values()) - want) < 1e-9


def test_scale_and_empty(spark):
    e, r = example_elements(spark), example_rules(spark)
    once = by_id(c.contribution(r, e))
    thrice = by_id(c.contribution(r.withColumn("score", F.col("score") * 3), e))
    assert all(abs(3 * once[i] - thrice[i]) < 1e-9 for i in once)
    none = c.itemset_values(r.limit(0))
    assert set(by_id(c.contribution_decomposed(none, e)).values()) == {0.0}


def test_restricted_elements(spark):
    e, r = example_elements(spark), example_rules(spark)
    got = by_id(c.contribution(r, e, within=e.where("elem_id <> 4")))
    same = by_id(c.contribution_multi(c.restrict(c.itemset_values(r), e.where("elem_id <> 4")), e.where("elem_id <> 4")))
    assert 4 not in got and all(abs(got[i] - same[i]) < 1e-9 for i in got)


def test_weights():
    assert abs(sum(comb(5, k) * x for k, x in enumerate(shapley_weights(6, 5))) - 1) < 1e-12
    assert shapley_weights(1, 3) == [1.0]
    assert kernel_weights(4, 4)[0] == kernel_weights(4, 4)[4] == 0.0


@pytest.mark.parametrize("method", ESTIMATORS)
def test_estimators(spark, small, method):
    b = bench(spark, small, "conversations")
    values = c.itemset_values(b.rules)
    ref = by_id(c.contribution_decomposed(values, b.scope))
    mean = by_id(approximate(values, b.scope, method, mode="expectation"))
    assert max(abs(ref[e] - mean[e]) for e in ref) < 1e-9
    est = by_id(approximate(values, b.scope, method, 8192, seed=3))
    assert max(abs(ref[e] - est[e]) for e in ref) < 0.25 * max(map(abs, ref.values()))


def test_full_budget_is_exact(spark, small):
    b = bench(spark, small, "conversations")
    values = c.itemset_values(b.rules)
    ref = by_id(c.contribution_decomposed(values, b.scope))
    est = by_id(approximate(values, b.scope, "stratified", 1 << 20))
    assert max(abs(ref[e] - est[e]) for e in ref) < 1e-9


def test_plan_has_no_cartesian(spark, small):
    b = bench(spark, small, "conversations")
    plan = c.contribution_decomposed(c.itemset_values(b.rules), b.scope)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_sobol_points_fill_every_dimension():
    """In each dimension the first 2 ** k points hit every interval of length 2 ** -k once."""
    for d in range(DIMENSIONS):
        v = directions(d)
        for k in (3, 6, 9):
            seen = set()
            for i in range(1 << k):
                x = 0
                for b in range(BITS):
                    x ^= v[b] if i >> b & 1 else 0
                seen.add(x >> (BITS - k))
            assert len(seen) == 1 << k, d


@pytest.mark.parametrize("method", ["monte_carlo", "antithetic", "sobol"])
def test_orders_are_unbiased(spark, method):
    """Six elements: many draws come near the mean over all 720 orders, which is the exact score."""
    e, r = example_elements(spark), example_rules(spark)
    values = c.itemset_values(r)
    ref = by_id(c.contribution_decomposed(values, e))
    est = by_id(approximate(values, e, method, 1 << 15, seed=5, frame="permutation"))
    assert max(abs(ref[i] - est[i]) for i in ref) < 0.5, (ref, est)


def test_sobol_orders_differ(spark):
    """Twelve elements: orders are no rotations of one cycle, and first places are even."""
    e = spark.range(12).selectExpr("cast(id as int) elem_id", "cast(id as int) attr_id", "'a' attr", "'v' val", "1L freq_cnt", "0D freq")
    one = spark.createDataFrame([([3, 7], [3, 7], 2, 1, 1.0)], "items array<int>, attrs array<int>, size int, n_rules long, value double")
    x = by_id(approximate(one, e, "sobol", 1 << 16, seed=2, frame="permutation"))
    ref = by_id(c.contribution_decomposed(one, e))
    assert max(abs(x[i] - ref[i]) for i in ref) < 0.2 * max(map(abs, ref.values()))


def test_ranks_in_buckets(spark, small, monkeypatch):
    """Numbers within a size are whole and unique however many buckets count them; quotas take the lowest hashes."""
    from rulecredit.operators import approx

    values = c.itemset_values(bench(spark, small, "conversations").rules)
    monkeypatch.setattr(approx, "BUCKET_ROWS", 10)
    rows = approx._positions(values).collect()
    sizes = {k: sorted(r["pos"] for r in rows if r["k"] == k) for k in {r["k"] for r in rows}}
    assert all(p == list(range(len(p))) for p in sizes.values()) and len(rows) > 50
    quota = {k: max(1, len(p) // 3) for k, p in sizes.items()}
    numbered = approx._positions(values).cache()
    got = {(r["k"], tuple(r["items"])) for r in approx._lowest(numbered, quota, 4).collect()}
    u = numbered.withColumn("u", approx.uniform(F.col("k"), F.col("pos"), 4)).collect()
    want = {(k, tuple(r["items"])) for k, q in quota.items() for r in sorted((r for r in u if r["k"] == k), key=lambda r: (r["u"], r["pos"]))[:q]}
    assert got == want


def test_worst_case_count():
    assert c.count_worst(1000, 5) == pytest.approx(15) and c.count_worst(0, 5) == 0.0
