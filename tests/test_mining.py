"""Views, binning, mining, rules, metrics, use cases, windows."""

from itertools import combinations
from math import factorial

import pytest
from pyspark.sql import functions as F

from rulecredit.operators import bitmaps
from rulecredit.operators import metrics as mt
from rulecredit.operators import usecases as us
from rulecredit.operators.contribution import combine, contribution, contribution_decomposed, itemset_values, shape
from rulecredit.operators.mining import (
    build_elements,
    filter_lift,
    frequent_itemsets,
    generate_rules,
    min_count,
    score_bands,
    top_rules,
    validate_rules,
    with_score,
)
from rulecredit.operators.prepare import Bins, discretize, sample_rows
from rulecredit.plans.fixtures import example_elements, example_rules
from rulecredit.plans.workbench import bench
from rulecredit.sources.tables import read_rules, render_rule, table
from rulecredit.sources.views import VIEWS
from rulecredit.streaming.windows import CHANGES, held_statistics, maintain_statistics, read_events, score_closed_windows, tumbling, windowed_tuples


def sets(mined):
    return {(tuple(r["items"]), r["cnt"]) for r in mined.itemsets.collect()}


def test_miners_agree(spark, small):
    view = VIEWS["conversations"](spark, small)
    level, cube, fp = (sets(frequent_itemsets(view, 0.05, 4, m)) for m in ("levelwise", "cube", "fpgrowth"))
    assert level == cube == fp and level


@pytest.mark.parametrize("view,support,most", [("conversations", 0.05, 4), ("documents", 0.05, 8), ("pages", 0.1, 3)])
def test_bitmaps_find_the_same_itemsets(spark, small, view, support, most, monkeypatch):
    """Over chunks smaller than a batch, null cells and elements handed on early too."""
    monkeypatch.setattr(bitmaps, "CHUNK_ROWS", 24)
    monkeypatch.setattr(bitmaps, "COUNTED", 3)
    rows = VIEWS[view](spark, small)
    level, bits = (frequent_itemsets(rows, support, most, m) for m in ("levelwise", "bitmap"))
    assert sets(level) == sets(bits) and sets(bits)
    assert sorted(level.elements.collect()) == sorted(bits.elements.collect()) and level.n_rows == bits.n_rows


def test_bitmaps_of_nothing(spark, small):
    none = frequent_itemsets(VIEWS["conversations"](spark, small).where("false"), 0.05, 4, "bitmap")
    assert none.n_rows == none.itemsets.count() == none.elements.count() == 0


def test_support_is_antimonotone(spark, small):
    counts = dict(sets(frequent_itemsets(VIEWS["pages"](spark, small), 0.1, 3, "cube")))
    for items, n in counts.items():
        for i in range(len(items)):
            rest = items[:i] + items[i + 1 :]
            assert not rest or counts[rest] >= n


def test_min_count():
    assert min_count(0.05, 100) == 5 and min_count(0.05, 101) == 6 and min_count(0.1, 30) == 3


def test_rules(spark, small):
    mined = frequent_itemsets(VIEWS["conversations"](spark, small), 0.05, 3, "cube")
    rules = with_score(generate_rules(mined)).cache()
    assert validate_rules(rules).count() == 0
    pairs = rules.alias("a").join(rules.alias("b"), (F.col("a.lhs") == F.col("b.rhs")) & (F.col("a.rhs") == F.col("b.lhs")))
    assert pairs.where(F.abs(F.col("a.lift") - F.col("b.lift")) > 1e-12).count() == 0
    assert filter_lift(rules, 1.05).where("lift > 0.953 and lift < 1.049").count() == 0
    assert top_rules(rules, 4).count() == 4
    assert score_bands(rules).select("band").distinct().count() <= 3


def test_nulls_give_no_element(spark):
    view = spark.createDataFrame([("a", None), ("a", "x"), (None, None)], "p string, q string")
    rows = build_elements(view, 3).collect()
    assert {(r["attr"], r["val"], r["freq_cnt"]) for r in rows} == {("p", "a", 2), ("q", "x", 1)}
    mined = frequent_itemsets(view, 0.3, 2)
    assert sets(mined) == {((0,), 2), ((1,), 1), ((0, 1), 1)}


def test_empty_view(spark):
    view = spark.createDataFrame([], "p string, q string")
    mined = frequent_itemsets(view, 0.1, 3)
    assert mined.n_rows == 0 and mined.itemsets.count() == 0


def test_bins(spark):
    df = spark.createDataFrame([(float(i), str(i % 7)) for i in range(100)] + [(None, None)], "n double, s string")
    spec = {"n": Bins.equal_width(4), "s": Bins.top_k(2)}
    rows = discretize(df, spec).groupBy("n").count().collect()
    assert len(rows) == 5
    assert discretize(df, {"n": Bins.equal_depth(4, exact=True)}).where("n is not null").groupBy("n").count().agg(F.max("count")).first()[0] <= 26
    assert {r[0] for r in discretize(df, spec).select("s").distinct().collect()} == {"0", "1", "other", None}
    assert discretize(df, {"n": Bins.cuts(50)}, nulls="element").where("n = '∅'").count() == 1
    with pytest.raises(ValueError):
        discretize(df, {"n": Bins.keep()}, max_distinct=10)
    assert sample_rows(df, 5, 1).count() == 5
    assert sample_rows(df, 5, 1).collect() == sample_rows(df.repartition(3), 5, 1).collect()


def scores(spark, xs):
    return spark.createDataFrame(list(enumerate(xs)), "elem_id int, x double")


def test_metrics(spark):
    a = scores(spark, [5.0, 4.0, 3.0, 2.0, 1.0])
    b = scores(spark, [1.0, 2.0, 3.0, 4.0, 5.0])
    assert mt.spearman(a, a).first()[0] == pytest.approx(1)
    assert mt.spearman(a, b).first()[0] == pytest.approx(-1)
    assert mt.precision_at(a, b, 2).first()[0] == 0
    assert mt.precision_at(a, a, 5).first()[0] == 1
    assert mt.average_precision_at(a, a, 5).first()[0] == pytest.approx(1)
    both = mt.quality_by(a, b.withColumn("m", F.lit("b")).unionByName(a.withColumn("m", F.lit("a"))), "m", 5)
    got = {r["m"]: r for r in both.collect()}
    assert got["a"]["ap"] == pytest.approx(1) and got["b"]["rho"] == pytest.approx(-1)


def test_use_cases(spark, small):
    b = bench(spark, small, "conversations")
    nx = us.normalized(contribution(b.rules, b.elements)).cache()
    n = nx.count()
    assert nx.where((F.col("nx") < 1 / n) | (F.col("nx") > n)).count() == 0
    scored = us.rule_importance(b.rules, nx)
    kept, report = us.filter_redundant(scored, 0.5)
    r = report.first()
    assert r["removed"] + r["kept"] == b.rules.count() and kept.count() == r["kept"]
    ax = us.attribute_importance(nx, b.rules)
    assert ax.agg(F.sum("n_elems")).first()[0] == n
    assert us.drop_elements(b.rules, nx, 1e9).count() == 0
    assert us.subset_importance(nx, [0, 1]).first()["n_elems"] == 2
    assert -1 <= us.score_correlation(nx).first()[0] <= 1


def test_rule_files(spark, tmp_path):
    rows = [(["a=1", "b=2"], ["c=3"], 0.5, 0.9, 1.2)]
    df = spark.createDataFrame(rows, "lhs array<string>, rhs array<string>, support double, confidence double, lift double")
    df.write.json(str(tmp_path / "j"))
    back = read_rules(spark, str(tmp_path / "j"))
    assert back.select(render_rule()).first()[0] == "(a, 1), (b, 2) -> (c, 3)"


def test_stream_equals_batch(spark, small, tmp_path):
    events = table(spark, small, "events")
    folder = str(tmp_path / "in")
    events.repartition(1).sortWithinPartitions("ts").write.parquet(folder)
    out = windowed_tuples(read_events(spark, folder), tumbling("7 days"))
    q = out.writeStream.format("memory").queryName("win").outputMode("complete").start()
    q.processAllAvailable()
    q.stop()
    batch = windowed_tuples(events, tumbling("7 days"))
    assert sorted(map(str, spark.table("win").collect())) == sorted(map(str, batch.collect()))


def test_closed_windows_are_scored(spark, small, tmp_path):
    batch = windowed_tuples(table(spark, small, "events"), tumbling("15 days"))
    handle = score_closed_windows(str(tmp_path / "out"))
    handle(batch, 0)
    first = spark.read.parquet(str(tmp_path / "out")).count()
    handle(batch, 0)  # a replay overwrites
    assert first > 0 and spark.read.parquet(str(tmp_path / "out")).count() == first


def test_late_rows_are_dropped(spark, tmp_path):
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    row = lambda i, t: (i, t, 1, "view", 1.0, '{"k": 1}')
    import datetime as dt

    day = lambda d: dt.datetime(2024, 1, d, tzinfo=dt.UTC)
    folder = tmp_path / "late"
    for k, rows in enumerate([[row(1, day(1)), row(2, day(20))], [row(3, day(19))], [row(4, day(1))], [row(5, day(29))]]):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(folder))
        q = (
            windowed_tuples(read_events(spark, str(folder)), tumbling("1 day"), "2 days")
            .writeStream.format("parquet")
            .option("path", str(tmp_path / "sink"))
            .option("checkpointLocation", str(tmp_path / "ck"))
            .outputMode("append")
            .start()
        )
        q.processAllAvailable()
        q.stop()
    got = {str(r["start"])[:10]: r["c"] for r in spark.read.parquet(str(tmp_path / "sink")).collect()}
    assert got["2024-01-01"] == 1 and got["2024-01-19"] == 1


def test_statistics_follow_a_stream(spark, small, tmp_path):
    """Changes of itemset values by stream, one batch replayed: scores are those of the last values."""
    b = bench(spark, small, "conversations")
    old, new = itemset_values(b.rules), itemset_values(with_score(b.rules, "lift"))
    folder, cells = str(tmp_path / "in"), str(tmp_path / "cells")
    first = old.select("items", "attrs", "size", F.lit(None).cast("double").alias("before"), F.col("value").alias("after"))
    then = old.select("items", "attrs", "size", F.col("value").alias("before")).join(new.select("items", F.col("value").alias("after")), "items")
    for part in (first, then.select(first.columns)):
        part.coalesce(1).write.mode("append").parquet(folder)
        q = spark.readStream.schema(CHANGES).parquet(folder).writeStream.foreachBatch(maintain_statistics(cells))
        q = q.option("checkpointLocation", str(tmp_path / "ck")).start()
        q.processAllAvailable()
        q.stop()
    maintain_statistics(cells)(then.select(first.columns), 1)
    got = combine(b.scope, held_statistics(spark, cells), *shape(new, b.scope))
    want = {r["elem_id"]: r["x"] for r in contribution_decomposed(new, b.scope).collect()}
    assert max(abs(r["x"] - want[r["elem_id"]]) for r in got.collect()) < 1e-9


def test_repeated_events_count_once(spark, small, tmp_path):
    events = table(spark, small, "events")
    folder = str(tmp_path / "in")
    events.unionByName(events.where("event_id % 3 = 0")).repartition(1).sortWithinPartitions("ts").write.parquet(folder)
    once = windowed_tuples(events, tumbling("7 days"))
    batch = windowed_tuples(spark.read.parquet(folder), tumbling("7 days"), dedup=True)
    assert sorted(map(str, batch.collect())) == sorted(map(str, once.collect()))
    q = windowed_tuples(read_events(spark, folder), tumbling("7 days"), dedup=True).writeStream.format("memory").queryName("once").outputMode("append")
    q = q.option("checkpointLocation", str(tmp_path / "ck")).start()
    q.processAllAvailable()
    q.stop()
    seen = spark.table("once")
    closed = [r[0] for r in seen.select("start").distinct().collect()]
    assert len(closed) > 1 and sorted(map(str, seen.collect())) == sorted(str(r) for r in once.collect() if r["start"] in closed)


def test_group_as_one_player(spark):
    """The score of a pair as one player, by enumeration of the coalitions of the others."""
    e, r = example_elements(spark), example_rules(spark)
    values = itemset_values(r)
    v = {frozenset(x["items"]): x["value"] for x in values.collect()}
    attr = {x["elem_id"]: x["attr"] for x in e.collect()}
    pair, n, want = {2, 3}, 5, 0.0
    others = [i for i in attr if i not in pair and attr[i] not in {attr[j] for j in pair}]
    for k in range(len(others) + 1):
        for s in combinations(others, k):
            if len({attr[i] for i in s}) == k:
                want += factorial(k) * factorial(n - k - 1) / factorial(n) * (v.get(frozenset(s) | pair, 0.0) - v.get(frozenset(s), 0.0))
    assert us.union_importance(values, e, [2, 3]).first()["x"] == pytest.approx(want)
    with pytest.raises(ValueError):
        us.union_importance(values, e, [4, 6])


def test_interaction_by_hand(spark):
    e, r = example_elements(spark), example_rules(spark)
    got = {x["given"]: x["x"] for x in us.interaction(r, e, 2, "income").collect()}
    only = contribution(r.where("rule_id <= 2"), e)
    assert got == {">=50K": pytest.approx(only.where("elem_id = 2").first()["x"])}


def test_mean_and_interval(spark):
    df = spark.createDataFrame([("a", 1.0), ("a", 3.0), ("b", 2.0), ("c", None)], "k string, x double")
    got = {r["k"]: (r["mean"], r["low"], r["high"]) for r in mt.mean_ci(df, "x", ["k"]).collect()}
    half = 1.96 * 2**0.5 / 2**0.5
    assert got["a"] == pytest.approx((2.0, 2.0 - half, 2.0 + half)) and got["b"] == (2.0, 2.0, 2.0) and got["c"] == (None, None, None)
