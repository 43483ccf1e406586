"""Queries return the whole of their job."""

from collections import Counter
from itertools import combinations

import pytest
from pyspark.sql import Observation
from pyspark.sql import functions as F

from rulecredit.operators import contribution as c
from rulecredit.operators import evaluation as ev
from rulecredit.operators.alternatives import i_top, influence
from rulecredit.operators.approx import approximate
from rulecredit.operators.grouped import grouped_contribution, grouped_counts, grouped_estimate, grouped_influence, grouped_top, grouped_values
from rulecredit.operators.mining import min_count
from rulecredit.plans import registry
from rulecredit.plans.fixtures import measured_rules
from rulecredit.plans.registry import QUERIES
from rulecredit.plans.workbench import SETTINGS, bench
from rulecredit.sources.store import TableStore
from rulecredit.sources.tables import table
from rulecredit.sources.views import RAW, VIEWS
from rulecredit.streaming.windows import tumbling, window_contribution, windowed_tuples


def test_every_window_is_scored(spark, small):
    got = {(r["window_start"], r["attr"], r["val"]): r["x"] for r in QUERIES["windowed_contribution_events"](spark, small).collect()}
    tuples = windowed_tuples(table(spark, small, "events"), tumbling(f"{registry.WINDOW_DAYS} days")).cache()
    starts = [r[0] for r in tuples.select("start").distinct().collect()]
    knobs = registry.WINDOW_SETTING
    want = {}
    for start in starts:
        one = window_contribution(tuples.where(F.col("start") == F.lit(start)), knobs.min_support, knobs.max_len, knobs.min_lift)
        day = tuples.where(F.col("start") == F.lit(start)).select(F.date_format("start", "yyyy-MM-dd")).first()[0]
        want |= {(day, r["attr"], r["val"]): r["x"] for r in one.collect()}
    assert len(starts) > 1 and got.keys() == want.keys()
    assert max(abs(got[k] - want[k]) for k in got) < 2e-6


def all_sets(rows, least):
    """Every itemset of any size met ``least`` times, by enumeration."""
    counts = Counter(
        picked for items in rows for k in range(1, len(items) + 1) for picked in combinations(sorted(items), k)
    )
    return {(s, n) for s, n in counts.items() if n >= least}


@pytest.mark.parametrize("view", ["documents", "events", "pages"])
def test_itemsets_of_every_size(spark, small, view):
    rows = [[f"{a}={v}" for a, v in r.asDict().items() if v is not None] for r in VIEWS[view](spark, small).collect()]
    b = bench(spark, small, view)
    names = {r["elem_id"]: f"{r['attr']}={r['val']}" for r in b.elements.collect()}
    got = {(tuple(names[i] for i in r["items"]), r["cnt"]) for r in b.itemsets.collect()}
    assert got == all_sets(rows, min_count(SETTINGS[view].min_support, len(rows)))


@pytest.mark.parametrize("view", list(SETTINGS))
def test_settings_do_not_cap_sizes(spark, small, view):
    assert SETTINGS[view].max_len >= len(VIEWS[view](spark, small).columns)


def test_grid_equals_single_instances(spark, small):
    """Counts, scores and estimates of instances mined together are those of each on its own."""
    grid = ev.build_instances(("events", "pages"), (300,), (3,), (0.1, 0.2), (1.05, 1.2))
    some = [i for i in grid if (i.view, i.min_support, i.min_lift) in {("events", 0.1, 1.05), ("events", 0.2, 1.2), ("pages", 0.2, 1.05)}]
    store = TableStore(spark, "t")
    rules = ev.grid_rules(spark, small, some)
    values = store.write(grouped_values(rules), "values")
    counts = {(r["g"], r["elem"]): (int(r["naive"]), r["pruned"]) for r in grouped_counts(values).collect()}
    scores = {(r["g"], r["elem"]): r["x"] for r in grouped_contribution(values, 8).collect()}
    frames = {"top": grouped_top(rules), "influence": grouped_influence(rules)}
    frames |= {m: grouped_estimate(values, m, 512, 8, store, 3) for m in ("monte_carlo", "kernel", "antithetic", "stratified", "sobol")}
    lists = {m: {(r["g"], r["elem"]): r["x"] for r in f.collect()} for m, f in frames.items()}
    met = 0
    for inst in some:
        one, elements = ev.mine_instance(spark, small, inst)
        scope = c.rule_elements(c.itemset_values(one), elements)
        names = {r["elem_id"]: (inst.run_id, f"{r['attr']}={r['val']}") for r in scope.collect()}
        met += len(names)
        alone = {names[r["elem_id"]]: (int(r["naive"]), r["pruned"]) for r in ev.coalition_counts(one, elements, inst.run_id).collect()}
        assert alone == {k: v for k, v in counts.items() if k[0] == inst.run_id}
        if not names:
            continue
        held = c.itemset_values(one)
        wanted = {"top": i_top(one, scope), "influence": influence(one, scope)}
        wanted |= {m: approximate(held, scope, m, 512, 3) for m in frames if m not in wanted}
        for m, want in {"exact": c.contribution_decomposed(held, scope), **wanted}.items():
            got = scores if m == "exact" else lists[m]
            assert all(abs(got[names[r["elem_id"]]] - r["x"]) < 1e-9 for r in want.collect()), (inst.run_id, m)
    assert met == len(scores) > 10


def test_experiments_cover_the_whole_grid():
    assert len({i.run_id for i in registry._INSTANCES}) == 6 * 2 * 3 * 3 * 2
    assert {i.view for i in registry._INSTANCES} == set(RAW)


def test_changed_tables_are_mined_anew(spark, small, tmp_path):
    folder = str(tmp_path)
    rows = table(spark, small, "conversations")
    rows.write.parquet(f"{folder}/conversations.parquet")
    first = bench(spark, folder, "conversations")
    assert bench(spark, folder, "conversations") is first
    rows.limit(40).write.mode("overwrite").parquet(f"{folder}/conversations.parquet")
    assert bench(spark, folder, "conversations").n_rows == 40 != first.n_rows


def test_wide_view_has_every_component(spark, small):
    rows = [r.asDict() for r in VIEWS["embeddings_wide"](spark, small).collect()]
    least = min_count(SETTINGS["embeddings_wide"].min_support, len(rows))
    masks = {}
    for i, r in enumerate(rows):
        for a, v in r.items():
            masks[f"{a}={v}"] = masks.get(f"{a}={v}", 0) | 1 << i
    level = {(e,): m for e, m in masks.items() if m.bit_count() >= least}
    single, want = dict(level), {}
    while level:
        want |= {s: m.bit_count() for s, m in level.items()}
        grown = ((s + e, m & n) for s, m in level.items() for e, n in single.items() if e[0] > s[-1])
        level = {s: m for s, m in grown if m.bit_count() >= least}
    b = bench(spark, small, "embeddings_wide")
    names = {r["elem_id"]: f"{r['attr']}={r['val']}" for r in b.elements.collect()}
    assert len(rows[0]) == 65 and {tuple(names[i] for i in r["items"]): r["cnt"] for r in b.itemsets.collect()} == want
    assert QUERIES["contribution_embeddings_wide"](spark, small).select("attr").distinct().count() > 9


def test_naive_form_scores_every_element(spark, small):
    got, want = ({(r["attr"], r["val"]): r["x"] for r in QUERIES[q](spark, small).collect()} for q in ("contribution_naive", "contribution_conversations"))
    assert len(got) > 1 and got.keys() == want.keys()
    assert max(abs(got[k] - want[k]) for k in got) < 2e-6


def test_every_query_mines_its_own_rules(spark, small, monkeypatch):
    """A query reads its table whatever ran before it."""
    read = []
    view = VIEWS["conversations"]
    monkeypatch.setitem(VIEWS, "conversations", lambda s, d: read.append(d) or view(s, d))
    first, second = ({tuple(r) for r in QUERIES[q](spark, small).collect()} for q in ("coalitions_naive", "coalitions_naive"))
    assert len(read) == 2 and first == second


def test_example_follows_its_table(spark, tmp_path):
    shape = "conv_id long, turn long, role string, text string"
    kinds = [(1, "user", "a" * 300 + "\n", 4), (0, "user", "b", 2), (0, "system", "b", 1), (2, "system", "c" * 150, 3), (2, "assistant", "d" * 150, 2)]
    rows = [(i, turn, role, text) for turn, role, text, n in kinds for i in range(n)]
    spark.createDataFrame(rows, shape).write.parquet(f"{tmp_path}/conversations.parquet")
    got = {q: {(r["attr"], r["val"]): r["x"] for r in QUERIES[q](spark, str(tmp_path)).collect()} for q in ("contribution_example_printed", "contribution_naive_example")}
    assert got["contribution_example_printed"] == pytest.approx(got["contribution_naive_example"], abs=2e-6)
    # supports 4/12, 4/12, 3/12 and 2/12; lifts 3, 3, 4 and 4
    scores = {r["rule_id"]: r["score"] for r in measured_rules(VIEWS["conversations"](spark, str(tmp_path))).collect()}
    assert scores == {1: 100, 2: 100, 3: 100, 4: 67}
    assert len(got["contribution_naive_example"]) == 6


ONE_TABLE = [
    "contribution_example_is_product",
    "contribution_example_printed",
    "contribution_naive_example",
    "influence_sum",
    "is_bands",
    "itemset_values_avg",
]


@pytest.mark.parametrize("query", ONE_TABLE)
def test_tasks_read_every_row(spark, small, monkeypatch, query):
    """All rows of the table pass Spark's tasks, also after a query that mined the same rules."""
    QUERIES["coalitions_pruned"](spark, small)
    view, read = VIEWS["conversations"], []

    def watched(s, d):
        read.append(Observation())
        return view(s, d).observe(read[-1], F.count(F.lit(1)).alias("n"))

    monkeypatch.setitem(VIEWS, "conversations", watched)
    QUERIES[query](spark, small).collect()
    assert read and read[0].get["n"] == table(spark, small, "conversations").count()
