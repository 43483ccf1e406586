"""SQL surface, previous-event attribute, sinks."""

import pytest

from rulecredit.plans.planner import choose_miner, costs
from rulecredit.plans.workbench import bench
from rulecredit.sources.sql_api import register
from rulecredit.sources.tables import register_views, table, write_result
from rulecredit.sources.views import with_previous_event


def test_sql_surface(spark, small):
    b = bench(spark, small, "conversations")
    register(spark, b.rules, b.elements, prefix="t_")
    top = spark.sql("select attr, val, x from t_scores order by round(x, 9) desc limit 3").collect()
    assert len(top) == 3 and top[0].x >= top[2].x
    assert spark.sql("select count(*) from rule_splits(array(1, 2, 3))").first()[0] == 6
    sets = "(select collect_list(struct(array_join(items, '|') as t, items, value)) from named)"
    b.rules.createOrReplaceTempView("plain_rules")
    names = {r["elem_id"]: f"{r['attr']}={r['val']}" for r in b.elements.collect()}
    pairs = ", ".join(f"{k}, '{v}'" for k, v in names.items())
    spark.sql(f"select transform(items, i -> map({pairs})[i]) as items, value from t_itemset_values").createOrReplaceTempView("named")
    got = {r["elem"]: r["x"] for r in spark.sql(f"select * from contribution_of({sets})").collect()}
    want = {f"{r['attr']}={r['val']}": r["x"] for r in spark.table("t_scores").collect()}
    assert got.keys() == want.keys() and max(abs(got[k] - want[k]) for k in got) < 1e-9
    register_views(spark, small, ["events"])
    assert spark.sql("select count(*) from events").first()[0] == 1000


def test_previous_event(spark, small):
    e = with_previous_event(table(spark, small, "events"), "3 days")
    assert e.count() == 1000 and e.where("prev is not null").count() > 0


def test_write_result(spark, small, tmp_path):
    b = bench(spark, small, "conversations")
    write_result(b.scope.select("attr", "val"), str(tmp_path / "s"), ["attr"])
    assert spark.read.parquet(str(tmp_path / "s")).count() == b.scope.count()


def test_planner():
    assert choose_miner(5, 5) == "cube" and choose_miner(40, 5) == "levelwise"
    c = costs(34, 84479, 15, 8)
    assert c["decomposed"] < c["multi"] < c["sequential"]


def test_tables_are_dropped(spark):
    from rulecredit.sources.store import TableStore

    store = TableStore(spark, "t")
    kept = store.write(spark.range(3), "kept")
    gone = store.write(spark.range(4), "gone")
    store.keep("kept")
    assert kept.count() == 3 and store.names == {"kept"}
    with pytest.raises(Exception, match="gone|exist|FILE"):
        gone.count()


def test_no_local_folder_on_a_cluster():
    from rulecredit.sources.store import shared_root

    class Far:
        master = "yarn"
        _jsc = property(lambda self: self)
        sc = getCheckpointDir = lambda self: self
        isDefined = lambda self: False

    class Session:
        conf = {}
        sparkContext = Far()

    with pytest.raises(ValueError, match=r"spark\.checkpoint\.dir"):
        shared_root(Session())
