"""Mined rule sets of the experiment workloads, written once per state of a folder.

What follows on a view's rules reads the written tables, however often it asks for them. Changed input
files, or written tables that are gone, mean mining anew. A registered query starts with ``forget``: it
mines its rules from the folder's tables itself, whatever ran before it in the session.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from rulecredit.operators.contribution import itemset_values, rule_elements
from rulecredit.operators.evaluation import build_instances, grid_rules
from rulecredit.operators.mining import filter_lift, frequent_itemsets, generate_rules, with_score
from rulecredit.sources.store import TableStore
from rulecredit.sources.views import VIEWS


@dataclass(frozen=True)
class Setting:
    min_support: float
    max_len: int
    method: str = "levelwise"
    min_lift: float = 1.05


#: Settings of the views, itemsets up to all attributes; attributes of the star view are near-independent and need lower support.
SETTINGS = {
    "conversations": Setting(0.05, 5, "cube"),
    "documents": Setting(0.05, 8),
    "events": Setting(0.01, 6, "cube"),
    "pages": Setting(0.05, 6, "cube"),
    "embeddings": Setting(0.05, 9),
    "embeddings_wide": Setting(0.2, 65, "bitmap"),
    "star": Setting(0.02, 11),
}


@dataclass
class Bench:
    n_rows: int
    elements: DataFrame  # frequent elements
    itemsets: DataFrame
    rules: DataFrame  # lift-filtered, scored by IS
    scope: DataFrame  # elements in a rule


_held: dict[tuple, Bench] = {}
_grids: dict[tuple, DataFrame] = {}


def _state(spark: SparkSession, folder: str) -> tuple:
    """What tells that a folder's tables are those seen before: their files' paths, sizes and times."""
    sc = spark.sparkContext
    make = sc._jvm.org.apache.hadoop.fs.Path
    root = make(folder)
    fs = root.getFileSystem(sc._jsc.hadoopConfiguration())
    out = []
    for s in fs.listStatus(root):
        parts = fs.listStatus(s.getPath()) if s.isDirectory() else [s]
        out.extend((str(p.getPath()), p.getLen(), p.getModificationTime()) for p in parts)
    return sc.applicationId, folder, tuple(sorted(out))


def _stands(spark: SparkSession, df: DataFrame) -> bool:
    """Whether a written table is still there: others may clean the shared folder."""
    sc = spark.sparkContext
    make = sc._jvm.org.apache.hadoop.fs.Path
    return all(make(f).getFileSystem(sc._jsc.hadoopConfiguration()).exists(make(f)) for f in df.inputFiles()[:1])


def bench(spark: SparkSession, folder: str, view: str, setting: Setting | None = None) -> Bench:
    setting = setting or SETTINGS[view]
    key = (*_state(spark, folder), view, setting)
    if key not in _held or not _stands(spark, _held[key].rules):
        store = TableStore(spark, f"bench-{view}")
        mined = frequent_itemsets(VIEWS[view](spark, folder), setting.min_support, setting.max_len, setting.method, store)
        rules = store.write(with_score(filter_lift(generate_rules(mined), setting.min_lift)), "rules")
        scope = store.write(rule_elements(itemset_values(rules), mined.elements), "scope")
        store.keep("elements", "itemsets", "rules", "scope")
        _held[key] = Bench(mined.n_rows, mined.elements, mined.itemsets, rules, scope)
    return _held[key]


def forget() -> None:
    """Let go of the views' rule sets; their tables stay for results that still read them."""
    _held.clear()


def grid(spark: SparkSession, folder: str) -> DataFrame:
    """Rules of the whole evaluation set (``evaluation.grid_rules``)."""
    key = _state(spark, folder)
    if key not in _grids or not _stands(spark, _grids[key]):
        store = TableStore(spark, "grid")
        _grids[key] = grid_rules(spark, folder, build_instances(), store)
        store.keep("rules")
    return _grids[key]
