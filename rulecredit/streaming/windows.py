"""Windowed rule contributions over a stream of tuples.

State is the count of each distinct tuple per window; late rows inside the watermark
update it, rows beyond it are dropped. Each closed window's tuples are mined and scored
by the batch functions, and written under (window, batch) so that replays overwrite.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.operators.contribution import contribution, merge_statistics, statistics
from rulecredit.operators.grouped import far_from_independent, grouped_contribution, grouped_itemsets, grouped_rules, grouped_values, limits, tuple_texts
from rulecredit.operators.mining import filter_lift, frequent_itemsets, generate_rules, with_score
from rulecredit.sources.store import TableStore
from rulecredit.sources.views import event_attributes

EVENT_SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def tumbling(length: str) -> Column:
    return F.window("ts", length)


def sliding(length: str, step: str) -> Column:
    return F.window("ts", length, step)


def session(gap: str) -> Column:
    return F.session_window("ts", gap)


def windowed_tuples(events: DataFrame, window: Column, watermark: str | None = "1 day", dedup: bool = False) -> DataFrame:
    """(start, end, attributes..., c): tuple counts by window; batch or streaming input."""
    if watermark and events.isStreaming:
        events = events.withWatermark("ts", watermark)
        if dedup:
            events = events.dropDuplicatesWithinWatermark(["event_id"])
    elif dedup:
        events = events.dropDuplicates(["event_id"])
    named = [c.alias(f"a{i}") for i, c in enumerate(event_attributes())]
    names = ["et", "h", "dow", "v", "u", "k"]
    keyed = events.select("ts", *named).groupBy(window.alias("w"), *[f"a{i}" for i in range(len(named))]).agg(F.count("*").alias("c"))
    return keyed.select("w.start", "w.end", *[F.col(f"a{i}").alias(n) for i, n in enumerate(names)], "c")


def window_contribution(tuples: DataFrame, min_support: float = 0.05, max_len: int = 3, min_lift: float = 1.05, store: TableStore | None = None) -> DataFrame:
    """Scores of the elements of one window's tuples."""
    mined = frequent_itemsets(tuples.drop("start", "end"), min_support, max_len, "cube", store, weight="c")
    return contribution(with_score(filter_lift(generate_rules(mined), min_lift)), mined.elements)


def contribution_by_window(
    tuples: DataFrame, min_support: float = 0.05, max_len: int = 3, min_lift: float = 1.05, store: TableStore | None = None
) -> DataFrame:
    """(start, attr, val, x) of the elements of every window, each mined on its own rows: the scores
    of ``window_contribution``, with the window as a key instead of a loop."""
    store = store or TableStore(tuples.sparkSession, "windows")
    attrs = [c for c in tuples.columns if c not in {"start", "end", "c"}]
    held = store.write(tuples.select(F.col("start").alias("g"), tuple_texts(attrs).alias("items"), "c"), "tuples")
    groups = held.select("g").distinct().withColumn("min_support", limits(min_support))
    rules = grouped_rules(grouped_itemsets(held, groups, max_len, store)).where(far_from_independent(F.lit(min_lift)))
    values = store.write(grouped_values(rules), "values")
    scores = grouped_contribution(values, max_len)
    return scores.select(F.col("g").alias("start"), F.substring_index("elem", "=", 1).alias("attr"), F.expr("substring(elem, instr(elem, '=') + 1)").alias("val"), "x")


def score_closed_windows(out: str, **knobs) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` handler for append-mode windowed tuples.

    The number of windows closed by one batch is small (windows per trigger), so they are looped over.
    """

    def handle(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        store = TableStore(spark, f"closed-{batch_id}")
        held = store.write(batch, "tuples")
        for i, r in enumerate(held.select("start").distinct().orderBy("start").collect()):
            part = held.where(F.col("start") == F.lit(r["start"]))
            scores = window_contribution(part, store=TableStore(spark, f"closed-{batch_id}-{i}"), **knobs)
            name = r["start"].strftime("%Y%m%d%H%M%S")
            scores.withColumn("window_start", F.lit(r["start"])).write.mode("overwrite").parquet(f"{out}/window={name}/batch={batch_id}")

    return handle


def update_statistics(held: DataFrame, before: DataFrame, after: DataFrame) -> DataFrame:
    """Contribution statistics after some itemsets' values changed: add the new cells, take back the old."""
    return merge_statistics(held, before.withColumn("v", -F.col("v")), after)


CHANGES = "items array<int>, attrs array<int>, size int, before double, after double"
CELLS = "kind string, id int, size int, v double"


def change_statistics(changes: DataFrame) -> DataFrame:
    """Signed cells of changed itemset values (CHANGES; null before: a new itemset, null after: one that is gone)."""
    side = lambda c: statistics(changes.where(F.col(c).isNotNull()).withColumn("value", F.col(c)))
    return merge_statistics(side("after"), side("before").withColumn("v", -F.col("v")))


def maintain_statistics(out: str) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` handler for a stream of CHANGES: a batch's cells go to a table of its own, so a replay overwrites them."""

    def handle(batch: DataFrame, batch_id: int) -> None:
        change_statistics(batch).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    return handle


def held_statistics(spark: SparkSession, out: str) -> DataFrame:
    """The cells over all batches so far: scores follow by ``combine`` whenever they are asked for."""
    return merge_statistics(spark.read.schema(f"{CELLS}, batch long").parquet(out).drop("batch"))
