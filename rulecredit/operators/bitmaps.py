"""Itemsets of wide rows by bitmaps: one bitmap an element, one bit a row.

Rows are read twice, to count elements and to cut them into chunks of bounded size that keep a bitmap of each
frequent element. A level's candidates join itemsets that differ in their last element only;
every chunk counts them by intersecting bitmaps, and counts add up by candidate with a shuffle of at most
candidates x tasks rows. Work and memory of a task follow its chunk, not the rows of the table, and wide
rows are neither grouped nor repeated. The driver holds one level of itemsets at a time and those found:
their number follows from the support and the associations, not from the number of rows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.sources.store import TableStore

#: Rows of a chunk (whole bytes), and bytes of bitmaps intersected at once.
CHUNK_ROWS, WORK_BYTES = 1 << 15, 1 << 22
#: Different elements that a task counts before it hands them on.
COUNTED = 100_000


@contextmanager
def split_methods(spark: SparkSession) -> Iterator[None]:
    """Wide projections as several methods: the JVM never compiles one of over 8000 bytes, which a row of many attributes has."""
    name = "spark.sql.codegen.hugeMethodLimit"
    before = spark.conf.get(name)
    spark.conf.set(name, "8000")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def element_counts(view: DataFrame) -> DataFrame:
    """(attr, val, freq_cnt) of every element of ``view``; null cells have none."""
    names, most = view.columns, COUNTED

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met: Counter = Counter()

        def flush() -> pa.RecordBatch:
            attr, val = [names[k] for k, _ in met], [v for _, v in met]
            out = [pa.array(attr, pa.string()), pa.array(val, pa.string()), pa.array(list(met.values()), pa.int64())]
            met.clear()
            return pa.RecordBatch.from_arrays(out, ["attr", "val", "c"])

        for b in batches:
            for k, c in enumerate(b.columns):
                values, counts = c.value_counts().flatten()
                for v, n in zip(values.to_pylist(), counts.to_pylist()):
                    if v is not None:
                        met[k, v] += n
            if len(met) > most:
                yield flush()
        yield flush()

    return view.mapInArrow(tally, "attr string, val string, c long").groupBy("attr", "val").agg(F.sum("c").alias("freq_cnt"))


def element_bitmaps(view: DataFrame, numbered: list) -> DataFrame:
    """(bits): for each chunk of rows the elements' bitmaps one after the other, in the order of ``numbered`` (attr, val)."""
    values: dict[str, list[tuple[str, int]]] = {}
    for i, r in enumerate(numbered):
        values.setdefault(r["attr"], []).append((r["val"], i))
    n, chunk = len(numbered), CHUNK_ROWS

    # nested, so that it travels by value and workers need no installation
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc

        held = np.zeros((n, chunk), bool)
        used = 0

        def flush() -> pa.RecordBatch:
            raw = np.packbits(held[:, :used], axis=1).tobytes()
            return pa.RecordBatch.from_arrays([pa.array([raw], pa.binary())], ["bits"])

        for b in batches:
            at = 0
            while at < b.num_rows:
                part = b.slice(at, chunk - used)
                to = used + part.num_rows
                for c, pairs in zip(part.columns, values.values()):
                    found = pc.index_in(c, value_set=pa.array([v for v, _ in pairs], c.type))
                    found = found.fill_null(-1).to_numpy(zero_copy_only=False)
                    for k, (_, i) in enumerate(pairs):
                        np.equal(found, k, out=held[i, used:to])
                at, used = at + part.num_rows, to
                if used == chunk:
                    yield flush()
                    used = 0
        if used:
            yield flush()

    return view.select(*[F.col(f"`{a}`") for a in values]).mapInArrow(pack, "bits binary")


def candidates(level: np.ndarray, attr: np.ndarray) -> np.ndarray:
    """Itemsets one longer than ``level`` (rows of ascending elements, sorted) whose two last elements follow one prefix and differ in attribute."""
    if not len(level):
        return np.zeros((0, level.shape[1] + 1), np.int32)
    fresh = np.ones(len(level), bool)
    fresh[1:] = (level[1:, :-1] != level[:-1, :-1]).any(axis=1)
    end = np.append(np.flatnonzero(fresh)[1:], len(level))[np.cumsum(fresh) - 1]
    more = end - np.arange(len(level)) - 1
    first = np.repeat(np.arange(len(level)), more)
    second = first + 1 + np.arange(len(first)) - np.repeat(np.cumsum(more) - more, more)
    keep = attr[level[first, -1]] != attr[level[second, -1]]
    first, second = first[keep], second[keep]
    return np.concatenate([level[first], level[second, -1:]], axis=1)


def count_sets(chunks: DataFrame, n_elements: int, sets: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """(index, count) of the ``sets`` met in at least ``least`` rows, by index."""
    shared = chunks.sparkSession.sparkContext.broadcast(sets)
    work = WORK_BYTES

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = shared.value
        total = np.zeros(len(wanted), np.int64)
        for b in batches:
            for raw in b.column(0):
                bits = np.frombuffer(raw.as_buffer(), np.uint8).reshape(n_elements, -1)
                step = max(1, work // bits.shape[1])
                for at in range(0, len(wanted), step):
                    some = wanted[at : at + step]
                    met = bits[some[:, 0]]
                    for j in range(1, some.shape[1]):
                        met &= bits[some[:, j]]
                    total[at : at + step] += np.bitwise_count(met).sum(axis=1, dtype=np.int64)
        here = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(here), pa.array(total[here])], ["i", "cnt"])

    summed = chunks.mapInArrow(count, "i long, cnt long").groupBy("i").agg(F.sum("cnt").alias("cnt")).where(F.col("cnt") >= least)
    found = summed.toArrow()
    shared.destroy()
    index, cnt = found.column("i").to_numpy(), found.column("cnt").to_numpy()
    order = np.argsort(index)
    return index[order], cnt[order]


def bitmap_itemsets(view: DataFrame, numbered: list, least: int, max_len: int, store: TableStore) -> DataFrame:
    """(items, size, cnt) of the itemsets of ``view`` met in at least ``least`` rows. ``numbered``: the frequent elements by id."""
    spark = view.sparkSession
    attr = np.array([r["attr_id"] for r in numbered], np.int32)
    level = np.arange(len(numbered), dtype=np.int32)[:, None]
    cnt = np.array([r["freq_cnt"] for r in numbered], np.int64)
    if numbered:
        with split_methods(spark):
            chunks = store.write(element_bitmaps(view, numbered), "bitmaps")
    found: list[tuple[np.ndarray, np.ndarray]] = []
    while len(level) and level.shape[1] <= max_len:
        found.append((level, cnt))
        grown = candidates(level, attr) if level.shape[1] < max_len else level[:0]
        if not len(grown):
            break
        kept, cnt = count_sets(chunks, len(numbered), grown, least)
        level = grown[kept]
    schema = "items array<int>, size int, cnt long"
    if not found:
        return spark.createDataFrame([], schema)
    lists = pa.concat_arrays(
        [pa.ListArray.from_arrays(pa.array(np.arange(0, s.size + 1, s.shape[1], dtype=np.int32)), pa.array(s.ravel(), pa.int32())) for s, _ in found]
    )
    size = np.concatenate([np.full(len(s), s.shape[1], np.int32) for s, _ in found])
    table = pa.table({"items": lists, "size": size, "cnt": np.concatenate([c for _, c in found])})
    return spark.createDataFrame(table).select(F.col("items").cast("array<int>").alias("items"), F.col("size").cast("int").alias("size"), F.col("cnt").cast("long").alias("cnt"))
