"""Best-fit packing planned on the length histogram.

1. A map over the texts yields pieces of at most ``capacity`` tokens (only the first
   piece of a longer document may be shorter).
2. The histogram of piece lengths (at most ``capacity`` rows, whatever the input) is
   packed on the driver: lengths in falling order, each into the tightest open
   sequence that takes it. Equal sequences are handled as one run, so the plan's size
   follows the histogram, not the number of documents.
3. Each piece gets its rank among the pieces of its length; the plan maps
   (length, rank) to a sequence and an offset. Ranks are counted in salted buckets, so
   a length that holds most rows is spread over many tasks.

Defined results: null and empty texts are one piece holding the end id; ties within a
length are taken in (doc_id, piece) order within their salt bucket; equal rows, and rows that
repeat an id or have none, are packed as documents of their own; a very long text is cut by one
task; an empty table gives an empty result; columns other than doc_id and text are not read.
"""

from __future__ import annotations

import bisect
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rulecredit.llm.bpe import default_path, load
from rulecredit.llm.runtime import SharedStore, ship

CAPACITY = 2048
END_ID = 0
BUCKET_ROWS = 100_000

PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long"


def _pieces(path: str, capacity: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    encoder = load(path)
    end = np.array([END_ID], "<u4").tobytes()
    for batch in batches:
        rows: list[tuple[int, int, int, int, int]] = []
        for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            ids = encoder.encode(text or "") + end
            n = len(ids) // 4
            first = (n - 1) % capacity + 1
            start, size, k = 0, first, 0
            while start < n:
                rows.append((doc, k, start, size, zlib.crc32(ids[4 * start : 4 * (start + size)])))
                start, size, k = start + size, capacity, k + 1
        cols = list(zip(*rows)) if rows else [[]] * 5
        kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
        yield pa.RecordBatch.from_arrays(
            [pa.array(list(c), t) for c, t in zip(cols, kinds)], ["doc_id", "piece", "start", "length", "ids_crc32"]
        )


def cut_pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32) of every document's ids and the end id."""
    ship(docs.sparkSession)
    where = path or default_path()
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(
        lambda it: _pieces(where, capacity, it), PIECE_SCHEMA
    )


def plan_slots(histogram: dict[int, int], capacity: int = CAPACITY) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Best-fit decreasing over counts.

    Returns plan rows (length, first rank, pieces per sequence, first sequence, offset),
    each covering the ranks up to the next row's, and the number of sequences. A run of
    equal open sequences is (first sequence, how many); ``open_`` keeps runs by the room left.
    """
    open_: dict[int, list[tuple[int, int]]] = {}
    rooms: list[int] = []  # the keys of open_, ascending
    plan: list[tuple[int, int, int, int, int]] = []
    sequences = 0

    def put(room: int, run: tuple[int, int]) -> None:
        if room <= 0 or run[1] <= 0:
            return
        if room not in open_:
            open_[room] = []
            bisect.insort(rooms, room)
        open_[room].append(run)

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        while left > 0:
            at = bisect.bisect_left(rooms, length)
            if at == len(rooms):  # none takes it: open as many as these pieces fill
                each = capacity // length
                room, first, count = capacity, sequences, -(-left // each)
                sequences += count
            else:
                room = rooms[at]
                first, count = open_[room].pop()
                if not open_[room]:
                    del open_[room]
                    rooms.pop(at)
                each = room // length
            full = min(count, left // each)
            if full:
                plan.append((length, rank, each, first, capacity - room))
                rank += full * each
                left -= full * each
                put(room - each * length, (first, full))
                first, count = first + full, count - full
            if count and left:  # fewer than one sequence's worth
                plan.append((length, rank, each, first, capacity - room))
                put(room - left * length, (first, 1))
                rank, left = rank + left, 0
                first, count = first + 1, count - 1
            put(room, (first, count))
    return plan, sequences


def _take_slots(plan: np.ndarray, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    key = plan[:, 0] * (1 << 44) + plan[:, 1]
    order = np.argsort(key, kind="stable")
    key, rows = key[order], plan[order]
    for b in batches:
        length = b.column(3).to_numpy()
        rank = b.column(5).to_numpy()
        hit = rows[np.searchsorted(key, length * (1 << 44) + rank, "right") - 1] if len(rank) else np.zeros((0, 5), np.int64)
        nth = rank - hit[:, 1]
        seq = hit[:, 3] + nth // np.maximum(hit[:, 2], 1)
        off = hit[:, 4] + nth % np.maximum(hit[:, 2], 1) * length
        yield pa.RecordBatch.from_arrays(
            [*b.columns[:5], pa.array(seq, pa.int64()), pa.array(off, pa.int64())],
            ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"],
        )


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Give each row of ``pieces`` (read twice: pass a written table) its sequence and offset."""
    spark = pieces.sparkSession
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    plan, _ = plan_slots(counts, capacity)
    salts = max(16, max(counts.values(), default=0) // BUCKET_ROWS)
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(salts)).cast("int"))
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    base = (
        salted.groupBy("length", "salt")
        .agg(F.count("*").alias("n"))
        .select("length", "salt", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    )
    own = Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")
    ranked = (
        salted.withColumn("nth", F.row_number().over(own) - 1)
        .join(base, ["length", "salt"])
        .select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("nth")).alias("rank"))
    )
    table = np.array(plan, np.int64).reshape(-1, 5)
    shared = spark.sparkContext.broadcast(table)  # at most one row per length and room
    return ranked.mapInArrow(
        lambda it: _take_slots(shared.value, it), PIECE_SCHEMA + ", sequence_id long, offset long"
    )


def pack_documents(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    store = SharedStore(docs.sparkSession, "packing")
    return pack_pieces(store.write(cut_pieces(docs, path, capacity), "pieces"), capacity)


def op3_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
