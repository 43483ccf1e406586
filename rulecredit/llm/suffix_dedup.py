"""Suffix-array deduplication of repeated byte strings.

1. :mod:`anchors` cuts each text's windows of the minimum length into blocks (one pass, map
   only); blocks whose anchor occurs once in the corpus cannot repeat and go.
2. Equal blocks are folded to one with a weight: a folded block occurs at least twice, so
   all its windows repeat. Blocks that meet other blocks under their anchor are taken on,
   one copy each, in shards of whole anchors and bounded bytes.
3. A shard concatenates its blocks, sorts their suffixes up to the minimum length, and
   expands intervals of the Burrows-Wheeler transform breadth first by backward
   extension: the boundaries found in round v are exactly the neighbours that share v - 1
   bytes. It stops at the minimum length; suffixes still in one interval share that many
   bytes. A window repeats when its interval's blocks weigh two or more.
4. An anchor with more different blocks than a shard holds is split (:data:`SPREADS`): its
   blocks' parts are folded and taken on as in 2, those still too many split into single
   windows, which only fold. So no shard grows with the number of documents.
5. Runs of repeated windows return to every occurrence of their block and are cut from the texts.

Defined results: null texts are empty; texts shorter than the minimum length are
unchanged; repeated rows and ties remove all copies, the first one too; every row is a text of
its own, so rows that repeat a doc_id with another text, or have none, are cut by
their own repeats; a very long text is one row of one task and otherwise like all others; an empty
table gives an empty result; extra columns, of any name, stay as they are (the text column
of :func:`remove_repeats` is ``text``). As text, what remains is decoded without partial
characters at cuts.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.llm import anchors
from rulecredit.llm import bytehash as bh
from rulecredit.llm.runtime import SharedStore, ship, spread_join

MIN_BYTES = 400
#: Part of the minimum length that an anchor's gram has.
GRAM_PART = 0.4
#: Bytes of block text in a shard, and of one anchor above which it is split.
SHARD_BYTES = 1_000_000
#: How far the offsets of a part of a split block may differ, split after split.
SPREADS = (16, 1)
SEPARATOR = 255  # never a byte of UTF-8

#: A block in work: its group, its own key, weight, place, and the first block (top) whose window `off` it starts at.
PARTS = "g long, body long, weight long, doc_id long, h long, start int, n int, top_a long, top_body long, off int"


def _gram(length: int) -> int:
    return max(1, int(GRAM_PART * length))


def _grams(data: np.ndarray, prefix: np.ndarray, gram: int) -> np.ndarray:
    at = np.arange(len(data) - gram + 1, dtype=np.int64)
    return bh.range_hash(prefix, at, at + gram)


def _find(length: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """BLOCKS of rows (doc_id, h, text)."""
    gram = _gram(length)
    for b in batches:
        for buf in bh.slices(b.column(2)):
            if len(buf.data) < length:
                continue
            found = anchors.find_blocks(_grams(buf.data, buf.prefix(), gram), buf.data, buf.offs, length, gram)
            if len(found.text):
                row = pa.array(found.text + buf.first)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(bh.signed(found.anchor)),
                        pa.array(bh.signed(found.body)),
                        b.column(0).take(row),
                        b.column(1).take(row),
                        pa.array(found.start.astype(np.int32)),
                        pa.array(found.count.astype(np.int32)),
                    ],
                    ["a", "body", "doc_id", "h", "start", "n"],
                )


def _wanted_parts(length: int, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int | None, int, dict, memoryview]]:
    """(doc_id, h, part, its bytes) of rows (doc_id, h, text, want); equal rows in a row count once."""
    last = None
    for b in batches:
        wants = b.column(3).to_pylist()
        for doc, h, text, want in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), wants):
            if (doc, h) == last:
                continue
            last = (doc, h)
            view = memoryview(text.as_buffer())
            for w in want:
                yield doc, h, w, view[w["start"] : w["start"] + w["n"] - 1 + length]


def _cut_blocks(length: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(g, body, weight, top_a, top_body, off, bytes) of the wanted parts of each text."""
    names, kinds = ["g", "body", "weight", "top_a", "top_body", "off"], [*[pa.int64()] * 5, pa.int32(), pa.binary()]
    rows: list[tuple] = []

    def flush() -> pa.RecordBatch:
        cols = list(zip(*rows)) if rows else [[]] * len(kinds)
        rows.clear()
        return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, kinds)], [*names, "bytes"])

    size = 0
    for _, _, w, raw in _wanted_parts(length, batches):
        rows.append((*(w[k] for k in names), bytes(raw)))
        size += len(raw)
        if size > SHARD_BYTES:
            yield flush()
            size = 0
    yield flush()


def _split_parts(length: int, spread: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """PARTS of the wanted parts, split."""
    gram, rows = _gram(length), []
    kinds = [*[pa.int64()] * 5, pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32()]
    names = re.findall(r"(\w+) (?:long|int)", PARTS)

    def flush() -> pa.RecordBatch:
        cols = list(zip(*rows)) if rows else [[]] * len(kinds)
        cols[:2] = [bh.signed(np.array(c, np.uint64)) for c in cols[:2]]
        rows.clear()
        return pa.RecordBatch.from_arrays([pa.array(c if isinstance(c, np.ndarray) else list(c), t) for c, t in zip(cols, kinds)], names)

    for doc, h, w, raw in _wanted_parts(length, batches):
        data = np.frombuffer(raw, np.uint8)
        grams = _grams(data, bh.Buffer(data, np.array([0, len(data)]), 0).prefix(), gram)
        for group, body, lo, n in anchors.split_block(data, grams, length, gram, spread):
            rows.append((group, body, w["weight"], doc, h, w["start"] + lo, n, w["top_a"], w["top_body"], w["off"] + lo))
        if len(rows) > 50_000:
            yield flush()
    yield flush()


def sort_suffixes(data: np.ndarray, depth: int) -> np.ndarray:
    """Suffix order (int32) by at least the first ``depth`` bytes (prefix doubling; the end sorts first)."""
    n = len(data)
    key = np.zeros(n, np.uint64)
    for j in range(8):
        key <<= bh.U(8)
        key[: max(n - j, 0)] |= data[j:]
    order = np.argsort(key).astype(np.int32)
    have = 8
    while True:
        fresh = np.ones(n, bool)
        sorted_key = key[order]
        np.not_equal(sorted_key[1:], sorted_key[:-1], out=fresh[1:])
        del sorted_key
        rank = np.empty(n, np.int32)
        rank[order] = np.cumsum(fresh, dtype=np.int32)
        if have >= depth or fresh.all():
            return order
        key[:] = rank
        key <<= bh.U(32)
        key[: max(n - have, 0)] |= rank[have:].astype(np.uint64)
        del order, rank
        order = np.argsort(key).astype(np.int32)
        have *= 2


def shared_intervals(data: np.ndarray, order: np.ndarray, depth: int) -> np.ndarray:
    """For each place in suffix order, the start of the interval sharing ``depth`` bytes.

    Works on the transform alone: ``step`` maps a place to the place of the suffix one
    byte longer, ``prior`` to the closest earlier place with the same byte.
    """
    n = len(data)
    transform = data[order - 1]
    by_byte = np.argsort(transform, kind="stable").astype(np.int32)
    step = np.empty(n, np.int32)
    step[by_byte] = np.arange(n, dtype=np.int32)
    prior = np.full(n, -1, np.int32)
    same = transform[by_byte[1:]] == transform[by_byte[:-1]]
    prior[by_byte[1:][same]] = by_byte[:-1][same]
    del transform, by_byte, same
    start, stop = np.zeros(n, np.int32), np.full(n, n, np.int32)
    border = np.zeros(n, bool)
    border[0] = True
    new = step[prior < 0]
    for _ in range(depth):
        new = np.unique(new[~border[new]])
        if not len(new):
            break
        border[new] = True
        left = np.unique(start[new])
        size = stop[left] - left
        place = bh.ragged_arange(left.astype(np.int64), size.astype(np.int64)).astype(np.int32)
        old = np.repeat(left, size)
        head = np.flatnonzero(border[place])
        counts = np.diff(np.append(head, len(place)))
        begin = np.repeat(place[head], counts)
        start[place] = begin
        stop[place] = begin + np.repeat(counts.astype(np.int32), counts)
        before = prior[place]
        new = step[place[(before >= old) & (before < begin)]]
    return start


def repeated_windows(blocks: list[bytes], weights: list[int], length: int) -> list[np.ndarray]:
    """For each block a flag per window: it starts somewhere else too (weights count occurrences)."""
    size = np.array([len(x) for x in blocks], np.int64)
    data = np.frombuffer(bytes([SEPARATOR]).join(blocks) + bytes([SEPARATOR]), np.uint8)
    order = sort_suffixes(data, length)
    start = shared_intervals(data, order, length)
    at = np.cumsum(size + 1) - (size + 1)
    windows = size - length + 1
    weight = np.zeros(len(data), np.int8)  # two and more are alike
    weight[bh.ragged_arange(at, windows)] = np.repeat(np.minimum(np.array(weights, np.int64), 2).astype(np.int8), windows)
    head = np.flatnonzero(start == np.arange(len(data), dtype=np.int32))
    total = np.add.reduceat(weight[order], head, dtype=np.int64)
    flag = np.zeros(len(data), bool)
    flag[order] = np.repeat(total >= 2, np.diff(np.append(head, len(data))))
    return [flag[a : a + w] for a, w in zip(at.tolist(), windows.tolist())]


def _expand(length: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by group; yields (a, body, s, c): runs of repeated windows of single blocks."""
    held: dict[tuple, tuple] = {}  # a shard: whole groups, each part once
    size, group = 0, None

    def solve() -> pa.RecordBatch:
        rows = list(held.values())
        out: tuple[list, ...] = ([], [], [], [])
        flags = repeated_windows([r[6] for r in rows], [r[2] for r in rows], length) if rows else []
        for r, f in zip(rows, flags):
            if r[2] == 1 and f.any():
                s, c = anchors.runs_of(f)
                for col, v in zip(out, ([r[3]] * len(s), [r[4]] * len(s), (s + r[5]).tolist(), c.tolist())):
                    col.extend(v)
        held.clear()
        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds)], ["a", "body", "s", "c"])

    for b in batches:
        for r in zip(*(c.to_pylist() for c in b.columns)):
            if r[0] != group and size >= SHARD_BYTES:
                yield solve()
                size = 0
            group = r[0]
            if r[:2] not in held:
                held[r[:2]] = r
                size += len(r[6])
    yield solve()


def repeated_runs(texts: DataFrame, parts: DataFrame, length: int, store: SharedStore) -> list[DataFrame]:
    """Runs (a, body, s, c) of the top blocks' windows that repeat, from ``parts`` (PARTS, ``size``) whose groups have several."""
    found = []
    place = F.min(F.struct("doc_id", "h", "start", "top_a", "top_body", "off")).alias("rep")
    for turn, spread in enumerate((*SPREADS, 0)):
        parts = store.write(parts, f"parts{turn}")
        fits = parts.where(F.col("size") <= SHARD_BYTES) if spread else parts
        total = fits.agg(F.sum(F.col("n") + length)).first()[0]
        if total:
            spread_over = int(min(max(int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions")), total >> 26), 100_000))
            pieces = _with_texts(texts, fits).mapInArrow(
                lambda it: _cut_blocks(length, it), "g long, body long, weight long, top_a long, top_body long, off int, bytes binary"
            )
            pieces = pieces.repartition(spread_over, "g").sortWithinPartitions("g")
            found.append(store.write(pieces.mapInArrow(lambda it: _expand(length, it), "a long, body long, s int, c int"), f"expanded{turn}"))
            store.release()
        large = parts.where(F.col("size") > SHARD_BYTES)
        if not spread or not large.take(1):
            break
        split = store.write(_with_texts(texts, large).mapInArrow(lambda it, d=spread: _split_parts(length, d, it), PARTS), f"split{turn}")
        folded = split.groupBy("g", "body").agg(
            F.sum("weight").alias("weight"), F.count("*").alias("parents"), place, F.first("n").alias("n")
        )
        folded = store.write(folded.select("g", "body", "weight", "parents", "rep.*", "n"), f"folded{turn}")
        often = store.write(folded.where("weight > 1").select("g", "body", "parents"), f"often{turn}")
        new = spread_join(split.where("weight = 1"), often, ["g", "body"], "parents", ["top_a", "top_body", "off"])
        found.append(store.write(new.select(F.col("top_a").alias("a"), F.col("top_body").alias("body"), F.col("off").alias("s"), F.col("n").alias("c")), f"equal{turn}"))
        parts = anchors.crowded(folded.drop("parents"), "g", length, store, f"sizes{turn}")
    return found


def _with_texts(texts: DataFrame, parts: DataFrame) -> DataFrame:
    """(doc_id, h, text, want): each text with its wanted parts."""
    cols = [c for c in parts.columns if c not in ("doc_id", "h")]
    wanted = parts.groupBy("doc_id", "h").agg(F.collect_list(F.struct(*cols)).alias("want"))
    texts = anchors.possible(texts, parts).where("near").drop("near")
    return texts.join(wanted, anchors.same_row(texts, wanted)).select(texts["doc_id"], texts["h"], "text", "want")


def repeated_spans(docs: DataFrame, store: SharedStore, length: int = MIN_BYTES) -> DataFrame:
    """(doc_id, h, starts, counts): runs of repeated windows of the rows that have any; ``h``: :func:`anchors.row_key`."""
    ship(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), anchors.row_key().alias("h"), "text").where(f"octet_length(text) >= {length}")
    occ = anchors.shared_blocks(texts.mapInArrow(lambda it: _find(length, it), anchors.BLOCKS), F.count("*") > 1, store)
    folded = occ.groupBy("a", "body").agg(
        F.count("*").alias("weight"), F.min(F.struct("doc_id", "h", "start")).alias("rep"), F.first("n").alias("n")
    )
    folded = store.write(folded.select("a", "body", "weight", "rep.*", "n"), "folded")
    parts = anchors.crowded(folded, "a", length, store, "sizes").select(
        F.col("a").alias("g"), "body", "weight", "doc_id", "h", "start", "n", F.col("a").alias("top_a"), F.col("body").alias("top_body"), F.lit(0).alias("off"), "size"
    )
    runs = repeated_runs(texts, parts, length, store)
    whole = folded.where("weight > 1").select("a", "body", F.lit(0).alias("s"), F.col("n").alias("c"))
    listed = reduce(DataFrame.unionByName, runs, whole).groupBy("a", "body").agg(F.collect_set(F.struct("s", "c")).alias("r"))
    verdict = store.write(listed.join(folded.select("a", "body", "weight"), ["a", "body"]), "verdict")
    hits = spread_join(occ, verdict, ["a", "body"], "weight", ["doc_id", "h", "start"]).select("doc_id", "h", "start", F.explode("r").alias("r"))
    rows = hits.select("doc_id", "h", (F.col("start") + F.col("r.s")).alias("s"), F.col("r.c").alias("c"))
    spans = store.write(anchors.runs_by_row(rows), "spans")
    store.keep("spans")
    store.release()
    return spans


def _with_spans(keyed: DataFrame, spans: DataFrame) -> DataFrame:
    """``keyed`` (doc_id, h, others) with ``starts`` and ``counts`` of its rows; rows that have none are not moved."""
    marked = anchors.possible(keyed, spans)
    near = marked.where("near").drop("near")
    kinds = dict(spans.dtypes)
    alone = marked.where("not near").drop("near").select("*", *[F.lit(None).cast(kinds[c]).alias(c) for c in ("starts", "counts")])
    met = near.join(spans, anchors.same_row(near, spans), "left").select(*[near[c] for c in keyed.columns], "starts", "counts")
    return met.unionByName(alone)


def _ranges(starts: list | None, counts: list | None, length: int) -> list[tuple[int, int]]:
    if not starts:
        return []
    return anchors.merge_runs(np.array(starts, np.int64), np.array(counts, np.int64), length)


def _remaining(raw: bytes, cut: list[tuple[int, int]]) -> bytes:
    out, at = [], 0
    for a, b in cut:
        out.append(raw[at:a])
        at = b
    out.append(raw[at:])
    return b"".join(out)


def _digest(length: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows: tuple[list, ...] = ([], [], [], [])
        for text, starts, counts in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist()):
            raw = (text or "").encode()
            cut = _ranges(starts, counts, length)
            rest = _remaining(raw, cut)
            for col, v in zip(rows, (len(raw), len(raw) - len(rest), len(cut), hashlib.sha256(rest).hexdigest())):
                col.append(v)
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string()]
        yield pa.RecordBatch.from_arrays(
            [b.column(0), *(pa.array(c, t) for c, t in zip(rows, kinds))], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
        )


def op9_suffix_interval_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    spans = repeated_spans(docs, SharedStore(spark, "suffix"))
    cut = _with_spans(docs.withColumn("h", anchors.row_key()), spans).select("doc_id", "text", "starts", "counts")
    return cut.mapInArrow(
        lambda it: _digest(MIN_BYTES, it), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    )


def remove_repeats(docs: DataFrame, length: int = MIN_BYTES, min_words: int = 0, sure_bytes: int = MIN_BYTES) -> DataFrame:
    """``docs`` with repeated strings of ``length`` bytes or more cut from ``text``; same columns.

    With ``min_words``, a repeated run of fewer words (parts of words count) stays unless it has ``sure_bytes`` bytes.
    """
    cols = docs.columns
    rest = [c for c in cols if c != "text"]
    row = docs.select(F.struct(*[F.col(f"`{c}`") for c in rest]).alias("_row"), F.col("doc_id").cast("long").alias("doc_id"), F.col("text"))
    spans = repeated_spans(row.select("doc_id", "text"), SharedStore(docs.sparkSession, "suffix"), length)

    def goes(raw: bytes, a: int, b: int) -> bool:
        return b - a >= sure_bytes or len(raw[a:b].split()) >= min_words

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(0).to_pylist()
            for i, (s, c) in enumerate(zip(b.column(1).to_pylist(), b.column(2).to_pylist())):
                if s and texts[i] is not None:
                    raw = texts[i].encode()
                    cut = [r for r in _ranges(s, c, length) if goes(raw, *r)]
                    if cut:
                        texts[i] = _remaining(raw, cut).decode("utf-8", errors="ignore")
            others = dict(zip(rest, b.column(3).flatten()))
            columns = [pa.array(texts, b.schema.field("text").type) if c == "text" else others[c] for c in cols]
            yield pa.RecordBatch.from_arrays(columns, cols)

    keyed = row.withColumn("h", anchors.row_key())
    joined = _with_spans(keyed, spans).select("text", "starts", "counts", "_row")
    return joined.mapInArrow(run, docs.schema)
