"""Substring deduplication with suffix automata of reference shards.

A 13-word window is removed from a document when the same words also start in a
document with a smaller id. The reference is the corpus itself, so:

1. :mod:`anchors` cuts each text's windows into blocks. Anchors met in one document only
   are dropped.
2. Equal blocks under an anchor fold to one with its first (smallest) document; in every
   other document such a block goes whole.
3. Anchors under which different blocks meet are taken on in shards of whole anchors and
   bounded words. Each shard is a reference: its blocks enter one suffix automaton in
   document order, so a state's first document is the smallest that holds its words; then
   every block is streamed through it. Matching statistics, held at the window length, tell
   for each window whether a smaller document holds it. (Sending each automaton to all documents
   would read the corpus once per shard; a block only needs its own anchor's shard.)
4. An anchor with more different blocks than a shard holds has them split into their
   windows (at most ten each), which fold by their words with their smallest document.
5. Runs of removed windows return to the documents; covered words go.

Word equality is equality of 64-bit keys (:func:`bytehash.word_keys`); a window needs thirteen of them.

Defined results: null texts have no words; texts under 13 words are unchanged; of equal
documents the one with the smallest id keeps its words. Rows that repeat an id are one document:
neither is smaller, and each row is cut by the smaller documents' words in its own text. A row
without an id is smaller than none and larger than none, so it stays whole and removes
nothing. A very long text is one row of one task and otherwise like all others; an empty table
gives an empty result; columns other than doc_id and text are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.llm import anchors
from rulecredit.llm import bytehash as bh
from rulecredit.llm.runtime import SharedStore, ship, spread_join

WINDOW, GRAM = 13, 4
#: Words of block text in a shard, and of one anchor above which its blocks are split.
SHARD_WORDS = 60_000


def _find(window: int, gram: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """BLOCKS of rows (doc_id, h, text)."""
    for b in batches:
        for buf in bh.slices(b.column(2)):
            words = bh.words(buf)
            if len(words.key) < window:
                continue
            found = anchors.find_blocks(bh.gram_keys(words.key, gram), words.key, words.offs, window, gram)
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


def _wanted_blocks(window: int, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, dict, np.ndarray]]:
    """(doc_id, block, keys of its words) of rows (doc_id, h, text, want); equal rows in a row count once."""
    last = None
    for b in batches:
        docs, hashes, wants = (b.column(i).to_pylist() for i in (0, 1, 3))
        for buf in bh.slices(b.column(2)):
            words = bh.words(buf)
            for i in range(len(buf.offs) - 1):
                row = buf.first + i
                if (docs[row], hashes[row]) == last:
                    continue
                last = (docs[row], hashes[row])
                for w in wants[row]:
                    s = words.offs[i] + w["start"]
                    yield docs[row], w, words.key[s : s + w["n"] - 1 + window]


def _cut_blocks(window: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(a, first, body, words): keys of the words of the wanted blocks."""
    rows: list[tuple] = []

    def flush() -> pa.RecordBatch:
        cols = list(zip(*rows)) if rows else [[]] * 4
        rows.clear()
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, kinds)], ["a", "first", "body", "words"])

    for doc, w, keys in _wanted_blocks(window, batches):
        rows.append((w["a"], doc, w["body"], keys.tobytes()))
        if len(rows) >= 5_000:
            yield flush()
    yield flush()


def _split_blocks(window: int, gram: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(g, body, top_a, top_body, first, off): the windows of the wanted blocks."""
    rows: list[tuple] = []

    def flush() -> pa.RecordBatch:
        cols = list(zip(*rows)) if rows else [[]] * 6
        rows.clear()
        cols = [pa.array(bh.signed(np.array(c, np.uint64))) for c in cols[:2]] + [pa.array(list(c), pa.int64()) for c in cols[2:]]
        return pa.RecordBatch.from_arrays(cols, ["g", "body", "top_a", "top_body", "first", "off"])

    for doc, w, keys in _wanted_blocks(window, batches):
        for group, body, lo, _ in anchors.split_block(keys, bh.gram_keys(keys, gram), window, gram, 1):
            rows.append((group, body, w["a"], w["body"], doc, lo))
        if len(rows) >= 50_000:
            yield flush()
    yield flush()


class SuffixAutomaton:
    """Generalised automaton over hashable symbols; texts are added in falling priority.

    ``owner[state]`` is the first text that holds the state's words.
    """

    def __init__(self):
        self.next: list[dict] = [{}]
        self.link = [-1]
        self.size = [0]
        self.owner = [-1]

    def _state(self, size: int, owner: int, moves: dict) -> int:
        self.next.append(moves)
        self.link.append(-1)
        self.size.append(size)
        self.owner.append(owner)
        return len(self.size) - 1

    def _split(self, p: int, symbol, q: int) -> int:
        """The state of p's words and the symbol, when q also stands for longer ones."""
        if self.size[q] == self.size[p] + 1:
            return q
        clone = self._state(self.size[p] + 1, self.owner[q], dict(self.next[q]))
        self.link[clone] = self.link[q]
        self.link[q] = clone
        while p >= 0 and self.next[p].get(symbol) == q:
            self.next[p][symbol] = clone
            p = self.link[p]
        return clone

    def add(self, text, owner: int) -> None:
        at = 0
        for symbol in text:
            q = self.next[at].get(symbol)
            if q is not None:
                at = self._split(at, symbol, q)
                continue
            new = self._state(self.size[at] + 1, owner, {})
            p = at
            while p >= 0 and symbol not in self.next[p]:
                self.next[p][symbol] = new
                p = self.link[p]
            self.link[new] = 0 if p < 0 else self._split(p, symbol, self.next[p][symbol])
            at = new

    def owners(self, text, window: int) -> list[int]:
        """For each window of ``text`` the first text holding it, -1 where none does."""
        nxt, link, size, owner = self.next, self.link, self.size, self.owner
        at = held = 0
        out = []
        for i, symbol in enumerate(text):
            while at and symbol not in nxt[at]:
                at = link[at]
                held = size[at]
            q = nxt[at].get(symbol)
            if q is None:
                at = held = 0
            else:
                at, held = q, held + 1
            if held > window:
                held = window
            while at and size[link[at]] >= held:  # the state of the last `held` words
                at = link[at]
            if i >= window - 1:
                out.append(owner[at] if held == window else -1)
        return out


def _match(window: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by anchor; yields the runs (a, body, first, s, c) of each block's first copy that a smaller document holds."""
    held: dict[tuple, tuple] = {}  # a shard: whole anchors, each block once
    size, anchor = 0, None

    def solve() -> pa.RecordBatch:
        out: tuple[list, ...] = ([], [], [], [], [])
        machine = SuffixAutomaton()
        rows = sorted(held.values(), key=lambda r: r[1])
        texts = [np.frombuffer(r[3], np.int64).tolist() for r in rows]
        for r, t in zip(rows, texts):
            machine.add(t, r[1])
        for r, t in zip(rows, texts):
            s, c = anchors.runs_of(np.array(machine.owners(t, window), np.int64) < r[1])
            for col, v in zip(out, ([r[0]] * len(s), [r[2]] * len(s), [r[1]] * len(s), s.tolist(), c.tolist())):
                col.extend(v)
        held.clear()
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds)], ["a", "body", "doc_id", "s", "c"])

    for b in batches:
        for r in zip(*(c.to_pylist() for c in b.columns)):
            if r[0] != anchor and size >= SHARD_WORDS:
                yield solve()
                size = 0
            anchor = r[0]
            if (r[0], r[2]) not in held:
                held[r[0], r[2]] = r
                size += len(r[3]) // 8
    yield solve()


def _with_texts(texts: DataFrame, blocks: DataFrame) -> DataFrame:
    """(doc_id, h, text, want): each text with its wanted blocks."""
    wanted = blocks.groupBy("doc_id", "h").agg(F.collect_list(F.struct("a", "body", "start", "n")).alias("want"))
    return texts.join(wanted, ["doc_id", "h"]).select("doc_id", "h", "text", "want")


def removal_spans(docs: DataFrame, store: SharedStore, window: int = WINDOW) -> DataFrame:
    """(doc_id, h, starts, counts): runs of removed windows, by word number; ``h``: :func:`anchors.row_key`."""
    spark = docs.sparkSession
    ship(spark)
    gram = min(GRAM, window)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), anchors.row_key().alias("h"), "text")
    texts = texts.where("doc_id is not null and text is not null")
    blocks = texts.mapInArrow(lambda it: _find(window, gram, it), anchors.BLOCKS)
    occ = anchors.shared_blocks(blocks, F.min("doc_id") < F.max("doc_id"), store)
    folded = occ.groupBy("a", "body").agg(
        F.min(F.struct("doc_id", "h", "start")).alias("rep"), F.max("doc_id").alias("last"), F.count("*").alias("weight"), F.first("n").alias("n")
    )
    folded = store.write(folded.select("a", "body", "rep.*", "last", "weight", "n"), "folded")
    mixed = store.write(anchors.crowded(folded, "a", window, store, "sizes"), "mixed")
    fits, large = mixed.where(F.col("size") <= SHARD_WORDS), mixed.where(F.col("size") > SHARD_WORDS)
    total = fits.agg(F.sum(F.col("n") + window)).first()[0] or 0
    spread_over = int(min(max(int(spark.conf.get("spark.sql.shuffle.partitions")), total >> 23), 100_000))
    pieces = _with_texts(texts, fits).mapInArrow(lambda it: _cut_blocks(window, it), "a long, first long, body long, words binary")
    pieces = pieces.repartition(spread_over, "a").sortWithinPartitions("a")
    partial = store.write(pieces.mapInArrow(lambda it: _match(window, it), "a long, body long, doc_id long, s int, c int"), "partial")
    store.release()
    if large.take(1):
        windows = _with_texts(texts, large).mapInArrow(
            lambda it: _split_blocks(window, gram, it), "g long, body long, top_a long, top_body long, first long, off long"
        )
        windows = store.write(windows, "windows")
        least = windows.groupBy("g", "body").agg(F.min("first").alias("lo"), F.max("first").alias("hi"), F.count("*").alias("rows"))
        least = store.write(least.where("lo < hi").select("g", "body", "lo", "rows"), "least")
        gone = spread_join(windows, least, ["g", "body"], "rows", ["top_a", "top_body", "off"]).where("first > lo")
        gone = gone.select(F.col("top_a").alias("a"), F.col("top_body").alias("body"), F.col("first").alias("doc_id"), F.col("off").cast("int").alias("s"), F.lit(1).alias("c"))
        partial = partial.unionByName(store.write(gone, "gone"))
    # a block goes whole where its document is not its first one; there its removed runs go
    later = store.write(folded.where("last > doc_id").select("a", "body", F.col("doc_id").alias("first"), "weight"), "later")
    whole = spread_join(occ, later, ["a", "body"], "weight", ["doc_id", "h", "start"]).where("doc_id > first")
    first = occ.join(partial, ["a", "body", "doc_id"])
    runs = whole.select("doc_id", "h", F.col("start").alias("s"), F.col("n").alias("c")).unionByName(
        first.select("doc_id", "h", (F.col("start") + F.col("s")).alias("s"), "c")
    )
    spans = store.write(anchors.runs_by_row(runs), "spans")
    store.keep("spans")
    store.release()
    return spans


def _kept_words(text: str | None, starts: list | None, counts: list | None, window: int) -> tuple[int, list[bytes]]:
    words = (text or "").encode().split()
    if not starts:
        return len(words), words
    out, at = [], 0
    for a, b in anchors.merge_runs(np.array(starts, np.int64), np.array(counts, np.int64), window):
        out.extend(words[at:a])
        at = b
    out.extend(words[at:])
    return len(words), out


def _digest(window: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows: tuple[list, ...] = ([], [], [])
        for text, s, c in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist()):
            n, rest = _kept_words(text, s, c, window)
            for col, v in zip(rows, (n, n - len(rest), hashlib.sha256(b" ".join(rest)).hexdigest())):
                col.append(v)
        kinds = [pa.int64(), pa.int64(), pa.string()]
        yield pa.RecordBatch.from_arrays(
            [b.column(0), *(pa.array(c, t) for c, t in zip(rows, kinds))], ["doc_id", "n_words", "n_removed", "kept_sha256"]
        )


def op4_suffix_automata_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    spans = removal_spans(docs, SharedStore(spark, "automata"))
    keyed = docs.withColumn("h", anchors.row_key())
    joined = keyed.join(spans, ["doc_id", "h"], "left").select("doc_id", "text", "starts", "counts")
    return joined.mapInArrow(lambda it: _digest(WINDOW, it), "doc_id long, n_words long, n_removed long, kept_sha256 string")
