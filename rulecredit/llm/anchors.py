"""Content-defined blocks: where a repeated window of a sequence can occur at all.

Every window of ``window`` symbols (bytes or words) is assigned to its smallest gram,
the leftmost on ties. The choice depends on the window's content only, so equal windows
anywhere share their anchor. Runs of windows with one anchor form a block; a block's
``body`` is a key of the symbols its windows cover and of the anchor's place in them, so
equal bodies hold equal windows. Comparing blocks that share an anchor is therefore enough
to find every repeated window, and folding equal bodies first keeps groups of copies small.

An anchor with very many different blocks (a common line in ever other surroundings) is
split further by :func:`split_block`: its windows are dealt by the anchor's place in them
and by the symbols around it that all windows of such a place share.

Rows are known by ``doc_id`` and a hash of their text, so rows that repeat an id with
another text, or have none, stay apart.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulecredit.llm import bytehash as bh
from rulecredit.llm.runtime import SharedStore, spread_join

#: Columns of block rows: anchor, body, row (doc_id, h), first window, number of windows.
BLOCKS = "a long, body long, doc_id long, h long, start int, n int"
#: Low bits of a gram that give way to its place; texts are below 2 ** 32 symbols.
PLACE_BITS = bh.U(32)
#: Words of 64 bits that tell which rows may have a partner: those a key gets, and the most.
KEY_WORDS, MOST_WORDS = 0.25, 1 << 18


@dataclass
class Blocks:
    """Per block: text index, first window (symbols from the text's start), windows, anchor, body."""

    text: np.ndarray
    start: np.ndarray
    count: np.ndarray
    anchor: np.ndarray
    body: np.ndarray


def _placed(grams: np.ndarray) -> np.ndarray:
    """Grams with their low bits replaced by their place, so that minima tell where they are."""
    return ((grams >> PLACE_BITS) << PLACE_BITS) | np.arange(len(grams), dtype=np.uint64)


def find_blocks(grams: np.ndarray, symbols: np.ndarray, offs: np.ndarray, window: int, gram: int) -> Blocks:
    """Blocks of the texts at ``offs`` (symbol offsets) of one sequence of ``symbols``.

    ``grams``: hash of the gram starting at each symbol.
    """
    z = np.zeros(0, np.int64)
    size = np.maximum(np.diff(offs) - window + 1, 0)
    if not size.any():
        return Blocks(z, z, z, z.view(np.uint64), z.view(np.uint64))
    low = bh.sliding_min(_placed(grams), window - gram + 1)
    at = bh.ragged_arange(offs[:-1], size)
    pos = (low[at] & ((bh.U(1) << PLACE_BITS) - bh.U(1))).astype(np.int64)
    text = np.repeat(np.arange(len(size)), size)
    first = np.ones(len(at), bool)
    first[1:] = (pos[1:] != pos[:-1]) | (text[1:] != text[:-1])
    head = np.flatnonzero(first)
    count = np.diff(np.append(head, len(at)))
    start, where = at[head], pos[head]
    body = bh.range_keys(symbols, start, start + count - 1 + window, where - start)
    return Blocks(text[head], start - offs[:-1][text[head]], count, grams[where], body)


def split_block(symbols: np.ndarray, grams: np.ndarray, window: int, gram: int, spread: int) -> list[tuple[int, int, int, int]]:
    """(group, body, first window, windows) of the parts of one block's ``symbols``.

    A window's offset is the anchor's place in it. Windows whose offsets agree but for the last
    ``spread`` form a part; its group is a key of the symbols that all windows of such offsets
    share, ``window - spread + 1`` of them. With a spread of 1 the group is the window itself.
    """
    n = len(symbols) - window + 1
    at = int(np.argmin(_placed(grams[: window - gram + 1])))
    view, item = memoryview(np.ascontiguousarray(symbols)).cast("B"), symbols.itemsize
    out = []
    for k in range((at - n + 1) // spread, at // spread + 1):
        lo, hi = max(0, at - k * spread - spread + 1), min(n - 1, at - k * spread)
        core = at - k * spread
        group = xxhash.xxh3_64_intdigest(view[core * item : (core - spread + 1 + window) * item], k)
        body = xxhash.xxh3_64_intdigest(view[lo * item : (hi + window) * item], at - lo)
        out.append((group, body, lo, hi - lo + 1))
    return out


def row_key(text: str = "text") -> Column:
    return F.xxhash64(text)


def same_row(a: DataFrame, b: DataFrame) -> Column:
    return a["doc_id"].eqNullSafe(b["doc_id"]) & (a["h"] == b["h"])


def possible(rows: DataFrame, wanted: DataFrame) -> DataFrame:
    """``rows`` with ``near``: false only where no row of ``wanted`` (a written table) has the same ``h``.

    So that a join need not move the texts that meet nothing. The broadcast is bounded; above
    the bound more rows without a partner are near.
    """
    words = int(min(max(wanted.count() * KEY_WORDS, 1), MOST_WORDS))
    at = F.pmod(F.xxhash64("h"), F.lit(words * 64))
    bit = "shiftleft(1L, cast(_at & 63 as int))"
    place = F.expr("shiftright(_at, 6)")
    held = wanted.select(at.alias("_at")).select(place.alias("_word"), F.expr(bit).alias("b")).groupBy("_word").agg(F.expr("bit_or(b)").alias("_bits"))
    met = rows.withColumn("_at", at).withColumn("_word", place).join(F.broadcast(held), "_word", "left")
    return met.withColumn("near", F.coalesce(F.expr(f"_bits & {bit} <> 0"), F.lit(False))).drop("_word", "_at", "_bits")


def shared_blocks(blocks: DataFrame, meets: Column, store: SharedStore) -> DataFrame:
    """The rows of ``blocks`` (BLOCKS) under an anchor that ``meets`` the condition (an aggregate)."""
    held = store.write(blocks, "blocks")
    shared = held.groupBy("a").agg(F.count("*").alias("c"), meets.alias("_meets")).where("_meets").select("a", "c")
    out = store.write(spread_join(held, store.write(shared, "anchors"), ["a"], "c", ["doc_id", "h", "start"]), "occurrences")
    store.drop("blocks", "anchors")
    store.release()
    return out.drop("c")


def crowded(folded: DataFrame, key: str, width: int, store: SharedStore, name: str) -> DataFrame:
    """The rows of ``folded`` (written; ``n`` windows a row) whose ``key`` has several, with ``size``, the key's symbols."""
    sizes = folded.groupBy(key).agg(F.count("*").alias("bodies"), F.sum(F.col("n") + (width - 1)).alias("size")).where("bodies > 1")
    return spread_join(folded, store.write(sizes, name), [key], "bodies", ["body"])


def runs_by_row(runs: DataFrame) -> DataFrame:
    """(doc_id, h, starts, counts) of runs of windows (doc_id, h, s, c); rows that repeat add nothing."""
    found = runs.groupBy("doc_id", "h").agg(F.collect_set(F.struct("s", "c")).alias("r"))
    return found.select("doc_id", "h", F.col("r.s").alias("starts"), F.col("r.c").alias("counts"))


def merge_runs(start: np.ndarray, count: np.ndarray, window: int) -> list[tuple[int, int]]:
    """Maximal covered ranges [a, b) of windows given as runs of starts."""
    order = np.argsort(start, kind="stable")
    out: list[tuple[int, int]] = []
    for s, c in zip(start[order].tolist(), count[order].tolist()):
        e = s + c - 1 + window
        if out and s <= out[-1][1]:
            if e > out[-1][1]:
                out[-1] = (out[-1][0], e)
        else:
            out.append((s, e))
    return out


def runs_of(flags: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(start, length) of the runs of true entries."""
    edge = np.diff(np.concatenate([[0], flags.astype(np.int8), [0]]))
    a = np.flatnonzero(edge == 1)
    return a, np.flatnonzero(edge == -1) - a
