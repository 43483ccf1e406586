"""N-gram Jaccard join: size-aware, light sets by subsets and heavy sets by inverted lists.

A text's set is its distinct 5-word shingles (ASCII lower case). Two sets link when
100 * |A and B| >= 75 * |A or B|, which for sizes s, t means at least
``need(s, t)`` shared shingles.

* Equal sets fold to one id first (map-side per task, then by key).
* *Light* sets (below the boundary) meet through every subset of each needed size.
* *Heavy* sets scan inverted lists: sets of sizes s <= t that link share a shingle among
  the first s - need(s, s) + 1 of the smaller and t - ceil(3t/4) + 1 of the larger, in
  any one order of shingles. The order puts shingles that very many texts hold last; a
  fixed-size counting sketch over all texts finds those.
* The boundary minimises the rows that both ways emit, from the histogram of small sizes.
* Candidates pass a parity bitmap of each set first: differing bits bound the symmetric
  difference from below, so a pair that fails cannot link. Links are then checked exactly
  on the texts. A few leader rounds check each set against one set at most: each list names
  a leader, and a set takes the leader whose bitmap is closest. This ties large groups of
  near copies together in linear work. The last round checks every remaining pair of a
  list whose sets are still in different groups, so no link between groups is missed; lists
  are cut into blocks of bounded size. Pairs do not leave a block: its sets in pairs that pass all filters get
their texts, and links that join groups leave, fewer than its sets.

The result is the exact components, not the linked pairs: two sets already in one group are
not tested against each other, so links inside a group are neither listed nor counted.

Lists of one shingle may hold a large part of all sets. Those of shingles that the sketch
calls frequent are dealt by set as well, what a list needs to know of itself comes from
aggregates with map-side combine, and joins on it spread its rows (:func:`runtime.spread_join`).

Defined results: null and blank texts have empty sets and stay alone; texts under five
words are one shingle; repeated rows and ties share a component, named by its smallest
doc_id; every row is a text of its own, so rows that repeat an id with another text have that
id and each the component of its text; a row without an id links as any other, and a
component of such rows only has no name (null); a very long text is one row of one task and
otherwise like all others; an empty table gives an empty result; columns other than doc_id
and text are not read, and :func:`one_per_component` passes them on whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rulecredit.llm import anchors
from rulecredit.llm import bytehash as bh
from rulecredit.llm.components import connected_components
from rulecredit.llm.runtime import SharedStore, ship, spread_join

WIDTH = 5
#: Counting sketch: cells, and the shares of texts from which a cell is reported by a task, and is frequent.
CELLS, TASK_SHARE, FREQUENT_SHARE = 1 << 22, 0.0002, 0.0004
#: Sizes among which the boundary is chosen, and list rows scanned per row emitted.
MAX_LIGHT, SCAN_COST = 20, 4
#: Sets checked against one leader in a unit of work, and list rows in a block.
CHUNK, BLOCK = 64, 1024
#: Cells of a parity bitmap up to which small sets get finer ones.
FINE_CELLS = 2048
#: Tasks over which lists with the same smallest set are spread.
LIST_TASKS = 8
#: Sets of a frequent shingle's list in one task when lists are made, about; sets a task remembers as seen.
DEALT_SETS, SEEN_SETS = 50_000, 200_000
#: Pairs a task remembers as seen in one of its units, about.
SEEN_PAIRS = 1_000_000
#: Rounds that check each set against one leader before the exhaustive one.
LEADER_ROUNDS = 3


def need(s: int, t: int) -> int:
    """Shared shingles that a linked pair of sizes s and t has at least."""
    return -(-3 * (s + t) // 7)


def probe_length(n: int) -> int:
    return n - -(-3 * n // 4) + 1


def index_length(n: int) -> int:
    return n - need(n, n) + 1


def subset_sizes(s: int, boundary: int) -> list[int]:
    """Subset sizes through which a light set meets its light partners."""
    return sorted({need(s, t) for t in range(-(-3 * s // 4), min(4 * s // 3, boundary - 1) + 1)})


def choose_boundary(histogram: dict[int, int]) -> int:
    """The smallest heavy size: least total of subset rows below and list rows from it on."""

    def cost(x: int) -> int:
        light = sum(c * sum(comb(s, k) for k in subset_sizes(s, x)) for s, c in histogram.items() if s < x)
        return light + sum(c * probe_length(s) * SCAN_COST for s, c in histogram.items() if s >= x)

    return min(range(1, MAX_LIGHT + 2), key=lambda x: (cost(x), x))


def shingle_sets(column: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
    """(row, sorted distinct shingle hashes) of every text."""
    for buf in bh.slices(column):
        words = bh.words(buf, lower=True)
        grams = bh.gram_keys(words.key, WIDTH)
        for i in range(len(buf.offs) - 1):
            a, b = int(words.offs[i]), int(words.offs[i + 1])
            if b - a >= WIDTH:
                t = np.sort(grams[a : b - WIDTH + 1])
                if len(t) > 1:
                    t = t[np.concatenate([[True], t[1:] != t[:-1]])]
            elif b > a:
                t = bh.mix(bh.gram_keys(words.key[a:b], b - a) + bh.U(b - a))
            else:
                t = grams[:0]
            yield buf.first + i, t


def set_key(tokens: np.ndarray) -> int:
    """One signed 64-bit key of a set."""
    total = bh.mix(tokens ^ bh.U(0x5851F42D4C957F2D)).sum(dtype=np.uint64) + bh.U(len(tokens))
    return int(bh.signed(bh.mix(np.array([total], np.uint64)))[0])


def parity_bits(tokens: np.ndarray) -> bytes:
    """Bit i tells whether an odd number of shingles falls to cell i; at least two cells a shingle,
    and up to sixteen while that stays within FINE_CELLS: fewer collisions, a tighter bound."""
    size = 1 << (len(tokens) - 1).bit_length()
    cells = max(64, 2 * size, min(8 * size, FINE_CELLS))
    at = ((tokens >> bh.U(22)) & bh.U(cells - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=cells) & 1).astype(np.uint8)).tobytes()


def _folded(bits: np.ndarray, size: int) -> np.ndarray:
    while len(bits) > size:
        bits = bits[: len(bits) // 2] ^ bits[len(bits) // 2 :]
    return bits


def _may_overlap(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (x, y, n_x, bits_x, n_y, bits_y); keeps the pairs whose bitmaps allow a link, with how near they may be."""
    for b in batches:
        keep, common = [], []
        for s, p, t, q in zip(*(b.column(i).to_pylist() for i in (2, 3, 4, 5))):
            p, q = np.frombuffer(p, np.uint8), np.frombuffer(q, np.uint8)
            size = min(len(p), len(q))
            differ = int(np.bitwise_count(_folded(p, size) ^ _folded(q, size)).sum())
            keep.append((s + t - differ) // 2 >= need(s, t))
            common.append((s + t - differ) // 2 / (s + t))
        cols = [*b.columns[:2], pa.array(common, pa.float64())]
        yield pa.RecordBatch.from_arrays(cols, ["x", "y", "near"]).filter(pa.array(keep, pa.bool_()))


def _block_pairs(rows: list[tuple]) -> Iterator[tuple[int, int]]:
    """Pairs (x, y) of a unit's rows (sid, n, pos, g, bits, block) that pass every filter; x is the smaller set."""
    sid, n, pos, g, block = (np.array([r[k] for r in rows], np.int64) for k in (0, 1, 2, 3, 5))
    order = np.lexsort((sid, n))
    sid, n, pos, g, block = sid[order], n[order], pos[order], g[order], block[order]
    bits = [np.frombuffer(rows[k][4], np.uint8) for k in order.tolist()]
    size = np.array([len(b) for b in bits])
    indexed = (pos < 0) | (pos < n - -(-6 * n // 7) + 1)
    for a in range(0, len(rows), 256):
        c = slice(a, a + 256)
        ok = indexed[c, None] & (g[c, None] != g[None, :]) & (4 * n[c, None] >= 3 * n[None, :])
        ok &= np.arange(len(rows))[None, :] > np.arange(len(rows))[c, None]
        if block.min() != block.max():
            ok &= block[c, None] != block[None, :]
        left = np.minimum((n - pos)[c, None], (n - pos)[None, :])
        ok &= (pos[c, None] < 0) | (left >= -(-3 * (n[c, None] + n[None, :]) // 7))
        i, j = np.nonzero(ok)
        i += a
        least = np.minimum(size[i], size[j])
        for s in np.unique(least).tolist():
            here = least == s
            p, q = i[here], j[here]
            used = np.unique(np.concatenate([p, q]))
            table = np.stack([_folded(bits[k], s) for k in used.tolist()])
            for at in range(0, len(p), 20_000):
                u, v = p[at : at + 20_000], q[at : at + 20_000]
                differ = np.bitwise_count(table[np.searchsorted(used, u)] ^ table[np.searchsorted(used, v)]).sum(axis=1, dtype=np.int64)
                good = (n[u] + n[v] - differ) // 2 >= -(-3 * (n[u] + n[v]) // 7)
                yield from zip(sid[u[good]].tolist(), sid[v[good]].tolist())


def _paired_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (token, bi, bj, sid, n, pos, g, bits, block) sorted by unit; passes on those in a pair of their unit that is new to the task."""
    rows: list[tuple] = []
    unit: tuple | None = None
    seen: set[tuple[int, int]] = set()
    out: list[tuple] = []
    kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.int32()]
    names = ["token", "bi", "bj", "sid", "n", "pos", "g", "bits", "block"]

    def solve() -> None:
        fresh = set(_block_pairs(rows)) - seen if len(rows) > 1 else set()
        wanted = {k for pair in fresh for k in pair}
        out.extend((*unit, *r) for r in rows if r[0] in wanted)
        if len(seen) > SEEN_PAIRS:
            seen.clear()
        seen.update(fresh)

    def flush() -> pa.RecordBatch:
        cols = list(zip(*out)) if out else [()] * len(names)
        out.clear()
        return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, kinds)], names)

    for b in batches:
        for r in zip(*(c.to_pylist() for c in b.columns)):
            if unit != r[:3]:
                if rows:
                    solve()
                rows, unit = [], r[:3]
            rows.append(r[3:])
        if len(out) > 20_000:
            yield flush()
    if rows:
        solve()
    yield flush()


def _linked_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of units (as for :func:`_paired_sets`, and text) sorted by unit; yields links (a, b), exact, that join a unit's groups.

    Pairs of sets that the unit's links have joined already are not tested: fewer links than sets leave.
    """
    held: dict[int, tuple[tuple, np.ndarray]] = {}
    unit: tuple | None = None

    def solve() -> pa.RecordBatch:
        a: list[int] = []
        c: list[int] = []
        root: dict[int, int] = {}

        def find(g: int) -> int:
            while root.setdefault(g, g) != g:
                root[g] = g = root[root[g]]
            return g

        sids = list(held)
        spot = {k: i for i, k in enumerate(sids)}
        tokens = [held[k][1] for k in sids]
        size = np.array([len(t) for t in tokens], np.int64)
        words, ids = np.unique(np.concatenate(tokens), return_inverse=True) if tokens else (np.zeros(0), np.zeros(0, np.int64))
        head = np.cumsum(size) - size
        mark = np.zeros(len(words), bool)
        last, common = None, size
        for x, y in _block_pairs([r for r, _ in held.values()]) if len(held) > 1 else ():
            gx, gy = find(held[x][0][3]), find(held[y][0][3])
            if gx == gy:
                continue
            i, j = spot[x], spot[y]
            if last != i:  # pairs come by x: its shingles are held against all sets at once
                mark[:] = False
                mark[ids[head[i] : head[i] + size[i]]] = True
                common, last = np.add.reduceat(mark[ids], head, dtype=np.int64), i
            if 100 * common[j] >= 75 * (size[i] + size[j] - common[j]):
                root[gx] = gy
                a.append(x)
                c.append(y)
        held.clear()
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(c, pa.int64())], ["a", "b"])

    for b in batches:
        rows = list(zip(*(c.to_pylist() for c in b.columns[:9])))
        for i, t in shingle_sets(b.column(9)):
            if unit != rows[i][:3]:
                yield solve()
                unit = rows[i][:3]
            held.setdefault(rows[i][3], (rows[i][3:], t))
    yield solve()


def _summary(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows (doc_id, h, text): kind 0, (doc_id, h, set size, set key, parity bits); at a task's end kind 1, (sketch cell, texts in it)."""
    cells = np.zeros(CELLS, np.int32)
    texts = 0
    for b in batches:
        size, key = np.zeros(b.num_rows, np.int64), np.zeros(b.num_rows, np.int64)
        bits: list[bytes] = [b""] * b.num_rows
        held: list[np.ndarray] = []
        waiting = 0
        for i, t in shingle_sets(b.column(2)):
            if len(t):
                size[i], key[i], bits[i] = len(t), set_key(t), parity_bits(t)
                held.append(t)
                waiting += len(t)
                texts += 1
            if waiting > 500_000:
                cells += np.bincount((np.concatenate(held) & bh.U(CELLS - 1)).astype(np.int64), minlength=CELLS).astype(np.int32)
                held, waiting = [], 0
        if held:
            cells += np.bincount((np.concatenate(held) & bh.U(CELLS - 1)).astype(np.int64), minlength=CELLS).astype(np.int32)
        kind = pa.array(np.zeros(b.num_rows, np.int32))
        cols = [kind, b.column(0), b.column(1), pa.array(size), pa.array(key), pa.array(bits, pa.binary())]
        yield pa.RecordBatch.from_arrays(cols, ["kind", "id", "h", "n", "sid", "bits"])
    hot = np.flatnonzero(cells >= max(4, TASK_SHARE * texts))
    yield pa.RecordBatch.from_arrays(
        [
            pa.array(np.ones(len(hot), np.int32)),
            pa.array(hot),
            pa.array(np.zeros(len(hot), np.int64)),
            pa.array(cells[hot].astype(np.int64)),
            pa.array(np.zeros(len(hot), np.int64)),
            pa.nulls(len(hot), pa.binary()),
        ],
        ["kind", "id", "h", "n", "sid", "bits"],
    )


def _prefix_rows(boundary: int, frequent: np.ndarray, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(token, sid, n, pos, often): list rows (pos >= 0) and subset rows (pos = -1) of each set new to the task; ``often``: a frequent shingle."""
    seen: set[int] = set()
    low_heavy = -(-3 * boundary // 4)
    for b in batches:
        tokens: list[np.ndarray] = []
        pos: list[np.ndarray] = []
        sid: list[int] = []
        size: list[int] = []
        count: list[int] = []
        often: list[np.ndarray] = []

        def emit(t: np.ndarray, p: np.ndarray, s: int, n: int, f: np.ndarray) -> None:
            tokens.append(t)
            pos.append(p)
            often.append(f)
            sid.append(s)
            size.append(n)
            count.append(len(t))

        if len(seen) > SEEN_SETS:
            seen.clear()
        for _, t in shingle_sets(b.column(0)):
            n = len(t)
            if not n:
                continue
            s = set_key(t)
            if s in seen:
                continue
            seen.add(s)
            if n < boundary:
                for k in subset_sizes(n, boundary):
                    subsets = np.array(list(combinations(t.tolist(), k)), np.uint64)
                    keys = np.full(len(subsets), k, np.uint64)
                    for j in range(k):
                        keys = bh.mix(keys * bh.U(0x2545F4914F6CDD1D) + subsets[:, j])
                    emit(keys, np.full(len(keys), -1, np.int32), s, n, np.zeros(len(keys), bool))
            if n >= low_heavy:
                late = frequent[(t & bh.U(CELLS - 1)).astype(np.int64)]
                take = probe_length(n) if n >= boundary else index_length(n)
                ordered = np.concatenate([t[~late], t[late]])[:take]
                emit(ordered, np.arange(take, dtype=np.int32), s, n, np.arange(take) >= n - np.count_nonzero(late))
        if tokens:
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(bh.signed(np.concatenate(tokens))),
                    pa.array(np.repeat(np.array(sid, np.int64), count)),
                    pa.array(np.repeat(np.array(size, np.int32), count)),
                    pa.array(np.concatenate(pos)),
                    pa.array(np.concatenate(often)),
                ],
                ["token", "sid", "n", "pos", "often"],
            )


def _need(s: Column, t: Column) -> Column:
    return F.ceil(3 * (s + t) / F.lit(7))


def _indexed(n: Column, pos: Column) -> Column:
    return pos < n - F.ceil(6 * n / F.lit(7)) + 1


def _may_link(n1: Column, p1: Column, n2: Column, p2: Column) -> Column:
    """Size and position filters for n1 <= n2."""
    left = F.least(n1 - p1, n2 - p2)
    return (4 * n1 >= 3 * n2) & ((p1 < 0) | (left >= _need(n1, n2)))


def _check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (x, part, role, sid, text) sorted; the leader (role 0) precedes the sets checked against it."""
    leader, tokens = None, np.zeros(0, np.uint64)
    for b in batches:
        key = list(zip(b.column(0).to_pylist(), b.column(1).to_pylist()))
        role, sid = b.column(2).to_pylist(), b.column(3).to_pylist()
        a: list[int] = []
        c: list[int] = []
        for i, t in shingle_sets(b.column(4)):
            if role[i] == 0:
                leader, tokens = key[i], t
                continue
            if leader != key[i]:
                raise ValueError("a set came before its leader")
            common = len(np.intersect1d(tokens, t, assume_unique=True))
            if 100 * common >= 75 * (len(tokens) + len(t) - common):
                a.append(key[i][0])
                c.append(sid[i])
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(c, pa.int64())], ["a", "b"])


def filter_pairs(pairs: DataFrame, reps: DataFrame) -> DataFrame:
    """(x, y, near) of the pairs whose parity bitmaps allow a link. ``reps``: (sid, n, bits)."""
    x = reps.select(F.col("sid").alias("x"), F.col("n").alias("n_x"), F.col("bits").alias("bits_x"))
    y = reps.select(F.col("sid").alias("y"), F.col("n").alias("n_y"), F.col("bits").alias("bits_y"))
    both = pairs.join(x, "x").join(y, "y").select("x", "y", "n_x", "bits_x", "n_y", "bits_y")
    return both.mapInArrow(_may_overlap, "x long, y long, near double")


def leader_pairs(lists: DataFrame, reps: DataFrame, tested: DataFrame | None, turn: int, store: SharedStore) -> DataFrame:
    """(x, y): each set y with the nearest leader x of its lists (token, sid, n, pos, g) that may link.

    The first turn's leaders are the lists' smallest sets; later ones are drawn by hash.
    """
    order = F.col("n").cast("long") if turn == 0 else F.xxhash64("sid", F.lit(turn))
    heads = lists.groupBy("token").agg(F.min(F.struct(order.alias("o"), "sid", "n", "pos", "g")).alias("lead"), F.count("*").alias("rows"))
    led = spread_join(lists, store.write(heads, f"heads{turn}"), ["token"], "rows", ["sid"]).where("g <> lead.g")
    ahead = (F.col("lead.n") < F.col("n")) | ((F.col("lead.n") == F.col("n")) & (F.col("lead.sid") < F.col("sid")))
    pick = lambda c, first: F.when(ahead if first else ~ahead, F.col(f"lead.{c}")).otherwise(F.col(c))
    small, large = ({c: pick(c, first) for c in ("n", "pos")} for first in (True, False))
    fits = ((small["pos"] < 0) | _indexed(small["n"], small["pos"])) & _may_link(small["n"], small["pos"], large["n"], large["pos"])
    pairs = led.where(fits).select(F.col("lead.sid").alias("x"), F.col("sid").alias("y")).distinct()
    if tested is not None:
        pairs = pairs.join(tested, ["x", "y"], "left_anti")
    best = filter_pairs(pairs, reps).groupBy("y").agg(F.max(F.struct("near", "x")).alias("best"))
    return best.select("best.x", "y")


def linked_lists(lists: DataFrame, reps: DataFrame, texts: DataFrame, store: SharedStore) -> DataFrame:
    """Links (a, b) that join all groups within lists (token, sid, n, pos, g) that some link joins.

    Pairs stay in their units: a unit first names its sets that are in any pair, then gets their texts.
    """
    heads = lists.groupBy("token").agg(F.min("sid").alias("lead"), F.count("*").alias("rows"))
    sized = spread_join(lists, store.write(heads, "heads-rest"), ["token"], "rows", ["sid"]).withColumns(
        {"blocks": F.ceil(F.col("rows") / F.lit(BLOCK)).cast("int"), "salt": F.pmod("token", F.lit(LIST_TASKS))}
    )
    dealt = sized.withColumn("block", F.pmod(F.xxhash64("sid"), F.col("blocks")).cast("int")).withColumn(
        "other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    )
    units = dealt.join(reps.select("sid", "bits"), "sid").select(
        "token", F.least("block", "other").alias("bi"), F.greatest("block", "other").alias("bj"), "sid", "n", "pos", "g", "bits", "block", "lead", "salt"
    )
    # lists with one smallest id mostly hold the same sets: a few tasks for them instead of one a
    # token let a task see, and drop, most repeats of a pair
    ordered = units.repartition("lead", "salt", "bi", "bj").drop("lead", "salt").sortWithinPartitions("token", "bi", "bj")
    unit = "token long, bi int, bj int, sid long, n int, pos int, g long, bits binary, block int"
    paired = store.write(ordered.mapInArrow(_paired_sets, unit), "paired")
    store.release()
    cols = ["token", "bi", "bj", "sid", "n", "pos", "g", "bits", "block"]
    wanted = paired.join(reps.select("sid", "doc_id", "h"), "sid").select(*cols, "doc_id", "h")
    found = texts.join(wanted, anchors.same_row(texts, wanted)).select(*cols, "text")
    return found.repartition("token", "bi", "bj").sortWithinPartitions("token", "bi", "bj").mapInArrow(_linked_sets, "a long, b long")


def verify_pairs(pairs: DataFrame, reps: DataFrame, texts: DataFrame, store: SharedStore, name: str) -> DataFrame:
    """The linked ones (a, b) of ``pairs`` (x, y). ``reps``: (sid, doc_id, h); ``texts``: (doc_id, h, text)."""
    sizes = store.write(pairs.groupBy("x").agg(F.count("*").alias("rows")), f"sizes-{name}")
    dealt = spread_join(pairs, sizes, ["x"], "rows", ["y"])
    dealt = dealt.withColumn("part", F.pmod(F.xxhash64("y"), F.ceil(F.col("rows") / F.lit(CHUNK))))
    rows = dealt.select("x", "part", F.lit(1).alias("role"), F.col("y").alias("sid")).unionByName(
        dealt.select("x", "part").distinct().select("x", "part", F.lit(0).alias("role"), F.col("x").alias("sid"))
    )
    wanted = rows.join(reps, "sid").select("doc_id", "h", "x", "part", "role", "sid")
    found = texts.join(wanted, anchors.same_row(texts, wanted)).select("x", "part", "role", "sid", "text")
    ordered = found.repartition("x", "part").sortWithinPartitions("x", "part", "role")
    return ordered.mapInArrow(_check, "a long, b long")


def jaccard_components(docs: DataFrame, store: SharedStore) -> DataFrame:
    """(doc_id, h, n_shingles, component_id, group) for every row of ``docs`` (doc_id, text).

    ``h``: :func:`anchors.row_key`. ``group``: a key of the component, null for rows without shingles.
    """
    spark = docs.sparkSession
    ship(spark)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), anchors.row_key().alias("h"), "text")
    summary = store.write(texts.mapInArrow(_summary, "kind int, id long, h long, n long, sid long, bits binary"), "summary")
    members = summary.where("kind = 0").select(F.col("id").alias("doc_id"), "h", F.col("n").alias("n_shingles"), "sid")
    own_sets = summary.where("kind = 0 and n > 0").groupBy("sid")
    place = F.min(F.struct("id", "h"))
    reps = own_sets.agg(place.alias("at"), F.min("id").alias("low"), F.first("n").alias("n"), F.first("bits").alias("bits"))
    reps = store.write(reps.select("sid", F.col("at.id").alias("doc_id"), "at.h", "low", "n", "bits"), "reps")
    sets = reps.count()
    small = reps.where(F.col("n") <= MAX_LIGHT).groupBy("n").agg(F.count("*").alias("c")).collect()
    boundary = choose_boundary({r["n"]: r["c"] for r in small})
    total = members.count()
    hot = (
        summary.where("kind = 1").groupBy("id").agg(F.sum("n").alias("n")).where(F.col("n") >= max(8, FREQUENT_SHARE * total)).select("id")
    )
    frequent = np.zeros(CELLS, bool)  # at most CELLS ids, whatever the input
    frequent[[r["id"] for r in hot.collect()]] = True
    shared = spark.sparkContext.broadcast(np.packbits(frequent))
    if sets == 0:
        return members.select("doc_id", "h", "n_shingles", F.col("doc_id").alias("component_id"), F.lit(None).cast("long").alias("group"))

    rows = texts.select("text").mapInArrow(
        lambda it: _prefix_rows(boundary, np.unpackbits(shared.value).astype(bool), it), "token long, sid long, n int, pos int, often boolean"
    )
    # a list of one set gives nothing; those of frequent shingles are dealt by set and kept as they are
    deal = F.when(F.col("often"), 1 + F.pmod(F.xxhash64("sid"), F.lit(max(16, total // DEALT_SETS)))).otherwise(0)
    own = Window.partitionBy("token", "deal")
    lists = store.write(
        rows.withColumn("deal", deal.cast("int"))
        .repartition("token", "deal")
        .withColumn("lo", F.min("sid").over(own))
        .withColumn("hi", F.max("sid").over(own))
        .where("lo < hi or deal > 0")
        .dropDuplicates(["token", "deal", "sid"])
        .select("token", "sid", "n", "pos", F.col("sid").alias("g")),
        "lists",
    )
    store.release()
    places = reps.select("sid", "doc_id", "h")
    edges = tested = None
    for turn in range(LEADER_ROUNDS):
        pairs = store.write(leader_pairs(lists, reps, tested, turn, store), f"leaders{turn}")
        if pairs.isEmpty():
            break
        store.release()
        found = store.write(verify_pairs(pairs, places, texts, store, str(turn)), f"edges{turn}")
        store.release()
        both = pairs.unionByName(pairs.select(F.col("y").alias("x"), F.col("x").alias("y")))
        tested = both if tested is None else tested.unionByName(both)
        edges = found if edges is None else edges.unionByName(found)
        groups = store.write(connected_components(edges, store, f"cc{turn}"), f"groups{turn}")
        tagged = lists.drop("g").join(groups.withColumnRenamed("node", "sid"), "sid", "left").withColumn("g", F.coalesce("component", "sid"))
        tagged = store.write(tagged.select("token", "sid", "n", "pos", "g"), f"tagged{turn}")
        # lists within one group can give no more
        live = tagged.groupBy("token").agg(F.min("g").alias("lo"), F.max("g").alias("hi"), F.count("*").alias("rows")).where("lo < hi")
        live = store.write(live.select("token", "rows"), f"live{turn}")
        lists = store.write(spread_join(tagged, live, ["token"], "rows", ["sid"]).drop("rows"), f"lists{turn}")
        store.drop("lists" if turn == 0 else f"lists{turn - 1}", f"tagged{turn}", f"live{turn}", f"heads{turn}", f"groups{turn}", f"sizes-{turn}")
    found = store.write(linked_lists(lists, reps, texts, store), "edges-rest")
    edges = found if edges is None else edges.unionByName(found)
    store.release()
    final = connected_components(edges, store, "cc2").withColumnRenamed("node", "sid").withColumnRenamed("component", "group")
    named = reps.select("sid", "low").join(final, "sid", "left").withColumn("group", F.coalesce("group", "sid"))
    named = store.write(named, "named")
    by_set = store.write(named.groupBy("group").agg(F.min("low").alias("component_id"), F.count("*").alias("sets")), "components")
    by_set = spread_join(named, by_set, ["group"], "sets", ["sid"]).select("sid", "group", "component_id")
    sized = store.write(by_set.join(members.groupBy("sid").agg(F.count("*").alias("rows")), "sid"), "by_set_sized")
    empty = members.where("n_shingles = 0").select(
        "doc_id", "h", "n_shingles", F.col("doc_id").alias("component_id"), F.lit(None).cast("long").alias("group")
    )
    filled = spread_join(members.where("n_shingles > 0"), sized, ["sid"], "rows", ["doc_id", "h"])
    out = store.write(filled.select("doc_id", "h", "n_shingles", "component_id", "group").unionByName(empty), "result")
    store.keep("result")
    return out


def op10_size_aware_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return jaccard_components(docs, SharedStore(spark, "jaccard")).select("doc_id", "n_shingles", "component_id")


def one_per_component(docs: DataFrame) -> DataFrame:
    """One document of every component, that with the smallest id (then hash), and all without shingles; same columns.

    Rows that repeat an id and a text are one document: one of them stays.
    """
    cols = docs.columns
    found = jaccard_components(docs.select("doc_id", "text"), SharedStore(docs.sparkSession, "jaccard"))
    first = found.where("group is not null").groupBy("group").agg(F.min(F.struct(F.isnull("doc_id").alias("none"), "doc_id", "h")).alias("k"))
    kept = first.select("k.doc_id", "k.h").unionByName(found.where("group is null").select("doc_id", "h").distinct())
    key = {"_id": F.coalesce("doc_id", F.lit(0).cast("long")), "_none": F.isnull("doc_id")}
    kept = kept.select(*[e.alias(k) for k, e in key.items()], F.col("h").alias("_h"))
    row = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in cols]).alias("_row"), F.col("doc_id").cast("long").alias("doc_id"), anchors.row_key().alias("_h")
    )
    row = row.select("_row", *[e.alias(k) for k, e in key.items()], "_h")
    names = ["_id", "_none", "_h"]
    return row.join(kept, names, "left_semi").dropDuplicates(names).select(*[F.col(f"_row.`{c}`").alias(c) for c in cols])
