"""Near-duplicate vectors: p-stable Euclidean hashing with exact cosine checks.

Unit vectors with cosine c lie sqrt(2 - 2c) apart. A table's key is a run of quantised
Gaussian projections floor((a.x + b) / width); with the table sizes of :func:`plan_tables`
a pair at the threshold shares a bucket in some table with probability ``RECALL``, closer
pairs almost surely. Equal vectors are folded first and weigh as many as they are. Vectors of
one length only meet each other: the length is part of a bucket's key.

Hashing writes (table, bucket, node) rows only; the buckets' sizes come from them. Buckets are
cut into blocks of bounded size, every pair of blocks is one unit of work, so no bucket has
to fit one task and none is capped, and only now a vector joins the rows that need it. A pair
that meets in several tables counts in the first one only: a row carries the vector's
keys in the tables before its own. A unit returns, per vector, its link count and a
local component root; roots are then merged by :mod:`components`.

Few tables with large buckets cost less than many with small ones: a bucket's vectors are
compared by one matrix product, while each table moves every vector once.

Defined results: null, empty or zero vectors and vectors with null or non-finite components
link with nothing; norms neither overflow nor underflow, as vectors are scaled by their largest
component first; rows that repeat a vec_id are vectors of their own, and a row without an
id links as any other (its component is named by the smallest id in it, null if none); vectors
of any length are linked with those of that length; ties go to the smallest id; an empty
table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.llm import bytehash as bh
from rulecredit.llm.components import connected_components
from rulecredit.llm.runtime import SharedStore, ship, spread_join

THRESHOLD = 0.9
WIDTH = 2.0
RECALL = 0.96
#: Unrelated vectors expected in a bucket, and vectors in a block.
BACKGROUND, BLOCK = 1024, 1024
SEED = 20240229


def collision(distance: float, width: float = WIDTH) -> float:
    """Probability that one quantised Gaussian projection agrees at a distance."""
    c = width / distance
    below = 0.5 * math.erfc(c / math.sqrt(2))
    return 1 - 2 * below - 2 / (math.sqrt(2 * math.pi) * c) * (1 - math.exp(-c * c / 2))


def plan_tables(n: int, threshold: float = THRESHOLD) -> tuple[int, int]:
    """(projections per table, tables) for n vectors."""
    near, far = collision(math.sqrt(2 - 2 * threshold)), collision(math.sqrt(2))
    k = max(4, round(math.log(max(n, 2) / BACKGROUND) / -math.log(far)))
    return k, math.ceil(math.log(1 - RECALL) / math.log(1 - near**k))


def _unit_rows(column: pa.Array) -> tuple[np.ndarray, list[np.ndarray]]:
    """(row numbers, unit vectors in double) of the valid vectors."""
    keep, rows = [], []
    for i, v in enumerate(column.to_pylist()):
        if v is None or any(x is None for x in v):
            continue
        x = np.array(v, np.float64)
        most = np.abs(x).max(initial=0.0)
        if np.isfinite(most) and most > 0:
            x /= most
            keep.append(i)
            rows.append(x / np.sqrt(np.dot(x, x)))
    return np.array(keep, np.int64), rows


def _signatures(x: np.ndarray, k: int, tables: int) -> np.ndarray:
    """Bucket key of each vector in each table."""
    rng = np.random.default_rng((SEED, x.shape[1]))
    planes = rng.standard_normal((x.shape[1], k * tables))
    shift = rng.uniform(0, WIDTH, k * tables)
    cells = np.floor((x @ planes + shift) / WIDTH).astype(np.int64).view(np.uint64).reshape(len(x), tables, k)
    out = np.full((len(x), tables), x.shape[1], np.uint64)
    for j in range(k):
        out = bh.mix(out * bh.U(31) + cells[:, :, j])
    return out.view(np.int64)


def _hash_rows(k: int, tables: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, weight, x, keys) of rows (node, weight, v): unit vectors and their keys in all tables."""
    for b in batches:
        keep, rows = _unit_rows(b.column(2))
        keys: list[bytes] = [b""] * len(rows)
        sizes = np.array([len(x) for x in rows], np.int64)
        for d in np.unique(sizes).tolist():
            here = np.flatnonzero(sizes == d).tolist()
            for i, sig in zip(here, _signatures(np.stack([rows[i] for i in here]), k, tables)):
                keys[i] = sig.tobytes()
        at = pa.array(keep)
        vectors = pa.array([x.tobytes() for x in rows], pa.binary())
        yield pa.RecordBatch.from_arrays([b.column(0).take(at), b.column(1).take(at), vectors, pa.array(keys, pa.binary())], ["node", "weight", "x", "keys"])


def _buckets(tables: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(t, bucket, node) of rows (node, keys)."""
    for b in batches:
        sigs = np.array([np.frombuffer(x, np.int64) for x in b.column(1).to_pylist()], np.int64).reshape(-1, tables)
        for t in range(tables):
            cols = [pa.array(np.full(len(sigs), t, np.int32)), pa.array(sigs[:, t]), b.column(0)]
            yield pa.RecordBatch.from_arrays(cols, ["t", "bucket", "node"])


class _Unit:
    """Two blocks of a bucket (or one with itself) gathered from sorted rows."""

    def __init__(self, key: tuple):
        self.key, self.rows = key, []

    def links(self) -> Iterator[tuple[int, int, int]]:
        """(node, links found here first, root) of the unit's linked vectors."""
        for size in sorted({len(r[2]) for r in self.rows}):
            yield from self._links(sorted(r for r in self.rows if len(r[2]) == size))

    def _links(self, rows: list[tuple]) -> Iterator[tuple[int, int, int]]:
        t, _, bi, bj = self.key
        ids = np.array([r[0] for r in rows], np.int64)
        weight = np.array([r[1] for r in rows], np.int64)
        x = np.array([np.frombuffer(r[2], np.float64) for r in rows])
        sigs = np.array([np.frombuffer(r[3], np.int64) for r in rows])
        block = np.array([r[4] for r in rows])
        n = len(ids)
        count = np.zeros(n, np.int64)
        root = np.arange(n)
        for a in range(0, n, 256):
            near = x[a : a + 256] @ x.T >= THRESHOLD
            i, j = np.nonzero(near)
            i += a
            ok = i < j
            if bi != bj:
                ok &= block[i] != block[j]
            i, j = i[ok], j[ok]
            if t and len(i):
                met = np.zeros(len(i), bool)
                for u in range(t):
                    met |= sigs[i, u] == sigs[j, u]
                i, j = i[~met], j[~met]
            count += np.bincount(i, weight[j], n).astype(np.int64) + np.bincount(j, weight[i], n).astype(np.int64)
            # hook each vector to its smallest partner; chains are flattened below
            while len(i):
                ri, rj = root[i], root[j]
                live = ri != rj
                if not live.any():
                    break
                i, j, ri, rj = i[live], j[live], ri[live], rj[live]
                np.minimum.at(root, np.maximum(ri, rj), np.minimum(ri, rj))
                while True:
                    flat = root[root]
                    if (flat == root).all():
                        break
                    root = flat
        for q in np.flatnonzero(count).tolist():
            yield int(ids[q]), int(count[q]), int(ids[root[q]])


def _link_units(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (t, bucket, bi, bj); one unit is in memory at a time."""
    unit: _Unit | None = None
    out: list[tuple[int, int, int]] = []

    def flush() -> pa.RecordBatch:
        cols = list(zip(*out)) if out else [[], [], []]
        batch = pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in cols], ["node", "n", "root"])
        out.clear()
        return batch

    for b in batches:
        cols = [c.to_pylist() for c in b.columns]
        for t, bucket, bi, bj, vec, weight, x, sigs, block in zip(*cols):
            key = (t, bucket, bi, bj)
            if unit is None or unit.key != key:
                if unit is not None and len(unit.rows) > 1:
                    out.extend(unit.links())
                unit = _Unit(key)
            unit.rows.append((vec, weight, x, sigs, block))
        if len(out) > 10_000:
            yield flush()
    if unit is not None and len(unit.rows) > 1:
        out.extend(unit.links())
    yield flush()


def link_vectors(vectors: DataFrame, vec_id: str = "vec_id", column: str = "embedding") -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of ``vectors``."""
    spark = vectors.sparkSession
    ship(spark)
    store = SharedStore(spark, "vectors")
    rows = vectors.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(column).cast("array<double>").alias("v"))
    zero = F.lit(0.0)
    bad = F.exists("v", lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == float("inf")))
    valid = F.coalesce(~bad & F.exists("v", lambda e: e != zero), F.lit(False))
    v = F.when(valid, F.transform("v", lambda e: F.when(e == zero, zero).otherwise(e)))
    # two hashes of a vector stand for it where its 64 and more numbers would be a join key
    keyed = rows.select("vec_id", v.alias("v")).withColumns({"k1": F.xxhash64("v"), "k2": F.xxhash64(F.lit(1), "v")})
    # equal vectors: one representative with their number
    folded = store.write(
        keyed.where("v is not null").groupBy("v").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight"), F.first("k1").alias("k1"), F.first("k2").alias("k2")),
        "folded",
    )
    # a node is known by its smallest id, or by a hash where other vectors have that id too
    shared = folded.groupBy("rep").agg(F.count("*").alias("same")).where("same > 1 or rep is null").select(F.col("rep").alias("_rep"), "same")
    node = F.when(F.col("same").isNull(), F.col("rep")).otherwise(F.col("k1"))
    nodes = folded.join(shared, F.col("rep").eqNullSafe(F.col("_rep")), "left").withColumn("node", node).drop("same", "_rep")
    k, tables = plan_tables(folded.count())
    reps = nodes.select("node", "weight", "v").mapInArrow(lambda it: _hash_rows(k, tables, it), "node long, weight long, x binary, keys binary")
    reps = store.write(reps, "reps")
    hashed = store.write(reps.select("node", "keys").mapInArrow(lambda it: _buckets(tables, it), "t int, bucket long, node long"), "hashed")
    sizes = store.write(hashed.groupBy("t", "bucket").agg(F.count("*").alias("n")).where("n > 1"), "sizes")
    placed = spread_join(hashed, sizes, ["t", "bucket"], "n", ["node"])
    blocks = F.ceil(F.col("n") / BLOCK).cast("int")
    own = F.pmod(F.xxhash64("node", "t"), blocks).cast("int")
    units = placed.withColumn("block", own).withColumn("o", F.explode(F.sequence(F.lit(0), blocks - 1)))
    units = units.select("t", "bucket", F.least("block", "o").alias("bi"), F.greatest("block", "o").alias("bj"), "node", "block")
    before = F.substring("keys", F.lit(1), F.col("t") * 8)  # of the tables before this one
    full = units.join(reps, "node").select("t", "bucket", "bi", "bj", "node", "weight", "x", before.alias("keys"), "block")
    ordered = full.repartition("t", "bucket", "bi", "bj").sortWithinPartitions("t", "bucket", "bi", "bj")
    found = store.write(ordered.mapInArrow(_link_units, "node long, n long, root long"), "found")
    store.drop("hashed", "sizes", "reps")
    store.release()
    parts = connected_components(found.select(F.col("node").alias("a"), F.col("root").alias("b")), store)
    links = found.groupBy("node").agg(F.sum("n").alias("n"))
    named = nodes.select("node", "rep", "weight", "k1", "k2").join(links, "node", "left").join(parts, "node", "left")
    named = store.write(named.withColumn("component", F.coalesce("component", "node")), "named")
    low = store.write(named.groupBy("component").agg(F.min("rep").alias("component_id"), F.count("*").alias("members")), "low")
    per_rep = spread_join(named, low, ["component"], "members", ["node"])
    n_links = (F.coalesce("n", F.lit(0)) + F.col("weight") - 1).cast("long")
    per_rep = store.write(per_rep.select("k1", "k2", "weight", n_links.alias("n_links"), "component_id"), "per_rep")
    linked = spread_join(keyed.where("v is not null").drop("v"), per_rep, ["k1", "k2"], "weight", ["vec_id"]).select("vec_id", "n_links", "component_id")
    alone = keyed.where("v is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    store.keep("per_rep")
    done = linked.unionByName(alone)
    return done.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op7_pstable_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
