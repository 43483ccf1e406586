"""BPE encoding with reuse of content-defined chunks.

1. A rolling hash cuts each text into chunks wherever 32 bytes hash to a multiple of about
   1,000, so equal passages are cut alike wherever they stand; a text without a cut is one chunk.
   A first pass counts chunks by a 128-bit key.
2. The chunks that most texts share, up to ``SHARED_BYTES`` of them, are encoded once for all: each
   where it first occurs. Their ids, with the pre-token borders near both ends, are broadcast; the
   bound holds whatever the input.
3. The other shared chunks are encoded once where they meet: texts are rebalanced by their smallest
   chunk key, and a task keeps the chunks it has encoded (bounded). Sending every chunk's ids to every
   text that holds it would move more bytes than the texts have.
4. A text is encoded from left to right: known chunks bring their ids, others are encoded
   where they stand. At each chunk join the last pre-tokens of the left chunk are dropped
   and the text is re-encoded until a pre-token border agrees with one of the right
   chunk; from there on both encodings are the same, as the pre-tokenizer looks ahead only. If none
   agrees near the join, the right chunk is encoded with it. So the whole text's ids are exact.

Texts travel compressed. Decoding maps ids back to bytes and decodes as the library does.

Defined results: null and empty texts have no ids; texts with a special token's string go
to the library whole; every row is a text of its own, whatever ids repeat or are null; repeated rows
are encoded alike; chunks shared by equally many texts are taken in the order of their keys; a very long text is one
row of one task and many chunks; an empty table gives an empty result; columns other than the two
named are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.llm import anchors
from rulecredit.llm import bytehash as bh
from rulecredit.llm.bpe import ExactEncoder, default_path, load, sha256
from rulecredit.llm.runtime import SharedStore, ship

GRAM, MEAN_CHUNK, MIN_CHUNK = 32, 1024, 256
#: Text of the chunks encoded once for all, and how many of them are looked at; chunk text a task remembers.
SHARED_BYTES, SHARED_CHUNKS, MEMO_BYTES = 12 << 20, 20_000, 8 << 20
#: Pre-tokens whose borders are known at a chunk's start and end, and characters of the right chunk a join may re-encode.
HEAD, TAIL, LOOK = 24, 4, 256
#: Pre-tokens at a chunk's end that following text may change: a blank run, or a contraction's parts.
UNSURE = 3

CHUNKS = "doc_id long, h long, at int, size int, k1 long, k2 long"


def cut_points(buf: bh.Buffer) -> list[np.ndarray]:
    """For each text the chunk borders strictly inside it, as byte offsets on character borders."""
    n = len(buf.data)
    out = [np.zeros(0, np.int64)] * (len(buf.offs) - 1)
    if n <= GRAM:
        return out
    prefix = buf.prefix()
    at = np.arange(n - GRAM, dtype=np.int64)
    h = bh.range_hash(prefix, at, at + GRAM)
    cuts = at[(h & bh.U(MEAN_CHUNK - 1)) == 0] + GRAM
    while True:
        inside = (buf.data[cuts] & 0xC0) == 0x80 if len(cuts) else np.zeros(0, bool)
        if not inside.any():
            break
        cuts = np.where(inside, cuts + 1, cuts)
        cuts = cuts[cuts < n]
    cuts = np.unique(cuts)
    lo = np.searchsorted(cuts, buf.offs[:-1] + GRAM, "left")
    hi = np.searchsorted(cuts, buf.offs[1:], "left")
    for i, (a, b) in enumerate(zip(lo, hi)):
        if b > a:
            kept, last = [], int(buf.offs[i])
            for c in cuts[a:b].tolist():
                if c - last >= MIN_CHUNK:
                    kept.append(c)
                    last = c
            out[i] = np.array(kept, np.int64) - buf.offs[i]
    return out


class Chunk:
    """A chunk's own encoding: ids (4 bytes each), pre-tokens, and (character, id) places of the borders near its ends."""

    __slots__ = ("n", "head", "tail", "ids")

    def __init__(self, n: int, head: list[tuple[int, int]], tail: list[tuple[int, int]], ids: bytes):
        self.n, self.head, self.tail, self.ids = n, head, tail, ids

    @staticmethod
    def of(text: str, encoder: ExactEncoder) -> Chunk:
        pieces = encoder.split(text)
        coded = [encoder.memo[p] for p in pieces]
        places, at, done = [(0, 0)], 0, 0
        for p, c in zip(pieces, coded):
            at += len(p)
            done += len(c)
            places.append((at, done))
        return Chunk(len(pieces), places[: HEAD + 1], places[-TAIL - 1 :], b"".join(coded))

    def place(self, i: int) -> tuple[int, int]:
        """(character, id) where pre-token i starts; i near an end."""
        return self.head[i] if i < len(self.head) else self.tail[i - self.n - 1]

    def pack(self) -> bytes:
        numbers = [self.n, len(self.head), len(self.tail), *(x for p in self.head + self.tail for x in p)]
        return np.array(numbers, "<u4").tobytes() + self.ids

    @staticmethod
    def unpack(raw: bytes) -> Chunk:
        n, head, tail = np.frombuffer(raw, "<u4", 3).tolist()
        places = list(map(tuple, np.frombuffer(raw, "<u4", 2 * (head + tail), 12).reshape(-1, 2).tolist()))
        return Chunk(n, places[:head], places[head:], raw[12 + 8 * (head + tail) :])


class ChunkEncoder:
    """Encodes texts by chunks. ``known``: packed chunks by key, encoded elsewhere."""

    def __init__(self, encoder: ExactEncoder, known: dict[bytes, bytes] | None = None):
        self.encoder, self.known = encoder, known or {}
        self.memo: dict[bytes, Chunk] = {}
        self.held = self.encoded = self.reused = self.joined = 0

    def encode(self, raw: bytes, cuts: np.ndarray) -> bytes:
        """Ids of a text cut at ``cuts``."""
        if not self.encoder.in_pieces(raw.decode()):
            return self.encoder.encode(raw.decode())
        bounds = [0, *cuts.tolist(), len(raw)]
        out: list[bytes] = []
        left, text, start = self._chunk(raw[: bounds[1]]), raw[: bounds[1]].decode(), 0
        for a, b in zip(bounds[1:], bounds[2:]):
            right, right_text = self._chunk(raw[a:b]), raw[a:b].decode()
            keep = max(start, left.n - UNSURE)
            (at, done), begun = left.place(keep), left.place(start)[1]
            out.append(left.ids[begun:done])
            fresh, agreed = self._join(text[at:], right, right_text)
            if agreed is None:  # no agreement in time: the join and the right chunk become one chunk
                text = text[at:] + right_text
                left, start = Chunk.of(text, self.encoder), 0
                self.joined += 1
            else:
                out.extend(fresh)
                left, text, start = right, right_text, agreed
        out.append(left.ids[left.place(start)[1] :])
        return b"".join(out)

    def _chunk(self, raw: bytes) -> Chunk:
        key = xxhash.xxh3_128_digest(raw)
        made = self.memo.get(key)
        if made is None:
            code = self.known.get(key)
            made = Chunk.of(raw.decode(), self.encoder) if code is None else Chunk.unpack(code)
            self.encoded += code is None
            self.reused += code is not None
            if self.held > MEMO_BYTES:
                self.memo.clear()
                self.held = 0
            self.held += len(raw)
            self.memo[key] = made
        else:
            self.reused += 1
        return made

    def _join(self, pending: str, right: Chunk, right_text: str) -> tuple[list[bytes], int | None]:
        """Ids from the pending text on up to the first border that agrees with one of ``right``, and that border's pre-token."""
        size, at = len(pending), 0
        where = {p[0]: i for i, p in enumerate(right.head)}
        fresh: list[bytes] = []
        for piece in self.encoder.split(pending + right_text[:LOOK])[:-UNSURE]:
            at += len(piece)
            fresh.append(self.encoder.memo[piece])
            agreed = where.get(at - size) if at >= size else None
            if agreed is not None:
                return fresh, agreed if agreed <= right.n - UNSURE else None
        return fresh, None


def _chunk_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """CHUNKS of rows (doc_id, h, text)."""
    for batch in batches:
        for buf in bh.slices(batch.column(2)):
            rows: list[int] = []
            cols: tuple[list, list, list, list] = ([], [], [], [])
            for i, cuts in enumerate(cut_points(buf)):
                raw = buf.text(i)
                if not raw:
                    continue
                bounds = [0, *cuts.tolist(), len(raw)]
                for a, b in zip(bounds, bounds[1:]):
                    key = xxhash.xxh3_128_intdigest(raw[a:b])
                    rows.append(buf.first + i)
                    for col, v in zip(cols, (a, b - a, key >> 64, key & (1 << 64) - 1)):
                        col.append(v)
            at = pa.array(rows, pa.int64())
            keys = [pa.array(bh.signed(np.array(c, np.uint64))) for c in cols[2:]]
            sizes = [pa.array(c, pa.int32()) for c in cols[:2]]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), *sizes, *keys], ["doc_id", "h", "at", "size", "k1", "k2"])


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, affinity, compressed text) of rows (doc_id, text)."""
    zip_ = zstandard.ZstdCompressor(level=1)
    for batch in batches:
        ids, column = batch.column(0), batch.column(1)
        for buf in bh.slices(column):
            cuts, prefix = cut_points(buf), buf.prefix()
            keys = np.zeros(len(cuts), np.uint64)
            for i, c in enumerate(cuts):
                bounds = np.concatenate([[0], c, [buf.offs[i + 1] - buf.offs[i]]]).astype(np.int64) + buf.offs[i]
                keys[i] = bh.range_hash(prefix, bounds[:-1], bounds[1:]).min()
            packed = [zip_.compress(buf.text(i)) for i in range(len(cuts))]
            yield pa.RecordBatch.from_arrays(
                [ids.slice(buf.first, len(cuts)), pa.array(bh.signed(keys)), pa.array(packed, pa.binary())], ["doc_id", "affinity", "packed"]
            )


def _encode_shared(path: str, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, code) of rows (text, want)."""
    encoder = load(path)
    for batch in batches:
        keys: list[bytes] = []
        codes: list[bytes] = []
        for text, want in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            if not encoder.in_pieces(text):
                continue  # the library takes such texts whole
            raw = text.encode()
            for w in want:
                chunk = raw[w["at"] : w["at"] + w["size"]]
                keys.append(xxhash.xxh3_128_digest(chunk))
                codes.append(Chunk.of(chunk.decode(), encoder).pack())
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(codes, pa.binary())], ["key", "code"])


def shared_codes(texts: DataFrame, path: str, store: SharedStore) -> dict[bytes, bytes]:
    """Packed chunks by key: the most shared ones of (doc_id, h, text), at most SHARED_BYTES of text, each encoded once."""
    chunks = texts.where("text <> ''").mapInArrow(_chunk_rows, CHUNKS)
    first = F.min(F.struct("doc_id", "h", "at", "size")).alias("first")
    counted = chunks.groupBy("k1", "k2").agg(F.count("*").alias("n"), first).where("n > 1")
    top = counted.where(F.col("first.size") <= 16 * MEAN_CHUNK).orderBy(F.desc("n"), "k1", "k2").limit(SHARED_CHUNKS).select("first.*").collect()
    room = np.searchsorted(np.cumsum([r["size"] for r in top]), SHARED_BYTES, "right") if top else 0
    if not room:
        return {}
    places = texts.sparkSession.createDataFrame([tuple(r) for r in top[:room]], "doc_id long, h long, at int, size int")
    wanted = store.write(places.groupBy("doc_id", "h").agg(F.collect_set(F.struct("at", "size")).alias("want")), "wanted")
    held = texts.join(F.broadcast(wanted), anchors.same_row(texts, wanted)).select("text", "want")  # SHARED_CHUNKS rows at most
    codes = held.mapInArrow(lambda it: _encode_shared(path, it), "key binary, code binary").dropDuplicates(["key"])
    out = {bytes(r["key"]): bytes(r["code"]) for r in codes.collect()}
    store.keep()
    return out


def _encoded(path: str, known: dict[bytes, bytes], batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, ExactEncoder, list[np.ndarray]]]:
    """Each batch of (doc_id, affinity, packed) with its texts' ids."""
    encoder, unzip = ChunkEncoder(load(path), known), zstandard.ZstdDecompressor()
    for batch in batches:
        raws = [unzip.decompress(x) for x in batch.column(2).to_pylist()]
        ids = []
        for buf in bh.slices(pa.array(raws, pa.binary())):
            ids += [np.frombuffer(encoder.encode(buf.text(i), cuts), "<u4") for i, cuts in enumerate(cut_points(buf))]
        yield batch, encoder.encoder, ids


def _digest(path: str, known: dict[bytes, bytes], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, encoder, ids in _encoded(path, known, batches):
        cols = (
            pa.array([len(x) for x in ids], pa.int64()),
            pa.array([sha256(encoder.ids_text(x).encode()) for x in ids], pa.string()),
            pa.array([sha256(encoder.decode(x).encode()) for x in ids], pa.string()),
        )
        yield pa.RecordBatch.from_arrays([batch.column(0), *cols], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def _ids(path: str, known: dict[bytes, bytes], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, _, ids in _encoded(path, known, batches):
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x.astype(np.int32) for x in ids], pa.list_(pa.int32()))], ["doc_id", "ids"])


def _by_chunks(docs: DataFrame, path: str, task, schema: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Rows of ``task`` over the rebalanced texts, the shared chunks' codes at hand."""
    spark = docs.sparkSession
    ship(spark)
    texts = docs.select(F.col(f"`{doc_id}`").cast("long").alias("doc_id"), F.col(f"`{text}`").alias("text"))
    keyed = texts.select("doc_id", F.xxhash64("text").alias("h"), "text")
    known = spark.sparkContext.broadcast(shared_codes(keyed, path, SharedStore(spark, "chunks")))
    packed = texts.mapInArrow(_pack, "doc_id long, affinity long, packed binary").hint("rebalance", "affinity")
    return packed.mapInArrow(lambda it: task(path, known.value, it), schema)


def encode_documents(docs: DataFrame, path: str | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, ids): the exact ids of every text."""
    return _by_chunks(docs, path or default_path(), _ids, "doc_id long, ids array<int>", doc_id, text)


def decode_documents(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, ids)."""
    where = path or default_path()
    ship(encoded.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = load(where)
        for b in batches:
            texts = [encoder.decode(np.array(x or [], np.uint32)) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def op1_bpe_chunk_reuse(spark: SparkSession, sf_dir: str, path: str | None = None) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    return _by_chunks(docs, path or default_path(), _digest, schema)
