"""Token counts kept as delta-maintained rollups.

A batch is a frame of signed changes (+1 insert, -1 delete; a revision is the delete
of the old text and the insert of the new one). It is tokenised, summed by source,
language and tokenizer version, and written as one small table of its own.

A batch counts once its commit file, named by the batch id, exists. The file is created only
where there is none, which file systems do atomically: of two writers of one id, or of a replay
and the first run, one wins and the others' tables are dropped. Readers start at commit
files, so tables of lost or beaten writers are never seen.

``compact`` folds committed batches into a snapshot of running totals, with the ids
folded, and drops their tables; ``apply`` does so whenever ``COMPACT_AFTER`` batches wait. So
totals are the latest snapshot and a bounded number of deltas, whatever has been committed
before. A snapshot counts once its own numbered file exists; commit files of batches it
holds are ignored from then on, so a driver that dies in between changes nothing.

Defined results: null texts count as empty (one document, no tokens); null source or
language is a group of its own; groups whose documents are all deleted vanish from the
totals; repeated rows count each; an empty batch commits an empty table; a very long text is
counted whole by one task; other columns are not read, and ties cannot arise.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from urllib.parse import quote

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.llm.bpe import SAFE, SPLIT, default_path, load, ranks_file
from rulecredit.llm.runtime import SharedStore, ship

KEYS = ("source", "lang", "tokenizer")
SUMS = ("n_docs", "n_chars", "n_tokens")
ROLLUP = "source string, lang string, tokenizer string, n_docs long, n_chars long, n_tokens long"


class Counter:
    """Counts a text's tokens under one tokenizer file (``.json`` or ``.tiktoken``)."""

    LIMIT = 300_000

    def __init__(self, path: str):
        self.memo: dict[str, int] = {}
        if path.endswith(".json"):
            encoder = load(path)
            self.whole = lambda t: len(encoder.encode(t)) // 4
            self.piece = lambda p: len(encoder.memo[p]) // 4
            self.split = lambda t: encoder.split(t) if encoder.in_pieces(t) else None
        else:
            import public_tokenizers
            import tiktoken

            core = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks_file(path), special_tokens={})
            self.whole = self.piece = lambda t: len(core.encode_ordinary(t))
            self.split = lambda t: SPLIT.findall(t) if SAFE.fullmatch(t) else None

    def count(self, text: str) -> int:
        pieces = self.split(text)
        if pieces is None:
            return self.whole(text)
        memo, total = self.memo, 0
        for p in pieces:
            n = memo.get(p)
            if n is None:
                n = self.piece(p)
                if len(memo) >= self.LIMIT:
                    memo.clear()
                if len(p) <= 64:
                    memo[p] = n
            total += n
        return total


_counters: dict[str, Counter] = {}


def _count(versions: dict[str, str], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for path in versions.values():
        if path not in _counters:
            _counters[path] = Counter(path)
    for b in batches:
        sign = np.array(b.column(0).to_pylist(), np.int64)
        texts = [t or "" for t in b.column(3).to_pylist()]
        chars = np.array([len(t) for t in texts], np.int64)
        for name, path in versions.items():
            tokens = np.array([_counters[path].count(t) for t in texts], np.int64)
            cols = [b.column(1), b.column(2), pa.array([name] * len(texts), pa.string())]
            cols += [pa.array(sign * x, pa.int64()) for x in (np.ones_like(chars), chars, tokens)]
            yield pa.RecordBatch.from_arrays(cols, [*KEYS, *SUMS])


def count_changes(changes: DataFrame, versions: dict[str, str]) -> DataFrame:
    """Summed signed counts of ``changes`` (sign, source, lang, text) by KEYS."""
    ship(changes.sparkSession)
    rows = changes.select(F.col("sign").cast("long"), "source", "lang", "text").mapInArrow(
        lambda it: _count(versions, it), ROLLUP
    )
    return rows.groupBy(*KEYS).agg(*[F.sum(c).alias(c) for c in SUMS])


class TokenLedger:
    """Additive totals over committed batches below ``root``, a folder that all machines see."""

    #: Committed batches that may wait before they are folded into a snapshot.
    COMPACT_AFTER = 32

    def __init__(self, spark: SparkSession, root: str, versions: dict[str, str]):
        self.spark, self.root, self.versions = spark, root.rstrip("/"), versions

    def _at(self, name: str):
        """(file system, path) of a name below the root."""
        sc = self.spark.sparkContext
        path = sc._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")
        return path.getFileSystem(sc._jsc.hadoopConfiguration()), path

    def _names(self, folder: str) -> list[str]:
        fs, path = self._at(folder)
        return sorted(s.getPath().getName() for s in fs.listStatus(path)) if fs.exists(path) else []

    def _exists(self, name: str) -> bool:
        fs, path = self._at(name)
        return fs.exists(path)

    def _create(self, name: str, content: str) -> bool:
        """Create a small file; False where one of the name exists."""
        fs, path = self._at(name)
        try:
            out = fs.create(path, False)
        except Exception as e:  # the file system's word for "exists" differs
            if fs.exists(path):
                return False
            raise e
        out.write(bytearray(content.encode()))
        out.close()
        return True

    def _read(self, name: str) -> str:
        fs, path = self._at(name)
        stream = fs.open(path)
        try:
            return bytes(stream.readAllBytes()).decode()
        finally:
            stream.close()

    def _drop(self, name: str) -> None:
        fs, path = self._at(name)
        fs.delete(path, True)

    def _snapshot(self) -> tuple[int, str | None]:
        """Number and table folder of the latest snapshot."""
        names = self._names("snapshots")
        return (int(names[-1]), self._read(f"snapshots/{names[-1]}")) if names else (0, None)

    def _folded(self, folder: str | None, files: list[str]) -> set[str]:
        """Those of the commit files whose batch the snapshot holds."""
        if folder is None or not files:
            return set()
        ids = self.spark.read.schema("file string").parquet(f"{self.root}/{folder}/files")
        return {r["file"] for r in ids.where(F.col("file").isin(files)).collect()}

    def pending(self) -> dict[str, str]:
        """Commit file -> table folder of the batches that no snapshot holds yet."""
        files = self._names("commits")
        known = self._folded(self._snapshot()[1], files)
        return {f: self._read(f"commits/{f}") for f in files if f not in known}

    def apply(self, batch_id: str, changes: DataFrame) -> bool:
        """Commit a batch; False when its id is committed already."""
        file = quote(batch_id, safe="")
        if self._exists(f"commits/{file}") or self._folded(self._snapshot()[1], [file]):
            return False
        table = f"tables/{uuid.uuid4().hex}"
        count_changes(changes, self.versions).write.parquet(f"{self.root}/{table}")
        if not self._create(f"commits/{file}", table):
            self._drop(table)
            return False
        if len(self._names("commits")) >= self.COMPACT_AFTER:
            self.compact()
        return True

    def _sums(self, folder: str | None, tables: list[str]) -> DataFrame:
        paths = [f"{self.root}/{t}" for t in tables] + ([f"{self.root}/{folder}/totals"] if folder else [])
        rows = self.spark.read.schema(ROLLUP).parquet(*paths) if paths else self.spark.createDataFrame([], ROLLUP)
        return rows.groupBy(*KEYS).agg(*[F.sum(c).alias(c) for c in SUMS])

    def totals(self) -> DataFrame:
        return self._sums(self._snapshot()[1], list(self.pending().values())).where("n_docs <> 0")

    def compact(self) -> bool:
        """Fold the waiting batches into a new snapshot; False where nothing waits or another writer was first."""
        number, old = self._snapshot()
        waiting = self.pending()
        if not waiting:
            return False
        folder = f"tables/{uuid.uuid4().hex}"
        self._sums(old, list(waiting.values())).coalesce(1).write.parquet(f"{self.root}/{folder}/totals")
        files = self.spark.createDataFrame([(f,) for f in waiting], "file string")
        if old:
            files = files.unionByName(self.spark.read.schema("file string").parquet(f"{self.root}/{old}/files"))
        files.write.parquet(f"{self.root}/{folder}/files")
        if not self._create(f"snapshots/{number + 1:012d}", folder):
            self._drop(folder)
            return False
        for file, table in waiting.items():
            self._drop(f"commits/{file}")
            self._drop(table)
        return True


def inserts(docs: DataFrame) -> DataFrame:
    return docs.select(F.lit(1).alias("sign"), "source", "lang", "text")


def deletes(docs: DataFrame) -> DataFrame:
    return docs.select(F.lit(-1).alias("sign"), "source", "lang", "text")


def revisions(old: DataFrame, new: DataFrame) -> DataFrame:
    return deletes(old).unionByName(inserts(new))


def default_versions() -> dict[str, str]:
    import public_tokenizers

    return {"byte_bpe_50k": default_path(), "byte_bpe_multi_50k": public_tokenizers.path("byte_bpe_multi_50k.tiktoken")}


def revised_text():
    """The revision of the workload: pipes become spaces and blank runs shrink to one."""
    return F.regexp_replace(F.translate("text", "|", " "), " {2,}", " ")


def op5_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Insert every document; revise those with pipes (and replay that batch); delete very short ones, on top of a snapshot."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("source", "lang", "text")
    ledger = TokenLedger(spark, SharedStore(spark, "token-ledger").root, default_versions())
    piped = docs.where(F.instr("text", "|") > 0)
    changed = piped.withColumn("text", revised_text())
    ledger.apply("0-load", inserts(docs))
    ledger.apply("1-revise", revisions(piped, changed))
    ledger.apply("1-revise", revisions(piped, changed))
    ledger.compact()
    ledger.apply("1-revise", revisions(piped, changed))
    ledger.apply("2-retire", deletes(docs.where((F.length("text") < 40) & (F.instr("text", "|") == 0))))
    return ledger.totals()
