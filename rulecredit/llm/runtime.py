"""Session plumbing shared by the training-data operators.

* ``ship`` sends this package to the executors once per application, so Python
  workers can import it without an installation.
* ``SharedStore`` writes intermediate tables below ``spark.checkpoint.dir`` (the
  folder every executor sees) and drops them again; re-reading a written table
  cuts lineage and survives lost executors.
* ``spread_join`` joins on keys of which a few may hold a large part of all rows.
"""

from __future__ import annotations

import gc
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.sources.store import TableStore

_shipped: set[str] = set()


#: Rows handed to a Python worker at once: texts are long, and a worker's memory should not follow the default.
BATCH_ROWS = 1000


def ship(spark: SparkSession) -> None:
    """Add this package to the executors' import path (idempotent) and keep worker batches small."""
    rows = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(rows, "10000")) <= BATCH_ROWS:
        spark.conf.set(rows, str(BATCH_ROWS))
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parents[1]
    target = Path(tempfile.mkdtemp()) / f"{root.name}_code.zip"
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    spark.sparkContext.addPyFile(str(target))
    _shipped.add(app)


#: Left rows of one key that go to one task, and the most keys that may be dealt over several.
KEY_ROWS, MOST_HOT = 50_000, 1_000


class SharedStore(TableStore):
    """Named intermediate tables of one operator call."""

    def release(self) -> None:
        """Let Spark's cleaner remove shuffle files of finished phases."""
        gc.collect()
        self.spark.sparkContext._jvm.System.gc()


def spread_join(left: DataFrame, right: DataFrame, keys: list[str], rows: str, row: list[str | Column], how: str = "inner") -> DataFrame:
    """``left`` joined to ``right`` on ``keys``, hot keys dealt over many tasks.

    ``right`` (read three times: pass a written table) has one row a key and, in column
    ``rows``, how many rows of ``left`` hold it. A key with more than a bound of rows has its
    right row copied once for each so many rows, and a left row takes the copy its ``row``
    columns hash to. The bound is at least a ``MOST_HOT``-th of all rows, so that the
    broadcast list of hot keys never has more than ``MOST_HOT`` entries.
    """
    total = right.agg(F.sum(rows)).first()[0] or 0
    bound = max(KEY_ROWS, total // MOST_HOT)
    if not right.where(F.col(rows) > bound).take(1):
        return left.join(right, keys, how)
    copies = F.ceil(F.col(rows) / F.lit(bound)).cast("int")
    hot = right.where(F.col(rows) > bound).select(*keys, copies.alias("_copies"))
    salt = F.coalesce(F.pmod(F.xxhash64(*row), F.col("_copies")), F.lit(0)).cast("int")
    salted = left.join(F.broadcast(hot), keys, "left").withColumn("_salt", salt).drop("_copies")
    copied = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), copies - 1)))
    return salted.join(copied, [*keys, "_salt"], how).drop("_salt")
