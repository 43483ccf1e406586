"""Written intermediate tables below the cluster's shared folder.

Re-reading a written table cuts lineage and survives lost executors; the folder is
the session's ``spark.checkpoint.dir``. Only a session in local mode, whose tasks run in
one process on one machine, may go without it and gets a temporary folder.
"""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The cluster's shared folder; on a cluster without one there is none, which raises."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = held.get() if held.isDefined() else None
    if not base:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError(f"set spark.checkpoint.dir to a folder that all machines of {master} share")
        base = f"file://{os.path.join(tempfile.gettempdir(), 'checkpoints')}"
    return base.rstrip("/")


class TableStore:
    """Tables of one run, each under its own name.

    ``keep`` drops the tables a finished run no longer reads; what its result still reads
    goes when the driver's process ends.
    """

    def __init__(self, spark: SparkSession, label: str = "rules"):
        self.spark, self.root = spark, f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
        self.names: set[str] = set()

    def write(self, df: DataFrame, name: str) -> DataFrame:
        if not self.names:
            _open[self.root] = self
        self.names.add(name)
        path = f"{self.root}/{name}"
        df.write.mode("overwrite").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        for name in names:
            self.names.discard(name)
            self._delete(f"{self.root}/{name}")

    def keep(self, *names: str) -> None:
        """Drop every table but these."""
        self.drop(*(self.names - set(names)))

    def _delete(self, path: str) -> None:
        sc = self.spark.sparkContext
        p = sc._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(sc._jsc.hadoopConfiguration()).delete(p, True)


_open: dict[str, TableStore] = {}


@atexit.register
def _close() -> None:
    for root, store in _open.items():
        try:
            store._delete(root)
        except Exception:  # the session has ended; its folder is the owner's to clean
            return
