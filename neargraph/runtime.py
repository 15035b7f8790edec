"""Session helpers: shared work folder, materialised tables, worker import path."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession

_ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


#: Bytes of a batch between the JVM and Python. Spark's own bound of 64 MB is held several times over for each task on both sides.
BATCH_BYTES = 4 << 20


def prepare(spark: SparkSession) -> SparkSession:
    """Let Python workers of this session import this package whatever their working folder is, and hand them batches of ``BATCH_BYTES``."""
    known = spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch", None)
    if known is not None and (not known.rstrip("b").isdigit() or int(known.rstrip("b")) > BATCH_BYTES):
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    environment = spark.sparkContext.environment
    known = environment.get("PYTHONPATH", "")
    if _ROOT not in known.split(os.pathsep):
        environment["PYTHONPATH"] = os.pathsep.join(x for x in (_ROOT, known) if x)
    return spark


def work_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors share: ``spark.checkpoint.dir`` of the session.

    Only where that is unset (tests, a single machine) a temporary folder is made and set.
    """
    sc = spark.sparkContext
    folder = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not folder:
        folder = sc.getCheckpointDir()
    if not folder:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="neargraph-")
        sc.setCheckpointDir(folder)
    elif not sc.getCheckpointDir():
        sc.setCheckpointDir(folder)
    return folder.rstrip("/")


class Scratch:
    """Tables written to the shared folder, so that a lost executor costs a re-read and no lineage.

    ``keep`` writes a frame as Parquet and reads it again; ``drop`` deletes tables that nothing needs any longer. What is left goes when
    the driver ends, as a result may read its tables until then.
    """

    def __init__(self, spark: SparkSession, name: str) -> None:
        self.spark = prepare(spark)
        self.base = f"{work_dir(spark)}/neargraph-{name}-{uuid.uuid4().hex[:12]}"
        self._made = 0

    def keep(self, df: DataFrame, *, partition_by: Iterable[str] = ()) -> DataFrame:
        self._made += 1
        path = f"{self.base}/{self._made:03d}"
        writer = df.write
        if names := list(partition_by):
            writer = writer.partitionBy(*names)
        writer.parquet(path)
        if self._made == 1:
            base = self._path(self.base)
            base.getFileSystem(self._conf()).deleteOnExit(base)
        schema = df.schema
        out = self.spark.read.schema(schema).parquet(path)
        out._neargraph_path = path  # type: ignore[attr-defined]
        return out

    def drop(self, *tables: DataFrame) -> None:
        for table in tables:
            path = self._path(table._neargraph_path)  # type: ignore[attr-defined]
            path.getFileSystem(self._conf()).delete(path, True)

    def _path(self, name: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(name)

    def _conf(self):
        return self.spark.sparkContext._jsc.hadoopConfiguration()


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
