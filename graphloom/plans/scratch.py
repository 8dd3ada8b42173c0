"""Durable cuts of lineage.

Intermediate tables are written as Parquet below the shared checkpoint folder, so a
lost executor never loses them (unlike ``localCheckpoint``), later reads get column
pruning, and a superseded step can be deleted while a loop still runs.
"""

from __future__ import annotations

import contextlib
import gc
import tempfile
import uuid

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder of the session; a local one only where none is set on a local master."""
    sc = spark.sparkContext
    told = sc.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if told:
        return told.rstrip("/")
    current = sc._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    if not sc.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    sc.setCheckpointDir(tempfile.mkdtemp(prefix="graphloom-"))
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


class Scratch:
    """Named Parquet tables of one run below the checkpoint folder."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{checkpoint_dir(spark)}/{label}-{uuid.uuid4().hex}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}-{uuid.uuid4().hex[:8]}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def save_by(self, df: DataFrame, name: str, key: str) -> DataFrame:
        """save() in buckets of the key, one for each shuffle partition of the session, so that joins on the key exchange only their other side."""
        table = f"{name}_{uuid.uuid4().hex}"
        buckets = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        df.repartition(buckets, key).write.option("path", f"{self.root}/{table}").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
        out = self.spark.table(table)
        out._scratch_path = f"{self.root}/{table}"
        return out

    def drop(self, *tables: DataFrame) -> None:
        """Delete tables of this run that no later plan reads."""
        jvm = self.spark._jvm
        for t in tables:
            if path := getattr(t, "_scratch_path", None):
                p = jvm.org.apache.hadoop.fs.Path(path)
                p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)

    def sweep(self) -> None:
        """Let Spark delete the shuffle files of plans that are done: it does so when the driver collects its garbage. Events that wait for listeners still hold their plans."""
        gc.collect()
        with contextlib.suppress(Py4JJavaError):  # not drained in that time
            self.spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(10_000)
        self.spark._jvm.System.gc()
