"""Materialised rounds for iterative plans: tables in the shared folder, so that lost executors cost one round."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session, else the context's checkpoint folder, else (local runs) a temporary one."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="walkstream_"))
        named = spark.sparkContext.getCheckpointDir()
    return named.rstrip("/")


def remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


class Rounds:
    """Numbered tables below one folder; `keep` writes a frame and reads it back without its lineage."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.base, self.n = spark, f"{shared_dir(spark)}/{name}_{uuid.uuid4().hex[:12]}", 0

    def keep(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.base}/{self.n}"
        df.write.mode("overwrite").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def keep_seen(self, df: DataFrame, seen: Column) -> tuple[DataFrame, int]:
        """`keep`, and the value of an aggregate over the rows as they are written: no job of its own."""
        watch = Observation()
        kept = self.keep(df.observe(watch, seen.alias("seen")))
        return kept, watch.get["seen"] or 0

    def drop(self, upto: int) -> None:
        """Delete the tables numbered up to `upto`; they must not be read any more."""
        for k in range(1, upto + 1):
            remove(self.spark, f"{self.base}/{k}")

    def drop_all(self) -> None:
        remove(self.spark, self.base)
