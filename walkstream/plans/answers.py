"""Answers as a table: one packed row for each source, its best nodes in order."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.query import best_k

ANSWERS = "source long, best array<struct<node: long, score: double>>"


def pack(scores: DataFrame, k: int) -> DataFrame:
    """source, best: its k best nodes, by score and then node; k bounds a row."""
    top = best_k(scores.select("source", "node", "score"), k)
    packed = top.groupBy("source").agg(F.sort_array(F.collect_list(F.struct("rank", "node", "score"))).alias("b"))
    return packed.select("source", F.transform("b", lambda x: F.struct(x["node"].alias("node"), x["score"].alias("score"))).alias("best"))


def write_answers(scores: DataFrame, path: str, k: int = 500, mode: str = "overwrite") -> None:
    pack(scores, k).write.mode(mode).parquet(path)


def read_answers(spark: SparkSession, path: str) -> DataFrame:
    """source, rank, node, score."""
    rows = spark.read.schema(ANSWERS).parquet(path).select("source", F.posexplode("best").alias("pos", "a"))
    return rows.select("source", (F.col("pos") + 1).alias("rank"), "a.node", "a.score")
