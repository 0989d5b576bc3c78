"""Derived graph tables and update algebra."""

from __future__ import annotations

from weakref import WeakKeyDictionary

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: A key with more rows than this is numbered range by range.
HUB, RANGES = 1_000_000, 256


def degrees(edges: DataFrame) -> DataFrame:
    """Out-degree of every node with an edge; 0 for dead ends. One shuffle: both ends of an edge vote."""
    votes = edges.select(F.explode(F.array(F.struct(F.col("src").alias("node"), F.lit(1).alias("n")), F.struct(F.col("dst").alias("node"), F.lit(0).alias("n")))).alias("v"))
    return votes.groupBy("v.node").agg(F.sum("v.n").cast("long").alias("out_deg"))


def dead_ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("node")).distinct().join(edges.select(F.col("src").alias("node")).distinct(), "node", "left_anti")


def numbered(df: DataFrame, key: str, order: Column, ties: list[str], name: str, hub: int = HUB) -> DataFrame:
    """Rows of each key numbered 0, 1, ... by (order, ties).

    A key with more than `hub` rows is cut into equal ranges of its order values; rows are numbered within a range and the
    counts of the ranges before are added, so no task holds a hub and the numbers don't depend on the cut. `order` is numeric.
    """
    df = df.withColumn("_o", order)
    hubs = df.groupBy(key).agg(F.count("*").alias("_n"), F.min("_o").alias("_lo"), F.max("_o").alias("_hi")).where(F.col("_n") > hub).drop("_n")
    share = F.least(F.lit(RANGES - 1), F.floor((F.col("_o").cast("double") - F.col("_lo").cast("double")) / (F.col("_hi").cast("double") - F.col("_lo").cast("double")) * RANGES))
    cut = df.join(hubs, key, "left").withColumn("_range", F.when(F.col("_hi").cast("double") > F.col("_lo").cast("double"), share).cast("int"))
    per = cut.where("_range is not null").groupBy(key, "_range").agg(F.count("*").alias("_n"))
    before = per.select(key, "_range", F.coalesce(F.sum("_n").over(Window.partitionBy(key).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inner = cut.withColumn("_k", F.row_number().over(Window.partitionBy(key, "_range").orderBy("_o", *ties)))
    return inner.join(before, [key, "_range"], "left").withColumn(name, (F.col("_k") - 1 + F.coalesce("_before", F.lit(0))).cast("long")).drop("_o", "_lo", "_hi", "_range", "_k", "_before")


def adjacency(edges: DataFrame, hub: int = HUB) -> DataFrame:
    """src, slot (0, 1, ... by dst), dst and the out-degree of dst: a walk joins one row, however large its node is."""
    slots = numbered(edges.select("src", "dst"), "src", F.col("dst"), [], "slot", hub)
    out = edges.groupBy(F.col("src").alias("dst")).agg(F.count("*").alias("dst_deg"))
    return slots.join(out, "dst", "left").select("src", "slot", "dst", F.coalesce("dst_deg", F.lit(0)).cast("long").alias("dst_deg"))


_sizes: WeakKeyDictionary[DataFrame, tuple[int, int]] = WeakKeyDictionary()


def graph_size(edges: DataFrame) -> tuple[int, int]:
    """(nodes with an edge, edges); counted once for each frame."""
    if edges not in _sizes:
        r = degrees(edges).agg(F.count("*").alias("n"), F.sum("out_deg").alias("m")).first()
        _sizes[edges] = r["n"], r["m"] or 0
    return _sizes[edges]


def expand_node_updates(node_updates: DataFrame, edges: DataFrame) -> DataFrame:
    """Removals of nodes as removals of their edges; new nodes come with their edges' insertions, so '+' adds nothing."""
    gone = node_updates.where("op = '-'").select("tau", "node")
    hit = edges.select("src", "dst", F.explode(F.array("src", "dst")).alias("node")).join(gone, "node").groupBy("src", "dst").agg(F.min("tau").alias("tau"))
    return hit.select("tau", F.lit("-").alias("op"), "src", "dst")


def normalize_updates(updates: DataFrame, edges: DataFrame) -> DataFrame:
    """Net updates: the last one of an edge counts; present insertions and absent deletions vanish."""
    last = updates.groupBy("src", "dst").agg(F.max_by("op", "tau").alias("op")).where("src <> dst")
    have = edges.select("src", "dst")
    return last.where("op = '+'").join(have, ["src", "dst"], "left_anti").unionByName(last.where("op = '-'").join(have, ["src", "dst"], "left_semi"))


def apply_updates(edges: DataFrame, net: DataFrame) -> DataFrame:
    kept = edges.select("src", "dst").join(net.where("op = '-'"), ["src", "dst"], "left_anti")
    return kept.unionByName(net.where("op = '+'").select("src", "dst"))


def graph_as_of(updates: DataFrame, tau: int) -> DataFrame:
    """Edges whose latest update up to tau is an insertion."""
    return updates.where(F.col("tau") <= tau).groupBy("src", "dst").agg(F.max_by("op", "tau").alias("op")).where("op = '+'").select("src", "dst")


def graph_diff(old: DataFrame, new: DataFrame) -> DataFrame:
    a, b = old.select("src", "dst"), new.select("src", "dst")
    return b.exceptAll(a).withColumn("op", F.lit("+")).unionByName(a.exceptAll(b).withColumn("op", F.lit("-")))
