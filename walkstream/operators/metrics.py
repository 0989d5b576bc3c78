"""Accuracy, identity, size and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import adjacency, degrees
from .query import best_k
from .repair import IndexState
from .walks import crossings_of, walk_ends


def relative_error(est: DataFrame, exact: DataFrame, delta: float) -> DataFrame:
    """Average and largest relative error of each source over nodes with an exact score of at least delta."""
    big = exact.where(F.col("score") >= delta).select("source", "node", F.col("score").alias("exact"))
    err = big.join(est, ["source", "node"], "left").withColumn("err", F.abs(F.coalesce("score", F.lit(0.0)) - F.col("exact")) / F.col("exact"))
    return err.groupBy("source").agg(F.count("*").alias("nodes"), F.avg("err").alias("avg_error"), F.max("err").alias("max_error"))


def topk_quality(est: DataFrame, exact: DataFrame, k: int, epsilon: float, delta: float) -> DataFrame:
    """precision at k, and ranks that break the definition: by own score, or by the exact score of their rank."""
    got = best_k(est, k).select("source", "node", "rank", "score")
    best = best_k(exact, k).select("source", "rank", F.col("node").alias("best_node"), F.col("score").alias("best"))
    own = exact.select("source", "node", F.col("score").alias("own"))
    j = got.join(best, ["source", "rank"]).join(own, ["source", "node"], "left").withColumn("own", F.coalesce("own", F.lit(0.0)))
    sure = F.col("best") >= delta
    bad = sure & ((F.abs(F.col("score") - F.col("own")) > epsilon * F.col("own") + 1e-12) | (F.col("own") < (1 - epsilon) * F.col("best") - 1e-12))
    hits = got.join(best.select("source", F.col("best_node").alias("node")), ["source", "node"], "left_semi").groupBy("source").agg(F.count("*").alias("hits"))
    sums = j.groupBy("source").agg(F.count("*").alias("ranks"), F.sum(F.when(bad, 1).otherwise(0)).alias("broken"))
    return sums.join(hits, "source", "left").select("source", "ranks", "broken", (F.coalesce("hits", F.lit(0)) / F.col("ranks")).alias("precision"))


def check_adequate(state: IndexState) -> DataFrame:
    """Nodes whose number of walks isn't ceil(x * degree); empty if all are adequate."""
    want = degrees(state.edges).select("node", state.params.walks_stored(F.col("out_deg")).alias("want"))
    have = state.walks.groupBy(F.col("source").alias("node")).agg(F.count("*").alias("have"))
    return want.join(have, "node", "full").where(F.coalesce("want", F.lit(0)) != F.coalesce("have", F.lit(0)))


def check_paths_valid(state: IndexState) -> DataFrame:
    """Hops that aren't edges of the graph (a dead end's self-loop is one), and paths without their hops."""
    c = crossings_of(state.walks)
    hop = c.select(F.col("node").alias("src"), F.col("next").alias("dst"), "walk_id")
    off = hop.join(state.edges.select("src", "dst"), ["src", "dst"], "left_anti")
    dead = off.where("src = dst").join(state.edges.select("src").distinct(), "src", "left_anti")
    bad = off.select("walk_id").exceptAll(dead.select("walk_id"))
    short = state.walks.where("size(path) <> hops + 1 or path[0] <> source").select("walk_id")
    return bad.unionByName(short)


def check_unbiased(state: IndexState, exact: DataFrame) -> DataFrame:
    """Chi-square per cell of the endpoints of each source against exact scores (cells with at least 5 expected walks)."""
    p = state.params
    have = state.walks.groupBy("source").agg(F.count("*").alias("n"))
    ends = walk_ends(state.walks).groupBy("source", F.col("terminal").alias("node")).agg(F.count("*").alias("c"))
    score = F.col("score") if state.zero_hop else (F.col("score") - F.when(F.col("source") == F.col("node"), p.alpha).otherwise(0.0)) / (1 - p.alpha)
    cells = exact.join(have, "source").withColumn("q", score).withColumn("want", F.col("n") * F.col("q")).where("want >= 5 and q < 0.999999").join(ends, ["source", "node"], "left")
    z = F.pow(F.coalesce("c", F.lit(0)) - F.col("want"), 2) / (F.col("want") * (1 - F.col("q")))
    return cells.agg(F.count("*").alias("cells"), F.avg(z).alias("chi2_per_cell"))


def check_crossing_identity(state: IndexState, exact: DataFrame) -> DataFrame:
    """Crossings of each node and their expectation from exact scores of all sources."""
    p = state.params
    have = state.walks.groupBy("source").agg(F.count("*").alias("n"))
    factor = (1 - p.alpha) / p.alpha if state.zero_hop else 1 / p.alpha
    want = exact.join(have, "source").groupBy("node").agg((F.sum(F.col("n") * F.col("score")) * factor).alias("expected"))
    got = crossings_of(state.walks).groupBy("node").agg(F.count("*").alias("crossings"))
    return want.join(got, "node", "left").withColumn("crossings", F.coalesce("crossings", F.lit(0)))


def edge_dispersion(state: IndexState) -> DataFrame:
    """Spread of records over a node's edges against independent draws (1 is ideal)."""
    c = crossings_of(state.walks).groupBy("node", F.col("next").alias("dst")).agg(F.count("*").alias("c"))
    e = state.edges.select(F.col("src").alias("node"), "dst").join(c, ["node", "dst"], "left").withColumn("c", F.coalesce("c", F.lit(0)))
    per = e.groupBy("node").agg(F.count("*").alias("d"), F.sum("c").alias("n"), F.sum(F.col("c") * F.col("c")).alias("s2")).where("d > 1 and n >= 5 * d")
    mean = F.col("n") / F.col("d")
    chi = (F.col("s2") - F.col("d") * mean * mean) / mean
    return per.agg(F.sum(chi).alias("chi2"), F.sum(F.col("d") - 1).alias("cells"), (F.sum(chi) / F.sum(F.col("d") - 1)).alias("dispersion"))


def repair_bound(p, zero_hop: bool = False) -> float:
    """Upper bound of expected repairs per random update."""
    return ((1 - p.alpha) / p.alpha if zero_hop else 1 / p.alpha) * (p.x + 1)


def size_report(state: IndexState) -> DataFrame:
    """Rows and raw bytes of each table of the index and of its parts."""
    c = crossings_of(state.walks)
    tables = {"edges": (state.edges, F.lit(16)), "adjacency": (adjacency(state.edges), F.lit(32)), "walk_ends": (walk_ends(state.walks), F.lit(24)), "walk_paths": (state.walks, 44 + 8 * F.size("path")), "crossings": (c, F.lit(44))}
    out = None
    for name, (df, width) in tables.items():
        row = df.select(width.cast("long").alias("w")).agg(F.count("*").alias("n_rows"), F.sum("w").alias("n_bytes")).select(F.lit(name).alias("table_name"), "n_rows", "n_bytes")
        out = row if out is None else out.unionByName(row)
    return out
