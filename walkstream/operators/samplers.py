"""Choosing which records of a node are redirected by an insertion: each with probability k/d.

records: node, walk_id, step, next. deg: node, d and k, the number of insertions at the node (1 where the column is missing). All draws are keyed by seed and epoch.

bernoulli looks at each record; geometric jumps between hits; binomial draws the number of hits and then that many distinct
records; edge_uniform draws the number and for each hit an active edge uniformly and a record on it (its spread over edges is
wider than independent draws have it); edge_weighted chooses edges by their records instead: the records of an edge hold a
range of the node's running total, and a uniform place in the total names the edge and the record.

Numbers of hits are counted by geometric gaps, which is the binomial law at any size. Sequences of draws are made in blocks
and made longer until every node has enough, so none is cut. Nothing is gathered by node: records are numbered by ranges.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.rng import id_keys, u01
from ..plans.iterate import Rounds
from .graph import numbered
from .walks import counted

HOW = ("bernoulli", "geometric", "binomial", "edge_uniform", "edge_weighted")


def gap_positions(counts: DataFrame, seed: int, purpose: str, rounds: Rounds) -> DataFrame:
    """node, pos: places 0, 1, ..., n - 1 that are hit with probability share each, by geometric gaps. counts: node, n, share."""
    mean = F.col("n") * F.col("share")
    guess = F.ceil(mean + 6 * F.sqrt(mean) + 8)
    w = Window.partitionBy("node").orderBy("j").rowsBetween(Window.unboundedPreceding, 0)
    longer = 1
    while True:
        u = u01(seed, purpose, F.col("node"), F.col("j"))
        gap = F.when(F.col("share") >= 1, 1).otherwise(F.least(F.lit(1 << 53), F.floor(F.log(F.lit(1.0) - u) / F.log(F.lit(1.0) - F.col("share"))) + 1)).cast("double")
        at = counted(counts.select("node", "n", "share"), F.lit(0), guess * longer, "j").withColumn("pos", F.sum(gap).over(w) - 1)
        at = rounds.keep(at.select("node", "n", "pos"))
        short = at.groupBy("node", "n").agg(F.max("pos").alias("top")).where("top < n - 1").limit(1).count()
        if not short:
            return at.where("pos < n").select("node", F.col("pos").cast("long").alias("pos"))
        longer *= 2


def hit_counts(counts: DataFrame, seed: int, purpose: str, rounds: Rounds) -> DataFrame:
    """node, hits: a binomial number of hits among n."""
    return gap_positions(counts, seed, purpose, rounds).groupBy("node").agg(F.count("*").alias("hits"))


def _accepted(need: DataFrame, draw, seed: int, purpose: str, rounds: Rounds) -> DataFrame:
    """The first `hits` accepted draws of each node. draw(rows with node, j, u) gives the accepted rows with their column j."""
    longer = 2
    while True:
        tries = counted(need, F.lit(0), F.col("hits") * longer + 16, "j").withColumn("u", u01(seed, purpose, F.col("node"), F.col("j")))
        good = numbered(draw(tries), "node", F.col("j"), [], "_rank").where("_rank < hits")
        good = rounds.keep(good)
        enough = good.groupBy("node").agg(F.count("*").alias("got"))
        if not need.join(enough, "node", "left").where("coalesce(got, 0) < hits").limit(1).count():
            return good
        longer *= 2


def _by_hash(records: DataFrame, seed: int, epoch: int) -> Column:
    return u01(seed, f"record{epoch}", *id_keys(records), F.col("step"))


def sample_records(records: DataFrame, deg: DataFrame, seed: int, epoch: int, how: str = "bernoulli") -> DataFrame:
    cols = ["node", "walk_id", "step", "next"]
    own = records.select(*cols).join(deg.select("node", "d", (F.col("k") if "k" in deg.columns else F.lit(1)).alias("k")), "node")
    if how == "bernoulli":
        return own.where(u01(seed, f"hit{epoch}", *id_keys(own), F.col("step")) < F.col("k") / F.col("d")).select(*cols)
    if how not in HOW:
        raise ValueError(how)
    rounds = Rounds(records.sparkSession, "sample")
    own = rounds.keep(own)
    counts = own.groupBy("node", "d", "k").agg(F.count("*").alias("n")).withColumn("share", F.col("k") / F.col("d"))
    if how == "geometric":
        hits = gap_positions(counts, seed, f"gap{epoch}", rounds)
        return numbered(own, "node", _by_hash(own, seed, epoch), ["walk_id", "step"], "pos").join(hits, ["node", "pos"]).select(*cols)
    hits = hit_counts(counts, seed, f"count{epoch}", rounds)
    if how == "binomial":
        return numbered(own, "node", _by_hash(own, seed, epoch), ["walk_id", "step"], "pos").join(hits, "node").where("pos < hits").select(*cols)
    need = rounds.keep(hits.join(counts.select("node", "n"), "node"))
    if how == "edge_uniform":
        per = own.groupBy("node", "next").agg(F.count("*").alias("on_edge"))
        edges = rounds.keep(numbered(per, "node", F.col("next"), [], "edge"))
        active = edges.groupBy("node").agg(F.count("*").alias("active"))

        def draw(tries: DataFrame) -> DataFrame:
            on = tries.join(active, "node").withColumn("edge", F.floor(F.col("u") * F.col("active")).cast("long")).join(edges, ["node", "edge"])
            turn = F.row_number().over(Window.partitionBy("node", "edge").orderBy("j")) - 1  # an edge's records run out
            return on.withColumn("turn", turn.cast("long")).where("turn < on_edge").select("node", "hits", "j", "next", "turn")

        chosen = _accepted(need, draw, seed, f"edge{epoch}", rounds)
        placed = own.join(need.select("node"), "node", "left_semi").withColumn("turn", (F.row_number().over(Window.partitionBy("node", "next").orderBy(_by_hash(own, seed, epoch), "walk_id", "step")) - 1).cast("long"))
        return placed.join(chosen.select("node", "next", "turn"), ["node", "next", "turn"]).select(*cols)

    def distinct(tries: DataFrame) -> DataFrame:
        place = F.floor(F.col("u") * F.col("n")).cast("long")
        return tries.withColumn("pos", place).groupBy("node", "hits", "pos").agg(F.min("j").alias("j"))  # a record once

    chosen = _accepted(need, distinct, seed, f"weight{epoch}", rounds)
    # an edge's records fill the range of its running total, in the order of their hashes
    in_ranges = numbered(own.withColumn("_h", _by_hash(own, seed, epoch)), "node", F.col("next"), ["_h", "walk_id", "step"], "pos")
    return in_ranges.join(chosen.select("node", "pos"), ["node", "pos"]).select(*cols)
