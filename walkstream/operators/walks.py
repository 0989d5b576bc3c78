"""Random walks with stop probability alpha, the walk index and its projections.

A walk's hop count is drawn at its birth; each superstep then joins one adjacency row on (node, slot), so a node's degree
never shows in a row. A walk's id is its birth key (source, slot, epoch), so ids never clash. Rows: walk_id, source, slot,
hops, path (hops + 1 nodes once finished); slot is the walk's present place among those of its source.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.params import PprParams
from ..functions.rng import geometric, id_keys, pick_slot, u01
from ..plans.iterate import Rounds
from .graph import adjacency, degrees, numbered
from .task_walks import finished_in_tasks, walks_in_tasks

#: Walks given from outside may have plain numbers as ids.
WALKS = "walk_id long, source long, slot long, hops int, path array<long>"
#: An adjacency of at most so many rows (32 bytes each) is sent to all executors.
BROADCAST_ROWS = 500_000
#: Counted rows are made in blocks of so many.
BLOCK = 10_000


def walk_id(source: Column, slot: Column, epoch: int) -> Column:
    return F.struct(source.cast("long").alias("source"), slot.cast("long").alias("slot"), F.lit(epoch).cast("long").alias("epoch"))


def counted(df: DataFrame, least: Column, n: Column, name: str = "slot") -> DataFrame:
    """A row for each of least, ..., n - 1. Made by blocks, which are dealt out: a hub's rows are neither one array nor one
    task."""
    some = df.withColumn("_lo", least.cast("long")).withColumn("_n", n.cast("long")).where("_lo < _n")
    blocks = some.withColumn("_b", F.explode(F.sequence(F.col("_lo"), F.col("_n") - 1, F.lit(BLOCK).cast("long"))))
    dealt = blocks.repartition(*df.columns, "_b")
    return dealt.withColumn(name, F.explode(F.sequence(F.col("_b"), F.least(F.col("_b") + BLOCK, F.col("_n")) - 1))).drop("_lo", "_n", "_b")


def new_walks(starts: DataFrame, p: PprParams, epoch: int, zero_hop: bool = False) -> DataFrame:
    """Unwalked rows for starts (source, slot)."""
    own = starts.select(walk_id(F.col("source"), F.col("slot"), epoch).alias("walk_id"), "source", "slot")
    hops = geometric(u01(p.seed, "hops", *id_keys(own), fast=p.fast_hash), p.alpha, 0 if zero_hop else 1, p.fast_hash)
    return own.select("walk_id", "source", "slot", hops.alias("hops"), F.array("source").alias("path"))


def _going() -> Column:
    return F.size("path") <= F.col("hops")


def _draw(live: DataFrame, p: PprParams, epoch: int) -> Column:
    return u01(p.seed, f"next{epoch}", *id_keys(live), F.size("path"), fast=p.fast_hash)


def advance(walks: DataFrame, adj: DataFrame, degree: DataFrame, p: PprParams, epoch: int, every: int = 5, rounds: Rounds | None = None) -> DataFrame:
    """Walk every row on until its path has its hops; dead ends stay where they are."""
    rounds = rounds or Rounds(walks.sparkSession, "walks")
    adj, n = rounds.keep_seen(adj, F.count("*"))
    live = walks.withColumn("_at", F.element_at("path", -1)).join(degree.select(F.col("node").alias("_at"), F.col("out_deg").alias("_deg")), "_at", "left").withColumn("_deg", F.coalesce("_deg", F.lit(0)).cast("long"))
    live = live.select("walk_id", "source", "slot", "hops", "path", "_at", "_deg")
    finished: list[DataFrame] = []
    steps = adj.select(F.col("src").alias("_src"), F.col("slot").alias("_slot"), "dst", "dst_deg")
    if n <= BROADCAST_ROWS:
        steps = F.broadcast(steps)
    # the columns of a superstep are the same in all of them
    going, to, deg = _going(), F.coalesce("dst", "_at"), F.coalesce("dst_deg", "_deg")
    pick = F.when(going & (F.col("_deg") > 0), pick_slot(_draw(live, p, epoch), F.col("_deg"))).alias("_pick")
    keyed = [F.col(c) for c in live.columns] + [pick]
    meet = (F.col("_at") == F.col("_src")) & (F.col("_pick") == F.col("_slot"))
    stepped = [F.col(c) for c in ("walk_id", "source", "slot", "hops")] + [F.when(going, F.concat("path", F.array(to))).otherwise(F.col("path")).alias("path"), F.when(going, to).otherwise(F.col("_at")).alias("_at"), F.when(going, deg).otherwise(F.col("_deg")).alias("_deg")]
    open_walks = F.sum(F.when(going, 1).otherwise(0))
    while True:
        for _ in range(every):
            live = live.select(*keyed).join(steps, meet, "left").select(*stepped)
        kept, left = rounds.keep_seen(live, open_walks)
        finished.append(kept.where(~going))
        live = kept.where(going)
        if not left:
            break
    return reduce(DataFrame.unionByName, finished).select("walk_id", "source", "slot", "hops", "path")


def advance_near(walks: DataFrame, edges_at: Callable[[DataFrame], DataFrame], p: PprParams, epoch: int, rounds: Rounds) -> DataFrame:
    """The same paths, superstep by superstep, reading only the edges of the nodes where walks stand: for few walks on a large
    graph. edges_at: edges (src, dst) of given nodes (node)."""
    live, finished = rounds.keep(walks.select("walk_id", "source", "slot", "hops", "path")), []
    while True:
        at = live.where(_going()).withColumn("_at", F.element_at("path", -1))
        slots = rounds.keep(numbered(edges_at(at.select(F.col("_at").alias("node")).distinct()).select("src", "dst"), "src", F.col("dst"), [], "_slot"))
        deg = slots.groupBy(F.col("src").alias("_at")).agg(F.count("*").alias("_deg"))
        keyed = at.join(deg, "_at", "left").withColumn("_pick", pick_slot(_draw(at, p, epoch), F.col("_deg")))
        moved = keyed.join(slots.select(F.col("src").alias("_at"), F.col("_slot").alias("_pick"), "dst"), ["_at", "_pick"], "left")
        stepped = moved.select("walk_id", "source", "slot", "hops", F.concat("path", F.array(F.coalesce("dst", "_at"))).alias("path"))
        finished.append(live.where(~_going()))
        live, left = rounds.keep_seen(stepped, F.sum(F.when(_going(), 1).otherwise(0)))
        if not left:
            return reduce(DataFrame.unionByName, [*finished, live])


def simulate_walks(edges: DataFrame, starts: DataFrame, p: PprParams, epoch: int = 0, zero_hop: bool = False) -> DataFrame:
    return advance(new_walks(starts, p, epoch, zero_hop), adjacency(edges), degrees(edges), p, epoch)


def index_starts(degree: DataFrame, p: PprParams, x: float | None = None) -> DataFrame:
    """(source, slot) of the walks that each node should have."""
    want = degree.select(F.col("node").alias("source"), p.walks_stored(F.col("out_deg"), x).alias("want"))
    return counted(want, F.lit(0), F.col("want")).select("source", "slot")


def build_walk_index(edges: DataFrame, p: PprParams, x: float | None = None, epoch: int = 0, store: str = "paths", zero_hop: bool = False, rounds: Rounds | None = None) -> DataFrame:
    """The written index (in `rounds`): made inside tasks where they can hold the graph, else by joins."""
    rounds = rounds or Rounds(edges.sparkSession, "index")
    made = walks_in_tasks(edges, p, epoch, zero_hop, store, x)
    if made is not None:
        return rounds.keep(made)
    d, steps = degrees(edges), Rounds(edges.sparkSession, "walks")
    walks = advance(new_walks(index_starts(d, p, x), p, epoch, zero_hop), adjacency(edges), d, p, epoch, rounds=steps)
    index = rounds.keep(walks if store == "paths" else walk_ends(walks))
    steps.drop_all()
    return index


def fresh_ends(edges: DataFrame, asked: DataFrame, p: PprParams, epoch: int = 0) -> DataFrame:
    """source, slot, terminal of walks 0, 1, ..., n - 1 of each asked node (source, n), zero-hop ones included."""
    made = walks_in_tasks(edges, p, epoch, True, "ends", asked=asked)
    if made is not None:
        return Rounds(edges.sparkSession, "fresh").keep(made)
    return walk_ends(simulate_walks(edges, counted(asked.select("source", "n"), F.lit(0), F.col("n")), p, epoch, zero_hop=True))


def fresh_counts(edges: DataFrame, asked: DataFrame, p: PprParams, epoch: int = 0) -> DataFrame:
    """source, terminal, cnt of the same walks, which aren't written one by one where tasks can hold the graph."""
    made = walks_in_tasks(edges, p, epoch, True, "counts", asked=asked)
    if made is not None:
        return made.groupBy("source", "terminal").agg(F.sum("cnt").alias("cnt"))
    return fresh_ends(edges, asked, p, epoch).groupBy("source", "terminal").agg(F.count("*").alias("cnt"))


def walk_on(walks: DataFrame, edges: DataFrame, p: PprParams, epoch: int, rounds: Rounds) -> DataFrame:
    """Walks with their hops to go, walked to their end on these edges."""
    walks = rounds.keep(walks)
    done = finished_in_tasks(walks, edges, p, epoch)
    return done if done is not None else advance(walks, adjacency(edges), degrees(edges), p, epoch, rounds=rounds)


def walk_ends(walks: DataFrame) -> DataFrame:
    """source, slot, terminal; endpoints stay as they are."""
    return walks.select("source", "slot", "terminal" if "terminal" in walks.columns else F.element_at("path", -1).alias("terminal"))


def end_counts(ends: DataFrame) -> DataFrame:
    """Pre-aggregated endpoints: source, terminal, cnt and all (walks of the source)."""
    c = ends.groupBy("source", "terminal").agg(F.count("*").alias("cnt"))
    return c.join(c.groupBy("source").agg(F.sum("cnt").alias("all")), "source")


def crossings_of(walks: DataFrame) -> DataFrame:
    """node, walk_id, step, next: each node that a walk leaves. Both crossing views are filters of this table."""
    rows = walks.select("walk_id", "path", F.posexplode(F.slice("path", F.lit(1), F.col("hops"))).alias("step", "node"))
    return rows.select("node", "walk_id", "step", F.element_at("path", F.col("step") + 2).alias("next"))


def node_counters(crossings: DataFrame) -> DataFrame:
    per_edge = crossings.groupBy("node", "next").agg(F.count("*").alias("c"))
    return per_edge.groupBy("node").agg(F.sum("c").alias("crossings"), F.count("*").alias("active_edges"))
