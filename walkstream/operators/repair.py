"""Repair of a walk index after edge updates.

`repair` takes any set of net updates in one pass. At a node whose out-degree goes from a (s edges survive) to b = s + k,
records of a path are looked at in step order until the first hit: a record on a removed edge always is one and goes to a
uniform edge of the new graph, a record on a surviving edge is one with probability k/b and goes to a uniform new edge. The
path is cut there and walked on to its old hop count. A dead end's self-loop counts as an edge removed by its first
insertion; a node that loses its last edge gets the self-loop. With one insertion or one deletion this is the edge-at-a-time
repair. Nodes then hold ceil(x * degree) walks each: a uniform choice is trimmed first, missing ones are walked anew.

The pass reads through a view: edges, records and walks of given nodes or ids, and gives a `Delta`. `apply_batch` merges it into
whole frames (`FrameView`); `plans.store.StateStore.apply` reads only touched partitions and appends the delta.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.params import PprParams
from ..functions.rng import id_keys, pick_slot, u01
from ..plans.iterate import Rounds
from .graph import apply_updates, expand_node_updates, normalize_updates, numbered
from .push import PushGraph
from .samplers import sample_records
from .walks import build_walk_index, counted, crossings_of, new_walks, walk_on

#: Net updates of at most so many rows are broadcast, and so are their nodes; more are joined by a shuffle.
BROADCAST_ROWS = 100_000


@dataclass(frozen=True)
class IndexState:
    """Edges and walks after `epoch` batches; x walks for each out-edge. folders: where this state's tables lie."""

    edges: DataFrame
    walks: DataFrame
    params: PprParams
    epoch: int = 0
    zero_hop: bool = False
    stats: dict | None = None
    folders: tuple[Rounds, ...] = field(default=(), compare=False)

    @property
    def x(self) -> float:
        return self.params.x

    @cached_property
    def push_graph(self) -> PushGraph:
        """The graph's tables for pushes, made by the first query on this state."""
        return PushGraph(self.edges)

    def release(self) -> None:
        """Delete this state's tables; neither it nor frames made of it must be read any more."""
        for f in self.folders:
            f.drop_all()


def build_state(edges: DataFrame, p: PprParams, zero_hop: bool = False, epoch: int = 0, store: str = "paths") -> IndexState:
    """store 'ends': endpoints only, which queries take as well but repairs don't."""
    rounds = Rounds(edges.sparkSession, "state")
    own = rounds.keep(edges.select("src", "dst"))
    return IndexState(own, build_walk_index(own, p, epoch=epoch, zero_hop=zero_hop, store=store, rounds=rounds), p, epoch, zero_hop, None, (rounds,))


@dataclass(frozen=True)
class Delta:
    """net: updates (src, dst, op) that change something. walks: rows that are new or replace those of their id. gone: ids
    (walk_id, source) of trimmed walks. old_records: records that no longer hold; new_records: those that hold now instead."""

    net: DataFrame
    touched: DataFrame
    walks: DataFrame
    gone: DataFrame
    old_records: DataFrame
    new_records: DataFrame
    stats: dict


class FrameView:
    """Reads a state held as whole frames."""

    def __init__(self, state: IndexState, crossings: DataFrame | None = None):
        self.state, self.records = state, crossings if crossings is not None else crossings_of(state.walks)

    def edges_at(self, nodes: DataFrame) -> DataFrame:
        return self.state.edges.join(nodes.select(F.col("node").alias("src")), "src", "left_semi")

    def records_at(self, nodes: DataFrame) -> DataFrame:
        return self.records.join(nodes.select("node"), "node", "left_semi")

    def walks_from(self, nodes: DataFrame) -> DataFrame:
        return self.state.walks.join(nodes.select(F.col("node").alias("source")), "source", "left_semi").select("walk_id", "source", "slot", "hops", "path")

    def walks_by(self, ids: DataFrame) -> DataFrame:
        return self.state.walks.join(ids, "walk_id")

    def walk_on(self, walks: DataFrame, net: DataFrame, p: PprParams, epoch: int, rounds: Rounds) -> DataFrame:
        edges = rounds.keep(apply_updates(self.state.edges, net))
        return walk_on(walks, edges, p, epoch, rounds)


def touched_nodes(edges: DataFrame, net: DataFrame) -> DataFrame:
    """node, a (old degree), k (new edges), gone (removed edges), b (new degree) of every node whose out-edges change."""
    changed = net.groupBy(F.col("src").alias("node")).agg(F.sum(F.when(F.col("op") == "+", 1).otherwise(0)).cast("long").alias("k"), F.sum(F.when(F.col("op") == "-", 1).otherwise(0)).cast("long").alias("gone"))
    old = edges.join(changed.select(F.col("node").alias("src")), "src", "left_semi").groupBy(F.col("src").alias("node")).agg(F.count("*").alias("a"))
    return changed.join(old, "node", "left").withColumn("a", F.coalesce("a", F.lit(0))).withColumn("b", F.col("a") - F.col("gone") + F.col("k"))


def trim_plan(walks: DataFrame, touched: DataFrame, p: PprParams, epoch: int, trim: str = "uniform") -> DataFrame:
    """Walks of touched sources with their place: those placed at or after the wanted number are trimmed."""
    own = walks.join(touched.select(F.col("node").alias("source"), p.walks_stored(F.col("b")).alias("want")), "source")
    if trim == "uniform":
        return numbered(own, "source", u01(p.seed, f"trim{epoch}", *id_keys(own)), ["walk_id"], "place")
    return numbered(own, "source", F.col("slot"), [], "place")


def _hits(records: DataFrame, touched: DataFrame, net: DataFrame, new_adj: DataFrame, p: PprParams, epoch: int, sampler: str) -> DataFrame:
    """First hit of each walk: walk_id, step, to. touched and net may be marked for broadcast."""
    gone = net.where("op = '-'").select(F.col("src").alias("node"), F.col("dst").alias("next"), F.lit(True).alias("removed"))
    r = records.join(touched, "node").join(gone, ["node", "next"], "left")
    r = r.withColumn("removed", F.coalesce("removed", F.col("a") == 0))
    on_removed = r.where("removed")
    on_kept = r.where("not removed and k > 0")
    keys = id_keys(records)
    if sampler == "bernoulli":
        redirected = on_kept.where(u01(p.seed, f"hit{epoch}", *keys, F.col("step")) < F.col("k") / F.col("b"))
    else:
        redirected = sample_records(on_kept, touched.select("node", F.col("b").alias("d"), "k"), p.seed, epoch, sampler).join(touched, "node")
    u = u01(p.seed, f"newedge{epoch}", *keys, F.col("step"))
    fresh = numbered(net.where("op = '+'").select(F.col("src").alias("node"), F.col("dst").alias("to")), "node", F.col("to"), [], "pick")
    every = new_adj.select(F.col("src").alias("node"), F.col("dst").alias("to"), F.col("slot").alias("pick"))
    a = redirected.select("node", "walk_id", "step", pick_slot(u, F.col("k")).alias("pick")).join(fresh, ["node", "pick"])
    b = on_removed.select("node", "walk_id", "step", F.when(F.col("b") > 0, pick_slot(u, F.col("b"))).alias("pick")).join(every, ["node", "pick"], "left").withColumn("to", F.coalesce("to", "node"))
    both = a.select("walk_id", "step", "to").unionByName(b.select("walk_id", "step", "to"))
    return both.groupBy("walk_id").agg(F.min("step").alias("step"), F.min_by("to", "step").alias("to"))


def repair(view, updates: DataFrame, p: PprParams, epoch: int, rounds: Rounds, zero_hop: bool = False, sampler: str = "bernoulli", trim: str = "uniform") -> Delta:
    """The delta of all updates (tau, op, src, dst); the last update of an edge counts."""
    asked = updates.select(F.col("src").alias("node")).distinct()
    net, n = rounds.keep_seen(normalize_updates(updates, view.edges_at(asked)), F.count("*"))
    small = F.broadcast if n <= BROADCAST_ROWS else (lambda df: df)
    nodes = net.select(F.col("src").alias("node")).distinct()
    near = rounds.keep(view.edges_at(nodes))
    touched = rounds.keep(touched_nodes(near, net))
    # adequacy: trim before repair, add after
    placed = rounds.keep(trim_plan(view.walks_from(nodes), small(touched), p, epoch, trim))
    gone, n_gone = rounds.keep_seen(placed.where("place >= want").select("walk_id", "source", "slot", "hops", "path"), F.count("*"))
    records = view.records_at(small(touched.select("node"))).join(gone.select("walk_id"), "walk_id", "left_anti")
    new_adj = numbered(apply_updates(near, net), "src", F.col("dst"), [], "slot")
    hits, n_hits = rounds.keep_seen(_hits(records, small(touched), small(net), new_adj, p, epoch, sampler), F.count("*"))
    old = rounds.keep(view.walks_by(hits).select("walk_id", "source", "slot", "hops", "path", "step", "to"))
    cut = old.select("walk_id", "source", "slot", "hops", F.concat(F.slice("path", F.lit(1), F.col("step") + 1), F.array("to")).alias("path"))
    have = placed.where("place < want").groupBy("source").agg(F.count("*").alias("have"))
    lack = touched.select(F.col("node").alias("source"), p.walks_stored(F.col("b")).alias("want")).join(have, "source", "left").withColumn("have", F.coalesce("have", F.lit(0)))
    starts, n_added = rounds.keep_seen(counted(lack.where("want > have"), F.col("have"), F.col("want")).select("source", "slot"), F.count("*"))
    added = new_walks(starts, p, epoch, zero_hop)
    walked = rounds.keep(view.walk_on(cut.unionByName(added), net, p, epoch, rounds)) if n_hits + n_added else cut.unionByName(added)
    # survivors at touched sources are numbered anew
    slots = placed.where("place < want").select("walk_id", F.col("place").alias("_slot"))
    moved = placed.where("place < want and place <> slot").select("walk_id", "source", "slot", "hops", "path").join(walked.select("walk_id"), "walk_id", "left_anti")
    changed = walked.unionByName(moved).join(slots, "walk_id", "left").withColumn("slot", F.coalesce("_slot", "slot")).drop("_slot")
    at = hits.select("walk_id", F.col("step").alias("_cut"))
    after_cut = crossings_of(walked).join(at, "walk_id", "left").where("_cut is null or step >= _cut").drop("_cut")
    before = crossings_of(old).join(at, "walk_id").where("step >= _cut").drop("_cut").unionByName(crossings_of(gone))
    stale = before.join(after_cut, ["node", "walk_id", "step"], "left_anti")
    stats = {"updates": n, "repaired": n_hits, "trimmed": n_gone, "added": n_added}
    return Delta(net, touched, changed, gone.select("walk_id", "source"), stale, after_cut, stats)


def apply_batch(state: IndexState, updates: DataFrame, sampler: str = "bernoulli", trim: str = "uniform", crossings: DataFrame | None = None) -> IndexState:
    """The state after all updates, with its tables written anew; for a large index see `plans.store.StateStore.apply`."""
    rounds = Rounds(state.edges.sparkSession, "batch")
    epoch = state.epoch + 1
    d = repair(FrameView(state, crossings), updates, state.params, epoch, rounds, state.zero_hop, sampler, trim)
    walks = rounds.keep(d.walks)
    replaced = walks.select("walk_id").unionByName(d.gone.select("walk_id"))
    merged = state.walks.select("walk_id", "source", "slot", "hops", "path").join(replaced, "walk_id", "left_anti").unionByName(walks)
    return replace(state, edges=rounds.keep(apply_updates(state.edges, d.net)), walks=rounds.keep(merged), epoch=epoch, stats=d.stats, folders=(rounds,))


def _one(state: IndexState, op: str, src: int, dst: int) -> DataFrame:
    return state.edges.sparkSession.createDataFrame([(state.epoch + 1, op, src, dst)], "tau long, op string, src long, dst long")


def apply_insert(state: IndexState, src: int, dst: int, sampler: str = "bernoulli") -> IndexState:
    return apply_batch(state, _one(state, "+", src, dst), sampler)


def apply_delete(state: IndexState, src: int, dst: int, trim: str = "uniform") -> IndexState:
    return apply_batch(state, _one(state, "-", src, dst), trim=trim)


def apply_node_updates(state: IndexState, node_updates: DataFrame) -> IndexState:
    return apply_batch(state, expand_node_updates(node_updates, state.edges))
