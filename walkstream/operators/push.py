"""Power iteration, forward and backward push, for many sources in one job.

Rounds are synchronous: all nodes over the threshold push together, which keeps the push invariant. State tables are
sparse and carry the out-degree of their node, so that the frontier is known before the join: only its rows meet their edges.
`every` rounds are planned together and then written; the size of the frontier is counted while they are written.

Rounds never leave what the sources reach. While that has at most NEAR_EDGES edges, counted first, the sources are dealt over
tasks and each task runs the rounds of its sources on those edges. A graph of more than NEAR_EDGES edges that a task can hold
(`task_push`) is dealt out whole instead, without a search of what is in reach; beyond that the rounds are joins of the whole graph.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.params import PprParams
from ..plans.iterate import Rounds
from .graph import HUB
from .graph import _sizes as known_sizes
from .graph import degrees as degrees_of
from .task_push import pushed_in_tasks

#: A frontier of at most so many rows is sent to the edges; a larger one is joined by a shuffle.
BROADCAST_ROWS = 100_000
#: Edges within reach up to which the rounds of a source run in one task (some 50 bytes each there), and rows of their states in a task.
NEAR_EDGES, NEAR_ROWS = 4_000_000, 2_000_000
STATE = "source long, node long, reserve double, residue double, out_deg long"


def with_degree(edges: DataFrame, degrees: DataFrame | None = None) -> DataFrame:
    """Edges with the out-degree of their source."""
    d = degrees if degrees is not None else degrees_of(edges)
    return edges.select("src", "dst").join(d.select(F.col("node").alias("src"), "out_deg"), "src")


def _parts(degree, hub: int):
    """Parts that the edges of a node are dealt over: one for each `hub` edges."""
    return F.ceil(degree / F.lit(hub)).cast("int")


def push_table(edges: DataFrame, degrees: DataFrame, hub: int = HUB) -> DataFrame:
    """src, dst, dst_deg, kind: the edges as a push needs them, those of a node in parts 1, 2, ... of some `hub` edges each."""
    to = degrees.select(F.col("node").alias("dst"), F.col("out_deg").alias("dst_deg"))
    kind = (F.pmod(F.xxhash64("dst"), _parts(F.col("out_deg"), hub)) + 1).cast("int")
    return with_degree(edges, degrees).join(to, "dst").select("src", "dst", "dst_deg", kind.alias("kind"))


def seed_state(sources: DataFrame, degrees: DataFrame) -> DataFrame:
    """All residue at the source; a source without an edge is a dead end."""
    d = degrees.select(F.col("node").alias("source"), "out_deg")
    return sources.select("source").join(d, "source", "left").select("source", F.col("source").alias("node"), F.lit(0.0).alias("reserve"), F.lit(1.0).alias("residue"), F.coalesce("out_deg", F.lit(0)).cast("long").alias("out_deg"))


def is_active(r_max: float | None):
    """Frontier test; r_max None takes every residue."""
    return F.col("residue") > 0 if r_max is None else (F.col("residue") > 0) & (F.col("residue") >= F.col("out_deg") * F.lit(r_max))


def _summed(rows: DataFrame) -> DataFrame:
    return rows.groupBy("source", "node").agg(F.sum("reserve").alias("reserve"), F.sum("residue").alias("residue"), F.max("out_deg").alias("out_deg"))


def _stay(alpha: float, moved):
    return F.col("reserve") + F.when(F.col("out_deg") == 0, moved).otherwise(moved * alpha)


def rounds_of(table: DataFrame, alpha: float, r_max: float | None, hub: int = HUB) -> Callable[[DataFrame], DataFrame]:
    """The function of one round: a row stays at its node (kind 0) and, if it is in the frontier, goes to each part of its edges
    (kind 1, 2, ...). One join and one sum, so that rounds planned together stay linear in size. Dead ends turn their residue
    into reserve."""
    active, stays = is_active(r_max), F.col("kind") == 0
    kinds = F.when(active, F.sequence(F.lit(0), _parts(F.col("out_deg"), hub))).otherwise(F.array(F.lit(0)))
    split = [F.col(c) for c in ("source", "node", "reserve", "residue", "out_deg")] + [F.when(active, F.col("residue")).otherwise(0.0).alias("moved"), F.explode(kinds).alias("kind")]
    edges = table.withColumnRenamed("src", "node")
    reserve = F.when(stays, _stay(alpha, F.col("moved"))).otherwise(0.0)
    residue = F.when(stays, F.col("residue") - F.col("moved")).otherwise(F.col("moved") * (1 - alpha) / F.col("out_deg"))
    out_deg = F.when(stays, F.col("out_deg")).otherwise(F.col("dst_deg"))
    sent = [F.col("source"), F.when(stays, F.col("node")).otherwise(F.col("dst")).alias("node"), reserve.alias("reserve"), residue.alias("residue"), out_deg.alias("out_deg")]
    sums = [F.sum("reserve").alias("reserve"), F.sum("residue").alias("residue"), F.max("out_deg").alias("out_deg")]
    return lambda state: state.select(*split).join(edges, ["node", "kind"], "left").select(*sent).groupBy("source", "node").agg(*sums)


def sparse_round(state: DataFrame, table: DataFrame, alpha: float, r_max: float) -> DataFrame:
    """The same round for a small frontier, which is broadcast to the edges: they aren't shuffled. Reads the state twice, so
    it is written after each round."""
    active = is_active(r_max)
    moved = F.when(active, F.col("residue")).otherwise(0.0)
    near = state.select("source", "node", _stay(alpha, moved).alias("reserve"), (F.col("residue") - moved).alias("residue"), "out_deg")
    front = state.where(active & (F.col("out_deg") > 0)).select("source", F.col("node").alias("src"), (F.col("residue") * (1 - alpha) / F.col("out_deg")).alias("share"))
    far = table.join(F.broadcast(front), "src").select("source", F.col("dst").alias("node"), F.lit(0.0).alias("reserve"), F.col("share").alias("residue"), F.col("dst_deg").alias("out_deg"))
    return _summed(near.unionByName(far))


class PushGraph:
    """Degrees and edges of one graph, each written where a push first needs it and used by every push on it."""

    def __init__(self, edges: DataFrame, name: str = "push"):
        self.rounds, self.given = Rounds(edges.sparkSession, name), edges
        self._near: tuple[DataFrame, DataFrame | None, int] | None = None

    @cached_property
    def degrees(self) -> DataFrame:
        return self.rounds.keep(degrees_of(self.given))

    @cached_property
    def edges(self) -> DataFrame:
        return self.rounds.keep(self.given.select("src", "dst"))

    @cached_property
    def size(self) -> tuple[int, int]:
        """Nodes with an edge, and edges; of a frame whose size is known, or from the degrees."""
        if self.given in known_sizes:
            return known_sizes[self.given]
        r = self.degrees.agg(F.count("*").alias("n"), F.sum("out_deg").alias("m")).first()
        return r["n"], r["m"] or 0

    @property
    def n(self) -> int:
        return self.size[0]

    @property
    def m(self) -> int:
        return self.size[1]

    def keep(self, state: DataFrame, r_max: float | None) -> tuple[DataFrame, int]:
        """The written state and its frontier's size."""
        return self.rounds.keep_seen(state, F.sum(F.when(is_active(r_max), 1).otherwise(0)))


    @cached_property
    def table(self) -> DataFrame:
        return self.rounds.keep(push_table(self.edges, self.degrees))

    def near(self, starts: DataFrame, most: int) -> tuple[DataFrame | None, int]:
        """(edges src, dst of all nodes that the starts (node) reach, number of these nodes that have an edge); None if there are more than `most`
        edges. What was found last serves all starts within it."""
        if self.m <= most:
            return self.edges, self.n
        if self._near and not starts.join(self._near[0], "node", "left_anti").limit(1).count():
            return self._near[1:]
        source, went, edges = self.degrees.where("out_deg > 0"), F.sum("out_deg"), 0
        front, new = self.rounds.keep_seen(source.join(self._sent(starts.select("node").distinct()), "node"), went)
        seen = front
        while new:
            edges += new
            if edges > most:
                self._near = seen.select("node"), None, 0
                return None, 0
            ahead = self.edges.join(self._sent(front.select(F.col("node").alias("src"))), "src").select(F.col("dst").alias("node")).distinct()
            ahead = self.rounds.keep(ahead.join(self._sent(seen.select("node")), "node", "left_anti"))
            front, new = self.rounds.keep_seen(source.join(self._sent(ahead), "node"), went)
            seen = self.rounds.keep(seen.unionByName(front))
        found = self.rounds.keep(self.edges.join(self._sent(seen.select(F.col("node").alias("src"))), "src").select("src", "dst"))
        nodes = self.rounds.keep(found.select(F.col("dst").alias("node")).union(seen.select("node")).distinct())
        self._near = nodes, found, nodes.count()
        return self._near[1:]

    @staticmethod
    def _sent(few: DataFrame) -> DataFrame:
        return F.broadcast(few) if few.count() <= BROADCAST_ROWS else few


def _columns(state: DataFrame) -> DataFrame:
    return state.select("source", "node", "reserve", "residue", "out_deg")


def rounds_at(src: np.ndarray, dst: np.ndarray, reserve: np.ndarray, residue: np.ndarray, alpha: float, r_max: float | None, rounds: int | None) -> np.ndarray:
    """The rounds of `rounds_of` on arrays by node, in place, until no frontier is left or `rounds` are done; whether an edge brought a node a row."""
    n = len(reserve)
    degree, met, done = np.bincount(src, minlength=n), np.zeros(n, dtype=bool), 0
    while rounds is None or done < rounds:
        active = residue > 0 if r_max is None else (residue > 0) & (residue >= degree * r_max)
        if not active.any():
            break
        moved = np.where(active, residue, 0.0)
        reserve += np.where(degree == 0, moved, moved * alpha)
        residue -= moved
        going = active[src]
        to, share = dst[going], (moved * (1 - alpha) / np.maximum(degree, 1))[src[going]]
        met[to] = True
        residue += np.bincount(to, weights=share, minlength=n)
        done += 1
    return met


def in_tasks(g: PushGraph, sources: DataFrame, init: DataFrame | None, alpha: float, r_max: float | None, rounds: int | None) -> DataFrame | None:
    """The state after these rounds from the sources or from `init`, each source's in one task: on the edges in reach, or on the whole graph if it
    is large but fits a task; None where neither does."""
    if g.m > NEAR_EDGES:
        seeds = sources.select(F.col("source").cast("long").alias("source")).select("source", F.col("source").alias("node"), F.lit(0.0).alias("reserve"), F.lit(1.0).alias("residue"), F.lit(0).cast("long").alias("out_deg"))
        made = pushed_in_tasks(g.given, g.m, g.rounds.keep(seeds if init is None else _columns(init)), alpha, r_max, rounds)
        if made is not None:
            return made
    return near_rounds(g, seed_state(sources, g.degrees) if init is None else _columns(init), alpha, r_max, rounds)


def near_rounds(g: PushGraph, state: DataFrame, alpha: float, r_max: float | None, rounds: int | None) -> DataFrame | None:
    """The state after these rounds, each source's in one task; None where too many edges are in reach."""
    state = g.rounds.keep(state)
    edges, n_nodes = g.near(state.select("node"), NEAR_EDGES)
    if edges is None:
        return None
    n_sources = state.select("source").distinct().count()
    packs = max(1, min(n_sources, max(state.sparkSession.sparkContext.defaultParallelism, -(-n_sources * n_nodes // NEAR_ROWS))))
    if packs * min(g.m, NEAR_EDGES) > 16 * NEAR_EDGES:  # copies of the edges
        return None

    def run(own: pa.Table, edges: pa.Table) -> pa.Table:
        out = []
        src, dst = (edges.column(c).to_numpy() for c in ("src", "dst"))
        source, node = (own.column(c).to_numpy() for c in ("source", "node"))
        nodes = np.unique(np.concatenate([src, dst, node]))
        src, dst = np.searchsorted(nodes, src), np.searchsorted(nodes, dst)
        degree = np.bincount(src, minlength=len(nodes))
        for one in np.unique(source):
            at = np.flatnonzero(source == one)
            rows = np.searchsorted(nodes, node[at])
            reserve, residue, have = np.zeros(len(nodes)), np.zeros(len(nodes)), np.zeros(len(nodes), dtype=bool)
            reserve[rows], residue[rows], have[rows] = own.column("reserve").to_numpy()[at], own.column("residue").to_numpy()[at], True
            k = np.flatnonzero(rounds_at(src, dst, reserve, residue, alpha, r_max, rounds) | have)
            out.append(pa.table([np.full(len(k), one), nodes[k], reserve[k], residue[k], degree[k]], names=["source", "node", "reserve", "residue", "out_deg"]))
        return pa.concat_tables(out) if out else own.select(["source", "node", "reserve", "residue", "out_deg"])

    dealt = state.withColumn("pack", F.pmod(F.xxhash64("source"), F.lit(packs)).cast("int"))
    copies = edges.crossJoin(F.broadcast(state.sparkSession.range(packs).select(F.col("id").cast("int").alias("pack"))))
    return dealt.groupBy("pack").cogroup(copies.groupBy("pack")).applyInArrow(run, STATE)


def forward_push(edges: DataFrame, sources: DataFrame, p: PprParams, r_max: float, init: DataFrame | None = None, max_rounds: int | None = None, every: int = 3, graph: PushGraph | None = None) -> DataFrame:
    """Push state (source, node, reserve, residue, out_deg): until no frontier is left, or exactly max_rounds rounds.

    init: an earlier state to go on from. graph: the graph's tables, if they are already there.
    """
    g = graph or PushGraph(edges)
    near = in_tasks(g, sources, init, p.alpha, r_max, max_rounds)
    if near is not None:
        return g.rounds.keep(near)
    state, done = _columns(init) if init is not None else seed_state(sources, g.degrees), 0
    push_round = rounds_of(g.table, p.alpha, r_max)
    while max_rounds is None or done < max_rounds:
        step = every if max_rounds is None else min(every, max_rounds - done)
        for _ in range(step):
            state = push_round(state)
        (state, front), done = g.keep(state, r_max), done + step
        if max_rounds is None and not front:
            break
    return state


def power_ppr(edges: DataFrame, sources: DataFrame, p: PprParams, rounds: int = 160, every: int = 8) -> DataFrame:
    """Ground truth: all mass moves in each round; (source, node, score)."""
    g = PushGraph(edges, "power")
    near = in_tasks(g, sources, None, p.alpha, None, rounds)
    if near is not None:
        return g.rounds.keep(near).where("reserve > 0").select("source", "node", F.col("reserve").alias("score"))
    state = seed_state(sources, g.degrees)
    push_round = rounds_of(g.table, p.alpha, None)
    for k in range(rounds):
        state = push_round(state)
        if k % every == every - 1:
            state = g.rounds.keep(state)
    return state.where("reserve > 0").select("source", "node", F.col("reserve").alias("score"))


def power_push(edges: DataFrame, sources: DataFrame, p: PprParams, r_max: float, dense_fraction: float = 0.25, every: int = 3) -> DataFrame:
    """Whole-graph sweeps by a shuffled join while the frontier holds `dense_fraction` of the nodes, else rounds of the
    frontier alone, broadcast to the edges while it has at most BROADCAST_ROWS rows.

    A sweep pushes every residue, whatever its degree, so it converges as power iteration does.
    """
    g = PushGraph(edges, "blend")
    n, n_sources = g.degrees.count(), max(1, sources.count())
    state, front = g.keep(seed_state(sources, g.degrees), r_max)
    sweep, push_round = rounds_of(g.table, p.alpha, None), rounds_of(g.table, p.alpha, r_max)
    while front:
        if front >= dense_fraction * n * n_sources:
            for _ in range(every):
                state = sweep(state)
        elif front <= BROADCAST_ROWS:
            state = sparse_round(state, g.table, p.alpha, r_max)
        else:
            state = push_round(state)
        state, front = g.keep(state, r_max)
    return state


def backward_push(edges: DataFrame, targets: DataFrame, p: PprParams, r_b: float, scale_by_degree: bool = False, every: int = 3, max_rounds: int | None = None) -> DataFrame:
    """(target, node, reserve, residue, limit): reserve <= score of the target from the node <= reserve + limit, where a node
    without a row has reserve 0.

    limit: r_b, or with scale_by_degree r_b times the target's out-degree (1 at least). A dead end keeps its mass as if it had
    a self-loop: what stands there counts wholly.
    """
    tables = Rounds(edges.sparkSession, "back")
    degrees = tables.keep(degrees_of(edges))
    # the edges by their end, each with the degree of its start, and whether the start's own degree is known there
    table = tables.keep(with_degree(edges, degrees).select(F.col("dst").alias("node"), "src", F.col("out_deg").alias("src_deg"), F.lit(1).alias("kind")))
    d = degrees.select(F.col("node").alias("target"), "out_deg")
    limit = F.greatest(F.col("out_deg"), F.lit(1)) * F.lit(float(r_b)) if scale_by_degree else F.lit(float(r_b))
    state = targets.select("target").join(d, "target", "left").withColumn("out_deg", F.coalesce("out_deg", F.lit(0)).cast("long")).select("target", F.col("target").alias("node"), F.lit(0.0).alias("reserve"), F.lit(1.0).alias("residue"), "out_deg", limit.alias("limit"))
    done = 0
    while max_rounds is None or done < max_rounds:
        step = every if max_rounds is None else min(every, max_rounds - done)
        for _ in range(step):
            active = F.col("residue") >= F.col("limit")
            split = state.withColumn("moved", F.when(active, F.col("residue")).otherwise(0.0)).withColumn("kind", F.explode(F.when(active, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))))
            j = split.join(table, ["node", "kind"], "left").where("kind = 0 or src is not null")
            stays = F.col("kind") == 0
            total = F.when(F.col("out_deg") == 0, F.col("moved") / p.alpha).otherwise(F.col("moved"))  # a self-loop's geometric series
            reserve = F.when(stays, F.col("reserve") + total * p.alpha).otherwise(0.0)
            residue = F.when(stays, F.col("residue") - F.col("moved")).otherwise(total * (1 - p.alpha) / F.col("src_deg"))
            rows = j.select("target", F.when(stays, F.col("node")).otherwise(F.col("src")).alias("node"), "limit", reserve.alias("reserve"), residue.alias("residue"), F.when(stays, F.col("out_deg")).otherwise(F.col("src_deg")).alias("out_deg"))
            state = rows.groupBy("target", "node", "limit").agg(F.sum("reserve").alias("reserve"), F.sum("residue").alias("residue"), F.max("out_deg").alias("out_deg"))
        (state, front), done = tables.keep_seen(state, F.sum(F.when(F.col("residue") >= F.col("limit"), 1).otherwise(0))), done + step
        if max_rounds is None and not front:
            break
    return state.select("target", "node", "reserve", "residue", "limit")


def check_push_invariant(state: DataFrame, exact: DataFrame) -> DataFrame:
    """Largest gap between exact scores and reserve + sum of residue x exact scores, by source; small graphs only."""
    far = state.where("residue > 0").select("source", F.col("node").alias("via"), "residue").join(exact.select(F.col("source").alias("via"), "node", "score"), "via").select("source", "node", (F.col("residue") * F.col("score")).alias("v"))
    near = state.select("source", "node", F.col("reserve").alias("v"))
    got = far.unionByName(near).groupBy("source", "node").agg(F.sum("v").alias("v"))
    both = got.join(exact, ["source", "node"], "left")
    return both.groupBy("source").agg(F.max(F.abs(F.col("v") - F.coalesce("score", F.lit(0.0)))).alias("gap"))


def push_stats(state: DataFrame) -> DataFrame:
    return state.groupBy("source").agg(F.count("*").alias("nodes"), F.sum(F.when(F.col("reserve") > 0, 1).otherwise(0)).alias("pushed"), F.sum("residue").alias("left_mass"))
