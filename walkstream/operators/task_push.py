"""Push rounds made inside tasks that hold the whole graph, as `task_walks` holds it: a task runs the rounds of its sources.

For graphs that are too large for the tables of `push.near_rounds`, whatever part of them the sources reach. A round of few nodes
takes their edges only, a round of many goes over all edges in blocks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.params import PprParams
from ..plans.iterate import Rounds
from .task_walks import TASK_EDGES, TASK_WALKS, TOGETHER, Held, _held, _walk, graph_rows

#: Edges of a round that are taken together, copies of a graph's edges that are dealt out, and sources up to which each is dealt by its rank.
BLOCK, COPIES, DEALT = 1 << 21, 8, 1000
STATE = "source long, node long, reserve double, residue double, out_deg long"


def edges_of(g: Held, nodes: np.ndarray, degree: np.ndarray) -> np.ndarray:
    """Numbers of the ends of these nodes' edges, node by node."""
    before = np.cumsum(degree) - degree
    return g.ends[np.repeat(g.first[nodes] - before, degree) + np.arange(int(degree.sum()))]


def blocks_of(degree: np.ndarray):
    """Ranges of nodes with some BLOCK edges together."""
    upto, lo = np.cumsum(degree), 0
    while lo < len(degree):
        hi = max(lo + 1, int(np.searchsorted(upto, upto[lo] - degree[lo] + BLOCK, side="right")))
        yield lo, hi
        lo = hi


def spread(g: Held, nodes: np.ndarray, share: np.ndarray, into: np.ndarray, met: np.ndarray) -> None:
    """Add each node's share to the ends of its edges."""
    degree = g.degree[nodes]
    if 2 * int(degree.sum()) > len(g.ends):  # all edges, which needs no list of them
        every = np.zeros(len(g.nodes))
        every[nodes] = share
        got = np.zeros(len(g.nodes))
        for lo, hi in blocks_of(g.degree):
            first = int(g.first[lo])
            to = g.ends[first : first + int(g.degree[lo:hi].sum())]
            if len(to):
                got += np.bincount(to, weights=np.repeat(every[lo:hi], g.degree[lo:hi]), minlength=len(got))
        into += got
        met |= got > 0
        return
    for lo, hi in blocks_of(degree):
        to, add = edges_of(g, nodes[lo:hi], degree[lo:hi]), np.repeat(share[lo:hi], degree[lo:hi])
        if 8 * len(to) > len(into):
            into += np.bincount(to, weights=add, minlength=len(into))
        else:
            np.add.at(into, to, add)
        met[to] = True


def held_rounds(g: Held, reserve: np.ndarray, residue: np.ndarray, alpha: float, r_max: float | None, rounds: int | None) -> np.ndarray:
    """The rounds of `push.rounds_at` on a held graph."""
    met, done = np.zeros(len(g.nodes), dtype=bool), 0
    least = None if r_max is None else g.degree * r_max
    while rounds is None or done < rounds:
        front = np.flatnonzero(residue > 0 if least is None else (residue > 0) & (residue >= least))
        if not len(front):
            break
        moved, degree = residue[front], g.degree[front]
        reserve[front] += np.where(degree == 0, moved, moved * alpha)
        residue[front] = 0.0
        going = degree > 0
        spread(g, front[going], moved[going] * (1 - alpha) / degree[going], residue, met)
        done += 1
    return met


def graph_in(table: pa.Table, some: np.ndarray) -> Held:
    """The graph of these pieces, whose bytes are read where they lie."""
    kind, first, second, base = (table.column(c).to_pylist() for c in ("kind", "first", "second", "base"))
    a, b, c = ([v.as_buffer() for v in table.column(x)] for x in "abc")
    return _held(list(zip(kind, first, second, a, b, c, base, strict=True)), some)


def with_pack(rows: DataFrame, key: str, packs: int) -> DataFrame:
    """`pack` of each row by its key: each key by its rank where they are few, else by hash."""
    keys = [r[0] for r in rows.select(key).distinct().orderBy(key).limit(DEALT + 1).collect()]
    if len(keys) > DEALT:
        return rows.withColumn("pack", F.pmod(F.xxhash64(key), F.lit(packs)).cast("int"))
    dealt = rows.sparkSession.createDataFrame([(k, i % packs) for i, k in enumerate(keys)], f"{key} long, pack int")
    return rows.join(F.broadcast(dealt), key)


def packs_for(spark, m: int, most: int) -> int:
    """Tasks that get a copy of a graph of m edges."""
    return max(1, min(most, spark.sparkContext.defaultParallelism, COPIES * TASK_EDGES // max(1, m)))


def pushed_in_tasks(edges: DataFrame, m: int, state: DataFrame, alpha: float, r_max: float | None, rounds: int | None) -> DataFrame | None:
    """The state after these rounds; None if the graph is too large for a task. state: a written one, its out_deg isn't read."""
    if m > TASK_EDGES:
        return None
    rows = graph_rows(edges)
    if rows is None:
        return None
    packs = packs_for(state.sparkSession, m, state.select("source").distinct().count())

    def run(own: pa.Table, graph: pa.Table):
        source, node = (own.column(c).to_numpy() for c in ("source", "node"))
        if not len(source):
            return own.select(["source", "node", "reserve", "residue", "out_deg"])
        g = graph_in(graph, node)
        at, out = g.find_all(node), []
        for one in np.unique(source):
            mine = np.flatnonzero(source == one)
            reserve, residue, have = np.zeros(len(g.nodes)), np.zeros(len(g.nodes)), np.zeros(len(g.nodes), dtype=bool)
            k = at[mine]
            reserve[k], residue[k], have[k] = own.column("reserve").to_numpy()[mine], own.column("residue").to_numpy()[mine], True
            k = np.flatnonzero(held_rounds(g, reserve, residue, alpha, r_max, rounds) | have)
            out.append(pa.table([np.full(len(k), one), g.nodes[k], reserve[k], residue[k], g.degree[k]], names=["source", "node", "reserve", "residue", "out_deg"]))
        return pa.concat_tables(out)

    dealt = with_pack(state.select("source", "node", "reserve", "residue", "out_deg"), "source", packs)
    copies = rows.withColumn("pack", F.explode(F.sequence(F.lit(0), F.lit(packs - 1))))
    return dealt.groupBy("pack").cogroup(copies.groupBy("pack")).applyInArrow(run, STATE)


#: Numbers (sources times nodes) that a task sums shares in.
SUMS = 20_000_000


def shares_in_tasks(edges: DataFrame, size: tuple[int, int], need: DataFrame, p: PprParams, epoch: int = 0, zero_hop: bool = False) -> DataFrame | None:
    """(source, node, score): each row of `need` (source, via, n, share) gives its share to the ends of the walks 0, ..., n - 1 of `via`,
    which are drawn for all sources at once and aren't written. A node may come more than once. None as for `walks_in_tasks`, or for too many sources."""
    n_nodes, m = size
    if p.fast_hash or m > TASK_EDGES:
        return None
    need, walks = Rounds(edges.sparkSession, "need").keep_seen(need.select("source", "via", F.col("n").cast("long").alias("n"), "share"), F.sum("n"))
    if need.select("source").distinct().count() * n_nodes > SUMS:
        return None
    rows = graph_rows(edges)
    if rows is None:
        return None
    packs = packs_for(edges.sparkSession, m, walks // TASK_WALKS)

    def run(own: pa.Table, graph: pa.Table) -> pa.Table:
        source, via, n, share = (own.column(c).to_numpy() for c in ("source", "via", "n", "share"))
        if not len(source):
            return pa.table([source, via, share], names=["source", "node", "score"])
        g = graph_in(graph, via)
        nodes, which = np.unique(via, return_inverse=True)
        births = g.find(nodes)
        whose, row = np.unique(source, return_inverse=True)
        use, each_gives = np.zeros((len(whose), len(nodes)), np.int64), np.zeros((len(whose), len(nodes)))
        use[row, which], each_gives[row, which] = n, share
        score = np.zeros((len(whose), len(g.nodes)))
        upto = np.cumsum(use.max(axis=0))
        lo, end = 0, int(upto[-1])
        while lo < end:
            hi = min(end, lo + TOGETHER)
            first, last = np.searchsorted(upto, [lo, hi - 1], side="right")
            some = np.arange(first, last + 1)
            before = np.where(some > 0, upto[some - 1], 0)
            k = np.repeat(some, np.minimum(upto[some], hi) - np.maximum(before, lo))
            slot = np.arange(lo, hi) - np.where(k > 0, upto[k - 1], 0)
            ends = _walk(g, births[k], slot, p, epoch, zero_hop, False)[1]
            for s in range(len(whose)):
                mine = slot < use[s][k]
                np.add.at(score[s], ends[mine], each_gives[s][k[mine]])
            lo = hi
        out = []
        for s, one in enumerate(whose):
            got = np.flatnonzero(score[s])
            out.append(pa.table([np.full(len(got), one), g.nodes[got], score[s][got]], names=["source", "node", "score"]))
        return pa.concat_tables(out)

    dealt = need.withColumn("pack", F.pmod(F.xxhash64("via"), F.lit(packs)).cast("int"))
    copies = rows.withColumn("pack", F.explode(F.sequence(F.lit(0), F.lit(packs - 1))))
    return dealt.groupBy("pack").cogroup(copies.groupBy("pack")).applyInArrow(run, "source long, node long, score double")


def back_rounds(g: Held, out_deg: np.ndarray, target: int, limit: float, alpha: float) -> tuple[np.ndarray, np.ndarray]:
    """Reserve and residue by node of `push.backward_push` for one target; g: the graph with its edges turned round."""
    reserve, residue = np.zeros(len(g.nodes)), np.zeros(len(g.nodes))
    residue[target] = 1.0
    front = np.array([target] if limit <= 1.0 else [], dtype=np.int64)
    while len(front):
        moved = residue[front]
        residue[front] = 0.0
        total = np.where(out_deg[front] == 0, moved / alpha, moved)  # a self-loop's geometric series
        reserve[front] += total * alpha
        degree, met = g.degree[front], []
        for lo, hi in blocks_of(degree):
            to = edges_of(g, front[lo:hi], degree[lo:hi])
            add = np.repeat(total[lo:hi] * (1 - alpha), degree[lo:hi]) / out_deg[to]
            if 8 * len(to) > len(residue):
                residue += np.bincount(to, weights=add, minlength=len(residue))
                met.append(None)
            else:
                np.add.at(residue, to, add)
                met.append(to)
        if any(to is None for to in met):
            front = np.flatnonzero(residue >= limit)
        else:
            front = np.unique(np.concatenate(met))
            front = front[residue[front] >= limit]
    return reserve, residue


def stale_in_tasks(edges: DataFrame, m: int, rates: DataFrame, alpha: float, r_b: float, scale_by_degree: bool) -> DataFrame | None:
    """What `engines.staleness_step` sums over the targets, each pushed back in one task: rows (node, sigma, floor), a node may come more than
    once, and rows without a node that hold parts of the floor. rates: target, rate. None if the graph is too large for a task."""
    if m > TASK_EDGES:
        return None
    rows = graph_rows(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    if rows is None:
        return None
    rates, n = Rounds(edges.sparkSession, "rates").keep_seen(rates.select(F.col("target").cast("long").alias("target"), "rate"), F.count("*"))
    packs = packs_for(edges.sparkSession, m, n)

    def run(own: pa.Table, graph: pa.Table) -> pa.Table:
        target, rate = (own.column(c).to_numpy() for c in ("target", "rate"))
        if not len(target):
            return pa.table([target, rate, rate], names=["node", "sigma", "floor"])
        g = graph_in(graph, target)
        at = g.find_all(target)
        out_deg = np.zeros(len(g.nodes), dtype=np.int64)
        if int(g.degree.sum()):
            for lo in range(0, len(g.ends), BLOCK):
                out_deg += np.bincount(g.ends[lo : lo + BLOCK], minlength=len(g.nodes))
        sigma, met, floor = np.zeros(len(g.nodes)), np.zeros(len(g.nodes), dtype=bool), 0.0
        for t, r in zip(at.tolist(), rate.tolist(), strict=True):
            limit = r_b * max(int(out_deg[t]), 1) if scale_by_degree else r_b
            reserve, residue = back_rounds(g, out_deg, t, limit, alpha)
            least, some = min(1.0, limit * r), np.flatnonzero(reserve)
            sigma[some] += np.minimum(1.0, (reserve[some] + limit) * r) - least
            met |= (reserve > 0) | (residue > 0)
            floor += least
        k = np.flatnonzero(met)
        return pa.table([pa.array([*g.nodes[k].tolist(), None], pa.int64()), np.append(sigma[k], 0.0), np.append(np.zeros(len(k)), floor)], names=["node", "sigma", "floor"])

    copies = rows.withColumn("pack", F.explode(F.sequence(F.lit(0), F.lit(packs - 1))))
    return with_pack(rates, "target", packs).groupBy("pack").cogroup(copies.groupBy("pack")).applyInArrow(run, "node long, sigma double, floor double")
