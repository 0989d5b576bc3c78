"""Walks made inside tasks: each task holds the graph's edges and walks its share of the walks from birth to end.

The edges go out as sorted pieces of bytes, about 4 bytes an edge in a task, so up to TASK_EDGES edges; a larger graph is walked by
the joins of `walks`. Draws are those of the joins, so the walks are the same rows.
"""

from __future__ import annotations

from weakref import WeakKeyDictionary

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.draws import Texts
from ..functions.params import PprParams
from ..functions.rng import hop_thresholds
from ..plans.iterate import Rounds

#: Edges up to which a task holds the graph, edges of a piece, walks made together.
TASK_EDGES, PIECE, TOGETHER = 40_000_000, 1_000_000, 1 << 17
#: Walks that are worth a task of their own, since each task reads all edges.
TASK_WALKS = 200_000
PATHS = "walk_id struct<source: bigint, slot: bigint, epoch: bigint>, source bigint, slot bigint, hops int, path array<bigint>"
OUT = {"paths": PATHS, "ends": "source bigint, slot bigint, terminal bigint", "counts": "source bigint, terminal bigint, cnt bigint", "hops": "walks bigint, hops bigint", "hits": "batch int, repaired bigint"}
ROWS = "kind int, first bigint, second bigint, a binary, b binary, c binary, base bigint"


def _pieces(batches):
    """Sorted edges as rows (first edge; start nodes, their numbers of edges, ends less `base`)."""
    held, n = [], 0

    def piece():
        src, dst = (np.concatenate([b.column(k).to_numpy() for b in held]) for k in (0, 1))
        nodes, degree = np.unique(src, return_counts=True)
        base = int(dst.min())
        narrow = int(dst.max()) - base < 1 << 32
        ends = (dst - base).astype(np.uint32) if narrow else dst
        return pa.RecordBatch.from_pydict({"kind": pa.array([0 if narrow else 1], pa.int32()), "first": [int(src[0])], "second": [int(dst[0])], "a": [nodes.tobytes()], "b": [degree.astype(np.int32).tobytes()], "c": [ends.tobytes()], "base": [base if narrow else 0]})

    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            n += batch.num_rows
        if n >= PIECE:
            yield piece()
            held, n = [], 0
    if n:
        yield piece()


def _asked(batches):
    """Nodes and their numbers of walks as rows of the same form."""
    for batch in batches:
        if batch.num_rows:
            source, n = (batch.column(k).to_numpy() for k in (0, 1))
            yield pa.RecordBatch.from_pydict({"kind": pa.array([2], pa.int32()), "first": [int(source[0])], "second": [0], "a": [source.tobytes()], "b": [n.tobytes()], "c": [b""], "base": [0]})


class Held:
    """A graph in a task: nodes, the place of each node's first end, and the ends as numbers of nodes."""

    def __init__(self, pieces: list[tuple]):
        pieces.sort(key=lambda x: x[1:3])
        src = np.concatenate([np.frombuffer(x[3], np.int64) for x in pieces])
        degree = np.concatenate([np.frombuffer(x[4], np.int32) for x in pieces])
        starts = np.flatnonzero(np.diff(src, prepend=src[0] - 1))  # a node may go on in the next piece
        src, degree = src[starts], np.add.reduceat(degree, starts, dtype=np.int64)
        self.ends = np.empty(int(degree.sum()), dtype=np.int32)
        low, table = int(src[0]), None
        if int(src[-1]) - low <= 16 * len(src):
            table = np.full(int(src[-1]) - low + 1, -1, dtype=np.int32)
            table[src - low] = np.arange(len(src), dtype=np.int32)
        unknown, at = [], 0
        for k, x in enumerate(pieces):
            dst = np.frombuffer(x[5], np.uint32 if x[0] == 0 else np.int64).astype(np.int64) + x[6]
            pieces[k] = None
            if table is not None:
                inside = (dst >= src[0]) & (dst <= src[-1])
                found = np.where(inside, table[np.where(inside, dst - low, 0)], -1)
            else:
                found = np.minimum(np.searchsorted(src, dst), len(src) - 1)
                found = np.where(src[found] == dst, found, -1)
            self.ends[at : at + len(dst)] = found
            bad = np.flatnonzero(found < 0)
            if len(bad):
                unknown.append((at + bad, dst[bad]))
            at += len(dst)
        self.nodes, self.degree = src, degree
        if unknown:  # dead ends
            place, who = (np.concatenate(c) for c in zip(*unknown, strict=True))
            more, which = np.unique(who, return_inverse=True)
            self.ends[place] = len(src) + which
            self.nodes, self.degree = np.concatenate([src, more]), np.concatenate([degree, np.zeros(len(more), np.int64)])
        self.first = np.cumsum(self.degree) - self.degree

    def find_all(self, nodes: np.ndarray) -> np.ndarray:
        """`find` of nodes that may come more than once."""
        some, which = np.unique(nodes, return_inverse=True)
        return self.find(some)[which]

    def find(self, nodes: np.ndarray) -> np.ndarray:
        """Numbers of the nodes; a node without an edge is entered as a dead end."""
        order = np.argsort(self.nodes, kind="stable")
        at = np.searchsorted(self.nodes, nodes, sorter=order)
        found = order[np.minimum(at, len(order) - 1)]
        new = np.flatnonzero(self.nodes[found] != nodes)
        if len(new):
            found[new] = len(self.nodes) + np.arange(len(new))
            self.nodes = np.concatenate([self.nodes, nodes[new]])
            self.degree, self.first = (np.concatenate([x, np.zeros(len(new), np.int64)]) for x in (self.degree, self.first))
        return found


def _held(pieces: list[tuple], some: np.ndarray) -> Held:
    """The graph; without any edge, one dead end of `some`."""
    if pieces:
        return Held(pieces)
    g = Held.__new__(Held)
    g.nodes, g.degree, g.first, g.ends = some[:1], np.zeros(1, np.int64), np.zeros(1, np.int64), np.zeros(1, np.int32)
    return g


def _hops(source: np.ndarray, slot: np.ndarray, p: PprParams, epoch: int, zero_hop: bool) -> np.ndarray:
    u = Texts(p.seed, "hops", source, slot, epoch).u01(len(source))
    return np.searchsorted(np.array(hop_thresholds(p.alpha)), u, side="right") + (0 if zero_hop else 1)


def _walk(g: Held, at: np.ndarray, slot: np.ndarray, p: PprParams, epoch: int, zero_hop: bool, paths: bool, numbers: bool = False):
    """Hops, and ends or whole paths (nodes, or their numbers; offsets), of the walks born at nodes `at`; in their order."""
    source = g.nodes[at]
    hops = _hops(source, slot, p, epoch, zero_hop)
    order = np.argsort(-hops, kind="stable")  # those still going are in front
    sorted_hops = hops[order]
    texts = Texts(p.seed, f"next{epoch}", source[order], slot[order], epoch)
    now = at[order].astype(np.int64)
    offsets = np.concatenate([[0], np.cumsum(hops + 1)])
    where = offsets[:-1][order]
    out = np.empty(int(offsets[-1]) if paths else 0, dtype=np.int64)
    if paths:
        out[where] = at[order] if numbers else source[order]
    for step in range(1, int(hops.max(initial=0)) + 1):
        m = int(np.searchsorted(-sorted_hops, -step, side="right"))
        here = now[:m]
        degree = g.degree[here]
        pick = np.floor(texts.u01(m, step) * degree).astype(np.int64)
        place = g.first[here] + pick
        now[:m] = np.where(degree > 0, g.ends[np.minimum(place, len(g.ends) - 1)], here)
        if paths:
            out[where[:m] + step] = now[:m] if numbers else g.nodes[now[:m]]
    ends = np.empty(len(at), dtype=np.int64)
    ends[order] = now
    return hops, ends, out, offsets


def _struct(source, slot, epoch: int) -> pa.Array:
    n = len(source)
    return pa.StructArray.from_arrays([pa.array(source), pa.array(slot), pa.array(np.full(n, epoch, np.int64))], names=["source", "slot", "epoch"])


class Marked:
    """A batch of net updates on a held graph: which nodes are touched, which of their edges go, and which of their walks are trimmed."""

    def __init__(self, g: Held, rows: list[dict], p: PprParams, epoch: int, x: float):
        src, dst, plus = (np.concatenate([np.frombuffer(r[k], t) for r in rows]) for k, t in (("a", np.int64), ("b", np.int64), ("c", np.bool_)))
        nodes, which = np.unique(src, return_inverse=True)
        k, gone = np.bincount(which[plus], minlength=len(nodes)), np.bincount(which[~plus], minlength=len(nodes))
        at = g.find(nodes)  # a node without an edge has no walk, but others may end there
        a = g.degree[at]
        b = a - gone + k
        want, have = np.ceil(b * x).astype(np.int64), np.ceil(a * x).astype(np.int64)
        self.p, self.epoch = p, epoch
        self.touched = np.full(len(g.nodes), -1, dtype=np.int32)
        self.touched[at] = np.arange(len(nodes), dtype=np.int32)
        self.a, self.k, self.share = a, k, np.where(b > 0, k / np.maximum(b, 1), 0.0)
        # removed edges as (number of the touched node, end)
        ends = g.find(dst[~plus])
        self.size = len(g.nodes)
        self.removed = np.unique(which[~plus].astype(np.int64) * self.size + ends)
        # walks of nodes that keep fewer: where a node's begin in `gone`
        self.begin, gone_walks, n = np.full(len(g.nodes), -1, dtype=np.int64), [np.zeros(0, dtype=bool)], 0
        for j in np.flatnonzero(have > want).tolist():
            slots = np.arange(have[j])
            u = Texts(p.seed, f"trim{epoch}", np.full(have[j], nodes[j]), slots, 0).u01(int(have[j]))
            gone_walks.append(np.ones(have[j], dtype=bool))
            gone_walks[-1][np.lexsort((slots, u))[: want[j]]] = False
            self.begin[at[j]] = n
            n += int(have[j])
        self.gone = np.concatenate(gone_walks)

    def hits(self, g: Held, at: np.ndarray, slot: np.ndarray, nodes: np.ndarray, offsets: np.ndarray) -> int:
        """Walks among these (their nodes as numbers) that the batch repairs."""
        inner = np.ones(len(nodes), dtype=bool)
        inner[offsets[1:] - 1] = False
        here = np.flatnonzero(inner & (self.touched[nodes] >= 0))
        if not len(here):
            return 0
        walk = np.searchsorted(offsets, here, side="right") - 1
        who = self.touched[nodes[here]]
        key = who.astype(np.int64) * self.size + nodes[here + 1]
        place = np.minimum(np.searchsorted(self.removed, key), max(len(self.removed) - 1, 0))
        hit = (self.a[who] == 0) | ((self.removed[place] == key) if len(self.removed) else False)
        rest = np.flatnonzero(~hit & (self.k[who] > 0))
        if len(rest):
            w = walk[rest]
            u = Texts(self.p.seed, f"hit{self.epoch}", g.nodes[at[w]], slot[w], 0, here[rest] - offsets[w]).u01(len(rest))
            hit[rest] = u < self.share[who[rest]]
        found = np.unique(walk[hit])
        begin = self.begin[at[found]]
        some = np.flatnonzero(begin >= 0)
        return len(found) - int(self.gone[begin[some] + slot[found[some]]].sum())


def _task(p: PprParams, epoch: int, zero_hop: bool, out: str, x: float, packs: int, asked: bool):
    def run(batches):
        pieces, starts, pack, updates = [], [], None, {}
        for batch in batches:
            for r in batch.to_pylist():
                pack = r["pack"]
                if r["kind"] == 3:
                    updates.setdefault(r["first"], []).append(r)
                    continue
                (starts if r["kind"] == 2 else pieces).append((r["kind"], r["first"], r["second"], r["a"], r["b"], r["c"], r["base"]))
        if pack is None or not (pieces or starts):
            return
        if asked and not starts:
            return
        g = _held(pieces, np.frombuffer(starts[0][3], np.int64) if starts else None)
        n_births = len(g.degree)
        if updates:
            g.find(np.unique(np.concatenate([np.frombuffer(r[k], np.int64) for rows in updates.values() for r in rows for k in ("a", "b")])))  # all numbers are given before any table by number is made
        marked = {k: Marked(g, rows, p, epoch + 1, x) for k, rows in updates.items()}
        if asked:
            source, n = (np.concatenate([np.frombuffer(s[k], np.int64) for s in starts]) for k in (3, 4))
            order = np.argsort(source)
            source, n = source[order], n[order]
            births = g.find(source)
        else:
            births, n = np.flatnonzero(g.degree[:n_births]), np.ceil(g.degree[g.degree > 0] * x).astype(np.int64)
        upto = np.cumsum(n)
        total = int(upto[-1])
        lo, end = total * pack // packs, total * (pack + 1) // packs
        tally, whose = None, -1
        while lo < end:
            hi = min(end, lo + TOGETHER)
            first, last = np.searchsorted(upto, [lo, hi - 1], side="right")
            some = np.arange(first, last + 1)
            before = upto[some] - n[some]
            each = np.minimum(upto[some], hi) - np.maximum(before, lo)
            at = np.repeat(births[some], each)
            slot = np.arange(lo, hi) - np.repeat(before, each)
            if out == "hops":
                hops = _hops(g.nodes[at], slot, p, epoch, zero_hop)
                yield pa.RecordBatch.from_pydict({"walks": [hi - lo], "hops": [int(hops.sum())]})
                lo = hi
                continue
            hops, ends, nodes, offsets = _walk(g, at, slot, p, epoch, zero_hop, out in ("paths", "hits"), out == "hits")
            if out == "hits":
                yield pa.RecordBatch.from_pydict({"batch": pa.array(list(marked), pa.int32()), "repaired": [m.hits(g, at, slot, nodes, offsets) for m in marked.values()]})
                lo = hi
                continue
            source = g.nodes[at]
            if out == "paths":
                path = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(nodes))
                batch = pa.RecordBatch.from_arrays([_struct(source, slot, epoch), pa.array(source), pa.array(slot), pa.array(hops, pa.int32()), path], names=["walk_id", "source", "slot", "hops", "path"])
                for k in range(0, hi - lo, 16384):
                    yield batch.slice(k, 16384)
            elif out == "ends":
                yield pa.RecordBatch.from_arrays([pa.array(source), pa.array(slot), pa.array(g.nodes[ends])], names=["source", "slot", "terminal"])
            else:
                cuts = np.concatenate([[0], np.cumsum(each)])
                for k, j in enumerate(some.tolist()):
                    if j != whose:
                        if tally is not None:
                            yield _counts(g, int(births[whose]), tally)
                        tally, whose = np.zeros(len(g.nodes), dtype=np.int64), j
                    mine = ends[cuts[k] : cuts[k + 1]]
                    if len(mine) * 8 > len(tally):
                        tally += np.bincount(mine, minlength=len(tally))
                    else:
                        np.add.at(tally, mine, 1)
            lo = hi
        if tally is not None:
            yield _counts(g, int(births[whose]), tally)

    return run


def _counts(g: Held, birth: int, tally: np.ndarray) -> pa.RecordBatch:
    k = np.flatnonzero(tally)
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(k), g.nodes[birth])), pa.array(g.nodes[k]), pa.array(tally[k])], names=["source", "terminal", "cnt"])


def _graph_rows(edges: DataFrame, rounds: Rounds) -> DataFrame | None:
    """The written pieces of a graph; None if it has too many edges for a task."""
    edges, m = rounds.keep_seen(edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")), F.count("*"))
    if m > TASK_EDGES:
        return None
    return rounds.keep(edges.repartitionByRange(max(1, m // PIECE), "src").sortWithinPartitions("src", "dst").mapInArrow(_pieces, ROWS))


_rows_of: WeakKeyDictionary[DataFrame, DataFrame | None] = WeakKeyDictionary()


def graph_rows(edges: DataFrame) -> DataFrame | None:
    """The pieces, made once for each frame and kept as long as the session's folder."""
    if edges not in _rows_of:
        _rows_of[edges] = _graph_rows(edges, Rounds(edges.sparkSession, "pieces"))
    return _rows_of[edges]


def walks_in_tasks(edges: DataFrame, p: PprParams, epoch: int, zero_hop: bool, out: str, x: float | None = None, asked: DataFrame | None = None, updates: DataFrame | None = None) -> DataFrame | None:
    """Rows of OUT[out] for the walks 0, 1, ... of each node: ceil(x * degree), or `asked` (source, n). None if the graph is too large
    for a task, or the draws aren't the portable ones. 'hits' gives the numbers of walks of parts of the index that each batch of `updates` (rows of `ROWS`) repairs; 'hops' gives the numbers of walks and hops of parts of the index, from its draws alone; 'counts' may give a node's terminal more than once."""
    if p.fast_hash:
        return None
    spark = edges.sparkSession
    rounds = Rounds(spark, "taskwalks")
    rows = graph_rows(edges)
    if rows is None:
        return None
    x = p.x if x is None else x
    if asked is not None:
        asked, walks = rounds.keep_seen(asked.groupBy("source").agg(F.max("n").alias("n")).select(F.col("source").cast("long").alias("source"), F.col("n").cast("long").alias("n")).where("source is not null and n > 0"), F.sum("n"))
        rows = rows.unionByName(asked.mapInArrow(_asked, ROWS))
    else:
        walks = (rows.agg(F.sum(F.octet_length("c") / F.when(F.col("kind") == 0, 4).otherwise(8))).first()[0] or 0) * x
    packs = max(1, min(spark.sparkContext.defaultParallelism, int(walks // TASK_WALKS)))
    rows = rows if updates is None else rows.unionByName(updates)
    dealt = rows.withColumn("pack", F.explode(F.sequence(F.lit(0), F.lit(packs - 1)))).repartitionById(packs, "pack")
    return dealt.mapInArrow(_task(p, epoch, zero_hop, out, x, packs, asked is not None), OUT[out])


#: Net updates up to which their repairs are counted inside tasks.
TASK_UPDATES = 1_000_000


def repairs_in_tasks(edges: DataFrame, batches: list[DataFrame], p: PprParams) -> list[dict] | None:
    """What `apply_batch` reports (updates, repaired, trimmed, added) for each of these net updates (src, dst, op) on a new index of the
    edges: its walks, trimming and hits are drawn inside tasks, and neither index nor repaired walks are written. None as for `walks_in_tasks`."""
    rounds = Rounds(edges.sparkSession, "repairs")
    sizes, rows, touched = [], None, []
    for k, net in enumerate(batches):
        kept, n = rounds.keep_seen(net.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), (F.col("op") == "+").alias("plus")), F.count("*"))
        if n > TASK_UPDATES:
            return None
        sizes.append(n)

        def packed(parts, k=k):
            for b in parts:
                if b.num_rows:
                    src, dst, plus = (b.column(c).to_numpy(zero_copy_only=False) for c in range(3))
                    yield pa.RecordBatch.from_pydict({"kind": pa.array([3], pa.int32()), "first": [k], "second": [0], "a": [src.tobytes()], "b": [dst.tobytes()], "c": [plus.astype(np.bool_).tobytes()], "base": [0]})

        own = rounds.keep(kept.mapInArrow(packed, ROWS))
        rows = own if rows is None else rows.unionByName(own)
        touched.append(kept.groupBy(F.col("src").alias("node")).agg(F.sum(F.when(F.col("plus"), 1).otherwise(-1)).alias("more")).withColumn("batch", F.lit(k)))
    found = walks_in_tasks(edges, p, 0, False, "hits", updates=rows)
    if found is None:
        return None
    hits = {r["batch"]: r["n"] for r in found.groupBy("batch").agg(F.sum("repaired").alias("n")).collect()}
    nodes = touched[0]
    for t in touched[1:]:
        nodes = nodes.unionByName(t)
    nodes = rounds.keep(nodes)
    some = nodes.select(F.col("node").alias("src")).distinct()
    old = edges.join(F.broadcast(some), "src", "left_semi").groupBy(F.col("src").alias("node")).agg(F.count("*").alias("a"))
    more = p.walks_stored(F.coalesce("a", F.lit(0)) + F.col("more")) - p.walks_stored(F.coalesce("a", F.lit(0)))
    walks = nodes.join(old, "node", "left").withColumn("w", more).groupBy("batch").agg(F.sum(F.greatest(-F.col("w"), F.lit(0))).alias("trimmed"), F.sum(F.greatest("w", F.lit(0))).alias("added")).collect()
    walks = {r["batch"]: r for r in walks}
    out = []
    for k, n in enumerate(sizes):
        w = walks.get(k)
        out.append({"updates": n, "repaired": hits.get(k, 0), "trimmed": w["trimmed"] if w else 0, "added": w["added"] if w else 0})
    rounds.drop_all()
    return out


#: Walks with their paths, given as rows, up to which a call finishes them inside tasks.
TASK_ROWS = 1_000_000


def finished_in_tasks(walks: DataFrame, edges: DataFrame, p: PprParams, epoch: int) -> DataFrame | None:
    """Written walks (with any prefix of their path) walked to their hops; None as for `walks_in_tasks`, or for too many rows."""
    n = walks.count()
    if p.fast_hash or n > TASK_ROWS:
        return None
    rows = _graph_rows(edges, Rounds(edges.sparkSession, "taskgraph"))
    if rows is None:
        return None
    packs = max(1, min(walks.sparkSession.sparkContext.defaultParallelism, n // 20_000))
    nested = walks.schema["walk_id"].dataType.typeName() == "struct"

    def run(own: pa.Table, graph: pa.Table) -> pa.Table:
        own = own.drop_columns(["pack"]).combine_chunks()
        path = own.column("path").combine_chunks()
        path = path.chunk(0) if isinstance(path, pa.ChunkedArray) else path
        if not len(own):
            return own
        sizes, nodes = np.diff(path.offsets.to_numpy()), path.flatten().to_numpy()
        ids = own.column("walk_id").combine_chunks()
        ids = ids.chunk(0) if isinstance(ids, pa.ChunkedArray) else ids
        keys = [f.to_numpy() for f in ids.flatten()] if nested else [ids.to_numpy()]
        g = _held([tuple(r[c] for c in ("kind", "first", "second", "a", "b", "c", "base")) for r in graph.to_pylist()], nodes)
        hops = own.column("hops").to_numpy().astype(np.int64)
        full = np.maximum(hops + 1, sizes)
        offsets, held = np.concatenate([[0], np.cumsum(full)]), np.cumsum(sizes) - sizes
        out = np.empty(int(offsets[-1]), dtype=np.int64)
        out[np.repeat(offsets[:-1] - held, sizes) + np.arange(len(nodes))] = nodes
        at, now = sizes.astype(np.int64), g.find(nodes[held + sizes - 1])
        live = np.flatnonzero(at <= hops)
        while len(live):
            degree = g.degree[now[live]]
            u = Texts(p.seed, f"next{epoch}", *[k[live] for k in keys], at[live], room=0).u01(len(live))
            place = g.first[now[live]] + np.floor(u * degree).astype(np.int64)
            now[live] = np.where(degree > 0, g.ends[np.minimum(place, len(g.ends) - 1)], now[live])
            out[offsets[live] + at[live]] = g.nodes[now[live]]
            at[live] += 1
            live = live[at[live] <= hops[live]]
        done = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(out))
        return own.set_column(own.schema.get_field_index("path"), "path", done)

    kept = walks.select("walk_id", "source", "slot", "hops", "path")
    dealt = kept.withColumn("pack", F.pmod(F.xxhash64("walk_id"), F.lit(packs)).cast("int"))
    copies = rows.withColumn("pack", F.explode(F.sequence(F.lit(0), F.lit(packs - 1))))
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in kept.schema)
    return dealt.groupBy("pack").cogroup(copies.groupBy("pack")).applyInArrow(run, schema)
