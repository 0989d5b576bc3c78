"""The proposal and its baselines behind one interface: update(updates) and query(sources), topk(sources, k)."""

from __future__ import annotations

from copy import copy
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.params import PprParams
from ..plans.iterate import Rounds
from ..plans.store import StateStore
from .graph import apply_updates, degrees, graph_size, normalize_updates
from .push import PushGraph, backward_push, forward_push
from .query import query_indexed, query_online, query_topk, refine, topk_by_levels, topk_online
from .repair import IndexState, apply_batch, build_state, touched_nodes
from .task_push import stale_in_tasks
from .task_walks import walks_in_tasks
from .walks import build_walk_index, counted, new_walks, walk_ends, walk_on

UPDATE = "tau long, op string, src long, dst long"


def _one_by_one(updates: DataFrame):
    """The updates as frames of one row, in order: the paper's edge-at-a-time form. Use batches for long logs."""
    for r in updates.orderBy("tau").collect():
        yield updates.sparkSession.createDataFrame([(r["tau"], r["op"], r["src"], r["dst"])], UPDATE)


class EagerEngine:
    """Stored paths, repaired at each update (batch: all updates at once, else edge by edge). store: keep the index on disk
    with `parts` partitions and repair it by deltas."""

    def __init__(self, edges: DataFrame, p: PprParams, sampler: str = "bernoulli", batch: bool = True, store: bool = False, parts: int = 64):
        self.sampler, self.batch = sampler, batch
        self.state = build_state(edges, p)
        self.store = StateStore(edges.sparkSession, Rounds(edges.sparkSession, "store").base, parts) if store else None
        if self.store:
            self.store.save(self.state)

    def _apply(self, updates: DataFrame) -> dict:
        if self.store:
            stats = self.store.apply(updates, self.sampler)
            self.state = self.store.load()
            return stats
        self.state = apply_batch(self.state, updates, self.sampler)
        return self.state.stats

    def update(self, updates: DataFrame) -> dict:
        if self.batch:
            return self._apply(updates)
        sums: dict = {}
        for one in _one_by_one(updates):
            sums = {k: sums.get(k, 0) + v for k, v in self._apply(one).items()}
        return sums

    def query(self, sources: DataFrame) -> DataFrame:
        return query_indexed(self.state, sources)

    def topk(self, sources: DataFrame, k: int) -> DataFrame:
        return query_topk(self.state, sources, k)


class OnlineEngine:
    """No index: an update changes the edges, a query walks anew."""

    def __init__(self, edges: DataFrame, p: PprParams, mode: str = "linear"):
        self.rounds = Rounds(edges.sparkSession, "online")
        self.edges, self.p, self.mode = self.rounds.keep(edges.select("src", "dst")), p, mode

    def update(self, updates: DataFrame) -> dict:
        self.edges = self.rounds.keep(apply_updates(self.edges, normalize_updates(updates, self.edges)))
        return {}

    def query(self, sources: DataFrame) -> DataFrame:
        return query_online(self.edges, sources, self.p, self.mode)

    def topk(self, sources: DataFrame, k: int) -> DataFrame:
        return topk_online(self.edges, sources, k, self.p, self.mode)


class RebuildEngine(OnlineEngine):
    """Endpoint index, built anew after each update, with draws of its own (batch: after all updates at once)."""

    def __init__(self, edges: DataFrame, p: PprParams, batch: bool = True):
        super().__init__(edges, p)
        self.batch, self.epoch = batch, 0
        self._build()

    def _build(self) -> int:
        walks = build_walk_index(self.edges, self.p, epoch=self.epoch, store="ends", rounds=self.rounds)
        self.state = IndexState(self.edges, walks, self.p, self.epoch)
        return walks.count()

    def update(self, updates: DataFrame) -> dict:
        built = 0
        for part in [updates] if self.batch else _one_by_one(updates):
            super().update(part)
            self.epoch += 1
            built += self._build()
        return {"rebuilt": built}

    def query(self, sources: DataFrame) -> DataFrame:
        return query_indexed(self.state, sources)

    def topk(self, sources: DataFrame, k: int) -> DataFrame:
        return query_topk(self.state, sources, k)


def staleness_step(edges: DataFrame, touched: DataFrame, p: PprParams, undirected: bool = False) -> tuple[DataFrame, float]:
    """What a batch adds to the staleness of the nodes: (node, sigma) beyond a floor that every node gets, and the floor.

    An upper bound of the expected share of a node's walks that the updates make stale, by backward push from each changed
    node u: a walk from w crosses u score(w, u) / alpha times in the mean (walks with a hop), the score is at most the reserve
    plus the threshold, and a crossing goes stale if its edge is removed (gone of a) or redirected (k of b). Nodes that the
    push didn't reach have reserve 0 but still the threshold, which is the floor. `edges`: the graph after the update.
    """
    n, m = graph_size(edges)
    stale = F.when(F.col("a") == 0, 1.0).otherwise((F.col("gone") + (F.col("a") - F.col("gone")) * F.when(F.col("b") > 0, F.col("k") / F.col("b")).otherwise(0.0)) / F.col("a"))
    rate = touched.select(F.col("node").alias("target"), (stale / p.alpha).alias("rate"))
    r_b = p.backward_r_max(m, n, undirected)
    drawn = stale_in_tasks(edges, m, rate, p.alpha, r_b, undirected)
    if drawn is not None:
        drawn = Rounds(edges.sparkSession, "stale").keep(drawn)
        return drawn.where("node is not null").groupBy("node").agg(F.sum("sigma").alias("sigma")), drawn.agg(F.sum("floor")).first()[0] or 0.0
    back = backward_push(edges, rate.select("target"), p, r_b, scale_by_degree=undirected).join(rate, "target")
    bound = lambda reserve: F.least(F.lit(1.0), (reserve + F.col("limit")) * F.col("rate"))
    floor = back.groupBy("target").agg(F.first(bound(F.lit(0.0))).alias("f")).agg(F.sum("f")).first()[0] or 0.0
    more = back.select("node", (bound(F.col("reserve")) - bound(F.lit(0.0))).alias("sigma"))
    return more.groupBy("node").agg(F.sum("sigma").alias("sigma")), floor


#: Errors are ranked by bands of 2 ** (1 / BANDS), then in DEALT groups of nodes.
BANDS, DEALT = 64, 64


def lazy_plan(sigma: DataFrame, push: DataFrame, allowed: float, floor: float = 0.0) -> DataFrame:
    """Nodes whose walks must be rebuilt: those with the largest staleness x residue, until what is left is at most `allowed`.

    Errors are ranked by bands of about 1 %, within a band by (node mod 64, error, node). Prefix sums run over the bands, then
    over the groups of the band where the budget ends, then within one group, so no task holds all nodes, even where all
    errors are equal. floor: staleness of every node beside its own.
    """
    load = push.groupBy("node").agg(F.max("residue").alias("residue"))
    own = load.join(sigma, "node", "left").select("node", (F.greatest(F.lit(0.0), F.coalesce("sigma", F.lit(0.0)) + F.lit(float(floor))) * F.col("residue")).alias("e")).where("e > 0")
    e = own.withColumn("band", F.floor(-F.log2("e") * BANDS).cast("int")).withColumn("grp", F.pmod("node", F.lit(DEALT)).cast("int"))
    upto = lambda *by: Window.partitionBy(*by[:-1]).orderBy(by[-1]).rowsBetween(Window.unboundedPreceding, -1)
    bands = e.groupBy("band").agg(F.sum("e").alias("sum"))  # tens of thousands at most: one for each hundredth of a magnitude
    below = bands.select("band", F.coalesce(F.sum("sum").over(Window.orderBy(F.desc("band")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("below"), "sum")
    j = e.join(F.broadcast(below), "band")
    whole = j.where(F.col("below") >= allowed).select("node")
    edge = j.where((F.col("below") < allowed) & (F.col("below") + F.col("sum") > allowed))
    groups = edge.groupBy("band", "grp").agg(F.sum("e").alias("gsum"), F.first("below").alias("below"))
    gbelow = groups.select("band", "grp", (F.col("below") + F.coalesce(F.sum("gsum").over(upto("band", "grp")), F.lit(0.0))).alias("gbelow"))
    run = F.sum("e").over(Window.partitionBy("band", "grp").orderBy("e", "node").rowsBetween(Window.unboundedPreceding, 0)) + F.col("gbelow")
    return whole.unionByName(edge.join(F.broadcast(gbelow), ["band", "grp"]).withColumn("run", run).where(F.col("run") > allowed).select("node"))


class LazyEngine:
    """Stored endpoints; updates only trace staleness, queries rebuild the worst nodes' walks. The error is split by theta;
    optimistic: the push runs at the full error. Staleness is sigma (by node) plus a floor that all nodes share; a node whose
    walks were rebuilt holds minus the floor of that time. build: make the index now, else where it is first read."""

    def __init__(self, edges: DataFrame, p: PprParams, undirected: bool = False, optimistic: bool = False, skip_when_safe: bool = True, batch: bool = True, build: bool = True):
        self.rounds = Rounds(edges.sparkSession, "lazy")
        self.p, self.undirected, self.optimistic, self.skip, self.batch = p, undirected, optimistic, skip_when_safe, batch
        self.first = Rounds(edges.sparkSession, "state").keep(edges.select("src", "dst"))
        self.state = IndexState(self.first, None, p)
        if build:
            self._indexed()
        self.sigma = edges.sparkSession.createDataFrame([], "node long, sigma double")
        self.floor = self.total_bound = 0.0
        self.skipped = self.rebuilt = self.rebuilt_nodes = 0

    def twin(self, optimistic: bool) -> LazyEngine:
        """An engine with this one's present state, which updates make alike for both; neither sees what the other does from now on."""
        other = copy(self)
        other.optimistic = optimistic
        return other

    def _indexed(self) -> IndexState:
        """The state with its index, which is that of the first edges until queries rebuild parts of it."""
        if self.state.walks is None:
            self.state = replace(self.state, walks=build_walk_index(self.first, self.p, store="ends"))
        return self.state

    def _bound(self) -> None:
        self.total_bound = self.floor + max(0.0, self.sigma.agg(F.max("sigma")).first()[0] or 0.0)

    def update(self, updates: DataFrame) -> dict:
        for part in [updates] if self.batch else _one_by_one(updates):
            s = self.state
            net = self.rounds.keep(normalize_updates(part, s.edges))
            touched = self.rounds.keep(touched_nodes(s.edges, net))
            edges = self.rounds.keep(apply_updates(s.edges, net))
            more, floor = staleness_step(edges, touched, self.p, self.undirected)
            self.sigma = self.rounds.keep(self.sigma.unionByName(more).groupBy("node").agg(F.sum("sigma").alias("sigma")))
            self.floor += floor
            self.state = IndexState(edges, s.walks, self.p, s.epoch + 1)
        self._bound()
        return {"stale": self.sigma.count()}

    def staleness(self) -> DataFrame:
        """node, sigma of every node with an edge: at most 1 counts as all walks."""
        own = degrees(self.state.edges).select("node").join(self.sigma, "node", "left")
        return own.select("node", F.greatest(F.lit(0.0), F.coalesce("sigma", F.lit(0.0)) + F.lit(float(self.floor))).alias("sigma"))

    def _push(self, sources: DataFrame, delta: float, init: DataFrame | None = None, graph: PushGraph | None = None) -> DataFrame:
        scale = 1.0 if self.optimistic else self.p.theta
        return forward_push(self.state.edges, sources, self.p, scale * self.p.x / replace(self.p, delta=delta).omega, init=init, graph=graph)

    def fix(self, push: DataFrame, delta: float) -> None:
        """Rebuild until the error left is within (1 - theta) * epsilon at the threshold."""
        allowed = (1 - self.p.theta) * self.p.epsilon * delta
        if self.skip and self.total_bound <= allowed:  # residues sum to 1 at most
            self.skipped += 1
            return
        plan, n = self.rounds.keep_seen(lazy_plan(self.sigma, push, allowed, self.floor), F.count("*"))
        if not n:
            return
        s, p, epoch = self._indexed(), self.p, self.state.epoch * 1000 + self.rebuilt + 1
        d = degrees(s.edges)
        want = d.join(plan, "node", "left_semi").select(F.col("node").alias("source"), p.walks_stored(F.col("out_deg")).alias("want"))
        fresh = walks_in_tasks(s.edges, p, epoch, False, "ends", asked=want.select("source", F.col("want").alias("n")))
        if fresh is None:
            starts = counted(want, F.lit(0), F.col("want")).select("source", "slot")
            fresh = walk_ends(walk_on(new_walks(starts, p, epoch), s.edges, p, epoch, self.rounds))
        rest = s.walks.join(plan.select(F.col("node").alias("source")), "source", "left_anti")
        self.state = IndexState(s.edges, self.rounds.keep(rest.unionByName(fresh)), p, s.epoch)
        self.sigma = self.rounds.keep(self.sigma.join(plan, "node", "left_anti").unionByName(plan.select("node", F.lit(-float(self.floor)).alias("sigma"))))
        self._bound()
        self.rebuilt += 1
        self.rebuilt_nodes += n

    def query(self, sources: DataFrame) -> DataFrame:
        push = self._push(sources, self.p.delta)
        self.fix(push, self.p.delta)
        return refine(push, walk_ends(self._indexed().walks), self.p, self.state.zero_hop)

    def topk(self, sources: DataFrame, k: int) -> DataFrame:
        """The check and fix step follows each coarse push, as the baseline has it."""
        g = PushGraph(self.state.edges, "topk")

        def refine_at(state: DataFrame, delta: float) -> DataFrame:
            self.fix(state, delta)
            return refine(state, walk_ends(self._indexed().walks), replace(self.p, delta=delta), self.state.zero_hop)

        return topk_by_levels(sources, k, self.p, lambda left, delta, before: self._push(left, delta, before, g), refine_at, Rounds(self.state.edges.sparkSession, "topk"))


ENGINES = {
    "eager": EagerEngine,
    "online": OnlineEngine,
    "rebuild": RebuildEngine,
    "lazy": LazyEngine,
    "lazy_optimistic": lambda edges, p, **kw: LazyEngine(edges, p, optimistic=True, **kw),
}
