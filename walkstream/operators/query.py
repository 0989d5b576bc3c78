"""Single-source, top-k and pair queries with relative-error guarantees, for many sources in one job."""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.params import PprParams
from ..plans.iterate import Rounds
from .graph import graph_size
from .push import NEAR_EDGES, PushGraph, forward_push, power_push
from .repair import IndexState, build_state
from .task_push import shares_in_tasks
from .walks import crossings_of, end_counts, fresh_counts, fresh_ends, walk_ends


def _reserve(state: DataFrame) -> DataFrame:
    return state.where("reserve > 0").select("source", "node", F.col("reserve").alias("score"))


def total(*parts: DataFrame) -> DataFrame:
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out.groupBy("source", "node").agg(F.sum("score").alias("score"))


def refine(push: DataFrame, ends: DataFrame, p: PprParams, zero_hop: bool = False, budget: str = "needed") -> DataFrame:
    """Scores from a push state and stored endpoints.

    Without zero-hop walks, alpha of a residue stops where it is and the rest follows stored walks. A node without stored
    walks (a dead end) keeps its residue. budget 'all' uses every walk through pre-aggregated counts.
    """
    left = push.where("residue > 0").select("source", F.col("node").alias("via"), "residue")
    own = left.select("source", F.col("via").alias("node"), (F.col("residue") * (0.0 if zero_hop else p.alpha)).alias("score"))
    mass = F.col("residue") * (1.0 if zero_hop else 1 - p.alpha)
    if budget == "all":
        c = end_counts(ends).withColumnRenamed("source", "via")
        j = left.join(c, "via", "left")
        share = j.select("source", F.coalesce("terminal", "via").alias("node"), (mass * F.coalesce(F.col("cnt") / F.col("all"), F.lit(1.0))).alias("score"))
        return total(_reserve(push), own, share)
    have = ends.groupBy(F.col("source").alias("via")).agg(F.count("*").alias("have"))
    need = left.join(have, "via", "left").withColumn("use", F.least(p.walks_needed(F.col("residue")), F.coalesce("have", F.lit(0))))
    alone = need.where("use = 0").select("source", F.col("via").alias("node"), mass.alias("score"))
    e = ends.select(F.col("source").alias("via"), "slot", "terminal")
    used = need.where("use > 0").join(e, "via").where("slot < use").select("source", F.col("terminal").alias("node"), (mass / F.col("use")).alias("score"))
    return total(_reserve(push), own, alone, used)


def query_indexed(state: IndexState, sources: DataFrame, p: PprParams | None = None, budget: str = "needed", mode: str = "tuned", max_rounds: int | None = None) -> DataFrame:
    p, g = p or state.params, state.push_graph
    push = forward_push(state.edges, sources, p, p.r_max(g.m, mode), max_rounds=max_rounds, graph=g)
    return refine(push, walk_ends(state.walks), p, state.zero_hop, budget)


def refine_drawn(g: PushGraph, push: DataFrame, q: PprParams, p: PprParams, epoch: int = 0) -> DataFrame | None:
    """`refine` at the threshold of q by the endpoints of a new index of p, of which only the walks that it takes are drawn; None where tasks
    can't hold the graph."""
    left = push.where("residue > 0").select("source", F.col("node").alias("via"), "residue", F.least(q.walks_needed(F.col("residue")), p.walks_stored(F.col("out_deg"))).alias("n"))
    mass = F.col("residue") * (1 - q.alpha)
    shares = shares_in_tasks(g.given, g.size, left.where("n > 0").select("source", "via", "n", (mass / F.col("n")).alias("share")), p, epoch)
    if shares is None:
        return None
    own = left.select("source", F.col("via").alias("node"), (F.col("residue") * q.alpha + F.when(F.col("n") > 0, 0.0).otherwise(mass)).alias("score"))
    return total(_reserve(push), own, shares)


def query_new(edges: DataFrame, sources: DataFrame, p: PprParams, k: int | None = None) -> DataFrame:
    """`query_indexed`, or with k the iterative `query_topk`, on a new endpoint index of the edges, which is only built where tasks can't hold the
    graph: else each walk is drawn when the query takes it."""
    g, states = PushGraph(edges), []

    def refined(push: DataFrame, q: PprParams) -> DataFrame:
        drawn = refine_drawn(g, push, q, p) if not states else None
        if drawn is not None:
            return drawn
        if not states:
            states.append(build_state(edges, p, store="ends"))
        return refine(push, walk_ends(states[0].walks), q, states[0].zero_hop)

    def push(left: DataFrame, q: PprParams, before: DataFrame | None = None) -> DataFrame:
        return forward_push(edges, left, q, q.x / q.omega, init=before, graph=g)

    if k is None:
        return refined(push(sources, p), p)
    return topk_by_levels(sources, k, p, lambda left, delta, before: push(left, replace(p, delta=delta), before), lambda s, delta: refined(s, replace(p, delta=delta)), Rounds(edges.sparkSession, "topk"))


def query_by_visits(state: IndexState, sources: DataFrame, p: PprParams | None = None) -> DataFrame:
    """Estimator that counts every visit of a stored path, start included: a score is alpha times expected visits."""
    p, g = p or state.params, state.push_graph
    push = forward_push(state.edges, sources, p, p.r_max(g.m), graph=g)
    left = push.where("residue > 0").select("source", F.col("node").alias("via"), "residue")
    per = state.walks.groupBy(F.col("source").alias("via")).agg(F.count("*").alias("all"))
    visits = state.walks.select(F.col("source").alias("via"), F.explode("path").alias("node")).groupBy("via", "node").agg(F.count("*").alias("c")).join(per, "via")
    j = left.join(visits, "via", "left")
    share = F.coalesce(F.col("c") / F.col("all") * p.alpha, F.lit(1.0))
    if not state.zero_hop:
        own = left.join(per, "via").select("source", F.col("via").alias("node"), (F.col("residue") * p.alpha * p.alpha).alias("score"))
        est = j.select("source", F.coalesce("node", "via").alias("node"), (F.col("residue") * F.coalesce(F.col("c") / F.col("all") * p.alpha * (1 - p.alpha), F.lit(1.0))).alias("score"))
        return total(_reserve(push), own, est)
    return total(_reserve(push), j.select("source", F.coalesce("node", "via").alias("node"), (F.col("residue") * share).alias("score")))


def query_online(edges: DataFrame, sources: DataFrame, p: PprParams, mode: str = "linear", blended: bool = False, epoch: int = 0, max_rounds: int | None = None) -> DataFrame:
    """Index-free: push, then fresh walks from every residue, each worth residue / number of walks."""
    g = PushGraph(edges)
    r = p.r_max(g.m, mode)
    push = power_push(edges, sources, p, r) if blended else forward_push(edges, sources, p, r, max_rounds=max_rounds, graph=g)
    push = g.rounds.keep(push)
    need = push.where("residue > 0").select("source", "node", "residue", p.walks_needed(F.col("residue")).alias("n"))
    most = need.groupBy(F.col("node").alias("source")).agg(F.max("n").alias("n"))  # walks of a node serve all sources of the job
    return fresh_shares(push, need, fresh_ends(_within(g, most), most, p, epoch))


def _within(g: PushGraph, starts: DataFrame) -> DataFrame:
    """Edges that walks from the starts (source) can take: all, or those in reach where these are few."""
    near = g.near(starts.select(F.col("source").alias("node")), NEAR_EDGES)[0]
    return g.edges if near is None else near


def fresh_shares(push: DataFrame, need: DataFrame, ends: DataFrame) -> DataFrame:
    """Scores from reserves and fresh walks (zero-hop walks kept). need: source, node, residue, n."""
    e = ends.withColumnRenamed("source", "node")
    share = need.join(e, "node").where("slot < n").select("source", F.col("terminal").alias("node"), (F.col("residue") / F.col("n")).alias("score"))
    return total(_reserve(push), share)


def topk_online(edges: DataFrame, sources: DataFrame, k: int, p: PprParams, mode: str = "linear", epoch: int = 0) -> DataFrame:
    """Index-free top-k by the same levels: the walks of each level are drawn anew."""
    _, m = graph_size(edges)
    g = PushGraph(edges, "topk")

    def push(left, delta, before):
        q = replace(p, delta=delta)
        return forward_push(edges, left, q, q.r_max(m, mode), init=before, graph=g)

    def refine_at(state, delta):
        q = replace(p, delta=delta)
        need = g.rounds.keep(state.where("residue > 0").select("source", "node", "residue", q.walks_needed(F.col("residue")).alias("n")))
        most = need.groupBy(F.col("node").alias("source")).agg(F.max("n").alias("n"))
        return fresh_shares(state, need, fresh_ends(_within(g, most), most, q, epoch))

    return topk_by_levels(sources, k, p, push, refine_at, g.rounds)


def query_monte_carlo(edges: DataFrame, sources: DataFrame, p: PprParams, walks: int | None = None, epoch: int = 0) -> DataFrame:
    n = walks or math.ceil(p.omega)
    asked = sources.select("source", F.lit(n).cast("long").alias("n"))
    counts = fresh_counts(_within(PushGraph(edges), sources), asked, p, epoch)
    return counts.select("source", F.col("terminal").alias("node"), (F.col("cnt") / F.lit(float(n))).alias("score"))


def best_k(scores: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("source").orderBy(F.desc("score"), "node")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


#: The first threshold is this part of the largest that could pass; a further one at most this part of the one before.
COARSER = 4
#: Below the threshold at which the present k-th estimate would just pass.
MARGIN = 1.25


def topk_by_levels(sources: DataFrame, k: int, p: PprParams, push, refine_at, rounds: Rounds) -> DataFrame:
    """The loop of every engine's top-k: a coarse threshold first; a source is done once its k-th estimate reaches (1 + epsilon)
    times the threshold, and leaves the working set. push(left, threshold, state) goes on from a state; refine_at(state,
    threshold) gives scores.

    k scores sum to 1 at most, so no threshold above 1 / (k (1 + epsilon)) can pass; the first is a quarter of that. The next
    one is where the least k-th estimate of the open sources would pass with a margin, or a quarter if that is less.
    """
    left, state, done, delta = rounds.keep(sources.select("source")), None, [], 1.0 / (k * (1 + p.epsilon)) / COARSER
    while True:
        delta = max(delta, p.delta)
        state = push(left, delta, state)
        top = rounds.keep(best_k(refine_at(state, delta), k))
        if delta <= p.delta:
            done.append(top)
            break
        lows = rounds.keep(top.groupBy("source").agg(F.count("*").alias("n"), F.min("score").alias("low")).withColumn("enough", (F.col("n") >= k) & (F.col("low") >= (1 + p.epsilon) * delta)))
        r = lows.agg(F.sum(F.when(F.col("enough"), 0).otherwise(1)).alias("open"), F.min(F.when(~F.col("enough") & (F.col("n") >= k), F.col("low"))).alias("low")).first()
        if not r["open"]:
            done.append(top)
            break
        enough = lows.where("enough").select("source")
        done.append(top.join(enough, "source", "left_semi"))
        left = rounds.keep(left.join(enough, "source", "left_anti"))
        state = state.join(left, "source", "left_semi")
        delta = delta / COARSER if r["low"] is None else min(delta / COARSER, r["low"] / (1 + p.epsilon) / MARGIN)
    out = done[0]
    for part in done[1:]:
        out = out.unionByName(part)
    return out


def query_topk(state: IndexState, sources: DataFrame, k: int | None = None, p: PprParams | None = None, strategy: str = "iterative") -> DataFrame:
    """source, node, score, rank. Iterative: coarse thresholds first, the push is resumed each time; full: a full query."""
    p = p or state.params
    k = k or p.k
    if strategy == "full":
        return best_k(query_indexed(state, sources, p), k)
    g, ends = state.push_graph, walk_ends(state.walks)

    def push(left, delta, before):
        q = replace(p, delta=delta)
        return forward_push(state.edges, left, q, q.x / q.omega, init=before, graph=g)

    return topk_by_levels(sources, k, p, push, lambda s, delta: refine(s, ends, replace(p, delta=delta), state.zero_hop), Rounds(state.edges.sparkSession, "topk"))


def query_pair(state: IndexState, source: int, target: int, p: PprParams | None = None) -> DataFrame:
    sources = state.edges.sparkSession.createDataFrame([(source,)], "source long")
    return query_indexed(state, sources, p).where(F.col("node") == target)


def visit_counts(state: IndexState) -> DataFrame:
    return crossings_of(state.walks).groupBy("node").agg(F.count("*").alias("crossings"))
