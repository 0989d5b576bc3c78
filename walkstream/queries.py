"""Registered queries of the walk engine."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.params import PprParams
from .operators import engines, graph, metrics, push, query, repair, samplers, walks, workloads
from .oracle import oracle_sql  # noqa: F401  (the SQL belongs to these queries)
from .plans.iterate import Rounds
from .plans.store import StateStore
from .sources import graphs
from .streaming.updates import sliding_window_graph, update_rate

BETA, SOURCES = 0.2, 4


def _basket(spark: SparkSession, d: str) -> DataFrame:
    return Rounds(spark, "graph").keep(graphs.basket_succession(spark, d))


def _params(edges: DataFrame, **over) -> PprParams:
    n, _ = graph.graph_size(edges)
    return PprParams.for_graph(n, **{"beta": BETA, **over})


def _sources(edges: DataFrame, n: int = SOURCES) -> DataFrame:
    return workloads.pick_sources(edges, n)


def _rounded(df: DataFrame, p: PprParams) -> DataFrame:
    """Every node with a score; at least three digits below the threshold delta."""
    return df.where("score > 0").select("source", "node", F.round("score", max(6, math.ceil(-math.log10(p.delta)) + 3)).alias("score"))


def _graph(name: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return graphs.GRAPHS[name](spark, d).select("src", "dst")

    return run


def degrees(spark, d):
    return graph.degrees(_basket(spark, d))


def dead_ends(spark, d):
    return graph.dead_ends(graphs.page_links(spark, d))


def adjacency_slots(spark, d):
    return graph.adjacency(_basket(spark, d))


def params_table(spark, d):
    edges = _basket(spark, d)
    n, m = graph.graph_size(edges)
    p = _params(edges)
    rows = [("n", float(n)), ("m", float(m)), ("omega", p.omega), ("r_max_balanced", p.r_max(m, "balanced")), ("r_max_linear", p.r_max(m, "linear")), ("r_max_tuned", p.r_max(m)), ("walks_per_edge", p.x)]
    return spark.createDataFrame(rows, "name string, v double").select("name", F.round("v", 9).alias("value"))


def power_ppr(spark, d):
    edges = _basket(spark, d)
    return _rounded(push.power_ppr(edges, _sources(edges), _params(edges)), _params(edges))


def _push(edges: DataFrame) -> DataFrame:
    p = _params(edges)
    _, m = graph.graph_size(edges)
    return push.forward_push(edges, _sources(edges), p, p.r_max(m))


def push_state(spark, d):
    s = _push(_basket(spark, d))
    return s.select("source", "node", F.round("reserve", 8).alias("reserve"), F.round("residue", 8).alias("residue"))


def push_stats(spark, d):
    s = push.push_stats(_push(_basket(spark, d)))
    return s.select("source", "nodes", "pushed", F.round("left_mass", 6).alias("left_mass"))


def push_invariant(spark, d):
    edges = Rounds(spark, "graph").keep(graphs.nation_trade(spark, d))
    p = _params(edges)
    every = edges.select(F.col("src").alias("source")).distinct()
    exact = push.power_ppr(edges, every, p)
    gap = push.check_push_invariant(push.forward_push(edges, every, p, 1e-3), exact)
    return gap.select("source", (F.col("gap") < 1e-9).alias("holds"))


def power_push(spark, d):
    edges = Rounds(spark, "graph").keep(graphs.nation_trade(spark, d))
    p = _params(edges)
    every = edges.select(F.col("src").alias("source")).distinct()
    s = push.power_push(edges, every, p, 1e-9, dense_fraction=0.05)
    return s.where("reserve > 0").select("source", "node", F.round("reserve", 5).alias("score"))


def backward_push(spark, d):
    edges = _basket(spark, d)
    t = _sources(edges, 2).select(F.col("source").alias("target"))
    p, (n, m) = _params(edges), graph.graph_size(edges)
    s = push.backward_push(edges, t, p, p.backward_r_max(m, n, False))
    return s.select("target", "node", F.round("reserve", 8).alias("reserve"), F.round("residue", 8).alias("residue"))


def _index(edges: DataFrame, **kw) -> DataFrame:
    return walks.build_walk_index(edges, _params(edges), **kw)


def walk_index(spark, d):
    return _paths(_index(_basket(spark, d)))


def walk_index_zero_hop(spark, d):
    edges = _basket(spark, d)
    return _paths(walks.build_walk_index(edges, _params(edges), zero_hop=True))


def walk_ends(spark, d):
    return _index(_basket(spark, d), store="ends")


def end_counts(spark, d):
    c = walks.end_counts(_index(_basket(spark, d), store="ends"))
    return c.select("source", "terminal", "cnt", F.col("all").alias("n_walks"))


def crossings(spark, d):
    c = walks.crossings_of(_index(_basket(spark, d)))
    return c.select("node", F.col("walk_id.source").alias("walk_source"), F.col("walk_id.slot").alias("walk_slot"), "step", "next")


def crossings_by_edge(spark, d):
    c = walks.crossings_of(_index(_basket(spark, d)))
    return c.groupBy("node", "next").agg(F.count("*").alias("records"))


def node_counters(spark, d):
    return walks.node_counters(walks.crossings_of(_index(_basket(spark, d))))


def query_indexed(spark, d):
    edges = _basket(spark, d)
    return _rounded(query.refine(_push(edges), walks.walk_ends(_index(edges)), _params(edges)), _params(edges))


def query_indexed_all(spark, d):
    edges = _basket(spark, d)
    return _rounded(query.refine(_push(edges), walks.walk_ends(_index(edges)), _params(edges), budget="all"), _params(edges))


def query_monte_carlo(spark, d):
    edges = _basket(spark, d)
    return query.query_monte_carlo(edges, _sources(edges), _params(edges))


def query_online(spark, d):
    edges = _basket(spark, d)
    return _rounded(query.query_online(edges, _sources(edges), _params(edges)), _params(edges))


def query_online_balanced(spark, d):
    edges = _basket(spark, d)
    return _rounded(query.query_online(edges, _sources(edges), _params(edges), mode="balanced"), _params(edges))


def query_by_visits(spark, d):
    edges = _basket(spark, d)
    return _rounded(query.query_by_visits(repair.build_state(edges, _params(edges)), _sources(edges)), _params(edges))


def _ranked(top: DataFrame) -> DataFrame:
    return top.select("source", "rank", "node", F.round("score", 8).alias("score"))


def topk_full(spark, d):
    edges = _basket(spark, d)
    state = repair.build_state(edges, _params(edges))
    return _ranked(query.query_topk(state, _sources(edges), 500, strategy="full"))


def topk_iterative(spark, d):
    edges = _basket(spark, d)
    return _ranked(query.query_topk(repair.build_state(edges, _params(edges, beta=1.0), store="ends"), _sources(edges), 10))


def pair(spark, d):
    edges = _basket(spark, d)
    s = query.refine(_push(edges), walks.walk_ends(_index(edges)), _params(edges))
    return _rounded(s.where("node = 17"), _params(edges))


def _batch(spark, d, n: int = 200):
    """State over the initial edges and a batch of updates on them."""
    edges = _basket(spark, d)
    split = workloads.random_arrival_split(edges)
    p = _params(edges)
    state = repair.build_state(split.where("part = 'initial'").select("src", "dst"), p)
    return state, Rounds(spark, "updates").keep(workloads.updates_from(split, n))


def _paths(w: DataFrame) -> DataFrame:
    return w.select("source", "slot", "hops", F.array_join(F.transform("path", lambda v: v.cast("string")), ",").alias("path"))


def update_log(spark, d):
    return _batch(spark, d)[1]


def net_updates(spark, d):
    state, ups = _batch(spark, d)
    return graph.normalize_updates(ups.unionByName(ups.withColumn("tau", F.col("tau") + 1000).withColumn("op", F.lit("-"))), state.edges)


def touched_nodes(spark, d):
    state, ups = _batch(spark, d)
    return repair.touched_nodes(state.edges, graph.normalize_updates(ups, state.edges)).select("node", "a", "k", "gone", "b")


def batch_walks(spark, d):
    state, ups = _batch(spark, d)
    return _paths(repair.apply_batch(state, ups).walks)


def batch_stats(spark, d):
    state, ups = _batch(spark, d)
    s = repair.apply_batch(state, ups).stats
    return spark.createDataFrame(sorted((k, int(v)) for k, v in s.items()), "name string, value long")


def insert_walks(spark, d):
    state, ups = _batch(spark, d)
    r = ups.where("op = '+'").orderBy("tau").first()
    return _paths(repair.apply_insert(state, r["src"], r["dst"]).walks)


def delete_walks(spark, d):
    state, ups = _batch(spark, d)
    r = ups.where("op = '-'").orderBy("tau").first()
    return _paths(repair.apply_delete(state, r["src"], r["dst"]).walks)


def _sampled(how: str):
    """The records of kept edges that a sampler redirects at the nodes of a batch's insertions."""

    def run(spark, d):
        state, ups = _batch(spark, d)
        rounds, p, epoch = Rounds(spark, "records"), state.params, state.epoch + 1
        net = rounds.keep(graph.normalize_updates(ups, state.edges))
        touched = rounds.keep(repair.touched_nodes(state.edges, net))
        gone = repair.trim_plan(state.walks, touched, p, epoch).where("place >= want").select("walk_id")
        removed = net.where("op = '-'").select(F.col("src").alias("node"), F.col("dst").alias("next"))
        kept = walks.crossings_of(state.walks).join(gone, "walk_id", "left_anti").join(removed, ["node", "next"], "left_anti")
        grown = touched.where("k > 0 and a > 0").select("node", F.col("b").alias("d"), "k")
        got = samplers.sample_records(kept.select("node", "walk_id", "step", "next"), grown, p.seed, epoch, how)
        return got.select("node", F.col("walk_id.source").alias("walk_source"), F.col("walk_id.slot").alias("walk_slot"), "step", "next")

    return run


def _stored(spark, d):
    """The batch again, by deltas on disk."""
    state, ups = _batch(spark, d)
    store = StateStore(spark, Rounds(spark, "store").base, 16)
    store.save(state)
    store.apply(ups)
    return store


def stored_walks(spark, d):
    return _paths(_stored(spark, d).table("walks"))


def stored_crossings(spark, d):
    c = _stored(spark, d).table("crossings")
    return c.select("node", F.col("walk_id.source").alias("walk_source"), F.col("walk_id.slot").alias("walk_slot"), F.col("walk_id.epoch").alias("walk_epoch"), "step", "next")


def adequacy(spark, d):
    state, ups = _batch(spark, d)
    s = repair.apply_batch(state, ups)
    bad = metrics.check_adequate(s).count() + metrics.check_paths_valid(s).count()
    return spark.createDataFrame([(bad,)], "violations long")


def node_delete_expansion(spark, d):
    edges = _basket(spark, d)
    gone = spark.createDataFrame([(1, "-", 5), (2, "-", 9)], "tau long, op string, node long")
    return graph.expand_node_updates(gone, edges)


def rebuild_after_update(spark, d):
    state, ups = _batch(spark, d)
    edges = graph.apply_updates(state.edges, graph.normalize_updates(ups, state.edges))
    return _paths(walks.build_walk_index(edges, state.params, epoch=1))


def staleness(spark, d):
    edges = _basket(spark, d)
    split = workloads.random_arrival_split(edges)
    engine = engines.LazyEngine(split.where("part = 'initial'").select("src", "dst"), _params(edges))
    engine.update(workloads.updates_from(split, 10))
    return engine.staleness().select("node", F.round("sigma", 8).alias("sigma"))


def _lazy(optimistic: bool):
    def run(spark, d):
        edges = _basket(spark, d)
        split = workloads.random_arrival_split(edges)
        start = split.where("part = 'initial'").select("src", "dst")
        engine = engines.LazyEngine(start, _params(edges), optimistic=optimistic)
        engine.update(workloads.updates_from(split, 10))
        return _rounded(engine.query(_sources(edges)), engine.p)

    return run


def random_split(spark, d):
    return workloads.random_arrival_split(_basket(spark, d)).groupBy("part").agg(F.count("*").alias("n"), F.sum("src").alias("src_sum"), F.sum("dst").alias("dst_sum"))


def random_split_half(spark, d):
    return workloads.random_arrival_split(graphs.customer_part(spark, d), 0.5).select("src", "dst", "part")


def temporal_split(spark, d):
    return workloads.temporal_split(_basket(spark, d)).select("src", "dst", "part")


def mixed_workload(spark, d):
    edges = _basket(spark, d)
    ups = workloads.updates_from(workloads.random_arrival_split(edges), 100)
    w = workloads.mixed_workload(ups, workloads.pick_sources(edges, 100), 50)
    return w.select("pos", "kind", F.coalesce("op", F.lit("")).alias("op"), *[F.coalesce(c, F.lit(-1)).cast("long").alias(c) for c in ("src", "dst", "source")])


def hub_updates(spark, d):
    return workloads.hub_updates(graphs.customer_supplier(spark, d), 50)


def relative_error(spark, d):
    edges = _basket(spark, d)
    p, sources = _params(edges), Rounds(spark, "sources").keep(_sources(edges))
    exact = push.power_ppr(edges, sources, p)
    e = metrics.relative_error(query.query_new(edges, sources, p), exact, p.delta)
    return e.select("source", "nodes", F.round("avg_error", 6).alias("avg_error"), F.round("max_error", 6).alias("max_error"))


def topk_quality(spark, d):
    edges = _basket(spark, d)
    p, sources = _params(edges), Rounds(spark, "sources").keep(_sources(edges))
    exact = push.power_ppr(edges, sources, p)
    return metrics.topk_quality(query.query_new(edges, sources, p, 50), exact, 50, p.epsilon, p.delta)


def crossing_identity(spark, d):
    edges = Rounds(spark, "graph").keep(graphs.nation_trade(spark, d))
    p = _params(edges, beta=20.0)
    every = edges.select(F.col("src").alias("source")).distinct()
    c = metrics.check_crossing_identity(repair.build_state(edges, p), push.power_ppr(edges, every, p))
    return c.select("node", F.round("expected", 3).alias("expected"), "crossings")


def endpoint_chi_square(spark, d):
    edges = Rounds(spark, "graph").keep(graphs.nation_trade(spark, d))
    p = _params(edges, beta=20.0)
    every = edges.select(F.col("src").alias("source")).distinct()
    c = metrics.check_unbiased(repair.build_state(edges, p), push.power_ppr(edges, every, p))
    return c.select("cells", F.round("chi2_per_cell", 6).alias("chi2_per_cell"))


def space_report(spark, d):
    edges = _basket(spark, d)
    return metrics.size_report(repair.build_state(edges, _params(edges))).select("table_name", F.col("n_rows").cast("long"), F.col("n_bytes").cast("long"))


def _log(spark, d) -> DataFrame:
    """events as an update log: user to the key of its properties; every seventh event is a deletion."""
    e = graphs.load_table(spark, d, "events")
    k = F.get_json_object("props", "$.k").cast("long")
    return e.select(F.col("event_id").alias("tau"), F.when(F.col("event_id") % 7 == 0, "-").otherwise("+").alias("op"), F.col("user_id").alias("src"), k.alias("dst"), "ts").where("dst is not null")


def graph_as_of(spark, d):
    log = _log(spark, d)
    return graph.graph_as_of(log, log.agg(F.max("tau")).first()[0])


def window_update_rate(spark, d):
    return update_rate(_log(spark, d), "1 hour")


def sliding_graph(spark, d):
    log = _log(spark, d)
    at = log.agg(F.max("ts")).first()[0]
    return sliding_window_graph(log, str(at), "2 DAYS")


def _stats(row: dict) -> tuple[int, int, int, int]:
    return tuple(int(row.get(k, 0)) for k in ("updates", "repaired", "trimmed", "added"))


_COUNTS = "updates long, repaired long, trimmed long, added long"


def _nations(spark, d) -> DataFrame:
    return Rounds(spark, "graph").keep(graphs.nation_trade(spark, d))


def x_accuracy_growth(spark, d):
    """Errors of all engines after 5 % of the edges were inserted."""
    edges = _nations(spark, d)
    r = workloads.accuracy_after_growth(edges, _params(edges, beta=1.0))
    return r.select("engine", "nodes", F.round("avg_error", 6).alias("avg_error"), F.round("max_error", 6).alias("max_error"))


def x_accuracy_updates(spark, d):
    """Errors of all engines after 1,000 updates, half of them deletions."""
    edges = Rounds(spark, "graph").keep(graphs.user_succession(spark, d))
    r = workloads.accuracy_after_updates(edges, _params(edges, beta=1.0))
    return r.select("engine", "nodes", F.round("avg_error", 6).alias("avg_error"), F.round("max_error", 6).alias("max_error"))


def x_mixed_engines(spark, d):
    """Work of all engines on one mixed workload of 8 operations, half of them updates; `bench.py` sweeps the share."""
    edges = _nations(spark, d)
    rows = []
    for r in workloads.compare_engines(edges, _params(edges, beta=1.0), 50, 8, batch=True):
        rows += [(r["engine"], r["percent"], r["updates"], r["queries"], int(r["work"].get("repaired", 0)), int(r["work"].get("rebuilt", 0)), int(r["lazy_rebuilt"]), int(r["lazy_skipped"]))]
    return spark.createDataFrame(rows, "engine string, percent int, updates long, queries long, repaired long, rebuilt long, lazy_rebuilt long, lazy_skipped long")


def x_insert_delete(spark, d):
    """Work of 1,000 insertions and of 1,000 deletions."""
    edges = Rounds(spark, "graph").keep(graphs.user_succession(spark, d))
    rows = [(r["engine"], r["op"], *_stats(r["stats"]), round(r["staleness"], 6)) for r in workloads.insert_vs_delete(edges, _params(edges, beta=1.0), initial=0.8, timed=False)]
    return spark.createDataFrame(rows, f"engine string, op string, {_COUNTS}, staleness double")


def x_arrival_orders(spark, d):
    edges = _basket(spark, d)
    rows = [(r["order"], *_stats(r), r["bound"]) for r in workloads.arrival_gap(edges, _params(edges, beta=1.0), timed=False)]
    return spark.createDataFrame(rows, f"arrival string, {_COUNTS}, bound double")


def x_memory(spark, d):
    edges = _basket(spark, d)
    m = workloads.memory_of_methods(edges, _params(edges, beta=1.0), files=False)
    return spark.createDataFrame([(k, v["raw"]) for k, v in m.items()], "method string, raw_bytes long")


def x_skip_shortcut(spark, d):
    edges = _nations(spark, d)
    rows = [(r["updates"], r["skip"], r["skipped"], r["rebuilt_nodes"]) for r in workloads.pure_queries(edges, _params(edges, beta=1.0))]
    return spark.createDataFrame(rows, "updates int, skip boolean, skipped long, rebuilt_nodes long")


def x_growth(spark, d):
    """Repairs per update on a quarter, half and all of the nodes' edges."""
    edges = _basket(spark, d)
    some = [edges.where((F.col("src") % 4 < k) & (F.col("dst") % 4 < k)) for k in (1, 2, 4)]
    rows = [(r["n"], r["m"], round(r["repairs_per_update"], 6), r["bound"]) for r in workloads.growth([Rounds(spark, "graph").keep(e) for e in some], {"beta": 1.0}, timed=False)]
    return spark.createDataFrame(rows, "n long, m long, repairs_per_update double, bound double")


def x_samplers(spark, d):
    edges = _nations(spark, d)
    rows = [(r["sampler"], *_stats(r), round(r["dispersion"], 6), round(r["chi2_per_cell"], 6)) for r in workloads.sampler_ablation(edges, _params(edges, beta=20.0), 50, exact=True)]
    return spark.createDataFrame(rows, f"sampler string, {_COUNTS}, dispersion double, chi2_per_cell double")


def x_batch_sizes(spark, d):
    edges = _basket(spark, d)
    rows = [(r["batch"], *_stats(r)) for r in workloads.batch_sizes(edges, _params(edges), timed=False)]
    return spark.createDataFrame(rows, f"batch int, {_COUNTS}")


def x_hub_repairs(spark, d):
    edges = Rounds(spark, "graph").keep(graphs.customer_supplier(spark, d))
    r = workloads.hub_repairs(edges, _params(edges))
    return spark.createDataFrame([(k, *_stats(r[k]), r["bound"], r["violations"]) for k in ("hub", "random")], f"kind string, {_COUNTS}, bound double, violations long")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    named = (degrees, dead_ends, adjacency_slots, params_table, power_ppr, push_state, push_stats, push_invariant, power_push, backward_push, walk_index, walk_index_zero_hop, walk_ends, end_counts, crossings, crossings_by_edge, node_counters, query_indexed, query_indexed_all, query_monte_carlo, query_online, query_online_balanced, query_by_visits, topk_full, topk_iterative, pair, update_log, net_updates, touched_nodes, batch_walks, batch_stats, insert_walks, delete_walks, stored_walks, stored_crossings, adequacy, node_delete_expansion, rebuild_after_update, staleness, random_split, random_split_half, temporal_split, mixed_workload, hub_updates, relative_error, topk_quality, crossing_identity, endpoint_chi_square, space_report, graph_as_of, window_update_rate, sliding_graph, x_accuracy_growth, x_accuracy_updates, x_mixed_engines, x_insert_delete, x_arrival_orders, x_memory, x_skip_shortcut, x_growth, x_samplers, x_batch_sizes, x_hub_repairs)
    out = {f"graph_{name}": _graph(name) for name in graphs.GRAPHS}
    out |= {f.__name__: f for f in named}
    out |= {f"sampler_{how}": _sampled(how) for how in ("bernoulli", "geometric", "binomial", "edge_uniform", "edge_weighted")}
    return out | {"lazy_query": _lazy(False), "lazy_optimistic_query": _lazy(True)}
