"""The ways for hubs, few walks and stored deltas give the plain ways' results."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from walkstream.functions.params import PprParams
from walkstream.functions.rng import geometric, u01
from walkstream.operators import engines, graph, metrics, push, repair, walks, workloads
from walkstream.plans.answers import read_answers, write_answers
from walkstream.plans.iterate import Rounds
from walkstream.plans.store import StateStore
from walkstream.sources import graphs
from walkstream.streaming import updates as stream

P = PprParams.for_graph(12, beta=2.0)


def frame(spark, edges):
    return spark.createDataFrame([(int(a), int(b)) for a, b in edges], "src long, dst long").coalesce(2)


def random_edges(seed, n=12, m=40):
    every = [(a, b) for a in range(n) for b in range(n) if a != b and a < n - 1]
    return sorted(random.Random(seed).sample(every, m))


def dense(edges, n):
    a = np.zeros((n, n))
    for s, d in edges:
        a[s, d] = 1
    for i in range(n):
        if not a[i].any():
            a[i, i] = 1
    a /= a.sum(axis=1, keepdims=True)
    return 0.2 * np.linalg.inv(np.eye(n) - 0.8 * a)


def test_hubs_are_numbered_alike(spark):
    e = frame(spark, [(0, d * d) for d in range(1, 300)] + [(1, 5), (1, 3), (2, 2**62), (2, -(2**62)), (2, 7)])
    rows = lambda hub: {(r.src, r.dst): r.slot for r in graph.numbered(e, "src", F.col("dst"), [], "slot", hub).collect()}
    assert rows(2) == rows(10**6) and rows(2)[1, 3] == 0 and rows(2)[0, 1] == 0 and rows(2)[2, 2**62] == 2


def test_hub_edges_are_pushed_in_parts(spark):
    e = frame(spark, random_edges(2))
    deg = graph.degrees(e)
    state = push.seed_state(spark.createDataFrame([(0,), (3,), (99,)], "source long"), deg)
    ends = []
    for hub in (2, 10**6):
        step = push.rounds_of(push.push_table(e, deg, hub), 0.2, None, hub)
        ends.append({(r.source, r.node): (round(r.reserve, 12), round(r.residue, 12)) for r in step(step(state)).collect()})
    assert ends[0] == ends[1] and ends[0][99, 99] == (1.0, 0.0)


def test_counted_rows(spark):
    n = walks.BLOCK * 2 + 3
    got = walks.counted(spark.createDataFrame([(1, 0, n), (2, 5, 5), (3, 4, 6), (4, 0, 0)], "source long, lo long, n long"), F.col("lo"), F.col("n"))
    per = {r.source: (r.c, r.lo, r.hi) for r in got.groupBy("source").agg(F.count("*").alias("c"), F.min("slot").alias("lo"), F.max("slot").alias("hi")).collect()}
    assert per == {1: (n, 0, n - 1), 3: (2, 4, 5)}


@pytest.mark.parametrize("alpha", [0.2, 0.02])
def test_hops_have_their_mean(spark, alpha):
    u = spark.range(20_000).select(u01(3, "h", F.col("id")).alias("u"))
    for fast in (False, True):
        mean = u.select(F.avg(geometric(F.col("u"), alpha, 1, fast))).first()[0]
        assert abs(mean - 1 / alpha) < 5 / alpha / 20_000**0.5


def test_stored_repair_equals_the_whole_one(spark, tmp_path):
    """Two batches, with few partitions (whole adjacency) and many (superstep by superstep), against frames written anew."""
    e = random_edges(3)
    new = [(a, b) for a in range(12) for b in range(12) if a != b and (a, b) not in e][::9][:6] + [(11, 0)]
    ups = [[(1, "+", *x) for x in new[:3]] + [(2, "-", *e[0]), (3, "-", *e[7])], [(1, "+", *x) for x in new[3:]] + [(2, "-", *new[0])] + [(3, "-", *x) for x in e if x[0] == 2]]
    state = repair.build_state(frame(spark, e), PprParams.for_graph(12, alpha=0.5, beta=2.0))
    stores = [StateStore(spark, f"file://{tmp_path}/{parts}", parts) for parts in (2, 300)]
    for s in stores:
        s.save(state)
    rows = lambda w: sorted((tuple(r.walk_id), r.slot, r.hops, tuple(r.path)) for r in w.collect())
    recs = lambda c: sorted((r.node, tuple(r.walk_id), r.step, r.next) for r in c.select("node", "walk_id", "step", "next").collect())
    for batch in ups:
        u = spark.createDataFrame(batch, "tau long, op string, src long, dst long").coalesce(1)
        state = repair.apply_batch(state, u)
        want, records = rows(state.walks), recs(walks.crossings_of(state.walks))
        for s in stores:
            assert s.apply(u) == state.stats
            assert rows(s.table("walks")) == want and recs(s.table("crossings")) == records
            assert sorted(map(tuple, s.table("edges").collect())) == sorted((r.src, r.dst) for r in state.edges.collect())
    stores[0].compact()
    assert stores[0].epochs() == [3] and recs(stores[0].table("crossings")) == records
    assert metrics.check_adequate(stores[0].load()).count() == 0


def test_a_small_repair_reads_few_partitions(spark, tmp_path):
    state = repair.build_state(frame(spark, random_edges(4)), P)
    store = StateStore(spark, f"file://{tmp_path}/s", 64)
    store.save(state)
    node = spark.createDataFrame([(3,)], "node long")
    plan = store.table("crossings", parts=store.parts_of(node, "node"))
    assert len({f.split("/part=")[1].split("/")[0] for f in plan.inputFiles()}) <= 64
    assert "PartitionFilters" in plan._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("undirected", [False, True])
def test_staleness_bounds_the_stale_share(spark, undirected):
    """Against dense scores: score / alpha crossings, each stale with the chance of its edge; every node, reached or not."""
    e = random_edges(5)
    if undirected:
        e = sorted({*e, *[(b, a) for a, b in e]})
    gone, come = e[3], next((a, b) for a in range(11) for b in range(12) if a != b and (a, b) not in e)
    after = sorted({*e, come} - {gone})
    p = PprParams.for_graph(12)
    engine = engines.LazyEngine(frame(spark, e), p, undirected=undirected)
    engine.update(spark.createDataFrame([(1, "+", *come), (2, "-", *gone)], "tau long, op string, src long, dst long"))
    got = {r.node: r.sigma for r in engine.staleness().collect()}
    exact, deg = dense(after, 12), lambda g, u: sum(a == u for a, _ in g)
    nodes = sorted({x for pair in after for x in pair})
    for w in nodes:
        want = 0.0
        for u in {come[0], gone[0]}:
            a, k, g = deg(e, u), int(come[0] == u), int(gone[0] == u)
            stale = 1.0 if a == 0 else (g + (a - g) * (k / (a - g + k) if a - g + k else 0)) / a
            want += min(1.0, exact[w, u] / p.alpha * stale)
        assert got[w] >= want - 1e-9
    engine.fix(push.forward_push(engine.state.edges, spark.createDataFrame([(0,)], "source long"), p, 1e-4), 1e-6)
    assert engine.rebuilt_nodes > 0 and min(r.sigma for r in engine.staleness().collect()) == 0.0


def test_answers_are_stored_and_read(spark, tmp_path):
    scores = spark.createDataFrame([(1, 2, 0.5), (1, 3, 0.7), (1, 4, 0.5), (2, 2, 0.1)], "source long, node long, score double")
    write_answers(scores, f"file://{tmp_path}/a", k=2)
    got = {(r.source, r.rank): (r.node, r.score) for r in read_answers(spark, f"file://{tmp_path}/a").collect()}
    assert got == {(1, 1): (3, 0.7), (1, 2): (2, 0.5), (2, 1): (2, 0.1)}


def test_edge_lists_node_updates_and_joins(spark, tmp_path):
    (tmp_path / "edges.txt").write_text("1 2\n2 3\n2 3\n3 3\n3 1\n")
    e = graphs.read_edges(spark, f"file://{tmp_path}/edges.txt", "csv", sep=" ")
    assert sorted((r.src, r.dst) for r in e.collect()) == [(1, 2), (2, 3), (3, 1)]
    state = repair.build_state(e, P)
    after = repair.apply_node_updates(state, spark.createDataFrame([(1, "-", 2)], "tau long, op string, node long"))
    assert [(r.src, r.dst) for r in after.edges.collect()] == [(3, 1)] and metrics.check_paths_valid(after).count() == 0
    ups = spark.createDataFrame([(1, "+", 3, 2, "2024-01-01 10:00:00"), (2, "-", 1, 2, "2024-01-01 10:25:00"), (3, "+", 3, 9, "2024-01-01 09:00:00")], "tau long, op string, src long, dst long, ts string").withColumn("ts", F.to_timestamp("ts"))
    assert stream.join_current(ups.where("op = '+'"), walks.crossings_of(state.walks)).where("src = 3 and node = 3").count() > 0
    seen = spark.createDataFrame([(3, "2024-01-01 10:05:00"), (1, "2024-01-01 10:20:00")], "node long, at string").withColumn("at", F.to_timestamp("at"))
    assert [(r.node, r.tau) for r in stream.near_events(ups, seen, "30 MINUTES").collect()] == [(3, 1)]


def test_streamed_counters_and_repeats(spark, tmp_path):
    rows = [(1, "+", 1, 2), (2, "+", 1, 3), (3, "+", 1, 2), (4, "-", 1, 9), (5, "-", 1, 3), (6, "+", 4, 5)]
    log = spark.createDataFrame([(*r, f"2024-01-01 00:0{r[0]}:00") for r in rows] + [(7, "+", 4, 5, "2024-01-01 00:06:00")], "tau long, op string, src long, dst long, ts string").withColumn("ts", F.to_timestamp("ts"))
    log.coalesce(1).write.parquet(f"{tmp_path}/log")
    live = stream.stream_updates(spark, f"{tmp_path}/log")
    q = stream.degree_counters(live).writeStream.format("memory").queryName("degs").outputMode("update").option("checkpointLocation", f"{tmp_path}/c1").trigger(availableNow=True).start()
    q.awaitTermination()
    assert {(r.node, r.out_deg) for r in spark.table("degs").collect()} == {(1, 1), (4, 1)}
    q = stream.deduplicate(live, "1 hour").writeStream.format("memory").queryName("once").option("checkpointLocation", f"{tmp_path}/c2").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("once").count() == 6
    assert stream.rate_updates(spark, 5, 10).columns == ["tau", "op", "src", "dst", "ts"]


def test_cost_report_rolls_up(spark):
    runs = [{"engine": "eager", "percent": p, "update_s": 2.0, "query_s": 4.0, "updates": 2, "queries": 4} for p in (10, 50)]
    got = {(r.engine, r.percent): r[2] for r in workloads.cost_report(runs, spark).collect()}
    assert set(got) == {("eager", 10), ("eager", 50), ("eager", None), (None, None)} and set(got.values()) == {1.0}


def test_written_rounds_can_be_dropped(spark):
    r = Rounds(spark, "drop")
    a, n = r.keep_seen(spark.range(5), F.count("*"))
    assert n == 5 and a.count() == 5
    r.drop_all()


def test_nearest_vectors_of_copies_and_odd_rows(spark, tmp_path):
    """Copies, scaled vectors, zeros, nulls, repeated ids and two lengths, against all pairs of rows."""
    rng = np.random.default_rng(3)
    some = [[float(x) for x in rng.normal(size=6)] for _ in range(9)]
    rows = [(i, some[i % 9]) for i in range(120)] + [(200 + i, [2.0 * x for x in some[i]]) for i in range(4)]
    rows += [(5, some[1]), (5, some[5]), (30, some[3]), (300, [0.0] * 6), (301, None), (None, some[0]), (302, [1.0, 2.0]), (303, [2.0, 1.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(4).write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {}
    for r in graphs.vector_knn(spark, str(tmp_path), block=2, pack=3).collect():
        got.setdefault(r.src, []).append(r.dst)
    fine = [(i, np.array(v)) for i, v in rows if i is not None and v is not None and any(v)]
    unit = [(i, v / np.linalg.norm(v)) for i, v in fine]
    want = {}
    for i in {i for i, _ in unit}:
        best = sorted((-round(float(a @ b), 9), j) for s, a in unit if s == i for j, b in unit if j != i and len(a) == len(b))[:10]
        want[i] = sorted(j for _, j in best)
    assert {i: sorted(x) for i, x in got.items()} == want


def test_rounds_within_reach_of_the_sources_match_joined_ones(spark, monkeypatch):
    """Copies of a graph that the sources don't reach are left out, and the states are those of whole rounds."""
    ring = [(c * 100 + i, c * 100 + (i + k) % 20, None) for c in range(6) for i in range(20) for k in (1, 3)] + [(7, 99, None)]
    edges = spark.createDataFrame(ring, "src long, dst long, ts timestamp")
    sources, p = spark.createDataFrame([(3,), (99,), (104,), (7777,)], "source long"), PprParams.for_graph(121)
    starts = sources.select(F.col("source").alias("node"))
    few, n = push.PushGraph(edges).near(starts, 100)
    assert few.count() == 81 and n == 41  # two of six copies and the dead end
    assert push.PushGraph(edges).near(starts, 80)[0] is None
    monkeypatch.setattr(push, "NEAR_EDGES", 100)
    monkeypatch.setattr(push, "rounds_of", None)  # no joined round is planned

    def take():
        rows = push.forward_push(edges, sources, p, 1e-3).collect()
        first = push.forward_push(edges, sources, p, 1e-2, max_rounds=2)
        again = push.forward_push(edges, sources, p, 1e-3, init=first).collect()
        exact = push.power_ppr(edges, sources, p, rounds=16).collect()
        return [{tuple(r[:2]): tuple(r[2:]) for r in x} for x in (rows, again, exact)]

    near = take()
    monkeypatch.undo()
    monkeypatch.setattr(push, "NEAR_EDGES", 0)
    for a, b in zip(near, take(), strict=True):
        assert a.keys() == b.keys()
        assert all(x == pytest.approx(b[k], abs=1e-12) for k, x in a.items())
