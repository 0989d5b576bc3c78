"""The walk engine: worked example, dense brute force, invariants, repair laws, baselines, streaming and plans."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from walkstream.functions.params import PprParams
from walkstream.functions.registered import register, views
from walkstream.functions.rng import u01
from walkstream.operators import engines, graph, metrics, push, query, repair, samplers, walks, workloads
from walkstream.plans.store import StateStore
from walkstream.sources import graphs
from walkstream.streaming import updates as stream

#: Walks of the worked example and the printed records by node (fixed values).
H0 = {1: (1, 2, 4), 2: (1, 2), 3: (2, 4), 4: (2, 4, 3, 1), 5: (3, 1, 2), 6: (3, 2, 4), 7: (3, 1), 8: (4, 3, 1), 9: (4, 3)}
RECORDS = {1: {(1, 0), (2, 0), (5, 1)}, 2: {(1, 1), (3, 0), (4, 0), (6, 1)}, 3: {(4, 2), (5, 0), (6, 0), (7, 0), (8, 1)}, 4: {(4, 1), (8, 0), (9, 0)}}
#: Exact scores of sources 1, 3 and 4 after each update (fixed values).
EXACT = {
    0: {1: (0.275964, 0.296736, 0.189911, 0.237389), 3: (0.148368, 0.267062, 0.370920, 0.213650), 4: (0.118694, 0.213650, 0.296736, 0.370920)},
    1: {1: (0.339564, 0.311526, 0.099688, 0.249221), 3: (0.205607, 0.280374, 0.289720, 0.224299), 4: (0.218069, 0.236760, 0.155763, 0.389408)},
    2: {1: (0.370920, 0.296736, 0.094955, 0.237389), 3: (0.296736, 0.237389, 0.275964, 0.189911), 4: (0.267062, 0.213650, 0.148368, 0.370920)},
}
P = PprParams(beta=0.25, delta=0.25, p_f=0.25, k=3)


def dense(edges, n, alpha=0.2):
    """Exact scores of all pairs; a dead end has a self-loop."""
    a = np.zeros((n, n))
    for s, d in edges:
        a[s, d] = 1
    for i in range(n):
        if not a[i].any():
            a[i, i] = 1
    a /= a.sum(axis=1, keepdims=True)
    return alpha * np.linalg.inv(np.eye(n) - (1 - alpha) * a)


def frame(spark, edges):
    return spark.createDataFrame([(int(a), int(b)) for a, b in edges], "src long, dst long")


def ups(spark, rows):
    return spark.createDataFrame(rows, "tau long, op string, src long, dst long")


def h0(spark):
    rows = [(i, p[0], 0, len(p) - 1, list(p)) for i, p in H0.items()]
    return spark.createDataFrame(rows, walks.WALKS)


def random_graph(seed, n=12, m=40):
    rng = random.Random(seed)
    every = [(a, b) for a in range(n) for b in range(n) if a != b and a < n - 1]  # node n-1 is a dead end
    return sorted(rng.sample(every, m))


def test_records_of_the_example(spark):
    got = {}
    for r in walks.crossings_of(h0(spark)).collect():
        got.setdefault(r.node, set()).add((r.walk_id, r.step))
    assert got == RECORDS
    c = {r.node: (r.crossings, r.active_edges) for r in walks.node_counters(walks.crossings_of(h0(spark))).collect()}
    assert c[3] == (5, 2) and c[4] == (3, 1)


def test_exact_scores_of_the_example(spark):
    g = list(graphs.TINY)
    for k, change in enumerate((None, (4, 1), (3, 2))):
        g = g + [change] if k == 1 else [e for e in g if e != change]
        src = spark.createDataFrame([(s,) for s in EXACT[k]], "source long")
        got = {(r.source, r.node): r.score for r in push.power_ppr(frame(spark, g), src, P, 64, every=16).collect()}
        for s, want in EXACT[k].items():
            assert np.allclose([got[s, v] for v in (1, 2, 3, 4)], want, atol=2e-6)


def test_repair_of_the_example(spark):
    """After (4,1) and the removal of (3,2): adequate, valid, hop counts kept."""
    state = repair.build_state(graphs.tiny(spark), P)
    assert {r.source: r["count"] for r in state.walks.groupBy("source").count().collect()} == {1: 2, 2: 2, 3: 3, 4: 2}
    hops = {r.walk_id: r.hops for r in state.walks.collect()}
    one = repair.apply_insert(state, 4, 1)
    two = repair.apply_delete(one, 3, 2)
    assert {r.source: r["count"] for r in one.walks.groupBy("source").count().collect()} == {1: 2, 2: 2, 3: 3, 4: 3}
    assert {r.source: r["count"] for r in two.walks.groupBy("source").count().collect()} == {1: 2, 2: 2, 3: 2, 4: 3}
    for s in (one, two):
        assert metrics.check_adequate(s).count() == 0 and metrics.check_paths_valid(s).count() == 0
        for r in s.walks.collect():
            assert hops.setdefault(r.walk_id, r.hops) == r.hops
    again = repair.apply_insert(two, 4, 1)  # present: nothing changes
    assert again.stats == {"updates": 0, "repaired": 0, "trimmed": 0, "added": 0}


def test_push_against_dense(spark):
    e = random_graph(1)
    exact = dense(e, 12)
    edges, src = frame(spark, e), spark.createDataFrame([(0,), (5,)], "source long")
    for s in (push.forward_push(edges, src, P, 0.01), push.power_push(edges, src, P, 0.01, dense_fraction=0.1)):
        rows = s.collect()
        for source in (0, 5):
            got = np.zeros(12)
            for r in rows:
                if r.source == source:
                    got[r.node] += r.reserve
                    got += r.residue * exact[r.node]
            assert np.allclose(got, exact[source])
    first = push.forward_push(edges, src, P, 0.2)
    resumed = push.forward_push(edges, src, P, 0.01, init=first)
    deg = {r.node: r.out_deg for r in graph.degrees(edges).collect()}
    assert all(r.residue < 0.01 * max(deg[r.node], 1) for r in resumed.collect())
    back = push.backward_push(edges, spark.createDataFrame([(3,), (11,)], "target long"), P, 1e-3)
    for r in back.collect():
        assert r.reserve - 1e-9 <= exact[r.node, r.target] <= r.reserve + 1e-3 + 1e-9


def test_queries_meet_the_error_bound(spark):
    e = random_graph(2)
    exact = dense(e, 12)
    p = PprParams.for_graph(12, beta=40.0)
    edges, src = frame(spark, e), spark.createDataFrame([(0,), (5,)], "source long")
    state = repair.build_state(edges, p)
    plain = repair.build_state(edges, p, zero_hop=True)
    answers = [query.query_indexed(state, src), query.query_indexed(state, src, budget="all"), query.query_indexed(plain, src), query.query_by_visits(state, src), query.query_online(edges, src, p), query.query_online(edges, src, p, mode="balanced", blended=True), query.query_monte_carlo(edges, src, p)]
    for k, a in enumerate(answers):
        got = {(r.source, r.node): r.score for r in a.collect()}
        for s in (0, 5):
            if k != 3:  # visits are unbiased, but don't sum to 1
                assert abs(sum(v for (x, _), v in got.items() if x == s) - 1) < 1e-6
            for v in range(12):
                if exact[s, v] >= p.delta:
                    assert abs(got.get((s, v), 0) - exact[s, v]) <= p.epsilon * exact[s, v]
    truth = spark.createDataFrame([(s, v, float(exact[s, v])) for s in (0, 5) for v in range(12)], "source long, node long, score double")
    top = query.query_topk(state, src, 4)
    assert all(r.broken == 0 and r.ranks == 4 for r in metrics.topk_quality(top, truth, 4, p.epsilon, p.delta).collect())
    assert query.query_pair(state, 0, 5).count() <= 1
    assert metrics.check_unbiased(state, spark.createDataFrame([(s, v, float(exact[s, v])) for s in range(12) for v in range(12)], "source long, node long, score double")).first().chi2_per_cell < 1.6


def test_batch_repair_keeps_the_law(spark):
    """Insertions, removals and both dead-end changes in one batch: endpoints follow the new graph's exact scores."""
    e = random_graph(3)
    new = [(a, b) for a in range(12) for b in range(12) if a != b and (a, b) not in e][::7][:8] + [(11, 0)]
    gone = e[::5] + [x for x in e if x[0] == 2]
    state = repair.build_state(frame(spark, e), PprParams.for_graph(12, beta=30.0))
    done = repair.apply_batch(state, ups(spark, [(1, "+", *x) for x in new] + [(2, "-", *x) for x in dict.fromkeys(gone)] + [(0, "-", *new[0]), (5, "-", 7, 7)]))
    after = sorted((set(e) | set(new)) - set(gone))
    assert sorted((r.src, r.dst) for r in done.edges.collect()) == after
    assert metrics.check_adequate(done).count() == 0 and metrics.check_paths_valid(done).count() == 0
    exact = dense(after, 12)
    truth = spark.createDataFrame([(s, v, float(exact[s, v])) for s in range(12) for v in range(12)], "source long, node long, score double")
    assert metrics.check_unbiased(done, truth).first().chi2_per_cell < 1.6
    assert done.stats["repaired"] > 0 and done.walks.select("walk_id").distinct().count() == done.walks.count()
    slots = done.walks.groupBy("source").agg(F.count("*").alias("n"), F.max("slot").alias("top"), F.countDistinct("slot").alias("d")).collect()
    assert all(r.n == r.top + 1 == r.d for r in slots)


@pytest.mark.parametrize("how", samplers.HOW)
def test_samplers_hit_the_right_share(spark, how):
    rows = [(n, w, w % 3, 100 + w % 4) for n in range(40) for w in range(60)]
    rec = spark.createDataFrame(rows, "node long, walk_id long, step int, next long")
    deg = spark.createDataFrame([(n, 5) for n in range(40)], "node long, d long")
    got = samplers.sample_records(rec, deg, 1, 1, how).collect()
    assert len({(r.node, r.walk_id, r.step) for r in got}) == len(got)
    assert abs(len(got) - 480) < 5 * (480 * 0.8) ** 0.5


def test_node_and_update_algebra(spark):
    e = frame(spark, [(1, 2), (2, 3), (3, 1)])
    out = graph.expand_node_updates(spark.createDataFrame([(1, "-", 2)], "tau long, op string, node long"), e)
    assert {(r.src, r.dst) for r in out.collect()} == {(1, 2), (2, 3)}
    log = ups(spark, [(1, "+", 1, 2), (2, "-", 1, 2), (3, "+", 4, 5)])
    assert {(r.src, r.dst) for r in graph.graph_as_of(log, 1).collect()} == {(1, 2)}
    assert {(r.src, r.dst) for r in graph.graph_as_of(log, 3).collect()} == {(4, 5)}
    assert graph.graph_diff(e, frame(spark, [(1, 2), (9, 9)])).count() == 3


def test_engines_answer_within_their_bounds(spark):
    e = random_graph(4)
    p = PprParams.for_graph(12, beta=40.0)
    exact = dense(sorted({*e, (11, 3)}), 12)
    src = spark.createDataFrame([(0,)], "source long")
    for name, make in engines.ENGINES.items():
        engine = make(frame(spark, e), p)
        engine.update(ups(spark, [(1, "+", 11, 3)]))
        got = {r.node: r.score for r in engine.query(src).collect()}
        limit = (2 - p.theta) * p.epsilon if name == "lazy_optimistic" else p.epsilon
        for v in range(12):
            if exact[0, v] >= p.delta:
                assert abs(got.get(v, 0) - exact[0, v]) <= limit * exact[0, v], name


def test_lazy_plan_takes_the_shortest_prefix(spark):
    sigma = spark.createDataFrame([(i, float(i)) for i in range(1, 9)], "node long, sigma double")
    state = spark.createDataFrame([(0, i, 0.0, 0.1) for i in range(1, 9)], "source long, node long, reserve double, residue double")
    got = sorted(r.node for r in engines.lazy_plan(sigma, state, 1.05).collect())  # 0.1 + ... + 0.4 = 1.0 may stay
    assert got == [5, 6, 7, 8]


def test_splits_and_workload(spark):
    e = spark.range(500).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.timestamp_seconds(F.col("id") * 10_000).alias("ts"))
    t = workloads.temporal_split(e)
    assert t.where("part = 'initial'").count() == 450 and t.where("part = 'initial'").agg(F.max("src")).first()[0] == 449
    r = workloads.random_arrival_split(e)
    assert 400 < r.where("part = 'initial'").count() < 490
    u = workloads.updates_from(r, 20)
    w = workloads.mixed_workload(u, workloads.pick_sources(e, 20), 25, 20)
    assert w.count() == 20 and w.where("kind = 'update'").count() == 5


def test_stream_equals_batches(spark, tmp_path):
    e = random_graph(5)
    later = [(k + 1, "+", a, b, None) for k, (a, b) in enumerate([(a, b) for a in range(11) for b in range(12) if a != b and (a, b) not in e][:9])]
    log = spark.createDataFrame(later, graphs.UPDATES)
    p = PprParams.for_graph(12, beta=2.0)
    stream.to_files(log, str(tmp_path / "log"), 3)
    store = StateStore(spark, f"file://{tmp_path}/state", 4)
    store.save(repair.build_state(frame(spark, e), p))
    live = stream.IndexStream(store, compact_after=2)
    live.start(stream.stream_updates(spark, str(tmp_path / "log")), str(tmp_path / "cp")).awaitTermination()
    state = store.load()
    assert len(live.log) > 1
    assert sorted((r.src, r.dst) for r in state.edges.collect()) == sorted([*e, *[(a, b) for _, _, a, b, _ in later]])
    assert metrics.check_adequate(state).count() == 0 and metrics.check_paths_valid(state).count() == 0
    before = store.epochs()
    stream.IndexStream(store).handle(log, live.log[-1]["batch"])  # a repeated batch, after a restart
    assert store.epochs() == before


def test_windows_and_expiry(spark):
    rows = [(1, "+", 1, 2, "2024-01-01 00:00:00"), (2, "+", 1, 2, "2024-01-01 00:30:00"), (3, "-", 3, 4, "2024-01-01 05:00:00")]
    log = spark.createDataFrame(rows, "tau long, op string, src long, dst long, ts string").withColumn("ts", F.to_timestamp("ts"))
    assert stream.update_rate(log, "1 hour").count() == 2
    assert stream.update_rate(log, "1 hour", "30 minutes").count() == 5
    assert stream.update_rate(log, "", gap="2 hours").count() == 2
    gone = stream.expire_edges(log, "1 HOUR").collect()
    assert [(r.src, r.dst, str(r.ts)) for r in gone] == [(1, 2, "2024-01-01 01:30:00")]
    assert stream.sliding_window_graph(log, "2024-01-01 01:00:00", "40 MINUTES").count() == 1


def test_store_and_sql_surface(spark, tmp_path):
    state = repair.build_state(graphs.tiny(spark), P)
    store = StateStore(spark, f"file://{tmp_path}/state", 4)
    store.save(state)
    new = repair.apply_insert(store.load(), 4, 1)
    store.save(new)
    assert store.epochs() == [0, 1] and store.load().edges.count() == 6 and store.load(0).edges.count() == 5
    plan = store.crossings_at([4])._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters" in plan and "part" in plan.split("PartitionFilters")[1][:200]
    store.compact(1)
    assert store.epochs() == [1]
    register(spark, P)
    views(state)
    assert spark.sql("SELECT * FROM ppr_walk(array(1L, 2L, 4L))").count() == 2
    assert abs(spark.sql("SELECT ppr_omega(0.25, 0.25) AS w").first().w - P.omega) < 1e-9
    assert spark.sql("SELECT count(*) AS n FROM crossings").first().n > 0


def test_random_numbers_are_portable_and_uniform(spark):
    df = spark.range(20_000).select(u01(1, "x", F.col("id")).alias("a"), u01(1, "x", F.col("id"), fast=True).alias("b"))
    r = df.agg(F.avg("a").alias("a"), F.avg("b").alias("b"), F.min("a").alias("lo"), F.max("a").alias("hi")).first()
    assert abs(r.a - 0.5) < 0.01 and abs(r.b - 0.5) < 0.01 and 0 <= r.lo and r.hi < 1
