"""Pushes inside tasks that hold the graph are those of the joins."""

import pytest

from walkstream.functions.params import PprParams
from walkstream.operators import engines, push, query, repair, task_push, workloads

P = PprParams.for_graph(120)
EDGES = [(c * 100 + i, c * 100 + (i + k) % 20, None) for c in range(6) for i in range(20) for k in (1, 3)] + [(7, 99, None), (-5, 2**61, None), (3, -5, None)]


def close(a, b):
    assert a.keys() == b.keys()
    assert all(x == pytest.approx(b[k], abs=1e-12) for k, x in a.items())


def by_key(rows):
    return {tuple(r[:2]): tuple(r[2:]) for r in rows}


def test_rounds_on_a_held_graph_match_joined_ones(spark, monkeypatch):
    edges = spark.createDataFrame(EDGES, "src long, dst long, ts timestamp")
    sources = spark.createDataFrame([(3,), (99,), (104,), (7777,)], "source long")
    monkeypatch.setattr(push, "NEAR_EDGES", 0)
    first = push.forward_push(edges, sources, P, 1e-2, max_rounds=2)

    def take():
        return [by_key(x.collect()) for x in (push.forward_push(edges, sources, P, 1e-2, init=first), push.power_ppr(edges, sources, P, rounds=8))]

    held = []
    with monkeypatch.context() as m:
        m.setattr(push, "rounds_of", None)  # no joined round is planned
        m.setattr(push.PushGraph, "near", None)  # and no edges in reach are looked for
        for block in (1, 7, 1 << 21):
            m.setattr(task_push, "BLOCK", block)
            held.append(take())
    monkeypatch.setattr(task_push, "TASK_EDGES", 0)
    joined = take()
    for some in held:
        for a, b in zip(some, joined, strict=True):
            close(a, b)


def test_queries_on_a_new_index_draw_only_the_walks_they_take(spark, monkeypatch):
    edges = spark.createDataFrame([e[:2] for e in EDGES], "src long, dst long").coalesce(2)
    sources = spark.createDataFrame([(3,), (104,), (7777,)], "source long")
    state = repair.build_state(edges, P, store="ends")
    monkeypatch.setattr(query, "build_state", None)  # no index is built
    close(by_key(query.query_new(edges, sources, P).collect()), by_key(query.query_indexed(state, sources).collect()))
    keyed = lambda df: {(r["source"], r["rank"]): (r["score"],) for r in df.collect()}
    close(keyed(query.query_new(edges, sources, P, 5)), keyed(query.query_topk(state, sources, 5)))


@pytest.mark.parametrize("undirected", [False, True])
def test_staleness_in_tasks_is_that_of_joins(spark, monkeypatch, undirected):
    edges = spark.createDataFrame([e[:2] for e in EDGES], "src long, dst long").coalesce(2)
    touched = spark.createDataFrame([(3, 4, 1, 1, 4), (2**61, 0, 1, 0, 1), (99, 0, 2, 0, 2), (505, 2, 0, 1, 1), (7777, 0, 1, 0, 1)], "node long, a long, k long, gone long, b long")
    monkeypatch.setattr(engines, "backward_push", None)
    drawn, floor = engines.staleness_step(edges, touched, P, undirected)
    drawn = {r.node: (r.sigma,) for r in drawn.collect()}
    monkeypatch.undo()
    monkeypatch.setattr(task_push, "TASK_EDGES", 0)
    joined, other = engines.staleness_step(edges, touched, P, undirected)
    close(drawn, {r.node: (r.sigma,) for r in joined.collect()})
    assert floor == pytest.approx(other) and floor > 0


def test_staleness_alone_builds_no_index(spark, monkeypatch):
    edges = spark.createDataFrame([e[:2] for e in EDGES], "src long, dst long").coalesce(2)
    monkeypatch.setattr(engines, "build_walk_index", None)
    got = workloads.insert_vs_delete(edges, P, 4, ("lazy",), timed=False)
    assert [r["op"] for r in got] == ["insert", "delete"] and all(r["staleness"] > 0 for r in got)


def test_lazy_rebuilds_inside_tasks_and_twins_share_an_update(spark, monkeypatch):
    edges = spark.createDataFrame([e[:2] for e in EDGES[:40]], "src long, dst long").coalesce(2)
    ups = spark.createDataFrame([(1, "+", 0, 9), (2, "-", 3, 4)], "tau long, op string, src long, dst long")
    sources = spark.createDataFrame([(3,)], "source long")
    lazy = engines.LazyEngine(edges, PprParams.for_graph(120, beta=20.0))
    lazy.update(ups)
    twin, joined = lazy.twin(True), lazy.twin(False)
    push_state = lazy._push(sources, P.delta)
    rows = lambda e: sorted(tuple(r) for r in e.state.walks.select("source", "slot", "terminal").collect())
    with monkeypatch.context() as m:
        m.setattr(engines, "walk_on", None)  # the nodes' walks aren't joined
        lazy.fix(push_state, 1e-9)
    assert lazy.rebuilt == 1 and twin.rebuilt == 0 and twin.optimistic
    monkeypatch.setattr(engines, "walks_in_tasks", lambda *a, **k: None)
    joined.fix(push_state, 1e-9)
    assert joined.rebuilt_nodes == lazy.rebuilt_nodes > 0 and rows(lazy) == rows(joined) != rows(twin)
