"""Registered queries do the whole job: brute force on small fixtures, no fixed cut of rounds, rows or digits."""

import json

import numpy as np
import pytest

from walkstream import queries
from walkstream.functions.params import PprParams

N = 4


def ring(spark):
    """A cycle: the slowest graph for a push, since no residue is ever split."""
    return spark.createDataFrame([(i, (i + 1) % N) for i in range(N)], "src long, dst long").coalesce(1)


def exact():
    a = np.roll(np.eye(N), 1, axis=1)
    return 0.2 * np.linalg.inv(np.eye(N) - 0.8 * a)


@pytest.fixture
def on_ring(spark, monkeypatch):
    edges = ring(spark)
    monkeypatch.setattr(queries, "_basket", lambda *_: edges)
    return PprParams.for_graph(N, beta=queries.BETA)


def test_pushes_end_below_the_threshold(spark, on_ring):
    p, want = on_ring, exact()
    state = queries.push_state(spark, "").collect()
    assert state and all(r.residue < p.r_max(N) for r in state)
    for r in queries.backward_push(spark, "").collect():
        assert r.reserve - 1e-6 <= want[r.node, r.target] <= r.reserve + 1 / N + 1e-6 and r.residue < 1 / N


def test_power_method_places_all_mass(spark, on_ring):
    want = exact()
    got = queries.power_ppr(spark, "").collect()
    assert got and all(abs(r.score - want[r.source, r.node]) < 1e-6 for r in got)


def test_graph_as_of_reads_the_whole_log(spark):
    last = {}
    for r in spark.read.parquet("/root/testdata/sf0.01/events.parquet").orderBy("event_id").collect():
        k = json.loads(r.props).get("k")
        if k is not None:
            last[r.user_id, int(k)] = r.event_id % 7 != 0
    got = {(r.src, r.dst) for r in queries.graph_as_of(spark, "/root/testdata/sf0.01").collect()}
    assert got == {e for e, there in last.items() if there}
    print("rows", len(got))


def test_scores_of_delta_stay_on_large_graphs(spark):
    p = PprParams.for_graph(5_000_000)
    rows = spark.createDataFrame([(1, 2, p.delta), (1, 3, p.delta / 1e6), (1, 4, 0.0)], "source long, node long, score double").coalesce(1)
    got = {r.node: r.score for r in queries._rounded(rows, p).collect()}
    assert set(got) == {2, 3} and abs(got[2] - p.delta) < p.delta / 1000
