"""Walks made inside tasks are those of the joins, and queries take them."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from walkstream.functions.draws import Texts
from walkstream.functions.params import PprParams
from walkstream.operators import metrics, query, repair, task_walks, walks, workloads
from walkstream.operators.graph import adjacency, degrees
from walkstream.plans.iterate import Rounds

P = PprParams.for_graph(12, beta=2.0)
EDGES = [(a, b) for a in range(11) for b in (0, 3, 7, 11, 40) if a != b] + [(2, 2**61), (-5, 1)]


def frame(spark, edges=EDGES):
    return spark.createDataFrame(edges, "src long, dst long").coalesce(2)


def joined(spark, e, starts, zero_hop, epoch=0):
    return walks.advance(walks.new_walks(starts, P, epoch, zero_hop), adjacency(e), degrees(e), P, epoch)


def rows(df):
    return sorted((r.source, r.slot, r.hops, tuple(r.path), tuple(r.walk_id)) for r in df.select("source", "slot", "hops", "path", "walk_id").collect())


@pytest.mark.parametrize("few", [0, 10**6])
def test_draws_are_the_md5_digits(few, monkeypatch):
    monkeypatch.setattr("walkstream.functions.draws.FEW", few)
    plain = lambda s: int(hashlib.md5(s.encode()).hexdigest()[:13], 16) / 2**52
    for a in (np.array([0, 9, 10, 123456]), np.array([2**32, 7, 2**62, 99]), np.array([-3, 4, -(2**40), 0])):
        b = np.array([5, 10**9, 0, 77])
        for last in (None, 3, 144, b):
            ends = [""] * 4 if last is None else [f":{k}" for k in (last if last is b else [last] * 4)]
            t = Texts(7, "next12", a, b, 3, room=12)
            assert t.u01(4, last).tolist() == t.u01(4, last).tolist() == [plain(f"7:next12:{x}:{y}:3{z}") for x, y, z in zip(a, b, ends, strict=True)]


@pytest.mark.parametrize("zero_hop", [False, True])
def test_index_is_that_of_the_joins(spark, zero_hop, monkeypatch):
    monkeypatch.setattr(task_walks, "PIECE", 7)
    monkeypatch.setattr(task_walks, "TASK_WALKS", 50)
    monkeypatch.setattr(task_walks, "TOGETHER", 64)
    e = frame(spark)
    want = rows(joined(spark, e, walks.index_starts(degrees(e), P), zero_hop))
    assert rows(walks.build_walk_index(e, P, zero_hop=zero_hop)) == want and len(want) > 100
    ends = walks.build_walk_index(e, P, zero_hop=zero_hop, store="ends")
    assert sorted(map(tuple, ends.collect())) == sorted((s, k, path[-1]) for s, k, _, path, _ in want)
    monkeypatch.setattr(task_walks, "TASK_EDGES", 5)
    assert task_walks.walks_in_tasks(e, P, 0, zero_hop, "paths") is None
    assert rows(walks.build_walk_index(e, P, zero_hop=zero_hop)) == want


def test_asked_walks_and_counts(spark, monkeypatch):
    monkeypatch.setattr(task_walks, "TASK_WALKS", 50)
    monkeypatch.setattr(task_walks, "TOGETHER", 64)
    e, asked = frame(spark), spark.createDataFrame([(0, 300), (40, 3), (99, 2), (-5, 150), (4, 0)], "source long, n long")
    want = rows(joined(spark, e, walks.counted(asked, F.lit(0), F.col("n")).select("source", "slot"), True))
    got = walks.fresh_ends(e, asked, P)
    assert sorted(map(tuple, got.collect())) == sorted((s, k, path[-1]) for s, k, _, path, _ in want) and len(want) == 455
    counts = {}
    for s, _, _, path, _ in want:
        counts[s, path[-1]] = counts.get((s, path[-1]), 0) + 1
    assert {(r.source, r.terminal): r.cnt for r in walks.fresh_counts(e, asked, P).collect()} == counts
    none = frame(spark, [(1, 2)]).where("src > 1")
    assert sorted(map(tuple, walks.fresh_ends(none, asked.where("source = 99"), P).collect())) == [(99, 0, 99), (99, 1, 99)]


def test_begun_walks_are_finished_alike(spark):
    e = frame(spark)
    begun = walks.new_walks(walks.index_starts(degrees(e), P), P, 1).withColumn("path", F.when(F.col("hops") > 2, F.array("source", F.lit(7).cast("long"))).otherwise(F.col("path")))
    begun = Rounds(spark, "begun").keep(begun)
    want = rows(walks.advance(begun, adjacency(e), degrees(e), P, 1))
    assert rows(walks.walk_on(begun, e, P, 1, Rounds(spark, "on"))) == want


def test_queries_make_no_supersteps(spark, monkeypatch):
    """The joins of a whole graph by superstep failed by time and disk on large tables."""
    monkeypatch.setattr(walks, "advance", None)
    e, s = frame(spark), spark.createDataFrame([(0,), (99,)], "source long")
    got = {(r.source, r.node): r.score for r in query.query_monte_carlo(e, s, P, walks=500).collect()}
    assert abs(sum(v for (a, _), v in got.items() if a == 0) - 1) < 1e-9 and got[99, 99] == 1
    assert query.query_online(e, s, P, mode="balanced").where("source = 0").agg(F.sum("score")).first()[0] == pytest.approx(1)


def test_raw_bytes_need_no_index(spark, monkeypatch):
    """The written index of x_memory passed its disk on large tables."""
    e = frame(spark)
    want = {r.table_name: r.n_bytes for r in metrics.size_report(repair.build_state(e, P)).collect()}
    monkeypatch.setattr(workloads, "build_state", None)
    assert workloads.raw_bytes(e, P) == want
    assert set(workloads.memory_of_methods(e, P, files=False)["eager"]) == {"raw"}


@pytest.mark.parametrize("beta", [0.5, 2.0])
def test_counted_repairs_are_those_of_the_batch(spark, beta, monkeypatch):
    monkeypatch.setattr(task_walks, "TASK_WALKS", 50)
    monkeypatch.setattr(task_walks, "TOGETHER", 64)
    monkeypatch.setattr(task_walks, "PIECE", 7)
    p = PprParams.for_graph(12, beta=beta)
    edges = frame(spark)
    some = [(1, "+", 0, 9), (2, "-", 0, 3), (3, "-", 4, 0), (4, "-", 4, 7), (5, "+", 40, 2), (6, "+", 40, 77), (7, "-", 2, 2**61), (8, "+", 0, 8), (9, "-", 1, 500), (10, "+", 900, 1), (11, "-", 7, 0)]
    batches = [spark.createDataFrame(rows, "tau long, op string, src long, dst long") for rows in (some, some[:1], [r for r in some if r[1] == "-"], [(1, "-", 500, 501)])]
    base = repair.build_state(edges, p)
    want = [repair.apply_batch(base, b).stats for b in batches]
    assert want[0]["repaired"] and want[0]["trimmed"] and want[0]["added"]

    def unbuilt(*_, **__):
        raise AssertionError("an index was built")

    monkeypatch.setattr(workloads, "build_state", unbuilt)
    assert workloads.repair_counts(edges, batches, p) == want
