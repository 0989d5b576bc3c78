"""Every sampler redirects k/b of the records at a node with k insertions in one batch."""

import pytest

from walkstream.operators import samplers


@pytest.mark.parametrize("how", samplers.HOW)
def test_samplers_take_many_insertions_at_a_node(spark, how):
    rec = spark.createDataFrame([(n, w, w % 3, 100 + w % 4) for n in range(10) for w in range(60)], "node long, walk_id long, step int, next long").coalesce(2)
    deg = spark.createDataFrame([(n, 15, 10) for n in range(10)], "node long, d long, k long").coalesce(2)
    got = samplers.sample_records(rec, deg, 1, 1, how).collect()
    assert len({(r.node, r.walk_id, r.step) for r in got}) == len(got)
    assert abs(len(got) - 400) < 5 * (400 / 3) ** 0.5
