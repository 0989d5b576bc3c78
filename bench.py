"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

The proposal's updates are taken in batches of several sizes; the baselines' ones singly, as they take them. `extra` holds the
ratios that the paper reports (per update and per query, to the proposal) and the cost of one stored update.
"""

from __future__ import annotations

import json
import os
import time

from walkstream.functions.params import PprParams
from walkstream.operators import engines, graph, push, query, repair, walks, workloads
from walkstream.plans.iterate import Rounds
from walkstream.plans.store import StateStore
from walkstream.session import local_session, ship
from walkstream.sources import graphs

SOURCES = 10


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = ship(local_session(cpus, int(cpus)))
    seconds: dict[str, float] = {}

    def timed(name, run):
        t = time.time()
        out = run()
        seconds[name] = round(time.time() - t, 3)
        return out

    def drain(df):
        df.write.format("noop").mode("overwrite").save()

    rounds = Rounds(spark, "bench")
    keep = rounds.keep
    edges = timed("graph_basket_succession", lambda: keep(graphs.basket_succession(spark, sf)))
    n, m = graph.graph_size(edges)
    p = PprParams.for_graph(n, fast_hash=True)
    split = keep(workloads.random_arrival_split(edges))
    start = keep(split.where("part = 'initial'").select("src", "dst"))
    sources = keep(workloads.pick_sources(start, SOURCES))
    state = timed("build_index", lambda: repair.build_state(start, p))
    stats = {}
    for size in (1000, 10_000, 40_000):
        ups = keep(workloads.updates_from(split, size))
        after = timed(f"update_batch_{size}", lambda ups=ups: repair.apply_batch(state, ups))
        stats[size] = after.stats
        if size != 1000:
            after.release()
        else:
            first = after
    after = first
    # the stored index: one batch and one single update by deltas
    store = StateStore(spark, f"{rounds.base}/store", 64)
    store.save(state)
    ups = keep(workloads.updates_from(split, 1000))
    timed("stored_update_batch_1000", lambda: store.apply(ups))
    one = keep(workloads.updates_from(split, 1100).where("tau > 1099"))
    timed("stored_update_1", lambda: store.apply(one))
    # queries
    pushed = timed("forward_push_10_sources", lambda: push.forward_push(after.edges, sources, p, p.r_max(m)))
    ends = keep(walks.walk_ends(after.walks))
    timed("refine_10_sources", lambda: drain(query.refine(pushed, ends, p)))
    after.push_graph  # the graph's tables are part of a state, not of a query
    timed("query_10_sources", lambda: drain(query.query_indexed(after, sources)))
    timed("query_topk_10_sources", lambda: drain(query.query_topk(after, sources, 500)))
    timed("query_top10_10_sources", lambda: drain(query.query_topk(after, sources, 10)))
    # baselines: an update each, and a query of as many sources
    online = engines.OnlineEngine(start, p)
    timed("online_query_10_sources", lambda: drain(online.query(sources)))
    timed("online_topk_10_sources", lambda: drain(online.topk(sources, 500)))
    rebuild = engines.RebuildEngine(start, p)
    timed("rebuild_update_1", lambda: rebuild.update(one))
    timed("rebuild_query_10_sources", lambda: drain(rebuild.query(sources)))
    lazy = engines.LazyEngine(start, p)
    timed("lazy_update_1", lambda: lazy.update(one))
    timed("lazy_query_10_sources", lambda: drain(lazy.query(sources)))
    each = {s: seconds[f"update_batch_{s}"] / s for s in stats}
    best = min(each.values())
    ratio = lambda a, b: round(a / b, 3)
    extra = {
        "update_s_each": {str(s): round(v, 7) for s, v in each.items()},
        "stats": {str(s): v for s, v in stats.items()},
        "repairs_per_update": stats[1000]["repaired"] / 1000,
        "rebuild_to_eager_update": ratio(seconds["rebuild_update_1"], best),
        "lazy_to_eager_update": ratio(seconds["lazy_update_1"], best),
        "online_to_eager_query": ratio(seconds["online_query_10_sources"], seconds["query_10_sources"]),
        "rebuild_to_eager_query": ratio(seconds["rebuild_query_10_sources"], seconds["query_10_sources"]),
        "lazy_to_eager_query": ratio(seconds["lazy_query_10_sources"], seconds["query_10_sources"]),
        "online_to_eager_topk": ratio(seconds["online_topk_10_sources"], seconds["query_topk_10_sources"]),
        "top10_to_full_query": ratio(seconds["query_top10_10_sources"], seconds["query_10_sources"]),
        "topk_to_full_query": ratio(seconds["query_topk_10_sources"], seconds["query_10_sources"]),
        "n": n,
        "m": m,
    }
    print(json.dumps({"metric": "total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf), "extra": extra}))


if __name__ == "__main__":
    main()
