"""The SQL of the registered queries, for DuckDB: the whole methods, with the same keyed draws.

Pushes and power iteration are recursive; PUSH_ROUNDS is more than any push at these sizes takes (further rounds change
nothing), POWER_ROUNDS the method's own number.
"""

from __future__ import annotations

from .functions.rng import hop_thresholds, u01_sql

PUSH_ROUNDS, POWER_ROUNDS, SOURCES = 60, 160, 4
_LINES = "lineitem JOIN orders ON l_orderkey = o_orderkey"


def _clean(inner: str) -> str:
    return f"SELECT src, dst, min(ts) AS ts FROM ({inner}) WHERE src IS NOT NULL AND dst IS NOT NULL AND src <> dst GROUP BY src, dst"


def _both(inner: str) -> str:
    return _clean(f"WITH one AS ({inner}) SELECT src, dst, ts FROM one UNION ALL SELECT dst, src, ts FROM one")


_DIGEST = "CAST('0x' || substr(md5({}), 1, 15) AS BIGINT)"
_LOG = "SELECT event_id AS tau, CASE WHEN event_id % 7 = 0 THEN '-' ELSE '+' END AS op, user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst, ts FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL"
GRAPHS = {
    "basket_succession": _clean(f"SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) AS dst, o_orderdate AS ts FROM {_LINES}"),
    "customer_supplier": _both(f"SELECT 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst, l_shipdate AS ts FROM {_LINES}"),
    "customer_part": _both(f"SELECT 2 * o_custkey AS src, 2 * l_partkey + 1 AS dst, l_shipdate AS ts FROM {_LINES}"),
    "user_succession": _clean("SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst, ts FROM events"),
    "user_propkey": _both("SELECT 2 * user_id AS src, 2 * CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 AS dst, ts FROM events"),
    "page_links": _clean(f"SELECT {_DIGEST.format('url')} AS src, {_DIGEST.format('href')} AS dst, NULL AS ts FROM (SELECT url, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages WHERE url IS NOT NULL)"),
    "nation_trade": _clean(f"SELECT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, l_shipdate AS ts FROM {_LINES} JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"),
}
KNN = """WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings WHERE embedding IS NOT NULL),
s AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_dot_product(a.x, b.x) / (sqrt(list_dot_product(a.x, a.x)) * sqrt(list_dot_product(b.x, b.x))), 9) AS s FROM v a JOIN v b ON a.vec_id <> b.vec_id)
SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY s DESC, dst) AS r FROM s) WHERE r <= 10"""


def derived(e: str, tag: str = "") -> str:
    """Degrees and slots of an edge table."""
    return f"""deg{tag} AS MATERIALIZED (SELECT node, CAST(sum(n) AS BIGINT) AS out_deg FROM (SELECT src AS node, 1 AS n FROM {e} UNION ALL SELECT dst, 0 FROM {e}) GROUP BY node),
adj{tag} AS MATERIALIZED (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS slot FROM {e})"""


def graph(name: str = "basket_succession", sources: int = SOURCES) -> str:
    """Edges, degrees, adjacency, sizes and sources of a graph as CTEs."""
    return f"""e AS MATERIALIZED (SELECT src, dst, ts FROM ({GRAPHS[name]})),
{derived('e')},
q AS MATERIALIZED (SELECT CAST(count(*) AS DOUBLE) AS n, CAST(sum(out_deg) AS DOUBLE) AS m FROM deg),
par AS MATERIALIZED (SELECT n, m, (2 * 0.5e0 / 3 + 2) * ln(2 * n) / (0.25e0 / n) AS omega, (2 * 0.5e0 / 3 + 2) * ln(2 * n) / 0.25e0 AS per_delta FROM q),
srcs AS MATERIALIZED (SELECT source FROM (SELECT DISTINCT src AS source FROM e) ORDER BY {u01_sql(7, "source", "source")}, source LIMIT {sources})"""


_SEED = "SELECT source, source AS node, 0.0e0 AS reserve, 1.0e0 AS residue FROM srcs"


def push(name: str, threshold: str | None, seed: str = _SEED, rounds: int = PUSH_ROUNDS, e: str = "e", tag: str = "") -> str:
    """Forward push (threshold None: power iteration) as {name}(source, node, reserve, residue)."""
    test = f"residue > 0 AND residue >= coalesce(out_deg, 0) * {threshold}" if threshold else "residue > 0"
    return f"""{name}t AS MATERIALIZED (SELECT node AS src, CAST(NULL AS BIGINT) AS dst, out_deg FROM deg{tag} UNION ALL SELECT x.src, x.dst, d.out_deg FROM {e} x JOIN deg{tag} d ON d.node = x.src),
{name}r(k, source, node, reserve, residue) AS (
  SELECT 0, source, node, reserve, residue FROM ({seed})
  UNION ALL
  SELECT k + 1, source, to_node, sum(more), sum(rest) FROM (
    SELECT k, source, coalesce(dst, node) AS to_node,
      CASE WHEN dst IS NULL THEN reserve + CASE WHEN coalesce(out_deg, 0) = 0 THEN moved ELSE moved * 0.2e0 END ELSE 0 END AS more,
      CASE WHEN dst IS NULL THEN residue - moved ELSE moved * 0.8e0 / out_deg END AS rest
    FROM (SELECT k, source, node, dst, out_deg, reserve, residue, CASE WHEN {test} THEN residue ELSE 0 END AS moved FROM {name}r LEFT JOIN {name}t ON {name}t.src = {name}r.node WHERE k < {rounds})
    WHERE dst IS NULL OR moved > 0) GROUP BY k, source, to_node),
{name} AS MATERIALIZED (SELECT source, node, reserve, residue FROM {name}r WHERE k = {rounds})"""


def backward(name: str, targets: str, limit: str, rounds: int = PUSH_ROUNDS, e: str = "e", tag: str = "") -> str:
    """Backward push as {name}(target, node, reserve, residue)."""
    moved = f"CASE WHEN residue >= {limit} THEN residue ELSE 0 END"
    return f"""{name}t AS MATERIALIZED (SELECT node AS at, CAST(NULL AS BIGINT) AS src, 0 AS src_deg, out_deg AS at_deg FROM deg{tag} UNION ALL SELECT x.dst, x.src, a.out_deg, b.out_deg FROM {e} x JOIN deg{tag} a ON a.node = x.src JOIN deg{tag} b ON b.node = x.dst),
{name}r(k, target, node, reserve, residue) AS (
  SELECT 0, target, target, 0.0e0, 1.0e0 FROM ({targets})
  UNION ALL
  SELECT k + 1, target, to_node, sum(more), sum(rest) FROM (
    SELECT k, target, coalesce(src, node) AS to_node, CASE WHEN src IS NULL THEN reserve + total * 0.2e0 ELSE 0 END AS more, CASE WHEN src IS NULL THEN residue - moved ELSE total * 0.8e0 / src_deg END AS rest
    FROM (SELECT k, target, node, src, src_deg, reserve, residue, moved, CASE WHEN coalesce(at_deg, 0) = 0 THEN moved / 0.2e0 ELSE moved END AS total
      FROM (SELECT k, target, node, src, src_deg, at_deg, reserve, residue, {moved} AS moved FROM {name}r LEFT JOIN {name}t ON {name}t.at = {name}r.node WHERE k < {rounds}))
    WHERE src IS NULL OR moved > 0) GROUP BY k, target, to_node),
{name} AS MATERIALIZED (SELECT target, node, reserve, residue FROM {name}r WHERE k = {rounds})"""


def born(starts: str, epoch: int = 0, least: int = 1) -> str:
    """Unwalked rows: id (ws, wl, we), source, slot, hops, path."""
    steps = ", ".join(f"{t!r}e0" for t in hop_thresholds(0.2))
    u = u01_sql(7, "hops", "source", "slot", str(epoch))
    return f"SELECT source AS ws, slot AS wl, {epoch} AS we, source, slot, CAST(len(list_filter([{steps}], lambda t: u >= t)) + {least} AS INTEGER) AS hops, [source] AS path FROM (SELECT source, slot, {u} AS u FROM ({starts}))"


def walk(name: str, start: str, epoch: int = 0, tag: str = "") -> str:
    """Walks started rows on to their hops, as {name}."""
    u = u01_sql(7, f"next{epoch}", "ws", "wl", "we", "len(path)")
    return f"""{name}0 AS MATERIALIZED ({start}),
{name}r(ws, wl, we, source, slot, hops, path, node) AS (
  SELECT ws, wl, we, source, slot, hops, path, path[-1] FROM {name}0
  UNION ALL
  SELECT ws, wl, we, source, {name}r.slot, hops, list_append(path, coalesce(a.dst, {name}r.node)), coalesce(a.dst, {name}r.node)
  FROM {name}r LEFT JOIN deg{tag} d ON d.node = {name}r.node LEFT JOIN adj{tag} a ON a.src = {name}r.node AND a.slot = CAST(floor({u} * coalesce(d.out_deg, 0)) AS BIGINT)
  WHERE len(path) <= hops),
{name} AS MATERIALIZED (SELECT ws, wl, we, source, slot, hops, path FROM {name}r WHERE len(path) = hops + 1)"""


def starts(x: str = "1.0e0", tag: str = "") -> str:
    return f"SELECT node AS source, unnest(range(CAST(ceil(out_deg * {x}) AS BIGINT))) AS slot FROM deg{tag} WHERE out_deg > 0"


def crossings(w: str = "w") -> str:
    return f"SELECT path[i] AS node, ws, wl, we, CAST(i - 1 AS INTEGER) AS step, path[i + 1] AS next FROM (SELECT ws, wl, we, path, unnest(range(1, hops + 1)) AS i FROM {w} WHERE hops > 0)"


def ends(w: str = "w") -> str:
    return f"SELECT source, slot, path[-1] AS terminal FROM {w}"


def refine(name: str, state: str, w: str = "w", omega: str = "(SELECT omega FROM par)") -> str:
    """Scores from a push state and walks without zero-hop ones, as {name}(source, node, score)."""
    return f"""{name}n AS MATERIALIZED (SELECT l.source, l.node, residue, least(CAST(ceil(residue * {omega}) AS BIGINT), coalesce(have, 0)) AS use FROM {state} l LEFT JOIN (SELECT source AS node, count(*) AS have FROM {w} GROUP BY 1) c ON c.node = l.node WHERE residue > 0),
{name} AS MATERIALIZED (SELECT source, node, sum(score) AS score FROM (
  SELECT source, node, reserve AS score FROM {state} WHERE reserve > 0
  UNION ALL SELECT source, node, residue * 0.2e0 FROM {state} WHERE residue > 0
  UNION ALL SELECT source, node, residue * 0.8e0 FROM {name}n WHERE use = 0
  UNION ALL SELECT n.source, w.terminal, residue * 0.8e0 / use FROM {name}n n JOIN ({ends(w)}) w ON w.source = n.node AND w.slot < use) GROUP BY source, node)"""


def split(share: float = 0.9) -> str:
    return f"sp AS MATERIALIZED (SELECT src, dst, u, CASE WHEN u < {share}e0 THEN 'initial' ELSE 'later' END AS part FROM (SELECT src, dst, {u01_sql(7, 'split', 'src', 'dst')} AS u FROM e))"


def updates(n: int, share: float = 0.5) -> str:
    k = round(n * share)
    return f"up AS MATERIALIZED (SELECT row_number() OVER (ORDER BY {u01_sql(7, 'workload', 'src', 'dst')}, src, dst) AS tau, op, src, dst FROM ((SELECT '+' AS op, src, dst FROM sp WHERE part = 'later' ORDER BY u, src, dst LIMIT {n - k}) UNION ALL (SELECT '-', src, dst FROM sp WHERE part = 'initial' ORDER BY u DESC, src, dst LIMIT {k})))"


#: The initial graph and an update log on it.
START = f"e0 AS MATERIALIZED (SELECT src, dst FROM sp WHERE part = 'initial'),\n{derived('e0', '0')}"
#: What the log changes, the nodes it touches and the graph after it.
NET = f"""lastop AS (SELECT src, dst, arg_max(op, tau) AS op FROM up WHERE src <> dst GROUP BY src, dst),
net AS MATERIALIZED (SELECT src, dst, op FROM lastop WHERE (op = '+') <> ((src, dst) IN (SELECT (src, dst) FROM e0))),
tch AS MATERIALIZED (SELECT node, coalesce(a, 0) AS a, k, gone, coalesce(a, 0) - gone + k AS b FROM (SELECT src AS node, CAST(sum(CASE WHEN op = '+' THEN 1 ELSE 0 END) AS BIGINT) AS k, CAST(sum(CASE WHEN op = '-' THEN 1 ELSE 0 END) AS BIGINT) AS gone FROM net GROUP BY src) LEFT JOIN (SELECT src AS node, count(*) AS a FROM e0 GROUP BY src) USING (node)),
e1 AS MATERIALIZED (SELECT src, dst FROM e0 WHERE (src, dst) NOT IN (SELECT (src, dst) FROM net WHERE op = '-') UNION ALL SELECT src, dst FROM net WHERE op = '+'),
{derived('e1', '1')}"""


def repaired() -> str:
    """Repair of the index w over e0 by the log, as epoch 1: place, hit, walks1."""
    u = u01_sql(7, "newedge1", "ws", "wl", "we", "step")
    id_in = lambda t: f"(ws, wl, we) NOT IN (SELECT (ws, wl, we) FROM {t})"
    cut = "SELECT w.ws, w.wl, w.we, source, slot, hops, list_append(path[1:step + 1], to_node) AS path FROM w JOIN hit ON hit.ws = w.ws AND hit.wl = w.wl AND hit.we = w.we"
    return f"""place AS MATERIALIZED (SELECT ws, wl, we, source, slot, CAST(ceil(b * 1.0e0) AS BIGINT) AS want, row_number() OVER (PARTITION BY source ORDER BY {u01_sql(7, "trim1", "ws", "wl", "we")}, ws, wl, we) - 1 AS p FROM w JOIN tch ON tch.node = w.source),
gone AS MATERIALIZED (SELECT ws, wl, we FROM place WHERE p >= want),
rec AS MATERIALIZED (SELECT c.node, ws, wl, we, step, next, a, k, b, (a = 0 OR (c.node, next) IN (SELECT (src, dst) FROM net WHERE op = '-')) AS removed FROM ({crossings()}) c JOIN tch ON tch.node = c.node WHERE {id_in('gone')}),
fresh AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS pick FROM net WHERE op = '+'),
red AS MATERIALIZED (SELECT node, ws, wl, we, step, k, CAST(floor({u} * k) AS BIGINT) AS pick FROM rec WHERE NOT removed AND k > 0 AND {u01_sql(7, "hit1", "ws", "wl", "we", "step")} < k / b),
every_hit AS MATERIALIZED (SELECT ws, wl, we, step, dst AS to_node FROM red JOIN fresh ON fresh.src = red.node AND fresh.pick = red.pick
  UNION ALL SELECT ws, wl, we, step, coalesce(dst, node) FROM rec LEFT JOIN adj1 ON adj1.src = node AND slot = CAST(floor({u} * b) AS BIGINT) WHERE removed),
hit AS MATERIALIZED (SELECT ws, wl, we, min(step) AS step, arg_min(to_node, step) AS to_node FROM every_hit GROUP BY ws, wl, we),
lack AS (SELECT node AS source, coalesce(have, 0) AS have, CAST(ceil(b * 1.0e0) AS BIGINT) AS want FROM tch LEFT JOIN (SELECT source, count(*) AS have FROM place WHERE p < want GROUP BY source) h ON h.source = tch.node),
added AS MATERIALIZED ({born("SELECT source, unnest(range(have, want)) AS slot FROM lack WHERE want > have", 1)}),
{walk("v", f"{cut} UNION ALL SELECT ws, wl, we, source, slot, hops, path FROM added", 1, "1")},
walks1 AS MATERIALIZED (SELECT a.ws, a.wl, a.we, a.source, coalesce(place.p, a.slot) AS slot, hops, path FROM (
  SELECT * FROM w WHERE {id_in('gone')} AND {id_in('hit')} UNION ALL SELECT * FROM v) a
  LEFT JOIN place ON place.ws = a.ws AND place.wl = a.wl AND place.we = a.we)"""


def gaps(name: str, purpose: str) -> str:
    """Places hit by geometric gaps among n, of counts cn(node, n, share), as {name}(node, pos)."""
    gap = f"CASE WHEN share >= 1 THEN 1 ELSE least(9007199254740992, floor(ln(1.0e0 - {u01_sql(7, purpose, 'node', 'j')}) / ln(1.0e0 - share)) + 1) END"
    return f"""{name}r(node, n, share, j, pos) AS (SELECT node, n, share, 0, CAST(-1 AS DOUBLE) FROM cn UNION ALL SELECT node, n, share, j + 1, pos + {gap} FROM {name}r WHERE pos < n),
{name} AS MATERIALIZED (SELECT node, CAST(pos AS BIGINT) AS pos FROM {name}r WHERE pos >= 0 AND pos < n)"""


def sampled(how: str) -> str:
    """Records of kept edges at nodes with insertions that a sampler redirects: node, walk (ws, wl, we), step, next."""
    out = "SELECT {a}node, {a}ws AS walk_source, {a}wl AS walk_slot, {a}step, {a}next FROM "
    h = u01_sql(7, "record1", "ws", "wl", "we", "step")
    base = f"""kept AS MATERIALIZED (SELECT node, ws, wl, we, step, next, k, b FROM rec WHERE NOT removed AND k > 0),
cn AS MATERIALIZED (SELECT node, count(*) AS n, any_value(k) / any_value(b) AS share FROM kept GROUP BY node)"""
    if how == "bernoulli":
        return f"{base}\n{out.format(a='')}kept WHERE {u01_sql(7, 'hit1', 'ws', 'wl', 'we', 'step')} < k / b"
    if how == "geometric":
        return f"{base},\n{gaps('g', 'gap1')},\nnum AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY {h}, ws, wl, we, step) - 1 AS p FROM kept)\n{out.format(a='num.')}num JOIN g ON g.node = num.node AND g.pos = num.p"
    base += f",\n{gaps('g', 'count1')},\nneed AS MATERIALIZED (SELECT g.node, any_value(n) AS n, count(*) AS hits FROM g JOIN cn ON cn.node = g.node GROUP BY g.node)"
    if how == "binomial":
        return f"{base},\nnum AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY {h}, ws, wl, we, step) - 1 AS p FROM kept)\n{out.format(a='num.')}num JOIN need ON need.node = num.node AND p < hits"
    tries = f"tries AS MATERIALIZED (SELECT node, n, hits, j, {u01_sql(7, '{}', 'node', 'j')} AS u FROM (SELECT node, n, hits, unnest(range(64 * hits + 1024)) AS j FROM need))"
    if how == "edge_uniform":
        return f"""{base},
{tries.format('edge1')},
ed AS MATERIALIZED (SELECT node, next, on_edge, row_number() OVER (PARTITION BY node ORDER BY next) - 1 AS edge, count(*) OVER (PARTITION BY node) AS active FROM (SELECT node, next, count(*) AS on_edge FROM kept GROUP BY 1, 2)),
turns AS (SELECT t.node, hits, j, next, on_edge, row_number() OVER (PARTITION BY t.node, edge ORDER BY j) - 1 AS turn FROM tries t JOIN (SELECT DISTINCT node, active FROM ed) c ON c.node = t.node JOIN ed ON ed.node = t.node AND ed.edge = CAST(floor(u * c.active) AS BIGINT)),
chosen AS (SELECT node, next, turn FROM (SELECT node, next, turn, hits, row_number() OVER (PARTITION BY node ORDER BY j) AS r FROM turns WHERE turn < on_edge) WHERE r <= hits),
num AS (SELECT *, row_number() OVER (PARTITION BY node, next ORDER BY {h}, ws, wl, we, step) - 1 AS p FROM kept)
{out.format(a='num.')}num JOIN chosen ON chosen.node = num.node AND chosen.next = num.next AND chosen.turn = num.p"""
    return f"""{base},
{tries.format('weight1')},
chosen AS (SELECT node, pos FROM (SELECT node, pos, hits, row_number() OVER (PARTITION BY node ORDER BY j) AS r FROM (SELECT node, hits, CAST(floor(u * n) AS BIGINT) AS pos, min(j) AS j FROM tries GROUP BY 1, 2, 3)) WHERE r <= hits),
num AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY next, {h}, ws, wl, we, step) - 1 AS p FROM kept)
{out.format(a='num.')}num JOIN chosen ON chosen.node = num.node AND chosen.pos = num.p"""


#: Staleness of every node after the log: a sum of bounds over the touched nodes.
STALE = f"""q1 AS MATERIALIZED (SELECT CAST(count(*) AS DOUBLE) AS n FROM deg1),
{backward('bk', 'SELECT node AS target FROM tch', '(SELECT 1 / n FROM q1)', e='e1', tag='1')},
rate AS MATERIALIZED (SELECT node AS target, (CASE WHEN a = 0 THEN 1.0e0 ELSE (gone + (a - gone) * CASE WHEN b > 0 THEN k / b ELSE 0.0e0 END) / a END) / 0.2e0 AS rate FROM tch),
bnd AS MATERIALIZED (SELECT bk.target, bk.node, least(1.0e0, (reserve + (SELECT 1 / n FROM q1)) * rate) AS hi, least(1.0e0, (0.0e0 + (SELECT 1 / n FROM q1)) * rate) AS lo FROM bk JOIN rate ON rate.target = bk.target),
flo AS MATERIALIZED (SELECT sum(lo) AS f FROM (SELECT target, any_value(lo) AS lo FROM bnd GROUP BY target)),
sig AS MATERIALIZED (SELECT node, sum(hi - lo) AS sigma FROM bnd GROUP BY node),
sigma AS MATERIALIZED (SELECT deg1.node, greatest(0.0e0, coalesce(sigma, 0.0e0) + f) AS sigma FROM deg1 CROSS JOIN flo LEFT JOIN sig ON sig.node = deg1.node)"""


def lazy(scale: str) -> str:
    """One query of the lazy engine after the log: push, plan, rebuilt walks, scores."""
    u = "node % 64"
    return f"""{push('ps', f'({scale} / (SELECT omega FROM par))', e='e1', tag='1')},
ok AS (SELECT 0.5e0 * 0.5e0 / n AS allowed, (SELECT f FROM flo) + greatest(0.0e0, (SELECT max(sigma) FROM sig)) AS bound FROM par),
err AS MATERIALIZED (SELECT l.node, greatest(0.0e0, coalesce(sigma, 0.0e0) + (SELECT f FROM flo)) * residue AS e FROM (SELECT node, max(residue) AS residue FROM ps GROUP BY node) l LEFT JOIN sig ON sig.node = l.node),
ranked AS (SELECT node, sum(e) OVER (ORDER BY band DESC, {u}, e, node ROWS UNBOUNDED PRECEDING) AS run FROM (SELECT node, e, CAST(floor(-log2(e) * 64) AS INTEGER) AS band FROM err WHERE e > 0)),
plan AS MATERIALIZED (SELECT node FROM ranked WHERE run > (SELECT allowed FROM ok) AND (SELECT bound > allowed FROM ok)),
{walk("y", born("SELECT plan.node AS source, unnest(range(CAST(ceil(out_deg * 1.0e0) AS BIGINT))) AS slot FROM plan JOIN deg1 ON deg1.node = plan.node WHERE out_deg > 0", 1001), 1001, "1")},
wz AS MATERIALIZED (SELECT * FROM w WHERE source NOT IN (SELECT node FROM plan) UNION ALL SELECT * FROM y),
{refine('est', 'ps', 'wz')}"""


def online(threshold: str) -> str:
    """Index-free query: push, then fresh walks, zero-hop ones kept."""
    return f"""{push('ps', threshold)},
need AS MATERIALIZED (SELECT source, node, residue, CAST(ceil(residue * (SELECT omega FROM par)) AS BIGINT) AS n FROM ps WHERE residue > 0),
{walk("w", born("SELECT node AS source, unnest(range(max(n))) AS slot FROM need GROUP BY node", least=0))},
est AS MATERIALIZED (SELECT source, node, sum(score) AS score FROM (SELECT source, node, reserve AS score FROM ps WHERE reserve > 0
  UNION ALL SELECT need.source, terminal, residue / n FROM need JOIN ({ends()}) t ON t.source = need.node AND t.slot < n) GROUP BY source, node)"""


def iterative(k: int, x: float, levels: int = 5) -> str:
    """A coarse threshold first, then where the least open k-th estimate passes; each source takes the first level it passes."""
    parts = [f"dl0 AS MATERIALIZED (SELECT greatest(1.0e0 / ({k} * 1.5e0) / 4, 1 / n) AS d FROM par)"]
    for i in range(levels):
        delta, omega = f"(SELECT d FROM dl{i})", f"(SELECT per_delta / d FROM par CROSS JOIN dl{i})"
        parts.append(push(f"p{i}", f"({x!r}e0 / {omega})", _SEED if i == 0 else f"SELECT source, node, reserve, residue FROM p{i - 1}"))
        parts.append(refine(f"x{i}", f"p{i}", omega=omega))
        parts.append(f"top{i} AS MATERIALIZED (SELECT {i} AS lvl, source, node, score, rank FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY score DESC, node) AS rank FROM x{i}) WHERE rank <= {k})")
        parts.append(f"pass{i} AS MATERIALIZED (SELECT source, {i} AS lvl FROM top{i} GROUP BY source HAVING (count(*) >= {k} AND min(score) >= 1.5e0 * {delta}) OR {delta} <= (SELECT 1 / n FROM par))")
        earlier = " UNION ALL ".join(f"SELECT source FROM pass{h}" for h in range(i + 1))
        parts.append(f"low{i} AS (SELECT source, min(score) AS low FROM top{i} WHERE source NOT IN ({earlier}) GROUP BY source HAVING count(*) >= {k})")
        parts.append(f"dl{i + 1} AS MATERIALIZED (SELECT greatest((SELECT 1 / n FROM par), coalesce(least({delta} / 4, (SELECT min(low) FROM low{i}) / 1.5e0 / 1.25e0), {delta} / 4)) AS d)")
    every = " UNION ALL ".join(f"SELECT * FROM top{i}" for i in range(levels))
    passed = " UNION ALL ".join(f"SELECT * FROM pass{i}" for i in range(levels))
    parts.append(f"topk AS MATERIALIZED (SELECT t.source, node, score, rank FROM ({every}) t JOIN (SELECT source, min(lvl) AS lvl FROM ({passed}) GROUP BY source) d ON d.source = t.source AND d.lvl = t.lvl)")
    return ",\n".join(parts)



_R = "(1.0e0 / (SELECT omega FROM par))"
_PATH = "array_to_string(list_transform(path, lambda v: CAST(v AS VARCHAR)), ',') AS path"
_SCORES = "SELECT source, node, round(score, (SELECT CAST(greatest(6, ceil(log10(n)) + 3) AS INTEGER) FROM par)) AS score FROM {} WHERE score > 0"


def oracle_sql() -> dict[str, str]:
    g = f"WITH RECURSIVE {graph()},\n"
    nation = f"WITH RECURSIVE {graph('nation_trade', 100)},\n"
    walked = walk("w", born(starts()))
    index = f"{g}{walked}\n"
    pushed = f"{g}{push('ps', _R)}"
    refined = f"{g}{walked},\n{push('ps', _R)},\n{refine('est', 'ps')}"
    exact = f"{push('xs', None, rounds=POWER_ROUNDS)},\nexact AS MATERIALIZED (SELECT source, node, reserve AS score FROM xs WHERE reserve > 0)"
    walked0 = walk("w", born(starts(tag="0")), tag="0")
    log = lambda n, share=0.5: f"{g}{split()},\n{updates(n, share)},\n{START},\n{NET}"
    batch = lambda ups: f"{g}{split()},\n{ups},\n{START},\n{walked0},\n{NET},\n{repaired()}"
    first = lambda op: f"{updates(200).replace('up AS', 'up200 AS')},\nup AS MATERIALIZED (SELECT * FROM up200 WHERE op = '{op}' ORDER BY tau LIMIT 1)"
    walks1 = f"SELECT source, slot, hops, {_PATH} FROM walks1"
    wide = walk("w", born(starts("100.0e0")))
    topk = lambda k, x: f"{g}{walk('w', born(starts(f'{x!r}e0')))},\n{iterative(k, x)}"
    lazy_walks = f"{g}{split()},\n{updates(10)},\n{START},\n{walked0},\n{NET},\n{STALE},\n"
    mc = walk("w", born("SELECT source, unnest(range((SELECT CAST(ceil(omega) AS BIGINT) FROM par))) AS slot FROM srcs", least=0))
    out = {f"graph_{k}": f"SELECT src, dst FROM ({v})" for k, v in GRAPHS.items()}
    out |= {
        "graph_vector_knn": KNN,
        "degrees": f"{g[:-2]} SELECT node, out_deg FROM deg",
        "dead_ends": f"WITH {graph('page_links')} SELECT DISTINCT dst AS node FROM e WHERE dst NOT IN (SELECT src FROM e)",
        "adjacency_slots": f"{g[:-2]} SELECT src, slot, dst, coalesce(out_deg, 0) AS dst_deg FROM adj LEFT JOIN deg ON deg.node = adj.dst",
        "params_table": f"{g[:-2]} SELECT name, round(v, 9) AS value FROM (SELECT 'n' AS name, n AS v FROM par UNION ALL SELECT 'm', m FROM par UNION ALL SELECT 'omega', omega FROM par UNION ALL SELECT 'r_max_balanced', sqrt(1 / (m * omega)) FROM par UNION ALL SELECT 'r_max_linear', 1 / omega FROM par UNION ALL SELECT 'r_max_tuned', 1.0e0 / omega FROM par UNION ALL SELECT 'walks_per_edge', 1.0e0)",
        "power_ppr": f"{g}{exact}\n{_SCORES.format('exact')}",
        "push_state": f"{pushed} SELECT source, node, round(reserve, 8) AS reserve, round(residue, 8) AS residue FROM ps",
        "push_stats": f"{pushed} SELECT source, count(*) AS nodes, CAST(sum(CASE WHEN reserve > 0 THEN 1 ELSE 0 END) AS BIGINT) AS pushed, round(sum(residue), 6) AS left_mass FROM ps GROUP BY source",
        "push_invariant": f"{nation}{push('ps', '1e-3')},\n{push('xs', None, rounds=POWER_ROUNDS)},\ngot AS (SELECT source, node, sum(v) AS v FROM (SELECT source, node, reserve AS v FROM ps UNION ALL SELECT ps.source, xs.node, ps.residue * xs.reserve FROM ps JOIN xs ON xs.source = ps.node WHERE ps.residue > 0) GROUP BY 1, 2) SELECT got.source, max(abs(v - reserve)) < 1e-9 AS holds FROM got JOIN xs ON xs.source = got.source AND xs.node = got.node GROUP BY got.source",
        "power_push": f"{nation}{push('ps', None, rounds=POWER_ROUNDS)}\nSELECT source, node, round(reserve, 5) AS score FROM ps WHERE reserve > 0",
        "backward_push": f"{g}srcs2 AS (SELECT source AS target FROM srcs ORDER BY {u01_sql(7, 'source', 'source')}, source LIMIT 2),\n{backward('bk', 'SELECT target FROM srcs2', '(SELECT 1 / n FROM par)')}\nSELECT target, node, round(reserve, 8) AS reserve, round(residue, 8) AS residue FROM bk",
        "walk_index": f"{index} SELECT source, slot, hops, {_PATH} FROM w",
        "walk_index_zero_hop": f"{g}{walk('w', born(starts(), least=0))}\nSELECT source, slot, hops, {_PATH} FROM w",
        "walk_ends": f"{index} {ends()}",
        "end_counts": f"{index} SELECT source, terminal, cnt, CAST(sum(cnt) OVER (PARTITION BY source) AS BIGINT) AS n_walks FROM (SELECT source, path[-1] AS terminal, count(*) AS cnt FROM w GROUP BY 1, 2)",
        "crossings": f"{index} SELECT node, ws AS walk_source, wl AS walk_slot, step, next FROM ({crossings()})",
        "crossings_by_edge": f"{index} SELECT node, next, count(*) AS records FROM ({crossings()}) GROUP BY node, next",
        "node_counters": f"{index} SELECT node, count(*) AS crossings, count(DISTINCT next) AS active_edges FROM ({crossings()}) GROUP BY node",
        "query_indexed": f"{refined} {_SCORES.format('est')}",
        "query_indexed_all": f"{g}{walked},\n{push('ps', _R)},\nc AS (SELECT source AS node, path[-1] AS terminal, count(*) AS cnt FROM w GROUP BY 1, 2),\nal AS (SELECT node, sum(cnt) AS n FROM c GROUP BY node),\nest AS (SELECT source, node, sum(score) AS score FROM (SELECT source, node, reserve AS score FROM ps WHERE reserve > 0 UNION ALL SELECT source, node, residue * 0.2e0 FROM ps WHERE residue > 0 UNION ALL SELECT ps.source, coalesce(terminal, ps.node), residue * 0.8e0 * coalesce(cnt / n, 1.0e0) FROM ps LEFT JOIN c ON c.node = ps.node LEFT JOIN al ON al.node = ps.node WHERE residue > 0) GROUP BY source, node) {_SCORES.format('est')}",
        "query_monte_carlo": f"{g}{mc}\nSELECT source, path[-1] AS node, count(*) / (SELECT ceil(omega) FROM par) AS score FROM w GROUP BY 1, 2",
        "query_online": f"{g}{online(_R)} {_SCORES.format('est')}",
        "query_online_balanced": f"{g}{online('(SELECT sqrt(1 / (m * omega)) FROM par)')} {_SCORES.format('est')}",
        "query_by_visits": f"{g}{walked},\n{push('ps', _R)},\nal AS (SELECT source AS via, count(*) AS n FROM w GROUP BY 1),\nvis AS (SELECT source AS via, node, count(*) AS c FROM (SELECT source, unnest(path) AS node FROM w) GROUP BY 1, 2),\nest AS (SELECT source, node, sum(score) AS score FROM (SELECT source, node, reserve AS score FROM ps WHERE reserve > 0 UNION ALL SELECT source, node, residue * 0.2e0 * 0.2e0 FROM ps JOIN al ON al.via = ps.node WHERE residue > 0 UNION ALL SELECT ps.source, coalesce(vis.node, ps.node), residue * coalesce(c / n * 0.2e0 * 0.8e0, 1.0e0) FROM ps LEFT JOIN vis ON vis.via = ps.node LEFT JOIN al ON al.via = ps.node WHERE residue > 0) GROUP BY source, node) {_SCORES.format('est')}",
        "topk_full": f"{refined} SELECT source, CAST(rank AS INTEGER) AS rank, node, round(score, 8) AS score FROM (SELECT source, node, score, row_number() OVER (PARTITION BY source ORDER BY score DESC, node) AS rank FROM est) WHERE rank <= 500",
        "topk_iterative": f"{topk(10, 5.0)} SELECT source, CAST(rank AS INTEGER) AS rank, node, round(score, 8) AS score FROM topk",
        "pair": f"{refined} {_SCORES.format('est')} AND node = 17",
        "update_log": f"{log(200)} SELECT tau, op, src, dst FROM up",
        "net_updates": f"{log(200)} SELECT src, dst, '-' AS op FROM up WHERE op = '-'",
        "touched_nodes": f"{log(200)} SELECT node, a, k, gone, b FROM tch",
        "batch_walks": f"{batch(updates(200))} {walks1}",
        "batch_stats": f"{batch(updates(200))} SELECT 'updates' AS name, count(*) AS value FROM net UNION ALL SELECT 'repaired', count(*) FROM hit UNION ALL SELECT 'trimmed', count(*) FROM gone UNION ALL SELECT 'added', count(*) FROM added",
        "insert_walks": f"{batch(first('+'))} {walks1}",
        "delete_walks": f"{batch(first('-'))} {walks1}",
        "stored_walks": f"{batch(updates(200))} {walks1}",
        "stored_crossings": f"{batch(updates(200))} SELECT node, ws AS walk_source, wl AS walk_slot, CAST(we AS BIGINT) AS walk_epoch, step, next FROM ({crossings('walks1')})",
        "adequacy": f"{batch(updates(200))},\nbad AS (SELECT 1 AS one FROM deg1 FULL JOIN (SELECT source, count(*) AS have FROM walks1 GROUP BY source) h ON h.source = deg1.node WHERE coalesce(CAST(ceil(out_deg * 1.0e0) AS BIGINT), 0) <> coalesce(have, 0) UNION ALL SELECT 1 FROM ({crossings('walks1')}) WHERE (node, next) NOT IN (SELECT (src, dst) FROM e1) AND NOT (node = next AND node NOT IN (SELECT src FROM e1)) UNION ALL SELECT 1 FROM walks1 WHERE len(path) <> hops + 1 OR path[1] <> source) SELECT count(*) AS violations FROM bad",
        "node_delete_expansion": f"{g[:-2]} SELECT CASE WHEN src = 5 OR dst = 5 THEN CAST(1 AS BIGINT) ELSE CAST(2 AS BIGINT) END AS tau, '-' AS op, src, dst FROM e WHERE src IN (5, 9) OR dst IN (5, 9)",
        "rebuild_after_update": f"{log(200)},\n{walk('w', born(starts(tag='1'), 1), 1, '1')} SELECT source, slot, hops, {_PATH} FROM w",
        "staleness": f"{log(10)},\n{STALE} SELECT node, round(sigma, 8) AS sigma FROM sigma",
        "lazy_query": f"{lazy_walks}{lazy('0.5e0 * 1.0e0')} {_SCORES.format('est')}",
        "lazy_optimistic_query": f"{lazy_walks}{lazy('1.0e0')} {_SCORES.format('est')}",
        "random_split": f"{g}{split()} SELECT part, count(*) AS n, CAST(sum(src) AS BIGINT) AS src_sum, CAST(sum(dst) AS BIGINT) AS dst_sum FROM sp GROUP BY part",
        "random_split_half": f"WITH {graph('customer_part')},\n{split(0.5)} SELECT src, dst, part FROM sp",
        "temporal_split": f"{g[:-2]} SELECT src, dst, CASE WHEN k <= round(0.9e0 * (SELECT count(*) FROM e)) THEN 'initial' ELSE 'later' END AS part FROM (SELECT src, dst, row_number() OVER (ORDER BY ts, {u01_sql(7, 'split', 'src', 'dst')}, src, dst) AS k FROM e)",
        "mixed_workload": f"{g}{split()},\n{updates(100)},\nqs AS (SELECT source, row_number() OVER (ORDER BY {u01_sql(7, 'source', 'source')}, source) AS n FROM (SELECT DISTINCT src AS source FROM e)),\nops AS (SELECT 'update' AS kind, op, src, dst, CAST(NULL AS BIGINT) AS source, tau AS n FROM up WHERE tau <= 50 UNION ALL SELECT 'query', NULL, NULL, NULL, source, n FROM qs WHERE n <= 50)\nSELECT CAST(row_number() OVER (ORDER BY {u01_sql(7, 'order', 'kind', 'n')}, kind, n) AS INTEGER) AS pos, kind, coalesce(op, '') AS op, coalesce(src, -1) AS src, coalesce(dst, -1) AS dst, coalesce(source, -1) AS source FROM ops",
        "hub_updates": f"WITH e AS ({GRAPHS['customer_supplier']}), hub AS (SELECT src FROM e GROUP BY src ORDER BY count(*) DESC, src LIMIT 1) SELECT row_number() OVER (ORDER BY dst) AS tau, '-' AS op, src, dst FROM (SELECT src, dst FROM e WHERE src = (SELECT src FROM hub) ORDER BY dst LIMIT 50)",
        "relative_error": f"{g}{walked},\n{push('ps', _R)},\n{refine('est', 'ps')},\n{exact} SELECT x.source, count(*) AS nodes, round(avg(abs(coalesce(est.score, 0) - x.score) / x.score), 6) AS avg_error, round(max(abs(coalesce(est.score, 0) - x.score) / x.score), 6) AS max_error FROM exact x LEFT JOIN est ON est.source = x.source AND est.node = x.node WHERE x.score >= (SELECT 1 / n FROM par) GROUP BY x.source",
        "topk_quality": f"{topk(50, 1.0)},\n{exact},\nbest AS (SELECT source, node, score, rank FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY score DESC, node) AS rank FROM exact) WHERE rank <= 50),\nj AS (SELECT t.source, t.score, coalesce(o.score, 0.0e0) AS own, b.score AS best, b.score >= (SELECT 1 / n FROM par) AS sure FROM topk t JOIN best b ON b.source = t.source AND b.rank = t.rank LEFT JOIN exact o ON o.source = t.source AND o.node = t.node) SELECT j.source, count(*) AS ranks, CAST(sum(CASE WHEN sure AND (abs(score - own) > 0.5e0 * own + 1e-12 OR own < 0.5e0 * best - 1e-12) THEN 1 ELSE 0 END) AS BIGINT) AS broken, (SELECT count(*) FROM topk t JOIN best b ON b.source = t.source AND b.node = t.node WHERE t.source = j.source) / count(*) AS precision FROM j GROUP BY j.source",
        "crossing_identity": f"{nation}{wide},\n{exact},\nhv AS (SELECT source, count(*) AS n FROM w GROUP BY source),\nwant AS (SELECT node, sum(n * score) * 5.0e0 AS expected FROM exact JOIN hv ON hv.source = exact.source GROUP BY node) SELECT want.node, round(expected, 3) AS expected, coalesce(c, 0) AS crossings FROM want LEFT JOIN (SELECT node, count(*) AS c FROM ({crossings()}) GROUP BY node) r ON r.node = want.node",
        "endpoint_chi_square": f"{nation}{wide},\n{exact},\nhv AS (SELECT source, count(*) AS n FROM w GROUP BY source),\nts AS (SELECT source, path[-1] AS node, count(*) AS c FROM w GROUP BY 1, 2),\ncells AS (SELECT x.source, x.node, n, (x.score - CASE WHEN x.source = x.node THEN 0.2e0 ELSE 0.0e0 END) / 0.8e0 AS q FROM exact x JOIN hv ON hv.source = x.source) SELECT count(*) AS cells, round(avg(pow(coalesce(c, 0) - n * q, 2) / (n * q * (1 - q))), 6) AS chi2_per_cell FROM cells LEFT JOIN ts ON ts.source = cells.source AND ts.node = cells.node WHERE n * q >= 5 AND q < 0.999999",
        "space_report": f"{index} SELECT 'edges' AS table_name, count(*) AS n_rows, 16 * count(*) AS n_bytes FROM e UNION ALL SELECT 'adjacency', count(*), 32 * count(*) FROM e UNION ALL SELECT 'walk_ends', count(*), 24 * count(*) FROM w UNION ALL SELECT 'walk_paths', count(*), CAST(sum(44 + 8 * len(path)) AS BIGINT) FROM w UNION ALL SELECT 'crossings', CAST(sum(hops) AS BIGINT), CAST(44 * sum(hops) AS BIGINT) FROM w",
        "graph_as_of": f"SELECT src, dst FROM (SELECT src, dst, arg_max(op, tau) AS op FROM ({_LOG}) GROUP BY src, dst) WHERE op = '+'",
        "window_update_rate": f"SELECT date_trunc('hour', ts) AS win_start, date_trunc('hour', ts) + INTERVAL 1 HOUR AS win_end, op, count(*) AS n FROM ({_LOG}) GROUP BY 1, 2, 3",
        "sliding_graph": f"SELECT src, dst FROM (SELECT src, dst, arg_max(op, (ts, tau)) AS op FROM ({_LOG}) WHERE ts > (SELECT max(ts) FROM events) - INTERVAL 2 DAY GROUP BY src, dst) WHERE op = '+'",
    }
    out |= {f"sampler_{how}": f"{batch(updates(200))},\n{sampled(how)}" for how in ("bernoulli", "geometric", "binomial", "edge_uniform", "edge_weighted")}
    return out
