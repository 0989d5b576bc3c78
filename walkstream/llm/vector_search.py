"""Exact top-k by inner product with M-trees.

Maximum inner product becomes a nearest-neighbour search: with M2 the largest squared norm of a block, a vector x gets the
further coordinate sqrt(M2 - |x|^2), a query 0, and then distance^2 = |q|^2 + M2 - 2 q.x, a metric. Rows are packed into
blocks by a hash; each block holds an M-tree: leaf pages of at most PAGE entries below routing nodes, each with its
centre, covering radius and its children's distances to the parent. A query searches best first by lower bounds and skips
nodes and entries through the stored distances and the triangle inequality, without computing theirs. Scores are exact
integers; bounds are compared with a slack above rounding error. Equal vectors are one entry with the ids that can win, and
equal queries are searched once, so copies cost no distances. Query vectors are packed too and dealt to every block (a stated
query set against all rows, in blocks); those of a pack go down a tree together, and their lists stay in the task from block
to block, so that later blocks meet their bounds. The lists of the tasks are merged by query vector.

Defined cases: vectors that are null or hold null, NaN or infinite components take no part; vectors meet only those of
their own length; ties go to the smaller id; rows with a null id take no part; repeated candidates count each, repeated queries once (a query skips
candidates with its own id); fewer than k candidates give fewer rows. Scores must fit into a long.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import Workspace

PAGE = 64
FAN = 16


def quantise(vector: Column, scale: float = 256.0) -> Column:
    """floor(scale * x) of each component as long; null for vectors that take no part."""
    ok = vector.isNotNull() & F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) < float("inf")))
    return F.when(ok, F.transform(vector, lambda x: F.floor(F.lit(scale) * x.cast("double"))))


class MTree:
    """Bulk-loaded M-tree over integer vectors of one block."""

    def __init__(self, vectors: np.ndarray, page: int = PAGE):
        norms = (vectors.astype(object) ** 2).sum(axis=1) if len(vectors) and np.abs(vectors).max() > 1 << 20 else (vectors.astype(np.int64) ** 2).sum(axis=1)
        self.top = int(norms.max()) if len(vectors) else 0
        self.exact = self.top < 1 << 50
        self.vectors = vectors if self.exact else vectors.astype(object)
        extra = np.sqrt(np.maximum(self.top - norms.astype(np.float64), 0.0))
        self.points = np.hstack([vectors.astype(np.float64), extra[:, None]])
        self.slack = 1e-6 * (1.0 + float(self.top) ** 0.5)
        self.page = page
        self.root = self._grow(np.arange(len(vectors)), None) if len(vectors) else None

    def _grow(self, rows: np.ndarray, parent: np.ndarray | None) -> dict:
        own = self.points[rows]
        middle = own.mean(axis=0)
        centre = own[int(((own - middle) ** 2).sum(axis=1).argmin())]
        dist = np.sqrt(((own - centre) ** 2).sum(axis=1))
        node = {"centre": centre, "radius": float(dist.max()), "parent": 0.0 if parent is None else float(np.sqrt(((centre - parent) ** 2).sum())), "rows": None, "children": ()}
        if len(rows) <= self.page or node["radius"] == 0.0:
            order = np.argsort(dist, kind="stable")
            node["rows"], node["dist"] = rows[order], dist[order]
            node["points"] = np.ascontiguousarray(self.points[node["rows"], :-1])
            return node
        seeds = [int(dist.argmax())]
        near = ((own - own[seeds[0]]) ** 2).sum(axis=1)
        owner = np.zeros(len(rows), dtype=np.int64)
        while len(seeds) < min(FAN, -(-len(rows) // self.page) + 1) and near.max() > 0:
            seeds.append(int(near.argmax()))
            d = ((own - own[seeds[-1]]) ** 2).sum(axis=1)
            owner[d < near] = len(seeds) - 1
            near = np.minimum(near, d)
        node["children"] = tuple(self._grow(rows[owner == s], centre) for s in range(len(seeds)) if (owner == s).any())
        node["child_centre"] = np.stack([c["centre"] for c in node["children"]])
        node["child_parent"] = np.array([c["parent"] for c in node["children"]])
        node["child_radius"] = np.array([c["radius"] for c in node["children"]])
        return node

    def _scores(self, page: dict, lo: int, hi: int, query: np.ndarray, fits: bool) -> np.ndarray:
        if fits:
            return (page["points"][lo:hi] @ query).astype(np.int64)
        whole = [int(x) for x in query]
        return np.array([sum(int(a) * b for a, b in zip(v, whole, strict=True)) for v in self.vectors[page["rows"][lo:hi]]], dtype=np.int64)

    def search(self, query: np.ndarray, k: int, ids: np.ndarray, skip: int | None) -> list[tuple[int, int]]:
        """The k best (score, id), ties to smaller ids; counts distance computations in `computed`."""
        self.computed = 0
        if self.root is None:
            return []
        q = np.append(query.astype(np.float64), 0.0)
        q2 = float((q * q).sum())
        fits = self.exact and float(np.abs(q).max(initial=0)) ** 2 * len(query) < 1 << 50
        asked = q[:-1] if fits else query
        best: list[tuple[int, int]] = []  # a heap of (score, -id): the worst one first
        far = np.inf  # distance beyond which nothing can enter `best`
        d = float(np.sqrt(((self.root["centre"] - q) ** 2).sum()))
        queue = [(max(0.0, d - self.root["radius"]), 0, d, self.root)]
        n = 0
        while queue:
            low, _, d, node = heapq.heappop(queue)
            if low > far:
                break
            if node["rows"] is not None:
                # the page is sorted by the stored distance to its centre: what the triangle inequality leaves is one range
                lo, hi = int(node["dist"].searchsorted(d - far)), int(node["dist"].searchsorted(d + far, side="right"))
                self.computed += hi - lo
                scores = self._scores(node, lo, hi, asked, fits)
                hits = np.arange(hi - lo) if len(best) < k else np.flatnonzero(scores >= best[0][0])
                for s, i in zip(scores[hits].tolist(), ids[node["rows"][lo + hits]].tolist(), strict=True):
                    if i == skip:
                        continue
                    if len(best) < k:
                        heapq.heappush(best, (s, -i))
                    elif (s, -i) > best[0]:
                        heapq.heapreplace(best, (s, -i))
                if len(best) == k:
                    far = max(0.0, q2 + self.top - 2.0 * best[0][0]) ** 0.5 + self.slack
                continue
            near = np.flatnonzero(np.abs(d - node["child_parent"]) - node["child_radius"] <= far)
            self.computed += len(near)
            to_child = np.sqrt(((node["child_centre"][near] - q) ** 2).sum(axis=1))
            for c, dc, lower in zip(near.tolist(), to_child.tolist(), (to_child - node["child_radius"][near]).tolist(), strict=True):
                if lower <= far:
                    n += 1
                    heapq.heappush(queue, (max(0.0, lower), n, dc, node["children"][c]))
        return sorted(((s, -i) for s, i in best), key=lambda x: (-x[0], x[1]))

    def _leaf_scores(self, page: dict, asked: np.ndarray) -> np.ndarray:
        name = "points32" if asked.dtype == np.float32 else "points"
        if name not in page:
            page[name] = page["points"].astype(np.float32)
        return asked @ page[name].T

    def search_many(self, queries: np.ndarray, best: Best, ids: np.ndarray, rows: np.ndarray) -> None:
        """Enter this block's vectors into the lists of many queries, which go down the tree together: each node is left by the
        queries whose bound excludes it, a page is one matrix product of the rest. ids orders ties; rows is kept with a hit."""
        if self.root is None:
            return
        q = np.hstack([queries.astype(np.float64), np.zeros((len(queries), 1))])
        q2 = (q * q).sum(axis=1)
        longest, slack = float(q2.max(initial=0.0)) * float(self.top), self.slack + 1e-6 * float(q2.max(initial=0.0)) ** 0.5
        if not self.exact or longest >= float(1 << 98):
            order = np.argsort(ids, kind="stable")
            for i, query in enumerate(queries):
                hits = self.search(query, best.keep, order.argsort(), None)
                if hits:
                    best.enter(np.full(len(hits), i), np.array([s for s, _ in hits], dtype=np.int64), order[[r for _, r in hits]], ids, rows)
            return
        # sums of products are at most |q| |x|, so below 2^24 (2^53) every step is exact in 32 (64) bits
        asked = queries.astype(np.float32 if longest < float(1 << 46) else np.float64)

        def far(at: np.ndarray) -> np.ndarray:
            worst = best.score[at, -1]
            return np.where(best.full(at), np.sqrt(np.maximum(0.0, q2[at] + self.top - 2.0 * worst)) + slack, np.inf)

        def visit(node: dict, at: np.ndarray, d: np.ndarray) -> None:
            if node["rows"] is not None:
                for lo in range(0, len(at), 1024):
                    part = at[lo : lo + 1024]
                    scores = self._leaf_scores(node, asked[part])
                    least, n = np.where(best.full(part), best.score[part, -1], -np.inf), scores.shape[1]
                    new = np.flatnonzero(~best.full(part))
                    if len(new) and n > best.keep:
                        least[new] = np.partition(scores[new], n - best.keep, axis=1)[:, n - best.keep]
                    r, c = np.nonzero(scores >= least.astype(scores.dtype)[:, None])
                    if len(r):
                        best.enter(part[r], scores[r, c].astype(np.int64), node["rows"][c], ids, rows)
                return
            centres = node["child_centre"]
            to = np.sqrt(np.maximum(0.0, q2[at][:, None] + (centres * centres).sum(axis=1)[None, :] - 2.0 * (q[at] @ centres.T)))
            lower = np.maximum(to - node["child_radius"], np.abs(d[:, None] - node["child_parent"]) - node["child_radius"]) - slack
            for c in np.argsort(to.mean(axis=0)).tolist():
                some = np.flatnonzero(lower[:, c] <= far(at))
                if len(some):
                    visit(node["children"][c], at[some], to[some, c])

        visit(self.root, np.arange(len(queries)), np.sqrt(((self.root["centre"] - q) ** 2).sum(axis=1)))


class Best:
    """The `keep` best (score, first id, rows) of each of n queries, in order; ties to the smaller first id."""

    def __init__(self, n: int, keep: int):
        self.keep, self.count = keep, np.zeros(n, dtype=np.int64)
        self.score, self.first = np.full((n, keep), np.iinfo(np.int64).min), np.zeros((n, keep), dtype=np.int64)
        self.rows = np.empty((n, keep), dtype=object)

    def full(self, at: np.ndarray) -> np.ndarray:
        return self.count[at] == self.keep

    def enter(self, query: np.ndarray, score: np.ndarray, place: np.ndarray, ids: np.ndarray, rows: np.ndarray) -> None:
        at = np.unique(query)
        r, c = np.nonzero(np.arange(self.keep)[None, :] < self.count[at][:, None])
        q = np.concatenate([at[r], query])
        s, first = np.concatenate([self.score[at[r], c], score]), np.concatenate([self.first[at[r], c], ids[place]])
        held = np.concatenate([self.rows[at[r], c], rows[place]])
        order = np.lexsort((first, ~s, q))  # ~s falls as s grows, without overflow
        q = q[order]
        rank = np.arange(len(q)) - np.searchsorted(q, q)
        stays = rank < self.keep
        q, rank, order = q[stays], rank[stays], order[stays]
        self.score[q, rank], self.first[q, rank], self.rows[q, rank] = s[order], first[order], held[order]
        self.count[at] = np.bincount(np.searchsorted(at, q), minlength=len(at))


#: Blocks hold at most so many different vectors; smaller inputs are dealt over up to SPREAD blocks of LEAST_BLOCK at least.
BLOCK, SPREAD, LEAST_BLOCK = 1 << 16, 48, 1 << 10
#: Lists of so many query vectors stay in a task while it goes from block to block; older ones are sent on first.
HELD = 100_000


def encode(values: DataFrame, name: str = "v") -> DataFrame:
    """vec_id, dim and the vector as bytes: 16-bit components if all of them fit, else 64-bit ones; equal vectors, equal bytes."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(1)
            flat, ends = lists.flatten().to_numpy(zero_copy_only=False).astype("<i8"), np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
            small = flat.astype("<i2")
            wrong = np.concatenate([[0], np.cumsum(small != flat)])
            out = [(small if wrong[a] == wrong[b] else flat)[a:b].tobytes() for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.diff(ends).astype(np.int32)), pa.array(out, pa.binary())], names=["vec_id", "dim", "v"])

    return values.select("vec_id", F.col(name).alias("v")).mapInArrow(pack, "vec_id long, dim int, v binary")


def decode(rows: list[bytes], dim: int) -> np.ndarray:
    if all(len(v) == 2 * dim for v in rows):
        return np.frombuffer(b"".join(rows), dtype="<i2").astype(np.int64).reshape(len(rows), dim)
    return np.array([np.frombuffer(v, dtype="<i2" if len(v) == 2 * dim else "<i8") for v in rows], dtype=np.int64).reshape(len(rows), dim)


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, vec_id: str = "vec_id", vector: str = "v", vector_block: int | None = None, query_block: int = 4096) -> DataFrame:
    """query_id, rank, vec_id, score: the k best rows of `vectors` for each row of `queries`; integer vectors (quantise).

    Equal vectors are one entry with their k + 1 smallest ids, and equal query vectors are searched once: no more can be among
    the k best of a query without its own id. An id may stand at several vectors, `most` at most; as many more vectors are kept.
    """
    spark = vectors.sparkSession
    work = Workspace(spark, "vectors")

    def clean(df: DataFrame) -> DataFrame:
        own = df.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(vector).alias("v")).where("v is not null and vec_id is not null")
        return encode(own)

    by_vector = Window.partitionBy("dim", "v")
    each = clean(vectors).groupBy("dim", "v", "vec_id").agg(F.least(F.count("*"), F.lit(k)).cast("int").alias("n"))
    ranked = each.withColumn("r", F.row_number().over(by_vector.orderBy("vec_id"))).where(F.col("r") <= k + 1)
    entries = work.write(ranked.groupBy("dim", "v").agg(F.array_sort(F.collect_list(F.struct("vec_id", "n"))).alias("ids")), "entries")
    asked = work.write(clean(queries).distinct(), "asked")
    # vectors of one id: an id that is no entry's is no candidate
    most = entries.select(F.explode("ids.vec_id").alias("vec_id")).groupBy("vec_id").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 1
    n, keep = entries.count(), k + most
    n_blocks = max(1, -(-n // vector_block)) if vector_block else max(-(-n // BLOCK), min(SPREAD, -(-n // LEAST_BLOCK)), 1)
    n_packs = max(1, -(-asked.select("dim", "v").distinct().count() // query_block))

    def dealt_to(parts: int) -> Column:
        return F.pmod(F.xxhash64("v"), F.lit(parts)).cast("int")

    data = entries.withColumn("block", dealt_to(n_blocks)).repartition(max(1, min(n_blocks, 1024)), "dim", "block").groupBy("dim", "block").agg(F.collect_list(F.struct("ids", "v")).alias("rows"))
    packs = asked.select("dim", "v").distinct().withColumn("pack", dealt_to(n_packs)).groupBy("dim", "pack").agg(F.collect_list("v").alias("pack_rows"))
    pairs = data.join(packs.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(n_blocks - 1)))), ["dim", "block"])

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, tree, first, ids = None, None, None, None
        held: dict[tuple[int, int], tuple[list[bytes], np.ndarray, Best]] = {}

        def sent(key: tuple[int, int]) -> pa.RecordBatch:
            rows, _, best = held.pop(key)
            tops = [[{"score": s, "vec_id": i} for s, e in zip(best.score[q, :m].tolist(), best.rows[q, :m], strict=True) for i, c in e for _ in range(c)] for q, m in enumerate(best.count.tolist())]
            return pa.RecordBatch.from_arrays([pa.array([key[0]] * len(rows), pa.int32()), pa.array(rows, pa.binary()), pa.array(tops, pa.list_(pa.struct([("score", pa.int64()), ("vec_id", pa.int64())])))], names=["dim", "v", "top"])

        for batch in batches:
            for at in range(batch.num_rows):
                dim, block, pack = (batch.column(c)[at].as_py() for c in (0, 1, 3))
                if last != (dim, block):
                    some = batch.column(2)[at].values
                    lists = some.field("ids")
                    ends = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
                    every = lists.flatten()
                    flat = list(zip(every.field("vec_id").to_pylist(), every.field("n").to_pylist(), strict=True))
                    ids = np.empty(len(some), dtype=object)
                    for j in range(len(some)):
                        ids[j] = tuple(flat[ends[j] : ends[j + 1]])
                    first = np.array([e[0][0] for e in ids], dtype=np.int64)
                    tree, last = MTree(decode(some.field("v").to_pylist(), dim), 8 * PAGE), (dim, block)
                key = (dim, pack)
                if key not in held:
                    while held and sum(len(x[0]) for x in held.values()) >= HELD:
                        yield sent(next(iter(held)))
                    rows = batch.column(4)[at].values.to_pylist()
                    held[key] = (rows, decode(rows, dim), Best(len(rows), keep))
                tree.search_many(held[key][1], held[key][2], first, ids)
        for key in list(held):
            yield sent(key)

    top = "array<struct<score: bigint, vec_id: bigint>>"
    found = pairs.sortWithinPartitions("dim", "block", "pack").select("dim", "block", "rows", "pack", "pack_rows").mapInArrow(search, f"dim int, v binary, top {top}")
    merged = found.groupBy("dim", "v").agg(F.flatten(F.collect_list("top")).alias("top"))
    ordered = F.transform(F.array_sort(F.transform("top", lambda x: F.struct((-x["score"]).alias("down"), x["vec_id"].alias("vec_id")))), lambda x: F.struct((-x["down"]).alias("score"), x["vec_id"].alias("vec_id")))
    merged = merged.select("dim", "v", F.slice(ordered, 1, k + k * most).alias("top"))
    own = asked.withColumnRenamed("vec_id", "query_id").join(merged, ["dim", "v"])
    rows = own.select("query_id", F.explode(F.slice(F.filter("top", lambda x: x["vec_id"] != F.col("query_id")), 1, k)).alias("x")).select("query_id", "x.vec_id", "x.score")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
