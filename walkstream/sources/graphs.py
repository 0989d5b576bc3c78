"""Graphs on the given tables, edge lists, and a dictionary for string nodes. Edges: src, dst, ts; unique (src, dst)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.iterate import Rounds

EDGES = "src long, dst long, ts timestamp"
UPDATES = "tau long, op string, src long, dst long, ts timestamp"
#: The worked example (fixed values).
TINY = ((1, 2), (2, 4), (3, 1), (3, 2), (4, 3))


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", **options: str) -> DataFrame:
    """Public edge lists: csv with any separator, json, parquet or orc; extra columns are left out."""
    df = spark.read.schema("src long, dst long").options(**options).csv(path) if fmt == "csv" else spark.read.format(fmt).load(path)
    ts = F.col("ts") if "ts" in df.columns else F.lit(None)
    return clean_edges(df.select(F.col("src").cast("long"), F.col("dst").cast("long"), ts.cast("timestamp").alias("ts")))


def clean_edges(raw: DataFrame) -> DataFrame:
    """Drop null ends and self-loops; one row for each edge with its earliest time."""
    return raw.where("src is not null and dst is not null and src <> dst").groupBy("src", "dst").agg(F.min("ts").alias("ts"))


def both_ways(raw: DataFrame) -> DataFrame:
    back = raw.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "ts")
    return clean_edges(raw.unionByName(back))


def _lines(spark: SparkSession, d: str) -> DataFrame:
    lines = load_table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate")
    orders = load_table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def basket_succession(spark: SparkSession, d: str) -> DataFrame:
    """Part to next part within an order."""
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    return clean_edges(_lines(spark, d).select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst"), F.col("o_orderdate").alias("ts")))


def customer_supplier(spark: SparkSession, d: str) -> DataFrame:
    return both_ways(_lines(spark, d).select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst"), F.col("l_shipdate").alias("ts")))


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    return both_ways(_lines(spark, d).select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_partkey") + 1).alias("dst"), F.col("l_shipdate").alias("ts")))


def user_succession(spark: SparkSession, d: str) -> DataFrame:
    """User to the next event's user. A table-wide order, so each day is ordered by itself and the days' ends are linked."""
    events = load_table(spark, d, "events").select("event_id", "ts", "user_id").withColumn("day", F.to_date("ts"))
    w = Window.partitionBy("day").orderBy("ts", "event_id")
    inner = events.withColumn("dst", F.lead("user_id").over(w)).withColumn("ts2", F.col("ts"))
    ends = events.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("head"), F.max_by(F.struct("user_id", "ts"), F.struct("ts", "event_id")).alias("tail"))
    days = Window.orderBy("day")  # one row a day
    links = ends.select(F.col("tail.user_id").alias("src"), F.lead("head").over(days).alias("dst"), F.col("tail.ts").alias("ts"))
    return clean_edges(inner.select(F.col("user_id").alias("src"), "dst", F.col("ts2").alias("ts")).unionByName(links))


def user_propkey(spark: SparkSession, d: str) -> DataFrame:
    events = load_table(spark, d, "events")
    key = F.get_json_object("props", "$.k").cast("long")
    return both_ways(events.select((2 * F.col("user_id")).alias("src"), (2 * key + 1).alias("dst"), "ts"))


def link_labels(spark: SparkSession, d: str) -> DataFrame:
    """url and href of every link of a page."""
    pages = load_table(spark, d, "pages").select("url", "html")
    return pages.select("url", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href")).where("url is not null")


def node_dict(labels: DataFrame, column: str) -> DataFrame:
    """Stable ids for strings: 60 bits of a hash, which needs no order of all labels. Labels that share an id are an error,
    raised where the dictionary is read: about one chance in two at a thousand million labels."""
    named = labels.select(F.col(column).alias("label")).distinct().groupBy(node_id(F.col("label")).alias("node")).agg(F.min("label").alias("label"), F.count("*").alias("_n"))
    clash = F.raise_error(F.concat(F.lit("labels share the node id "), F.col("node").cast("string")))
    return named.select("node", F.when(F.col("_n") == 1, F.col("label")).otherwise(clash.cast("string")).alias("label"))


def node_id(label: Column) -> Column:
    return F.conv(F.substring(F.md5(label), 1, 15), 16, 10).cast("long")


def page_links(spark: SparkSession, d: str) -> DataFrame:
    return clean_edges(link_labels(spark, d).select(node_id(F.col("url")).alias("src"), node_id(F.col("href")).alias("dst"), F.lit(None).cast("timestamp").alias("ts")))


def nation_trade(spark: SparkSession, d: str) -> DataFrame:
    c = load_table(spark, d, "customer").select("c_custkey", "c_nationkey")
    s = load_table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    sold = _lines(spark, d).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    return clean_edges(sold.select(F.col("c_nationkey").cast("long").alias("src"), F.col("s_nationkey").cast("long").alias("dst"), F.col("l_shipdate").alias("ts")))


#: Blocks of the nearest-neighbour search hold at most so many different vectors; smaller inputs are dealt over up to SPREAD
#: blocks. The lists of HELD vectors stay in a task while it goes from block to block.
BLOCK, SPREAD, LEAST_BLOCK, HELD = 1 << 16, 12, 512, 50_000


def _units(lists):
    """The rows of an Arrow column of lists of one length, divided by their norms."""
    import numpy as np

    x = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(lists), -1)
    with np.errstate(all="ignore"):
        return x / np.linalg.norm(x, axis=1, keepdims=True)


def _nearer(lists: list, a, b, rows_of, first, keep: int) -> None:
    """Enter the rows of b into the lists (score, rows_of, first, count) of the rows of a, ties to the smaller `first`. A product in
    32 bits leaves out what its error can't bring into a list; scores are then taken in 64 bits, to nine digits."""
    import numpy as np

    score, entry, ids, count = lists
    a32, b32, slack = a.astype(np.float32), b.astype(np.float32), 1.2e-7 * (a.shape[1] + 16) + 1e-9
    for lo in range(0, len(a), 512):
        for at in range(0, len(b), 8192):
            s, q = a32[lo : lo + 512] @ b32[at : at + 8192].T, slice(lo, lo + 512)
            least = np.where(count[q] == keep, score[q, -1], -np.inf)
            new = np.flatnonzero(count[q] < keep)
            if len(new) and s.shape[1] > keep:
                least[new] = np.partition(s[new], s.shape[1] - keep, axis=1)[:, s.shape[1] - keep] - slack
            r, c = np.nonzero(s >= (least - slack).astype(np.float32)[:, None])
            if not len(r):
                continue
            r, c = r + lo, c + at
            rows = np.unique(r)
            old, k = np.nonzero(np.arange(keep)[None, :] < count[rows][:, None])
            old = rows[old]
            qs, hit = np.concatenate([old, r]), np.concatenate([score[old, k], np.round(np.einsum("ij,ij->i", a[r], b[c]), 9)])
            who, what = np.concatenate([ids[old, k], first[c]]), np.concatenate([entry[old, k], rows_of[c]])
            order = np.lexsort((who, -hit, qs))
            qs = qs[order]
            rank = np.arange(len(qs)) - np.searchsorted(qs, qs)
            order, qs, rank = order[rank < keep], qs[rank < keep], rank[rank < keep]
            score[qs, rank], ids[qs, rank], entry[qs, rank] = hit[order], who[order], what[order]
            count[rows] = np.bincount(np.searchsorted(rows, qs), minlength=len(rows))


def vector_knn(spark: SparkSession, d: str, k: int = 10, block: int | None = None, pack: int = 4096) -> DataFrame:
    """The k nearest vectors by cosine, ties to smaller ids; all pairs of different vectors, in blocks of matrix products.

    Equal vectors are one entry with their k + 1 smallest ids, searched once; each row then drops its own id from its vector's
    list. An id may stand at several vectors, `most` at most; as many more vectors are kept.
    """
    import numpy as np
    import pyarrow as pa

    rounds = Rounds(spark, "knn")
    rows = load_table(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v")).where("v is not null and vec_id is not null")
    each = rows.groupBy("v", "vec_id").agg(F.least(F.count("*"), F.lit(k)).cast("int").alias("n"))
    ranked = each.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("vec_id"))).where(F.col("r") <= k + 1)
    entries = rounds.keep(ranked.groupBy("v").agg(F.array_sort(F.collect_list(F.struct("vec_id", "n"))).alias("ids")).withColumn("dim", F.size("v")))
    most = entries.select(F.explode("ids.vec_id").alias("vec_id")).groupBy("vec_id").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 1
    n, keep, enough = entries.count(), k + most, k + k * most  # vectors of a list, and rows: an own id takes up to k * most of them
    n_blocks = max(1, -(-n // block)) if block else max(-(-n // BLOCK), min(SPREAD, -(-n // LEAST_BLOCK)), 1)
    dealt_to = lambda parts: F.pmod(F.xxhash64("v"), F.lit(parts)).cast("int")
    data = entries.withColumn("b", dealt_to(n_blocks)).repartition(min(n_blocks, 1024), "dim", "b").groupBy("dim", "b").agg(F.collect_list(F.struct("v", "ids")).alias("rows"))
    packs = entries.withColumn("p", dealt_to(max(1, -(-n // pack)))).groupBy("dim", "p").agg(F.collect_list("v").alias("asked"))
    pairs = data.join(packs.withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(n_blocks - 1)))), ["dim", "b"])

    def near(batches):
        last, units, first, ids = None, None, None, None
        held = {}

        def sent(key):
            vs, _, (score, entry, _, count) = held.pop(key)
            downs, dsts, ends = [], [], [0]
            for own, e, m in zip(score.tolist(), entry, count.tolist(), strict=True):
                rows, last = [], None
                for s, listed in zip(own[:m], e[:m], strict=True):
                    if len(rows) >= enough and s < last:
                        break  # what follows is behind all these rows
                    rows += [(-s, i) for i, c in listed for _ in range(c)]
                    last = s
                rows = sorted(rows)[:enough]
                downs += [r[0] for r in rows]
                dsts += [r[1] for r in rows]
                ends.append(len(dsts))
            top = pa.StructArray.from_arrays([pa.array(downs, pa.float64()), pa.array(dsts, pa.int64())], names=["down", "dst"])
            return pa.RecordBatch.from_arrays([vs, pa.ListArray.from_arrays(pa.array(ends, pa.int32()), top)], names=["v", "top"])

        for batch in batches:
            for at in range(batch.num_rows):
                dim, b, p = (batch.column(c)[at].as_py() for c in (0, 1, 3))
                if last != (dim, b):
                    some, last = batch.column(2)[at].values, (dim, b)
                    units = _units(some.field("v"))
                    good = np.flatnonzero(np.isfinite(units).all(axis=1))
                    units, listed = units[good], some.field("ids").to_pylist()
                    ids = np.empty(len(good), dtype=object)
                    for j, g in enumerate(good.tolist()):
                        ids[j] = tuple((e["vec_id"], e["n"]) for e in listed[g])
                    first = np.array([e[0][0] for e in ids], dtype=np.int64)
                if (dim, p) not in held:
                    while held and sum(len(x[0]) for x in held.values()) >= HELD:
                        yield sent(next(iter(held)))
                    vs = batch.column(4)[at].values
                    m = len(vs)
                    held[dim, p] = (vs, _units(vs), [np.full((m, keep), -np.inf), np.empty((m, keep), dtype=object), np.zeros((m, keep), dtype=np.int64), np.zeros(m, dtype=np.int64)])
                _nearer(held[dim, p][2], held[dim, p][1], units, ids, first, keep)
        for key in list(held):
            yield sent(key)

    v_type = rows.schema["v"].dataType.simpleString()
    found = pairs.sortWithinPartitions("dim", "b", "p").select("dim", "b", "rows", "p", "asked").mapInArrow(near, f"v {v_type}, top array<struct<down: double, dst: bigint>>")
    merged = found.groupBy("v").agg(F.flatten(F.collect_list("top")).alias("top"))
    merged = merged.select("v", F.slice(F.array_sort("top"), 1, enough).alias("top"))
    own = rows.select(F.col("vec_id").alias("src"), "v").join(merged, "v")
    best = own.select("src", F.explode(F.slice(F.filter("top", lambda x: x["dst"] != F.col("src")), 1, k)).alias("x")).select("src", "x.dst", "x.down")
    counts = rows.agg(F.count("*").alias("n"), F.count_distinct("vec_id").alias("ids")).first()
    if counts["n"] > counts["ids"]:
        best = best.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy("down", "dst"))).where(F.col("r") <= k)
    return best.select("src", "dst", F.lit(None).cast("timestamp").alias("ts"))


def tiny(spark: SparkSession, d: str = "") -> DataFrame:
    return spark.createDataFrame([(a, b, None) for a, b in TINY], EDGES)


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (basket_succession, customer_supplier, customer_part, user_succession, user_propkey, page_links, nation_trade, vector_knn)}
UNDIRECTED = frozenset({"customer_supplier", "customer_part", "user_propkey"})
