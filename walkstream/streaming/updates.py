"""Update streams: windows, late rows, expiry, stateful counters and the stream that keeps an index current."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..plans.store import StateStore
from ..sources.graphs import UPDATES


def stream_updates(spark: SparkSession, path: str, fmt: str = "parquet", max_files: int = 1, schema: str = UPDATES) -> DataFrame:
    """Update log as a stream of files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).format(fmt).load(path)


def rate_updates(spark: SparkSession, rows_per_second: int, nodes: int) -> DataFrame:
    """Load test: random insertions and deletions from the rate source."""
    raw = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    node = lambda k: F.pmod(F.xxhash64("value", F.lit(k)), F.lit(nodes))
    return raw.select(F.col("value").alias("tau"), F.when(F.pmod(F.xxhash64("value"), F.lit(4)) == 0, "-").otherwise("+").alias("op"), node(1).alias("src"), node(2).alias("dst"), F.col("timestamp").alias("ts"))


def update_rate(updates: DataFrame, width: str, slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Updates by tumbling, sliding or (gap) session window and operation; works on streams and tables."""
    w = F.session_window("ts", gap) if gap else F.window("ts", width, slide) if slide else F.window("ts", width)
    return updates.groupBy(w.alias("w"), "op").agg(F.count("*").alias("n")).select(F.col("w.start").alias("win_start"), F.col("w.end").alias("win_end"), "op", "n")


def deduplicate(updates: DataFrame, delay: str) -> DataFrame:
    return updates.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["src", "dst", "op", "ts"])


def expire_edges(updates: DataFrame, keep: str) -> DataFrame:
    """A deletion `keep` after each insertion that no later insertion of the edge renews in time."""
    from pyspark.sql.window import Window

    w = Window.partitionBy("src", "dst").orderBy("ts", "tau")
    end = F.col("ts") + F.expr(f"INTERVAL {keep}")
    ins = updates.where("op = '+'").withColumn("_next", F.lead("ts").over(w)).where(F.col("_next").isNull() | (F.col("_next") > end))
    return ins.select("tau", F.lit("-").alias("op"), "src", "dst", end.alias("ts"))


def sliding_window_graph(updates: DataFrame, at: str, keep: str) -> DataFrame:
    """Edges inserted within `keep` before `at` and not deleted since."""
    end = F.to_timestamp(F.lit(at))
    live = updates.where((F.col("ts") <= end) & (F.col("ts") > end - F.expr(f"INTERVAL {keep}")))
    return live.groupBy("src", "dst").agg(F.max_by("op", F.struct("ts", "tau")).alias("op")).where("op = '+'").select("src", "dst")


class IndexStream:
    """Keeps a stored index current: each micro-batch is one repair, written as the deltas of one epoch.

    A batch's id is committed with its epoch in the `stream` folder of the store, so after a restart a batch that comes again
    is skipped, and one whose commit was lost is made again with the same draws, over the same folders. Updates older than
    the watermark go to the store's `late` table, one folder for each batch. Every `compact_after` epochs the deltas become a
    new base."""

    def __init__(self, store: StateStore, late_delay_us: int | None = None, compact_after: int = 32):
        self.store, self.spark, self.late_delay_us, self.compact_after = store, store.spark, late_delay_us, compact_after
        self.log: list[dict] = []

    def _marks(self) -> list[dict]:
        """The committed batches: one small row for each."""
        jvm = self.spark._jvm
        at = jvm.org.apache.hadoop.fs.Path(f"{self.store.path}/stream")
        if not at.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(at):
            return []
        rows = self.spark.read.schema("value string, batch long").option("basePath", at.toString()).text(at.toString()).select("value").collect()
        return sorted((json.loads(r["value"]) for r in rows if r["value"]), key=lambda m: m["batch"])

    def handle(self, batch: DataFrame, batch_id: int) -> None:
        marks = self._marks()
        if marks and batch_id <= marks[-1]["batch"]:
            return
        high = marks[-1]["high"] if marks else None
        if self.late_delay_us is not None and "ts" in batch.columns:
            if high is not None:
                limit = F.timestamp_micros(F.lit(high - self.late_delay_us))
                batch.where(F.col("ts") < limit).write.mode("overwrite").parquet(f"{self.store.path}/late/batch={batch_id}")
                batch = batch.where(F.col("ts").isNull() | (F.col("ts") >= limit))
            top = batch.agg(F.max(F.unix_micros(F.col("ts").cast("timestamp")))).first()[0]
            high = max(filter(lambda v: v is not None, (top, high)), default=None)
        before = marks[-1]["epoch"] if marks else None
        at = self.store.epochs()[-1]
        if before is not None and at > before:
            self.store.forget(before)  # the batch was applied but not committed: made again from the same state
        stats = self.store.apply(batch.select("tau", "op", "src", "dst"))
        epoch = self.store.epochs()[-1]
        if self.compact_after and epoch - self.store.meta(epoch)["base"] >= self.compact_after:
            self.store.compact()
            epoch = self.store.epochs()[-1]
        mark = {"batch": batch_id, "epoch": epoch, "high": high}
        self.spark.createDataFrame([(json.dumps(mark),)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.store.path}/stream/batch={batch_id}")
        self.log.append({"batch": batch_id, **stats})

    def late(self) -> DataFrame:
        """The rows that came too late (tau, op, src, dst, ts, batch)."""
        jvm = self.spark._jvm
        at = jvm.org.apache.hadoop.fs.Path(f"{self.store.path}/late")
        if not at.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(at):
            return self.spark.createDataFrame([], f"{UPDATES}, batch long")
        return self.spark.read.schema(f"{UPDATES}, batch long").option("basePath", at.toString()).parquet(at.toString())

    def start(self, updates: DataFrame, checkpoint: str) -> StreamingQuery:
        return updates.writeStream.foreachBatch(self.handle).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def degree_counters(updates: DataFrame) -> DataFrame:
    """Running out-degree of each source of an update stream, as keyed state: the present targets of a node are kept, so a
    repeated insertion or the deletion of an absent edge changes nothing. A hub's targets are one state row."""

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        have = set(state.get[0]) if state.exists else set()
        for pdf in batches:
            for op, dst in pdf.sort_values("tau")[["op", "dst"]].itertuples(index=False):
                have.add(int(dst)) if op == "+" else have.discard(int(dst))
        state.update((sorted(have),))
        yield pd.DataFrame({"node": [key[0]], "out_deg": [len(have)]})

    return updates.groupBy("src").applyInPandasWithState(step, "node long, out_deg long", "targets array<long>", "update", "NoTimeout")


def near_events(updates: DataFrame, events: DataFrame, within: str) -> DataFrame:
    """Interval join: updates at an event's node that happened at most `within` before it. events: node, at. Times are cut into
    tens of minutes, so that the join is on equal keys."""
    step = 600
    width = F.expr(f"INTERVAL {within}")
    cell = lambda t: F.floor(F.unix_timestamp(t) / step)
    spread = events.select("node", "at", F.explode(F.sequence(cell(F.col("at") - width), cell(F.col("at")))).alias("_cell"))
    own = updates.withColumn("_cell", cell(F.col("ts")))
    j = own.join(spread, (own["src"] == spread["node"]) & (own["_cell"] == spread["_cell"])).where((F.col("ts") <= F.col("at")) & (F.col("ts") >= F.col("at") - width))
    return j.select("node", "at", "tau", "op", "src", "dst", "ts")


def join_current(updates: DataFrame, crossings: DataFrame) -> DataFrame:
    """Stream-static join: the records that each update may touch."""
    return updates.join(crossings, updates["src"] == crossings["node"])


def to_files(updates: DataFrame, path: str, batches: int, key: Callable[[], None] | None = None) -> None:
    """Write an update table as `batches` files in tau order, for a file stream."""
    n = updates.count()
    for b in range(batches):
        lo, hi = n * b // batches, n * (b + 1) // batches
        updates.where((F.col("tau") > lo) & (F.col("tau") <= hi)).coalesce(1).write.mode("append").parquet(path)
