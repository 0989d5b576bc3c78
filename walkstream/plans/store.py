"""State on disk: a base and deltas by epoch, partitioned by a hash of the key, committed by their meta row."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.params import PprParams
from ..operators.graph import apply_updates
from ..operators.repair import IndexState, repair
from ..operators.walks import advance_near, crossings_of, walk_on
from .iterate import Rounds, remove

_ID = "walk_id struct<source: bigint, slot: bigint, epoch: bigint>"
#: For each table: the column that places a row, its key and its columns. `live` is false for a key that is gone.
TABLES = {
    "edges": ("src", ["src", "dst"], "src long, dst long, live boolean"),
    "walks": ("source", ["walk_id"], f"{_ID}, source long, slot long, hops int, path array<long>, terminal long, live boolean"),
    "crossings": ("node", ["node", "walk_id", "step"], f"node long, {_ID}, step int, next long, live boolean"),
}


class StateStore:
    """edges, walks and crossings below `path`: one folder for each epoch, whole for the base and changed rows for later
    epochs. The newest row of a key counts. An epoch is readable once its meta file stands; a repeated write of an epoch
    replaces the same folders, with the same rows, since all draws are keyed.

    `apply` reads the partitions of touched nodes and of the walks that are cut, and writes deltas; nothing else of the
    index is opened, so that an update's bytes depend on the partition size, not on the graph. Give as many `parts` as keep a
    partition at a bearable size (some 128 MB).
    """

    def __init__(self, spark: SparkSession, path: str, parts: int = 64):
        self.spark, self.path, self.parts = spark, path.rstrip("/"), parts

    # writing

    def _part(self, column: str):
        return F.pmod(F.xxhash64(column), F.lit(self.parts)).cast("int")

    def _write(self, name: str, epoch: int, df: DataFrame) -> None:
        by, key, _ = TABLES[name]
        placed = df.withColumn("part", self._part(by)).repartition(min(self.parts, 4 * self.spark.sparkContext.defaultParallelism), "part").sortWithinPartitions("part", by)
        placed.write.mode("overwrite").partitionBy("part").parquet(f"{self.path}/{name}/epoch={epoch}")

    def _commit(self, meta: dict) -> None:
        self.spark.createDataFrame([(json.dumps(meta),)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.path}/meta/epoch={meta['epoch']}")

    def save(self, state: IndexState) -> None:
        """Write a whole state as a new base."""
        walks = state.walks.select("walk_id", "source", "slot", "hops", "path").withColumn("terminal", F.element_at("path", -1))
        for name, df in {"edges": state.edges.select("src", "dst"), "walks": walks, "crossings": crossings_of(state.walks)}.items():
            self._write(name, state.epoch, df.withColumn("live", F.lit(True)))
        self._commit({"epoch": state.epoch, "base": state.epoch, "zero_hop": state.zero_hop, "params": state.params.__dict__, "parts": self.parts})

    def apply(self, updates: DataFrame, sampler: str = "bernoulli", trim: str = "uniform") -> dict:
        """Repair by one batch of updates: deltas of the next epoch. Returns the counts of the repair."""
        meta = self.meta()
        epoch, p = meta["epoch"] + 1, PprParams(**meta["params"])
        rounds = Rounds(self.spark, "repair")
        d = repair(StoreView(self, meta), updates, p, epoch, rounds, meta["zero_hop"], sampler, trim)
        walks = d.walks.withColumn("terminal", F.element_at("path", -1)).withColumn("live", F.lit(True))
        none = {c: F.lit(None) for c in ("slot", "hops", "path", "terminal")}
        gone = d.gone.select("walk_id", "source").withColumns(none).withColumn("live", F.lit(False)).select(*[F.col(f.name).cast(f.dataType) for f in walks.schema])
        records = d.new_records.withColumn("live", F.lit(True)).unionByName(d.old_records.withColumn("live", F.lit(False)))
        for name, df in {"edges": d.net.select("src", "dst", (F.col("op") == "+").alias("live")), "walks": walks.unionByName(gone), "crossings": records}.items():
            self._write(name, epoch, df)
        self._commit({**meta, "epoch": epoch})
        rounds.drop_all()
        return d.stats

    def compact(self, keep: int | None = None) -> None:
        """Write the newest state as the base of one more epoch and remove the older ones. keep: write nothing, only remove
        the epochs that neither this one nor later ones read."""
        if keep is None:
            state, rounds = self.load(), Rounds(self.spark, "compact")
            keep = state.epoch + 1
            self.save(IndexState(state.edges, rounds.keep(state.walks), state.params, keep, state.zero_hop))
            rounds.drop_all()
        base = self.meta(keep)["base"]
        for e in self.epochs():
            if e < base:
                for name in ("meta", *TABLES):
                    remove(self.spark, f"{self.path}/{name}/epoch={e}")

    def forget(self, after: int) -> None:
        """Remove the epochs after `after`."""
        for e in self.epochs():
            if e > after:
                for name in ("meta", *TABLES):
                    remove(self.spark, f"{self.path}/{name}/epoch={e}")

    # reading

    def epochs(self) -> list[int]:
        rows = self.spark.read.text(f"{self.path}/meta").select("epoch").distinct().collect()  # one row for each epoch
        return sorted(int(r["epoch"]) for r in rows)

    def meta(self, epoch: int | None = None) -> dict:
        epoch = self.epochs()[-1] if epoch is None else epoch
        return json.loads(self.spark.read.text(f"{self.path}/meta/epoch={epoch}").first()["value"])

    def _read(self, name: str, epochs: list[int]) -> DataFrame:
        paths = [f"{self.path}/{name}/epoch={e}" for e in epochs]
        return self.spark.read.schema(f"{TABLES[name][2]}, epoch int, part int").option("basePath", f"{self.path}/{name}").parquet(*paths)

    def parts_of(self, nodes: DataFrame, column: str) -> list[int]:
        """Partitions that hold the given keys: at most `parts` numbers."""
        return [r[0] for r in nodes.select(self._part(column).alias("part")).distinct().collect()]

    def table(self, name: str, epoch: int | None = None, parts: list[int] | None = None, meta: dict | None = None) -> DataFrame:
        """Rows that hold at an epoch; `parts`: of these partitions only, which literal filters prune."""
        meta = meta or self.meta(epoch)
        key, base, last = TABLES[name][1], meta["base"], meta["epoch"]
        only = (lambda df: df.where(F.col("part").isin(parts))) if parts is not None else (lambda df: df)
        old = only(self._read(name, [base]))
        if last == base:
            return old.where("live").drop("epoch", "part", "live")
        new = only(self._read(name, list(range(base + 1, last + 1))))
        newest = new.groupBy(*key).agg(F.max_by(F.struct(*[c for c in new.columns if c not in key]), "epoch").alias("r")).select(*key, "r.*").select(*new.columns)
        return old.join(newest.select(*key), key, "left_anti").unionByName(newest).where("live").drop("epoch", "part", "live")

    def load(self, epoch: int | None = None) -> IndexState:
        meta = self.meta(epoch)
        return IndexState(self.table("edges", meta=meta), self.table("walks", meta=meta), PprParams(**meta["params"]), meta["epoch"], meta["zero_hop"])

    def crossings_at(self, nodes: list[int], epoch: int | None = None) -> DataFrame:
        """Records of a few nodes: literal partitions prune the scan, sorted files skip row groups."""
        frame = self.spark.createDataFrame([(n,) for n in nodes], "node long")
        return self.table("crossings", epoch, self.parts_of(frame, "node")).where(F.col("node").isin(nodes))


class StoreView:
    """Reads a stored state for `repair`: only the partitions of the nodes or ids that are asked for."""

    def __init__(self, store: StateStore, meta: dict):
        self.store, self.meta = store, meta

    def _at(self, name: str, keys: DataFrame, column: str) -> DataFrame:
        own = keys.select(F.col(column).alias(TABLES[name][0]))
        parts = self.store.parts_of(own, TABLES[name][0])
        return self.store.table(name, parts=parts, meta=self.meta).join(own.distinct(), TABLES[name][0], "left_semi")

    def edges_at(self, nodes: DataFrame) -> DataFrame:
        return self._at("edges", nodes, "node")

    def records_at(self, nodes: DataFrame) -> DataFrame:
        return self._at("crossings", nodes, "node").select("node", "walk_id", "step", "next")

    def walks_from(self, nodes: DataFrame) -> DataFrame:
        return self._at("walks", nodes, "node").select("walk_id", "source", "slot", "hops", "path")

    def walks_by(self, ids: DataFrame) -> DataFrame:
        own = self._at("walks", ids.select(F.col("walk_id.source").alias("node")), "node")
        return own.select("walk_id", "source", "slot", "hops", "path").join(ids, "walk_id")

    def walk_on(self, walks: DataFrame, net: DataFrame, p: PprParams, epoch: int, rounds: Rounds) -> DataFrame:
        """Few walks open only the partitions where they stand; as many walks as partitions would open all in each superstep,
        so they take the whole adjacency once."""
        walks, n = rounds.keep_seen(walks, F.count("*"))
        if n >= self.store.parts:
            edges = rounds.keep(apply_updates(self.store.table("edges", meta=self.meta), net))
            return walk_on(walks, edges, p, epoch, rounds)
        gone, come = net.where("op = '-'").select("src", "dst"), net.where("op = '+'").select("src", "dst")

        def edges_at(nodes: DataFrame) -> DataFrame:
            own = self.edges_at(nodes).select("src", "dst").join(gone, ["src", "dst"], "left_anti")
            return own.unionByName(come.join(nodes.select(F.col("node").alias("src")), "src", "left_semi"))

        return advance_near(walks, edges_at, p, epoch, rounds)
