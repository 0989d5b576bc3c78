"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

Targets: sources share `share` times all words by weight; no target exceeds `cap` times its source's size, and what is cut is
shared again by weight until none is above. A source is taken in whole epochs first; the rest of its target is filled with
documents in the order of exponential keys -ln(u) / quality, the last one by part, so the target is met exactly up to one
word. u is an md5 of (seed, id, text), so reruns agree and lost tasks repeat their choice.

Prefix sums are made on three levels, so that no task gathers a source: keys fall into BUCKETS ranges, each GROUP of which is
a coarse range. The sums of the coarse ranges say where a source's budget ends, those of the ranges in that one say in which
range, and only that range's documents are ordered one by one.

Defined cases: a null text has size 0 and takes nothing; a null source is a source of its own, the last one; a source of
size 0 has target 0; repeated rows are ordered by equal keys in one range and taken as separate documents; an empty table
gives an empty result; other columns of the input are ignored unless they are carried. Sources are a bounded dimension,
checked against MAX_SOURCES.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import WORD_PATTERN, Workspace

BUCKETS, GROUP = 1 << 14, 1 << 7
MAX_SOURCES = 1_000_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_PATTERN)), F.lit(0)).cast("long")


def quality_weight(text: Column, size: Column) -> Column:
    """Default quality: mean characters a word over six, between 1/4 and 2."""
    return F.greatest(F.lit(0.25), F.least(F.lit(2.0), F.coalesce(F.length(text) / F.when(size > 0, size) / 6.0, F.lit(1.0))))


def targets(sizes: Sequence[tuple[str | None, int]], weights: Sequence[float] = (3, 1, 2), share: float = 1.5, cap: float = 2.0) -> dict[str | None, float]:
    """Target of each source; weights repeat over the sources by code point, null last."""
    order = sorted(sizes, key=lambda x: (x[0] is None, (x[0] or "").encode("utf-8", "surrogatepass")))
    weight = {s: float(weights[i % len(weights)]) for i, (s, _) in enumerate(order)}
    limit = {s: cap * n for s, n in order}
    budget = share * sum(n for _, n in order)
    out: dict[str | None, float] = {}
    free = [s for s, _ in order]
    while free:
        left = budget - sum(out.values())
        total = sum(weight[s] for s in free)
        over = [s for s in free if left * weight[s] / total > limit[s]]
        if not over:
            return out | {s: left * weight[s] / total for s in free}
        out |= {s: limit[s] for s in over}
        free = [s for s in free if s not in out]
    return out


def uniform(seed: int, *keys: Column) -> Column:
    """In (0, 1): 52 bits of an md5 of the keys; nulls are left out."""
    digits = F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), *[k.cast("string") for k in keys])), 1, 13)
    return (F.conv(digits, 16, 10).cast("long") + F.lit(0.5)) / F.lit(float(1 << 52))


def mix(docs: DataFrame, workspace: Workspace, weights: Sequence[float] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, quality: Column | None = None, seed: int = 0, doc_id: str = "doc_id", text: str = "text", source: str = "source", carry: Sequence[str] = ()) -> DataFrame:
    """doc_id, source, size, source_size, target and taken (words of the mix, repeats counted), a row for each document.

    carry: input columns that come along, as fields of a struct `row`.
    """
    spark = docs.sparkSession
    sized = docs.withColumn("_n", word_count(F.col(text)))
    es_key = -F.ln(uniform(seed, F.col(doc_id), F.col(text))) / (quality if quality is not None else quality_weight(F.col(text), F.col("_n")))
    row = [F.struct(*carry).alias("row")] if carry else []
    keyed = sized.select(F.col(doc_id).alias("doc_id"), F.col(source).cast("string").alias("source"), F.col("_n").alias("size"), es_key.alias("es_key"), *row)
    keyed = workspace.write(keyed.withColumn("bucket", F.least(F.lit(BUCKETS - 1), F.floor((1 - F.exp(-F.col("es_key"))) * BUCKETS)).cast("int")), "keyed")
    per_bucket = workspace.write(keyed.groupBy("source", "bucket").agg(F.sum("size").alias("words")), "buckets")
    totals = per_bucket.groupBy("source").agg(F.sum("words").alias("n")).limit(MAX_SOURCES + 1).collect()
    if len(totals) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    goal = targets([(r["source"], r["n"]) for r in totals], weights, share, cap)
    rows = []
    for r in totals:
        n, t = r["n"], goal[r["source"]]
        epochs = int(t // n) if n else 0
        rows.append((r["source"], n, t, epochs, int(round(t - epochs * n)) if n else 0))
    per_source = F.broadcast(spark.createDataFrame(rows, "source string, source_size long, target double, epochs long, rest long"))  # at most MAX_SOURCES rows
    same = F.col("source").eqNullSafe(F.col("_s"))
    before = lambda by: F.coalesce(F.sum("words").over(Window.partitionBy("source").orderBy(by).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ends_here = (F.col("before") < F.col("rest")) & (F.col("rest") <= F.col("before") + F.col("words"))
    ranges = per_bucket.withColumn("coarse", F.floor(F.col("bucket") / GROUP).cast("int"))
    coarse = ranges.groupBy("source", "coarse").agg(F.sum("words").alias("words")).withColumn("before", before("coarse"))  # BUCKETS / GROUP rows a source
    end = coarse.join(per_source.select(F.col("source").alias("_s"), "rest"), same).where(ends_here).select(F.col("source").alias("_s"), F.col("coarse").alias("_c"), F.col("before").alias("_base"), "rest")
    fine = ranges.join(F.broadcast(end), same & (F.col("coarse") == F.col("_c"))).withColumn("before", F.col("_base") + before("bucket"))  # GROUP rows a source
    ends = fine.where(ends_here)
    per_source = F.broadcast(per_source.join(ends.select(F.col("source").alias("_s"), F.col("bucket").alias("last"), F.col("before").alias("base")), same, "left").drop("_s"))
    both = keyed.join(per_source.withColumnRenamed("source", "_s"), same).drop("_s")
    run = F.sum("size").over(Window.partitionBy("source").orderBy("es_key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1))
    clear = both.where("last is null or bucket <> last").withColumn("extra", F.when(F.col("bucket") < F.col("last"), F.col("size")).otherwise(F.lit(0)).cast("long"))
    edge = both.where("bucket = last").withColumn("_run", F.coalesce(run, F.lit(0)) + F.col("base")).withColumn("extra", F.greatest(F.lit(0), F.least(F.col("size"), F.col("rest") - F.col("_run"))).cast("long")).drop("_run")
    return clear.unionByName(edge).select("doc_id", "source", "size", "source_size", "target", (F.col("epochs") * F.col("size") + F.col("extra")).alias("taken"), *["row"] * bool(carry))
