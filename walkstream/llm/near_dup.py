"""Near-duplicates by MinHash signatures in an inverted join over coordinates, confirmed on full shingle sets.

1. Each text becomes a set of 64-bit shingle hashes and a signature of COORDS minima. Texts with equal sets form a class.
2. Coordinate-value pairs have one order for all classes: those of few classes by coordinate, then those of many by their
   count. Two signatures that agree on `least` coordinates agree on one of the first COORDS - least + 1 of both, so each
   class is posted under that prefix alone, and a value that boilerplate gives to a third of all rows is posted only by
   signatures made of such values. Postings of a pair are merged in tiles of bounded size; a tile counts on how many of
   all coordinates two members agree, skips members that are connected already, and returns a spanning forest of the
   matches at or above the match threshold, not all pairs: its components stay the same.
3. Components of the matches are the candidates. Full sets are made anew for their members only and compared within parts
   of bounded size; in a component of several parts one set of each group found goes on to the next round, as long as the
   rounds link groups. Only where several groups are left do all sets of a component meet in tiles, and there only pairs
   of different groups are compared. Confirmed links leave as forests.
4. Components of confirmed links give the result. All component searches run over written tables.

Losses: two sets of the similarity asked for fall below the match threshold with a chance below 1e-7, by choice of the
threshold; the prefix loses nothing. Links are confirmed on sets of 64-bit hashes, of which two shingles share one with a
chance of about 2^-64.

Defined cases: a null, empty or blank text has no shingles, is linked with nothing and is its own component; a text with
fewer than `words` words has its whole sequence as the one shingle; repeated rows with one id share its component; a
null id gets the smallest id of its class and component, null if there is none. An empty table gives an empty result.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as tk
from .common import Workspace

COORDS = 64
#: Members of a tile come from two parts of about so many postings, or about so many bytes of full sets.
TILE_ROWS, TILE_SETS, TILE_BYTES = 512, 128, 8 << 20
_BLOCK = 1 << 18
#: Frequent coordinate-value pairs up to which they are sent to the classes: 24 bytes each, 5 MB.
BROADCAST_VALUES = 200_000
#: Links up to which one side of a component round is broadcast: 16 bytes each, 3 MB.
BROADCAST_LINKS = 200_000
#: Candidate members up to which they are sent to the texts: 20 bytes each, 10 MB.
BROADCAST_MEMBERS = 500_000


@functools.cache
def match_threshold(percent: int) -> int:
    """The largest count that a pair of this similarity reaches but with chance 1e-7."""
    s, below = percent / 100, 0.0
    for k in range(COORDS + 1):
        below += math.comb(COORDS, k) * s**k * (1 - s) ** (COORDS - k)
        if below > 1e-7:
            return max(1, k)
    return COORDS


def shingle_sets(texts, words: int = 5) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    buf, offsets = tk.text_buffer(texts)
    n = len(offsets) - 1
    start, length, doc = tk.split_words(buf, offsets)
    h = tk.hash_spans(buf, start, length, tk.byte_values(True))
    ends = np.searchsorted(doc, np.arange(n + 1))
    for d in range(n):
        own = h[ends[d] : ends[d + 1]]
        if not len(own):
            yield own
            continue
        k = min(words, len(own))
        out = np.full(len(own) - k + 1, k, dtype=np.uint64)
        for j in range(k):
            out = tk.mix(out + own[j : len(own) - k + 1 + j])
        out.sort()
        yield out[np.concatenate([[True], out[1:] != out[:-1]])]


@functools.cache
def _multipliers() -> np.ndarray:
    return np.random.default_rng(771).integers(1, 1 << 63, size=COORDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def signature(shingles: np.ndarray) -> np.ndarray:
    """COORDS minima of the set under multiplicative hashing."""
    a = _multipliers()
    out = np.full(COORDS, np.iinfo(np.uint64).max, dtype=np.uint64)
    step = max(1, _BLOCK // COORDS)
    for lo in range(0, len(shingles), step):
        np.minimum(out, (a[:, None] * shingles[None, lo : lo + step]).min(axis=1), out=out)
    return out


def sketch(docs: DataFrame, words: int = 5, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles, set_key (two hashes of the set as text, null without shingles), minima, sig (16 bits of each)."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("set_key", pa.string()), ("minima", pa.list_(pa.int64())), ("sig", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        tk.forget()
        for batch in batches:
            sizes, keys, minima, sigs = [], [], [], []
            for s in shingle_sets(batch.column(1), words):
                sizes.append(len(s))
                if not len(s):
                    keys.append(None), minima.append(None), sigs.append(None)
                    continue
                sig = signature(s)
                keys.append(xxhash.xxh3_128_hexdigest(s.tobytes()))
                minima.append(sig.view(np.int64))
                sigs.append((sig >> np.uint64(40)).astype("<u2").tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(sizes, pa.int64()), pa.array(keys, pa.string()), pa.array(minima, pa.list_(pa.int64())), pa.array(sigs, pa.binary())], schema=schema)

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(run, "doc_id long, n_shingles long, set_key string, minima array<long>, sig binary")


class _Forest:
    """Union-find over positions 0..n-1."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        i, j = self.find(i), self.find(j)
        if i == j:
            return False
        self.up[max(i, j)] = min(i, j)
        return True

    def roots(self) -> np.ndarray:
        return np.array([self.find(i) for i in range(len(self.up))])


def matching_forest(sigs: np.ndarray, sizes: np.ndarray, least: int, percent: int) -> list[tuple[int, int]]:
    """A spanning forest of the pairs that agree on `least` coordinates and whose sizes allow the similarity."""
    out, tree = [], np.arange(len(sigs))
    for i in range(len(sigs) - 1):
        rest = i + 1 + np.flatnonzero(tree[i + 1 :] != tree[i])
        if not len(rest):
            continue
        small, large = np.minimum(sizes[i], sizes[rest]), np.maximum(sizes[i], sizes[rest])
        rest = rest[100 * small >= percent * large]
        for j in rest[(sigs[rest] == sigs[i]).sum(axis=1) >= least].tolist():
            if tree[j] != tree[i]:
                out.append((i, j))
                tree[tree == tree[j]] = tree[i]
    return out


def confirmed_forest(sets: list[np.ndarray], percent: int, groups: np.ndarray | None = None) -> list[tuple[int, int]]:
    """A spanning forest of the pairs with 100 * intersection >= percent * union, on full sets; groups: sets that are
    connected already, whose links may be left out."""
    n = len(sets)
    if groups is not None and (groups == groups[0]).all():
        return []
    sizes = np.array([len(s) for s in sets], dtype=np.int64)
    forest, out = _Forest(n), []
    if groups is not None:
        first: dict = {}
        for i, g in enumerate(groups.tolist()):
            forest.join(first.setdefault(g, i), i)
    flat, owner = np.concatenate(sets), np.repeat(np.arange(n), sizes)
    order = np.argsort(flat, kind="stable")
    flat, owner = flat[order], owner[order]
    code = np.cumsum(np.concatenate([[True], flat[1:] != flat[:-1]])) - 1
    shared = np.bincount(code) > 1
    keep = shared[code]
    owner, code = owner[keep], np.cumsum(shared)[code[keep]] - 1
    n_codes = int(shared.sum())
    both = np.zeros((n, n), dtype=np.float64)
    step = max(1, (1 << 22) // max(n, 1))
    for lo in range(0, n_codes, step):  # members x shared shingles, a bounded stretch at a time
        a, z = np.searchsorted(code, [lo, lo + step])
        table = np.zeros((n, step), dtype=np.float32)
        table[owner[a:z], code[a:z] - lo] = 1
        both += table @ table.T
    linked = 100 * both >= percent * (sizes[:, None] + sizes[None, :] - both)
    for i, j in zip(*np.nonzero(np.triu(linked, 1)), strict=True):
        if forest.join(int(i), int(j)):
            out.append((int(i), int(j)))
    return out


def _tile_pairs(df: DataFrame, parts: str, salt_of: str) -> DataFrame:
    """Deal rows to the tiles (lo, hi) that hold their part: `parts` parts make parts * (parts + 1) / 2 tiles."""
    own = df.withColumn("_part", F.pmod(F.xxhash64(F.lit(5), salt_of), F.col(parts)).cast("int"))
    other = own.withColumn("_other", F.explode(F.sequence(F.lit(0), (F.col(parts) - 1).cast("int"))))
    return other.withColumn("lo", F.least("_part", "_other")).withColumn("hi", F.greatest("_part", "_other")).drop("_part", "_other")


def prefix_posts(classes: DataFrame, workspace: Workspace, least: int, tile_rows: int) -> DataFrame:
    """rep, n, sig, late, coord, value of the postings of each class (set_key, rep, n, minima, sig); late: a value of more
    than tile_rows classes."""
    spark, length = classes.sparkSession, COORDS - least + 1
    values = classes.select("set_key", F.posexplode("minima").alias("coord", "value"))
    frequent = workspace.write(values.groupBy("coord", "value").agg(F.count("*").alias("n_classes")).where(F.col("n_classes") > tile_rows), "frequent")
    if frequent.count() > BROADCAST_VALUES:
        late = values.join(frequent, ["coord", "value"]).groupBy("set_key").agg(F.sort_array(F.collect_list(F.struct("n_classes", "coord", "value"))).alias("late"))
        every = F.transform("minima", lambda v, i: F.struct(F.lit(0).cast("long").alias("n_classes"), i.alias("coord"), v.alias("value")))
        early = F.filter(every, lambda t: ~F.array_contains(F.col("late.coord"), t["coord"]))
        ordered = F.when(F.col("late").isNull(), every).otherwise(F.concat(early, "late"))
        posted = classes.join(late, "set_key", "left").select("rep", "n", "sig", F.explode(F.slice(ordered, 1, length)).alias("_t"))
        return posted.select("rep", "n", "sig", (F.col("_t.n_classes") > 0).alias("late"), "_t.coord", "_t.value")
    table = frequent.orderBy("n_classes", "coord", "value").toPandas()
    ranked = []
    for c in range(COORDS):
        at = np.flatnonzero(table["coord"].to_numpy() == c)
        own = table["value"].to_numpy(dtype=np.int64)[at]
        order = np.argsort(own)
        ranked.append((own[order], at[order] + 1))
    sent = spark.sparkContext.broadcast(ranked)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            minima = batch.column("minima").flatten().to_numpy(zero_copy_only=False).reshape(-1, COORDS)
            rank = np.zeros(minima.shape, dtype=np.int32)  # 0 of an early value
            for c, (known, place) in enumerate(sent.value):
                if len(known):
                    at = np.minimum(known.searchsorted(minima[:, c]), len(known) - 1)
                    rank[:, c] = np.where(known[at] == minima[:, c], place[at], 0)
            first = np.argsort(rank, axis=1, kind="stable")[:, :length]
            fields = [np.take_along_axis(rank, first, 1) > 0, first.astype(np.int32), np.take_along_axis(minima, first, 1)]
            rows = pa.StructArray.from_arrays([pa.array(f.ravel()) for f in fields], ["late", "coord", "value"])
            posts = pa.ListArray.from_arrays(pa.array(np.arange(len(minima) + 1, dtype=np.int32) * length), rows)
            yield pa.RecordBatch.from_arrays([batch.column("rep"), batch.column("n"), batch.column("sig"), posts], ["rep", "n", "sig", "posts"])

    posted = classes.select("rep", "n", "sig", "minima").mapInArrow(run, "rep long, n long, sig binary, posts array<struct<late: boolean, coord: int, value: long>>")
    return posted.select("rep", "n", "sig", F.inline("posts"))


def candidate_links(classes: DataFrame, workspace: Workspace, percent: int, tile_rows: int = TILE_ROWS) -> DataFrame:
    """a, b: forests of matches among classes (set_key, rep, n, minima, sig)."""
    least = match_threshold(percent)
    posts = prefix_posts(classes, workspace, least, tile_rows)
    hot = posts.where("late").groupBy("coord", "value").count().where(F.col("count") > tile_rows)
    hot = workspace.write(hot.select("coord", "value", F.ceil(F.col("count") / tile_rows).cast("int").alias("parts")), "hot")
    few = hot.count() <= BROADCAST_VALUES
    dealt = _tile_pairs(posts.drop("late").join(F.broadcast(hot) if few else hot, ["coord", "value"], "left").withColumn("parts", F.coalesce("parts", F.lit(1))), "parts", "rep")
    tiles = dealt.groupBy("coord", "value", "lo", "hi").agg(F.collect_list(F.struct("rep", "n", "sig")).alias("rows")).where(F.size("rows") > 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = [], []
            lists = batch.column(0)
            fields = lists.flatten()
            ends = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))])
            rep, n = fields.field(0).to_numpy(), fields.field(1).to_numpy()
            sig = np.frombuffer(b"".join(fields.field(2).to_pylist()), dtype="<u2").reshape(-1, COORDS)
            for lo, hi in zip(ends[:-1], ends[1:], strict=True):
                order = lo + np.argsort(rep[lo:hi], kind="stable")
                for i, j in matching_forest(sig[order], n[order], least, percent):
                    a.append(rep[order[i]])
                    b.append(rep[order[j]])
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return tiles.select("rows").mapInArrow(run, "a long, b long").distinct()


def components(links: DataFrame, workspace: Workspace, name: str, max_rounds: int = 60) -> DataFrame:
    """node, component (the smallest node reachable) of all nodes with links, by alternating large and small stars.

    Links are written each round, so a lost executor costs one round; rounds grow as the logarithm of the nodes.
    """
    def sums(df: DataFrame):
        return df.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("a", "b")).alias("h")).first()

    stars = workspace.write(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct(), f"{name}_0")
    prior = sums(stars)
    for k in range(1, max_rounds):
        # larger neighbours go to the smallest of a neighbourhood, then so do the smaller ones
        def small_side(df: DataFrame, step: str, n: int = prior["n"], k: int = k) -> DataFrame:
            """A join's side with one row a node: sent to all tasks up to BROADCAST_LINKS links, else written, so that both
            sides are dealt out by the join itself and large partitions of the other one can be split."""
            return F.broadcast(df) if n <= BROADCAST_LINKS else workspace.write(df, f"{name}_{step}_{k}")

        both = stars.unionByName(stars.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("u"), F.least("a", "m").alias("m"))
        large = both.join(small_side(least, "large"), F.col("a") == F.col("u")).where("b > u").select(F.col("m").alias("a"), "b").distinct()
        low = large.groupBy("b").agg(F.min("a").alias("m")).withColumnRenamed("b", "u")
        small = large.join(small_side(low, "small"), F.col("b") == F.col("u")).select("m", F.explode(F.array("a", "u")).alias("y")).where("m <> y")
        stars = workspace.write(small.select(F.col("m").alias("a"), F.col("y").alias("b")).distinct(), f"{name}_{k}")
        last, prior = prior, sums(stars)
        if k > 1:
            workspace.drop(f"{name}_{k - 2}")
        if last == prior:
            break
    else:
        raise RuntimeError("components don't settle")
    return stars.select(F.col("b").alias("node"), F.col("a").alias("component")).unionByName(stars.select(F.col("a").alias("node"), F.col("a").alias("component"))).distinct()


def _groups(members: DataFrame, links: DataFrame, workspace: Workspace, name: str) -> DataFrame:
    """rep, n, component, grp: the smallest set that the links connect with each."""
    found = components(links, workspace, name)
    return members.join(found.withColumnRenamed("component", "_least"), F.col("rep") == F.col("node"), "left").select("rep", "n", members["component"], F.coalesce("_least", "rep").alias("grp"))


def confirm(docs: DataFrame, members: DataFrame, workspace: Workspace, percent: int, words: int, doc_id: str, text: str, tile_sets: int = TILE_SETS, tile_bytes: int = TILE_BYTES) -> DataFrame:
    """a, b: forests of confirmed links within the candidate components of `members` (rep, n, component)."""
    texts = docs.select(F.col(doc_id).cast("long").alias("rep"), F.col(text).cast("string").alias("text"))
    parts = F.greatest(F.ceil(F.col("k") / tile_sets), F.ceil(F.col("total") * 8 / tile_bytes)).cast("int")

    def parted(rows: DataFrame) -> DataFrame:
        """rep, n, component, grp, parts: how many parts the component's sets take."""
        return rows.join(rows.groupBy("component").agg(F.count("*").alias("k"), F.sum("n").alias("total")).select("component", parts.alias("parts")), "component")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [s.tobytes() for s in shingle_sets(batch.column("text"), words)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("rep", "component", "grp", "parts")), pa.array(found, pa.binary())], ["rep", "component", "grp", "parts", "shingles"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = [], []
            for rows in batch.column(0):
                own = sorted(((r["rep"], r["grp"], r["shingles"]) for r in rows.as_py()), key=lambda r: r[0])
                groups = np.array([g for _, g, _ in own], dtype=np.int64)
                for i, j in confirmed_forest([np.frombuffer(s, dtype=np.uint64) for _, _, s in own], percent, groups):
                    a.append(own[i][0])
                    b.append(own[j][0])
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    def compared(rows: DataFrame, name: str, across: bool) -> DataFrame:
        """Confirmed links of sets in one part; across: of any two parts."""
        placed = rows.select("rep", "component", "grp", "parts")
        if rows.count() <= BROADCAST_MEMBERS:  # few, as checked here: the texts needn't be dealt out anew
            placed = F.broadcast(placed)
        full = texts.join(placed, "rep").select("rep", "component", "grp", "parts", "text").mapInArrow(sets, "rep long, component long, grp long, parts int, shingles binary")
        one = F.pmod(F.xxhash64(F.lit(5), "rep"), F.col("parts")).cast("int")
        tiled = _tile_pairs(full, "parts", "rep") if across else full.withColumn("lo", one).withColumn("hi", F.lit(-1))
        tiles = tiled.groupBy("component", "lo", "hi").agg(F.collect_list(F.struct("rep", "grp", "shingles")).alias("rows")).where(F.size("rows") > 1)
        return workspace.write(tiles.select("rows").mapInArrow(run, "a long, b long").where("a <> b").distinct(), name)

    rows = workspace.write(parted(members.withColumn("grp", F.col("rep"))), "parted_0")
    links = compared(rows, "confirmed_0", False)
    every = rows.where("parts > 1").select("rep", "n", "component")  # components that one part doesn't hold
    left, k = every.count(), 0
    while left:  # one set of each group goes on, for as long as that links a tenth of them
        k += 1
        grouped = workspace.write(_groups(every, links, workspace, f"grouped_{k}"), f"groups_{k}")
        open_ = grouped.groupBy("component").agg(F.min("grp").alias("_lo"), F.max("grp").alias("_hi")).where("_lo < _hi").select("component")
        grouped = grouped.join(open_, "component", "left_semi")
        leaders = workspace.write(parted(grouped.where("rep = grp").select("rep", "n", "component", "grp").dropDuplicates(["rep"])), f"parted_{k}")
        before, left = left, leaders.count()
        if not left:
            break
        if 10 * left > 9 * before:
            return links.unionByName(compared(workspace.write(parted(grouped), "open"), "confirmed_open", True))
        links = workspace.write(links.unionByName(compared(leaders, f"confirmed_{k}", False)), f"links_{k}")
    return links


def link(docs: DataFrame, workspace: Workspace, percent: int = 80, words: int = 5, doc_id: str = "doc_id", text: str = "text", salts: int = 64) -> DataFrame:
    """doc_id, n_shingles, component_id and kept (doc_id is the component's) of every row."""
    sketches = workspace.write(sketch(docs, words, doc_id, text), "sketches")
    # classes of equal sets: partial minima in every task, so a class of any size is cheap
    named = sketches.where("set_key is not null and doc_id is not null")
    classes = workspace.write(named.groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.count("*").alias("k"), F.first("n_shingles").alias("n"), F.first("minima").alias("minima"), F.first("sig").alias("sig")), "classes")
    matches = components(candidate_links(classes.select("set_key", "rep", "n", "minima", "sig"), workspace, percent), workspace, "matches")
    members = workspace.write(matches.join(classes.select("rep", "n"), matches["node"] == F.col("rep")).select("rep", "n", "component"), "members")
    confirmed = components(confirm(docs, members, workspace, percent, words, doc_id, text), workspace, "links")
    # classes whose members need another label than their own id; those of large classes are dealt out by salt
    labels = classes.select("set_key", "rep", "k").join(confirmed, F.col("rep") == F.col("node"), "left").select("set_key", F.coalesce("component", "rep").alias("label"), "rep", "k").where("k > 1 or label <> rep")
    labels = workspace.write(labels, "labels")
    dealt = labels.withColumn("_salt", F.explode(F.when(F.col("k") > 4 * salts, F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(-1))))).select("set_key", "label", "_salt")
    large = labels.where(F.col("k") > 4 * salts).select("set_key").withColumn("_large", F.lit(True))
    own = sketches.select("doc_id", "n_shingles", "set_key").join(large, "set_key", "left")
    own = own.withColumn("_salt", F.when(F.col("_large"), F.pmod(F.xxhash64("doc_id"), F.lit(salts)).cast("int")).otherwise(F.lit(-1)))
    out = own.join(dealt, ["set_key", "_salt"], "left").withColumn("component_id", F.coalesce("label", "doc_id"))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)).alias("kept"))
