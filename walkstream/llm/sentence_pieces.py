"""SentencePiece encoding and decoding by max-plus algebra.

A text is encoded into the pieces of the best total score (unigram Viterbi over the vocabulary's own scores). No piece holds
a blank after another character, so a text falls apart before each run of blanks; parts are solved once per distinct part
of a batch. Texts of more than `chunk_bytes` bytes are cut into chunks at fixed byte positions. The state at a cut is the
overhang: how many bytes the piece across the cut reaches past it. Each chunk yields its matrix of best scores from entry
to exit overhang; matrices are combined associatively by a prefix scan in blocks of chunks, which gives the best score of
every overhang at every cut. From these each chunk maps its exit overhangs to the entry overhangs of the encoding with the
rule for ties below; the maps, composed from the end, fix the overhang at every cut, and each chunk is then traced back by
itself. All scores are integers, and the rule for ties is one of the whole text, so any `chunk_bytes` gives the same ids.

Scores below -(vocabulary size) are raised to it; a byte without a piece costs -(vocabulary size) - 10 and becomes its byte
piece, so every text can be encoded and `decode` returns it exactly. Ties: from the end, the longest last piece. A null text
encodes to null, an empty one to no pieces; an empty table gives an empty result. Repeated rows are encoded alike. Columns
named like the results are replaced.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as tk
from .common import Workspace
from .vocab import PieceVocab, load_pieces, piece_trie

BLANK = 0x20
NEVER = -(1 << 50)
CROSSING = -2
#: Matrices are combined by blocks of so many chunks, so that a task holds no more of a text.
SCAN_BLOCK = 256
#: Characters of texts that are encoded at once.
SLICE = 1 << 18


class Encoder:
    def __init__(self, vocab: PieceVocab):
        n = len(vocab.pieces)
        self.vocab = vocab
        known = [i for i, k in enumerate(vocab.kinds) if k == "piece"]
        self.trie = piece_trie(vocab)
        self.score = np.maximum(np.array(vocab.scores, dtype=np.int64), -n)
        self.byte = np.array(vocab.byte_ids, dtype=np.int32)
        self.lone = -n - 10
        self.states = max(self.trie.depth, 1)
        if self.states > 62:
            raise ValueError("pieces of more than 62 bytes don't fit the keys of `solve`")
        if (self.byte < 0).any() or any(b" " in vocab.pieces[i].lstrip(b" ") for i in known):
            raise ValueError("the vocabulary needs byte pieces, and blanks only at the start of pieces")
        size = np.array([len(p) for p in vocab.pieces], dtype=np.int64)
        self.flat = np.frombuffer(b"".join(vocab.pieces), dtype=np.uint8)
        self.piece_start = np.concatenate([[0], np.cumsum(size)[:-1]])
        self.piece_size = size

    def solve(self, buf: np.ndarray, offsets: np.ndarray, stop: int | None = None, entry: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(best score, last piece) at each node: byte position + index of the part. Arcs start before `stop` in a part.

        entry (one part only): best scores of the first nodes by a piece from before the part, which is longer than any
        from within it; its last piece is CROSSING.
        """
        n = len(offsets) - 1
        part = np.repeat(np.arange(n), np.diff(offsets))
        pos, length, piece = self.trie.matches(buf, offsets[1:][part])
        lone = np.arange(len(buf), dtype=np.int64)
        value = np.concatenate([self.score[piece], np.full(len(buf), self.lone)])
        pos, length, piece = np.concatenate([pos, lone]), np.concatenate([length, np.ones(len(buf), np.int32)]), np.concatenate([piece, self.byte[buf]])
        rank = pos + length - offsets[part[pos]]
        keep = np.flatnonzero(pos - offsets[part[pos]] < stop) if stop is not None else slice(None)
        order = np.argsort(rank[keep], kind="stable")
        order = keep[order] if stop is not None else order
        src = (pos + part[pos])[order]
        dst = src + length[order]
        value, piece, length, rank = value[order], piece[order], length[order].astype(np.int64), rank[order]
        best = np.full(len(buf) + n, NEVER, dtype=np.int64)
        last = np.full(len(best), -1, dtype=np.int32)
        best[offsets[:-1] + np.arange(n)] = 0
        key = np.full(len(best), NEVER * 64, dtype=np.int64)
        if entry is not None:
            best[: len(entry)] = entry
            key[: len(entry)] = np.where(entry > NEVER, entry * 64 + 63, NEVER * 64)
            last[: len(entry)] = np.where(entry > NEVER, CROSSING, -1)
        bounds = np.searchsorted(rank, np.arange(1, (int(rank[-1]) if len(rank) else 0) + 2))
        for lo, hi in zip(bounds[:-1], bounds[1:], strict=True):
            d = dst[lo:hi]
            got = (best[src[lo:hi]] + value[lo:hi]) * 64 + length[lo:hi]  # equal scores: the longer piece
            np.maximum.at(key, d, got)
            won = got == key[d]
            last[d[won]] = piece[lo:hi][won]
            best[d] = key[d] >> 6  # a score below NEVER / 2 is unreachable
        best[best < NEVER // 2] = NEVER
        return best, last

    def trace(self, offsets: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(pieces, offsets by part) from the last pieces."""
        n = len(offsets) - 1
        first = offsets[:-1] + np.arange(n)
        node = offsets[1:] + np.arange(n)
        live = np.flatnonzero(node > first)
        parts, ids, steps, step = [], [], [], 0
        while len(live):
            p = last[node[live]]
            parts.append(live)
            ids.append(p)
            steps.append(np.full(len(live), -step))
            node[live] -= self.piece_size[p]
            live = live[node[live] > first[live]]
            step += 1
        if not parts:
            return np.zeros(0, np.int32), np.zeros(n + 1, np.int64)
        part, piece = np.concatenate(parts), np.concatenate(ids)
        order = np.lexsort((np.concatenate(steps), part))
        return piece[order], np.concatenate([[0], np.cumsum(np.bincount(part, minlength=n))])

    def encode_buffer(self, buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(pieces, offsets by text) of texts in the vocabulary's form, blanks for word marks."""
        n = len(offsets) - 1
        if not len(buf):
            return np.zeros(0, np.int32), np.zeros(n + 1, np.int64)
        cut = np.zeros(len(buf) + 1, dtype=bool)
        cut[1:-1] = (buf[1:] == BLANK) & (buf[:-1] != BLANK)
        cut[offsets] = True
        cut = np.flatnonzero(cut)
        start, length = cut[:-1], np.diff(cut)
        codes, rep = tk.distinct(tk.hash_spans(buf, start, length, tk.byte_values(False)))
        b, o = tk.gather_spans(buf, start[rep], length[rep])
        pieces, ends = [], [np.zeros(1, np.int64)]
        for lo, hi in tk.word_blocks(o, 1 << 16):
            own = o[lo : hi + 1] - o[lo]
            got, end = self.trace(own, self.solve(b[o[lo] : o[hi]], own)[1])
            pieces.append(got)
            ends.append(end[1:] + ends[-1][-1])
        flat, end = np.concatenate(pieces), np.concatenate(ends)
        size = np.diff(end)
        out, at = tk.gather_spans(flat, end[:-1][codes], size[codes])
        text_of = np.searchsorted(start, offsets)  # the first part of each text
        return out, at[text_of]

    def transfer(self, buf: np.ndarray, size: int) -> np.ndarray:
        """Best scores from each entry overhang to each exit overhang; buf: the chunk of `size` bytes and what may follow it."""
        s = self.states
        out = np.full((s, s), NEVER, dtype=np.int64)
        inner = np.flatnonzero((buf[1:size] == BLANK) & (buf[: size - 1] != BLANK)) + 1
        starts = range(min(s, size + 1))
        if not len(inner):
            for i in starts:
                best, _ = self.solve(buf[i:], np.array([0, len(buf) - i]), stop=size - i)
                exits = best[size - i : size - i + s]
                out[i, : len(exits)] = exits
            return out
        a, z = int(inner[0]), int(inner[-1])
        entry = np.full(s, NEVER, dtype=np.int64)
        own = [i for i in starts if i <= a]
        b, o = tk.gather_spans(buf, np.array(own), a - np.array(own))
        entry[own] = self.solve(b, o)[0][o[1:] + np.arange(len(own))]
        cuts = np.append(inner, z)
        start, length = cuts[:-1], np.diff(cuts)
        middle = 0
        if z > a:
            start, length = inner[:-1], np.diff(inner)
            codes, rep = tk.distinct(tk.hash_spans(buf, start, length, tk.byte_values(False)))
            b, o = tk.gather_spans(buf, start[rep], length[rep])
            middle = int(self.solve(b, o)[0][o[1:] + np.arange(len(rep))][codes].sum())
        leave = np.full(s, NEVER, dtype=np.int64)
        best, _ = self.solve(buf[z:], np.array([0, len(buf) - z]), stop=size - z)
        leave[: len(best) - (size - z)] = best[size - z : size - z + s]
        ok = (entry[:, None] > NEVER) & (leave[None, :] > NEVER)
        return np.where(ok, entry[:, None] + middle + leave[None, :], NEVER)

    def entry_of(self, buf: np.ndarray, size: int, entry: np.ndarray) -> np.ndarray:
        """For each exit overhang the entry overhang of the best way to it, ties as for the whole text; -1 if there is none.
        buf: the chunk of `size` bytes and what may follow it; entry: best scores of the entry overhangs."""
        s = self.states
        inner = np.flatnonzero((buf[1:size] == BLANK) & (buf[: size - 1] != BLANK)) + 1
        if len(inner):  # every way passes the first inner part's start
            a = int(inner[0])
            last = self.solve(buf[:a], np.array([0, a]), entry=entry[: a + 1])[1]
            return np.full(s, self._entry(last, a), dtype=np.int64)
        last = self.solve(buf, np.array([0, len(buf)]), stop=size, entry=entry[: len(buf) + 1])[1]
        return np.array([self._entry(last, size + j) if size + j <= len(buf) else -1 for j in range(s)], dtype=np.int64)

    def _entry(self, last: np.ndarray, node: int) -> int:
        while last[node] >= 0:
            node -= int(self.piece_size[last[node]])
        return node if last[node] == CROSSING else -1

    def decodes_to(self, ids: np.ndarray, offsets: np.ndarray, buf: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """For each text, whether its ids decode to its bytes."""
        back, at = self.decode_ids(ids, offsets)
        if len(back) == len(buf) and (at == ends).all() and (back == buf).all():
            return np.ones(len(ends) - 1, dtype=bool)
        return np.array([back[at[i] : at[i + 1]].tobytes() == buf[ends[i] : ends[i + 1]].tobytes() for i in range(len(ends) - 1)])

    def decode_ids(self, ids: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        size = self.piece_size[ids]
        ends = np.concatenate([[0], np.cumsum(size)])
        buf, _ = tk.gather_spans(self.flat, self.piece_start[ids], size)
        return buf, ends[offsets]


def combine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Max-plus product of two transfer matrices; associative."""
    return np.maximum((a[:, :, None] + b[None, :, :]).max(axis=1), NEVER)


def prefix_scan(mats: list[np.ndarray]) -> list[np.ndarray]:
    """Products of the first 1, 2, ... matrices, by combining neighbours and scanning the half as many products."""
    if len(mats) < 2:
        return list(mats)
    pairs = prefix_scan([combine(mats[i], mats[i + 1]) for i in range(0, len(mats) - 1, 2)])
    out = [mats[0]]
    for k in range(1, len(mats)):
        out.append(pairs[k // 2] if k % 2 else combine(pairs[k // 2 - 1], mats[k]))
    return out


def entries(mats: list[np.ndarray], start: np.ndarray) -> list[np.ndarray]:
    """Best scores of the overhangs at the start of each chunk, from those at the first one's: prefix products, applied to it."""
    ahead = prefix_scan(mats[:-1])
    return [start, *[np.maximum((start[:, None] + m).max(axis=0), NEVER) for m in ahead]]


def first_entry(states: int) -> np.ndarray:
    """A text starts without an overhang."""
    return np.where(np.arange(states) == 0, 0, NEVER)


def boundary_states(enc: Encoder, chunks: list[tuple[np.ndarray, int]]) -> tuple[list[int], int]:
    """(overhang at the start of each chunk and at the end, best total score) of a text's chunks, all in one place."""
    mats = [enc.transfer(*c) for c in chunks]
    scores = entries(mats, first_entry(enc.states))
    maps = [enc.entry_of(b, n, e) for (b, n), e in zip(chunks, scores, strict=True)]
    return follow(maps), int((scores[-1] + mats[-1][:, 0]).max())


def follow(maps: list[np.ndarray]) -> list[int]:
    """Overhangs at all cuts, from the end, where there is none."""
    states = [0]
    for m in reversed(maps):
        states.append(int(m[states[-1]]))
    return states[::-1]


@tk.keep_last
def encoder(vocab: PieceVocab) -> Encoder:
    return Encoder(vocab)


def _marked(texts: pd.Series) -> tuple[np.ndarray, np.ndarray]:
    """Texts with a blank before each that isn't empty."""
    buf, offsets = tk.text_buffer(texts)
    size = np.diff(offsets)
    full = np.flatnonzero(size)
    b, o = tk.gather_spans(buf, offsets[:-1][full], size[full], prefix=BLANK)
    return b, np.concatenate([[0], np.cumsum(size + (size > 0))])


def _binary(data: np.ndarray, offsets: np.ndarray, width: int, null: np.ndarray | None = None) -> pd.Series:
    raw = np.ascontiguousarray(data).tobytes()
    out = [raw[a * width : b * width] for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
    if null is not None:
        for i in np.flatnonzero(null):
            out[i] = None
    return pd.Series(out, dtype=object)


def encode(docs: DataFrame, text: str = "text", vocab: PieceVocab | None = None, chunk_bytes: int = 1 << 16, verify: bool = False) -> DataFrame:
    """Add `piece_ids`: the ids as 32-bit little-endian numbers in one binary value (`ids_array` makes an array of it).

    verify: also add `round_trip`, whether the ids decode to the text; made where the ids are, without another pass.
    """
    spark, vocab = docs.sparkSession, vocab or load_pieces()
    sent = spark.sparkContext.broadcast(vocab)
    chunk_bytes = max(chunk_bytes, max(map(len, vocab.pieces)))  # no piece spans a chunk

    @F.pandas_udf("ids binary, ok boolean")
    def whole(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        enc = encoder(sent.value)
        for texts in batches:
            parts = []
            for rows in tk.slices(texts.str.len().fillna(0), SLICE):
                own = texts.iloc[rows]
                buf, ends = _marked(own)
                ids, offsets = enc.encode_buffer(buf, ends)
                ok = enc.decodes_to(ids, offsets, buf, ends) if verify else np.ones(len(own), dtype=bool)
                parts.append(pd.DataFrame({"ids": _binary(ids.astype("<i4"), offsets, 4, own.isna().to_numpy()), "ok": ok}))
            tk.give_back()
            yield pd.concat(parts, ignore_index=True) if parts else pd.DataFrame({"ids": pd.Series([], dtype=object), "ok": pd.Series([], dtype=bool)})
        tk.forget()  # else every worker that waits for a task holds an encoder

    docs = docs.drop("piece_ids", *["round_trip"] * verify)
    giant = F.coalesce(F.octet_length(text) > chunk_bytes, F.lit(False))
    small = docs.where(~giant).withColumn("_e", whole(F.col(text))).withColumn("piece_ids", F.col("_e.ids"))
    small = (small.withColumn("round_trip", F.col("_e.ok")) if verify else small).drop("_e")
    found = docs.where(giant).withColumn("_text_key", F.sha2(F.col(text), 256))
    solved = _encode_giants(found.select("_text_key", F.col(text).alias("_text")), sent, chunk_bytes, max([1, *(len(p) for p, k in zip(vocab.pieces, vocab.kinds, strict=True) if k == "piece")]))
    if verify:
        solved = decode(solved, vocab, to="_back").withColumn("_back", F.sha2("_back", 256)).withColumn("round_trip", F.col("_back") == F.col("_text_key")).drop("_back")
    large = found.join(solved, "_text_key").drop("_text_key")
    return small.unionByName(large.select(*small.columns))


def _encode_giants(found: DataFrame, sent, chunk_bytes: int, states: int) -> DataFrame:
    """_text_key, piece_ids of the distinct giant texts. states: overhangs that a cut can have; only the workers that solve
    chunks load the encoder."""
    texts = found.groupBy("_text_key").agg(F.first("_text").alias("_text"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ahead = states - 1
        for batch in batches:
            for key, text in zip(batch.column(0), batch.column(1), strict=True):
                raw = b" " + text.as_buffer().to_pybytes()
                last = (len(raw) + chunk_bytes - 1) // chunk_bytes - 1
                for k in range(last + 1):
                    at = k * chunk_bytes
                    yield pa.RecordBatch.from_pydict({"_text_key": [key.as_py()], "part": [k], "size": [min(chunk_bytes, len(raw) - at)], "raw": [raw[at : at + chunk_bytes + ahead]]}, schema=cut_schema)

    cut_schema = pa.schema([("_text_key", pa.string()), ("part", pa.int64()), ("size", pa.int64()), ("raw", pa.binary())])
    chunks = texts.mapInArrow(cut, "_text_key string, part long, size long, raw binary").repartition("_text_key", "part")

    kept = Workspace(found.sparkSession, "pieces")

    def matrices(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        enc = encoder(sent.value)
        for pdf in batches:
            tk.give_back()
            yield pd.DataFrame({"_text_key": pdf["_text_key"], "part": pdf["part"], "block": pdf["part"] // SCAN_BLOCK, "matrix": [enc.transfer(np.frombuffer(r, dtype=np.uint8), n).tobytes() for r, n in zip(pdf["raw"], pdf["size"], strict=True)]})
        tk.forget()

    def unpack(pdf: pd.DataFrame) -> list[np.ndarray]:
        return [np.frombuffer(m, dtype=np.int64).reshape(states, states) for m in pdf["matrix"]]

    def product(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("part")
        return pd.DataFrame({"_text_key": pdf["_text_key"].iloc[:1], "block": pdf["block"].iloc[:1], "matrix": [functools.reduce(combine, unpack(pdf)).tobytes()]})

    def heads(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("block")
        enter = entries(unpack(pdf), first_entry(states))
        return pd.DataFrame({"_text_key": pdf["_text_key"], "block": pdf["block"], "head": [e.tobytes() for e in enter]})

    def inside(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("part")
        enter = entries(unpack(pdf), np.frombuffer(pdf["head"].iloc[0], dtype=np.int64))
        return pd.DataFrame({"_text_key": pdf["_text_key"], "part": pdf["part"], "entry": [e.tobytes() for e in enter]})

    @F.pandas_udf("array<long>")
    def maps(batches: Iterator[tuple[pd.Series, pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        enc = encoder(sent.value)
        for raw, size, entry in batches:
            yield pd.Series([enc.entry_of(np.frombuffer(r, dtype=np.uint8), n, np.frombuffer(e, dtype=np.int64)) for r, n, e in zip(raw, size, entry, strict=True)], dtype=object)
        tk.forget()

    def chain(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("part")
        at = follow(list(pdf["map"]))
        return pd.DataFrame({"_text_key": pdf["_text_key"].to_numpy(), "part": pdf["part"].to_numpy(), "enter": at[:-1], "leave": at[1:]})

    # a task holds the matrices of SCAN_BLOCK chunks, or one for each block, or a few numbers for each chunk of a text
    mats = kept.write(chunks.mapInPandas(matrices, "_text_key string, part long, block long, matrix binary"), "matrices")
    starts = mats.groupBy("_text_key", "block").applyInPandas(product, "_text_key string, block long, matrix binary").groupBy("_text_key").applyInPandas(heads, "_text_key string, block long, head binary")
    scores = mats.join(starts, ["_text_key", "block"]).groupBy("_text_key", "block").applyInPandas(inside, "_text_key string, part long, entry binary")
    mapped = chunks.join(scores, ["_text_key", "part"]).select("_text_key", "part", maps("raw", "size", "entry").alias("map"))
    cuts = mapped.groupBy("_text_key").applyInPandas(chain, "_text_key string, part long, enter long, leave long")

    @F.pandas_udf("binary")
    def solve(batches: Iterator[tuple[pd.Series, pd.Series, pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        enc = encoder(sent.value)
        for raw, size, enter, leave in batches:
            out = []
            for r, n, i, j in zip(raw, size, enter, leave, strict=True):
                own = np.frombuffer(r, dtype=np.uint8)[i : n + j]
                out.append(enc.encode_buffer(own, np.array([0, len(own)]))[0].astype("<i4").tobytes())
            tk.give_back()
            yield pd.Series(out, dtype=object)
        tk.forget()

    traced = chunks.join(cuts, ["_text_key", "part"]).select("_text_key", "part", F.hex(solve("raw", "size", "enter", "leave")).alias("ids"))
    joined = traced.groupBy("_text_key").agg(F.sort_array(F.collect_list(F.struct("part", "ids"))).alias("parts"))  # one text's pieces
    return joined.select("_text_key", F.unhex(F.array_join(F.col("parts.ids"), "")).alias("piece_ids"))


def decode(df: DataFrame, vocab: PieceVocab | None = None, ids: str = "piece_ids", to: str = "decoded") -> DataFrame:
    """Add the text of the ids; null for null."""
    sent = df.sparkSession.sparkContext.broadcast(vocab or load_pieces())

    @F.pandas_udf("string")
    def udf(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        enc = encoder(sent.value)
        for batch in batches:
            out = []
            for b in batch:
                if b is None:
                    out.append(None)
                    continue
                own = np.frombuffer(b, dtype="<i4")
                out.append(enc.decode_ids(own, np.array([0, len(own)]))[0].tobytes()[1:].decode("utf-8", "replace"))
            yield pd.Series(out, dtype=object)
        tk.forget()

    return df.withColumn(to, udf(F.col(ids)))


def ids_array(df: DataFrame, ids: str = "piece_ids", to: str = "ids") -> DataFrame:
    @F.pandas_udf("array<int>")
    def udf(batch: pd.Series) -> pd.Series:
        return batch.map(lambda b: None if b is None else np.frombuffer(b, dtype="<i4"))

    return df.withColumn(to, udf(F.col(ids)))
