"""Greedy word-piece token counts by a linear longest-match automaton.

Words are `[^\\x20\\x09-\\x0D]+`. A word is read with a word mark before it; its first token is the longest piece that starts
with the mark, each further token the longest piece without mark. The automaton is the vocabulary's trie with, for each
node, a failure link and the number of tokens popped on taking it, so each byte of a word is read once and no piece is built.
A word for which some longest match fails is one unknown token, as word-piece tokenisers have it. Counts are made once
per distinct word of a batch.

Defined cases: a null or empty text has 0 words and tokens; repeated rows count alike; existing result columns are replaced.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as tk
from .vocab import PieceVocab, load_pieces


class LongestMatch:
    def __init__(self, vocab: PieceVocab):
        known = [i for i, k in enumerate(vocab.kinds) if k == "piece"]
        self.trie = t = tk.Trie([vocab.pieces[i] for i in known], known)
        self.link = np.full(t.size, -1, dtype=np.int32)
        self.popped = np.zeros(t.size, dtype=np.int32)
        child = [dict(zip(np.flatnonzero(t.child[n] >= 0).tolist(), t.child[n][t.child[n] >= 0].tolist(), strict=True)) if n < t.inner else {} for n in range(t.size)]
        level = [0]
        while level:  # breadth first: links lead to shorter strings
            below = []
            for u in level:
                for b, v in child[u].items():
                    below.append(v)
                    if t.piece[v] >= 0:
                        self.link[v], self.popped[v] = 0, 1
                        continue
                    z, n = int(self.link[u]), int(self.popped[u])
                    while z >= 0 and b not in child[z]:
                        n += int(self.popped[z])
                        z = int(self.link[z])
                    if z >= 0:
                        self.link[v], self.popped[v] = child[z][b], n
            level = below

    def count(self, buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(tokens of each word, whether it is unknown); words side by side, one byte of each at a time."""
        t, n = self.trie, len(offsets) - 1
        size = np.diff(offsets)
        order = np.argsort(-size, kind="stable")
        node, tokens, lost = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, dtype=bool)
        live = order
        step = 0
        while True:
            live = live[: int(np.searchsorted(-size[live], -step, side="left"))]  # words that are longer than `step`
            at = live[~lost[live]]
            if not len(at):
                break
            byte = buf[offsets[at] + step]
            while len(at):
                s = node[at]
                nxt = np.where(s < t.inner, t.child[np.minimum(s, t.inner - 1), byte], -1)
                hit = nxt >= 0
                node[at[hit]] = nxt[hit]
                at, byte, s = at[~hit], byte[~hit], s[~hit]
                tokens[at] += self.popped[s]
                node[at] = self.link[s]
                gone = node[at] < 0
                lost[at[gone]] = True
                at, byte = at[~gone], byte[~gone]
            step += 1
        at = np.flatnonzero(~lost & (node > 0))
        while len(at):
            s = node[at]
            tokens[at] += self.popped[s]
            node[at] = self.link[s]
            lost[at[node[at] < 0]] = True
            at = at[node[at] > 0]
        return np.where(lost, 1, tokens), lost


@functools.lru_cache(maxsize=2)
def automaton(vocab: PieceVocab) -> LongestMatch:
    return LongestMatch(vocab)


def count_texts(match: LongestMatch, texts: pd.Series) -> pd.DataFrame:
    buf, offsets = tk.text_buffer(texts)
    start, length, doc = tk.split_words(buf, offsets)
    codes, rep = tk.distinct(tk.hash_spans(buf, start, length, tk.byte_values(False)))
    b, o = tk.gather_spans(buf, start[rep], length[rep], prefix=0x20)
    tokens, lost = np.zeros(len(rep), np.int64), np.zeros(len(rep), dtype=bool)
    for lo, hi in tk.word_blocks(o):
        tokens[lo:hi], lost[lo:hi] = match.count(b[o[lo] : o[hi]], o[lo : hi + 1] - o[lo])
    n = len(texts)
    total = np.zeros(n, np.int64)
    np.add.at(total, doc, tokens[codes])
    return pd.DataFrame({"n_words": np.bincount(doc, minlength=n), "n_tokens": total, "n_unknown": np.bincount(doc[lost[codes]], minlength=n)})


def count_tokens(docs: DataFrame, text: str = "text", vocab: PieceVocab | None = None) -> DataFrame:
    """Add n_words, n_tokens and n_unknown."""
    sent = docs.sparkSession.sparkContext.broadcast(vocab or load_pieces())

    @F.pandas_udf("n_words long, n_tokens long, n_unknown long")
    def udf(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        match = automaton(sent.value)
        for texts in batches:
            yield count_texts(match, texts)

    out = docs.withColumn("_n", udf(F.col(text).cast("string")))
    for c in ("n_words", "n_tokens", "n_unknown"):
        out = out.withColumn(c, F.col(f"_n.{c}"))
    return out.drop("_n")
