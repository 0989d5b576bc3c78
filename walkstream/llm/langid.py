"""Language identification by segmentation-marginalised unigrams.

Each language has a probability for every piece of a fixed public vocabulary. The likelihood of a word is the sum over all
of its segmentations into pieces, by a forward pass; words are independent, since no piece spans a blank. The piece
probabilities are fitted by expectation-maximisation: each round sums expected piece counts over words of labelled
texts in the executors; the driver gets a table of vocabulary x languages, never texts.

The fit may use a bounded sample of distinct labelled texts, taken by a hash of the text: of each language its part of
`fit_documents`, or `fit_least` if that is more (both in the mean), and all if it has no more than `fit_least`. Prediction
covers every whole text. score is the posterior of the language predicted, with equal priors, tempered by `temper` characters.

Defined cases: a null text, or one without a letter, is `und` with score 0; without labelled rows every text is `und`; ties
go to the smaller language name; repeated rows are predicted alike. Existing columns of the result names are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as tk
from .vocab import PieceVocab, load_pieces
from .vocab import piece_trie as _trie

#: Texts are taken in slices of about so many characters, words in blocks of so many bytes: what a worker holds at once.
SLICE, BLOCK = 1 << 21, 1 << 17
#: Probability of any single byte that no piece covers.
BYTE_FLOOR = 1e-9


@dataclass(frozen=True)
class LanguageModel:
    langs: tuple[str, ...]
    vocab: PieceVocab
    log_probs: np.ndarray  # pieces x languages


def _lattice(trie: tk.Trie, buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, piece or -1 for a lone byte, end within the word) of all arcs, by end within the word."""
    word = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    end = offsets[1:][word]
    pos, length, piece = trie.matches(buf, end)
    lone = np.arange(len(buf), dtype=np.int64)
    pos, length, piece = np.concatenate([pos, lone]), np.concatenate([length, np.ones(len(buf), np.int32)]), np.concatenate([piece, np.full(len(buf), -1, np.int32)])
    rank = pos + length - offsets[word[pos]]
    order = np.argsort(rank, kind="stable")
    return pos[order], (pos + length)[order], piece[order], rank[order]


def _forward(arcs, probs: np.ndarray, offsets: np.ndarray, n_langs: int) -> tuple[np.ndarray, np.ndarray]:
    """Scaled forward sums at node (byte position + index of the word) and the logarithm taken out at each node.

    Each node keeps its own logarithm, so words of any length stay in range.
    """
    start, end, piece, rank = arcs
    n = len(offsets) - 1
    word = np.repeat(np.arange(n), np.diff(offsets))
    alpha = np.zeros((int(offsets[-1]) + n, n_langs))
    taken = np.zeros(len(alpha))
    first = offsets[:-1] + np.arange(n)
    alpha[first] = 1.0
    src = start + word[start]
    dst = end + word[start]
    bounds = np.searchsorted(rank, np.arange(1, (int(rank[-1]) if len(rank) else 0) + 2))
    for lo, hi in zip(bounds[:-1], bounds[1:], strict=True):
        s, d = src[lo:hi], dst[lo:hi]
        nodes, inv = np.unique(d, return_inverse=True)
        top = np.full(len(nodes), -np.inf)
        np.maximum.at(top, inv, taken[s])
        part = alpha[s] * probs[piece[lo:hi]] * np.exp(taken[s] - top[inv])[:, None]
        for k in range(n_langs):
            alpha[nodes, k] = np.bincount(inv, weights=part[:, k], minlength=len(nodes))
        scale = alpha[nodes].max(axis=1)
        alpha[nodes] /= scale[:, None]
        taken[nodes] = top + np.log(scale)
    return alpha, taken


def _with_floor(log_probs: np.ndarray) -> np.ndarray:
    return np.vstack([np.exp(log_probs), np.full((1, log_probs.shape[1]), BYTE_FLOOR)])


def _short_scores(trie: tk.Trie, probs: np.ndarray, buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Log-likelihoods of words of at most SHORT bytes, longest first: plain forward sums stay in range there.

    Node (r, w), r bytes into word w, lies at base[r] + w: the words that reach r are the first ones.
    """
    n, n_langs = len(offsets) - 1, probs.shape[1]
    size = np.diff(offsets)
    word = np.repeat(np.arange(n), size)
    pos, length, piece = trie.matches(buf, offsets[1:][word])
    at = np.arange(len(buf)) - offsets[:-1][word]
    rank = np.concatenate([at[pos] + length, at + 1]).astype(np.int16)
    order = np.argsort(rank, kind="stable")
    reach = np.searchsorted(-size, -np.arange(int(size[0]) + 1), side="right")
    base = np.concatenate([[0], np.cumsum(reach)])
    owner = np.concatenate([word[pos], word])[order]
    src = (base[np.concatenate([at[pos], at])] + np.concatenate([word[pos], word]))[order]
    piece = np.concatenate([piece, np.full(len(buf), -1, np.int32)])[order]
    alpha = np.zeros((n_langs, int(base[-1])))
    alpha[:, :n] = 1.0
    table = np.ascontiguousarray(probs.T)
    bounds = np.searchsorted(rank[order], np.arange(1, len(reach) + 1))
    for r, (lo, hi) in enumerate(zip(bounds[:-1], bounds[1:], strict=True), start=1):
        s, p, w = src[lo:hi], piece[lo:hi], owner[lo:hi]
        for k in range(n_langs):
            alpha[k, base[r] : base[r] + reach[r]] = np.bincount(w, weights=alpha[k][s] * table[k][p], minlength=int(reach[r]))
    return np.log(alpha[:, base[size] + np.arange(n)]).T


#: Words up to so many bytes need no scaling: BYTE_FLOOR to this power is still a normal number.
SHORT = 32


def word_scores(trie: tk.Trie, log_probs: np.ndarray, buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Log-likelihood of each word (words x languages)."""
    n_langs = log_probs.shape[1]
    size = np.diff(offsets)
    out = np.empty((len(size), n_langs))
    probs = _with_floor(log_probs)
    order = np.argsort(-size, kind="stable")
    n_long = int((size > SHORT).sum())
    for some, short in ((order[:n_long], False), (order[n_long:], True)):
        own, ends = tk.gather_spans(buf, offsets[:-1][some], size[some])
        for lo, hi in tk.word_blocks(ends, BLOCK):
            b, o = own[ends[lo] : ends[hi]], ends[lo : hi + 1] - ends[lo]
            if short:
                out[some[lo:hi]] = _short_scores(trie, probs, b, o)
                continue
            alpha, taken = _forward(_lattice(trie, b, o), probs, o, n_langs)
            last = o[1:] + np.arange(hi - lo)
            out[some[lo:hi]] = np.log(np.maximum(alpha[last], 1e-300)) + taken[last][:, None]
    return out


def expected_counts(trie: tk.Trie, log_probs: np.ndarray, buf: np.ndarray, offsets: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Expected uses of each piece (pieces x languages): forward and backward sums; weight: words x languages."""
    n_langs = log_probs.shape[1]
    probs = _with_floor(log_probs)
    total = np.zeros((len(probs), n_langs))
    for lo, hi in tk.word_blocks(offsets, BLOCK // 2):
        b, o = buf[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        start, end, piece, rank = arcs = _lattice(trie, b, o)
        alpha, taken = _forward(arcs, probs, o, n_langs)
        word = np.repeat(np.arange(hi - lo), np.diff(o))
        src, dst, owner = start + word[start], end + word[start], word[start]
        last = o[1:] + np.arange(hi - lo)
        beta = np.zeros_like(alpha)  # share of the word's mass that passes the node
        beta[last] = weight[lo:hi]
        bounds = np.searchsorted(rank, np.arange(1, (int(rank[-1]) if len(rank) else 0) + 2))
        for r in range(len(bounds) - 2, -1, -1):
            x, y = bounds[r], bounds[r + 1]
            s, d, p = src[x:y], dst[x:y], piece[x:y]
            flow = alpha[s] * probs[p] * np.exp(taken[s] - taken[d])[:, None] / np.maximum(alpha[d], 1e-300) * beta[d]
            np.add.at(beta, s, flow)
            for k in range(n_langs):
                total[:, k] += np.bincount(p % len(probs), weights=flow[:, k], minlength=len(probs))
        del owner
    return total[:-1]


def _batch_words(text: pd.Series) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(bytes, offsets of distinct words with the word mark, word code, text of each word)."""
    buf, offsets = tk.text_buffer(text)
    start, length, doc = tk.split_words(buf, offsets)
    codes, rep = tk.distinct(tk.hash_spans(buf, start, length, tk.byte_values(False)))
    b, o = tk.gather_spans(buf, start[rep], length[rep], prefix=0x20)
    return b, o, codes, doc


def fit_sample(labelled: DataFrame, text: str = "text", lang: str = "lang", fit_documents: int = 4_000, fit_least: int = 1_000) -> tuple[tuple[str, ...], DataFrame]:
    """(languages, distinct labelled texts of the fit as _text, _lang)."""
    rows = labelled.select(F.col(text).alias("_text"), F.col(lang).alias("_lang")).where("_lang is not null and _text is not null").withColumn("_h", F.xxhash64("_text"))
    # hashes only: copies of a text count once, and texts stay where they are
    counts = rows.select("_lang", "_h").distinct().groupBy("_lang").count().limit(1001).collect()
    if len(counts) > 1000:
        raise ValueError("more than 1,000 languages")
    n = {r["_lang"]: r["count"] for r in counts}
    every = sum(n.values())
    share = {x: min(1.0, max(fit_documents / every, fit_least / c)) for x, c in n.items()}
    limits = labelled.sparkSession.createDataFrame([(x, int(v * (1 << 30))) for x, v in share.items()], "_lang string, _limit long")  # a row for each language
    chosen = rows.join(F.broadcast(limits), "_lang").where(F.pmod("_h", F.lit(1 << 30)) < F.col("_limit"))
    parts = 2 * labelled.sparkSession.sparkContext.defaultParallelism
    return tuple(sorted(n)), chosen.select("_text", "_lang").distinct().repartition(parts, F.xxhash64("_text"))


def train(labelled: DataFrame, vocab: PieceVocab | None = None, text: str = "text", lang: str = "lang", rounds: int = 2, fit_documents: int = 4_000, fit_least: int = 1_000) -> LanguageModel:
    """Fit piece probabilities on rows with a non-null label. Languages: a bounded dimension (at most 1,000)."""
    vocab = vocab or load_pieces()
    langs, sample = fit_sample(labelled, text, lang, fit_documents, fit_least)
    n_pieces = len(vocab.pieces)
    log_probs = np.full((n_pieces, max(1, len(langs))), -np.log(n_pieces))
    if not langs:
        return LanguageModel((), vocab, log_probs)
    index = {x: i for i, x in enumerate(langs)}
    sc = labelled.sparkSession.sparkContext
    vocab_sent = sc.broadcast(vocab)
    for _ in range(rounds):
        sent = sc.broadcast(log_probs)

        def partial(batches: Iterator[pd.DataFrame], sent=sent) -> Iterator[pd.DataFrame]:
            trie = _trie(vocab_sent.value)
            total = np.zeros((n_pieces, len(langs)))
            for pdf in (batch.iloc[rows] for batch in batches for rows in tk.slices(batch["_text"].str.len(), SLICE)):
                b, o, codes, doc = _batch_words(pdf["_text"])
                which = pdf["_lang"].map(index).to_numpy(dtype=np.int64)
                weight = np.zeros((len(o) - 1, len(langs)))
                np.add.at(weight, (codes, which[doc]), 1.0)
                total += expected_counts(trie, sent.value, b, o, weight)
                tk.give_back()
            p, k = np.nonzero(total)
            yield pd.DataFrame({"p": p, "k": k, "v": total[p, k]})

        table = np.full((n_pieces, len(langs)), 0.01)
        for r in sample.mapInPandas(partial, "p long, k long, v double").groupBy("p", "k").agg(F.sum("v").alias("v")).collect():  # vocabulary x languages
            table[r["p"], r["k"]] += r["v"]
        log_probs = np.log(table / table.sum(axis=0))
    return LanguageModel(langs, vocab, log_probs)


def predict_texts(model: LanguageModel, text: pd.Series, temper: float = 40.0, slice_chars: int = SLICE) -> tuple[np.ndarray, np.ndarray]:
    """(language or und, score) of each text; works through slices of about `slice_chars`, which bounds working memory."""
    found = [_predict_slice(model, text.iloc[rows], temper) for rows in tk.slices(text.str.len().fillna(0), slice_chars)]
    if not found:
        return np.zeros(0, dtype=object), np.zeros(0)
    return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])


def _predict_slice(model: LanguageModel, text: pd.Series, temper: float) -> tuple[np.ndarray, np.ndarray]:
    n = len(text)
    name, score = np.full(n, "und", dtype=object), np.zeros(n)
    if not model.langs or not n:
        return name, score
    b, o, codes, doc = _batch_words(text)
    words = word_scores(_trie(model.vocab), model.log_probs, b, o)
    total = np.stack([np.bincount(doc, weights=words[codes, k], minlength=n) for k in range(len(model.langs))], axis=1).astype(float)
    size = np.bincount(doc, weights=np.diff(o)[codes], minlength=n)
    total *= np.minimum(1.0, temper / np.maximum(size, 1))[:, None]
    total = np.round(total, 9)
    best = total.argmax(axis=1)
    post = 1 / np.exp(total - total.max(axis=1, keepdims=True)).sum(axis=1)
    letters = text.map(has_letter).to_numpy(dtype=bool)
    name[letters] = np.array(model.langs, dtype=object)[best[letters]]
    score[letters] = post[letters]
    return name, score


def has_letter(text: str | None) -> bool:
    return isinstance(text, str) and any(map(str.isalpha, text))


def identify(docs: DataFrame, model: LanguageModel, text: str = "text") -> DataFrame:
    """Add lang_pred and score; one row for each row."""
    sc = docs.sparkSession.sparkContext
    sent = sc.broadcast(model)  # vocabulary x languages

    @F.pandas_udf("lang_pred string, score double")
    def udf(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for texts in batches:
            name, score = predict_texts(sent.value, texts)
            tk.give_back()
            yield pd.DataFrame({"lang_pred": name, "score": score})

    found = docs.withColumn("_found", udf(F.col(text).cast("string")))
    return found.withColumn("lang_pred", F.col("_found.lang_pred")).withColumn("score", F.col("_found.score")).drop("_found")
