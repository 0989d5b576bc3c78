"""Personal data: fixed base patterns, and a semi-Markov conditional random field that adds spans.

Base spans (email, ip, card, phone) are found by linear scans and always stay. The field works on runs: stretches of
chunks between blanks that hold a digit, an at sign or a bracketed "at". A segment is one to MAX_CHUNKS chunks with a kind, or
one chunk of other text; its features look at the whole segment (digits, groups, separators, Luhn sum, octets, shape at its
ends), and each pair of neighbouring labels has a weight. Dynamic programming over at most MAX_CHUNKS chunks per entity
chooses boundaries and kinds together; sums over all segmentations (forward and backward) give the likelihood that is
maximised in `fit` and the probability of a segment. Segments with a probability of `least` that touch no base span are added.

The field is fitted on a bounded sample: the `fit_documents` distinct texts with the smallest hashes; of each, read whole, the
`fit_runs` distinct pieces of runs with the smallest hashes; of all these the `fit_pieces` with the smallest hashes. A piece
has `fit_chunks` chunks, more only where its end would cut a base span. Labels are the base spans and forms of them that the
base patterns don't take (`variants`): phones with 00 or brackets or slashes, cards with other separators, addresses with
bracketed dots or at signs; card numbers with a wrong check digit are labelled as other text. So the field learns to find
written-out forms and not only what the patterns find.

Defined cases: a null or empty text has no spans; texts of any length are read whole; offsets are code points, the end
exclusive; repeated rows are treated alike; an empty table fits no weights and adds nothing; columns named like the results
(base_spans, spans) are replaced.
"""

from __future__ import annotations

import bisect
import hashlib
import heapq
import itertools
import math
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textkernel as tk

KINDS = ("email", "ip", "card", "phone")
MAX_CHUNKS = 6

_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
# A run of digits is only tried from its start: later starts in it meet the same end.
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_NOT_DIGIT = re.compile(r"[^0-9]+")
_RUN = re.compile(r"(?<!\S)(?:[^\s0-9@]*+[0-9@]|[^\s0-9@(\[]*+[(\[][aA][tT][)\]])\S*+(?:[ ](?=\S*[0-9@(])\S++)*")
_CHUNK = re.compile(r"\S+")

Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def _emails(text: str) -> Iterator[Span]:
    floor, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _LOCAL:
            start -= 1
        found = _DOMAIN.match(text, at + 1) if start < at else None
        if found:
            yield ("email", start, found.end())
        floor = found.end() if found else at + 1
        at = text.find("@", floor)


def base_spans(text: str | None) -> list[Span]:
    """By kind as listed in KINDS, then by start."""
    if not text:
        return []
    out = list(_emails(text))
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or "0") <= 255 for p in m[0].split(".")):
            out.append(("ip", *m.span()))
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 16 and 16 <= len(d := _NOT_DIGIT.sub("", m[0])) <= 19 and luhn(d):
            out.append(("card", *m.span()))
    for m in _PHONE.finditer(text):
        if 8 <= len(_NOT_DIGIT.sub("", m[0])) <= 15:
            out.append(("phone", *m.span()))
    return out


_EDGE = ".,;:!?\"'()[]<>"
_ALNUM = re.compile(r"[0-9A-Za-z]+")
_MARK = re.compile(r"[(\[][aA][tT][)\]]")
_OTHER = re.compile(r"[^0-9]+")


def features(segment: str, n_chunks: int) -> list[str]:
    """Whole-span features of a candidate segment."""
    core = segment.strip(_EDGE)
    digits = _NOT_DIGIT.sub("", core)
    letters = sum(map(str.isalpha, core))
    seps = "".join(sorted(set(_ALNUM.sub("", core))))
    groups = _OTHER.split(core.strip("+(). -"))
    out = ["bias", f"digits={min(len(digits), 20)}", f"chunks={n_chunks}", f"at={min(core.count('@'), 2)}", f"seps={seps[:6]}", f"letters={min(letters, 3)}", f"groups={min(len(groups), 8)}", f"dots={min(core.count('.'), 5)}", f"shape={len(digits) // 4}:{min(letters, 1)}:{seps[:3]}"]
    if core.startswith("+"):
        out.append("plus")
    if core.startswith("00"):
        out.append("zeros")
    if segment.startswith("(0") and not letters:
        out.append("area")
    if 16 <= len(digits) <= 19 and not letters:
        out.append(f"luhn={luhn(digits)}")
    if len(groups) == 4 and not letters and core.count(".") == 3 and n_chunks == 1:
        out.append(f"octets={all(g and len(g) <= 3 and int(g) <= 255 for g in groups)}:{'[' in core or '(' in core}")
    if "@" in core:
        name, _, domain = core.partition("@")
        out.append(f"mail={bool(name) and bool(_DOMAIN.fullmatch(domain))}")
    mark = _MARK.search(core) if letters >= 2 else None
    if mark:
        name, domain = core[: mark.start()], core[mark.end() :]
        out.append(f"mark={bool(name) and set(name) <= _LOCAL and bool(_DOMAIN.fullmatch(domain))}")
    return out


def _trim(text: str, start: int, end: int) -> tuple[int, int]:
    while start < end and text[start] in ",;:!?\"'([<":
        start += 1
    while end > start and text[end - 1] in ".,;:!?\"')]>":
        end -= 1
    return start, end


Weights = dict[str, float]
Case = tuple[str, list[tuple[int, int, str]]]
LABELS = ("O", *KINDS)
_NONE = (0.0,) * len(LABELS)


class Field:
    """Weights laid out by feature: `label|feature` of segments, `label>label` of neighbours (^ before the first)."""

    def __init__(self, weights: Weights):
        table: dict[str, list[float]] = {}
        for name, w in weights.items():
            label, bar, feature = name.partition("|")
            if bar and label in LABELS:
                table.setdefault(feature, [0.0] * len(LABELS))[LABELS.index(label)] = w
        self.table = {f: tuple(w) for f, w in table.items()}
        self.first = tuple(weights.get(f"^>{x}", 0.0) for x in LABELS)
        self.next = tuple(tuple(weights.get(f"{x}>{y}", 0.0) for y in LABELS) for x in LABELS)

    def segment(self, text: str, n_chunks: int) -> list[float]:
        """Score of the segment under each label."""
        rows = [self.table.get(f, _NONE) for f in features(text, n_chunks)]
        return [sum(x) for x in zip(*rows, strict=True)]


def _as_field(weights: Weights | Field) -> Field:
    return weights if isinstance(weights, Field) else Field(weights)


def _scores(text: str, chunks: list[tuple[int, int]], field: Field) -> list[list[list[float]]]:
    """scores[j][j - i - 1]: of the segment of chunks i, ..., j - 1 under each label."""
    return [[]] + [[field.segment(text[chunks[i][0] : chunks[j - 1][1]], j - i) for i in range(j - 1, max(-1, j - 1 - MAX_CHUNKS), -1)] for j in range(1, len(chunks) + 1)]


def _viterbi(scores: list[list[list[float]]], field: Field) -> list[tuple[int, int, str]]:
    n, m = len(scores) - 1, len(LABELS)
    best: list[list[float]] = []  # best score up to a chunk and the label before it
    back: list[list[tuple[int, int]]] = []
    enter: list[list[tuple[float, int]]] = []  # best way into each label from there
    for j in range(n + 1):
        top, arg = [float("-inf")] * m, [(0, -1)] * m
        for k, own in enumerate(scores[j]):
            i = j - k - 1
            for label in range(m) if not k else range(1, m):
                score = enter[i][label][0] + own[label]
                if score > top[label] + 1e-12:
                    top[label], arg[label] = score, (i, enter[i][label][1])
        best.append(top)
        back.append(arg)
        if j == 0:
            enter.append([(w, -1) for w in field.first])
        else:
            enter.append([max(((top[x] + field.next[x][y], -x) for x in range(m)), key=lambda v: v) for y in range(m)])
            enter[j] = [(v, -x) for v, x in enter[j]]
    if not n:
        return []
    out, j = [], n
    label = max(range(m), key=lambda x: (best[n][x], -x))
    while j:
        i, before = back[j][label]
        out.append((i, j, LABELS[label]))
        j, label = i, before
    return out[::-1]


def decode_run(text: str, chunks: list[tuple[int, int]], weights: Weights | Field) -> list[tuple[int, int, str]]:
    """Best segmentation: (first chunk, chunk after the last, kind or O)."""
    field = _as_field(weights)
    return _viterbi(_scores(text, chunks, field), field)


def _log_sum(values: list[float]) -> float:
    top = max(values, default=float("-inf"))
    return top if top == float("-inf") else top + math.log(sum(math.exp(v - top) for v in values))


def _sums(scores: list[list[list[float]]], field: Field) -> tuple[list[list[float]], list[list[float]], float]:
    """(log sums of all ways to a chunk that go on with a label, of all ways from a chunk after a label, and of all)."""
    n, m = len(scores) - 1, range(len(LABELS))
    ahead = [list(field.first)]
    for j in range(1, n + 1):
        at = [_log_sum([ahead[j - k - 1][x] + own[x] for k, own in enumerate(scores[j]) if x or not k]) for x in m]
        if j < n:
            ahead.append([_log_sum([at[x] + field.next[x][y] for x in m]) for y in m])
    total = _log_sum(at) if n else 0.0
    behind: list[list[float]] = [[0.0] * len(LABELS) for _ in range(n + 1)]
    for i in range(n - 1, 0, -1):
        go = [_log_sum([scores[j][j - i - 1][y] + behind[j][y] for j in range(i + 1, min(n, i + MAX_CHUNKS) + 1) if y or j == i + 1]) for y in m]
        behind[i] = [_log_sum([field.next[x][y] + go[y] for y in m]) for x in m]
    return ahead, behind, total


def segment_probability(text: str, chunks: list[tuple[int, int]], weights: Weights | Field) -> dict[tuple[int, int, str], float]:
    """Probability of every possible segment of a run."""
    field = _as_field(weights)
    scores = _scores(text, chunks, field)
    ahead, behind, total = _sums(scores, field)
    return {(j - k - 1, j, LABELS[x]): math.exp(ahead[j - k - 1][x] + own[x] + behind[j][x] - total) for j in range(1, len(scores)) for k, own in enumerate(scores[j]) for x in range(len(LABELS)) if x or not k}


def runs(text: str) -> Iterator[list[tuple[int, int]]]:
    for m in _RUN.finditer(text):
        yield [c.span() for c in _CHUNK.finditer(text, m.start(), m.end())]


def _gold(text: str, chunks: list[tuple[int, int]], base: list[Span]) -> list[tuple[int, int, str]]:
    """Base spans of a run as segments of whole chunks."""
    out, j = [], 0
    own = sorted((s, e, k) for k, s, e in base if s < chunks[-1][1] and e > chunks[0][0])
    while j < len(chunks):
        hit = next(((s, e, k) for s, e, k in own if s < chunks[j][1] and e > chunks[j][0]), None)
        to = j + 1
        if hit:
            while to < len(chunks) and chunks[to][0] < hit[1]:
                to += 1
        out += [(j, to, hit[2])] if hit and to - j <= MAX_CHUNKS else [(x, x + 1, "O") for x in range(j, to)]
        j = to
    return out


def fit(docs: DataFrame, text: str = "text", fit_documents: int = 300, fit_runs: int = 40, fit_chunks: int = 60, epochs: int = 4, fit_most: int = 1500) -> Weights:
    """Weights of the largest likelihood (regularised) on a bounded sample."""
    rows = docs.select(F.col(text).alias("t")).where(F.col("t").rlike("[0-9@]")).select(F.xxhash64("t").alias("h"), "t")
    # hashes first: only they travel from every task, texts just for the hashes chosen
    least = [r["h"] for r in rows.select("h").distinct().orderBy("h").limit(fit_documents).collect()]
    if not least:
        return {}

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for h, t in zip(batch["h"], batch["t"], strict=True):
                cases = fit_cases(t, fit_runs, fit_chunks)
                gold = [[dict(zip(("i", "j", "kind"), g, strict=True)) for g in gold] for _, gold in cases]
                yield pd.DataFrame({"h": [h] * len(cases), "k": range(len(cases)), "piece": [piece for piece, _ in cases], "gold": gold})

    texts = rows.where(F.col("h") <= least[-1]).distinct()
    found = texts.mapInPandas(cut, "h long, k long, piece string, gold array<struct<i:int,j:int,kind:string>>").collect()  # fit_documents x fit_runs pieces
    found.sort(key=lambda r: (r["h"], r["k"], r["piece"]))
    cases = {r["piece"]: [(g["i"], g["j"], g["kind"]) for g in r["gold"]] for r in found}
    chosen = heapq.nsmallest(fit_most, cases, key=_digest)
    return fit_pieces([(p, cases[p]) for p in chosen], epochs)


def fit_cases(text: str, fit_runs: int = 40, fit_chunks: int = 60) -> list[Case]:
    """(piece of a run, its base spans as segments): the fit_runs distinct pieces with the smallest hashes, of the whole text.

    A run is cut after every fit_chunks chunks, or later where that would be inside a base span.
    """
    base = base_spans(text)
    spans = sorted((s, e) for _, s, e in base)
    starts, reach = [s for s, _ in spans], list(itertools.accumulate((e for _, e in spans), max))

    def inside(at: int) -> bool:
        n = bisect.bisect_left(starts, at)
        return n > 0 and reach[n - 1] > at

    pieces: dict[str, list[tuple[int, int]]] = {}
    for chunks in runs(text):
        i = 0
        while i < len(chunks):
            j = min(i + fit_chunks, len(chunks))
            while j < len(chunks) and inside(chunks[j][0]):
                j += 1
            pieces.setdefault(text[chunks[i][0] : chunks[j - 1][1]], chunks[i:j])
            i = j
    chosen = heapq.nsmallest(fit_runs, pieces, key=_digest)
    return [(p, _gold(text, pieces[p], base)) for p in chosen]


def _digest(text: str) -> tuple[bytes, str]:
    return hashlib.md5(text.encode("utf-8", "replace")).digest(), text


def _spaced(digits: str, sep: str, size: int = 4) -> str:
    return sep.join(digits[i : i + size] for i in range(0, len(digits), size))


def _rewritten(kind: str, span: str, turn: int) -> str:
    """A form of a base span that its pattern doesn't take."""
    digits = _NOT_DIGIT.sub("", span)
    if kind == "phone":
        forms = (f"00{digits[:2]} {digits[2:5]} {digits[5:]}", f"(0{digits[2:5]}) {_spaced(digits[5:], '-', 3)}", f"+{digits[:2]}/{digits[2:5]}/{digits[5:]}")
    elif kind == "card":
        forms = tuple(_spaced(digits, sep) for sep in (".", "/", "_"))
    elif kind == "ip":
        forms = (span.replace(".", "[.]"), span.replace(".", "(.)"), ".".join(f"[{x}]" for x in span.split(".")))
    else:
        forms = (span.replace("@", "[at]"), span.replace("@", "(at)"), span.replace("@", "[AT]"))
    return forms[turn % len(forms)]


def variants(piece: str, gold: list[tuple[int, int, str]], turn: int | None = None) -> Iterator[Case]:
    """The piece with its base spans in other forms, labelled alike; and its cards with a wrong check digit, as other text."""
    if all(k == "O" for _, _, k in gold):
        return
    chunks = [c.span() for c in _CHUNK.finditer(piece)]
    turn = _digest(piece)[0][0] if turn is None else turn
    wrong = any(k == "card" for _, _, k in gold)
    for spoil in (False, True) if wrong else (False,):
        words: list[str] = []
        labels: list[tuple[int, int, str]] = []
        for i, j, kind in gold:
            start, end = chunks[i][0], chunks[j - 1][1]
            a, b = _trim(piece, start, end)
            own = piece[start:end]
            if kind != "O":
                core = next((piece[x:y] for k, x, y in base_spans(piece) if k == kind and x < end and y > start), piece[a:b])
                if spoil and kind == "card":
                    last = max(x for x, c in enumerate(core) if c.isdigit())
                    new = core[:last] + str((int(core[last]) + 1 + turn % 8) % 10) + core[last + 1 :]
                    own, kind = own.replace(core, new), "O" if not luhn(_NOT_DIGIT.sub("", new)) else kind
                elif not spoil:
                    own = own.replace(core, _rewritten(kind, core, turn))
            parts = own.split()
            at = len(words)
            words += parts
            labels += [(at, at + len(parts), kind)] if kind != "O" and len(parts) <= MAX_CHUNKS else [(at + x, at + x + 1, "O") for x in range(len(parts))]
        yield " ".join(words), labels


def fit_pieces(cases: list[Case], epochs: int = 4, step: float = 0.5, decay: float = 1e-3) -> Weights:
    """Gradient ascent on the log likelihood of the cases and their variants, with a rate for each weight that falls with its
    gradients' squares; `decay` pulls weights to 0."""
    every = [c for case in cases for c in (case, *variants(*case))]
    every.sort(key=lambda c: _digest(c[0]))
    number: dict[str, int] = {}
    prepared = []
    for text, gold in every:
        chunks = [c.span() for c in _CHUNK.finditer(text)]
        n = len(chunks)
        if not n:
            continue
        spans = [(j - k - 1, j) for j in range(1, n + 1) for k in range(min(MAX_CHUNKS, j))]
        own = [[number.setdefault(f, len(number) + 1) for f in features(text[chunks[i][0] : chunks[j - 1][1]], j - i)] for i, j in spans]
        width = max(map(len, own))
        index = np.array([x + [0] * (width - len(x)) for x in own])
        place = {ij: k for k, ij in enumerate(spans)}
        prepared.append((n, spans, index, [(place[i, j], LABELS.index(kind)) for i, j, kind in gold]))
    m = len(LABELS)
    w, seen = np.zeros((len(number) + 1, m)), np.full((len(number) + 1, m), 1e-8)
    t, t_seen = np.zeros((m + 1, m)), np.full((m + 1, m), 1e-8)  # the last row: before the first segment

    def grown(a: np.ndarray) -> np.ndarray:
        top = a.max(axis=0)
        return top + np.log(np.exp(a - top).sum(axis=0))

    for _ in range(epochs):
        for n, spans, index, gold in prepared:
            s = w[index].sum(axis=1)
            length = np.array([j - i for i, j in spans])
            s[length > 1, 0] = -1e30
            at, enter = np.zeros((n + 1, m)), np.zeros((n + 1, m))
            enter[0] = t[m]
            k = 0
            for j in range(1, n + 1):
                here = min(MAX_CHUNKS, j)
                at[j] = grown(enter[j - 1 : (j - 1 - here) if j > here else None : -1][:here] + s[k : k + here])
                enter[j] = grown(at[j][:, None] + t[:m])
                k += here
            total = grown(at[n])
            behind, go = np.zeros((n + 1, m)), np.zeros((n + 1, m))
            ends = np.array([j for _, j in spans])
            by_start: list[list[int]] = [[] for _ in range(n)]
            for x, (i, _) in enumerate(spans):
                by_start[i].append(x)
            for i in range(n - 1, -1, -1):
                rows = by_start[i]
                go[i] = grown(s[rows] + behind[ends[rows]])
                if i:
                    behind[i] = grown((t[:m] + go[i]).T)
            prob = np.exp(enter[[i for i, _ in spans]] + s + behind[ends] - total)
            pairs = np.zeros((m + 1, m))
            pairs[m] = np.exp(t[m] + go[0] - total)
            for i in range(1, n):
                pairs[:m] += np.exp(at[i][:, None] + t[:m] + go[i] - total)
            want, before = np.zeros_like(prob), m
            t_want = np.zeros_like(pairs)
            for x, label in gold:
                want[x, label] += 1
                t_want[before, label] += 1
                before = label
            g = np.zeros_like(w)
            np.add.at(g, index, np.broadcast_to((want - prob)[:, None, :], (*index.shape, m)))
            rows = np.unique(index)
            own = g[rows] - decay * w[rows]
            seen[rows] += own * own
            w[rows] += step * own / np.sqrt(seen[rows])
            own = t_want - pairs - decay * t
            t_seen += own * own
            t += step * own / np.sqrt(t_seen)
            w[0] = 0.0
    out = {f"{LABELS[x]}|{f}": float(w[k, x]) for f, k in number.items() for x in range(m) if w[k, x]}
    return out | {f"{'^' if x == m else LABELS[x]}>{LABELS[y]}": float(t[x, y]) for x in range(m + 1) for y in range(m) if t[x, y]}


def added_spans(text: str | None, weights: Weights | Field, base: list[Span], least: float = 0.9) -> list[Span]:
    """Segments of the field with a probability of `least` that touch no base span."""
    if not text or not weights:
        return []
    field = _as_field(weights)
    out: list[Span] = []
    taken = sorted((s, e) for _, s, e in base)
    k = 0
    for chunks in runs(text):
        while k < len(taken) and taken[k][1] <= chunks[0][0]:
            k += 1
        near = []
        for x in range(k, len(taken)):
            if taken[x][0] >= chunks[-1][1]:
                break
            near.append(taken[x])
        scores = _scores(text, chunks, field)
        sums = None
        for i, j, kind in _viterbi(scores, field):
            if kind == "O":
                continue
            start, end = _trim(text, chunks[i][0], chunks[j - 1][1])
            if start >= end or any(s < end and e > start for s, e in near):
                continue
            sums = sums or _sums(scores, field)
            ahead, behind, total = sums
            x = LABELS.index(kind)
            if ahead[i][x] + scores[j][j - i - 1][x] + behind[j][x] - total >= math.log(least):
                out.append((kind, start, end))
    return sorted(out, key=lambda x: (KINDS.index(x[0]), x[1]))


_SPANS = "array<struct<kind:string,start:int,end:int>>"


def _all_spans(text: str, weights: Weights | Field) -> tuple[list[Span], list[Span]]:
    """(base spans, all spans by kind as in KINDS, then start)."""
    base = base_spans(text)
    more = added_spans(text, weights, base)
    return base, sorted(base + more, key=lambda x: (KINDS.index(x[0]), x[1])) if more else base


def _masked(text: str, spans: list[Span]) -> str:
    parts, at = [], 0
    for kind, start, end in sorted(spans, key=lambda s: (s[1], -s[2])):
        if start >= at:
            parts += [text[at:start], f"[{kind.upper()}]"]
        at = max(at, end)
    return "".join(parts) + text[at:]


def find(docs: DataFrame, weights: Weights, text: str = "text") -> DataFrame:
    """Add base_spans and spans: arrays of (kind, start, end), by kind as in KINDS, then start."""

    @F.pandas_udf(f"base {_SPANS}, every {_SPANS}")
    def udf(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        tk.forget()
        named = lambda spans: [dict(zip(("kind", "start", "end"), s, strict=True)) for s in spans]
        field = Field(weights) if weights else {}
        for batch in batches:
            found = [_all_spans(t if isinstance(t, str) else "", field) for t in batch]
            tk.give_back()
            yield pd.DataFrame([(named(base), named(every)) for base, every in found], columns=["base", "every"])

    out = docs.drop("base_spans", "spans").withColumn("_p", udf(F.col(text).cast("string")))
    return out.withColumn("base_spans", F.col("_p.base")).withColumn("spans", F.col("_p.every")).drop("_p")


def mask(docs: DataFrame, weights: Weights, text: str = "text") -> DataFrame:
    """What `find` and `redact` give together, without spans and in one pass through one worker."""

    @F.pandas_udf("string")
    def udf(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        tk.forget()
        field = Field(weights) if weights else {}
        for batch in batches:
            out = [_masked(t, _all_spans(t, field)[1]) if isinstance(t, str) else None for t in batch]
            tk.give_back()
            yield pd.Series(out, dtype=object)

    return docs.withColumn(text, udf(F.col(text).cast("string")))


def span_text(spans: Column) -> Column:
    """kind:start:end, joined by commas."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(docs: DataFrame, text: str = "text", spans: str = "spans") -> DataFrame:
    """Replace each span by its kind in brackets; of overlapping spans the union is replaced, named after the first."""

    @F.pandas_udf("string")
    def udf(texts: pd.Series, found: pd.Series) -> pd.Series:
        out = []
        for t, own in zip(texts, found, strict=True):
            if not isinstance(t, str):
                out.append(None)
            else:
                out.append(t if own is None else _masked(t, [(s["kind"], s["start"], s["end"]) for s in own]))
        return pd.Series(out, dtype=object)

    return docs.withColumn(text, udf(F.col(text), F.col(spans)))
