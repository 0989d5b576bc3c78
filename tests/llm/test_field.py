"""The semi-Markov field: sums and best segmentation by brute force, held-out precision and recall beyond the base patterns."""

import itertools
import math
import random
import re

from walkstream.llm import pii

SF = "/root/testdata/sf0.01"


def _segmentations(n):
    for cuts in itertools.chain.from_iterable(itertools.combinations(range(1, n), r) for r in range(n)):
        ends = [0, *cuts, n]
        spans = list(zip(ends, ends[1:]))
        for kinds in itertools.product(*[pii.LABELS if j - i == 1 else pii.KINDS for i, j in spans]):
            yield [(i, j, k) for (i, j), k in zip(spans, kinds)]


def test_sums_against_all_segmentations():
    rng = random.Random(8)
    for _ in range(5):
        text = " ".join(rng.choice(["12", "a@b.c", "+4", "x"]) for _ in range(4))
        chunks = [m.span() for m in re.finditer(r"\S+", text)]
        weights = {f"{x}>{y}": rng.uniform(-1, 1) for x in ("^", *pii.LABELS) for y in pii.LABELS}
        for i in range(4):
            for j in range(i + 1, 5):
                weights |= {f"{k}|{f}": rng.uniform(-1, 1) for f in pii.features(text[chunks[i][0] : chunks[j - 1][1]], j - i) for k in pii.LABELS}

        def score(seg):
            own = sum(weights[f"{k}|{f}"] for i, j, k in seg for f in pii.features(text[chunks[i][0] : chunks[j - 1][1]], j - i))
            return own + sum(weights[f"{x}>{y}"] for x, y in zip(["^", *[k for _, _, k in seg]], [k for _, _, k in seg]))

        every = [(seg, score(seg)) for seg in _segmentations(4)]
        total = sum(math.exp(v) for _, v in every)
        got = pii.segment_probability(text, chunks, weights)
        for (i, j, k), p in got.items():
            want = sum(math.exp(v) for seg, v in every if (i, j, k) in seg) / total
            assert math.isclose(p, want, rel_tol=1e-9, abs_tol=1e-12)
        assert math.isclose(score(pii.decode_run(text, chunks, weights)), max(v for _, v in every))


def test_held_out_forms_are_found(spark):
    """Fit on even documents; forms that no base pattern takes, made of the odd ones' spans."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").where("text is not null")
    weights = pii.fit(docs.where("doc_id % 2 = 0"))
    hit = made = added = clean_added = 0
    for r in docs.where("doc_id % 2 = 1").orderBy("doc_id").collect():
        base = pii.base_spans(r.text)
        own = pii.added_spans(r.text, weights, base)
        clean_added += len(own)
        for piece, gold in pii.fit_cases(r.text):
            for text, labels in pii.variants(piece, gold):
                chunks = [m.span() for m in re.finditer(r"\S+", text)]
                known = pii.base_spans(text)
                want = {(k, *pii._trim(text, chunks[i][0], chunks[j - 1][1])) for i, j, k in labels if k != "O"}
                want = {w for w in want if not any(s < w[2] and e > w[1] for _, s, e in known)}
                got = set(pii.added_spans(text, weights, known))
                hit, made, added = hit + len(got & want), made + len(want), added + len(got)
    print("recall", hit / made, "precision", hit / added, "made", made, "added to plain texts", clean_added)
    assert made > 30 and hit / made >= 0.8 and hit / added >= 0.9


def test_long_words_are_read_in_linear_time():
    field = pii.Field({"card|bias": 1.0})
    assert pii.added_spans("a" * 300_000 + " " + "1" * 300_000, field, []) is not None
    assert list(pii.runs("a" * 300_000)) == []


def test_long_segments_keep_their_digits():
    assert any(f.startswith("digits=20") for f in pii.features("x" * 70 + "1" * 30, 1))
