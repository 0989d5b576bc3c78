"""Small cases of the training-data operators, against brute force, round trips and held-out accuracy."""

import base64
import hashlib
import io
import itertools
import math
import random
import re
import zlib

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
pytest.importorskip("walkstream.llm")

from walkstream.llm import langid, media, mixing, near_dup, pii, sentence_pieces, token_counts, url_filter, vector_search, warc  # noqa: E402
from walkstream.llm import textkernel as tk  # noqa: E402
from walkstream.llm.common import Workspace  # noqa: E402
from walkstream.llm.queries import RULES, queries  # noqa: E402
from walkstream.llm.vocab import load_pieces  # noqa: E402

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ODD_TEXTS = [None, "", "   ", "\n\t", "a", "ß▁é 日本語", "x" * 70_000, "word " * 20_000, "same text", "same text", "a  b   c\n\nd", "\x00 nul \x7f", "emoji 👩‍👩‍👧 end "]


@pytest.fixture(scope="module")
def vocab():
    return load_pieces()


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(i, t, None if i % 3 else "en", None if i % 2 else "s", 7, "x") for i, t in enumerate(ODD_TEXTS)]
    rows.append((None, None, None, None, None, None))
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, size long, score string")


def test_words_and_hashes():
    texts = pd.Series([t for t in ODD_TEXTS if t is not None])
    buf, offsets = tk.text_buffer(texts)
    start, length, doc = tk.split_words(buf, offsets)
    want = [(i, w.encode()) for i, t in enumerate(texts) for w in WORD.findall(t)]
    got = [(int(d), bytes(buf[s : s + n])) for s, n, d in zip(start, length, doc)]
    assert got == want
    h = tk.hash_spans(buf, start, length, tk.byte_values(False))
    seen = {}
    for (_, w), x in zip(want, h.tolist()):
        assert seen.setdefault(w, x) == x
    assert len(set(seen.values())) == len(seen)


# 1. URL filters


def _judge(url):
    host = path = ""
    if url is not None and "://" in url:
        rest = url.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest)[0]
        path = re.match(r"[^?#]*", rest[len(host) :])[0]
        host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    fits = [(len(h + p), h + p, a) for h, p, a in RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, default=None)
    return host, path, best and best[1], best[2] if best else "allow"


URLS = [None, "", "nothing", "http://a.com/en/1", "HTTP://A.Example.COM/en/7?x", "https://example.net/de/8", "x://example.net/de/9#f", "http://com/en/", "http://xcom/en/1", "http://b.org?/es/", "http://org/es/", "http://b.org/es", "http://b.org#/es/", "a://b://c.com/en/", "http://", "http:///en/", "http://ex.com//en/", "http://é.com/en/é", "http://.com/en/"]


def test_url_rules(spark):
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(URLS * 2)], "page_id long, url string, host string")
    want = {i: _judge(u) for i, u in enumerate(URLS * 2)}
    for fn in (url_filter.judge, url_filter.judge_by_join):
        got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in fn(pages, RULES).select("page_id", "host", "path", "rule", "verdict").collect()}
        assert got == want
    assert url_filter.judge(pages.limit(0), RULES).count() == 0
    assert {r.verdict for r in url_filter.judge(pages, ()).collect()} == {"allow"}


def test_url_rules_are_those_of_the_contract(spark):
    urls = ["http://a.com/en/1", "http://example.com/en/7", "http://a.net/de/1", "http://example.net/de/9", "http://example.net/de/8", "http://b.org/es/"]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    want = [("com/en/", "block"), ("example.com/en/7", "allow"), ("net/de/", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"), ("org/es/", "block")]
    for fn in (url_filter.judge, url_filter.judge_by_join):
        assert [(r["rule"], r.verdict) for r in fn(pages, RULES).orderBy("page_id").collect()] == want


def test_cascade_is_exact_for_its_universe(spark):
    url_filter._shared(spark)
    universe = spark.range(20_000).select(F.concat(F.lit("k"), "id").alias("key"))
    listed = universe.where("pmod(xxhash64(key), 7) = 0")
    cascade = url_filter.build_cascade(listed, universe, 20_000)
    assert len(cascade.levels) > 2
    wrong = universe.where(cascade.listed(F.col("key")) != F.expr("pmod(xxhash64(key), 7) = 0"))
    assert wrong.count() == 0
    assert url_filter.build_cascade(listed, universe, 20_000, max_bits=64) is None


# 2. Language ID


def test_forward_sums_all_segmentations(vocab):
    rng = np.random.default_rng(0)
    log_probs = np.log(rng.random((len(vocab.pieces), 2)) * 1e-3)
    known = {p: i for i, (p, k) in enumerate(zip(vocab.pieces, vocab.kinds)) if k == "piece"}
    words = [b" the", b" gr\xc3\xbcn", b" zqx", b" " + b"ab" * 30]
    buf = np.frombuffer(b"".join(words), dtype=np.uint8)
    offsets = np.cumsum([0, *map(len, words)])
    got = langid.word_scores(langid._trie(vocab), log_probs, buf, offsets)
    for w, row in zip(words, got):
        a = np.zeros((len(w) + 1, 2))
        a[0] = 1
        for j in range(1, len(w) + 1):
            for i in range(j):
                p = known.get(w[i:j])
                a[j] += a[i] * ((np.exp(log_probs[p]) if p is not None else 0) + (langid.BYTE_FLOOR if j - i == 1 else 0))
        assert np.allclose(np.log(a[-1]), row)


def test_language_accuracy_on_held_out_rows(spark):
    got = queries()["op2_language_id"](spark, SF).join(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang"), "doc_id")
    held = got.where("held_out and lang is not null and lang_pred <> 'und'")
    n, right = held.count(), held.where("lang = lang_pred").count()
    assert n > 20 and right / n > 0.95


def test_language_odd_rows(spark, odd, vocab):
    model = langid.LanguageModel(("a", "b"), vocab, np.full((len(vocab.pieces), 2), -9.0))
    got = {r.doc_id: r for r in langid.identify(odd, model).collect()}
    assert len(got) == odd.count()
    for i, t in enumerate(ODD_TEXTS):
        letters = t is not None and any(c.isalpha() for c in t)
        assert (got[i].lang_pred == "und") == (not letters) and 0 <= got[i].score <= 1
    assert langid.train(odd.where("false")).langs == ()
    assert {r.lang_pred for r in langid.identify(odd, langid.train(odd.where("false"))).collect()} == {"und"}


# 3. Media


def test_media_formats_round_trip():
    rng = np.random.default_rng(1)
    for shape in ((1, 1), (5, 7), (8, 64), (3, 5, 3)):
        image = rng.integers(0, 256, shape, dtype=np.uint8)
        for coded in (media.encode_netpbm(image), media.encode_bmp(image)):
            assert (media.decode(coded) == image).all()
        plain = (b"P2" if len(shape) == 2 else b"P3") + b"\n# note\n%d %d\n255\n" % (shape[1], shape[0]) + b" ".join(b"%d" % x for x in image.ravel())
        assert (media.decode(plain) == image).all()
        assert np.load(io.BytesIO(media.npy_tile(image, 4))).shape[:2] == (4, 4)
    for bad in (b"", b"P5", b"P5 2 2 255\nx", b"BM", b"P5\n0 1\n255\n"):
        with pytest.raises(ValueError):
            media.decode(bad)


def test_area_resize_against_brute_force():
    image = np.random.default_rng(2).integers(0, 256, (7, 10)).astype(np.uint8)
    big = np.kron(image, np.ones((3, 9)))  # 21 x 90: both sides divide
    want = big.reshape(3, 7, 9, 10).mean(axis=(1, 3))
    assert np.allclose(media.area_resize(image, 3, 9), want)


def test_media_query_contract(spark, odd):
    got = {r.doc_id: r for r in media.media_features(media.store_texts(odd)).collect() if r.doc_id is not None}
    for i, t in enumerate(ODD_TEXTS):
        raw = (t or "").encode()
        payload = raw + bytes(-len(raw) % 64 if raw else 64)
        r = got[i]
        assert (r.n_bytes, r.payload_bytes) == (len(raw), len(payload))
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest() and r.tail_crc32 == zlib.crc32(payload[-64:])
        stored = b"P5\n64 %d\n255\n" % (len(payload) // 64) + payload
        assert (r.media_bytes, r.media_sha256) == (len(stored), hashlib.sha256(stored).hexdigest())
    assert got[8].feature == got[9].feature
    bad = spark.createDataFrame([(None,), (b"no",)], "media binary")
    assert {r.dhash for r in media.tiles(bad).collect()} == {None}


# 4. SentencePiece


def _viterbi(vocab, raw):
    n = len(vocab.pieces)
    known = {p: max(s, -n) for p, s, k in zip(vocab.pieces, vocab.scores, vocab.kinds) if k == "piece"}
    best = [0] + [-math.inf] * len(raw)
    for j in range(1, len(raw) + 1):
        best[j] = best[j - 1] - n - 10
        for i in range(max(0, j - 30), j):
            s = known.get(raw[i:j])
            if s is not None:
                best[j] = max(best[j], best[i] + s)
    return best[-1]


def test_encoding_is_optimal_and_chunks_agree(vocab):
    enc = sentence_pieces.encoder(vocab)
    rng = random.Random(3)
    for case in range(12):
        text = "".join(rng.choice(["the ", "ing", "é", "日", " ", "x", "ß", "\n", "tion"]) for _ in range(150)) if case else "abcdefgh" * 40
        raw = b" " + text.encode()
        buf = np.frombuffer(raw, dtype=np.uint8)
        score = lambda ids: sum(enc.lone if vocab.kinds[i] == "byte" else int(enc.score[i]) for i in ids)
        whole = enc.encode_buffer(buf, np.array([0, len(buf)]))[0]
        assert score(whole) == _viterbi(vocab, raw)
        size = 61
        chunks = [(buf[k : k + size + enc.states - 1], min(size, len(buf) - k)) for k in range(0, len(buf), size)]
        states, total = sentence_pieces.boundary_states(enc, chunks)
        parts = [enc.encode_buffer(b[i : n + j], np.array([0, n + j - i]))[0] for (b, n), i, j in zip(chunks, states, states[1:])]
        joined = np.concatenate(parts)
        assert total == score(joined) == score(whole)
        assert joined.tolist() == whole.tolist()  # ties too
        assert b"".join(vocab.pieces[i] for i in joined) == raw


def test_combine_is_associative():
    rng = np.random.default_rng(4)
    a, b, c = (rng.integers(-9, 9, (4, 4)) for _ in range(3))
    assert (sentence_pieces.combine(sentence_pieces.combine(a, b), c) == sentence_pieces.combine(a, sentence_pieces.combine(b, c))).all()
    got = sentence_pieces.prefix_scan([a, b, c])
    assert (got[2] == sentence_pieces.combine(sentence_pieces.combine(a, b), c)).all()


def test_encode_and_decode_texts(odd):
    both = sentence_pieces.ids_array(sentence_pieces.decode(sentence_pieces.encode(odd, chunk_bytes=4096))).collect()
    assert len(both) == odd.count()
    for r in both:
        assert r.decoded == r.text and (r.ids is None) == (r.text is None)


def test_workers_do_not_keep_an_encoder(spark, odd):
    sentence_pieces.decode(sentence_pieces.encode(odd, chunk_bytes=4096)).collect()

    def kept(batches):
        from walkstream.llm import sentence_pieces as own
        from walkstream.llm import textkernel

        for b in batches:
            yield pd.DataFrame({"n": [own.encoder.cache_info().currsize + len(textkernel._cache)]})

    assert spark.range(64, numPartitions=16).mapInPandas(kept, "n long").groupBy().max("n").first()[0] == 0


def test_any_chunk_size_gives_the_same_ids(spark, monkeypatch):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("length(text) > 4000").select("doc_id", "text")
    extra = spark.createDataFrame([(-1, "ab" * 2000), (-2, "x" * 700 + " tion" * 300), (-3, "日本" * 400)], "doc_id long, text string")
    docs = docs.unionByName(extra).coalesce(2)
    monkeypatch.setattr(sentence_pieces, "SCAN_BLOCK", 3)
    want = {r.doc_id: bytes(r.piece_ids) for r in sentence_pieces.encode(docs, chunk_bytes=1 << 24).collect()}
    assert len(want) > 20
    for size in (64, 700):
        got = sentence_pieces.encode(docs, chunk_bytes=size, verify=True).collect()
        assert len(got) == len(want) and all(r.round_trip and bytes(r.piece_ids) == want[r.doc_id] for r in got)


# 5. PII


def _plain_spans(text):
    text = text or ""
    out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = re.sub(r"[^0-9]", "", m[0])
        if 16 <= len(d) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(d))) % 10 == 0:
            out.append(("card", *m.span()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text):
        if 8 <= len(re.sub(r"[^0-9]", "", m[0])) <= 15:
            out.append(("phone", *m.span()))
    return out


def test_base_spans_against_plain_patterns(spark):
    rng = random.Random(5)
    pieces = ["a@b.c", "@", "x.y+z@d-e.f.g", "1.2.3.4", "300.1.1.1", "1.2.3.4.5.6.7.8", ".", "4111 1111 1111 1111", "4111-1111-1111-1112", "+49 (30) 1234-567", "+1", "+12345678901234567", "é", " ", "-", "7", "\n", "a@b", "٣", "001.02.3.4", "@x.y"]
    for _ in range(3000):
        text = "".join(rng.choice(pieces) for _ in range(rng.randint(0, 9)))
        assert pii.base_spans(text) == _plain_spans(text), text
    for r in spark.read.parquet(f"{SF}/documents.parquet").select("text").collect():
        assert pii.base_spans(r.text) == _plain_spans(r.text)
    pii.base_spans("9" * 200_000 + "a" * 200_000 + "@" * 1000)  # linear


def test_field_adds_spans_and_keeps_base(spark, odd):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    weights = pii.fit(docs)
    for r in docs.select("text").collect():
        base = pii.base_spans(r.text)
        more = pii.added_spans(r.text, weights, base)
        assert not any(s < e2 and e > s2 for _, s, e in more for _, s2, e2 in base)
    chunks = [m.span() for m in re.finditer(r"\S+", "call +49 30 123456 or a@b.de")]
    best = pii.decode_run("call +49 30 123456 or a@b.de", chunks, weights)
    assert [j for _, j, _ in best][-1] == len(chunks) and all(j - i <= pii.MAX_CHUNKS for i, j, _ in best)
    found = pii.find(odd, weights)
    assert found.count() == odd.count()
    red = pii.redact(pii.find(spark.createDataFrame([("mail a@b.de now",), (None,)], "text string"), {}))
    assert {r.text for r in red.collect()} == {"mail [EMAIL] now", None}


def test_decoding_is_optimal(spark):
    rng = random.Random(6)
    for _ in range(30):
        words = [rng.choice(["12", "a@b.c", "+4", "x"]) for _ in range(5)]
        text = " ".join(words)
        chunks = [m.span() for m in re.finditer(r"\S+", text)]
        weights = {f"{k}|{f}": rng.uniform(-1, 1) for i in range(5) for j in range(i + 1, 6) for f in pii.features(text[chunks[i][0] : chunks[j - 1][1]], j - i) for k in (*pii.KINDS, "O")}
        part = lambda i, j, k: sum(weights[f"{k}|{f}"] for f in pii.features(text[chunks[i][0] : chunks[j - 1][1]], j - i))
        top = -math.inf
        for cuts in itertools.chain.from_iterable(itertools.combinations(range(1, 5), r) for r in range(5)):
            ends = [0, *cuts, 5]
            top = max(top, sum(max(part(i, j, k) for k in (*pii.KINDS, *["O"] * (j - i == 1))) for i, j in zip(ends, ends[1:])))
        assert math.isclose(sum(part(*s) for s in pii.decode_run(text, chunks, weights)), top)


# 6. Mixing


def test_targets_fill_up_to_the_cap():
    got = mixing.targets([("b", 10), ("a", 100), (None, 50)])
    assert list(got) and got["b"] == 20 and math.isclose(sum(got.values()), 240)
    assert all(got[s] <= 2 * n + 1e-9 for s, n in (("b", 10), ("a", 100), (None, 50)))
    assert math.isclose(got["a"], min(200, (240 - 20) * 3 / 5))


def test_mix_meets_targets(spark, odd):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    first = mixing.mix(docs, Workspace(spark, "m")).collect()
    again = mixing.mix(docs.repartition(7), Workspace(spark, "m")).collect()
    assert sorted((r.doc_id, r.taken) for r in first) == sorted((r.doc_id, r.taken) for r in again)
    by = {}
    for r in first:
        n, t = by.setdefault(r.source, [0, 0])
        by[r.source] = [n + r.size, t + r.taken]
        assert 0 <= r.taken <= 2 * r.size and r.taken >= r.size * int(r.target // r.source_size)
    goal = mixing.targets([(s, n) for s, (n, _) in by.items()])
    for s, (_, taken) in by.items():
        assert abs(taken - goal[s]) <= 1
    got = mixing.mix(odd, Workspace(spark, "m")).collect()
    assert len(got) == odd.count() and all(r.taken == 0 for r in got if r.size == 0)
    assert mixing.mix(odd.where("false"), Workspace(spark, "m")).count() == 0


def test_mix_takes_the_first_documents_of_the_key_order(spark):
    """Which documents are taken, by brute force: keys in order, whole epochs first, the budget's end in one document."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = mixing.mix(docs, Workspace(spark, "m"), carry=("doc_id", "text")).collect()
    key = {r.doc_id: r.k for r in docs.withColumn("n", mixing.word_count(F.col("text"))).select("doc_id", (-F.ln(mixing.uniform(0, F.col("doc_id"), F.col("text"))) / mixing.quality_weight(F.col("text"), F.col("n"))).alias("k")).collect()}
    by = {}
    for r in got:
        assert r.row.doc_id == r.doc_id
        by.setdefault(r.source, []).append(r)
    for rows in by.values():
        n, target = rows[0].source_size, rows[0].target
        epochs = int(target // n)
        left = round(target - epochs * n)
        for r in sorted(rows, key=lambda r: (key[r.doc_id], r.doc_id)):
            extra = min(r.size, left)
            left -= extra
            assert r.taken == epochs * r.size + extra


def test_mix_keeps_repeated_rows_apart(spark):
    rows = [(None, "a b c d e f g h i j", "x")] * 250 + [(7, "one two three", "y")] * 50 + [(None, None, "y")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").coalesce(3)
    got = mixing.mix(docs, Workspace(spark, "m"), carry=("text",)).collect()
    goal = mixing.targets([("x", 2500), ("y", 150)])
    assert len(got) == len(rows)
    for s in ("x", "y"):
        assert abs(sum(r.taken for r in got if r.source == s) - goal[s]) <= 1


# 7. Vector search


def test_top_k_against_brute_force(spark):
    rng = np.random.default_rng(7)
    rows = [(i, [float(x) for x in rng.normal(size=6)]) for i in range(400)] + [(i, [1.0, 0.5, 0.0, 0.0, 0.0, 0.0]) for i in range(400, 500)]
    rows += [(900, None), (901, [None] * 6), (902, [math.nan] * 6), (903, [math.inf] * 6), (904, [1.0, 2.0]), (950, [1e7, 0.0, 0.0, 0.0, 0.0, 1.0]), (None, [1.0] * 6)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").select("vec_id", vector_search.quantise(F.col("embedding")).alias("v"))
    got = {}
    for r in vector_search.top_k(df, df.where("vec_id % 50 = 0"), vector_block=64, query_block=3).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    ints = {i: [math.floor(256 * x) for x in v] for i, v in rows if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)}
    for q in [i for i in ints if i % 50 == 0]:
        best = sorted((-sum(a * b for a, b in zip(ints[q], ints[i])), i) for i in ints if i != q and len(ints[i]) == len(ints[q]))[:5]
        assert sorted(got[q]) == [(k + 1, i, -s) for k, (s, i) in enumerate(best)]
    assert vector_search.top_k(df.where("false"), df.where("false")).count() == 0


def test_top_k_of_copies_and_repeated_ids(spark):
    rng = np.random.default_rng(9)
    some = [[int(x) for x in rng.integers(-300, 300, 5)] for _ in range(12)]
    rows = [(i, some[i % 12]) for i in range(600)] + [(50, some[3])] * 9 + [(50, some[4]), (7, some[5]), (7, some[6])] + [(i, [1 << 40, 0, 0, 0, -5]) for i in (601, 602)]
    df = spark.createDataFrame(rows, "vec_id long, v array<long>").repartition(5)
    got = {}
    for r in vector_search.top_k(df, df.where("vec_id % 50 = 0"), vector_block=5, query_block=2).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    asked = {(i, tuple(v)) for i, v in rows if i % 50 == 0}
    for q in {i for i, _ in asked}:
        best = sorted((-sum(a * b for a, b in zip(u, v)), i) for p, u in asked if p == q for i, v in rows if i != q)
        assert sorted(got[q]) == [(k + 1, i, -s) for k, (s, i) in enumerate(best[:5])]


def test_queries_go_down_a_tree_together():
    rng = np.random.default_rng(10)
    v = rng.integers(-40, 40, (700, 3))
    ids, rows = rng.permutation(700), np.arange(700).astype(object)
    asked = np.vstack([v[:50] * 1000, v[50:90], np.zeros((1, 3), np.int64)])
    for at in (v, v * (1 << 26)):  # the larger ones don't fit floating point
        best = vector_search.Best(len(asked), 6)
        for lo in (0, 350):
            vector_search.MTree(at[lo : lo + 350], page=16).search_many(asked, best, ids[lo : lo + 350], rows[lo : lo + 350])
        for q, query in enumerate(asked.tolist()):
            want = sorted((-sum(a * b for a, b in zip(query, u)), i) for u, i in zip(at.tolist(), ids.tolist()))[:6]
            assert list(zip((-best.score[q]).tolist(), best.first[q].tolist())) == want
            assert [ids[r] for r in best.rows[q]] == best.first[q].tolist()


def test_m_tree_skips_distances():
    rng = np.random.default_rng(8)
    v = (rng.normal(size=(20, 4)) * 300).repeat(100, axis=0).astype(np.int64) + rng.integers(-3, 4, (2000, 4))
    tree = vector_search.MTree(v)
    tree.search(v[5], 5, np.arange(2000), 5)
    assert tree.computed < 1000


# 8. Token counts


def test_counts_against_greedy(spark, odd, vocab):
    known = {p for p, k in zip(vocab.pieces, vocab.kinds) if k == "piece"}

    def greedy(word):
        s, n = b" " + word.encode(), 0
        while s:
            k = next((k for k in range(min(len(s), 30), 0, -1) if s[:k] in known), 0)
            if not k:
                return 1
            s, n = s[k:], n + 1
        return n

    docs = spark.read.parquet(f"{SF}/documents.parquet").select("text").unionByName(odd.select("text"))
    for r in token_counts.count_tokens(docs).collect():
        words = WORD.findall(r.text or "")
        assert r.n_words == len(words) and r.n_tokens == sum(map(greedy, words))


# 9. WARC


def test_warc_round_trip(spark):
    rows = [(5, "u\r\n", "same"), (3, None, "same"), (9, "u", None), (1, "u", ""), (4, "u", "é" * 100_000), (3, None, "same"), (None, "u", "same"), (7, "u", "x\r\n\r\ny")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload", F.lit("clash"))
    archives = warc.write_archives(pages, Workspace(spark, "w"), archive_bytes=5000)
    got = [(r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in warc.read_archives(archives).collect()]
    least = {}
    for i, _, h in rows:
        if i is not None:
            least[h or ""] = min(i, least.get(h or "", i))
    want = []
    for i, _, h in rows:
        raw = (h or "").encode()
        first = least[h or ""]
        revisit = i is not None and i != first
        want.append((i, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "revisit" if revisit else "response", first if revisit else None))
    order = lambda x: sorted(x, key=str)
    assert order(got) == order(want)
    assert warc.read_archives(warc.write_archives(pages.where("false"), Workspace(spark, "w"))).count() == 0


def test_warc_keeps_pages_that_share_ids(spark, tmp_path):
    rows = [(1, "http://a/", f"<p>{k}</p>" * 50) for k in range(40)] + [(None, None, "x"), (None, "u", None)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(4)
    archives = warc.write_archives(pages, Workspace(spark, "w"), archive_bytes=700)
    names = [r.name for r in archives.select("name").collect()]
    assert len(names) == len(set(names)) > 10
    assert warc.export(archives, str(tmp_path)).count() == len(names)
    for read in (warc.read_files(spark, f"file://{tmp_path}"), warc.read_mounted(spark, str(tmp_path))):
        assert sorted(bytes(r.payload) for r in read.collect()) == sorted((h or "").encode() for _, _, h in rows)
        assert warc.unmatched_revisits(read).count() == 0


def test_warc_files_and_damage(spark, tmp_path):
    pages = spark.createDataFrame([(1, "u", "a"), (2, "v", "b")], "page_id long, url string, html string")
    archives = warc.write_archives(pages, Workspace(spark, "w"))
    assert warc.export(archives, str(tmp_path)).count() >= 1
    assert {bytes(r.payload) for r in warc.read_files(spark, str(tmp_path)).collect()} == {b"a", b"b"}
    body = bytes(archives.first().body)
    for bad in (body[:-3], body[:20] + b"xx" + body[22:]):
        with pytest.raises(ValueError):
            list(warc.read_archive(bad))


# 10. Near-duplicates


def _shingles(text):
    words = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return frozenset(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))) if words else frozenset()


def _components(rows, percent):
    sets = {i: _shingles(t) for i, t in rows}
    ids = sorted(sets)
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in itertools.combinations(ids, 2):
        x, y = sets[a], sets[b]
        if x and y and 100 * len(x & y) >= percent * len(x | y):
            p, q = sorted((find(a), find(b)))
            root[q] = p
    return {i: (len(sets[i]), find(i), find(i) == i) for i in ids}


@pytest.mark.parametrize("percent", [85, 80])
def test_near_duplicates_against_brute_force(spark, percent):
    rng = random.Random(9)
    rows = [(i, t) for i, t in enumerate(ODD_TEXTS)]
    base = [f"w{rng.randint(0, 5000)}" for _ in range(200)]
    passage = " ".join(f"p{k}" for k in range(60))
    for _ in range(160):
        words = list(base)
        for _ in range(rng.randint(0, 8)):
            words[rng.randrange(200)] = f"e{rng.randint(0, 10**6)}"
        rows.append((len(rows), " ".join(words)))
    for _ in range(60):
        rows.append((len(rows), passage + " " + " ".join(f"q{rng.randint(0, 10**6)}" for _ in range(rng.randint(5, 300)))))
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("rep", F.lit(1)).withColumn("component", F.lit("x"))
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in near_dup.link(df, Workspace(spark, "n"), percent).collect()}
    assert got == _components(rows, percent)


def test_near_duplicate_tiles_keep_components(spark):
    rng = random.Random(10)
    base = [f"w{k}" for k in range(100)]
    rows = []
    for i in range(150):
        words = list(base)
        for _ in range(rng.randint(0, 4)):
            words[rng.randrange(100)] = f"e{rng.randint(0, 10**6)}"
        rows.append((i, " ".join(words)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    ws = Workspace(spark, "n")
    classes = near_dup.sketch(df).groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"), F.first("minima").alias("minima"), F.first("sig").alias("sig"))
    posted = [{tuple(r) for r in near_dup.prefix_posts(classes, ws, 37, 16).collect()}]
    limit, near_dup.BROADCAST_VALUES = near_dup.BROADCAST_VALUES, 0
    try:
        posted.append({tuple(r) for r in near_dup.prefix_posts(classes, ws, 37, 16).collect()})
    finally:
        near_dup.BROADCAST_VALUES = limit
    assert posted[0] == posted[1] and any(p[3] for p in posted[0])
    links = near_dup.candidate_links(classes, ws, 85, tile_rows=16)
    members = near_dup.components(links, ws, "c").join(classes.select("rep", "n"), F.col("node") == F.col("rep")).select("rep", "n", "component")
    found = near_dup.components(near_dup.confirm(df, members, ws, 85, 5, "doc_id", "text", tile_sets=16), ws, "d")
    label = {r.node: r.component for r in found.collect()}
    want = _components(rows, 85)
    reps = [r.rep for r in classes.select("rep").collect()]
    assert {i: label.get(i, i) for i in reps} == {i: want[i][1] for i in reps}


def test_components_of_a_long_chain(spark):
    links = spark.range(300).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    got = near_dup.components(links, Workspace(spark, "c"), "chain")
    assert got.count() == 301 and {r.component for r in got.collect()} == {0}
    near_dup_limit, near_dup.BROADCAST_LINKS = near_dup.BROADCAST_LINKS, 1
    try:
        assert near_dup.components(links, Workspace(spark, "c"), "chain").where("component = 0").count() == 301
    finally:
        near_dup.BROADCAST_LINKS = near_dup_limit


def test_near_duplicates_of_nothing(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert near_dup.link(df, Workspace(spark, "n")).count() == 0


# Pipeline


def test_pipeline_stages(spark):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = cp.run(spark, SF)
    assert out.count() > 0 and {"doc_id", "n_pieces", "piece_ids"} <= set(out.columns)
    kept = cp.language_id(spark, docs, SF)
    assert set(kept.columns) == set(docs.columns)
    near = cp.near_duplicates(spark, kept, SF)
    rows = [(r.doc_id, r.text) for r in kept.collect()]
    want = {i for i, (_, _, k) in _components(rows, 80).items() if k}
    assert {r.doc_id for r in near.collect()} == want
    clean = cp.personal_data(spark, near, SF)
    assert all(not _plain_spans(r.text) for r in clean.collect()) and clean.count() == len(want)
    sizes = {r.doc_id: len(WORD.findall(r.text or "")) for r in clean.collect()}
    taken = {r.doc_id: r.taken for r in mixing.mix(clean, Workspace(spark, "m")).collect()}
    got = {}
    for r in cp.source_mix(spark, clean, SF).collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + len(WORD.findall(r.text))
    assert got == {i: t for i, t in taken.items() if t} and all(t <= 2 * sizes[i] for i, t in got.items())


def test_pipeline_on_odd_rows(spark, odd):
    import corpus_pipeline as cp

    docs = odd.select("doc_id", "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))
    for frame in (docs, docs.where("false")):
        for _, stage in cp.STAGES:
            frame = Workspace(spark, "s").write(stage(spark, frame, SF), "x")
        frame.count()
