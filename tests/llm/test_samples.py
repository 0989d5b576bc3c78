"""Samples of the fits: copies count once, whole texts are read, rare languages stay."""

import tracemalloc

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from walkstream.llm import langid, mixing, pii, vocab
from walkstream.llm import textkernel as tk


def test_copies_do_not_fill_the_personal_data_fit(spark):
    texts = [f"call +49 30 {123400 + i} or mail a{i}@b.de {i} times" for i in range(320)]
    one = spark.createDataFrame([(t,) for t in texts], "text string").coalesce(4)
    first = one.orderBy(F.xxhash64("text")).first().text
    copies = one.unionByName(spark.createDataFrame([(first,)] * 400, "text string").coalesce(4))
    assert pii.fit(copies, epochs=1) == pii.fit(one, epochs=1)


def test_the_end_of_a_long_text_teaches(spark):
    late = "word " * 6_000 + "write to a@b.de"
    assert any(k.startswith("email|") for k in pii.fit(spark.createDataFrame([(late,)], "text string")))
    digits = "7 " * 100 + "a@b.de"
    assert any(k == "email" for _, gold in pii.fit_cases(digits) for _, _, k in gold)
    assert ("x1 y2 +49 30 123456", [(0, 1, "O"), (1, 2, "O"), (2, 5, "phone")]) in pii.fit_cases("x1 y2 +49 30 123456 z3", fit_chunks=3)


def test_language_fit_takes_copies_once_and_all_of_a_rare_language(spark):
    h = F.pmod(F.xxhash64("text"), F.lit(1 << 30))
    own = spark.range(12_000).select(F.concat(F.lit("the house number "), F.col("id").cast("string")).alias("text"), F.lit("en").alias("lang"))
    first = own.orderBy(h).first().text
    copies = spark.range(4_000).select(F.lit(first).alias("text"), F.lit("en").alias("lang"))
    last = spark.range(40).select(F.concat(F.lit("ein kleines haus "), F.col("id").cast("string")).alias("text"), F.lit("de").alias("lang")).orderBy(h.desc()).limit(1)
    rows = own.unionByName(copies).unionByName(last).coalesce(4)
    langs, sample = langid.fit_sample(rows)
    got = sample.collect()
    assert langs == ("de", "en") and len(got) == len({r._text for r in got})
    assert sum(r._lang == "de" for r in got) == 1 and abs(len(got) - 4_000) < 5 * 4_000**0.5
    model = langid.train(rows, rounds=1)
    assert model.log_probs[:, 0].max() - model.log_probs[:, 0].min() > 1


def test_source_mix_meets_targets_with_repeated_rows(spark):
    import corpus_pipeline as cp

    rows = [(None, "a b c d e f g h i j", "en", "x", 19)] * 200 + [(3, "one two", "en", "y", 7)] * 100
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").coalesce(3)
    goal = mixing.targets([("x", 2000), ("y", 200)])
    got = {}
    for r in cp.source_mix(spark, docs, "").collect():
        got[r.source] = got.get(r.source, 0) + len(r.text.split())
    assert all(abs(got[s] - goal[s]) <= 1 for s in goal)


def test_language_id_holds_little_of_a_large_batch():
    pieces = vocab.load_pieces()
    trie = langid._trie(pieces)
    model = langid.LanguageModel(("a", "b"), pieces, np.random.default_rng(3).normal(-9, 1, (len(pieces.pieces), 2)))
    texts = pd.Series([" ".join(f"word{k}of{d}" for k in range(2_000)) for d in range(200)])
    some = texts.iloc[:4].reset_index(drop=True)
    langid.predict_texts(model, some)
    tracemalloc.start()
    name, score = langid.predict_texts(model, texts)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 80 << 20
    alone = langid.predict_texts(model, some)
    assert list(name[:4]) == list(alone[0]) and np.allclose(score[:4], alone[1])
    assert langid._trie(pieces) is trie
    tk.forget()
    assert langid._trie(pieces) is not trie
