"""A training corpus from `documents`: language ID, near-duplicates, personal data, source mix, SentencePiece ids.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the last return the columns of
documents. `run` writes each stage's result to the shared folder and reads it again.

Language ID drops texts without a language (null, or no letter) and those whose best language has a posterior of at most
MIN_SCORE. Of each near-duplicate group the smallest id stays; rows without words stay. Personal data are replaced by
their kind in brackets. The mix repeats and cuts documents to the words taken: whole copies first, then the first words of
one more. n_chars follows the text wherever it changes.

Defined cases, in every stage: rows are taken one by one, so repeated rows and null ids stay apart (near_duplicates alone
works by id: a row without an id, or without words, stays, and rows that share an id stay or go together); columns beyond
those of `documents` are left out; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkstream.llm import langid, mixing, near_dup, pii, sentence_pieces
from walkstream.llm.common import Workspace, load
from walkstream.session import ship

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
MIN_SCORE = 0.3
SIMILARITY = 80


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    model = langid.train(docs.select("text", "lang"))
    found = langid.identify(docs.select(*COLUMNS), model)
    return found.where((F.col("lang_pred") != "und") & (F.col("score") > MIN_SCORE)).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    found = near_dup.link(docs.select("doc_id", "text"), Workspace(spark, "near_dup"), percent=SIMILARITY)
    gone = found.where(~F.col("kept") & F.col("doc_id").isNotNull()).select("doc_id").distinct()
    return docs.select(*COLUMNS).join(gone, "doc_id", "left_anti").select(*COLUMNS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return pii.mask(docs.select(*COLUMNS), pii.fit(docs.select("text"))).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(docs.select(*COLUMNS), Workspace(spark, "mixing"), carry=COLUMNS).where("taken > 0")
    n, more = F.col("size"), F.col("taken") % F.col("size")
    copies = F.concat(F.array_repeat(F.lit(-1).cast("long"), F.floor(F.col("taken") / n).cast("int")), F.when(more > 0, F.array(more.cast("long"))).otherwise(F.array().cast("array<bigint>")))
    out = mixed.select("row.*", F.explode(copies).alias("_words"))
    words = F.array_join(F.slice(F.split(F.regexp_replace("text", r"^[\x20\x09-\x0D]+", ""), r"[\x20\x09-\x0D]+"), F.lit(1), F.col("_words").cast("int")), " ")
    out = out.withColumn("text", F.when(F.col("_words") < 0, F.col("text")).otherwise(words))
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def piece_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    coded = sentence_pieces.encode(docs.select(*COLUMNS))
    return coded.select("doc_id", "lang", "source", (F.octet_length("piece_ids") / 4).cast("long").alias("n_pieces"), "piece_ids")


STAGES = [
    ("language_id", language_id),
    ("near_duplicates", near_duplicates),
    ("personal_data", personal_data),
    ("source_mix", source_mix),
    ("piece_ids", piece_ids),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    workspace = Workspace(spark, "pipeline")
    docs = load(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = workspace.write(stage(spark, docs, sf_dir), f"{k}_{name}")
    return docs
