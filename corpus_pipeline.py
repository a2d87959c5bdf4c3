"""Corpus pipeline: toxicity, quality, near duplicates, secrets, packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again as
the next stage's ``docs``. A stage works on all that its predecessor kept. All but the last return the columns of
``documents``; the last returns the placed pieces of the packed corpus.

Rows with nulls: a null text is an empty one; rows without id pass the filters by their texts; among near copies
a row with an id stays before them.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.llm.bradleyterry import fit_ranker, score_quality
from localfreq.llm.common import checkpointed, read_table, shared_folder
from localfreq.llm.packing import pack_pieces, token_pieces
from localfreq.llm.secrets import redact
from localfreq.llm.simjoin import keep_one
from localfreq.llm.toxicity import fit_toxicity, score_toxicity

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is under 0.3; trained on the corpus's labelled rows."""
    model = fit_toxicity(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
    return score_toxicity(docs.select(*COLUMNS), model).where("toxicity_score < 0.3").select(*COLUMNS)


def drop_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose quality score reaches 0.5; trained on the corpus's labelled rows."""
    ranker = fit_ranker(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
    return score_quality(docs.select(*COLUMNS), ranker).where("quality_score >= 0.5").select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five words, similarity 0.8 or more) the document of the smallest id."""
    return keep_one(docs.select(*COLUMNS)).select(*COLUMNS)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, every secret replaced by a mark; n_chars follows the text."""
    return redact(docs.select(*COLUMNS))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The placed pieces: (doc_id, piece, start, length, ids_crc32, sequence_id, offset)."""
    return pack_pieces(checkpointed(token_pieces(docs, public_tokenizers.path("word_bpe_49k.json"))))


STAGES = [
    ("toxicity", drop_toxic),
    ("quality", drop_low_quality),
    ("near_duplicates", drop_near_duplicates),
    ("secrets", redact_secrets),
    ("packing", pack_sequences),
]

#: The stages train models and tokenise, which SQL can't express; tests compare each with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over ``documents``, each result written to the shared folder and read again."""
    docs = read_table(spark, sf_dir, "documents")
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
