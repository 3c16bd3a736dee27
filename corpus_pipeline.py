"""A cleaning pipeline over ``documents``: toxicity, near copies, repeated passages, secrets, packing.

Each stage takes (spark, docs, sf_dir) and returns a table that ``run`` writes as Parquet and reads again for the next one.  All but the
last return the columns of ``documents``.  SQL cannot express the stages (a trained score, components, tokenising), so there is no
ORACLE_SQL; ``tests/llm/test_pipeline.py`` compares each stage with a plain version.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsplit.llm import packing, recompress, secrets, setjoin, storage, toxicity

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
ORACLE_SQL = None


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score stays below the threshold; the lexicon is learnt from the labelled ones."""
    storage.modest_batches(spark)
    docs = docs.select(*COLUMNS)
    lexicon = toxicity.train(docs, storage.table(spark, sf_dir, "labels"))
    return toxicity.score_documents(docs, lexicon).where(F.col("toxic_score") < toxicity.THRESHOLD).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of least id of each group that similarity 0.8 of five-word shingles links."""
    return setjoin.keep_one(docs, setjoin.Rule(5, 80, 100)).select(*COLUMNS)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the words of 35-word windows that occur again anywhere."""
    return recompress.remove_repeats(docs).select(*COLUMNS)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with a mark in place of each secret."""
    return secrets.redact(docs).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document stands in sequences of 2048 tokens."""
    import public_tokenizers

    with open(public_tokenizers.path("byte_bpe_50k.json"), "rb") as f:
        vocabulary = f.read()
    return packing.pack_pieces(packing.token_pieces(docs, vocabulary, public_tokenizers.PATTERN))


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_jaccard_join", drop_near_copies),
    ("substring_dedup", drop_repeated_passages),
    ("secret_scan", redact_secrets),
    ("best_fit_packing", pack),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = storage.table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = storage.spill(stage(spark, docs, sf_dir), name)
    return docs
