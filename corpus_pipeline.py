"""A corpus from raw documents to token ids, in five stages. Each works on all rows that the one before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nbrmatch.llm import bpe, linededup, minhash, mixing, quality
from nbrmatch.llm.common import documents, labels, materialise
from nbrmatch.llm.queries import BPE_FILE


def line_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents whose line quality is under 0.3. The model learns from labelled documents of the raw table."""
    model = quality.train(documents(spark, sf_dir), labels(spark, sf_dir))
    return quality.score(docs, model, out="_score").where(quality.keeps("_score")).drop("_score")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates (likeness 0.8 or more) the document of the least id stays."""
    return minhash.keep_one(docs, percent=80)


def repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of any length that an earlier document or place has are cut out of the text, and longer sentences."""
    return linededup.clean(docs)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of small domains are repeated until the expected tokens meet the targets; none is dropped."""
    return mixing.mix(docs, labels(spark, sf_dir))


def byte_bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each text, and whether they decode to it. The last stage of a long job: its memo tables are kept small."""
    import public_tokenizers

    return bpe.checked(docs, bpe.load_ranks(public_tokenizers.path(BPE_FILE)), public_tokenizers.PATTERN, max_states=40_000, max_words=100_000, max_chunks=30_000)


STAGES = [("line_quality", line_quality), ("near_duplicates", near_duplicates), ("repeated_lines", repeated_lines), ("source_mix", source_mix), ("byte_bpe", byte_bpe)]

#: Classifiers and rates are learnt, which SQL can't say; tests hold each stage against a plain version of it.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir).select("doc_id", "lang", "source", F.size("ids").cast("long").alias("n_tokens"), "ids", "round_trip")
