"""A corpus pipeline of five of the training-data operators.

Each stage takes (spark, docs, sf_dir), works on all documents that the stage before it kept, and returns the columns
of documents; the last one returns the digest of the token files. Between stages documents are a Parquet table in
the shared folder.

Every stage takes null and empty texts (they count as texts without words), very long texts (read whole), null ids (kept
by all stages that drop by id), repeated rows, an empty table (no rows come out), and other columns of any
name, which pass through with their values.
"""

from __future__ import annotations

import logging

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcloom.llm import decontamination, mixing, ngram_join, quality, token_output
from arcloom.llm.common import materialise, table


log = logging.getLogger(__name__)

#: Wanted shares of tokens that are clean, poor and toxic; the quality stage has left few of the latter.
SHARES = [0.9985, 0.001, 0.0005]


def select_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose tail probability of the best grade reaches the cut. A text without words is judged by the thresholds alone."""
    return quality.select_documents(docs, quality.train(docs, quality.graded(table(spark, sf_dir, "labels"))))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the one with the smallest id, of each class of near copies. Texts without words are no copies of each other; of rows with one id and text one stays."""
    return ngram_join.drop_near_duplicates(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark passage. Without a benchmark all stay."""
    return decontamination.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents drawn at the fitted rates, those of a short domain more than once. The classifier learns from the whole table of documents. A text without words counts no tokens and stays at its rate."""
    keyed = docs.select("doc_id", "text", F.xxhash64("text").alias("text_hash"))
    rates, said = mixing.document_rates(keyed, mixing.domain_labels(table(spark, sf_dir, "labels")), SHARES, ["doc_id", "text_hash"], learn_from=table(spark, sf_dir, "documents"))
    log.log(logging.INFO if said["converged"] else logging.WARNING, "mixing: converged %s, shares %s", said["converged"], said["shares"])
    return mixing.draw(docs, rates)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files and their digest by document. A null or empty text is its end id; null ids come first."""
    return token_output.read_digest(token_output.write_tokens(docs, token_output.tokenizer_file()))


STAGES = [("quality", select_quality), ("near_duplicates", drop_near_duplicates), ("decontamination", drop_contaminated), ("mixing", mix), ("tokens", write_tokens)]

#: Signatures, seeds, posteriors and the tokenizer cannot be said in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
