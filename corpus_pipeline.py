"""A corpus pipeline of five stages, each over all that its predecessor kept.

Documents that the toxicity classifier or the quality rules reject go, of each group of near copies the
document with the smallest doc_id stays, documents that hold a benchmark window go, and what is
left is encoded.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from flipmine.llm import bpe_replay, decontaminate, jaccard_join, risk_rules, toxicity
from flipmine.llm.common import stored

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose own text is not predicted to be toxic; the classifier learns from the labelled rows of ``docs``."""
    model = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.scored(docs, model, tuple(COLUMNS)).where("predicted = 0").select(COLUMNS)


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose own text passes the base rules and the risk-controlled cutoffs."""
    return risk_rules.judged(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), tuple(COLUMNS)).where("kept").select(COLUMNS)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near copies (five words, similarity 0.8): its smallest doc_id.

    Of rows that repeat a doc_id the smallest stays; rows without a doc_id go if they are linked to a named
    document, and else one of each group of them stays. Rows without any word stay, one for each doc_id.
    """
    return jaccard_join.one_of_each(docs, COLUMNS, size=5, percent=80)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows in whose own text no benchmark window occurs; a null or empty text has none."""
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, number of tokens, and digests of ids and decoded bytes of every row; a null text is an empty one."""
    return bpe_replay.digests(docs, RANKS, public_tokenizers.PATTERN)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", drop_toxic),
    ("quality rules", keep_quality),
    ("n-gram Jaccard join", one_of_each_group),
    ("benchmark decontamination", drop_contaminated),
    ("byte-level BPE", encode),
]
#: A fitted classifier and a vocabulary's merges are beyond SQL; tests hold the pipeline against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = stored(docs, f"stage-{i}-{name.replace(' ', '-')}")
    return docs
