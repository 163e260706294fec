"""The corpus pipeline: classify, deduplicate, decontaminate, mix, write tokens. Counted as part of the llm subpackage.

Each stage takes the documents that the stage before has kept, as (spark, docs, sf_dir), and returns a DataFrame; all but
the last return the columns of documents.

Other columns of docs are handed on. An empty table goes through every stage and gives an empty one. What stages make of
nulls, ties and repeated rows is stated at each.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from twigrank.llm import decontaminate, mixing, near_dedup, quality_classifier, token_output
from twigrank.llm.common import materialize
from twigrank.llm.queries import table, vocabulary


def classify_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose tail probability of a good grade is a half at least, each row by its own text; null and empty texts are
    texts without words. Rows with equal texts go or stay together. Without ratings the shares of the grades decide."""
    return quality_classifier.keep_good(docs, quality_classifier.fit(docs, table(spark, sf_dir, "labels")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: five words, similarity 0.8; that of the smallest doc_id. Of rows that
    share a doc_id one stays. Null and empty texts have no duplicates and stay, as do rows with a null doc_id."""
    return near_dedup.keep_one(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any window of a benchmark item. Rows that share a doc_id, or have none, go together; null and empty
    texts stay. Benchmark rows with a null id or text are ignored."""
    return decontaminate.keep_clean(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix by source weights; a document is there once for each pass that takes some of it. Null and wordless texts are
    absent; a null source is one source, the last; repeated rows are documents of their own."""
    return mixing.mixed_documents(docs)


def write_token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files, read back: a row for each document of the mix, in ascending order of doc_id, nulls first, rows that share
    an id by a hash of their text; a null text is the end id alone."""
    path = token_output.tokens_in_shared_folder(docs, token_output.TokenFormat(vocabulary()))
    return token_output.read_tokens(spark, path)


STAGES = [
    ("quality_classifier", classify_quality),
    ("minhash_near_dedup", drop_near_duplicates),
    ("benchmark_decontamination", drop_contaminated),
    ("source_mixing", mix_sources),
    ("token_id_output", write_token_ids),
]

#: No SQL: the classifier, the mix's draws and the tokenizer are beyond it. tests/llm/test_llm_pipeline.py holds each stage of
#: one run() against brute force on what the stage was given.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialize(docs)
    return docs
