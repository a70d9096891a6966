"""The corpus pipeline: toxicity, near-duplicates, benchmark passages, personal data, tokens.

Every stage takes (spark, docs, sf_dir) and works on all that the one before kept.  All but the last return the columns of
documents.  Rows whose text is null count as empty texts; repeated rows are reduced by the near-duplicate stage.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from seqsearch.llm import decontaminate, pieces, pii, simhash, toxicity
from seqsearch.llm.common import discard, shared_dir
from seqsearch.llm.queries import KEY, VOCABULARY


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go.  It is fitted on the labelled documents that are not held out."""
    model = toxicity.fit_on(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.drop_toxic(docs, model)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the smallest id stays of each group: five-word shingles, similarity 0.8 or more; candidates by SimHash and
    by bands of minima."""
    return simhash.keep_first_similar(docs)


def drop_benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a test item stands go."""
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pseudonymise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal values are replaced in the texts."""
    return pii.with_pseudonyms(docs, KEY)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, round_trip, ids) of every document that stayed."""
    return pieces.encode_decode(docs, pieces.load_vocabulary(VOCABULARY))


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_near_duplicates),
    ("benchmark_decontamination", drop_benchmark_passages),
    ("pseudonyms", pseudonymise),
    ("sentencepiece", encode),
]

#: SQL can't express zstandard, XXH64 or Feistel networks; tests/llm compares with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; each one's rows are written as Parquet to the shared folder and read again.

    A stage's copy is deleted when the next one's is written; the last copy stays, since the result is computed from it.
    """
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs.write.parquet(f"{folder}/{k}-{name}")
            docs = spark.read.schema(docs.schema).parquet(f"{folder}/{k}-{name}")
            discard(before)
            before = docs
    return docs
