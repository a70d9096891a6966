"""The index on disk: sequences and postings in batches, each of which counts once it is committed.

``data/<batch>/sequences`` and ``data/<batch>/postings`` are written first, and the empty file ``commits/<batch>`` last.  Readers
list the commits, so a batch that a crash left half written is not seen, and writing it again replaces what is there.
Postings are sorted by word within files, so that row groups are skipped by word.
"""

from __future__ import annotations

import uuid

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import POSTING, SEQ
from .histogram import norm_of, word_counts

STORED = SEQ + ", norm2 bigint"


def _files(spark: SparkSession, path: str):
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark._jsc.hadoopConfiguration()), where


def committed(spark: SparkSession, path: str) -> list[str]:
    """The names of the batches that count."""
    fs, where = _files(spark, f"{path}/commits")
    return sorted(f.getPath().getName() for f in fs.listStatus(where)) if fs.exists(where) else []


def _commit(spark: SparkSession, path: str, batch: str) -> None:
    fs, where = _files(spark, f"{path}/commits/{batch}")
    fs.create(where, True).close()


def write_batch(sequences: DataFrame, path: str, batch: str, buckets: int = 16) -> None:
    """Write a batch and commit it; ids must be new to the index.  The postings are made from the sequences as written."""
    spark, folder = sequences.sparkSession, f"{path}/data/{batch}"
    rows = sequences.withColumn("norm2", norm_of("tokens")).select(*[c.split()[0] for c in STORED.split(", ")])
    rows.write.mode("overwrite").parquet(f"{folder}/sequences")
    kept = spark.read.schema(STORED).parquet(f"{folder}/sequences")
    word_counts(kept).repartition(buckets, "word").sortWithinPartitions("word").write.mode("overwrite").parquet(f"{folder}/postings")
    _commit(spark, path, batch)


def build_index(sequences: DataFrame, path: str, buckets: int = 16, batch: str | None = None) -> None:
    """Add sequences whose ids the index does not hold."""
    write_batch(sequences, path, batch or uuid.uuid4().hex, buckets)


def _read(spark: SparkSession, path: str, part: str, schema: str) -> DataFrame:
    paths = [f"{path}/data/{b}/{part}" for b in committed(spark, path)]
    return spark.read.schema(schema).parquet(*paths) if paths else spark.createDataFrame([], schema)


def _removed(spark: SparkSession, path: str) -> DataFrame | None:
    fs, where = _files(spark, f"{path}/removed")
    return spark.read.schema("seq_id bigint").parquet(f"{path}/removed").distinct() if fs.exists(where) else None


def merge_index(spark: SparkSession, path: str, new: DataFrame, buckets: int = 16, batch: str | None = None) -> int:
    """Add the sequences that the index does not hold yet; returns how many.  A batch name that is committed is not merged again."""
    name = batch or uuid.uuid4().hex
    if name in committed(spark, path):
        return 0
    have = _read(spark, path, "sequences", STORED).select("seq_id")
    write_batch(new.join(have, "seq_id", "left_anti").dropDuplicates(["seq_id"]), path, name, buckets)
    return spark.read.schema(STORED).parquet(f"{path}/data/{name}/sequences").count()


def remove_from_index(spark: SparkSession, path: str, ids: DataFrame) -> None:
    """Mark sequences as removed: readers leave them out, compaction drops them."""
    ids.select("seq_id").write.mode("append").parquet(f"{path}/removed")


def read_index(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(postings, sequences with their squared lengths) of the committed batches, without what was removed."""
    postings, rows = _read(spark, path, "postings", POSTING), _read(spark, path, "sequences", STORED)
    gone = _removed(spark, path)
    return (postings, rows) if gone is None else (postings.join(gone, "seq_id", "left_anti"), rows.join(gone, "seq_id", "left_anti"))


def compact_index(spark: SparkSession, path: str, to: str, buckets: int = 16) -> None:
    """Rewrite the index as one batch without removed sequences."""
    write_batch(read_index(spark, path)[1].drop("norm2"), to, "compacted", buckets)


class Retriever:
    """Queries against a stored index, again and again; ``persist`` keeps what they read."""

    def __init__(self, spark: SparkSession, path: str) -> None:
        self.postings, self.sequences = read_index(spark, path)
        self._size: int | None = None

    def persist(self) -> Retriever:
        self.postings, self.sequences = (t.persist(StorageLevel.MEMORY_AND_DISK) for t in (self.postings, self.sequences))
        return self

    def unpersist(self) -> None:
        for t in (self.postings, self.sequences):
            t.unpersist()

    def size(self) -> int:
        """Sequences in the index, counted once."""
        if self._size is None:
            self._size = self.sequences.count()
        return self._size

    def retrieve(self, queries: DataFrame, plan=None, periodic_only: bool = False) -> DataFrame:
        """RANKED, as ``plans.retrieve.retrieve`` over the stored sequences."""
        from ..plans.retrieve import RetrievalPlan, retrieve

        plan = plan or RetrievalPlan(policy="capped")
        return retrieve(queries, self.sequences, plan, self.size(), periodic_only, postings=self.postings)
