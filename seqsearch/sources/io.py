"""Scans and sinks."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import SEQ, validate


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None, where: str | Column | None = None) -> DataFrame:
    """A Parquet table; columns and predicates go down to the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.where(where)
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    """parquet, orc, json, csv, text or binaryFile, with an explicit schema where the format carries none."""
    if fmt in ("json", "csv") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_sequences(df: DataFrame, path: str, partition_by: Sequence[str] = (), mode: str = "errorifexists") -> None:
    """Sequences sorted by length within files, so that row groups can be skipped by length."""
    own = validate(df, SEQ) if not partition_by else df
    own.sortWithinPartitions("len").write.mode(mode).partitionBy(*partition_by).parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str = "seq_id", mode: str = "overwrite") -> None:
    """A table bucketed by a key: joins on it need no shuffle."""
    df.write.mode(mode).bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def parse_props(events: DataFrame, field: str = "k") -> DataFrame:
    """The JSON of ``props`` as a column."""
    return events.withColumn(field, F.from_json("props", f"{field} INT")[field])


def work_dir(spark: SparkSession, name: str) -> str:
    """A new folder that the driver and all executors see, under spark.checkpoint.dir.

    Where that is unset, a session of one machine (``local[n]``) gets a folder of its own, as in tests; a cluster gets an error.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors see")
        base = _OWN.setdefault("dir", tempfile.mkdtemp(prefix="seqsearch-"))
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


_OWN: dict[str, str] = {}
