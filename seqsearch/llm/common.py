"""Helpers shared by the corpus operators: Arrow text functions, shared tables, connected components."""

from __future__ import annotations

import re
import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator
from typing import Any

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import DataType, _parse_datatype_string

import seqsearch

# Functions travel with their modules, so executors need no copy of this package.
cloudpickle.register_pickle_by_value(seqsearch)

#: Texts that a function turns into Python strings at a time.  Spark bounds a batch by its bytes (64 MB by default).
SLICE_ROWS = 500

_OWN_DIR: dict[str, str] = {}


def worker_cache() -> dict:
    """A dictionary that lives as long as the Python worker process."""
    return sys.__dict__.setdefault("_seqsearch_worker_cache", {})


def once(key: Any, build: Callable[[], Any]) -> Any:
    """Build a heavy object once in each worker process."""
    cache = worker_cache()
    if key not in cache:
        cache[key] = build()
    return cache[key]


def text_function(of: Callable[[list[str | None]], list], ddl: str) -> Callable[[Column], Column]:
    """An Arrow function from a text column to a column of type ``ddl``; it sees a list of texts at a time."""
    kind: DataType = _parse_datatype_string(ddl)
    arrow = to_arrow_type(kind)

    def apply(texts: pa.Array) -> pa.Array:
        parts = []
        for at in range(0, max(1, len(texts)), SLICE_ROWS):
            out = of(texts.slice(at, SLICE_ROWS).to_pylist())
            parts.append(out if isinstance(out, pa.Array) else pa.array(out, type=arrow))
        return parts[0] if len(parts) == 1 else pa.concat_arrays(parts)

    apply.__annotations__ = {"texts": pa.Array, "return": pa.Array}
    return F.arrow_udf(apply, returnType=kind)


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: spark.checkpoint.dir.

    Where it is unset, a session of one machine (``local[n]``) gets a folder of its own, as in tests; a cluster gets an error,
    since its executors don't see each other's disks.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors see")
        base = _OWN_DIR.setdefault("dir", tempfile.mkdtemp(prefix="seqsearch-"))
    return base.rstrip("/")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write a table to the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame | None) -> None:
    """Delete the files of a table made by :func:`materialise` that nothing reads any more."""
    if df is None:
        return
    spark = df.sparkSession
    base = shared_dir(spark)
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if folder.split(":", 1)[-1].lstrip("/").startswith(base.split(":", 1)[-1].lstrip("/")):
            path = spark._jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def finished(df: DataFrame, name: str, *used: DataFrame | None) -> DataFrame:
    """``df`` as a table of its own, and the tables that it was made from deleted: one table of an operator stays, its result."""
    out = materialise(df, name)
    for t in used:
        discard(t)
    return out


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root) for every node of ``edges``, a table in the shared folder; root is the smallest node of its component.

    Contraction: each round every node hooks onto its smallest neighbour, pointers are jumped, and the edges are
    rewritten between the new roots.  A round costs a few shuffles of what edges remain; a node with very many
    neighbours is pre-aggregated, and joins on it can be split.  Null ends and loops are ignored.
    """
    live = materialise(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"))
        .where("u is not null and v is not null and u <> v")
        .distinct(),
        "cc-edges",
    )
    labels: DataFrame | None = None
    while not live.isEmpty():
        both = live.select("u", "v").unionByName(live.select(F.col("v").alias("u"), F.col("u").alias("v")))
        first = materialise(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("p")), "cc-first")
        up = first.select(F.col("u").alias("p"), F.col("p").alias("p2"))
        far = first.select(F.col("u").alias("p2"), F.col("p").alias("p3"))
        hook = materialise(first.join(up, "p").join(far, "p2").select("u", F.col("p3").alias("p")), "cc-hook")
        if labels is None:
            new = hook.select(F.col("u").alias("node"), F.col("p").alias("root"))
        else:
            up = hook.select(F.col("u").alias("root"), F.col("p").alias("p"))
            new = labels.join(up, "root", "left").select("node", F.coalesce("p", "root").alias("root"))
        new = materialise(new, "cc-labels")
        left = hook.select("u", F.col("p").alias("pu"))
        right = hook.select(F.col("u").alias("v"), F.col("p").alias("pv"))
        after = materialise(
            live.join(left, "u")
            .join(right, "v")
            .where("pu <> pv")
            .select(F.greatest("pu", "pv").alias("u"), F.least("pu", "pv").alias("v"))
            .distinct(),
            "cc-edges",
        )
        for old in (live, labels, first, hook):
            discard(old)
        live, labels = after, new
    if labels is None:
        return live.select(F.col("u").alias("node"), F.col("v").alias("root"))
    discard(live)
    return labels


def held_out(doc_id: str) -> Column:
    """True for the quarter of the documents that no model may learn from; a null id is never held out."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 4 == 2, F.lit(False))


def pieces_of(data: bytes, width: int, step: int) -> Iterator[bytes]:
    """Windows of ``width`` bytes that cover all of ``data``; the last may be shorter."""
    last = max(1, len(data) - width + step)
    return (data[i : i + width] for i in range(0, last, step))
