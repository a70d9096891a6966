"""Pose frames: sources, resampling, smoothing, alignment, packing, segments, weak labels."""

from __future__ import annotations

from collections.abc import Callable
from typing import Protocol

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seqsearch.functions.times import micros

from ..functions.times import let
from .io import read_table


#: First words of labels that a plan may list.
FIRST_WORDS = 5_000


class PoseSource(Protocol):
    """An exchangeable estimator of skeletons: FRAME rows (clip_id, t, pose: joints of coordinates)."""

    def load(self, spark: SparkSession, sf_dir: str) -> DataFrame: ...


class EmbeddingPoses:
    """Each vector of ``embeddings`` read as joints of coordinates; a clip is so many consecutive ids."""

    def __init__(self, frames: int = 20, coords: int = 4) -> None:
        self.frames, self.coords = frames, coords

    def load(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
        joints = F.sequence(F.lit(0), (F.size("embedding") / self.coords).cast("int") - 1)
        pose = F.transform(joints, lambda j: F.transform(F.slice("embedding", j * self.coords + 1, F.lit(self.coords)), lambda x: x.cast("double")))
        return rows.select(F.floor(F.col("vec_id") / self.frames).alias("clip_id"), (F.col("vec_id") % self.frames).cast("int").alias("t"), pose.alias("pose"))


class OrderPoses:
    """A clip for each customer, a frame for each order by date, a joint for each line number; absent joints are null."""

    def __init__(self, joints: int = 7) -> None:
        self.joints = joints

    def load(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        orders = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
        lines = read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount"])
        t = F.row_number().over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")) - 1
        frames = orders.select("o_orderkey", F.col("o_custkey").alias("clip_id"), t.cast("int").alias("t"))
        joint = lines.groupBy("l_orderkey", "l_linenumber").agg(F.avg("l_quantity").alias("x"), F.avg("l_extendedprice").alias("y"), F.avg("l_discount").alias("z"))
        rows = joint.join(frames, joint["l_orderkey"] == frames["o_orderkey"]).select("clip_id", "t", (F.col("l_linenumber") - 1).alias("joint"), F.array("x", "y", "z").alias("coord"))
        return pack_frames(rows, self.joints)


class BinaryFilePoses:
    """Recordings as files, read by an estimator: an iterator of Arrow batches (path, content) to FRAME batches."""

    def __init__(self, path: str, estimator: Callable) -> None:
        self.path, self.estimator = path, estimator

    def load(self, spark: SparkSession, sf_dir: str = "") -> DataFrame:
        from ..schemas import FRAME

        files = spark.read.format("binaryFile").load(self.path).select("path", "content")
        return files.mapInArrow(self.estimator, FRAME)


def pack_frames(rows: DataFrame, joints: int) -> DataFrame:
    """(clip_id, t, joint, coord) to FRAME; joints that are absent are null."""
    found = F.map_from_entries(F.collect_list(F.struct("joint", "coord")))
    return rows.groupBy("clip_id", "t").agg(found.alias("m")).select("clip_id", "t", F.transform(F.sequence(F.lit(0), F.lit(joints - 1)), lambda j: F.try_element_at("m", j)).alias("pose"))


def unpack_frames(frames: DataFrame) -> DataFrame:
    """FRAME to (clip_id, t, joint, coord), absent joints left out."""
    return frames.select("clip_id", "t", F.posexplode("pose").alias("joint", "coord")).where(F.col("coord").isNotNull())


def resample(df: DataFrame, key: str, time: str, value: str, hz: float, how: str = "linear") -> DataFrame:
    """(key, k, t, value) on the grid first time + k / hz, up to the last time; ``time`` in seconds, or a timestamp.

    linear: between the neighbours; last: the latest value at or before.  Of equal times the last by value counts.
    """
    seconds = F.col(time).cast("double") if dict(df.dtypes)[time] in ("double", "float") else micros(time) / 1_000_000.0
    points = df.select(F.col(key).alias("key"), seconds.alias("t"), F.col(value).cast("double").alias("v")).groupBy("key", "t").agg(F.max("v").alias("v"))
    w = Window.partitionBy("key").orderBy("t")
    span = points.withColumn("t1", F.lead("t").over(w)).withColumn("v1", F.lead("v").over(w)).withColumn("t0", F.min("t").over(Window.partitionBy("key")))
    # the grid points in [t, t1): each source row makes its own, so nothing is joined
    first = F.ceil(F.round((F.col("t") - F.col("t0")) * hz, 6))
    last = F.when(F.col("t1").isNull(), F.floor(F.round((F.col("t") - F.col("t0")) * hz, 6))).otherwise(F.ceil(F.round((F.col("t1") - F.col("t0")) * hz, 6)) - 1)
    grid = span.where(last >= first).withColumn("k", F.explode(F.sequence(first.cast("bigint"), last.cast("bigint"))))
    at = F.col("t0") + F.col("k") / hz
    share = (at - F.col("t")) / (F.col("t1") - F.col("t"))
    between = F.when(F.col("t1").isNull() | (how == "last"), F.col("v")).otherwise(F.col("v") + (F.col("v1") - F.col("v")) * share)
    return grid.select(F.col("key").alias(key), "k", at.alias("t"), between.alias(value))


def smooth(df: DataFrame, key: str, order: list[str], column: str, radius: int = 1, kernel: str = "mean") -> DataFrame:
    """Append ``smooth``: mean, median, or (exp) weights halving with distance, over ``radius`` rows on both sides."""
    by = Window.partitionBy(key).orderBy(*order)
    near = by.rowsBetween(-radius, radius)
    if kernel == "mean":
        value = F.avg(column).over(near)
    elif kernel == "median":
        value = F.percentile(column, F.lit(0.5)).over(near)
    else:
        total, weight = F.lit(0.0), F.lit(0.0)
        for d in range(-radius, radius + 1):
            x = (F.lag(column, -d) if d < 0 else F.lead(column, d)).over(by) if d else F.col(column)
            x = F.lag(column, -d).over(by) if d < 0 else x
            part = 0.5 ** abs(d)
            total, weight = total + F.coalesce(x * part, F.lit(0.0)), weight + F.when(x.isNotNull(), part).otherwise(0.0)
        value = total / weight
    return df.withColumn("smooth", value)


def align_poses(frames: DataFrame, root: int = 0, center: bool = True, scale: str = "none", start: str = "none") -> DataFrame:
    """Poses relative to the root joint (center), over their root-mean-square length (scale 'unit'), minus the clip's first pose
    (start 'first')."""
    def minus(p: Column, q: Column) -> Column:
        return F.zip_with(p, q, lambda a, b: a - b)

    out = frames
    if center:
        out = out.withColumn("pose", F.transform("pose", lambda p: minus(p, F.get("pose", root))))
    if scale == "unit":
        squares = F.aggregate(F.flatten(F.filter("pose", lambda p: p.isNotNull())), F.lit(0.0), lambda s, x: s + x * x)
        size = F.sqrt(squares / F.size(F.filter("pose", lambda p: p.isNotNull())))
        out = out.withColumn("size", size).withColumn("pose", F.transform("pose", lambda p: F.transform(p, lambda x: F.when(F.col("size") > 0, x / F.col("size")).otherwise(x)))).drop("size")
    if start == "first":
        first = F.first("pose").over(Window.partitionBy("clip_id").orderBy("t").rowsBetween(Window.unboundedPreceding, Window.currentRow))
        out = out.withColumn("first", first).withColumn("pose", F.zip_with("pose", "first", minus)).drop("first")
    return out


def segment(frames: DataFrame, length: int) -> DataFrame:
    """Append ``segment``: the number of the clip of fixed length within the recording; t is counted anew in each."""
    return frames.withColumn("segment", F.floor(F.col("t") / length)).withColumn("t", (F.col("t") % length).cast("int"))


def segment_by_gap(df: DataFrame, key: str, time: str, order: list[str], gap: float) -> DataFrame:
    """Append ``segment``: 0, 1, ... within the key, a new one where more than ``gap`` seconds passed."""
    by = Window.partitionBy(key).orderBy(*order)
    passed = (micros(time) - F.lag(micros(time)).over(by)) / 1_000_000.0
    return df.withColumn("segment", F.sum(F.coalesce((passed > gap).cast("int"), F.lit(0))).over(by))


def map_labels(items: DataFrame, dictionary: DataFrame, mode: str = "contains", min_overlap: float = 0.5, item_id: str = "doc_id", text: str = "text", label_id: str = "item_id", label: str = "text", words: int = 4) -> DataFrame:
    """(item, label): each text's canonical label, by what its text holds; ties: the longest label, then the lowest id.

    Texts and labels meet on shared words (token_overlap) or on the label's first ``words`` words in a row (contains); only
    pairs that meet are compared.  The dictionary is small by definition; Spark broadcasts it if its size allows.
    """
    def split(c: str) -> Column:
        return F.filter(F.split(F.lower(F.coalesce(c, F.lit(""))), "[^\\p{L}\\p{N}]+"), lambda w: w != "")

    names = dictionary.select(F.col(label_id).alias("label"), split(label).alias("lw")).where(F.size("lw") > 0)
    if mode == "contains":
        key = names.withColumn("k", F.least(F.size("lw"), F.lit(words))).withColumn("key", F.concat_ws(" ", F.slice("lw", F.lit(1), F.col("k"))))

        lengths = sorted(r["k"] for r in key.select("k").distinct().collect())  # at most ``words`` numbers
        # a run of words is put together only where a label may begin, if the first words of labels are few enough to list
        firsts = [r["w"] for r in names.select(F.get("lw", 0).alias("w")).distinct().limit(FIRST_WORDS + 1).collect()]

        def gram(tw: Column, k: int):
            return lambda i: F.concat_ws(" ", F.slice(tw, i, k))

        def places(tw: Column, last: Column) -> Column:
            every = F.sequence(F.lit(1), last)
            return F.filter(every, lambda i: F.get(tw, i - 1).isin(firsts)) if len(firsts) <= FIRST_WORDS else every

        def starts(tw: Column) -> Column:
            n = F.size(tw)
            parts = [F.array().cast("array<string>")] + [F.when(n >= k, F.array_distinct(F.transform(places(tw, n - (k - 1)), gram(tw, k)))).otherwise(F.array().cast("array<string>")) for k in lengths]
            return F.concat(*parts)

        # only ids and keys meet the dictionary; the text comes to the few that met
        small = key.select("label", "key", F.size("lw").alias("size"), F.concat(F.lit(" "), F.concat_ws(" ", "lw"), F.lit(" ")).alias("wanted"))
        met = items.select(F.col(item_id).alias("item"), F.explode(let(split(text), starts)).alias("key")).join(small, "key").select("item", "label", "size", "wanted").distinct()
        whole = items.select(F.col(item_id).alias("item"), F.concat(F.lit(" "), F.concat_ws(" ", split(text)), F.lit(" ")).alias("whole"))
        found = whole.join(met, "item").where(F.contains("whole", F.col("wanted"))).select("item", "label", "size")
    else:
        texts = items.select(F.col(item_id).alias("item"), split(text).alias("tw"))
        left = texts.select("item", F.explode(F.array_distinct("tw")).alias("w"))
        right = names.select("label", F.size(F.array_distinct("lw")).alias("n"), F.size("lw").alias("size"), F.explode(F.array_distinct("lw")).alias("w"))
        found = left.join(right, "w").groupBy("item", "label", "n", "size").agg(F.count("*").alias("c")).where(F.col("c") >= min_overlap * F.col("n")).select("item", "label", "size")
    return found.groupBy("item").agg(F.max_by("label", F.struct("size", -F.col("label"))).alias("label"))
