"""Token sequences from the given tables, in place of a learned tokeniser; and planted variants of sequences.

Each source is one shuffle by key.  Order is total: every sort has a full tie-break.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqsearch.functions.times import micros

#: The number of each kind of event.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def as_sequences(rows: DataFrame, key: str, order: list[Column], token: Column, time: Column | None = None, class_id: Column | None = None) -> DataFrame:
    """Rows to SEQ: one sequence for each key, items in the given order."""
    names = [f"o{k}" for k in range(len(order))]
    item = F.struct(*[o.alias(n) for o, n in zip(order, names, strict=True)], token.cast("int").alias("token"), (time if time is not None else F.lit(None)).cast("double").alias("time"))
    grouped = rows.select(F.col(key).cast("bigint").alias("seq_id"), item.alias("item")).groupBy("seq_id").agg(F.array_sort(F.collect_list("item")).alias("items"))
    times = F.col("items.time") if time is not None else F.lit(None).cast("array<double>")
    cls = class_id if class_id is not None else F.col("seq_id").cast("string")
    return grouped.select("seq_id", cls.alias("class_id"), F.lit(0).alias("instance_id"), F.col("items.token").alias("tokens"), times.alias("times"), F.size("items").alias("len"))


def event_token(buckets: int = 1) -> Column:
    kind = F.create_map(*[x for k, name in enumerate(EVENT_TYPES) for x in (F.lit(name), F.lit(k))])[F.col("event_type")]
    return (kind * buckets + F.least(F.lit(buckets - 1), F.floor(F.col("value") / 20))).cast("int") if buckets > 1 else kind


def event_tokens(events: DataFrame, buckets: int = 1, timed: bool = True) -> DataFrame:
    """A sequence for each user: kind of event, by ``buckets`` of 20 of its value; times are mean gaps since the first.
    Not ``timed``: times are null, and are not sent with the items."""
    if not timed:
        return as_sequences(events, "user_id", [F.col("ts"), F.col("event_id")], event_token(buckets))
    seq = as_sequences(events, "user_id", [F.col("ts"), F.col("event_id")], event_token(buckets), micros("ts") / 1_000_000)
    first, last = F.col("times")[0], F.element_at("times", -1)
    gap = F.when((F.col("len") > 1) & (last > first), (last - first) / (F.col("len") - 1)).otherwise(F.lit(1.0))
    return seq.withColumn("times", F.transform("times", lambda t: (t - first) / gap))


def hashed(word: Column, vocabulary: int) -> Column:
    return (F.conv(F.substring(F.md5(word), 1, 4), 16, 10).cast("int") % vocabulary).cast("int")


def document_tokens(documents: DataFrame, vocabulary: int = 512) -> DataFrame:
    """A sequence for each document: its blank-separated words in lower case, hashed.  No shuffle: documents are rows."""
    text = F.trim(F.lower(F.coalesce("text", F.lit(""))))
    words = F.filter(F.split(text, r"\s+"), lambda w: w != "")
    tokens = F.transform(words, lambda w: hashed(w, vocabulary))
    return documents.select(F.col("doc_id").alias("seq_id"), F.col("lang").alias("class_id"), F.lit(0).alias("instance_id"), tokens.alias("tokens"), F.lit(None).cast("array<double>").alias("times")).withColumn("len", F.size("tokens"))


def lineitem_tokens(lineitem: DataFrame, by: str = "l_partkey", width: int = 10) -> DataFrame:
    """A sequence of quantity steps for each part or supplier, by ship date."""
    order = [F.col(c) for c in ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")]
    return as_sequences(lineitem, by, order, F.floor(F.col("l_quantity") / width))


def order_tokens(orders: DataFrame) -> DataFrame:
    """A sequence of priorities (their first digit) for each customer, by date."""
    return as_sequences(orders, "o_custkey", [F.col("o_orderdate"), F.col("o_orderkey")], F.substring("o_orderpriority", 1, 1).cast("int"))


def conversation_tokens(conversations: DataFrame, width: int = 100, buckets: int = 4) -> DataFrame:
    """A sequence for each conversation: role by length of the turn."""
    role = F.when(F.col("role") == "user", 0).when(F.col("role") == "assistant", 1).otherwise(2)
    token = role * buckets + F.least(F.lit(buckets - 1), F.floor(F.length("text") / width))
    return as_sequences(conversations, "conv_id", [F.col("turn"), F.col("role"), F.col("text")], token)


def page_tokens(pages: DataFrame, vocabulary: int = 512) -> DataFrame:
    """The parts of a URL, hashed; one row for each page."""
    parts = F.filter(F.split(F.coalesce("url", F.lit("")), "[^A-Za-z0-9]+"), lambda w: w != "")
    tokens = F.transform(parts, lambda w: hashed(w, vocabulary))
    return pages.select(F.col("page_id").alias("seq_id"), F.lit("page").alias("class_id"), F.lit(0).alias("instance_id"), tokens.alias("tokens"), F.lit(None).cast("array<double>").alias("times")).withColumn("len", F.size("tokens"))


def draw(seq: Column, instance: Column, place: Column, salt: str) -> Column:
    """A number below 65,536 that depends on class, instance, place and salt only."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", seq.cast("string"), instance.cast("string"), place.cast("string"), F.lit(salt))), 1, 4), 16, 10).cast("int")


def perturb(sequences: DataFrame, instances: int = 5, noise: int = 30, vocabulary: int = 5, kind: str = "substitute", first: int = 0) -> DataFrame:
    """Planted performances: ``instances`` noisy variants of each sequence; the sequence's id becomes the class.

    Kinds: substitute, delete (each with ``noise`` percent), duplicate (tempo doubled), rotate (phase shifted by half), crop
    (the middle half), jitter (times moved by up to half a step).  All draws are hashes: the same on every run.  An instance's id
    is a thousand times the sequence's and its own number, so ids must be below 2**53 and instances below 1,000.
    """
    k = F.explode(F.sequence(F.lit(first), F.lit(first + instances - 1))).alias("instance_id")
    rows = sequences.select(F.col("seq_id").alias("base"), "tokens", "times", "len", k)
    base, inst = F.col("base"), F.col("instance_id")
    n = F.size("tokens")
    times = F.coalesce("times", F.transform("tokens", lambda _, i: (i + 1).cast("double")))
    if kind == "substitute":
        def swap(w: Column, i: Column) -> Column:
            return F.when(draw(base, inst, i, "s") % 100 < noise, (w + 1 + draw(base, inst, i, "v") % (vocabulary - 1)) % vocabulary).otherwise(w)

        tokens = F.transform("tokens", swap)
    elif kind == "delete":
        tokens = F.filter("tokens", lambda _, i: draw(base, inst, i, "d") % 100 >= noise)
        times = F.filter(times, lambda _, i: draw(base, inst, i, "d") % 100 >= noise)
    elif kind == "duplicate":
        tokens = F.flatten(F.transform("tokens", lambda w: F.array(w, w)))
        times = F.flatten(F.transform(times, lambda t: F.array(t, t)))
    elif kind == "rotate":
        half = F.floor(n / 2).cast("int")
        tokens = F.concat(F.slice("tokens", half + 1, n), F.slice("tokens", F.lit(1), half))
    elif kind == "crop":
        a, b = F.floor(n / 4).cast("int"), F.floor(3 * n / 4).cast("int")
        tokens, times = F.slice("tokens", a + 1, b - a), F.slice(times, a + 1, b - a)
    elif kind == "jitter":
        tokens = F.col("tokens")
        times = F.array_sort(F.transform(times, lambda t, i: t + (draw(base, inst, i, "t") % 101 - 50) / 100))
    else:
        raise ValueError(kind)
    out = rows.select((base * 1000 + inst).alias("seq_id"), base.cast("string").alias("class_id"), "instance_id", tokens.alias("tokens"), times.alias("times"))
    return out.withColumn("len", F.size("tokens"))


def noisy_labels(sequences: DataFrame, percent: int) -> DataFrame:
    """Sequences of which ``percent`` carry the class after theirs, by name, the last the first: weak labels.  Draws are hashes.
    The classes are few by definition; Spark broadcasts their table if its size allows."""
    names = sequences.select("class_id").distinct().withColumn("k", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("class_id")))
    n = names.agg(F.max("k").alias("n"))
    after = names.crossJoin(n).select((F.when(F.col("k") == 1, F.col("n")).otherwise(F.col("k") - 1)).alias("k"), F.col("class_id").alias("other"))  # a single row
    swap = names.join(after, "k").select("class_id", "other")
    wrong = draw(F.col("seq_id"), F.col("instance_id"), F.lit(0), "l") % 100 < percent
    return sequences.join(swap, "class_id").withColumn("class_id", F.when(wrong, F.col("other")).otherwise(F.col("class_id"))).select(*sequences.columns)


def planted_rhythm(sequences: DataFrame, length: int = 36, periods: tuple[int, ...] = (3, 4, 6), noises: tuple[int, ...] = (0, 10, 30), vocabulary: int = 5) -> DataFrame:
    """SEQ whose tokens repeat the first r tokens of each sequence up to ``length``, with noise; class ``r|noise``."""
    shapes = F.explode(F.array(*[F.struct(F.lit(r).alias("r"), F.lit(p).alias("p")) for r in periods for p in noises])).alias("shape")
    rows = sequences.where(F.col("len") >= max(periods)).select(F.col("seq_id").alias("base"), "tokens", shapes)

    def item(i: Column) -> Column:
        w = F.element_at("tokens", (i % F.col("shape.r") + 1).cast("int"))
        inst = F.col("shape.r") * 100 + F.col("shape.p")
        return F.when(draw(F.col("base"), inst, i, "s") % 100 < F.col("shape.p"), (w + 1 + draw(F.col("base"), inst, i, "v") % (vocabulary - 1)) % vocabulary).otherwise(w).cast("int")

    tokens = F.transform(F.sequence(F.lit(0), F.lit(length - 1)), item)
    cls = F.concat_ws("|", F.col("shape.r").cast("string"), F.col("shape.p").cast("string"))
    inst = F.col("shape.r") * 100 + F.col("shape.p")
    return rows.select((F.col("base") * 1000 + inst).alias("seq_id"), cls.alias("class_id"), inst.alias("instance_id"), tokens.alias("tokens"), F.lit(None).cast("array<double>").alias("times")).withColumn("len", F.size("tokens"))
