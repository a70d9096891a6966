"""Benchmark decontamination by pigeonhole edit matching.

A test item of n characters may stand in a document with up to k = floor(rate * n) edits.  The item is cut into k + 1
pieces; k edits can spoil at most k of them, so one stands unchanged.  All pieces are found by one pass of an
Aho-Corasick automaton over the document; around each hit the whole item is compared by Myers' bit-parallel edit distance,
with free start and end in the document.  Text is compared as lower-case words with single blanks between.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from .common import SLICE_ROWS, once, text_function

_WORDS = re.compile(r"\w+")
#: Characters of test items in one automaton; more items are taken in further blocks, each over all documents.
BLOCK_CHARS = 2_000_000


def normalise(text: str | None) -> str:
    return " ".join(_WORDS.findall((text or "").lower()))


def cut(item: str, budget: int) -> list[tuple[int, str]]:
    """(offset, piece) of budget + 1 pieces of nearly equal length that cover the item."""
    n, k = len(item), budget + 1
    ends = [n * i // k for i in range(k + 1)]
    return [(a, item[a:b]) for a, b in zip(ends, ends[1:], strict=False)]


def peq(pattern: str) -> dict[str, int]:
    """For each character the bit set of its places in the pattern."""
    out: dict[str, int] = {}
    for i, c in enumerate(pattern):
        out[c] = out.get(c, 0) | 1 << i
    return out


def best_match(places: dict[str, int], m: int, text: str, most: int) -> tuple[int, int] | None:
    """(distance, end) of the best match of a pattern of length m within ``text``, the first of equals; None over ``most``.

    Myers: the column of the edit matrix is kept as two bit vectors, of where it steps up and where down.
    """
    full, top = (1 << m) - 1, 1 << (m - 1)
    up, down, score = full, 0, m
    found = None
    for end, c in enumerate(text, 1):
        eq = places.get(c, 0)
        vertical = eq | down
        across = (((eq & up) + up) ^ up) | eq
        right = down | ~(across | up)
        left = up & across
        if right & top:
            score += 1
        elif left & top:
            score -= 1
        right, left = right << 1, left << 1
        up = (left | ~(vertical | right)) & full
        down = right & vertical & full
        if score <= most and (found is None or score < found[0]):
            found = (score, end)
    return found


class Matcher:
    """All items of a block against one document at a time."""

    def __init__(self, items: list[tuple[int, str]], rate: float) -> None:
        pieces: dict[str, list[tuple[int, int]]] = {}
        self.items = []
        for item_id, item in items:
            budget = int(rate * len(item))
            for offset, piece in cut(item, budget):
                pieces.setdefault(piece, []).append((len(self.items), offset))
            self.items.append((item_id, item, budget, peq(item), peq(item[::-1])))
        self.automaton = ahocorasick.Automaton()
        for piece, uses in pieces.items():
            self.automaton.add_word(piece, (len(piece), uses))
        if pieces:
            self.automaton.make_automaton()

    def hits(self, text: str | None) -> Iterator[tuple[int, int, int, int]]:
        """(item_id, distance, start, stop) of each place where an item stands, in normalised characters.

        Of overlapping places of one item the first is reported.  Places start and end at words.
        """
        doc = normalise(text)
        if not doc or not len(self.automaton):
            return
        framed = f" {doc} "
        found_until: dict[int, int] = {}
        failed: dict[int, set[int]] = {}
        for at, (size, uses) in self.automaton.iter(doc):
            for which, offset in uses:
                start = at - size + 1 - offset
                if start + 1 <= found_until.get(which, 0):
                    continue
                item_id, item, budget, places, reverse = self.items[which]
                n = len(item)
                if start >= 0 and doc.startswith(item, start):
                    distance, stop = 0, start + n
                else:
                    if not budget or start in failed.setdefault(which, set()):
                        continue
                    low = max(0, start - budget)
                    area = doc[low : start + n + budget]
                    match = best_match(places, n, area, budget)
                    if match is None:
                        failed[which].add(start)
                        continue
                    distance, end = match
                    back = best_match(reverse, n, area[:end][::-1], budget)
                    stop, start = low + end, low + end - back[1]
                if framed[start] != " " or framed[stop + 1] != " ":
                    if distance == 0:  # inside a longer word: the words at the ends differ
                        cost = (framed[start] != " ") + (framed[stop + 1] != " ")
                        if cost > budget:
                            continue
                        distance = cost
                yield item_id, distance, start, stop
                found_until[which] = stop


def item_blocks(items: DataFrame, item_id: str, text: str) -> Iterator[list[tuple[int, str]]]:
    """The items, normalised and distinct, in blocks of bounded size.  Empty items match nothing and are left out."""
    own = items.select(F.col(item_id).alias("id"), F.col(text).alias("t")).where("id is not null and t is not null")
    total = own.agg(F.sum(F.length("t"))).first()[0] or 0
    n = int(total * 1.2) // BLOCK_CHARS + 1
    for k in range(n):
        part = own if n == 1 else own.where(F.pmod(F.xxhash64("id"), F.lit(n)) == k)
        rows = {(r["id"], normalise(r["t"])) for r in part.collect()}
        block = sorted(x for x in rows if x[1])
        if block:
            yield block


def contaminated(docs: DataFrame, items: DataFrame, rate: float = 0.05, doc_id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """(doc_id, item_id, distance, start, stop): every place where an item stands in a document with at most
    ``rate`` edits a character.  Documents without such a place have no row; null and empty texts have none.
    A repeated document repeats its rows.  Items are compared in blocks, each block with all documents.
    """
    own = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    kinds = {"doc_id": own.schema["doc_id"].dataType, "item_id": items.schema[item_id].dataType}
    hits = ", ".join([*(f"{k} {t.simpleString()}" for k, t in kinds.items()), "distance int, start bigint, stop bigint"])
    types = (*map(to_arrow_type, kinds.values()), pa.int32(), pa.int64(), pa.int64())
    out = None
    for block in item_blocks(items, item_id, item_text):
        sent, key = docs.sparkSession.sparkContext.broadcast(block), uuid.uuid4().hex

        def scan(batches, sent=sent, key=key):
            matcher = once(("items", key), lambda: Matcher(sent.value, rate))
            for batch in batches:
                for at in range(0, batch.num_rows, SLICE_ROWS):
                    ids, texts = (c.to_pylist() for c in batch.slice(at, SLICE_ROWS).columns)
                    rows = [(d, *h) for d, t in zip(ids, texts, strict=True) for h in matcher.hits(t)]
                    columns = list(zip(*rows, strict=True)) or [()] * 5
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, types, strict=True)], names=["doc_id", "item_id", "distance", "start", "stop"])

        part = own.mapInArrow(scan, hits)
        out = part if out is None else out.unionAll(part)
    return own.sparkSession.createDataFrame([], hits) if out is None else out


def drop_contaminated(docs: DataFrame, items: DataFrame, rate: float = 0.05, text: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns, in which no item stands.

    Null and empty texts hold no item and stay; repeated rows go or stay together; with no items all rows stay.
    """
    for block in item_blocks(items, item_id, item_text):
        sent, key = docs.sparkSession.sparkContext.broadcast(block), uuid.uuid4().hex

        def clean(texts, sent=sent, key=key):
            matcher = once(("items", key), lambda: Matcher(sent.value, rate))
            return [next(matcher.hits(t), None) is None for t in texts]

        docs = docs.where(text_function(clean, "boolean")(F.col(text)))
    return docs
