"""SentencePiece encoding and decoding, and token counts, with a unigram model over the pieces of a public vocabulary.

Blanks are written as U+2581 and one is put before the text.  No piece has a blank after another character, so the best
segmentation of a text is that of its pre-tokens (blanks and what follows them) put together; this is checked when a
vocabulary is loaded.  Each distinct pre-token is segmented once in a worker, and a bounded memory keeps the result.

* Encoding: an Aho-Corasick automaton over the pieces reads a pre-token once.  At each position its output links give all
  pieces that end there, and each relaxes the best score of that position.
* Counting: the distinct pre-tokens of a batch go into a trie.  The forward score of a node depends only on the path to it,
  so it is computed once for all words that share the prefix; the token count is stored where a word ends.

A character that no piece covers is written as its UTF-8 bytes.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterable
from dataclasses import dataclass
from itertools import chain

import ahocorasick
import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import once, text_function

BLANK = "▁"
_PRETOKEN = re.compile(f"{BLANK}+[^{BLANK}]*|[^{BLANK}]+")
#: Pre-tokens that a worker remembers, and the longest that it does; beyond, memory starts afresh.
MEMORY, MEMORY_CHARS = 300_000, 64


@dataclass(frozen=True)
class Vocabulary:
    pieces: tuple[str, ...]  # by id; "" for ids that no text may give
    scores: tuple[float, ...]
    byte_ids: tuple[int, ...]  # of the 256 bytes
    unknown: float  # score of a character that is written as bytes
    name: str = ""


def load_vocabulary(path: str, scores: str = "zipf", max_bytes: int = 64_000_000) -> Vocabulary:
    """Read a SentencePiece model file on the driver.  ``scores``: "file", or "zipf" for models whose scores are ranks
    (merge orders): the log of a Zipf law over the ranks."""
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    n = model.get_piece_size()
    if n > max_bytes // 64:
        raise ValueError("the vocabulary is too large to send to every worker")
    pieces, found, byte_ids = [], [], [-1] * 256
    for i in range(n):
        piece = model.id_to_piece(i)
        if model.is_byte(i):
            byte_ids[int(piece[1:-1], 16)] = i
            piece = ""
        elif model.is_control(i) or model.is_unknown(i) or model.is_unused(i):
            piece = ""
        pieces.append(piece)
        found.append(model.get_score(i))
    if min(byte_ids) < 0:
        raise ValueError("the vocabulary needs pieces for all bytes")
    if scores == "zipf":
        total = math.log(sum(1 / (k + 2.7) for k in range(n)))
        found = [-math.log(max(0.0, -s) + 2.7) - total for s in found]
    if any(BLANK in p.lstrip(BLANK) for p in pieces):
        raise ValueError("a piece has a blank after another character")
    low = min(s for s, p in zip(found, pieces, strict=True) if p)
    return Vocabulary(tuple(pieces), tuple(found), tuple(byte_ids), low - 10.0, f"{path}:{scores}")


def normalise(text: str) -> str:
    return BLANK + text.replace(" ", BLANK) if text else ""


def pretokens(text: str | None) -> list[str]:
    return _PRETOKEN.findall(normalise(text or ""))


class Encoder:
    """Pre-token to ids by one pass of the automaton."""

    def __init__(self, vocabulary: Vocabulary) -> None:
        self.v = vocabulary
        automaton = ahocorasick.Automaton()
        for i, (piece, score) in enumerate(zip(vocabulary.pieces, vocabulary.scores, strict=True)):
            if piece:
                automaton.add_word(piece, (len(piece), score, i))
        automaton.make_automaton()
        self.ending = automaton.iter
        self.memory: dict[str, tuple[int, ...]] = {}
        self.singles = frozenset(p for p in vocabulary.pieces if len(p) == 1)
        self.sizes = list(map(len, vocabulary.pieces))
        self.shown = list(vocabulary.pieces)
        self.bytes = {i: b for b, i in enumerate(vocabulary.byte_ids)}

    def segment(self, word: str) -> tuple[int, ...]:
        n = len(word)
        best, by = [0.0] + [-math.inf] * n, [-1] * (n + 1)
        if self.singles.issuperset(word):
            for at, (size, score, i) in self.ending(word):
                s = best[at + 1 - size] + score
                if s > best[at + 1]:
                    best[at + 1], by[at + 1] = s, i
        else:
            # a character without a piece of its own is bytes; its score must stand before any later piece is relaxed
            singles, unknown, done = self.singles, self.v.unknown, 0
            for at, (size, score, i) in chain(self.ending(word), [(n, (0, 0.0, -1))]):
                for e in range(done + 1, at + 1):
                    if word[e - 1] not in singles and best[e - 1] + unknown > best[e]:
                        best[e], by[e] = best[e - 1] + unknown, -1
                done = at
                if size:
                    s = best[at + 1 - size] + score
                    if s > best[at + 1]:
                        best[at + 1], by[at + 1] = s, i
        out, e, sizes = [], n, self.sizes
        while e:
            i = by[e]
            if i >= 0:
                out.append(i)
                e -= sizes[i]
            else:
                out.extend(self.v.byte_ids[b] for b in reversed(word[e - 1].encode("utf-8", "surrogatepass")))
                e -= 1
        return tuple(reversed(out))

    def encode(self, text: str | None) -> np.ndarray:
        memory, words = self.memory, pretokens(text)
        for w in words:
            if w not in memory:
                if len(memory) >= MEMORY:
                    memory.clear()
                    return self._encode_slowly(words)
                memory[w] = self.segment(w)
        out = np.fromiter(chain.from_iterable(map(memory.__getitem__, words)), np.int32)
        for w in words:
            if len(w) > MEMORY_CHARS:
                memory.pop(w, None)
        return out

    def _encode_slowly(self, words: list[str]) -> np.ndarray:
        """A text during which the memory filled up: piece by piece, with what memory there is."""
        parts = []
        for at in range(0, len(words), MEMORY // 2):
            own: dict[str, tuple[int, ...]] = {}
            part = words[at : at + MEMORY // 2]
            for w in part:
                if w not in own:
                    own[w] = self.segment(w)
            parts.append(np.fromiter(chain.from_iterable(map(own.__getitem__, part)), np.int32))
        return np.concatenate(parts)

    def decode(self, ids: Iterable[int]) -> str:
        """The text of the ids; bytes that are not UTF-8 become U+FFFD."""
        ids = ids.tolist() if isinstance(ids, np.ndarray) else list(ids)
        as_bytes = self.bytes
        if as_bytes.keys().isdisjoint(ids):
            shown = "".join(map(self.shown.__getitem__, ids))
        else:
            parts, run = [], bytearray()
            for i in ids:
                if i in as_bytes:
                    run.append(as_bytes[i])
                    continue
                if run:
                    parts.append(_utf8(run))
                    run = bytearray()
                parts.append(self.shown[i])
            if run:
                parts.append(_utf8(run))
            shown = "".join(parts)
        shown = shown.replace(BLANK, " ")
        return shown[1:] if shown[:1] == " " else shown


def _utf8(run: bytearray) -> str:
    try:
        return run.decode("utf-8", "surrogatepass")
    except UnicodeDecodeError:
        return run.decode("utf-8", "replace")


class Counter:
    """Token counts of pre-tokens by dynamic programming over a trie of the words of a batch."""

    def __init__(self, vocabulary: Vocabulary) -> None:
        self.v = vocabulary
        self.by_text = {p: s for p, s in zip(vocabulary.pieces, vocabulary.scores, strict=True) if p}
        # all ends of pieces; None where the end is no piece itself.  What is not here ends no longer piece either.
        self.ends: dict[str, float | None] = {}
        for p, score in self.by_text.items():
            for k in range(1, len(p)):
                self.ends.setdefault(p[k:], None)
            self.ends[p] = score
        self.memory: dict[str, int] = {}

    def count_words(self, words: set[str]) -> dict[str, int]:
        """Number of tokens of each word.  Words are taken in sorted order: the part of the path that a word shares with
        the one before it is still on the stack, with its forward scores and counts."""
        singles, ends, unknown = self.by_text.get, self.ends, self.v.unknown
        best, count, out = [0.0], [0], {}
        before = ""
        for word in sorted(words):
            shared, limit = 0, min(len(before), len(word))
            while shared < limit and before[shared] == word[shared]:
                shared += 1
            del best[shared + 1 :], count[shared + 1 :]
            for e in range(shared + 1, len(word) + 1):
                single = singles(word[e - 1])
                if single is None:
                    top, n = best[e - 1] + unknown, count[e - 1] + len(word[e - 1].encode("utf-8", "surrogatepass"))
                else:
                    top, n = best[e - 1] + single, count[e - 1] + 1
                for start in range(e - 2, -1, -1):
                    end = word[start:e]
                    if end not in ends:
                        break
                    s = ends[end]
                    # of equally good ways the one with the longest last piece, as in encoding
                    if s is not None and best[start] + s >= top:
                        top, n = best[start] + s, count[start] + 1
                best.append(top)
                count.append(n)
            out[word] = count[-1]
            before = word
        return out

    def count(self, texts: list[str | None]) -> list[tuple[int, int]]:
        """(pre-tokens, tokens) of each text."""
        out = []
        for at in range(0, len(texts), 64):
            split = [pretokens(t) for t in texts[at : at + 64]]
            memory = self.memory
            new = set(chain.from_iterable(split))
            new = {w for w in new if w not in memory}
            if len(memory) + len(new) > MEMORY:
                memory.clear()
                new = set(chain.from_iterable(split))
            found = self.count_words(new)
            memory.update(found)
            out += [(len(words), sum(map(memory.__getitem__, words))) for words in split]
            for w in found:
                if len(w) > MEMORY_CHARS:
                    del memory[w]
            if len(memory) > MEMORY:
                memory.clear()
        return out


def _shared(docs: DataFrame, vocabulary: Vocabulary):
    return docs.sparkSession.sparkContext.broadcast(vocabulary)


def encode_decode(docs: DataFrame, vocabulary: Vocabulary, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_tokens, round_trip, ids): the ids of the whole text, and whether they decode to it.

    A null or empty text has no ids and decodes to the empty text.  One row for each row; other columns are not read.
    """
    sent = _shared(docs, vocabulary)

    def of(texts: list[str | None]) -> pa.Array:
        coder = once(("encoder", sent.value.name), lambda: Encoder(sent.value))
        ids = [coder.encode(t) for t in texts]
        ok = [coder.decode(i) == (t or "") for i, t in zip(ids, texts, strict=True)]
        sizes = [len(i) for i in ids]
        offsets = np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)
        flat = pa.array(np.concatenate(ids) if ids else np.zeros(0, np.int32), pa.int32())
        lists = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), flat)
        return pa.StructArray.from_arrays([pa.array(sizes, pa.int64()), pa.array(ok, pa.bool_()), lists], names=["n_tokens", "round_trip", "ids"])

    coded = text_function(of, "struct<n_tokens:bigint,round_trip:boolean,ids:array<int>>")
    own = docs.select(F.col(doc_id).alias("doc_id"), coded(F.col(text)).alias("c"))
    return own.select("doc_id", "c.n_tokens", "c.round_trip", "c.ids")


def decode(coded: DataFrame, vocabulary: Vocabulary, doc_id: str = "doc_id", ids: str = "ids") -> DataFrame:
    """(doc_id, text) of a column of ids; null ids give a null text."""
    sent = _shared(coded, vocabulary)

    def of(lists: list) -> list[str | None]:
        coder = once(("encoder", sent.value.name), lambda: Encoder(sent.value))
        return [None if i is None else coder.decode(i) for i in lists]

    return coded.select(F.col(doc_id).alias("doc_id"), text_function(of, "string")(F.col(ids)).alias("text"))


def token_counts(docs: DataFrame, vocabulary: Vocabulary, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_pretokens, n_tokens) of whole texts; 0 and 0 for a null or empty one.  One row for each row."""
    sent = _shared(docs, vocabulary)

    def of(texts: list[str | None]) -> pa.Array:
        found = once(("counter", sent.value.name), lambda: Counter(sent.value)).count(texts)
        return pa.StructArray.from_arrays([pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], names=["n_pretokens", "n_tokens"])

    counts = text_function(of, "struct<n_pretokens:bigint,n_tokens:bigint>")
    own = docs.select(F.col(doc_id).alias("doc_id"), counts(F.col(text)).alias("c"))
    return own.select("doc_id", "c.n_pretokens", "c.n_tokens")
