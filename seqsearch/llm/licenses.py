"""License scans by ordered signature rules.

A rule is a regular expression over the words of a text (A-Z in lower case, ASCII punctuation dropped, one blank between
words), with keywords that any match must hold, a label, a priority and a weight; ``license_rules`` has them.  A text's words
fetch the rules whose rarest keyword they hold; only rules with all keywords run.  Of the matches, in order of priority and
then length, one is dropped if an accepted match contains its interval; equal intervals go to the rule that comes first.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import once, text_function
from .license_rules import LINES

_WORD_BYTES = bytes(c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))

#: Fixed: phrase and label.
BASE_PHRASES = (
    ("under the mit license", "mit"),
    ("apache license version 2", "apache-2"),
    ("cc by nc", "cc-by-nc"),
)


@dataclass(frozen=True)
class Signature:
    pattern: str  # over words with single blanks
    keywords: tuple[str, ...]  # whole words that every match has
    label: str
    priority: int  # higher first
    weight: float  # of the evidence, 0 to 1


#: Kind of a rule: priority and weight of its evidence.
KINDS = {"id": (90, 1.0), "base": (85, 1.0), "grant": (80, 1.0), "url": (75, 0.95), "text": (65, 0.95), "title": (60, 0.9), "name": (50, 0.8), "hint": (10, 0.4)}
_GROUP = re.compile(r"\(\?:([^()]*)\)(\?|\{[0-9,]+\})?")


def keywords(pattern: str) -> tuple[str, ...]:
    """The whole words that every match of a pattern has.

    A group all whose branches end (or all start) with a blank stands between words and is left out; any other group, and any
    other sign of a regular expression, spoils the word that it touches.
    """
    text = pattern
    while m := _GROUP.search(text):
        branches = m[1].split("|")
        between = all(x.endswith(" ") for x in branches) or all(x.startswith(" ") for x in branches)
        text = text[: m.start()] + ("" if between else "*") + text[m.end() :]
    text = re.sub(r"\[[^]]*\]", "*", re.sub(r" \?", "* *", text))
    return tuple(dict.fromkeys(w for w in text.split() if re.fullmatch(r"[a-z0-9]+", w)))


def _rules() -> tuple[Signature, ...]:
    rows = [tuple(x.strip() for x in line.split(" | ")) for line in LINES.strip().splitlines()]
    rows += [(label, "base", phrase) for phrase, label in BASE_PHRASES]
    rules = [Signature(pattern, keywords(pattern), label, *KINDS[kind]) for label, kind, pattern in rows]
    return tuple(sorted(rules, key=lambda r: (-r.priority, r.pattern)))


RULES = _rules()


def word_bytes(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().translate(_WORD_BYTES).split()


class Scanner:
    def __init__(self, rules: tuple[Signature, ...] = RULES) -> None:
        self.rules = [(r, re.compile(rb"(?<= )" + r.pattern.encode() + rb"(?= )"), frozenset(k.encode() for k in r.keywords)) for r in rules]
        uses: dict[bytes, int] = {}
        for _, _, keys in self.rules:
            for k in keys:
                uses[k] = uses.get(k, 0) + 1
        self.by_key: dict[bytes, list[int]] = {}
        for i, (_, _, keys) in enumerate(self.rules):
            self.by_key.setdefault(min(keys, key=lambda k: (uses[k], k)), []).append(i)
        self.keys = frozenset(self.by_key)

    def base(self, framed: bytes) -> list[tuple[int, str]]:
        """(byte, label) of every place of a base phrase."""
        out = []
        for phrase, label in BASE_PHRASES:
            wanted, at = b" " + phrase.encode() + b" ", -1
            while (at := framed.find(wanted, at + 1)) >= 0:
                out.append((at, label))
        return out

    def detections(self, words: list[bytes], framed: bytes) -> list[tuple[int, int, int]]:
        """(start byte, stop byte, rule) of the accepted matches."""
        have = self.keys.intersection(words)
        if not have:
            return []
        have_all = set(words)
        tried = sorted(i for k in have for i in self.by_key[k] if self.rules[i][2] <= have_all)
        found = [(-self.rules[i][0].priority, m.start() - m.end(), m.start(), i) for i in tried for m in self.rules[i][1].finditer(framed)]
        found.sort()
        kept: list[tuple[int, int, int]] = []
        spans: dict[int, list[tuple[int, int]]] = {}  # accepted intervals by the cells of 64 bytes that they touch
        for _, size, a, i in found:
            b, cell = a - size, a >> 6
            for x, y in spans.get(cell, ()):
                if x <= a and b <= y:
                    break
            else:
                kept.append((a, b, i))
                for c in range(cell, (b >> 6) + 1):
                    spans.setdefault(c, []).append((a, b))
        return sorted(kept)

    def scan(self, text: str | None) -> dict:
        words = word_bytes(text)
        framed = b" %b " % b" ".join(words)
        base = self.base(framed) if len(words) > 2 else []
        found = self.detections(words, framed)
        blanks = np.cumsum([0, *map(len, words)]) + np.arange(len(words) + 1)  # before each word, and the last
        starts = np.searchsorted(blanks, [p for p, _ in base]).tolist()
        first = np.searchsorted(blanks, [a - 1 for a, _, _ in found]).tolist()
        after = np.searchsorted(blanks, [b for _, b, _ in found]).tolist()
        rules = [self.rules[i][0] for _, _, i in found]
        base_labels = {label for _, label in base}
        weights = [r.weight for r in rules] + [1.0] * bool(base)
        miss = 1.0
        for w in sorted(set(weights)):
            miss *= 1.0 - w
        return {
            "n_words": len(words),
            "n_base": len(base),
            "first_word": min(starts, default=None),
            "last_word": max(starts, default=None),
            "base_labels": ",".join(sorted(base_labels)),
            "labels": ",".join(sorted(base_labels | {r.label for r in rules})),
            "score": 1.0 - miss,
            "detections": [{"label": r.label, "first_word": i, "after_word": j, "weight": r.weight} for r, i, j in zip(rules, first, after, strict=True)],
        }


_KIND = "struct<n_words:bigint,n_base:bigint,first_word:bigint,last_word:bigint,base_labels:string,labels:string,score:double,detections:array<struct<label:string,first_word:bigint,after_word:bigint,weight:double>>>"


def scan(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections), a row for each row.

    A null or empty text has no words, empty labels and score 0.  Of matches of equal priority and length the earlier in the
    text is taken first, of equal places the rule of the smaller pattern.  Repeated rows and null ids are kept; other columns
    of ``docs`` are not read.
    """

    def of(texts: list[str | None]) -> list[dict]:
        scanner = once("licenses", Scanner)
        return [scanner.scan(t) for t in texts]

    found = text_function(of, _KIND)
    own = docs.select(F.col(doc_id).alias("doc_id"), found(F.col(text)).alias("s"))
    return own.select("doc_id", "s.n_words", "s.n_base", "s.first_word", "s.last_word", "s.base_labels", "s.labels", "s.score", "s.detections")
