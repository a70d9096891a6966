"""Language identification by compression.

For each language a raw-content zstandard dictionary is cut from labelled text.  Every window of a text is compressed with
each of them; the language with the fewest bytes over the whole text wins.  A narrow margin is reported as not confident.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import held_out, once, pieces_of, text_function

_JUNK = bytes(c if c >= 128 or 97 <= c <= 122 or c == 39 else 32 for c in range(256))
_LETTERS = re.compile(r"[^\W\d_]")


@dataclass(frozen=True)
class LanguageModel:
    languages: tuple[str, ...]  # the most frequent first, so that it wins ties
    contents: tuple[bytes, ...]
    window: int = 2048
    level: int = 3
    margin: float = 0.01  # of the winner's bytes


def normal_bytes(text: str) -> bytes:
    return b" ".join(text.lower().encode("utf-8", "surrogatepass").translate(_JUNK).split())


def has_letter(text: str | None) -> bool:
    """True if any character is a letter of any script."""
    return text is not None and any(m.group().isalpha() for m in _LETTERS.finditer(text))


def _compressors(model: LanguageModel) -> list:
    out = []
    for content in model.contents:
        zd = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        zd.precompute_compress(level=model.level)
        out.append(zstandard.ZstdCompressor(level=model.level, dict_data=zd, write_content_size=False, write_checksum=False, write_dict_id=False).compress)
    return out


def compressed_bytes(text: str, model: LanguageModel) -> list[int]:
    compress = once(("langid", model), lambda: _compressors(model))
    data = normal_bytes(text)
    windows = list(pieces_of(data, model.window, model.window))
    return [sum(len(c(w)) for w in windows) for c in compress]


def identify_text(text: str | None, model: LanguageModel | None) -> tuple[str, float, bool]:
    """(language, score, confident).  ``und`` for a null text or one without letters, and where nothing was learned."""
    if model is None or not model.languages or not has_letter(text):
        return "und", 0.0, False
    size = np.array(compressed_bytes(text, model), float)
    best = int(size.argmin())
    rest = np.delete(size, best)
    score = float(1 / np.exp(np.clip(size[best] - size, -50, 0) * 0.7).sum())
    gap = (rest.min() - size[best]) if len(rest) else size[best]
    return model.languages[best], score, bool(gap >= max(1.0, model.margin * size[best]))


def content(texts: list[str], dictionary_bytes: int = 128 * 1024) -> bytes:
    """The dictionary of one language: equal shares of as many of its texts as fit, so that none rules; empty if none has a letter."""
    rows = sorted({normal_bytes(t) for t in texts if has_letter(t)} - {b""}, key=lambda b: (len(b), b))
    if not rows:
        return b""
    left, out = dictionary_bytes, []
    for i, row in enumerate(rows):
        share = left // (len(rows) - i)
        part = row[: max(share, 64)][:left]
        out.append(part)
        left -= len(part)
        if left <= 0:
            break
    return (b" ".join(out) + b" " * 8)[: dictionary_bytes + 8]


def fit(texts: dict[str, list[str]], counts: dict[str, int] | None = None, **options) -> LanguageModel:
    """A dictionary of each language from its texts; languages without a letter are not learned."""
    return assemble({k: content(v) for k, v in texts.items()}, counts or {k: len(v) for k, v in texts.items()}, **options)


def assemble(contents: dict[str, bytes], counts: dict[str, int], **options) -> LanguageModel:
    order = sorted((k for k, c in contents.items() if c), key=lambda k: (-counts.get(k, 0), k))
    return LanguageModel(tuple(order), tuple(contents[k] for k in order), **options)


def fit_on(docs: DataFrame, per_language: int = 800, max_chars: int = 20000, doc_id: str = "doc_id", text: str = "text", lang: str = "lang") -> LanguageModel:
    """Learn every language that has a labelled text which is not held out, from ``per_language`` of its texts: those of the
    smallest hashes of id and text.  Of a longer text, ``max_chars`` characters from a place given by the hash are learned.

    The sample of a language is cut into its dictionary in one task; what comes to the driver is 128 KB a language.  The
    sample depends on the rows alone, not on their order or partitions; a row without an id counts like any other.
    """
    own = docs.select(F.col(doc_id).alias("__id"), F.col(lang).alias("__l"), F.col(text).alias("__t")).where("__l is not null and __t is not null").where(~held_out("__id"))
    counts = {r["__l"]: r["n"] for r in own.groupBy("__l").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return LanguageModel((), ())
    hashed = own.withColumn("__h", F.xxhash64(F.lit(7), "__id", "__t"))
    # a share of the rows by hash that holds twice what is wanted of a frequent language, and all of a rare one
    frequent = {k: n for k, n in counts.items() if n > 2 * per_language}
    if frequent:
        n = F.create_map(*[F.lit(x) for kv in sorted(frequent.items()) for x in kv])
        part = (F.col("__h").cast("double") + 2.0**63) / 2.0**64
        hashed = hashed.where(F.coalesce(part * n[F.col("__l")] < 2.0 * per_language, F.lit(True)))
    first = F.pmod(F.col("__h"), F.greatest(F.lit(1), F.length("__t") - max_chars + 1)).cast("int") + 1
    cut = hashed.select("__l", "__h", F.substring(F.col("__t"), first, F.lit(max_chars)).alias("__t"))
    place = F.row_number().over(Window.partitionBy("__l").orderBy("__h", "__t"))
    chosen = cut.withColumn("__n", place).where(F.col("__n") <= per_language).select("__l", "__t")

    def dictionary(key: tuple, rows: pa.Table) -> pa.Table:
        return pa.table({"lang": pa.array([key[0].as_py()], pa.string()), "content": pa.array([content(rows.column("__t").to_pylist())], pa.binary())})

    made = chosen.groupBy("__l").applyInArrow(dictionary, "lang string, content binary").collect()
    return assemble({r["lang"]: bytes(r["content"]) for r in made}, counts)


def identify(docs: DataFrame, model: LanguageModel, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, held_out, lang_pred, score, confident), one row for each row of ``docs``, over whole texts.

    Null and empty texts, and those without a letter, are ``und`` with score 0; of equally short encodings the language with
    more labelled texts wins.  Repeated rows and null ids are kept; other columns are not read.
    """

    def of(texts: list[str | None]) -> pa.Array:
        found = [identify_text(t, model) for t in texts]
        return pa.StructArray.from_arrays(
            [pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64()), pa.array([f[2] for f in found], pa.bool_())],
            names=["lang_pred", "score", "confident"],
        )

    guess = text_function(of, "struct<lang_pred:string,score:double,confident:boolean>")
    own = docs.select(F.col(doc_id).alias("doc_id"), held_out(doc_id).alias("held_out"), guess(F.col(text)).alias("g"))
    return own.select("doc_id", "held_out", "g.lang_pred", "g.score", "g.confident")
