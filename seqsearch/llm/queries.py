"""The queries of the corpus operators, as the driver runs them, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import caps, decontaminate, langid, licenses, pieces, pii, simhash, toxicity, urls

#: The tokenizer file, a parameter of the operators; and the demonstration key of the pseudonyms.
#: The queries that tokenise need this file; another one gives other token counts.
VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"
KEY = b"demonstration key, not a secret"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_feistel_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pseudonymise(_table(spark, sf_dir, "documents"), KEY)


def op2_trie_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.token_counts(_table(spark, sf_dir, "documents"), pieces.load_vocabulary(VOCABULARY))


def op3_compression_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit_on(docs, _table(spark, sf_dir, "labels")))


def op4_sentencepiece_coding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode_decode(_table(spark, sf_dir, "documents"), pieces.load_vocabulary(VOCABULARY))


def op5_pigeonhole_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op6_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op7_cap_filter_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return caps.near_duplicates(_table(spark, sf_dir, "embeddings"))


def op8_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = urls.judge(_table(spark, sf_dir, "pages"))
    return found.select("page_id", "host", "path", "rule", "verdict", "pattern")


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(_table(spark, sf_dir, "documents")).drop("detections")


def op10_compression_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return langid.identify(docs, langid.fit_on(docs))


OPERATORS = (
    op1_feistel_pseudonyms, op2_trie_token_counts, op3_compression_toxicity, op4_sentencepiece_coding, op5_pigeonhole_decontamination,
    op6_simhash_near_dedup, op7_cap_filter_near_dedup, op8_url_filters, op9_license_scan, op10_compression_language,
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in OPERATORS}


#: All pairs of equal label; only for checks on small tables.
CAPS_SQL = """
WITH RECURSIVE e AS (
    SELECT row_number() OVER () AS n, vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings),
g AS (SELECT *, sqrt(list_sum(list_transform(v, lambda x: x * x))) AS norm FROM e
      WHERE label IS NOT NULL AND v IS NOT NULL AND len(list_filter(v, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
p AS (SELECT a.n AS a, b.n AS b FROM g a JOIN g b ON a.label = b.label AND a.n <> b.n
      WHERE a.norm > 0 AND b.norm > 0 AND list_dot_product(a.v, b.v) / (a.norm * b.norm) >= 0.98),
r AS (SELECT DISTINCT a AS n, a AS other FROM p UNION SELECT r.n, p.b FROM r JOIN p ON p.a = r.other),
c AS (SELECT r.n, min(e.vec_id) AS root FROM r JOIN e ON e.n = r.other GROUP BY r.n),
d AS (SELECT a AS n, count(*) AS links FROM p GROUP BY a)
SELECT e.vec_id, coalesce(d.links, 0)::BIGINT AS n_links, coalesce(c.root, e.vec_id) AS component_id,
       e.vec_id = coalesce(c.root, e.vec_id) AS kept
FROM e LEFT JOIN d ON d.n = e.n LEFT JOIN c ON c.n = e.n"""


def oracle_sql() -> dict[str, str]:
    return {"op7_cap_filter_near_dedup": CAPS_SQL, "op8_url_filters": urls.verdict_sql()}
