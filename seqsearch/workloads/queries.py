"""The methods, variants, baselines, measures and operators as named queries over the given tables, with their SQL.

Alignment and retrieval: the users whose id is divisible by 20 are the queries, all users are the base, whole sequences.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seqsearch.functions.times import micros

from ..config import LARGE_REFERENCES, WEIGHTS, CodebookParams, MetricParams, ModelParams, weight_presets
from ..functions.metrics import attach_tokens, combine, pair_distance, pair_metric, register_metric
from ..operators import histogram as H
from ..operators import index as I
from ..operators import periodicity as P
from ..operators import quantize as Q
from ..operators import relational as R
from ..operators.shortlist import ranked, shortlist, shortlist_size
from ..plans import evaluate as E
from ..plans import retrieve as T
from ..sources import io, pose
from ..sources import tokens as S
from . import sql as O

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(fn: Query) -> Query:
        QUERIES[name or fn.__name__] = fn
        if sql:
            ORACLES[name or fn.__name__] = sql
        return fn

    return add


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    return io.read_table(spark, d, name)


def joined(c: str):
    return F.array_join(F.transform(c, lambda w: w.cast("string")), ",")


def r6(c: str):
    return F.round(c, 6).alias(c)


def users(spark: SparkSession, d: str, buckets: int = 1) -> DataFrame:
    return S.event_tokens(table(spark, d, "events"), buckets)


def users_once(spark: SparkSession, d: str) -> DataFrame:
    """``users`` without times, kept: for queries that read the sequences in several jobs, which else shuffle the events in each."""
    return S.event_tokens(table(spark, d, "events"), timed=False).persist()


def asked(seq: DataFrame) -> DataFrame:
    return seq.where(F.col("seq_id") % 20 == 0)


# --- token sources ---------------------------------------------------------------------------------------------------
@query(f"WITH {O.seq(8)} SELECT seq_id, array_to_string(tokens, ',') AS tokens, len::INT AS len FROM seq")
def tok_events(spark, d):
    return users(spark, d, 8).select("seq_id", joined("tokens").alias("tokens"), "len")


DOC_SEQ = "seq AS (SELECT doc_id AS seq_id, lang AS class_id, list_transform(list_filter(regexp_split_to_array(trim(lower(coalesce(text, ''))), '\\s+'), lambda w: w <> ''), lambda w: ('0x' || substr(md5(w), 1, 4))::INT % 512) AS tokens FROM documents)"


@query(f"WITH {DOC_SEQ} SELECT seq_id, array_to_string(tokens, ',') AS tokens, len(tokens)::INT AS len FROM seq")
def tok_documents(spark, d):
    return S.document_tokens(table(spark, d, "documents")).select("seq_id", joined("tokens").alias("tokens"), "len")


@query("SELECT l_partkey AS seq_id, string_agg(floor(l_quantity / 10)::INT::VARCHAR, ',' ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) AS tokens, count(*)::INT AS len FROM lineitem GROUP BY 1")
def tok_lineitem(spark, d):
    return S.lineitem_tokens(table(spark, d, "lineitem")).select("seq_id", joined("tokens").alias("tokens"), "len")


@query("SELECT o_custkey AS seq_id, string_agg(substr(o_orderpriority, 1, 1), ',' ORDER BY o_orderdate, o_orderkey) AS tokens, count(*)::INT AS len FROM orders GROUP BY 1")
def tok_orders(spark, d):
    return S.order_tokens(table(spark, d, "orders")).select("seq_id", joined("tokens").alias("tokens"), "len")


@query("SELECT conv_id AS seq_id, string_agg(((CASE role WHEN 'user' THEN 0 WHEN 'assistant' THEN 1 ELSE 2 END) * 4 + least(3, length(text) // 100))::VARCHAR, ',' ORDER BY turn, role, text) AS tokens, count(*)::INT AS len FROM conversations GROUP BY 1")
def tok_conversations(spark, d):
    return S.conversation_tokens(table(spark, d, "conversations")).select("seq_id", joined("tokens").alias("tokens"), "len")


@query("SELECT page_id AS seq_id, array_to_string(list_transform(list_filter(regexp_split_to_array(coalesce(url, ''), '[^A-Za-z0-9]+'), lambda w: w <> ''), lambda w: ('0x' || substr(md5(w), 1, 4))::INT % 512), ',') AS tokens FROM pages")
def tok_pages(spark, d):
    return S.page_tokens(table(spark, d, "pages")).select("seq_id", joined("tokens").alias("tokens"))


@query(f"WITH {O.planted()} SELECT seq_id, class_id, array_to_string(tokens, ',') AS tokens FROM seq")
def perturb(spark, d):
    return S.perturb(users(spark, d)).select("seq_id", "class_id", joined("tokens").alias("tokens"))


for _kind in ("delete", "duplicate", "rotate", "crop"):

    def _perform(spark, d, kind=_kind):
        return S.perturb(users(spark, d), 2, kind=kind).select("seq_id", "class_id", joined("tokens").alias("tokens"))

    query(f"""WITH {O.seq().replace('seq AS (', 'base AS (')}, every AS ({O.performed(_kind)} UNION ALL {O.performed(_kind, 1)}) SELECT seq_id, class_id, array_to_string(tokens, ',') AS tokens FROM every""", f"perturb_{_kind}")(_perform)


@query(f"""WITH {O.seq().replace('seq AS (', 'base AS (')}, j AS (SELECT seq_id, list_sort(list_transform(range(0, len), lambda i: times[i + 1] + ({O.draw('t', 'seq_id', '0')} % 101 - 50) / 100.0::DOUBLE)) AS times FROM base)
    SELECT seq_id * 1000 AS seq_id, unnest(range(0, len(times)))::INT AS i, round(unnest(times), 4) AS t FROM j""")
def perturb_jitter(spark, d):
    got = S.perturb(users(spark, d), 1, kind="jitter")
    return got.select("seq_id", F.posexplode("times").alias("i", "t")).select("seq_id", "i", F.round("t", 4).alias("t"))


# --- stage 1 ---------------------------------------------------------------------------------------------------------
COUNTS = f"{O.seq(8)}, {O.COSINE.split(', cosine AS')[0].split('cosine AS')[0].rstrip().rstrip(',')}"


@query(f"WITH {COUNTS} SELECT seq_id, word, c AS cnt FROM cnt")
def hist_counts(spark, d):
    return H.word_counts(users(spark, d, 8))


@query(f"WITH {COUNTS} SELECT seq_id, word, round(c / sqrt(n2), 6) AS weight FROM cnt JOIN nrm USING (seq_id)")
def hist_l2(spark, d):
    return H.histogram(users(spark, d, 8)).select("seq_id", "word", r6("weight"))


@query(f"WITH {O.seq()}, {O.COSINE.split('cosine AS')[0].rstrip().rstrip(',')}, ks AS (SELECT range::INT AS word FROM range(0, 5)) SELECT s.seq_id, ks.word, round(coalesce(c / sqrt(n2), 0), 6) AS weight FROM seq s CROSS JOIN ks LEFT JOIN cnt ON cnt.seq_id = s.seq_id AND cnt.word = ks.word LEFT JOIN nrm ON nrm.seq_id = s.seq_id")
def hist_dense(spark, d):
    return H.dense_histogram(users(spark, d), 5).select("seq_id", F.posexplode("hist").alias("word", "weight")).select("seq_id", "word", r6("weight"))


@query(f"WITH {DOC_SEQ}, {O.COSINE.replace('{where}', O.BY_20)} SELECT query_id, cand_id, dot, round(cos, 6) AS cosine FROM cosine")
def cosine_pairs(spark, d):
    seq = S.document_tokens(table(spark, d, "documents"))
    return H.cosine_pairs(asked(seq), seq).select("query_id", "cand_id", "dot", r6("cosine"))


def shortlist_sql(size: str, buckets: int = 8) -> str:
    return f"""WITH {O.seq(buckets)}, {O.COSINE.replace('{where}', O.BY_20)}, n AS (SELECT count(*) AS n FROM seq),
    every AS (SELECT q.seq_id AS query_id, s.seq_id AS cand_id FROM seq q JOIN seq s ON q.seq_id <> s.seq_id WHERE q.seq_id % 20 = 0),
    rk AS (SELECT every.*, coalesce(cos, 0) AS cosine, row_number() OVER (PARTITION BY query_id ORDER BY round(coalesce(cos, 0), 9) DESC, cand_id)::INT AS rank FROM every LEFT JOIN cosine USING (query_id, cand_id))
    SELECT query_id, cand_id, round(cosine, 6) AS cosine, rank FROM rk, n WHERE rank <= {size}"""


@query(shortlist_sql("greatest(n // 2, least(200, n))"))
def shortlist_printed(spark, d):
    seq = users(spark, d, 8).persist()  # counted, and both sides' histograms
    return shortlist(asked(seq), seq, "printed").select("query_id", "cand_id", r6("cosine"), "rank")


@query(shortlist_sql("least(20, n)"))
def shortlist_capped(spark, d):
    seq = users(spark, d, 8)
    return shortlist(asked(seq), seq, "capped", 20).select("query_id", "cand_id", r6("cosine"), "rank")


@query("WITH n AS (SELECT user_id, count(*) AS n FROM events GROUP BY 1 UNION ALL SELECT -1, count(*) FROM events UNION ALL SELECT -2, count(*) FROM documents) SELECT user_id, n, greatest(n // 2, least(200, n)) AS printed, least(200, n) AS capped FROM n")
def shortlist_sizes(spark, d):
    ev, docs = table(spark, d, "events"), table(spark, d, "documents")
    n = ev.groupBy("user_id").agg(F.count("*").alias("n"))
    n = n.unionByName(ev.agg(F.count("*").alias("n")).select(F.lit(-1).cast("bigint").alias("user_id"), "n")).unionByName(docs.agg(F.count("*").alias("n")).select(F.lit(-2).cast("bigint").alias("user_id"), "n"))
    return n.select("user_id", "n", shortlist_size(F.col("n"), "printed").alias("printed"), shortlist_size(F.col("n"), "capped").alias("capped"))


AC = """u AS (SELECT seq_id, list_transform(tokens, lambda w: w * len - list_sum(tokens)) AS u, len FROM seq),
    ac AS (SELECT seq_id, t::INT AS lag, list_sum(list_transform(range(1, len - t + 1), lambda i: u[i] * u[i + t])) AS num, list_sum(list_transform(u, lambda x: x * x)) AS den, len FROM u, range(1, 200) r(t) WHERE t < len),
    peak AS (SELECT *, num > coalesce(lag(num) OVER w, den) AND num > lead(num) OVER w AND 5 * num > 3 * den AND den > 0 AS up FROM ac WINDOW w AS (PARTITION BY seq_id ORDER BY lag))"""


@query(f"WITH {O.seq()}, {AC} SELECT seq_id, lag, round(num::DOUBLE / den, 6) AS ac FROM ac")
def autocorr(spark, d):
    ac = P.autocorrelation(users(spark, d)).select("seq_id", F.posexplode("ac").alias("k", "ac"))
    return ac.select("seq_id", (F.col("k") + 1).alias("lag"), r6("ac"))


@query(f"WITH {O.seq()}, {AC} SELECT seq_id, coalesce(string_agg(lag::VARCHAR, ',' ORDER BY lag) FILTER (up), '') AS peaks, count(*) FILTER (up) >= 2 AS is_periodic FROM peak GROUP BY seq_id")
def periodicity(spark, d):
    return P.periodicity(users(spark, d)).select("seq_id", joined("peaks").alias("peaks"), "is_periodic")


RHYTHM = f"""{O.seq().replace('seq AS (', 'base AS (')}, cells AS (SELECT seq_id AS u, r, p, r * 100 + p AS k, i, tokens[i % r + 1] AS w FROM base, (VALUES (3), (4), (6)) a(r), (VALUES (0), (10), (30)) b(p), range(0, 36) c(i) WHERE len >= 6),
    noisy AS (SELECT u, r, p, k, i, CASE WHEN {O.draw('s')} % 100 < p THEN (w + 1 + {O.draw('v')} % 4) % 5 ELSE w END AS w FROM cells),
    seq AS (SELECT u * 1000 + k AS seq_id, r || '|' || p AS class_id, list(w ORDER BY i) AS tokens, count(*) AS len FROM noisy GROUP BY u, r, p, k)"""


@query(f"WITH {RHYTHM}, {AC}, f AS (SELECT seq_id, count(*) FILTER (up) >= 2 AS yes FROM peak GROUP BY 1) SELECT class_id, count(*) AS sequences, count(*) FILTER (yes) AS tagged FROM seq JOIN f USING (seq_id) GROUP BY 1")
def periodicity_planted(spark, d):
    seq = S.planted_rhythm(users(spark, d))
    return P.periodicity(seq).join(seq.select("seq_id", "class_id"), "seq_id").groupBy("class_id").agg(F.count("*").alias("sequences"), F.sum(F.col("is_periodic").cast("long")).alias("tagged"))


@query()
def cluster_histograms(spark, d):
    return H.cluster_histograms(users(spark, d), 8, 5)


@query(f"WITH {COUNTS}, s AS (SELECT word, count(*) AS sequences, sum(c)::BIGINT AS total FROM cnt GROUP BY 1) SELECT * FROM s")
def index_merge(spark, d):
    """The index built from half of the users and merged with all, twice: the second time nothing is new."""
    seq, path = users(spark, d, 8), io.work_dir(spark, "index")
    I.build_index(seq.where("seq_id % 2 = 0"), path)
    I.merge_index(spark, path, seq)
    I.merge_index(spark, path, seq)
    return I.read_index(spark, path)[0].groupBy("word").agg(F.count("*").alias("sequences"), F.sum("cnt").alias("total"))


# --- stage 2: distances of pairs -----------------------------------------------------------------------------------------
for _name, _metric, _params, _timed, _sql in (
    ("lcss", "lcss", MetricParams(), False, O.distance("lcss")),
    ("lcss_eps_delta", "lcss", MetricParams(lcss_eps=1, lcss_delta=4), False, O.distance("lcss", eps=1, delta=4)),
    ("edr", "edr", MetricParams(), False, O.distance("edr")),
    ("edr_eps", "edr", MetricParams(edr_eps=1), False, O.distance("edr", eps=1)),
    ("erp", "erp", MetricParams(), False, O.distance("erp")),
    ("dtw", "dtw", MetricParams(), False, O.distance("dtw")),
    ("dtw_band", "dtw", MetricParams(dtw_band=5), False, O.distance("dtw", band=5)),
    ("dtw_abs", "dtw", MetricParams(dtw_cost="abs"), False, O.distance("dtw_abs")),
    ("twed_abs", "twed", MetricParams(twed_cost="abs"), False, O.distance("twed_abs")),
    ("twed_printed", "twed", MetricParams(), False, O.distance("twed")),
    ("twed_original", "twed", MetricParams(twed="original"), False, O.distance("twed_original")),
    ("twed_times", "twed", MetricParams(), True, O.distance("twed", timed=True)),
):

    def _run(spark, d, metric=_metric, params=_params, timed=_timed):
        seq = users(spark, d)
        return T.distances(asked(seq), seq, metric, params, timed, 6).select("query_id", "cand_id", "value")

    query(_sql, _name)(_run)


@query("WITH RECURSIVE seq AS (SELECT conv_id AS seq_id, list(((CASE role WHEN 'user' THEN 0 WHEN 'assistant' THEN 1 ELSE 2 END) * 4 + least(3, length(text) // 100))::INT ORDER BY turn, role, text) AS tokens, count(*)::INT AS len, NULL AS times FROM conversations GROUP BY 1), "
       f"{O.PAIRS}, {O.wave({'v': 'edr'})} SELECT query_id, cand_id, round(v, 6) AS value FROM wave")
def edr_native(spark, d):
    """Short sequences, with higher-order functions only."""
    seq = S.conversation_tokens(table(spark, d, "conversations"))
    pairs = attach_tokens(T.all_pairs(asked(seq), seq), asked(seq), seq)
    return pair_distance(pairs, "edr", how="native").select("query_id", "cand_id", r6("value"))


for _n, _kind in ((2, "cosine"), (2, "jaccard"), (2, "dice"), (3, "cosine")):

    def _gram(spark, d, n=_n, kind=_kind):
        seq = users(spark, d)
        got = T.score_all(asked(seq), seq, T.RetrievalPlan(weights={"ngram": 1.0}, params=MetricParams(ngram=n, ngram_kind=kind)), 6)
        return got.select("query_id", "cand_id", F.col("s_ngram").alias("value"))

    query(O.gram_query(_n, _kind), f"ngram_{_kind}" + ("" if _n == 2 else "_3"))(_gram)


# --- retrieval -------------------------------------------------------------------------------------------------------
SIMS = ", ".join(f"round(s_{k}, 6) AS s_{k}" for k in ("hist", "twed", "lcss", "edr", "erp", "ngram"))


def answers(df: DataFrame) -> DataFrame:
    return df.select("query_id", F.col("rank").cast("bigint").alias("rank"), "cand_id", r6("score"))


@query(f"WITH RECURSIVE {O.scored()} SELECT query_id, cand_id, {SIMS}, round(score, 6) AS score FROM scored")
def combined_score(spark, d):
    seq = users_once(spark, d)
    got = T.score_all(asked(seq), seq, T.RetrievalPlan(), 6)
    return got.select("query_id", "cand_id", *[f"s_{k}" for k in ("hist", "twed", "lcss", "edr", "erp", "ngram")], "score")


@query(f"WITH RECURSIVE {O.scored(20)} {O.TOP3}")
def retrieve_two_stage(spark, d):
    seq = users(spark, d)
    return answers(T.retrieve(asked(seq), seq, T.RetrievalPlan(policy="capped", cap=20)))


@query(f"WITH RECURSIVE {O.scored()} {O.TOP3}")
def retrieve_exhaustive(spark, d):
    seq = users(spark, d)
    return answers(T.retrieve_exhaustive(asked(seq), seq))


@query(f"WITH RECURSIVE {O.scored()} {O.TOP3}")
def retrieve_bounded(spark, d):
    seq = users(spark, d)
    return answers(T.retrieve_bounded(asked(seq), seq))


@query(f"WITH {O.seq()}, {O.COSINE.replace('{where}', O.BY_20)}, {O.HIST_RANKED} SELECT query_id, rank::BIGINT AS rank, cand_id, round(score, 6) AS score FROM hr WHERE rank <= 3")
def retrieve_histogram(spark, d):
    seq = users(spark, d)
    return answers(T.retrieve_histogram(asked(seq), seq))


@query(f"""WITH RECURSIVE {RHYTHM}, {AC}, yes AS (SELECT seq_id FROM peak GROUP BY 1 HAVING count(*) FILTER (up) >= 2),
    {O.COSINE.replace('{where}', O.BY_20 + ' AND y.seq_id IN (SELECT seq_id FROM yes)')}, near AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(cos, 9) DESC, cand_id) AS rk FROM cosine),
    p AS (SELECT query_id, cand_id, a.tokens AS a, b.tokens AS b, a.len::INT AS m, b.len::INT AS n FROM near JOIN seq a ON a.seq_id = query_id JOIN seq b ON b.seq_id = cand_id WHERE rk <= 20), {O.wave({'v': 'lcss'})},
    rk AS (SELECT *, v / ((m + n) / 2.0::DOUBLE) AS score, row_number() OVER (PARTITION BY query_id ORDER BY round(v / ((m + n) / 2.0::DOUBLE), 9) DESC, cand_id) AS rank FROM wave)
    SELECT query_id, rank::BIGINT AS rank, cand_id, round(score, 6) AS score FROM rk WHERE rank <= 3""")
def retrieve_periodic(spark, d):
    """Only periodic sequences are candidates."""
    seq = S.planted_rhythm(users(spark, d)).persist()  # both sides of the histograms, and of the pairs
    return answers(T.retrieve(asked(seq), seq, T.RetrievalPlan(policy="capped", cap=20, weights={"lcss": 1.0}), periodic_only=True))


PLANTED_RANKED = f"{O.planted()}, {O.COSINE.replace('{where}', O.BY_20)}, {O.HIST_RANKED}"


@query(f"WITH {PLANTED_RANKED} SELECT h.query_id, arg_max(s.class_id, -h.rank) AS class_id FROM hr h JOIN seq s ON s.seq_id = h.cand_id WHERE h.rank <= 3 GROUP BY 1")
def identify(spark, d):
    seq = S.perturb(users(spark, d))
    return T.identify(T.retrieve_histogram(asked(seq), seq), seq)


@query(f"WITH {PLANTED_RANKED}, v AS (SELECT h.query_id, s.class_id, count(*) AS n, min(h.rank) AS first FROM hr h JOIN seq s ON s.seq_id = h.cand_id WHERE h.rank <= 5 GROUP BY ALL) SELECT query_id, arg_max(class_id, n * 100 - first) AS class_id FROM v GROUP BY 1")
def identify_majority(spark, d):
    seq = S.perturb(users(spark, d))
    return T.identify(T.retrieve_histogram(asked(seq), seq, 5), seq, "majority")


@query(f"""WITH {PLANTED_RANKED}, v AS (SELECT h.query_id, s.class_id, round(sum(h.score), 9) AS total, min(h.rank) AS first, max(h.score) AS best FROM hr h JOIN seq s ON s.seq_id = h.cand_id WHERE h.rank <= 5 GROUP BY ALL),
    o AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY total DESC, first) AS k, max(best) OVER (PARTITION BY query_id) AS top FROM v) SELECT query_id, CASE WHEN top >= 0.995 THEN class_id END AS class_id FROM o WHERE k = 1""")
def identify_score(spark, d):
    """By the largest sum of scores; rejected where the first answer is below 0.995."""
    seq = S.perturb(users(spark, d))
    return T.identify(T.retrieve_histogram(asked(seq), seq, 5), seq, "score", 0.995)


@query(f"""WITH {PLANTED_RANKED}, c AS (SELECT h.query_id, s.class_id, avg(h.score) AS score FROM hr h JOIN seq s ON s.seq_id = h.cand_id GROUP BY ALL),
    r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(score, 9) DESC, class_id) AS rank FROM c) SELECT query_id, rank::BIGINT AS rank, class_id, round(score, 6) AS score FROM r WHERE rank <= 3""")
def retrieve_classes_mean(spark, d):
    seq = S.perturb(users(spark, d))
    got = T.retrieve_classes_histogram(asked(seq), seq, by="mean")
    return got.select("query_id", F.col("rank").cast("bigint").alias("rank"), "class_id", r6("score"))


@query(f"""WITH {PLANTED_RANKED}, c AS (SELECT h.query_id, s.class_id, max(h.score) AS score FROM hr h JOIN seq s ON s.seq_id = h.cand_id GROUP BY ALL),
    r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(score, 9) DESC, class_id) AS rank FROM c) SELECT query_id, rank::BIGINT AS rank, class_id, round(score, 6) AS score FROM r WHERE rank <= 3""")
def retrieve_classes(spark, d):
    seq = S.perturb(users(spark, d))
    got = T.retrieve_classes_histogram(asked(seq), seq)
    return got.select("query_id", F.col("rank").cast("bigint").alias("rank"), "class_id", r6("score"))


@query(f"""WITH RECURSIVE {O.seq()}, starts AS (SELECT seq_id, start FROM seq, range(0, 200000, 8) r(start) WHERE start + 16 <= len UNION SELECT seq_id, greatest(0, len - 16) FROM seq),
    parts AS (SELECT seq_id, start, tokens[start + 1:start + 16] AS tokens FROM seq JOIN starts USING (seq_id)),
    p AS (SELECT q.seq_id AS query_id, s.seq_id * 1000000 + s.start AS cand_id, q.tokens AS a, s.tokens AS b, q.len::INT AS m, len(s.tokens)::INT AS n FROM seq q JOIN parts s ON q.seq_id <> s.seq_id WHERE q.seq_id % 20 = 0),
    {O.wave({'v': 'lcss'})}, g AS (SELECT query_id, cand_id // 1000000 AS whole, (cand_id % 1000000)::INT AS start, v / ((m + n) / 2.0::DOUBLE) AS score FROM wave),
    b AS (SELECT query_id, whole AS cand_id, start, score FROM g QUALIFY row_number() OVER (PARTITION BY query_id, whole ORDER BY round(score, 9) DESC, start) = 1),
    r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(score, 9) DESC, cand_id) AS rank FROM b)
    SELECT query_id, rank::BIGINT AS rank, cand_id, start, round(score, 6) AS score FROM r WHERE rank <= 3""")
def retrieve_segments(spark, d):
    seq = users(spark, d)
    got = T.retrieve_segments(asked(seq), seq, 16, 8, T.RetrievalPlan(weights={"lcss": 1.0}))
    return got.select("query_id", F.col("rank").cast("bigint").alias("rank"), "cand_id", "start", r6("score"))


@query("""WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings),
    s AS (SELECT q.vec_id AS query_id, e.vec_id AS cand_id, list_dot_product(q.v, e.v) / (sqrt(list_dot_product(q.v, q.v)) * sqrt(list_dot_product(e.v, e.v))) AS score FROM e q JOIN e ON q.vec_id <> e.vec_id WHERE q.vec_id % 20 = 0),
    r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(score, 9) DESC, cand_id) AS rank FROM s) SELECT query_id, rank::BIGINT AS rank, cand_id, round(score, 6) AS score FROM r WHERE rank <= 3""")
def embedding_knn(spark, d):
    e = table(spark, d, "embeddings")
    return answers(T.retrieve_embedding(e.where("vec_id % 20 = 0"), e))


# --- evaluation ------------------------------------------------------------------------------------------------------
LOO = f"WITH {O.planted()}, {O.COSINE.replace('{where}', '')}, {O.HIST_RANKED}, asked AS (SELECT * FROM seq), {O.judged()} "


def loo(spark, d):
    """Leave-one-out over the planted instances of all users, by histogram."""
    seq = S.perturb(users(spark, d))
    return E.query_scores(T.retrieve_histogram(seq, seq), seq, seq)


def shown(metrics: DataFrame) -> DataFrame:
    return metrics.select("method", r6("mean_score"), r6("match_rate"), r6("rank1_rate"), "queries")


@query(LOO + O.MEASURES.replace("{method}", "histogram"))
def eval_loo(spark, d):
    return shown(E.measures(loo(spark, d), "histogram"))


@query(LOO + ", n(best_rank) AS (VALUES ('1'), ('2'), ('3'), ('none')) SELECT n.best_rank, count(b.query_id) AS queries, round(count(b.query_id) / (SELECT count(*) FROM best)::DOUBLE, 6) AS share FROM n LEFT JOIN best b ON coalesce(b.best_rank::VARCHAR, 'none') = n.best_rank GROUP BY 1")
def eval_rank_distribution(spark, d):
    return E.rank_distribution(loo(spark, d)).select("best_rank", "queries", r6("share"))


@query(LOO + "SELECT class_id, count(*) AS queries, round(avg(score), 6) AS mean_score, round(avg(CASE WHEN best_rank IS NULL THEN 0.0 ELSE 1.0 END::DOUBLE), 6) AS match_rate FROM best GROUP BY ROLLUP (class_id)")
def eval_per_class_rollup(spark, d):
    return E.per_class(loo(spark, d)).select("class_id", "queries", r6("mean_score"), r6("match_rate"))


@query(LOO + "SELECT x.class_id, y.class_id AS answer_class, count(*) AS n FROM hr h JOIN seq x ON x.seq_id = h.query_id JOIN seq y ON y.seq_id = h.cand_id WHERE h.rank = 1 GROUP BY ALL")
def eval_confusion(spark, d):
    seq = S.perturb(users(spark, d))
    return E.confusion(T.retrieve_histogram(seq, seq), seq)


SPLIT = "split AS (SELECT *, row_number() OVER (PARTITION BY class_id ORDER BY md5('7|' || seq_id), seq_id) AS place FROM seq0)"


@query(f"WITH {O.planted().replace('seq AS (SELECT u * 1000', 'seqp AS (SELECT u * 1000')}, {SPLIT.replace('FROM seq0', 'FROM seqp')}, seq AS (SELECT * FROM split), {O.COSINE.replace('{where}', '')},"
       "hr AS (SELECT c.query_id, c.cand_id, c.cos AS score, row_number() OVER (PARTITION BY c.query_id ORDER BY round(cos, 9) DESC, c.cand_id) AS rank FROM cosine c JOIN split a ON a.seq_id = c.query_id AND a.place > 2 JOIN split b ON b.seq_id = c.cand_id AND b.place <= 2),"
       f"asked AS (SELECT * FROM split WHERE place > 2), {O.judged()} " + O.MEASURES.replace("{method}", "histogram"))
def eval_leave_k(spark, d):
    seq = S.perturb(users(spark, d))
    refs, queries = E.leave_k_out(seq, 2)
    got = T.retrieve_histogram(queries, refs)
    return shown(E.measures(E.query_scores(got, seq, queries), "histogram"))


TEN = "AND seq_id IN (SELECT seq_id FROM base ORDER BY seq_id::VARCHAR LIMIT 10)"
SIX = """sims AS (SELECT wave.query_id, wave.cand_id, m, n, twed, lcss, edr, erp FROM wave UNION ALL SELECT wave.cand_id, wave.query_id, m, n, twed, lcss, edr, erp FROM wave),
    d AS (SELECT u.seq_id AS query_id, v.seq_id AS cand_id, sum(u.c * v.c)::DOUBLE AS dot FROM gram u JOIN gram v ON u.g = v.g GROUP BY ALL),
    scored AS (SELECT query_id, cand_id, coalesce(cosine.cos, 0) AS cos, {F03} * coalesce(cosine.cos, 0) + {F015} * exp(-twed / (m + n)) + {F015} * (lcss / ((m + n) / 2.0::DOUBLE)) + {F015} * (1 - edr / greatest(m, n)) + {F01} * exp(-erp / ((m + n) / 2.0::DOUBLE)) + {F015} * coalesce(d.dot / sqrt(x.n2 * y.n2), 0) AS score
      FROM sims LEFT JOIN cosine USING (query_id, cand_id) LEFT JOIN d USING (query_id, cand_id) LEFT JOIN gnorm x ON x.seq_id = query_id LEFT JOIN gnorm y ON y.seq_id = cand_id)""".replace("{F03}", O.F03).replace("{F015}", O.F015).replace("{F01}", O.F01)
HALF = "p AS (SELECT a.seq_id AS query_id, b.seq_id AS cand_id, a.tokens AS a, b.tokens AS b, a.len::INT AS m, b.len::INT AS n FROM seq a JOIN seq b ON a.seq_id < b.seq_id)"


def one_of_ten(spark, d, instances: int = 20) -> DataFrame:
    """Ten classes of twenty planted performances: the experiment's size.  Classes of equal size go by name."""
    return E.filter_classes(S.perturb(users(spark, d), instances), 2, instances, 10)


def report(methods: dict[str, DataFrame], seq: DataFrame, base: str = "exhaustive") -> DataFrame:
    """METRICS of several methods on the same queries, and the ratio of the mean score to that of ``base``."""
    rows = None
    for name, got in methods.items():
        row = E.measures(E.query_scores(got, seq, seq), name)
        rows = row if rows is None else rows.unionByName(row)
    whole = F.max(F.when(F.col("method") == base, F.col("mean_score"))).over(Window.partitionBy(F.lit(0)))  # a row a method
    return rows.select("method", r6("mean_score"), r6("match_rate"), r6("rank1_rate"), "queries", F.round(F.col("mean_score") / whole, 6).alias("ratio"))


@query(f"""WITH RECURSIVE {O.planted(20, where=TEN)}, {O.COSINE.replace('{where}', '')}, {HALF}, {O.grams(2)}, {O.wave({'twed': 'twed', 'lcss': 'lcss', 'edr': 'edr', 'erp': 'erp'})}, {SIX},
    short AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(cos, 9) DESC, cand_id) AS near FROM scored),
    method(name, cap) AS (VALUES ('exhaustive', 1000000), ('histogram', 3), ('two_stage_10', 10), ('two_stage_20', 20), ('two_stage_50', 50)),
    ranks AS (SELECT name, query_id, cand_id, row_number() OVER (PARTITION BY name, query_id ORDER BY CASE WHEN name = 'histogram' THEN round(cos, 9) ELSE round(score, 9) END DESC, cand_id) AS rank FROM method JOIN short ON near <= cap),
    hits AS (SELECT name, query_id, min(rank) AS best FROM ranks JOIN seq x ON x.seq_id = query_id JOIN seq y ON y.seq_id = cand_id WHERE rank <= 3 AND x.class_id = y.class_id GROUP BY ALL),
    judged AS (SELECT name, seq_id, best, CASE best WHEN 1 THEN 1.0 WHEN 2 THEN 0.5 WHEN 3 THEN 0.25 ELSE 0.0 END::DOUBLE AS score FROM method CROSS JOIN seq LEFT JOIN hits USING (name) WHERE TRUE AND (hits.query_id = seq.seq_id) UNION ALL
      SELECT name, seq_id, NULL, 0.0 FROM method CROSS JOIN seq WHERE (name, seq_id) NOT IN (SELECT name, query_id FROM hits)),
    m AS (SELECT name AS method, avg(score) AS mean, 100 * avg(CASE WHEN best IS NOT NULL THEN 1.0 ELSE 0.0 END::DOUBLE) AS match, 100 * avg(CASE WHEN best = 1 THEN 1.0 ELSE 0.0 END::DOUBLE) AS first, count(*) AS queries FROM judged GROUP BY 1)
    SELECT method, round(mean, 6) AS mean_score, round(match, 6) AS match_rate, round(first, 6) AS rank1_rate, queries, round(mean / (SELECT mean FROM m WHERE method = 'exhaustive'), 6) AS ratio FROM m""")
def index_vs_brute_ratio(spark, d):
    """Ten classes of twenty, leave-one-out, top three: exhaustive scoring, histograms alone, and shortlists of several sizes."""
    seq = one_of_ten(spark, d).persist()
    methods = {"exhaustive": T.retrieve_exhaustive(seq, seq), "histogram": T.retrieve_histogram(seq, seq)}
    methods |= {f"two_stage_{n}": T.retrieve(seq, seq, T.RetrievalPlan(policy="capped", cap=n)) for n in (10, 20, 50)}
    return report(methods, seq)


@query(LOO.replace(O.planted(), O.planted(10)).replace(O.judged(), f"lev AS (SELECT 'choreography' AS level, seq_id, class_id FROM seq UNION ALL SELECT 'genre', seq_id, (class_id::INT % 10)::VARCHAR FROM seq), {O.judged()}") + """,
    lhit AS (SELECT x.level, h.query_id, min(h.rank) AS best FROM hr h JOIN lev x ON x.seq_id = h.query_id JOIN lev y ON y.seq_id = h.cand_id AND x.level = y.level WHERE h.rank <= 3 AND x.class_id = y.class_id GROUP BY ALL),
    lj AS (SELECT lev.level, lev.class_id, lhit.best, CASE lhit.best WHEN 1 THEN 1.0 WHEN 2 THEN 0.5 WHEN 3 THEN 0.25 ELSE 0.0 END::DOUBLE AS score FROM lev LEFT JOIN lhit ON lhit.query_id = lev.seq_id AND lhit.level = lev.level)
    SELECT level AS method, round(avg(score), 6) AS mean_score, round(100 * avg(CASE WHEN best IS NOT NULL THEN 1.0 ELSE 0.0 END::DOUBLE), 6) AS match_rate, round(100 * avg(CASE WHEN best = 1 THEN 1.0 ELSE 0.0 END::DOUBLE), 6) AS rank1_rate, count(*) AS queries FROM lj GROUP BY 1""")
def eval_studio(spark, d):
    """The set of about 1,400 sequences: ten performances of every user, in ten genres; matches at the level of the choreography
    and of the genre."""
    seq = S.perturb(users(spark, d), 10)
    got = T.retrieve_histogram(seq, seq).persist()  # judged at both levels
    rows = [E.measures(E.query_scores(got, E.at_level(seq, level), seq), level) for level in ("choreography", "genre")]
    return shown(rows[0].unionByName(rows[1]))


def extended_sql(noise: int) -> str:
    label = "class_id" if not noise else f"CASE WHEN ('0x' || substr(md5(concat_ws('|', seq_id, instance_id, 0, 'l')), 1, 4))::INT % 100 < {noise} THEN other ELSE class_id END"
    return f"""WITH {O.planted(50, where="AND seq_id IN (SELECT seq_id FROM base ORDER BY seq_id::VARCHAR LIMIT 100)").replace('seq AS (SELECT u * 1000', 'seqp AS (SELECT u * 1000')},
    names AS (SELECT class_id, coalesce(lead(class_id) OVER (ORDER BY class_id), min(class_id) OVER ()) AS other FROM (SELECT DISTINCT class_id FROM seqp)),
    split AS (SELECT *, row_number() OVER (PARTITION BY class_id ORDER BY md5('7|' || seq_id), seq_id) AS place FROM seqp),
    truth AS (SELECT seq_id, CASE WHEN place <= 10 THEN {label} ELSE class_id END AS class_id FROM split JOIN names USING (class_id)),
    cnt AS (SELECT seq_id, place <= 10 AS ref, w AS word, count(*) AS c FROM (SELECT seq_id, place, unnest(tokens) AS w FROM split) GROUP BY ALL), nrm AS (SELECT seq_id, sum(c * c)::DOUBLE AS n2 FROM cnt GROUP BY 1),
    cosine AS (SELECT x.seq_id AS query_id, y.seq_id AS cand_id, sum(x.c * y.c) / sqrt(any_value(u.n2) * any_value(v.n2)) AS cos FROM cnt x JOIN cnt y ON x.word = y.word AND NOT x.ref AND y.ref JOIN nrm u ON u.seq_id = x.seq_id JOIN nrm v ON v.seq_id = y.seq_id GROUP BY ALL),
    hr AS (SELECT query_id, cand_id, row_number() OVER (PARTITION BY query_id ORDER BY round(cos, 9) DESC, cand_id) AS rank FROM cosine),
    seq AS (SELECT * FROM truth), asked AS (SELECT truth.* FROM truth JOIN split USING (seq_id) WHERE place > 10), {O.judged()} {O.MEASURES.replace('{method}', f'histogram_{noise}')}"""


def extended(spark, d, noise: int = 0):
    """(references, queries, truth): a hundred classes of fifty performances, ten references each, some with a wrong label."""
    seq = E.filter_classes(S.perturb(users(spark, d), 50), 2, 50, 100)
    refs, asked_ = E.leave_k_out(seq, LARGE_REFERENCES)
    refs = S.noisy_labels(refs, noise) if noise else refs
    return refs, asked_, refs.unionByName(asked_)


for _noise in (0, 10):

    def _extended(spark, d, noise=_noise):
        refs, asked_, truth = extended(spark, d, noise)
        return shown(E.measures(E.query_scores(T.retrieve_histogram(asked_, refs), truth, asked_), f"histogram_{noise}"))

    query(extended_sql(_noise), "eval_extended" + ("_noisy" if _noise else ""))(_extended)


@query()
def eval_extended_two_stage(spark, d):
    """The same by two stages with a shortlist of fifty."""
    refs, asked_, truth = extended(spark, d)
    refs, asked_ = refs.persist(), asked_.persist()
    return shown(E.measures(E.query_scores(T.retrieve(asked_, refs, T.RetrievalPlan(policy="capped", cap=50)), truth, asked_), "two_stage_50"))


TEMPO = ("substitute", "delete", "duplicate", "rotate", "crop")


def tempo_sql(kind: str) -> str:
    return f"""SELECT '{kind}' AS method, q.seq_id AS query_id, q.class_id, q.tokens FROM ({O.performed(kind)}) q"""


@query(f"""WITH {O.seq().replace('seq AS (', 'base AS (')}, asked AS ({' UNION ALL '.join(map(tempo_sql, TEMPO))}),
    a AS (SELECT method, query_id, w, count(*) AS c FROM (SELECT method, query_id, unnest(tokens) AS w FROM asked) GROUP BY ALL), an AS (SELECT method, query_id, sum(c * c)::DOUBLE AS n2 FROM a GROUP BY ALL),
    b AS (SELECT seq_id, w, count(*) AS c FROM (SELECT seq_id, unnest(tokens) AS w FROM base) GROUP BY ALL), bn AS (SELECT seq_id, sum(c * c)::DOUBLE AS n2 FROM b GROUP BY ALL),
    cosine AS (SELECT a.method, a.query_id, b.seq_id AS cand_id, sum(a.c * b.c) / sqrt(any_value(an.n2) * any_value(bn.n2)) AS cos FROM a JOIN b USING (w) JOIN an USING (method, query_id) JOIN bn USING (seq_id) GROUP BY ALL),
    rk AS (SELECT *, row_number() OVER (PARTITION BY method, query_id ORDER BY round(cos, 9) DESC, cand_id) AS rank FROM cosine),
    hit AS (SELECT method, query_id, rank AS best_rank FROM rk JOIN asked USING (method, query_id) WHERE rank <= 3 AND cand_id::VARCHAR = class_id),
    best AS (SELECT asked.method, best_rank, CASE best_rank WHEN 1 THEN 1.0 WHEN 2 THEN 0.5 WHEN 3 THEN 0.25 ELSE 0.0 END::DOUBLE AS score FROM asked LEFT JOIN hit USING (method, query_id))
    SELECT method, {O.MEASURES.split("AS method, ")[1]} GROUP BY method""")
def eval_cross_tempo(spark, d):
    """Another performer (noise), another tempo (double, or items left out), another start, a part: each kind of performance of
    every user against the users' own sequences, by histogram."""
    seq = users(spark, d).persist()  # every kind of performance reads it
    rows = None
    for kind in TEMPO:
        q = S.perturb(seq, 1, kind=kind).withColumn("seq_id", F.col("seq_id") + 1_000_000_000)  # apart from the users' own ids
        truth = q.select("seq_id", "class_id").unionByName(seq.select("seq_id", "class_id"))
        got = T.retrieve_histogram(q, seq)
        row = shown(E.measures(E.query_scores(got, truth, q), kind))
        rows = row if rows is None else rows.unionByName(row)
    return rows


@query(f"""WITH RECURSIVE {O.seq().replace('seq AS (', 'base AS (')}, asked AS ({' UNION ALL '.join(f"SELECT {k + 1} * 1000000 + query_id AS query_id, '{kind}' AS method, class_id, tokens FROM ({tempo_sql(kind)}) WHERE class_id::INT % 20 = 0" for k, kind in enumerate(TEMPO))}),
    p AS (SELECT q.query_id, s.seq_id AS cand_id, q.tokens AS a, s.tokens AS b, len(q.tokens)::INT AS m, s.len::INT AS n FROM asked q CROSS JOIN base s), {O.wave({'v': 'edr'})},
    rk AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(1 - v / greatest(m, n), 9) DESC, cand_id) AS rank FROM wave),
    hit AS (SELECT query_id, rank AS best_rank FROM rk JOIN asked USING (query_id) WHERE rank <= 3 AND cand_id::VARCHAR = class_id),
    best AS (SELECT asked.method, best_rank, CASE best_rank WHEN 1 THEN 1.0 WHEN 2 THEN 0.5 WHEN 3 THEN 0.25 ELSE 0.0 END::DOUBLE AS score FROM asked LEFT JOIN hit USING (query_id))
    SELECT method, {O.MEASURES.split("AS method, ")[1]} GROUP BY method""")
def eval_cross_tempo_aligned(spark, d):
    """The same for the users whose id is divisible by 20, by the edit distance of sequences against all users."""
    seq = users(spark, d)
    rows = None
    for kind in TEMPO:
        q = S.perturb(asked(seq), 1, kind=kind).withColumn("seq_id", F.col("seq_id") + 1_000_000_000)
        truth = q.select("seq_id", "class_id").unionByName(seq.select("seq_id", "class_id"))
        got = T.retrieve_exhaustive(q, seq, T.RetrievalPlan(weights={"edr": 1.0}))
        row = shown(E.measures(E.query_scores(got, truth, q), kind))
        rows = row if rows is None else rows.unionByName(row)
    return rows


@query(f"""WITH RECURSIVE {O.scored()}, top AS (SELECT query_id, cand_id FROM ranked WHERE rank <= 3),
    sl AS (SELECT query_id, cand_id, row_number() OVER (PARTITION BY query_id ORDER BY round(cos, 9) DESC, cand_id) AS rk FROM cosine)
    SELECT count(sl.cand_id) AS found, count(*) AS wanted, round(count(sl.cand_id) / count(*)::DOUBLE, 6) AS recall FROM top LEFT JOIN sl ON top.query_id = sl.query_id AND top.cand_id = sl.cand_id AND rk <= 20""")
def shortlist_recall(spark, d):
    """The exhaustive answers by the bounded form, which aligns fewer pairs."""
    seq = users_once(spark, d)
    got = E.shortlist_recall(shortlist(asked(seq), seq, "capped", 20), T.retrieve_bounded(asked(seq), seq))
    return got.select("found", "wanted", r6("recall"))


@query(f"""WITH {O.seq()}, {O.COSINE.replace('{where}', O.BY_20)}, q AS (SELECT * FROM seq WHERE seq_id % 20 = 0),
    rk AS (SELECT query_id, cand_id, row_number() OVER (PARTITION BY query_id ORDER BY round(cos, 9) DESC, cand_id) AS rk FROM cosine),
    t AS (SELECT count(*) AS postings_touched FROM cnt a JOIN cnt b ON a.word = b.word WHERE b.seq_id % 20 = 0),
    w AS (SELECT count(*) AS pairs_reranked, coalesce(sum(x.len * y.len), 0)::BIGINT AS cells FROM rk JOIN seq x ON x.seq_id = query_id JOIN seq y ON y.seq_id = cand_id WHERE rk <= 20)
    SELECT (SELECT count(*) FROM q) * (SELECT count(*) FROM seq) AS comparisons, * FROM t, w""")
def cost_counters(spark, d):
    seq = users(spark, d)
    return E.cost_counters(asked(seq), seq, shortlist(asked(seq), seq, "capped", 20))


FAMILIES = f"{DOC_SEQ.replace('seq AS (', 'seqx AS (')}, fam AS (SELECT doc_id AS seq_id, md5(regexp_replace(trim(lower(coalesce(text, ''))), '\\s+', ' ', 'g')) AS class_id FROM documents), seq AS (SELECT seq_id, fam.class_id, tokens FROM seqx JOIN fam USING (seq_id)), big AS (SELECT class_id FROM seq GROUP BY 1 HAVING count(*) >= 2), asked AS (SELECT * FROM seq WHERE class_id IN (FROM big))"


@query(f"WITH {FAMILIES}, {O.COSINE.replace('{where}', 'WHERE x.seq_id IN (SELECT seq_id FROM asked)')}, {O.HIST_RANKED}, {O.judged()} " + O.MEASURES.replace("{method}", "histogram"))
def eval_document_families(spark, d):
    """Exact families of documents (case and blanks aside): every member is a query against all documents."""
    docs = table(spark, d, "documents")
    cls = F.md5(F.regexp_replace(F.trim(F.lower(F.coalesce("text", F.lit("")))), r"\s+", " "))
    seq = S.document_tokens(docs).drop("class_id").join(docs.select(F.col("doc_id").alias("seq_id"), cls.alias("class_id")), "seq_id")
    members = E.filter_classes(seq, 2)
    return shown(E.measures(E.query_scores(T.retrieve_histogram(members, seq), seq, members), "histogram"))


def presets_sql() -> str:
    """Every preset's score from the same similarities, and the share of its top three among the default's."""
    every = O.scored().replace("'erp': 'erp'", "'erp': 'erp'").replace(O.wave({"twed": "twed", "lcss": "lcss", "edr": "edr", "erp": "erp"}), O.wave({"twed": "twed", "lcss": "lcss", "edr": "edr", "erp": "erp", "dtw": "dtw"}))
    every = every.replace("AS s_ngram\n", "AS s_ngram, 1 - dtw / (m + n) AS s_dtw\n")
    parts = []
    for name, w in weight_presets().items():
        total = " + ".join(f"CAST({x!r} AS DOUBLE) * s_{k}" for k, x in w.items() if x)
        parts.append(f"SELECT '{name}' AS preset, query_id, cand_id, row_number() OVER (PARTITION BY query_id ORDER BY round({total}, 9) DESC, cand_id) AS rank FROM sims")
    return f"""WITH RECURSIVE {every}, every AS ({' UNION ALL '.join(parts)}), base AS (SELECT query_id, cand_id FROM every WHERE preset = 'default' AND rank <= 3)
    SELECT preset, round(avg(CASE WHEN (query_id, cand_id) IN (SELECT query_id, cand_id FROM base) THEN 1.0 ELSE 0.0 END::DOUBLE), 6) AS agreement FROM every WHERE rank <= 3 GROUP BY preset"""


@query(presets_sql())
def eval_weight_presets(spark, d):
    """Rank agreement of every weight preset with default scoring: share of its top three that are the same."""
    seq = users(spark, d)
    full = attach_tokens(T.all_pairs(asked(seq), seq), asked(seq), seq)
    sims = pair_metric(full, [*WEIGHTS, "dtw"]).persist()
    base = ranked(combine(sims), "score", 3).select("query_id", "cand_id", F.lit(1).alias("hit"))
    out = None
    for name, w in weight_presets().items():
        got = ranked(combine(sims, w), "score", 3).select("query_id", "cand_id").join(base, ["query_id", "cand_id"], "left")
        row = got.agg(F.round(F.avg(F.coalesce("hit", F.lit(0)).cast("double")), 6).alias("agreement")).select(F.lit(name).alias("preset"), "agreement")
        out = row if out is None else out.unionByName(row)
    return out


IN_WILD = f"""l AS (SELECT item_id AS label, {O.words('text')} AS lw FROM benchmark), t AS (SELECT doc_id AS item, ' ' || array_to_string({O.words('text')}, ' ') || ' ' AS whole FROM documents),
    lab AS (SELECT item, arg_max(label, len(lw) * 1000000 - label) AS label FROM t JOIN l ON len(lw) > 0 AND contains(whole, ' ' || array_to_string(lw, ' ') || ' ') GROUP BY 1),
    seq AS (SELECT seq_id, label::VARCHAR AS class_id, tokens FROM seqx JOIN lab ON item = seq_id), asked AS (SELECT * FROM seq)"""


@query(f"WITH {DOC_SEQ.replace('seq AS (', 'seqx AS (')}, {IN_WILD}, {O.COSINE.replace('{where}', '')}, {O.HIST_RANKED}, {O.judged()} " + O.MEASURES.replace("{method}", "histogram"))
def eval_in_the_wild(spark, d):
    """Texts whose class is the canonical name that their words hold: every labelled one is a query against the others."""
    docs = table(spark, d, "documents")
    labels = pose.map_labels(docs, table(spark, d, "benchmark"))
    seq = S.document_tokens(docs).drop("class_id").join(labels.select(F.col("item").alias("seq_id"), F.col("label").cast("string").alias("class_id")), "seq_id")
    return shown(E.measures(E.query_scores(T.retrieve_histogram(seq, seq), seq, seq), "histogram"))


PARTS = "seq AS (SELECT l_partkey AS seq_id, list(floor(l_quantity / 10)::INT ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) AS tokens, count(*)::INT AS len, NULL AS times FROM lineitem GROUP BY 1)"


@query(f"""WITH RECURSIVE {PARTS}, {O.COSINE.replace('{where}', O.BY_20)}, near AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(cos, 9) DESC, cand_id) AS rk FROM cosine),
    p AS (SELECT query_id, cand_id, a.tokens AS a, b.tokens AS b, a.len AS m, b.len AS n FROM near JOIN seq a ON a.seq_id = query_id JOIN seq b ON b.seq_id = cand_id WHERE rk <= 10), {O.wave({'v': 'edr'})},
    rk AS (SELECT *, 1 - v / greatest(m, n) AS score, row_number() OVER (PARTITION BY query_id ORDER BY round(1 - v / greatest(m, n), 9) DESC, cand_id) AS rank FROM wave)
    SELECT query_id, rank::BIGINT AS rank, cand_id, round(score, 6) AS score FROM rk WHERE rank <= 3""")
def retrieve_interactive(spark, d):
    """Thousands of short sequences in a stored index: the parts whose id is divisible by 20 are asked, ten shortlisted each."""
    seq, path = S.lineitem_tokens(table(spark, d, "lineitem")), io.work_dir(spark, "parts")
    I.build_index(seq, path)
    index = I.Retriever(spark, path)
    return answers(index.retrieve(asked(index.sequences), T.RetrievalPlan(policy="capped", cap=10, weights={"edr": 1.0})))


@query(f"WITH RECURSIVE {O.scored(20)} {O.TOP3}")
def retrieve_from_index(spark, d):
    """Two-stage retrieval from a stored index that was merged in two parts."""
    seq, path = users(spark, d), io.work_dir(spark, "stored")
    I.build_index(seq.where("seq_id % 3 = 0"), path)
    I.merge_index(spark, path, seq)
    index = I.Retriever(spark, path)
    return answers(index.retrieve(asked(index.sequences), T.RetrievalPlan(policy="capped", cap=20)))


@query(f"""WITH e AS (SELECT user_id, date_trunc('day', ts) AS day, {O.TYPES} AS w FROM events) SELECT w AS word, count(DISTINCT (user_id, day)) AS sequences, count(*) AS total FROM e GROUP BY 1""")
def index_daily(spark, d):
    """The events as a stream of days: each day's sequences of users are one committed batch of the index."""
    from ..streaming.stream import index_batch

    path = io.work_dir(spark, "daily")
    merge = index_batch(path, 1)
    events = table(spark, d, "events").withColumn("day", F.datediff(F.to_date("ts"), F.lit("1970-01-01").cast("date"))).persist()
    for k, row in enumerate(events.select("day").distinct().orderBy("day").collect()):  # a driver's clock: one batch a day
        day = events.where(F.col("day") == row["day"])
        seq = S.event_tokens(day).withColumn("seq_id", F.xxhash64("seq_id", F.lit(row["day"])))
        merge(seq, k)
        merge(seq, k)  # a replay changes nothing
    return I.read_index(spark, path)[0].groupBy("word").agg(F.count("*").alias("sequences"), F.sum("cnt").alias("total"))


@query()
def pruning_counters(spark, d):
    """What bounded retrieval aligns of the noisy performances of ten classes, against all cells."""
    seq = one_of_ten(spark, d)
    return T.pruning_counters(asked(seq), seq).select("pairs", (F.col("aligned") <= F.col("pairs")).alias("fewer"), (F.col("cells") < F.col("all_cells")).alias("pruned"), "all_cells")


@query(f"WITH {O.seq()} SELECT q.seq_id AS query_id, s.seq_id AS cand_id, round(least(q.len, s.len) / greatest(q.len, s.len)::DOUBLE, 6) AS s_length, round(CAST(0.5 AS DOUBLE) * least(q.len, s.len) / greatest(q.len, s.len) + CAST(0.5 AS DOUBLE) * (q.tokens[1] = s.tokens[1])::INT, 6) AS score FROM seq q JOIN seq s ON q.seq_id <> s.seq_id WHERE q.seq_id % 20 = 0")
def user_metrics(spark, d):
    """Two similarities of one's own, weighted like the others: the ratio of lengths, and the same first item."""
    register_metric("length", lambda a, b, ta, tb: F.least(F.size(a), F.size(b)) / F.greatest(F.size(a), F.size(b)))
    register_metric("start", lambda a, b, ta, tb: (a[0] == b[0]).cast("double"))
    seq = users(spark, d)
    got = T.score_pairs(T.all_pairs(asked(seq), seq), asked(seq), seq, T.RetrievalPlan(weights={"length": 0.5, "start": 0.5}))
    return got.select("query_id", "cand_id", r6("s_length"), r6("score"))


# --- quantiser -------------------------------------------------------------------------------------------------------
BOOK = CodebookParams(codes=64)


def latents(spark, d) -> DataFrame:
    rows = table(spark, d, "embeddings")
    return rows.select(F.floor(F.col("vec_id") / 20).alias("clip_id"), (F.col("vec_id") % 20).cast("int").alias("t"), F.transform("embedding", lambda x: x.cast("double")).alias("latent"))


def book_and_patches(spark, d):
    patches = Q.patchify(latents(spark, d), 2)
    return patches, Q.initial_codebook(patches, BOOK.codes)


def entries(df: DataFrame, keys: list[str], column: str) -> DataFrame:
    return df.select(*keys, F.posexplode(column).alias("i", "x")).select(*keys, "i", r6("x"))


@query(f"WITH {O.PATCHES} SELECT clip_id, patch_idx, unnest(range(0, len(vec)))::INT AS i, round(unnest(vec), 6) AS x FROM pat")
def patchify(spark, d):
    return entries(book_and_patches(spark, d)[0], ["clip_id", "patch_idx"], "vec")


@query(f"WITH {O.PATCHES} SELECT clip_id, patch_idx, code, round(dist2, 6) AS dist2 FROM asg")
def vq_assign(spark, d):
    return Q.assign(*book_and_patches(spark, d)).select("clip_id", "patch_idx", "code", r6("dist2"))


@query(f"WITH {O.PATCHES} SELECT clip_id, patch_idx, code, round(dist2, 6) AS dist2 FROM asg")
def vq_assign_arrow(spark, d):
    return Q.assign(*book_and_patches(spark, d), "arrow").select("clip_id", "patch_idx", "code", r6("dist2"))


@query(f"WITH {O.PATCHES}, {O.EMA} SELECT code, n AS ema_n, i::INT AS i, round(m / greatest(n, 1e-5::DOUBLE), 6) AS x FROM ema")
def ema_step(spark, d):
    patches, book = book_and_patches(spark, d)
    new = Q.ema_step(book, Q.code_sums(patches, Q.assign(patches, book)))
    return entries(new, ["code", "ema_n"], "centroid")


@query(f"""WITH {O.PATCHES}, far AS (SELECT code, c FROM book), dead AS (SELECT code, row_number() OVER (ORDER BY code) AS k FROM book WHERE code % 4 <> 0 OR code NOT IN (SELECT code FROM asg)),
    drawn AS (SELECT vec, row_number() OVER (ORDER BY md5('7|' || clip_id || '|' || patch_idx), clip_id, patch_idx) AS k FROM pat)
    SELECT b.code, round(list_sum(coalesce(drawn.vec, b.c)), 6) AS total, (drawn.vec IS NOT NULL) AS revived FROM book b LEFT JOIN dead USING (code) LEFT JOIN drawn ON drawn.k = dead.k""")
def revival(spark, d):
    """Only the hits of every fourth code are told to the revival, so that the others are dead."""
    patches, book = book_and_patches(spark, d)
    found = Q.assign(patches, book).where("code % 4 = 0")
    new = Q.revive(book, found, patches, 7)
    hit = found.select("code").distinct().withColumn("hit", F.lit(1))
    total = F.aggregate("centroid", F.lit(0.0), lambda s, x: s + x)
    return new.join(hit, "code", "left").select("code", F.round(total, 6).alias("total"), F.col("hit").isNull().alias("revived"))


@query(f"WITH {O.PATCHES} SELECT count(DISTINCT code) / 64.0::DOUBLE * 100 AS usage FROM asg")
def usage_ratio(spark, d):
    return Q.usage(Q.assign(*book_and_patches(spark, d)), BOOK.codes)


@query(f"WITH {O.PATCHES}, c AS (SELECT count(*)::DOUBLE AS c FROM asg GROUP BY code), t AS (SELECT sum(c) AS n FROM c) SELECT round(-sum(c / n * ln(c / n)), 6) AS entropy, round(exp(-sum(c / n * ln(c / n))), 6) AS perplexity FROM c, t")
def code_entropy(spark, d):
    return Q.code_entropy(Q.assign(*book_and_patches(spark, d))).select(r6("entropy"), r6("perplexity"))


@query(f"WITH {O.PATCHES} SELECT round(avg(dist2), 6) AS loss FROM asg")
def commit_loss(spark, d):
    return Q.commitment_loss(Q.assign(*book_and_patches(spark, d))).select(r6("loss"))


@query(f"WITH {O.PATCHES}, {O.EMA}, e AS (SELECT DISTINCT code, n FROM ema) SELECT count(*) FILTER (n > 0.75) / 64.0::DOUBLE * 100 AS usage FROM e")
def usage_moving(spark, d):
    """The share of codes whose moving count exceeds 0.75 after one epoch."""
    patches, book = book_and_patches(spark, d)
    found = Q.assign(patches, book, "arrow")
    return Q.usage(found, BOOK.codes, Q.ema_step(book, Q.code_sums(patches, found)), 0.75)


@query(f"WITH {O.PATCHES}, {O.EMA}, c AS (SELECT code, n, list(m / greatest(n, 1e-5::DOUBLE) ORDER BY i) AS v FROM ema GROUP BY code, n), h AS (SELECT code, hits FROM hit) SELECT c.code, coalesce(hits, 0)::BIGINT AS hits, round(list_sum(v), 6) AS total FROM c LEFT JOIN h USING (code)")
def epoch_fused(spark, d):
    """One epoch in one pass: hits and the sum of each new centroid."""
    patches, book = book_and_patches(spark, d)
    sums = Q.epoch_sums(patches, book)
    new = Q.ema_step(book, sums.select("code", "hits", "total")).join(sums.select("code", "hits"), "code", "left")
    return new.select("code", F.coalesce("hits", F.lit(0)).alias("hits"), F.round(F.aggregate("centroid", F.lit(0.0), lambda s, x: s + x), 6).alias("total"))


@query(f"WITH {O.PATCHES} SELECT clip_id AS seq_id, string_agg(code::VARCHAR, ',' ORDER BY patch_idx) AS tokens, count(*)::INT AS len FROM asg GROUP BY 1")
def tok_embeddings(spark, d):
    _, book = book_and_patches(spark, d)
    return Q.embedding_tokens(table(spark, d, "embeddings"), book).select("seq_id", joined("tokens").alias("tokens"), "len")


@query(f"WITH {O.PATCHES} SELECT a.clip_id, a.patch_idx, round(list_sum(c), 6) AS total FROM asg a JOIN book USING (code)")
def reconstruct_codes(spark, d):
    """Codes back to patches: the sum of each patch's centroid."""
    patches, book = book_and_patches(spark, d)
    got = Q.reconstruct(Q.token_sequences(Q.assign(patches, book, "arrow")), book)
    return got.select("clip_id", "patch_idx", F.round(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x), 6).alias("total"))


@query(f"WITH {O.PATCHES} SELECT count(*) AS patches, count(*) * 64 * 2 AS floats_before, count(*) AS tokens_after, 0.5::DOUBLE AS tokens_per_frame FROM asg")
def compression(spark, d):
    return Q.compression(Q.assign(*book_and_patches(spark, d), "arrow"), 64, 2)


@query(f"WITH {O.PATCHES} SELECT a.clip_id, a.patch_idx, round(list_sum(c), 6) AS total FROM asg a JOIN book USING (code)")
def straight_through(spark, d):
    """The value that passes the bottleneck is the code's."""
    patches, book = book_and_patches(spark, d)
    both = patches.join(Q.assign(patches, book, "arrow"), ["clip_id", "patch_idx"]).join(book.select("code", "centroid"), "code")
    out = both.withColumn("q", Q.straight_through("vec", "centroid"))
    return out.select("clip_id", "patch_idx", F.round(F.aggregate("q", F.lit(0.0), lambda s, x: s + x), 6).alias("total"))


@query(f"""WITH {O.PATCHES}, c AS (SELECT count(*)::DOUBLE AS c FROM asg GROUP BY code), t AS (SELECT sum(c) AS n FROM c), h AS (SELECT -sum(c / n * ln(c / n)) AS entropy FROM c, t), l AS (SELECT avg(dist2) AS commit FROM asg)
    SELECT round(commit, 6) AS commit, round(entropy, 6) AS entropy, round(commit + CAST(0.25 AS DOUBLE) * commit - CAST(0.01 AS DOUBLE) * entropy, 6) AS total FROM h, l""")
def total_loss(spark, d):
    """Commitment, codebook and entropy terms of one assignment, with a reconstruction term of zero."""
    found = Q.assign(*book_and_patches(spark, d), "arrow")
    commit, entropy = Q.commitment_loss(found).first()["loss"], Q.code_entropy(found).first()["entropy"]
    total = Q.total_loss(0.0, commit, commit, entropy)
    return spark.createDataFrame([(round(commit, 6), round(entropy, 6), round(total, 6))], "commit double, entropy double, total double")


@query()
def codebook_sweep(spark, d):
    """Usage and error after four epochs for 8 to 64 codes, with and without revival."""
    rows = Q.codebook_sweep(Q.patchify(latents(spark, d), 2), CodebookParams(epochs=4))
    return spark.createDataFrame([(r["codes"], r["revive"], r["usage"], r["error"]) for r in rows], "codes int, revive boolean, usage double, error double")


@query()
def ablations(spark, d):
    """The last epoch of a short fit without revival, without warm-up, with other decay, codes, weights and branches."""
    from ..operators.training import ablate

    base = ModelParams(epochs=2, warmup_epochs=1, learning_rate=1e-3, codebook=CodebookParams(codes=16))
    rows = ablate(pose.EmbeddingPoses().load(spark, d), base)
    return spark.createDataFrame([(r["variant"], float(r["rec"]), float(r["usage"])) for r in rows], "variant string, rec double, usage double")


POSES = "pose AS (SELECT vec_id // 20 AS clip_id, (vec_id % 20)::INT AS t, j::INT AS joint, list_transform(embedding[j * 4 + 1:j * 4 + 4], lambda x: x::DOUBLE) AS p FROM embeddings, range(0, 16) r(j))"


@query(f"""WITH {POSES}, ids AS (SELECT *, lead(p) OVER (PARTITION BY clip_id, joint ORDER BY t) AS nx FROM pose),
    pr AS (SELECT sqrt(list_sum(list_transform(list_zip(a.p, b.p), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS u, sqrt(list_sum(list_transform(list_zip(a.nx, b.nx), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS v
      FROM ids a JOIN ids b ON a.clip_id = b.clip_id AND a.t = b.t AND a.joint < b.joint WHERE a.nx IS NOT NULL)
    SELECT round(avg(abs(u - v)), 6) AS loss FROM pr""")
def interjoint_loss(spark, d):
    """Each frame against the one after it."""
    x = pose.EmbeddingPoses().load(spark, d)
    return Q.interjoint_loss(x, x.withColumn("t", F.col("t") - 1)).select(r6("loss"))


@query()
def fit_codebook(spark, d):
    """Usage and error by epoch, from a collapsed start, with and without revival."""
    patches = Q.patchify(latents(spark, d), 2)
    start = Q.initial_codebook(patches, 128, collapsed=True)
    rows = []
    for revive in (False, True):
        _, history = Q.fit_codebook(patches, CodebookParams(codes=128, revive=revive, epochs=6), start)
        rows += [(revive, h["epoch"], h["usage"], h["error"]) for h in history]
    return spark.createDataFrame(rows, "revive boolean, epoch int, usage double, error double")


@query()
def encode_decode(spark, d):
    """Poses to latents to codes to poses, with initial weights: what the fit starts from."""
    from ..operators import encoder as N

    p = ModelParams()
    frames = pose.EmbeddingPoses().load(spark, d)
    weights = N.init_weights(p)
    patches = Q.patchify(N.encode(frames, weights, p), p.patch)
    _, codes = Q.codebook_rows(Q.initial_codebook(patches, 32))
    tokens = N.tokenize(frames, weights, codes, p)
    return Q.interjoint_loss(frames, N.decode(tokens, weights, codes, p))


@query()
def fit_full(spark, d):
    """The history of a short fit of encoder, codes and decoder."""
    from ..operators.training import fit

    p = ModelParams(epochs=4, warmup_epochs=2, learning_rate=1e-3, codebook=CodebookParams(codes=32))
    history = fit(pose.EmbeddingPoses().load(spark, d), p).history
    return spark.createDataFrame([(h["epoch"], *(float(h[k]) for k in ("rec", "commit", "entropy", "total", "usage"))) for h in history], "epoch int, rec double, commit double, entropy double, total double, usage double")


# --- poses -----------------------------------------------------------------------------------------------------------
@query("""WITH e AS (SELECT user_id, epoch_us(ts) / 1000000.0::DOUBLE AS t, max(value) AS v FROM events GROUP BY ALL),
    s AS (SELECT *, lead(t) OVER w AS t1, lead(v) OVER w AS v1, min(t) OVER (PARTITION BY user_id) AS t0 FROM e WINDOW w AS (PARTITION BY user_id ORDER BY t)),
    b AS (SELECT *, ceil(round((t - t0) / 3600, 6))::BIGINT AS lo, CASE WHEN t1 IS NULL THEN floor(round((t - t0) / 3600, 6))::BIGINT ELSE ceil(round((t1 - t0) / 3600, 6))::BIGINT - 1 END AS hi FROM s),
    g AS (SELECT *, unnest(range(lo, hi + 1)) AS k FROM b WHERE hi >= lo)
    SELECT user_id, k, round(CASE WHEN t1 IS NULL THEN v ELSE v + (v1 - v) * ((t0 + k * 3600 - t) / (t1 - t)) END, 4) AS value FROM g""")
def resample(spark, d):
    """Event values on an hourly grid."""
    got = pose.resample(table(spark, d, "events"), "user_id", "ts", "value", 1 / 3600)
    return got.select("user_id", "k", F.round("value", 4).alias("value"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 6) AS smooth FROM events")
def smooth(spark, d):
    return pose.smooth(table(spark, d, "events"), "user_id", ["ts", "event_id"], "value", 2).select("event_id", r6("smooth"))


@query("SELECT event_id, round(median(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 6) AS smooth FROM events")
def smooth_median(spark, d):
    return pose.smooth(table(spark, d, "events"), "user_id", ["ts", "event_id"], "value", 2, "median").select("event_id", r6("smooth"))


@query("""WITH w AS (SELECT event_id, [lag(value, 2) OVER o, lag(value) OVER o, value, lead(value) OVER o, lead(value, 2) OVER o] AS v FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id)),
    p AS (SELECT event_id, list_filter(list_transform(range(1, 6), lambda i: CASE WHEN v[i] IS NOT NULL THEN [v[i], pow(0.5, abs(i - 3))] END), lambda x: x IS NOT NULL) AS p FROM w)
    SELECT event_id, round(list_sum(list_transform(p, lambda x: x[1] * x[2])) / list_sum(list_transform(p, lambda x: x[2])), 6) AS smooth FROM p""")
def smooth_exp(spark, d):
    return pose.smooth(table(spark, d, "events"), "user_id", ["ts", "event_id"], "value", 2, "exp").select("event_id", r6("smooth"))


@query("""WITH e AS (SELECT user_id, epoch_us(ts) / 1000000.0::DOUBLE AS t, max(value) AS v FROM events GROUP BY ALL), s AS (SELECT user_id, min(t) AS t0, max(t) AS t1 FROM e GROUP BY 1),
    g AS (SELECT user_id, t0, unnest(range(0, floor(round((t1 - t0) / 3600, 6))::BIGINT + 1)) AS k FROM s)
    SELECT g.user_id, k, round(e.v, 4) AS value FROM g ASOF JOIN e ON g.user_id = e.user_id AND t0 + k * 3600 + 0.000001 >= e.t""")
def resample_last(spark, d):
    """The latest event value on an hourly grid."""
    got = pose.resample(table(spark, d, "events"), "user_id", "ts", "value", 1 / 3600, "last")
    return got.select("user_id", "k", F.round("value", 4).alias("value"))


@query("SELECT vec_id // 20 AS clip_id, (vec_id % 20) // 8 AS segment, ((vec_id % 20) % 8)::INT AS t FROM embeddings")
def segment_fixed(spark, d):
    return pose.segment(pose.EmbeddingPoses().load(spark, d), 8).select("clip_id", "segment", "t")


@query(f"WITH {POSES}, c AS (SELECT a.clip_id, a.t, a.joint, unnest(range(0, 4))::INT AS i, unnest(a.p) - unnest(r.p) AS x FROM pose a JOIN pose r ON a.clip_id = r.clip_id AND a.t = r.t AND r.joint = 0) SELECT clip_id, t, joint, i, round(x - first_value(x) OVER (PARTITION BY clip_id, joint, i ORDER BY t), 6) AS x FROM c")
def align_pose(spark, d):
    frames = pose.align_poses(pose.EmbeddingPoses().load(spark, d), start="first")
    rows = frames.select("clip_id", "t", F.posexplode("pose").alias("joint", "p"))
    return entries(rows, ["clip_id", "t", "joint"], "p")


@query("""WITH o AS (SELECT o_orderkey, o_custkey AS clip_id, (row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) - 1)::INT AS t FROM orders)
    SELECT clip_id, t, (l_linenumber - 1)::INT AS joint, round(avg(l_quantity), 6) AS x, round(avg(l_extendedprice), 4) AS y FROM lineitem JOIN o ON l_orderkey = o_orderkey WHERE l_linenumber <= 7 GROUP BY ALL""")
def order_poses(spark, d):
    rows = pose.unpack_frames(pose.OrderPoses().load(spark, d))
    return rows.select("clip_id", "t", F.col("joint").cast("int").alias("joint"), F.round(F.col("coord")[0], 6).alias("x"), F.round(F.col("coord")[1], 4).alias("y"))


@query(f"""WITH l AS (SELECT item_id AS label, {O.words('text')} AS lw FROM benchmark), t AS (SELECT doc_id AS item, ' ' || array_to_string({O.words('text')}, ' ') || ' ' AS whole FROM documents)
    SELECT item, arg_max(label, len(lw) * 1000000 - label) AS label FROM t JOIN l ON len(lw) > 0 AND contains(whole, ' ' || array_to_string(lw, ' ') || ' ') GROUP BY 1""")
def map_labels(spark, d):
    return pose.map_labels(table(spark, d, "documents"), table(spark, d, "benchmark"))


@query(f"""WITH l AS (SELECT item_id AS label, {O.words('text')} AS lw FROM benchmark), r AS (SELECT label, len(lw) AS size, len(list_distinct(lw)) AS n, unnest(list_distinct(lw)) AS w FROM l),
    t AS (SELECT doc_id AS item, unnest(list_distinct({O.words('text')})) AS w FROM documents), m AS (SELECT item, label, size FROM t JOIN r USING (w) GROUP BY item, label, size, n HAVING count(*) >= 0.9 * n)
    SELECT item, arg_max(label, size * 1000000 - label) AS label FROM m GROUP BY 1""")
def map_labels_overlap(spark, d):
    return pose.map_labels(table(spark, d, "documents"), table(spark, d, "benchmark"), "token_overlap", 0.9)


@query("""WITH g AS (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w > 86400000000 THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))
    SELECT event_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id)::BIGINT AS segment FROM g""")
def segment_by_gap(spark, d):
    return pose.segment_by_gap(table(spark, d, "events"), "user_id", "ts", ["ts", "event_id"], 86400.0).select("event_id", "segment")


# --- streams ---------------------------------------------------------------------------------------------------------
@query(f"""WITH e AS (SELECT *, {O.TYPES} AS w, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 21600000000 THEN 0 ELSE 1 END AS new FROM events),
    s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM e)
    SELECT user_id::VARCHAR AS class_id, string_agg(w::VARCHAR, ',' ORDER BY ts, event_id) AS tokens, count(*)::INT AS len FROM s GROUP BY user_id, n""")
def session_sequences(spark, d):
    from ..streaming.stream import sessions

    return sessions(table(spark, d, "events"), "6 hours").select("class_id", joined("tokens").alias("tokens"), "len")


@query(f"SELECT user_id, epoch_us(date_trunc('day', ts)) AS start_us, {O.TYPES} AS word, count(*) AS cnt FROM events GROUP BY ALL")
def stream_hist(spark, d):
    """A stream of the whole table: daily counts, in complete mode, to the end of the input."""
    from ..streaming.stream import histograms

    source = table(spark, d, "events")
    files = f"{d}/events.parquet"
    # a stream reads folders; a single file is given by its name
    stream = spark.readStream.schema(source.schema).option("pathGlobFilter", "*.parquet").parquet(files if _is_folder(spark, files) else f"{d}/events.parquet*")
    counts, path = histograms(stream, delay=None), io.work_dir(spark, "hist")
    spark.createDataFrame([], counts.schema).write.parquet(path)

    def replace(batch: DataFrame, _: int) -> None:  # the whole result each time, written by tasks: a memory sink holds it on the driver
        batch.write.mode("overwrite").parquet(path)

    q = counts.writeStream.outputMode("complete").foreachBatch(replace).option("checkpointLocation", io.work_dir(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(counts.schema).parquet(path).select("user_id", micros("start").alias("start_us"), "word", "cnt")


def _is_folder(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


# --- SQL surface -----------------------------------------------------------------------------------------------------
@query(O.distance("lcss").replace("round(v, 6) AS value", "v::INT AS value"))
def sql_functions(spark, d):
    from ..sql import register

    register(spark, users(spark, d))
    return spark.sql("SELECT q.seq_id AS query_id, s.seq_id AS cand_id, seq_lcss(q.tokens, s.tokens) AS value FROM sequences s JOIN sequences q ON q.seq_id <> s.seq_id WHERE q.seq_id % 20 = 0")


@query()
def align_path(spark, d):
    """The alignment of each user asked for with its best answer."""
    from ..sql import register

    register(spark)
    seq = users(spark, d)
    best = T.retrieve_histogram(asked(seq), seq, 1)
    attach_tokens(best, asked(seq), seq).createOrReplaceTempView("best_pairs")
    return spark.sql("SELECT query_id, cand_id, p.step, p.i, p.j, p.op FROM best_pairs, LATERAL align_path(a, b, 'edr') p")


@query(f"""WITH RECURSIVE {O.seq()}, {O.COSINE.replace('{where}', O.BY_20)}, {O.HIST_RANKED}, p AS (SELECT query_id, cand_id, a.tokens AS a, b.tokens AS b, a.len::INT AS m, b.len::INT AS n FROM hr JOIN seq a ON a.seq_id = query_id JOIN seq b ON b.seq_id = cand_id WHERE rank = 1), {O.wave({'v': 'edr'})}
    SELECT query_id, cand_id, v::BIGINT AS edits, m::BIGINT AS items_a, n::BIGINT AS items_b FROM wave""")
def align_path_cost(spark, d):
    """The paths' edits are the edit distance, and they pass every item of both sequences once."""
    path = QUERIES["align_path"](spark, d)
    count = lambda c: F.sum(c.cast("bigint"))
    return path.groupBy("query_id", "cand_id").agg(count(F.col("op") != "match").alias("edits"), count(F.col("op") != "drop_b").alias("items_a"), count(F.col("op") != "drop_a").alias("items_b"))


# --- relational operators --------------------------------------------------------------------------------------------
@query("SELECT event_id, user_id, value FROM events WHERE event_type = 'purchase' AND value > 50")
def scan_filter_project(spark, d):
    return io.read_table(spark, d, "events", ["event_id", "user_id", "value"], "event_type = 'purchase' AND value > 50")


@query("SELECT event_id, (props->>'k')::INT AS k FROM events")
def scan_json_props(spark, d):
    return io.parse_props(table(spark, d, "events")).select("event_id", "k")


REGION = "SELECT r_name, n_name, count(*) AS suppliers, round(sum(s_acctbal), 2) AS balance FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY {by}"


def geography(spark, d, hint: str | None = None) -> DataFrame:
    s, n, r = (table(spark, d, t) for t in ("supplier", "nation", "region"))
    if hint:
        n, r = n.hint(hint), r.hint(hint)
    return s.join(n, s["s_nationkey"] == n["n_nationkey"]).join(r, F.col("n_regionkey") == F.col("r_regionkey"))


def totals() -> dict:
    return {"suppliers": F.count("*"), "balance": F.round(F.sum("s_acctbal"), 2)}


for _hint in ("broadcast", "merge", "shuffle_hash"):

    def _join(spark, d, hint=_hint):
        return geography(spark, d, hint).groupBy("r_name", "n_name").agg(*[v.alias(k) for k, v in totals().items()])

    query(REGION.format(by="r_name, n_name"), f"join_{_hint}")(_join)


@query(REGION.format(by="ROLLUP (r_name, n_name)"))
def agg_rollup_region(spark, d):
    return R.breakdown(geography(spark, d), ["r_name", "n_name"], totals())


@query(REGION.format(by="CUBE (r_name, n_name)"))
def agg_cube(spark, d):
    return R.breakdown(geography(spark, d), ["r_name", "n_name"], totals(), "cube")


@query(REGION.format(by="GROUPING SETS ((r_name), (n_name), ())"))
def agg_grouping_sets(spark, d):
    g = geography(spark, d)
    return R.breakdown(g, [F.col("r_name"), F.col("n_name")], totals(), "sets", [[F.col("r_name")], [F.col("n_name")], []])


@query(f"WITH {O.seq()} SELECT a.seq_id AS a, b.seq_id AS b FROM seq a JOIN seq b ON a.seq_id < b.seq_id AND greatest(a.len, b.len) <= 1.1 * least(a.len, b.len)")
def join_theta_pairs(spark, d):
    """All pairs of users of like length."""
    return R.like_length_pairs(users(spark, d), 1.1)


@query("SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND epoch_us(b.ts) - epoch_us(a.ts) BETWEEN 1000000 AND 7200000000")
def join_interval_events(spark, d):
    e = table(spark, d, "events")
    a = e.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("ta"))
    b = e.select(F.col("event_id").alias("next_id"), "user_id", F.col("ts").alias("tb"))
    return R.interval_join(a, b, "user_id", "ta", "tb", 1.0, 7200.0).select("first_id", "next_id")


@query("SELECT e.event_id, p.event_id AS purchase_id FROM events e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts >= p.ts")
def join_asof_events(spark, d):
    e = table(spark, d, "events")
    bought = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase_id"))
    return R.asof_join(e.select("event_id", "user_id", "ts"), bought, "user_id", "ts", ["purchase_id"], tie="purchase_id").select("event_id", "purchase_id")


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi_labelled(spark, d):
    return R.keep(table(spark, d, "documents").select("doc_id", "lang"), table(spark, d, "labels").select(F.col("doc_id").alias("id")), "doc_id", "id")


@query("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE doc_id IS NOT NULL)")
def join_anti_unmatched(spark, d):
    return R.exclude(table(spark, d, "documents").select("doc_id", "lang"), table(spark, d, "labels").select(F.col("doc_id").alias("id")), "doc_id", "id")


@query(f"""WITH {DOC_SEQ}, w AS (SELECT class_id, w, count(*) AS c FROM (SELECT class_id, unnest(tokens) AS w FROM seq) GROUP BY ALL),
    t AS (SELECT class_id, sum(c)::BIGINT AS items, count(*) AS distinct_tokens, arg_max(w, c * 1000 - w) AS top_token FROM w GROUP BY 1)
    SELECT s.class_id, count(*) AS sequences, max(len(tokens))::INT AS longest, any_value(items) AS items, any_value(distinct_tokens) AS distinct_tokens, any_value(top_token)::INT AS top_token FROM seq s JOIN t USING (class_id) GROUP BY 1""")
def agg_sequence_stats(spark, d):
    return R.sequence_stats(S.document_tokens(table(spark, d, "documents"))).withColumnRenamed("distinct", "distinct_tokens")


@query("SELECT lang, count(DISTINCT source) AS sources, count(DISTINCT n_chars) AS sizes FROM documents GROUP BY 1")
def agg_distinct(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.count_distinct("source").alias("sources"), F.count_distinct("n_chars").alias("sizes"))


@query()
def agg_approx_distinct(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.approx_count_distinct("n_chars").alias("sizes"))


for _how in ("rank", "dense_rank", "row_number"):

    def _ranks(spark, d, how=_how):
        seq = users(spark, d)
        got = R.rank_candidates(H.cosine_pairs(asked(seq), seq), 5, how, "cosine")
        return got.select("query_id", "cand_id", F.col("rank").cast("bigint").alias("rank"))

    query(f"WITH {O.seq()}, {O.COSINE.replace('{where}', O.BY_20)}, r AS (SELECT query_id, cand_id, {_how}() OVER (PARTITION BY query_id ORDER BY round(cos, 9) DESC{', cand_id' if _how == 'row_number' else ''}) AS rank FROM cosine) SELECT * FROM r WHERE rank <= 5", f"win_{_how}")(_ranks)


@query("SELECT event_id, user_id, epoch_us(ts) - lag(epoch_us(ts)) OVER w AS since, lead(epoch_us(ts)) OVER w - epoch_us(ts) AS until FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_gap(spark, d):
    return R.event_gaps(table(spark, d, "events")).select("event_id", "user_id", *[F.round(F.col(c) * 1_000_000).cast("bigint").alias(c) for c in ("since", "until")])


@query("SELECT event_id, user_id, round(avg(CASE WHEN event_type = 'purchase' THEN 1.0 ELSE 0.0 END::DOUBLE) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS mix FROM events")
def win_rows_frame(spark, d):
    return R.running_mix(table(spark, d, "events")).select("event_id", "user_id", r6("mix"))


@query("SELECT event_id, user_id, count(*) OVER w AS n, max(value) OVER w AS top FROM events WINDOW w AS (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW)")
def win_range_frame(spark, d):
    return R.range_frame(table(spark, d, "events"), 86400)


@query("SELECT c_custkey, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey)::INT AS quarter FROM customer")
def win_ntile(spark, d):
    from pyspark.sql import Window

    w = Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")
    return table(spark, d, "customer").select("c_custkey", F.ntile(4).over(w).alias("quarter"))


@query(f"WITH {O.seq()}, {O.COSINE.replace('{where}', O.BY_20)} SELECT query_id, cand_id, round(cos, 6) AS cosine FROM cosine ORDER BY round(cos, 9) DESC, query_id, cand_id LIMIT 25")
def topk_global(spark, d):
    seq = users(spark, d)
    return R.top_pairs(H.cosine_pairs(asked(seq), seq), 25, "cosine").select("query_id", "cand_id", r6("cosine"))


@query(f"""WITH RECURSIVE {O.scored()}, {O.HIST_RANKED}, x AS (SELECT query_id, cand_id FROM ranked WHERE rank <= 3), y AS (SELECT query_id, cand_id FROM hr WHERE hr.rank <= 3)
    SELECT * FROM (SELECT 'both' AS which, count(*) AS n FROM (FROM x INTERSECT FROM y) UNION ALL SELECT 'only_a', count(*) FROM (FROM x EXCEPT FROM y) UNION ALL SELECT 'only_b', count(*) FROM (FROM y EXCEPT FROM x)) WHERE n > 0""")
def set_compare(spark, d):
    """The exhaustive answers by the bounded form, which aligns fewer pairs."""
    seq = users_once(spark, d)
    return R.compare_results(T.retrieve_bounded(asked(seq), seq), T.retrieve_histogram(asked(seq), seq))


SETS = "(SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F') {op} (SELECT o_custkey FROM orders WHERE o_orderstatus = 'O')"
for _op, _fn in (("INTERSECT", "intersect"), ("EXCEPT", "subtract"), ("UNION", None)):

    def _sets(spark, d, fn=_fn):
        o = table(spark, d, "orders")
        a, b = (o.where(F.col("o_orderstatus") == s).select(F.col("o_custkey").alias("k")) for s in "FO")
        return getattr(a, fn)(b) if fn else a.union(b).distinct()

    query(SETS.format(op=_op), f"set_{_op.lower()}")(_sets)


@query(f"WITH {O.seq()}, {O.grams(2)} SELECT seq_id, g, c FROM gram")
def fn_ngrams(spark, d):
    from ..functions.native import ngrams

    g = users(spark, d).select("seq_id", F.explode(ngrams("tokens", 2)).alias("x"))
    return g.select("seq_id", F.array_join(F.transform("x", lambda w: w.cast("string")), "|").alias("g")).groupBy("seq_id", "g").agg(F.count("*").alias("c"))


@query("SELECT event_id, year(ts)::INT AS y, month(ts)::INT AS m, day(ts)::INT AS d, hour(ts)::INT AS h, (isodow(ts))::INT AS wd FROM events")
def fn_date_parts(spark, d):
    return table(spark, d, "events").select("event_id", F.year("ts").alias("y"), F.month("ts").alias("m"), F.dayofmonth("ts").alias("d"), F.hour("ts").alias("h"), (F.weekday("ts") + 1).alias("wd"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS norm, round(exp(-list_sum(list_transform(embedding, lambda x: abs(x::DOUBLE)))), 9) AS e FROM embeddings")
def fn_math_scores(spark, d):
    total = lambda f: F.aggregate(F.transform("embedding", f), F.lit(0.0), lambda s, x: s + x)
    return table(spark, d, "embeddings").select("vec_id", F.round(F.sqrt(total(lambda x: x.cast("double") * x.cast("double"))), 6).alias("norm"), F.round(F.exp(-total(lambda x: F.abs(x.cast("double")))), 9).alias("e"))


@query(f"WITH {O.seq()}, s AS (SELECT *, row_number() OVER (PARTITION BY len ORDER BY md5('7|' || seq_id), seq_id) AS n FROM seq) SELECT seq_id, len::INT AS len FROM s WHERE n <= 2")
def sample_refs(spark, d):
    return R.stratified(users(spark, d), "len", 2, "seq_id").select("seq_id", "len")


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return QUERIES["retrieve_two_stage"](spark, sf_dir)
