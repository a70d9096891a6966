"""The same results in DuckDB's SQL, written independently of the Spark plans: alignment by a recursive query over diagonals."""

from __future__ import annotations

import re

TYPES = "CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 WHEN 'view' THEN 4 END"
F03, F015, F01 = "CAST(0.3 AS DOUBLE)", "CAST(0.15 AS DOUBLE)", "CAST(0.1 AS DOUBLE)"


def token(buckets: int) -> str:
    return TYPES if buckets == 1 else f"({TYPES} * {buckets} + least({buckets - 1}, floor(value / 20)))::INT"


def seq(buckets: int = 1) -> str:
    """CTEs ev, seq(seq_id, tokens, secs, len, times)."""
    return f"""ev AS (SELECT user_id AS seq_id, ts, event_id, {token(buckets)} AS w FROM events),
    seq0 AS (SELECT seq_id, list(w ORDER BY ts, event_id) AS tokens, list(epoch_us(ts) / 1000000.0::DOUBLE ORDER BY ts, event_id) AS secs, count(*) AS len FROM ev GROUP BY seq_id),
    seq1 AS (SELECT *, CASE WHEN len > 1 AND secs[len] > secs[1] THEN (secs[len] - secs[1]) / (len - 1) ELSE 1.0::DOUBLE END AS gap FROM seq0),
    seq AS (SELECT seq_id, tokens, len, list_transform(secs, lambda t: (t - secs[1]) / gap) AS times FROM seq1)"""


PAIRS = """p AS (SELECT q.seq_id AS query_id, s.seq_id AS cand_id, q.tokens AS a, s.tokens AS b, q.times AS ta, s.times AS tb, q.len::INT AS m, s.len::INT AS n
    FROM seq q JOIN seq s ON q.seq_id <> s.seq_id WHERE q.seq_id % 20 = 0)"""

#: name -> (cell, edge i, edge j); P is the diagonal neighbour, U the one above, L the one to the left.
RULES = {
    "lcss": ("CASE WHEN abs(a[i] - b[j]) <= {eps} {window} THEN P + 1 ELSE greatest(U, L) END", "0", "0"),
    "edr": ("least(P + CASE WHEN abs(a[i] - b[j]) <= {eps} THEN 0 ELSE 1 END, U + 1, L + 1)", "i", "j"),
    "erp": ("least(P + abs(a[i] - b[j]), U + 0.5::DOUBLE * abs(a[i]), L + 0.5::DOUBLE * abs(b[j]))", "list_sum(list_transform(a[1:i], lambda v: 0.5::DOUBLE * abs(v)))", "list_sum(list_transform(b[1:j], lambda v: 0.5::DOUBLE * abs(v)))"),
    "dtw": ("CASE WHEN {band} THEN least(P, U, L) + CASE WHEN a[i] = b[j] THEN 0 ELSE 1 END END", "NULL", "NULL"),
    "twed": ("least(P + CASE WHEN a[i] = b[j] THEN 0 ELSE 1 END + CASE WHEN a[i-1] IS NOT DISTINCT FROM b[j-1] THEN 0 ELSE 1 END + 0.125::DOUBLE * abs({ti} - {tj}), least(U, L) + CASE WHEN a[i] = b[j] THEN 0 ELSE 1 END + 0.125::DOUBLE * abs({ti} - {tj}) + 1)", "NULL", "NULL"),
    "twed_original": ("least(P + CASE WHEN a[i] = b[j] THEN 0 ELSE 1 END + CASE WHEN a[i-1] IS NOT DISTINCT FROM b[j-1] THEN 0 ELSE 1 END + 0.25::DOUBLE * abs(i - j), U + CASE WHEN i > 1 AND a[i] = a[i-1] THEN 0 ELSE 1 END + 1.125::DOUBLE, L + CASE WHEN j > 1 AND b[j] = b[j-1] THEN 0 ELSE 1 END + 1.125::DOUBLE)", "NULL", "NULL"),
}


def absolute(a: str, b: str) -> str:
    """The numeric mismatch; 1 between an item and the sentinel before the first."""
    return f"CASE WHEN {a} IS NULL AND {b} IS NULL THEN 0 WHEN {a} IS NULL OR {b} IS NULL THEN 1 ELSE abs({a} - {b}) END"


RULES["dtw_abs"] = ("least(P, U, L) + abs(a[i] - b[j])", "NULL", "NULL")
RULES["twed_abs"] = (f"least(P + abs(a[i] - b[j]) + {absolute('a[i-1]', 'b[j-1]')} + 0.125::DOUBLE * abs({{ti}} - {{tj}}), least(U, L) + abs(a[i] - b[j]) + 0.125::DOUBLE * abs({{ti}} - {{tj}}) + 1)", "NULL", "NULL")


def wave(rules: dict[str, str], source: str = "p", name: str = "wave", eps: float = 0, delta: int | None = None, band: int | None = None, timed: bool = False) -> str:
    """CTEs that end in ``name``(query_id, cand_id, m, n, one column for each of ``rules``: column -> rule)."""
    first, step, last = [], [], []
    for col, rule in rules.items():
        cell, edge_i, edge_j = (t.replace("{eps}", f"{eps}").replace("{window}", "" if delta is None else f"AND abs(i - j) <= {delta}").replace("{band}", "TRUE" if band is None else f"abs(i - j) <= greatest({band}, abs(m - n))").replace("{ti}", "ta[i]" if timed else "i").replace("{tj}", "tb[j]" if timed else "j") for t in RULES[rule])
        cell = re.sub(r"\bP\b", f"q_{col}[i]", cell)
        cell = re.sub(r"\bU\b", f"w_{col}[i]", cell)
        cell = re.sub(r"\bL\b", f"w_{col}[i+1]", cell)
        j = "(d + 1 - i)"
        cell, edge_i, edge_j = (re.sub(r"\bj\b", j, t) for t in (cell, edge_i, edge_j))
        first.append(f"[]::DOUBLE[] AS w_{col}, []::DOUBLE[] AS q_{col}")
        step.append(f"list_transform(range(0, m + 1), lambda i: (CASE WHEN i > d + 1 OR {j} > n THEN NULL WHEN i = 0 AND d = -1 THEN 0 WHEN i = 0 THEN {edge_j} WHEN i = d + 1 THEN {edge_i} ELSE {cell} END)::DOUBLE), w_{col}")
        last.append(f"w_{col}[m + 1] AS {col}")
    times = ", ta, tb" if timed else ""
    return f"""{name}_r AS (SELECT query_id, cand_id, a, b{times}, m, n, -1 AS d, {', '.join(first)} FROM {source}
    UNION ALL SELECT query_id, cand_id, a, b{times}, m, n, d + 1, {', '.join(step)} FROM {name}_r WHERE d < m + n),
    {name} AS (SELECT query_id, cand_id, m, n, {', '.join(last)} FROM {name}_r WHERE d = m + n)"""


def distance(rule: str, **options) -> str:
    return f"WITH RECURSIVE {seq()}, {PAIRS}, {wave({'v': rule}, **options)} SELECT query_id, cand_id, round(v, 6) AS value FROM wave"


def grams(n: int) -> str:
    """CTE gram(seq_id, g, c)."""
    parts = " || '|' || ".join(f"tokens[k + {i}]::VARCHAR" for i in range(n))
    return f"""gram0 AS (SELECT seq_id, {parts} AS g FROM seq, range(1, 200000) r(k) WHERE k <= len - {n - 1}),
    gram AS (SELECT seq_id, g, count(*) AS c FROM gram0 GROUP BY ALL),
    gnorm AS (SELECT seq_id, sum(c * c)::DOUBLE AS n2, sum(c)::DOUBLE AS s FROM gram GROUP BY seq_id)"""


def gram_query(n: int, kind: str) -> str:
    value = {"cosine": "dot / sqrt(x.n2 * y.n2)", "jaccard": "common / (x.s + y.s - common)", "dice": "2 * common / (x.s + y.s)"}[kind]
    return f"""WITH {seq()}, {PAIRS}, {grams(n)},
    d AS (SELECT u.seq_id AS query_id, v.seq_id AS cand_id, sum(u.c * v.c)::DOUBLE AS dot, sum(least(u.c, v.c))::DOUBLE AS common FROM gram u JOIN gram v ON u.g = v.g GROUP BY ALL)
    SELECT p.query_id, p.cand_id, round(coalesce({value}, 0), 6) AS value FROM p LEFT JOIN d ON p.query_id = d.query_id AND p.cand_id = d.cand_id
    LEFT JOIN gnorm x ON x.seq_id = p.query_id LEFT JOIN gnorm y ON y.seq_id = p.cand_id"""


COSINE = """cnt AS (SELECT seq_id, w AS word, count(*) AS c FROM (SELECT seq_id, unnest(tokens) AS w FROM seq) GROUP BY ALL),
    nrm AS (SELECT seq_id, sum(c * c)::DOUBLE AS n2 FROM cnt GROUP BY seq_id),
    cosine AS (SELECT x.seq_id AS query_id, y.seq_id AS cand_id, sum(x.c * y.c)::BIGINT AS dot, sum(x.c * y.c) / sqrt(any_value(u.n2) * any_value(v.n2)) AS cos
      FROM cnt x JOIN cnt y ON x.word = y.word AND x.seq_id <> y.seq_id JOIN nrm u ON u.seq_id = x.seq_id JOIN nrm v ON v.seq_id = y.seq_id {where} GROUP BY ALL)"""
BY_20 = "WHERE x.seq_id % 20 = 0"


def scored(limit: int | None = None) -> str:
    """CTEs that end in scored(query_id, cand_id, s_*, score); limit: only so many candidates by cosine."""
    pairs = PAIRS if limit is None else PAIRS.replace("p AS", "p0 AS") + f""", p1 AS (SELECT p0.*, row_number() OVER (PARTITION BY p0.query_id ORDER BY round(coalesce(cos, 0), 9) DESC, p0.cand_id) AS rk
      FROM p0 LEFT JOIN cosine USING (query_id, cand_id)), p AS (SELECT * FROM p1 WHERE rk <= {limit})"""
    order = [seq(), *([COSINE.replace("{where}", BY_20)] if limit else []), pairs, *([] if limit else [COSINE.replace("{where}", BY_20)])]
    return f"""{', '.join(order)}, {grams(2)},
    d AS (SELECT u.seq_id AS query_id, v.seq_id AS cand_id, sum(u.c * v.c)::DOUBLE AS dot FROM gram u JOIN gram v ON u.g = v.g WHERE u.seq_id % 20 = 0 GROUP BY ALL),
    {wave({'twed': 'twed', 'lcss': 'lcss', 'edr': 'edr', 'erp': 'erp'})},
    sims AS (SELECT wave.query_id, wave.cand_id, coalesce(cosine.cos, 0) AS s_hist, exp(-twed / (m + n)) AS s_twed, lcss / ((m + n) / 2.0::DOUBLE) AS s_lcss, 1 - edr / greatest(m, n) AS s_edr,
      exp(-erp / ((m + n) / 2.0::DOUBLE)) AS s_erp, coalesce(d.dot / sqrt(x.n2 * y.n2), 0) AS s_ngram
      FROM wave LEFT JOIN cosine USING (query_id, cand_id) LEFT JOIN d USING (query_id, cand_id) LEFT JOIN gnorm x ON x.seq_id = query_id LEFT JOIN gnorm y ON y.seq_id = cand_id),
    scored AS (SELECT *, {F03} * s_hist + {F015} * s_twed + {F015} * s_lcss + {F015} * s_edr + {F01} * s_erp + {F015} * s_ngram AS score FROM sims),
    ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(score, 9) DESC, cand_id) AS rank FROM scored)"""


TOP3 = "SELECT query_id, rank::BIGINT AS rank, cand_id, round(score, 6) AS score FROM ranked WHERE rank <= 3"
HIST_RANKED = "hr AS (SELECT query_id, cand_id, cos AS score, row_number() OVER (PARTITION BY query_id ORDER BY round(cos, 9) DESC, cand_id) AS rank FROM cosine)"


#: What a kind of planted performance makes of the places i = 0 .. len - 1: CTE ``seq`` from ``base`` (seq_id, tokens, len).
KINDS = {
    "delete": "list_filter(list_transform(range(0, len), lambda i: CASE WHEN {d} % 100 >= 30 THEN tokens[i + 1] END), lambda w: w IS NOT NULL)",
    "duplicate": "flatten(list_transform(tokens, lambda w: [w, w]))",
    "rotate": "tokens[len // 2 + 1:] || tokens[:len // 2]",
    "crop": "tokens[len // 4 + 1:3 * len // 4]",
}


def performed(kind: str, k: int = 0) -> str:
    """SELECT seq_id, class_id, tokens of one instance of every user's sequence (CTE base), changed by the kind."""
    if kind == "substitute":
        swap = f"CASE WHEN {draw('s', 'seq_id', str(k))} % 100 < 30 THEN (tokens[i + 1] + 1 + {draw('v', 'seq_id', str(k))} % 4) % 5 ELSE tokens[i + 1] END"
        made = f"list_transform(range(0, len), lambda i: {swap})"
    else:
        made = KINDS[kind].replace("{d}", draw("d", "seq_id", str(k)))
    return f"SELECT seq_id * 1000 + {k} AS seq_id, seq_id::VARCHAR AS class_id, {made} AS tokens FROM base"


def draw(salt: str, u: str = "u", k: str = "k") -> str:
    return f"('0x' || substr(md5(concat_ws('|', {u}, {k}, i, '{salt}')), 1, 4))::INT"


def planted(instances: int = 5, noise: int = 30, vocabulary: int = 5, where: str = "") -> str:
    """CTEs up to seq(seq_id, class_id, instance_id, tokens): the noisy variants of every user's sequence."""
    return f"""{seq().replace("seq AS (", "base AS (")},
    cells AS (SELECT seq_id AS u, k, i, tokens[i + 1] AS w FROM base, range(0, {instances}) a(k), range(0, 200000) b(i) WHERE i < len {where}),
    noisy AS (SELECT u, k, i, CASE WHEN {draw('s')} % 100 < {noise} THEN (w + 1 + {draw('v')} % {vocabulary - 1}) % {vocabulary} ELSE w END AS w FROM cells),
    seq AS (SELECT u * 1000 + k AS seq_id, u::VARCHAR AS class_id, k::INT AS instance_id, list(w ORDER BY i) AS tokens, count(*) AS len FROM noisy GROUP BY u, k)"""


def judged(ranked: str = "hr") -> str:
    """CTE best(query_id, class_id, best_rank, score) from the ranked answers and seq."""
    return f"""hits AS (SELECT r.query_id, min(r.rank) AS best_rank FROM {ranked} r JOIN seq x ON x.seq_id = r.query_id JOIN seq y ON y.seq_id = r.cand_id WHERE r.rank <= 3 AND x.class_id = y.class_id GROUP BY r.query_id),
    best AS (SELECT q.seq_id AS query_id, q.class_id, hits.best_rank, CASE hits.best_rank WHEN 1 THEN 1.0 WHEN 2 THEN 0.5 WHEN 3 THEN 0.25 ELSE 0.0 END::DOUBLE AS score FROM asked q LEFT JOIN hits ON hits.query_id = q.seq_id)"""


MEASURES = """SELECT '{method}' AS method, round(avg(score), 6) AS mean_score, round(100 * avg(CASE WHEN best_rank IS NOT NULL THEN 1.0 ELSE 0.0 END::DOUBLE), 6) AS match_rate,
    round(100 * avg(CASE WHEN best_rank = 1 THEN 1.0 ELSE 0.0 END::DOUBLE), 6) AS rank1_rate, count(*) AS queries FROM best"""

LATENTS = "lat AS (SELECT vec_id // 20 AS clip_id, (vec_id % 20)::INT AS t, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings)"
PATCHES = LATENTS + """, pat AS (SELECT clip_id, t // 2 AS patch_idx, flatten(list(v ORDER BY t)) AS vec FROM lat GROUP BY clip_id, t // 2 HAVING count(*) = 2),
    book AS (SELECT row_number() OVER (ORDER BY md5('start7|' || clip_id || '|' || patch_idx), clip_id, patch_idx)::INT - 1 AS code, vec AS c FROM pat QUALIFY code < 64),
    asg AS (SELECT clip_id, patch_idx, arg_min(code, (round(d, 9), code)) AS code, min(round(d, 9)) AS dist2 FROM
      (SELECT clip_id, patch_idx, code, list_sum(list_transform(list_zip(vec, c), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS d FROM pat, book) GROUP BY clip_id, patch_idx)"""
EMA = """sums AS (SELECT code, i, sum(x) AS s FROM (SELECT a.code, unnest(p.vec) AS x, unnest(range(0, len(p.vec))) AS i FROM pat p JOIN asg a USING (clip_id, patch_idx)) GROUP BY code, i),
    hit AS (SELECT code, count(*) AS hits FROM asg GROUP BY code),
    old AS (SELECT code, unnest(c) AS x, unnest(range(0, len(c))) AS i FROM book),
    ema AS (SELECT old.code, old.i, 0.5::DOUBLE * old.x + 0.5::DOUBLE * coalesce(s, 0) AS m, 0.5::DOUBLE + 0.5::DOUBLE * coalesce(hits, 0) AS n FROM old LEFT JOIN sums USING (code, i) LEFT JOIN hit USING (code))"""


def words(column: str) -> str:
    return f"list_filter(regexp_split_to_array(lower(coalesce({column}, '')), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> '')"
