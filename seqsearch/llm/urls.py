"""URL filters by rules that are indexed by their rarest literal token.

Two kinds of rules: *site* rules (a host and its subdomains, and the start of a path; the longest that fits wins), and
*pattern* rules (a regular expression over the URL).  Every rule names the literal tokens that a URL must have for the rule
to fit; it is filed under the one that is rarest among the URLs.  A URL's tokens fetch its candidate rules, and only those
are tried.  All of it is DataFrame functions.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .url_rules import LINES

#: Rules beyond this many are joined rather than kept in the plan.
PLAN_RULES = 5_000


@dataclass(frozen=True)
class SiteRule:
    host: str
    path: str  # starts with "/"
    verdict: str

    @property
    def text(self) -> str:
        return self.host + self.path

    @property
    def tokens(self) -> list[str]:
        """The whole tokens of every URL that fits: a path that ends within a token only starts one of the URL's."""
        found = _split(self.text.lower())
        return found[:-1] if self.path[-1:].isascii() and self.path[-1:].isalnum() else found


@dataclass(frozen=True)
class PatternRule:
    pattern: str  # a regular expression that Java and RE2 read alike, over the lower-case URL
    literals: tuple[str, ...]  # whole tokens that every URL that fits has
    verdict: str = "block"

    @property
    def tokens(self) -> list[str]:
        return list(self.literals)


def _split(text: str) -> list[str]:
    return "".join(c if c.isascii() and c.isalnum() else " " for c in text).split()


SITE_RULES = (
    SiteRule("com", "/", "allow"),
    SiteRule("example.com", "/en/", "block"),
    SiteRule("www.example.com", "/en/", "allow"),
    SiteRule("net", "/es/", "block"),
    SiteRule("net", "/fr/", "block"),
)

def _pattern_rules() -> tuple[PatternRule, ...]:
    rows = [line.split(" | ", 2) if line.count(" | ") > 1 else [line.split(" ", 1)[0], "", line.split(" | | ")[1]] for line in LINES.strip().splitlines()]
    return tuple(PatternRule(pattern, tuple(literals.split()), verdict) for verdict, literals, pattern in rows)


PATTERN_RULES = _pattern_rules()


def rules_from(table: DataFrame) -> tuple[list[SiteRule], list[PatternRule]]:
    """(site rules, pattern rules) of a table (host, path, pattern, literals, verdict), in order of its column ``rank``; a rule
    with a null pattern is a site rule.  At most ``PLAN_RULES`` rows; larger tables are for :func:`judge_by_join`."""
    rows = table.select("rank", "host", "path", "pattern", "literals", "verdict").limit(PLAN_RULES + 1).collect()
    if len(rows) > PLAN_RULES:
        raise ValueError(f"more than {PLAN_RULES} rules: use judge_by_join")
    rows.sort(key=lambda r: r["rank"])
    sites = [SiteRule(r["host"], r["path"] or "/", r["verdict"]) for r in rows if r["pattern"] is None]
    return sites, [PatternRule(r["pattern"], tuple(r["literals"] or ()), r["verdict"]) for r in rows if r["pattern"] is not None]


def _low(url: Column) -> Column:
    """A-Z in lower case, null as empty."""
    return F.translate(F.coalesce(url, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host: what follows the first ``://`` up to ``/ ? #``, A-Z in lower case; path: then up to ``? #``.  Else both empty."""
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substr(url, at + F.lit(3))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return host, path


def url_tokens(url: Column) -> Column:
    """The distinct runs of ASCII letters and digits, in lower case."""
    return F.array_distinct(F.filter(F.split(_low(url), "[^a-z0-9]+"), lambda t: t != ""))


def rarest_tokens(urls: DataFrame, rules: Sequence, url: str = "url") -> dict[str, int]:
    """How many URLs have each literal token of the rules: one row for each token of the rules, counted over all URLs."""
    wanted = sorted({t for r in rules for t in r.tokens})
    if not wanted:
        return {}
    named = F.array(*[F.lit(t) for t in wanted])
    rows = urls.select(F.explode(F.array_intersect(url_tokens(F.col(url)), named)).alias("t")).groupBy("t").agg(F.count("*").alias("n")).collect()
    return {r["t"]: r["n"] for r in rows}


def index_rules(rules: Sequence, counts: dict[str, int]) -> dict[str, list[int]]:
    """Token to the rules filed under it: each rule under its rarest; rules without a literal under ``""``."""
    out: dict[str, list[int]] = {}
    for i, r in enumerate(rules):
        out.setdefault(min(r.tokens, key=lambda t: (counts.get(t, 0), t), default=""), []).append(i)
    return out


def _rule_struct(rule, position: int) -> Column:
    site = isinstance(rule, SiteRule)
    return F.struct(
        F.lit(site).alias("site"),
        F.lit(rule.host if site else "").alias("host"),
        F.lit(rule.path if site else "").alias("path"),
        F.lit("" if site else rule.pattern).alias("pattern"),
        F.lit(rule.verdict).alias("verdict"),
        F.lit(len(rule.text) if site else 0).alias("size"),
        F.lit(-position).alias("rank"),
    )


def _fits(r: Column, host: Column, path: Column, lower: Column) -> Column:
    site = ((host == r["host"]) | F.endswith(host, F.concat(F.lit("."), r["host"]))) & F.startswith(path, r["path"])
    return F.when(r["site"], site).otherwise(F.regexp_like(lower, r["pattern"]))


def judge(urls: DataFrame, site_rules: Sequence[SiteRule] = SITE_RULES, pattern_rules: Sequence[PatternRule] = PATTERN_RULES, url: str = "url", default: str = "allow", keep: Sequence[str] = ("page_id",)) -> DataFrame:
    """``keep`` columns and host, path, rule, verdict, pattern, n_candidates; one row for each row of ``urls``.

    The longest site rule that fits decides (of equal ones the first); where none does, the first pattern rule that fits,
    else ``default``.  A null URL, or one without ``://``, has an empty host and path: no site rule fits.
    Empty tables and repeated rows need no care: rows are judged one by one, without a shuffle.
    """
    rules = [*site_rules, *pattern_rules]
    if len(rules) > PLAN_RULES:
        raise ValueError(f"more than {PLAN_RULES} rules: use judge_by_join")
    counts = rarest_tokens(urls, rules, url)
    filed = index_rules(rules, counts)
    kind = _rule_struct(SiteRule("", "", ""), 0)
    always = F.array(*[_rule_struct(rules[i], i) for i in filed.pop("", [])]) if "" in filed else F.filter(F.array(kind), lambda r: F.lit(False))
    host, path = host_and_path(F.col(url))
    own = urls.select(*[F.col(c) for c in keep], F.col(url).alias("__url"))
    own = own.select(*keep, "__url", host_and_path(F.col("__url"))[0].alias("host"), host_and_path(F.col("__url"))[1].alias("path"), url_tokens(F.col("__url")).alias("__tokens"))
    if filed:
        by_token = F.create_map(*[x for t, ids in sorted(filed.items()) for x in (F.lit(t), F.array(*[_rule_struct(rules[i], i) for i in ids]))])
        named = F.array(*[F.lit(t) for t in sorted(filed)])
        fetched = F.flatten(F.transform(F.array_intersect(F.col("__tokens"), named), lambda t: F.element_at(by_token, t)))
        candidates = F.concat(fetched, always)
    else:
        candidates = always
    own = own.withColumn("__c", candidates)
    lower = _low(F.col("__url"))
    own = own.withColumn("__fit", F.filter("__c", lambda r: _fits(r, F.col("host"), F.col("path"), lower)))
    return own.select(*keep, "host", "path", *_decide(F.col("__fit"), default), F.size("__c").alias("n_candidates"))


def _decide(fit: Column, default: str) -> list[Column]:
    site = F.array_max(F.transform(F.filter(fit, lambda r: r["site"]), lambda r: F.struct(r["size"], r["rank"], F.concat(r["host"], r["path"]).alias("rule"), r["verdict"])))
    pattern = F.array_max(F.transform(F.filter(fit, lambda r: ~r["site"]), lambda r: F.struct(r["rank"], r["pattern"], r["verdict"])))
    return [
        site["rule"].alias("rule"),
        F.coalesce(site["verdict"], pattern["verdict"], F.lit(default)).alias("verdict"),
        pattern["pattern"].alias("pattern"),
    ]


def judge_by_join(urls: DataFrame, rules: DataFrame, url: str = "url", key: str = "page_id", default: str = "allow") -> DataFrame:
    """The same for a large table of rules (token, site, host, path, pattern, verdict, size, rank), where token is the rarest
    literal: URLs are joined to their candidates on the token.  ``key`` must be unique.  Each URL gives a row for each of its
    tokens; a token that very many URLs have is the rarest of few rules, and the join on it can be split."""
    host, path = host_and_path(F.col(url))
    own = urls.select(F.col(key).alias("__key"), _low(F.col(url)).alias("__url"), host.alias("host"), path.alias("path"), F.explode_outer(F.array_union(url_tokens(F.col(url)), F.array(F.lit("")))).alias("token"))
    r = rules.select("token", F.struct("site", "host", "path", "pattern", "verdict", "size", "rank").alias("r"))
    tried = own.join(r, "token").where(_fits(F.col("r"), own["host"], own["path"], F.col("__url")))
    best = tried.groupBy("__key").agg(F.max(F.when(F.col("r.site"), F.struct("r.size", "r.rank", F.concat("r.host", "r.path").alias("rule"), "r.verdict"))).alias("s"), F.max(F.when(~F.col("r.site"), F.struct("r.rank", "r.pattern", "r.verdict"))).alias("p"))
    every = urls.select(F.col(key).alias("__key"), host.alias("host"), path.alias("path"))
    return every.join(best, "__key", "left").select(F.col("__key").alias(key), "host", "path", F.col("s.rule").alias("rule"), F.coalesce("s.verdict", "p.verdict", F.lit(default)).alias("verdict"), F.col("p.pattern").alias("pattern"))


def rule_table(spark, rules: Sequence, counts: dict[str, int] | None = None) -> DataFrame:
    """Rules as a table for :func:`judge_by_join`."""
    filed = {i: t for t, ids in index_rules(rules, counts or {}).items() for i in ids}
    rows = [(filed[i], isinstance(r, SiteRule), getattr(r, "host", ""), getattr(r, "path", ""), getattr(r, "pattern", ""), r.verdict, len(getattr(r, "text", "")), -i) for i, r in enumerate(rules)]
    return spark.createDataFrame(rows, "token string, site boolean, host string, path string, pattern string, verdict string, size int, rank int")


def verdict_sql(pages: str = "pages", site_rules: Sequence[SiteRule] = SITE_RULES, pattern_rules: Sequence[PatternRule] = PATTERN_RULES, default: str = "allow") -> str:
    """The same judgement as SQL without the index, for checks."""
    def q(s: str) -> str:
        return "'" + s.replace("'", "''") + "'"

    sites = ", ".join(f"({q(r.host)}, {q(r.path)}, {q(r.verdict)}, {i})" for i, r in enumerate(site_rules))
    patterns = ", ".join(f"({q(r.pattern)}, {q(r.verdict)}, {i})" for i, r in enumerate(pattern_rules))
    low = "translate(%s, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    return f"""
    WITH s(h, p, v, i) AS (VALUES {sites}), x(re, v, i) AS (VALUES {patterns}),
    u AS (SELECT page_id, coalesce(url, '') AS url, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM {pages}),
    w AS (SELECT row_number() OVER () AS n, page_id, url, {low % "regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1)"} AS host, regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) AS path FROM u),
    b AS (SELECT w.n, arg_max(s.h || s.p, length(s.h || s.p) * 1000000 - s.i) AS rule, arg_max(s.v, length(s.h || s.p) * 1000000 - s.i) AS v
          FROM w JOIN s ON (w.host = s.h OR ends_with(w.host, '.' || s.h)) AND starts_with(w.path, s.p) GROUP BY w.n),
    c AS (SELECT w.n, arg_min(x.re, x.i) AS re, arg_min(x.v, x.i) AS v FROM w JOIN x ON regexp_matches({low % 'w.url'}, x.re) GROUP BY w.n)
    SELECT page_id, host, path, b.rule AS rule, coalesce(b.v, c.v, {q(default)}) AS verdict, c.re AS pattern
    FROM w LEFT JOIN b ON w.n = b.n LEFT JOIN c ON w.n = c.n"""
