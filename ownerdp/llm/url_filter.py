"""URL filters in DataFrame functions only: host rules, then pattern rules fetched by their rarest literal token."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The host rules of the contract, (host and path, verdict).
HOST_RULES = [("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block"), ("net/fr/", "block")]


@dataclass(frozen=True)
class PatternRule:
    """A regular expression over the whole lower-cased URL. Of the rules that match, the highest priority decides."""

    pattern: str
    verdict: str
    priority: int

    def tokens(self) -> list[str]:
        """The literal tokens that every matching URL has as whole tokens: runs of letters and digits with a delimiter on both sides."""
        plain = re.sub(r"\[[^\]]*\]", "\0", self.pattern)  # a class is no literal, nor is a group that may be missing
        plain = re.sub(r"\((?:\?:)?[^()]*\)[?*]", "", plain)
        plain = re.sub(r"\\([./?=&-])", r"\1", plain)
        return [m[1] for m in re.finditer(r"(?<=[/.?=&-])([a-z0-9_]+)(?=[/.?=&-])", plain)]


PATTERN_RULES = [
    PatternRule(r"/(?:[^?#]*/)?ads/", "block", 5),
    PatternRule(r"\?(?:[^#]*&)?utm_source=feed\b", "block", 2),
    PatternRule(r"//m\.[a-z]+\.example\.org/", "block", 3),
    PatternRule(r"//blog\.[a-z]+\.example\.org/de/", "block", 4),
    PatternRule(r"//[a-z.]+\.example\.org/de/[0-9]+\.html$", "block", 3),
    PatternRule(r"\?(?:[^#]*&)?ref=x\b", "allow", 1),
    PatternRule(r"//www\.[a-z]+\.example\.org/de/", "allow", 6),
    PatternRule(r"/login/", "block", 7),
    PatternRule(r"/tag/[a-z]+/page/", "block", 3),
]
_ALWAYS = ""  # the index key of rules without a literal token
BUCKETS = 64
#: The rule index is a literal in the plan; more rules than this are refused.
MOST_RULES = 5000


def _after_scheme() -> Column:
    return F.when(F.instr("url", "://") > 0, F.expr("substring(url, locate('://', url) + 3)"))


def host() -> Column:
    """The host of the column ``url``, A-Z lower-cased; empty for null and where there is no ``://``."""
    return F.coalesce(F.translate(F.regexp_extract(_after_scheme(), r"^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path() -> Column:
    return F.coalesce(F.regexp_extract(_after_scheme(), r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def matching_host_rule(host: Column, path: Column, rules: list[tuple[str, str]]) -> Column:
    """The longest rule that fits, as struct<rule, verdict>; null if none does."""
    out = None
    for rule, verdict in sorted(rules, key=lambda r: -len(r[0])):
        rule_host, slash, rule_path = rule.partition("/")
        fits = ((host == rule_host) | F.endswith(host, F.lit("." + rule_host))) & F.startswith(path, F.lit(slash + rule_path))
        value = F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))
        out = F.when(fits, value) if out is None else out.when(fits, value)
    return F.lit(None).cast("struct<rule:string,verdict:string>") if out is None else out


def url_tokens(url: Column) -> Column:
    return F.array_distinct(F.filter(F.split(F.lower(url), r"[^a-z0-9_]+"), lambda t: t != ""))


def token_frequencies(pages: DataFrame, rules: list[PatternRule], url: str = "url") -> dict[str, int]:
    """How many URLs have each token of a rule; the result has at most as many rows as the rules have tokens."""
    wanted = sorted({t for r in rules for t in r.tokens()})
    if not wanted:
        return {}
    held = F.array_intersect(url_tokens(F.col(url)), F.array(*map(F.lit, wanted)))
    return {r["t"]: r["n"] for r in pages.select(F.explode(held).alias("t")).groupBy("t").agg(F.count(F.lit(1)).alias("n")).collect()}


def rule_index(rules: list[PatternRule], frequency: dict[str, int]) -> Column:
    """array<map<token, array<rule>>>, one map for each hash bucket of the tokens, as a literal of the plan.

    Every rule stands under the least frequent of its literal tokens, so that a URL fetches few rules.
    """
    if len(rules) > MOST_RULES:
        raise ValueError(f"{len(rules)} pattern rules; the index of the plan holds {MOST_RULES}")
    by_token: dict[str, list[PatternRule]] = {}
    for r in rules:
        by_token.setdefault(min(r.tokens(), key=lambda t: (frequency.get(t, 0), t), default=_ALWAYS), []).append(r)
    buckets: list[list[tuple[str, list[PatternRule]]]] = [[] for _ in range(BUCKETS)]
    for token, its in sorted(by_token.items()):
        buckets[_bucket(token)].append((token, its))
    as_rule = lambda r: F.struct(F.lit(r.priority).alias("priority"), F.lit(r.pattern).alias("pattern"), F.lit(r.verdict).alias("verdict"))
    kind = "map<string,array<struct<priority:int,pattern:string,verdict:string>>>"
    empty = F.create_map().cast(kind)
    return F.array(*(F.create_map(*(c for t, its in b for c in (F.lit(t), F.array(*map(as_rule, its))))).cast(kind) if b else empty for b in buckets))


def _bucket(token: str) -> int:
    return sum(token.encode()) % BUCKETS


def bucket_of(token: Column) -> Column:
    """The same bucket number in Spark: the sum of the token's ASCII bytes."""
    codes = F.transform(F.split(token, ""), lambda c: F.when(c == "", 0).otherwise(F.ascii(c)))
    return F.aggregate(codes, F.lit(0), lambda a, c: a + c) % BUCKETS


def filter_urls(
    pages: DataFrame, url: str = "url", page_id: str = "page_id", host_rules=HOST_RULES, pattern_rules=PATTERN_RULES,
    default: str = "allow", frequency: dict[str, int] | None = None,
) -> DataFrame:
    """One row for each page: page_id, host, path, rule, verdict, pattern, n_candidates.

    A host rule decides where one fits. Else the pattern rule of the highest priority among the candidates that match
    decides (ties: the alphabetically last pattern), else ``default``. Null URLs and those without ``://`` have an empty
    host and path, and no host rule fits them. Nothing is shuffled but the counts of the rules' tokens.
    """
    rows = pages.select(F.col(page_id).alias("page_id"), F.col(url).alias("url"))
    counts = token_frequencies(rows, pattern_rules) if frequency is None else frequency
    index = rule_index(pattern_rules, counts)
    parts = rows.select("page_id", "url", host().alias("host"), path().alias("path"), F.lower(F.coalesce("url", F.lit(""))).alias("low"))
    chosen = parts.withColumn("h", matching_host_rule(F.col("host"), F.col("path"), host_rules))
    tokens = F.concat(F.array(F.lit(_ALWAYS)), url_tokens(F.coalesce(F.col("url"), F.lit(""))))
    fetched = F.flatten(F.filter(F.transform(tokens, lambda t: F.try_element_at(F.get(index, bucket_of(t)), t)), lambda x: x.isNotNull()))
    candidates = chosen.withColumn("candidates", F.when(F.col("h").isNull(), fetched))
    hits = candidates.withColumn("best", F.array_max(F.filter("candidates", lambda r: F.regexp_like(F.col("low"), r["pattern"]))))
    return hits.select(
        "page_id", "host", "path", F.col("h.rule").alias("rule"),
        F.coalesce(F.col("h.verdict"), F.col("best.verdict"), F.lit(default)).alias("verdict"),
        F.col("best.pattern").alias("pattern"), F.coalesce(F.size("candidates"), F.lit(0)).alias("n_candidates"),
    )


def oracle_sql(host_rules=HOST_RULES, pattern_rules=PATTERN_RULES, default: str = "allow") -> str:
    """The same verdicts in DuckDB SQL, with every pattern tried on every URL."""
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    fits = lambda r: f"(host = {quote(r.partition('/')[0])} OR ends_with(host, {quote('.' + r.partition('/')[0])})) AND starts_with(path, {quote('/' + r.partition('/')[2])})"
    ordered = sorted(host_rules, key=lambda r: -len(r[0]))
    rule = " ".join(f"WHEN {fits(r)} THEN {quote(r)}" for r, _ in ordered)
    verdict = " ".join(f"WHEN rule = {quote(r)} THEN {quote(v)}" for r, v in ordered)
    best = sorted(pattern_rules, key=lambda r: (-r.priority, [-ord(c) for c in r.pattern]))
    pattern = " ".join(f"WHEN regexp_matches(low, {quote(r.pattern)}) THEN {quote(r.pattern)}" for r in best)
    said = " ".join(f"WHEN pattern = {quote(r.pattern)} THEN {quote(r.verdict)}" for r in best)
    return f"""
WITH parts AS (
  SELECT page_id, coalesce(lower(url), '') AS low,
         CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
cut AS (
  SELECT page_id, low, translate(regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) AS path FROM parts),
ruled AS (SELECT *, CASE {rule} END AS rule FROM cut),
matched AS (SELECT *, CASE WHEN rule IS NULL THEN CASE {pattern} END END AS pattern FROM ruled)
SELECT page_id, host, path, rule, CASE {verdict} {said} ELSE {quote(default)} END AS verdict, pattern FROM matched"""
