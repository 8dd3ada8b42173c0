"""URL filter: pattern rules found through their rarest literal token. DataFrame functions only.

Each rule names the literal tokens that any URL it matches must hold. The index keeps a rule under
the one of them that is rarest in the corpus; a URL's own tokens fetch its candidate rules, and only
those run their regular expression. The rule set is small by nature (its size is checked), so the
index is a literal map and a URL is judged where it is read: no join, no exchange.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MAX_RULES = 5000


@dataclass(frozen=True)
class PatternRule:
    """tokens: runs of a-z and 0-9, bounded on both sides, that every match holds in lower case."""

    name: str
    verdict: str
    pattern: str
    tokens: tuple[str, ...]
    on: str = "url"


def site_rule(verdict: str, host: str, path: str) -> PatternRule:
    """A rule on a host with its subdomains and a path prefix."""
    quoted = "".join(c if c.isalnum() or c in "/_" else "\\" + c for c in host + path)
    whole = host.split(".") + [t for t in path.split("/")[1:-1] if t.isalnum()]
    return PatternRule(host + path, verdict, f"^([^/]*\\.)?{quoted}", tuple(t.lower() for t in whole if t), "site")


#: The site rules asked for. Fixed values.
SITE_RULES = (
    site_rule("allow", "org", "/"),
    site_rule("block", "example.org", "/es/"),
    site_rule("block", "example.org", "/en/1"),
    site_rule("allow", "com", "/fr/"),
    site_rule("block", "com", "/de/"),
)

#: The method's own rules, on whole URLs in lower case.
PATTERN_RULES = (
    PatternRule("gambling-host", "block", r"://[^/?#]*\bcasino\b", ("casino",)),
    PatternRule("poker-host", "block", r"://[^/?#]*\bpoker\b", ("poker",)),
    PatternRule("adult-host", "block", r"://[^/?#]*\bporn\b", ("porn",)),
    PatternRule("adult-tld", "block", r"://[^/?#]*\.xxx([:/?#]|$)", ("xxx",)),
    PatternRule("pills", "block", r"\b(buy|cheap)[-_/]viagra\b", ("viagra",)),
    PatternRule("prize", "block", r"\bfree[-_]prize\b", ("free", "prize")),
    PatternRule("torrent", "block", r"://[^/?#]*\btorrent\b", ("torrent",)),
    PatternRule("admin-login", "block", r"/wp-login\.php\b", ("wp", "login", "php")),
    PatternRule("ad-click", "block", r"/ads?/click\b", ("click",)),
    PatternRule("tracker", "block", r"[?&]affiliate_id=[0-9]+", ("affiliate", "id")),
)


def _url_parts(url: Column) -> tuple[Column, Column]:
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.expr("substring(url, instr(url, '://') + 3)")).otherwise("")
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(F.translate(host, upper, lower), F.lit("")), F.coalesce(path, F.lit(""))


def url_tokens(url: Column) -> Column:
    """Distinct runs of a-z and 0-9 of the lower-case URL."""
    return F.array_distinct(F.split(F.lower(F.coalesce(url, F.lit(""))), "[^a-z0-9]+"))


def token_frequencies(pages: DataFrame, tokens: set[str]) -> dict[str, int]:
    """How many URLs hold each of the rules' tokens; the result is bounded by the rules."""
    wanted = F.array(*[F.lit(t) for t in sorted(tokens)])
    held = pages.select(F.explode(F.array_intersect(url_tokens(F.col("url")), wanted)).alias("token"))
    return {r.token: r["n"] for r in held.groupBy("token").agg(F.count("*").alias("n")).collect()}


def rarest_token_index(rules: tuple[PatternRule, ...], frequency: dict[str, int]) -> dict[str, list[int]]:
    """Token -> positions of the rules kept under it."""
    index: dict[str, list[int]] = {}
    for k, rule in enumerate(rules):
        index.setdefault(min(rule.tokens, key=lambda t: (frequency.get(t, 0), t)), []).append(k)
    return index


def judge_urls(pages: DataFrame, site_rules: tuple[PatternRule, ...] = SITE_RULES, pattern_rules: tuple[PatternRule, ...] = PATTERN_RULES) -> DataFrame:
    """pages plus host, path, rule (longest fitting site rule or null), verdict and pattern (first fitting pattern rule or null).

    A site rule decides; else a block by any pattern rule; else allow. Null URLs and URLs without ://
    have an empty host and path and fit no site rule. Rows are judged one by one: repeats repeat.
    """
    rules = tuple(sorted(site_rules, key=lambda r: (-len(r.name), r.name))) + tuple(pattern_rules)
    if len(rules) > MAX_RULES:
        raise ValueError(f"{len(rules)} rules exceed the literal index of {MAX_RULES}")
    index = rarest_token_index(rules, token_frequencies(pages, {t for r in rules for t in r.tokens}))
    entries: list[Column] = []
    for token, own in sorted(index.items()):
        entries += [F.lit(token), F.array(*[F.lit(k) for k in own])]
    by_token = F.create_map(*entries)
    patterns = F.array(*[F.lit(r.pattern) for r in rules])
    names = F.array(*[F.lit(r.name) for r in rules])
    verdicts = F.array(*[F.lit(r.verdict) for r in rules])
    n_site = len(site_rules)
    host, path = _url_parts(F.col("url"))
    keys = F.array(*[F.lit(t) for t in sorted(index)])
    base = pages.select("page_id", "url").withColumns({"host": host, "path": path})
    fetched = base.withColumn("candidates", F.flatten(F.transform(F.array_intersect(url_tokens(F.col("url")), keys), lambda t: F.element_at(by_token, t))))
    site, whole = F.concat("host", "path"), F.lower("url")
    fits = F.filter("candidates", lambda k: F.rlike(F.when(k < n_site, site).otherwise(whole), F.get(patterns, k)))
    found = fetched.withColumn("fits", F.array_sort(fits))
    first_site = F.when(F.size("fits") > 0, F.when(F.col("fits")[0] < n_site, F.col("fits")[0]))
    own = F.filter("fits", lambda k: k >= n_site)
    first_pattern = F.when(F.size(own) > 0, own[0])
    judged = found.withColumns({"site_at": first_site, "pattern_at": first_pattern})
    return judged.select(
        "page_id",
        "host",
        "path",
        F.get(names, F.col("site_at")).alias("rule"),
        F.coalesce(F.get(verdicts, F.col("site_at")), F.get(verdicts, F.col("pattern_at")), F.lit("allow")).alias("verdict"),
        F.get(names, F.col("pattern_at")).alias("pattern"),
    )


def judge_sql(site_rules: tuple[PatternRule, ...] = SITE_RULES, pattern_rules: tuple[PatternRule, ...] = PATTERN_RULES) -> str:
    """The same verdicts by trying every rule, in DuckDB's SQL."""
    q = lambda s: "'" + s.replace("'", "''") + "'"
    ordered = sorted(site_rules, key=lambda r: (-len(r.name), r.name))
    pick = lambda rs, on, out: "CASE " + " ".join(f"WHEN regexp_matches({on}, {q(r.pattern)}) THEN {q(getattr(r, out))}" for r in rs) + " END"
    return f"""
    WITH rest AS (SELECT page_id, url, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
    parts AS (SELECT page_id, url, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
      regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM rest)
    SELECT page_id, host, path, {pick(ordered, "host || path", "name")} AS rule,
      coalesce({pick(ordered, "host || path", "verdict")}, {pick(pattern_rules, "lower(url)", "verdict")}, 'allow') AS verdict,
      {pick(pattern_rules, "lower(url)", "name")} AS pattern FROM parts"""
