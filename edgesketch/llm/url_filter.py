"""URL filters: pattern rules indexed by their rarest literal token, in DataFrame functions only.

Every rule is a regular expression with the literal tokens that any match of it holds whole. How
often each of these tokens occurs in the urls is counted over all of them, and each rule is entered
in the index under its rarest token (a rule without a token, under the empty one, which every url
has). The tokens of a url fetch its candidate rules, and only those are run. Site rules (a host with
its subdomains and a path prefix, longest wins) are such patterns over ``host || path``; block
patterns over the whole lower-cased url give the verdict where no site rule fits.

Each distinct url is judged once, then joined back, so a repeated url costs nothing more.

Defined results: a null url, or one without ``://``, has an empty host and path and is allowed; an
empty url too; repeated rows get a row each; an empty table gives no rows; extra columns are ignored;
very long urls are read whole; of site rules of one length the first by name wins.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from edgesketch.llm.common import ascii_lower, table


@dataclass(frozen=True)
class SiteRule:
    host: str
    path: str
    verdict: str

    @property
    def name(self) -> str:
        return self.host + self.path

    @property
    def pattern(self) -> str:
        return rf"^(?:[^/]*\.)?{re.escape(self.name)}"

    @property
    def tokens(self) -> tuple[str, ...]:
        """Whole tokens of any match: all but one that the path may cut off at its end."""
        found = re.findall(r"[a-z0-9]+", self.name.lower())
        return tuple(found[:-1] if re.search(r"[A-Za-z0-9]$", self.name) else found)


@dataclass(frozen=True)
class Pattern:
    """Blocks a url whose lower-cased whole matches; tokens stand whole in every match."""

    name: str
    pattern: str
    tokens: tuple[str, ...]


SITE_RULES = (
    SiteRule("com", "/en/", "block"),
    SiteRule("example.com", "/en/7", "allow"),
    SiteRule("net", "/de/", "allow"),
    SiteRule("example.net", "/de/8", "block"),
    SiteRule("org", "/es/", "block"),
)

def branches(name: str, before: str, words: tuple[str, ...], after: str, more: tuple[str, ...] = ()) -> list[Pattern]:
    """One pattern for each literal of an alternation, so that each is indexed by a token of its own."""
    return [Pattern(f"{name}: {w}", before + w + after, (w, *more)) for w in words]


#: Urls that hold no article: sign-in, baskets, feeds, trackers and the like.
PATTERNS = (
    Pattern("login script", r"/wp-login\.php(?:[?#]|$)", ("wp", "login", "php")),
    Pattern("admin area", r"/wp-admin(?:/|$)", ("wp", "admin")),
    *(p for w in ("account", "user", "users", "member") for p in branches(f"sign in to {w}", rf"/{w}/", ("login", "signin", "register"), r"\b", (w,))),
    *branches("basket", "/", ("cart", "basket", "checkout"), r"(?:/|\?|$)"),
    *branches("feed", "/", ("rss", "feed", "atom"), r"(?:\.xml)?/?(?:\?|$)"),
    *branches("ad server", "://", ("ad", "ads", "adserver", "doubleclick"), r"\."),
    # digits make one token with the word, so this one has none
    Pattern("numbered ad server", r"://(?:ad|ads|adserver|doubleclick)\d+\.", ()),
    *branches("tracker", "/", ("pixel", "beacon", "collect"), r"\.gif(?:\?|$)", ("gif",)),
    *branches("gambling host", r"://[^/?#]*\b", ("casino", "poker", "slots"), r"\b"),
    *branches("adult host", r"://[^/?#]*\b", ("porn", "xxx"), r"\b"),
    *branches("archive file", r"\.", ("zip", "rar", "exe", "dmg", "iso"), r"(?:\?|$)"),
    *branches("print view", "[?&]print=", ("1", "true", "yes"), "(?:&|$)", ("print",)),
    Pattern("reply form", r"[?&]replytocom=\d+", ("replytocom",)),
    *branches("session id", "[?&;]", ("phpsessid", "jsessionid"), "=[0-9a-f]{16,}"),
)


def parts(url: Column) -> tuple[Column, Column]:
    """(host, path) of a url; both empty for null or without ``://``."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise(F.lit(""))
    host = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(F.substr(rest, F.length(host) + 1), "^[^?#]*", 0)
    return F.coalesce(ascii_lower(host), F.lit("")), F.coalesce(path, F.lit(""))


def url_tokens(url: Column) -> Column:
    """Distinct tokens of a lower-cased url, and the empty token that fetches rules without one."""
    return F.array_append(F.array_distinct(F.regexp_extract_all(F.lower(url), F.lit("[a-z0-9]+"), F.lit(0))), F.lit(""))


def rule_table(spark, site_rules=SITE_RULES, patterns=PATTERNS) -> DataFrame:
    rows = [(r.name, True, r.pattern, r.verdict, len(r.name), list(r.tokens) or [""]) for r in site_rules]
    rows += [(p.name, False, p.pattern, "block", 0, list(p.tokens) or [""]) for p in patterns]
    return spark.createDataFrame(rows, "rule string, site boolean, pattern string, verdict string, rank int, tokens array<string>")


def index(rules: DataFrame, tokens: DataFrame) -> DataFrame:
    """The rules with the token, rarest in the urls, under which each is entered."""
    literal = rules.select("rule", "site", F.explode("tokens").alias("token"))
    seen = tokens.join(F.broadcast(literal.select("token").distinct()), "token", "left_semi").groupBy("token").agg(F.count(F.lit(1)).alias("n"))
    counted = literal.join(seen, "token", "left").select("rule", "site", "token", F.coalesce("n", F.lit(0)).alias("n"))
    rarest = counted.groupBy("rule", "site").agg(F.min_by("token", F.struct("n", "token")).alias("token"))
    return rules.drop("tokens").join(rarest, ["rule", "site"])


def judge(pages: DataFrame, site_rules=SITE_RULES, patterns=PATTERNS) -> DataFrame:
    """page_id, host, path, rule and verdict of every page."""
    spark = pages.sparkSession
    own = pages.select("page_id", F.col("url").cast("string").alias("url"))
    urls = own.select("url").where(F.col("url").isNotNull()).distinct()
    host, path = parts(F.col("url"))
    tokens = urls.select("url", F.explode(url_tokens(F.col("url"))).alias("token"))
    entered = index(rule_table(spark, site_rules, patterns), tokens)
    fetched = tokens.join(entered, "token").select("url", "rule", "site", "pattern", "verdict", "rank")
    fetched = fetched.withColumn("subject", F.when(F.col("site"), F.concat(host, path)).otherwise(F.lower("url")))
    hit = fetched.where(F.rlike("subject", F.col("pattern")))
    best = F.min_by(F.struct("rule", "verdict"), F.struct(F.negative("rank"), "rule"))
    judged = hit.groupBy("url").agg(F.max_by(F.struct("rule", "verdict", "site"), F.struct("site", "rank")).alias("top"), best.alias("b"))
    judged = judged.select("url", F.when(F.col("top.site"), F.col("b.rule")).alias("rule"), F.when(F.col("top.site"), F.col("b.verdict")).otherwise(F.lit("block")).alias("verdict"))
    return own.join(judged, "url", "left").select("page_id", host.alias("host"), path.alias("path"), "rule", F.coalesce("verdict", F.lit("allow")).alias("verdict"))


def query(spark, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "pages"))


def oracle(site_rules=SITE_RULES, patterns=PATTERNS) -> str:
    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    sites = ", ".join(f"({quoted(r.host)}, {quoted(r.path)}, {quoted(r.verdict)})" for r in site_rules)
    bad = " OR ".join(f"regexp_matches(lower(url), {quoted(p.pattern)})" for p in patterns)
    return rf"""
WITH u AS (SELECT page_id, url, CASE WHEN contains(url, '://') THEN url[strpos(url, '://') + 3:] ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, url, rest, regexp_extract(rest, '^[^/?#]*') AS host FROM u),
p AS (SELECT page_id, url, translate(host, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest[length(host) + 1:], '^[^?#]*') AS path FROM h),
rules(rh, rp, verdict) AS (VALUES {sites}),
fit AS (SELECT page_id, rh || rp AS rule, verdict, row_number() OVER (PARTITION BY page_id ORDER BY length(rh || rp) DESC, rh || rp) AS k
        FROM p JOIN rules ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp))
SELECT p.page_id, p.host, p.path, fit.rule, coalesce(fit.verdict, CASE WHEN {bad} THEN 'block' ELSE 'allow' END) AS verdict
FROM p LEFT JOIN fit ON fit.page_id = p.page_id AND fit.k = 1
"""


ORACLE = oracle()
