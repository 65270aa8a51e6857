"""URL filters: host and path rules first, then pattern rules found through their rarest literal token.

Host and path rules are looked up too: a URL's host and its parents fetch the rules of that very host by an
equi-join, and the longest one whose path begins the URL's path wins.

A pattern rule lists sets of literal tokens (whole runs of letters and digits), one set for each way in
which it can match: every URL that it matches holds all tokens of some set.  Each set is indexed by that
of its tokens which the fewest of the given URLs hold; the tokens of a URL fetch its candidate rules by
an equi-join and only those run their regular expression.  All of it is DataFrame work; work is done
once per distinct URL, so a URL that holds a third of all rows costs as one.

Null or unparsable URLs have an empty host and path, match no host rule, and are allowed unless a
pattern fits.  Repeated rows, with a page_id or without, give repeated results.  Columns other than page_id
and url are not looked at.  An empty table gives an empty result.
"""

from __future__ import annotations

import json
from dataclasses import astuple, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table


@dataclass(frozen=True)
class HostRule:
    verdict: str
    host: str
    path: str


@dataclass(frozen=True)
class PatternRule:
    """tokens: sets of lower-case tokens; a lower-cased URL that pattern matches holds all tokens of at least one set."""

    pattern: str
    tokens: tuple[tuple[str, ...], ...]
    verdict: str = "block"


#: Fixed values of the host and path rules.
HOST_RULES = (
    HostRule("allow", "com", "/"),
    HostRule("block", "example.com", "/en/"),
    HostRule("allow", "www.example.com", "/en/"),
    HostRule("block", "net", "/es/"),
    HostRule("block", "net", "/fr/"),
)
#: Production pattern rules: advertising, gambling, drugs, adult pages, session and archive traps.
PATTERN_RULES = (
    PatternRule(r"[/.]cheap-(pills|meds|viagra)[./-]", (("cheap", "pills"), ("cheap", "meds"), ("cheap", "viagra"))),
    PatternRule(r"[/.-]casino(s)?-?(bonus|online)[./?-]", (("casino", "bonus"), ("casino", "online"), ("casinos", "bonus"), ("casinos", "online"), ("casinobonus",), ("casinoonline",), ("casinosbonus",), ("casinosonline",))),
    PatternRule(r"[/.-]online-?casino[./?-]", (("online", "casino"), ("onlinecasino",))),
    PatternRule(r"[/.-]free-?spins[./?-]", (("free", "spins"), ("freespins",))),
    PatternRule(r"[/.-]payday-?loans?[./?-]", (("payday", "loan"), ("payday", "loans"), ("paydayloan",), ("paydayloans",))),
    PatternRule(r"[/.-]replica-watch(es)?[./?-]", (("replica", "watch"), ("replica", "watches"))),
    PatternRule(r"[/.-]buy-(viagra|cialis|tramadol)[./?-]", (("buy", "viagra"), ("buy", "cialis"), ("buy", "tramadol"))),
    PatternRule(r"[/.-]porn[./?-]", (("porn",),)),
    PatternRule(r"[/.-]xxx[./?-]", (("xxx",),)),
    PatternRule(r"[?&](phpsessid|jsessionid)=[0-9a-f]{8,}", (("phpsessid",), ("jsessionid",))),
    PatternRule(r"/wp-(login|admin)(\.php|/)", (("wp", "login"), ("wp", "admin"))),
    PatternRule(r"/calendar/[0-9]{4}/[0-9]{2}/[0-9]{2}", (("calendar",),)),
    PatternRule(r"[?&]add-to-cart=[0-9]+", (("add", "to", "cart"),)),
    PatternRule(r"[/.-]mirror[0-9]*\.[^/]*/pub/", (("pub",),)),
)


def split_url(url: str = "url") -> tuple[str, str]:
    """SQL of host and path of a URL."""
    lower = f"translate(coalesce({url}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    host = rf"regexp_extract({lower}, '(?s)^.*?://([^/?#]*)', 1)"
    path = rf"regexp_extract(coalesce({url}, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1)"
    return host, path


def listed(spark: SparkSession, rows: list[dict], schema: str) -> DataFrame:
    """A table of a rule list, which is a parameter and not data, so it may be broadcast."""
    return spark.range(1).select(F.inline(F.from_json(F.lit(json.dumps(rows)), f"array<struct<{schema}>>")))


def index_rules(urls: DataFrame, rules: tuple[PatternRule, ...]) -> DataFrame:
    """(rule, pattern, verdict, token): for each set of a rule that one of its tokens that the fewest URLs hold."""
    rows = [{"rule": i, "pattern": r.pattern, "verdict": r.verdict, "way": k, "tokens": tokens} for i, r in enumerate(rules) for k, tokens in enumerate(r.tokens)]
    sets = listed(urls.sparkSession, rows, "rule: int, pattern: string, verdict: string, way: int, tokens: array<string>")
    wanted = F.broadcast(sets.select(F.explode("tokens").alias("token")).distinct())
    held = urls.select(F.explode("tokens").alias("token")).join(wanted, "token").groupBy("token").agg(F.count("*").alias("n"))
    each = sets.select("rule", "pattern", "verdict", "way", F.explode("tokens").alias("token")).join(held, "token", "left")
    rarest = each.groupBy("rule", "pattern", "verdict", "way").agg(F.min_by("token", F.struct(F.coalesce("n", F.lit(0)), "token")).alias("token"))
    return rarest.drop("way").distinct()  # sets of a rule may share their rarest token


def pattern_verdicts(pages: DataFrame, rules: tuple[PatternRule, ...] = PATTERN_RULES) -> DataFrame:
    """(url, pattern_verdict) for the distinct URLs that at least one pattern rule fits.

    The rule with the smallest number in the list decides among several.
    """
    urls = pages.where("url is not null").select("url").distinct()
    urls = urls.withColumn("low", F.lower("url")).withColumn("tokens", F.expr("array_distinct(filter(split(low, '[^a-z0-9]+'), t -> t != ''))"))
    index = F.broadcast(index_rules(urls, rules))
    fetched = urls.select("url", "low", F.explode("tokens").alias("token")).join(index, "token")
    fits = fetched.where(F.expr("regexp_like(low, pattern)"))
    return fits.groupBy("url").agg(F.min_by("verdict", "rule").alias("pattern_verdict"))


def host_verdicts(pages: DataFrame, rules: tuple[HostRule, ...] = HOST_RULES) -> DataFrame:
    """(url, rule, ruled) for the distinct URLs that at least one host rule fits; of several the longest decides, then the greatest."""
    host, path = split_url()
    urls = pages.where("url is not null").select("url").distinct().select("url", F.expr(host).alias("host"), F.expr(path).alias("path"))
    most = max((r.host.count(".") for r in rules), default=0) + 1  # parts of a rule's host, so that a host of very many is looked up as often
    parents = f"transform(array(split(host, '[.]', -1)), p -> transform(sequence(greatest(1, size(p) - {most - 1}), size(p)), i -> array_join(slice(p, i, {most}), '.')))[0]"
    index = listed(pages.sparkSession, [dict(zip(("verdict", "named", "begin"), astuple(r), strict=True)) for r in rules], "verdict: string, named: string, begin: string")
    fits = urls.select("url", "path", F.explode(F.expr(parents)).alias("named")).join(F.broadcast(index), "named").where(F.startswith("path", "begin"))
    longest = F.max(F.struct((F.length("named") + F.length("begin")).alias("n"), "named", "begin", "verdict")).alias("r")
    return fits.groupBy("url").agg(longest).select("url", F.concat("r.named", "r.begin").alias("rule"), F.col("r.verdict").alias("ruled"))


def judge_urls(pages: DataFrame, host_rules: tuple[HostRule, ...] = HOST_RULES, rules: tuple[PatternRule, ...] = PATTERN_RULES) -> DataFrame:
    """page_id, host, path, rule, verdict for every row of pages."""
    host, path = split_url()
    found = host_verdicts(pages, host_rules).join(pattern_verdicts(pages, rules), "url", "full")
    judged = pages.select("page_id", "url", F.expr(host).alias("host"), F.expr(path).alias("path")).join(found, "url", "left")
    return judged.select("page_id", "host", "path", "rule", F.coalesce("ruled", "pattern_verdict", F.lit("allow")).alias("verdict"))


def op9_url_filters(spark, sf_dir: str) -> DataFrame:
    return judge_urls(table(spark, sf_dir, "pages"))


def _oracle() -> str:
    lower = "translate(coalesce(url, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    rules = sorted(HOST_RULES, key=lambda r: -len(r.host) - len(r.path))
    fit = [f"('.' || host) like '%.{r.host}' and starts_with(path, '{r.path}')" for r in rules]
    rule = " ".join(f"when {f} then '{r.host}{r.path}'" for f, r in zip(fit, rules, strict=True))
    ruled = " ".join(f"when {f} then '{r.verdict}'" for f, r in zip(fit, rules, strict=True))
    pattern = " ".join(f"when regexp_matches(lower(url), '{r.pattern}') then '{r.verdict}'" for r in PATTERN_RULES)
    return f"""
    with parts as (
      select page_id, url,
             regexp_extract({lower}, '^.*?://([^/?#]*)', 1, 's') as host,
             regexp_extract(coalesce(url, ''), '^.*?://[^/?#]*([^?#]*)', 1, 's') as path
      from pages)
    select page_id, host, path, case {rule} else null end as rule,
           case {ruled} {pattern} else 'allow' end as verdict
    from parts"""


QUERIES = {"op9_url_filters": op9_url_filters}
ORACLES = {"op9_url_filters": _oracle()}
