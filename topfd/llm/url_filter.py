"""URL filters: pattern rules indexed by their rarest literal token, in DataFrame functions alone.

A rule has a regular expression and the literal tokens that every match of it must contain. Tokens are runs of ASCII
letters and digits. The frequencies of the rules' tokens over all URLs decide which one token a rule is filed under; a rule without any is filed
under the empty token, which every URL has. A URL's tokens fetch its candidate rules, and only their expressions run.

* A list of up to LITERAL_RULES rules (and LITERAL_BYTES) is a hash table in one literal: slot h holds the rules whose token hashes to h. A page is judged in one
  narrow pass, without a shuffle, and its cost follows its candidates, not the number of rules.
* Longer lists are a table keyed by token. The different (host, path) keys are joined to it by their tokens, judged, and joined back.

Rules come from `default_rules`, from `parse_rule` (lines of the common filter-list syntax), or from a text file by `read_rules`.

Host and path rules win over pattern rules, the longest (host and path together) first; a rule fits its host and all
subdomains. Among pattern rules an allowing one wins over a blocking one. Null URLs and URLs without ``://`` have an empty host and path, fit no host rule and,
having no host, are allowed unless a pattern fits nothing at all. Line breaks in a URL are ordinary characters.
Repeated pages are judged alike; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import json
import re
import zlib
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, table

#: The host and path rules of the contract. Fixed values.
HOST_RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
#: Words that mark link farms and trackers in a host's labels.
SPAM_WORDS = ("spam-farm", "cheap-pills", "casino-win", "ads-track", "free-bets")


#: A list that is one literal of the plan has so many rules and bytes of JSON at most.
LITERAL_RULES, LITERAL_BYTES = 2_000, 1_000_000


@dataclass(frozen=True)
class Rule:
    """pattern runs on 'host#path': neither part can hold a '#'. label is None for a pattern rule without a host and path."""

    verdict: str
    pattern: str
    tokens: tuple[str, ...]
    label: str | None = None


def tokens_of(text: str) -> tuple[str, ...]:
    return tuple(dict.fromkeys(re.findall("[a-z0-9]+", text.lower())))


def host_rule(verdict: str, host: str, path: str) -> Rule:
    return Rule(verdict, rf"^(?:[^#]*\.)?{_quoted(host)}#{_quoted(path)}", tokens_of(host), host + path)


def _quoted(text: str) -> str:
    return re.sub(r"([^a-zA-Z0-9\u0080-\U0010ffff])", r"\\\1", text)


def default_rules() -> list[Rule]:
    spam = [Rule("block", rf"^(?:[^#]*\.)?{_quoted(w)}\.", tokens_of(w)) for w in SPAM_WORDS]
    return [*(host_rule(*r) for r in HOST_RULES), *spam]


def parse_rule(line: str) -> Rule | None:
    """A line of a filter list: `||host^` or `||host/path` for a host and its subdomains, `|` for an end of the URL, `*` for anything, `^` for a separator or the end,
    `@@` before a rule that allows. Comments (`!`, `[`) and empty lines are None. Options after `$` are not supported and an error."""
    line = line.strip().lower()
    if not line or line[0] in "![":
        return None
    verdict = "block"
    if line.startswith("@@"):
        verdict, line = "allow", line[2:]
    if "$" in line:
        raise ValueError(f"options are not supported: {line}")
    start = "^(?:[^#]*\\.)?" if line.startswith("||") else "^" if line.startswith("|") else ""
    stop = "$" if line.endswith("|") and line != "||" else ""
    body = line.lstrip("|")[: -1 if stop else None]
    # a host and its path meet at a '#' in the key; in a rule they meet at the first '/'
    if start:
        body = body.replace("/", "\0", 1)
    pattern = "".join({"*": ".*", "^": "(?:[^a-z0-9_.%-]|$)", "\0": "#\\/"}.get(c) or _quoted(c) for c in body)
    # a token is certain where both its ends are: at an anchor, or at a literal character that isn't part of one
    tokens = [m[0] for m in re.finditer("[a-z0-9]+", body) if (m.start() or start) and (m.end() < len(body) or stop) and body[m.start() - 1 : m.start()] != "*" and body[m.end() : m.end() + 1] != "*"]
    return Rule(verdict, "(?si)" + start + pattern + stop, tuple(dict.fromkeys(tokens)))


def read_rules(spark: SparkSession, path: str) -> list[Rule]:
    """The rules of a text file in the filter-list syntax, one a line. A rule list is a setting of the run, not data; it is held by the driver."""
    rules = [parse_rule(r["value"]) for r in spark.read.text(path).collect()]
    return [r for r in rules if r is not None]


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Both empty for null or without '://'. Cut by position, so that line breaks in a URL are ordinary characters."""
    rest = F.when(F.instr(url, "://") > 0, F.substring_index(F.expr("substring(%s, instr(%s, '://') + 3)" % (("url",) * 2)), "#", 1)).otherwise(F.lit(""))
    rest = F.substring_index(F.coalesce(rest, F.lit("")), "?", 1)
    host = F.substring_index(rest, "/", 1)
    return ascii_lower(host), F.substring(rest, F.length(host) + 1, 1 << 30)


def url_tokens(host: Column, path: Column) -> Column:
    """The empty token stands in every URL."""
    return F.array_union(F.split(ascii_lower(F.concat(host, F.lit("/"), path)), "[^a-z0-9]+"), F.array(F.lit("")))


def rarest(pages: DataFrame, rules: list[Rule]) -> dict[str, int]:
    """In how many URLs each of the rules' tokens stands, over all pages; as many numbers as the rules have tokens."""
    spark = pages.sparkSession
    wanted = sorted({t for r in rules for t in r.tokens})
    host, path = host_and_path(F.col("url"))
    if len(wanted) <= LITERAL_RULES:
        some = pages.select(F.explode(F.array_intersect(url_tokens(host, path), F.array(*map(F.lit, wanted)) if wanted else F.array().cast("array<string>"))).alias("token"))
    else:
        some = pages.select(F.explode(url_tokens(host, path)).alias("token")).join(spark.createDataFrame([(t,) for t in wanted], "token string"), "token")
    return dict.fromkeys(wanted, 0) | {r["token"]: r["count"] for r in some.groupBy("token").count().collect()}


def _filed_under(rule: Rule, counts: dict[str, int]) -> str:
    return min(rule.tokens, key=lambda t: (counts.get(t, 0), t), default="")


def index(rules: list[Rule], counts: dict[str, int]) -> tuple[str, int]:
    """The hash table as JSON, an array of slots, and its number of slots."""
    slots = 1 << max(3, len(rules).bit_length() + 1)
    filed: list[list[dict]] = [[] for _ in range(slots)]
    for r in rules:
        token = _filed_under(r, counts)
        filed[_slot(token, slots)].append({"token": token, "pattern": r.pattern, "verdict": r.verdict, "label": r.label})
    return json.dumps(filed), slots


def _slot(token: str, slots: int) -> int:
    return zlib.crc32(token.encode()) % slots


_RULE = "struct<token:string,pattern:string,verdict:string,label:string>"


def _verdict(fits: Column) -> list[Column]:
    """rule and verdict of the rules that fit."""
    named = F.filter(fits, lambda r: r["label"].isNotNull())
    best = F.array_max(F.transform(named, lambda r: F.struct(F.length(r["label"]).alias("length"), r["label"].alias("label"), r["verdict"].alias("verdict"))))
    pattern = lambda verdict: F.exists(fits, lambda r: r["label"].isNull() & (r["verdict"] == verdict))
    by_pattern = F.when(pattern("block") & ~pattern("allow"), "block").otherwise("allow")
    return [best["label"].alias("rule"), F.coalesce(best["verdict"], by_pattern).alias("verdict")]


def judge(pages: DataFrame, rules: list[Rule] | None = None) -> DataFrame:
    """pages(page_id, url) -> page_id, url, host, path, rule, verdict, n_candidates."""
    rules = default_rules() if rules is None else rules
    counts = rarest(pages, rules)
    host, path = host_and_path(F.col("url"))
    cut = pages.select("page_id", "url", host.alias("host"), path.alias("path"))
    key = F.concat(F.col("host"), F.lit("#"), F.col("path"))
    body, slots = index(rules, counts)
    if len(rules) > LITERAL_RULES or len(body) > LITERAL_BYTES:
        return _judge_by_join(cut, rules, counts)
    table_of_rules = F.from_json(F.lit(body), f"array<array<{_RULE}>>")
    candidates = F.flatten(
        F.transform(
            url_tokens(F.col("host"), F.col("path")),
            lambda t: F.filter(F.element_at(table_of_rules, (F.crc32(t.cast("binary")) % slots + 1).cast("int")), lambda r: r["token"] == t),
        )
    )
    fits = F.filter(F.col("candidates"), lambda r: F.regexp_like(F.col("key"), r["pattern"]))
    return (
        cut.select("*", key.alias("key"), candidates.alias("candidates"))
        .select("*", fits.alias("fits"))
        .select("page_id", "url", "host", "path", *_verdict(F.col("fits")), F.size("candidates").alias("n_candidates"))
    )


def _judge_by_join(cut: DataFrame, rules: list[Rule], counts: dict[str, int]) -> DataFrame:
    """For lists that no literal should hold: the different keys meet the rules by token. Rules of one token are dealt to several rows, so none is hot on that side;
    a token of many keys is split by adaptive execution."""
    spark = cut.sparkSession
    filed = spark.createDataFrame([(_filed_under(r, counts), r.pattern, r.verdict, r.label) for r in rules], "token string, pattern string, verdict string, label string")
    keys = cut.select("host", "path").distinct()
    met = keys.select("host", "path", F.explode(url_tokens(F.col("host"), F.col("path"))).alias("token")).join(filed, "token")
    key = F.concat(F.col("host"), F.lit("#"), F.col("path"))
    rule = F.when(F.regexp_like(key, F.col("pattern")), F.struct("token", "pattern", "verdict", "label"))
    found = met.groupBy("host", "path").agg(F.collect_list(rule).alias("fits"), F.count(F.lit(1)).cast("int").alias("n"))
    judged = found.select(F.col("host").alias("h"), F.col("path").alias("p"), *_verdict(F.col("fits")), "n")
    joined = cut.join(judged, (F.col("host") == F.col("h")) & (F.col("path") == F.col("p")), "left")
    return joined.select("page_id", "url", "host", "path", "rule", F.coalesce("verdict", F.lit("allow")).alias("verdict"), F.coalesce("n", F.lit(0)).alias("n_candidates"))


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


ORACLE = r"""
WITH cut AS (
  SELECT page_id, CASE WHEN position('://' IN url) > 0 THEN split_part(split_part(substr(url, position('://' IN url) + 3), '#', 1), '?', 1) ELSE '' END AS rest
  FROM pages),
parts AS (
  SELECT page_id, translate(split_part(rest, '/', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         substr(rest, length(split_part(rest, '/', 1)) + 1) AS path
  FROM cut),
fits AS (
  SELECT *, CASE WHEN (host = 'example.net' OR host LIKE '%.example.net') AND starts_with(path, '/en/') THEN 'example.net/en/'
                 WHEN (host = 'example.com' OR host LIKE '%.example.com') AND starts_with(path, '/de/') THEN 'example.com/de/'
                 WHEN (host = 'org' OR host LIKE '%.org') AND starts_with(path, '/fr/') THEN 'org/fr/'
                 WHEN (host = 'net' OR host LIKE '%.net') AND starts_with(path, '/') THEN 'net/' END AS rule
  FROM parts)
SELECT page_id, host, path, rule,
       CASE WHEN rule IN ('net/', 'example.com/de/') THEN 'block' WHEN rule IS NOT NULL THEN 'allow'
            WHEN regexp_matches(host, '^((?s:.)*\.)?(spam-farm|cheap-pills|casino-win|ads-track|free-bets)\.') THEN 'block' ELSE 'allow' END AS verdict
FROM fits
"""
