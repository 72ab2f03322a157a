"""URL filter rules, indexed by their rarest literal token.

A rule is a pattern over `host + path`: either a host with its subdomains and a
path prefix (``example.com/en/``) or a wildcard pattern (``*`` any run, ``^`` a
separator, a leading ``|`` the start).  Its literal tokens are the alphanumeric
runs that must stand whole in a URL.  Of these the one rarest in the URLs at hand
is the rule's key; a URL's tokens fetch the rules filed under them, and only
those run their regular expression.  Rules without a whole token are filed under
the empty token, which every URL has.

All on DataFrame functions.  Rule tables are small and join by Catalyst's own
choice (broadcast under the session's size threshold, else a sort-merge join that
AQE splits where a token is hot).  Of equal pages only one URL is judged; longest
rule wins, then the smaller text.

Defined cases: a null URL, or one without ``://``, has empty host and path, fits no
rule and is allowed; null ids and repeated rows keep their own rows; without
rules every URL gets the default; the url column may have any other columns beside it.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


@dataclass(frozen=True)
class Rule:
    """`pattern` decides; `anchored` rules are host/path rules and take precedence over the method's own patterns."""

    pattern: str
    verdict: str
    anchored: bool = True


#: The host rules that a query may fix, and the method's own patterns for all other URLs.
HOST_RULES = [
    Rule("com/", "allow"),
    Rule("example.com/en/", "block"),
    Rule("www.example.com/en/", "allow"),
    Rule("net/es/", "block"),
    Rule("net/fr/", "block"),
]
PATTERN_RULES = [
    Rule("*^spam-farm^*", "block", False),
    Rule("*^cheap-pills^*", "block", False),
    Rule("*^casino^*", "block", False),
    Rule("*^xxx^*", "block", False),
    Rule("*^adserver^*", "block", False),
    Rule("*^doubleclick^*", "block", False),
]


def regex(rule: Rule) -> str:
    """The rule over `host + path`, for Java and RE2 alike."""
    if rule.anchored:
        return r"^([^/]*\.)?" + re.escape(rule.pattern).replace(r"\/", "/").replace(r"\-", "-")
    out, body = "", rule.pattern
    if body.startswith("|"):
        out, body = "^", body[1:]
    for c in body:
        out += ".*" if c == "*" else "([^A-Za-z0-9]|^|$)" if c == "^" else re.escape(c).replace(r"\/", "/").replace(r"\-", "-")
    return out


def tokens(rule: Rule) -> list[str]:
    """Alphanumeric runs that stand whole in every URL the rule fits."""
    body = rule.pattern.lower()
    found = []
    for m in re.finditer(r"[a-z0-9]+", body):
        left = body[m.start() - 1] if m.start() else ("." if rule.anchored else "*")
        right = body[m.end()] if m.end() < len(body) else "*"
        if left != "*" and right != "*":
            found.append(m[0])
    return found


def host(url: Column) -> Column:
    rest = F.substring_index(url, "://", 1)
    after = F.substr(url, F.length(rest) + 4)
    return F.when(F.instr(url, "://") > 0, F.translate(F.regexp_extract(after, r"^([^/?#]*)", 1), UPPER, UPPER.lower())).otherwise("")


def path(url: Column) -> Column:
    rest = F.substring_index(url, "://", 1)
    after = F.substr(url, F.length(rest) + 4)
    return F.when(F.instr(url, "://") > 0, F.regexp_extract(after, r"^[^/?#]*([^?#]*)", 1)).otherwise("")


def judge(pages: DataFrame, rules: list[Rule], id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """Every row with host, path, rule (the host rule that fits, else null), pattern (the method's, else null) and verdict."""
    spark = pages.sparkSession
    rows = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"))
    parts = rows.select("page_id", F.coalesce(host(F.col("url")), F.lit("")).alias("host"), F.coalesce(path(F.col("url")), F.lit("")).alias("path"))
    if not rules:
        return parts.select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(None).cast("string").alias("pattern"), F.lit(default).alias("verdict"))
    # A location is judged once however many pages stand at it.
    places = parts.filter("host <> '' or path <> ''").select(F.concat("host", "path").alias("place")).distinct()
    url_tokens = F.array_union(F.array_distinct(F.split(F.lower("place"), r"[^a-z0-9]+")), F.array(F.lit("")))
    exploded = places.select("place", F.explode(url_tokens).alias("token"))
    best = _candidates(spark, exploded, rules).filter(F.expr("place rlike regex")).groupBy("place").agg(
        F.min(F.when(F.col("anchored"), F.struct((-F.length("rule")).alias("n"), "rule", "verdict"))).alias("fixed"),
        F.min(F.when(~F.col("anchored"), F.struct((-F.length("rule")).alias("n"), "rule", "verdict"))).alias("own"),
    )
    return (
        parts.withColumn("place", F.concat("host", "path"))
        .join(best, "place", "left")
        .select("page_id", "host", "path", F.col("fixed.rule").alias("rule"), F.col("own.rule").alias("pattern"), F.coalesce("fixed.verdict", "own.verdict", F.lit(default)).alias("verdict"))
    )


def _candidates(spark: SparkSession, exploded: DataFrame, rules: list[Rule]) -> DataFrame:
    """(place, rule, ...) of the rules that a URL's tokens fetch."""
    table = spark.createDataFrame([(r.pattern, r.verdict, r.anchored, regex(r), t) for r in rules for t in (tokens(r) or [""])], "rule string, verdict string, anchored boolean, regex string, token string")
    counts = exploded.join(table.select("token").distinct(), "token", "left_semi").groupBy("token").count()
    rarest = Window.partitionBy("rule", "verdict").orderBy("n", "token")
    index = table.join(counts, "token", "left").withColumn("n", F.coalesce("count", F.lit(0))).withColumn("k", F.row_number().over(rarest)).filter("k = 1").select("token", "rule", "verdict", "anchored", "regex")
    return exploded.join(index, "token")
