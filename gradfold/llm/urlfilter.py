"""URL filtering by host-suffix and path-prefix expressions.

A rule is a host and a path; it fits a URL whose host is the rule's or lies under
it and whose path starts with the rule's.  Each URL is expanded into the
expressions host suffix + path prefix that a rule could have - only suffixes with
as many labels and prefixes as long as some rule's - and the expressions meet the
rules in an equi-join on the first 32 bits of their SHA-256, confirmed on the full
digest.  Of the rules that fit the longest wins; of equally long ones that with
the longer host, and then blocking wins.

Everything is DataFrame functions.  The only exchange is by URL, after partial
aggregation, so a URL that repeats a million times is judged once.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import ascii_lower, quoted

#: (host, path, verdict): fixed rules of the query.
RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]
#: Rules up to this number are broadcast (about 100 bytes each); more are joined by exchange.
BROADCAST_RULES = 200_000
SEP = "\x00"


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL; both empty without `://` and for null.

    The host is what stands after the first `://` up to `/`, `?`, `#` or the end, the path what follows up to `?`, `#` or the end.
    """
    rest = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    url = F.coalesce(url, F.lit(""))
    return ascii_lower(F.regexp_extract(url, rest, 1)), F.regexp_extract(url, rest, 2)


def rules_table(spark, rules: list[tuple[str, str, str]] = RULES) -> DataFrame:
    """A small list of rules as a table; host and path must not be null."""
    quote = lambda s: "'" + s.replace("\\", "\\\\").replace("'", "\\'") + "'"
    return spark.sql("SELECT * FROM VALUES " + ", ".join("(" + ", ".join(map(quote, r)) + ")" for r in rules) + " AS t(rule_host, rule_path, rule_verdict)")


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat(host, F.lit(SEP), path), 256)


def judge(urls: DataFrame, rules: DataFrame, ident: str = "page_id", url: str = "url", default: str = "allow", broadcast_rules: int = BROADCAST_RULES) -> DataFrame:
    """(ident, host, path, rule, verdict), one row for each row of `urls`; no rule that fits gives null and `default`.

    Null ids and URLs, empty ones and repeated rows are judged like others and come out as often as they come in.
    """
    clean = rules.where("rule_host is not null and rule_path is not null and rule_verdict is not null").dropDuplicates(["rule_host", "rule_path", "rule_verdict"])
    shape = clean.agg(F.count("*"), F.collect_set(F.size(F.split("rule_host", "\\."))), F.collect_set(F.length("rule_path"))).first()
    number, labels, lengths = shape[0], sorted(shape[1]), sorted(shape[2])  # at most as many as a host has labels and a URL characters
    grouped = urls.groupBy(quoted(ident).alias("i"), quoted(url).alias("u")).agg(F.count("*").alias("n"))
    host, path = host_and_path(F.col("u"))
    each = grouped.select("i", "u", "n", host.alias("host"), path.alias("path"))
    if not number:
        out = each.withColumn("best", F.lit(None).cast("struct<length:int,h:int,blocks:boolean,rule:string,verdict:string>"))
    else:
        parts = F.split("host", "\\.")
        suffixes = F.array_compact(F.array(*(F.when(F.size(parts) >= k, F.substring_index("host", ".", -k)) for k in labels)))
        prefixes = F.array_compact(F.array(*(F.when(F.length("path") >= n, F.substring("path", 1, n)) for n in lengths)))
        pairs = F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.struct(s.alias("s"), p.alias("p")))))
        asked = each.select("i", "u", "n", "host", "path", F.explode_outer(F.when(F.col("host") != "", F.array_distinct(pairs))).alias("e"))
        full = _digest(F.col("e.s"), F.col("e.p"))
        asked = asked.withColumn("full", full).withColumn("short", F.substring("full", 1, 8))
        known = clean.withColumn("rule_full", _digest(F.col("rule_host"), F.col("rule_path"))).withColumn("rule_short", F.substring("rule_full", 1, 8))
        known = F.broadcast(known) if number <= broadcast_rules else known
        met = asked.join(known, (F.col("short") == F.col("rule_short")) & (F.col("full") == F.col("rule_full")), "left")
        rule = F.concat("rule_host", "rule_path")
        weight = F.when(F.col("rule_host").isNotNull(), F.struct(F.length(rule).alias("length"), F.length("rule_host").alias("h"), (F.col("rule_verdict") == "block").alias("blocks"), rule.alias("rule"), F.col("rule_verdict").alias("verdict")))
        out = met.groupBy("i", "u", "n", "host", "path").agg(F.max(weight).alias("best"))
    out = out.select(F.col("i").alias(ident), "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"), F.explode(F.sequence(F.lit(1).cast("long"), F.col("n"))).alias("copy"))
    return out.drop("copy")
