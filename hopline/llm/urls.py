"""URL rules by expression expansion: host suffixes x path prefixes, hash-prefix join, full digest, precedence.

A URL's host runs from after the first ``://`` to ``/``, ``?``, ``#`` or the end (A-Z lower-cased), its path from
there to ``?``, ``#`` or the end. A rule (host, path, verdict) fits its host and all subdomains when the URL's path
starts with the rule's. Expansions are formed for every host suffix of as many labels as some rule has, and every rule
path length, so a host of very many labels adds no more than a short one.
They meet the rules on the first 8 hex digits of SHA-256, then the whole digest must agree. The longest rule wins;
at equal length the longer host, then ``block``.

Defined cases: null URLs and those without ``://`` have empty host and path and get the default verdict; repeated
rows get equal results; an empty rule table leaves the default; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopline.session import small_enough

#: (host, path, verdict)
RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]
DEFAULT = "allow"
BROADCAST_RULES = 100_000
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_PATTERN = r"(?s)^.*?://([^/?#]*)([^?#]*)"


def split_url(pages: DataFrame) -> DataFrame:
    url = F.coalesce("url", F.lit(""))
    return pages.select("page_id", F.translate(F.regexp_extract(url, _PATTERN, 1), _UPPER, _LOWER).alias("host"), F.regexp_extract(url, _PATTERN, 2).alias("path"))


def judge(pages: DataFrame, rules: DataFrame, default: str = DEFAULT) -> DataFrame:
    """page_id, host, path, rule, verdict for every row of ``pages``."""
    rules = rules.select(F.translate("host", _UPPER, _LOWER).alias("rule_host"), F.col("path").alias("rule_path"), F.col("verdict").alias("rule_verdict"))
    keyed = rules.withColumn("digest", F.sha2(F.concat("rule_host", F.lit("\n"), "rule_path"), 256)).withColumn("short", F.substring("digest", 1, 8))
    lengths = sorted(r[0] for r in rules.select(F.length("rule_path")).distinct().collect())
    most = rules.agg(F.max(F.size(F.split("rule_host", r"\.")))).first()[0] or 1
    parts = split_url(pages)
    urls = parts.where("host <> ''").select("host", "path").distinct()
    labels = F.split("host", r"\.")
    last = F.slice(labels, -F.least(F.size(labels), F.lit(most)), F.lit(most))
    suffixes = F.transform(F.sequence(F.lit(1), F.size(last)), lambda k: F.array_join(F.slice(last, k, F.size(last)), "."))
    prefixes = F.filter(F.array(*[F.lit(n) for n in lengths]), lambda n: n <= F.length("path"))
    grown = urls.withColumn("suffix", F.explode(suffixes)).withColumn("n", F.explode(prefixes))
    grown = grown.withColumn("full", F.sha2(F.concat("suffix", F.lit("\n"), F.expr("substring(path, 1, n)")), 256)).withColumn("short", F.substring("full", 1, 8))
    side = F.broadcast(keyed) if small_enough(keyed, BROADCAST_RULES) else keyed
    hits = grown.join(side, "short").where("full = digest")
    rank = F.struct((F.length("rule_host") + F.length("rule_path")).alias("all"), F.length("rule_host").alias("host"), (F.col("rule_verdict") == "block").alias("block"))
    best = hits.groupBy("host", "path").agg(F.max_by(F.struct(F.concat("rule_host", "rule_path").alias("rule"), "rule_verdict"), rank).alias("won"))
    out = parts.join(best, ["host", "path"], "left")
    return out.select("page_id", "host", "path", F.col("won.rule").alias("rule"), F.coalesce("won.rule_verdict", F.lit(default)).alias("verdict"))


def rule_table(spark, rules=RULES) -> DataFrame:
    return spark.createDataFrame(rules, "host string, path string, verdict string")
