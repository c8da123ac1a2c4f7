"""URL filter on DataFrame functions alone: expressions, an equi-join on short hash prefixes, full digests, precedence.

A rule is a host and a path prefix; it fits its host and all subdomains when the url's path starts with its path, and
the longest fitting rule wins. Each url is expanded into the suffixes of its host and the prefixes of its path that
any rule could have (the rules' label counts and path lengths), and each expression is hashed. The join is on the
first bytes of the digest, so its keys are short; full digests then confirm, and the winner is taken for each url.

Nulls: a null url, or one without "://", has an empty host and path and fits no rule. An empty rule table leaves the
default verdict. Repeated rows come back as often as they came. Only page_id and url are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The rules as (host, path, verdict), and the verdict where none fits.
RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]
DEFAULT = "allow"
#: Hex digits of the digest to join on, and the largest rule table that is broadcast.
SHORT, BROADCAST_RULES = 8, 200_000


def _lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_path(url: Column) -> tuple[Column, Column]:
    pattern = "^(?s).*?://([^/?#]*)([^?#]*)"
    url = F.coalesce(url, F.lit(""))
    return _lower(F.regexp_extract(url, pattern, 1)), F.regexp_extract(url, pattern, 2)


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat(host, path).cast("binary"), 256)


def judge(pages: DataFrame, rules: DataFrame, default: str = DEFAULT) -> DataFrame:
    """page_id, host, path, rule, verdict for each page. rules: host, path, verdict; paths begin with "/"."""
    host, path = host_path(F.col("url"))
    # Equal rows are counted and not repeated; they come back at the end.
    seen = pages.select("page_id", host.alias("host"), path.alias("path")).groupBy("page_id", "host", "path").agg(F.count("*").alias("n"))
    rules = rules.select(_lower(F.col("host")).alias("h"), F.col("path").alias("p"), F.col("verdict").alias("v")).dropna()
    rules = rules.dropDuplicates(["h", "p"])
    # What lengths there are is bounded by the longest rule, not by the pages.
    shape = rules.select(F.size(F.split("h", r"\.")).alias("labels"), F.length("p").alias("chars"))
    labels = [r[0] for r in shape.select("labels").distinct().collect()]
    chars = [r[0] for r in shape.select("chars").distinct().collect()]
    few = rules.count() <= BROADCAST_RULES
    parts = F.split("host", r"\.")
    suffixes = F.filter(
        F.array(*(F.when(F.size(parts) >= k, F.substring_index("host", ".", -k)) for k in labels)), lambda x: x.isNotNull()
    ) if labels else F.array().cast("array<string>")
    prefixes = F.filter(
        F.array(*(F.when(F.length("path") >= k, F.col("path").substr(1, k)) for k in chars)), lambda x: x.isNotNull()
    ) if chars else F.array().cast("array<string>")
    tried = F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda q: F.struct(s.alias("s"), q.alias("q")))))
    open_ = seen.withColumn("e", F.explode_outer(tried)).withColumn("digest", _digest(F.col("e.s"), F.col("e.q")))
    open_ = open_.withColumn("short", F.substring("digest", 1, SHORT))
    keyed = rules.withColumn("full", _digest(F.col("h"), F.col("p"))).withColumn("short", F.substring("full", 1, SHORT))
    met = open_.join(F.broadcast(keyed) if few else keyed, "short", "left")
    fits = (F.col("full") == F.col("digest")) & (F.col("h") == F.col("e.s")) & (F.col("p") == F.col("e.q"))
    rule = F.when(fits, F.struct(F.length(F.concat("h", "p")).alias("chars"), F.concat("h", "p").alias("rule"), F.col("v").alias("v")))
    best = met.groupBy("page_id", "host", "path").agg(F.max(rule).alias("best"), F.max("n").alias("n"))
    out = best.withColumn("again", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("n"))))
    return out.select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.v", F.lit(default)).alias("verdict"))


def standard_rules(spark) -> DataFrame:  # noqa: ANN001
    return spark.createDataFrame(RULES, "host string, path string, verdict string")
