"""URL block and allow rules by host-suffix and path-prefix expressions. DataFrame functions only.

Every URL is expanded into (host suffix) x (path prefix) expressions; they meet the rules in an equi-join on
the first hex digits of the expression's SHA-256, the full digests are compared, and the longest rule wins.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import UPPER

#: The rules of the registered query, (action, host, path).
RULES = [
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("block", "net", "/de/"),
    ("allow", "example.net", "/de/8"),
    ("block", "org", "/es/"),
]
#: Rule lists of at most so many rows are broadcast (64 bytes or so each); longer ones are joined by shuffle.
BROADCAST_RULES = 200_000
SHORT = 8


def host_of(url: Column) -> Column:
    """Between the first ``://`` and the next ``/``, ``?``, ``#``; A-Z lower-cased; '' without ``://`` or for null."""
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), UPPER, UPPER.lower()), F.lit(""))


def path_of(url: Column) -> Column:
    """What follows the host up to ``?`` or ``#``; '' without ``://`` or for null."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rules_frame(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    return spark.createDataFrame(rules, "verdict string, rule_host string, rule_path string")


def filter_urls(pages: DataFrame, rules: DataFrame, default: str = "allow") -> DataFrame:
    """Adds host, path, rule (host + path of the winning rule or null) and verdict to the rows of ``pages`` (url).

    A rule fits its host and all subdomains when the URL's path starts with the rule's path. The longest rule
    wins, ``block`` before ``allow`` on equal rules; without a rule the verdict is ``default``. Null and odd
    URLs have host and path '' and the default verdict; rows are kept as they are, repeated ones too; an empty
    rule table gives every row the default. Columns of ``pages`` named like the four results are replaced.
    """
    spark = pages.sparkSession
    rules = rules.where("rule_host is not null").select(
        "verdict", F.concat("rule_host", F.coalesce("rule_path", F.lit(""))).alias("rule"),
        F.length(F.coalesce("rule_path", F.lit(""))).alias("n"),
    ).groupBy("rule").agg(F.max("verdict").alias("verdict"), F.max("n").alias("n"))
    sizes = sorted(r.n for r in rules.select("n").distinct().collect())  # distinct path lengths of the rule list
    few = rules.limit(BROADCAST_RULES + 1).count() <= BROADCAST_RULES
    base = pages.drop("host", "path", "rule", "verdict").withColumns({"host": host_of(F.col("url")), "path": path_of(F.col("url"))})
    if not sizes:
        return base.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default)})
    keyed = rules.withColumn("digest", F.sha2("rule", 256)).withColumn("short", F.substring("digest", 1, SHORT))
    parts = F.split("host", r"\.", -1)
    suffixes = F.transform(
        F.sequence(F.lit(1), F.size(parts)), lambda i: F.array_join(F.slice(parts, i, F.size(parts)), ".")
    )
    cuts = F.filter(F.array(*[F.lit(n) for n in sizes]), lambda n: n <= F.length("path"))
    asked = (
        base.select("host", "path").distinct()
        .withColumn("prefixes", F.transform(cuts, lambda n: F.substr(F.col("path"), F.lit(1), n)))
        .withColumn("expression", F.explode(F.flatten(F.transform(suffixes, lambda h: F.transform("prefixes", lambda p: F.concat(h, p))))))
        .select("host", "path", F.sha2("expression", 256).alias("asked"))
        .withColumn("short", F.substring("asked", 1, SHORT))
    )
    hits = asked.join(F.broadcast(keyed) if few else keyed, "short").where("asked = digest")
    best = hits.groupBy("host", "path").agg(
        F.max(F.struct(F.length("rule").alias("l"), "verdict", "rule")).alias("best")
    ).select("host", "path", "best.rule", F.col("best.verdict").alias("found"))
    return base.join(best, ["host", "path"], "left").withColumn("verdict", F.coalesce("found", F.lit(default))).drop("found")
