"""URL filters by hashed host-suffix and path-prefix expressions.

Each URL expands into expressions: suffixes of its host at label boundaries times prefixes of its
path at slashes. A rule is filed under its host and its path up to the last slash. Expressions meet
rules in an equi-join on a short prefix of their SHA-256, full digests confirm, what a rule's path has
after its last slash is compared in place, and the longest rule decides.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lower_ascii

#: The rules of the query: verdict, host, path.
RULES = [
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
]
#: Hex digits of the digest that are joined on.
SHORT = 8
#: Rules up to this many are broadcast; more are joined by shuffle.
BROADCAST_RULES = 200_000


def split_url(url: Column) -> tuple[Column, Column]:
    """(host, path): empty for null and for a text without ``://``."""
    after = F.substring(url, F.instr(url, "://") + 3, F.length(url))
    has = F.coalesce(F.instr(url, "://") > 0, F.lit(False))
    host = F.when(has, lower_ascii(F.regexp_extract(after, r"^[^/?#]*+", 0))).otherwise("")
    path = F.when(has, F.regexp_extract(after, r"^[^/?#]*+([^?#]*+)", 1)).otherwise("")
    return host, path


def rules_table(spark: SparkSession, rules: list[tuple[str, str, str]] = RULES) -> DataFrame:
    """(verdict, host, path) as a table; hosts are lower-cased."""
    rows = [
        F.struct(F.lit(v).alias("verdict"), F.lit(h).alias("host"), F.lit(p).alias("path")) for v, h, p in rules
    ]
    return spark.range(1).select(F.inline(F.array(*rows)))


def judge(pages: DataFrame, rules: DataFrame, default: str = "allow", hostless: str = "block") -> DataFrame:
    """(page_id, host, path, rule, verdict) for every row of ``pages`` (page_id, url, ...).

    A rule fits its host and all subdomains where the path starts with the rule's; the longest
    rule wins, and of the same rule with two verdicts ``block``. Without a rule (null) the
    verdict is ``default``, and ``hostless`` where the URL has no host. Repeated rows each get
    a row, null ids and URLs too; other columns are ignored. An empty table gives an empty result.
    """
    keyed = rules.select(
        "verdict", lower_ascii(F.col("host")).alias("host"), F.coalesce("path", F.lit("")).alias("path")
    ).where("host is not null")
    folder = F.regexp_extract("path", "^.*/", 0)
    keyed = keyed.withColumn("folder", folder)
    digest = F.sha2("expression", 256)
    table = (
        keyed.groupBy("host", "path", "folder")
        .agg(F.max("verdict").alias("verdict"))
        .withColumn("expression", F.concat("host", "folder"))
        .withColumn("digest", digest)
        .withColumn("short", F.substring("digest", 1, SHORT))
    )
    # which expansions can be a rule: numbers of labels of a host and of slashes of a path
    shape = keyed.agg(
        F.collect_set(F.size(F.split("host", r"\."))).alias("labels"),
        F.collect_set(F.length(F.regexp_replace("path", "[^/]", ""))).alias("slashes"),
        F.count("*").alias("rules"),
    ).first()
    host, path = split_url(F.col("url"))
    rows = (
        pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"))
        .select("page_id", host.alias("host"), path.alias("path"))
        .groupBy("page_id", "host", "path")
        .agg(F.count("*").alias("copies"))
    )
    # at most one expression for each label and slash that the URL itself has
    suffixes = F.array_compact(F.array(*(_suffix(n) for n in sorted(shape["labels"])), F.lit(None).cast("string")))
    prefixes = F.array_compact(F.array(*(_slashed(n) for n in sorted(shape["slashes"])), F.lit(None).cast("string")))
    expressions = F.flatten(F.transform(suffixes, lambda h: F.transform(prefixes, lambda p: F.concat(h, p))))
    expanded = rows.withColumn("expression", F.explode_outer(expressions)).withColumn("digest", digest)
    expanded = expanded.withColumn("short", F.substring("digest", 1, SHORT))
    side = table.select(
        "short", F.col("digest").alias("rule_digest"), F.concat("host", "path").alias("rule"), F.col("path").alias("rule_path"),
        F.col("verdict").alias("said"), F.length("host").alias("host_length"),
    )
    if shape["rules"] <= BROADCAST_RULES:
        side = F.broadcast(side)
    best = F.struct(F.length("rule").alias("length"), "host_length", "rule", "said")
    fits = (F.col("digest") == F.col("rule_digest")) & F.col("path").startswith(F.col("rule_path"))
    judged = (
        expanded.join(side, "short", "left")
        .groupBy("page_id", "host", "path", "copies")
        .agg(F.max(F.when(fits, best)).alias("best"))
    )
    verdict = F.coalesce("best.said", F.when(F.col("host") == "", F.lit(hostless)).otherwise(default))
    return judged.select(
        "page_id",
        "host",
        "path",
        F.col("best.rule").alias("rule"),
        verdict.alias("verdict"),
        F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))).alias("copy"),
    ).drop("copy")


def _suffix(labels: int) -> Column:
    """The host's last ``labels`` labels, null where it has fewer."""
    enough = F.size(F.split("host", r"\.")) >= labels
    return F.when(enough, F.substring_index("host", ".", -labels))


def _slashed(slashes: int) -> Column:
    """The path up to its ``slashes``-th slash, null where it has fewer."""
    if slashes == 0:
        return F.lit("")
    enough = F.length(F.regexp_replace("path", "[^/]", "")) >= slashes
    return F.when(enough, F.concat(F.substring_index("path", "/", slashes), F.lit("/")))
