"""URL filters: host-suffix and path-prefix expressions, equi-joined on short hash prefixes.

Each URL is expanded into the expressions that a rule could name: every suffix of its host whose
number of labels some rule's host has, with every prefix of its path whose length some rule's path has. An expression's 32-bit hash prefix
meets the rules' prefixes in an equi-join; the full 256-bit digest then confirms. The longest rule
wins; between equally long rules the longer host wins, then block.

The rule table goes to every executor only while it has at most `broadcast_rules` rows (checked);
a larger one is joined by shuffle, with the URL side salted so that a common suffix such as a top
level domain is spread over `salts` tasks. One shuffle by (page, url) gathers the matches.

Edge cases: a null url or one without '://' has an empty host and path, no rule, and the verdict
`no_host_verdict`; other URLs that no rule fits get `default_verdict`; repeated rows come back as
often as they occur; rules with null host or path are ignored; of equally long rules with equal hosts
a block wins; hosts and paths of any length cost in proportion to their length times the rules' distinct
lengths; an empty table gives no rows; further columns of pages don't matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The rules of the production query (host, path, verdict).
PAGE_RULES = (
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
)
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host and path, cut at the first '://' and the first of '/', '?', '#'."""
    found = F.instr(url, "://")
    rest = F.when(found > 0, F.substring(url, found + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.translate(F.coalesce(host, F.lit("")), UPPER, LOWER), F.coalesce(path, F.lit(""))


def rules_frame(spark: SparkSession, rules=PAGE_RULES) -> DataFrame:
    return spark.createDataFrame(list(rules), "host string, path string, verdict string")


def _digest(expression: Column) -> Column:
    return F.sha2(expression, 256)


def judge_urls(pages: DataFrame, rules: DataFrame, *, page_id: str = "page_id", url: str = "url", default_verdict: str = "allow", no_host_verdict: str = "allow", broadcast_rules: int = 1_000_000, salts: int = 32) -> DataFrame:
    """page_id, host, path, rule, verdict of every page."""
    rules = rules.where("host is not null and path is not null").select(F.translate("host", UPPER, LOWER).alias("r_host"), F.col("path").alias("r_path"), F.col("verdict").alias("r_verdict"))
    rules = rules.withColumns({"rule": F.concat("r_host", "r_path"), "digest": _digest(F.concat("r_host", F.lit("\n"), "r_path"))})
    rules = rules.groupBy("digest").agg(F.first("rule").alias("rule"), F.first("r_host").alias("r_host"), F.max("r_verdict").alias("r_verdict"))
    rules = rules.withColumn("short", F.substring("digest", 1, 8))
    # Bounded by the longest path and the deepest host a rule has, not by the number of rules.
    path_size, depth = F.length("rule") - F.length("r_host"), F.size(F.split("r_host", r"\.", -1))
    seen = rules.select(F.collect_set(path_size).alias("n"), F.collect_set(depth).alias("d")).first()
    lengths, depths = sorted(seen["n"]), sorted(seen["d"])
    n_rules = rules.count()
    rows = pages.select(F.col(page_id).alias("page_id"), F.col(url).cast("string").alias("url")).groupBy("page_id", "url").agg(F.count(F.lit(1)).alias("_times"))
    host, path = url_parts(F.col("url"))
    rows = rows.withColumns({"host": host, "path": path})
    labels = F.split("host", r"\.", -1)
    numbers = lambda x: F.array(*[F.lit(n) for n in x]) if x else F.array().cast("array<int>")
    # One slice a depth: regular expressions would read the host again for each.
    suffixes = F.transform(F.filter(numbers(depths), lambda n: n <= F.size(labels)), lambda n: F.array_join(F.slice(labels, -n, n), "."))
    sizes = F.filter(numbers(lengths), lambda n: n <= F.length("path"))
    every = F.flatten(F.transform(suffixes, lambda s: F.transform(sizes, lambda n: F.concat(s, F.lit("\n"), F.substring(F.col("path"), F.lit(1), n)))))
    rows = rows.withColumn("_expr", F.explode_outer(F.when(F.col("host") != "", every))).withColumn("_full", _digest(F.col("_expr"))).withColumn("_short", F.substring("_full", 1, 8))
    if n_rules <= broadcast_rules:
        met = rows.join(F.broadcast(rules), rows["_short"] == rules["short"], "left")
    else:
        rows = rows.withColumn("_salt", F.pmod(F.hash("page_id", "url"), F.lit(salts)))
        spread = rules.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        met = rows.join(spread, (rows["_short"] == spread["short"]) & (rows["_salt"] == spread["salt"]), "left")
    fits = F.col("digest") == F.col("_full")
    best = F.struct(F.length("rule").alias("n"), F.length("r_host").alias("h"), F.col("r_verdict").alias("v"), F.col("rule").alias("r"))
    out = met.groupBy("page_id", "url").agg(F.first("host").alias("host"), F.first("path").alias("path"), F.first("_times").alias("_times"), F.max(F.when(fits, best)).alias("b"))
    verdict = F.coalesce(F.col("b.v"), F.when(F.col("host") == "", F.lit(no_host_verdict)).otherwise(F.lit(default_verdict)))
    out = out.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times").cast("int"))))
    return out.select("page_id", "host", "path", F.col("b.r").alias("rule"), verdict.alias("verdict"))
