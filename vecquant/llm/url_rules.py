"""Judge URLs by host-and-path rules with a hashed equi-join.

A URL is expanded into the strings a rule could have: its last k host labels for every label
count k among the rules, each with the first p path characters for every path length p among
them. Short hash prefixes of these join with the rules; the full digest confirms a hit, and
the longest confirmed rule decides.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Rules whose digests are known to be within this many rows are sent to every task.
BROADCAST_RULES = 200_000


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host: after the first :// up to / ? # or the end, A-Z lower-cased. Path: then up to ? # or the end."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    tail = F.substring(rest, F.length(host) + 1, F.length(rest))
    path = F.regexp_extract(tail, r"^[^?#]*", 0)
    return F.coalesce(F.translate(host, UPPER, LOWER), F.lit("")), F.coalesce(path, F.lit(""))


def rule_table(spark: SparkSession, rules: list[tuple[str, str]]) -> DataFrame:
    """Rules from (verdict, "host/path") pairs."""
    return spark.createDataFrame([(v, *_parts(r)) for v, r in rules], "verdict string, host string, path string")


def _parts(rule: str) -> tuple[str, str]:
    host, slash, path = rule.partition("/")
    return host.lower(), slash + path


def _digest(text: Column) -> Column:
    return F.sha2(text, 256)


def judge_urls(
    pages: DataFrame,
    rules: DataFrame,
    url_column: str = "url",
    default: str = "allow",
    prefix_digits: int = 8,
) -> DataFrame:
    """host, path, rule and verdict of every row's URL, beside the row's own columns.

    rules: verdict, host, path; a rule fits its host and all subdomains where the URL's path
    starts with its path. Of several, the longest (host and path together, then the longer host)
    decides; of repeated rules, "block" does before "allow". No rule: rule is null and the
    verdict is `default`. A null URL or one without :// has an empty host and path and fits no
    rule. Every row of pages stays, repeated ones too. Columns of pages that are called
    like the results are replaced.
    """
    rules = rules.groupBy("host", "path").agg(F.max("verdict").alias("verdict"))
    shape = rules.agg(
        F.count("*").alias("n"),
        F.collect_set(F.size(F.split("host", r"\."))).alias("labels"),
        F.collect_set(F.length("path")).alias("lengths"),
    ).first()
    known = rules.select(
        _digest(F.concat("host", "path")).alias("digest"),
        F.concat("host", "path").alias("rule"),
        F.length("host").alias("host_length"),
        "verdict",
    ).withColumn("short", F.substring("digest", 1, prefix_digits))
    if shape.n <= BROADCAST_RULES:
        known = F.broadcast(known)

    host, path = host_and_path(F.col("url"))
    urls = pages.select(F.col(url_column).alias("url")).where(F.instr("url", "://") > 0).distinct()
    urls = urls.select("url", host.alias("host"), path.alias("path"))
    labels = F.split("host", r"\.")
    suffixes = F.filter(
        F.transform(
            F.array(*map(F.lit, sorted(shape.labels))),
            lambda k: F.when(F.size(labels) >= k, F.array_join(F.slice(labels, -k, k), ".")),
        ),
        lambda s: s.isNotNull(),
    )
    prefixes = F.transform(
        F.filter(F.array(*map(F.lit, sorted(shape.lengths))), lambda n: n <= F.length("path")),
        lambda n: F.substring(F.col("path"), F.lit(1), n),
    )
    if not shape.n:
        suffixes = prefixes = F.array().cast("array<string>")
    forms = urls.select("url", F.explode(suffixes).alias("suffix"), prefixes.alias("prefixes"))
    forms = forms.select("url", F.explode(F.transform("prefixes", lambda p: F.concat("suffix", p))).alias("form"))
    forms = forms.withColumn("full", _digest(F.col("form")))
    hits = forms.withColumn("short", F.substring("full", 1, prefix_digits)).join(known, "short")
    best = hits.where(F.col("full") == F.col("digest")).groupBy("url").agg(
        F.max_by(F.struct("rule", "verdict"), F.struct(F.length("rule"), "host_length", "rule")).alias("hit")
    )
    own = [c for c in pages.columns if c.lower() not in {"host", "path", "rule", "verdict"}]
    rows = pages.select(*own) if url_column in own else pages.select(*own, url_column)
    joined = rows.alias("p").join(best.alias("b"), F.col(f"p.{url_column}") == F.col("b.url"), "left")
    return joined.select(
        *[F.col(f"p.{c}") for c in own],
        host_and_path(F.col(f"p.{url_column}"))[0].alias("host"),
        host_and_path(F.col(f"p.{url_column}"))[1].alias("path"),
        F.col("b.hit.rule").alias("rule"),
        F.coalesce(F.col("b.hit.verdict"), F.lit(default)).alias("verdict"),
    )
