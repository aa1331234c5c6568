"""URL filters: host-suffix and path-prefix expressions, joined on short digest prefixes.

Every (host, path) is expanded into expressions `suffix + prefix`: each suffix of the host that begins at a label, with
each prefix of the path whose length occurs among the rules' paths. Expressions meet the rules by an equi-join on the
first 32 bits of their SHA-256; the full digests then confirm, and the longest rule decides. Only DataFrame functions.

Defined results: a null url or one without `://` has empty host and path and takes the default verdict; rules with null
host, path or verdict are left out; repeated rows each get their row; of equal rules with different verdicts, block
wins; a null page_id is kept as it is; a very long url makes no more expressions than the rules have shapes; an empty
table gives an empty result; other columns of the pages are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
PREFIX_HEX = 8


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url; both empty without `://`."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"(?s)^[^/?#]*", 0)
    after = F.substring(rest, F.length(host) + 1, F.length(rest))
    return F.translate(host, UPPER, LOWER), F.regexp_extract(after, r"(?s)^[^?#]*", 0)


def _rules(rules: DataFrame) -> DataFrame:
    return (
        rules.where(F.col("host").isNotNull() & F.col("path").isNotNull() & F.col("verdict").isNotNull())
        .select(F.translate("host", UPPER, LOWER).alias("host"), "path", "verdict")
        .select(F.concat("host", "path").alias("rule"), F.length("path").alias("path_len"), F.size(F.split("host", r"\.")).alias("labels"), "verdict", F.sha2(F.concat("host", "path"), 256).alias("digest"))
        .groupBy("rule", "path_len", "labels", "digest")
        .agg(F.max("verdict").alias("verdict"))
    )


def expressions(parts: DataFrame, lengths: list[int], counts: list[int]) -> DataFrame:
    """(host, path) into rows with an expression each; `lengths` are those of the rules' paths, `counts` the numbers of
    labels of their hosts, so that a host of many labels makes no more expressions than the rules ask for."""
    labels = F.split("host", r"\.")
    some = F.filter(F.array(*[F.lit(n) for n in counts]), lambda n: n <= F.size(labels))
    suffixes = F.transform(some, lambda n: F.array_join(F.slice(labels, F.size(labels) - n + 1, n), "."))
    fitting = F.filter(F.array(*[F.lit(n) for n in lengths]), lambda n: n <= F.length("path"))
    return (
        parts.withColumn("suffix", F.explode(suffixes))
        .withColumn("path_len", F.explode(fitting))
        .withColumn("digest", F.sha2(F.concat("suffix", F.substring(F.col("path"), F.lit(1), F.col("path_len"))), 256))
    )


def url_filter(pages: DataFrame, rules: DataFrame, default: str = "allow") -> DataFrame:
    """Judge every page: page_id, host, path, rule, verdict.

    pages: page_id, url. rules: host, path, verdict (allow or block). A rule fits its host and all subdomains if the
    path begins with the rule's; the longest wins. The distinct path lengths and label counts of the rules, at most as
    many as a path has characters and a host labels, go to the driver; the rules themselves are joined, and broadcast
    only if Spark finds them small.
    """
    host, path = url_parts(F.col("url"))
    judged = pages.select("page_id", host.alias("host"), path.alias("path"))
    known = _rules(rules)
    shapes = known.select("path_len", "labels").distinct().collect()
    lengths, counts = sorted({r[0] for r in shapes}), sorted({r[1] for r in shapes})
    if not lengths:
        return judged.select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    short = lambda c: F.substring(c, 1, PREFIX_HEX)
    asked = expressions(judged.select("host", "path").where("host <> ''").distinct(), lengths, counts)
    left = asked.select("host", "path", F.col("path_len").alias("asked_len"), F.col("digest").alias("asked"), short(F.col("digest")).alias("short"))
    right = known.select("rule", "path_len", "verdict", "digest", short(F.col("digest")).alias("short"))
    rank = F.struct(F.length("rule").alias("n"), F.col("verdict"), F.col("rule"))
    best = (
        left.join(right, "short")
        .where((F.col("asked") == F.col("digest")) & (F.col("asked_len") == F.col("path_len")))
        .groupBy("host", "path")
        .agg(F.max(rank).alias("best"))
        .select("host", "path", F.col("best.rule").alias("rule"), F.col("best.verdict").alias("found"))
    )
    return judged.join(best, ["host", "path"], "left").select("page_id", "host", "path", "rule", F.coalesce("found", F.lit(default)).alias("verdict"))
