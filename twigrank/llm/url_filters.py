"""URL filters: host-suffix and path-prefix expressions joined on short hash prefixes, confirmed by full digests."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from twigrank.llm.common import join_per_key, materialize

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Hexadecimal digits of the digest that the join compares first.
SHORT = 8
#: Rule tables up to this many rows are broadcast (about 120 bytes each); larger ones are shuffled on the short prefix.
BROADCAST_RULES = 200_000


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str


def url_parts(url: Column) -> tuple[Column, Column]:
    """(host, path) of a url; null or without ``://``: both empty. Only A-Z of the host are lower-cased."""
    url = F.coalesce(url, F.lit(""))
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + F.lit(3), F.length(url))).otherwise("")
    raw = F.regexp_extract(rest, "^([^/?#]*)", 1)
    path = F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)
    return F.translate(raw, UPPER, LOWER), path


def rules_frame(spark: SparkSession, rules: list[Rule]) -> DataFrame:
    rows = [(r.verdict, r.host, r.path) for r in rules]
    return spark.createDataFrame(rows, "verdict string, host string, path string")


def judge_urls(df: DataFrame, rules: DataFrame, url_col: str = "url", default: str = "allow") -> DataFrame:
    """All rows and columns of df with host, path, rule and verdict (columns of these names in df are replaced).

    A rule fits its host and all subdomains if the url's path starts with the rule's; the longest rule string wins, then
    the longer host, then block. Rules with a null field are ignored. Without a fitting rule: rule null, verdict `default`.
    Null urls and urls without ``://`` have an empty host and path and get the default unless a rule has an empty host.
    Repeated rows are judged each; an empty table gives an empty one. Each distinct host and path is judged once; verdicts
    of URLs that many rows share come back to their rows by broadcast.
    """
    rules = rules.dropna(subset=["verdict", "host", "path"]).select(
        "verdict", F.translate("host", UPPER, LOWER).alias("rule_host"), F.col("path").alias("rule_path")
    )
    rules = rules.withColumn("rule", F.concat("rule_host", "rule_path")).withColumn("digest", F.sha2("rule", 256))
    rules = rules.withColumn("short", F.substring("digest", 1, SHORT))
    # what an expression can be: numbers of host labels and lengths of paths that any rule has
    shape = rules.agg(
        F.collect_set(F.size(F.split("rule_host", r"\."))).alias("labels"),
        F.collect_set(F.length("rule_path")).alias("lengths"),
        F.count("*").alias("n"),
    ).first()
    if shape["n"] <= BROADCAST_RULES:
        rules = F.broadcast(rules)

    host, path = url_parts(F.col(url_col))
    rows = df.drop("host", "path", "rule", "verdict").withColumn("host", host).withColumn("path", path)
    labels = F.split("host", r"\.")
    suffixes = F.filter(
        F.transform(
            F.array(*[F.lit(int(n)) for n in sorted(shape["labels"])]),
            lambda n: F.when(n <= F.size(labels), F.array_join(F.slice(labels, F.size(labels) - n + 1, n), ".")),
        ),
        lambda x: x.isNotNull(),
    )
    prefixes = F.filter(
        F.transform(
            F.array(*[F.lit(int(n)) for n in sorted(shape["lengths"])]),
            lambda n: F.when(n <= F.length("path"), F.substring("path", F.lit(1), n)),
        ),
        lambda x: x.isNotNull(),
    )
    if not shape["n"]:
        return rows.withColumn("rule", F.lit(None).cast("string")).withColumn("verdict", F.lit(default))
    urls = materialize(rows.groupBy("host", "path").agg(F.count("*").alias("n")))
    expressions = (
        urls.select("host", "path")
        .withColumn("suffix", F.explode(suffixes))
        .withColumn("prefix", F.explode(prefixes))
        .withColumn("full", F.sha2(F.concat("suffix", "prefix"), 256))
        .withColumn("short", F.substring("full", 1, SHORT))
    )
    best = F.max(
        F.struct(F.length("rule"), F.length("rule_host"), F.when(F.col("verdict") == "block", 1).otherwise(0), "rule", "verdict")
    )
    found = (
        expressions.join(rules, "short")
        .where("full = digest")
        .groupBy("host", "path")
        .agg(best.alias("best"))
        .select("host", "path", F.col("best.rule").alias("rule"), F.col("best.verdict").alias("verdict"))
    )
    judged = urls.join(found, ["host", "path"], "left").withColumn("verdict", F.coalesce("verdict", F.lit(default)))
    n_rows = urls.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    return join_per_key(rows, judged, ["host", "path"], n_rows).select(*rows.columns, "rule", "verdict")
