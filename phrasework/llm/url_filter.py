"""URL filter: host-suffix and path-prefix expressions against a hashed rule list.

Each distinct (host, path) is expanded into its expressions, every host suffix joined with
the path cut at every length that a rule path has. Expressions meet rules by an equi-join on
the first ``PREFIX_HEX`` hex digits of their SHA-256 digests; the full digest then confirms,
and the longest rule decides. DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Hex digits of a digest that the join compares first (32 bits).
PREFIX_HEX = 8
#: A rule list of at most this many rows is broadcast; a longer one is shuffled.
BROADCAST_RULES = 200_000
#: Distinct path lengths in a rule list; each one is an expression per host suffix.
MAX_PATH_LENGTHS = 4096

UPPER, LOWERED = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

# The rule list of the production query, as (action, host, path).
PRODUCTION_RULES = [
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
]


def rules_frame(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    """A rule list given as (action, host, path) tuples, as a table of literals."""
    rows = [F.struct(*(F.lit(x).cast("string").alias(c) for c, x in zip(("action", "host", "path"), rule))) for rule in rules]
    return spark.range(1).select(F.inline(F.array(*rows)))


def split_url(url):
    """Columns (host, path) of a URL column.

    The host lies between the first ``://`` and the next ``/``, ``?`` or ``#``, with A-Z
    lower-cased; the path goes on to ``?``, ``#`` or the end. Both are empty for null and
    where ``://`` is absent.
    """
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    before_query = F.substring_index(F.substring_index(rest, "?", 1), "#", 1)
    slash = F.instr(before_query, "/")
    host = F.when(slash > 0, F.substring(before_query, F.lit(1), slash - 1)).otherwise(before_query)
    path = F.when(slash > 0, F.substring(before_query, slash, F.length(before_query))).otherwise(F.lit(""))
    return F.translate(host, UPPER, LOWERED), path


def hashed_rules(rules: DataFrame) -> DataFrame:
    """Rules with their digest; of rules with one expression a block stays before an allow.

    Null actions, hosts or paths drop out: such a rule fits nothing.
    """
    return (
        rules.where("action is not null and host is not null and path is not null")
        .select(
            F.concat(F.translate("host", UPPER, LOWERED), F.col("path")).alias("rule"),
            F.length("path").alias("rule_path"),
            F.col("action"),
        )
        .groupBy("rule", "rule_path")
        .agg(F.max("action").alias("action"))
        .withColumn("digest", F.sha2("rule", 256))
        .withColumn("prefix", F.substring("digest", 1, PREFIX_HEX))
    )


def filter_urls(
    pages: DataFrame,
    rules: DataFrame,
    id_col: str = "page_id",
    url_col: str = "url",
    default: str = "allow",
    broadcast_rules: int = BROADCAST_RULES,
) -> DataFrame:
    """Judge every row's URL: (id, host, path, rule, verdict, matched_rules).

    A rule fits its host and all subdomains where the path starts with the rule's path; of
    several the longest wins, on equal lengths the one with the longer host. Without a
    fitting rule ``rule`` is null and ``verdict`` is ``default``. Null ids stay, repeated rows
    stay repeated, an empty table gives an empty result, other columns are ignored.
    """
    host, path = split_url(F.col(url_col))
    rows = pages.select(F.col(id_col), host.alias("host"), path.alias("path"))
    known = hashed_rules(rules)
    lengths = [r[0] for r in known.select("rule_path").distinct().limit(MAX_PATH_LENGTHS + 1).collect()]
    if len(lengths) > MAX_PATH_LENGTHS:
        raise ValueError(f"more than {MAX_PATH_LENGTHS} path lengths in the rule list")
    if known.limit(broadcast_rules + 1).count() <= broadcast_rules:
        known = F.broadcast(known)
    labels = F.split("host", "\\.")
    count = F.size(labels)
    suffixes = F.transform(F.sequence(F.lit(1), count), lambda k: F.array_join(F.slice(labels, k, count), "."))
    cuts = F.array_compact(F.array(*[F.when(F.length("path") >= n, F.substring("path", F.lit(1), F.lit(n))) for n in sorted(lengths)]))
    expressions = F.flatten(F.transform(suffixes, lambda s: F.transform(cuts, lambda p: F.concat(s, p))))
    judged = (
        rows.select("host", "path")
        .where("host <> ''")
        .distinct()
        .select("host", "path", F.explode(expressions).alias("expression"))
        .withColumn("own", F.sha2("expression", 256))
        .withColumn("prefix", F.substring("own", 1, PREFIX_HEX))
        .join(known, "prefix")
        .where(F.col("own") == F.col("digest"))
        .groupBy("host", "path")
        .agg(
            F.max(F.struct(F.length("rule").alias("n"), (-F.col("rule_path")).alias("h"), "rule", "action")).alias("best"),
            F.count(F.lit(1)).alias("matched_rules"),
        )
        .select("host", "path", "best.rule", "best.action", "matched_rules")
    )
    return rows.join(judged, ["host", "path"], "left").select(
        id_col,
        "host",
        "path",
        "rule",
        F.coalesce("action", F.lit(default)).alias("verdict"),
        F.coalesce("matched_rules", F.lit(0)).alias("matched_rules"),
    )
