"""URL allow/block rules by hashed host-suffix and path-prefix expressions (operator 1).

Every URL is expanded into ``host suffix + path prefix`` strings.  Each string meets the rule table in an
equi-join on a short prefix of its digest; the full digest and then the text itself confirm the hit, and the
longest rule that fits decides.  Only the shapes that occur in the rules are expanded: suffixes
with as many labels as some rule's host and path prefixes as long as some rule's path, so no
fitting rule is missed and a URL yields at most one string per shape.  Different (host, path) pairs are expanded, once each and without
the other columns; rows get the verdict of their pair back by a join.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import stored
from .text import free_name

#: Rules, or pairs that fit one, beyond this count are joined by shuffle instead of broadcast (about 200 bytes each), rules with salted keys.
BROADCAST_RULES, BROADCAST_BYTES = 200_000, 32 << 20
#: Copies of the rule table in the shuffled join, so that one host with a third of all URLs is dealt to many tasks.
SALTS = 64
#: Letters that are compared without case in hosts of URLs and rules alike.
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Hexadecimal digits of the digest that form the join key.
PREFIX_DIGITS = 8


def rules_table(spark: SparkSession, rules: Iterable[tuple[str, str]]) -> DataFrame:
    """``(verdict, "host/path")`` pairs as a table ``rule, verdict``."""
    return spark.createDataFrame([(r, v) for v, r in rules], "rule string, verdict string")


def url_host(url: Column) -> Column:
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    return F.coalesce(F.translate(host, UPPER, UPPER.lower()), F.lit(""))


def url_path(url: Column) -> Column:
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    return F.coalesce(F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1), F.lit(""))


def judge_urls(pages: DataFrame, rules: DataFrame, url_col: str = "url", default: str = "allow", broadcast_limit: int = BROADCAST_RULES) -> DataFrame:
    """Columns of ``pages`` plus ``host``, ``path``, ``rule``, ``verdict``.

    A rule ``host/path`` fits a URL whose host is the rule's or a subdomain of it and whose path starts with the
    rule's path, slash included; hosts are compared with A-Z in lower case.  The longest fitting rule text wins; of equal lengths the
    smaller text, and of one text with two verdicts ``block``.  No fit: ``rule`` null and ``default``.
    A null URL or one without ``://`` has an empty host and path and fits no rule.  Rows are
    judged one by one: repeated rows stay repeated, an empty table gives an empty one, and columns of ``pages`` that
    bear an added column's name are replaced.
    """
    added = ("host", "path", "rule", "verdict")
    kept = [c for c in pages.columns if c.lower() not in added]
    clean = (
        rules.filter("rule is not null and instr(rule, '/') > 0")
        .select(
            "rule",
            F.translate(F.substring_index("rule", "/", 1), UPPER, UPPER.lower()).alias("r_host"),
            F.expr("substr(rule, instr(rule, '/'))").alias("r_path"),
            "verdict",
        )
        .withColumn("expr", F.concat("r_host", "r_path"))
        .groupBy("expr")
        .agg(F.min("rule").alias("rule"), F.max("verdict").alias("verdict"), F.first("r_host").alias("r_host"), F.first("r_path").alias("r_path"))
        .withColumn("digest", F.sha2("expr", 256))
        .withColumn("key", F.substring("digest", 1, PREFIX_DIGITS))
    )
    shape = clean.select(F.size(F.split("r_host", r"\.")).alias("labels"), F.length("r_path").alias("chars"))
    # Shapes are few (label counts times path lengths), whatever the number of rules.
    shapes = sorted((r.labels, r.chars) for r in shape.distinct().collect())
    taken = [*kept, *added, url_col]
    key, expr, digest, salt = (free_name(n, taken) for n in ("hash_key", "expression", "digest", "salt"))
    base = pages.withColumns({"host": url_host(F.col(url_col)), "path": url_path(F.col(url_col))}) if url_col in kept else pages
    base = base.select(*kept, "host", "path")
    if not shapes:
        return base.select(*kept, "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    forms = F.array_distinct(
        F.array_compact(
            F.array(
                *(
                    F.when(
                        (F.col("host") != "") & (F.size(F.split("host", r"\.")) >= labels) & (F.length("path") >= chars),
                        F.concat(F.substring_index("host", ".", -labels), F.substring("path", 1, chars)),
                    )
                    for labels, chars in shapes
                )
            )
        )
    )
    # One row per pair that may fit a rule; hosts of rules are never empty.
    pairs = base.filter(F.col("host") != "").select("host", "path").distinct()
    expanded = pairs.withColumn(expr, F.explode_outer(forms)).withColumn(digest, F.sha2(F.col(expr), 256)).withColumn(key, F.substring(F.col(digest), 1, PREFIX_DIGITS))
    right = clean.select(F.col("key").alias("_k"), F.col("digest").alias("_d"), F.col("expr").alias("_e"), F.col("rule").alias("_r"), F.col("verdict").alias("_v"))
    if clean.limit(broadcast_limit + 1).count() <= broadcast_limit:
        on = F.col(key) == F.col("_k")
        right = F.broadcast(right)
    else:
        right = right.withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        expanded = expanded.withColumn(salt, F.pmod(F.xxhash64("host", "path"), F.lit(SALTS)).cast("int"))
        on = (F.col(key) == F.col("_k")) & (F.col(salt) == F.col("_s"))
    hits = expanded.join(right, on).filter((F.col(digest) == F.col("_d")) & (F.col(expr) == F.col("_e")))
    hit = F.struct((-F.length("_r")).alias("n"), F.col("_r").alias("r"), F.col("_v").alias("v"))
    own_host, own_path, won = (free_name(n, taken) for n in ("hit_host", "hit_path", "hit"))
    best = stored(hits.groupBy(F.col("host").alias(own_host), F.col("path").alias(own_path)).agg(F.min(hit).alias(won)), "hits")
    # Few pairs that fit go to every task; more are joined by shuffle, where Spark splits what one pair has of the rows.
    n, size = best.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length(own_host) + F.octet_length(own_path)), F.lit(0))).first()
    found = F.broadcast(best) if n <= broadcast_limit and size <= BROADCAST_BYTES else best.hint("merge")
    judged = base.join(found, (F.col("host") == F.col(own_host)) & (F.col("path") == F.col(own_path)), "left")
    return judged.select(*kept, "host", "path", F.col(f"{won}.r").alias("rule"), F.coalesce(F.col(f"{won}.v"), F.lit(default)).alias("verdict"))
