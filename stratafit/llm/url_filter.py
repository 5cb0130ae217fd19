"""URL rules: host-suffix and path-prefix expressions, an equi-join on short digests, confirmation on full digests, precedence."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stratafit.llm.common import checkpointed, hot_safe_lookup

#: Rule tables of at most so many rows are broadcast; larger ones are joined by shuffle.
BROADCAST_RULES = 100_000
#: Columns of the result beside those of the pages.
ADDED = ("host", "path", "rule", "verdict")
#: Hex digits of a digest on which expressions and rules are first joined: 32 bits.
SHORT = 8


def host_of(url: Column) -> Column:
    """After the first :// up to / ? # or the end, A-Z folded; empty without ://, or for null."""
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url)))
    raw = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    return F.coalesce(F.translate(raw, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    """After the host up to ? # or the end; empty without ://, or for null."""
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url)))
    return F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def _digest(host: Column, path: Column) -> Column:
    """The length prefix keeps (host, path) apart from any other split of the same characters."""
    return F.sha2(F.concat(F.length(host).cast("string"), F.lit(":"), host, path), 256)


def judge_urls(pages: DataFrame, rules: DataFrame, url: str = "url", default: str = "allow") -> DataFrame:
    """pages with host, path, rule and verdict; rules has (host, path, verdict), verdict allow or block.

    A rule fits its host and every subdomain when the url's path starts with the rule's path. The longest rule (host and path
    together) wins, then block before allow, then the smallest text; no rule: null and the default. Rules with null or empty host fit nothing;
    repeated rules count once. Columns of pages named host, path, rule or verdict are replaced. A null url has an empty host and fits no rule; repeated
    rows are judged alike; empty tables of pages give no rows, of rules the default. The plan has one expression whatever the number of rules.

    Each url is expanded into the suffixes of its host at label borders (as many labels as rules have) and the prefixes of its path (of
    the lengths that rules have). So a url gives at most labels x lengths expressions, whatever its own length, and no rule can be missed.
    Urls with the same expressions are judged once, so a hot host costs one row; digests meet on their first 32 bits and are confirmed whole.
    """
    listed = (
        rules.filter("host is not null and host <> ''")
        .select(F.lower("host").alias("rule_host"), F.coalesce("path", F.lit("")).alias("rule_path"), F.col("verdict").alias("rule_verdict"))
        .groupBy("rule_host", "rule_path").agg(F.max("rule_verdict").alias("rule_verdict"))
        .withColumn("full", _digest(F.col("rule_host"), F.col("rule_path"))).withColumn("short", F.substring("full", 1, SHORT))
    )
    shape = listed.agg(F.count(F.lit(1)).alias("n"), F.collect_set(F.size(F.split("rule_host", r"\."))).alias("labels"), F.collect_set(F.length("rule_path")).alias("lengths")).first()
    base = pages.select(F.struct(*[pages[c] for c in pages.columns if c not in ADDED]).alias("row"), host_of(F.col(url)).alias("host"), path_of(F.col(url)).alias("path"))
    if not shape["n"]:
        return base.select("row.*", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    labels, lengths = sorted(shape["labels"]), sorted(shape["lengths"])

    suffixes = F.array_distinct(F.transform(F.lit(labels), lambda k: F.call_function("substring_index", F.col("host"), F.lit("."), -k)))
    prefixes = F.transform(F.filter(F.lit(lengths), lambda k: k <= F.length("path")), lambda k: F.substring(F.col("path"), 1, k))
    every = F.flatten(F.transform(suffixes, lambda h: F.transform(F.col("_prefixes"), lambda p: _digest(h, p))))
    base = base.withColumn("_prefixes", prefixes)
    digests = F.when(F.col("host") != "", F.array_distinct(every)).otherwise(F.array().cast("array<string>"))
    keyed = base.withColumn("_digests", digests).withColumn("_key", F.sha2(F.concat_ws(",", "_digests"), 256)).withColumn("_row", F.monotonically_increasing_id())
    sets = checkpointed(keyed.groupBy("_key").agg(F.first("_digests").alias("_digests"), F.count(F.lit(1)).alias("_members")))
    right = F.broadcast(listed) if shape["n"] <= BROADCAST_RULES else listed
    hits = sets.select("_key", "_members", F.explode("_digests").alias("_full")).join(right, F.substring("_full", 1, SHORT) == F.col("short")).filter(F.col("_full") == F.col("full"))
    judged = hot_safe_lookup(keyed.drop("_digests", "_prefixes"), _best(hits, "_key", "_members"), "_key", "_members", max(1, pages.count()), "_row")
    return judged.select("row.*", "host", "path", "rule", F.coalesce("v", F.lit(default)).alias("verdict"))


def _best(hits: DataFrame, *keys: str) -> DataFrame:
    """The winning rule of each key: the largest (length, block first, smallest text)."""
    text = F.concat("rule_host", "rule_path")
    order = F.struct((-F.length(text)).alias("l"), F.when(F.col("rule_verdict") == "block", 0).otherwise(1).alias("a"), text.alias("rule"), F.col("rule_verdict").alias("v"))
    return hits.groupBy(*keys).agg(F.min(order).alias("best")).select(*keys, F.col("best.rule").alias("rule"), F.col("best.v").alias("v"))
