"""URL filters as a temporal join: captures against the list entries active when they were fetched.

A dated feed of additions and removals becomes validity intervals; every capture is looked up
under the keys that can concern it (its host and each parent domain, its host with each
path prefix) and the interval that held at its fetch time decides. DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

HOST = r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)"
PATH = r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*(/[^?#]*)"


def host_of(url: Column) -> Column:
    """Lower-case host without user, port and final dot; empty if there is none."""
    return F.regexp_replace(F.lower(F.regexp_extract(url, HOST, 1)), r"\.$", "")


def lookup_keys(url: Column) -> Column:
    """All keys of entries that cover the URL: domains as "b.c", path prefixes as "a.b.c/x/"."""
    host, path = host_of(url), F.regexp_extract(url, PATH, 1)
    labels = F.split(host, r"\.")
    domains = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    steps = F.split(F.regexp_replace(path, "^/", ""), "/")
    prefixes = F.transform(F.sequence(F.lit(1), F.size(steps)), lambda i: F.concat(host, F.lit("/"), F.array_join(F.slice(steps, 1, i), "/")))
    return F.when(host == "", F.array().cast("array<string>")).when(path.isin("", "/"), domains).otherwise(F.array_union(domains, prefixes))


def validity_intervals(feed: DataFrame) -> DataFrame:
    """feed(key, action, at, change 'add'/'remove') -> intervals(key, action, since, until).

    An entry is active from an addition up to, without, the next removal; additions of an
    active entry change nothing; a removal at the time of an addition wins; removals of
    unknown entries are ignored; until is null while the entry lasts. Rows with a null in any
    of the four columns are left out.
    """
    changes = feed.select("key", "action", "at", "change").dropna().groupBy("key", "action", "at").agg(F.max((F.col("change") == "remove").cast("int")).alias("gone"))
    turn = Window.partitionBy("key", "action").orderBy("at")
    seen = changes.withColumn("before", F.lag("gone", 1, 1).over(turn)).where("gone <> before")
    return seen.withColumn("until", F.lead("at").over(turn)).where("gone = 0").select("key", "action", F.col("at").alias("since"), "until")


def as_of_filter(captures: DataFrame, intervals: DataFrame, id_col: str, url_col: str = "url", time_col: str = "fetched") -> DataFrame:
    """One row per capture: id, host, time, n_active, rule, rule_action, blocked.

    The most specific active entry decides (a longer key is more specific); 'allow' beats
    'block' on one key. Captures without URL, host or time match nothing and are not blocked.
    A decision depends on URL and time alone and is made once for each such pair, so null and
    repeated ids change nothing: every row gets its own. Other columns are ignored. A host or
    URL with very many captures is a skewed equi-join, which the engine splits.
    """
    rows = captures.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(time_col).alias("at"))
    asked = rows.where("url is not null and at is not null").select("url", "at").distinct()
    asked = asked.select("url", "at", F.explode(lookup_keys(F.col("url"))).alias("key"))
    listed = intervals.select("key", "action", "since", "until")
    active = asked.join(listed, "key").where("at >= since and (until is null or at < until)")
    # 'allow' sorts after 'block' here
    weight = F.struct(F.length("key").alias("n"), (F.col("action") == "allow").alias("a"), "key", "action")
    best = active.groupBy("url", "at").agg(F.max(weight).alias("best"), F.count("*").alias("n_active"))
    joined = rows.join(best, ["url", "at"], "left")
    return joined.select(
        F.col("id").alias(id_col),
        F.coalesce(host_of(F.col("url")), F.lit("")).alias("host"),
        F.col("at").alias(time_col),
        F.coalesce("n_active", F.lit(0)).cast("bigint").alias("n_active"),
        F.col("best.key").alias("rule"),
        F.col("best.action").alias("rule_action"),
        F.coalesce(F.col("best.action") == "block", F.lit(False)).alias("blocked"),
    )
