"""URL filtering by temporal lists: dated changes become validity intervals, captures are joined as of their fetch time.

A list is a log of changes (list, key, action, date). A key is a host, which covers its subdomains, or a
host with a path prefix. An entry is valid from an addition to the next removal. Intervals are entered in
each month they touch, and a capture asks for its own month only, under its host's suffixes and path
prefixes. So a key with a long history does not multiply captures, and a frequent host is spread over
months. Hosts and paths may be of any depth: a capture asks for those suffixes and prefixes only whose
number of labels or segments some key of the list has. The interval's ends are then compared exactly, and per capture the most specific entry decides,
of these the latest, of these the smallest list name.

Defined cases: null or unparsable URLs and null times match nothing and are kept; a repeated addition
while an entry is valid changes nothing, nor does a removal without one; of changes of one moment removals
come first; intervals include their start and not their end; an entry that is never removed stays valid to
the horizon, the latest capture; repeated captures, also with one id, are rows of their own, each decided by its own
URL and time; extra columns are ignored; an empty list leaves every capture unmatched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import small, stored

#: Entries up to which the list travels to every executor.
LIST_ROWS = 200_000


def host_of(url: Column) -> Column:
    """Lower-case host without user, port and final dot; empty if there is none."""
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]+?)\.?(?::[0-9]*)?(?:[/?#]|$)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*(/[^?#]*)", 1), F.lit(""))


def keys_of(url: Column, label_counts: list[int], segment_counts: list[int]) -> Column:
    """array<string>: host suffixes of two labels and more (or the whole host), and the host with path prefixes of whole segments, of these numbers of labels or segments."""
    host = host_of(url)
    labels = F.split(host, r"\.")
    parts = F.filter(F.split(path_of(url), "/"), lambda x: x != "")
    n, m = F.size(labels), F.size(parts)
    among = lambda counts, wanted: F.filter(F.lit(sorted(counts)).cast("array<int>"), wanted)
    suffixes = F.transform(among(label_counts, lambda c: (c <= n) & ((c >= 2) | (c == n))), lambda c: F.array_join(F.slice(labels, n - c + 1, c), "."))
    prefixes = F.transform(among(segment_counts, lambda c: c <= m), lambda c: F.concat(host, F.lit("/"), F.array_join(F.slice(parts, F.lit(1), c), "/")))
    return F.when(host == "", F.array().cast("array<string>")).otherwise(F.array_distinct(F.concat(suffixes, prefixes)))


def intervals(changes: DataFrame) -> DataFrame:
    """changes(list, key, action 'add' or 'remove', at) to (list, key, valid_from, valid_to); valid_to is null while nothing ends it."""
    by_key = Window.partitionBy("list", "key").orderBy("at", F.col("action") == "add")
    log = changes.where("list is not null and key is not null and at is not null").select("list", "key", "action", "at").distinct()
    log = log.withColumn("before", F.lag("action").over(by_key)).where("before is null or before <> action").where("before is not null or action = 'add'")
    ends = log.withColumn("valid_to", F.lead("at").over(by_key))
    return ends.where("action = 'add' and (valid_to is null or valid_to > at)").select("list", "key", F.col("at").alias("valid_from"), "valid_to")


def temporal_list_join(captures: DataFrame, changes: DataFrame, id_col: str = "id", url_col: str = "url", at_col: str = "at") -> DataFrame:
    """One row per capture: id, n_active (entries valid at its time), list, key and valid_from of the deciding one (null if none)."""
    seen = captures.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(at_col).alias("at"))
    horizon = seen.agg(F.max("at").alias("h")).first()[0]
    month = lambda t: (F.year(t) * 12 + F.month(t)).cast("int")
    spans = intervals(changes)
    if horizon is None:
        spans = spans.where("false")
        horizon_col = F.col("valid_from")
    else:
        horizon_col = F.lit(horizon).cast(seen.schema["at"].dataType)
    spans = spans.where(F.col("valid_from") <= horizon_col)
    last = F.least(F.coalesce("valid_to", horizon_col), horizon_col)
    spans = spans.withColumn("month", F.explode(F.sequence(month(F.col("valid_from")), month(last))))
    spans = stored(spans, "intervals")
    slashes = F.length("key") - F.length(F.translate("key", "/", ""))
    depths = spans.agg(
        F.count("*").alias("rows"),
        F.collect_set(F.when(slashes == 0, F.size(F.split("key", r"\.")))).alias("labels"),
        F.collect_set(F.when(slashes > 0, slashes)).alias("segments"),
    ).first()
    # equal captures are asked once and get one answer; no number of a row is needed, which a retried task might give anew
    once = seen.where("url is not null and at is not null").select("url", "at").distinct()
    asked = once.select("url", "at", month(F.col("at")).alias("month"), F.explode(keys_of(F.col("url"), depths["labels"], depths["segments"])).alias("key"))
    hit = asked.join(small(spans, depths["rows"], LIST_ROWS), ["key", "month"]).where("valid_from <= at and (valid_to is null or at < valid_to)")
    best = F.min_by(F.struct("list", "key", "valid_from"), F.struct((-F.length("key")).alias("a"), F.expr("-unix_micros(cast(valid_from as timestamp))").alias("b"), F.col("list").alias("c"), F.col("key").alias("d")))
    decided = hit.groupBy("url", "at").agg(F.count("*").alias("n_active"), best.alias("best"))
    return seen.join(decided, ["url", "at"], "left").select(F.col("id").alias(id_col), F.coalesce("n_active", F.lit(0).cast("long")).alias("n_active"), F.col("best.list").alias("list"), F.col("best.key").alias("key"), F.col("best.valid_from").alias("valid_from"))
