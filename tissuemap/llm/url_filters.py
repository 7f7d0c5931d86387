"""URL rules by a sort-merge range join, in DataFrame operations only.

A rule (host, path) fits a URL whose host is the rule's host or a subdomain of
it and whose path starts with the rule's path. Written back to front with a dot
after each label, a host becomes a key whose prefixes are its parent domains, so
each rule host is an interval of keys; each path prefix is an interval of paths.
Such intervals nest or are disjoint. Their ends, sorted together with the URLs,
are swept once: each end carries the stack of intervals that are open after it,
and a URL takes the stack of the last end before it. One sweep finds the rule
hosts above each URL's host, a second the path rules under those hosts. A rule's
own stack is the rules that equal one of its prefixes, found by an equal-key join
of rules with rules, as no task sees all rules in order.

The sweep is distributed: ends and URLs are dealt to blocks by key range, with
the row id as the last part of the key so that a host with any share of the rows
is cut into many blocks; what is open at a block's beginning is carried over
from earlier blocks through a table with one row per block.

Defined results: a null URL, or one without ``://``, has an empty host and path
and no rule; the longest rule (host plus path, then host) wins; of equal rules
the blocking one counts; repeated rows are each judged; an empty table gives an
empty result, and no rules leave each URL at the default verdict.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import lower_ascii, materialise

RULES = (
    ("org", "/", "allow"),
    ("example.org", "/es/", "block"),
    ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"),
    ("com", "/de/", "block"),
)
DEFAULT = "allow"


def host_of(url: Column) -> Column:
    """Lower-cased authority: after the first ``://`` up to ``/``, ``?`` or ``#``."""
    return lower_ascii(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)\A.*?://([^/?#]*)", 1))


def path_of(url: Column) -> Column:
    """What follows the host, up to ``?`` or ``#``."""
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)\A.*?://[^/?#]*([^?#]*)", 1)


def reversed_host(host: Column) -> Column:
    """``www.example.org`` as ``org.example.www.``; nothing for an empty host."""
    return F.when(host == "", F.lit("")).otherwise(F.concat(F.array_join(F.reverse(F.split(host, r"\.", -1)), "."), F.lit(".")))


def rule_table(spark: SparkSession, rules=RULES) -> DataFrame:
    """Rules as rows, one for each host and path."""
    empty = F.array().cast("array<struct<host:string,path:string,verdict:string>>")
    rows = [F.struct(F.lit(h).alias("host"), F.lit(p).alias("path"), F.lit(v).alias("verdict")) for h, p, v in rules]
    df = spark.range(1).select(F.inline(F.array(*rows) if rows else empty))
    # "block" sorts after "allow", so the maximum lets blocking win among equals
    return df.groupBy("host", "path").agg(F.max("verdict").alias("verdict"))


def interval_ends(nodes: DataFrame, key: Column) -> DataFrame:
    """Two rows per node: its key opens the stack that ends with it, and the key
    followed by a byte that no text holds closes it, leaving the parent's stack.

    ``nodes`` has ``prefix`` (the key's text) and ``stack`` (prefixes that are
    open there, outermost first, itself last).
    """
    begin = F.encode(key, "utf-8")
    begins = nodes.select(begin.alias("key"), F.col("stack"))
    ends = nodes.select(
        F.concat(begin, F.lit(bytearray(b"\xff"))).alias("key"),
        F.slice("stack", 1, F.size("stack") - 1).alias("stack"),
    )
    return begins.unionByName(ends)


def stacks(prefixes: DataFrame, proper_prefixes: Column) -> DataFrame:
    """For each prefix the chain of prefixes in the table that enclose it."""
    own = prefixes.select("prefix", F.explode(F.concat(proper_prefixes, F.array("prefix"))).alias("above"))
    known = prefixes.select(F.col("prefix").alias("above"))
    return own.join(known, "above").groupBy("prefix").agg(F.sort_array(F.collect_set("above")).alias("stack"))


def sweep(points: DataFrame, ends: DataFrame, blocks: int) -> DataFrame:
    """Each point (``key`` binary, ``row`` struct, ``tie`` long) with the stack
    of the last interval end at or before its key; empty before the first one."""
    empty = F.array().cast("array<string>")
    every = ends.select("key", F.lit(0).alias("kind"), F.lit(0).cast("long").alias("tie"), "stack", F.lit(None).cast(points.schema["row"].dataType).alias("row")).unionByName(
        points.select("key", F.lit(1).alias("kind"), "tie", F.lit(None).cast("array<string>").alias("stack"), "row")
    )
    # written out, so that the blocks stay as they are when read again
    dealt = materialise(every.repartitionByRange(blocks, "key", "kind", "tie").withColumn("block", F.spark_partition_id()), "sweep")
    last = dealt.filter("stack is not null").groupBy("block").agg(F.max_by("stack", "key").alias("open"))
    # one row per block, a number fixed by the caller: small whatever the input
    marks = dealt.select("block").distinct().join(last, "block", "left")
    before = Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    carried = marks.select("block", F.last("open", ignorenulls=True).over(before).alias("carried"))
    inside = Window.partitionBy("block").orderBy("key", "kind", "tie").rowsBetween(Window.unboundedPreceding, 0)
    out = dealt.withColumn("seen", F.last("stack", ignorenulls=True).over(inside)).filter("kind = 1")
    out = out.join(F.broadcast(carried), "block")
    return out.select("row", F.coalesce("seen", "carried", empty).alias("stack"))


def apply_rules(urls: DataFrame, rules: DataFrame, blocks: int | None = None) -> DataFrame:
    """``urls`` (any columns, ``url`` among them) with host, path, rule, verdict."""
    spark = urls.sparkSession
    blocks = blocks or int(spark.conf.get("spark.sql.shuffle.partitions"))
    keep = [c for c in urls.columns if c not in ("host", "path", "rule", "verdict")]
    base = urls.select(*keep).withColumns({"host": host_of(F.col("url")), "path": path_of(F.col("url"))})
    base = base.withColumn("_uid", F.monotonically_increasing_id())
    base = materialise(base, "urls")

    hosts = rules.select(reversed_host(F.col("host")).alias("prefix")).distinct()
    labels = F.split(F.col("prefix"), r"\.", -1)
    above = F.transform(
        F.sequence(F.lit(1), F.greatest(F.size(labels) - 2, F.lit(1))),
        lambda i: F.concat(F.array_join(F.slice(labels, 1, i), "."), F.lit(".")),
    )
    above = F.when(F.size(labels) > 2, above).otherwise(F.array().cast("array<string>"))
    host_ends = interval_ends(stacks(hosts, above), F.col("prefix"))
    row = F.struct("_uid", "path")
    points = base.select(F.encode(reversed_host(F.col("host")), "utf-8").alias("key"), row.alias("row"), F.col("_uid").alias("tie"))
    under = sweep(points, host_ends, blocks).select("row.*", F.explode("stack").alias("over"))

    # the second sweep: rule host, a byte below any text, then the path
    cut = F.lit("\x00")
    pair = rules.select(F.concat(reversed_host(F.col("host")), cut, F.col("path")).alias("prefix"), F.concat("host", "path").alias("rule"), "verdict", F.col("host").alias("rule_host"))
    heads = F.transform(
        F.sequence(F.instr("prefix", "\x00"), F.greatest(F.length("prefix") - 1, F.instr("prefix", "\x00"))),
        lambda i: F.substring(F.col("prefix"), F.lit(1), i),
    )
    heads = F.filter(heads, lambda x: x != F.col("prefix"))
    path_ends = interval_ends(stacks(pair.select("prefix"), heads), F.col("prefix"))
    points = under.select(F.encode(F.concat("over", cut, "path"), "utf-8").alias("key"), F.struct("_uid").alias("row"), F.col("_uid").alias("tie"))
    hit = sweep(points, path_ends, blocks).filter(F.size("stack") > 0).select("row._uid", F.get("stack", F.size("stack") - 1).alias("prefix"))
    named = hit.join(pair, "prefix").select("_uid", F.struct(F.length("rule").alias("n"), F.length("rule_host").alias("h"), "rule", "verdict").alias("r"))
    best = named.groupBy("_uid").agg(F.max("r").alias("r"))
    out = base.join(best, "_uid", "left")
    return out.select(*keep, "host", "path", F.col("r.rule").alias("rule"), F.coalesce("r.verdict", F.lit(DEFAULT)).alias("verdict"))
