"""Mixing sources to target weights by Pareto order sampling.

Each source gets a target number of words. What a source's documents give as
whole copies is allocated first; for the rest each document draws a random
number u from its id, and is ranked by the odds of u over the odds of its
inclusion probability. That is proportional to its words; documents for which it
would exceed one are certain, and the others' is solved anew, so that the expected
words are the rest. Documents are taken in the order of the ranks until the rest is
reached: an unequal-probability sample of fixed size, the size counted in words.

The order is never sorted as a whole. A source's cut point is found by repeated
histograms of the rank value, 256 bins each, that close in on the bin in which
the running total of words reaches the rest, until that bin holds one document;
every pass is one aggregation with map-side sums. The sample is then a projection:
rank value below the cut.

Defined results: a null text has no words and is never taken; documents of equal
rank (repeated rows) are taken or left together; the null source is a source of
its own, last in order; sources without words get a target of 0; an empty table
gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import count_words, materialise

WEIGHTS = (3, 1, 2)
SHARE = 1.5
MOST = 2.0
BINS = 256
#: After so many passes a bin is finer than the numbers themselves.
PASSES = 7
#: Rank value of documents that are certain, below all others.
CERTAIN = -1000.0
#: Source tables up to this many rows are broadcast; larger ones are joined.
SMALL = 50_000


def _known(df: DataFrame, count: int) -> DataFrame:
    return F.broadcast(df) if count <= SMALL else df


def sizes(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id, source and number of words of each document, and ``more`` columns."""
    return docs.select("doc_id", F.col("source").alias("_source"), count_words(F.col("text")).alias("size"), *more)


def with_odds(df: DataFrame) -> DataFrame:
    # 52 bits of a digest of the id, half a step off the ends: never 0 or 1
    bits = F.conv(F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))), 1, 13), 16, 10).cast("long")
    return df.withColumn("_u", (bits.cast("double") + 0.5) / F.lit(float(2**52)))


def targets(per_source: DataFrame, share: float = SHARE, weights=WEIGHTS, most: float = MOST) -> DataFrame:
    """``per_source`` (_source, source_size) with ``weight`` and ``target``.

    The excess above ``most`` times a source's size goes to the others by weight
    until none is above. That fixed point is a water level: in order of capacity
    per weight, a source is full if the level, were it and all later ones open,
    would not stay below its capacity. The windows see one row per source.
    """
    order = Window.orderBy(F.col("_source").asc_nulls_last())
    cycle = F.array(*[F.lit(float(x)) for x in weights])
    t = per_source.withColumn("weight", F.get(cycle, F.pmod(F.row_number().over(order) - 1, F.lit(len(weights)))))
    t = t.withColumn("cap", F.col("source_size") * F.lit(most))
    all_ = Window.partitionBy()
    rising = Window.orderBy(F.col("cap") / F.col("weight"), F.col("_source").asc_nulls_last())
    t = t.withColumns(
        {
            "budget": F.sum("source_size").over(all_) * F.lit(share),
            "full_before": F.coalesce(F.sum("cap").over(rising.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)),
            "open_weight": F.sum("weight").over(rising.rowsBetween(0, Window.unboundedFollowing)),
        }
    )
    t = t.withColumn("level", (F.col("budget") - F.col("full_before")) / F.col("open_weight"))
    t = t.withColumn("full", F.col("level") * F.col("weight") >= F.col("cap"))
    t = t.withColumn("first_open", F.min(F.when(~F.col("full"), F.struct((F.col("cap") / F.col("weight")).alias("at"), F.col("_source").isNull().alias("none"), F.col("_source"), F.col("level")))).over(all_))
    level = F.col("first_open").getField("level")
    target = F.when(F.col("full") | level.isNull(), F.col("cap")).otherwise(F.least("cap", level * F.col("weight")))
    return t.select("_source", "source_size", "weight", target.alias("target"))


def mix(docs: DataFrame, share: float = SHARE, weights=WEIGHTS, most: float = MOST) -> DataFrame:
    """doc_id, size, source, source_size, target, copies and taken of each document."""
    numbers = materialise(sizes(docs), "mixsizes")
    return _mixed(numbers, share, weights, most)


def _mixed(numbers: DataFrame, share: float, weights, most: float) -> DataFrame:
    cut, count = cut_points(numbers, share, weights, most)
    out = with_odds(numbers).join(_known(cut, count), F.col("_source").eqNullSafe(F.col("_s")))
    return out.select(
        "doc_id", "size", F.col("_source").alias("source"), "source_size", "target", _copies().alias("copies"),
        (F.col("size") * _copies()).alias("taken"),
    )


def _rank_value() -> Column:
    """Logarithm of the odds of u over the odds of inclusion."""
    p = F.col("slope") * F.col("size")
    return F.when(p >= 1.0, F.lit(CERTAIN)).otherwise(F.log(F.col("_u") / (1.0 - F.col("_u"))) - F.log(p / (1.0 - p)))


def _copies() -> Column:
    extra = F.when((F.col("size") > 0) & (F.col("rest") > 0) & (_rank_value() < F.col("cut")), F.lit(1)).otherwise(F.lit(0))
    return (F.when(F.col("size") > 0, F.col("whole")).otherwise(F.lit(0)) + extra).cast("long")


def slopes(by_size: DataFrame, s: DataFrame, count: int) -> DataFrame:
    """_source, slope, certain: inclusion per word, and the words of the documents
    that are certain.

    From the largest size down, the first at which the slope, were it and all smaller
    sizes open, includes it with a probability of at most one. ``by_size`` has a row
    per size of a source.
    """
    rest = s.select(F.col("_s"), "rest")
    falling = Window.partitionBy("_source").orderBy(F.desc("size"))
    t = by_size.withColumns(
        {
            "larger": F.coalesce(F.sum(F.col("n") * F.col("size")).over(falling.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)),
            "squares": F.sum(F.col("n").cast("decimal(38,0)") * F.col("size") * F.col("size")).over(falling.rowsBetween(0, Window.unboundedFollowing)),
        }
    )
    t = t.join(_known(rest, count), F.col("_source").eqNullSafe(F.col("_s"))).filter("rest > 0")
    t = t.withColumn("slope", (F.col("rest") - F.col("larger")) / F.col("squares").cast("double")).filter(F.col("slope") * F.col("size") <= 1)
    best = F.max(F.struct("size", "slope", "larger"))
    return t.groupBy("_source").agg(best.alias("b")).select("_source", "b.slope", F.col("b.larger").alias("certain"))


def cut_points(numbers: DataFrame, share: float = SHARE, weights=WEIGHTS, most: float = MOST) -> tuple[DataFrame, int]:
    """Per source: whole copies, rest and the rank value below which a document
    is taken once more; and the number of sources."""
    by_size = materialise(numbers.groupBy("_source", "size").agg(F.count("*").alias("n")), "bysize")
    per = materialise(by_size.groupBy("_source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size")), "sources")
    count = per.count()
    s = targets(per, share, weights, most).withColumnRenamed("_source", "_s")
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    s = s.withColumn("whole", F.floor(ratio + 1e-9))
    s = s.withColumn("rest", F.greatest(F.col("target") - F.col("whole") * F.col("source_size"), F.lit(0.0)))
    s = materialise(s, "targets")
    open_ = slopes(by_size.filter("size > 0"), s, count)
    s = s.join(_known(open_, count), F.col("_s").eqNullSafe(F.col("_source")), "left").drop("_source")
    s = s.withColumns({"low": F.lit(-100.0), "high": F.lit(100.0), "under": F.coalesce("certain", F.lit(0)).cast("long")})
    s = materialise(s.drop("certain"), "slopes")
    ranked = with_odds(numbers.filter("size > 0"))
    for _ in range(PASSES):
        step = (F.col("high") - F.col("low")) / BINS
        inside = ranked.join(_known(s, count), F.col("_source").eqNullSafe(F.col("_s"))).filter("rest > 0")
        inside = inside.withColumn("v", _rank_value()).filter((F.col("v") >= F.col("low")) & (F.col("v") < F.col("high")))
        sums = inside.withColumn("bin", F.least(F.floor((F.col("v") - F.col("low")) / step), F.lit(BINS - 1)).cast("int"))
        sums = sums.groupBy("_source", "bin").agg(F.sum("size").alias("n"), F.count("*").alias("docs"))
        run = Window.partitionBy("_source").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
        sums = sums.withColumn("upto", F.sum("n").over(run))
        s2 = sums.join(_known(s.select("_s", "under", "rest"), count), F.col("_source").eqNullSafe(F.col("_s")))
        # bins that fit as a whole are below the cut; the first that does not holds it
        fit = s2.filter(F.col("under") + F.col("upto") <= F.col("rest")).groupBy("_source").agg(F.max("bin").alias("b"), F.max("upto").alias("below"))
        s = s.join(_known(fit, count), F.col("_source").eqNullSafe(F.col("_s")), "left").drop("_source")
        first = s2.filter(F.col("under") + F.col("upto") > F.col("rest")).groupBy("_source").agg(F.min(F.struct("bin", "docs")).alias("first"))
        first = first.select("_source", F.col("first.bin").alias("over"), "first.docs")
        s = s.join(_known(first, count), F.col("_source").eqNullSafe(F.col("_s")), "left").drop("_source")
        step = (F.col("high") - F.col("low")) / BINS
        s = s.withColumns(
            {
                "under": F.col("under") + F.coalesce("below", F.lit(0)),
                # no bin overflows: everything up to the upper end is taken
                "low2": F.when(F.col("over").isNull(), F.col("high")).otherwise(F.col("low") + F.col("over") * step),
                "high2": F.when(F.col("over").isNull(), F.col("high")).otherwise(F.col("low") + (F.col("over") + 1) * step),
            }
        ).drop("below", "b", "over", "low", "high")
        s = materialise(s.withColumnRenamed("low2", "low").withColumnRenamed("high2", "high"), "cuts")
        if (s.agg(F.max("docs")).first()[0] or 0) <= 1:
            break
        s = s.drop("docs")
    # the bin is now a sliver with the document that crosses the target: take it
    # if that comes nearer
    last = ranked.join(_known(s, count), F.col("_source").eqNullSafe(F.col("_s"))).filter("rest > 0")
    last = last.withColumn("v", _rank_value()).filter((F.col("v") >= F.col("low")) & (F.col("v") < F.col("high")))
    last = last.groupBy("_source").agg(F.sum("size").alias("more"))
    s = s.join(_known(last, count), F.col("_source").eqNullSafe(F.col("_s")), "left").drop("_source")
    nearer = F.col("under") + F.col("more") - F.col("rest") < F.col("rest") - F.col("under")
    s = s.withColumn("cut", F.when(nearer, F.col("high")).otherwise(F.col("low")))
    return materialise(s.select("_s", "source_size", "target", "whole", "rest", "slope", "cut"), "cut"), count


def mixed_rows(docs: DataFrame, share: float = SHARE, weights=WEIGHTS, most: float = MOST) -> DataFrame:
    """The mix itself: each document as often as it is taken, columns unchanged.

    The cut points are all that the second pass needs, so no text is shuffled.
    """
    numbers = materialise(sizes(docs), "mixsizes")
    cut, count = cut_points(numbers, share, weights, most)
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")
    counted = with_odds(sizes(docs.select(row, "doc_id", "source", "text"), "_row"))
    out = counted.join(_known(cut, count), F.col("_source").eqNullSafe(F.col("_s")))
    return out.select("_row", F.explode(F.array_repeat(F.lit(1), _copies().cast("int"))).alias("_copy")).select("_row.*")
