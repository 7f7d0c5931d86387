"""Quality rules: a table of thresholds compiled into one Spark projection.

Every metric is a built-in expression over the whole text, so the rules run in
a single narrow stage: no shuffle, no Python, nothing kept between rows.

Defined results: a null text counts as an empty one; an empty or blank text has
no words, fails the base rule and is not kept; repeated rows and ties are judged
row by row; an empty table gives an empty result; further columns of the input
are left alone, and clashing names are overwritten only in the result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANKS, words

SYMBOLS = "#*$%&|<>"
SHOUT = "!"
#: Frequent function words of the four languages, in lower case.
STOP_WORDS = (
    "the of and to in is that it for was on as with be by at this are from or an have not "
    "der die das und ist nicht ein eine zu den von mit sich des dem im für auf "
    "le la les de des et un une est que pour dans en du par sur au "
    "el los las y una con su del se al como lo"
).split()


@dataclass(frozen=True)
class Rule:
    """``metric`` must lie within [low, high]; None leaves a side open."""

    name: str
    metric: str
    low: float | None = None
    high: float | None = None


#: Shares are per word, per character or per line as the metric's name says.
RULES = (
    Rule("too many symbols", "symbols_per_word", high=0.3),
    Rule("too much shouting", "shouts_per_word", high=0.3),
    Rule("mostly capitals", "capitals_per_char", high=0.5),
    Rule("words too short", "chars_per_word", low=2.0),
    Rule("words too long", "chars_per_word", high=20.0),
    Rule("no function words", "distinct_stops", low=1.0),
    Rule("lines repeat", "dup_lines_per_line", high=0.6),
)

BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
METRICS = ("chars_per_word", "symbols_per_word", "shouts_per_word", "capitals_per_char", "distinct_stops", "dup_lines_per_line")
COMPUTED = (*BASE, *METRICS, "broken", "base_failed", "kept")


def _count_of(text: Column, chars: str) -> Column:
    return F.length(text) - F.length(F.translate(text, chars, ""))


def measures(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with the base counts and the metrics that rules may name."""
    body = F.coalesce(F.col(text), F.lit(""))
    out = docs.withColumn("_body", body).withColumn("_words", words(F.col("_body")))
    w, n = F.col("_words"), F.size("_words").cast("long")
    gram = F.transform(
        F.slice(w, 1, F.greatest(F.size(w) - 2, F.lit(0))),
        lambda x, i: F.struct(F.xxhash64(x, F.get(w, i + 1), F.get(w, i + 2)).alias("h"), i.alias("at")),
    )
    out = out.withColumn("_grams", F.sort_array(gram))
    g = F.col("_grams")
    twice = F.transform(
        F.filter(
            g,
            lambda x, i: F.coalesce(F.get(g, i - 1)["h"] == x["h"], F.lit(False))
            | F.coalesce(F.get(g, i + 1)["h"] == x["h"], F.lit(False)),
        ),
        lambda x: x["at"],
    )
    lines = F.filter(F.split("_body", "\n", -1), lambda x: F.trim(x, F.lit(BLANKS)) != "")
    out = out.withColumn("_twice", F.sort_array(twice)).withColumn("_lines", lines)
    covered = F.aggregate(
        "_twice",
        F.struct(F.lit(0).alias("n"), F.lit(-3).alias("last")),
        lambda a, x: F.struct((a["n"] + F.least(F.lit(3), x - a["last"])).alias("n"), x.alias("last")),
        lambda a: a["n"].cast("long"),
    )
    chars = F.length("_body").cast("long")
    out = out.withColumns(
        {
            "n_words": n,
            "word_chars": F.length(F.translate("_body", BLANKS, "")).cast("long"),
            "n_symbols": _count_of(F.col("_body"), SYMBOLS).cast("long"),
            "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
            "n_repeat_words": covered,
        }
    )
    per = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))
    stops = F.array(*[F.lit(x) for x in dict.fromkeys(STOP_WORDS)])
    return out.withColumns(
        {
            "chars_per_word": per(F.col("word_chars"), n),
            "symbols_per_word": per(F.col("n_symbols"), n),
            "shouts_per_word": per(_count_of(F.col("_body"), SHOUT), n),
            "capitals_per_char": per(_count_of(F.col("_body"), "ABCDEFGHIJKLMNOPQRSTUVWXYZ"), chars),
            "distinct_stops": F.size(F.array_intersect(w, stops)).cast("double"),
            "dup_lines_per_line": per(F.col("n_dup_lines"), F.size("_lines")),
        }
    )


def base_failed(n_words: Column, n_repeat_words: Column) -> Column:
    """Too short, or more than half of the words stand in repeated windows."""
    return (n_words < 50) | (100 * n_repeat_words > 50 * n_words)


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text: str = "text") -> DataFrame:
    """``docs`` with base counts, ``base_failed``, ``broken`` (names) and ``kept``."""
    out = measures(docs, text)
    names = []
    for r in rules:
        bad = F.lit(False)
        if r.low is not None:
            bad = bad | (F.col(r.metric) < r.low)
        if r.high is not None:
            bad = bad | (F.col(r.metric) > r.high)
        names.append(F.when(bad, F.lit(r.name)))
    out = out.withColumn("broken", F.array_compact(F.array(*names)) if names else F.array().cast("array<string>"))
    out = out.withColumn("base_failed", base_failed(F.col("n_words"), F.col("n_repeat_words")))
    out = out.withColumn("kept", ~F.col("base_failed") & (F.size("broken") == 0))
    own = [c for c in docs.columns if c not in COMPUTED]
    # a filter on the result would be pushed below the projections, and so put
    # the splitting of a text inside the functions that run for each of its
    # words; nothing is pushed below a generator that makes the columns
    made = F.explode_outer(F.array(F.struct(*COMPUTED))).alias("_made")
    return out.select(*[F.col(f"`{c}`") for c in own], made).select(*[F.col(f"`{c}`") for c in own], "_made.*")


def keep(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The documents that pass, with the columns they came with."""
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")
    return judge(docs.select(row, F.col("text")), rules).filter("kept").select("_row.*")
