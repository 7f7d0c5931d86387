"""Sharding by vector bin packing: bytes, words and rows balanced together.

Equal texts form a group. Heavy groups, of which there are at most ``bins * SPLIT``,
are items of their own; light ones hash into a fixed number of cells, which are
items too, so the driver sees a table whose size does not depend on the input. Items
are placed in order of falling weight, each into the shard where the dot product of
its (bytes, words, rows) vector with what the shard still has room for is highest.
Of the shards only those are asked that have room for the item in all three; if none
has, those with room for its bytes. Single moves of items then level the shards.

A group goes to one shard as long as any shard has room for it, or lacks less than
``1/SPLIT`` of a shard. Only a group that is larger than what every shard has left is
dealt out, by document, into ``PARTS`` parts; these fill one shard after the other.

Law: ``bytes``. The sizes of the shards are near equal.

Defined results: a null text has size 1 and the checksum of an empty text;
repeated rows are placed each, and rows that agree in id and text share a part; null
ids hash like any value; an empty table gives an empty result; clashing extra columns
do not matter, as only doc_id and text are read.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import count_words, materialise

CELLS = 2048
#: Parts that a group is dealt into if no shard can take it whole.
PARTS = 512
#: A group above this part of a shard's bytes is an item of its own.
SPLIT = 128
SLOT_PARTS = 64
#: Weight of bytes, words and rows where shards are levelled; the law is on bytes, so
#: that words and rows decide among placements of nearly equal bytes.
WEIGHTS = (400.0, 1.0, 1.0)
MOVES = 4000


def digest(docs: DataFrame) -> DataFrame:
    """What packing needs of each document; the texts are read once, here."""
    body = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(
        "doc_id",
        (F.octet_length(body) + 1).cast("long").alias("size"),
        count_words(body).alias("n_words"),
        F.crc32(F.encode(body, "utf-8")).alias("text_crc32"),
        F.xxhash64(body).alias("_group"),
    )


def place(weights: np.ndarray, left: np.ndarray) -> np.ndarray:
    """Shard of each item (rows of ``weights``), -1 where no shard has room for its
    bytes; ``left``, what each shard has room for, is updated."""
    out = np.full(len(weights), -1, np.int32)
    # light items last, so that they level what heavy ones leave
    for i in np.lexsort((np.arange(len(weights)), -weights.sum(axis=1), -weights[:, 0])):
        v = weights[i]
        fits = (left >= v).all(axis=1)
        fits = fits if fits.any() else left[:, 0] >= v[0]
        if fits.any():
            out[i] = int(np.argmax(np.where(fits, left @ v, -np.inf)))
        elif (left[:, 0] + 1 / SPLIT).max() >= v[0]:
            out[i] = int(np.argmax(left[:, 0]))
        else:
            continue
        left[out[i]] -= v
    return out


def level(weights: np.ndarray, where: np.ndarray, left: np.ndarray, moves: int = MOVES) -> None:
    """Move single items, best move first, while that brings what the shards have
    left nearer to nothing; ``where`` and ``left`` are updated."""
    scale = np.sqrt(np.array(WEIGHTS))
    v, room = weights * scale, left * scale
    square = (v**2).sum(axis=1)
    for _ in range(moves if len(v) else 0):
        # change of the sum of squares of room when item i goes to shard b
        gain = 2 * ((v * room[where]).sum(axis=1)[:, None] - v @ room.T + square[:, None])
        gain[np.arange(len(v)), where] = 0
        i, b = np.unravel_index(int(gain.argmin()), gain.shape)
        if gain[i, b] > -1e-15:
            break
        room[where[i]] += v[i]
        room[b] -= v[i]
        where[i] = b
    left[:] = room / scale


def deal(parts: np.ndarray, left: np.ndarray) -> np.ndarray:
    """Shards of the parts of one group: the shard of highest dot product is filled
    as far as it has room, then the next; ``left`` is updated."""
    out, at = np.zeros(len(parts), np.int32), -1
    for i, v in enumerate(parts):
        if at < 0 or left[at, 0] < v[0]:
            room = left[:, 0] >= v[0]
            at = int(np.argmax(np.where(room, left @ v, -np.inf) if room.any() else left[:, 0]))
        out[i] = at
        left[at] -= v
    return out


def plan(numbers: DataFrame, bins: int) -> tuple[DataFrame, DataFrame]:
    """``numbers`` with the cell of each document, and the shard of each (cell,
    part). A heavy group's cell is its own, beyond those of the light ones."""
    spark = numbers.sparkSession
    sums = [F.sum("size").cast("double").alias("b"), F.sum("n_words").cast("double").alias("w"), F.count("*").cast("double").alias("r")]
    three = lambda rows: np.array([[x["b"], x["w"], x["r"]] for x in rows], float).reshape(-1, 3)
    groups = materialise(numbers.groupBy("_group").agg(*sums), "groups")
    total = groups.agg(*[F.coalesce(F.sum(c), F.lit(0.0)).alias(c) for c in ("b", "w", "r")]).first()
    unit = bins / np.maximum(np.array(list(total)), 1.0)
    limit = total["b"] / bins / SPLIT
    heavy = sorted(groups.filter(F.col("b") > limit).collect(), key=lambda x: x["_group"])
    own = spark.createDataFrame([(x["_group"], CELLS + i) for i, x in enumerate(heavy)], "_group long, own int")
    cell = F.coalesce("own", F.pmod("_group", F.lit(CELLS)).cast("int")).alias("cell")
    light = sorted(groups.filter(F.col("b") <= limit).groupBy(F.pmod("_group", F.lit(CELLS)).cast("int").alias("cell")).agg(*[F.sum(c).alias(c) for c in "bwr"]).collect())
    left = np.ones((bins, 3))
    weights = three(heavy) * unit
    where = place(weights, left)
    # groups that no shard has room for: at most bins * SPLIT * PARTS rows
    split = np.flatnonzero(where < 0).tolist()
    keyed = numbers.join(F.broadcast(own), "_group", "left")
    keyed = keyed.withColumn("cell", cell).drop("own")
    dealt = F.col("cell").isin([CELLS + i for i in split])
    keyed = keyed.withColumn("part", F.when(dealt, F.pmod(F.xxhash64("doc_id", "_group"), F.lit(PARTS)).cast("int")).otherwise(F.lit(-1)))
    rows: list[tuple[int, int, int]] = []
    parts = sorted(keyed.filter("part >= 0").groupBy("cell", "part").agg(*sums).collect()) if split else []
    for c in sorted({x["cell"] for x in parts}):
        mine = [x for x in parts if x["cell"] == c]
        rows += [(c, x["part"], int(s)) for x, s in zip(mine, deal(three(mine) * unit, left), strict=True)]
    cells = three(light) * unit
    small = place(cells, left)
    for i in np.flatnonzero(small < 0):  # a cell is never dealt
        small[i] = int(np.argmax(left[:, 0]))
        left[small[i]] -= cells[i]
    whole = np.flatnonzero(where >= 0)
    names = [CELLS + int(i) for i in whole] + [x["cell"] for x in light]
    both = np.concatenate([where[whole], small])
    level(np.concatenate([weights[whole], cells]), both, left)
    rows += [(c, -1, int(s)) for c, s in zip(names, both, strict=True)]
    return keyed, spark.createDataFrame(rows, "cell int, part int, shard int")


def shard(docs: DataFrame, bins: int = 8) -> DataFrame:
    """doc_id, size, n_words, text_crc32, law, shard, slot, grown_shard."""
    numbers = materialise(digest(docs), "sizes")
    keyed, where = plan(numbers, bins)
    # at most CELLS + bins * SPLIT * PARTS rows, whatever the input
    placed = keyed.join(F.broadcast(where), ["cell", "part"])
    # slots: rank within a slice of the shard, after the slices before it
    placed = placed.withColumn("slice", F.pmod(F.xxhash64("doc_id", "_group", F.lit(7)), F.lit(SLOT_PARTS)).cast("int"))
    counts = placed.groupBy("shard", "slice").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select("shard", "slice", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    rank = F.row_number().over(Window.partitionBy("shard", "slice").orderBy("doc_id", "_group"))
    out = placed.withColumn("rank", rank).join(F.broadcast(starts), ["shard", "slice"])
    return out.select(
        "doc_id", "size", "n_words", "text_crc32", F.lit("bytes").alias("law"), "shard",
        (F.col("start") + F.col("rank") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
    )
