"""Weighted rendezvous sharding of stable record keys, in built-in functions only.

Each shard draws a score for a key from the key and the shard's number alone; the largest score wins.
With w the shard's weight and u the draw in (0, 1), the score is -w / ln(u), so a shard gets keys in
proportion to its weight, and a further shard can only take keys to itself. The draw is the first 52 bits
of an MD5 digest, which any SQL engine can repeat.

Defined results: a null key is a key of its own (the text `null`); rows with equal keys share a shard;
a null text counts as empty; an empty table gives an empty result; extra columns are kept out of the result.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Groups per shard for the gapless numbering. 8 shards x 4096 groups are 32,768 rows of a broadcast table;
#: at 10**12 rows a group has some 30 million narrow rows, which a sort can spill.
SLOT_GROUPS = 4096
_SPAN = float(1 << 52)


def shard_of(key: Column, weights: Sequence[float]) -> Column:
    """The winning shard's number for each key."""
    if not weights or min(weights) <= 0:
        raise ValueError("every shard needs a positive weight")
    text = F.coalesce(key.cast("string"), F.lit("null"))

    def score(shard: int, weight: float) -> Column:
        digest = F.md5(F.concat(text, F.lit(f":{shard}")).cast("binary"))
        draw = (F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") + 0.5) / F.lit(_SPAN)
        return F.struct((F.lit(-float(weight)) / F.log(draw)).alias("score"), F.lit(shard).alias("shard"))

    return F.array_max(F.array(*[score(s, w) for s, w in enumerate(weights)]))["shard"]


def assign_shards(df: DataFrame, weights: Sequence[float], *, key: str = "doc_id", text: str = "text", groups: int = SLOT_GROUPS) -> DataFrame:
    """key, size, text_crc32, shard, grown_shard and slot (0, 1, ... in each shard).

    A slot is the row's rank in its group plus the rows of the shard's earlier groups. The group sizes are at
    most len(weights) x groups rows, whatever the table's size, so that side is broadcast; no window sees a whole shard.
    """
    group = (F.conv(F.substring(F.md5(F.concat(F.coalesce(F.col("k").cast("string"), F.lit("null")), F.lit(":g")).cast("binary")), 1, 8), 16, 10).cast("long") % F.lit(groups)).cast("int")
    body = F.coalesce(F.col(text), F.lit("")).cast("binary")
    rows = df.select(F.col(key).alias("k"), F.octet_length(body).cast("long").alias("bytes"), F.crc32(body).alias("text_crc32"))
    rows = rows.select("*", shard_of(F.col("k"), weights).alias("shard"), shard_of(F.col("k"), [*weights, max(weights)]).alias("grown_shard"), group.alias("g"))
    sizes = df.select(F.col(key).alias("k")).select(shard_of(F.col("k"), weights).alias("shard"), group.alias("g")).groupBy("shard", "g").agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("shard").orderBy("g").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select("shard", "g", before.alias("base"))
    rank = F.row_number().over(Window.partitionBy("shard", "g").orderBy("k", "text_crc32", "bytes"))
    return (
        rows.withColumn("rank", rank)
        .join(F.broadcast(offsets), ["shard", "g"])
        .select(F.col("k").alias(key), (F.col("bytes") + 1).alias("size"), "text_crc32", "shard", (F.col("base") + F.col("rank") - 1).alias("slot"), "grown_shard")
    )
