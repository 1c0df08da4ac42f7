"""Measures over hits and occurrences."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from symseek.operators.sifter import KEYS


def hit_counts(methods: dict[str, DataFrame]) -> DataFrame:
    """stream_id, pattern_id and one column per method with its number of rows."""
    rows = None
    for name, df in methods.items():
        own = df.select(*KEYS, F.lit(name).alias("method"))
        rows = own if rows is None else rows.unionByName(own)
    names = list(methods)
    return rows.groupBy(*KEYS).pivot("method", names).count().na.fill(0, names)


def coverage(hits: DataFrame, *, block: int = 1 << 20) -> DataFrame:
    """stream_id, pattern_id, pos, n: how many hits cover each position that any covers. From steps (+1 at a start, -1 past an end),
    so the rows between are made from two per hit and not one per hit and position. A hit is cut at the borders of blocks of positions: no task sees a whole stream."""
    last = F.col("start") + F.col("len") - 1
    cut = hits.select(*KEYS, "start", last.alias("last"), F.explode(F.sequence(F.floor(F.col("start") / block), F.floor(last / block))).alias("block"))
    cut = cut.select(*KEYS, "block", F.greatest("start", F.col("block") * block).alias("low"), (F.least("last", (F.col("block") + 1) * block - 1) + 1).alias("high"))
    steps = cut.select(*KEYS, "block", F.inline(F.array(F.struct(F.col("low").alias("pos"), F.lit(1).alias("step")), F.struct(F.col("high").alias("pos"), F.lit(-1).alias("step")))))
    steps = steps.groupBy(*KEYS, "block", "pos").agg(F.sum("step").alias("step"))
    order = Window.partitionBy(*KEYS, "block").orderBy("pos")
    level = steps.withColumn("n", F.sum("step").over(order.rowsBetween(Window.unboundedPreceding, 0))).withColumn("next", F.lead("pos").over(order)).where("n > 0")
    return level.select(*KEYS, F.explode(F.sequence(F.col("pos"), F.col("next") - 1)).alias("pos"), F.col("n").cast("long").alias("n"))


def shadow_ratio(hits: DataFrame, kept: DataFrame) -> DataFrame:
    """pattern_id, hits, kept, ratio: raw hits for one that is kept."""
    raw = hits.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("hits"))
    few = kept.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("kept"))
    return raw.join(few, "pattern_id").select("pattern_id", "hits", "kept", F.round(F.col("hits") / F.col("kept"), 6).alias("ratio"))


def overlap_violations(kept: DataFrame) -> DataFrame:
    """pattern_id, violations: kept occurrences that reach into a later one of their stream."""
    order = Window.partitionBy(*KEYS).orderBy("start", "len")
    reach = F.max(F.col("start") + F.col("len") - 1).over(order.rowsBetween(Window.unboundedPreceding, -1))
    return kept.withColumn("bad", (F.col("start") <= reach).cast("long")).groupBy("pattern_id").agg(F.coalesce(F.sum("bad"), F.lit(0)).alias("violations"))


def delay_bound(lp: Column, level: Column) -> Column:
    """Most symbols between an occurrence's first symbol and its decision, if a group's weakest level is `level`."""
    return lp * (level + 1) + (level * (level - 1) / 2).cast("long")


def decision_delay(kept: DataFrame, patterns: DataFrame) -> DataFrame:
    """Per pattern and level: occurrences, largest and mean delay in symbols, and the largest excess over the bound of the group's weakest kept level."""
    group = Window.partitionBy(*KEYS, "decided_at")
    rows = kept.withColumn("weakest", F.max("dist").over(group)).withColumn("delay", F.col("decided_at") - F.col("start") + 1).join(F.broadcast(patterns.select("pattern_id", "lp")), "pattern_id")
    rows = rows.withColumn("bound", delay_bound(F.col("lp"), F.col("weakest")))
    return rows.groupBy("pattern_id", "dist").agg(
        F.count(F.lit(1)).alias("n"), F.max("delay").alias("max_delay"), F.round(F.avg("delay"), 6).alias("mean_delay"), F.max(F.greatest(F.col("delay") - F.col("bound"), F.lit(0))).alias("excess")
    )


def motif_histogram(kept: DataFrame, patterns: DataFrame) -> DataFrame:
    """stream_id, vector: for streams with any occurrence, how often each pattern occurs, by pattern_id."""
    counts = kept.groupBy("stream_id", "pattern_id").agg(F.count(F.lit(1)).alias("n"))
    found = counts.groupBy("stream_id").agg(F.map_from_entries(F.collect_list(F.struct("pattern_id", "n"))).alias("of"))
    ids = patterns.agg(F.sort_array(F.collect_list("pattern_id")).alias("ids"))
    return found.join(F.broadcast(ids), how="cross").select("stream_id", F.transform("ids", lambda i: F.coalesce(F.try_element_at("of", i), F.lit(0)).cast("long")).alias("vector"))


def pack_result(start: Column, length: Column, dist: Column) -> Column:
    """A result as one number: 16 bits of start, 3 of distance, 5 of length, as the test rig's records; larger starts use the bits above. A length over 31 or a distance over 7 raises."""
    fits = length.between(0, 31) & dist.between(0, 7) & (start >= 0)
    packed = F.shiftleft(start.cast("long"), 8).bitwiseOR(F.shiftleft(dist.cast("long"), 5)).bitwiseOR(length.cast("long"))
    return F.when(fits, packed).otherwise(F.raise_error(F.lit("a result doesn't fit a packed record: at most 31 symbols and distance 7")).cast("long"))


def unpack_result(packed: Column) -> Column:
    return F.struct(F.shiftright(packed, 8).alias("start"), packed.bitwiseAND(31).cast("int").alias("len"), F.shiftright(packed, 5).bitwiseAND(7).cast("int").alias("dist"))
