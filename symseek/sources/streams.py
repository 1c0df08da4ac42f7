"""Symbol streams and pattern tables.

A stream is a row (stream_id, n, text): n symbols, one code point each. Long streams are cut into blocks
with a halo, so that each start position belongs to exactly one block and sees all symbols it can need.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from symseek.sources.scratch import written

#: Two symbols that no stream or pattern may hold.
FILLER, STOP = "\ue000", "\ue001"
PATTERN_SCHEMA = T.StructType([T.StructField("pattern_id", T.IntegerType()), T.StructField("pattern", T.StringType()), T.StructField("lp", T.IntegerType()), T.StructField("k_max", T.IntegerType())])


def fold_ascii(text: Column) -> Column:
    """Lower case; everything but a-z and space becomes `?`. One symbol per code point, the same in every engine."""
    return F.regexp_replace(F.lower(text), "[^a-z ]", "?")


def fold_printable(text: Column) -> Column:
    """Printable ASCII as it is; everything else becomes `?`."""
    return F.regexp_replace(text, "[^ -~]", "?")


def build_streams(df: DataFrame, stream_id: Column, order_by: Sequence[str], symbol: Column, *, nulls: str = "skip", unique_order: bool = False) -> DataFrame:
    """Rows of one symbol each to streams. The one shuffle is by stream_id; symbols are ordered inside their group.

    nulls: `skip` drops rows without a symbol, `fail` raises. unique_order: raise where two rows of a stream share an order key.
    """
    if nulls not in ("skip", "fail"):
        raise ValueError("nulls is 'skip' or 'fail'")
    rows = df.select(stream_id.cast("long").alias("stream_id"), F.struct(*order_by).alias("at"), symbol.alias("sym"))
    if nulls == "fail":
        rows = rows.withColumn("sym", F.coalesce("sym", F.raise_error(F.lit("a symbol is null")).cast("string")))
    ordered = F.sort_array(F.collect_list(F.struct("at", "sym")))
    out = rows.where(F.col("sym").isNotNull()).groupBy("stream_id").agg(ordered.alias("rows"))
    if unique_order:
        repeated = F.exists(F.zip_with(F.slice("rows", 1, F.size("rows") - 1), F.slice("rows", 2, F.size("rows")), lambda a, b: a["at"] == b["at"]), lambda x: x)
        out = out.withColumn("rows", F.when(F.size("rows").__gt__(1) & repeated, F.raise_error(F.lit("two rows of a stream have the same order key")).cast(out.schema["rows"].dataType)).otherwise(F.col("rows")))
    return out.select("stream_id", F.size("rows").cast("long").alias("n"), F.array_join(F.transform("rows", lambda r: r["sym"]), "").alias("text"))


def build_blocks(df: DataFrame, stream_id: Column, order_by: Sequence[str], symbol: Column, *, block: int, halo: int) -> DataFrame:
    """Rows of one symbol each to blocks: stream_id, block, base, own, text and final (the text reaches the stream's end). For streams of any length: none is ever in one row or task.

    Rows are sorted by range partitioning and packed into pieces of text where they lie; a piece's place follows from the pieces before it in its
    partition and from one number for each stream and partition before. Only pieces are dealt to blocks, those at a border to both.
    halo: lp + K - 1 of the longest pattern, or more. Rows without a symbol are skipped; rows with equal order keys come by symbol.
    """
    if not 0 <= halo <= block:
        raise ValueError("a halo is at most a block")
    keys = [f"__o{i}" for i in range(len(order_by))]
    rows = df.select(stream_id.cast("long").alias("stream_id"), *[F.col(c).alias(k) for c, k in zip(order_by, keys, strict=True)], symbol.alias("sym")).where(F.col("sym").isNotNull())
    dealt = rows.repartitionByRange("stream_id", *keys, "sym").sortWithinPartitions("stream_id", *keys, "sym").select("stream_id", "sym", F.spark_partition_id().alias("part"))

    def pack(batches):
        import numpy as np
        import pyarrow as pa

        stream, within, first = None, 0, True
        for batch in batches:
            ids = batch.column(0).to_pylist()
            symbols, parts = batch.column(1).to_pylist(), batch.column(2)
            cuts = [0, *[i for i in range(1, len(ids)) if ids[i] != ids[i - 1]], len(ids)] if ids else [0]
            out = []
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if first or ids[a] != stream:
                    stream, within, first = ids[a], 0, False
                text = "".join(symbols[a:b])
                out.append((a, within, len(text), text))
                within += len(text)
            if out:
                at, begin, n, text = zip(*out, strict=True)
                taken = pa.array(np.array(at))
                yield pa.RecordBatch.from_arrays([batch.column(0).take(taken), parts.take(taken), pa.array(begin, pa.int64()), pa.array(n, pa.int64()), pa.array(text, pa.string())], names=["stream_id", "part", "within", "n", "text"])

    pieces = written(dealt.mapInArrow(pack, "stream_id long, part int, within long, n long, text string"), "pieces")
    stream, before = Window.partitionBy("stream_id"), Window.partitionBy("stream_id").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    parts = pieces.groupBy("stream_id", "part").agg(F.sum("n").alias("size"))
    parts = parts.select(F.col("stream_id").alias("of"), F.col("part").alias("of_part"), F.coalesce(F.sum("size").over(before), F.lit(0)).alias("before"), F.sum("size").over(stream).alias("total"))
    # <=> so that a null stream_id is a stream like any other
    mine = F.col("stream_id").eqNullSafe(F.col("of")) & (F.col("part") == F.col("of_part"))
    placed = pieces.join(parts, mine).select("stream_id", "total", "n", "text", (F.col("before") + F.col("within")).alias("at"))
    low, high = F.greatest(F.floor((F.col("at") - halo) / block), F.lit(0)), F.floor((F.col("at") + F.col("n") - 1) / block)
    cut = placed.withColumn("block", F.explode(F.sequence(low, high))).withColumn("lo", F.greatest("at", F.col("block") * block))
    hi = F.least(F.col("at") + F.col("n"), (F.col("block") + 1) * block + halo)
    cut = cut.select("stream_id", "block", "total", "lo", F.substr("text", (F.col("lo") - F.col("at") + 1).cast("int"), (hi - F.col("lo")).cast("int")).alias("text"))
    joined = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("lo", "text"))), lambda x: x["text"]), "")
    blocks = cut.groupBy("stream_id", "block").agg(joined.alias("text"), F.first("total").alias("total"))
    base, size = F.col("block") * block, F.char_length("text")
    return blocks.select("stream_id", "block", base.alias("base"), F.least(F.lit(block), size).cast("int").alias("own"), "text", (base + size == F.col("total")).alias("final"))


def text_streams(df: DataFrame, stream_id: Column, text: Column) -> DataFrame:
    """Rows of whole texts as streams; nulls are skipped."""
    return df.select(stream_id.cast("long").alias("stream_id"), text.alias("text")).where(F.col("text").isNotNull()).select("stream_id", F.char_length("text").cast("long").alias("n"), "text")


def checked(streams: DataFrame) -> DataFrame:
    """Raise where a stream holds a reserved symbol."""
    bad = F.col("text").contains(FILLER) | F.col("text").contains(STOP)
    return streams.withColumn("text", F.when(bad, F.raise_error(F.lit("a stream holds a reserved symbol")).cast("string")).otherwise(F.col("text")))


def first_symbols(streams: DataFrame, count: int) -> DataFrame:
    """Each stream's first `count` symbols: the test length of an experiment."""
    return streams.select("stream_id", F.least("n", F.lit(count).cast("long")).alias("n"), F.substring("text", 1, count).alias("text"))


def block_streams(streams: DataFrame, block: int, halo: int, *, side: str = "right") -> DataFrame:
    """stream_id, block, base, own, text: blocks of `block` symbols with `halo` more on one side. `own` symbols belong to the block; `base` is the place of text's first."""
    if block <= 0 or halo < 0:
        raise ValueError("a block has at least one symbol")
    number = F.explode(F.sequence(F.lit(0), F.greatest(F.ceil(F.col("n") / block) - 1, F.lit(0)).cast("int"))).alias("block")
    rows = streams.where("n > 0").select("stream_id", "n", "text", number)
    at = F.col("block").cast("long") * block
    base = at if side == "right" else F.greatest(at - halo, F.lit(0).cast("long"))
    stop = F.least(at + block + (halo if side == "right" else 0), F.col("n"))
    own = F.least(F.lit(block).cast("long"), F.col("n") - at)
    return rows.select("stream_id", "block", base.alias("base"), own.cast("int").alias("own"), F.substr("text", (base + 1).cast("int"), (stop - base).cast("int")).alias("text"))


def slide_windows(streams: DataFrame, width: int) -> DataFrame:
    """A mask of `width` symbols moved by one symbol at a time; cells beyond the end hold fillers."""
    starts = streams.where("n > 0").select("stream_id", "n", "text", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("start"))
    return starts.select("stream_id", "start", F.rpad(F.substr("text", (F.col("start") + 1).cast("int"), F.lit(width)), width, FILLER).alias("win"))


def unpack_streams(streams: DataFrame) -> DataFrame:
    """stream_id, pos, sym: one row per symbol."""
    rows = streams.where("n > 0").select("stream_id", F.posexplode(F.split("text", "")).alias("pos", "sym"))
    return rows.where(F.col("sym") != "").select("stream_id", F.col("pos").cast("long").alias("pos"), "sym")


def pattern_frame(spark: SparkSession, patterns: Sequence[tuple[int, str, int]]) -> DataFrame:
    """Patterns as a table, small enough to be broadcast: (pattern_id, pattern, K)."""
    for _, pattern, k in patterns:
        if not pattern or FILLER in pattern or STOP in pattern:
            raise ValueError("a pattern is empty or holds a reserved symbol")
        if k < 0:
            raise ValueError("a threshold is negative")
    return spark.createDataFrame([(i, p, len(p), k) for i, p, k in patterns], PATTERN_SCHEMA)


def pattern_bank(df: DataFrame, pattern_id: Column, text: Column, length: int, k: int) -> DataFrame:
    """The first `length` symbols of each row as a pattern; shorter texts give none."""
    rows = df.select(pattern_id.cast("int").alias("pattern_id"), F.substring(text, 1, length).alias("pattern"))
    return rows.where(F.char_length("pattern") == length).select("pattern_id", "pattern", F.lit(length).alias("lp"), F.lit(k).alias("k_max"))


#: A pattern table is broadcast up to so many patterns; larger ones are taken in shards.
MOST_PATTERNS = 10_000


def collected(patterns: DataFrame) -> list[tuple[int, str, int]]:
    """The pattern table on the driver, behind a check of its size."""
    rows = patterns.select("pattern_id", "pattern", "k_max").limit(MOST_PATTERNS + 1).collect()
    if len(rows) > MOST_PATTERNS:
        raise ValueError(f"more than {MOST_PATTERNS} patterns: search in shards of the table (pattern_id % s), or by the q-gram index")
    return sorted((r[0], r[1], r[2]) for r in rows)
