"""Baselines to compare the sifter with: free-start search, and offline filters of complete hit lists."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from symseek.functions import kernels
from symseek.functions.distance import free_start_row
from symseek.operators.hits import BLOCK, find_hits
from symseek.operators.sifter import KEYS, split_islands
from symseek.sources.scratch import written
from symseek.sources.streams import block_streams, collected

END_SCHEMA = "stream_id long, pattern_id int, end long, dist int"


def free_start_ends(streams: DataFrame, patterns: DataFrame, *, kernel: str = "columns", block: int = BLOCK) -> DataFrame:
    """End positions of hits with the least distance of any run that ends there.

    kernel: `native` (built-in functions), or over blocks with a left warm-up of lp + K symbols, on which a value within
    the threshold depends at most: `columns`, `bits` (two machine words per column) or `automaton` (a word per number of edits).
    """
    if kernel == "native":
        pairs = streams.where("n > 0").join(F.broadcast(patterns), how="cross")
        ends = pairs.select("stream_id", "pattern_id", "k_max", F.posexplode(free_start_row(F.col("pattern"), F.col("text"))).alias("end", "dist"))
        return ends.where("dist <= k_max").select("stream_id", "pattern_id", F.col("end").cast("long").alias("end"), F.col("dist").cast("int").alias("dist"))
    rows = {"columns": lambda p, c, k: kernels.free_start_row(p, c), "bits": lambda p, c, k: kernels.bit_parallel_row(p, c), "automaton": kernels.automaton_row}[kernel]
    bank = [(i, kernels.encode(p), k) for i, p, k in collected(patterns)]
    warm = max((len(p) + k for _, p, k in bank), default=0)

    def ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(4).to_pylist()
            order = np.argsort([len(t) for t in texts], kind="stable")
            for at in range(0, len(order), 256):
                part = order[at : at + 256]
                width = max(len(texts[i]) for i in part)
                if not width:
                    continue
                codes = np.full((len(part), width), kernels.GAP, np.uint32)
                for r, i in enumerate(part):
                    codes[r, : len(texts[i])] = kernels.encode(texts[i])
                taken = batch.take(pa.array(part))
                base, own, block_no = (taken.column(c).to_numpy() for c in (2, 3, 1))
                size = np.array([len(texts[i]) for i in part])
                first = block_no.astype(np.int64) * block - base  # owned symbols begin behind the warm-up
                for pattern_id, pattern, k in bank:
                    dist = rows(pattern, codes, k)
                    r, m = np.nonzero(dist <= k)
                    good = (m >= first[r]) & (m < first[r] + own[r]) & (m < size[r])
                    r, m = r[good], m[good]
                    yield pa.RecordBatch.from_arrays(
                        [taken.column(0).take(pa.array(r)), pa.array(np.full(len(r), pattern_id, np.int32)), pa.array(base[r] + m), pa.array(dist[r, m].astype(np.int32))], names=["stream_id", "pattern_id", "end", "dist"]
                    )

    return block_streams(streams, block, warm, side="left").select("stream_id", "block", "base", "own", "text").mapInArrow(ends, END_SCHEMA)


def free_start_intervals(ends: DataFrame, hits: DataFrame) -> DataFrame:
    """An interval for each end: the run with the least distance that ends there, the shortest of several."""
    runs = hits.withColumn("end", F.col("start") + F.col("len") - 1)
    best = Window.partitionBy(*KEYS, "end").orderBy("dist", "len")
    met = ends.select(*KEYS, "end").join(runs, [*KEYS, "end"]).withColumn("__nth", F.row_number().over(best)).where(F.col("__nth") == 1)
    return met.select(*KEYS, "start", "len", "dist")


def offline_filter(hits: DataFrame, policy: str) -> DataFrame:
    """Filter a complete list of hits. `island_best`: of each island the least distance, then the earliest, then the shortest.
    `greedy`: again and again the best of what is left, dropping what it overlaps. `max_disjoint`: as many disjoint hits as possible."""
    islands = split_islands(written(hits, "hits"))
    if policy == "island_best":
        best = Window.partitionBy(*KEYS, "island").orderBy("dist", "start", "len")
        return islands.withColumn("__nth", F.row_number().over(best)).where(F.col("__nth") == 1).select(*KEYS, "start", "len", "dist")
    span = lambda h: h["start"] + h["len"] - 1
    if policy == "greedy":
        order = F.struct("dist", "start", "len")
        clear = lambda kept, h: ~F.exists(kept, lambda x: (x["start"] <= span(h)) & (h["start"] <= span(x)))
    elif policy == "max_disjoint":
        order = F.struct((F.col("start") + F.col("len") - 1).alias("end"), F.col("start"), F.col("len"), F.col("dist"))
        clear = lambda kept, h: F.coalesce(span(F.try_element_at(kept, F.lit(-1))) < h["start"], F.lit(True))
    else:
        raise ValueError("policy is 'island_best', 'greedy' or 'max_disjoint'")
    arrays = islands.groupBy(*KEYS, "island").agg(F.sort_array(F.collect_list(order)).alias("hits"))

    def take(kept: Column, h: Column) -> Column:
        return F.when(clear(kept, h), F.concat(kept, F.array(F.struct(h["start"].alias("start"), h["len"].alias("len"), h["dist"].alias("dist"))))).otherwise(kept)

    none = F.array().cast("array<struct<start:bigint,len:int,dist:int>>")
    return arrays.select(*KEYS, F.inline(F.aggregate("hits", none, take)))


def baseline_counts(streams: DataFrame, patterns: DataFrame) -> DataFrame:
    """Hits of the free-start baseline with the runs that they stand for."""
    return free_start_intervals(free_start_ends(streams, patterns), find_hits(streams, patterns))
