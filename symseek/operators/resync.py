"""The fold of giant islands, in blocks of positions that repair each other.

With a short pattern and a large threshold a whole stream is one island. Every block is folded from an empty state first; then only blocks whose
true state at entry differs from the one assumed are folded again, until none differs. As the state empties each time
a group closes, a block's state at its end rarely depends on how it began, so a round or two repair all blocks; in the worst case a change
travels on by one block a round.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from symseek.operators.fold import KEYS, Rules, SerialSifter
from symseek.sources.scratch import written

EMPTY = "[-1, []]"


def _fold_blocks(rows: DataFrame, levels: int, rules: Rules) -> DataFrame:
    """For each block, given hits and its `entry` state: occurrences (state null), and one row with its state at the end. The last block of a stream closes its group."""

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, sifter, final, entry = None, SerialSifter(levels, rules), False, EMPTY
        out: list[tuple] = []

        def end() -> None:
            if key is not None:
                if final:
                    out.extend((*key, *o, entry, None) for o in sifter.close())
                state = json.dumps([sifter.leader, [list(s) if s else None for s in sifter.slots] if sifter.leader >= 0 else []])
                out.append((*key, None, None, None, None, entry, state))

        def ready() -> pa.RecordBatch:
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.string())
            names = ["stream_id", "pattern_id", "block", "start", "len", "dist", "decided_at", "entry", "state"]
            batch = pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], k) for i, k in enumerate(kinds)], names=names)
            out.clear()
            return batch

        for batch in batches:
            for stream, pattern, block, start, length, dist, given, last in zip(*[batch.column(i).to_pylist() for i in range(8)], strict=True):
                if (stream, pattern, block) != key:
                    end()
                    key, final, entry = (stream, pattern, block), last, given
                    leader, slots = json.loads(given)
                    sifter = SerialSifter(levels, rules, leader, [tuple(s) if s else None for s in slots])
                out.extend((*key, *o, entry, None) for o in sifter.add(start, length, dist))
            if len(out) > 10_000:
                yield ready()
        end()
        yield ready()

    columns = [*KEYS, "block", "start", "len", "dist", "entry", "final"]
    dealt = rows.select(*columns).repartition(*KEYS, "block").sortWithinPartitions(*KEYS, "block", "start", "len")
    return dealt.mapInArrow(fold, "stream_id long, pattern_id int, block long, start long, len int, dist int, decided_at long, entry string, state string")


def resync_fold(hits: DataFrame, levels: int, *, width: int = 1 << 16, tie: str = "earliest", validation: str = "accumulated", strict: bool = True) -> DataFrame:
    """The occurrences among some hits, as sift_hits gives them without group numbers; no task holds or waits for a whole stream.

    Each round writes the blocks that it folds and nothing else; a block's last round counts.
    """
    rules = Rules(tie, validation, strict)
    by_block = [*KEYS, "block"]
    order = Window.partitionBy(*KEYS).orderBy("block")
    rows = written(hits.select(*KEYS, "start", "len", "dist", F.floor(F.col("start") / width).alias("block")), "resync-hits")
    final = rows.select(*by_block).distinct().withColumn("final", F.lead("block").over(order).isNull())
    rounds = [written(_fold_blocks(rows.join(final, by_block).withColumn("entry", F.lit(EMPTY)), levels, rules), "resync-round")]
    while True:
        every = reduce(DataFrame.unionByName, [r.withColumn("round", F.lit(i)) for i, r in enumerate(rounds)])
        states = every.where("state is not null").groupBy(*by_block).agg(F.max_by(F.struct("entry", "state", "round"), "round").alias("now"))
        due = states.select(*by_block, "now.entry", F.coalesce(F.lag("now.state").over(order), F.lit(EMPTY)).alias("true_entry"))
        wrong = written(due.where("entry <> true_entry").select(*by_block, F.col("true_entry").alias("entry")), "resync-wrong")
        if wrong.isEmpty():
            latest = states.select(*by_block, F.col("now.round").alias("round"))
            return every.where("state is null").join(latest, [*by_block, "round"], "left_semi").select(*KEYS, "start", "len", "dist", "decided_at")
        rounds.append(written(_fold_blocks(rows.join(final, by_block).join(wrong, by_block), levels, rules), "resync-round"))
