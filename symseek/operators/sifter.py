"""The online sifter: which hits are kept when they overlap.

Reading starts in order, a hit that is strictly better than the pending leader becomes the leader, and the older ones wait in
one slot per level. When the leader's last symbol has gone by, its group closes: the leader is kept, then each weaker slot, from
better to worse, if it doesn't reach into what is kept. Then the state is empty again.

Hits fall into islands, maximal runs of overlapping hits. At an island's border the state is empty, so islands are
folded independently of each other. Detection runs once: islands that lie inside a block of the stream are folded in the pass that finds
them, and what it gives, occurrences and the hits at the blocks' edges, is written before it forks. An edge hit's island comes from running maxima in two levels
(inside blocks of positions, then over one row per block), and an island of very many hits is folded in blocks that repair each other. No task sees a whole stream.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from symseek.functions import kernels
from symseek.operators.fold import KEYS, TIES, VALIDATIONS, Rules, SerialSifter, fold_islands  # noqa: F401
from symseek.operators.hits import BLOCK, _kernel_arrays, blocks_of, find_hits
from symseek.operators.resync import resync_fold
from symseek.sources.scratch import written
from symseek.sources.streams import collected

OCCURRENCE = "struct<start:bigint,len:int,dist:int,decided_at:bigint>"
KEPT_SCHEMA = "stream_id long, pattern_id int, start long, len int, dist int, decided_at long"
#: Positions of a block in the two-level running maximum.
ISLAND_BLOCK = 1 << 20
#: Islands over so many hits are folded in blocks that repair each other.
GIANT = 1 << 20


def rule_better(leader: Column, hit: Column) -> Column:
    """A hit that overlaps the leader takes its place only with a smaller distance."""
    return hit < leader


def _island_starts(hits: DataFrame, block: int) -> DataFrame:
    """hits with `__block`, `__local` (the first start of the hit's island as its block sees it) and `island` (the first start of its island)."""
    last = F.col("start") + F.col("len") - 1
    rows = hits.withColumn("__block", F.floor(F.col("start") / block)).withColumn("__end", last)
    inside = Window.partitionBy(*KEYS, "__block").orderBy("start", "len")
    reach = F.max("__end").over(inside.rowsBetween(Window.unboundedPreceding, -1))
    begins = F.when(F.col("start") > F.coalesce("__reach", F.lit(-1)), F.col("start"))
    rows = rows.withColumn("__reach", reach).withColumn("__local", F.max(begins).over(inside.rowsBetween(Window.unboundedPreceding, 0)))
    # One row per block with hits. The last island of a block ends last, as it begins behind all ends before.
    over = Window.partitionBy(*KEYS).orderBy("__block").rowsBetween(Window.unboundedPreceding, -1)
    blocks = rows.groupBy(*KEYS, "__block").agg(F.max("__end").alias("__top"), F.max("__local").alias("__latest"))
    blocks = blocks.withColumn("__carry", F.coalesce(F.max("__top").over(over), F.lit(-1)))
    own = F.when(F.col("__latest") > F.col("__carry"), F.col("__latest"))
    blocks = blocks.withColumn("__from", F.last(own, ignorenulls=True).over(over)).drop("__top", "__latest")
    joined = rows.join(blocks, [*KEYS, "__block"])
    island = F.when(F.col("__local") > F.col("__carry"), F.col("__local")).otherwise(F.col("__from"))
    return joined.select(*hits.columns, "__block", island.alias("island"))


def split_islands(hits: DataFrame, *, block: int = ISLAND_BLOCK) -> DataFrame:
    """hits with `island`, numbered from 0 in each stream and pattern. hits are read several times: a written table, or cheap to make."""
    rows = _island_starts(hits, block)
    inside = Window.partitionBy(*KEYS, "__block").orderBy("island")
    over = Window.partitionBy(*KEYS).orderBy("__block").rowsBetween(Window.unboundedPreceding, -1)
    # A block counts the islands that begin in it.
    begun = F.countDistinct(F.when(F.floor(F.col("island") / block) == F.col("__block"), F.col("island")))
    counts = rows.groupBy(*KEYS, "__block").agg(begun.alias("__n")).withColumn("__before", F.coalesce(F.sum("__n").over(over), F.lit(0))).drop("__n")
    old = F.max((F.floor(F.col("island") / block) != F.col("__block")).cast("long")).over(inside.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    ranked = rows.withColumn("__nth", F.dense_rank().over(inside) - old)
    return ranked.join(counts, [*KEYS, "__block"]).select(*hits.columns, (F.col("__before") + F.col("__nth") - 1).cast("long").alias("island"))


def islands_by_window(hits: DataFrame) -> DataFrame:
    """The same islands by one window per stream and pattern: the plain plan, for streams of moderate length."""
    order = Window.partitionBy(*KEYS).orderBy("start", "len")
    reach = F.max(F.col("start") + F.col("len") - 1).over(order.rowsBetween(Window.unboundedPreceding, -1))
    rows = hits.withColumn("__fresh", (F.col("start") > F.coalesce(reach, F.lit(-1))).cast("long"))
    return rows.select(*hits.columns, (F.sum("__fresh").over(order.rowsBetween(Window.unboundedPreceding, 0)) - 1).cast("long").alias("island"))


# The fold over an island's hits, in column expressions. State: leader (level, -1 if none), slots (by level), out (kept so far).


def _reaches(rules: Rules, counter: Column, length: Column, end: Column, kept: Column) -> Column:
    """Whether a weaker slot stays clear of what has been kept."""
    if rules.validation == "interval":
        return (end < kept["low"] - 1) if rules.strict else (end < kept["low"])
    room = counter - (kept["total"] if rules.validation == "accumulated" else kept["last"])
    return (room > length) if rules.strict else (room >= length)


def _close(state: Column, levels: int, rules: Rules) -> Column:
    """What a group keeps: its leader, then weaker slots by level."""
    leader = state["slots"][state["leader"]]
    last = leader["start"] + leader["len"] - 1
    start = F.struct(leader["len"].cast("long").alias("total"), leader["len"].cast("long").alias("last"), leader["start"].alias("low"), F.array(_kept(leader, state["leader"], last)).alias("rows"))

    def weigh(kept: Column, level: Column) -> Column:
        slot = state["slots"][level]
        length, begin = slot["len"], slot["start"]
        counter = last - begin + 1
        good = (level > state["leader"]) & slot.isNotNull() & _reaches(rules, counter, length, begin + length - 1, kept)
        more = F.struct((kept["total"] + length).alias("total"), length.cast("long").alias("last"), F.least(kept["low"], begin).alias("low"), F.concat(kept["rows"], F.array(_kept(slot, level, last))).alias("rows"))
        return F.when(good, more).otherwise(kept)

    return F.aggregate(F.sequence(F.lit(0), F.lit(levels - 1)), start, weigh, lambda kept: kept["rows"])


def _kept(slot: Column, level: Column, last: Column) -> Column:
    return F.struct(slot["start"].alias("start"), slot["len"].alias("len"), level.cast("int").alias("dist"), last.alias("decided_at"))


def _wins_tie(rules: Rules, hit: Column, slot: Column) -> Column:
    if rules.tie == "earliest":  # hits come by start, then length: the first stays
        return F.lit(False)
    return (hit["len"] < slot["len"]) if rules.tie == "shortest" else F.lit(True)


def step_hit(state: Column, hit: Column, levels: int, rules: Rules) -> Column:
    """The state after one more hit."""
    empty = F.transform(F.sequence(F.lit(0), F.lit(levels - 1)), lambda _: F.lit(None).cast("struct<start:bigint,len:int>"))
    leader = state["slots"][state["leader"]]
    closes = (state["leader"] >= 0) & (hit["start"] > leader["start"] + leader["len"] - 1)
    none = (state["leader"] < 0) | closes
    takes = none | rule_better(state["leader"], hit["dist"]) | ((hit["dist"] == state["leader"]) & _wins_tie(rules, hit, leader))
    slots = F.when(closes, empty).otherwise(state["slots"])
    new = F.struct(hit["start"].alias("start"), hit["len"].alias("len"))
    return F.struct(
        F.when(takes, hit["dist"]).otherwise(state["leader"]).alias("leader"),
        F.when(takes, F.transform(slots, lambda slot, j: F.when(j == hit["dist"], new).otherwise(slot))).otherwise(slots).alias("slots"),
        F.when(closes, F.concat(state["out"], _close(state, levels, rules))).otherwise(state["out"]).alias("out"),
    )


def fold_hits(hits: Column, levels: int, rules: Rules) -> Column:
    """What is kept of an array of hits that is sorted by start and length."""
    empty = F.transform(F.sequence(F.lit(0), F.lit(levels - 1)), lambda _: F.lit(None).cast("struct<start:bigint,len:int>"))
    start = F.struct(F.lit(-1).alias("leader"), empty.alias("slots"), F.array().cast(f"array<{OCCURRENCE}>").alias("out"))
    return F.aggregate(hits, start, lambda s, h: step_hit(s, h, levels, rules), lambda s: F.when(s["leader"] >= 0, F.concat(s["out"], _close(s, levels, rules))).otherwise(s["out"]))


def _sorted_fold(rows: DataFrame, by: list[str], levels: int, rules: Rules) -> DataFrame:
    """Fold groups of sorted rows with one iterator per partition. Groups inside a batch are folded together; one that goes on over
    batches keeps its state only, so memory doesn't grow with a group."""

    def fold(batches):
        key, sifter, head = None, SerialSifter(levels, rules), None

        def ended() -> pa.RecordBatch | None:
            out = sifter.close()
            return _kept_rows(head, np.zeros(len(out), np.int64), *np.array(out, np.int64).reshape(-1, 4).T) if out else None

        for batch in batches:
            if not batch.num_rows:
                continue
            ids = np.column_stack([batch.column(i).fill_null(-(1 << 31)).to_numpy().astype(np.int64) for i in range(len(by))])
            start, length, dist = (batch.column(len(by) + i).to_numpy().astype(np.int64) for i in range(3))
            first = np.append(0, 1 + np.flatnonzero((np.diff(ids, axis=0) != 0).any(1)))
            stops = np.append(first[1:], len(start))
            run = 0
            if key is not None and key == tuple(ids[0]):
                out = [o for hit in zip(start[: stops[0]].tolist(), length[: stops[0]].tolist(), dist[: stops[0]].tolist(), strict=True) for o in sifter.add(*hit)]
                if out:
                    yield _kept_rows(head, np.zeros(len(out), np.int64), *np.array(out, np.int64).T)
                run = 1
            if run == len(first):
                continue
            if key is not None and (done := ended()) is not None:
                yield done
            a = first[-1]
            if run < len(first) - 1:
                whole = slice(first[run], a)
                island, *kept = fold_islands(first[run:-1] - first[run], start[whole], length[whole], dist[whole], levels, rules)
                if len(island):
                    yield _kept_rows(batch, first[run:-1][island], *kept)
            key, head, sifter = tuple(ids[a]), batch.slice(int(a), 1), SerialSifter(levels, rules)
            out = [o for hit in zip(start[a:].tolist(), length[a:].tolist(), dist[a:].tolist(), strict=True) for o in sifter.add(*hit)]
            if out:
                yield _kept_rows(head, np.zeros(len(out), np.int64), *np.array(out, np.int64).T)
        if key is not None and (done := ended()) is not None:
            yield done

    dealt = rows.select(*by, "start", "len", "dist").repartition(*by).sortWithinPartitions(*by, "start", "len")
    return dealt.mapInArrow(fold, KEPT_SCHEMA)


def _kept_rows(batch: pa.RecordBatch, at: np.ndarray, start: np.ndarray, length: np.ndarray, level: np.ndarray, last: np.ndarray) -> pa.RecordBatch:
    """Occurrences with the stream and pattern of some rows of a batch."""
    rows = pa.array(at)
    numbers = [pa.array(np.asarray(c, k)) for c, k in ((start, np.int64), (length, np.int32), (level, np.int32), (last, np.int64))]
    return pa.RecordBatch.from_arrays([batch.column(0).take(rows), batch.column(1).take(rows), *numbers], names=["stream_id", "pattern_id", "start", "len", "dist", "decided_at"])


def _array_fold(islands: DataFrame, levels: int, rules: Rules) -> DataFrame:
    arrays = islands.groupBy(*KEYS, "island").agg(F.sort_array(F.collect_list(F.struct("start", "len", "dist"))).alias("hits"))
    return arrays.select(*KEYS, F.inline(fold_hits(F.col("hits"), levels, rules)))


def _fold_by_size(hits: DataFrame, levels: int, rules: Rules, giant: int, *, arrays: bool = False) -> DataFrame:
    """Fold written hits by islands; those of over `giant` hits in blocks that repair each other."""
    islands = _island_starts(hits, ISLAND_BLOCK).drop("__block")
    key = [*KEYS, "island"]
    giants = written(islands.groupBy(*key).agg(F.count(F.lit(1)).alias("__hits")).where(F.col("__hits") > giant).select(*key), "giant-islands")
    some = not giants.isEmpty()
    small = islands.join(giants, key, "left_anti") if some else islands
    kept = _array_fold(small, levels, rules) if arrays else _sorted_fold(small, key, levels, rules)
    if some:
        large = islands.join(giants, key).select("stream_id", "pattern_id", "start", "len", "dist")
        kept = kept.unionByName(resync_fold(large, levels, tie=rules.tie, validation=rules.validation, strict=rules.strict))
    return kept


def sift_hits(hits: DataFrame, levels: int, *, tie: str = "earliest", validation: str = "accumulated", strict: bool = True, engine: str = "auto", number: bool = True, giant: int = GIANT) -> DataFrame:
    """The occurrences among some hits: stream_id, pattern_id, start, len, dist, decided_at and, if `number`, group_no (from 0 in each stream and pattern).

    levels: one more than the largest threshold. engine `auto`: islands as sorted rows, many at a time, those of over `giant` hits in blocks that repair each other;
    `native`: array fold of each island in built-in functions, with the same guard; `iterator`: all islands as sorted rows; `resync`: everything in blocks that repair each other;
    `serial`: whole streams as sorted rows, as a symbol loop would do. All but `serial` write the hits once, before they fork.
    """
    rules = Rules(tie, validation, strict)
    if engine == "serial":
        kept = _sorted_fold(hits, list(KEYS), levels, rules)
    elif engine == "resync":
        kept = resync_fold(hits, levels, tie=tie, validation=validation, strict=strict)
    elif engine in ("auto", "native", "iterator"):
        found = written(hits.select("stream_id", "pattern_id", "start", "len", "dist"), "hits")
        if engine == "iterator":
            kept = _sorted_fold(_island_starts(found, ISLAND_BLOCK), [*KEYS, "island"], levels, rules)
        else:
            kept = _fold_by_size(found, levels, rules, giant, arrays=engine == "native")
    else:
        raise ValueError("engine is 'auto', 'native', 'iterator', 'resync' or 'serial'")
    return numbered(kept) if number else kept


def numbered(kept: DataFrame, *, block: int = ISLAND_BLOCK) -> DataFrame:
    """Occurrences with group_no: the place of their group, by its decision, in the stream and pattern. Ranks inside blocks of positions, and one row per block over a stream."""
    rows = kept.withColumn("__block", F.floor(F.col("decided_at") / block))
    inside = Window.partitionBy(*KEYS, "__block").orderBy("decided_at")
    over = Window.partitionBy(*KEYS).orderBy("__block").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("__nth", F.dense_rank().over(inside))
    blocks = rows.groupBy(*KEYS, "__block").agg(F.max("__nth").alias("__n")).withColumn("__before", F.coalesce(F.sum("__n").over(over), F.lit(0))).drop("__n")
    return rows.join(blocks, [*KEYS, "__block"]).select(*kept.columns, (F.col("__before") + F.col("__nth") - 1).cast("long").alias("group_no"))


def _fold_in_kernel(streams: DataFrame, patterns: DataFrame, rules: Rules, block: int, spread: bool = False) -> DataFrame:
    """Detection and fold in one pass over blocks: occurrences of islands that lie inside a block, and the hits of the other islands (decided_at is -1).
    spread: deal the blocks out first, where the search costs much more than moving them.

    An island is inside if no hit of the block before can reach it, that is if it starts at least lp + K - 1 symbols behind the block's first start, and if
    it ends before the next block's first start. The first and the last block of a stream have no neighbour on one side.
    """
    bank = collected(patterns)
    levels = max((k for _, _, k in bank), default=0) + 1
    numbers, reach = np.array([i for i, _, _ in bank], np.int32), np.array([len(p) + k - 1 for _, p, k in bank], np.int64)
    groups: dict[tuple[int, int], list] = {}
    for n, (_, p, k) in enumerate(bank):
        groups.setdefault((len(p), k), []).append((n, kernels.encode(p)))
    blocks = blocks_of(streams, bank, block).withColumn("final", F.char_length("text") == F.col("own"))
    if spread:
        blocks = blocks.repartition("stream_id", "base")

    def fold(batches):
        for batch in batches:
            finals = batch.column(4).to_numpy(zero_copy_only=False)
            bases, owns = batch.column(1).to_numpy(), batch.column(2).to_numpy()
            for ids, of, pattern, start, length, dist in _kernel_arrays(iter([batch.select([0, 1, 2, 3])]), groups, 1, together=True):
                end = start + length - 1
                # islands: runs in a row and pattern whose starts don't lie behind all ends so far; ends are lifted one by one of these so that one running maximum serves all
                lift = np.cumsum(np.append(False, (np.diff(of) != 0) | (np.diff(pattern) != 0))) << 32
                base = bases[of]
                fresh = np.append(True, (start - base + lift)[1:] > np.maximum.accumulate(end - base + lift)[:-1])
                first = np.flatnonzero(fresh)
                last_end = np.maximum.reduceat(end, first)
                row, of_pattern = of[first], pattern[first]
                inner = ((bases[row] == 0) | (start[first] >= bases[row] + reach[of_pattern])) & (finals[row] | (last_end < bases[row] + owns[row]))
                sizes = np.diff(np.append(first, len(start)))
                whose = np.repeat(inner, sizes)
                begin = np.cumsum(sizes[inner]) - sizes[inner]
                island, *kept = fold_islands(begin, start[whose], length[whose].astype(np.int64), dist[whose].astype(np.int64), levels, rules)
                edge = ~whose
                inside = (row[inner][island], of_pattern[inner][island], *kept)
                columns = [np.concatenate(c) for c in zip(inside, (of[edge], pattern[edge], start[edge], length[edge], dist[edge], np.full(int(edge.sum()), -1)), strict=True)]
                if len(columns[0]):
                    arrays = [pa.array(np.asarray(c, k)) for c, k in zip((numbers[columns[1]], *columns[2:]), (np.int32, np.int64, np.int32, np.int32, np.int64), strict=True)]
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(columns[0])), *arrays], names=["stream_id", "pattern_id", "start", "len", "dist", "decided_at"])

    return blocks.select("stream_id", "base", "own", "text", "final").mapInArrow(fold, KEPT_SCHEMA)


def most_levels(patterns: DataFrame) -> int:
    """One more than the largest threshold of a pattern table."""
    return (patterns.agg(F.max("k_max")).first()[0] or 0) + 1


def sift(
    streams: DataFrame, patterns: DataFrame, *, tie: str = "earliest", validation: str = "accumulated", strict: bool = True, engine: str = "kernel", kernel: str = "arrow", number: bool = True, block: int = BLOCK, giant: int = GIANT, spread: bool = False
) -> DataFrame:
    """Occurrences of patterns in streams or blocks of streams: detection, islands, fold.

    engine `kernel`: islands inside a block are folded where they are found, before any shuffle; only hits at a block's edge are shuffled. The other engines (see sift_hits)
    shuffle all hits, found by any kernel of find_hits. spread: engine `kernel` deals the blocks over all cores first; a file of one row group is one task otherwise.
    """
    rules = {"tie": tie, "validation": validation, "strict": strict}
    if engine != "kernel":
        return sift_hits(find_hits(streams, patterns, kernel=kernel, block=block), most_levels(patterns), engine=engine, number=number, giant=giant, **rules)
    detected = written(_fold_in_kernel(streams, patterns, Rules(**rules), block, spread), "detected")
    kept, edges = detected.where("decided_at >= 0"), detected.where("decided_at < 0").drop("decided_at")
    if not edges.isEmpty():
        kept = kept.unionByName(_fold_by_size(edges, most_levels(patterns), Rules(**rules), giant))
    return numbered(kept) if number else kept


def sift_bank(streams: DataFrame, patterns: DataFrame, **options) -> DataFrame:
    """A bank of patterns over common streams: each block is read and encoded once for all of them; results carry their pattern."""
    return sift(streams, patterns, **{"spread": True} | options)
