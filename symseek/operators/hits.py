"""Hits: all substrings of a stream within the threshold of a pattern, by several plans with the same result.

Schema of a hit: stream_id, pattern_id, start (0-based), len, dist.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from symseek.functions import kernels
from symseek.sources.streams import block_streams, collected

HIT_SCHEMA = "stream_id long, pattern_id int, start long, len int, dist int"
#: Symbols that a kernel call takes at once, and the longest stretch of a stream before it is cut in blocks.
CHUNK, BLOCK = 1 << 17, 1 << 16
#: For so many patterns of one length and threshold, a pass that finds all their starts together pays.
BANK = 4


def blocks_of(streams: DataFrame, patterns: list[tuple[int, str, int]], block: int) -> DataFrame:
    """Streams as blocks with the halo that the longest window needs: (stream_id, base, own, text). Frames that are blocks already are taken as they are."""
    halo = max((len(p) + k - 1 for _, p, k in patterns), default=0)
    if "own" in streams.columns:
        short = (F.char_length("text") - F.col("own") < halo) & ~F.col("final") if "final" in streams.columns else F.lit(False)
        text = F.when(short, F.raise_error(F.lit("the blocks' halo is shorter than a window of the patterns")).cast("string")).otherwise(F.col("text"))
        return streams.select("stream_id", "base", "own", text.alias("text"))
    if halo > block:
        raise ValueError("a pattern is longer than a block")
    return block_streams(streams, block, halo).select("stream_id", "base", "own", "text")


def find_hits(streams: DataFrame, patterns: DataFrame, *, kernel: str = "arrow", min_len: int = 1, block: int = BLOCK) -> DataFrame:
    """All hits. kernel `native`: built-in functions, a row per start and length until the filter in the same stage, over whole streams.
    kernel `arrow`: all lengths of a start from one matrix, all starts of a block at once; only hits leave the kernel. `wavefront` and `counter` fill
    the same matrices by anti-diagonals, with stored borders or with borders from the step number."""
    bank = collected(patterns)
    if kernel == "native":
        if "own" in streams.columns:
            raise ValueError("the native plan takes whole streams, not blocks")
        pairs = streams.join(F.broadcast(patterns), how="cross").where(F.col("n") >= F.greatest(F.col("lp") - F.col("k_max"), F.lit(min_len)))
        starts = pairs.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("start"))
        low = F.greatest(F.col("lp") - F.col("k_max"), F.lit(min_len))
        high = F.least((F.col("lp") + F.col("k_max")).cast("long"), F.col("n") - F.col("start")).cast("int")
        lengths = starts.where(high >= low).select("*", F.explode(F.sequence(low, high)).alias("len"))
        dist = F.call_function("levenshtein", F.col("pattern"), F.substr("text", (F.col("start") + 1).cast("int"), F.col("len")), F.col("k_max"))
        return lengths.select("stream_id", "pattern_id", "start", "len", dist.alias("dist")).where("dist >= 0")
    if kernel not in KERNELS:
        raise ValueError(f"kernel is 'native' or one of {sorted(KERNELS)}")
    groups: dict[tuple[int, int], list[tuple[int, np.ndarray]]] = defaultdict(list)
    for i, p, k in bank:
        groups[len(p), k].append((i, kernels.encode(p)))
    return blocks_of(streams, bank, block).mapInArrow(lambda batches: _kernel_hits(batches, groups, min_len, KERNELS[kernel]), HIT_SCHEMA)


#: Ways to fill the matrices of many starts.
KERNELS = {"arrow": kernels.band_distances, "wavefront": kernels.wavefront_distances, "counter": partial(kernels.wavefront_distances, by_counter=True)}


def _kernel_hits(batches: Iterator[pa.RecordBatch], groups: dict, min_len: int, distances=kernels.band_distances) -> Iterator[pa.RecordBatch]:
    """The hits of blocks, as record batches."""
    for ids, of, pattern_id, start, length, dist in _kernel_arrays(batches, groups, min_len, distances):
        kinds = (np.int32, np.int64, np.int32, np.int32)
        columns = [ids.take(pa.array(of)), *[pa.array(np.asarray(c, k)) for c, k in zip((np.full(len(of), pattern_id), start, length, dist), kinds, strict=True)]]
        yield pa.RecordBatch.from_arrays(columns, names=["stream_id", "pattern_id", "start", "len", "dist"])


def _kernel_arrays(batches: Iterator[pa.RecordBatch], groups: dict, min_len: int, distances=kernels.band_distances, *, together: bool = False) -> Iterator[tuple]:
    """(stream ids of the batch, row of each hit, pattern, starts, lengths, distances) for each pattern and chunk of blocks; hits by row, start and length.
    together: for many patterns of a bank at once, with an array of patterns, by which hits come first."""
    gap = max((lp + k for lp, k in groups), default=1)
    for batch in batches:
        ids, bases, owns, texts = (batch.column(i) for i in range(4))
        base, own, texts = bases.to_numpy(), owns.to_numpy(), texts.to_pylist()
        row = 0
        while row < len(texts):
            stop, size = row, 0
            while stop < len(texts) and (size == 0 or size + len(texts[stop]) <= CHUNK):
                size += len(texts[stop]) + gap
                stop += 1
            codes, begin, sizes = kernels.joined(texts[row:stop], gap)
            of = np.repeat(np.arange(row, stop), own[row:stop])
            inside = np.arange(len(of)) - np.repeat(np.cumsum(own[row:stop]) - own[row:stop], own[row:stop])
            starts, left = begin[of - row] + inside, sizes[of - row] - inside
            place = np.full(len(codes), -1)
            place[starts] = np.arange(len(starts))
            for (lp, k), patterns in groups.items():
                # for a bank, the banded matrices are filled only where a hit starts, those of many patterns in one call
                words = distances is kernels.band_distances and k < lp <= 64 and len(patterns) >= BANK
                if words:
                    near = [(at := place[some])[at >= 0] for some in kernels.bank_starts(codes, [p for _, p in patterns], k)]
                    bank = np.array([p for _, p in patterns]).T
                for run in _runs([len(x) for x in near], CHUNK) if words else [[i] for i in range(len(patterns))]:
                    own_starts = np.concatenate([near[i] for i in run]) if words else np.arange(len(starts))
                    if not len(own_starts):
                        continue
                    which = np.repeat(run, [len(near[i]) for i in run] if words else len(own_starts))
                    lengths, dist = distances(codes, starts[own_starts], bank[:, which] if words else patterns[run[0]][1], k)
                    l, s = np.divmod(np.flatnonzero(dist <= k), len(own_starts))
                    order = np.lexsort((l, s))
                    s, l = s[order], l[order]
                    d, w, s, length = dist[l, s], which[s], own_starts[s], np.array(lengths)[l]
                    good = (length <= left[s]) & (length >= min_len)
                    d, w, s, length = d[good], w[good], s[good], length[good]
                    if not len(s):
                        continue
                    found = (of[s], base[of[s]] + inside[s], length, d)
                    if together:
                        yield ids, found[0], np.array([i for i, _ in patterns])[w], *found[1:]
                        continue
                    cuts = [0, *(1 + np.flatnonzero(np.diff(w))).tolist(), len(w)]
                    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                        yield ids, found[0][a:b], patterns[w[a]][0], *[x[a:b] for x in found[1:]]
            row = stop


def _runs(sizes: list[int], most: int) -> list[list[int]]:
    """Numbers from 0 in runs whose sizes come to `most` at most, or of one number."""
    runs, size = [[]], 0
    for i, n in enumerate(sizes):
        if runs[-1] and size + n > most:
            runs.append([])
            size = 0
        runs[-1].append(i)
        size += n
    return runs


def exhaustive_hits(streams: DataFrame, patterns: DataFrame, *, materialize: bool = False, max_len: int = 512) -> DataFrame:
    """The brute-force baseline: every substring of every length. materialize: all substrings are stored before any is dropped.

    The number of substrings grows with the square of the stream, so streams over max_len symbols raise.
    """
    text = F.when(F.col("n") > max_len, F.raise_error(F.lit(f"exhaustive search takes streams of up to {max_len} symbols")).cast("string")).otherwise(F.col("text"))
    starts = streams.where("n > 0").select("stream_id", "n", text.alias("text"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("start"))
    subs = starts.select("stream_id", "start", "text", F.explode(F.sequence(F.lit(1), (F.col("n") - F.col("start")).cast("int"))).alias("len"))
    subs = subs.select("stream_id", "start", "len", F.substr("text", (F.col("start") + 1).cast("int"), F.col("len")).alias("sub"))
    collected(patterns)  # checks the size
    pairs = subs.join(F.broadcast(patterns.select("pattern_id", "pattern", "k_max")), how="cross")
    scored = pairs.select("stream_id", "pattern_id", "start", "len", F.levenshtein("pattern", "sub").alias("dist"), "k_max")
    if materialize:
        scored = scored.persist()
    return scored.where("dist <= k_max").select("stream_id", "pattern_id", "start", "len", "dist")


def piece_filter(streams: DataFrame, patterns: DataFrame, *, block: int = BLOCK) -> DataFrame:
    """Blocks and patterns where a hit is possible: of K + 1 pieces of the pattern, a hit leaves one unchanged.
    Patterns of K symbols or fewer have no such pieces, and keep all blocks."""
    bank = collected(patterns)
    rows = blocks_of(streams, bank, block)
    found = []
    for i, p, k in bank:
        cuts = [len(p) * j // (k + 1) for j in range(k + 2)]
        pieces = [p[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        some = F.lit(False)
        for piece in pieces:
            some = some | (F.col("text").contains(piece) if piece else F.lit(True))
        found.append(F.when(some, F.lit(i)))
    wanted = F.array_compact(F.array(*found)) if found else F.array().cast("array<int>")
    return rows.select("*", wanted.alias("wanted")).where(F.size("wanted") > 0)


def hits_prefiltered(streams: DataFrame, patterns: DataFrame, *, block: int = BLOCK) -> DataFrame:
    """Filter, then verify: the kernel sees only the blocks and patterns that the pieces leave."""
    bank = {i: (kernels.encode(p), k) for i, p, k in collected(patterns)}

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            wanted = batch.column(4).to_pylist()
            for i, (code, k) in bank.items():
                rows = [r for r, w in enumerate(wanted) if i in w]
                if rows:
                    yield from _kernel_hits(iter([batch.take(pa.array(rows)).select([0, 1, 2, 3])]), {(len(code), k): [(i, code)]}, 1)

    return piece_filter(streams, patterns, block=block).mapInArrow(verify, HIT_SCHEMA)


def qgram_index(streams: DataFrame, q: int) -> DataFrame:
    """gram, stream_id, pos: an index built once, before any pattern is known."""
    rows = streams.where(F.col("n") >= q).select("stream_id", "text", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - q)).alias("pos"))
    return rows.select(F.substr("text", (F.col("pos") + 1).cast("int"), F.lit(q)).alias("gram"), "stream_id", "pos")


def hits_qgram_index(streams: DataFrame, patterns: DataFrame, index: DataFrame, q: int) -> DataFrame:
    """Offline search: an equi-join of the index with the patterns' grams gives the windows to verify. Each edit spoils q grams at most,
    so a hit shares lp + 1 - q (K + 1) grams with the pattern; patterns where that isn't positive are searched without the index."""
    collected(patterns)  # checks the size
    usable = (F.col("lp") + 1 - q * (F.col("k_max") + 1)) > 0
    indexed, rest = patterns.where(usable), patterns.where(~usable)
    grams = indexed.select("*", F.explode(F.sequence(F.lit(0), F.col("lp") - q)).alias("off")).select("pattern_id", "lp", "k_max", "pattern", "off", F.substr("pattern", F.col("off") + 1, F.lit(q)).alias("gram"))
    met = index.join(F.broadcast(grams), "gram")
    at = F.col("pos") - F.col("off")
    starts = met.select("stream_id", "pattern_id", "pattern", "lp", "k_max", F.explode(F.sequence(F.greatest(at - F.col("k_max"), F.lit(0).cast("long")), F.greatest(at + F.col("k_max"), F.lit(0).cast("long")))).alias("start")).distinct()
    pairs = starts.join(streams, "stream_id").where("start < n")
    low = F.greatest(F.col("lp") - F.col("k_max"), F.lit(1))
    high = F.least((F.col("lp") + F.col("k_max")).cast("long"), F.col("n") - F.col("start")).cast("int")
    lengths = pairs.where(high >= low).select("*", F.explode(F.sequence(low, high)).alias("len"))
    dist = F.call_function("levenshtein", F.col("pattern"), F.substr("text", (F.col("start") + 1).cast("int"), F.col("len")), F.col("k_max"))
    return lengths.select("stream_id", "pattern_id", "start", "len", dist.alias("dist")).where("dist >= 0").unionByName(find_hits(streams, rest, kernel="native"))


def exact_hits(streams: DataFrame, patterns: DataFrame) -> DataFrame:
    """Exact matching, the traditional way: the hits with K = 0."""
    return find_hits(streams, patterns.withColumn("k_max", F.lit(0)), kernel="arrow")


def hamming_hits(streams: DataFrame, patterns: DataFrame) -> DataFrame:
    """Substrings of the pattern's length with at most K substitutions."""
    from symseek.functions.distance import hamming

    collected(patterns)  # checks the size
    pairs = streams.join(F.broadcast(patterns), how="cross").where("n >= lp")
    starts = pairs.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - F.col("lp"))).alias("start"))
    dist = hamming(F.col("pattern"), F.substr("text", (F.col("start") + 1).cast("int"), F.col("lp")))
    return starts.select("stream_id", "pattern_id", "start", F.col("lp").alias("len"), dist.alias("dist"), "k_max").where("dist <= k_max").drop("k_max")


def episode_hits(streams: DataFrame, patterns: DataFrame) -> DataFrame:
    """Substrings that hold the pattern as a subsequence with at most K symbols between, first and last symbol matching."""
    from symseek.functions.distance import episode_distance

    collected(patterns)  # checks the size
    pairs = streams.join(F.broadcast(patterns), how="cross").where("n >= lp")
    starts = pairs.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - F.col("lp"))).alias("start"))
    starts = starts.where(F.substr("text", (F.col("start") + 1).cast("int"), F.lit(1)) == F.substr("pattern", F.lit(1), F.lit(1)))
    lengths = starts.select("*", F.explode(F.sequence(F.col("lp"), F.least((F.col("lp") + F.col("k_max")).cast("long"), F.col("n") - F.col("start")).cast("int"))).alias("len"))
    sub = F.substr("text", (F.col("start") + 1).cast("int"), F.col("len"))
    ends = F.substr("text", (F.col("start") + F.col("len")).cast("int"), F.lit(1)) == F.substr("pattern", F.col("lp"), F.lit(1))
    return lengths.where(ends).select("stream_id", "pattern_id", "start", "len", episode_distance(F.col("pattern"), sub).alias("dist")).where("dist is not null")
