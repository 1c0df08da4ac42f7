"""Removal of repeated passages by super-k-mer partitioning.

A window is `width` consecutive words of one document. Each window has a minimiser: the smallest hash of the
runs of `seed` words in it. Consecutive windows with the same minimiser make a super-k-mer, however often it occurs in them (a line that is
repeated a hundred times is one), and travel as one packed string to the minimiser's bucket. Equal windows have equal minimisers, so they meet there, where sorting
finds for each window the smallest doc_id with it. A document loses the words under windows that start in a document with
a smaller doc_id too.

How it stays small and even:
* First only (minimiser, doc_id, place) rows are shuffled. A minimiser of a single document can't hold a
  repetition, so its super-k-mers never travel as text.
* Equal strings of a bucket are merged, with the smallest doc_id, before and after the shuffle. A bucket's
  group is then its different strings, however many copies there are: inside a common passage all documents have the same string.
* A bucket of more than `crowd` different strings (the edge of a passage that many documents share, a phrase inside many passages)
  is cut finer. Its window hashes are counted as narrow rows, and windows of a single document leave. What stays is packed again,
  consecutive windows together, into the buckets of a minimiser of longer runs (`wider_seeds`). At the last level a run is a
  whole window, and a bucket one string. Where `crowd` lies changes the work, not the result.

Words are compared as bytes where hashes agree, so a hash collision can't remove anything.

Defined results: a null text has no words; a document shorter than a window loses nothing; repeated rows (equal doc_id
and text) get equal results; a null doc_id is compared with nothing and loses nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from symseek.llm.common import Words, column_of, give_back, list_array, map_texts, records, run_hashes, signed, words_of, written

WIDTH = 50
SEED = 16
#: Different strings that a task sorts together; a bucket of more is cut finer.
CROWD = 2_000
#: Shared window hashes that travel as one list.
_SET = 256


def wider_seeds(width: int, seed: int) -> list[int]:
    """The runs by which crowded buckets are cut, level by level; the last is the window itself."""
    return sorted({(2 * width + seed) // 3, width} - {seed})


def super_kmers(w: Words, width: int, seed: int, wanted: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, first window's word in the text, windows, minimiser) of each super-k-mer of some texts. wanted: for each word, whether its window takes part."""
    counts = w.counts()
    empty = np.zeros(0, np.int64)
    if len(w.hashes) < width:
        return empty, empty, empty, empty.astype(np.uint64)
    seeds = run_hashes(w.hashes, seed)
    text = np.repeat(np.arange(len(counts)), counts)
    inside = text[: len(text) - width + 1] == text[width - 1 :]
    at = np.flatnonzero(inside if wanted is None else inside & wanted[: len(inside)])
    if not len(at):
        return empty, empty, empty, empty.astype(np.uint64)
    views = np.lib.stride_tricks.sliding_window_view(seeds, width - seed + 1)
    least = np.concatenate([views[at[i : i + 32768]].min(1) for i in range(0, len(at), 32768)])
    new = np.ones(len(at), bool)
    new[1:] = (at[1:] != at[:-1] + 1) | (least[1:] != least[:-1]) | (text[at[1:]] != text[at[:-1]])
    begin = np.flatnonzero(new)
    first = at[begin]
    return text[first], first - w.first[text[first]], np.diff(np.append(begin, len(at))), least[begin]


def _places(docs: DataFrame, width: int, seed: int) -> DataFrame:
    """id, h, start, n, mini: where each super-k-mer is, without its text."""

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        text, start, n, mini = super_kmers(words_of(column_of(batch, "body")), width, seed)
        of = pa.array(text)
        return records(id=column_of(batch, "id").take(of), h=column_of(batch, "h").take(of), start=pa.array(start, pa.int32()), n=pa.array(n, pa.int32()), mini=signed(mini))

    return map_texts(docs, step, f"id {dict(docs.dtypes)['id']}, h long, start int, n int, mini long", text="body")


def _strings(w: Words, rows: np.ndarray, start: np.ndarray, n: np.ndarray, width: int) -> pa.Array:
    """The packed strings of super-k-mers: their words, joined by one space."""
    first = w.first[rows] + start
    data = w.data.tobytes()
    spans = zip(w.starts[first].tolist(), w.ends[first + n + width - 2].tolist(), strict=True)
    return pa.array([b" ".join(data[x:y].split()) for x, y in spans], pa.binary())


def _packed(docs: DataFrame, width: int) -> DataFrame:
    """bucket, packed, id, h, start: the super-k-mers that travel. docs has their places in `own`."""
    kind = dict(docs.dtypes)["id"]

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        w = words_of(column_of(batch, "body"))
        own = column_of(batch, "own")
        rows = np.repeat(np.arange(batch.num_rows), np.diff(np.asarray(own.offsets)))
        start, n, mini = (own.flatten().field(k).to_numpy(zero_copy_only=False) for k in ("start", "n", "mini"))
        of = pa.array(rows)
        return records(bucket=mini, packed=_strings(w, rows, start.astype(np.int64), n.astype(np.int64), width), id=column_of(batch, "id").take(of), h=column_of(batch, "h").take(of), start=pa.array(start, pa.int32()))

    return map_texts(docs, step, f"bucket long, packed binary, id {kind}, h long, start int", text="body")


def _crowded(packed: DataFrame, crowd: int) -> DataFrame:
    """bucket: those with more than `crowd` different strings."""
    return packed.groupBy("bucket", "sig").agg(F.lit(1).alias("one")).groupBy("bucket").agg(F.count(F.lit(1)).alias("strings")).where(F.col("strings") > crowd).select("bucket")


def _window_hashes(packed: pa.Array, width: int) -> tuple[Words, np.ndarray, np.ndarray]:
    """The words of packed strings, the place of each window's first word, and each window's hash."""
    w = words_of(packed.cast(pa.string()))
    counts = w.counts() - width + 1
    at = np.repeat(w.first[:-1], counts) + np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    return w, at, run_hashes(w.hashes, width)[at]


def _finer(aside: DataFrame, width: int, seed: int) -> DataFrame:
    """The super-k-mers of crowded buckets, cut by longer runs and without the windows of a single document."""
    kind = dict(aside.dtypes)["id"]

    def hashed(batch: pa.RecordBatch) -> pa.RecordBatch:
        w, _, hashes = _window_hashes(column_of(batch, "packed"), width)
        kept = {c: column_of(batch, c) for c in ("bucket", "packed", "id", "h", "start")}
        return records(**kept, windows=list_array(signed(hashes), w.counts() - width + 1))

    runs = written(map_texts(aside, hashed, f"bucket long, packed binary, id {kind}, h long, start int, windows array<long>", text="packed"), "crowded")

    def owners(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """bucket, window, lo, hi: merged in each batch, before the shuffle."""
        for batch in batches:
            ids, windows = column_of(batch, "id"), column_of(batch, "windows")
            row = np.repeat(np.arange(batch.num_rows), np.diff(np.asarray(windows.offsets)))
            if not len(row):
                continue
            rank = np.empty(batch.num_rows, np.int64)
            rank[pc.sort_indices(ids).to_numpy()] = np.arange(batch.num_rows)
            bucket, window = column_of(batch, "bucket").to_numpy()[row], windows.flatten().to_numpy()
            order = np.lexsort((rank[row], window, bucket))
            new = np.append(True, (np.diff(window[order]) != 0) | (np.diff(bucket[order]) != 0))
            first, last = np.flatnonzero(new), np.append(np.flatnonzero(new)[1:], len(order)) - 1
            lo, hi = (ids.take(pa.array(row[order[x]])) for x in (first, last))
            yield records(bucket=bucket[order[first]], window=window[order[first]], lo=lo, hi=hi)

    met = runs.select("bucket", "id", "windows").mapInArrow(owners, f"bucket long, window long, lo {kind}, hi {kind}")
    shared = written(met.groupBy("bucket", "window").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).where("lo < hi").select("bucket", "window"), "shared-windows")
    # A bucket's shared windows travel in lists of about _SET, dealt by the window's hash; a run asks for the lists that its windows would be in.
    sizes = shared.groupBy("bucket").agg(F.ceil(F.count(F.lit(1)) / _SET).alias("lists"))
    lists = shared.join(sizes, "bucket").groupBy("bucket", F.pmod("window", "lists").alias("part")).agg(F.collect_list("window").alias("found"))
    asks = runs.join(sizes, "bucket").withColumn("part", F.explode(F.array_distinct(F.transform("windows", lambda x: F.pmod(x, F.col("lists"))))))
    answers = asks.join(lists, ["bucket", "part"]).select("id", "h", "start", "packed", F.array_intersect("windows", "found").alias("found"))
    alive = answers.groupBy("id", "h", "start", "packed").agg(F.flatten(F.collect_list("found")).alias("found")).where(F.size("found") > 0)

    def again(batch: pa.RecordBatch) -> pa.RecordBatch:
        w, at, hashes = _window_hashes(column_of(batch, "packed"), width)
        found = column_of(batch, "found")
        offsets, flat = np.asarray(found.offsets), found.flatten().to_numpy()  # of a slice, offsets don't begin at 0
        offsets = offsets - offsets[0]
        wanted = np.zeros(len(w.hashes), bool)
        counts = np.cumsum(w.counts() - width + 1)
        for i, b in enumerate(counts.tolist()):
            a = int(counts[i - 1]) if i else 0
            wanted[at[a:b]] = np.isin(signed(hashes[a:b]), flat[offsets[i] : offsets[i + 1]])
        rows, start, n, mini = super_kmers(w, width, seed, wanted)
        of = pa.array(rows)
        begin = column_of(batch, "start").to_numpy()[rows] + start
        return records(bucket=signed(mini), packed=_strings(w, rows, start, n, width), id=column_of(batch, "id").take(of), h=column_of(batch, "h").take(of), start=pa.array(begin, pa.int32()))

    return map_texts(alive, again, f"bucket long, packed binary, id {kind}, h long, start int", text="packed")


def _bucket_firsts(strings: list[bytes], owners: list, width: int) -> list[list]:
    """For each string of a bucket, the smallest owner of each of its windows."""
    counts = [s.count(b" ") + 2 - width for s in strings]
    if len(strings) == 1:
        return [[owners[0]] * counts[0]]
    w = words_of(pa.array([s.decode() for s in strings], pa.string()))
    whole = run_hashes(w.hashes, width)
    text = np.repeat(np.arange(len(strings)), counts)
    at = w.first[text] + np.arange(len(text)) - np.repeat(np.cumsum(counts) - counts, counts)
    order = np.lexsort((np.asarray(text), whole[at]))
    ranks = np.argsort(np.argsort(np.array(owners), kind="stable"), kind="stable")
    best = list(range(len(text)))  # position -> position with the smallest owner of the same window
    data = w.data.tobytes()
    keys = whole[at[order]]
    edges = np.append(np.flatnonzero(np.append(True, keys[1:] != keys[:-1])), len(order))
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        if b - a > 1:
            least: dict[bytes, int] = {}
            group = order[a:b].tolist()
            bodies = [data[w.starts[at[k]] : w.ends[at[k] + width - 1]] for k in group]
            for k, body in zip(group, bodies, strict=True):
                if body not in least or ranks[text[k]] < ranks[text[least[body]]]:
                    least[body] = k
            for k, body in zip(group, bodies, strict=True):
                best[k] = least[body]
    flat = [owners[text[k]] for k in best]
    stops = np.cumsum(counts).tolist()
    return [flat[e - c : e] for e, c in zip(stops, counts, strict=True)]


def _firsts(strings: DataFrame, width: int) -> DataFrame:
    """sig, firsts: the smallest id of each window of each different string. Input sorted by bucket in each partition."""
    kind = dict(strings.dtypes)["id"]

    def grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, group, ready, size = None, ([], [], []), ([], []), 0

        def close():
            if group[0]:
                ready[0].extend(group[2])
                ready[1].extend(_bucket_firsts(group[0], group[1], width))
            for x in group:
                x.clear()

        def flush():
            out = pa.RecordBatch.from_arrays([pa.array(ready[0], pa.binary()), pa.array(ready[1])], names=["sig", "firsts"])
            ready[0].clear()
            ready[1].clear()
            return out

        for batch in batches:
            columns = [column_of(batch, c).to_pylist() for c in ("bucket", "packed", "id", "sig")]
            for bucket, packed, owner, sig in zip(*columns, strict=True):
                if bucket != key:
                    close()
                    key = bucket
                    if len(ready[0]) >= 2000:
                        yield flush()
                group[0].append(packed)
                group[1].append(owner)
                group[2].append(sig)
        close()
        if ready[0]:
            yield flush()
        give_back()

    return strings.mapInArrow(grouped, f"sig binary, firsts array<{kind}>")


def remove_repeats(df: DataFrame, *, key: str = "doc_id", text: str = "text", width: int = WIDTH, seed: int = SEED, crowd: int = CROWD, keep: dict[str, Column] | None = None, text_as: str | None = None) -> DataFrame:
    """key, n_words, n_removed and kept (the words left, joined by one space) of every row, with the columns of `keep`.

    text_as: a name for one more column: the text as it was where nothing is removed, else the same as kept.
    """
    if not 0 < seed <= width:
        raise ValueError("the seed is at least one word and at most a window")
    docs = df.select(F.col(key).alias("id"), F.xxhash64(F.col(text)).alias("h"), F.col(text).alias("body"))
    places = written(_places(docs.where(F.col("id").isNotNull()), width, seed), "places")
    meets = written(places.groupBy("mini").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).where("lo < hi").select("mini"), "shared-minimisers")  # so that the join can split a frequent minimiser's rows
    travel = places.join(meets, "mini").groupBy("id", "h").agg(F.collect_list(F.struct("start", "n", "mini")).alias("own"))
    signed_off = lambda rows, name: written(rows.withColumn("sig", F.unhex(F.md5("packed"))), name)
    packed, level = None, signed_off(_packed(docs.join(travel, ["id", "h"]), width), "super-kmers")
    for longer in [*wider_seeds(width, seed), None]:
        crowded = written(_crowded(level, crowd), "crowded-buckets") if longer else None
        few = longer is None or crowded.isEmpty()
        done = level if few else level.join(crowded, "bucket", "left_anti")
        packed = done if packed is None else packed.unionByName(done)
        if few:
            break
        level = signed_off(_finer(level.join(crowded, "bucket"), width, longer), "finer-super-kmers")
    strings = packed.groupBy("bucket", "packed", "sig").agg(F.min("id").alias("id"))
    firsts = _firsts(strings.repartition("bucket").sortWithinPartitions("bucket"), width)
    again = F.filter(F.transform("firsts", lambda x, i: F.when(x < F.col("id"), F.col("start") + i)), lambda x: x.isNotNull())
    repeats = packed.select("sig", "id", "h", "start").join(firsts, "sig").select("id", "h", again.alias("again")).where(F.size("again") > 0)
    gone = repeats.groupBy("id", "h").agg(F.flatten(F.collect_list("again")).alias("gone"))
    kind, names = dict(docs.dtypes)["id"], list(keep or {})

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        w = words_of(column_of(batch, "body"))
        begins = [x or () for x in column_of(batch, "gone").to_pylist()]
        delta = np.zeros(len(w.starts) + 1, np.int64)
        for i, found in enumerate(begins):
            if found:
                at = w.first[i] + np.array(found)
                np.add.at(delta, at, 1)
                np.add.at(delta, at + width, -1)
        covered = np.cumsum(delta)[:-1] > 0
        data, kept, removed = w.data.tobytes(), [], []
        for i, found in enumerate(begins):
            a, b = int(w.first[i]), int(w.first[i + 1])
            removed.append(int(covered[a:b].sum()))
            if removed[-1]:
                kept.append(b" ".join(data[x:y] for x, y in zip(w.starts[a:b][~covered[a:b]].tolist(), w.ends[a:b][~covered[a:b]].tolist(), strict=True)))
            else:
                kept.append(b" ".join(data[w.starts[a] : w.ends[b - 1]].split()) if b > a else b"")
        own = {n: column_of(batch, n) for n in names}
        if text_as:
            bodies = column_of(batch, "body").to_pylist()
            own[text_as] = pa.array([x.decode() if r else t for x, r, t in zip(kept, removed, bodies, strict=True)], pa.string())
        return records(
            id=column_of(batch, "id"), **own, n_words=pa.array(w.counts(), pa.int64()), n_removed=pa.array(removed, pa.int64()), kept=pa.array([x.decode() for x in kept], pa.string())
        )

    whole = df.select(F.col(key).alias("id"), F.xxhash64(F.col(text)).alias("h"), F.col(text).alias("body"), *[c.alias(n) for n, c in (keep or {}).items()])
    rows = whole.join(gone, ["id", "h"], "left")
    kinds = dict(rows.dtypes)
    schema = ", ".join([f"id {kind}", *[f"`{n}` {kinds[n]}" for n in names], *[f"`{text_as}` string"] * bool(text_as), "n_words long, n_removed long, kept string"])
    return map_texts(rows, step, schema, text="body").withColumnRenamed("id", key)
