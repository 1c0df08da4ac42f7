"""Near copies by the Jaccard similarity of word n-gram sets, with prefix filters under several global orders.

Two documents link when their sets' similarity is at least a threshold t. A document of n n-grams can only link with one
that shares `SHARED` of its first n - ceil(t n) + `SHARED` n-grams, in any order of all n-grams. Here each order puts rare ones first, by a
table of counts, with different roundings of the counts and different tie-breaks. A pair must share prefix n-grams under
every order; only then its sets are compared, exactly.

1. Documents with equal sets are one vertex; they link with each other.
2. A pass over all documents counts n-grams in 2**22 buckets (a fixed size, so it may be broadcast). A bucket's count only
   orders; any table gives right results.
3. Prefix n-grams under the first order are shuffled; those of one set only are dropped. Pairs of fitting sizes are counted over
   groups of up to `small` sets; both prefixes hold so few of the n-grams that linked sets must share many of these (`least_shared`).
   Larger groups can't be expanded into pairs. Sets that meet in no small group must share SHARED n-grams of large groups, so of a set's m such n-grams
   only the m - SHARED + 1 with the smallest groups count (`_rarest`), and a set of fewer counts in none: one frequent n-gram glues nothing. In what is left, a chain through
   the sizes joins a group's sets. Both kinds of candidates make clusters.
4. The sets of a cluster meet in a task. Clusters over `block` sets are cut in blocks, each pair of which is a task, so no task's
   memory grows with a cluster. In a task the filters of all orders are intersected, and the remaining pairs verified.
   A task returns a spanning forest of its links: as many edges as vertices, never all pairs.
5. Components of these edges.

Defined results: a null or empty text has no n-grams and stands alone; with fewer words than n the whole sequence is the one n-gram;
repeated rows share a component; a null doc_id has a null component_id and takes no part; ties don't occur, as
components don't depend on any order.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.window import Window

from symseek.llm.common import LOWER_ASCII, PLAIN_WORD, byte_slices, column_of, give_back, map_texts, mix64, records, run_hashes, signed, small_batches, span_hashes, words_of, written
from symseek.llm.connected import components

_COUNT_BITS = 22
_COUNT_SLICES = 64
#: Tasks whose counts are added up together, before these sums are.
_LOT = 64
_SMALL = 48
#: The prefix n-grams that linked sets have in common at least.
SHARED = 3


def gram_sets(texts: pa.Array, n: int) -> list[np.ndarray]:
    """The sorted set of n-gram hashes of each text."""
    w = words_of(texts, PLAIN_WORD, LOWER_ASCII)
    grams = run_hashes(w.hashes, n)
    out = []
    for a, b in zip(w.first[:-1].tolist(), w.first[1:].tolist(), strict=True):
        if b - a >= n:
            out.append(np.unique(grams[a : b - n + 1]))
        elif b > a:
            out.append(span_hashes(w.hashes[a:b], np.array([0]), np.array([b - a])))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def prefix_length(n: int, percent: int) -> int:
    return min(n, n + (-percent * n // 100) + SHARED)


def order_keys(grams: np.ndarray, codes: np.ndarray, order: int) -> np.ndarray:
    """Places in a global order: rounded counts first, then a tie-break of the order's own."""
    code = codes[(grams >> np.uint64(64 - _COUNT_BITS)).astype(np.int64)].astype(np.uint64)
    if order:
        code >>= np.uint64(order)
    return code << np.uint64(56) | mix64(grams + np.uint64(order)) >> np.uint64(8)


def prefix(grams: np.ndarray, codes: np.ndarray, order: int, percent: int) -> np.ndarray:
    size = prefix_length(len(grams), percent)
    if size >= len(grams):
        return grams
    return grams[np.argpartition(order_keys(grams, codes, order), size - 1)[:size]]


def _survey(docs: DataFrame, n: int) -> DataFrame:
    """id, n, s1, s2 of each document (its set's size and two sums that identify it), and each task's bucket counts in slices."""

    def facts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(1 << _COUNT_BITS, np.int32)
        for batch in batches:
            for part in byte_slices(batch, "body") if batch.num_rows else ():
                sets = gram_sets(column_of(part, "body"), n)
                every = np.concatenate(sets)
                np.add.at(counts, (every >> np.uint64(64 - _COUNT_BITS)).astype(np.int64), 1)
                sizes = np.array([len(s) for s in sets])
                ends = np.cumsum(sizes)
                sums = [np.append(np.uint64(0), np.cumsum(mix64(every ^ np.uint64(salt)), dtype=np.uint64)) for salt in (0x0123456789ABCDEF, 0x5DEECE66D)]
                s1, s2 = (signed(s[ends] - s[ends - sizes]) for s in sums)
                none = {"slice": pa.nulls(len(sets), pa.int32()), "lot": pa.nulls(len(sets), pa.int32()), "counts": pa.nulls(len(sets), pa.binary())}
                yield records(id=column_of(part, "id"), n=pa.array(sizes, pa.int32()), s1=s1, s2=s2, **none)
        if counts.any():
            parts = np.minimum(counts, 65535).astype(np.uint16).reshape(_COUNT_SLICES, -1)  # a larger count orders as well; a task's counts are small numbers
            none = {c: pa.nulls(_COUNT_SLICES, kind) for c, kind in (("id", id_type), ("n", pa.int32()), ("s1", pa.int64()), ("s2", pa.int64()))}
            lot = TaskContext.get().partitionId() // _LOT
            yield records(**none, slice=pa.array(range(_COUNT_SLICES), pa.int32()), lot=pa.array([lot] * _COUNT_SLICES, pa.int32()), counts=pa.array([p.tobytes() for p in parts], pa.binary()))
        give_back()

    kind = dict(docs.dtypes)["id"]
    id_type = to_arrow_type(docs.schema["id"].dataType)
    return docs.mapInArrow(facts, f"id {kind}, n int, s1 long, s2 long, slice int, lot int, counts binary")


def _codes(surveyed: DataFrame) -> np.ndarray:
    """Four steps for each doubling of a bucket's count; one byte per bucket."""

    def added(rows: DataFrame, *by: str, last: bool) -> DataFrame:
        """The sums of counts by slice, or slice and lot; the last ones as codes."""

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[tuple, np.ndarray] = {}
            for batch in batches:
                kind = np.uint64 if last else np.uint16
                for *key, counts in zip(*[column_of(batch, c).to_pylist() for c in (*by, "counts")], strict=True):
                    own = np.frombuffer(counts, kind).astype(np.uint64)
                    sums[tuple(key)] = sums[tuple(key)] + own if tuple(key) in sums else own
            if sums:
                coded = [np.minimum(4 * np.log2(1.0 + s), 255).astype(np.uint8) if last else s for s in sums.values()]
                keys = {c: pa.array([k[i] for k in sums], pa.int32()) for i, c in enumerate(by)}
                yield records(**keys, counts=pa.array([c.tobytes() for c in coded], pa.binary()))

        return rows.select(*by, "counts").repartition(*by).mapInArrow(add, "".join(f"{c} int, " for c in by) + "counts binary")

    lots = added(surveyed.where("slice is not null"), "slice", "lot", last=False)
    rows = added(lots, "slice", last=True).collect()
    codes = np.zeros((_COUNT_SLICES, (1 << _COUNT_BITS) // _COUNT_SLICES), np.uint8)
    for r in rows:
        codes[r["slice"]] = np.frombuffer(r["counts"], np.uint8)
    return codes.ravel()


def _prefix_rows(docs: DataFrame, codes: Callable[[], np.ndarray], n: int, percent: int) -> DataFrame:
    """gram, s1, id, n: the first order's prefixes. A task gives each set once; copies in one task are merged before the shuffle."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            for part in byte_slices(batch, "body") if batch.num_rows else ():
                grams, s1, of, sizes = [], [], [], []
                for i, own in enumerate(gram_sets(column_of(part, "body"), n)):
                    total = int(np.sum(mix64(own ^ np.uint64(0x0123456789ABCDEF)), dtype=np.uint64)) if len(own) else 0
                    if len(own) and total not in seen:
                        if len(seen) < 200_000:
                            seen.add(total)
                        head = prefix(own, codes(), 0, percent)
                        grams.append(head)
                        s1.append(np.full(len(head), total, np.uint64))
                        of.append(np.full(len(head), i))
                        sizes.append(np.full(len(head), len(own), np.int32))
                if grams:
                    yield records(gram=signed(np.concatenate(grams)), s1=signed(np.concatenate(s1)), id=column_of(part, "id").take(pa.array(np.concatenate(of))), n=np.concatenate(sizes))
        give_back()

    return docs.mapInArrow(rows, f"gram long, s1 long, id {dict(docs.dtypes)['id']}, n int")


def least_shared(a: Column, b: Column, percent: int) -> Column:
    """How many n-grams the prefixes of linked sets of sizes a and b share at least. All n-grams that both sets have, but for those shared
    by the prefixes, lie behind the prefix that ends first in the order, so they are at most as many as that set has behind its prefix."""
    behind = lambda n: F.ceil(n * percent / 100) - 1
    return F.greatest(F.ceil((a + b) * percent / (100 + percent)) - F.greatest(behind(a), behind(b)), F.lit(1))


def _group_edges(shared: DataFrame, percent: int, *, pairs: bool) -> DataFrame:
    """a, b, a_n, b_n from groups of sets with a common prefix n-gram. Input: gram, id, n with one row per set, sorted by gram, n and id.
    pairs: all pairs of fitting sizes, once for each common n-gram; else neighbours in size only."""
    kind = dict(shared.dtypes)["id"]

    def edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: pa.RecordBatch | None = None
        for batch in batches:
            if rest is not None:
                batch = pa.Table.from_batches([rest, batch]).combine_chunks().to_batches()[0]
            gram = column_of(batch, "gram").to_numpy()
            cut = int(np.searchsorted(gram, gram[-1], "left")) if len(gram) else 0
            if cut or pairs:
                rest = batch.slice(cut)
            else:  # a group longer than a batch: its chain goes on from its last row
                cut, rest = len(gram), batch.slice(max(len(gram) - 1, 0))
            if cut:
                yield from emit(batch.slice(0, cut))
        if rest is not None and rest.num_rows:
            yield from emit(rest)

    def emit(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        gram, n = column_of(batch, "gram").to_numpy(), column_of(batch, "n").to_numpy().astype(np.int64)
        ids = column_of(batch, "id")
        for step in range(1, len(gram) if pairs else 2):
            a = np.arange(len(gram) - step)
            a = a[gram[a] == gram[a + step]]
            if not len(a):
                break
            a = a[100 * n[a] >= percent * n[a + step]]
            yield records(a=ids.take(pa.array(a)), b=ids.take(pa.array(a + step)), a_n=pa.array(n[a], pa.int32()), b_n=pa.array(n[a + step], pa.int32()))

    return shared.mapInArrow(edges, f"a {kind}, b {kind}, a_n int, b_n int")


def _rarest(many: DataFrame, percent: int) -> DataFrame:
    """Of each set's n-grams in large groups, those that have to be looked at. Two sets that meet in large groups only share at least `least` of them; the first of these
    in one order of all n-grams has least - 1 behind it in either set, so it is among each one's first m - least + 1."""
    least = F.greatest(F.least(F.lit(SHARED), F.ceil(F.col("n") * percent / 100)), F.lit(1))
    own = Window.partitionBy("id")
    ranked = many.withColumn("nth", F.row_number().over(own.orderBy("size", "gram"))).withColumn("m", F.count(F.lit(1)).over(own))
    return ranked.where(F.col("nth") <= F.col("m") - least + 1).drop("nth", "m")


def _candidates(shared: DataFrame, percent: int, small: int) -> DataFrame:
    """a, b: edges that connect all sets that may link. Input: gram, id, n, and size, the number of sets with the gram."""
    dealt = lambda rows: rows.select("gram", "id", "n").repartition("gram").sortWithinPartitions("gram", "n", "id")
    few, many = shared.where(F.col("size") <= small), _rarest(shared.where(F.col("size") > small), percent)
    common = shared.where(F.col("size") > small).groupBy("id").agg(F.count(F.lit(1)).alias("common"))
    pairs = _group_edges(dealt(few), percent, pairs=True).groupBy("a", "b", "a_n", "b_n").agg(F.count(F.lit(1)).alias("met"))
    for side in "ab":
        pairs = pairs.join(common.select(F.col("id").alias(side), F.col("common").alias(f"{side}_common")), side, "left")
    more = F.least(F.coalesce("a_common", F.lit(0)), F.coalesce("b_common", F.lit(0)))
    met = pairs.where(F.col("met") + more >= least_shared(F.col("a_n"), F.col("b_n"), percent))
    return met.select("a", "b").unionByName(_group_edges(dealt(many), percent, pairs=False).select("a", "b"))


def linked_pairs(sets: list[np.ndarray], codes: np.ndarray, percent: int, orders: int, pairs: np.ndarray | None = None) -> np.ndarray:
    """All linked pairs (i < j) of some sets: sizes and every order's filter first, then exact intersections."""
    n = np.array([len(s) for s in sets])
    near = np.triu(100 * np.minimum.outer(n, n) >= percent * np.maximum.outer(n, n), 1)
    if pairs is not None:
        near &= pairs
    for order in range(orders):
        if not near.any():
            break
        near &= _overlaps([prefix(s, codes, order, percent) for s in sets]) > 0
    i, j = np.nonzero(near)
    if not len(i):
        return np.zeros((0, 2), np.int64)
    if len(i) > 8 * len(sets):
        both = _overlaps(sets)[i, j].astype(np.int64)
    else:
        both = np.array([len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for a, b in zip(i.tolist(), j.tolist(), strict=True)])
    return np.column_stack([i, j])[100 * both >= percent * (n[i] + n[j] - both)]


def _overlaps(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections, by products of slices of the incidence matrix of n-grams in two sets or more."""
    every = np.concatenate(sets)
    row = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    values, column, times = np.unique(every, return_inverse=True, return_counts=True)
    number = np.cumsum(times > 1) - 1
    held = times[column] > 1
    row, column = row[held], number[column[held]]
    out = np.zeros((len(sets), len(sets)), np.float32)
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    for lo in range(0, int(number[-1]) + 1 if len(number) else 0, 2048):
        a, b = np.searchsorted(column, [lo, lo + 2048])
        part = np.zeros((len(sets), 2048), np.float32)
        part[row[a:b], column[a:b] - lo] = 1
        out += part @ part.T
    return out


def forest(pairs: np.ndarray, n: int) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the pairs."""
    parent = list(range(n))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    for i, j in pairs.tolist():
        a, b = root(i), root(j)
        if a != b:
            parent[max(a, b)] = min(a, b)
            out.append((i, j))
    return out


def _links(tasks: DataFrame, codes: Callable[[], np.ndarray], percent: int, orders: int) -> DataFrame:
    """a, b: spanning forests of the links in each task. Input: cluster, i, j (the task), part (which block of its two), id and grams, sorted by task."""
    kind = dict(tasks.dtypes)["id"]

    def edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, ids, parts, sets, out = None, [], [], [], []

        def close() -> None:
            if len(sets) > 1:
                own = np.array(parts)
                across = own[:, None] != own[None, :] if key[1] != key[2] else None  # pairs inside a block belong to the block's own task
                out.extend((ids[a], ids[b]) for a, b in forest(linked_pairs(sets, codes(), percent, orders, across), len(sets)))
            for x in (ids, parts, sets):
                x.clear()

        def ready() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array([e[k] for e in out]) for k in (0, 1)], names=["a", "b"])
            out.clear()
            return batch

        for batch in batches:
            for *task, part, one, grams in zip(*[column_of(batch, c).to_pylist() for c in ("cluster", "i", "j", "part", "id", "grams")], strict=True):
                if task != key:
                    close()
                    key = task
                    if len(out) > 10_000:
                        yield ready()
                ids.append(one)
                parts.append(part)
                sets.append(np.frombuffer(grams, np.uint64))
        close()
        if out:
            yield ready()
        give_back()

    return tasks.mapInArrow(edges, f"a {kind}, b {kind}")


def near_copies(df: DataFrame, *, n: int = 3, percent: int = 90, orders: int = 3, block: int = 600, small: int = _SMALL, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_shingles and component_id (the smallest key reachable by links) of every row.

    n: words of an n-gram; percent: the least similarity; orders: filters that are intersected; block: sets of a cluster that a task takes from one side;
    small: sets of a group up to which its pairs are counted.
    """
    small_batches(df.sparkSession)
    every = df.select(F.col(key).alias("id"), F.col(text).alias("body"))
    docs = every.where(F.col("id").isNotNull())
    kind = dict(docs.dtypes)["id"]
    surveyed = written(_survey(docs, n), "survey")
    shared_codes = df.sparkSession.sparkContext.broadcast(_codes(surveyed))
    codes = lambda: shared_codes.value
    known = surveyed.where("slice is null").select("id", "n", "s1", "s2")
    firsts = known.where("n > 0").groupBy("s1", "s2").agg(F.min("id").alias("rep"))
    whose = written(known.where("n > 0").join(firsts, ["s1", "s2"]).select("id", "n", "rep"), "representatives")

    by_gram = Window.partitionBy("gram")
    rows = _prefix_rows(docs, codes, n, percent).withColumn("lo", F.min("s1").over(by_gram)).withColumn("hi", F.max("s1").over(by_gram)).where("lo < hi")
    sets_once = rows.groupBy("gram", "s1").agg(F.min("id").alias("id"), F.first("n").alias("n"))
    shared = written(sets_once.select("gram", "id", "n", F.count(F.lit(1)).over(by_gram).alias("size")), "shared-prefixes")
    clusters = written(components(_candidates(shared, percent, small)), "clusters")

    members = clusters.join(whose.select(F.col("id").alias("v"), "rep"), "v").groupBy("v", "root").agg(F.min("rep").alias("rep"))
    sizes = clusters.groupBy("root").agg(F.count(F.lit(1)).alias("size"))
    placed = members.join(sizes, "root").withColumn("blocks", F.ceil(F.col("size") / block).cast("int")).withColumn("part", F.pmod(F.xxhash64("v"), F.col("blocks")).cast("int"))
    bodies = docs.join(placed.select(F.col("v").alias("id"), "rep", F.col("root").alias("cluster"), "blocks", "part"), "id")

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = pa.array([s.tobytes() for s in gram_sets(column_of(batch, "body"), n)], pa.binary())
        return records(id=column_of(batch, "rep"), cluster=column_of(batch, "cluster"), blocks=column_of(batch, "blocks"), part=column_of(batch, "part"), grams=sets)

    sets = map_texts(bodies, step, f"id {kind}, cluster {kind}, blocks int, part int, grams binary", text="body")
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    tasks = sets.select("*", other.alias("o")).select("cluster", F.least("part", "o").alias("i"), F.greatest("part", "o").alias("j"), "part", "id", "grams")
    links = _links(tasks.repartition("cluster", "i", "j").sortWithinPartitions("cluster", "i", "j"), codes, percent, orders)
    roots = components(links)

    placed_rows = whose.join(roots.withColumnRenamed("v", "rep"), "rep", "left").select("id", F.col("n").cast("long").alias("n_shingles"), F.coalesce("root", "rep").alias("component_id"))
    alone = known.where("n = 0").select("id", F.lit(0).cast("long").alias("n_shingles"), F.col("id").alias("component_id"))
    out = placed_rows.unionByName(alone)
    nulls = every.where(F.col("id").isNull())

    def unnamed(batch: pa.RecordBatch) -> pa.RecordBatch:
        return records(id=column_of(batch, "id"), n_shingles=pa.array([len(s) for s in gram_sets(column_of(batch, "body"), n)], pa.int64()), component_id=column_of(batch, "id"))

    return out.unionByName(map_texts(nulls, unnamed, f"id {kind}, n_shingles long, component_id {kind}", text="body")).withColumnRenamed("id", key)
