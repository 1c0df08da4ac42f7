"""Benchmark passages in documents: SimHash windows, multi-index Hamming lookup, exact verification.

A benchmark item of n words is looked for in every window of n words of every document, words being runs of
letters and digits in lower case. Item and window are compared by their shingles of five words (the whole
sequence, if shorter), weighted by how often they occur: the sum of the smaller weights over the sum of the larger ones.
From a similarity of 0.8 on, the document holds the item.

Each item and window has a 128-bit SimHash of its weighted shingles, in four blocks of 32 bits. Block b of a pair may differ in t_b bits,
where the sum of t_b + 1 exceeds the radius, so that some block of every pair within the radius is within its share, and none is missed; of
unrelated pairs one in twenty passes a block. Equal-sized sets with similarity 0.8 differ in 19.4 bits on average, with a
standard deviation of 4.1; the radius of 40 bits lies five deviations above, and radius=128 misses nothing. Pairs within the radius are then compared exactly.

A document of fewer words than an item is one window, compared exactly whatever its fingerprint.

A window is compared with the items that it shares a shingle with; with all others its similarity is 0. Nothing is shuffled: items
are a stated query set, taken in blocks of bounded size. Each block goes over all documents and is written before the next is read, so the driver holds one at a time.

Defined results: null and empty texts hold nothing; items without words are found nowhere; items with equal words are found
together; repeated document rows give repeated rows; of several windows the most similar counts, then the first.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from symseek.llm.common import ALNUM_WORD, Words, column_of, map_texts, mix64, records, run_hashes, words_of, written

SHINGLE = 5
RADIUS = 40
_BYTES, _BLOCKS = 16, 4
_SIEVE_BITS = 20


def block_radii(radius: int, blocks: int = _BLOCKS) -> list[int]:
    """The bits that each block may differ in, so that some block is within its share whenever all bits together are within the radius."""
    whole, rest = divmod(radius + 1, blocks)
    return [whole - 1 + (b < rest) for b in range(blocks)]


def simhash(shingles: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    """128-bit fingerprints, as 16 bytes each, of the runs of `length` shingles from each start."""
    halves = np.column_stack([mix64(shingles), mix64(shingles ^ np.uint64(0xA5A5A5A5DEADBEEF))])
    bits = np.unpackbits(halves.view(np.uint8), axis=1).astype(np.int32) * 2 - 1
    sums = np.zeros((len(bits) + 1, 8 * _BYTES), np.int32)
    np.cumsum(bits, axis=0, out=sums[1:])
    return np.packbits(sums[starts + length] - sums[starts] > 0, axis=1)


def window_prints(grams: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    """simhash of sorted starts that may lie far apart: their own stretches only."""
    out, parts = np.zeros((len(starts), _BYTES), np.uint8), [(0, len(starts))] if len(starts) else []
    while parts:
        a, b = parts.pop()
        lo, hi = int(starts[a]), int(starts[b - 1]) + length
        if b - a > 4096 or (b - a > 1 and hi - lo > 65536):
            parts += [(a, (a + b) // 2), ((a + b) // 2, b)]
        else:
            out[a:b] = simhash(grams[lo:hi], starts[a:b] - lo, length)
    return out


@dataclass
class Item:
    """An item: its place in the block of items, its shingles with their weights, and its fingerprint."""

    number: int
    words: int
    weights: Counter
    prints: np.ndarray

    @property
    def shingles(self) -> int:
        return self.weights.total()


class ItemIndex:
    """The items of a block: which hold a shingle, and which fingerprints are near."""

    def __init__(self, ids: list, texts: list[str | None], radius: int = RADIUS):
        self.ids, self.radius = ids, radius
        self.radii = np.array(block_radii(radius))
        w = words_of(pc.utf8_lower(pa.array(texts, pa.string())), ALNUM_WORD)
        self.items: list[Item] = []
        holders: dict[int, dict[int, list[int]]] = defaultdict(lambda: defaultdict(list))
        for i, (a, b) in enumerate(zip(w.first[:-1].tolist(), w.first[1:].tolist(), strict=True)):
            if b > a:
                width = min(SHINGLE, b - a)
                h = run_hashes(w.hashes[a:b], width)
                for x in set(h.tolist()):
                    holders[width][x].append(len(self.items))
                self.items.append(Item(i, b - a, Counter(h.tolist()), simhash(h, np.array([0]), len(h))))
        self.words = np.array([x.words for x in self.items], np.int64)
        self.shingles = np.array([x.shingles for x in self.items], np.int64)
        self.prints = np.concatenate([x.prints for x in self.items]) if self.items else np.zeros((0, _BYTES), np.uint8)
        #: for each width: its shingles in order, where the items of each begin, the items, and a sieve of the shingles' first bits
        self.known = {}
        for width, table in holders.items():
            values = np.array(sorted(table), np.uint64)
            offsets = np.cumsum([0, *[len(table[x]) for x in values.tolist()]])
            sieve = np.zeros(1 << _SIEVE_BITS, bool)
            sieve[(values >> np.uint64(64 - _SIEVE_BITS)).astype(np.int64)] = True
            self.known[width] = (values, offsets, np.array([i for x in values.tolist() for i in table[x]]), sieve)

    def near(self, prints: np.ndarray, items: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of pairs of a window's fingerprint and an item: which are within the radius, and their bits apart. Blocks first, all bits of what passes."""
        apart = np.bitwise_count(prints.view(np.uint32) ^ self.prints[items].view(np.uint32))
        some = np.flatnonzero((apart <= self.radii).any(1))
        bits = apart[some].sum(1, dtype=np.int64)
        close = bits <= self.radius
        return some[close], bits[close]

    def search(self, w: Words, threshold: float) -> list[tuple[int, int, float, int, int, int]]:
        """(text, item, similarity, bits apart, first word, words) of every item that each text holds."""
        best: dict[tuple[int, int], tuple] = {}
        for width, (values, offsets, holders, sieve) in self.known.items():
            grams = run_hashes(w.hashes, width)
            hits = np.flatnonzero(sieve[(grams >> np.uint64(64 - _SIEVE_BITS)).astype(np.int64)])
            place = np.minimum(np.searchsorted(values, grams[hits]), len(values) - 1)
            found = values[place] == grams[hits]
            hits, place = hits[found], place[found]
            text = np.searchsorted(w.first, hits, "right") - 1
            inside = hits + width <= w.first[text + 1]
            hits, place, text = hits[inside], place[inside], text[inside]
            # each place of a shingle with each item that holds it, and the windows of the item's size around it
            times = offsets[place + 1] - offsets[place]
            item = holders[np.repeat(offsets[place], times) + np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)]
            at, text = np.repeat(hits, times), np.repeat(text, times)
            low, high = np.maximum(w.first[text], at - self.shingles[item] + 1), np.minimum(at, w.first[text + 1] - self.words[item])
            short = w.first[text + 1] - w.first[text] < self.words[item]
            for i, one in {*zip(text[short].tolist(), item[short].tolist(), strict=True)}:
                self._compare_short(i, one, grams, int(w.first[i]), int(w.first[i + 1]), width, threshold, best)
            for one in np.unique(item[~short]).tolist():
                own = np.flatnonzero(~short & (item == one))
                self._compare(one, windows(low[own], high[own]), grams, w, threshold, best)
        return [(i, self.items[one].number, -s, bits, at - int(w.first[i]), n) for (i, one), (s, at, bits, n) in sorted(best.items())]

    def _compare(self, one: int, starts: np.ndarray, grams: np.ndarray, w: Words, threshold: float, best: dict) -> None:
        item = self.items[one]
        near, bits = self.near(window_prints(grams, starts, item.shingles), np.full(len(starts), one))
        text = np.searchsorted(w.first, starts[near], "right") - 1
        for i, at, apart in zip(text.tolist(), starts[near].tolist(), bits.tolist(), strict=True):
            own = Counter(grams[at : at + item.shingles].tolist())
            both = sum(min(c, item.weights[x]) for x, c in own.items() if x in item.weights)
            similarity = both / (2 * item.shingles - both)
            if similarity >= threshold:
                best[i, one] = min(best.get((i, one), (1,)), (-similarity, at, apart, item.words))

    def _compare_short(self, i: int, one: int, grams: np.ndarray, at: int, end: int, width: int, threshold: float, best: dict) -> None:
        """A text of fewer words than the item: one window."""
        item, count = self.items[one], end - at - width + 1
        if count / item.shingles < threshold:  # more than that can't be shared
            return
        own = Counter(grams[at : at + count].tolist())
        both = sum(min(c, item.weights[x]) for x, c in own.items() if x in item.weights)
        similarity = both / (count + item.shingles - both)
        if similarity >= threshold:
            bits = int(np.bitwise_count(simhash(grams[at : at + count], np.array([0]), count) ^ item.prints).sum())
            best[i, one] = (-similarity, at, bits, end - at)


def windows(low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """All numbers of some ranges low .. high, each once, in order. low is sorted, and so is high."""
    begin = np.maximum(low, np.append(-1, np.maximum.accumulate(high)[:-1]) + 1)
    sizes = np.maximum(high - begin + 1, 0)
    return np.repeat(begin, sizes) + np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)


def find_items(docs: DataFrame, items: DataFrame, *, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", threshold: float = 0.8, radius: int = RADIUS, block_bytes: int = 8 << 20) -> DataFrame:
    """key, item, similarity, bits_apart, first_word, n_words for every item that a document holds.

    Items go to the executors in blocks of about block_bytes of text, each over all documents.
    """
    if not 0 < threshold <= 1:
        raise ValueError("the threshold is over 0 and at most 1")
    asked = items.where(F.col(item_text).isNotNull()).select(F.col(item).alias("i"), F.col(item_text).alias("t"))
    total = asked.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    blocks = -(-total // block_bytes) or 1
    rows = docs.select(F.col(key).alias("k"), F.col(text).alias("body"))
    kinds = dict(rows.dtypes) | dict(asked.dtypes)
    parts = []
    for b in range(blocks):
        own = sorted(asked.where(F.pmod(F.xxhash64("t"), F.lit(blocks)) == b).collect(), key=lambda r: (str(r[0]), r[1]))
        shared = docs.sparkSession.sparkContext.broadcast(([r[0] for r in own], [r[1] for r in own]))
        found = _search(rows, shared, kinds, to_arrow_type(asked.schema["i"].dataType), threshold, radius)
        if blocks > 1:
            found = written(found, "held-items")
            shared.destroy()
        parts.append(found)
    return reduce(DataFrame.unionByName, parts).withColumnsRenamed({"k": key, "i": item})


def _search(rows: DataFrame, shared, kinds: dict[str, str], item_kind: pa.DataType, threshold: float, radius: int) -> DataFrame:
    built: list[ItemIndex] = []

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        if not built:
            built.append(ItemIndex(*shared.value, radius=radius))
        w = words_of(pc.utf8_lower(column_of(batch, "body")), ALNUM_WORD)
        of, *columns = list(zip(*built[0].search(w, threshold), strict=True)) or [()] * 6
        return records(
            k=column_of(batch, "k").take(pa.array(of, pa.int64())), i=pa.array([built[0].ids[x] for x in columns[0]], item_kind), similarity=pa.array(columns[1], pa.float64()),
            bits_apart=pa.array(columns[2], pa.int32()), first_word=pa.array(columns[3], pa.int64()), n_words=pa.array(columns[4], pa.int32()),
        )

    return map_texts(rows, step, f"k {kinds['k']}, i {kinds['i']}, similarity double, bits_apart int, first_word long, n_words int", text="body")


def without_items(docs: DataFrame, items: DataFrame, *, key: str = "doc_id", **options) -> DataFrame:
    """The documents that hold no item, with all their columns. Documents with a null key stay."""
    found = find_items(docs, items, key=key, **options).select(key).distinct()
    return docs.join(found, key, "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])
