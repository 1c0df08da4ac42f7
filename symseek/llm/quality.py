"""Quality classification: histogram gradient-boosted trees over document statistics.

Statistics come from a document's bytes and words alone, for slices of documents at once. Training bins each
statistic into at most 64 quantile bins, grows trees of fixed depth from gradient histograms with a logistic
loss, and flattens them into arrays; scoring walks all trees of all rows of a slice level by level in numpy.

Training looks at a bounded sample of labelled rows (`sample`, by a hash of the key); only their statistics
reach the driver. Scoring covers every row's whole text.

Defined results: null and empty texts have all-zero statistics and a score as any other; repeated rows score
alike; labels that are null are left out; without labels, or with one class only, the score is the class's share
(0.5 without any).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from symseek.llm.common import PLAIN_WORD, column_of, list_array, map_texts, mix64, records, text_bytes, uniform, words_of

_CLASS = np.full(256, 6, np.int64)  # 0 lower, 1 upper, 2 digit, 3 space, 4 sentence marks, 5 other ASCII, 6 beyond ASCII
_CLASS[:0x80] = 5
_CLASS[list(b".,;:'\"()-")] = 4
_CLASS[list(b" \t\n\r\x0b\x0c")] = 3
_CLASS[0x30:0x3A] = 2
_CLASS[0x41:0x5B] = 1
_CLASS[0x61:0x7B] = 0
#: A document is accepted from this score on.
ACCEPT = 0.3
STATISTICS = (
    "log_bytes", "lower", "upper", "digit", "space", "mark", "other_ascii", "beyond_ascii", "log_words", "word_length", "word_spread",
    "distinct_words", "log_lines", "line_words", "repeated_lines", "symbol_words", "capital_words", "short_words", "long_words", "full_stops", "repeated_pairs", "top_symbol",
)


def _distinct(group: np.ndarray, value: np.ndarray, groups: int) -> np.ndarray:
    """How many different values (by 44 bits of their hashes) each group has."""
    both = np.sort(group.astype(np.uint64) << np.uint64(44) | value >> np.uint64(20))
    new = np.ones(len(both), bool)
    new[1:] = both[1:] != both[:-1]
    return np.bincount((both[new] >> np.uint64(44)).astype(np.int64), minlength=groups)


def statistics(column: pa.Array) -> np.ndarray:
    """One row of STATISTICS per text."""
    n = len(column)
    data, offsets = text_bytes(column)
    size = np.diff(offsets)
    row = np.repeat(np.arange(n), size)
    kind = _CLASS[data]
    share = np.bincount(row * 7 + kind, minlength=7 * n).reshape(n, 7) / np.maximum(size, 1)[:, None]

    w = words_of(column, PLAIN_WORD)
    words = w.counts()
    some = np.maximum(words, 1)
    of = np.repeat(np.arange(n), words)
    length = (w.ends - w.starts).astype(np.float64)
    total = lambda x: np.bincount(of, weights=x, minlength=n)
    mean = total(length) / some
    spread = np.sqrt(np.maximum(total(length**2) / some - mean**2, 0))
    symbols = np.zeros(len(data) + 1, np.int64)
    np.cumsum(kind == 5, out=symbols[1:])
    capitals = np.zeros(len(data) + 1, np.int64)
    np.cumsum(kind == 1, out=capitals[1:])
    in_word = lambda c: c[w.ends] - c[w.starts]
    pair = np.arange(max(len(of) - 1, 0))
    pair = pair[of[pair] == of[pair + 1]] if len(pair) else pair
    pairs = np.bincount(of[pair], minlength=n)
    new_pairs = _distinct(of[pair], mix64(w.hashes[pair] * np.uint64(31) + w.hashes[pair + 1]), n)

    lines = words_of(column, np.arange(256) != 0x0A)
    line_count = lines.counts()
    line_of = np.repeat(np.arange(n), line_count)
    new_lines = _distinct(line_of, lines.hashes, n)
    last = data[w.ends - 1] if len(w.ends) else np.zeros(0, np.uint8)
    odd = np.bincount(row[kind == 5] * 128 + data[kind == 5], minlength=128 * n).reshape(n, 128).max(1) if n else np.zeros(0)
    return np.column_stack([
        np.log1p(size), *share.T, np.log1p(words), mean, spread,
        _distinct(of, w.hashes, n) / some, np.log1p(line_count), words / np.maximum(line_count, 1), 1 - np.where(line_count, new_lines, 1) / np.maximum(line_count, 1),
        total(in_word(symbols) > 0) / some, total((in_word(capitals) == length) & (length > 1)) / some, total(length <= 2) / some, total(length >= 12) / some,
        total(np.isin(last, list(b".!?"))) / some, 1 - np.where(pairs, new_pairs, 1) / np.maximum(pairs, 1), odd / some,
    ]).astype(np.float32)


@dataclass
class TreeArrays:
    """All trees, each complete to the same depth: node i of a tree has the children 2i + 1 and 2i + 2."""

    depth: int
    base: float
    feature: np.ndarray  # tree x inner node
    threshold: np.ndarray  # go right where the statistic is larger
    leaf: np.ndarray  # tree x leaf

    def score(self, x: np.ndarray) -> np.ndarray:
        trees = np.arange(len(self.feature))
        raw = np.full(len(x), self.base)
        for at in range(0, len(x), 4096):
            part = x[at : at + 4096]
            node = np.zeros((len(part), len(trees)), np.int64)
            for _ in range(self.depth if len(trees) else 0):
                value = np.take_along_axis(part, self.feature[trees, node], axis=1)
                node = 2 * node + 1 + (value > self.threshold[trees, node])
            if len(trees):
                raw[at : at + 4096] += self.leaf[trees, node - (2**self.depth - 1)].sum(1)
        return 1 / (1 + np.exp(-raw))


def fit(x: np.ndarray, y: np.ndarray, *, trees: int = 120, depth: int = 4, rate: float = 0.1, bins: int = 64, least: float = 5.0, damping: float = 1.0) -> TreeArrays:
    """Gradient boosting on binned statistics. `least`: the smallest sum of second derivatives in a leaf."""
    empty = TreeArrays(depth, 0.0, np.zeros((0, 2**depth - 1), np.int64), np.zeros((0, 2**depth - 1), np.float32), np.zeros((0, 2**depth)))
    if not len(y) or y.min() == y.max():
        mean = min(max(float(y.mean()), 1e-3), 1 - 1e-3) if len(y) else 0.5
        empty.base = float(np.log(mean / (1 - mean)))
        return empty
    n, features = x.shape
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1]).astype(np.float32)) for f in range(features)]
    binned = np.column_stack([np.searchsorted(e, x[:, f], "left") for f, e in enumerate(edges)])
    base = float(np.log(y.mean() / (1 - y.mean())))
    raw = np.full(n, base)
    inner, leaves = 2**depth - 1, 2**depth
    feature, threshold, leaf = np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf, np.float32), np.zeros((trees, leaves))
    for t in range(trees):
        p = 1 / (1 + np.exp(-raw))
        g, h = p - y, p * (1 - p)
        node = np.zeros(n, np.int64)
        for level in range(depth):
            nodes = 2**level
            local = node - (nodes - 1)
            gain = np.full((nodes, features, bins), -np.inf)
            for f in range(features):
                at = local * bins + binned[:, f]
                gs = np.bincount(at, g, nodes * bins).reshape(nodes, bins).cumsum(1)
                hs = np.bincount(at, h, nodes * bins).reshape(nodes, bins).cumsum(1)
                gt, ht = gs[:, -1:], hs[:, -1:]
                value = gs**2 / (hs + damping) + (gt - gs) ** 2 / (ht - hs + damping) - gt**2 / (ht + damping)
                gain[:, f] = np.where((hs >= least) & (ht - hs >= least), value, -np.inf)
            flat = gain.reshape(nodes, -1)
            best = flat.argmax(1)
            for k in np.flatnonzero(flat[np.arange(nodes), best] > 1e-6):
                f, b = divmod(int(best[k]), bins)
                if b < len(edges[f]):
                    feature[t, nodes - 1 + k], threshold[t, nodes - 1 + k] = f, edges[f][b]
            node = 2 * node + 1 + (x[np.arange(n), feature[t, node]] > threshold[t, node])
        at = node - inner
        leaf[t] = -rate * np.bincount(at, g, leaves) / (np.bincount(at, h, leaves) + damping)
        raw += leaf[t, at]
    return TreeArrays(depth, base, feature, threshold, leaf)


def train(docs: DataFrame, labels: DataFrame, usable: Column, *, key: str = "doc_id", text: str = "text", label: str = "quality", sample: int = 20_000, **options) -> TreeArrays:
    """Fit on labelled rows where `usable` (of the key) holds; at most about `sample` of them."""
    marked = labels.where(usable & F.col(label).isNotNull()).select(F.col(key).alias("k"), F.col(label).cast("int").alias("y"))
    n = marked.count()
    some = marked.where(uniform(F.col("k"), 2) < F.lit(min(1.0, sample / max(n, 1))))  # its size is bounded by `sample`, so it may be broadcast
    rows = docs.select(F.col(key).alias("k"), F.col(text).alias("body")).join(F.broadcast(some), "k")

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        x = statistics(column_of(batch, "body"))
        return records(k=column_of(batch, "k"), y=column_of(batch, "y"), x=list_array(x.ravel(), np.full(len(x), x.shape[1])))

    got = map_texts(rows, step, f"k {dict(rows.dtypes)['k']}, y int, x array<float>", text="body").toArrow()
    x = np.asarray(got["x"].combine_chunks().flatten()).reshape(-1, len(STATISTICS)) if len(got) else np.zeros((0, len(STATISTICS)), np.float32)
    y = got["y"].to_numpy().astype(np.float64)
    order = np.lexsort((y, *x.T)) if len(y) else np.zeros(0, int)  # the same sums, whatever order the rows came in
    return fit(x[order], y[order], **options)


def score(df: DataFrame, model: TreeArrays, *, key: str = "doc_id", text: str = "text", keep: dict[str, Column] | None = None, text_as: str | None = None) -> DataFrame:
    """key, the columns of `keep`, the text under the name text_as if given, and score (0 to 1) for every row."""
    keep = keep or {}
    names_kept = list(keep)
    rows = df.select(F.col(key).alias("k"), *[c.alias(n) for n, c in keep.items()], F.col(text).alias("body"))
    shared = df.sparkSession.sparkContext.broadcast(model)

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        own = {n: column_of(batch, n) for n in names_kept} | ({text_as: column_of(batch, "body")} if text_as else {})
        return records(k=column_of(batch, "k"), **own, score=shared.value.score(statistics(column_of(batch, "body"))))

    kinds = dict(rows.dtypes)
    schema = ", ".join([f"k {kinds['k']}", *[f"`{n}` {kinds[n]}" for n in keep], *[f"`{text_as}` string"] * bool(text_as), "score double"])
    return map_texts(rows, step, schema, text="body").withColumnRenamed("k", key)
