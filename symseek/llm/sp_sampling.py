"""Encoding and decoding with a SentencePiece vocabulary, and sampled segmentations without replacement.

`encode` and `decode` are the library's own. `sample` draws k different segmentations of each whole text by
Gumbel top-k: every segmentation's log-probability is perturbed by a Gumbel draw, and the k largest
are wanted, largest first. They are found by A-star search with a queue of sets of segmentations, each with the
largest perturbed value in it, which is drawn from the set's total probability alone:

* The lattice of a text is a chain of unit lattices, since no piece has a space mark behind another character; a unit
  is a run of space marks with the characters up to the next one, or a line feed. Sums over all segmentations
  come from the unit lattices by backward recursion.
* Taking a set off the queue draws its best segmentation along the chain. What is left of the set splits into the
  segmentations that leave this path at its first, second, ... edge. Each part has a known probability, and its largest
  perturbed value is a Gumbel draw truncated at the value just taken. The parts go into the queue.

The inclusion score of a segmentation is its probability of being among the k, given the next perturbed value in the queue.

Weights: a BPE vocabulary has merge ranks but no probabilities. A piece of rank r gets the weight
(r + 3) ** -(1 / temperature), after Zipf's law; a character outside the vocabulary is spelled in byte pieces with the last rank's weight.

All draws follow from the row's key, so a row gets the same segmentations wherever and however often it is computed.

Defined results: a null or empty text has one segmentation, the empty one, with inclusion 1; a text with fewer than k
segmentations gives them all, with inclusion 1, but for those that rounding can't tell from nothing: parts of a set with less than e**-60 of its
probability, or an edge's remainder below 1e-12, aren't queued; repeated keys with equal texts get equal rows; a null key is a key of its own.
"""

from __future__ import annotations

import heapq
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from symseek.llm.common import column_of, list_array, map_texts, mix64, records

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
_SLICE = 1 << 19
_SLOTS = 21
_SIEVE = (1 << 19) - 1
_UNITS = re.compile(f"{SPACE}*[^{SPACE}\n]+|{SPACE}+|\n")


@lru_cache(maxsize=2)
def _library(model: str):
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=model)


@dataclass
class Vocabulary:
    """Pieces by the hash of their characters, in two open tables behind a small sieve, with log-weights and the bytes they stand for.

    The sieve has bit 1 where a piece may be and bit 2 where the beginning of a longer piece may be.
    """

    ids: list[np.ndarray]
    keys: list[np.ndarray]
    sieve: np.ndarray
    weight: np.ndarray
    byte_base: int
    byte_weight: float
    spelled: list[bytes]
    longest: int  # characters of the longest piece

    def marks(self, hashes: np.ndarray) -> np.ndarray:
        return self.sieve[_sieve_slots(hashes)]

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """The piece with each hash, or -1."""
        found = np.full(len(hashes), -1, np.int32)
        for shift, ids, keys in zip((64 - _SLOTS, 20), self.ids, self.keys, strict=True):
            slot = (hashes >> np.uint64(shift)).astype(np.int64) & (1 << _SLOTS) - 1
            hit = keys[slot] == hashes
            found[hit] = ids[slot[hit]]
        return found


def _sieve_slots(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(2)).astype(np.int64) & _SIEVE


@lru_cache(maxsize=2)
def vocabulary(model: str, temperature: float) -> Vocabulary:
    lib = _library(model)
    size = lib.get_piece_size()
    spelled, usable, byte_base = [b""] * size, [], None
    for i in range(size):
        piece = lib.id_to_piece(i)
        if lib.is_byte(i):
            byte_base = i if byte_base is None else byte_base
            spelled[i] = bytes([i - byte_base])
        elif not lib.is_control(i) and not lib.is_unknown(i):
            spelled[i] = piece.replace(SPACE, " ").encode()
            usable.append((i, piece))
    codes = np.frombuffer("".join(p for _, p in usable).encode("utf-32-le"), np.uint32)
    sizes = np.array([len(p) for _, p in usable])
    begins = np.cumsum(sizes) - sizes
    raw, sieve = np.zeros(len(sizes), np.uint64), np.zeros(_SIEVE + 1, np.uint8)
    for length in range(1, int(sizes.max()) + 1):
        own = np.flatnonzero(sizes >= length)
        raw[own] = longer_hashes(raw[own], codes[begins[own] + (length - 1)])
        sieve[_sieve_slots(mix64(raw[sizes > length] + np.uint64(length)))] |= 2
    hashes = mix64(raw + sizes.astype(np.uint64))
    rest = list(zip([i for i, _ in usable], hashes, strict=True))
    ids, keys = [], []
    for shift in (64 - _SLOTS, 20):
        table, key, left = np.full(1 << _SLOTS, -1, np.int32), np.zeros(1 << _SLOTS, np.uint64), []
        for i, h in rest:
            slot = int(h) >> shift & (1 << _SLOTS) - 1
            if table[slot] < 0:
                table[slot], key[slot] = i, h
            else:
                left.append((i, h))
        ids, keys, rest = [*ids, table], [*keys, key], left
    if rest or byte_base is None:
        raise ValueError("this vocabulary has no byte pieces or doesn't fit the tables")
    sieve[_sieve_slots(hashes)] |= 1
    rank = np.maximum(np.arange(size) - (byte_base + 256), 0)
    weight = -np.log(rank + 3.0) / temperature
    return Vocabulary(ids, keys, sieve, weight, byte_base, float(weight.min()), spelled, int(sizes.max()))


def units_of(text: str) -> list[str]:
    """The text's units, with the space mark that stands before every text."""
    if "  " in text or SPACE in text or text.startswith(" "):
        return _UNITS.findall(SPACE + text.replace(" ", SPACE))
    return [u for u in (SPACE + text.replace(" ", " " + SPACE).replace("\n", " \n ")).split(" ") if u]


class Lattices:
    """The lattices of different units, side by side.

    A node is a place in a unit, numbered by its distance `left` to the unit's end, so that a unit's end comes before
    all that leads to it. Node v has the edges first[v] .. first[v + 1] - 1: a piece each, and the node that follows.
    """

    def __init__(self, units: list[str], v: Vocabulary):
        codes = np.frombuffer("\0".join([*units, ""]).encode("utf-32-le"), np.uint32)
        sizes = np.array([len(u) for u in units], np.int64)
        begin = np.cumsum(sizes + 1) - sizes - 1
        n = len(codes)
        left = np.repeat(begin + sizes, sizes + 1) - np.arange(n)
        sources, pieces, weights, targets = [], [], [], []
        single = np.zeros(n, bool)
        at = np.flatnonzero(left)
        raw = np.zeros(len(at), np.uint64)
        for length in range(1, v.longest + 1):
            if not len(at):
                break
            raw = longer_hashes(raw, codes[at + (length - 1)])
            hashes = mix64(raw + np.uint64(length))
            mark = v.marks(hashes)
            some = np.flatnonzero(mark & 1)
            piece = v.find(hashes[some])
            hit = np.flatnonzero(piece >= 0)
            found, piece = at[some[hit]], piece[hit]
            if length == 1:
                single[found] = True
            sources.append(found)
            pieces.append(piece)
            weights.append(v.weight[piece])
            targets.append(found + length)
            longer = np.flatnonzero((mark & 2).view(bool) & (left[at] > length))
            at, raw = at[longer], raw[longer]
        bare = np.flatnonzero(~single & (left > 0))
        code = codes[bare].astype(np.int64)
        sources.append(bare)
        pieces.append(np.where(code < 0x80, v.byte_base + code, -2 - code).astype(np.int32))
        weights.append(v.byte_weight * (1 + (code >= 0x80) + (code >= 0x800) + (code >= 0x10000)))
        targets.append(bare + 1)
        order = np.argsort(left.astype(np.int16) if n and left.max() < 1 << 15 else left, kind="stable")
        number = np.empty(n, np.int64)
        number[order] = np.arange(n)
        self.left, self.start = left[order], number[begin]
        count = np.zeros(n, np.int64)
        for at in sources:
            count[at] += 1
        count = count[order]
        self.first = np.append(0, np.cumsum(count))
        self.piece, weight, self.target = np.empty(self.first[-1], np.int32), np.empty(self.first[-1]), np.empty(self.first[-1], np.int64)
        fill = self.first[number]
        for at, piece, w, to in zip(sources, pieces, weights, targets, strict=True):
            edge = fill[at]
            self.piece[edge], weight[edge], self.target[edge] = piece, w, number[to]
            fill[at] = edge + 1
        total = np.zeros(n)
        bounds = np.searchsorted(self.left, np.arange(1, int(self.left[-1]) + 2 if n else 1))
        for a, b in zip(bounds[:-1], bounds[1:], strict=True):  # from the units' ends to their starts
            if b > a:
                lo, hi = self.first[a], self.first[b]
                value = weight[lo:hi] + total[self.target[lo:hi]]
                cut = self.first[a:b] - lo
                top = np.maximum.reduceat(value, cut)
                total[a:b] = top + np.log(np.add.reduceat(np.exp(value - np.repeat(top, count[a:b])), cut))
        self.logp = weight + total[self.target] - np.repeat(total, count)
        share = np.cumsum(np.exp(self.logp))
        before = np.append(0.0, share)[self.first[:-1]]
        self.upto = share - np.repeat(before, count)  # the share of a node's edges up to this one
        self.upto[self.first[1:][count > 0] - 1] = 2.0

    def choose(self, node: np.ndarray, u: np.ndarray) -> np.ndarray:
        """An edge of each node, by its probability."""
        edge = self.first[node]
        beyond = np.flatnonzero(u >= self.upto[edge])
        while len(beyond):
            edge[beyond] += 1
            beyond = beyond[u[beyond] >= self.upto[edge[beyond]]]
        return edge


def longer_hashes(raw: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Hashes of strings with one more character each; 0 is that of the empty string."""
    return raw * np.uint64(0x5851F42D4C957F2D) + codes + np.uint64(1)


def _mixed(seed: np.ndarray, number) -> np.ndarray:
    return mix64(seed + np.atleast_1d(number).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(0x632BE59BD9B4E019))


def _uniforms(seed: np.ndarray, *numbers) -> np.ndarray:
    """Draws in (0, 1) that follow from a row's seed and some numbers."""
    h = seed
    for x in numbers:
        h = _mixed(h, x)
    return ((h >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)


@dataclass
class Draw:
    """One free draw of every unit of some texts, flat: the edges taken; unit u has first[u] .. first[u + 1] - 1."""

    edge: np.ndarray
    logp: np.ndarray
    first: np.ndarray


def draw_all(lattices: Lattices, unit: np.ndarray, seed: np.ndarray, number: np.ndarray, draw: int) -> Draw:
    """Draw a segmentation of each unit occurrence. unit: its lattice; seed, number: its text's seed and its place in the text."""
    order = np.argsort(unit, kind="stable")  # neighbours in memory read the same lattices
    node, who, steps = lattices.start[unit[order]], order, []
    base = mix64(mix64(seed + mix64(number.astype(np.uint64))) + np.uint64(draw + 1))[order]  # whatever the draw's number, no two units share draws
    length = np.zeros(len(unit), np.int64)
    while len(who):
        edge = lattices.choose(node, _uniforms(base, len(steps)))
        steps.append((who, edge))
        length[who] += 1
        node = lattices.target[edge]
        go = lattices.left[node] > 0
        who, node, base = who[go], node[go], base[go]
    first = np.zeros(len(unit) + 1, np.int64)
    np.cumsum(length, out=first[1:])
    edges = np.zeros(first[-1], np.int64)
    for k, (who, edge) in enumerate(steps):
        edges[first[who] + k] = edge
    return Draw(edges, lattices.logp[edges], first)


@dataclass
class Path:
    """A segmentation of a text: its edges, their log-probabilities, where each unit's edges begin, and its perturbed value."""

    edge: np.ndarray
    logp: np.ndarray
    first: np.ndarray
    perturbed: float


#: Parts of a set with less than e**-60 of its probability aren't queued: rounding loses more.
_FAINT = 60.0


class Search:
    """The A-star search over one text."""

    def __init__(self, lattices: Lattices):
        self.lattices = lattices
        self.paths: list[Path] = []
        self.queue: list[tuple[float, int, int, list[int] | None]] = []

    def next(self, draw: Draw, a: int, b: int, base: np.ndarray) -> tuple[Path, int, list[int]]:
        """Take the set with the largest perturbed value off the queue and draw its best path; where it leaves the old path; the edges taken there.

        `draw` gives the units behind that place, draws from `base` the rest of the unit it is in.
        """
        negative, source, j, used = heapq.heappop(self.queue)
        old, lattices = self.paths[source], self.lattices
        used = used or [int(old.edge[j])]
        unit = int(np.searchsorted(old.first, j, "right")) - 1
        node = int(np.searchsorted(lattices.first, old.edge[j], "right")) - 1
        u = _uniforms(base, np.arange(lattices.left[node])).tolist()
        new: list[int] = []
        while lattices.left[node] > 0:
            lo, hi = int(lattices.first[node]), int(lattices.first[node + 1])
            share = np.exp(lattices.logp[lo:hi])
            if not new:
                share[[x - lo for x in used]] = 0
            share = np.cumsum(share)
            new.append(lo + int(np.searchsorted(share, u[len(new)] * share[-1], "right")))
            node = int(lattices.target[new[-1]])
        lo, hi = draw.first[a + unit + 1], draw.first[b]
        path = Path(
            np.concatenate([old.edge[:j], new, draw.edge[lo:hi]]),
            np.concatenate([old.logp[:j], lattices.logp[new], draw.logp[lo:hi]]),
            np.concatenate([old.first[: unit + 1], draw.first[a + unit + 1 : b + 1] - lo + (j + len(new))]),
            -negative,
        )
        return path, j, [*used, new[0]]


def take(lattices: Lattices, taken: list[tuple[Search, Path, int, list[int] | None]], seeds: np.ndarray, k: int) -> None:
    """For each search, queue what is left of a set once `path` is taken: the parts that leave it at edge `since` or later. used: the edges taken at `since`.

    All searches have taken equally many paths. Only as much of a path is looked at as may hold parts of a set that are queued.
    """
    source = len(taken[0][0].paths)
    for search, path, _, _ in taken:
        search.paths.append(path)
    size, todo = 256, np.arange(len(taken))
    while len(todo):
        logp = np.zeros((len(todo), size))
        for row, i in zip(logp, todo, strict=True):
            _, path, since, _ = taken[i]
            part = path.logp[since : since + size]
            row[: len(part)] = part
        fall = np.cumsum(logp, axis=1)
        over = np.array([since + size >= len(path.logp) for _, path, since, _ in (taken[i] for i in todo)]) | (fall[:, -1] < -_FAINT)
        now, logp, fall = todo[over], logp[over], fall[over]
        todo, size = todo[~over], size * 2
        if not len(now):
            continue
        mass = fall - logp + np.log1p(-np.minimum(np.exp(logp), 1 - 1e-15))
        mass[logp > -1e-12] = -np.inf  # no other edge, or beyond the path's end
        sinces = np.array([taken[i][2] for i in now])
        for row, i in zip(mass, now, strict=True):
            _, path, since, used = taken[i]
            if used is not None:
                rest = -np.expm1(np.log(np.exp(lattices.logp[used]).sum()))
                row[0] = np.log(rest) if rest > 1e-12 else -np.inf
                row += path.logp[:since].sum()
        u = _uniforms(seeds[now][:, None], source + 1, sinces[:, None] + np.arange(mass.shape[1]))
        perturbed = np.array([taken[i][1].perturbed for i in now])[:, None]
        with np.errstate(divide="ignore", over="ignore"):
            value = mass - np.log(np.exp(mass - perturbed) - np.log(u))  # Gumbel draws, given that they are at most path.perturbed
        best = np.argpartition(-value, min(k, value.shape[1] - 1), axis=1)[:, : k + 1]
        for i, js, values in zip(now, best.tolist(), np.take_along_axis(value, best, 1).tolist(), strict=True):
            search, _, since, used = taken[i]
            for j, x in zip(js, values, strict=True):
                if x > -np.inf:
                    heapq.heappush(search.queue, (-x, source, since + j, used if j == 0 else None))


def top_k(lattices: Lattices, draws: list[Draw], first: np.ndarray, seeds: np.ndarray, k: int) -> list[tuple[list[Path], float]]:
    """For each text, whose units are first[i] .. first[i + 1] - 1 (one at least), the k segmentations with the largest perturbed values, and the next value."""
    d, searches, taken = draws[0], [Search(lattices) for _ in seeds], []
    largest = -np.log(-np.log(_uniforms(seeds, 0, 0)))
    for search, a, b, value in zip(searches, first[:-1], first[1:], largest.tolist(), strict=True):
        lo, hi = d.first[a], d.first[b]
        taken.append((search, Path(d.edge[lo:hi], d.logp[lo:hi], d.first[a : b + 1] - lo, value), 0, None))
    live = np.arange(len(searches))
    while len(live):
        take(lattices, taken, seeds[live], k)
        number = len(taken[0][0].paths)
        live = np.array([i for i in live if number < k and searches[i].queue], np.int64)
        base = _mixed(_mixed(seeds[live], 1 << 20), number)
        taken = [(searches[i], *searches[i].next(draws[number], first[i], first[i + 1], base[at : at + 1])) for at, i in enumerate(live)]
    return [(s.paths, -s.queue[0][0] if s.queue else -np.inf) for s in searches]


def piece_ids(piece: np.ndarray, byte_base: int) -> np.ndarray:
    """Vocabulary ids; a spelled-out character becomes its UTF-8 bytes' pieces."""
    if (piece >= 0).all():
        return piece
    out: list[int] = []
    for p in piece.tolist():
        out.extend([p] if p >= 0 else [byte_base + x for x in chr(-2 - p).encode()])
    return np.array(out, np.int32)


def spell(ids, v: Vocabulary) -> str:
    """The text of some ids: pieces one after the other, without the leading space."""
    data = b"".join(map(v.spelled.__getitem__, ids))
    return (data[1:] if data[:1] == b" " else data).decode("utf-8", "replace")


def segment(texts: list[str | None], seeds: np.ndarray, k: int, v: Vocabulary) -> Iterator[list[tuple[np.ndarray, float, float, float]]]:
    """For each text its (ids, log_prob, perturbed, inclusion), largest perturbed value first."""
    units, sizes = [], []
    for text in texts:
        before = len(units)
        units += units_of(text) if text else ()
        sizes.append(len(units) - before)
    known = dict.fromkeys(units)
    known = dict(zip(known, range(len(known)), strict=True))
    unit = np.fromiter(map(known.__getitem__, units), np.int64, len(units))
    first = np.append(0, np.cumsum(sizes))
    if len(unit):
        lattices = Lattices(list(known), v)
        text_seed = np.repeat(seeds, sizes)
        number = np.arange(len(unit)) - np.repeat(first[:-1], sizes)
        draws = [draw_all(lattices, unit, text_seed, number, i) for i in range(k)]
        some = np.flatnonzero(sizes)
        results = iter(top_k(lattices, draws, np.append(first[some], first[-1]), seeds[some], k))
    for size in sizes:
        if not size:
            yield [(np.zeros(0, np.int32), 0.0, 0.0, 1.0)]
            continue
        found, beyond = next(results)
        out = []
        for path in found:
            log_prob = float(path.logp.sum())
            out.append((piece_ids(lattices.piece[path.edge], v.byte_base), log_prob, path.perturbed, float(-np.expm1(-np.exp(min(log_prob - beyond, 700.0))))))
        yield out


def sample(df: DataFrame, *, k: int = 2, temperature: float = 0.5, seed: int = 0, model: str = MODEL, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, draw (0, 1, ...), token_ids, log_prob, perturbed, inclusion, and restored: whether decoding gives the text back. One row per segmentation."""
    rows = df.select(F.col(key).alias("k"), F.xxhash64(F.coalesce(F.col(key).cast("string"), F.lit("null")), F.lit(seed)).alias("seed"), F.col(text).alias("body"))

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        v = vocabulary(model, temperature)
        texts = column_of(batch, "body").to_pylist()
        seeds = column_of(batch, "seed").to_numpy().view(np.uint64)
        of, draw, ids, numbers, restored = [], [], [], [], []
        for i, found in enumerate(segment(texts, seeds, k, v)):
            whole = f" {texts[i]}".encode() if texts[i] else b""
            for j, (tokens, *rest) in enumerate(found):
                of.append(i)
                draw.append(j)
                ids.append(tokens)
                numbers.append(rest)
                restored.append(b"".join(map(v.spelled.__getitem__, tokens.tolist())) == whole)
        numbers = np.array(numbers)
        return records(
            k=column_of(batch, "k").take(pa.array(of)), draw=pa.array(draw, pa.int32()), token_ids=list_array(np.concatenate(ids), np.array([len(x) for x in ids])),
            log_prob=numbers[:, 0], perturbed=numbers[:, 1], inclusion=numbers[:, 2], restored=pa.array(restored, pa.bool_()),
        )

    schema = f"k {dict(rows.dtypes)['k']}, draw int, token_ids array<int>, log_prob double, perturbed double, inclusion double, restored boolean"
    return map_texts(rows, step, schema, text="body", limit=_SLICE).withColumnRenamed("k", key)


def encode(df: DataFrame, *, model: str = MODEL, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key and token_ids by the library's own deterministic segmentation."""
    rows = df.select(F.col(key).alias("k"), F.col(text).alias("body"))

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids = _library(model).encode([x or "" for x in column_of(batch, "body").to_pylist()], num_threads=1)
        return records(k=column_of(batch, "k"), token_ids=pa.array(ids, pa.list_(pa.int32())))

    return map_texts(rows, step, f"k {dict(rows.dtypes)['k']}, token_ids array<int>", text="body", limit=_SLICE).withColumnRenamed("k", key)


def decode(df: DataFrame, *, model: str = MODEL, ids: str = "token_ids") -> DataFrame:
    """df with `decoded`, the text of its ids; null ids decode to an empty text. Extra columns stay, but for one named `decoded`, which is replaced."""
    names = [c for c in df.columns if c != "decoded"]
    rows = df.select(*[F.col(f"`{c}`") for c in names])

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = vocabulary(model, 1.0)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = [spell(x or [], v) for x in column_of(part, ids).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(texts, pa.string())], names=[*part.schema.names, "decoded"])

    from pyspark.sql.types import StringType, StructField, StructType

    return rows.mapInArrow(pieces, StructType([*rows.schema.fields, StructField("decoded", StringType())]))
