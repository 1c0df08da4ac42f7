"""Edit-distance kernels over many start positions or texts at once, on numpy arrays of symbol codes.

The paths differ in the order in which the same matrices are filled; all give the same distances:
`band_distances` runs over the columns of all starts' matrices together, inside the diagonal band that can stay within
the threshold; `wavefront_last_row` fills anti-diagonals, whose cells don't depend on each other; with `by_counter` its borders come
from the step number instead of stored cells; `free_start_row` keeps one column per text; `bit_parallel_row` keeps the column's
vertical differences in two machine words; `automaton_row` keeps one word of live states per number of edits.
`hit_starts` says for many patterns together at which starts there is any hit, so that matrices are filled only there; `bank_starts` says the same,
but looks only where the text's three-symbol grams leave room for a hit.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

GAP = np.uint32(0xFFFFFFFF)  # a code that no symbol has: matches nothing


def encode(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), np.uint32)


def joined(texts: list[str], gap: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All texts in one array with `gap` fillers behind each; where each begins, and its length."""
    codes = [encode(t) for t in texts]
    sizes = np.array([len(c) for c in codes], np.int64)
    starts = np.cumsum(sizes + gap) - sizes - gap
    out = np.full(int((sizes + gap).sum()), GAP, np.uint32)
    for at, c in zip(starts.tolist(), codes, strict=True):
        out[at : at + len(c)] = c
    return out, starts, sizes


def band_distances(codes: np.ndarray, starts: np.ndarray, pattern: np.ndarray, k: int) -> tuple[list[int], np.ndarray]:
    """Distances, k + 1 where larger, of the pattern to codes[start : start + l] for the lengths l of the band. One matrix per start
    gives all lengths. codes must go on for lp + k symbols behind the last start. Starts that can't stay within k are given up in between.
    A pattern of two dimensions has a column for each start: starts of different patterns of one length are taken together."""
    lp = len(pattern)
    kind = np.int8 if k < 100 else np.int16  # narrow numbers: as many as possible at once
    one, top = kind(1), kind(k + 1)
    lengths = list(range(max(1, lp - k), lp + k + 1))
    out = np.full((len(lengths), len(starts)), top, kind)
    live, at = None, starts
    # column[j] is the cell of pattern prefix j; outside the diagonal band it counts as k + 1
    column = [np.full(len(at), min(j, k + 1), kind) for j in range(lp + 1)]
    for m in range(1, lp + k + 1):
        sym = codes[at + (m - 1)]
        lo, hi = max(0, m - k), min(lp, m + k)
        diagonal = column[lo - 1] if lo else None
        best = None
        for j in range(lo, hi + 1):
            up_left, diagonal = diagonal, column[j]
            if j == 0:
                cell = np.full(len(at), min(m, k + 1), kind)
            else:
                cell = up_left + (sym != pattern[j - 1])
                if j < m + k:  # inside the band to the left
                    np.minimum(cell, diagonal + one, out=cell)
                if j > lo:
                    np.minimum(cell, column[j - 1] + one, out=cell)
                np.minimum(cell, top, out=cell)
            column[j] = cell
            best = cell if best is None else np.minimum(best, cell)
        if lo:
            column[lo - 1] = np.full(len(at), top, kind)
        if m >= lengths[0] and hi == lp:
            out[m - lengths[0], slice(None) if live is None else live] = column[lp]
        if m > k + 1:
            keep = np.flatnonzero(best <= k)
            if len(keep) < 0.7 * len(at):
                live, at = keep if live is None else live[keep], at[keep]
                if not len(at):
                    break
                pattern = pattern if pattern.ndim == 1 else pattern[:, keep]
                # only the band's cells are read again
                column = [c[keep] if lo - 1 <= j <= hi else np.full(len(at), min(j, k + 1), kind) for j, c in enumerate(column)]
    return lengths, out


#: Symbols that a lane of `hit_starts` walks over, and (lane, pattern) pairs that are taken at once.
LANE, AT_ONCE = 128, 1 << 16


def hit_starts(codes: np.ndarray, patterns: list[np.ndarray], k: int) -> list[np.ndarray]:
    """For each of some patterns of one length (1 to 64), all places of codes where a substring within k edits of it starts, in order. Nothing is left out and
    nothing is added, but for the least length: the empty substring counts where the pattern has k symbols or fewer.

    Read backwards, a start is the end of a match that may begin anywhere, so the column's vertical differences in two machine words are enough. Codes are cut in lanes
    that are walked side by side, each behind a run-up of the longest substring; the words of all lanes and patterns make up one array. A pattern has a word's
    highest bits, so that its last difference is a sign; below it, cells are 0 and stay so, as every symbol fits there."""
    lp, n = len(patterns[0]), len(codes)
    if not 0 < lp <= 64:
        raise ValueError("a pattern of 1 to 64 symbols is needed")
    kind, signed = next((u, i) for u, i in ((np.uint8, np.int8), (np.uint16, np.int16), (np.uint32, np.int32), (np.uint64, np.int64)) if lp <= np.iinfo(u).bits)
    low = np.iinfo(kind).bits - lp
    below = kind((1 << low) - 1)
    run_up = lp + k
    lane = max(LANE, 4 * run_up)
    lanes = max(1, -(-n // lane))
    alphabet = np.unique(np.concatenate(patterns))
    at = np.minimum(np.searchsorted(alphabet, codes[::-1]), len(alphabet) - 1)
    symbols = np.full(run_up + lanes * lane, len(alphabet), np.intp)
    symbols[run_up : run_up + n] = np.where(alphabet[at] == codes[::-1], at, len(alphabet))
    walked = np.lib.stride_tricks.sliding_window_view(symbols, lane + run_up)[::lane]
    out = []
    together = max(1, AT_ONCE // lanes)
    for first in range(0, len(patterns), together):
        some = patterns[first : first + together]
        places = np.full((len(alphabet) + 1, len(some)), below, kind)  # by symbol: the places of the reversed pattern that hold it
        for i, p in enumerate(some):
            for j, a in enumerate(np.searchsorted(alphabet, p[::-1]).tolist()):
                places[a, i] |= kind(1 << (low + j))
        shape = (lanes, len(some))
        plus, minus = np.full(shape, ~below, kind), np.zeros(shape, kind)
        score = np.full(shape, lp, np.uint8)
        same, across, rise, fall = (np.empty(shape, kind) for _ in range(4))
        last = np.empty(shape, bool)
        near = []
        for step in range(lane + run_up):
            np.take(places, walked[:, step], axis=0, out=same, mode="clip")
            np.bitwise_and(same, plus, out=across)
            np.add(across, plus, out=across)
            np.bitwise_xor(across, plus, out=across)
            np.bitwise_or(across, same, out=across)
            np.bitwise_or(across, plus, out=rise)
            np.invert(rise, out=rise)
            np.bitwise_or(rise, minus, out=rise)
            np.bitwise_and(plus, across, out=fall)
            for change, put in ((rise, np.add), (fall, np.subtract)):
                np.less(change.view(signed), 0, out=last)
                put(score, last.view(np.uint8), out=score)
                np.add(change, change, out=change)  # shifted by one; a match may begin anywhere: nothing is carried in
            np.bitwise_or(same, minus, out=same)
            np.bitwise_or(same, rise, out=plus)
            np.invert(plus, out=plus)
            np.bitwise_or(plus, fall, out=plus)
            np.bitwise_and(rise, same, out=minus)
            if step >= run_up and len(found := np.flatnonzero(np.less_equal(score, k, out=last))):
                row, which = np.divmod(found, len(some))
                near.append((which, n - 1 - (row * lane + step - run_up)))
        which, start = (np.concatenate(x) for x in zip(*near, strict=True)) if near else (np.zeros(0, np.int64),) * 2
        which, start = which[start >= 0], start[start >= 0]
        order = np.lexsort((start, which))
        out += np.split(start[order], np.searchsorted(which[order], np.arange(1, len(some))))
    return out


#: Bytes that the tables of a bank's grams may take, and survivors of theirs that are decided at once.
TABLES, DECIDED = 1 << 26, 1 << 15


class GramFilter:
    """Starts of hits of many patterns of one length. A hit holds the first lp - k symbols behind its start, and the edits of these are at least the sum of what each
    gram of three symbols in a row needs to become some piece of the pattern near its place (of the pattern's beginning for the first gram). That is a table
    lookup: a row has half a byte for each pattern, and the sum, begun at 7 - k, reaches 8 where the start is out. The few that are left are decided one by one.

    The rows of a gram are computed when a text has it for the first time."""

    def __init__(self, patterns: np.ndarray, k: int):
        self.count, self.lp = patterns.shape
        self.k = k
        self.alphabet = np.unique(patterns)
        self.size = len(self.alphabet) + 1  # the last one: any symbol that no pattern has
        self.grams = min((self.lp - k) // 3, (8 + k) // 3)  # so that a sum stays below 16
        self.width = -(-self.count // 16) * 8
        self.useful = k < 8 and 3 * self.grams > k and self.lp <= 64 and self.grams * self.size**3 * self.width <= TABLES
        if not self.useful:
            return
        top = int(self.alphabet[-1]) + 1
        self.letters = np.full(top + 1, self.size - 1, np.int32)
        self.letters[self.alphabet] = np.arange(self.size - 1)
        self.patterns = self.letters[patterns]
        self.tables = np.zeros((self.grams, self.size**3, self.width), np.uint8)
        self.known = np.zeros(self.size**3, bool)
        kind = next(u for u in (np.uint8, np.uint16, np.uint32, np.uint64) if self.lp <= np.iinfo(u).bits)
        self.low = np.iinfo(kind).bits - self.lp
        self.places = np.zeros((self.count, self.size), kind)
        for j in range(self.lp):
            self.places[np.arange(self.count), self.patterns[:, j]] |= kind(1 << (self.low + j))

    def _learn(self, grams: np.ndarray) -> None:
        """Fill the rows of some grams."""
        symbols = [grams // self.size**2, grams // self.size % self.size, grams % self.size]
        one = np.uint8(1)
        for g in range(self.grams):
            lo, hi = max(0, 3 * g - self.k), min(self.lp, 3 * g + 3 + self.k)
            shape = (len(grams), self.count)
            # row[j]: edits of the gram's symbols so far to a piece that ends behind the pattern's symbol lo + j; it may begin anywhere but for the first gram
            row = [np.full(shape, 0 if g else j, np.uint8) for j in range(hi - lo + 1)]
            for symbol in symbols:
                corner, row[0] = row[0], row[0] + one
                for j in range(1, hi - lo + 1):
                    cell = corner + (symbol[:, None] != self.patterns[:, lo + j - 1])
                    np.minimum(cell, row[j] + one, out=cell)
                    np.minimum(cell, row[j - 1] + one, out=cell)
                    corner, row[j] = row[j], cell
            least = np.full((len(grams), 2 * self.width), 0 if g else 15, np.uint8)
            least[:, : self.count] = np.minimum.reduce(row) + np.uint8(0 if g else 7 - self.k)
            self.tables[g, grams] = least[:, 0::2] | least[:, 1::2] << 4
        self.known[grams] = True

    def _decide(self, symbols: np.ndarray, start: np.ndarray, which: np.ndarray) -> np.ndarray:
        """Whether a substring within k edits of the pattern begins at the start: the matrix's last row from its column's differences in two words,
        whose highest bits the pattern has; below them both are 0."""
        kind = self.places.dtype.type
        signed = np.dtype(f"i{self.places.dtype.itemsize}")
        edge = kind((2 << self.low) - 1)  # a match begins at the start: each symbol before the pattern's first is an edit
        plus, minus = np.full(len(start), ~kind((1 << self.low) - 1), kind), np.zeros(len(start), kind)
        score, best = np.full(len(start), self.lp, np.int8), np.full(len(start), self.k + 1, np.int8)
        row = which * self.size
        places = self.places.ravel()
        for m in range(self.lp + self.k):
            same = places.take(row + symbols.take(start + m))
            across = (((same & plus) + plus) ^ plus) | same
            rise, fall = minus | ~(across | plus), plus & across
            score += (rise.view(signed) < 0).view(np.int8)
            score -= (fall.view(signed) < 0).view(np.int8)
            rise, fall = rise + rise | edge, fall + fall
            same |= minus
            plus, minus = fall | ~(same | rise), rise & same
            if m + 1 >= self.lp - self.k:
                np.minimum(best, score, out=best)
        return best <= self.k

    def starts(self, codes: np.ndarray) -> list[np.ndarray] | None:
        """As hit_starts; None where so many starts are left that it is the better way."""
        n, ahead = len(codes), self.lp + self.k + 3
        symbols = np.full(n + ahead, self.size - 1, np.int32)
        np.take(self.letters, np.minimum(codes, len(self.letters) - 1), out=symbols[:n], mode="clip")
        gram = (symbols[:-2] * self.size + symbols[1:-1]) * self.size + symbols[2:]
        gram = gram.astype(np.intp)
        seen = np.zeros(len(self.known), bool)
        seen[gram] = True
        new = np.flatnonzero(seen & ~self.known)
        at_once = max(1, (1 << 20) // self.count)
        for a in range(0, len(new), at_once):
            self._learn(new[a : a + at_once])
        step = max(16, (1 << 18) // self.width)
        total, term = np.empty((step, self.width), np.uint8), np.empty((step, self.width), np.uint8)
        out, left = [], 0
        for a in range(0, n, step):
            rows = min(step, n - a)
            some, more = total[:rows], term[:rows]
            np.take(self.tables[0], gram[a : a + rows], axis=0, out=some, mode="clip")
            for g in range(1, self.grams):
                np.take(self.tables[g], gram[a + 3 * g : a + 3 * g + rows], axis=0, out=more, mode="clip")
                np.add(some, more, out=some)
            words = some.view(np.uint64).ravel()
            np.invert(words, out=words)
            np.bitwise_and(words, np.uint64(0x8888888888888888), out=words)
            word = np.flatnonzero(words)
            pairs = words[word].view(np.uint8)
            byte = np.flatnonzero(pairs)
            pair, byte = pairs[byte], word[byte >> 3] * 8 + (byte & 7)
            for half, bit in enumerate((8, 128)):
                row, column = np.divmod(byte[(pair & bit) > 0], self.width)
                out.append((row + a, 2 * column + half))
                left += len(row)
            if left > (a + rows) * self.count // 32 + 8 * DECIDED:
                return None
        start, which = (np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, np.int64),) * 2
        good = [self._decide(symbols, start[a : a + DECIDED], which[a : a + DECIDED]) for a in range(0, len(start), DECIDED)]
        good = np.concatenate(good) if good else np.zeros(0, bool)
        start, which = start[good], which[good]
        order = np.lexsort((start, which))
        return np.split(start[order], np.searchsorted(which[order], np.arange(1, self.count)))


@lru_cache(maxsize=2)
def _gram_filter(patterns: tuple[bytes, ...], k: int) -> GramFilter:
    return GramFilter(np.array([np.frombuffer(p, np.uint32) for p in patterns]), k)


def bank_starts(codes: np.ndarray, patterns: list[np.ndarray], k: int) -> list[np.ndarray]:
    """As hit_starts, for thresholds below the patterns' length. A process keeps the tables of the last banks."""
    grams = _gram_filter(tuple(p.tobytes() for p in patterns), k)
    found = grams.starts(codes) if grams.useful else None
    return hit_starts(codes, patterns, k) if found is None else found


def wavefront_last_row(pattern: np.ndarray, text: np.ndarray, *, by_counter: bool = False) -> np.ndarray:
    """Distances of the pattern to every prefix of text, by anti-diagonals. A cell of diagonal d with row j has column d - j."""
    lp, n = len(pattern), len(text)
    row = np.empty(n + 1, np.int64)
    row[0] = lp
    if not lp:
        return np.arange(n + 1)
    # one register per pattern row 0 .. lp, for the last two diagonals
    older = np.zeros(lp + 1, np.int64)
    old = np.full(lp + 1, 1, np.int64)
    for d in range(2, lp + n + 1):
        j = np.arange(max(1, d - n), min(lp, d - 1) + 1)
        m = d - j
        step = np.where(pattern[j - 1] == text[m - 1], 0, 1)
        if by_counter:
            # the step number d stands in for the borders: cell (j, 0) is j and cell (0, m) is m
            left = np.where(m == 1, j, old[j])
            above = np.where(j == 1, m, old[j - 1])
            corner = np.where(j == 1, m - 1, np.where(m == 1, j - 1, older[j - 1]))
        else:
            left, above, corner = old[j], old[j - 1], older[j - 1]
        # the least neighbour, one more unless it is a corner with equal symbols
        least = np.minimum(np.minimum(left, above), corner)
        cell = np.where((corner == least) & (step == 0), corner, np.minimum(np.minimum(left, above) + 1, corner + step))
        older, old = old, old.copy()
        old[j] = cell
        if not by_counter:
            if d <= lp:
                old[d] = d
            if d <= n:
                old[0] = d
        if j[-1] == lp:
            row[d - lp] = cell[-1]
    return row


def wavefront_distances(codes: np.ndarray, starts: np.ndarray, pattern: np.ndarray, k: int, *, by_counter: bool = False) -> tuple[list[int], np.ndarray]:
    """As band_distances, by anti-diagonals: the cells of a diagonal don't depend on each other, and neither do the starts."""
    lp = len(pattern)
    n = lp + k
    lengths = list(range(max(1, lp - k), n + 1))
    out = np.full((len(lengths), len(starts)), k + 1, np.int16)
    # a register per pattern row 0 .. lp and start, for the last two diagonals
    older, old = np.zeros((lp + 1, len(starts)), np.int16), np.ones((lp + 1, len(starts)), np.int16)
    for d in range(2, lp + n + 1):
        j = np.arange(max(1, d - n), min(lp, d - 1) + 1)
        m = d - j
        step = (pattern[j - 1][:, None] != codes[starts[None, :] + (m - 1)[:, None]]).astype(np.int16)
        left, above, corner = old[j], old[j - 1], older[j - 1]
        if by_counter:  # cell (j, 0) is j and cell (0, m) is m, from the step number and not from a register
            row, column = j[:, None].astype(np.int16), m[:, None].astype(np.int16)
            left, above = np.where(column == 1, row, left), np.where(row == 1, column, above)
            corner = np.where(row == 1, column - 1, np.where(column == 1, row - 1, corner))
        cell = np.minimum(np.minimum(left, above) + 1, corner + step)
        older, old = old, old.copy()
        old[j] = cell
        if not by_counter:
            if d <= lp:
                old[d] = d
            old[0] = d
        if j[-1] == lp and d - lp >= lengths[0]:
            out[d - lp - lengths[0]] = np.minimum(cell[-1], k + 1)
    return lengths, out


def free_start_row(pattern: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """codes: texts x symbols. Least distance of the pattern to any run that ends at each symbol."""
    lp = len(pattern)
    column = [np.full(len(codes), j, np.int16) for j in range(lp + 1)]
    out = np.empty(codes.shape, np.int16)
    for m in range(codes.shape[1]):
        corner = column[0]
        for j in range(1, lp + 1):
            cell = np.minimum(np.minimum(column[j - 1], column[j]) + 1, corner + (codes[:, m] != pattern[j - 1])).astype(np.int16)
            corner, column[j] = column[j], cell
        out[:, m] = column[lp]
    return out


def _masks(pattern: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """For each symbol the word of pattern places that hold it."""
    word = np.zeros(codes.shape, np.uint64)
    for j, p in enumerate(pattern.tolist()):
        word |= np.where(codes == p, np.uint64(1 << j), np.uint64(0))
    return word


def bit_parallel_row(pattern: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """As free_start_row, from the vertical differences of the column in two words; patterns of up to 64 symbols."""
    lp = len(pattern)
    if not 0 < lp <= 64:
        raise ValueError("a pattern of 1 to 64 symbols is needed")
    equal = _masks(pattern, codes)
    plus, minus = np.full(len(codes), (1 << lp) - 1, np.uint64), np.zeros(len(codes), np.uint64)
    score = np.full(len(codes), lp, np.int64)
    top, one = np.uint64(lp - 1), np.uint64(1)
    out = np.empty(codes.shape, np.int64)
    for m in range(codes.shape[1]):
        same = equal[:, m]
        carry = (((same & plus) + plus) ^ plus) | same | minus
        rise, fall = minus | ~(carry | plus), plus & carry
        score = score + ((rise >> top) & one).astype(np.int64) - ((fall >> top) & one).astype(np.int64)
        rise, fall = rise << one, fall << one  # a match may begin anywhere: nothing is carried in
        across = same | minus
        plus, minus = fall | ~(across | rise), rise & across
        out[:, m] = score
    return out


def automaton_row(pattern: np.ndarray, codes: np.ndarray, k: int) -> np.ndarray:
    """Least number of edits, k + 1 above k, of a run that ends at each symbol: k + 1 rows of automaton states, a word each."""
    lp = len(pattern)
    if not 0 < lp < 64:
        raise ValueError("a pattern of 1 to 63 symbols is needed")
    equal = _masks(pattern, codes)
    one = np.uint64(1)
    # bit j: the first j + 1 pattern symbols are matched with that many edits; deletions are free steps along a row's edits
    rows = [np.full(len(codes), (1 << e) - 1, np.uint64) for e in range(k + 1)]
    accept = np.uint64(1 << (lp - 1))
    out = np.full(codes.shape, k + 1, np.int64)
    for m in range(codes.shape[1]):
        same, new = equal[:, m], []
        for e in range(k + 1):
            state = (rows[e] << one | one) & same
            if e:
                state |= rows[e - 1] | (rows[e - 1] << one | one) | (new[e - 1] << one | one)
            new.append(state)
        rows = new
        for e in range(k, -1, -1):
            out[(rows[e] & accept) > 0, m] = e
    return out
