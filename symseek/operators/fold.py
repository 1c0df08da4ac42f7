"""The sifter's rules over many islands at once, on numpy arrays.

Islands don't depend on each other, so their first hits are taken together, then their second ones, and so on: a step costs some array operations for
all islands that still go on. What few islands are left at the end, the long ones, go on hit by hit.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

#: What the hits and occurrences of one pattern in one stream share.
KEYS = ("stream_id", "pattern_id")
TIES = ("earliest", "shortest", "latest")
VALIDATIONS = ("accumulated", "last_length", "interval")
#: So many islands still make a step of arrays worth while.
FEW = 12


@dataclass(frozen=True)
class Rules:
    """tie: which of two hits of one level is kept; validation: what a weaker one must not reach into; strict: whether touching counts as reaching."""

    tie: str = "earliest"
    validation: str = "accumulated"
    strict: bool = True

    def __post_init__(self):
        if self.tie not in TIES or self.validation not in VALIDATIONS:
            raise ValueError(f"tie is one of {TIES}, validation one of {VALIDATIONS}")


@dataclass
class SerialSifter:
    """The rules, hit by hit: for streams of updates, islands too long for steps of arrays, and the serial engine."""

    levels: int
    rules: Rules = field(default_factory=Rules)
    leader: int = -1
    slots: list = field(default_factory=list)

    def __post_init__(self):
        self.slots = self.slots or [None] * self.levels

    def last(self) -> int:
        start, length = self.slots[self.leader]
        return start + length - 1

    def add(self, start: int, length: int, dist: int) -> list[tuple[int, int, int, int]]:
        """Take one more hit, in order of start and length; what a group that closes before it keeps."""
        out = self.close() if self.leader >= 0 and start > self.last() else []
        pending = self.slots[self.leader] if self.leader >= 0 else None
        tie = dist == self.leader and (self.rules.tie == "latest" or (self.rules.tie == "shortest" and length < pending[1]))
        if pending is None or dist < self.leader or tie:
            self.leader, self.slots[dist] = dist, (start, length)
        return out

    def close(self) -> list[tuple[int, int, int, int]]:
        if self.leader < 0:
            return []
        last, out = self.last(), []
        total = recent = 0
        low = None
        for level in range(self.leader, self.levels):
            if self.slots[level] is None:
                continue
            start, length = self.slots[level]
            counter = last - start + 1
            if level > self.leader:
                if self.rules.validation == "interval":
                    clear = start + length - 1 < low - self.rules.strict
                else:
                    room = counter - (total if self.rules.validation == "accumulated" else recent)
                    clear = room > length if self.rules.strict else room >= length
                if not clear:
                    continue
            out.append((start, length, level, last))
            total, recent, low = total + length, length, start if low is None else min(low, start)
        self.leader, self.slots = -1, [None] * self.levels
        return out


class _Slots:
    """The state of many islands: a leader's level, and a start and length (0 if empty) for each level and island."""

    def __init__(self, islands: int, levels: int, rules: Rules):
        self.levels, self.rules = levels, rules
        self.leader = np.full(islands, -1, np.int64)
        self.start = np.zeros((levels, islands), np.int64)
        self.length = np.zeros((levels, islands), np.int64)
        self.kept: list[tuple[np.ndarray, ...]] = []  # island, start, length, level, last

    def close(self, of: np.ndarray) -> None:
        """Close the groups of some islands that have a leader."""
        leader = self.leader[of]
        last = self.start[leader, of] + self.length[leader, of] - 1
        total, recent, low = (np.zeros(len(of), np.int64) for _ in range(3))
        for level in range(self.levels):
            start, length = self.start[level, of], self.length[level, of]
            if self.rules.validation == "interval":
                clear = start + length - 1 < low - self.rules.strict
            else:
                room = last - start + 1 - (total if self.rules.validation == "accumulated" else recent)
                clear = room > length if self.rules.strict else room >= length
            first = leader == level
            keeps = first | ((leader < level) & (length > 0) & clear)
            if keeps.any():
                self.kept.append((of[keeps], start[keeps], length[keeps], np.full(int(keeps.sum()), level), last[keeps]))
                total, recent, low = total + length * keeps, np.where(keeps, length, recent), np.where(first, start, np.where(keeps, np.minimum(low, start), low))
        self.leader[of] = -1
        self.length[:, of] = 0

    def add(self, start: np.ndarray, length: np.ndarray, dist: np.ndarray) -> None:
        """One more hit for each of the first islands."""
        active = np.arange(len(start))
        leader = self.leader[: len(start)]
        level = np.maximum(leader, 0)
        held = self.length[level, active]
        closes = np.flatnonzero((leader >= 0) & (start > self.start[level, active] + held - 1))
        if len(closes):
            self.close(closes)
        takes = (leader < 0) | (dist < leader)
        if self.rules.tie != "earliest":
            takes |= (dist == leader) & ((length < held) if self.rules.tie == "shortest" else True)
        at = np.flatnonzero(takes)
        self.start[dist[at], at], self.length[dist[at], at], self.leader[at] = start[at], length[at], dist[at]


def fold_islands(begin: np.ndarray, start: np.ndarray, length: np.ndarray, dist: np.ndarray, levels: int, rules: Rules) -> tuple[np.ndarray, ...]:
    """(island, start, length, distance, decided at) of what islands keep, by island. begin: the place of each island's first hit; hits by island, start and length."""
    sizes = np.diff(np.append(begin, len(start)))
    order = np.argsort(-sizes, kind="stable")
    first, longest = begin[order], sizes[order]
    state, step = _Slots(len(order), levels, rules), 0
    goes_on = np.searchsorted(-longest, -np.arange(1, (longest[0] if len(longest) else 0) + 1), "right")  # islands with more than `step` hits
    while step < len(goes_on) and goes_on[step] > FEW:
        at = first[: goes_on[step]] + step
        state.add(start[at], length[at], dist[at])
        step += 1
    rest = int(goes_on[step]) if step < len(goes_on) else 0
    out = []
    for i in range(rest):
        slots = [(int(s), int(n)) if n else None for s, n in zip(state.start[:, i], state.length[:, i], strict=True)]
        sifter = SerialSifter(levels, rules, int(state.leader[i]), slots)
        a, b = int(first[i]) + step, int(first[i] + longest[i])
        for hit in zip(start[a:b].tolist(), length[a:b].tolist(), dist[a:b].tolist(), strict=True):
            found = sifter.add(*hit)
            if found:
                out += [(i, *o) for o in found]
        out += [(i, *o) for o in sifter.close()]
    open_groups = rest + np.flatnonzero(state.leader[rest:] >= 0)
    if len(open_groups):
        state.close(open_groups)
    parts = state.kept + ([tuple(np.array(out, np.int64).T)] if out else [])
    if not parts:
        return (np.zeros(0, np.int64),) * 5
    island, *columns = (np.concatenate(x) for x in zip(*parts, strict=True))
    island = order[island]
    by = np.lexsort((columns[0], columns[3], island))
    return island[by], *(c[by] for c in columns)
