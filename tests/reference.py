"""A symbol-by-symbol reference, written apart from the library: it moves a clock and keeps counters, as the rules are worded."""


def distance(p, s):
    row = list(range(len(s) + 1))
    for i, a in enumerate(p, 1):
        row, old = [i], row
        for j, b in enumerate(s, 1):
            row.append(min(row[-1] + 1, old[j] + 1, old[j - 1] + (a != b)))
    return row[-1]


def hits(p, text, k):
    low = max(1, len(p) - k)
    return [(i, n, d) for i in range(len(text)) for n in range(low, len(p) + k + 1) if i + n <= len(text) and (d := distance(p, text[i : i + n])) <= k]


def sift(p, text, k, tie="earliest", validation="accumulated", strict=True):
    by_start = {}
    for i, n, d in hits(p, text, k):
        by_start.setdefault(i, []).append((n, d))
    kept, slots, leader = [], {}, None
    for clock in range(len(text)):
        for level in slots:
            slots[level][2] += 1
        for n, d in by_start.get(clock, []):
            better = leader is None or d < leader
            if not better and d == leader:
                better = tie == "latest" or (tie == "shortest" and n < slots[leader][1])
            if better:
                slots[d], leader = [clock, n, 1], d
        if leader is not None and slots[leader][2] == slots[leader][1]:
            own = []
            for level in range(leader, k + 1):
                if level not in slots:
                    continue
                start, n, r = slots[level]
                if level != leader:
                    if validation == "interval":
                        gap = 1 if strict else 0
                        if any(start + n - 1 + gap >= s and s + m - 1 + gap >= start for s, m, _ in own):
                            continue
                    else:
                        room = r - (sum(m for _, m, _ in own) if validation == "accumulated" else own[-1][1])
                        if not (room > n if strict else room >= n):
                            continue
                own.append((start, n, level))
            kept += own
            slots, leader = {}, None
    return sorted(kept)
