"""The ordered fold behind Greedy, Expectation and the sequential matcher.

Candidates come in lexicographic order. A clique G grows while the next candidate
conflicts with all of it; the first one that doesn't closes G: a winner is
emitted, and the closing candidate is tried again for the next clique. At the
end the last clique is emitted too. ``literal`` keeps neither of these two steps.

State at any point is bounded: G, and the cells of winners at most 2 beta leads back.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from alignspark.params import AlignParams


@dataclass
class Counters:
    candidates: int = 0
    conflict_tests: int = 0
    cliques: int = 0
    largest_clique: int = 0
    looked_ahead: int = 0
    extra: dict = field(default_factory=dict)


def tie_key(x: np.ndarray, p: AlignParams) -> np.ndarray:
    """An integer for each candidate that breaks ties: its order, or a hash of (seed, x)."""
    if p.tie == "first":
        return np.zeros(len(x), dtype=np.uint64)
    h = np.full(len(x), (p.seed * 0x9E3779B97F4A7C15 + 0x1234567) & (2**64 - 1), dtype=np.uint64)
    for j in range(x.shape[1]):
        h = (h ^ x[:, j].astype(np.uint64)) * np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(29)
    return h


def _choose(members: list[int], score: np.ndarray, ties: np.ndarray) -> int:
    """The member of best score; ties by key, then by order."""
    best = members[0]
    top = score[0]
    for k in range(1, len(members)):
        g = members[k]
        if score[k] > top or (score[k] == top and ties[g] < ties[best]):
            best, top = g, score[k]
    return best


def look_ahead(x: np.ndarray, members: list[int], beta: int) -> int:
    """First candidate that can no longer conflict with a member: its lead is beyond the members' largest row + beta."""
    top = int(x[members].max()) + beta
    return int(np.searchsorted(x[:, 0], top, side="right"))


def expectation_scores(x: np.ndarray, w: np.ndarray, members: list[int], p: AlignParams, live: np.ndarray | None = None, counters: Counters | None = None) -> np.ndarray:
    """W(g) plus the weight of later candidates that meet the clique but not g."""
    start, stop = members[0] + 1, look_ahead(x, members, p.beta)
    zone = np.arange(start, stop)
    if live is not None:
        zone = zone[live[start:stop]]
    g = np.array(members)
    later = x[start:stop] if live is None else x[zone]
    meets = np.zeros((len(g), len(zone)), dtype=bool)  # members x zone
    for j in range(x.shape[1]):
        meets |= x[g, j][:, None] == later[:, j][None, :]
    some = meets.any(axis=0)
    gain = ~meets & some[None, :] & (zone[None, :] > g[:, None])
    if counters is not None:
        counters.looked_ahead += int(some.sum())
    if p.expect_mode == "sum":
        weight = w[zone]
        if int(weight.sum()) < 1 << 53:  # whole numbers that floats hold exactly, in any order of addition
            return w[g] + (gain.astype(float) @ weight.astype(float)).astype(np.int64)
        return w[g] + gain @ weight
    out = np.zeros(len(g), dtype=np.int64)
    for k in range(len(g)):  # heaviest first, without conflicts among themselves
        own = zone[gain[k]]
        taken: list[np.ndarray] = []
        for r in own[np.argsort(-w[own], kind="stable")]:
            if not any((x[r] == t).any() for t in taken):
                taken.append(x[r])
                out[k] += w[r]
    return w[g] + out


def _holders(column: np.ndarray) -> dict[int, np.ndarray]:
    """For every row number the candidates that hold it."""
    order = np.argsort(column, kind="stable")
    held = np.split(order, np.flatnonzero(np.diff(column[order])) + 1) if len(column) else []
    return {int(column[h[0]]): h for h in held}


def fold(x: np.ndarray, w: np.ndarray, p: AlignParams, method: str, spread: np.ndarray | None = None, taken: list[dict] | None = None, counters: Counters | None = None) -> list[int]:
    """Numbers of the candidates chosen. ``taken``: per series the rows that earlier winners hold."""
    m = x.shape[1] if len(x) else 0
    counters = counters if counters is not None else Counters()
    counters.candidates += len(x)
    used = taken if taken is not None else [set() for _ in range(m)]
    ties = tie_key(x, p)
    rows = x.tolist()
    chosen: list[int] = []
    clique: list[int] = []
    # candidates that share a cell with a winner, marked through an index of cells
    blocked = bytearray(len(x))
    marks = np.frombuffer(blocked, dtype=np.uint8) if len(x) else np.zeros(0, np.uint8)
    held_by = [_holders(x[:, j]) for j in range(m)]
    for own, index in zip(used, held_by):
        for v in own:
            if v in index:
                marks[index[v]] = 1
    live = np.ones(len(x), dtype=bool) if p.expect_live_only and method == "expectation" else None

    def emit() -> list[int]:
        counters.cliques += 1
        counters.largest_clique = max(counters.largest_clique, len(clique))
        if len(clique) == 1:
            best = clique[0]
        elif method == "expectation":
            best = _choose(clique, expectation_scores(x, w, clique, p, live, counters), ties)
        elif method == "sequential":
            best = min(clique, key=lambda g: (spread[g], g))
        else:
            best = _choose(clique, w[clique], ties)
        chosen.append(best)
        for j, v in enumerate(rows[best]):
            used[j].add(v)
            marks[held_by[j][v]] = 1
        if live is not None:
            live[(x == x[best]).any(axis=1)] = False
        return rows[best]

    for k, r in enumerate(rows):
        if blocked[k]:
            continue
        joins = True
        for g in clique:
            counters.conflict_tests += 1
            if not any(a == b for a, b in zip(rows[g], r)):
                joins = False
                break
        if joins:
            clique.append(k)
            continue
        won = emit()
        clique = []
        if not p.literal and not any(a == b for a, b in zip(won, r)):
            clique = [k]
    if clique and not p.literal:
        emit()
    return chosen
