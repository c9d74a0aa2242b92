"""The compressors for one small relation within a task, so that many relations are compressed in one job.

A problem has up to hundreds of relations of a few thousand tuples; as plans of their own, each would cost a dozen jobs.
Here a relation is an array of codes (sorted distinct rows), an itemset a tuple of (position, value), and every form is
the same, to the last tie, as that of the DataFrame compressors, which are for relations that no task can hold.
"""

from __future__ import annotations

from collections import Counter, defaultdict

import numpy as np

from . import mining

Set = tuple[tuple[int, int], ...]


def ordered(rows: np.ndarray) -> np.ndarray:
    """Sorted distinct rows."""
    return np.unique(rows, axis=0) if len(rows) else rows


class Items:
    """Items of a relation by rising frequency, then position and value, with the tuples of each."""

    def __init__(self, rows: np.ndarray, s_min: int = 1):
        found = []
        for p in range(rows.shape[1]):
            values, counts = np.unique(rows[:, p], return_counts=True)
            found += [(int(n), p, int(v)) for v, n in zip(values, counts) if n >= s_min]
        found.sort()
        self.names = [(p, v) for _, p, v in found]
        self.freq = [n for n, *_ in found]
        self.at = {x: i for i, x in enumerate(self.names)}
        self.matrix = np.stack([rows[:, p] == v for p, v in self.names], axis=1) if found else np.zeros((len(rows), 0), bool)

    def set_of(self, places) -> Set:
        return tuple(sorted(self.names[i] for i in places))


def count_of(k: float | int, tuples: int) -> int:
    return mining.count_of(k, tuples)


def threshold(rows: np.ndarray, k: float | int, reduce: str = "mean") -> int:
    """The automatic threshold, from the k most frequent closed sets."""
    most = count_of(k, len(rows))
    items = Items(rows, 2)
    top = [f for _, f in mining.enumerate_top(items.matrix, np.ones(len(rows), np.int64), [[i] for i in range(len(items.names))], 2, most)] if most > 0 and items.names else []
    if not top:
        return 2
    return max(2, min(top) if reduce == "min" else -(-sum(top) // len(top)))


def maximal(rows: np.ndarray, s_min: int) -> list[tuple[Set, int]]:
    items = Items(rows, s_min)
    weight = np.ones(len(rows), np.int64)
    out = []
    for i in range(len(items.names)):
        here = items.matrix[:, i]
        out += [(items.set_of(s), f) for s, f in mining.enumerate_closed(items.matrix[here], weight[here], [i], s_min, True)]
    return out


def frequent(rows: np.ndarray, s_min: int) -> list[tuple[Set, int]]:
    """All frequent sets, by counting the parts of the rows on every set of columns."""
    out = []
    for mask in range(1, 1 << rows.shape[1]):
        at = [p for p in range(rows.shape[1]) if mask >> p & 1]
        values, counts = np.unique(rows[:, at], axis=0, return_counts=True)
        out += [(tuple(zip(at, map(int, v))), int(n)) for v, n in zip(values[counts >= s_min], counts[counts >= s_min])]
    return out


def paths(rows: np.ndarray, s_min: int = 2) -> list[tuple[Set, int]]:
    """Root-to-node paths of the frequency-ordered prefix tree."""
    counts: Counter = Counter()
    for path in _paths_of(rows):
        for n in range(1, max(2, rows.shape[1])):
            counts[path[:n]] += 1
    return [(tuple(sorted(p)), n) for p, n in counts.items() if n >= s_min]


def _paths_of(rows: np.ndarray) -> list[tuple]:
    items = Items(rows)
    rank = {x: (-f, *x) for x, f in zip(items.names, items.freq)}
    return [tuple(sorted(((p, int(v)) for p, v in enumerate(r)), key=rank.__getitem__)) for r in rows]


SCORES = {
    "area": lambda length, n, a: float(length * n),
    "savings": lambda length, n, a: float(length * (n - 1)),
    "rate": lambda length, n, a: float(f"{length * (n - 1) / (a * n):.12f}"),
    "length": lambda length, n, a: float(length),
    "freq": lambda length, n, a: float(n),
}


def choose(rows: np.ndarray, sets: list[tuple[Set, int]], objective: str = "area") -> list[tuple[Set, np.ndarray]]:
    """Greedy choice with disjoint covers: (itemset, its tuples' numbers)."""
    score, a = SCORES[objective], rows.shape[1]
    items = Items(rows)
    packed = np.packbits(items.matrix, axis=0)
    free = np.packbits(np.ones(len(rows), bool))
    out = []
    for s, _ in sorted(sets, key=lambda x: (-score(len(x[0]), x[1], a), x[0])):
        cover = np.bitwise_and.reduce(packed[:, [items.at[x] for x in s]], axis=1)
        if not (cover & ~free).any():
            free = free & ~cover
            out.append((s, np.flatnonzero(np.unpackbits(cover, count=len(rows)))))
    return out


def best_path(rows: np.ndarray) -> list[tuple[Set, np.ndarray]]:
    """The prefix tree read path by path: of every tuple's path the node that saves most, chosen on, and the tree of what
    is left built anew, until no node saves a cell."""
    left, out = np.arange(len(rows)), []
    while len(left) > 1:
        by_path: dict = defaultdict(list)
        every = _paths_of(rows[left])
        for t, path in zip(left, every):
            for n in range(1, max(2, rows.shape[1])):
                by_path[path[:n]].append(t)
        gain = {p: len(p) * (len(ts) - 1) for p, ts in by_path.items() if len(ts) > 1}
        # Every tuple names the best node of its path; a node that all its tuples name becomes an entry.
        named: Counter = Counter()
        for path in every:
            own = [path[:n] for n in range(1, max(2, rows.shape[1])) if path[:n] in gain]
            if own:
                named[max(own, key=lambda p: (gain[p], tuple((-x[0], -x[1]) for x in p)))] += 1
        won = sorted(p for p, n in named.items() if n == len(by_path[p]))
        if not won:
            break
        taken = [(tuple(sorted(p)), np.array(by_path[p])) for p in won]
        out += taken
        left = np.setdiff1d(left, np.concatenate([t for _, t in taken]), assume_unique=True)
    return out


def area_cover(rows: np.ndarray, k: float | int = 0.4, reduce: str = "mean") -> tuple[list[tuple[Set, np.ndarray]], int, int]:
    """(entries, number of candidates, threshold)."""
    s = threshold(rows, k, reduce)
    sets = maximal(rows, s)
    return choose(rows, sets, "area"), len(sets), s


def savings_slice(rows: np.ndarray, objective: str = "savings") -> tuple[list[tuple[Set, np.ndarray]], int, int]:
    sets = paths(rows)
    return choose(rows, sets, objective), len(sets), 2


def report(rows: np.ndarray, entries: list[tuple[Set, np.ndarray]], n_mined: int, s_min: int) -> dict:
    """The measures of ``CompressedRelation.report``, with the numbers of candidates and the threshold."""
    m, a = rows.shape
    covered, saved = sum(len(t) for _, t in entries), sum(len(s) * (len(t) - 1) for s, t in entries)

    def part(x, y):
        return round(x / y, 6) if y else 0.0

    return {
        "tuples": m, "cells": m * a, "n_mined": n_mined, "threshold": s_min, "n_used": len(entries), "covered": covered, "saved": saved, "compressed_share": part(covered, m), "table_rate": part(saved, m * a),
        "mean_len": part(sum(len(s) for s, _ in entries), len(entries)), "mean_freq": part(covered, len(entries)),
    }


def products(rows: np.ndarray) -> list[tuple[tuple[int, ...], ...]]:
    """Product rows: columns from the last to the first merge rows that differ in that column only."""
    d = [tuple((int(v),) for v in r) for r in rows]
    for c in range(rows.shape[1] - 1, -1, -1):
        merged: dict = defaultdict(set)
        for r in d:
            merged[r[:c] + r[c + 1 :]].update(r[c])
        d = [(*rest[:c], tuple(sorted(v)), *rest[c:]) for rest, v in merged.items()]
    return sorted(d)


def wildcards(rows: np.ndarray, sizes: list[int]) -> list[tuple[int, ...]]:
    """Short rows: (mask of "any" columns, values or -1)."""
    d = {(0, *map(int, r)) for r in rows}
    for c in range(rows.shape[1] - 1, -1, -1):
        merged: dict = defaultdict(set)
        for r in d:
            merged[r[: c + 1] + (None,) + r[c + 2 :]].add(r[c + 1])
        d = set()
        for key, values in merged.items():
            if len(values) == sizes[c] and None not in values and -1 not in values:
                d.add((key[0] | 1 << c, *key[1 : c + 1], -1, *key[c + 2 :]))
            else:
                d |= {(*key[: c + 1], v, *key[c + 2 :]) for v in values}
    return sorted(d)


def diagram(rows: np.ndarray) -> np.ndarray:
    """Edges (level, node, code, child); nodes of equal suffix sets are one, numbered from 0 within their level."""
    a = rows.shape[1]
    child, out = {tuple(map(int, r)): 0 for r in rows}, []
    for level in range(a - 1, -1, -1):
        sets: dict = defaultdict(set)
        for prefix, n in child.items():
            sets[prefix[:-1]].add((prefix[-1], n))
        number: dict = {}
        child = {prefix: number.setdefault(frozenset(s), len(number)) for prefix, s in sorted(sets.items())}
        out += [(level, n, code, c) for s, n in number.items() for code, c in s]
    return np.array(sorted(out), np.int64).reshape(-1, 4)
