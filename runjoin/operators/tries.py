"""Joins of a grid cell's rows by tries: levels of sorted values, found by seeks or by hash tables, a batch of prefixes at a time."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Prefixes that are held at once for each variable, and values that these are offered at once.
BATCH = 1 << 16


def narrow(values: np.ndarray) -> np.ndarray:
    """The same whole numbers in 32 bits, where they fit."""
    if values.dtype != np.int64 or not len(values):
        return values
    return values.astype(np.int32) if values.min() >= -(1 << 31) and values.max() < 1 << 31 else values


def _sorted(columns: list[np.ndarray]) -> np.ndarray:
    """Rows in the order of their columns: by one packed number each, where that has 62 bits at most."""
    spans = [(int(c.min()), int(c.max()) - int(c.min()) + 1) for c in columns] if len(columns[0]) else []
    width = 1
    for _, span in spans:
        width *= span
    if not spans or width >= 1 << 62:
        return np.lexsort(columns[::-1])
    packed = np.zeros(len(columns[0]), np.int64)
    for c, (low, span) in zip(columns, spans, strict=True):
        packed *= span
        packed += c
        packed -= low
    return np.argsort(packed)


class SortedTrie:
    """Distinct rows as levels of nodes: the values of a level under one node of the level above are one sorted stretch.

    ``find`` seeks values in their stretches, in time logarithmic in these. ``seeks`` counts them.
    """

    path = ()  # no place is kept between walks

    def __init__(self, columns: list[np.ndarray], counts: np.ndarray) -> None:
        order, self.seeks = _sorted(columns), 0
        self.keys: list[np.ndarray] = []  # values of each level's nodes
        self.first: list[np.ndarray] = [np.zeros(1, np.int64)]  # of each node, and of one beyond the last: the first node below it
        fresh, heads = np.zeros(len(order), bool), np.zeros(min(1, len(order)), np.int64)
        fresh[:1] = True
        for column in columns:
            column = column[order]
            fresh[1:] |= column[1:] != column[:-1]
            own = np.flatnonzero(fresh)
            self.first[-1] = narrow(np.append(np.searchsorted(own, heads), len(own)))
            self.keys.append(column[own])
            self.first.append(heads := own)
        self.first.pop()
        counts = counts[order]
        self.counts = narrow(np.add.reduceat(counts, heads) if len(heads) < len(counts) else counts)

    def below(self, level: int, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The stretch of ``level`` under each node of the level above (the root is node 0)."""
        first = self.first[level]
        return (first[nodes], first[nodes + 1]) if len(first) > 1 else (nodes, nodes)

    def find(self, level: int, nodes: np.ndarray, values: np.ndarray) -> np.ndarray:
        """The node that has the value under each node of the level above, or -1."""
        self.seeks += len(values)
        keys = self.keys[level]
        low, end = self.below(level, nodes)
        if not level and len(keys):  # one stretch
            place = np.minimum(np.searchsorted(keys, values), len(keys) - 1)
            return np.where(keys[place] == values, place, -1)
        low, high = low.astype(np.int64), end.astype(np.int64)
        while len(keys) and (high > low).any():
            middle = (low + high) >> 1
            less = (keys[np.minimum(middle, len(keys) - 1)] < values) & (low < high)
            low = np.where(less, middle + 1, low)
            high = np.where(less, high, middle)
        if not len(keys):
            return np.full(len(values), -1)
        return np.where((low < end) & (keys[np.minimum(low, len(keys) - 1)] == values), low, -1)


class HashTrie(SortedTrie):
    """The same levels, but values are found in a hash table of each level: open addressing by the node above and the value."""

    def __init__(self, columns: list[np.ndarray], counts: np.ndarray) -> None:
        super().__init__(columns, counts)
        self.tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    @staticmethod
    def _spot(nodes: np.ndarray, values: np.ndarray) -> np.ndarray:
        mixed = (nodes.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) ^ (values.astype(np.int64).view(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))
        mixed ^= mixed >> np.uint64(29)
        return (mixed * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(16)

    def _table(self, level: int) -> tuple[np.ndarray, np.ndarray]:
        """Slots (a node or -1), and the node above each node. Made when a level is first asked."""
        if level not in self.tables:
            keys, first = self.keys[level], self.first[level].astype(np.int64)
            above = np.repeat(np.arange(len(first) - 1, dtype=np.int32), np.diff(first))
            slots = np.full(1 << max(1, 2 * len(keys) - 1).bit_length(), -1, np.int32)
            for start in range(0, len(keys), BATCH):
                left = np.arange(start, min(len(keys), start + BATCH), dtype=np.int32)
                at = self._spot(above[left], keys[left]) & np.uint64(len(slots) - 1)
                while len(left):
                    open_ones = slots[at] < 0
                    slots[at[open_ones]] = left[open_ones]
                    moved = slots[at] != left
                    left, at = left[moved], (at[moved] + np.uint64(1)) & np.uint64(len(slots) - 1)
            self.tables[level] = slots, above
        return self.tables[level]

    def find(self, level: int, nodes: np.ndarray, values: np.ndarray) -> np.ndarray:
        slots, above = self._table(level)
        keys, found = self.keys[level], np.full(len(values), -1)
        left, at = np.arange(len(values)), self._spot(nodes, values) & np.uint64(len(slots) - 1)
        while len(left):
            node = slots[at]
            used = node >= 0
            left, at, node = left[used], at[used], node[used]
            same = (above[node] == nodes[left]) & (keys[node] == values[left])
            found[left[same]] = node[same]
            left, at = left[~same], (at[~same] + np.uint64(1)) & np.uint64(len(slots) - 1)
        return found


def _pieces(low: np.ndarray, fans: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Stretches gone through, BATCH places at a time: which stretch, and the place."""
    ends = np.cumsum(fans)
    total = int(ends[-1]) if len(ends) else 0
    for start in range(0, total, BATCH):
        spots = np.arange(start, min(total, start + BATCH))
        which = np.searchsorted(ends, spots, side="right")
        yield which, low[which] + spots - (ends[which] - fans[which])


def batches(order: list[str], parts: list[tuple[list[str], SortedTrie]]) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
    """The join's rows in batches: a column of values for each variable, and the product of counts.

    Each prefix takes the values of the next variable from the trie that has fewest below it, and the others are asked for
    them. Batches of prefixes go down one after another, so no more than BATCH of them wait at a variable.
    """
    holders = [[(i, keys.index(v), len(keys) == keys.index(v) + 1) for i, (keys, _) in enumerate(parts) if v in keys] for v in order]

    def down(depth: int, columns: list[np.ndarray], nodes: list[np.ndarray], n: np.ndarray) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
        if depth == len(order):
            yield columns, n
            return
        here = holders[depth]
        stretches = [parts[i][1].below(level, nodes[i]) for i, level, _ in here]
        fans = np.stack([end.astype(np.int64) - low for low, end in stretches])
        fewest = fans.argmin(axis=0)
        for k, (i, level, _) in enumerate(here):
            asked = np.flatnonzero((fewest == k) & (fans[k] > 0))
            for which, place in _pieces(stretches[k][0][asked].astype(np.int64), fans[k][asked]):
                prefix = asked[which]
                values = parts[i][1].keys[level][place]
                met = {i: place}
                for j, other, _ in here:
                    if j != i and len(prefix):
                        found = parts[j][1].find(other, nodes[j][prefix], values)
                        kept = found >= 0
                        prefix, values = prefix[kept], values[kept]
                        met = {x: at[kept] for x, at in met.items()} | {j: found[kept]}
                if len(prefix):
                    times = n[prefix]
                    for j, _, last in here:
                        if last:
                            times = times * parts[j][1].counts[met[j]]
                    at = [met[j] if j in met else nodes[j][prefix] for j in range(len(parts))]
                    yield from down(depth + 1, [*(c[prefix] for c in columns), values], at, times)

    root = np.zeros(1, np.int64)
    return down(0, [], [root] * len(parts), np.ones(1, np.int64))


def leapfrog(order: list[str], parts: list[tuple[list[str], SortedTrie]]) -> Iterator[tuple]:
    """Rows (a code of each variable, product of counts) of the join; each trie's columns follow ``order``."""
    for columns, n in batches(order, parts):
        yield from zip(*(c.tolist() for c in columns), n.tolist(), strict=True)


#: The same rows by hash tables: the smallest stretch is gone through, the others' tables are asked.
hash_join = leapfrog
nested = HashTrie
