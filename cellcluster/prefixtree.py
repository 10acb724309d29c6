"""The prefix tree over non-empty cells, as sorted arrays: a node is a distinct prefix of identifiers.

Level j holds the distinct prefixes of length j in order; children of a node are
one stretch of the next level. A query walks down all levels at once for many
cells: the children within the reach are found by bisection, offsets add up, and
what reaches d is dropped.
"""

from __future__ import annotations

import numpy as np


class PrefixTree:
    def __init__(self, keys: np.ndarray):
        """``keys``: distinct cells in lexicographic order."""
        self.keys = keys
        m, self.d = keys.shape
        parent = np.zeros(m, np.int64)
        self.level: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.base = int(keys.max(initial=0)) + 2
        for j in range(self.d):
            mark = parent * self.base + keys[:, j]
            first = np.flatnonzero(np.r_[True, mark[1:] != mark[:-1]]) if m else np.empty(0, np.int64)
            self.level.append((mark[first], keys[first, j], parent[first]))
            parent = np.cumsum(np.r_[False, mark[1:] != mark[:-1]]) if m else parent
        self.visited = 0

    def nodes(self) -> list[int]:
        return [1, *(len(mark) for mark, _, _ in self.level)]

    def jump_table(self, level: int, node: int, reach: int, top: int) -> dict[int, int]:
        """For each key from 0 to ``top``, the first child key within the reach of it; keys without one are left out."""
        _, key, parent = self.level[level]
        own = key[parent == node]
        out = {}
        for k in range(top + 1):
            at = int(np.searchsorted(own, k - reach))
            if at < len(own) and own[at] <= k + reach:
                out[k] = int(own[at])
        return out

    def query(self, cells: np.ndarray, reach: int, with_self: bool = False, trace: list | None = None, mode: str = "jump", fanout: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Query number, cell number and offset of each neighbour, by query, then offset, then cell.

        ``scan`` looks at all children of nodes with at most ``fanout`` of them,
        ``jump`` bisects everywhere; answers are equal.
        """
        q, node, off = np.arange(len(cells)), np.zeros(len(cells), np.int64), np.zeros(len(cells), np.int64)
        for j in range(self.d):
            mark, key, _ = self.level[j]
            own = cells[q, j]
            low = np.searchsorted(mark, node * self.base + np.maximum(own - reach, 0))
            high = np.searchsorted(mark, node * self.base + np.minimum(own + reach, self.base - 1), side="right")
            if mode == "scan":
                a, b = np.searchsorted(mark, node * self.base), np.searchsorted(mark, (node + 1) * self.base)
                few = b - a <= fanout
                low, high = np.where(few, a, low), np.where(few, b, high)
            n = np.maximum(high - low, 0)
            self.visited += int(n.sum())
            at = np.repeat(low, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            q, off, own = np.repeat(q, n), np.repeat(off, n), np.repeat(own, n)
            gap = np.maximum(np.abs(key[at] - own) - 1, 0)
            off = off + gap * gap
            ok = off < self.d
            q, node, off = q[ok], at[ok], off[ok]
            if trace is not None:
                trace.append(len(q))
        if not with_self and len(q):
            ok = ~(self.keys[node] == cells[q]).all(axis=1)
            q, node, off = q[ok], node[ok], off[ok]
        order = np.lexsort((node, off, q))
        return q[order], node[order], off[order]


class RectTree:
    """Packed rectangles over cells, sorted and tiled, ``fan`` children a node: the tree of comparison for neighbour queries."""

    def __init__(self, keys: np.ndarray, fan: int = 16):
        self.keys, self.fan = keys, fan
        order = self._tile(np.arange(len(keys)), 0)
        self.order = order
        low = high = keys[order]
        self.levels = []
        while True:
            cut = np.arange(0, max(1, len(low)), fan)
            if len(low):
                low, high = np.minimum.reduceat(low, cut), np.maximum.reduceat(high, cut)
            self.levels.append((low, high))
            if len(low) <= 1:
                break
        self.visited = 0

    def _tile(self, rows: np.ndarray, j: int) -> np.ndarray:
        d = self.keys.shape[1]
        rows = rows[np.argsort(self.keys[rows, j], kind="stable")]
        if j == d - 1 or len(rows) <= self.fan:
            return rows
        slabs = max(1, round((len(rows) / self.fan) ** (1 / (d - j))))
        return np.concatenate([self._tile(s, j + 1) for s in np.array_split(rows, slabs) if len(s)])

    def query(self, cells: np.ndarray, reach: int, with_self: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        d = self.keys.shape[1]
        q = np.arange(len(cells))
        node = np.zeros(len(cells), np.int64)
        if not len(self.keys):
            return q[:0], node[:0], node[:0]
        for low, high in reversed(self.levels):
            self.visited += len(q)
            ok = ((low[node] <= cells[q] + reach) & (high[node] >= cells[q] - reach)).all(axis=1)
            q, node = q[ok], node[ok]
            q = np.repeat(q, self.fan)
            node = (node[:, None] * self.fan + np.arange(self.fan)).ravel()
            below = len(self.order) if low is self.levels[0][0] else len(self.levels[[x is low for x, _ in self.levels].index(True) - 1][0])
            ok = node < below
            q, node = q[ok], node[ok]
        leaf = self.order[node]
        self.visited += len(leaf)
        gap = np.maximum(np.abs(self.keys[leaf] - cells[q]) - 1, 0)
        off = (gap * gap).sum(axis=1)
        ok = off < d
        if not with_self:
            ok &= ~(self.keys[leaf] == cells[q]).all(axis=1)
        q, leaf, off = q[ok], leaf[ok], off[ok]
        order = np.lexsort((leaf, off, q))
        return q[order], leaf[order], off[order]
