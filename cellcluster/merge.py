"""The merge step for one machine, with counters: graph search and low density first, as sequences of gap tests.

``cells`` are the core points by cell; ``near`` lists the neighbours of each
cell by ascending offset. Both return the component of each cell and counts.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Callable

import numpy as np

from .components import UnionFind
from .gaptest import GapVerdict, alternating_prune


def merge_search(cells: list[np.ndarray], near: list[np.ndarray], eps: int, test: Callable[..., GapVerdict] = alternating_prune) -> tuple[list[int], dict[str, int]]:
    """Search from each cell that has no component yet; pairs with a classified cell are not tested."""
    label, count = [-1] * len(cells), {"checks": 0, "kappa": 0, "distances": 0}
    for s in range(len(cells)):
        if label[s] >= 0:
            continue
        label[s], queue = s, deque([s])
        while queue:
            c = queue.popleft()
            for o in near[c]:
                if label[o] < 0:
                    v = test(cells[c], cells[o], eps)
                    count["checks"] += 1
                    count["kappa"] = max(count["kappa"], v.iterations)
                    count["distances"] += v.distances
                    if v.yes:
                        label[o] = s
                        queue.append(int(o))
    return label, count


def merge_sparse_first(cells: list[np.ndarray], near: list[np.ndarray], eps: int, test: Callable[..., GapVerdict] = alternating_prune, memo_failed: bool = True) -> tuple[list[int], dict[str, int]]:
    """Cells by ascending number of core points, each against its neighbours unless they are joined; failed pairs are remembered on request."""
    forest, failed = UnionFind(len(cells)), set()
    count = {"checks": 0, "repeats": 0, "kappa": 0, "distances": 0}
    for c in sorted(range(len(cells)), key=lambda k: (len(cells[k]), k)):
        for o in map(int, near[c]):
            if forest.find(c) == forest.find(o):
                continue
            pair = (min(c, o), max(c, o))
            if pair in failed:
                if memo_failed:
                    continue
                count["repeats"] += 1
            v = test(cells[c], cells[o], eps)
            count["checks"] += 1
            count["kappa"] = max(count["kappa"], v.iterations)
            count["distances"] += v.distances
            if v.yes:
                forest.join(c, o)
            else:
                failed.add(pair)
    return [forest.find(k) for k in range(len(cells))], count
