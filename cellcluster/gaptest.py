"""Tests whether two point sets have a pair within eps of each other.

Sets are integer matrices. Every yes is a comparison of integers; doubles only
prune, and only beyond a relative margin, so rounding cannot change a verdict.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

_MARGIN = 1e-9


@dataclass
class GapVerdict:
    """The answer and what it took: iterations, distances, and points pruned by each rule."""

    yes: bool
    iterations: int = 0
    distances: int = 0
    pruned_triangle: int = 0
    pruned_angle: int = 0


def _square(points: np.ndarray, p: np.ndarray) -> np.ndarray:
    diff = points - p
    return np.einsum("ij,ij->i", diff, diff)


def maximum_angle(p: np.ndarray, q: np.ndarray, others: np.ndarray, eps: float) -> float:
    """The widest angle at p, from the direction of q, under which a point can be within eps of one of ``others``."""
    to_q, to_y = (q - p).astype(float), (others - p).astype(float)
    far = np.linalg.norm(to_y, axis=1)
    turn = np.arccos(np.clip(to_y @ to_q / (far * np.linalg.norm(to_q)), -1, 1))
    return float((np.arcsin(np.clip(eps / far, -1, 1)) + turn).max())


def prune(own: np.ndarray, others: np.ndarray, p: np.ndarray, q: np.ndarray, eps: float, rules: frozenset[str] = frozenset({"tri", "ang"})) -> tuple[np.ndarray, int, int]:
    """Which rows of ``own`` may still have a partner, and how many each rule took.

    ``q`` is the nearest of ``others`` to ``p`` and farther than eps. The angle
    is looked at only where the triangle inequality does not decide.
    """
    to_x = (own - p).astype(float)
    dist = np.linalg.norm(to_x, axis=1)
    gap = float(np.linalg.norm((q - p).astype(float)))
    near = dist < (gap - eps) * (1 - _MARGIN) if "tri" in rules else np.zeros(len(own), bool)
    near |= dist == 0  # p itself has no partner
    wide = np.zeros(len(own), bool)
    if "ang" in rules:
        widest = maximum_angle(p, q, others, eps)
        rest = ~near
        to_q = (q - p).astype(float)
        angle = np.arccos(np.clip(to_x[rest] @ to_q / (dist[rest] * gap), -1, 1))
        wide[rest] = angle > widest + 1e-7
    return ~(near | wide), int(near.sum()), int(wide.sum())


def alternating_prune(a: np.ndarray, b: np.ndarray, eps: float, start: str | int = "first", rules: frozenset[str] = frozenset({"tri", "ang"}), seed: int = 0, slack: float = 0) -> GapVerdict:
    """Exact: nearest points are sought from side to side, and after each miss the side of the pivot is pruned.

    ``slack`` over 0 answers yes up to eps + slack, may answer either way in
    between, and never overlooks a pair within eps.
    """
    out = GapVerdict(False)
    if not len(a) or not len(b):
        return out
    limit = int((eps + slack) ** 2) if float(eps + slack).is_integer() else (eps + slack) ** 2
    if start == "random":
        k = int(np.random.default_rng(seed).integers(len(a)))
    elif start == "nearest_box":
        k = int(np.square(a - np.clip(a, b.min(axis=0), b.max(axis=0))).sum(axis=1).argmin())
    else:
        k = 0 if start == "first" else int(start)
    sides, pivot, turn = [a, b], a[k], 0
    while len(sides[0]) and len(sides[1]):
        own, others = sides[turn], sides[1 - turn]
        out.iterations += turn == 0
        near = _square(others, pivot)
        found = others[int(near.argmin())]
        out.distances += len(others)
        if near.min() <= limit:
            out.yes = True
            return out
        stay, tri, ang = prune(own, others, pivot, found, eps, rules)
        out.distances += len(own) + len(others)
        out.pruned_triangle += tri
        out.pruned_angle += ang
        sides[turn] = own[stay]
        pivot, turn = found, 1 - turn
    return out


def delta(a: np.ndarray, b: np.ndarray, eps: float, slack: float) -> GapVerdict:
    return alternating_prune(a, b, eps, slack=slack)


def brute(a: np.ndarray, b: np.ndarray, eps: float) -> GapVerdict:
    """All pairs, a stretch of rows at a time."""
    out = GapVerdict(False, 1)
    for k in range(0, len(a), 512):
        part = a[k : k + 512]
        out.distances += len(part) * len(b)
        if len(b) and (np.square(part[:, None, :] - b[None, :, :]).sum(axis=2) <= eps * eps).any():
            out.yes = True
            break
    return out


def min_square(a: np.ndarray, b: np.ndarray) -> int:
    return min(int(np.square(a[k : k + 512][:, None, :] - b[None, :, :]).sum(axis=2).min()) for k in range(0, len(a), 512))


def centre_filter(a: np.ndarray, b: np.ndarray, eps: float, centre: str = "mean") -> GapVerdict:
    """Points beyond eps plus the other side's radius from its centre are left out, the rest compared in full."""
    def middle(s: np.ndarray) -> tuple[np.ndarray, float]:
        c = s.mean(axis=0)
        if centre == "medoid":
            c = s[int(np.square(s - c).sum(axis=1).argmin())].astype(float)
        return c, float(np.sqrt(np.square(s - c).sum(axis=1).max()))

    (ca, ra), (cb, rb) = middle(a), middle(b)
    keep_a = np.sqrt(np.square(a - cb).sum(axis=1)) <= (eps + rb) * (1 + _MARGIN)
    keep_b = np.sqrt(np.square(b - ca).sum(axis=1)) <= (eps + ra) * (1 + _MARGIN)
    out = brute(a[keep_a], b[keep_b], eps) if keep_a.any() and keep_b.any() else GapVerdict(False, 1)
    out.distances += len(a) + len(b)
    return out


def pingpong(a: np.ndarray, b: np.ndarray, eps: float, start: int = 0) -> GapVerdict:
    """Nearest point in the other set by turns until it stays; may answer no wrongly, never yes."""
    out, p, last = GapVerdict(False), a[start], None
    while True:
        out.iterations += 1
        near = _square(b, p)
        q = b[int(near.argmin())]
        back = _square(a, q)
        out.distances += len(a) + len(b)
        if min(near.min(), back.min()) <= eps * eps:
            out.yes = True
            return out
        if last is not None and back.min() >= last:
            return out
        last, p = back.min(), a[int(back.argmin())]


class _KdTree:
    """Median splits over a point matrix, leaves of a few rows."""

    def __init__(self, points: np.ndarray, leaf: int = 16):
        self.points, self.leaf = points, leaf
        self.root = self._build(np.arange(len(points)))

    def _build(self, rows: np.ndarray):
        own = self.points[rows]
        box = own.min(axis=0), own.max(axis=0)
        if len(rows) <= self.leaf or (box[0] == box[1]).all():
            return box, rows, None, None
        j = int((box[1] - box[0]).argmax())
        rows = rows[np.argsort(own[:, j], kind="stable")]
        half = len(rows) // 2
        return box, None, self._build(rows[:half]), self._build(rows[half:])

    def nearest(self, p: np.ndarray) -> tuple[int, int]:
        """Squared distance to the nearest row, and rows looked at."""
        best, seen, stack = None, 0, [(0, self.root)]
        while stack:
            least, (_, rows, left, right) = stack.pop()
            if best is not None and least >= best:
                continue
            if rows is not None:
                seen += len(rows)
                d = int(_square(self.points[rows], p).min())
                best = d if best is None else min(best, d)
                continue
            sides = sorted(((int(np.square(np.maximum(np.maximum(n[0][0] - p, p - n[0][1]), 0)).sum()), k) for k, n in enumerate((left, right))), reverse=True)
            stack += [(s, (left, right)[k]) for s, k in sides]
        return best, seen


def nn_index(a: np.ndarray, b: np.ndarray, eps: float) -> GapVerdict:
    """Each point of one set asks a search tree of the other for its nearest point."""
    tree, out = _KdTree(b), GapVerdict(False, 1)
    for p in a:
        d, seen = tree.nearest(p)
        out.distances += seen
        if d <= eps * eps:
            out.yes = True
            break
    return out


def closest_pair(a: np.ndarray, b: np.ndarray, eps: float) -> GapVerdict:
    """Two search trees are descended together; pairs of boxes farther apart than the best pair are cut."""
    out, limit = GapVerdict(False, 1), eps * eps
    stack = [(_KdTree(a).root, _KdTree(b).root)]
    while stack:
        x, y = stack.pop()
        (lx, hx), (ly, hy) = x[0], y[0]
        if int(np.square(np.maximum(np.maximum(lx - hy, ly - hx), 0)).sum()) > limit:
            continue
        if x[1] is not None and y[1] is not None:
            out.distances += len(x[1]) * len(y[1])
            if (np.square(a[x[1]][:, None, :] - b[y[1]][None, :, :]).sum(axis=2) <= limit).any():
                out.yes = True
                return out
        elif y[1] is not None or (x[1] is None and (hx - lx).max() >= (hy - ly).max()):
            stack += [(x[2], y), (x[3], y)]
        else:
            stack += [(x, y[2]), (x, y[3])]
    return out


def planar_front(a: np.ndarray, b: np.ndarray, eps: float) -> GapVerdict:
    """In the plane, sets with a line along an axis between them: a point of one is tested against the front of the other's discs.

    Sets that no such line separates are compared in full.
    """
    for j in (0, 1):
        for low, high in ((a, b), (b, a)):
            if low[:, j].max() <= high[:, j].min():
                return _front(low, high, eps, j)
    return brute(a, b, eps)


def _front(low: np.ndarray, high: np.ndarray, eps: float, j: int) -> GapVerdict:
    """One sorted pass: along the other axis, each point of ``high`` meets the discs of ``low`` that reach its column.

    A disc that lies nowhere above the discs of both its neighbours on the front
    is off it: its centre is dominated by one that is as near in the column and
    higher. Where neighbours of the front cross, the highest disc changes: a
    point asks the one of its column, found by bisection, and the two beside it,
    as crossings are rounded.
    """
    out = GapVerdict(False, 1)
    order = np.lexsort((-low[:, j], low[:, 1 - j]))
    u, v = low[order, 1 - j], low[order, j]
    first = np.r_[True, u[1:] != u[:-1]]
    u, v = u[first], v[first]  # the highest of each column
    on = _upper_front(u, v, eps)
    u, v = u[on], v[on]
    x, y = high[:, 1 - j], high[:, j]
    cross = np.maximum.accumulate([_meet(u, v, k, k + 1, eps) for k in range(len(u) - 1)]) if len(u) > 1 else np.empty(0)
    own = np.searchsorted(cross, x)
    at = np.clip(own[:, None] + np.arange(-1, 2), 0, len(u) - 1)
    out.distances += at.size
    out.yes = bool(((u[at] - x[:, None]) ** 2 + (v[at] - y[:, None]) ** 2 <= eps * eps).any())
    return out


def _upper_front(u: np.ndarray, v: np.ndarray, eps: float) -> np.ndarray:
    """Columns whose disc is not below both a left and a right neighbour's disc wherever it stands."""
    keep: list[int] = []
    for k in range(len(u)):
        while len(keep) >= 2 and _meet(u, v, keep[-2], keep[-1], eps) > _meet(u, v, keep[-1], k, eps) + 1e-6:
            keep.pop()
        keep.append(k)
    return np.array(keep)


def _meet(u: np.ndarray, v: np.ndarray, x: int, y: int, eps: float) -> float:
    """Where the upper arcs of two discs of one radius cross: left of it the first is higher, right of it the second."""
    du, dv = float(u[y] - u[x]), float(v[y] - v[x])
    far = math.hypot(du, dv)
    if far >= 2 * eps:
        return float(u[x] + u[y]) / 2
    return float(u[x] + u[y]) / 2 - math.sqrt(eps * eps - far * far / 4) * dv / far


def sub_cells(points: np.ndarray, low: np.ndarray, side: float, levels: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Halved sub-cells of one cell: for each level the distinct identifiers in order, and where the children of each begin in the next."""
    finest = np.unique(np.floor((points - low) / (side / 2**levels)).astype(np.int64), axis=0)
    each = [finest >> (levels - level) for level in range(levels + 1)]
    # children of one node side by side, on all levels
    order = np.lexsort([k[:, j] for k in reversed(each) for j in range(points.shape[1])])
    cut, out = np.zeros(len(order), bool), []
    cut[:1] = True
    for keys in each:
        keys = keys[order]
        cut[1:] |= (keys[1:] != keys[:-1]).any(axis=1)
        out.append((keys[cut], np.flatnonzero(cut)))
    return [(keys, np.searchsorted(out[level + 1][1], np.r_[at, len(order)]) if level < levels else np.zeros(len(keys) + 1, np.int64)) for level, (keys, at) in enumerate(out)]


def rho_count(a: np.ndarray, b: np.ndarray, eps: float, rho: float, side: float | None = None) -> GapVerdict:
    """Approximate: yes if some point of ``a`` has a sub-cell of ``b`` within its reach, by descent from the whole cell.

    A sub-cell that lies beyond eps is left with all below it, one that lies
    wholly inside eps (1 + rho) is enough, and of the finest ones touching is.
    Yes up to eps, no beyond eps (1 + rho), either way in between but always the
    same way. Counts the sub-cells looked at as distances.
    """
    d = a.shape[1]
    side = eps / math.sqrt(d) if side is None else side
    levels = max(0, math.ceil(math.log2(1 / rho))) if rho < 1 else 0
    low, out = b.min(axis=0).astype(float), GapVerdict(False, 1)
    tree = sub_cells(b, low, side, levels)
    for k in range(0, len(a), 256):
        part = a[k : k + 256]
        point, box = np.divmod(np.arange(len(part) * len(tree[0][0])), len(tree[0][0]))
        for level, (keys, child) in enumerate(tree):
            own = side / 2**level
            at, p = keys[box] * own + low, part[point]
            out.distances += len(point)
            near = np.square(np.maximum(np.maximum(at - p, p - at - own), 0)).sum(axis=1) <= eps * eps
            inside = np.square(np.maximum(np.abs(p - at), np.abs(p - at - own))).sum(axis=1) <= (eps * (1 + rho)) ** 2
            if (near & (inside | (level == levels))).any():
                out.yes = True
                return out
            point, box = point[near], box[near]
            n = child[box + 1] - child[box]
            point, box = np.repeat(point, n), np.repeat(child[box], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            if not len(point):
                break
    return out


def clip(a: np.ndarray, b: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray]:
    """The points of each set within eps of the other's box; no pair within eps is lost."""
    near = lambda s, t: s[np.square(s - np.clip(s, t.min(axis=0), t.max(axis=0))).sum(axis=1) <= eps * eps]
    return near(a, b), near(b, a)


def box_test(low_a, high_a, low_b, high_b, eps: float) -> np.ndarray:
    """For rows of boxes: -1 if they are farther apart than eps, 1 if their farthest corners are within eps, 0 if open."""
    near = np.square(np.maximum(np.maximum(low_a - high_b, low_b - high_a), 0)).sum(axis=-1)
    far = np.square(np.maximum(high_a - low_b, high_b - low_a)).sum(axis=-1)
    return np.where(near > eps * eps, -1, np.where(far <= eps * eps, 1, 0))


def kappa_bound(a: np.ndarray, b: np.ndarray, width: float, eps: float) -> float:
    """Most iterations that geometry allows for points of a cell of side ``width``; 1 if every point of ``a`` has a partner."""
    least = np.array([_square(b, p).min() for p in a])
    alone = least > eps * eps
    if not alone.any():
        return 1.0
    d, tau = a.shape[1], math.sqrt(least[alone].min()) - eps
    ball = math.pi ** (d / 2) / math.gamma(d / 2 + 1) * (tau / 2) ** d
    return (width + 2 * tau) ** d / ball


TESTS = {
    "alternating_prune": alternating_prune, "brute": brute, "centre_filter": centre_filter, "pingpong": pingpong,
    "nn_index": nn_index, "closest_pair": closest_pair, "planar_front": planar_front,
}
EXACT = ("alternating_prune", "brute", "centre_filter", "nn_index", "closest_pair", "planar_front")
