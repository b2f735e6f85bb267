"""Axes, the split of the target space by pivots, and the labels that guide it."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np

from ..functions.metrics import Metric, as_matrix, padded

#: Pivots that are clustered; further ones take the label of the nearest of these.
MOST_CLUSTERED = 2000


@dataclass(frozen=True)
class Tree:
    """A binary split of the space into half-open cells, which tile it.

    Inner nodes have an axis and a cut: below the cut to ``left``, else to ``right``. Leaves have
    axis -1 and their region in ``left``.
    """

    axis: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    right: np.ndarray
    regions: int
    width: int

    def home(self, x: np.ndarray) -> np.ndarray:
        """The one cell of each row."""
        at = np.zeros(len(x), np.int64)
        while True:
            inner = np.flatnonzero(self.axis[at] >= 0)
            if not len(inner):
                return self.left[at]
            node = at[inner]
            at[inner] = np.where(x[inner, self.axis[node]] < self.cut[node], self.left[node], self.right[node])

    def near(self, x: np.ndarray, delta: float) -> tuple[np.ndarray, np.ndarray]:
        """(row, region) of all cells within delta of each row in every coordinate; only such branches are visited."""
        d = padded(delta)
        rows, at = np.arange(len(x)), np.zeros(len(x), np.int64)
        out_rows, out_regions = [], []
        while len(rows):
            leaf = self.axis[at] < 0
            out_rows.append(rows[leaf])
            out_regions.append(self.left[at[leaf]])
            rows, at = rows[~leaf], at[~leaf]
            v, c = x[rows, self.axis[at]], self.cut[at]
            below, above = v - d < c, v + d >= c
            rows, at = np.concatenate([rows[below], rows[above]]), np.concatenate([self.left[at[below]], self.right[at[above]]])
        return np.concatenate(out_rows), np.concatenate(out_regions)

    def bounds(self) -> tuple[np.ndarray, np.ndarray]:
        """Lower and upper corners of the cells."""
        lo, hi = np.full((self.regions, self.width), -np.inf), np.full((self.regions, self.width), np.inf)

        def walk(node: int, a: np.ndarray, b: np.ndarray) -> None:
            if self.axis[node] < 0:
                lo[self.left[node]], hi[self.left[node]] = a, b
                return
            d, c = self.axis[node], self.cut[node]
            a2, b2 = a.copy(), b.copy()
            b2[d], a2[d] = c, c
            walk(int(self.left[node]), a, b2)
            walk(int(self.right[node]), a2, b)

        walk(0, np.full(self.width, -np.inf), np.full(self.width, np.inf))
        return lo, hi

    def rows(self) -> list[tuple[int, int, float, int, int]]:
        return [(i, int(a), float(c), int(p), int(q)) for i, (a, c, p, q) in enumerate(zip(self.axis, self.cut, self.left, self.right, strict=True))]


def cut_at(values: np.ndarray, share: float) -> float | None:
    """The boundary between distinct values that leaves about ``share`` of them below; None if all are equal."""
    v = np.sort(values)
    steps = np.flatnonzero(v[1:] > v[:-1]) + 1
    if not len(steps):
        return None
    at = steps[np.argmin(np.abs(steps - share * len(v)))]
    return float(v[at])


def entropy(labels: np.ndarray, n: np.ndarray | None = None) -> float:
    """Entropy of labels; n: how many rows each entry stands for, one without it."""
    _, at = np.unique(labels, return_inverse=True)
    f = np.bincount(at, n) if len(at) else np.ones(1)
    f = f[f > 0] / f.sum()
    return float(-(f * np.log(f)).sum())


def split_gain(labels: np.ndarray, below: np.ndarray, n: np.ndarray | None = None) -> float:
    """How much a split lowers the entropy of the labels."""
    n = np.ones(len(labels)) if n is None else n
    f = float(np.average(below, weights=n))
    return entropy(labels, n) - f * (entropy(labels[below], n[below]) if below.any() else 0) - (1 - f) * (entropy(labels[~below], n[~below]) if (~below).any() else 0)


def gain_ratio(labels: np.ndarray, below: np.ndarray, n: np.ndarray | None = None) -> float:
    """The gain over the entropy of the split itself; 0 where nothing is split off."""
    own = entropy(below.astype(int), n)
    return split_gain(labels, below, n) / own if own > 0 else 0.0


def grow(coords: np.ndarray, p: int, how: str = "iterative", labels: np.ndarray | None = None, seed: int = 7, measure: str = "ratio") -> Tree:
    """Split pivots into p cells, or fewer where they do not differ.

    Each cut gives both sides their share of the cells to come. The axis is random ('iterative'),
    the one of the best gain ratio of the labels ('learned'), or the widest ('widest').
    """
    g = np.random.default_rng(seed)
    coords = as_matrix(coords)
    axis, cut, left, right = [], [], [], []
    leaves = 0

    def new() -> int:
        axis.append(-1)
        cut.append(0.0)
        left.append(-1)
        right.append(-1)
        return len(axis) - 1

    stack = [(new(), np.arange(len(coords)), p)]
    while stack:
        node, rows, want = stack.pop()
        options = {}
        if want > 1 and len(rows) > 1:
            share = math.ceil(want / 2) / want
            for d in range(coords.shape[1]):
                if (c := cut_at(coords[rows, d], share)) is not None:
                    options[d] = c
        if not options:
            left[node] = leaves
            leaves += 1
            continue
        widest = max(options, key=lambda d: (float(np.ptp(coords[rows, d])), -d))
        d = widest
        if how == "iterative":
            d = int(g.choice(sorted(options)))
        elif how == "learned" and labels is not None:
            score = {e: (gain_ratio if measure == "ratio" else split_gain)(labels[rows], coords[rows, e] < c) for e, c in options.items()}
            best = max(score.values())
            d = min(e for e in score if score[e] == best) if best > 1e-12 else widest
        axis[node], cut[node] = d, options[d]
        below = coords[rows, d] < options[d]
        left[node], right[node] = new(), new()
        stack.append((right[node], rows[~below], want // 2))
        stack.append((left[node], rows[below], math.ceil(want / 2)))
    return Tree(np.array(axis), np.array(cut), np.array(left), np.array(right), leaves, coords.shape[1])


def linkage_labels(d: np.ndarray, n_labels: int, linkage: str = "average") -> np.ndarray:
    """Labels 0.. by merging the nearest clusters until n_labels are left."""
    n = len(d)
    d = d.astype(float).copy()
    np.fill_diagonal(d, np.inf)
    size, of = np.ones(n), np.arange(n)
    nearest = d.argmin(axis=1) if n else np.empty(0, int)
    low = d[np.arange(n), nearest] if n else np.empty(0)
    for _ in range(n - max(1, n_labels)):
        a = int(low.argmin())
        b = int(nearest[a])
        if not np.isfinite(low[a]):
            break
        if linkage == "single":
            row = np.minimum(d[a], d[b])
        elif linkage == "complete":
            row = np.maximum(d[a], d[b])
        else:
            row = (size[a] * d[a] + size[b] * d[b]) / (size[a] + size[b])
        gone = np.isinf(d[a]) | np.isinf(d[b])
        row[gone] = np.inf
        row[a] = np.inf
        d[a], d[:, a] = row, row
        d[b], d[:, b] = np.inf, np.inf
        size[a] += size[b]
        of[of == b] = a
        low[b] = np.inf
        stale = np.flatnonzero((nearest == a) | (nearest == b) | (row < low))
        for i in {a, *stale.tolist()} - {b}:
            if np.isfinite(low[i]) or i == a:
                nearest[i] = d[i].argmin()
                low[i] = d[i, nearest[i]]
    return np.unique(of, return_inverse=True)[1]


def cluster_labels(pivots: Sequence, metric: Metric | None, n_labels: int | None = None, linkage: str = "average", seed: int = 7) -> np.ndarray:
    """Labels of similar pivots; metric None: coordinates under the maximum distance, a lower bound of any metric."""
    n = len(pivots)
    want = n_labels or max(1, math.ceil(math.sqrt(n)))
    chosen = np.sort(np.random.default_rng(seed).permutation(n)[:MOST_CLUSTERED])
    part = [pivots[i] for i in chosen]

    def distances(a, b) -> np.ndarray:
        if metric is not None:
            return metric.block(a, b)
        x, y = np.asarray(a, float), np.asarray(b, float)
        return np.stack([np.abs(v - y).max(axis=1) for v in x]) if len(x) else np.zeros((0, len(y)))

    labels = linkage_labels(distances(part, part), want, linkage)
    if len(chosen) == n:
        return labels
    out = np.empty(n, np.int64)
    for a in range(0, n, 512):
        out[a : a + 512] = labels[distances(pivots[a : a + 512], part).argmin(axis=1)]
    return out


def compactness(tree: Tree, coords: np.ndarray, labels: np.ndarray) -> float:
    """Mean label entropy of the cells, weighted by their pivots."""
    home = tree.home(coords)
    return float(sum(entropy(labels[home == h]) * (home == h).mean() for h in np.unique(home)))


def choose_axes(pivots: Sequence, n: int, metric: Metric, how: str = "random", seed: int = 7) -> list:
    """n distinct pivots as axes: at random, or each far from those before."""
    g = np.random.default_rng(seed + 1)
    order = [pivots[i] for i in g.permutation(len(pivots))]
    key = lambda o: tuple(o) if isinstance(o, list | np.ndarray) else o
    distinct = list({key(o): o for o in order}.values())
    if how == "random" or len(distinct) <= n:
        return distinct[:n]
    chosen = [0]
    far = metric.block(distinct, [distinct[0]])[:, 0]
    while len(chosen) < n:
        chosen.append(int(far.argmax()))
        far = np.minimum(far, metric.block(distinct, [distinct[chosen[-1]]])[:, 0])
    return [distinct[i] for i in chosen]
