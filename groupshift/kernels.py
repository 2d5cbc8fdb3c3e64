"""Dense numpy kernels for one panel that fits in a task: p rows are series, n columns are time points.

Groups are a list of integer arrays of row numbers; they may overlap and together cover all rows.
"""

from __future__ import annotations

import math

import numpy as np


def cusum(x):
    """Right mean less left mean at every split 1..n-1, times sqrt(t (n - t) / n), from prefix sums."""
    p, n = x.shape
    t = np.arange(1, n)
    s = np.cumsum(x, axis=1)
    return (t * s[:, -1:] - n * s[:, :-1]) / np.sqrt(n * t * (n - t))


def row_scale(x, kind: str = "mean_ad"):
    """Noise level of each row from successive differences: mean or median absolute deviation, consistent for normal noise."""
    d = np.diff(x, axis=1)
    if kind == "mean_ad":
        return np.abs(d - d.mean(1, keepdims=True)).mean(1) * math.sqrt(math.pi) / 2
    return np.median(np.abs(d - np.median(d, axis=1, keepdims=True)), axis=1) * 1.4826 / math.sqrt(2)


def disjoint(groups) -> bool:
    every = np.concatenate(groups)
    return len(every) == len(np.unique(every))


def block_shrink(c, groups, lam: float, normalise: bool = False):
    """Each group's part of each column pulled towards 0 by lam * sqrt(group size), zero if shorter than that."""
    out = np.zeros_like(c)
    for g in groups:
        norm = np.sqrt((c[g] ** 2).sum(0))
        keep = np.maximum(0, 1 - lam * math.sqrt(len(g)) / np.where(norm > 0, norm, 1)) * (norm > 0)
        out[g] = c[g] * keep
    size = np.linalg.norm(out)
    return out / size if normalise and size else out


def penalty_slope(m, groups, lam: float):
    """Sum over groups of lam * sqrt(size) * unit column parts; a zero part contributes zero."""
    out = np.zeros_like(m)
    for g in groups:
        norm = np.sqrt((m[g] ** 2).sum(0))
        out[g] += lam * math.sqrt(len(g)) * m[g] / np.where(norm > 0, norm, 1)
    return out


def conditional_gradient(c, groups, lam: float, eps: float = 1e-4, most: int = 200, steps: list | None = None):
    """The iterative solver on the unit sphere, for groups that overlap. steps receives (|g|^2, <m, g>) of each step."""
    size = np.linalg.norm(c)
    if not size:
        return np.zeros_like(c)
    m = c / size
    for k in range(1, most + 1):
        g = c - penalty_slope(m, groups, lam)
        norm2, inner = float((g * g).sum()), float((m * g).sum())
        if steps is not None:
            steps.append((norm2, inner))
        if norm2 == 0:
            break
        m, moved = blend(m, g, k, norm2, inner)
        if moved <= eps:
            break
    return m


def blend(m, g, k: int, norm2: float, inner: float):
    """The next point on the sphere after step k, and how far it is from m; both follow from the two sums alone."""
    a, b, length = k / (k + 2), 2 / (k + 2), math.sqrt(norm2)
    norm = math.sqrt(a * a + 2 * a * b * inner / length + b * b)
    if norm == 0:
        return m, 0.0
    return (a * m + b * g / length) / norm, math.sqrt(max(0.0, 2 - 2 * (a + b * inner / length) / norm))


def columnwise_dual(c, groups, lam: float, tol: float = 1e-9, sweeps: int = 500):
    """What is left of c after projection on the penalty's dual ball: the exact solution before normalising, columns apart.

    The ball is the sum of balls of radius lam * sqrt(size), one in each group's coordinates; each sweep projects on
    one after the other what the others leave.
    """
    parts = [np.zeros((len(g), c.shape[1])) for g in groups]
    rest = c.copy()
    for _ in range(sweeps):
        moved = 0.0
        for g, u in zip(groups, parts, strict=True):
            want = rest[g] + u
            norm = np.sqrt((want**2).sum(0))
            new = want * np.minimum(1, lam * math.sqrt(len(g)) / np.where(norm > 0, norm, 1))
            moved = max(moved, float(np.abs(new - u).max(initial=0)))
            rest[g] += u - new
            u[:] = new
        if moved <= tol:
            break
    return rest


def oriented(v):
    """v with its entry of largest size positive; the first such entry decides."""
    return -v if len(v) and v[np.argmax(np.abs(v) > np.abs(v).max() * (1 - 1e-12))] < 0 else v


def leading_left(m):
    """The leading left singular vector; zero for a zero matrix."""
    if not m.any():
        return np.zeros(m.shape[0])
    if m.shape[0] <= m.shape[1]:
        return oriented(np.linalg.eigh(m @ m.T)[1][:, -1])
    v = m @ np.linalg.eigh(m.T @ m)[1][:, -1]
    return oriented(v / np.linalg.norm(v))


def leading_of_gram(g):
    return oriented(np.linalg.eigh(g)[1][:, -1])


def relaxed(c, groups, lam: float, solver: str = "auto", **options):
    if solver == "auto":
        solver = "closed" if disjoint(groups) else "iterative"
    return {"closed": block_shrink, "iterative": conditional_gradient, "columnwise": columnwise_dual}[solver](c, groups, lam, **options)


def peak(values):
    """(time of the largest value, the value); times count from 1, ties go to the earliest."""
    if not len(values) or not values.any():
        return None, 0.0
    return int(np.argmax(values)) + 1, float(values.max())


def group_direction(c, groups, lam: float, solver: str = "auto", **options):
    return leading_left(relaxed(c, groups, lam, solver, **options))


def detect_single(x, groups, lam: float, solver: str = "auto", **options):
    """(z, statistic, direction) of the group-sparse projection detector."""
    c = cusum(x)
    v = group_direction(c, groups, lam, solver, **options)
    return (*peak(np.abs(v @ c)), v)


def detect_split(x, groups, lam: float, solver: str = "auto", **options):
    """Odd times give the direction, even times the place."""
    n = x.shape[1] // 2 * 2
    v = group_direction(cusum(x[:, 0:n:2]), groups, lam, solver, **options)
    z, stat = peak(np.abs(v @ cusum(x[:, 1:n:2])))
    return (None if z is None else 2 * z), stat, v


def sparse_level(p: int, n: int) -> float:
    return math.sqrt(math.log(p * math.log(n)) / 2)


def sparse_projection(x, lam: float | None = None):
    """The competitor without groups: entries are soft-thresholded."""
    c = cusum(x)
    lam = sparse_level(*x.shape) if lam is None else lam
    v = leading_left(np.sign(c) * np.maximum(np.abs(c) - lam, 0))
    return (*peak(np.abs(v @ c)), v)


def aggregate_l2(c):
    return np.sqrt((c * c).sum(0))


def aggregate_max(c):
    return np.abs(c).max(0)


def double_cusum(c, power: float = 0.5):
    """At each time, over m: how far the mean of the m largest sizes exceeds the spread of the others, weighted."""
    p = len(c)
    top = np.cumsum(-np.sort(-np.abs(c), axis=0), axis=0)
    m = np.arange(1, p + 1)[:, None]
    return ((m * (2 * p - m) / (2 * p)) ** power * (top / m - (top[-1:] - top) / (2 * p - m))).max(0)


def scan(c):
    """At each time, over m: the sum of the m largest squares, less m, over sqrt(2 m)."""
    top = np.cumsum(-np.sort(-(c * c), axis=0), axis=0)
    m = np.arange(1, len(c) + 1)[:, None]
    return ((top - m) / np.sqrt(2 * m)).max(0)


def sparsified(c, level: float):
    a = np.abs(c)
    return np.where(a > level, a, 0).sum(0)


def locate_by(c, how: str, level: float | None = None):
    curve = {"l2": aggregate_l2, "linf": aggregate_max, "double_cusum": double_cusum, "scan": scan}.get(how)
    return peak(sparsified(c, level) if curve is None else curve(c))


def method(x, name: str, groups, lam: float):
    """(z, statistic, direction or None) of a detector by its name."""
    if name == "gsp":
        return detect_single(x, groups, lam)
    if name == "gsp_columnwise":
        return detect_single(x, groups, lam, "columnwise")
    if name == "gsp_split":
        return detect_split(x, groups, lam)
    if name == "sparse_projection":
        return sparse_projection(x)
    level = math.sqrt(2 * math.log(max(2, x.shape[0] * x.shape[1])))
    return (*locate_by(cusum(x), name, level), None)


def interval_candidates(x, intervals, find):
    """(s, e, b, statistic) of find(columns s+1..e) for each interval."""
    out = []
    for s, e in intervals:
        z, stat = find(x[:, s:e])[:2]
        out.append((s, e, None if z is None else s + z, stat))
    return out


def recurse(candidates, n: int, threshold: float):
    """The points that random-interval segmentation finds: (z, statistic, depth, interval number), by z."""
    found, waiting = [], [(0, n, 0)]
    usable = [(q, s, e, b, stat) for q, (s, e, b, stat) in enumerate(candidates) if b is not None]
    while waiting:
        low, high, depth = waiting.pop()
        inside = [c for c in usable if low <= c[1] and c[2] <= high]
        best = max(inside, key=lambda c: (c[4], -c[3], -c[0]), default=None)
        if best is not None and best[4] >= threshold:
            found.append((best[3], best[4], depth, best[0]))
            waiting += [(low, best[3], depth + 1), (best[3], high, depth + 1)]
    return sorted(found)


def top_down(x, find, threshold: float):
    """Segmentation whose only interval is the current segment."""
    found, waiting = [], [(0, x.shape[1], 0)]
    while waiting:
        low, high, depth = waiting.pop()
        if high - low < 2:
            continue
        z, stat = find(x[:, low:high])[:2]
        if z is not None and stat >= threshold:
            found.append((low + z, stat, depth))
            waiting += [(low, low + z, depth + 1), (low + z, high, depth + 1)]
    return sorted(found)


def ari(true_points, found_points, n: int) -> float:
    """Adjusted Rand index of the two segmentations of 1..n."""
    a, b = ([0, *sorted(set(z) - {0, n}), n] for z in (true_points, found_points))
    pairs = lambda k: k * (k - 1) / 2
    common = sum(pairs(max(0, min(a[i + 1], b[j + 1]) - max(a[i], b[j]))) for i in range(len(a) - 1) for j in range(len(b) - 1))
    first, second = (sum(pairs(x[i + 1] - x[i]) for i in range(len(x) - 1)) for x in (a, b))
    expected = first * second / pairs(n)
    most = (first + second) / 2
    return 1.0 if most == expected else (common - expected) / (most - expected)


def best_group_subset(c, groups, s: int):
    """The ideal problem by trying all sets of s groups; for small numbers of groups."""
    from itertools import combinations

    best, best_v = -1.0, np.zeros(len(c))
    for chosen in combinations(range(len(groups)), min(s, len(groups))):
        rows = np.unique(np.concatenate([groups[g] for g in chosen]))
        values, vectors = np.linalg.eigh(c[rows] @ c[rows].T)
        if values[-1] > best:
            best, best_v = values[-1], np.zeros(len(c))
            best_v[rows] = vectors[:, -1]
    return oriented(best_v)


def group_norm(m, groups) -> float:
    return float(sum(math.sqrt(len(g)) * np.sqrt((m[g] ** 2).sum(0)).sum() for g in groups))


def dual_norm(m, groups) -> float:
    return float(max(np.sqrt((m[g] ** 2).sum(0)).max() / math.sqrt(len(g)) for g in groups))


def windows(p: int, size: int, step: int):
    """Overlapping windows of row numbers that cover 0..p-1."""
    starts = list(range(0, max(p - size, 0) + 1, step))
    if starts[-1] + size < p:
        starts.append(p - size)
    return [np.arange(s, min(s + size, p)) for s in starts]


def blocks(p: int, size: int):
    return [np.arange(s, min(s + size, p)) for s in range(0, p, size)]


def gaussian(p: int, n: int, changes, seed: int, sigma: float = 1.0):
    """Normal noise with mean steps: changes is a list of (z, vector), each vector added from z + 1 on."""
    x = np.random.Generator(np.random.Philox(seed)).normal(0, sigma, (p, n))
    for z, theta in changes:
        x[:, z:] += np.asarray(theta)[:, None]
    return x


def step_vector(p: int, groups, chosen, size: float):
    """Equal entries on the chosen groups' rows, with the given length."""
    rows = np.unique(np.concatenate([groups[g] for g in chosen]))
    out = np.zeros(p)
    out[rows] = size / math.sqrt(len(rows))
    return out
