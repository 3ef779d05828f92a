"""Dense kernels on one block (a pair of classes): all are plain NumPy and run inside Arrow-fed tasks.

A block is an m x m matrix of weights in [0, 1]; rows are class A, columns class B.
"""

from __future__ import annotations

import itertools
import math

import numpy as np

UNIFORM, WITNESS, UNVERIFIED = "UNIFORM", "WITNESS", "UNVERIFIED"


def theory(eps: float, k: int, n: int) -> dict:
    """Constants of the lemmas at (eps, k classes, n vertices)."""
    ga, gb = eps**4 / 16, eps**9 / 108
    needed = 1
    while 4**needed <= 600 * ga**-5:
        needed += 1
    return {
        "gamma_a": ga, "gamma_b": gb, "witness_floor": ga, "witness_gap": eps**4, "energy_gain": ga**5 / 20, "rounds_a": math.ceil(10 * ga**-5),
        "rounds_b": eps**-45, "full_classes": k * 4**k, "least_k": needed, "in_range": bool(2 * (n / max(k, 1)) ** -0.25 < eps < 1 / 16),
    }


def class_sizes(n: int, fanout: int, h: int, recycle: str = "class") -> list[tuple[int, int, int]]:
    """(k, m, residue) of each round when every class splits, down to the first class size below ``h``."""
    k, m = fanout, n // fanout
    out = [(k, m, n - k * m)]
    while m >= h and m // fanout >= 1:
        m //= fanout
        k = n // m if recycle == "global" else k * fanout
        out.append((k, m, n - k * m))
    return out


def gaussian(x: np.ndarray, y: np.ndarray, sx, sy=None) -> np.ndarray:
    """exp(-d^2 / (2 s^2)), or exp(-d^2 / (s_i s_j)) with a scale for each point."""
    d2 = (x**2).sum(1)[:, None] + (y**2).sum(1)[None, :]
    d2 -= 2 * x @ y.T
    np.maximum(d2, 0, out=d2)
    d2 /= -(2 * sx**2) if sy is None else -np.maximum(np.outer(sx, sy), 1e-300)
    return np.exp(d2, out=d2)


def codegree(w: np.ndarray, eps: float, policy: str = "max_gap", anchors: str | int = "all", above_density: bool = True):
    """(status, gap, rows, columns): degree step and codegree step; every witness is measured again.

    ``anchors``: all columns, those of typical degree, or a number of columns spread evenly. A sample that finds
    nothing proves nothing, so its answer is then UNVERIFIED.
    """
    m = w.shape[1]
    d = float(w.mean())
    mean = d * m
    if mean < eps**3 * m:
        return UNIFORM, 0.0, None, None
    floor, gap, found = max(eps**4 / 16 * m, 1), eps**4, []
    off = w.sum(0) - mean
    for side in (off >= gap * m, off <= -gap * m):
        if side.sum() >= eps**4 / 16 * m and (np.abs(off) >= gap * m).sum() >= eps**4 / 8 * m and side.any():
            g = abs(float(w[:, side].mean()) - d)
            if side.sum() >= floor and g >= gap:
                found.append((g, np.ones(w.shape[0], bool), side))
    if found and policy == "lemma_order":
        g, a, b = max(found, key=lambda f: f[2].sum())
        return WITNESS, g, a, b
    pick = np.unique(np.linspace(0, m - 1, min(anchors, m)).astype(int)) if isinstance(anchors, int) else np.arange(m)
    at = w if len(pick) == m else w[:, pick]
    near = _reach(w, at, 2 * gap * m + mean**2 / m)
    near[np.arange(len(pick)), pick] = False
    size_b = near.sum(1)
    open_ = size_b >= max(eps**4 / 4 * m, 1)
    if anchors == "typical":
        typical = np.abs(off) < gap * m
        if not typical.any() and not found:
            return UNVERIFIED, 0.0, None, None
        open_ &= typical
    if open_.any():
        hood = at > (d if above_density else 0)
        size_a = hood.sum(0)
        asked = np.flatnonzero(open_ & (size_a >= floor) & (size_b >= floor))
        if len(asked):
            y, g = _best_anchor(w, hood, near, asked, size_a * size_b, d)
            if g >= gap:
                found.append((g, hood[:, y], near[y]))
    if found:
        g, a, b = max(found, key=lambda f: f[0])
        return WITNESS, g, a, b
    return (UNVERIFIED if open_.any() or len(pick) < m else UNIFORM), 0.0, None, None


#: Blocks of fewer columns are multiplied in double precision at once.
LEAST_SINGLE = 256


def _reach(w: np.ndarray, at: np.ndarray, bar: float) -> np.ndarray:
    """Where at.T @ w >= bar.  Single precision decides what its error bound allows, sums in double precision the rest."""
    rows = w.shape[0]
    if w.shape[1] < LEAST_SINGLE or w.min() < 0:
        return at.T @ w >= bar
    v = w.astype(np.float32)
    n = v.T @ v if at is w else at.astype(np.float32).T @ v
    slack = (rows + 8) * 2.0**-23  # relative, for sums of ``rows`` products of weights that are not negative, in any order
    near = n >= bar
    close = np.argwhere((n >= bar * (1 - 2 * slack)) & (n <= bar * (1 + 2 * slack)))
    if len(close) * 8 > n.size:
        return at.T @ w >= bar
    left, right = np.ascontiguousarray(at.T), np.ascontiguousarray(w.T)
    for lo in range(0, len(close), 2048):
        i, j = close[lo : lo + 2048].T
        near[i, j] = np.einsum("ij,ij->i", left[i], right[j]) >= bar
    return near


def _best_anchor(w: np.ndarray, hood: np.ndarray, near: np.ndarray, asked: np.ndarray, area: np.ndarray, d: float) -> tuple[int, float]:
    """(anchor, gap) with the largest gap of ``asked``: single precision leaves those that may have it, double decides."""
    gaps = lambda of, form: np.abs(((hood[:, of].T.astype(form) @ w.astype(form, copy=False)) * near[of]).sum(1, dtype=float) / area[of] - d)
    if w.shape[1] >= LEAST_SINGLE and w.min() >= 0:
        some = gaps(asked, np.float32)
        asked = asked[some >= some.max() - 4 * (w.shape[0] + 8) * 2.0**-23 * w.max()]
    exact = gaps(asked, float)
    return int(asked[exact.argmax()]), float(exact.max())


#: Blocks of fewer rows or columns are decomposed whole; steps that the first triple of larger ones may take, and its residual.
LEAST_STEPPED, MOST_STEPS, RESIDUAL = 128, 160, 1e-13


def first_triple(c: np.ndarray) -> tuple[np.ndarray, float, np.ndarray]:
    """(left vector, first singular value, right vector), by bidiagonal steps kept orthogonal until nothing moves; else by the whole decomposition."""
    p, q = c.shape
    most = min(MOST_STEPS, p, q)
    if min(p, q) >= LEAST_STEPPED:
        left, right, small = np.zeros((most, p)), np.zeros((most + 1, q)), np.zeros((most, most))
        v = np.random.default_rng(42).normal(size=q)
        right[0], beta = v / np.linalg.norm(v), 0.0
        for k in range(most):
            u = c @ right[k] - (beta * left[k - 1] if k else 0.0)
            for _ in range(2):
                u -= left[:k].T @ (left[:k] @ u)
            if not (alpha := np.linalg.norm(u)) > 0:
                break
            left[k], small[k, k] = u / alpha, alpha
            v = c.T @ left[k] - alpha * right[k]
            for _ in range(2):
                v -= right[: k + 1].T @ (right[: k + 1] @ v)
            beta = np.linalg.norm(v)
            if k % 4 == 3 or k == most - 1:
                a, sv, b = np.linalg.svd(small[: k + 1, : k + 1])
                if beta * abs(a[-1, 0]) <= RESIDUAL * sv[0]:
                    return left[: k + 1].T @ a[:, 0], float(sv[0]), right[: k + 1].T @ b[0]
            if not beta > 0 or k == most - 1:
                break
            right[k + 1], small[k, k + 1] = v / beta, beta
    u, sv, vt = np.linalg.svd(c)
    return u[:, 0], float(sv[0]), vt[0]


def rounded(u: np.ndarray, v: np.ndarray, c: np.ndarray, floor: float):
    """Level sets of a pair of singular vectors with the largest mean of |c|: (mean, rows, columns)."""
    best, least = (-1.0, None, None), max(1, math.ceil(floor))
    for su in (1, -1):
        for sv in (1, -1):
            r, s = np.argsort(su * u, kind="stable"), np.argsort(sv * v, kind="stable")
            mean = c[np.ix_(r, s)]
            np.cumsum(mean, 0, out=mean)
            np.cumsum(mean, 1, out=mean)
            np.abs(mean, out=mean)
            mean /= np.outer(np.arange(1, len(u) + 1), np.arange(1, len(v) + 1))
            mean[: least - 1], mean[:, : least - 1] = -1, -1
            i, j = np.unravel_index(int(mean.argmax()), mean.shape)
            if mean[i, j] > best[0]:
                rows, cols = np.zeros(len(u), bool), np.zeros(len(v), bool)
                rows[r[: i + 1]], cols[s[: j + 1]] = True, True
                best = (float(mean[i, j]), rows, cols)
    return best


def sigma(w: np.ndarray, eps: float, noise_adjust: bool = False, large: float = 0.05):
    """(status, gap, rows, columns, sigma_1): first singular value of the centred block against eps^3 sqrt(pq).

    Witnesses need the lemma's tiny sizes only; level sets of less than ``large`` of a class are not looked at, since
    a cut that small says nothing about the class.
    """
    d = float(w.mean())
    c = w - d
    edge = eps**3 * math.sqrt(w.size)
    if noise_adjust:
        edge = max(edge, 1.05 * 2 * math.sqrt(max(d * (1 - d), 0) * w.shape[1]))
    if np.linalg.norm(c) < edge:
        return UNIFORM, 0.0, None, None, float(np.linalg.norm(c))
    u, first, v = first_triple(c)
    if first < edge:
        return UNIFORM, 0.0, None, None, first
    g = eps**9 / 108
    mean, a, b = rounded(u, v, c, max(g, large) * w.shape[1])
    return (WITNESS, mean, a, b, first) if mean >= g else (UNVERIFIED, 0.0, None, None, first)


def exhaustive(w: np.ndarray, eps: float):
    """Literal definition, by trying every sub-rectangle; for m up to 10."""
    m = w.shape[0]
    if m > 10:
        raise ValueError("the exhaustive check is for blocks of at most 10 x 10")
    d, best = float(w.mean()), (0.0, None, None)
    subsets = [np.array(c) for r in range(1, m + 1) if r > eps * m for c in itertools.combinations(range(m), r)]
    for a in subsets:
        part = w[a]
        for b in subsets:
            g = abs(float(part[:, b].mean()) - d)
            if g > best[0]:
                best = (g, a, b)
    if best[0] < eps:
        return UNIFORM, best[0], None, None
    rows, cols = np.zeros(m, bool), np.zeros(w.shape[1], bool)
    rows[best[1]], cols[best[2]] = True, True
    return WITNESS, best[0], rows, cols


def check(w: np.ndarray, eps: float, checker: str, **options):
    """(status, gap, rows, columns) by any checker; codegree looks in both directions and keeps the larger gap."""
    if checker == "density":  # nothing is tested
        return UNIFORM, 0.0, None, None
    if checker == "sigma":
        return sigma(w, eps, **options)[:4]
    if checker == "exhaustive":
        return exhaustive(w, eps)
    one = codegree(w, eps, **options)
    other = codegree(w.T, eps, **options)
    if other[0] == WITNESS and (one[0] != WITNESS or other[1] > one[1]):
        return other[0], other[1], other[3], other[2]
    return one if one[0] == WITNESS or other[0] == UNIFORM else other


def spectral_labels(a: np.ndarray, c: int, seed: int = 42) -> np.ndarray:
    """Normalised spectral clustering of a symmetric weight matrix: c top eigenvectors, unit rows, k-means."""
    n = len(a)
    if c > n:
        raise ValueError(f"{c} clusters of {n} classes: refine further (min_parts)")
    deg = np.maximum(a.sum(1), 1e-12)
    _, vec = np.linalg.eigh(a / np.sqrt(np.outer(deg, deg)))
    rows = vec[:, -c:]
    return kmeans(rows / np.maximum(np.linalg.norm(rows, axis=1, keepdims=True), 1e-12), c, seed)


def kmeans(x: np.ndarray, c: int, seed: int = 42, restarts: int = 8, steps: int = 100) -> np.ndarray:
    rng, best = np.random.default_rng(seed), (np.inf, np.zeros(len(x), int))
    for _ in range(restarts):
        centres = x[[int(rng.integers(len(x)))]]
        while len(centres) < c:
            d = ((x[:, None] - centres[None]) ** 2).sum(2).min(1)
            centres = np.vstack([centres, x[int(rng.choice(len(x), p=d / d.sum())) if d.sum() > 0 else int(rng.integers(len(x)))]])
        for _ in range(steps):
            d = ((x**2).sum(1)[:, None] + (centres**2).sum(1)[None] - 2 * x @ centres.T)
            lab = d.argmin(1)
            new = np.array([x[lab == j].mean(0) if (lab == j).any() else centres[j] for j in range(c)])
            if np.allclose(new, centres):
                break
            centres = new
        cost = float(d.min(1).sum())
        if cost < best[0] - 1e-12:
            best = (cost, lab)
    return best[1]


def dominant_set_labels(a: np.ndarray, c: int, steps: int = 1000) -> np.ndarray:
    """Replicator dynamics, one dominant set after another; what is left joins the set it is closest to."""
    a = a - np.diag(np.diag(a))
    left, out = np.ones(len(a), bool), np.full(len(a), -1)
    for j in range(c):
        idx = np.flatnonzero(left)
        if not len(idx):
            break
        sub, x = a[np.ix_(idx, idx)], np.full(len(idx), 1 / len(idx))
        for _ in range(steps):
            y = x * (sub @ x)
            if y.sum() <= 0:
                break
            y /= y.sum()
            if np.abs(y - x).sum() < 1e-10:
                break
            x = y
        inside = x > 1e-4 * x.max()
        out[idx[inside]] = j
        left[idx[inside]] = False
    for i in np.flatnonzero(out < 0):
        means = [a[i, out == j].mean() if (out == j).any() else -1 for j in range(c)]
        out[i] = int(np.argmax(means))
    return out


def assignment(gain: np.ndarray) -> np.ndarray:
    """Column of each row in a largest one-to-one matching (potentials, O(c^3)); square input."""
    n = len(gain)
    cost = gain.max() - gain
    u, v, p, way = np.zeros(n + 1), np.zeros(n + 1), np.zeros(n + 1, int), np.zeros(n + 1, int)
    for i in range(1, n + 1):
        p[0], j0 = i, 0
        least, used = np.full(n + 1, np.inf), np.zeros(n + 1, bool)
        while True:
            used[j0] = True
            i0, free = p[j0], np.flatnonzero(~used[1:]) + 1
            cur = cost[i0 - 1, free - 1] - u[i0] - v[free]
            better = cur < least[free]
            least[free[better]], way[free[better]] = cur[better], j0
            j1 = free[int(least[free].argmin())]
            delta = least[j1]
            u[p[used]] += delta
            v[used] -= delta
            least[~used] -= delta
            j0 = j1
            if p[j0] == 0:
                break
        while j0:
            p[j0], j0 = p[way[j0]], way[j0]
    out = np.zeros(n, int)
    out[p[1:] - 1] = np.arange(n)
    return out


def scores(table: np.ndarray) -> dict:
    """Measures of a confusion table (clusters x classes)."""
    table = np.asarray(table, float)
    n, side = table.sum(), max(table.shape)
    square = np.zeros((side, side))
    square[: table.shape[0], : table.shape[1]] = table
    hit = square[np.arange(side), assignment(square)].sum() if n else 0.0
    rows, cols, p = table.sum(1), table.sum(0), table / max(n, 1)
    h = lambda q: float(-(q[q > 0] * np.log(q[q > 0])).sum())
    hr, hc = h(rows / max(n, 1)), h(cols / max(n, 1))
    mutual = hr + hc - h(p.ravel())
    pairs = lambda q: float((q * (q - 1) / 2).sum())
    index, a, b = pairs(table.ravel()), pairs(rows), pairs(cols)
    expected = a * b / max(n * (n - 1) / 2, 1)
    return {
        "accuracy": 100 * hit / max(n, 1), "majority": 100 * cols.max() / max(n, 1), "purity": 100 * table.max(1).sum() / max(n, 1), "clusters": int((rows > 0).sum()),
        "nmi": 0.0 if min(hr, hc) < 1e-12 else mutual / math.sqrt(hr * hc), "ari": 0.0 if (a + b) / 2 == expected else (index - expected) / ((a + b) / 2 - expected),
    }


def confusion_of(labels: np.ndarray, truth: np.ndarray) -> np.ndarray:
    _, a = np.unique(labels, return_inverse=True)
    _, b = np.unique(truth, return_inverse=True)
    out = np.zeros((a.max() + 1, b.max() + 1))
    np.add.at(out, (a, b), 1)
    return out
