"""Numeric kernels for one small graph or model; they run inside a task and see no Spark.

Graphs are dense symmetric arrays with zero diagonal; labels are integer arrays.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np

# --- cuts and relaxations ---------------------------------------------------------------------------------------------------


def laplacian(a: np.ndarray) -> np.ndarray:
    return np.diag(a.sum(1)) - a


def cut_value(a: np.ndarray, labels: np.ndarray) -> float:
    """Weight of the edges between clusters."""
    return float(a[labels[:, None] != labels[None, :]].sum() / 2)


def canonical(labels: np.ndarray) -> np.ndarray:
    """Clusters renamed by their smallest node."""
    _, first, inverse = np.unique(labels, return_index=True, return_inverse=True)
    return np.argsort(np.argsort(first))[inverse]


def cluster_sizes(n: int, k: int, sizes: list[int] | None = None) -> np.ndarray:
    """Prescribed sizes, or sizes that differ by one at most."""
    out = np.array(sizes if sizes else [n // k + (i < n % k) for i in range(k)])
    if out.sum() != n or len(out) != k:
        raise ValueError("cluster sizes must add up to the number of nodes")
    return out


def _affine(m: np.ndarray, size: float) -> np.ndarray:
    """Nearest symmetric matrix with unit diagonal and row sums ``size``; at least 3 nodes."""
    n = len(m)
    r, d = m.sum(1), np.diag(m)
    s = (n * (size - 1) - r.sum() + d.sum()) / (1 - n)
    u = (size - 1 - r + d + s / 2) / (1 - n / 2)
    out = m - (u[:, None] + u[None, :]) / 2
    out[np.diag_indices(n)] -= d - u - 1
    return out


def _spectral(m: np.ndarray, top: float) -> np.ndarray:
    """Nearest symmetric matrix with eigenvalues from 0 to ``top``; row sums and non-negative entries imply the upper end."""
    value, vector = np.linalg.eigh((m + m.T) / 2)
    keep = value > 0
    return (vector[:, keep] * np.minimum(value[keep], top)) @ vector[:, keep].T


#: How far a step of the splitting goes beyond the projection.
AHEAD = 1.6


def _distances(x: np.ndarray, p: np.ndarray, q: np.ndarray, last_p: np.ndarray, last_q: np.ndarray, both: bool) -> tuple[float, float]:
    """How far the copies are apart, and how far they have moved."""
    apart, moved = np.linalg.norm(x - p), np.linalg.norm(p - last_p)
    return (max(apart, np.linalg.norm(x - q)), max(moved, np.linalg.norm(q - last_q))) if both else (apart, moved)


def _pull(apart: float, moved: float) -> float:
    """Factor of the penalty: more where the copies disagree, less where they wander."""
    return 1.6 if apart > 3 * moved else 1 / 1.6 if moved > 3 * apart else 1.0


def _certificate(cost: np.ndarray, size: float, pull_p: np.ndarray, pull_n: np.ndarray) -> float:
    """A lower bound on <cost, Y> over the relaxation, valid for any multipliers: a feasible Y has trace n and eigenvalues up to ``size``."""
    n = len(cost)
    m = cost - pull_p - pull_n
    r, d = m.sum(1), np.diag(m)
    s = (d.sum() - r.sum()) / (1 - n)
    u = (d - r + s / 2) / (1 - n / 2)
    y = d - u
    rest = cost - pull_n - np.diag(y) - (u[:, None] + u[None, :]) / 2
    low = np.linalg.eigvalsh((rest + rest.T) / 2)
    return float(y.sum() + size * u.sum() + size * low[: round(n / size)].sum())


def eigen_bound(a: np.ndarray, sizes: np.ndarray, sense: str) -> float:
    """Bound of the cut into clusters of these sizes from the Laplacian's spectrum.

    The Gram matrix of a partition has the sizes as eigenvalues, so the largest meets the smallest of the Laplacian's, or the
    largest for a maximum; equal sizes leave the zero eigenvalue to the constant vector.
    """
    value, sizes = np.linalg.eigvalsh(laplacian(a)), np.sort(sizes)[::-1]
    if sense == "min":
        return float((sizes * value[: len(sizes)]).sum() / 2)
    if len(set(sizes.tolist())) == 1:
        return float(sizes[0] * value[len(a) - len(sizes) + 1 :].sum() / 2)
    return float((sizes * value[::-1][: len(sizes)]).sum() / 2)


def _least_trace(low: np.ndarray, total: float, top: float) -> float:
    """Least <Z, W> over W with this trace and eigenvalues from 0 to ``top``, for Z with ascending eigenvalues ``low``."""
    whole = min(len(low), int(total // top))
    rest = total - whole * top
    return float(top * low[:whole].sum() + (rest * low[whole] if whole < len(low) else 0.0))


def relax_sizes(a: np.ndarray, sizes: np.ndarray, sense: str, level: str = "psd_nonneg", rounds: int = 1500, tol: float = 2e-5, gap: float = 1e-5) -> tuple[np.ndarray, float, float]:
    """``relax`` for clusters of any prescribed sizes: Gram matrix, objective and certified bound.

    Row sums differ then, so the matrix keeps a unit diagonal, the sum of the squared sizes over all entries, and an excess over
    the constant matrix 1/k without negative eigenvalues; ``psd_nonneg`` adds non-negative entries.  The bound holds for any
    multipliers, as that excess has trace n - n/k and eigenvalues up to the largest size; the spectral bound stands in where
    it is tighter.
    """
    n, k = len(a), len(sizes)
    sign = 1.0 if sense == "min" else -1.0
    spectral = eigen_bound(a, sizes, sense)
    if level == "eigen":
        return np.eye(n), spectral, spectral
    whole, most = float((sizes**2).sum()), float(sizes.max())
    cost = sign * laplacian(a) / 2
    rho = max(float(np.abs(cost).mean()), 1e-12)
    both = level == "psd_nonneg"
    off = ~np.eye(n, dtype=bool)
    pairs = n * (n - 1)

    def affine(m: np.ndarray) -> np.ndarray:
        out = (m + m.T) / 2
        out = out + (whole - n - out[off].sum()) / pairs
        np.fill_diagonal(out, 1.0)
        return out

    def certified(up: np.ndarray, un: np.ndarray) -> float:
        pull = np.maximum(-rho * un, 0) if both else np.zeros((n, n))
        fit = cost + rho * up - pull
        s = fit[off].mean()
        y = np.diag(fit) - s
        low = np.linalg.eigvalsh(cost - pull - np.diag(y) - s)
        rest = (cost - pull - np.diag(y) - s).sum() / k  # what meets the constant matrix
        return float(y.sum() + s * whole + rest + _least_trace(low, n - n / k, most))

    x = affine(np.full((n, n), (whole - n) / pairs))
    p = q = x
    up, un = np.zeros((n, n)), np.zeros((n, n))
    best = -math.inf
    for step in range(1, rounds + 1):
        x = affine((p - up + q - un) / 2 - cost / (2 * rho) if both else p - up - cost / rho)
        last_p, last_q = p, q
        ahead = AHEAD * x + (1 - AHEAD) * p
        value, vector = np.linalg.eigh(ahead + up - 1.0 / k)
        keep = value > 0
        p = (vector[:, keep] * np.minimum(value[keep], most)) @ vector[:, keep].T + 1.0 / k
        up = up + ahead - p
        if both:
            ahead = AHEAD * x + (1 - AHEAD) * q
            q = np.maximum(ahead + un, 0)
            un = un + ahead - q
        apart, moved = _distances(x, p, q, last_p, last_q, both)
        if max(apart, moved) < tol * n:
            break
        if step % 50 == 0 and max(apart, moved) < 20 * tol * n:
            best = max(best, certified(up, un))
            if abs((cost * x).sum() - best) <= gap * max(1.0, abs(best)):
                break
        if step % 20 == 0:
            pull = _pull(apart, moved)
            rho, up, un = rho * pull, up / pull, un / pull
    bound = sign * max(best, certified(up, un))
    bound = max(bound, spectral) if sense == "min" else min(bound, spectral)
    return x, sign * float((cost * x).sum()), bound


def relax(a: np.ndarray, k: int, sense: str, level: str = "psd_nonneg", rounds: int = 1500, tol: float = 2e-5, gap: float = 1e-5) -> tuple[np.ndarray, float, float]:
    """Relaxed Gram matrix, its objective and a certified bound of the cut into k equal clusters.

    It ends when the copies agree to ``tol``, when the bound comes within the share ``gap`` of the objective, or after ``rounds``.

    ``level``: ``psd`` keeps unit diagonal, row sums and eigenvalues from 0 to the cluster size; ``psd_nonneg`` adds non-negative entries;
    ``eigen`` is the spectral bound with no matrix of its own.  Splitting: one copy of the matrix for each constraint set.
    """
    n = len(a)
    size = n / k
    sign = 1.0 if sense == "min" else -1.0
    if level == "eigen":
        return np.eye(n), *[eigen_bound(a, np.full(k, n // k), sense)] * 2
    if k == 1 or n <= 2 or k == n:
        y = np.ones((n, n)) if k == 1 else np.eye(n)
        value = 0.0 if k == 1 else float(a.sum() / 2)
        return y, value, value
    cost = sign * laplacian(a) / 2
    rho = max(float(np.abs(cost).mean()), 1e-12)
    both = level == "psd_nonneg"
    x = np.full((n, n), (size - 1) / (n - 1))
    np.fill_diagonal(x, 1.0)
    p = q = x
    up, un = np.zeros((n, n)), np.zeros((n, n))
    certified = lambda: _certificate(cost, size, -rho * up, np.maximum(-rho * un, 0) if both else np.zeros((n, n)))
    best = -math.inf
    for step in range(1, rounds + 1):
        x = _affine((p - up + q - un) / 2 - cost / (2 * rho) if both else p - up - cost / rho, size)
        last_p, last_q = p, q
        ahead = AHEAD * x + (1 - AHEAD) * p
        p = _spectral(ahead + up, size)
        up = up + ahead - p
        if both:
            ahead = AHEAD * x + (1 - AHEAD) * q
            q = np.maximum(ahead + un, 0)
            un = un + ahead - q
        apart, moved = _distances(x, p, q, last_p, last_q, both)
        if max(apart, moved) < tol * n:
            break
        if step % 50 == 0 and max(apart, moved) < 20 * tol * n:
            best = max(best, certified())
            if abs((cost * x).sum() - best) <= gap * max(1.0, abs(best)):
                break
        if step % 20 == 0:
            pull = _pull(apart, moved)
            rho, up, un = rho * pull, up / pull, un / pull
    bound = sign * max(best, certified())
    return x, sign * float((cost * x).sum()), bound


def solve_sdp(cost: np.ndarray, rows: list[np.ndarray], rhs: np.ndarray, *, trace: float | None = None, rounds: int = 2000, tol: float = 1e-7) -> tuple[np.ndarray, float, float]:
    """min <cost, X> over X without negative eigenvalues and <rows[i], X> = rhs[i]: X, its objective and a lower bound.

    The canonical form, for any symmetric constraint matrices, by an augmented Lagrangian of the dual.  The bound is
    certified where ``trace`` limits the trace of a feasible X; without it, it is the dual objective.
    """
    n = len(cost)
    a = np.stack([np.asarray(m, float).ravel() for m in rows])
    rhs = np.asarray(rhs, float)
    inverse = np.linalg.pinv(a @ a.T)
    x, s = np.eye(n), np.zeros((n, n))
    mu = 1.0
    y = np.zeros(len(rhs))
    for step in range(1, rounds + 1):
        y = -inverse @ (mu * (a @ x.ravel() - rhs) + a @ (s - cost).ravel())
        v = cost - (a.T @ y).reshape(n, n) - mu * x
        value, vector = np.linalg.eigh((v + v.T) / 2)
        keep = value > 0
        s = (vector[:, keep] * value[keep]) @ vector[:, keep].T
        x = (s - v) / mu
        primal = np.linalg.norm(a @ x.ravel() - rhs) / (1 + np.linalg.norm(rhs))
        dual = np.linalg.norm(cost - (a.T @ y).reshape(n, n) - s) / (1 + np.linalg.norm(cost))
        if max(primal, dual) < tol:
            break
        if step % 20 == 0:
            mu = mu * 0.7 if primal < dual / 3 else mu / 0.7 if dual < primal / 3 else mu
    low = float(np.linalg.eigvalsh(cost - (a.T @ y).reshape(n, n))[0])
    return x, float((cost * x).sum()), float(rhs @ y) + (min(0.0, low) * trace if trace is not None else 0.0)


def canonical_cut(a: np.ndarray, k: int, sense: str) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Constraint matrices, right-hand sides and cost of the relaxed cut into k equal clusters in canonical form: unit diagonal, equal row sums."""
    n = len(a)
    unit = np.eye(n)
    rows = [np.outer(e, e) for e in unit] + [(np.outer(e, np.ones(n)) + np.outer(np.ones(n), e)) / 2 for e in unit]
    return rows, np.array([1.0] * n + [n / k] * n), (1.0 if sense == "min" else -1.0) * laplacian(a) / 2


def factor(y: np.ndarray, rank: int | None = None) -> np.ndarray:
    """Points whose inner products are the Gram matrix."""
    value, vector = np.linalg.eigh((y + y.T) / 2)
    points = vector * np.sqrt(np.maximum(value, 0))
    points = points[:, ::-1]
    return points[:, :rank] if rank else points


def spectral_points(a: np.ndarray, k: int, sense: str) -> np.ndarray:
    """Eigenvectors of the Laplacian for the relaxation that drops everything but the spectrum."""
    _, vector = np.linalg.eigh(laplacian(a))
    return vector[:, 1:k] if sense == "min" else vector[:, len(a) - k + 1 :]


# --- rounding ---------------------------------------------------------------------------------------------------------------


def assign_balanced(score: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Labels that take the largest scores first while clusters have room."""
    n, k = score.shape
    room = sizes.copy()
    labels = np.full(n, -1)
    for flat in np.argsort(-score, axis=None, kind="stable"):
        i, c = divmod(int(flat), k)
        if labels[i] < 0 and room[c]:
            labels[i] = c
            room[c] -= 1
    return labels


def _swap(score: np.ndarray, labels: np.ndarray) -> np.ndarray:
    """Pair swaps while they raise the total score."""
    n = len(labels)
    labels = labels.copy()
    for _ in range(4 * n):
        own = score[np.arange(n), labels]
        cross = score[:, labels]  # score of i in the cluster of j
        gain = cross + cross.T - own[:, None] - own[None, :]
        i, j = divmod(int(gain.argmax()), n)
        if gain[i, j] <= 1e-12:
            break
        labels[i], labels[j] = labels[j], labels[i]
    return labels


def polish(a: np.ndarray, labels: np.ndarray, sense: str) -> np.ndarray:
    """Pair swaps while they better the cut itself."""
    sign = 1.0 if sense == "min" else -1.0
    labels = labels.copy()
    n, k = len(labels), labels.max() + 1
    for _ in range(8 * n):
        inside = a @ np.eye(k)[labels]  # weight from each node into each cluster
        own = inside[np.arange(n), labels]
        cross = inside[:, labels]
        gain = sign * (cross + cross.T - own[:, None] - own[None, :] - 2 * a)
        gain[labels[:, None] == labels[None, :]] = -np.inf
        i, j = divmod(int(gain.argmax()), n)
        if not gain[i, j] > 1e-12:
            break
        labels[i], labels[j] = labels[j], labels[i]
    return labels


def _best(a: np.ndarray, found: list[np.ndarray], sense: str) -> np.ndarray:
    cuts = [cut_value(a, x) for x in found]
    return found[int(np.argmin(cuts) if sense == "min" else np.argmax(cuts))]


def round_kmeans(points: np.ndarray, a: np.ndarray, sizes: np.ndarray, sense: str, restarts: int = 20, seed: int = 0) -> np.ndarray:
    """K-means under capacities, from several starts; the best cut stays."""
    rng = np.random.default_rng(seed)
    n, k = len(points), len(sizes)
    found = []
    for _ in range(restarts):
        centre = points[rng.choice(n, k, replace=False)]
        labels = None
        for _ in range(30):
            score = -((points[:, None, :] - centre[None, :, :]) ** 2).sum(2)
            new = _swap(score, assign_balanced(score, sizes))
            if labels is not None and (new == labels).all():
                break
            labels = new
            centre = np.stack([points[labels == c].mean(0) if (labels == c).any() else centre[c] for c in range(k)])
        found.append(labels)
    return canonical(_best(a, found, sense))


def round_projection(points: np.ndarray, a: np.ndarray, sizes: np.ndarray, sense: str, trials: int = 1, repair: bool = True, seed: int = 0) -> np.ndarray:
    """The nearest of k random directions for each point; with ``repair`` under capacities, else clusters may be uneven or empty."""
    rng = np.random.default_rng(seed)
    found = []
    for _ in range(trials):
        score = points @ rng.normal(size=(points.shape[1], len(sizes)))
        found.append(assign_balanced(score, sizes) if repair else score.argmax(1))
    return canonical(_best(a, found, sense))


def round_hyperplane(points: np.ndarray, a: np.ndarray, sense: str, trials: int = 20, sizes: np.ndarray | None = None, seed: int = 0) -> np.ndarray:
    """Two sides of a random hyperplane; with ``sizes`` it is moved until they hold."""
    rng = np.random.default_rng(seed)
    found = []
    for _ in range(trials):
        side = points @ rng.normal(size=points.shape[1])
        if sizes is not None:
            labels = np.zeros(len(side), int)
            labels[np.argsort(side, kind="stable")[sizes[0] :]] = 1
        else:
            labels = (side > 0).astype(int)
        found.append(labels)
    return canonical(_best(a, found, sense))


def round_linearised(y: np.ndarray, a: np.ndarray, sizes: np.ndarray, sense: str, starts: int = 20, steps: int = 20, seed: int = 0) -> np.ndarray:
    """First-order rounding around the relaxed solution.

    The quadratic cost is replaced by its tangent at the relaxed matrix' own soft clusters (the mean relaxed affinity of each node
    to the members of a cluster), and the linear problem is solved under capacities; the members follow until they stay.
    """
    rng = np.random.default_rng(seed)
    n, k = len(a), len(sizes)
    sign = 1.0 if sense == "min" else -1.0
    found = []
    for _ in range(starts):
        labels = assign_balanced(y[:, rng.choice(n, k, replace=False)], sizes)
        for _ in range(steps):
            soft = y @ np.eye(k)[labels] / sizes
            slope = sign * (a @ soft)
            new = _swap(slope, assign_balanced(slope, sizes))
            found.append(new)
            if (new == labels).all():
                break
            labels = new
    return canonical(_best(a, found, sense))


def partitions_of(sizes: np.ndarray):
    """All partitions into clusters of these sizes, as label tuples; cluster ids rise with their smallest node."""
    n = int(sum(sizes))

    def grow(labels: list[int], room: list[int], closed: list[int]):
        if len(labels) == n:
            yield tuple(labels)
            return
        for c in range(len(room)):
            if room[c]:
                room[c] -= 1
                yield from grow([*labels, c], room, closed)
                room[c] += 1
        for size in sorted(set(closed)):  # a new cluster of one of the sizes that are left
            rest = closed.copy()
            rest.remove(size)
            yield from grow([*labels, len(room)], [*room, size - 1], rest)

    yield from grow([], [], [int(x) for x in sizes])


def brute_cut(a: np.ndarray, k: int, sense: str, sizes: np.ndarray | None = None) -> tuple[float, np.ndarray]:
    """The best cut of all partitions into k clusters of these sizes, or of sizes that differ by one at most."""
    best, out = None, None
    for labels in partitions_of(cluster_sizes(len(a), k) if sizes is None else sizes):
        c = cut_value(a, np.array(labels))
        if best is None or (c < best - 1e-12 if sense == "min" else c > best + 1e-12):
            best, out = c, np.array(labels)
    return best, out


METHODS = ("kmeans", "projection", "projection_raw", "hyperplane", "hyperplane_raw", "linearised", "spectral", "brute")


def partition(a: np.ndarray, k: int, sense: str = "min", method: str = "kmeans", sizes: list[int] | None = None, seed: int = 0, restarts: int = 20, level: str = "psd_nonneg", rounds: int = 1500) -> dict:
    """Labels, cut, bound and their ratio by one of the ways to relax and round.

    Sizes that differ are relaxed as such.  The bound is certified; without one (raw roundings may break the sizes) bound and
    ratio are None, never the cut itself.
    """
    n = len(a)
    if method not in METHODS:
        raise ValueError(f"no method {method}")
    if method.startswith("hyperplane") and k != 2:
        raise ValueError("a hyperplane has two sides")
    room = cluster_sizes(n, k, sizes)
    equal = len(set(room.tolist())) == 1
    scale = float(np.abs(a).max()) or 1.0
    b = a / scale
    if k in (1, n):
        labels = np.arange(n) if k == n else np.zeros(n, int)
        bound = cut_value(b, labels)  # the one partition there is
    elif method == "brute":
        bound, labels = brute_cut(b, k, sense, room)
    elif method == "spectral":
        bound = eigen_bound(b, room, sense)
        labels = round_kmeans(spectral_points(b, k, sense), b, room, sense, restarts, seed)
    else:
        y, _, bound = relax(b, k, sense, level if level != "eigen" else "psd", rounds) if equal else relax_sizes(b, room, sense, level if level != "eigen" else "psd", rounds)
        points = factor(y)
        if method == "kmeans":
            labels = round_kmeans(points, b, room, sense, restarts, seed)
        elif method.startswith("projection"):
            labels = round_projection(points, b, room, sense, restarts, method == "projection", seed)
        elif method.startswith("hyperplane"):
            labels = round_hyperplane(points, b, sense, restarts, room if method == "hyperplane" else None, seed)
        else:
            labels = round_linearised(y, b, room, sense, restarts, seed=seed)
        if method.endswith("_raw"):
            bound = None
    cut = cut_value(a, labels)
    if bound is None:
        return {"labels": canonical(labels), "cut": cut, "bound": None, "ratio": None}
    bound = float(bound * scale)
    return {"labels": canonical(labels), "cut": cut, "bound": bound, "ratio": cut / bound if abs(bound) > 1e-9 * scale else 1.0 if cut <= 1e-9 * scale else None}


def treewidth_minfill(a: np.ndarray) -> int:
    """Upper bound of the treewidth: eliminate, again and again, the node that needs fewest new edges."""
    near = [set(np.flatnonzero(row)) for row in a]
    left = set(range(len(a)))
    width = 0
    while left:
        fill = lambda v: sum(y not in near[x] for x, y in combinations(sorted(near[v]), 2))
        v = min(sorted(left), key=fill)
        width = max(width, len(near[v]))
        for x, y in combinations(near[v], 2):
            near[x].add(y)
            near[y].add(x)
        for x in near[v]:
            near[x].discard(v)
        left.discard(v)
    return width


# --- inference --------------------------------------------------------------------------------------------------------------


def values_of(domain: str) -> np.ndarray:
    return np.array({"spin": (-1.0, 1.0), "bit": (0.0, 1.0)}[domain])


def states_of(n: int, domain: str) -> np.ndarray:
    """All joint states of n binary variables; bit i of the row number is variable i."""
    return values_of(domain)[(np.arange(1 << n)[:, None] >> np.arange(n)) & 1]


def exact(h: np.ndarray, w: np.ndarray, domain: str) -> tuple[float, np.ndarray]:
    """Log-normaliser and probabilities of the upper state, by enumeration in two halves joined by one product."""
    n = len(h)
    lo, hi = n // 2, n - n // 2
    s, t = states_of(lo, domain), states_of(hi, domain)
    u = np.triu(w, 1)
    low = s @ h[:lo] + ((s @ u[:lo, :lo]) * s).sum(1)
    high = t @ h[lo:] + ((t @ u[lo:, lo:]) * t).sum(1)
    bridge = s @ u[:lo, lo:]
    top, total = -np.inf, 0.0
    rows, cols = np.zeros(len(s)), np.zeros(len(t))
    step = max(1, (1 << 22) // len(s))
    for i in range(0, len(t), step):
        e = low[:, None] + high[None, i : i + step] + bridge @ t[i : i + step].T
        new = max(top, float(e.max()))
        shrink = math.exp(top - new) if top > -np.inf else 0.0
        p = np.exp(e - new)
        rows, cols, total, top = rows * shrink, cols * shrink, total * shrink, new
        rows += p.sum(1)
        cols[i : i + step] += p.sum(0)
        total += p.sum()
    up = values_of(domain)[1]
    return top + math.log(total), np.concatenate([rows @ (s == up), cols @ (t == up)]) / total


def _softmax(x: np.ndarray) -> tuple[np.ndarray, float]:
    top = x.max()
    p = np.exp(x - top)
    z = p.sum()
    return p / z, float(top + math.log(z))


class ClusterField:
    """Cluster mean field of one pairwise binary model: exact tables inside clusters, averages across."""

    def __init__(self, h: np.ndarray, w: np.ndarray, labels: np.ndarray, domain: str = "spin", budget: int = 1 << 20):
        self.h, self.w, self.domain = h, w, domain
        self.labels = np.asarray(labels)
        self.members = [np.flatnonzero(self.labels == c) for c in np.unique(self.labels)]
        if max(len(m) for m in self.members) > math.log2(budget):
            raise ValueError("a cluster has more joint states than the budget allows")
        self.states = [states_of(len(m), domain) for m in self.members]
        self.inner = [((s @ np.triu(w[np.ix_(m, m)], 1)) * s).sum(1) + s @ h[m] for m, s in zip(self.members, self.states)]
        self.across = np.where(self.labels[:, None] != self.labels[None, :], w, 0.0)
        self.mean = np.full(len(h), values_of(domain).mean())
        self.q = [np.full(len(s), 1 / len(s)) for s in self.states]
        self.log_z = [0.0] * len(self.members)

    def update(self, c: int, mean: np.ndarray, damping: float = 0.0) -> None:
        m, s = self.members[c], self.states[c]
        q, self.log_z[c] = _softmax(self.inner[c] + s @ (self.across[m] @ mean))
        self.q[c] = q if not damping else (1 - damping) * q + damping * self.q[c]

    def _means(self, c: int) -> None:
        self.mean[self.members[c]] = self.q[c] @ self.states[c]

    def run(self, schedule: str = "sequential", tol: float = 1e-10, sweeps: int = 500, damping: float = 0.0, init: np.ndarray | None = None) -> list[tuple[int, float, float]]:
        """Updates until no mean moves by ``tol``; rows of (sweep, largest move, bound).

        ``colour`` takes the clusters in the order of colours that touching clusters do not share.
        """
        trace = []
        order = self.colours() if schedule == "colour" else range(len(self.members))
        if init is not None:
            self.mean = init.astype(float).copy()
        for sweep in range(sweeps):
            before = self.mean.copy()
            for c in order:
                self.update(c, before if schedule == "jacobi" else self.mean, damping)
                if schedule != "jacobi":
                    self._means(c)
            if schedule == "jacobi":
                for c in range(len(self.members)):
                    self._means(c)
            move = float(np.abs(self.mean - before).max())
            trace.append((sweep, move, self.bound()))
            if move < tol:
                break
        return trace

    def colours(self) -> list[int]:
        """Clusters by the least colour that no touching cluster before them has."""
        colour: dict[int, int] = {}
        for c, m in enumerate(self.members):
            taken = {colour[d] for d in colour if self.across[np.ix_(m, self.members[d])].any()}
            colour[c] = next(x for x in range(len(self.members)) if x not in taken)
        return sorted(colour, key=lambda c: (colour[c], c))

    def bound(self) -> float:
        """Expected log-potential plus entropy: a lower bound of the log-normaliser at any tables."""
        total = 0.5 * float(self.mean @ self.across @ self.mean)
        for q, e in zip(self.q, self.inner):
            p = q[q > 0]
            total += float(q @ e - p @ np.log(p))
        return total

    def prob(self) -> np.ndarray:
        low, high = values_of(self.domain)
        return (self.mean - low) / (high - low)

    def broken(self) -> float:
        return float(np.abs(self.across).sum() / 2)

    def kl_upper(self) -> float:
        """Certificate of the divergence from the broken weight; the sign of a coupling is part of its potential."""
        used = self.across[np.triu_indices(len(self.h), 1)]
        used = used[used != 0]
        if not len(used):
            return 0.0
        low, high = zip(*[self._range(x) for x in used])
        b_phi = max(high)
        a_z = min(lo + (lo - hi) for lo, hi in zip(low, high))
        return (b_phi - a_z) * float(np.abs(used).sum())

    def _range(self, x: float) -> tuple[float, float]:
        if self.domain == "spin":
            return -1.0, 1.0
        return (0.0, 1.0) if x > 0 else (-1.0, 0.0)


def best_restart(h: np.ndarray, w: np.ndarray, labels: np.ndarray, domain: str, restarts: int = 1, seed: int = 0, budget: int = 1 << 20, init: np.ndarray | None = None, **options) -> tuple[ClusterField, list[tuple[int, float, float]]]:
    """The run with the best bound, and its trace, among a uniform (or the given) start, all high, all low, and random ones.

    Attractive couplings have one optimum near each of the two ordered starts, which random ones may miss.
    """
    rng = np.random.default_rng(seed)
    best, steps = None, []
    for r in range(restarts):
        field = ClusterField(h, w, labels, domain, budget)
        low, high = values_of(domain)
        start = init if r == 0 else np.full(len(h), 0.05 * low + 0.95 * high if r == 1 else 0.95 * low + 0.05 * high) if r < 3 else rng.uniform(low, high, len(h))
        trace = field.run(init=start, **options)
        if best is None or field.bound() > best.bound() + 1e-12:
            best, steps = field, trace
    return best, steps


# --- tree-linked clusters ---------------------------------------------------------------------------------------------------


def cluster_tree(w: np.ndarray, labels: np.ndarray) -> list[tuple[int, int, int, int]]:
    """Maximum spanning forest of the cluster graph: (cluster, cluster, node, node) of each link, the heaviest shared edge."""
    edges = [(-abs(w[i, j]), i, j) for i in range(len(w)) for j in range(i + 1, len(w)) if w[i, j] and labels[i] != labels[j]]
    root = {c: c for c in np.unique(labels)}

    def find(c: int) -> int:
        while root[c] != c:
            c = root[c]
        return c

    out = []
    for _, i, j in sorted(edges):
        a, b = find(labels[i]), find(labels[j])
        if a != b:
            root[max(a, b)] = min(a, b)
            out.append((min(labels[i], labels[j]), max(labels[i], labels[j]), i, j))
    return out


class TreeField(ClusterField):
    """Clusters joined by a spanning forest of links that stay exact; all other crossing edges are averaged."""

    def __init__(self, h: np.ndarray, w: np.ndarray, labels: np.ndarray, domain: str = "spin", budget: int = 1 << 20):
        super().__init__(h, w, labels, domain, budget)
        ids = {int(c): k for k, c in enumerate(np.unique(self.labels))}
        self.links = [(ids[int(a)], ids[int(b)], i, j) if ids[int(a)] == self._at(ids, i) else (ids[int(b)], ids[int(a)], i, j) for a, b, i, j in cluster_tree(w, self.labels)]
        for _, _, i, j in self.links:
            self.across[i, j] = self.across[j, i] = 0.0
        self.near: dict[int, list[tuple[int, int, int]]] = {c: [] for c in range(len(self.members))}
        for a, b, i, j in self.links:
            self.near[a].append((b, i, j))
            self.near[b].append((a, j, i))

    def _at(self, ids: dict[int, int], node: int) -> int:
        return ids[int(self.labels[node])]

    def _message(self, source: int, target: int, fields: list[np.ndarray]) -> np.ndarray:
        """Log-message from a cluster over the link's far node, from the part of the tree behind it."""
        value = values_of(self.domain)
        e = fields[source].copy()
        link = None
        for other, mine, far in self.near[source]:
            if other == target:
                link = (mine, far)
            else:
                bit = (np.arange(len(e)) >> int(np.searchsorted(self.members[source], mine))) & 1
                e += self._message(other, source, fields)[bit]
        mine, far = link
        own = self.states[source][:, int(np.searchsorted(self.members[source], mine))]
        return np.array([_softmax(e + self.w[mine, far] * own * v)[1] for v in value])

    def _tables(self, mean: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray]]:
        fields = [e + s @ (self.across[m] @ mean) for e, s, m in zip(self.inner, self.states, self.members)]
        out = []
        for c in range(len(self.members)):
            e = fields[c].copy()
            for other, mine, _ in self.near[c]:
                bit = (np.arange(len(e)) >> int(np.searchsorted(self.members[c], mine))) & 1
                e += self._message(other, c, fields)[bit]
            out.append(_softmax(e)[0])
        return out, fields

    def _tree_log_z(self, fields: list[np.ndarray]) -> float:
        seen: set[int] = set()
        total = 0.0
        for c in range(len(self.members)):
            if c in seen:
                continue
            stack = [c]
            while stack:
                x = stack.pop()
                if x not in seen:
                    seen.add(x)
                    stack += [o for o, _, _ in self.near[x]]
            e = fields[c].copy()
            for other, mine, _ in self.near[c]:
                bit = (np.arange(len(e)) >> int(np.searchsorted(self.members[c], mine))) & 1
                e += self._message(other, c, fields)[bit]
            total += _softmax(e)[1]
        return total

    def _pair(self, i: int, j: int, mean: np.ndarray) -> float:
        """Expectation of a product under the current tree, by clamping one end to each of its values."""
        low, high = values_of(self.domain)
        c = int(np.searchsorted(np.unique(self.labels), self.labels[i]))
        fields = [e + s @ (self.across[m] @ mean) for e, s, m in zip(self.inner, self.states, self.members)]
        base = self._tree_log_z(fields)
        total = 0.0
        for v in (low, high):
            held = list(fields)
            held[c] = np.where(self.states[c][:, int(np.searchsorted(self.members[c], i))] == v, fields[c], -1e300)
            p = math.exp(self._tree_log_z(held) - base)
            if p > 0:
                d = int(np.searchsorted(np.unique(self.labels), self.labels[j]))
                e = held[d].copy()
                for other, mine, _ in self.near[d]:
                    bit = (np.arange(len(e)) >> int(np.searchsorted(self.members[d], mine))) & 1
                    e += self._message(other, d, held)[bit]
                q = _softmax(e)[0]
                total += p * v * float(q @ self.states[d][:, int(np.searchsorted(self.members[d], j))])
        return total

    def _bound_at(self, mean: np.ndarray) -> tuple[float, list[np.ndarray], np.ndarray]:
        """Bound of the tree distribution whose fields come from ``mean``, its tables and its own means."""
        tables, fields = self._tables(mean)
        own = mean.copy()
        for c, q in enumerate(tables):
            own[self.members[c]] = q @ self.states[c]
        # log-normaliser of the tree, fields out, true crossing potentials in
        total = self._tree_log_z(fields) - float(own @ self.across @ mean)
        for i, j in zip(*np.nonzero(np.triu(self.across, 1))):
            total += self.across[i, j] * self._pair(int(i), int(j), mean)
        return total, tables, own

    def run(self, tol: float = 1e-9, sweeps: int = 200, **_) -> list[tuple[int, float, float]]:
        """Fields from means, messages up and down the tree, and a step that is shortened while the bound would fall."""
        trace = []
        plain = ClusterField(self.h, self.w, self.labels, self.domain)
        plain.run(tol=tol)
        starts = [(self._bound_at(m)[0], k, m) for k, m in enumerate((self.mean.copy(), plain.mean))]
        used = max(starts, key=lambda x: x[:2])[2]
        best, self.q, own = self._bound_at(used)
        for sweep in range(sweeps):
            step, moved = 1.0, 0.0
            while step > 1e-3:
                trial = used + step * (own - used)
                value, tables, after = self._bound_at(trial)
                if value >= best - 1e-12:
                    moved = float(np.abs(trial - used).max())
                    best, self.q, own, used = value, tables, after, trial
                    break
                step /= 2
            trace.append((sweep, moved, best))
            if moved < tol:
                break
        self.mean, self._value = own, best
        return trace

    def bound(self) -> float:
        return getattr(self, "_value", -math.inf)
