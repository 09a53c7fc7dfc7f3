"""Clusterers on one dense matrix, for topics that fit a task (thousands of predicates); used inside grouped maps."""

from __future__ import annotations

import numpy as np


def sq_distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None] - 2 * x @ y.T, 0)


def seeds(x: np.ndarray, k: int, init: str, rng: np.random.Generator, degree: np.ndarray | None = None) -> np.ndarray:
    """Row numbers to start from: random, spread (farthest first from the row nearest the mean) or top_degree."""
    n = len(x)
    if init == "random":
        return rng.permutation(n)[:k]
    if init == "top_degree":
        return np.argsort(-degree, kind="stable")[:k]
    chosen = [int(np.round(sq_distances(x, x.mean(0, keepdims=True))[:, 0], 9).argmin())]
    near = sq_distances(x, x[chosen])[:, 0]
    while len(chosen) < k:
        chosen.append(int(np.round(near, 9).argmax()))
        near = np.minimum(near, sq_distances(x, x[chosen[-1:]])[:, 0])
    return np.array(chosen)


def lloyd(x: np.ndarray, k: int, init: str = "spread", seed: int = 0, degree: np.ndarray | None = None, max_iter: int = 100) -> tuple[np.ndarray, float]:
    """(labels, inertia). An empty cluster is seeded anew with the row farthest from its centre."""
    k = min(k, len(x))
    centres = x[seeds(x, k, init, np.random.default_rng(seed), degree)].copy()
    labels = np.full(len(x), -1)
    for _ in range(max_iter):
        d = np.round(sq_distances(x, centres), 9)
        new = d.argmin(1)
        for c in range(k):
            if not (new == c).any():
                far = int(d[np.arange(len(x)), new].argmax())
                new[far] = c
                d[far] = 0
        if (new == labels).all():
            break
        labels = new
        centres = np.stack([x[labels == c].mean(0) if (labels == c).any() else centres[c] for c in range(k)])
    return labels, float(((x - centres[labels]) ** 2).sum())


def silhouette(d: np.ndarray, labels: np.ndarray) -> np.ndarray:
    """Silhouette of each row; 0 for rows alone in a cluster and where there is one cluster only."""
    names, at = np.unique(labels, return_inverse=True)
    size = np.bincount(at)
    if len(names) < 2:
        return np.zeros(len(labels))
    sums = np.stack([d[:, at == c].sum(1) for c in range(len(names))], axis=1)
    own = size[at] - 1
    rows = np.arange(len(labels))
    a = sums[rows, at] / np.maximum(own, 1)
    mean = sums / size
    mean[rows, at] = np.inf
    b = mean.min(1)
    top = np.maximum(a, b)
    return np.where((own == 0) | (top == 0), 0.0, (b - a) / np.where(top == 0, 1, top))


def dissimilarities(rows: np.ndarray, at: np.ndarray, kind: str, eps: float = 1e-3) -> np.ndarray:
    """Between members, from their whole matrix rows and their own columns."""
    block = rows[:, at]
    if kind == "one_minus":
        d = 1 - block
    elif kind == "reciprocal":
        d = 1 / np.maximum(block, eps) - 1
    else:
        d = sq_distances(rows, rows)
        d = d if kind == "row_sqeuclid" else np.sqrt(d)
    d = d.copy()
    np.fill_diagonal(d, 0)
    return d


def medoids(d: np.ndarray, k: int, max_swaps: int = 200) -> tuple[np.ndarray, float]:
    """(medoid of each row, cost): greedy build, then the best swap as long as one helps."""
    n = len(d)
    k = min(k, n)
    chosen = [int(d.sum(1).argmin())]
    near = d[:, chosen[0]].copy()
    while len(chosen) < k:
        gain = np.maximum(near[:, None] - d, 0).sum(0)
        gain[chosen] = -1
        chosen.append(int(gain.argmax()))
        near = np.minimum(near, d[:, chosen[-1]])
    cost = near.sum()
    for _ in range(max_swaps):
        best = (cost - 1e-12, None)
        for j, m in enumerate(chosen):
            rest = [c for c in chosen if c != m]
            base = d[:, rest].min(1) if rest else np.full(n, np.inf)
            total = np.minimum(base[:, None], d).sum(0)
            total[chosen] = np.inf
            h = int(total.argmin())
            if total[h] < best[0]:
                best = (total[h], (j, h))
        if best[1] is None:
            break
        chosen[best[1][0]] = best[1][1]
        cost = best[0]
    chosen = np.sort(np.array(chosen))
    return chosen[d[:, chosen].argmin(1)], float(d[:, chosen].min(1).sum())


def sampled_medoids(d: np.ndarray, k: int, samples: int = 5, size: int | None = None, seed: int = 0) -> tuple[np.ndarray, float]:
    """Medoids of samples; those of least cost over all rows."""
    rng, n, best = np.random.default_rng(seed), len(d), None
    for _ in range(samples):
        pick = np.sort(rng.permutation(n)[: min(n, size or 40 + 2 * k)])
        inside, _ = medoids(d[np.ix_(pick, pick)], k)
        chosen = pick[np.unique(inside)]
        cost = float(d[:, chosen].min(1).sum())
        if best is None or cost < best[1] - 1e-12:
            best = (chosen[d[:, chosen].argmin(1)], cost)
    return best


def agglomerate(d: np.ndarray, linkage: str = "average") -> list[tuple[int, int, float]]:
    """Merges (kept, absorbed, height) of the clusters named by their smallest row; single, complete, average or ward (squared distances)."""
    n = len(d)
    work, size, alive, out = d.astype(float).copy(), np.ones(n), list(range(n)), []
    np.fill_diagonal(work, np.inf)
    for _ in range(n - 1):
        sub = np.round(work[np.ix_(alive, alive)], 12)
        i, j = divmod(int(sub.argmin()), len(alive))
        a, b = sorted((alive[i], alive[j]))
        height = float(work[a, b])
        for c in alive:
            if c in (a, b):
                continue
            x, y = work[a, c], work[b, c]
            if linkage == "single":
                v = min(x, y)
            elif linkage == "complete":
                v = max(x, y)
            elif linkage == "average":
                v = (size[a] * x + size[b] * y) / (size[a] + size[b])
            else:
                t = size[a] + size[b] + size[c]
                v = ((size[a] + size[c]) * x + (size[b] + size[c]) * y - size[c] * height) / t
            work[a, c] = work[c, a] = v
        size[a] += size[b]
        work[b, :] = work[:, b] = np.inf
        alive.remove(b)
        out.append((a, b, height))
    return out


def cut(merges: list[tuple[int, int, float]], n: int, k: int) -> np.ndarray:
    """Labels (the smallest row of each cluster) with k clusters left."""
    root = np.arange(n)
    for a, b, _ in merges[: max(0, n - k)]:
        root[root == b] = a
    return root


def divide(d: np.ndarray, k: int) -> np.ndarray:
    """Divisive splitting: the cluster of largest diameter gives off a splinter group until there are k."""
    labels = np.zeros(len(d), int)
    while len(np.unique(labels)) < min(k, len(d)):
        names = np.unique(labels)
        diameter = [d[np.ix_(labels == c, labels == c)].max() for c in names]
        if max(diameter) <= 0:
            break
        members = np.flatnonzero(labels == names[int(np.argmax(diameter))])
        inner = d[np.ix_(members, members)]
        out = np.zeros(len(members), bool)
        out[int((inner.sum(1) / (len(members) - 1)).argmax())] = True
        while (~out).sum() > 1:
            stay = inner[:, ~out].sum(1) / np.maximum((~out).sum() - 1, 1)
            gain = np.where(out, -np.inf, stay - inner[:, out].mean(1))
            if gain.max() <= 0:
                break
            out[int(gain.argmax())] = True
        labels[members[out]] = labels.max() + 1
    return labels


def adjusted_rand(a: np.ndarray, b: np.ndarray) -> float:
    _, x = np.unique(a, return_inverse=True)
    _, y = np.unique(b, return_inverse=True)
    table = np.zeros((x.max() + 1, y.max() + 1))
    np.add.at(table, (x, y), 1)
    pairs = lambda v: (v * (v - 1) / 2).sum()
    both, one, two, n = pairs(table), pairs(table.sum(1)), pairs(table.sum(0)), len(a) * (len(a) - 1) / 2
    expected = one * two / n if n else 0
    top = (one + two) / 2
    return 1.0 if top == expected else float((both - expected) / (top - expected))


def normalised_information(a: np.ndarray, b: np.ndarray) -> float:
    _, x = np.unique(a, return_inverse=True)
    _, y = np.unique(b, return_inverse=True)
    p = np.zeros((x.max() + 1, y.max() + 1))
    np.add.at(p, (x, y), 1 / len(a))
    px, py = p.sum(1), p.sum(0)
    h = lambda q: float(-(q[q > 0] * np.log(q[q > 0])).sum())
    mutual = h(px) + h(py) - h(p.ravel())
    return 1.0 if h(px) + h(py) == 0 else 2 * mutual / (h(px) + h(py))
