"""Normalised cut of the small cluster graph (numpy on the driver)."""

from __future__ import annotations

import numpy as np


def ncut_value(w: np.ndarray, groups: np.ndarray) -> float:
    """Sum over groups of the weight that leaves the group over the weight that touches it."""
    degree = w.sum(1)
    total = 0.0
    for g in np.unique(groups):
        inside = groups == g
        volume = degree[inside].sum()
        if volume > 0:
            total += float(w[np.ix_(inside, ~inside)].sum() / volume)
    return total


def components(w: np.ndarray) -> np.ndarray:
    out, n = np.full(len(w), -1), 0
    for start in range(len(w)):
        if out[start] < 0:
            stack = [start]
            out[start] = n
            while stack:
                for j in np.flatnonzero((w[stack.pop()] > 0) & (out < 0)):
                    out[j] = n
                    stack.append(int(j))
            n += 1
    return out


def _embedding(w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    d = w.sum(1)
    s = 1 / np.sqrt(np.where(d > 0, d, 1))
    values, vectors = np.linalg.eigh(np.eye(len(w)) - s[:, None] * w * s[None])
    sign = np.sign(vectors[np.abs(vectors).argmax(0), np.arange(len(w))])
    return values, vectors * np.where(sign == 0, 1, sign)


def eigengap(values: np.ndarray, most: int = 10) -> int:
    gaps = np.diff(values[: most + 1])
    return int(gaps.argmax()) + 1 if len(gaps) else 1


def small_kmeans(x: np.ndarray, k: int, restarts: int = 20, seed: int = 0) -> np.ndarray:
    rng, best = np.random.default_rng(seed), (np.inf, np.zeros(len(x), int))
    for _ in range(restarts):
        c = [x[rng.integers(len(x))]]
        while len(c) < k:
            d = np.min([((x - y) ** 2).sum(1) for y in c], axis=0)
            c.append(x[rng.choice(len(x), p=d / d.sum())] if d.sum() > 0 else x[rng.integers(len(x))])
        centers = np.array(c)
        for _ in range(50):
            label = ((x[:, None] - centers[None]) ** 2).sum(2).argmin(1)
            new = np.array([x[label == j].mean(0) if (label == j).any() else centers[j] for j in range(k)])
            if np.allclose(new, centers):
                break
            centers = new
        cost = float(((x - centers[label]) ** 2).sum())
        if cost < best[0] - 1e-12:
            best = (cost, label)
    return best[1]


def _ordered(groups: np.ndarray) -> np.ndarray:
    """Groups numbered by their first node."""
    names: dict[int, int] = {}
    return np.array([names.setdefault(int(g), len(names)) for g in groups])


def _bisect(w: np.ndarray, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray] | None:
    if len(nodes) < 2:
        return None
    own = w[np.ix_(nodes, nodes)]
    comp = components(own)
    if comp.max() > 0:
        return nodes[comp == 0], nodes[comp > 0]
    _, vectors = _embedding(own)
    order = np.argsort(vectors[:, 1] / np.sqrt(np.maximum(own.sum(1), 1e-300)), kind="stable")
    best = min(range(1, len(nodes)), key=lambda i: ncut_value(own, np.isin(np.arange(len(nodes)), order[:i]).astype(int)))
    return nodes[np.sort(order[:best])], nodes[np.sort(order[best:])]


def normalized_cut(w: np.ndarray, k: int | None = None, method: str = "spectral") -> np.ndarray:
    """Group of each node.  spectral: k-means on the first k eigenvectors, rows scaled to length 1;
    recursive: the cut of least value, again on the part where it is least; components.  Without
    k the widest gap between eigenvalues decides."""
    if method == "components":
        return _ordered(components(w))
    k = min(len(w), k or eigengap(_embedding(w)[0]))
    if method == "recursive":
        parts = [np.arange(len(w))]
        while len(parts) < k:
            options = []
            for i, p in enumerate(parts):
                if cut := _bisect(w, p):
                    label = np.zeros(len(w), int)
                    for j, q in enumerate([*parts[:i], *cut, *parts[i + 1 :]]):
                        label[q] = j
                    options.append((ncut_value(w, label), i, cut))
            if not options:
                break
            _, i, cut = min(options, key=lambda x: (x[0], x[1]))
            parts[i : i + 1] = cut
        out = np.zeros(len(w), int)
        for j, p in enumerate(parts):
            out[p] = j
        return _ordered(out)
    _, vectors = _embedding(w)
    x = vectors[:, :k]
    x = x / np.maximum(np.sqrt((x**2).sum(1, keepdims=True)), 1e-12)
    return _ordered(small_kmeans(x, k))
