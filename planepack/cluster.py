"""Grouping byte planes: agglomerative clustering, internal scores, and all set partitions.  At most eight planes, so NumPy on the driver."""

from __future__ import annotations

import numpy as np

Partition = list[list[int]]


def canonical(c) -> Partition:
    return sorted((sorted(int(i) for i in g) for g in c), key=lambda g: g[0])


def is_partition(c, n: int) -> bool:
    flat = sorted(i for g in c for i in g)
    return flat == list(range(n)) and all(len(g) for g in c)


def set_partitions(n: int) -> list[Partition]:
    """All partitions of n planes: 1, 2, 5, 15, ... 4140 for n = 8."""
    out: list[Partition] = [[]]
    for i in range(n):
        out = [p[:j] + [p[j] + [i]] + p[j + 1 :] for p in out for j in range(len(p))] + [p + [[i]] for p in out]
    return sorted(map(canonical, out))


def pairwise(x: np.ndarray) -> np.ndarray:
    return np.sqrt(((x[:, None, :] - x[None, :, :]) ** 2).sum(-1))


def linkage(x: np.ndarray, method: str = "single") -> list[Partition]:
    """Partitions with n, n - 1, ... 1 clusters; ties go to the smallest members."""
    d, c = pairwise(x), [[i] for i in range(len(x))]
    out = [canonical(c)]

    def gap(a, b):
        block = d[np.ix_(a, b)]
        if method == "ward":
            return len(a) * len(b) / (len(a) + len(b)) * ((x[a].mean(0) - x[b].mean(0)) ** 2).sum()
        return {"single": block.min, "complete": block.max, "average": block.mean}[method]()

    while len(c) > 1:
        _, _, _, i, j = min((round(float(gap(c[i], c[j])), 12), min(c[i] + c[j]), min(max(c[i]), max(c[j])), i, j) for i in range(len(c)) for j in range(i + 1, len(c)))
        c = [g for k, g in enumerate(c) if k not in (i, j)] + [c[i] + c[j]]
        out.append(canonical(c))
    return out


def cut(tree: list[Partition], k: int) -> Partition:
    return next(p for p in tree if len(p) == k)


def kmeans(x: np.ndarray, k: int, seed: int = 0, rounds: int = 50) -> Partition:
    """A rival clusterer for the ablation."""
    rng = np.random.default_rng(seed)
    centre = x[rng.choice(len(x), k, replace=False)]
    for _ in range(rounds):
        own = ((x[:, None] - centre[None]) ** 2).sum(-1).argmin(1)
        centre = np.stack([x[own == j].mean(0) if (own == j).any() else centre[j] for j in range(k)])
    return canonical([np.nonzero(own == j)[0] for j in range(k) if (own == j).any()])


def separation(c: Partition, x: np.ndarray, kind: str = "single") -> float | None:
    """The least distance between clusters: of two planes, or of two centroids."""
    if len(c) < 2:
        return None
    if kind == "centroid":
        x, c = np.stack([x[g].mean(0) for g in c]), [[i] for i in range(len(c))]
    d = pairwise(x)
    return float(min(d[np.ix_(a, b)].min() for i, a in enumerate(c) for b in c[i + 1 :]))


def silhouette(c: Partition, x: np.ndarray) -> float | None:
    if not 2 <= len(c) <= len(x) - 1:
        return None
    d, total = pairwise(x), 0.0
    for g in c:
        for i in g:
            if len(g) > 1:
                a = d[i, [j for j in g if j != i]].mean()
                b = min(d[i, h].mean() for h in c if h is not g)
                total += (b - a) / max(a, b) if max(a, b) else 0.0
    return total / len(x)


def davies_bouldin(c: Partition, x: np.ndarray) -> float | None:
    """Lower is better."""
    if not 2 <= len(c) <= len(x) - 1:
        return None
    m = [x[g].mean(0) for g in c]
    s = [np.sqrt(((x[g] - m[k]) ** 2).sum(1)).mean() for k, g in enumerate(c)]

    def r(i, j):
        gap = np.sqrt(((m[i] - m[j]) ** 2).sum())
        return (s[i] + s[j]) / gap if gap else np.inf

    return float(np.mean([max(r(i, j) for j in range(len(c)) if j != i) for i in range(len(c))]))


def calinski_harabasz(c: Partition, x: np.ndarray) -> float | None:
    n, k = len(x), len(c)
    if not 2 <= k <= n - 1:
        return None
    all_ = x.mean(0)
    between = sum(len(g) * ((x[g].mean(0) - all_) ** 2).sum() for g in c)
    within = sum(((x[g] - x[g].mean(0)) ** 2).sum() for g in c)
    return float(between / (k - 1) / (within / (n - k))) if within else float("inf")


def _spread(c: Partition, x: np.ndarray) -> float:
    d2 = pairwise(x) ** 2
    return float(sum(d2[np.ix_(g, g)].sum() / (2 * len(g)) for g in c))


def gap_statistic(tree: list[Partition], x: np.ndarray, method: str = "single", refs: int = 20, seed: int = 0) -> dict[int, tuple[float, float]]:
    """k -> (gap, deviation) against uniform references in the bounding box; k without spread is left out."""
    rng = np.random.default_rng(seed)
    trees = [(r, linkage(r, method)) for r in (rng.uniform(x.min(0), x.max(0), x.shape) for _ in range(refs))]
    out = {}
    for k in range(1, len(x)):
        w = _spread(cut(tree, k), x)
        logs = [np.log(max(_spread(cut(t, k), r), 1e-300)) for r, t in trees]
        if w > 0:
            out[k] = (float(np.mean(logs) - np.log(w)), float(np.std(logs) * np.sqrt(1 + 1 / refs)))
    return out


SCORES = {"silhouette": (silhouette, 1), "davies_bouldin": (davies_bouldin, -1), "calinski_harabasz": (calinski_harabasz, 1)}


def candidates(x: np.ndarray, score: str = "davies_bouldin", method: str = "single", seed: int = 0) -> list[dict]:
    """A candidate per cluster count: partition, score (as published), orientation, validity, separation."""
    tree = linkage(x, method)
    gaps = gap_statistic(tree, x, method, seed=seed) if score == "gap" else {}
    out = []
    for k in range(1, len(x) + 1):
        c = cut(tree, k)
        f, sign = SCORES.get(score, (None, 1))
        s = gaps.get(k, (None,))[0] if f is None else f(c, x)
        out.append({"k": k, "partition": c, "score": s, "oriented": None if s is None or np.isnan(s) else sign * s, "separation": separation(c, x)})
    return out


def one_se(x: np.ndarray, method: str = "single", seed: int = 0) -> Partition:
    """The smallest count whose gap is not below the next one's by more than its deviation; the largest defined count if none is."""
    tree = linkage(x, method)
    gaps = gap_statistic(tree, x, method, seed=seed)
    ks = sorted(k for k in gaps if k > 1)
    for k in ks:
        if k + 1 in gaps and gaps[k][0] >= gaps[k + 1][0] - gaps[k + 1][1]:
            return cut(tree, k)
    return cut(tree, ks[-1]) if ks else tree[0]


def choose_partition(x: np.ndarray, score: str = "davies_bouldin", method: str = "single", degenerate: str = "strict", seed: int = 0) -> Partition:
    """The candidate with the best valid score; two planes have one option; without a valid score all planes stay apart.

    ``degenerate``: ``strict`` asks for more than one cluster, ``allow_identity`` lets k = 1 compete where the score allows it, ``paper`` lets every
    k from 1 to n compete, undefined scores counting as the worst.  Score ``gap_one_se`` takes the smallest sufficient count instead of the largest gap.
    """
    n = len(x)
    if n == 2:
        return [[0], [1]]
    if score == "gap_one_se":
        return one_se(x, method, seed)
    least = 2 if degenerate == "strict" else 1
    found = candidates(x, score, method, seed)
    if degenerate == "paper":
        return max(found, key=lambda c: (-np.inf if c["oriented"] is None else c["oriented"], -c["k"]))["partition"]
    ok = [c for c in found if c["oriented"] is not None and least <= c["k"] <= n - 1]
    return max(ok, key=lambda c: (c["oriented"], -c["k"]))["partition"] if ok else [[i] for i in range(n)]


def default_policy(width: int) -> tuple[str, str]:
    """(feature set, score) by word width."""
    return ("combined", "gap") if width == 8 else ("frequency", "davies_bouldin")
