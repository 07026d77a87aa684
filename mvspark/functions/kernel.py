"""Numpy kernels over one query and one object, or one object and many, as rows of token vectors."""

from __future__ import annotations

import math

import numpy as np


def _cosine(q: np.ndarray, v: np.ndarray) -> np.ndarray:
    unit = lambda x: x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
    return unit(q) @ unit(v).T


def _neg_l2(q: np.ndarray, v: np.ndarray) -> np.ndarray:
    return -np.sqrt(np.maximum((q**2).sum(1)[:, None] + (v**2).sum(1)[None] - 2 * q @ v.T, 0))


#: name -> function of two matrices of rows, higher is better
METRICS = {"ip": lambda q, v: q @ v.T, "cosine": _cosine, "l2": _neg_l2}


def register_metric(name: str, function) -> None:
    """A metric of one's own: ``function(q, v)`` gives the matrix of similarities of rows, higher is better."""
    got = np.asarray(function(np.eye(2), np.eye(2)))
    if got.shape != (2, 2):
        raise ValueError("a metric gives one similarity for every pair of rows")
    METRICS[name] = function


def metric_of(metric):
    """The function of a metric's name, or the function itself (which travels to workers with the task)."""
    if callable(metric):
        return metric
    if metric not in METRICS:
        raise ValueError(f"unknown metric {metric!r}; known: {', '.join(sorted(METRICS))}")
    return METRICS[metric]


def similarities(q: np.ndarray, v: np.ndarray, metric="ip") -> np.ndarray:
    return metric_of(metric)(q, v)


def top_sums(s: np.ndarray, gamma: int, short: str = "literal") -> np.ndarray:
    """Mean of the gamma best of each row; rows shorter than gamma divide by gamma or by what is found."""
    g = min(gamma, s.shape[1])
    if not g:
        return np.zeros(len(s))
    best = s.max(1) if g == 1 else np.partition(s, s.shape[1] - g, axis=1)[:, -g:].sum(1)
    return best / (gamma if short == "literal" else g)


def mv_sim(q, v, gamma=1, weights=None, metric="ip", short="literal") -> float:
    q, v = np.atleast_2d(np.asarray(q, float)), np.atleast_2d(np.asarray(v, float))
    if not q.size:
        return 0.0
    w = np.ones(len(q)) if weights is None else np.asarray(weights, float)
    if (w < 0).any():
        raise ValueError("token weights must not be negative")
    return float(w @ top_sums(similarities(q, v, metric), gamma, short))


def edge_weight(u, v, gamma=1, edge_fn="fused", beta=None, groups=None) -> float:
    """Similarity of two objects; fused is the mean of both size-normalised directions, from one matrix.

    raw, one_sided and sum are the controls. With ``groups`` = (clusters of u, clusters of v) both
    directions are approximated by shortlists.
    """
    u, v = np.atleast_2d(np.asarray(u, float)), np.atleast_2d(np.asarray(v, float))
    if groups is not None:
        a, b = clustered_sim(u, v, gamma, groups=groups[0], beta=beta), clustered_sim(v, u, gamma, groups=groups[1], beta=beta)
    else:
        s = u @ v.T
        a, b = top_sums(s, gamma).sum(), top_sums(s.T, gamma).sum()
    if edge_fn not in EDGES:
        raise ValueError(f"unknown edge function {edge_fn!r}")
    return float(EDGES[edge_fn](a, b, len(u), len(v)))


def cluster_tokens(x: np.ndarray, n: int | None = None, rounds: int = 5) -> np.ndarray:
    """Group of each token: Lloyd rounds from farthest-first seeds; deterministic."""
    x = np.asarray(x, float)
    n = min(len(x), n or math.ceil(math.sqrt(len(x))))
    seeds = [0]
    far = ((x - x[0]) ** 2).sum(1)
    while len(seeds) < n:
        seeds.append(int(far.argmax()))
        far = np.minimum(far, ((x - x[seeds[-1]]) ** 2).sum(1))
    c = x[seeds]
    for _ in range(max(1, rounds)):
        g = ((x[:, None] - c[None]) ** 2).sum(2).argmin(1)
        c = np.array([x[g == i].mean(0) if (g == i).any() else c[i] for i in range(n)])
    return g


def clustered_sim(q, d, gamma=1, weights=None, beta=None, groups=None, rounds=5) -> float:
    """Filter and refine: the tokens of d nearest each group's centre are all its members look at."""
    q, d = np.atleast_2d(np.asarray(q, float)), np.atleast_2d(np.asarray(d, float))
    w = np.ones(len(q)) if weights is None else np.asarray(weights, float)
    g = cluster_tokens(q, rounds=rounds) if groups is None else np.asarray(groups)
    beta = min(len(d), beta or max(gamma, math.ceil(math.sqrt(len(d)))))
    total = 0.0
    for i in np.unique(g):
        own = np.flatnonzero(g == i)
        near = np.lexsort((np.arange(len(d)), -(d @ q[own].sum(0))))[:beta]
        total += w[own] @ top_sums(q[own] @ d[near].T, gamma)
    return float(total)


def _mean_best(s: np.ndarray, gamma: int) -> np.ndarray:
    """Sum of the gamma best along the last axis, divided by gamma."""
    g = min(gamma, s.shape[-1])
    return (s.max(-1) if g == 1 else np.partition(s, s.shape[-1] - g, axis=-1)[..., s.shape[-1] - g :].sum(-1)) / gamma


def spans(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """All places of the given spans, one after the other."""
    return np.repeat(start - (np.cumsum(size) - size), size) + np.arange(size.sum())


def cubes(s: np.ndarray, first: np.ndarray, size: np.ndarray):
    """(objects, their columns as rows x objects x tokens) for the objects of each size."""
    for n in np.unique(size).tolist():
        at = np.flatnonzero(size == n)
        yield at, s[:, first[at][:, None] + np.arange(n)]


class Block:
    """Many objects as one matrix: ``x`` has all tokens, object i has rows ``start[i]`` to ``start[i] + size[i] - 1``.

    ``dots`` counts products of two token vectors, the unit of work of every score.
    """

    def __init__(self, x: np.ndarray, size: np.ndarray):
        self.x, self.size = np.ascontiguousarray(x), np.asarray(size, np.int64)
        self.start = np.cumsum(self.size) - self.size
        self.dots = 0
        self.groups: dict[int, np.ndarray] = {}

    def of(self, i: int) -> np.ndarray:
        return self.x[self.start[i] : self.start[i] + self.size[i]]

    def clusters(self, i: int) -> np.ndarray:
        """Groups of an object's tokens, made once."""
        if i not in self.groups:
            self.groups[i] = cluster_tokens(self.of(i))
        return self.groups[i]

    def _best(self, s: np.ndarray, first: np.ndarray, size: np.ndarray, gamma: int, short: str = "literal") -> np.ndarray:
        """Of every row and object of a matrix, the mean of the gamma best."""
        if gamma == 1:
            return np.maximum.reduceat(s, first, axis=1)
        out = np.empty((len(s), len(first)))
        for at, cube in cubes(s, first, size):
            n = cube.shape[2]
            g = min(gamma, n)
            out[:, at] = (np.partition(cube, n - g, axis=2)[:, :, n - g :].sum(2) if g else np.zeros(cube.shape[:2])) / (gamma if short == "literal" else max(g, 1))
        return out

    def scores(self, q: np.ndarray, some: np.ndarray, gamma: int = 1, w: np.ndarray | None = None, metric="ip", short: str = "literal") -> np.ndarray:
        """The unified similarity of a query to each of ``some`` objects, by one product."""
        some = np.asarray(some, np.int64)
        size = self.size[some]
        s = similarities(q, self.x[spans(self.start[some], size)], metric)
        self.dots += s.size
        best = self._best(s, np.cumsum(size) - size, size, gamma, short)
        return best.sum(0) if w is None else w @ best

    def clustered_scores(self, q: np.ndarray, groups: np.ndarray, some: np.ndarray, gamma: int = 1, w: np.ndarray | None = None, beta: int | None = None) -> np.ndarray:
        """As ``scores``, but each group of query tokens looks only at the object's tokens nearest to the group's centre."""
        some = np.asarray(some, np.int64)
        out = np.empty(len(some))
        named, own = np.unique(groups, return_inverse=True)
        centres = np.stack([q[groups == g].sum(0) for g in named])
        for n in np.unique(self.size[some]):  # objects of one size form a cube
            at = np.flatnonzero(self.size[some] == n)
            rows = self.start[some[at]][:, None] + np.arange(n)
            b = min(n, beta or max(gamma, math.ceil(math.sqrt(n))))
            near = np.einsum("gd,otd->ogt", centres, self.x[rows], optimize=True)
            self.dots += near.size
            pick = np.argsort(-near, axis=2, kind="stable")[:, :, :b]  # objects x groups x beta
            tokens = np.take_along_axis(rows[:, None], pick, axis=2)
            got = np.einsum("qd,oqbd->oqb", q, self.x[tokens][:, own], optimize=True)
            self.dots += got.size
            g = min(gamma, b)
            best = got.max(2) if g == 1 else np.partition(got, b - g, axis=2)[:, :, b - g :].sum(2)
            out[at] = (best / gamma) @ (np.ones(len(q)) if w is None else w)
        return out

    def edges(self, i: int, some: np.ndarray, gamma: int = 1, kind: str = "fused", clustered: bool = False, beta: int | None = None) -> np.ndarray:
        """Edge weights of object i and each of ``some``; both directions of the exact form come from one product."""
        if kind not in EDGES:
            raise ValueError(f"unknown edge function {kind!r}")
        some = np.asarray(some, np.int64)
        if not clustered:
            return self.weights(self.of(i), some, gamma, kind)
        u = self.of(i)
        a = self.clustered_scores(u, self.clusters(i), some, gamma, beta=beta)
        b = np.array([self._toward(j, u, gamma, beta) for j in some.tolist()])
        return EDGES[kind](a, b, len(u), self.size[some])

    def weights(self, u: np.ndarray, some: np.ndarray | None = None, gamma: int = 1, kind: str = "fused", back: bool = False) -> np.ndarray:
        """Edge weights of an object ``u`` from elsewhere and each of ``some`` (none given: all); ``back`` from each of them to ``u``."""
        if some is None:
            x, size, first = self.x, self.size, self.start
        else:
            size = self.size[some]
            x, first = self.x[spans(self.start[some], size)], np.cumsum(size) - size
        if not len(size):
            return np.zeros(0)
        s = x @ u.T if back else u @ x.T
        self.dots += s.size
        s = s.T if back else s
        a = self._best(s, first, size, gamma).sum(0)
        b = np.add.reduceat(s.max(0) if gamma == 1 else top_sums(s.T, gamma), first)
        return EDGES[kind](b, a, size, len(u)) if back else EDGES[kind](a, b, len(u), size)

    def clustered_weights(self, u: np.ndarray, own: np.ndarray, gamma: int = 1, kind: str = "fused", beta: int | None = None) -> np.ndarray:
        """As ``edges`` with ``clustered``, of an object ``u`` from elsewhere, grouped by ``own``, and all objects: one product, shortlists by its sums."""
        out = np.empty(len(self.size))
        m = len(u)
        named, mine = np.unique(own, return_inverse=True)
        hot = np.eye(len(named))[mine].T
        for n in np.unique(self.size).tolist():  # objects of one size form a cube
            at = np.flatnonzero(self.size == n)
            s = (u @ self.x[spans(self.start[at], self.size[at])].T).reshape(m, len(at), n)
            self.dots += s.size
            near = np.tensordot(hot, s, 1)  # a sum of members is a centre
            b = min(n, beta or max(gamma, math.ceil(math.sqrt(n))))
            pick = np.argsort(-near, axis=2, kind="stable")[:, :, :b]
            a = _mean_best(np.take_along_axis(s, pick[mine], axis=2), gamma).sum(0)
            groups = np.stack([self.clusters(i) for i in at.tolist()])
            b = min(m, beta or max(gamma, math.ceil(math.sqrt(m))))
            away = s.transpose(1, 2, 0)  # objects x their tokens x tokens of u
            near = np.matmul((groups[:, None] == np.arange(groups.max() + 1)[:, None]).astype(float), away)
            pick = np.argsort(-near, axis=2, kind="stable")[:, :, :b]
            pick = np.take_along_axis(pick, groups[:, :, None], axis=1)
            out[at] = EDGES[kind](a, _mean_best(np.take_along_axis(away, pick, axis=2), gamma).sum(1), m, n)
        return out

    def _toward(self, j: int, u: np.ndarray, gamma: int, beta: int | None) -> float:
        """Clustered similarity of object j to the tokens ``u``."""
        v, g = self.of(j), self.clusters(j)
        named, own = np.unique(g, return_inverse=True)
        b = min(len(u), beta or max(gamma, math.ceil(math.sqrt(len(u)))))
        near = np.stack([v[g == k].sum(0) for k in named]) @ u.T
        pick = np.argsort(-near, axis=1, kind="stable")[:, :b]
        got = np.einsum("td,tbd->tb", v, u[pick[own]], optimize=True)
        self.dots += near.size + got.size
        return float(top_sums(got, gamma).sum())


#: edge functions of both directed sums and both sizes; all but the first are the controls
EDGES = {
    "fused": lambda a, b, n, m: (a / n + b / m) / 2,
    "raw": lambda a, b, n, m: a,
    "one_sided": lambda a, b, n, m: a / n,
    "sum": lambda a, b, n, m: a + b,
}


def contribution(q, v, gamma=1, weights=None) -> np.ndarray:
    """What each token of v adds to gamma times the similarity."""
    s = np.asarray(q, float) @ np.asarray(v, float).T
    if not s.size:
        return np.zeros(s.shape[1])
    top = s.argmax(1)[:, None] if gamma == 1 else np.argsort(-s, axis=1, kind="stable")[:, :gamma]  # ties by place
    w = np.ones(len(s)) if weights is None else np.asarray(weights, float)
    return np.bincount(top.ravel(), (np.take_along_axis(s, top, 1) * w[:, None]).ravel(), s.shape[1])


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max())
    return e / e.sum()
