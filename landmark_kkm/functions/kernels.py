"""Kernels over payloads: each gives the matrix of two batches and the diagonal of one."""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from landmark_kkm.functions.payloads import Dense, Objects, Payload


class Kernel:
    """matrix(a, b) is len(a) by len(b). psd tells whether every kernel matrix is positive semidefinite, shift_invariant whether it depends on the difference only."""

    psd = True
    shift_invariant = False

    def matrix(self, a: Payload, b: Payload) -> np.ndarray:
        raise NotImplementedError

    def diagonal(self, a: Payload) -> np.ndarray:
        return np.array([self.matrix(a.take([i]), a.take([i]))[0, 0] for i in range(len(a))])


def squared_distances(a: Payload, b: Payload) -> np.ndarray:
    d = a.dot(b)
    d *= -2
    d += a.norms()[:, None]
    d += b.norms()[None, :]
    return np.maximum(d, 0, out=d)


@dataclass
class Rbf(Kernel):
    """exp(-|x - z|^2 / (2 sigma^2))"""

    sigma: float = 1.0
    shift_invariant = True

    def __post_init__(self):
        if not self.sigma > 0:
            raise ValueError("sigma must be positive")

    def matrix(self, a, b):
        d = squared_distances(a, b)
        d /= -2 * self.sigma**2
        return np.exp(d, out=d)

    def diagonal(self, a):
        return np.ones(len(a))


@dataclass
class LocalRbf(Kernel):
    """exp(-|x - z|^2 / (s_x s_z)), the local scale s being the last entry of each vector. May be indefinite."""

    psd = False

    def matrix(self, a, b):
        x, z = Dense(a.rows[:, :-1]), Dense(b.rows[:, :-1])
        return np.exp(-squared_distances(x, z) / (a.rows[:, -1:] * b.rows[:, -1][None, :]))

    def diagonal(self, a):
        return np.ones(len(a))


@dataclass
class Laplacian(Kernel):
    """exp(-|x - z|_1 / sigma)"""

    sigma: float = 1.0
    shift_invariant = True

    def matrix(self, a, b):
        out = np.empty((len(a), len(b)))
        for at in range(0, len(a), 256):
            out[at : at + 256] = np.abs(a.rows[at : at + 256, None, :] - b.rows[None]).sum(2)
        return np.exp(-out / self.sigma)

    def diagonal(self, a):
        return np.ones(len(a))


@dataclass
class Linear(Kernel):
    def matrix(self, a, b):
        return a.dot(b)

    def diagonal(self, a):
        return a.norms()


@dataclass
class Polynomial(Kernel):
    """(x z + coef0)^degree"""

    degree: int = 5
    coef0: float = 1.0

    def matrix(self, a, b):
        return (a.dot(b) + self.coef0) ** self.degree

    def diagonal(self, a):
        return (a.norms() + self.coef0) ** self.degree


@dataclass
class Neural(Kernel):
    """tanh(a x z + b), indefinite in general"""

    a: float = 0.0045
    b: float = 0.11
    psd = False

    def matrix(self, a, b):
        return np.tanh(self.a * a.dot(b) + self.b)

    def diagonal(self, a):
        return np.tanh(self.a * a.norms() + self.b)


@dataclass
class Normalized(Kernel):
    """k(x, z) / sqrt(k(x, x) k(z, z)); 0 where a diagonal entry is 0."""

    base: Kernel

    def __post_init__(self):
        self.psd = self.base.psd

    def matrix(self, a, b):
        scale = np.sqrt(np.outer(self.base.diagonal(a), self.base.diagonal(b)))
        return np.divide(self.base.matrix(a, b), scale, out=np.zeros_like(scale), where=scale > 0)

    def diagonal(self, a):
        return (self.base.diagonal(a) > 0).astype(float)


def cosine() -> Normalized:
    return Normalized(Linear())


@dataclass
class Jaccard(Kernel):
    """Shared members over all members of two sets; 0 for two empty sets."""

    def matrix(self, a, b):
        left, right = [set(r or ()) for r in a.rows], [set(r or ()) for r in b.rows]
        out = np.zeros((len(a), len(b)))
        for i, x in enumerate(left):
            for j, z in enumerate(right):
                if both := len(x & z):
                    out[i, j] = both / (len(x) + len(z) - both)
        return out

    def diagonal(self, a):
        return np.array([1.0 if r else 0.0 for r in a.rows])


def _as_map(row) -> dict:
    return dict(row or {})


@dataclass
class HistogramIntersection(Kernel):
    """Sum over keys of the lesser value, for maps of weights of 0 or more, or dense rows."""

    def matrix(self, a, b):
        if isinstance(a, Dense):
            return np.array([np.minimum(x[None], b.rows).sum(1) for x in a.rows]).reshape(len(a), len(b))
        keys = {k: j for j, k in enumerate(sorted({k for r in b.rows for k in _as_map(r)}))}
        right = np.zeros((len(b), len(keys)))
        for i, r in enumerate(b.rows):
            for k, v in _as_map(r).items():
                right[i, keys[k]] = v
        out = np.zeros((len(a), len(b)))
        for i, r in enumerate(a.rows):
            if own := [(keys[k], v) for k, v in _as_map(r).items() if k in keys]:
                at, v = zip(*own)
                out[i] = np.minimum(right[:, list(at)], np.array(v)).sum(1)
        return out

    def diagonal(self, a):
        return a.rows.sum(1) if isinstance(a, Dense) else np.array([float(sum(_as_map(r).values())) for r in a.rows])


@dataclass
class Spectrum(Kernel):
    """Dot product of the counts of k-grams of two strings."""

    k: int = 3

    def _counts(self, text) -> Counter:
        text = text or ""
        return Counter(text[i : i + self.k] for i in range(len(text) - self.k + 1))

    def matrix(self, a, b):
        grams: dict[str, list[tuple[int, int]]] = {}
        for j, r in enumerate(b.rows):
            for g, n in self._counts(r).items():
                grams.setdefault(g, []).append((j, n))
        out = np.zeros((len(a), len(b)))
        for i, r in enumerate(a.rows):
            for g, n in self._counts(r).items():
                for j, m in grams.get(g, ()):
                    out[i, j] += n * m
        return out

    def diagonal(self, a):
        return np.array([float(sum(n * n for n in self._counts(r).values())) for r in a.rows])


@dataclass
class Precomputed(Kernel):
    """Similarities that are given: a row's payload is the map of column id to similarity, a landmark's too, with its own id under `id_key`."""

    id_key: int = -1
    psd = False

    def matrix(self, a, b):
        columns = [int(_as_map(r)[self.id_key]) for r in b.rows]
        rows = [_as_map(r) for r in a.rows]
        return np.array([[r.get(c, 0.0) for c in columns] for r in rows]).reshape(len(a), len(b))

    def diagonal(self, a):
        return np.array([(m := _as_map(r)).get(int(m[self.id_key]), 0.0) for r in a.rows])


@dataclass
class SharedBits(Kernel):
    """The number of bits that two binary values have in common, 0 if under `least`: the weighted adjacency matrix of a graph without its edges as rows.

    With `shift` the values begin with 16 bytes, the row's number and its degree, and the entries are those whose weighted kernel k-means has the
    normalised-cut objective: the edge over both degrees, and with itself shift over the degree."""

    least: int = 2
    shift: float | None = None
    psd = False

    def _parts(self, a) -> tuple[np.ndarray, np.ndarray]:
        raw = np.frombuffer(b"".join(a.rows), np.uint8).reshape(len(a), -1)
        head = 0 if self.shift is None else 16
        return raw[:, :head], np.unpackbits(raw[:, head:], axis=1).astype(np.float32)

    def matrix(self, a, b):
        if not len(a) or not len(b):
            return np.zeros((len(a), len(b)))
        (head_a, bits_a), (head_b, bits_b) = self._parts(a), self._parts(b)
        w = bits_a @ bits_b.T
        w[w < self.least] = 0
        if self.shift is None:
            return w.astype(float)
        ids, degree = zip(*[(np.ascontiguousarray(h[:, :8]).view(np.int64).ravel(), np.ascontiguousarray(h[:, 8:]).view(np.float64).ravel()) for h in (head_a, head_b)])
        same = ids[0][:, None] == ids[1]
        return np.where(same, self.shift / degree[0][:, None], w / (degree[0][:, None] * degree[1]))

    def diagonal(self, a):
        head, bits = self._parts(a) if len(a) else (np.zeros((0, 16), np.uint8), np.zeros((0, 0)))
        if self.shift is None:
            n = bits.sum(1).astype(float)
            return np.where(n >= self.least, n, 0.0)
        return self.shift / np.ascontiguousarray(head[:, 8:]).view(np.float64).ravel()


@dataclass
class Custom(Kernel):
    """fn(rows, rows) gives the matrix, rows being an array (dense) or a list."""

    fn: Callable
    psd: bool = True

    def matrix(self, a, b):
        return np.asarray(self.fn(a.rows, b.rows), dtype=float).reshape(len(a), len(b))


def rbf(sigma: float = 1.0) -> Rbf:
    return Rbf(sigma)


def self_tuned_sigma(sample: Payload, neighbor: int = 7, stat: str = "mean") -> float:
    """stat "mean" or "median": of the distance to the neighbor-th nearest other row; "mean_pairwise", "median_pairwise": of all distances in the sample."""
    if len(sample) < 2:
        raise ValueError("two rows or more are needed to tune sigma")
    d = np.sqrt(squared_distances(sample, sample))
    if stat.endswith("_pairwise"):
        pairs = d[np.triu_indices(len(d), 1)]
        return float(np.median(pairs) if stat.startswith("median") else pairs.mean())
    np.fill_diagonal(d, np.inf)
    near = np.sort(d, axis=1)[:, min(neighbor, len(d) - 1) - 1]
    return float(np.median(near) if stat == "median" else near.mean())


def local_scales(rows: Payload, sample: Payload, neighbor: int = 7) -> np.ndarray:
    """Distance of each row to its neighbor-th nearest sample row that lies elsewhere; 1 if the sample has too few. Squared distances that are within
    rounding of the vectors' own length count as none, as a row and its copy in the sample are the same place."""
    d2 = squared_distances(rows, sample)
    same = d2 <= 1e-12 * (rows.norms()[:, None] + sample.norms()[None, :])
    d = np.sort(np.sqrt(np.where(same, np.inf, d2)), axis=1)
    near = d[:, min(neighbor, d.shape[1]) - 1]
    return np.where(np.isfinite(near) & (near > 0), near, 1.0)


__all__ = ["Custom", "HistogramIntersection", "Jaccard", "Kernel", "Laplacian", "Linear", "LocalRbf", "Neural", "Normalized", "Objects", "Polynomial", "Precomputed", "Rbf", "Spectrum", "cosine", "local_scales", "rbf", "self_tuned_sigma", "squared_distances"]
