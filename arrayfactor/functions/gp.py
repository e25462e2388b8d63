"""One subarray's Gaussian process: expectation step, bound, gradient, step and prediction.

All of it works on a dense K-way block of a few thousand cells and one small covariance a mode.
With eigenvectors V and eigenvalues s of each mode's covariance, the Kronecker covariance has the
eigenvalues that products of the s give; it is never formed, and no covariance is inverted.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

from .kernels import Kernel, covariance, diagonal, row_gradient
from .normal import tails


def along(x: np.ndarray, m: np.ndarray, k: int) -> np.ndarray:
    """Mode-k product of a block with a matrix."""
    shape = (*x.shape[:k], len(m), *x.shape[k + 1 :])
    if k == x.ndim - 1:
        return (x.reshape(-1, x.shape[k]) @ m.T).reshape(shape)
    return (m @ x.reshape(-1 if k else 1, x.shape[k], math.prod(x.shape[k + 1 :]))).reshape(shape)


def unfold(x: np.ndarray, k: int) -> np.ndarray:
    return np.moveaxis(x, k, 0).reshape(x.shape[k], -1)


@dataclass
class Spectrum:
    """Eigen form of the modes' covariances."""

    sigma: list[np.ndarray]
    vectors: list[np.ndarray] = field(init=False)
    values: list[np.ndarray] = field(init=False)
    joint: np.ndarray = field(init=False)

    def __post_init__(self) -> None:
        parts = [np.linalg.eigh(s) for s in self.sigma]
        self.values = [np.maximum(v, 0.0) for v, _ in parts]
        self.vectors = [q for _, q in parts]
        joint = np.ones(())
        for v in self.values:
            joint = np.multiply.outer(joint, v)
        self.joint = joint

    def filtered(self, x: np.ndarray, weight: np.ndarray) -> np.ndarray:
        for k, v in enumerate(self.vectors):
            x = along(x, v.T, k)
        x = x * weight
        for k, v in enumerate(self.vectors):
            x = along(x, v, k)
        return x

    def variance(self, noise: float = 1.0) -> np.ndarray:
        """Diagonal of the posterior covariance under Gaussian noise."""
        x = self.joint * noise / (noise + self.joint)
        for k, v in enumerate(self.vectors):
            x = along(x, v * v, k)
        return x


@dataclass
class Posterior:
    mean: np.ndarray
    alpha: np.ndarray  # covariance times alpha is the mean
    bound: list[float]
    noise: float = 1.0


def probit(y: np.ndarray, spec: Spectrum, sweeps: int = 10, tol: float = 1e-4, mask: np.ndarray | None = None, offset: float = 0.0) -> Posterior:
    """Binary cells: alternate the latent utilities' expectation and the shrinkage until the bound settles."""
    sign = 2.0 * y - 1.0
    seen = np.ones_like(sign) if mask is None else mask.astype(float)
    push, mean, alpha, trace = seen * sign, np.zeros_like(sign), np.zeros_like(sign), []
    shrink, half_log = spec.joint / (1 + spec.joint), 0.5 * float(np.log1p(spec.joint).sum())
    _, ratio = tails(sign * (mean + offset))
    for _ in range(sweeps):
        target = mean + push * ratio
        mean = spec.filtered(target, shrink)
        alpha = target - mean  # the covariance times this is the mean, at every sweep
        logs, ratio = tails(sign * (mean + offset))  # the ratio is the next sweep's
        trace.append(float((seen * logs).sum() - 0.5 * (alpha * mean).sum() - half_log))
        if len(trace) > 1 and abs(trace[-1] - trace[-2]) < tol * y.size:
            break
    return Posterior(mean, alpha, trace)


def gaussian(y: np.ndarray, spec: Spectrum, noise: float = 1.0) -> Posterior:
    """Continuous cells: one filter; the bound is the log evidence."""
    alpha = spec.filtered(y, 1 / (noise + spec.joint))
    mean = spec.filtered(y, spec.joint / (noise + spec.joint))
    evidence = -0.5 * float((y * alpha).sum()) - 0.5 * float(np.log(noise + spec.joint).sum()) - 0.5 * y.size * np.log(2 * np.pi)
    return Posterior(mean, alpha, [evidence], noise)


def count(y: np.ndarray, spec: Spectrum) -> Posterior:
    """Counts, variance-stabilised to unit noise."""
    return gaussian(2 * np.sqrt(y + 0.375), spec, 1.0)


ESTEPS = {"binary": probit, "continuous": gaussian, "count": count}


def covariance_gradients(post: Posterior, spec: Spectrum) -> list[np.ndarray]:
    """Gradient of the bound by each mode's covariance, with the other modes held."""
    out = []
    for k, v in enumerate(spec.vectors):
        right = post.alpha
        for j, s in enumerate(spec.sigma):
            if j != k:
                right = along(right, s, j)
        fit = 0.5 * unfold(post.alpha, k) @ unfold(right, k).T
        others = spec.joint / np.where(spec.values[k] > 0, spec.values[k], 1).reshape([-1 if j == k else 1 for j in range(spec.joint.ndim)])
        pull = unfold(others / (post.noise + spec.joint), k).sum(1)
        out.append(fit - 0.5 * (v * pull) @ v.T)
    return out


def factor_gradients(rows: list[np.ndarray], post: Posterior, spec: Spectrum, kernel: Kernel) -> list[np.ndarray]:
    return [row_gradient(u, g, kernel) for u, g in zip(rows, covariance_gradients(post, spec), strict=True)]


def infer(rows: list[np.ndarray], y: np.ndarray, kernel: Kernel, likelihood: str = "binary", **options) -> tuple[Posterior, Spectrum]:
    spec = Spectrum([covariance(u, u, kernel, same=True) for u in rows])
    return ESTEPS[likelihood](y, spec, **options), spec


def contracted(block: np.ndarray, rows: list[np.ndarray], step: int = 1024) -> np.ndarray:
    """For each point, the block contracted with the point's row of every mode; a bounded number of points at once."""
    out = np.zeros(len(rows[0]))
    for a in range(0, len(out), step):
        x = rows[0][a : a + step] @ block.reshape(block.shape[0], -1)
        for r in rows[1:]:
            own = r[a : a + step]
            x = np.matmul(own[:, None, :], x.reshape(len(own), own.shape[1], -1))[:, 0, :]
        out[a : a + step] = x[:, 0]
    return out


def predictive(points: list[np.ndarray], rows: list[np.ndarray], post: Posterior, spec: Spectrum, kernel: Kernel) -> tuple[np.ndarray, np.ndarray]:
    """Mean and variance at new index tuples: one row of factors for each mode and point."""
    cross = [covariance(p, u, kernel) for p, u in zip(points, rows, strict=True)]
    mean = contracted(post.alpha, cross)
    rotated = [(c @ v) ** 2 for c, v in zip(cross, spec.vectors, strict=True)]
    prior = np.prod([diagonal(p, kernel) for p in points], axis=0)
    return mean, np.maximum(prior - contracted(1 / (post.noise + spec.joint), rotated), 0.0)


class ShardState:
    """One shard's copy of the factors as deviations from the parent rows, touched rows only.

    The prior pulls every row back a little at every step. For rows outside the current subarray
    that pull is a constant factor a step, so it is applied in one go when the row is next needed.
    Gradient rows longer than ``clip`` are shortened to it; with ``by_row`` a row's gradient is divided by
    the root of the sum of its squared norms so far in the pass.
    """

    def __init__(self, parent, steps: int, rate: float, variance: float, clip: float = 5.0, by_row: bool = False):
        self.parent, self.rate, self.steps, self.variance = parent, rate, max(steps, 1), variance
        self.clip, self.by_row = clip, by_row
        self.squares: dict[tuple[int, int], float] = {}
        self.pull = rate / (variance * self.steps) if np.isfinite(variance) else 0.0
        self.deviation: dict[tuple[int, int], np.ndarray] = {}
        self.seen: dict[tuple[int, int], int] = {}
        self.now = 0

    def gather(self, mode: int, index) -> np.ndarray:
        out = []
        for i in index:
            key, base = (mode, int(i)), self.parent(mode, int(i))
            if key in self.deviation:
                out.append(base + self.settled(key))
            else:
                out.append(base)
        return np.array(out)

    def settled(self, key: tuple[int, int]) -> np.ndarray:
        gap = self.now - self.seen[key]
        if gap:
            self.deviation[key] = self.deviation[key] * max(1 - self.pull, 0.0) ** gap
            self.seen[key] = self.now
        return self.deviation[key]

    def step(self, sets, gradients: list[np.ndarray], plain: bool = False) -> None:
        """Move the rows of one subarray; ``plain`` steps are taken as they are."""
        for mode, (index, grad) in enumerate(zip(sets, gradients, strict=True)):
            if not plain:
                norm = np.linalg.norm(grad, axis=1, keepdims=True)
                grad = grad * np.minimum(1.0, self.clip / np.maximum(norm, 1e-12))
            for i, g in zip(index, grad, strict=True):
                key = (mode, int(i))
                if self.by_row and not plain:
                    self.squares[key] = self.squares.get(key, 0.0) + float(g @ g)
                    g = g / np.sqrt(self.squares[key] + 1e-8)
                old = self.settled(key) if key in self.deviation else np.zeros_like(g)
                self.deviation[key] = old * (1 - self.pull) + (self.rate * g if self.variance > 0 else 0 * g)
                self.seen[key] = self.now + 1
        self.now += 1

    def deltas(self):
        for key in list(self.deviation):
            yield key, self.settled(key)
