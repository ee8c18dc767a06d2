"""Clustering of one group of points in numpy: representatives as (points, weights)."""

from __future__ import annotations

import numpy as np


def _spread(points: np.ndarray, k: int, rng: np.random.Generator, weights: np.ndarray) -> np.ndarray:
    """Starting points: each next one is drawn by weight times squared distance to those chosen."""
    chosen = [points[rng.choice(len(points), p=weights / weights.sum())]]
    far = ((points - chosen[0]) ** 2).sum(axis=1)
    while len(chosen) < k:
        p = far * weights
        chosen.append(points[rng.choice(len(points), p=p / p.sum())] if p.sum() > 0 else points[rng.integers(len(points))])
        far = np.minimum(far, ((points - chosen[-1]) ** 2).sum(axis=1))
    return np.array(chosen)


def nearest(points: np.ndarray, centres: np.ndarray, distance: str = "euclidean") -> np.ndarray:
    """The number of each point's nearest centre; the smaller number of equal ones. In pieces, so that memory is bounded."""
    out = np.empty(len(points), np.int64)
    for i in range(0, len(points), 8192):
        x = points[i : i + 8192]
        if distance == "euclidean":
            d = ((x[:, None, :] - centres[None]) ** 2).sum(axis=2)
        elif distance == "manhattan":
            d = np.abs(x[:, None, :] - centres[None]).sum(axis=2)
        elif distance == "cosine":
            norm = np.linalg.norm(x, axis=1)[:, None] * np.linalg.norm(centres, axis=1)[None]
            d = 1 - np.divide(x @ centres.T, norm, out=np.zeros_like(norm), where=norm > 0)
        else:
            raise ValueError(f"no distance {distance}")
        out[i : i + 8192] = d.argmin(axis=1)
    return out


def kmeans(points: np.ndarray, k: int, seed: int = 0, weights: np.ndarray | None = None, start: np.ndarray | None = None, rounds: int = 50, distance: str = "euclidean") -> tuple[np.ndarray, np.ndarray]:
    """(centres, total weight of each). Fewer than k distinct points: those points. An empty cluster starts anew at the point that is farthest from its centre."""
    weights = np.ones(len(points)) if weights is None else np.asarray(weights, float)
    distinct = np.unique(points, axis=0)
    if len(distinct) <= k:
        at = nearest(points, distinct)
        return distinct, np.bincount(at, weights, minlength=len(distinct))
    rng = np.random.default_rng(seed)
    positive = np.maximum(weights, 1e-12)
    centres = np.array(start, float) if start is not None else _spread(points, k, rng, positive)
    for _ in range(rounds):
        at = nearest(points, centres, distance)
        total = np.bincount(at, positive, minlength=k)
        moved = np.stack([np.bincount(at, positive * x, minlength=k) for x in points.T], axis=1) / np.maximum(total, 1e-300)[:, None]
        for empty in np.flatnonzero(total == 0):
            off = ((points - centres[at]) ** 2).sum(axis=1)
            moved[empty] = points[off.argmax()]
            centres[at[off.argmax()]] = points[off.argmax()]
        shift = np.abs(moved - centres).max()
        centres = moved
        if shift < 1e-9:
            break
    return centres, np.bincount(nearest(points, centres, distance), weights, minlength=k)


def _log_density(points: np.ndarray, share: np.ndarray, means: np.ndarray, covs: np.ndarray) -> np.ndarray:
    d, out = points.shape[1], []
    for p, m, c in zip(share, means, covs, strict=True):
        low = np.linalg.cholesky(c)
        z = np.linalg.solve(low, (points - m).T)
        out.append(np.log(max(p, 1e-300)) - 0.5 * (z * z).sum(axis=0) - np.log(np.diag(low)).sum() - 0.5 * d * np.log(2 * np.pi))
    return np.stack(out, axis=1)


def fit_mixture(points: np.ndarray, k: int, seed: int = 0, rounds: int = 60, ridge: float = 1e-6, diagonal: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Shares, means and covariances of a Gaussian mixture by expectation maximisation, started from k-means. diagonal: covariances between dimensions are 0, for many dimensions."""
    means, total = kmeans(points, k, seed)
    k, d = len(means), points.shape[1]
    floor = ridge * max(points.var(axis=0).max(), 1e-12)
    share, covs = np.maximum(total, 1e-9) / max(total.sum(), 1e-9), np.stack([np.diag(np.maximum(points.var(axis=0), floor))] * k)
    before = -np.inf
    for _ in range(rounds):
        logs = _log_density(points, share, means, covs)
        top = np.logaddexp.reduce(logs, axis=1)
        held = np.exp(logs - top[:, None])
        mass = held.sum(axis=0) + 1e-12
        share, means = mass / mass.sum(), held.T @ points / mass[:, None]
        for j in range(k):
            off = points - means[j]
            full = (held[:, j, None] * off).T @ off / mass[j] + floor * np.eye(d)
            covs[j] = np.diag(np.diag(full)) if diagonal else full
        if abs(top.mean() - before) < 1e-8:
            break
        before = top.mean()
    return share, means, covs


def mixture(points: np.ndarray, k: int, seed: int = 0, n_samples: int = 20, diagonal: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Points drawn from the fitted mixture, each weighted by its density under the fit."""
    if len(np.unique(points, axis=0)) <= k:
        return kmeans(points, k, seed)
    share, means, covs = fit_mixture(points, k, seed, ridge=1e-2 if diagonal else 1e-6, diagonal=diagonal)
    rng = np.random.default_rng(seed + 1)
    which = rng.choice(len(share), n_samples, p=share / share.sum())
    drawn = np.array([rng.multivariate_normal(means[j], covs[j], method="cholesky") for j in which])
    return drawn, np.exp(np.logaddexp.reduce(_log_density(drawn, share, means, covs), axis=1))


def moments(points: np.ndarray, k: int, seed: int = 0, n_samples: int = 20) -> tuple[np.ndarray, np.ndarray]:
    """Draws from the mean and variance of each local cluster, weighted by the cluster's size over its number of draws."""
    centres, total = kmeans(points, k, seed)
    at, rng, each = nearest(points, centres), np.random.default_rng(seed + 1), max(1, n_samples // len(centres))
    out = [rng.normal(c, points[at == j].std(axis=0) if (at == j).any() else 0.0, (each, points.shape[1])) for j, c in enumerate(centres)]
    return np.concatenate(out), np.repeat(total / each, each)
