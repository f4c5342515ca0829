"""Weighted maximum-likelihood fit of influence curves as a convex problem.

With lo and hi the class means of a feature, tau * (x - alpha) = p * (x - lo) + q * (x - hi),
where p, q >= 0 and p + q = tau <= tau_max say the same as alpha in [lo, hi] and
0 <= tau <= tau_max. The log loss is linear in (p, q) under the logistic, hence
convex. ``fit`` reaches its least value by projected gradient steps with momentum over
sparse entries; ``fit_many`` fits several targets that share most of their evidence by
projected Newton steps, which need few passes from a near start.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


def project(p: np.ndarray, q: np.ndarray, top: float) -> tuple[np.ndarray, np.ndarray]:
    """Onto p, q >= 0, p + q <= top."""
    p, q = np.maximum(p, 0), np.maximum(q, 0)
    over = p + q > top
    if over.any():
        half = (p[over] - q[over]) / 2
        p[over] = np.clip(top / 2 + half, 0, top)
        q[over] = top - p[over]
    return p, q


def curve_of(p: np.ndarray, q: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """alpha, tau."""
    tau = p + q
    return np.where(tau > 1e-12, (p * lo + q * hi) / np.maximum(tau, 1e-12), (lo + hi) / 2), tau


def _logistic(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -700, 700)))


def fit(
    row: np.ndarray, col: np.ndarray, theta: np.ndarray, x: np.ndarray, label: np.ndarray, lo: np.ndarray, hi: np.ndarray,
    tau_max: float = 20.0, match_weight: float = 1.0, ridge: float = 1e-6, steps: int = 200, tol: float = 1e-6, start: np.ndarray | None = None,
) -> tuple[np.ndarray, np.ndarray, float]:
    """alpha, tau of each feature, and the norm of the projected gradient.

    Entries (row: evidence pair, col: feature, theta, x); label of each row; lo and hi of each feature, lo < hi;
    start: p and q of each feature, one after the other. Memory is that of the entries, whatever their number of rows and features.
    """
    n, f = len(label), len(lo)
    weight = np.where(label > 0, match_weight, 1.0)
    weight = weight / max(weight.sum(), 1e-12)
    a, b = theta * (x - lo[col]), theta * (x - hi[col])
    forward = lambda v: np.bincount(row, a * v[col] + b * v[col + f], minlength=n)

    def back(r: np.ndarray) -> np.ndarray:
        r = r[row]
        return np.concatenate([np.bincount(col, a * r, minlength=f), np.bincount(col, b * r, minlength=f)])

    # step length from a bound of the curvature: power iteration, with room for what it has not reached
    v, size = np.ones(2 * f), 0.0
    for _ in range(20 if n else 0):
        u = back(weight * forward(v))
        size = float(np.linalg.norm(u))
        if size <= 0:
            break
        v = u / size
    rate = 1 / (1.1 * size / 4 + ridge + 1e-12)
    v = np.full(2 * f, 0.5) if start is None else start
    y, t, size = v, 1.0, np.inf
    target = label.astype(float)
    for _ in range(steps):
        g = back(weight * (_logistic(forward(y)) - target)) + ridge * y
        new = y - rate * g
        new = np.concatenate(project(new[:f].copy(), new[f:].copy(), tau_max))
        size = float(np.abs(new - y).max() / rate) if f else 0.0
        if size < tol:
            v = new
            break
        if (y - new) @ (new - v) > 0:  # momentum points uphill: start it anew
            t = 1.0
        t_new = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y = new + (t - 1) / t_new * (new - v)
        y = np.concatenate(project(y[:f].copy(), y[f:].copy(), tau_max))
        v, t = new, t_new
    alpha, tau = curve_of(v[:f], v[f:], lo, hi)
    return alpha, tau, size


@dataclass
class Own:
    """What a target's fit has beyond the shared evidence: rows (numbers in the common numbering) and their columns, p columns before q columns."""

    rows: np.ndarray
    columns: np.ndarray


def fit_many(shared: np.ndarray, n_shared: int, label: np.ndarray, owns: list[Own], top: float, match_weight: float, start: np.ndarray, ridge: float = 1e-6, tol: float = 1e-7, rounds: int = 60) -> tuple[np.ndarray, np.ndarray]:
    """p and q (targets x 2 x features: the shared ones first) of each target, and the norms of their projected gradients.

    shared: rows x 2d, p columns before q columns, nil beyond the first n_shared rows; these rows count for all targets, further ones for those that own them.
    """
    k, d = len(owns), shared.shape[1] // 2
    width = d + max(o.columns.shape[1] // 2 for o in owns)
    at = np.ascontiguousarray(shared.T)  # features x rows
    w = np.where(label > 0, match_weight, 1.0)
    weight = np.zeros((k, len(label)))
    weight[:, :n_shared] = w[:n_shared]
    for t, o in enumerate(owns):
        weight[t, o.rows] = w[o.rows]
    weight /= np.maximum(weight.sum(axis=1, keepdims=True), 1e-12)
    target = label.astype(float)
    upper = np.triu_indices(2 * d)
    products = None
    places = np.concatenate([np.arange(d), width + np.arange(d)])
    mine = [np.concatenate([d + np.arange(o.columns.shape[1] // 2), width + d + np.arange(o.columns.shape[1] // 2)]) for o in owns]
    v = start.reshape(k, 2 * width).copy()

    def slopes(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Probabilities (targets x rows) and gradients."""
        z = v[:, places] @ at
        for t, o in enumerate(owns):
            if len(mine[t]):
                z[t, o.rows] += o.columns @ v[t, mine[t]]
        s = _logistic(z)
        r = weight * (s - target)
        g = ridge * v
        g[:, places] += r @ at.T
        for t, o in enumerate(owns):
            if len(mine[t]):
                g[t, mine[t]] += r[t, o.rows] @ o.columns
        return s, g

    def inside(v: np.ndarray) -> np.ndarray:
        p, q = project(v[:, :width].copy(), v[:, width:].copy(), top)
        return np.concatenate([p, q], axis=1)

    def loss(v: np.ndarray) -> np.ndarray:
        z = v[:, places] @ at
        for t, o in enumerate(owns):
            if len(mine[t]):
                z[t, o.rows] += o.columns @ v[t, mine[t]]
        return (weight * np.logaddexp(0, np.where(label > 0, -z, z))).sum(axis=1) + ridge / 2 * (v * v).sum(axis=1)

    s, g = slopes(v)
    size = np.abs(inside(v - g) - v).max(axis=1)
    for _ in range(rounds):
        todo = np.nonzero(size >= tol)[0]
        if not len(todo):
            break
        if products is None:
            products = at[upper[0]] * at[upper[1]]
        curved = weight[todo] * s[todo] * (1 - s[todo])
        h = np.zeros((len(todo), 2 * width, 2 * width))
        dense = curved @ products.T
        h[:, places[upper[0]], places[upper[1]]] = dense
        h[:, places[upper[1]], places[upper[0]]] = dense
        for j, t in enumerate(todo.tolist()):
            o, m = owns[t], mine[t]
            if len(m):
                scaled = o.columns * curved[j, o.rows][:, None]
                h[j][np.ix_(m, m)] = scaled.T @ o.columns
                cross = scaled.T @ shared[o.rows]
                h[j][np.ix_(m, places)] = cross
                h[j][np.ix_(places, m)] = cross.T
        step = _newton(v[todo], g[todo], h, width, top, ridge)
        new = inside(v[todo] + step)
        full = v.copy()
        full[todo] = new
        s_new, g_new = slopes(full)
        size_new = np.abs(inside(full - g_new) - full).max(axis=1)
        poor = todo[size_new[todo] > 0.5 * size[todo]]
        if len(poor):  # shorter steps until the loss falls; a gradient step where none does
            before = loss(v)
            back = full.copy()
            open_ = poor
            for halving in range(12):
                open_ = open_[loss(back)[open_] > before[open_] - 1e-15]
                if not len(open_):
                    break
                j = np.searchsorted(todo, open_)
                back[open_] = inside(v[open_] + step[j] * 0.5 ** (halving + 1))
            if len(open_):
                j = np.searchsorted(todo, open_)
                rate = 1 / (np.abs(h[j]).sum(axis=2).max(axis=1) + ridge)
                back[open_] = inside(v[open_] - rate[:, None] * g[open_])
            full = back
            s_new, g_new = slopes(full)
            size_new = np.abs(inside(full - g_new) - full).max(axis=1)
        v, s, g, size = full, s_new, g_new, size_new
    return v.reshape(k, 2, width), size


def _newton(v: np.ndarray, g: np.ndarray, h: np.ndarray, width: int, top: float, ridge: float, near: float = 1e-9) -> np.ndarray:
    """Newton steps in the directions that the bounds leave free; along a bound that holds, only its own direction is free."""
    p, q, gp, gq = v[:, :width], v[:, width:], g[:, :width], g[:, width:]
    no_p, no_q = (p <= near) & (gp > 0), (q <= near) & (gq > 0)
    full = p + q >= top - near
    # on the upper bound the step may go inwards, or along the bound; outwards means that the mean slope is negative
    along = full & (gp + gq < 0) & ~no_p & ~no_q
    stuck_p, stuck_q = full & (gp < 0) & no_q, full & (gq < 0) & no_p
    # at a corner the other bound decides
    corner_q, corner_p = along & (p <= near) & (gp >= gq), along & (q <= near) & (gq >= gp)
    free_p, free_q = ~(no_p | stuck_p | corner_q | corner_p), ~(no_q | stuck_q | corner_q | corner_p)
    free = np.concatenate([free_p, free_q], axis=1).astype(float)
    # basis: along the bound (p, q) moves by (1, -1), held in p's place
    a = np.nonzero(along & free_p & free_q)
    basis = np.zeros_like(h)
    i = np.arange(2 * width)
    basis[:, i, i] = free
    if len(a[0]):
        basis[a[0], width + a[1], a[1]] = -1.0
        basis[a[0], width + a[1], width + a[1]] = 0.0
    reduced = np.swapaxes(basis, 1, 2) @ h @ basis
    held = np.abs(np.diagonal(reduced, axis1=1, axis2=2)) < 1e-300
    reduced[:, i, i] += ridge + np.where(held, 1.0, 0.0)
    slope = (np.swapaxes(basis, 1, 2) @ g[:, :, None])[:, :, 0]
    return (basis @ np.linalg.solve(reduced, -slope[:, :, None]))[:, :, 0]


def loss(row, col, theta, x, label, alpha, tau, match_weight: float = 1.0) -> float:
    """Weighted mean log loss."""
    z = np.bincount(row, theta * tau[col] * (x - alpha[col]), minlength=len(label))
    w = np.where(label > 0, match_weight, 1.0)
    return float((w * np.logaddexp(0, np.where(label > 0, -z, z))).sum() / w.sum())
