"""Influence of features on the probability of a match, as column expressions.

Targets of the regression take two values, plus and minus the label's log-odds, so a
feature's weighted line, its residual variance and its error bound follow from six
sums: count, sum and sum of squares of x, for non-matches (0) and matches (1).
"""

from __future__ import annotations

from math import pi

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..settings import Settings

SIMPSON = 64  # intervals
REACH = 9.0  # standard deviations beyond which the integrand is nil
LEAST_SXX = 1e-9


def logistic(z: Column) -> Column:
    return 1 / (1 + F.exp(-F.least(F.greatest(z, F.lit(-700.0)), F.lit(700.0))))


def curve(x: Column, alpha: Column, tau: Column) -> Column:
    return logistic(tau * (x - alpha))


def factor_weight(theta: Column, tau: Column, x: Column, alpha: Column) -> Column:
    return theta * tau * (x - alpha)


def normalize(theta: Column) -> Column:
    return (1 + theta) / 2


def entropy(p: Column) -> Column:
    part = lambda q: F.when((q <= 0) | (q >= 1), 0.0).otherwise(-q * F.log2(q))
    return part(p) + part(1 - p)


def interval(x: Column, bins: int = 10) -> Column:
    return F.least(F.greatest(F.floor(x * bins), F.lit(0)), F.lit(bins - 1)).cast("int")


def curve_columns(settings: Settings, w: Column) -> dict[str, Column]:
    """From n0 s0 q0 n1 s1 q1 and the class weight w: tau, alpha, sigma, xbar, dev, nobs, active, lo, hi."""
    n0, s0, q0, n1, s1, q1 = (F.col(c).cast("double") for c in ("n0", "s0", "q0", "n1", "s1", "q1"))
    z = settings.label_logit
    sw, sx, sxx = n0 + w * n1, s0 + w * s1, q0 + w * q1
    sy, sxy = (w * n1 - n0) * z, (w * s1 - s0) * z
    spread = sw * sxx - sx * sx
    tau = F.when(spread > LEAST_SXX, (sw * sxy - sx * sy) / F.when(spread > LEAST_SXX, spread))
    icpt = (sy - tau * sx) / sw
    alpha = -icpt / F.when(F.abs(tau) > 1e-12, tau)
    nobs = n0 + n1
    dof = F.when(nobs > 2, nobs - 2)
    low, high = F.lit(-z) - icpt, F.lit(z) - icpt
    # one chain in the order of the other engine and of curves_np: on a line without residuals the sum is rounding alone, and sigma's confidence shows it
    rss = n0 * low * low - 2 * tau * low * s0 + tau * tau * q0 + n1 * high * high - 2 * tau * high * s1 + tau * tau * q1
    sigma = F.sqrt(F.greatest(rss / dof, F.lit(0.0)))
    xbar = (s0 + s1) / F.when(nobs > 0, nobs)
    dev = (q0 + q1) - nobs * xbar * xbar
    lo, hi = s0 / F.when(n0 > 0, n0), s1 / F.when(n1 > 0, n1)
    active = F.coalesce((lo < hi) & (tau > 0) & (nobs > 2) & (dev > LEAST_SXX), F.lit(False))
    if settings.clip:
        tau = F.least(F.greatest(tau, F.lit(0.0)), F.lit(settings.tau_max))
        alpha = F.least(F.greatest(alpha, lo), hi)
    return {"tau": tau, "alpha": alpha, "sigma": sigma, "xbar": xbar, "dev": dev, "nobs": nobs, "active": active, "lo": lo, "hi": hi}


def _end(dof: Column) -> Column:
    return F.least(F.lit(pi / 2), REACH / F.sqrt(dof))


def _area(b: Column, dof: Column) -> Column:
    h = b / SIMPSON
    node = lambda i: F.when(i.isin(0, SIMPSON), 1.0).otherwise(F.when(i % 2 == 1, 4.0).otherwise(2.0)) * F.pow(F.greatest(F.cos(h * i), F.lit(0.0)), dof - 1)
    return F.aggregate(F.sequence(F.lit(0), F.lit(SIMPSON)), F.lit(0.0), lambda s, i: s + node(i)) * h / 3


def whole_area(dof: Column) -> Column:
    """What normalises central_t; it depends on the degrees of freedom alone, so it is made once for a feature and not for each of its entries."""
    return _area(_end(dof), dof)


def central_t(q: Column, dof: Column, whole: Column | None = None) -> Column:
    """P(-q <= T <= q) of Student's t: with t = sqrt(dof) tan(phi) the density is a power of the cosine, which Simpson's rule integrates; the whole integral normalises it."""
    return F.least(F.lit(1.0), _area(F.least(F.atan(q / F.sqrt(dof)), _end(dof)), dof) / (whole_area(dof) if whole is None else whole))


def confidence(settings: Settings, x: Column, whole: Column | None = None) -> Column:
    """Of an active feature's value at x: how surely the line's error stays within the bound."""
    root = F.sqrt(1 + 1 / F.col("nobs") + (x - F.col("xbar")) * (x - F.col("xbar")) / F.col("dev"))
    q = settings.error_bound / (F.pow(F.greatest(F.col("sigma"), F.lit(1e-9)), F.lit(float(settings.sigma_power))) * root)
    return F.when(F.col("active"), central_t(q, F.col("nobs") - 2, whole)).otherwise(0.0)


def log_odds_of_support(theta_n: Column) -> Column:
    """One feature's addend; the sum is the log-odds of the combined support, so products never underflow."""
    t = F.least(theta_n, F.lit(1 - 1e-12))
    return F.ln(t / (1 - t))


# the same for numpy kernels


def central_t_np(q: np.ndarray, dof: np.ndarray) -> np.ndarray:
    q, dof = np.broadcast_arrays(np.asarray(q, float), np.asarray(dof, float))
    coef = np.where(np.arange(SIMPSON + 1) % 2 == 1, 4.0, 2.0)
    coef[[0, -1]] = 1.0
    grid = np.arange(SIMPSON + 1) / SIMPSON
    end = np.minimum(pi / 2, REACH / np.sqrt(dof))

    def area(b: np.ndarray, d: np.ndarray) -> np.ndarray:
        return (coef * np.maximum(np.cos(b[:, None] * grid), 0.0) ** (d[:, None] - 1)).sum(axis=1) * b / SIMPSON / 3

    flat_d, flat_e = dof.ravel(), end.ravel()
    some, back = np.unique(flat_d, return_inverse=True)
    whole = area(np.minimum(pi / 2, REACH / np.sqrt(some)), some)[back]
    return np.minimum(1.0, area(np.minimum(np.arctan(q.ravel() / np.sqrt(flat_d)), flat_e), flat_d) / whole).reshape(q.shape)


class CentralT:
    """central_t_np by tables: for each number of degrees of freedom the integral up to each of so many nodes, and between nodes the cubic that has its values and slopes there. Within 1e-8."""

    def __init__(self, nodes: int = 384, most: int = 2048):
        self.nodes, self.most = nodes, most
        self.clear()

    def clear(self) -> None:
        self.slot: dict[float, int] = {}
        self.value, self.slope = np.zeros((16, self.nodes + 1)), np.zeros((16, self.nodes + 1))
        self.end = np.zeros(16)

    def slots(self, dof: np.ndarray) -> np.ndarray:
        """Numbers of the tables of these degrees of freedom."""
        some, back = np.unique(dof, return_inverse=True)
        if len(self.slot) + len(some) > max(self.most, len(some)):
            self.clear()
        for d in some.tolist():
            if d not in self.slot:
                self._make(d)
        return np.array([self.slot[d] for d in some.tolist()], dtype=np.int64)[back]

    def _make(self, dof: float) -> None:
        k = len(self.slot)
        if k == len(self.end):
            grow = lambda a: np.concatenate([a, np.zeros_like(a)])
            self.value, self.slope, self.end = grow(self.value), grow(self.slope), grow(self.end)
        end = min(pi / 2, REACH / np.sqrt(dof))
        step = end / self.nodes
        g = np.maximum(np.cos(np.arange(2 * self.nodes + 1) * step / 2), 0.0) ** (dof - 1)
        area = np.concatenate([[0.0], np.cumsum(g[:-1:2] + 4 * g[1::2] + g[2::2])]) * step / 6
        self.value[k], self.slope[k], self.end[k] = area / area[-1], g[::2] * step / area[-1], end
        self.slot[dof] = k

    def __call__(self, q: np.ndarray, dof: np.ndarray) -> np.ndarray:
        table = self.slots(dof)
        return self._read(np.arctan(q / np.sqrt(dof)) / self.end[table] * self.nodes, table * (self.nodes + 1))

    def along(self, lines: dict[str, np.ndarray], f: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Confidence of entries (feature f, value x) from what confidence_lines gives; features that are not active have 0."""
        off = x - lines["xbar"][f]
        at = np.arctan(lines["reach"][f] / np.sqrt(lines["base"][f] + off * off * lines["bend"][f])) * lines["scale"][f]
        return self._read(at, lines["first"][f])

    def _read(self, at: np.ndarray, first: np.ndarray) -> np.ndarray:
        """at: place in a table, in nodes; first: place of the table."""
        at = np.minimum(at, self.nodes)
        i = np.minimum(at.astype(np.int64), self.nodes - 1)
        s = at - i
        flat = first + i
        y0, y1 = self.value.ravel()[flat], self.value.ravel()[flat + 1]
        d0, d1 = self.slope.ravel()[flat], self.slope.ravel()[flat + 1]
        c = 3 * (y1 - y0) - 2 * d0 - d1
        return np.minimum(1.0, y0 + s * (d0 + s * (c + s * (2 * (y0 - y1) + d0 + d1))))


def curves_np(stats: np.ndarray, w: float, settings: Settings) -> dict[str, np.ndarray]:
    """stats: columns n0 s0 q0 n1 s1 q1."""
    n0, s0, q0, n1, s1, q1 = stats.T
    z = settings.label_logit
    with np.errstate(all="ignore"):
        sw, sx, sxx = n0 + w * n1, s0 + w * s1, q0 + w * q1
        sy, sxy = (w * n1 - n0) * z, (w * s1 - s0) * z
        spread = sw * sxx - sx * sx
        tau = np.where(spread > LEAST_SXX, (sw * sxy - sx * sy) / spread, np.nan)
        icpt = (sy - tau * sx) / sw
        alpha = -icpt / tau
        nobs = n0 + n1
        rss = n0 * (-z - icpt) ** 2 - 2 * tau * (-z - icpt) * s0 + tau**2 * q0 + n1 * (z - icpt) ** 2 - 2 * tau * (z - icpt) * s1 + tau**2 * q1
        sigma = np.sqrt(np.maximum(rss / (nobs - 2), 0))
        xbar = (s0 + s1) / nobs
        dev = q0 + q1 - nobs * xbar**2
        lo, hi = s0 / n0, s1 / n1
        active = (lo < hi) & (tau > 0) & (nobs > 2) & (dev > LEAST_SXX)
        if settings.clip:
            tau, alpha = np.clip(tau, 0, settings.tau_max), np.minimum(np.maximum(alpha, lo), hi)
    return {"tau": tau, "alpha": alpha, "sigma": sigma, "xbar": xbar, "dev": dev, "nobs": nobs, "active": active, "lo": lo, "hi": hi}


def confidence_lines(c: dict[str, np.ndarray], settings: Settings, central: CentralT) -> dict[str, np.ndarray]:
    """Per feature what its confidence at any value follows from; reach 0 where it is not active."""
    n = len(c["active"])
    on = np.nonzero(c["active"])[0]
    out = {"xbar": np.zeros(n), "reach": np.zeros(n), "base": np.ones(n), "bend": np.zeros(n), "scale": np.zeros(n), "first": np.zeros(n, dtype=np.int64)}
    if len(on):
        nobs = c["nobs"][on]
        table = central.slots(nobs - 2)
        out["xbar"][on], out["base"][on], out["bend"][on] = c["xbar"][on], 1 + 1 / nobs, 1 / c["dev"][on]
        out["reach"][on] = settings.error_bound / (np.maximum(c["sigma"][on], 1e-9) ** settings.sigma_power * np.sqrt(nobs - 2))
        out["scale"][on], out["first"][on] = central.nodes / central.end[table], table * (central.nodes + 1)
    return out


def confidence_np(c: dict[str, np.ndarray], f: np.ndarray, x: np.ndarray, settings: Settings) -> np.ndarray:
    """Of entries (feature f, value x)."""
    out = np.zeros(len(f))
    on = np.nonzero(c["active"][f])[0]
    g = f[on]
    root = np.sqrt(1 + 1 / c["nobs"][g] + (x[on] - c["xbar"][g]) ** 2 / c["dev"][g])
    out[on] = central_t_np(settings.error_bound / (np.maximum(c["sigma"][g], 1e-9) ** settings.sigma_power * root), c["nobs"][g] - 2)
    return out


def entropy_np(p: np.ndarray) -> np.ndarray:
    with np.errstate(all="ignore"):
        part = lambda q: np.where((q <= 0) | (q >= 1), 0.0, -q * np.log2(q))
        return part(p) + part(1 - p)
