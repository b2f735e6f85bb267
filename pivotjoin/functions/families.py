"""Exponential families: p(x) = h(x) exp(eta . T(x) - A(eta)), fitted by matching the mean of T.

The published table's gamma row is used with eta = (shape - 1, -rate), which is what makes the
gradient of A the mean of T; the tests check that for every family.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass
from statistics import NormalDist

import numpy as np

from .numerics import beta_p, bisect, digamma, gamma_p, inverse_digamma, trigamma

Params = Mapping[str, float]
#: Means of T that one pass over the data gathers: of x, x*x, log x, log(1 - x); and the extremes and count.
Stats = Mapping[str, float]


@dataclass(frozen=True)
class Family:
    """A family on the line. ``fit`` returns None where the data are outside its support."""

    name: str
    w: int
    fit: Callable[[Stats], Params | None]
    eta: Callable[[Params], np.ndarray]
    log_partition: Callable[[np.ndarray], float]
    statistic: Callable[[float], np.ndarray]
    log_base: Callable[[float], float]
    cdf: Callable[[Params, float], float]
    quantile: Callable[[Params, float], float]
    draw: Callable[[Params, np.random.Generator, int], np.ndarray]
    variance: Callable[[Params], float]

    def logpdf(self, params: Params, x: float) -> float:
        e = self.eta(params)
        return self.log_base(x) + float(e @ self.statistic(x)) - self.log_partition(e)


def _by_bisection(cdf, lo: float, start: float):
    def quantile(p: Params, q: float) -> float:
        if q <= 0:
            return lo
        hi = start
        while cdf(p, hi) < q:
            hi *= 2
        return bisect(lambda x: cdf(p, x) - q, lo, hi)

    return quantile


def _exponential(s: Stats) -> Params | None:
    return {"rate": 1 / s["x"]} if s["min"] >= 0 and s["x"] > 0 else None


EXPONENTIAL = Family(
    "exponential", 1, _exponential, lambda p: np.array([-p["rate"]]), lambda e: -math.log(-e[0]), lambda x: np.array([x]), lambda x: 0.0, lambda p, x: -math.expm1(-p["rate"] * x) if x > 0 else 0.0,
    lambda p, q: -math.log1p(-min(q, 1 - 1e-16)) / p["rate"] if q > 0 else 0.0, lambda p, g, n: g.exponential(1 / p["rate"], n), lambda p: p["rate"] ** -2,
)


def _gamma(s: Stats) -> Params | None:
    """Newton's method on log(shape) - digamma(shape) = log(mean) - mean(log), a function of the statistics alone."""
    if s["min"] <= 0 or s["x"] <= 0:
        return None
    gap = math.log(s["x"]) - s["log"]
    if gap <= 1e-12:
        return None
    a = (3 - gap + math.sqrt((gap - 3) ** 2 + 24 * gap)) / (12 * gap)
    for _ in range(60):
        step = (math.log(a) - digamma(a) - gap) / (1 / a - trigamma(a))
        a = a - step if a > step else a / 2
        if abs(step) < 1e-13 * a:
            break
    return {"shape": a, "rate": a / s["x"]}


def _gamma_cdf(p: Params, x: float) -> float:
    return gamma_p(p["shape"], p["rate"] * x) if x > 0 else 0.0


GAMMA = Family(
    "gamma", 2, _gamma, lambda p: np.array([p["shape"] - 1, -p["rate"]]), lambda e: math.lgamma(e[0] + 1) - (e[0] + 1) * math.log(-e[1]), lambda x: np.array([math.log(x), x]), lambda x: 0.0, _gamma_cdf,
    lambda p, q: _by_bisection(_gamma_cdf, 0.0, p["shape"] / p["rate"])(p, q), lambda p, g, n: g.gamma(p["shape"], 1 / p["rate"], n), lambda p: p["shape"] / p["rate"] ** 2,
)


def _chi_square(s: Stats) -> Params | None:
    return {"dof": 2 * inverse_digamma(s["log"] - math.log(2))} if s["min"] > 0 else None


def _chi_square_cdf(p: Params, x: float) -> float:
    return gamma_p(p["dof"] / 2, x / 2) if x > 0 else 0.0


CHI_SQUARE = Family(
    "chi_square", 1, _chi_square, lambda p: np.array([p["dof"] / 2 - 1]), lambda e: math.lgamma(e[0] + 1) + (e[0] + 1) * math.log(2), lambda x: np.array([math.log(x)]), lambda x: -x / 2, _chi_square_cdf,
    _by_bisection(_chi_square_cdf, 0.0, 1.0), lambda p, g, n: g.chisquare(p["dof"], n), lambda p: 2 * p["dof"],
)


def _normal(s: Stats) -> Params | None:
    var = s["xx"] - s["x"] ** 2
    return {"mean": s["x"], "var": var} if var > 1e-12 * max(1.0, s["xx"]) else None


NORMAL = Family(
    "normal", 2, _normal, lambda p: np.array([p["mean"] / p["var"], -0.5 / p["var"]]), lambda e: -e[0] ** 2 / (4 * e[1]) - 0.5 * math.log(-2 * e[1]), lambda x: np.array([x, x * x]), lambda x: -0.5 * math.log(2 * math.pi),
    lambda p, x: NormalDist(p["mean"], math.sqrt(p["var"])).cdf(x), lambda p, q: NormalDist(p["mean"], math.sqrt(p["var"])).inv_cdf(min(max(q, 1e-300), 1 - 1e-16)), lambda p, g, n: g.normal(p["mean"], math.sqrt(p["var"]), n), lambda p: p["var"],
)


def _log_normal(s: Stats) -> Params | None:
    var = s["loglog"] - s["log"] ** 2
    return {"mean": s["log"], "var": var} if s["min"] > 0 and var > 1e-12 else None


LOG_NORMAL = Family(
    "log_normal", 2, _log_normal, NORMAL.eta, NORMAL.log_partition, lambda x: np.array([math.log(x), math.log(x) ** 2]), lambda x: -0.5 * math.log(2 * math.pi) - math.log(x), lambda p, x: NORMAL.cdf(p, math.log(x)) if x > 0 else 0.0,
    lambda p, q: math.exp(NORMAL.quantile(p, q)), lambda p, g, n: np.exp(NORMAL.draw(p, g, n)), lambda p: math.expm1(p["var"]) * math.exp(2 * p["mean"] + p["var"]),
)


def dirichlet_fit(mean_logs: Sequence[float], tol: float = 1e-12) -> np.ndarray:
    """Fixed point: digamma(alpha_j) = digamma(sum alpha) + mean log x_j."""
    g = np.asarray(mean_logs, float)
    a = np.ones(len(g))
    for _ in range(20_000):
        top = digamma(float(a.sum()))
        new = np.array([inverse_digamma(top + v) for v in g])
        if np.abs(new - a).max() < tol * new.max():
            return new
        a = new
    return a


def dirichlet_log_partition(a: np.ndarray) -> float:
    return sum(math.lgamma(v) for v in a) - math.lgamma(float(np.sum(a)))


def _beta(s: Stats) -> Params | None:
    if s["min"] <= 0 or s["max"] >= 1:
        return None
    a, b = dirichlet_fit([s["log"], s["log1m"]])
    return {"a": float(a), "b": float(b)}


def _beta_quantile(p: Params, q: float) -> float:
    return bisect(lambda x: beta_p(p["a"], p["b"], x) - q, 0.0, 1.0)


BETA = Family(
    "beta", 2, _beta, lambda p: np.array([p["a"], p["b"]]), lambda e: dirichlet_log_partition(e), lambda x: np.array([math.log(x), math.log1p(-x)]), lambda x: -math.log(x) - math.log1p(-x), lambda p, x: beta_p(p["a"], p["b"], x),
    _beta_quantile, lambda p, g, n: g.beta(p["a"], p["b"], n), lambda p: p["a"] * p["b"] / ((p["a"] + p["b"]) ** 2 * (p["a"] + p["b"] + 1)),
)


def _poisson(s: Stats) -> Params | None:
    return {"mean": s["x"]} if s["min"] >= 0 and s["x"] > 0 and s.get("whole", 1) else None


def _poisson_cdf(p: Params, x: float) -> float:
    return 1 - gamma_p(math.floor(x) + 1, p["mean"]) if x >= 0 else 0.0


def _poisson_quantile(p: Params, q: float) -> float:
    x = 0
    while _poisson_cdf(p, x) < min(q, 1 - 1e-12):
        x += 1
    return float(x)


POISSON = Family(
    "poisson", 1, _poisson, lambda p: np.array([math.log(p["mean"])]), lambda e: math.exp(e[0]), lambda x: np.array([x]), lambda x: -math.lgamma(x + 1), _poisson_cdf,
    _poisson_quantile, lambda p, g, n: g.poisson(p["mean"], n).astype(float), lambda p: p["mean"],
)

FAMILIES: dict[str, Family] = {f.name: f for f in (EXPONENTIAL, GAMMA, CHI_SQUARE, NORMAL, LOG_NORMAL, BETA, POISSON)}


def fit_numeric(mean_t: Sequence[float], family: Family, start: Sequence[float], how: str = "newton", tol: float = 1e-10, max_iter: int = 20_000, rate: float = 0.05) -> np.ndarray:
    """eta whose gradient of A is the mean of T, for families without a closed inverse.

    Newton steps or gradient ascent on the mean log likelihood; derivatives of A are taken by
    differences, and steps are halved while they leave the domain or fall. A step along the gradient
    is as long as the slope's change over the last one tells, or narrow ridges are crossed to and fro. No data are read.
    """
    e, t = np.array(start, float), np.asarray(mean_t, float)

    def value(x: np.ndarray) -> float:
        try:
            return float(x @ t) - family.log_partition(x)
        except (ValueError, OverflowError):
            return -math.inf

    def slope(x: np.ndarray) -> np.ndarray:
        # four places: values are exact to 16 digits only, which nearer ones would leave few of; nearer where the domain ends
        out = []
        for i, h in enumerate(1e-3 * np.clip(np.abs(x), 0.1, 1.0)):
            d = np.zeros(len(x))
            while True:
                d[i] = h
                far, near = (value(x + k * d) - value(x - k * d) for k in (2, 1))
                if math.isfinite(far) or h < 1e-9:
                    break
                h /= 10
            out.append((8 * near - far) / (12 * h))
        return np.array(out)

    before = None
    for _ in range(max_iter):
        g = slope(e)
        if how == "gradient" and before is not None:
            turn = float((e - before[0]) @ (g - before[1]))
            rate = float((e - before[0]) @ (e - before[0])) / -turn if turn < 0 else rate
        before = e, g
        step = g * rate
        if how == "newton":
            h = 1e-4 * np.maximum(0.1, np.abs(e))
            curve = np.column_stack([(slope(e + d) - slope(e - d)) / (2 * h[i]) for i, d in enumerate(np.diag(h))])
            step = -np.linalg.solve(curve, g) if abs(np.linalg.det(curve)) > 1e-14 else step
        now, scale = value(e), 1.0
        while value(e + scale * step) < now - 1e-14 * max(1.0, abs(now)) and scale > 1e-12:
            scale /= 2
        rate *= 1.5 if scale == 1.0 else scale  # longer steps as long as they climb and nothing tells better
        e = e + scale * step
        if np.abs(scale * step).max() < tol * max(1.0, np.abs(e).max()):
            break
    return e


@dataclass(frozen=True)
class MultiNormal:
    """Normal law of vectors; ``full`` keeps the covariances, else they are 0."""

    mean: np.ndarray
    cov: np.ndarray
    full: bool = True

    @classmethod
    def fit(cls, mean_x: np.ndarray, mean_xx: np.ndarray, full: bool = True, ridge: float = 1e-9) -> MultiNormal:
        cov = mean_xx - np.outer(mean_x, mean_x)
        cov = cov if full else np.diag(np.diag(cov))
        return cls(mean_x, cov + np.eye(len(cov)) * ridge * max(1.0, float(np.trace(cov)) / max(1, len(cov))), full)

    @property
    def w(self) -> int:
        m = len(self.mean)
        return m + (m * (m + 1) // 2 if self.full else m)

    def radius2(self, x: np.ndarray) -> np.ndarray:
        """Squared distance from the centre in units of the covariance: chi-square with m degrees of freedom."""
        z = np.linalg.solve(np.linalg.cholesky(self.cov), (x - self.mean).T)
        return (z * z).sum(axis=0)

    def draw(self, g: np.random.Generator, n: int) -> np.ndarray:
        return self.mean + g.standard_normal((n, len(self.mean))) @ np.linalg.cholesky(self.cov).T

    def marginal(self, d: int) -> tuple[Family, Params]:
        return NORMAL, {"mean": float(self.mean[d]), "var": float(self.cov[d, d])}

    def eta(self) -> tuple[np.ndarray, np.ndarray]:
        inv = np.linalg.inv(self.cov)
        return inv @ self.mean, -inv / 2

    @staticmethod
    def log_partition(eta1: np.ndarray, eta2: np.ndarray) -> float:
        return float(-eta1 @ np.linalg.solve(eta2, eta1) / 4 - np.linalg.slogdet(-2 * eta2)[1] / 2)


def _log_multigamma(q: int, a: float) -> float:
    return q * (q - 1) / 4 * math.log(math.pi) + sum(math.lgamma(a - i / 2) for i in range(q))


@dataclass(frozen=True)
class Wishart:
    """Law of q x q scatter matrices with ``dof`` degrees of freedom and scale ``v``."""

    v: np.ndarray
    dof: float

    @classmethod
    def fit(cls, mean_x: np.ndarray, mean_logdet: float) -> Wishart:
        """v = mean / dof; dof solves the equation of the mean log determinant."""
        q = len(mean_x)
        base = float(np.linalg.slogdet(mean_x)[1])

        def gap(n: float) -> float:
            return sum(digamma((n - i) / 2) for i in range(q)) + q * math.log(2) + base - q * math.log(n) - mean_logdet

        hi = q + 10.0
        while gap(hi) < 0 and hi < 1e9:
            hi *= 2
        n = bisect(gap, q - 1 + 1e-6, hi)
        return cls(mean_x / n, n)

    def eta(self) -> tuple[np.ndarray, float]:
        return -np.linalg.inv(self.v) / 2, (self.dof - len(self.v) - 1) / 2

    @staticmethod
    def log_partition(eta1: np.ndarray, eta2: float) -> float:
        q = len(eta1)
        n = 2 * eta2 + q + 1
        return -n / 2 * float(np.linalg.slogdet(-2 * eta1)[1]) + n * q / 2 * math.log(2) + _log_multigamma(q, n / 2)

    def draw(self, g: np.random.Generator, n: int) -> np.ndarray:
        """By Bartlett's triangular factors."""
        q, low = len(self.v), np.linalg.cholesky(self.v)
        out = np.empty((n, q, q))
        for k in range(n):
            a = np.tril(g.standard_normal((q, q)), -1)
            a[np.diag_indices(q)] = np.sqrt(g.chisquare(self.dof - np.arange(q)))
            f = low @ a
            out[k] = f @ f.T
        return out


@dataclass(frozen=True)
class Dirichlet:
    alpha: np.ndarray

    @classmethod
    def fit(cls, mean_logs: Sequence[float]) -> Dirichlet:
        return cls(dirichlet_fit(mean_logs))

    def draw(self, g: np.random.Generator, n: int) -> np.ndarray:
        return g.dirichlet(self.alpha, n)
