"""Rival learners as numpy kernels over one bounded group of series.

Each takes a matrix y (series x steps, NaN where nothing was observed) and gives
estimates; ``grouped`` runs one per (experiment, cohort) group. Groups are
bounded by the cohort size and the number of steps; training samples of the
networks are capped by a parameter.
"""

from __future__ import annotations

from collections.abc import Callable

from statistics import NormalDist

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from pagecast.cluster import ship, slots


Forecaster = Callable[[int], np.ndarray]


# ---------------------------------------------------------------- factorisation
def trmf_fit(y: np.ndarray, rank: int = 5, lags: tuple[int, ...] = (1, 2, 24), lam_f: float = 0.1, lam_x: float = 0.1, lam_w: float = 0.1, rounds: int = 12, trace: list | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Series factors f (n x r), time factors x (r x t) and lag weights (r x lags)
    by alternating ridge steps: y ~ f x on observed cells, x follows its own
    lags. The time factors are updated one step at a time with all else fixed,
    so the objective never rises."""
    n, t = y.shape
    seen = ~np.isnan(y)
    z = np.where(seen, y, 0.0)
    rng = np.random.default_rng(1)
    lags = tuple(l for l in lags if l < t) or (1,)
    x = rng.normal(0, 0.3, (rank, t))
    f = rng.normal(0, 0.3, (n, rank))
    w = np.zeros((rank, len(lags)))
    w[:, 0] = 0.5
    most, own = max(lags), np.arange(rank)

    def residual(k: int, at: np.ndarray) -> np.ndarray:
        return x[k, at] - sum(w[k, i] * x[k, at - l] for i, l in enumerate(lags))

    def objective() -> float:
        at = np.arange(most, t)
        follow = sum(np.sum(residual(k, at) ** 2) for k in range(rank))
        return float(np.sum((z - f @ x)[seen] ** 2) + lam_f * np.sum(f**2) + lam_x * (follow + 0.1 * np.sum(x**2)) + lam_w * np.sum(w**2))

    for _ in range(rounds):
        for i in range(n):
            xs = x[:, seen[i]]
            f[i] = np.linalg.solve(xs @ xs.T + lam_f * np.eye(rank), xs @ z[i, seen[i]])
        for s in range(t):
            fs = f[seen[:, s]]
            a = fs.T @ fs + lam_x * 0.1 * np.eye(rank)
            b = fs.T @ z[seen[:, s], s]
            # own residual, and those of later steps that look back to this one
            if s >= most:
                a[own, own] += lam_x
                b += lam_x * sum(w[:, i] * x[:, s - l] for i, l in enumerate(lags))
            for i, l in enumerate(lags):
                if most <= s + l < t:
                    other = x[:, s + l] - sum(w[:, j] * x[:, s + l - m] for j, m in enumerate(lags) if j != i)
                    a[own, own] += lam_x * w[:, i] ** 2
                    b += lam_x * w[:, i] * other
            x[:, s] = np.linalg.solve(a, b)
        at = np.arange(most, t)
        for k in range(rank):
            past = np.stack([x[k, at - l] for l in lags])
            w[k] = np.linalg.solve(lam_x * past @ past.T + lam_w * np.eye(len(lags)), lam_x * past @ x[k, at])
        if trace is not None:
            trace.append(objective())
    return f, x, w


def trmf_impute(y: np.ndarray, **options) -> np.ndarray:
    f, x, _ = trmf_fit(y, **options)
    return f @ x


def trmf_fitted(y: np.ndarray, lags: tuple[int, ...] = (1, 2, 24), **options) -> Forecaster:
    f, x, w = trmf_fit(y, lags=lags, **options)
    used = tuple(l for l in lags if l < y.shape[1]) or (1,)

    def ahead(horizon: int) -> np.ndarray:
        every = np.hstack([x[:, -max(used) :], np.zeros((len(x), horizon))])
        for s in range(every.shape[1] - horizon, every.shape[1]):
            every[:, s] = sum(w[:, i] * every[:, s - l] for i, l in enumerate(used))
        return f @ every[:, every.shape[1] - horizon :]

    return ahead


def trmf_forecast(y: np.ndarray, horizon: int, **options) -> np.ndarray:
    return trmf_fitted(y, **options)(horizon)


def trmf_variance(y: np.ndarray, **options) -> np.ndarray:
    """Two fits, on values and on squares; the difference, clipped."""
    return np.maximum(0.0, trmf_impute(y**2, **options) - trmf_impute(y, **options) ** 2)


# --------------------------------------------------------------------- additive
def additive_fitted(y: np.ndarray, changepoints: int = 8, periods: tuple[float, ...] = (24.0, 168.0), order: int = 3, ridge: float = 0.1) -> Forecaster:
    """Each series by itself: a piecewise linear trend and Fourier terms, ridge
    least squares on observed steps."""
    n, t = y.shape
    knots = np.linspace(0, 0.8, changepoints + 1)[1:]

    def terms(steps: np.ndarray) -> np.ndarray:
        at = steps / t
        columns = [np.ones_like(at), at, *(np.maximum(0, at - k) for k in knots)]
        for p in periods:
            for k in range(1, order + 1):
                columns += [np.cos(2 * np.pi * k * steps / p), np.sin(2 * np.pi * k * steps / p)]
        return np.stack(columns, 1)

    design = terms(np.arange(t))
    penalty = ridge * np.eye(design.shape[1])
    penalty[0, 0] = penalty[1, 1] = 1e-9
    found = np.zeros((n, design.shape[1]))
    for i in range(n):
        at = np.flatnonzero(~np.isnan(y[i]))
        if len(at):
            a = design[at]
            found[i] = np.linalg.solve(a.T @ a + penalty, a.T @ y[i, at])
    return lambda horizon: found @ terms(np.arange(t, t + horizon)).T


def additive_fit_forecast(y: np.ndarray, horizon: int, **options) -> np.ndarray:
    return additive_fitted(y, **options)(horizon)


# ---------------------------------------------------------------------- networks
class Recurrent:
    """One gated recurrent layer with a linear head: squared loss for the mean,
    or a Gaussian likelihood with a second output for the spread."""

    def __init__(self, hidden: int = 12, probabilistic: bool = False, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.hidden, self.out = hidden, 2 if probabilistic else 1
        self.p = {
            "wx": rng.normal(0, 0.4, (1, 4 * hidden)),
            "wh": rng.normal(0, 1 / np.sqrt(hidden), (hidden, 4 * hidden)),
            "b": np.concatenate([np.zeros(hidden), np.ones(hidden), np.zeros(2 * hidden)]),
            "v": rng.normal(0, 0.3, (hidden, self.out)),
            "c": np.zeros(self.out),
        }

    def forward(self, x: np.ndarray) -> tuple[np.ndarray, list]:
        """x: samples x steps -> outputs after the last step, and the tape."""
        p, m = self.p, self.hidden
        h = np.zeros((len(x), m))
        c = np.zeros((len(x), m))
        tape = []
        for s in range(x.shape[1]):
            a = x[:, s : s + 1] @ p["wx"] + h @ p["wh"] + p["b"]
            i, f, o = (1 / (1 + np.exp(-np.clip(a[:, k * m : (k + 1) * m], -30, 30))) for k in range(3))
            g = np.tanh(a[:, 3 * m :])
            after = f * c + i * g
            tape.append((x[:, s : s + 1], h, c, i, f, o, g, after))
            c = after
            h = o * np.tanh(c)
        tape.append(h)
        return h @ p["v"] + p["c"], tape

    def loss(self, out: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
        e = out[:, 0] - y
        if self.out == 1:
            return float(np.mean(e**2)), (2 * e / len(y))[:, None]
        log_sd = np.clip(out[:, 1], -6, 4)
        inverse = np.exp(-2 * log_sd)
        value = np.mean(log_sd + 0.5 * e**2 * inverse)
        return float(value), np.stack([e * inverse, 1 - e**2 * inverse], 1) / len(y)

    def gradient(self, d_out: np.ndarray, tape: list) -> dict[str, np.ndarray]:
        p = self.p
        grads = {k: np.zeros_like(v) for k, v in p.items()}
        h = tape[-1]
        grads["v"], grads["c"] = h.T @ d_out, d_out.sum(0)
        dh, dc = d_out @ p["v"].T, 0.0
        for x, before, c, i, f, o, g, after in reversed(tape[:-1]):
            th = np.tanh(after)
            dc = dc + dh * o * (1 - th**2)
            da = np.hstack([dc * g * i * (1 - i), dc * c * f * (1 - f), dh * th * o * (1 - o), dc * i * (1 - g**2)])
            grads["wx"] += x.T @ da
            grads["wh"] += before.T @ da
            grads["b"] += da.sum(0)
            dh, dc = da @ p["wh"].T, dc * f
        return grads

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 12, batch: int = 128, rate: float = 0.01) -> Recurrent:
        rng = np.random.default_rng(5)
        first = {k: np.zeros_like(v) for k, v in self.p.items()}
        second = {k: np.zeros_like(v) for k, v in self.p.items()}
        step = 0
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for at in range(0, len(order), batch):
                rows = order[at : at + batch]
                out, tape = self.forward(x[rows])
                _, d = self.loss(out, y[rows])
                step += 1
                for k, g in self.gradient(d, tape).items():
                    g = np.clip(g, -5, 5)
                    first[k] = 0.9 * first[k] + 0.1 * g
                    second[k] = 0.999 * second[k] + 0.001 * g * g
                    self.p[k] -= rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
        return self


def _samples(y: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Windows and targets of all series, scaled by series, gaps carried forward.
    Every window of every series is there: training takes them in mini-batches."""
    mu = np.nan_to_num(np.nanmean(y, axis=1, keepdims=True))
    sd = np.nan_to_num(np.nanstd(y, axis=1, keepdims=True))
    sd[sd == 0] = 1.0
    z = pd.DataFrame((y - mu) / sd).ffill(axis=1).fillna(0.0).to_numpy()
    if z.shape[1] <= window:
        return np.zeros((0, window)), np.zeros(0), z, np.hstack([mu, sd])
    runs = np.lib.stride_tricks.sliding_window_view(z, window + 1, axis=1).reshape(-1, window + 1)
    return runs[:, :-1], runs[:, -1], z, np.hstack([mu, sd])


def recurrent_fitted(y: np.ndarray, window: int = 24, hidden: int = 12, epochs: int = 6) -> Forecaster:
    """A recurrent network on pooled windows, its predictions fed back."""
    x, target, z, scale = _samples(y, window)
    net = Recurrent(hidden).fit(x, target, epochs)

    def ahead(horizon: int) -> np.ndarray:
        state, out = z[:, -window:].copy(), []
        for _ in range(horizon):
            value = net.forward(state)[0][:, 0]
            out.append(value)
            state = np.hstack([state[:, 1:], value[:, None]])
        return np.stack(out, 1) * scale[:, 1:] + scale[:, :1]

    return ahead


def recurrent_forecast(y: np.ndarray, horizon: int, **options) -> np.ndarray:
    return recurrent_fitted(y, **options)(horizon)


def probabilistic_fitted(y: np.ndarray, window: int = 24, hidden: int = 12, epochs: int = 6, paths: int = 100) -> Callable[..., tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Mean and interval ends over sampled paths of a network that emits a
    location and a spread."""
    x, target, z, scale = _samples(y, window)
    net = Recurrent(hidden, probabilistic=True).fit(x, target, epochs)

    def ahead(horizon: int, confidence: float = 95.0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        rng = np.random.default_rng(13)
        n = len(z)
        state = np.repeat(z[:, -window:], paths, axis=0)
        drawn = []
        for _ in range(horizon):
            out = net.forward(state)[0]
            value = out[:, 0] + np.exp(np.clip(out[:, 1], -6, 2)) * rng.normal(size=len(out))
            drawn.append(value.reshape(n, paths))
            state = np.hstack([state[:, 1:], value[:, None]])
        drawn = np.stack(drawn, 1)
        low, high = np.quantile(drawn, [0.5 - confidence / 200, 0.5 + confidence / 200], axis=2)
        back = lambda v: v * scale[:, 1:] + scale[:, :1]
        return back(drawn.mean(2)), back(low), back(high)

    return ahead


def deviation_of(low: np.ndarray, high: np.ndarray, confidence: float = 95.0) -> np.ndarray:
    """The standard deviation that a Gaussian interval of this width has."""
    return (high - low) / (2 * NormalDist().inv_cdf(0.5 + confidence / 200))


def probabilistic_forecast(y: np.ndarray, horizon: int, **options) -> tuple[np.ndarray, np.ndarray]:
    """Mean, and the variance that the interval implies."""
    mean, low, high = probabilistic_fitted(y, **options)(horizon)
    return mean, deviation_of(low, high) ** 2


#: The rivals of the forecasting experiments: a matrix (series x steps, NaN where
#: missing) -> what forecasts any number of steps.
FITTED = {"factorisation": trmf_fitted, "additive": additive_fitted, "recurrent": recurrent_fitted, "probabilistic": probabilistic_fitted}


# ------------------------------------------------------------------------ groups
def grouped(long: DataFrame, by: list[str], steps: int, kernel: Callable[[np.ndarray], dict[str, np.ndarray]], first: int) -> DataFrame:
    """Run a kernel on each group's matrix of steps 0..steps-1. The kernel gives
    arrays (series x k) by name, whose first column is step ``first``."""
    ship(long.sparkSession)
    kinds = {f.name: f.dataType.simpleString() for f in long.schema}
    head = [*dict.fromkeys([*by, "cohort"])]
    names = ["mean", "variance"]
    schema = ", ".join(f"{c} {kinds[c]}" for c in head) + ", series_id string, step bigint, " + ", ".join(f"{n} double" for n in names)

    def run(key, frame: pd.DataFrame) -> pd.DataFrame:
        y = frame.pivot_table(index="series_id", columns="step", values="value", dropna=False).reindex(columns=range(steps)).sort_index()
        found = kernel(y.to_numpy(float))
        width = next(iter(found.values())).shape[1]
        out = {c: v for c, v in zip(head, key)}
        table = pd.DataFrame({**out, "series_id": np.repeat(y.index.to_numpy(), width), "step": np.tile(np.arange(first, first + width), len(y))})
        for n in names:
            table[n] = found[n].reshape(-1) if n in found else np.nan
        return table

    # few rows but long work in each group: more tasks than by bytes, so that groups run side by side
    rows = long.where(f"step < {steps}").select(*head, "series_id", "step", "value").repartition(8 * slots(long.sparkSession), *head)
    return rows.groupBy(*head).applyInPandas(run, schema)
