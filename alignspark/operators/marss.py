"""A multivariate autoregressive state-space model that tolerates gaps, fitted by EM in numpy.

State x_t = B x_(t-1) + u + w_t, observation y_t = x_t + v_t, with diagonal Q and
R and diagonal or full B; missing entries drop out of the update. Values are
standardised inside.

Under a diagonal B nothing mixes the variables: every covariance stays diagonal,
so each variable is a model of its own. ``fit_many`` therefore fits all variables
of many series at once, one numpy step per position.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

FLOOR = 1e-6


class Marss:
    def __init__(self, m: int, iters: int = 15, b: str = "diag"):
        self.m, self.iters, self.kind = m, iters, b
        self.loglik: list[float] = []

    def fit(self, y: np.ndarray) -> Marss:
        if self.kind != "full":
            return fit_many([y], self.m, self.iters, models=[self])[0]
        self._prepare(y)
        for _ in range(self.iters):
            self.loglik.append(self._filter())
            if len(self.y) < 3:
                break
            self._smooth()
            self._maximise()
        self.loglik.append(self._filter())
        self._smooth()
        return self

    def _prepare(self, y: np.ndarray) -> None:
        self.raw = np.asarray(y, dtype=float).reshape(-1, self.m)
        with np.errstate(all="ignore"):
            count = (~np.isnan(self.raw)).sum(axis=0)
            self.mean = np.where(count > 0, np.nansum(np.nan_to_num(self.raw), axis=0) / np.maximum(count, 1), 0.0)
            spread = np.sqrt(np.where(count > 0, np.nansum((np.nan_to_num(self.raw - self.mean)) ** 2, axis=0) / np.maximum(count, 1), 1.0))
        self.sd = np.where(spread > 0, spread, 1.0)
        self.y = (self.raw - self.mean) / self.sd
        m = self.m
        self.B, self.u, self.Q, self.R = 0.8 * np.eye(m), np.zeros(m), 0.5 * np.ones(m), 0.3 * np.ones(m)
        self.x0, self.V0 = np.zeros(m), np.eye(m)
        self.loglik = []

    def _filter(self) -> float:
        n, m = len(self.y), self.m
        self.xp, self.Vp, self.xf, self.Vf = np.zeros((n, m)), np.zeros((n, m, m)), np.zeros((n, m)), np.zeros((n, m, m))
        x, v, total = self.x0, self.V0, 0.0
        for t in range(n):
            if t:
                x, v = self.B @ x + self.u, self.B @ v @ self.B.T + np.diag(self.Q)
            self.xp[t], self.Vp[t] = x, v
            seen = ~np.isnan(self.y[t])
            if seen.any():
                z = np.eye(m)[seen]
                s = z @ v @ z.T + np.diag(self.R[seen])
                e = self.y[t, seen] - x[seen]
                gain = np.linalg.solve(s, z @ v).T
                x = x + gain @ e
                keep = np.eye(m) - gain @ z
                v = keep @ v @ keep.T + gain @ np.diag(self.R[seen]) @ gain.T
                total -= 0.5 * (np.linalg.slogdet(s)[1] + e @ np.linalg.solve(s, e) + seen.sum() * np.log(2 * np.pi))
            self.xf[t], self.Vf[t] = x, v
        return float(total)

    def _smooth(self) -> None:
        n = len(self.y)
        self.xs, self.Vs = self.xf.copy(), self.Vf.copy()
        self.Vlag = np.zeros_like(self.Vf)
        for t in range(n - 2, -1, -1):
            gain = np.linalg.solve(self.Vp[t + 1], self.B @ self.Vf[t]).T
            self.xs[t] = self.xf[t] + gain @ (self.xs[t + 1] - self.xp[t + 1])
            self.Vs[t] = self.Vf[t] + gain @ (self.Vs[t + 1] - self.Vp[t + 1]) @ gain.T
            self.Vlag[t + 1] = self.Vs[t + 1] @ gain.T

    def _maximise(self) -> None:
        n, m = len(self.y), self.m
        a, b = self.xs[:-1], self.xs[1:]
        s00 = self.Vs[:-1].sum(axis=0) + a.T @ a
        s11 = self.Vs[1:].sum(axis=0) + b.T @ b
        s10 = self.Vlag[1:].sum(axis=0) + b.T @ a
        sa, sb, k = a.sum(axis=0), b.sum(axis=0), n - 1
        big = np.block([[s00, sa[:, None]], [sa[None, :], np.array([[float(k)]])]])
        sol = np.linalg.solve(big + FLOOR * np.eye(m + 1), np.vstack([s10.T, sb[None, :]])).T
        self.B, self.u = sol[:, :m], sol[:, m]
        B, u = self.B, self.u
        q = s11 - s10 @ B.T - B @ s10.T + B @ s00 @ B.T - np.outer(sb, u) - np.outer(u, sb) + B @ np.outer(sa, u) + np.outer(u, sa) @ B.T + k * np.outer(u, u)
        self.Q = np.maximum(np.diag(q) / k, FLOOR)
        seen = ~np.isnan(self.y)
        err = np.where(seen, (np.nan_to_num(self.y) - self.xs) ** 2 + np.diagonal(self.Vs, axis1=1, axis2=2), self.R[None, :])
        self.R = np.maximum(err.mean(axis=0), FLOOR)
        self.x0, self.V0 = self.xs[0], self.Vs[0]

    def predict(self, how: str = "one_step") -> np.ndarray:
        return (self.xp if how == "one_step" else self.xs) * self.sd + self.mean


def fit_many(ys: Iterable[np.ndarray], m: int, iters: int = 15, cells: int = 400_000, models: list[Marss] | None = None) -> list[Marss]:
    """A model with diagonal B for each series (rows x m), in the given order.

    Series of similar length are fitted together, about ``cells`` values at a time; each is padded to the longest.
    """
    ys = list(ys)
    models = models or [Marss(m, iters) for _ in ys]
    for model, y in zip(models, ys):
        model._prepare(y)
    order = sorted(range(len(ys)), key=lambda k: len(models[k].y))
    while order:
        longest = max(1, len(models[order[-1]].y))
        take = max(1, cells // (longest * m))
        _fit_together([models[k] for k in order[-take:]], iters)
        del order[-take:]
    return models


def _fit_together(models: list[Marss], iters: int) -> None:
    """EM for independent variables: arrays hold positions x variables of all models."""
    m = models[0].m
    lengths = np.array([len(k.y) for k in models])
    n = int(lengths.max())
    y = np.full((n, len(models), m), np.nan)
    for k, model in enumerate(models):
        y[: lengths[k], k] = model.y
    y = y.reshape(n, -1)
    length = np.repeat(lengths, m)
    seen = ~np.isnan(y)
    y = np.nan_to_num(y)
    inside = np.arange(n)[:, None] < length
    last = np.arange(n)[:, None] >= length - 1
    before, after = ~last, inside.copy()
    after[:1] = False
    count, steps = np.maximum(length, 1), np.maximum(length - 1, 1)
    learns = length >= 3
    cols = y.shape[1]
    B, u, Q, R = np.full(cols, 0.8), np.zeros(cols), np.full(cols, 0.5), np.full(cols, 0.3)
    x0, V0 = np.zeros(cols), np.ones(cols)
    xp, Vp, xf, Vf, xs, Vs, lag = (np.zeros((n, cols)) for _ in range(7))

    def filtered() -> np.ndarray:
        x, v = x0, V0
        for t in range(n):
            if t:
                x, v = B * x + u, B * B * v + Q
            xp[t], Vp[t] = x, v
            gain = np.where(seen[t], v / (v + R), 0.0)
            x = x + gain * (y[t] - x)
            v = (1 - gain) ** 2 * v + gain * gain * R
            xf[t], Vf[t] = x, v
        spread = Vp + R
        return -0.5 * np.where(seen, np.log(spread) + (y - xp) ** 2 / spread + np.log(2 * np.pi), 0.0).sum(axis=0).reshape(-1, m).sum(axis=1)

    def smoothed() -> None:
        if not n:
            return
        xs[-1], Vs[-1] = xf[-1], Vf[-1]
        for t in range(n - 2, -1, -1):
            gain = np.where(last[t], 0.0, B * Vf[t] / Vp[t + 1])  # past its end a series is only padding
            xs[t] = xf[t] + gain * (xs[t + 1] - xp[t + 1])
            Vs[t] = Vf[t] + gain * gain * (Vs[t + 1] - Vp[t + 1])
            lag[t + 1] = Vs[t + 1] * gain

    for turn in range(iters):
        total = filtered()
        for model, value in zip(models, total):
            model.loglik.append(float(value))
        if not learns.any():
            break
        smoothed()
        a, b = np.where(before, xs, 0.0), np.where(after, xs, 0.0)
        s00 = np.where(before, Vs, 0.0).sum(axis=0) + (a * a).sum(axis=0)
        s11 = np.where(after, Vs, 0.0).sum(axis=0) + (b * b).sum(axis=0)
        s10 = np.where(after, lag, 0.0).sum(axis=0) + (b[1:] * a[:-1]).sum(axis=0)
        sa, sb, k = a.sum(axis=0), b.sum(axis=0), steps
        slope = (s10 - sb * sa / k) / np.maximum(s00 - sa * sa / k, FLOOR)
        drift = (sb - slope * sa) / k
        q = s11 - 2 * slope * s10 + slope * slope * s00 - 2 * sb * drift + 2 * slope * sa * drift + k * drift * drift
        err = np.where(seen, (y - xs) ** 2 + Vs, R)
        B, u = np.where(learns, slope, B), np.where(learns, drift, u)
        Q = np.where(learns, np.maximum(q / k, FLOOR), Q)
        R = np.where(learns, np.maximum(np.where(inside, err, 0.0).sum(axis=0) / count, FLOOR), R)
        x0, V0 = np.where(learns, xs[0], x0), np.where(learns, Vs[0], V0)
    total = filtered()
    smoothed()
    for k, model in enumerate(models):
        own, rows = slice(k * m, (k + 1) * m), slice(0, lengths[k])
        model.loglik.append(float(total[k]))
        model.B, model.u, model.Q, model.R = np.diag(B[own]), u[own].copy(), Q[own].copy(), R[own].copy()
        model.x0, model.V0 = x0[own].copy(), np.diag(V0[own])
        model.xp, model.xf, model.xs = xp[rows, own].copy(), xf[rows, own].copy(), xs[rows, own].copy()


def groups_together(df: DataFrame, run: Callable[[list[pd.DataFrame]], Iterator[pd.DataFrame]], schema: str, cells: int = 200_000) -> DataFrame:
    """``run`` over lists of whole groups (by grp), about ``cells`` rows at a time: a task reads its groups one after another."""

    def stream(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ready, held, open_ = [], 0, []
        for frame in frames:
            cuts = np.flatnonzero((frame["grp"] != frame["grp"].shift()).to_numpy()) if len(frame) else []
            for lo, hi in zip(cuts, [*cuts[1:], len(frame)]):
                part = frame.iloc[lo:hi]
                if open_ and open_[-1]["grp"].iloc[0] != part["grp"].iloc[0]:
                    ready.append(pd.concat(open_, ignore_index=True))
                    held, open_ = held + len(ready[-1]), []
                open_.append(part)
            if held >= cells:
                yield from run(ready)
                ready, held = [], 0
        if open_:
            ready.append(pd.concat(open_, ignore_index=True))
        if ready:
            yield from run(ready)

    return df.repartition("grp").sortWithinPartitions("grp").mapInPandas(stream, schema)


def estimates(groups: list[pd.DataFrame], place: str, m: int, iters: int, how: str) -> Iterator[np.ndarray]:
    """For each group's rows (``place``, sid, val) the model's value, in the order of the rows."""
    at, ys = [], []
    for pdf in groups:
        _, row = np.unique(pdf[place].to_numpy(), return_inverse=True)
        col = pdf["sid"].to_numpy(dtype=np.int64) - 1
        y = np.full((int(row.max()) + 1, m), np.nan)
        y[row, col] = pdf["val"].to_numpy(dtype=float)
        at.append((row, col))
        ys.append(y)
    for model, where in zip(fit_many(ys, m, iters), at):
        yield model.predict(how)[where]
