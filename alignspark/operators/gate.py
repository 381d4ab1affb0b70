"""The model constraint inside a task: prediction error of one composed series, and the choice among alternatives."""

from __future__ import annotations

import heapq
from collections.abc import Iterable, Iterator

import numpy as np

from alignspark.operators.marss import Marss, fit_many


def last_seen(y: np.ndarray) -> np.ndarray:
    """For every row the last present value of each column before it (NaN: none)."""
    place = np.where(np.isnan(y), -1, np.arange(len(y))[:, None])
    before = np.vstack([np.full((1, y.shape[1]), -1), np.maximum.accumulate(place, axis=0)[:-1]]) if len(y) else place
    out = np.take_along_axis(y, np.maximum(before, 0), axis=0) if len(y) else y
    return np.where(before < 0, np.nan, out)


def predictions(y: np.ndarray, model: str) -> np.ndarray:
    if model == "locf":
        return last_seen(y)
    if model in ("marss", "marss_smoothed"):
        return Marss(y.shape[1]).fit(y).predict("smoothed" if model.endswith("smoothed") else "one_step")
    raise ValueError(f"no model {model!r} inside a task")


def scales(values: np.ndarray) -> np.ndarray:
    """Present values times their range, by series; NaN where that is 0."""
    with np.errstate(all="ignore"):
        count = (~np.isnan(values)).sum(axis=0)
        top = np.where(np.isnan(values), -np.inf, values).max(axis=0, initial=-np.inf)
        low = np.where(np.isnan(values), np.inf, values).min(axis=0, initial=np.inf)
        mu = count * (top - low)
    return np.where((count > 0) & (mu > 0), mu, np.nan)


def composed(values: np.ndarray, first: int, x: np.ndarray) -> np.ndarray:
    """Values of the series composed of tuples ``x`` (in order)."""
    return values[x - first, np.arange(values.shape[1])[None, :]] if len(x) else np.zeros((0, values.shape[1]))


def consistency_of(values: np.ndarray, first: int, x: np.ndarray, model: str) -> float:
    """Mean normalised error of the series composed of tuples ``x`` (in order); NaN where no series has a scale."""
    y = composed(values, first, x)
    return _error(values, y, predictions(y, model) if len(y) else y)


def consistencies_of(parts: list[tuple[np.ndarray, int, np.ndarray]], model: str) -> list[float]:
    """``consistency_of`` of many (values, first, x); the state-space model fits them together."""
    if model not in ("marss", "marss_smoothed") or not parts:
        return [consistency_of(*part, model) for part in parts]
    ys = [composed(*part) for part in parts]
    how = "smoothed" if model.endswith("smoothed") else "one_step"
    return [_error(values, y, fitted.predict(how)) for (values, _, _), y, fitted in zip(parts, ys, fit_many(ys, ys[0].shape[1]))]


def _error(values: np.ndarray, y: np.ndarray, pred: np.ndarray) -> float:
    loss = np.nansum(np.abs(pred - y), axis=0) if len(y) else np.zeros(values.shape[1])
    nmae = loss / scales(values)
    return float(np.nanmean(nmae)) if (~np.isnan(nmae)).any() else float("nan")


def by_weight(segments: list[list[list[int]]], w: np.ndarray) -> Iterator[list[int]]:
    """Every combination of one alternative for each segment, heaviest first (segments' own lists are in that order)."""
    weight = [[sum(int(w[k]) for k in one) for one in seg] for seg in segments]
    start = (0,) * len(segments)
    heap, seen = [(-sum(ws[0] for ws in weight), start)], {start}
    while heap:
        total, at = heapq.heappop(heap)
        yield sorted(k for seg, i in zip(segments, at) for k in seg[i])
        for s, i in enumerate(at):
            if i + 1 < len(segments[s]):
                step = (*at[:s], i + 1, *at[s + 1 :])
                if step not in seen:
                    seen.add(step)
                    heapq.heappush(heap, (total + weight[s][i] - weight[s][i + 1], step))


def first_feasible(alternatives: list[Iterable[list[int]]], errors, limit: float, most: int) -> list[tuple[list[int], float, str]]:
    """For each group its first alternative within the limit (a NaN error is within it); else none, as ``infeasible``, or
    as ``untested`` where more than ``most`` alternatives would have to be tried.

    Groups take turns: ``errors`` gets one alternative of every group still open, as (group's number, alternative).
    """
    left = [iter(a) for a in alternatives]
    done: list = [([], float("nan"), "infeasible")] * len(left)
    open_, tried = list(range(len(left))), 0
    while open_:
        drawn = [(k, chosen) for k in open_ if (chosen := next(left[k], None)) is not None]
        if tried == most:
            for k, _ in drawn:
                done[k] = [], float("nan"), "untested"
            break
        tried += 1
        open_ = []
        for (k, chosen), value in zip(drawn, errors(drawn)):
            if not value > limit:
                done[k] = chosen, value, "feasible"
            else:
                open_.append(k)
    return done
