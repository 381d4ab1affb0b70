"""Warping of sequences in numpy: DTW, derivative DTW, canonical, basis-curve and trainable warps; DTW and canonical of many pairs a step."""

from __future__ import annotations

import numpy as np


def slopes(v: np.ndarray) -> np.ndarray:
    """Slope estimate: mean of the left difference and half the centred difference; ends copy their neighbour."""
    v = np.asarray(v, dtype=float)
    if len(v) < 3:
        return np.zeros_like(v)
    inner = ((v[1:-1] - v[:-2]) + (v[2:] - v[:-2]) / 2) / 2
    return np.concatenate([inner[:1], inner, inner[-1:]])


def dtw(a: np.ndarray, b: np.ndarray, band: int | None = None) -> tuple[float, np.ndarray]:
    """Least summed distance and the warping path (pairs of positions) of two sequences (n x d), by anti-diagonals.

    Only the band is stored: n rows of its width.
    """
    a, b = (np.asarray(s, dtype=float).reshape(len(s), -1) for s in (a, b))
    n, k = len(a), len(b)
    if not n or not k:
        return 0.0, np.zeros((0, 2), dtype=np.int64)
    width = max(n, k) if band is None else max(band, abs(n - k) + 1)
    reach, steps = width * max(n - 1, k - 1, 1), max(n - 1, 1)
    low = np.clip(-((reach - np.arange(n) * (k - 1)) // steps), 0, k - 1) if n > 1 else np.zeros(1, dtype=np.int64)
    cost = np.full((n, min(k, 2 * reach // steps + 2)), np.inf)

    def at(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Costs of some cells, infinite outside the band."""
        inside = (i >= 0) & (j >= 0)
        place = j - low[np.maximum(i, 0)]
        inside &= (place >= 0) & (place < cost.shape[1])
        return np.where(inside, cost[np.maximum(i, 0), np.clip(place, 0, cost.shape[1] - 1)], np.inf)

    for step in range(n + k - 1):
        i = np.arange(max(0, step - k + 1), min(n, step + 1))
        if band is not None:  # the rows whose cell on this diagonal lies in the band
            i = i[np.searchsorted(i * (k - 1) - (step - i) * (n - 1), -reach) : np.searchsorted(i * (k - 1) - (step - i) * (n - 1), reach, side="right")]
        if not len(i):
            continue
        j = step - i
        d = np.abs(a[i] - b[j]).sum(axis=1)
        best = np.minimum(np.minimum(at(i - 1, j), at(i, j - 1)), at(i - 1, j - 1))
        best[(i == 0) & (j == 0)] = 0.0
        cost[i, j - low[i]] = d + best
    path, i, j = [(n - 1, k - 1)], n - 1, k - 1
    one = lambda i, j: float(cost[i, j - low[i]]) if i >= 0 and 0 <= j - low[i] < cost.shape[1] and j >= 0 else np.inf
    while i or j:
        _, i, j = min(((one(i - 1, j - 1), i - 1, j - 1), (one(i - 1, j), i - 1, j), (one(i, j - 1), i, j - 1)), key=lambda o: o[0])
        path.append((i, j))
    return one(n - 1, k - 1), np.array(path[::-1], dtype=np.int64)


#: Cells of many pairs whose turns are held at once, and the most pairs: more of them need no fewer numpy steps a cell.
CELLS, PAIRS = 1 << 27, 1 << 12

#: Cells of a diagonal that are reckoned at once: what a numpy step reads and writes stays near a core.
STEP = 1 << 15


def _turns(a: np.ndarray, b: np.ndarray, size: np.ndarray, band: int | None) -> tuple[np.ndarray, np.ndarray]:
    """Where the least costs of each cell of pairs (columns of ``a`` and ``b``, of which the first ``size`` rows count) come
    from, by block of pairs and anti-diagonal, and the row that each diagonal's place begins with. Cells, costs and ties as in ``dtw``: 0 comes from both before, 1 from the row before, 2 from the
    column before, 3 is the first cell."""
    n, many = a.shape
    width = n if band is None else max(band, 1)
    first = np.maximum(0, np.arange(2 * n - 1) - width + 1) // 2
    high = min(n, width + 1)
    wide = min(many, max(1, STEP // high))
    turn = np.zeros((-(-many // wide), 2 * n - 1, high, wide), dtype=np.uint8)
    for block, at in enumerate(range(0, many, wide)):
        pairs = slice(at, at + wide)
        rows = int(size[pairs].max())  # pairs that are all shorter end sooner
        x, y = np.ascontiguousarray(a[:rows, pairs]), np.ascontiguousarray(b[:rows, pairs][::-1])
        last = [np.full((rows + 3, x.shape[1]), np.inf) for _ in range(3)]  # the cell of row i stands at i + 1
        costs, sides, lines = (np.empty((high, x.shape[1]), dtype=kind) for kind in (float, bool, bool))
        for step in range(2 * rows - 1):
            lo, hi = max(int(first[step]), step - rows + 1), min(rows, step + 1, (step + width) // 2 + 1)
            now, before, two = last[step % 3], last[(step - 1) % 3], last[(step - 2) % 3]
            both, up, left, out = two[lo:hi], before[lo:hi], before[lo + 1 : hi + 1], now[lo + 1 : hi + 1]
            least, side, line, skip = costs[: hi - lo], sides[: hi - lo], lines[: hi - lo], lo - first[step]
            np.minimum(up, left, out=least)
            np.greater(both, least, out=side)
            np.greater(up, left, out=line)
            np.logical_and(side, line, out=line)
            np.add(side.view(np.uint8), line.view(np.uint8), out=turn[block, step, skip : skip + hi - lo, : x.shape[1]])
            np.subtract(x[lo:hi], y[rows - 1 - step + lo : rows - 1 - step + hi], out=out)
            np.abs(out, out=out)
            if step:
                np.minimum(least, both, out=least)
                np.add(out, least, out=out)
            now[lo] = now[hi + 1 : hi + 3] = np.inf
    turn[:, 0] = 3
    return turn, first


def _paths(a: np.ndarray, b: np.ndarray, size: np.ndarray, band: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Paths of pairs, of which the first ``size`` rows count, from their ends to their beginnings: both positions
    (steps x pairs) and the number of steps."""
    turn, first = _turns(a, b, size, band)
    many, wide = a.shape[1], turn.shape[3]
    pair = np.arange(many)
    i = size - 1
    j, steps, seen = i, np.ones(many, dtype=np.int64), [(i, i)]
    while (live := i + j > 0).any():
        t = turn[pair // wide, i + j, i - first[i + j], pair % wide]
        i, j = i - (live & (t != 2)), j - (live & (t != 1))
        steps += live
        seen.append((i, j))
    return np.stack([x[0] for x in seen]), np.stack([x[1] for x in seen]), steps


def _middles(a: np.ndarray, b: np.ndarray, size: np.ndarray, band: int | None) -> np.ndarray:
    """``last_per_frame`` of the paths of pairs (rows x pairs, zeros below the shorter ones), without the paths.

    A row is paired with all positions from its least to its greatest, so their mean is that of these two.
    """
    turn, first = _turns(a, b, size, band)
    n, many = a.shape
    _, steps, high, wide = turn.shape
    pair = np.arange(many)
    start = (np.arange(steps) * high - first) * wide
    turns, down, back = turn.reshape(-1), np.array([wide, wide, 0, 0]), np.array([2, 1, 1, 0])
    cell = pair // wide * (n * wide) + (size - 1) * wide + pair % wide  # of arrays by block, row and pair
    step, skip = 2 * (size - 1), pair // wide * ((steps * high - n) * wide)  # row and column; to the block's turns
    seen, came = (np.zeros((len(turn), n, wide), dtype=kind) for kind in (np.int64, np.uint8))
    for k in range(steps):
        if k % 8 == 0 and not step.any():
            break
        t = turns.take(start.take(step) + cell + skip)
        # what a row sees last: its least position, and how the path left it
        seen.reshape(-1)[cell], came.reshape(-1)[cell] = step, t
        cell, step = cell - down.take(t), step - back.take(t)
    seen, came = (x.transpose(1, 0, 2).reshape(n, -1)[:, :many] for x in (seen, came))
    rows = np.arange(n)[:, None]
    least = seen - rows
    least[0] = 0
    most = np.concatenate([least[1:] - (came[1:] == 0), np.zeros((1, many), dtype=np.int64)])
    most[size - 1, pair] = size - 1
    return np.where(rows < size, np.rint((least + most) / 2).astype(np.int64), 0)


def _padded(parts: list[np.ndarray]) -> np.ndarray:
    """Sequences side by side (rows x parts x ...), zeros below the shorter ones."""
    out = np.zeros((max(map(len, parts)), len(parts), *parts[0].shape[1:]))
    for g, part in enumerate(parts):
        out[: len(part), g] = part
    return out


def _rounds(sizes: np.ndarray, band: int | None, each: int = 1):
    """Numbers of pairs (or of groups of ``each`` pairs), the longest first, in rounds whose cells fit in ``CELLS``, of ``PAIRS`` at most."""
    order, at = np.argsort(-sizes, kind="stable"), 0
    while at < len(order):
        n = max(1, int(sizes[order[at]]))
        yield order[at : (at := at + max(1, min(PAIRS, CELLS // (2 * n * min(n, n if band is None else max(band, 1) + 1))) // each))]


def dtw_many(a: list[np.ndarray], b: list[np.ndarray], band: int | None = None) -> list[np.ndarray]:
    """The paths that ``dtw`` finds for many pairs of single sequences, both of a pair equally long and not empty."""
    out: list = [None] * len(a)
    for chosen in _rounds(np.array([len(s) for s in a], dtype=np.int64), band):
        size = np.array([len(a[g]) for g in chosen])
        i, j, steps = _paths(_padded([a[g] for g in chosen]), _padded([b[g] for g in chosen]), size, band)
        for k, g in enumerate(chosen):
            out[g] = np.stack([i[: steps[k], k], j[: steps[k], k]], axis=1)[::-1]
    return out


def scaled(v: np.ndarray) -> np.ndarray:
    v = np.asarray(v, dtype=float)
    sd = v.std(axis=0)
    return (v - v.mean(axis=0)) / np.where(sd > 0, sd, 1.0)


def _delayed(v: np.ndarray, d: int) -> np.ndarray:
    """Each position with its neighbours: gives single series enough columns to project."""
    pad = np.pad(v, (d, d), mode="edge")
    return np.stack([pad[k : k + len(v)] for k in range(2 * d + 1)], axis=1)


def ctw(a: np.ndarray, b: np.ndarray, iters: int = 5, d: int = 2, band: int | None = None) -> np.ndarray:
    """DTW in a space of canonical correlation, in turns until the path is stable."""
    fa, fb = _delayed(scaled(a), d), _delayed(scaled(b), d)
    _, path = dtw(scaled(a), scaled(b), band)
    for _ in range(iters):
        x, y = fa[path[:, 0]], fb[path[:, 1]]
        x, y = x - x.mean(axis=0), y - y.mean(axis=0)
        ridge = 1e-3 * len(path)

        def whiten(s: np.ndarray) -> np.ndarray:
            val, vec = np.linalg.eigh(s.T @ s + ridge * np.eye(s.shape[1]))
            return vec / np.sqrt(val)

        wx, wy = whiten(x), whiten(y)
        u, _, vt = np.linalg.svd((x @ wx).T @ (y @ wy))
        _, fresh = dtw(scaled(fa @ wx @ u[:, :1]), scaled(fb @ wy @ vt.T[:, :1]), band)
        if len(fresh) == len(path) and (fresh == path).all():
            break
        path = fresh
    return path


def ctw_many(a: list[np.ndarray], b: list[np.ndarray], iters: int = 5, d: int = 2, band: int | None = None) -> list[np.ndarray]:
    """The paths of ``ctw`` for many pairs, both of a pair equally long and not empty: a step takes all that still move."""
    out: list = [None] * len(a)
    sa, sb = [scaled(s) for s in a], [scaled(s) for s in b]
    paths = dtw_many(sa, sb, band)
    for chosen in _rounds(np.array([len(s) for s in a], dtype=np.int64), band):
        live = chosen
        for _ in range(iters):
            size, steps = np.array([len(a[g]) for g in live]), np.array([len(paths[g]) for g in live])
            there = (np.arange(steps.max())[:, None] < steps)[..., None]
            sides = []
            for k, parts in enumerate((sa, sb)):
                f = _padded([_delayed(parts[g], d) for g in live])
                x = np.take_along_axis(f, _padded([paths[g][:, k] for g in live]).astype(np.int64)[..., None], axis=0)
                x = np.where(there, x - (x * there).sum(axis=0) / steps[:, None], 0.0).transpose(1, 0, 2)
                val, vec = np.linalg.eigh(x.transpose(0, 2, 1) @ x + (1e-3 * steps)[:, None, None] * np.eye(x.shape[2]))
                sides.append((f.transpose(1, 0, 2), x, vec / np.sqrt(val)[:, None, :]))
            (fa, x, wx), (fb, y, wy) = sides
            u, _, vt = np.linalg.svd((x @ wx).transpose(0, 2, 1) @ (y @ wy))
            pa, pb = (fa @ wx @ u[:, :, :1])[..., 0], (fb @ wy @ vt[:, :1].transpose(0, 2, 1))[..., 0]
            fresh = dtw_many([scaled(p[:n]) for p, n in zip(pa, size)], [scaled(p[:n]) for p, n in zip(pb, size)], band)
            moved = [len(new) != len(paths[g]) or (new != paths[g]).any() for g, new in zip(live, fresh)]
            for g, new in zip(live, fresh):
                paths[g] = new
            live = live[np.array(moved)]
            if not len(live):
                break
        for g in chosen:
            out[g] = paths[g]
    return out


def monotone_basis(n: int, count: int) -> np.ndarray:
    """Rising curves from 0 to 1: powers, their mirror images, and logistic steps."""
    t = np.linspace(0, 1, n)
    curves = [t, t**2, 1 - (1 - t) ** 2, np.sqrt(t)]
    for c in np.linspace(0.2, 0.8, max(1, count - len(curves))):
        s = 1 / (1 + np.exp(-12 * (t - c)))
        curves.append((s - s[0]) / (s[-1] - s[0]))
    return np.stack(curves[:count], axis=1)


def gtw(a: np.ndarray, b: np.ndarray, n_basis: int = 6, iters: int = 20) -> np.ndarray:
    """The warp of b onto a as a non-negative mix of rising curves, by damped Gauss-Newton on the mix; pairs of positions."""
    a, b = scaled(a), scaled(b)
    n, k = len(a), len(b)
    basis = monotone_basis(n, n_basis)
    mix = np.zeros(n_basis)
    mix[0] = 1.0
    at = lambda w: np.clip(basis @ (w / max(w.sum(), 1e-12)) * (k - 1), 0, k - 1)
    read = lambda where: np.interp(where, np.arange(k), b)
    damp, err = 1.0, ((a - read(at(mix))) ** 2).sum()
    for _ in range(iters):
        where = at(mix)
        slope = np.interp(where, np.arange(k), np.gradient(b) if k > 1 else np.zeros(k))
        jac = slope[:, None] * (basis * (k - 1) - where[:, None]) / max(mix.sum(), 1e-12)
        step = np.linalg.solve(jac.T @ jac + damp * np.eye(n_basis), jac.T @ (a - read(where)))
        fresh = np.maximum(mix + step, 0)
        if fresh.sum() > 0 and (new := ((a - read(at(fresh))) ** 2).sum()) < err:
            mix, err, damp = fresh, new, damp / 2
        else:
            damp *= 4
    return np.stack([np.arange(n), np.rint(at(mix)).astype(np.int64)], axis=1)


def ttw(matrix: np.ndarray, terms: int = 4, rate: float = 0.05, iters: int = 60) -> np.ndarray:
    """Smooth shifts of all series at once: sine coefficients by gradient descent on the spread around the mean.

    Returns for each position of the common frame the position read from every series.
    """
    v = np.stack([scaled(matrix[:, j]) for j in range(matrix.shape[1])], axis=1)
    n, m = v.shape
    t = np.linspace(0, 1, n)
    sines = np.stack([np.sin(np.pi * (k + 1) * t) for k in range(terms)], axis=1)
    coef = np.zeros((terms, m))
    grid = np.arange(n)
    grads = np.gradient(v, axis=0) if n > 1 else np.zeros_like(v)
    where = np.repeat(grid[:, None].astype(float), m, axis=1)
    for _ in range(iters):
        where = np.clip(grid[:, None] + sines @ coef * n * 0.05, 0, n - 1)
        now = np.stack([np.interp(where[:, j], grid, v[:, j]) for j in range(m)], axis=1)
        slope = np.stack([np.interp(where[:, j], grid, grads[:, j]) for j in range(m)], axis=1)
        off = now - now.mean(axis=1, keepdims=True)
        coef -= rate * (sines.T @ (off * slope)) / n
    return np.maximum.accumulate(np.rint(where).astype(np.int64), axis=0)


def procrustes(matrix: np.ndarray, pairwise, iters: int = 3) -> np.ndarray:
    """Each series against the running mean, the mean renewed, in turns; position read from every series per frame of the mean."""
    v = np.stack([scaled(matrix[:, j]) for j in range(matrix.shape[1])], axis=1)
    n, m = v.shape
    mean = v.mean(axis=1)
    where = np.repeat(np.arange(n)[:, None], m, axis=1)
    for _ in range(iters):
        fresh = np.empty_like(where)
        for j in range(m):
            path = pairwise(mean, v[:, j])
            fresh[:, j] = last_per_frame(path, n)
        mean = np.take_along_axis(v, fresh, axis=0).mean(axis=1)
        if (fresh == where).all():
            break
        where = fresh
    return where


def procrustes_many(matrices: list[np.ndarray], pairs, iters: int = 3) -> list[np.ndarray]:
    """``procrustes`` of many groups, none without rows: ``pairs`` gets the means and series of all groups that still move."""
    vs = [np.stack([scaled(matrix[:, j]) for j in range(matrix.shape[1])], axis=1) for matrix in matrices]
    means = [v.mean(axis=1) for v in vs]
    where = [np.repeat(np.arange(len(v))[:, None], v.shape[1], axis=1) for v in vs]
    live = list(range(len(vs)))
    for _ in range(iters):
        paths = iter(pairs([means[g] for g in live for _ in range(vs[g].shape[1])], [vs[g][:, j] for g in live for j in range(vs[g].shape[1])]))
        still = []
        for g in live:
            n, m = vs[g].shape
            fresh = np.stack([last_per_frame(next(paths), n) for _ in range(m)], axis=1)
            means[g] = np.take_along_axis(vs[g], fresh, axis=0).mean(axis=1)
            if (fresh != where[g]).any():
                where[g] = fresh
                still.append(g)
        live = still
        if not live:
            break
    return where


def procrustes_dtw(matrices: list[np.ndarray], band: int | None = None, derivative: bool = False, iters: int = 3) -> list[np.ndarray]:
    """``procrustes`` of many groups, none without rows, by dtw of the values or of their slopes: groups and series side by side in one array."""
    out: list = [None] * len(matrices)
    sizes = np.array([len(v) for v in matrices], dtype=np.int64)
    m = matrices[0].shape[1] if len(matrices) else 0
    for chosen in _rounds(sizes, band, m):
        size, n = sizes[chosen], int(sizes[chosen[0]])
        v = np.zeros((n, len(chosen), m))
        for rows in np.unique(size):  # groups of one length are scaled in one step, with the sums of one series alone
            same = np.flatnonzero(size == rows)
            part = np.ascontiguousarray(np.stack([matrices[g] for g in chosen[same]]).transpose(0, 2, 1), dtype=float)
            sd = part.std(axis=2, keepdims=True)
            v[:rows, same] = ((part - part.mean(axis=2, keepdims=True)) / np.where(sd > 0, sd, 1.0)).transpose(2, 0, 1)
        mean = v.mean(axis=2)
        rows = np.arange(n)[:, None]
        where = np.repeat((rows * (rows < size))[..., None], m, axis=2)
        live = np.arange(len(chosen))
        for _ in range(iters):
            a, b, long = np.repeat(mean[:, live], m, axis=1), v[:, live].reshape(n, -1), np.repeat(size[live], m)
            if derivative:
                a, b = _slopes(a, long), _slopes(b, long)
            fresh = _middles(a, b, long, band).reshape(n, len(live), m)
            mean[:, live] = np.take_along_axis(v[:, live], fresh, axis=0).mean(axis=2)
            moved = (fresh != where[:, live]).any(axis=(0, 2))
            where[:, live] = fresh
            live = live[moved]
            if not len(live):
                break
        for k, g in enumerate(chosen):
            out[g] = where[: size[k], k]
    return out


def _slopes(v: np.ndarray, size: np.ndarray) -> np.ndarray:
    """``slopes`` of columns, of which the first ``size`` rows count; zeros below."""
    out = np.zeros_like(v)
    if len(v) > 2:
        out[1:-1] = ((v[1:-1] - v[:-2]) + (v[2:] - v[:-2]) / 2) / 2
        out[0] = out[1]
        col = np.flatnonzero(size > 2)
        out[size[col] - 1, col] = out[size[col] - 2, col]
        out[(np.arange(len(v))[:, None] >= size) | (size < 3)] = 0.0
    return out


def last_per_frame(path: np.ndarray, n: int) -> np.ndarray:
    """For each position of the first sequence, the middle of the positions it is paired with."""
    total = np.bincount(path[:, 0], weights=path[:, 1], minlength=n)
    count = np.maximum(np.bincount(path[:, 0], minlength=n), 1)
    return np.rint(total / count).astype(np.int64)
