"""Selection within one block, in NumPy.  Matrices are m x n, columns are candidates."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

DEAD = 1e-10


@dataclass
class Trace:
    """Positions picked in order, with the score, the gain and what is left of the target's energy."""

    picks: list[int] = field(default_factory=list)
    scores: list[float] = field(default_factory=list)
    left: list[float] = field(default_factory=list)

    def add(self, p: int, score: float, left: float) -> None:
        self.picks.append(int(p))
        self.scores.append(float(score))
        self.left.append(max(0.0, float(left)))


def best(score: np.ndarray, alive: np.ndarray, ids: np.ndarray, digits: int = 9) -> int | None:
    """Position of the best live score; scores equal to ``digits`` significant digits go to the smallest id."""
    if not alive.any():
        return None
    top = score[alive].max()
    near = alive & (score >= top * (1 - 10.0**-digits) if top > 0 else score >= top)
    at = np.flatnonzero(near)
    return int(at[np.argmin(ids[at])])


def _by_column(a: np.ndarray, work, most: int = 1 << 15) -> np.ndarray:
    """``work`` of the columns, ``most`` at a time: a number for each, and no second matrix of the size of ``a``."""
    return np.concatenate([work(a[:, at : at + most]) for at in range(0, max(1, a.shape[1]), most)])


def targeted(a: np.ndarray, l: int, b: np.ndarray | None = None, ids: np.ndarray | None = None, cross: np.ndarray | None = None, start: list[int] = ()) -> Trace:
    """Greedy choice of columns of ``a`` that span ``b`` (``a`` itself by default) best.

    Two numbers a column: what its residual captures of the target's residual,
    and its residual's energy.  A pick gives a direction over the columns (w)
    and one over the target (v); both numbers follow from them and from past
    directions, no residual is formed.  ``cross``, b'a, may stand in for b.  A
    target with more columns than there are rows, a wide ``a`` itself above all,
    takes part by bb' alone, see :func:`by_rows`.
    """
    target = a if b is None else b
    if cross is None and target.shape[1] > a.shape[0]:
        return by_rows(a, l, target @ target.T, ids, start)
    n = a.shape[1]
    ids = np.arange(n) if ids is None else np.asarray(ids)
    c = cross if cross is not None else target.T @ a
    energy = float("nan") if cross is not None else float((target**2).sum())
    f, g = (_by_column(x, lambda x: (x * x).sum(axis=0)) for x in (c, a))
    floor = DEAD * g
    w, v = np.zeros((n, 0)), np.zeros((c.shape[0], 0))
    out, left, free, queue = Trace(), energy, np.ones(n, dtype=bool), list(start)
    while len(out.picks) < l:
        alive = free & (g > floor) & (g > 0)
        score = np.divide(f, g, out=np.zeros(n), where=alive)
        p = queue.pop(0) if queue else best(score, alive, ids)
        if p is None:
            break
        free[p] = False
        if not alive[p]:
            continue
        delta = a.T @ a[:, p] - w @ w[p]
        root = np.sqrt(max(delta[p], 1e-300))
        new_w, new_v = delta / root, (c[:, p] - v @ w[p]) / root
        f = np.maximum(f - 2 * new_w * (new_v @ c - (new_v @ v) @ w.T) + (new_v @ new_v) * new_w**2, 0)
        g = np.maximum(g - new_w**2, 0)
        left -= score[p]
        w, v = np.column_stack([w, new_w]), np.column_stack([v, new_v])
        out.add(p, score[p], left)
    return out


def by_rows(a: np.ndarray, l: int, middle: np.ndarray, ids: np.ndarray | None = None, start: list[int] = ()) -> Trace:
    """The same from bb' (``middle``, m x m): nothing of n x n entries is formed and no history by column is kept."""
    n = a.shape[1]
    ids = np.arange(n) if ids is None else np.asarray(ids)
    f = _by_column(a, lambda x: np.maximum(np.einsum("in,in->n", x, middle @ x), 0))
    g = _by_column(a, lambda x: (x * x).sum(axis=0))
    floor, q = DEAD * g, np.zeros((a.shape[0], 0))
    out, left, free, queue = Trace(), float(np.trace(middle)), np.ones(n, dtype=bool), list(start)
    while len(out.picks) < l:
        alive = free & (g > floor) & (g > 0)
        score = np.divide(f, g, out=np.zeros(n), where=alive)
        p = queue.pop(0) if queue else best(score, alive, ids)
        if p is None:
            break
        free[p] = False
        if not alive[p]:
            continue
        u = a[:, p]
        for _ in range(2):
            u = u - q @ (q.T @ u)
        u = u / np.linalg.norm(u)
        back = middle @ u
        inner, w = float(u @ back), u @ a
        f = np.maximum(f - 2 * w * ((back - q @ (q.T @ back)) @ a) + inner * w**2, 0)
        g = np.maximum(g - w**2, 0)
        left -= score[p]
        q = np.column_stack([q, u])
        out.add(p, score[p], left)
    return out


class Rows:
    """Columns of a block in pieces n_i x m, a column a row; a piece whose entries are exact in 4 bytes is kept in 4."""

    def __init__(self, most: int = 1 << 20):
        self.pieces, self.ends, self.most = [], [0], most

    def add(self, x: np.ndarray) -> None:
        step = max(1, self.most // max(1, x.shape[1]))
        for at in range(0, len(x), step):
            part = x[at : at + step]
            with np.errstate(over="ignore"):
                small = part.astype(np.float32)
            self.pieces.append(small if np.array_equal(small, part) else part.copy())
            self.ends.append(self.ends[-1] + len(part))

    def each(self, work) -> np.ndarray:
        """``work`` of every piece, m x n_i, side by side."""
        return np.concatenate([work(x.T.astype(np.float64, copy=False)) for x in self.pieces], axis=-1)

    def column(self, p: int) -> np.ndarray:
        k = int(np.searchsorted(self.ends, p, "right")) - 1
        return self.pieces[k][p - self.ends[k]].astype(np.float64)


def targeted_many(a: np.ndarray | Rows, l: int, targets: list[np.ndarray], ids: np.ndarray | None = None) -> list[Trace]:
    """:func:`targeted` for many targets in step, so that a step reads ``a`` once for all of them.

    A new direction u and bb'u give both numbers of every column; no history by
    column is kept.
    """
    if isinstance(a, np.ndarray):
        whole, a = a, Rows()
        a.pieces, a.ends = [whole.T], [0, whole.shape[1]]
    n, m, many = a.ends[-1], a.pieces[0].shape[1] if a.pieces else 0, len(targets)
    ids = np.arange(n) if ids is None else np.asarray(ids)
    if not n:
        return [Trace() for _ in targets]
    g0 = a.each(lambda x: np.einsum("in,in->n", x, x))
    floor, g = DEAD * g0, np.tile(g0, (many, 1))
    f = a.each(lambda x: np.array([((b.T @ x) ** 2).sum(axis=0) for b in targets]).reshape(many, -1))
    out, left, free = [Trace() for _ in targets], [float((b**2).sum()) for b in targets], np.ones((many, n), dtype=bool)
    q, live = [np.zeros((m, 0)) for _ in targets], list(range(many))
    for _ in range(l):
        sides, going = [], []
        for k in live:
            alive = free[k] & (g[k] > floor) & (g[k] > 0)
            score = np.divide(f[k], g[k], out=np.zeros(n), where=alive)
            if (p := best(score, alive, ids)) is None:
                continue
            u = a.column(p)
            for _ in range(2):
                u = u - q[k] @ (q[k].T @ u)
            u = u / np.linalg.norm(u)
            back = targets[k] @ (targets[k].T @ u)
            going.append((k, float(u @ back)))
            sides += [u, back - q[k] @ (q[k].T @ back)]
            q[k], free[k, p] = np.column_stack([q[k], u]), False
            left[k] -= score[p]
            out[k].add(p, score[p], left[k])
        if not going:
            break
        got = a.each(np.array(sides).__matmul__)
        for i, (k, inner) in enumerate(going):
            w = got[2 * i]
            f[k] = np.maximum(f[k] - 2 * w * got[2 * i + 1] + inner * w**2, 0)
            g[k] = np.maximum(g[k] - w**2, 0)
        live = [k for k, _ in going]
    return out


def on_gram(gram: np.ndarray, l: int, ids: np.ndarray | None = None, by_norm: bool = False) -> Trace:
    """The same for the target a'a from the Gram matrix alone, which is deflated in place of a residual.

    by_norm: pivots by largest residual norm instead, as in :func:`pivoted_qr`.
    """
    g, n = gram.astype(np.float64).copy(), len(gram)
    ids = np.arange(n) if ids is None else np.asarray(ids)
    floor, left, out, free = DEAD * np.diag(g), float(np.trace(g)), Trace(), np.ones(n, dtype=bool)
    for _ in range(l):
        own = np.diag(g).copy()
        alive = free & (own > floor) & (own > 0)
        score = own if by_norm else np.divide((g * g).sum(axis=1), own, out=np.zeros(n), where=alive)
        if (p := best(score, alive, ids)) is None:
            break
        gain = (g[p] @ g[p]) / own[p]
        g -= np.outer(g[:, p], g[p]) / own[p]
        free[p] = False
        left -= gain if by_norm else score[p]
        out.add(p, score[p], left)
    return out


def on_residual(a: np.ndarray, l: int, ids: np.ndarray | None = None) -> Trace:
    """The same with the residual matrix formed and deflated."""
    e, n = a.astype(np.float64).copy(), a.shape[1]
    ids = np.arange(n) if ids is None else np.asarray(ids)
    floor, out, free = DEAD * (a * a).sum(axis=0), Trace(), np.ones(n, dtype=bool)
    for _ in range(l):
        own = (e * e).sum(axis=0)
        alive = free & (own > floor) & (own > 0)
        score = np.divide(((e.T @ e) ** 2).sum(axis=1), own, out=np.zeros(n), where=alive)
        if (p := best(score, alive, ids)) is None:
            break
        u = e[:, p] / np.sqrt(own[p])
        e -= np.outer(u, u @ e)
        free[p] = False
        out.add(p, score[p], (e * e).sum())
    return out


def naive(a: np.ndarray, l: int, ids: np.ndarray | None = None) -> Trace:
    """The same by computing the whole criterion for each candidate; for tests."""
    n, out, chosen = a.shape[1], Trace(), []
    ids = np.arange(n) if ids is None else np.asarray(ids)
    left = energy = float((a * a).sum())
    for _ in range(l):
        loss = np.array([residual_sq(a, orth(a[:, [*chosen, i]])) if i not in chosen else np.inf for i in range(n)])
        gain = np.where(np.isfinite(loss), left - loss, -1)
        alive = gain > DEAD * energy
        if (p := best(gain, alive, ids)) is None:
            break
        chosen.append(p)
        out.add(p, gain[p], loss[p])
        left = loss[p]
    return out


def orth(columns: np.ndarray, how: str = "svd") -> np.ndarray:
    """Orthonormal basis of the columns' span, by Gram-Schmidt ('gs'), 'qr' or 'svd'; dependent columns add nothing."""
    if not columns.shape[1]:
        return np.zeros((columns.shape[0], 0))
    scale = np.sqrt((columns**2).sum(axis=0))
    x = columns / np.where(scale > 0, scale, 1)
    if how == "gs":
        q = np.zeros((x.shape[0], 0))
        for v in x.T:
            for _ in range(2):
                v = v - q @ (q.T @ v)
            if (s := np.linalg.norm(v)) > 1e-8:
                q = np.column_stack([q, v / s])
        return q
    if how == "qr":
        q, r = np.linalg.qr(x)
        if (np.abs(np.diag(r)) > 1e-8).all():
            return q
    u, s, _ = np.linalg.svd(x, full_matrices=False)
    return u[:, s > 1e-8 * max(s[0], 1e-300)] if s[0] > 0 else u[:, :0]


def residual_sq(a: np.ndarray, q: np.ndarray) -> float:
    return float(max(0.0, (a * a).sum() - ((q.T @ a) ** 2).sum()))


def pivoted_qr(a: np.ndarray, l: int, ids: np.ndarray | None = None) -> Trace:
    """Pivots by largest residual norm."""
    e, n = a.astype(np.float64).copy(), a.shape[1]
    ids = np.arange(n) if ids is None else np.asarray(ids)
    g0, out, free = (a * a).sum(axis=0), Trace(), np.ones(n, dtype=bool)
    for _ in range(l):
        own = (e * e).sum(axis=0)
        if (p := best(own, free & (own > DEAD * g0) & (own > 0), ids)) is None:
            break
        u = e[:, p] / np.sqrt(own[p])
        e -= np.outer(u, u @ e)
        free[p] = False
        out.add(p, own[p], (e * e).sum())
    return out


def strong_rrqr(a: np.ndarray, l: int, ids: np.ndarray | None = None, factor: float = 2.0, max_swaps: int = 200) -> Trace:
    """Pivoted QR, then swaps of a chosen and another column while one enlarges the chosen volume by more than ``factor``."""
    first = pivoted_qr(a, l, ids)
    chosen = list(first.picks)
    rest = [i for i in range(a.shape[1]) if i not in set(chosen)]
    for _ in range(max_swaps if rest and chosen else 0):
        q, r = np.linalg.qr(a[:, chosen])
        if np.abs(np.diag(r)).min() < 1e-12 * max(1e-300, np.abs(np.diag(r)).max()):
            break
        inverse = np.linalg.inv(r)
        inside = q.T @ a[:, rest]
        outside = np.maximum((a[:, rest] ** 2).sum(axis=0) - (inside**2).sum(axis=0), 0)
        growth = np.sqrt((inverse @ inside) ** 2 + np.outer((inverse**2).sum(axis=1), outside))
        i, j = np.unravel_index(np.argmax(growth), growth.shape)
        if growth[i, j] <= factor:
            break
        chosen[i], rest[j] = rest[j], chosen[i]
    out, e = Trace(), a.astype(np.float64).copy()
    for p in chosen:
        own = float(e[:, p] @ e[:, p])
        if own > 0:
            u = e[:, p] / np.sqrt(own)
            e -= np.outer(u, u @ e)
        out.add(p, own, (e * e).sum())
    return out
