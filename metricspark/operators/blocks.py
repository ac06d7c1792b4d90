"""Nearest and farthest of whole blocks of vectors, exactly: both sides are halved into runs of neighbours, and runs that the triangle inequality excludes are left out.

Every run of one side meets the centres of all runs of the other. The nearest (farthest) run is measured first and gives a bound; then runs
within it are measured, pair by pair. Where nothing prunes, all pairs are.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa

from ..functions.metrics import Metric

RUN = 64  # most vectors of a run
AT_ONCE = 16_384  # vectors that a run is compared with at once
PENDING = 1_000_000  # pairs that are kept before they are ranked
TIE = 4e-9  # ties are decided on distances rounded to 9 digits


def ranges(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The places first, first + 1, ... of ranges of some sizes, one range after the other."""
    return np.repeat(first - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum()) if len(size) else np.empty(0, np.int64)


def halved(x: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, first place of each run): rows halved at the median of their widest component until at most `most` are together."""
    order, todo, first = np.arange(len(x)), [(0, len(x))], []
    while todo:
        a, b = todo.pop()
        if b - a <= most:
            first.append(a)
            continue
        rows, half = order[a:b], (b - a) // 2
        part = x[rows]
        order[a:b] = rows[np.argpartition(part[:, np.argmax(part.max(axis=0) - part.min(axis=0))], half)]
        todo += [(a, a + half), (a + half, b)]
    return order, np.sort(first)


class Runs:
    """Vectors in runs of neighbours, each with a centre and a covering radius."""

    def __init__(self, m: Metric, x: np.ndarray):
        self.sums, self.root = m.crossed
        self.order, self.first = halved(x, RUN)
        self.x, self.size = x[self.order], np.diff(np.append(self.first, len(x)))
        self.center = np.minimum.reduceat(self.x, self.first) / 2 + np.maximum.reduceat(self.x, self.first) / 2
        self.radius = np.array([self.root(self.sums(c[None], self.x[a : a + n]).max()) for c, a, n in zip(self.center, self.first, self.size)])

    def __iter__(self):
        """(places, vectors, centre, radius) of each run."""
        for a, n, c, r in zip(self.first.tolist(), self.size.tolist(), self.center, self.radius):
            yield slice(a, a + n), self.x[a : a + n], c, r

    def limits(self, center: np.ndarray, radius: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(distance of the centres, least, greatest distance that a vector of the run can have to one within `radius` of `center`), rounding allowed for."""
        d = self.root(self.sums(center[None], self.center))[0]
        around = self.radius + radius
        loose = 1e-12 * (d + around)
        return d, d - around - loose, d + around + loose

    def places(self, runs: np.ndarray):
        """The places of some runs, AT_ONCE a step."""
        at = ranges(self.first[runs], self.size[runs])
        return (at[a : a + AT_ONCE] for a in range(0, len(at), AT_ONCE))


def first_copies(x: np.ndarray, oid: np.ndarray, k: int) -> np.ndarray:
    """The rows with the k smallest oids of every vector: no other copy is among the k nearest."""
    order = np.lexsort((oid, *x.T))
    new = np.flatnonzero(np.concatenate([[True], (x[order[1:]] != x[order[:-1]]).any(axis=1)]))
    return order[np.arange(len(x)) - np.repeat(new, np.diff(np.append(new, len(x)))) < k]


def k_of_each(of: np.ndarray, oid: np.ndarray, d: np.ndarray, k: int) -> np.ndarray:
    """Which pairs (of, oid, d) go on: of every `of` those within its k-th distance, ties by rounding included, and of equal distances the k smallest oids."""
    order = np.lexsort((oid, d, of))
    of, d = of[order], d[order]
    new = np.diff(of, prepend=-1) != 0
    first = np.flatnonzero(new)
    size = np.diff(np.append(first, len(of)))
    last = np.repeat(d[first + np.minimum(k, size) - 1], size)
    equal = np.flatnonzero(new | (d != np.concatenate([[np.nan], d[:-1]])))
    nth = np.arange(len(of)) - np.repeat(equal, np.diff(np.append(equal, len(of))))
    return order[(d <= last + TIE) & (nth < k)]


def nearest_of_block(m: Metric, x: np.ndarray, oid: np.ndarray, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, oid, distance) of the k nearest of finite vectors `x` for each of `q`."""
    kept = first_copies(x, oid, k)
    objs, oid, asked = Runs(m, x[kept]), oid[kept], Runs(m, q)
    oid, out, pending, kept_pairs = oid[objs.order], [], [], 0

    def rank():
        of, at, d = (np.concatenate(c) for c in zip(*pending))
        who = oid[at]
        best = k_of_each(of, who, d, k)
        out.append((asked.order[of[best]], who[best], d[best]))
        pending.clear()

    need = min(len(objs.size), -(-k // int(objs.size.min())))  # so many runs hold k, if all together do
    for mine, vectors, center, radius in asked:
        d, least, _ = objs.limits(center, radius)
        close = np.argpartition(d, need - 1)[:need]
        first = objs.root(objs.sums(vectors, objs.x[ranges(objs.first[close], objs.size[close])]))
        far = np.partition(first, k - 1, axis=1)[:, k - 1] + TIE if first.shape[1] >= k else np.full(len(vectors), np.inf)
        for at in objs.places(np.flatnonzero(~(least > far.max()))):
            d = objs.root(objs.sums(vectors, objs.x[at]))
            if len(at) > k:
                far = np.minimum(far, np.partition(d, k - 1, axis=1)[:, k - 1] + TIE)
            which, there = np.nonzero(d <= far[:, None])
            pending.append((mine.start + which, at[there], d[which, there]))
            kept_pairs += len(which)
        if kept_pairs > PENDING:
            rank()
            kept_pairs = 0
    if pending:
        rank()
    return tuple(np.concatenate(c) for c in zip(*out))


def extremes(m: Metric, x: np.ndarray, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(least, greatest) distance of every row of `x` to the rows of `q`; NaN counts as the greatest, as in SQL."""
    least, most = np.full(len(x), np.nan), np.full(len(x), -np.inf)
    sums, root = m.crossed
    plain, own = np.isfinite(x).all(axis=1), np.isfinite(q).all(axis=1)
    if plain.any() and own.any():
        least[plain], most[plain] = _extremes(m, x[plain], q[own])
    for rows, others in ((np.arange(len(x)), q[~own]), (np.flatnonzero(~plain), q[own])):
        for a in range(0, len(rows), RUN):
            at = rows[a : a + RUN]
            for b in range(0, len(others), AT_ONCE):
                d = root(sums(x[at], others[b : b + AT_ONCE]))
                least[at], most[at] = np.fmin(least[at], np.fmin.reduce(d, axis=1)), np.maximum(most[at], d.max(axis=1))
    return least, most


def _extremes(m: Metric, x: np.ndarray, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    objs, asked = Runs(m, x), Runs(m, q)
    sums, root = m.crossed
    near, far = np.full(len(x), np.inf), np.full(len(x), -np.inf)  # before the root
    for mine, vectors, center, radius in objs:
        d, least, most = asked.limits(center, radius)
        for at in asked.places(np.argmin(d)[None]):
            near[mine] = np.minimum(near[mine], sums(vectors, asked.x[at]).min(axis=1))
        for at in asked.places(np.argmax(d)[None]):
            far[mine] = np.maximum(far[mine], sums(vectors, asked.x[at]).max(axis=1))
        for at in asked.places(np.flatnonzero(~(least > root(near[mine].max())))):
            near[mine] = np.minimum(near[mine], sums(vectors, asked.x[at]).min(axis=1))
        for at in asked.places(np.flatnonzero(~(most < root(far[mine].min())))):
            far[mine] = np.maximum(far[mine], sums(vectors, asked.x[at]).max(axis=1))
    out = np.empty((2, len(x)))
    out[:, objs.order] = root(near), root(far)
    return out[0], out[1]


def nearest_rows(m: Metric, k: int, otherwise):
    """For a cogroup of objects [oid, obj, ...] and queries [qid, q, ...]: [qid, oid, dist, k]. Blocks with vectors that are not finite go to `otherwise`."""

    def run(rows: pa.Table, asked: pa.Table) -> pa.Table:
        if len(rows) and len(asked):
            x, q = (m.from_arrow(t.column(c).combine_chunks()) for t, c in ((rows, "obj"), (asked, "q")))
            if np.isfinite(x).all() and np.isfinite(q).all():
                of, oid, d = nearest_of_block(m, x, rows.column("oid").to_numpy(), q, k)
                return pa.table({"qid": asked.column("qid").to_numpy()[of], "oid": oid, "dist": d, "k": np.full(len(d), k, np.int32)})
        return otherwise(rows, asked)

    return run


def extreme_rows(m: Metric):
    """For a cogroup of objects [oid, obj, ...] and queries [q, ...]: [oid, d0, d1]."""

    def run(rows: pa.Table, asked: pa.Table) -> pa.Table:
        if not len(rows) or not len(asked):
            return pa.table({"oid": pa.array([], pa.int64()), "d0": pa.array([], pa.float64()), "d1": pa.array([], pa.float64())})
        least, most = extremes(m, *(m.from_arrow(t.column(c).combine_chunks()) for t, c in ((rows, "obj"), (asked, "q"))))
        return pa.table({"oid": rows.column("oid"), "d0": pa.array(least, from_pandas=False), "d1": pa.array(most, from_pandas=False)})

    return run
