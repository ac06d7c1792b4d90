"""Metrics: a Catalyst expression, a NumPy kernel and a DuckDB template for each distance."""
from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F, types as T

UNROLLED = 8  # vectors up to this length get plain arithmetic; longer ones would make methods that the JVM doesn't compile


@dataclass(frozen=True)
class Metric:
    """A distance: `column(a, b, dim)` for plans, `kernel(many, one)` for batches, `sql(a, b)` for the oracle."""

    name: str
    kind: str  # "vector" or "string"
    column: Callable[[Column, Column, int | None], Column]
    kernel: Callable
    sql: Callable[[str, str], str]
    integer_valued: bool = False
    before_root: tuple[Callable, Callable] | None = None  # (column of the sum, its root), where the root of the least sum can be taken once
    rows: Callable | None = None  # distances of the rows of two matrices, pair by pair
    crossed: tuple[Callable, Callable] | None = None  # (sums of all rows of one matrix with all of another, their root), in NumPy
    products: bool = False  # squares of the distances come from inner products, but for rounding

    @property
    def dtype(self) -> T.DataType:
        return T.StringType() if self.kind == "string" else T.ArrayType(T.DoubleType())

    def slack(self, x: Column) -> Column:
        """`x` a little larger, so that rounding never dismisses an answer; integer metrics need none."""
        return x if self.integer_valued else x * (1 + 1e-9) + 1e-12

    def tight(self, x: Column) -> Column:
        return x if self.integer_valued else x * (1 - 1e-9) - 1e-12

    def batch(self, objs: list) -> object:
        """Objects in the form that `kernel` takes."""
        return encode_strings(objs) if self.kind == "string" else np.array(objs, float).reshape(len(objs), -1)

    def from_arrow(self, col) -> object:
        """The same from an Arrow column; vectors of one length are read without Python lists."""
        if self.kind == "string":
            return encode_strings(col.to_pylist())
        flat = col.flatten().to_numpy(zero_copy_only=False)
        return flat.astype(float, copy=False).reshape(len(col), -1) if len(col) else np.empty((0, 0))

    def take(self, batch, rows: np.ndarray):
        """Some rows of a batch."""
        return (batch[0][rows], batch[1][rows]) if isinstance(batch, tuple) else batch[rows]


def _unrolled(a: Column, b: Column, dim: int, each) -> list[Column]:
    return [each(F.get(a, F.lit(i)) - F.get(b, F.lit(i))) for i in range(dim)]


def _summed(each):
    def column(a: Column, b: Column, dim: int | None = None) -> Column:
        if dim and dim <= UNROLLED:
            parts = _unrolled(a, b, dim, each)
            total = parts[0]
            for p in parts[1:]:
                total = total + p
            return total
        return F.aggregate(F.zip_with(a, b, lambda x, y: each(x - y)), F.lit(0.0), lambda s, x: s + x)

    return column


def _rows_summed(each):
    """Row by row in the order of the components, as the plans and SQL add: NumPy's own sums of rows differ in the last bit, which decides pairs at the radius."""

    def rows(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        total = np.zeros(len(x))
        for part in np.ascontiguousarray(each(x - y).T):
            total += part
        return total

    return rows


def _crossed(each, root=lambda x: x, add=np.add):
    """All rows of a matrix with all of another, by the components in their order, and the root that makes distances of the sums. `each` may overwrite its differences."""

    def sums(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        total = None
        for a, b in zip(x.T, y.T):
            part = each(np.subtract.outer(a, b))
            total = part if total is None else add(total, part, out=total)
        return np.zeros((len(x), len(y))) if total is None else total

    return sums, root


def _power(p: float):
    def each(d: np.ndarray) -> np.ndarray:
        size = np.abs(d)
        if p != 3:
            return np.power(size, p, out=size)
        np.multiply(d, d, out=d)
        return np.multiply(size, d, out=size)

    return each


def l1() -> Metric:
    return Metric("l1", "vector", _summed(F.abs), lambda x, o: np.abs(x - o).sum(axis=1), lambda a, b: f"list_sum(list_transform(list_zip({a}, {b}), lambda t: abs(t[1] - t[2])))", rows=_rows_summed(np.abs), crossed=_crossed(lambda d: np.abs(d, out=d)))


def l2() -> Metric:
    square, squares = _summed(lambda d: d * d), _rows_summed(np.square)
    return Metric("l2", "vector", lambda a, b, dim=None: F.sqrt(square(a, b, dim)), lambda x, o: np.sqrt(((x - o) ** 2).sum(axis=1)), lambda a, b: f"list_distance({a}, {b})", rows=lambda x, y: np.sqrt(squares(x, y)), crossed=_crossed(lambda d: np.square(d, out=d), np.sqrt), products=True)


def lp(p: float) -> Metric:
    """General L_p, p >= 1."""
    if p < 1:
        raise ValueError("L_p is a metric for p >= 1 only")
    summed, root = _summed(lambda d: F.abs(d) * d * d if p == 3 else F.pow(F.abs(d), F.lit(float(p)))), lambda x: F.pow(x, F.lit(1.0 / p))
    crossed = _crossed(_power(p), lambda x: x ** (1 / p))
    return Metric(f"l{p:g}", "vector", lambda a, b, dim=None: root(summed(a, b, dim)), before_root=(summed, root), crossed=crossed, kernel=lambda x, o: (np.abs(x - o) ** p).sum(axis=1) ** (1 / p), sql=lambda a, b: f"pow(list_sum(list_transform(list_zip({a}, {b}), lambda t: pow(abs(t[1] - t[2]), {p}))), 1.0 / {p})")


def linf() -> Metric:
    def column(a: Column, b: Column, dim: int | None = None) -> Column:
        if dim and 1 < dim <= UNROLLED:
            return F.greatest(*_unrolled(a, b, dim, F.abs))
        return F.coalesce(F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y))), F.lit(0.0))

    return Metric("linf", "vector", column, lambda x, o: np.abs(x - o).max(axis=1, initial=0.0), lambda a, b: f"list_max(list_transform(list_zip({a}, {b}), lambda t: abs(t[1] - t[2])))", crossed=_crossed(lambda d: np.abs(d, out=d), add=np.maximum))


def encode_strings(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(code points, padded with -1; lengths)."""
    n = np.array([len(w) for w in words], np.int64)
    out = np.full((len(words), int(n.max(initial=0))), -1, np.int32)
    flat = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.int32)
    out[np.arange(out.shape[1])[None, :] < n[:, None]] = flat
    return out, n


SIZES = (6, 10, 16, 32, 1 << 30)  # words are handled by size, so that a long one doesn't widen all tables


def edit_kernel(many, one: str) -> np.ndarray:
    """Edit distances of many words to one: one row of the table for all words at once, a character of `one` at a time."""
    codes, n = many
    out = np.zeros(len(n))
    low = -1
    for high in SIZES:
        at = np.flatnonzero((n > low) & (n <= high))
        low = high
        if len(at):
            out[at] = _edit_rows(codes[at, : int(n[at].max())], n[at], one)
    return out


def _edit_rows(codes: np.ndarray, n: np.ndarray, one: str) -> np.ndarray:
    width = codes.shape[1]
    kind = np.int16 if width + len(one) < 30_000 else np.int32
    steps = np.arange(width + 1, dtype=kind)[:, None]
    codes = np.ascontiguousarray(codes.T)  # a row of the table for one place in all words is contiguous
    row = np.repeat(steps, len(n), axis=1)
    for i, c in enumerate(one):
        new = row + kind(1)
        np.minimum(new[1:], row[:-1] + (codes != ord(c)), out=new[1:])
        for j in range(1, width + 1):
            np.minimum(new[j], new[j - 1] + kind(1), out=new[j])
        row = new
    return row[n, np.arange(len(n))].astype(float)


WORD = 64  # code points of a query whose column of the table fits one machine word
LANES = 2048  # queries that are compared with a text at once
SHARED = 256  # code points of a common beginning whose state is kept for the next text


def edit_extremes(texts: list[str], queries: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(least, greatest) edit distance of each text to all queries; every pair is measured, equal texts and equal queries once.

    Queries of up to WORD code points keep a column of the table as two words of bits (it rises or falls by one), many queries
    a step; texts are taken in order, so what they have in common at the beginning is computed once. Longer queries take `edit_kernel`.
    """
    own, where = np.unique(np.array(texts, object), return_inverse=True)
    own, asked = own.tolist(), sorted(set(queries))
    least, most = np.full(len(own), np.iinfo(np.int64).max), np.full(len(own), -1, np.int64)
    short = [q for q in asked if len(q) <= WORD]
    for lo in range(0, len(short), LANES):
        _extremes_of_short(own, short[lo : lo + LANES], least, most)
    batch = encode_strings(own) if len(short) < len(asked) else None
    for q in asked:
        if len(q) > WORD:
            d = edit_kernel(batch, q).astype(np.int64)
            np.minimum(least, d, out=least)
            np.maximum(most, d, out=most)
    return least[where], most[where]


def _extremes_of_short(texts: list[str], queries: list[str], least: np.ndarray, most: np.ndarray) -> None:
    n, one = len(queries), np.uint64(1)
    within_ = np.array([(1 << len(q)) - 1 for q in queries], np.uint64)
    places: dict[str, list[int]] = {}
    for lane, q in enumerate(queries):
        for i, c in enumerate(q):
            places.setdefault(c, [0] * n)[lane] |= 1 << i
    equal, nowhere = {c: np.array(bits, np.uint64) for c, bits in places.items()}, np.zeros(n, np.uint64)
    common = [0]
    for a, b in zip(texts, texts[1:]):
        k, stop = 0, min(len(a), len(b), SHARED)
        while k < stop and a[k] == b[k]:
            k += 1
        common.append(k)
    kept = max(common)
    up, down = np.zeros((kept + 3, n), np.uint64), np.zeros((kept + 3, n), np.uint64)  # a state a depth, and two in turn beyond
    up[0] = ~np.uint64(0)
    xv, xh, ph, mh = (np.empty(n, np.uint64) for _ in range(4))
    for at, (text, start) in enumerate(zip(texts, common)):
        here = start
        for depth in range(start + 1, len(text) + 1):
            to = depth if depth <= kept else kept + 1 + depth % 2
            pv, mv, eq = up[here], down[here], equal.get(text[depth - 1], nowhere)
            np.bitwise_or(eq, mv, out=xv)
            np.bitwise_and(eq, pv, out=xh)
            np.add(xh, pv, out=xh)
            np.bitwise_xor(xh, pv, out=xh)
            np.bitwise_or(xh, eq, out=xh)
            np.bitwise_or(xh, pv, out=ph)
            np.invert(ph, out=ph)
            np.bitwise_or(ph, mv, out=ph)
            np.bitwise_and(pv, xh, out=mh)
            np.left_shift(ph, one, out=ph)
            np.bitwise_or(ph, one, out=ph)
            np.left_shift(mh, one, out=mh)
            np.bitwise_or(xv, ph, out=xh)
            np.invert(xh, out=xh)
            np.bitwise_or(mh, xh, out=up[to])
            np.bitwise_and(ph, xv, out=down[to])
            here = to
        d = np.bitwise_count(up[here] & within_).astype(np.int64) - np.bitwise_count(down[here] & within_)
        least[at], most[at] = min(least[at], len(text) + d.min()), max(most[at], len(text) + d.max())


def edit() -> Metric:
    return Metric("edit", "string", lambda a, b, dim=None: F.levenshtein(a, b).cast("double"), edit_kernel, lambda a, b: f"levenshtein({a}, {b})::double", True)


REGISTRY: dict[str, Callable[[], Metric]] = {"l1": l1, "l2": l2, "linf": linf, "edit": edit}


def register(name: str, column, kernel, kind: str = "vector", sql=None, integer_valued: bool = False) -> Metric:
    """A user's metric: `column` may be any expression, a pandas_udf included."""
    made = Metric(name, kind, lambda a, b, dim=None: column(a, b), kernel, sql or (lambda a, b: f"{name}({a}, {b})"), integer_valued)
    REGISTRY[name] = lambda: made
    return made


def metric(name: str) -> Metric:
    return REGISTRY[name]()


def pair_column(m: Metric, a: Column, b: Column, dim: int | None) -> Column:
    """d(a, b) where many pairs of long vectors are verified: there both list columns go to NumPy whole, in Arrow batches.

    Short vectors and strings stay on the JVM. Both ways give the same distances but for the last bits.
    """
    if m.kind == "string" or not dim or dim <= UNROLLED or m.rows is None:
        return m.column(a, b, dim)
    rows = m.rows

    def distances(x, y):
        import pyarrow as pa

        flat = lambda v: v.flatten().to_numpy(zero_copy_only=False).reshape(len(v), dim)
        return pa.array(rows(flat(x), flat(y)) if len(x) else [], pa.float64())

    import pyarrow as pa

    distances.__annotations__ = {"x": pa.Array, "y": pa.Array, "return": pa.Array}  # the kind of function is read off these
    # said to be nondeterministic so that a filter on the distance isn't pushed below, where it would be computed again
    return F.arrow_udf(distances, "double").asNondeterministic()(a, b)


def within(m: Metric, a: Column, b: Column, r: Column, dim: int | None) -> tuple[Column, Column]:
    """(distance or null, d(a, b) <= r). For edit distance the length difference and the threshold stop work early."""
    if m.name == "edit":
        cap = F.floor(r).cast("int")
        d = F.when(F.abs(F.length(a) - F.length(b)) <= r, F.call_function("levenshtein", a, b, F.greatest(cap, F.lit(0)))).cast("double")
        return d, (r >= 0) & d.isNotNull() & (d >= 0)
    d = pair_column(m, a, b, dim)
    return d, d <= r


def check_axioms(objects: DataFrame, m: Metric, n: int = 40, seed: int = 7, dim: int | None = None) -> DataFrame:
    """(axiom, tested, violated) over all triples of `n` hash-chosen objects."""
    from ..operators.sampling import hash_sample

    s = hash_sample(objects, n, seed).select("oid", "obj")
    a, b, c = (s.select(F.col("oid").alias(f"{x}i"), F.col("obj").alias(f"{x}o")) for x in "abc")
    d = lambda x, y: m.column(F.col(f"{x}o"), F.col(f"{y}o"), dim)
    pairs = a.crossJoin(b)  # n * n rows, n a parameter
    triples = pairs.crossJoin(c)
    count = lambda df, name, bad: df.agg(F.lit(name).alias("axiom"), F.count("*").alias("tested"), F.coalesce(F.sum(bad.cast("long")), F.lit(0)).alias("violated"))
    eps = 0.0 if m.integer_valued else 1e-9
    return (
        count(pairs, "symmetry", F.abs(d("a", "b") - d("b", "a")) > eps)
        .unionByName(count(pairs, "non_negativity", d("a", "b") < 0))
        .unionByName(count(pairs, "identity", (d("a", "b") <= eps) != (F.col("ao") == F.col("bo"))))
        .unionByName(count(triples, "triangle", d("a", "c") > d("a", "b") + d("b", "c") + eps))
    )
