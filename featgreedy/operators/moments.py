"""Second moments of blocks and response: what the greedy fits read of the data.

Two providers give the loop the same answers. :class:`GramMoments` holds all inner products on the driver after one
tree-shaped aggregate; it is for column sets within ``GRAM_BYTES``. :class:`StateMoments` leaves one matrix per block
in Spark, reads the data once per distinct winner, and brings one row per step to the driver.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from featgreedy.operators.kernel import top_scores, top_triple
from featgreedy.session import BROADCAST_BYTES, forget, ship, stored

#: Bytes of inner products that the driver may hold.
GRAM_BYTES = 512_000_000


def matrix(x, n: int, q: int) -> np.ndarray:
    """A block's payload as an ``n`` by ``q`` matrix."""
    return np.asarray(x, np.float64).reshape(q, n).T


def arrays(column) -> list[np.ndarray]:
    """Rows of an Arrow list column as numpy views."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = column.flatten().to_numpy(zero_copy_only=False)
    at = np.concatenate([[0], np.cumsum(column.value_lengths().to_numpy(zero_copy_only=False))]).astype(int)
    return [flat[i:j] for i, j in zip(at, at[1:], strict=False)]


class Centre:
    """Column means of blocks and response, to centre inner products without rewriting data."""

    def __init__(self, x: dict[int, np.ndarray], y: np.ndarray):
        self.x, self.y = x, y


class GramMoments:
    """All inner products of some blocks: ``g`` (Q by Q), ``c`` (Q by d), ``yy``, with their row count ``n``."""

    def __init__(self, ids, widths, g, c, yy, n, sums=None, y_sum=None):
        self.ids, self.widths, self.g, self.c0, self.yy, self.n = list(map(int, ids)), list(map(int, widths)), g, c, float(yy), int(n)
        ends = np.cumsum(self.widths)
        self.range = {j: (int(e - w), int(e)) for j, w, e in zip(self.ids, self.widths, ends, strict=True)}
        self.d = c.shape[1]
        self.sums, self.y_sum = sums, y_sum
        self.reset()

    def reset(self) -> None:
        self.c = self.c0.copy()
        self.passes = 1

    def centred(self) -> GramMoments:
        """The same moments about the means."""
        m, my = self.sums / self.n, self.y_sum / self.n
        out = GramMoments(self.ids, self.widths, self.g - self.n * np.outer(m, m), self.c0 - self.n * np.outer(m, my), self.yy - self.n * my @ my, self.n)
        out.means, out.y_mean = m, my
        return out

    def only(self, ids) -> GramMoments:
        ids = sorted(ids)
        at = np.concatenate([np.arange(*self.range[j]) for j in ids]) if len(ids) else np.zeros(0, int)
        return GramMoments(ids, [self.range[j][1] - self.range[j][0] for j in ids], self.g[np.ix_(at, at)], self.c0[at], self.yy, self.n)

    def __add__(self, other: GramMoments) -> GramMoments:
        return GramMoments(self.ids, self.widths, self.g + other.g, self.c0 + other.c0, self.yy + other.yy, self.n + other.n, self.sums + other.sums, self.y_sum + other.y_sum)

    def block(self, a: np.ndarray, j: int) -> np.ndarray:
        i, k = self.range[j]
        return a[i:k]

    def gram(self, j: int) -> np.ndarray:
        i, k = self.range[j]
        return self.g[i:k, i:k]

    def best(self):
        """Winner of the present residual: block, score, pair; ties within 1e-12 go to the smaller block."""
        if len(set(self.widths)) == 1 and self.ids:
            s = top_scores(self.c.reshape(len(self.ids), self.widths[0], self.d))
        else:
            s = np.array([top_triple(self.block(self.c, j))[0] for j in self.ids])
        k = int(np.flatnonzero(s >= s.max() * (1 - 1e-12))[0])
        j = self.ids[k]
        return j, *top_triple(self.block(self.c, j))

    def fit_norm(self, j: int, u: np.ndarray) -> float:
        """Squared length of ``X_j u``."""
        return float(u @ self.gram(j) @ u)

    def with_response(self, j: int, u: np.ndarray, v: np.ndarray) -> float:
        return float(u @ self.block(self.c0, j) @ v)

    def advance(self, j: int, u: np.ndarray, v: np.ndarray, lam: float, radius: float) -> None:
        i, k = self.range[j]
        self.c *= 1 - lam
        self.c += lam * (self.c0 - radius * np.outer(self.g[:, i:k] @ u, v))


class ArrayMoments:
    """The same answers from arrays, one pass over the columns a step: for local fits whose inner products are too many."""

    def __init__(self, x: np.ndarray, y: np.ndarray, width: int, rows=None):
        """``rows``: of these rows alone; the others weigh zero, so no copy of the columns is made."""
        self.rows = slice(None) if rows is None else rows
        self.weight = np.zeros(len(y))
        self.weight[self.rows] = 1.0
        self.x, self.y, self.width = x, y * self.weight[:, None], width
        self.n, self.d = int(self.weight.sum()), y.shape[1]
        p = x.shape[1] // width
        self.ids, self.widths = list(range(p)), [width] * p
        self.range = {j: (j * width, (j + 1) * width) for j in self.ids}
        self.c0, self.yy = x.T @ self.y, float((self.y * self.y).sum())
        self.reset()

    def reset(self) -> None:
        self.c, self.passes = self.c0.copy(), 1

    def block(self, a: np.ndarray, j: int) -> np.ndarray:
        return a[slice(*self.range[j])]

    best = GramMoments.best

    def only(self, ids) -> GramMoments:
        ids = sorted(ids)
        x = np.hstack([self.x[:, slice(*self.range[j])] for j in ids])[self.rows] if ids else np.zeros((self.n, 0))
        return GramMoments(ids, [self.width] * len(ids), x.T @ x, x.T @ self.y[self.rows], self.yy, self.n)

    def fit_norm(self, j: int, u: np.ndarray) -> float:
        z = self.weight * (self.x[:, slice(*self.range[j])] @ u)
        return float(z @ z)

    def with_response(self, j: int, u: np.ndarray, v: np.ndarray) -> float:
        return float(u @ self.block(self.c0, j) @ v)

    def advance(self, j: int, u: np.ndarray, v: np.ndarray, lam: float, radius: float) -> None:
        w = self.x.T @ (self.weight * (self.x[:, slice(*self.range[j])] @ u))
        self.c *= 1 - lam
        self.c += lam * (self.c0 - radius * np.outer(w, v))


def _segment_moments(ids):
    def run(key, left, right):
        h = key[0].as_py()
        js = left.column("j").to_pylist()
        order = [js.index(j) for j in sorted(js)] if ids is None else [js.index(j) for j in ids if j in js]
        n, d = right.column("n_h")[0].as_py(), right.column("d")[0].as_py()
        pay, qs = arrays(left.column("x")), left.column("q").to_pylist()
        x = np.hstack([matrix(pay[k], n, qs[k]) for k in order])
        y = arrays(right.column("y"))[0].reshape(n, d)
        full = np.hstack([np.ones((n, 1)), x, y])
        out = full.T @ full
        return pa.table({"h": [h], "part": [h % 16], "m": pa.array([out.ravel()], pa.list_(pa.float64()))}).cast(pa.schema([("h", pa.int32()), ("part", pa.int32()), ("m", pa.list_(pa.float64()))]))

    return run


def _sum(key, table):
    total = None
    for a in arrays(table.column("m")):
        total = a.copy() if total is None else total + a
    return pa.table({"m": pa.array([total], pa.list_(pa.float64()))})


def read_moments(m, js, qs) -> GramMoments:
    """From the inner products of a column of ones, the blocks and the response."""
    k = 1 + sum(qs)
    m = np.asarray(m)
    m = m.reshape(int(round(len(m) ** 0.5)), -1)
    return GramMoments(js, qs, m[1:k, 1:k], m[1:k, k:], np.trace(m[k:, k:]), round(m[0, 0]), m[0, 1:k], m[0, k:])


def summed(rows: DataFrame, js, qs) -> GramMoments:
    """Sum of the matrices ``part, m``, by part first and then on the driver."""
    total = None
    for r in rows.groupBy("part").applyInArrow(_sum, "m array<double>").toLocalIterator():
        m = np.asarray(r["m"])
        total = m if total is None else total + m
    return read_moments(total, js, qs)


def gram_moments(blocks: DataFrame, segments: DataFrame, ids=None, by_segment: bool = False):
    """Moments of blocks ``ids`` (all if None): one pass, sums in two levels, one matrix on the driver.

    ``by_segment``: a dict of moments per row segment instead of their sum.
    """
    ids = sorted(ids) if ids is not None else None
    some = blocks.filter(F.col("j").isin(list(map(int, ids)))) if ids is not None else blocks
    widths = sorted((r["j"], r["q"]) for r in some.select("j", "q").distinct().collect())
    js, qs = [j for j, _ in widths], [q for _, q in widths]
    d = segments.select("d").first()["d"]
    if (sum(qs) + d + 1) ** 2 * 8 > GRAM_BYTES:
        raise MemoryError("too many columns for inner products on the driver; use StateMoments")
    rows = some.groupBy("h").cogroup(segments.groupBy("h")).applyInArrow(_segment_moments(js), "h int, part int, m array<double>")

    if by_segment:
        return {r["h"]: read_moments(r["m"], js, qs) for r in rows.select("h", "m").toLocalIterator()}
    return summed(rows, js, qs)


def segment_products(blocks: DataFrame, segments: DataFrame) -> DataFrame:
    """``h, m``: every row segment's ``X'X`` beside its ``X'y``, as doubles row by row; scalar response."""

    def run(key, left, right):
        js, qs, n = left.column("j").to_pylist(), left.column("q").to_pylist(), right.column("n_h")[0].as_py()
        pay = arrays(left.column("x"))
        x = np.hstack([matrix(pay[k], n, qs[k]) for k in sorted(range(len(js)), key=js.__getitem__)])
        m = x.T @ np.hstack([x, arrays(right.column("y"))[0].reshape(n, 1)])
        return pa.table({"h": pa.array([key[0].as_py()], pa.int32()), "m": pa.array([m.tobytes()], pa.binary())})

    return blocks.groupBy("h").cogroup(segments.groupBy("h")).applyInArrow(run, "h int, m binary")


#: Bytes of products that a task sums up before it hands them on.
PARTIAL_BYTES = 64_000_000


def _cross(batches):
    """Products of blocks with their segments' matrices, summed over the task's segments of each block."""
    held: dict[int, list] = {}
    size = 0

    def flush():
        cols = [pa.array([f(j, h) for j, h in held.items()], kind) for f, kind in ((lambda j, h: j, pa.int32()), (lambda j, h: h[0], pa.int32()), (lambda j, h: h[1], pa.int32()), (lambda j, h: h[2].ravel(), pa.list_(pa.float64())))]
        return pa.RecordBatch.from_arrays(cols, ["j", "q", "k", "c"])

    for batch in batches:
        names = ("j", "n_h", "q", "k")
        for j, n, q, k, x, a in zip(*[batch.column(c).to_pylist() for c in names], arrays(batch.column("x")), arrays(batch.column("a")), strict=True):
            got = matrix(x, n, q).T @ a.reshape(n, k)
            if j in held:
                held[j][2] += got
            else:
                held[j] = [q, k, got]
                size += got.nbytes
        if size > PARTIAL_BYTES:
            yield flush()
            held, size = {}, 0
    yield flush()


def _sum_by_block(key, table):
    total = sum(arrays(table.column("c")))
    return pa.table({"j": table.column("j")[:1], "q": table.column("q")[:1], "k": table.column("k")[:1], "c": pa.array([total], pa.list_(pa.float64()))})


def cross(blocks: DataFrame, vectors: DataFrame) -> DataFrame:
    """``j, q, k, c``: every block's product with per-segment matrices ``h, k, a`` (n_h by k, row-major).

    The matrices are broadcast while their bytes, counted first, are within the bound, else joined on ``h``.
    """
    size = vectors.agg(F.sum(F.size("a")).alias("s")).first()["s"] or 0
    side = F.broadcast(vectors) if size * 8 <= BROADCAST_BYTES else vectors
    pairs = blocks.join(side, "h").select("j", "q", "n_h", "k", "x", "a")
    parts = pairs.mapInArrow(_cross, "j int, q int, k int, c array<double>")
    return parts.groupBy("j").applyInArrow(_sum_by_block, "j int, q int, k int, c array<double>")


def _score(batches):
    for batch in batches:
        q, d, c = batch.column("q").to_pylist(), batch.column("k").to_pylist(), arrays(batch.column("c"))
        got = [top_triple(m.reshape(a, b)) for m, a, b in zip(c, q, d, strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column("j"), pa.array([g[0] for g in got]), pa.array([g[1] for g in got], pa.list_(pa.float64())), pa.array([g[2] for g in got], pa.list_(pa.float64()))], ["j", "s1", "u", "v"])


def score_blocks(state: DataFrame) -> DataFrame:
    """``j, s1, u, v``: the best atom of every block from its matrix ``c``."""
    return state.select("j", "q", "k", "c").mapInArrow(_score, "j int, s1 double, u array<double>, v array<double>")


def pick_winner(scores: DataFrame):
    """The row of the largest score, the smaller block on ties; partial maxima, one row to the driver."""
    return scores.agg(F.max(F.struct("s1", (-F.col("j")).alias("minus"), "j", "u", "v")).alias("w")).select("w.*").first()


def _columns(ids):
    """Blocks of one segment, side by side, row-major."""

    def run(key, table):
        js, qs, n = table.column("j").to_pylist(), table.column("q").to_pylist(), table.column("n_h")[0].as_py()
        pay = arrays(table.column("x"))
        m = np.hstack([matrix(pay[js.index(j)], n, qs[js.index(j)]) for j in ids])
        return pa.table({"h": pa.array([key[0].as_py()], pa.int32()), "k": pa.array([m.shape[1]], pa.int32()), "a": pa.array([m.ravel()], pa.list_(pa.float64()))})

    return run


class StateMoments:
    """Inner products kept in Spark, one row a block: ``X_j' Y`` and ``X_j' X_w`` for every winner ``w`` so far.

    The residual's product is ``X_j' Y`` less the winners' products times their present coefficients, which are small
    and travel with the task: a step is one pass over these rows and one row to the driver, and writes nothing. The
    data are read once more, and the rows written again, only when a block wins for the first time. ``lookahead``: that
    pass also fetches the products with the next best blocks not met yet, so fewer passes serve the same path.
    """

    def __init__(self, blocks: DataFrame, segments: DataFrame, lookahead: int = 1):
        self.blocks, self.segments, self.lookahead = blocks, segments, lookahead
        self.d = segments.select("d").first()["d"]
        first = segments.agg(F.sum("n_h").alias("n"), F.sum(F.aggregate("y", F.lit(0.0), lambda s, x: s + x * x)).alias("yy")).first()
        self.n, self.yy = int(first["n"]), float(first["yy"])
        start = cross(blocks, segments.select("h", F.col("d").alias("k"), F.col("y").alias("a")))
        self.table = stored(start.select("j", "q", "k", F.col("c").alias("c0"), F.array().cast("array<double>").alias("xx")), "state")
        self.met: dict[int, tuple[int, int]] = {}  # columns of ``xx`` that belong to a winner
        self.own: dict[int, np.ndarray] = {}
        self.start: dict[int, np.ndarray] = {}
        self.coef: dict[int, np.ndarray] = {}
        self.passes = 1
        self.next: list[int] = []

    def reset(self) -> None:
        self.coef = {}

    def _held(self) -> np.ndarray:
        """The winners' coefficients, one below the other in the order of ``xx``."""
        out = np.zeros((sum(b - a for a, b in self.met.values()), self.d))
        for j, b in self.coef.items():
            out[slice(*self.met[j])] = b
        return out

    def residual_rows(self, only=None) -> DataFrame:
        """``j, q, k, c``: every block's product with the present residual."""
        held = self._held()

        def run(batches):
            for batch in batches:
                out = []
                for q, c0, xx in zip(batch.column("q").to_pylist(), arrays(batch.column("c0")), arrays(batch.column("xx")), strict=True):
                    out.append(c0 - (xx.reshape(q, -1) @ held).ravel() if len(held) else c0)
                yield pa.RecordBatch.from_arrays([batch.column("j"), batch.column("q"), batch.column("k"), pa.array(out, pa.list_(pa.float64()))], ["j", "q", "k", "c"])

        rows = self.table if only is None else self.table.filter(F.col("j").isin([int(j) for j in only]))
        return rows.mapInArrow(run, "j int, q int, k int, c array<double>")

    def best(self):
        scores = score_blocks(self.residual_rows())
        if self.lookahead > 1:
            top = scores.orderBy(F.desc("s1"), "j").limit(self.lookahead).collect()  # a bounded few
            self.next = [r["j"] for r in top]
            w = top[0]
        else:
            w = pick_winner(scores)
        return w["j"], w["s1"], np.array(w["u"]), np.array(w["v"])

    def meet(self, *ids: int) -> None:
        """Fetch the products of all blocks with some blocks not met yet, in one pass."""
        ids = [i for i in dict.fromkeys(int(i) for i in ids) if i not in self.met]
        if not ids:
            return
        some = self.blocks.filter(F.col("j").isin(ids)).select("j", "h", "n_h", "q", "x")
        rows = some.groupBy("h").applyInArrow(_columns(ids), "h int, k int, a array<double>")
        new = cross(self.blocks, rows).select("j", F.col("k").alias("width"), F.col("c").alias("new"))

        def widen(batches):
            for batch in batches:
                out = []
                for q, a, b in zip(batch.column("q").to_pylist(), arrays(batch.column("xx")), arrays(batch.column("new")), strict=True):
                    out.append(np.hstack([a.reshape(q, -1), b.reshape(q, -1)]).ravel())
                yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("j", "q", "k", "c0")] + [pa.array(out, pa.list_(pa.float64()))], ["j", "q", "k", "c0", "xx"])

        old = self.table
        both = old.join(new, "j").select("j", "q", "k", "c0", "xx", "new")
        self.table = stored(both.mapInArrow(widen, "j int, q int, k int, c0 array<double>, xx array<double>"), "state")
        forget(old)
        at = sum(b - a for a, b in self.met.values())
        mine = {r["j"]: r for r in self.table.filter(F.col("j").isin(ids)).collect()}  # the new winners' rows
        for i in ids:
            q = mine[i]["q"]
            self.met[i] = (at, at + q)
            self.own[i] = np.array(mine[i]["xx"]).reshape(q, -1)[:, at : at + q]
            self.start[i] = np.array(mine[i]["c0"]).reshape(q, self.d)
            at += q
        self.passes += 1

    def _meet(self, j: int) -> None:
        if j not in self.met:
            self.meet(j, *self.next)

    def fit_norm(self, j, u):
        self._meet(j)
        return float(u @ self.own[j] @ u)

    def with_response(self, j, u, v):
        self._meet(j)
        return float(u @ self.start[j] @ v)

    def advance(self, j, u, v, lam, radius):
        self._meet(j)
        self.coef = {i: (1 - lam) * b for i, b in self.coef.items()}
        self.coef[j] = self.coef.get(j, 0) + lam * radius * np.outer(u, v)


ship(__name__)
