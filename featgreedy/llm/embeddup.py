"""Near-duplicate vectors by randomised-rotation binary codes with stored correction factors.

Each unit vector ``o`` is rotated by a seeded random orthogonal matrix; its code is the signs of the rotated
components and its correction factor ``f`` is the inner product of ``o`` with its code's own unit vector.
For any unit vector ``q`` the ratio <code(o), q> / f estimates <o, q> without bias, and its error is within
``eps * sqrt((1 - f^2) / f^2) / sqrt(dim - 1)`` but for a chance that vanishes with ``eps``. A pair whose upper
bound is below the threshold is out; every other pair is computed again in double precision, so links are exact.

All pairs of a label are compared by their codes, so the bound alone decides. Equal vectors are first collapsed to
one. A label with more rows than ``block`` is cut into blocks, and each pair of blocks is a task of its own, so no
label is gathered whole; no pair is ever emitted, only counts of links and a spanning forest. A caller who can lose
pairs may name a ``recall``: then only pairs that meet in tables over bits of further rotations are compared.

Null, zero, or non-finite vectors and null labels link with nothing: ``n_links`` 0 and a component of their own.
Vectors of unequal lengths never link. Rows equal in ``vec_id``, label and embedding are one vector, which is
counted once and returned for each of its rows.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from featgreedy.llm.common import components, forget, ship, stored

THRESHOLD = 0.93


def rotation(dim: int, seed: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng([seed, dim]).standard_normal((dim, dim)))
    return q * np.sign(np.diag(r))


def codes(x: np.ndarray, seed: int = 7) -> tuple[np.ndarray, np.ndarray]:
    """Signs (+1/-1) of rotated unit vectors and correction factors."""
    y = x @ rotation(x.shape[1], seed)
    s = np.where(y >= 0, 1.0, -1.0)
    return s, (y * s).sum(1) / math.sqrt(x.shape[1])


def estimate(s: np.ndarray, f: np.ndarray, y: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray]:
    """Estimated inner products of coded rows with rotated unit vectors ``y``, and half widths of their bounds."""
    dim = s.shape[1]
    est = (s @ y.T) / math.sqrt(dim) / f[:, None]
    half = eps * np.sqrt(np.maximum(0.0, 1 - f * f)) / f / math.sqrt(max(dim - 1, 1))
    return est, half[:, None]


def plan_tables(count: int, threshold: float, recall: float = 0.998, bucket: int = 512) -> tuple[int, int]:
    """Bits and tables such that a pair on the threshold meets in some table with probability ``recall``."""
    bits = max(1, math.ceil(math.log2(max(count, 2) / bucket))) if count > bucket else 0
    if not bits:
        return 0, 1
    hit = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(1 - recall) / math.log(1 - hit)))


def _tables(bits: int, tables: int, seed: int):
    planes: dict[int, np.ndarray] = {}

    def add(batches):
        for pdf in batches:
            out = np.zeros((len(pdf), tables), np.int64)
            dims = pdf["embedding"].map(len).to_numpy()
            for dim in np.unique(dims):
                if bits:
                    if dim not in planes:
                        planes[dim] = np.random.default_rng([seed, int(dim)]).standard_normal((int(dim), tables * bits))
                    rows = np.flatnonzero(dims == dim)
                    x = np.stack(pdf["embedding"].to_numpy()[rows]).astype(np.float64)
                    out[rows] = ((x @ planes[dim] >= 0).reshape(len(rows), tables, bits) << np.arange(bits)).sum(2)
            pdf["keys"] = [k.astype(np.int32) for k in out]
            yield pdf

    return add


def _link(threshold: float, eps: float, side: int = 1024):
    def run(key, pdf):
        t, same = int(key[2]), int(key[4]) == int(key[5])
        none = pd.DataFrame({"rep": pd.Series(dtype="int64"), "n": pd.Series(dtype="int64"), "root": pd.Series(dtype="int64")})
        if len(pdf) < 2:
            return none
        pdf = pdf.sort_values("rep")
        x = np.stack(pdf["embedding"].to_numpy()).astype(np.float64)
        x /= np.abs(x).max(1, keepdims=True)
        x /= np.sqrt((x * x).sum(1))[:, None]
        keys = np.stack(pdf["keys"].to_numpy())[:, :t]
        rep, cnt, block = pdf["rep"].to_numpy(), pdf["cnt"].to_numpy(), pdf["own"].to_numpy()
        s, f = codes(x)
        y = x @ rotation(x.shape[1], 7)
        n, root = np.zeros(len(x), np.int64), np.arange(len(x))

        def find(i: int) -> int:
            while root[i] != i:
                root[i] = root[root[i]]
                i = root[i]
            return i

        for i in range(0, len(x), side):
            for j in range(i, len(x), side):
                est, half = estimate(s[i : i + side], f[i : i + side], y[j : j + side], eps)
                a, b = np.nonzero(est + half >= threshold)
                a, b = a + i, b + j
                keep = a < b
                if not same:
                    keep &= block[a] != block[b]
                a, b = a[keep], b[keep]
                for lo in range(0, len(a), 200_000):
                    p, q = a[lo : lo + 200_000], b[lo : lo + 200_000]
                    ok = (x[p] * x[q]).sum(1) >= threshold
                    if t:
                        ok &= ~(keys[p] == keys[q]).any(1)  # counted in an earlier table
                    p, q = p[ok], q[ok]
                    n += np.bincount(p, cnt[q], len(x)).astype(np.int64) + np.bincount(q, cnt[p], len(x)).astype(np.int64)
                    if len(p):
                        first = np.unique(q, return_index=True)[1]
                        rest = np.setdiff1d(np.arange(len(q)), first, assume_unique=True)
                        for k in (*first, *rest):
                            u, v = find(p[k]), find(q[k])
                            if u != v:
                                root[max(u, v)] = min(u, v)
        hit = np.flatnonzero(n)
        return pd.DataFrame({"rep": rep[hit], "n": n[hit], "root": rep[[find(i) for i in hit]]}) if len(hit) else none

    return run


def near_vectors(vectors: DataFrame, threshold: float = THRESHOLD, eps: float = 4.5, block: int = 4096, recall: float | None = None) -> DataFrame:
    """``vec_id, label, embedding`` -> ``vec_id, n_links, component_id, kept``; with ``recall``, pairs come from tables."""
    fine = F.col("label").isNotNull() & F.col("vec_id").isNotNull() & F.coalesce(
        F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v.cast("double")) < float("inf"))) & F.exists("embedding", lambda v: v != 0), F.lit(False)
    )
    rows = stored(vectors.select("vec_id", "label", "embedding", fine.alias("fine")), "vectors")
    good = rows.filter("fine")
    held = good.select("label", "embedding", "vec_id").distinct()  # partial aggregates: repeated rows end before the shuffle
    reps = stored(held.groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("cnt")), "reps")
    bits, tables = 0, 1
    if recall is not None:
        most = reps.groupBy("label").count().agg(F.max("count")).first()[0] or 0
        bits, tables = plan_tables(most, threshold, recall)
    keyed = reps.mapInPandas(_tables(bits, tables, 11), "label int, embedding array<float>, rep long, cnt long, keys array<int>")
    keyed = stored(keyed, "keyed")
    each = keyed.select("*", F.posexplode("keys").alias("t", "key"))
    sizes = each.groupBy("label", "t", "key").agg(F.count("*").alias("m")).filter("m > 1")
    each = each.join(sizes, ["label", "t", "key"]).withColumn("nb", F.ceil(F.col("m") / block).cast("int"))
    each = each.withColumn("own", F.pmod(F.xxhash64("rep"), F.col("nb")).cast("int"))
    mates = F.transform(F.sequence(F.lit(0), F.col("nb") - 1), lambda o: F.struct(F.least(F.col("own"), o).alias("i"), F.greatest(F.col("own"), o).alias("j")))
    tasks = each.select("label", F.size("embedding").alias("dim"), "t", "key", "rep", "cnt", "embedding", "keys", "own", F.explode(mates).alias("ij"))
    tasks = tasks.select("*", "ij.i", "ij.j").drop("ij")
    linked = tasks.groupBy("label", "dim", "t", "key", "i", "j").applyInPandas(_link(threshold, eps), "rep long, n long, root long")
    linked = stored(linked, "links")
    forget(keyed)
    n = linked.groupBy("rep").agg(F.sum("n").alias("n"))
    comp = components(linked.select("rep", "root"), "rep", "root")
    reps_out = reps.join(n, "rep", "left").join(comp.withColumnRenamed("node", "rep"), "rep", "left")
    reps_out = reps_out.select("label", "embedding", (F.coalesce("n", F.lit(0)) + F.col("cnt") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    out = good.join(reps_out, ["label", "embedding"]).select("vec_id", "n_links", "component_id")
    out = out.union(rows.filter("NOT fine").select("vec_id", F.lit(0).cast("long").alias("n_links"), (F.col("vec_id") + F.lit(0)).alias("component_id")))
    return out.withColumn("kept", F.col("vec_id") == F.col("component_id"))


def contract(vectors: DataFrame) -> DataFrame:
    return near_vectors(vectors)


ORACLE = """
WITH RECURSIVE v AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
u AS (SELECT vec_id, label, list_transform(e, lambda x: x / sqrt(list_sum(list_transform(e, lambda z: z * z)))) AS e FROM v),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.label = b.label AND a.vec_id <> b.vec_id
      WHERE list_dot_product(a.e, b.e) >= 0.93),
r(vec_id, c) AS (SELECT vec_id, vec_id FROM u UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.vec_id),
c AS (SELECT vec_id, min(c) AS component_id FROM r GROUP BY vec_id),
n AS (SELECT a AS vec_id, count(*) AS n FROM l GROUP BY a)
SELECT u.vec_id, coalesce(n.n, 0)::BIGINT AS n_links, c.component_id, u.vec_id = c.component_id AS kept
FROM u JOIN c USING (vec_id) LEFT JOIN n USING (vec_id)
"""

ship(__name__)
