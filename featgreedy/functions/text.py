"""Tokens, term weights and latent semantic scores of a corpus."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from featgreedy.session import BROADCAST_BYTES, forget, ship, stored

#: Words that the token filter drops.
STOP = ("and", "are", "das", "den", "der", "des", "die", "est", "for", "from", "les", "los", "not", "que", "sur", "the", "und", "was", "with")


def tokenise(docs: DataFrame, min_tokens: int = 50, text: str = "text", id_: str = "doc_id", least: int = 3) -> DataFrame:
    """``doc, token, tf``: lower-cased runs of letters of at least ``least``, no stop words, documents of at least
    ``min_tokens`` white-space words."""
    words = F.split(F.trim(F.regexp_replace(F.lower(F.col(text)), r"[^\p{L}]+", " ")), " ")
    long_enough = docs.filter(F.size(F.split(F.trim(F.col(text)), r"\s+")) >= min_tokens)
    e = long_enough.select(F.col(id_).alias("doc"), F.explode(words).alias("token"))
    e = e.filter((F.length("token") >= least) & ~F.col("token").isin(*STOP))
    return e.groupBy("doc", "token").agg(F.count("*").alias("tf"))


def idf(tokens: DataFrame) -> DataFrame:
    """``token, df, idf`` with ``idf = ln(D / df)``; D counts documents with any token."""
    total = tokens.select("doc").distinct().agg(F.count("*").alias("D"))
    df = tokens.groupBy("token").agg(F.count("*").alias("df"))
    return df.join(F.broadcast(total)).select("token", "df", F.ln(F.col("D") / F.col("df")).alias("idf"))


def tfidf(tokens: DataFrame, table: DataFrame) -> DataFrame:
    """``doc, token, w``; tokens absent from the table are dropped. The table's join follows its size."""
    return tokens.join(table.select("token", "idf"), "token").select("doc", "token", (F.col("tf") * F.col("idf")).alias("w"))


#: The tokens of most documents, whose vectors travel to the tasks; the others' meet their weights by joins.
HEAD = 1 << 16


def counted(docs: DataFrame, min_tokens: int = 50, text: str = "text", id_: str = "doc_id", least: int = 3) -> DataFrame:
    """``doc, token, tf`` as arrays, one row a document: what :func:`tokenise` gives, counted inside the row where ids are unique."""
    once = docs.groupBy(id_).agg(F.count("*").alias("n")).agg(F.max("n")).first()[0]
    if (once or 0) > 1:
        g = tokenise(docs, min_tokens, text, id_, least).groupBy("doc").agg(F.collect_list(F.struct("token", F.col("tf").cast("double").alias("tf"))).alias("p"))
        return g.select("doc", F.col("p.token").alias("token"), F.col("p.tf").alias("tf"))
    words = F.split(F.trim(F.regexp_replace(F.lower(F.col(text)), r"[^\p{L}]+", " ")), " ")
    long_enough = docs.filter(F.size(F.split(F.trim(F.col(text)), r"\s+")) >= min_tokens)
    e = long_enough.select(F.col(id_).alias("doc"), F.sort_array(F.filter(words, lambda w: (F.length(w) >= least) & ~w.isin(*STOP))).alias("s")).filter(F.size("s") > 0)

    def run(batches):
        import pyarrow.compute as pc

        for batch in batches:
            s = batch.column("s")
            flat, size = s.flatten(), s.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            ends = np.cumsum(size)
            new = np.ones(len(flat), bool)
            new[1:] = pc.not_equal(flat[1:], flat[:-1]).to_numpy(zero_copy_only=False)
            new[(ends - size)[: len(size)]] = True
            at = np.flatnonzero(new)
            tf = np.diff(np.append(at, len(flat))).astype(float)
            cuts = pa.array(np.append(0, np.searchsorted(at, ends)), pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column("doc"), pa.ListArray.from_arrays(cuts, flat.take(pa.array(at))), pa.ListArray.from_arrays(cuts, pa.array(tf))], ["doc", "token", "tf"])

    return e.mapInArrow(run, f"doc {e.schema['doc'].dataType.simpleString()}, token array<string>, tf array<double>")


class Weights:
    """Weights of a corpus, read once: ``rows`` (``doc, i, w``: the head's tokens by number, one row a document), ``tail``
    (``doc, token, w``: the others) and ``table`` (``token, idf``)."""

    def __init__(self, by_doc: DataFrame, weigh: bool = True, head: int | None = None):
        spark = by_doc.sparkSession
        kind = by_doc.schema["doc"].dataType.simpleString()
        held = stored(by_doc, "counted")
        df = held.select(F.explode("token").alias("token")).groupBy("token").agg(F.count("*").alias("df"))
        total = held.count()
        weight = F.ln(F.lit(total) / F.col("df")) if weigh else F.lit(1.0)
        self.table = stored(df.select("token", "df", weight.alias("idf")), "idf")
        self.docs = total
        got = self.table.orderBy(F.desc("df"), "token").limit(head or HEAD).toArrow()  # a bounded few
        self.head = got.column("token").combine_chunks()
        words, scale = spark.sparkContext.broadcast(self.head), spark.sparkContext.broadcast(got.column("idf").to_numpy())

        def run(batches):
            import pyarrow.compute as pc

            for batch in batches:
                size = batch.column("token").value_lengths().to_numpy(zero_copy_only=False)
                flat, tf = batch.column("token").flatten(), batch.column("tf").flatten().to_numpy(zero_copy_only=False)
                i = pc.fill_null(pc.index_in(flat, value_set=words.value), -1).to_numpy(zero_copy_only=False)
                hit, row = i >= 0, np.repeat(np.arange(len(size)), size)
                cut = lambda m: pa.array(np.append(0, np.cumsum(np.bincount(row[m], minlength=len(size)))), pa.int32())
                a, b = cut(hit), cut(~hit)
                w = tf[hit] * scale.value[i[hit]]
                rest = pa.array(np.flatnonzero(~hit))
                yield pa.RecordBatch.from_arrays([batch.column("doc"), pa.ListArray.from_arrays(a, pa.array(i[hit], pa.int32())), pa.ListArray.from_arrays(a, pa.array(w)), pa.ListArray.from_arrays(b, flat.take(rest)), pa.ListArray.from_arrays(b, pa.array(tf[~hit]))], ["doc", "i", "w", "token", "tf"])

        both = stored(held.mapInArrow(run, f"doc {kind}, i array<int>, w array<double>, token array<string>, tf array<double>"), "weights")
        self.rows = both.select("doc", "i", "w")
        tail = both.select("doc", F.explode(F.arrays_zip("token", "tf")).alias("p")).select("doc", "p.token", "p.tf")
        self.tail = stored(tail.join(self.table.select("token", "idf"), "token").select("doc", "token", (F.col("tf") * F.col("idf")).alias("w")), "tail")
        self.kind = kind
        self.kept = [both, self.tail]
        forget(held)

    def to_tokens(self, side: DataFrame, r: int) -> DataFrame:
        """``token, x``: sums over documents of weight times ``side``'s array."""
        n, words = len(self.head), self.head
        side = F.broadcast(side) if self.docs * (r + 4) * 8 <= BROADCAST_BYTES else side

        def run(batches):
            total = np.zeros((r, n))
            for batch in batches:
                size = batch.column("i").value_lengths().to_numpy(zero_copy_only=False)
                i, w = batch.column("i").flatten().to_numpy(zero_copy_only=False), batch.column("w").flatten().to_numpy(zero_copy_only=False)
                x = batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(-1, r)
                row = np.repeat(np.arange(len(size)), size)
                for k in range(r):
                    total[k] += np.bincount(i, w * x[row, k], n)
            some = np.flatnonzero(total.any(0))
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), *[pa.array(total[k, some]) for k in range(r)]], ["i", *[f"x{k}" for k in range(r)]])

        spark = side.sparkSession
        few = self.rows.coalesce(max(1, 2 * spark.sparkContext.defaultParallelism))  # a task hands on the head once
        parts = few.join(side, "doc").select("i", "w", "x").mapInArrow(run, "i int, " + ", ".join(f"x{k} double" for k in range(r)))
        top = parts.groupBy("i").agg(*[F.sum(f"x{k}").alias(f"x{k}") for k in range(r)])
        names = spark.createDataFrame(pa.table({"i": pa.array(np.arange(n), pa.int32()), "token": words}))
        top = top.join(F.broadcast(names), "i").select("token", F.array(*[f"x{k}" for k in range(r)]).alias("x"))
        return top.unionByName(_times(self.tail, side, "doc", "token", r))

    def to_docs(self, left: DataFrame, r: int) -> DataFrame:
        """``doc, x``: sums over tokens of weight times ``left``'s array ``u``."""
        n = len(self.head)
        names = left.sparkSession.createDataFrame(pa.table({"i": pa.array(np.arange(n), pa.int32()), "token": self.head}))
        got = left.join(F.broadcast(names), "token").select("i", "u").toArrow()
        u = np.zeros((n, r))
        if got.num_rows:
            u[got.column("i").to_numpy()] = np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in got.column("u").chunks]).reshape(-1, r)
        shared = left.sparkSession.sparkContext.broadcast(u)

        def run(batches):
            for batch in batches:
                size = batch.column("i").value_lengths().to_numpy(zero_copy_only=False)
                i, w = batch.column("i").flatten().to_numpy(zero_copy_only=False), batch.column("w").flatten().to_numpy(zero_copy_only=False)
                row = np.repeat(np.arange(len(size)), size)
                out = np.stack([np.bincount(row, w * shared.value[i, k], len(size)) for k in range(r)], 1)
                yield pa.RecordBatch.from_arrays([batch.column("doc"), pa.array(list(out), pa.list_(pa.float64()))], ["doc", "x"])

        top = self.rows.mapInArrow(run, f"doc {self.kind}, x array<double>")
        both = top.unionByName(_times(self.tail, left.withColumnRenamed("u", "x"), "token", "doc", r))
        return both.groupBy("doc").agg(*[F.sum(F.col("x")[k]).alias(f"x{k}") for k in range(r)]).select("doc", F.array(*[f"x{k}" for k in range(r)]).alias("x"))


def lsi_fit(weights: DataFrame | Weights, k: int, extra: int = 8, sweeps: int = 2, seed: str = "lsi"):
    """Leading left vectors ``token, u`` of the token-by-document matrix and ``doc, x`` = projected training scores.

    Randomised subspace iteration; products with the head's tokens are sums inside tasks, those with the others joins and
    per-key sums. The small orthonormalisation uses the k-by-k Gram matrix of the rows. Signs are set by the largest entry
    of each vector.
    """
    if not isinstance(weights, Weights):
        g = weights.groupBy("doc").agg(F.collect_list(F.struct("token", F.col("w").alias("tf"))).alias("p"))
        weights = Weights(g.select("doc", F.col("p.token").alias("token"), F.col("p.tf").alias("tf")), weigh=False)
    r = k + extra
    draw = F.transform(F.sequence(F.lit(1), F.lit(r)), lambda i: (F.pmod(F.xxhash64("doc", i, F.lit(seed)), F.lit(2000001)) - 1000000) / 1000000.0)
    side = weights.rows.select("doc", draw.alias("x"))
    left = old = None
    for _ in range(sweeps + 1):
        raw, old = _orthonormal(weights.to_tokens(side, r), "token", r), left
        left = stored(raw, "left")
        forget(raw.behind)
        forget(side)
        side = stored(weights.to_docs(left, r), "right")
        if old is not None:
            forget(old)
    for df in weights.kept:
        forget(df)
    # rotate so that columns are singular vectors
    g = _gram(side.withColumnRenamed("x", "u"), r)
    vals, vecs = np.linalg.eigh(g)
    rot = vecs[:, np.argsort(-vals)][:, :k]
    top = _rotate(left, "token", "u", rot).select(F.posexplode("u").alias("i", "v"), "token").groupBy("i").agg(F.max(F.struct(F.abs("v").alias("a"), "token", "v")).alias("m")).collect()
    sign = np.diag([1.0 if s["m"]["v"] >= 0 else -1.0 for s in sorted(top, key=lambda s: s["i"])])
    return _rotate(left, "token", "u", rot @ sign), _rotate(side, "doc", "x", rot @ sign), np.sqrt(np.maximum(np.sort(vals)[::-1][:k], 0))


def lsi_project(weights: DataFrame, left: DataFrame) -> DataFrame:
    """``doc, x`` of new documents on training vectors."""
    one = left.first()
    return _times(weights, left.withColumnRenamed("u", "x"), "token", "doc", len(one["u"]) if one else 0)


def _times(w: DataFrame, side: DataFrame, by: str, out: str, r: int) -> DataFrame:
    """Sums over ``by`` of weight times array of ``r``, per ``out``; element sums stay in the JVM and are partial before the shuffle."""
    e = w.join(side, by).groupBy(out).agg(*[F.sum(F.col("w") * F.col("x")[k]).alias(f"x{k}") for k in range(r)])
    return e.select(out, F.array(*[f"x{k}" for k in range(r)]).alias("x"))


def _gram(rows: DataFrame, r: int) -> np.ndarray:
    def run(batches):
        from featgreedy.operators.moments import arrays

        total = np.zeros((r, r))
        for batch in batches:
            got = arrays(batch.column("u"))
            if got:
                m = np.stack(got)
                total += m.T @ m
        yield pa.RecordBatch.from_arrays([pa.array([total.ravel()], pa.list_(pa.float64()))], ["g"])

    return sum((np.array(row["g"]) for row in rows.select("u").mapInArrow(run, "g array<double>").toLocalIterator()), np.zeros(r * r)).reshape(r, r)


def _rotate(rows: DataFrame, id_: str, name: str, m: np.ndarray) -> DataFrame:
    kind = rows.schema[id_].dataType.simpleString()

    def run(batches):
        from featgreedy.operators.moments import arrays

        for batch in batches:
            got = arrays(batch.column(name))
            out = np.stack(got) @ m if got else np.zeros((0, m.shape[1]))
            yield pa.RecordBatch.from_arrays([batch.column(id_), pa.array(list(out), pa.list_(pa.float64()))], [id_, name])

    return rows.select(id_, name).mapInArrow(run, f"{id_} {kind}, {name} array<double>")


def _orthonormal(rows: DataFrame, id_: str, r: int) -> DataFrame:
    rows, turn = stored(rows.withColumnRenamed("x", "u"), "q"), np.eye(r)
    for _ in range(2):  # twice, for accuracy
        vals, vecs = np.linalg.eigh(_gram(_rotate(rows, id_, "u", turn), r))
        keep = vals > 1e-12 * max(vals.max(), 1e-300)
        scale = np.where(keep, 1 / np.sqrt(np.where(keep, vals, 1.0)), 0.0)
        turn = turn @ (vecs * scale)
    out = _rotate(rows, id_, "u", turn)
    out.behind = rows
    return out


def onehot(tokens: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """``doc, f``: presence of the vocabulary's tokens (``token, i`` from 0), zeros elsewhere."""
    n = vocabulary.agg(F.max("i")).first()[0] + 1
    hit = tokens.join(F.broadcast(vocabulary), "token").groupBy("doc").agg(F.collect_set("i").alias("s"))
    return tokens.select("doc").distinct().join(hit, "doc", "left").select("doc", F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.when(F.array_contains("s", i), 1.0).otherwise(0.0)).alias("f"))


def top_terms(weights: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("doc").orderBy(F.round(F.col("w"), 6).desc(), "token")
    return weights.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def fourier_block(series: DataFrame, k: int) -> DataFrame:
    """``id, f``: leading cosine and sine coefficients of ``id, s (position in [0, 1)), v``."""
    two_pi = 6.283185307179586
    sums = [F.sum(F.col("v") * fn(F.col("s") * (two_pi * i))).alias(f"c{i}{n}") for i in range(1, k + 1) for n, fn in (("c", F.cos), ("s", F.sin))]
    g = series.groupBy("id").agg(F.count("*").alias("n"), *sums)
    return g.select("id", F.array(*[F.col(f"c{i}{n}") / F.col("n") for i in range(1, k + 1) for n in "cs"]).alias("f"))


ship(__name__)
