"""Quality by nearest-neighbour voting among labelled latent-semantic vectors.

A text's terms are the shapes of its words (letters by case, digits and marks, runs joined), whether a word
repeats the one before, and hashed words. Term weights are log counts times inverse document frequency; their
leading singular vectors, from the labelled rows, give the latent space. Labelled vectors are at most
``max_docs`` (the documented bound of the sample), chosen in the order of a seeded hash, and are broadcast with
the term matrix, both of fixed size. Every document's exact cosines with all of them are computed in blocks;
the ``k`` nearest (the earlier labelled row where cosines are equal) vote with weights that grow with similarity.
Shapes and repeats count more than words (``SHARE`` and ``DAMP``): junk shows in how words look, and single words
are many and rare, so undamped they drown it (held-out accuracy on sf0.1 falls without).

Scores use text alone. Null or empty text is the zero vector: it scores the share of label 1 in the sample.
Repeated rows are scored each by itself. Null labels and labels without document are left out.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from featgreedy.llm.common import ship, tidied
from featgreedy.llm.toxicity import held_out, training_rows

BUCKETS = 2048
#: Scale of a term's share of the text before its logarithm, and the weight of whole words beside shapes and repeats.
SHARE, DAMP = 100, 0.15
_RUN = re.compile(r"(.)\1+")


def shape(word: str) -> str:
    """Kinds of characters with runs joined: ``Word!!`` -> ``Aa!``."""
    kinds = "".join("a" if c.islower() else "A" if c.isupper() else "0" if c.isdigit() else "w" if c.isalpha() else c for c in word)
    return _RUN.sub(r"\1", kinds)


class Terms:
    """Bucket counts of a text; remembers the buckets of words it has met, up to a bound."""

    def __init__(self):
        self.known: dict[str, int] = {}

    def bucket(self, word: str) -> int:
        if len(self.known) > 150_000:
            self.known.clear()
        kind = zlib.crc32(b"s" + shape(word).encode("utf-8", "replace")) % (BUCKETS // 4)
        own = BUCKETS // 4 + zlib.crc32(word.encode("utf-8", "replace")) % (BUCKETS - BUCKETS // 4 - 1)
        self.known[word] = kind * BUCKETS + own
        return self.known[word]

    def vector(self, text: str | None, scale: np.ndarray | None = None) -> np.ndarray:
        words = (text or "").split()
        if not words:
            return np.zeros(BUCKETS)
        known = self.known.get
        both = np.array([known(w) or self.bucket(w) for w in words])
        out = np.bincount(both // BUCKETS, minlength=BUCKETS) + np.bincount(both % BUCKETS, minlength=BUCKETS).astype(np.float64)
        out[-1] = np.count_nonzero(both[1:] == both[:-1])
        share = out / len(words)  # of length-free weight: shapes and repeats by share, words damped
        out = np.log1p(SHARE * share)
        out[BUCKETS // 4 : -1] *= DAMP
        return out if scale is None else out * scale


def fit(x: np.ndarray, y: np.ndarray, dim: int = 48, seed: int = 5) -> dict:
    """Term scales, latent basis, unit labelled vectors and labels, from term vectors (changed in place) and labels."""
    idf = np.log((1 + len(x)) / (1 + (x > 0).sum(0))) + 1
    x *= idf.astype(np.float32)
    rng = np.random.default_rng(seed)
    basis = np.linalg.qr(x.T @ (x @ rng.standard_normal((BUCKETS, dim + 8)).astype(np.float32)))[0] if len(x) else np.zeros((BUCKETS, dim), np.float32)
    for _ in range(3 if len(x) else 0):
        basis = np.linalg.qr(x.T @ (x @ basis))[0]
    if len(x):
        u, _, _ = np.linalg.svd(basis.T @ (x.T @ (x @ basis)))
        basis = (basis @ u)[:, :dim]
    z = x @ basis
    z /= np.maximum(np.sqrt((z * z).sum(1)), 1e-12)[:, None]
    return {"scale": idf.astype(np.float64), "basis": basis.astype(np.float64), "z": z.astype(np.float64), "y": y.astype(np.float64), "rate": float(y.mean()) if len(y) else 0.5}


def vote(model: dict, v: np.ndarray, k: int = 25, sharp: float = 8.0) -> np.ndarray:
    """Scores of the rows of ``v`` (term vectors) by their nearest labelled rows."""
    z = v @ model["basis"]
    norm = np.sqrt((z * z).sum(1))
    out = np.full(len(v), model["rate"])
    k = min(k, len(model["y"]))
    if not k:
        return out
    cos = (z / np.maximum(norm, 1e-12)[:, None]) @ model["z"].T
    near = np.argpartition(-cos, k - 1, axis=1)[:, :k]
    last = np.take_along_axis(cos, near, 1).min(1)
    for i in np.flatnonzero((cos >= last[:, None]).sum(1) > k):  # equal cosines at the edge: the earlier labelled rows
        near[i] = np.argsort(-cos[i], kind="stable")[:k]
    c = np.take_along_axis(cos, near, 1)
    w = np.exp(sharp * (c - c.max(1, keepdims=True)))
    out[norm > 0] = ((w * model["y"][near]).sum(1) / w.sum(1))[norm > 0]
    return np.clip(out, 0, 1)


def _scores(texts: list, model: dict, terms: Terms, block: int = 128) -> np.ndarray:
    parts = [vote(model, np.stack([terms.vector(t, model["scale"]) for t in texts[i : i + block]])) for i in range(0, len(texts), block)]
    return np.concatenate(parts) if parts else np.zeros(0)


def trained(docs: DataFrame, labels: DataFrame, max_docs: int, seed: str):
    """The broadcast model; term vectors of at most ``max_docs`` labelled rows, made on the executors, reach the driver."""

    def run(batches):
        terms = Terms()
        for pdf in batches:
            pdf["v"] = [terms.vector(t).astype(np.float32).tobytes() for t in pdf.pop("text")]
            yield pdf[["doc_id", "y", "v"]]

    rows = training_rows(docs, labels, "quality", max_docs, seed).mapInPandas(tidied(run), "doc_id long, y int, v binary")
    got = sorted(((r["doc_id"], r["y"], r["v"]) for r in rows.toLocalIterator()), key=lambda r: (r[0], r[2]))
    x = np.frombuffer(b"".join(r[2] for r in got), np.float32).reshape(len(got), BUCKETS).copy()
    return docs.sparkSession.sparkContext.broadcast(fit(x, np.array([r[1] for r in got], np.float32)))


def score_documents(docs: DataFrame, labels: DataFrame, max_docs: int = 3000, seed: str = "quality") -> DataFrame:
    """``doc_id, score`` for every row of ``docs``."""
    shared = trained(docs, labels, max_docs, seed)

    def run(batches):
        model, terms = shared.value, Terms()
        for pdf in batches:
            pdf["score"] = _scores(pdf.pop("text").tolist(), model, terms)
            yield pdf

    return docs.select("doc_id", "text").mapInPandas(tidied(run), "doc_id long, score double")


def keep_good(docs: DataFrame, labels: DataFrame, least: float = 0.7, max_docs: int = 3000, seed: str = "quality") -> DataFrame:
    """Rows of ``docs`` whose score reaches ``least``, all columns kept."""
    import pyarrow as pa

    shared = trained(docs, labels, max_docs, seed)

    def run(batches):
        model, terms = shared.value, Terms()
        for batch in batches:
            yield batch.filter(pa.array(_scores(batch.column("text").to_pylist(), model, terms) >= least))

    return docs.mapInArrow(tidied(run), docs.schema)


def contract(docs: DataFrame, labels: DataFrame) -> DataFrame:
    out = score_documents(docs, labels)
    return out.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


ship(__name__)
