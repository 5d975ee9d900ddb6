"""Toxicity by multiple-instance learning: sentence scores joined by noisy-or, trained from document labels.

A sentence's probability is the logistic of a bias plus the weights of its distinct words and of the words' first
letters (inflected and joined forms share a stem); a document's is one
minus the product of its sentences' complements. Weights are found by gradient ascent of the documents'
likelihood with an L1 shrinkage, on at most ``max_docs`` labelled documents taken in the order of a seeded hash
of their ids (the documented bound; beside it every document is scored whole). Words enter the vocabulary from
``min_docs`` documents on, at most ``max_words`` by document frequency, which bounds the broadcast model; words
of more than ``max_share`` of the sample tell nothing and are left out.

Scores use text alone. Null or empty text: score of no sentence, 0. Repeated rows are scored each by itself.
Labels that are null, and label rows without a document, are left out of the training.
"""

from __future__ import annotations

import math
import re
import zlib
from array import array

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from featgreedy.llm.common import ship, tidied

SENTENCE = re.compile(r"(?<=[.!?])\s+|\n+")
#: Fixed value: lengths of the stems that are features beside the whole word.
STEMS = (4, 5, 6, 7, 8)
_TRIM = {ord(c): " " for c in "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~«»“”„…¡¿"}


def held_out(doc_id: str = "doc_id") -> Column:
    """Rows kept for testing: remainder 2 of crc32 of the id as text by 4."""
    return F.pmod(F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit(""))), F.lit(4)) == 2


def training_rows(docs: DataFrame, labels: DataFrame, target: str, max_docs: int, seed: str) -> DataFrame:
    """At most ``max_docs`` labelled, not held-out rows ``doc_id, text, y``."""
    chosen = labels.filter(F.col(target).isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    chosen = chosen.groupBy("doc_id").agg(F.max(target).cast("int").alias("y"))
    chosen = chosen.orderBy(F.md5(F.concat(F.lit(seed), F.col("doc_id").cast("string"))), "doc_id").limit(max_docs)
    return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")


def features(word: str) -> list[str]:
    """The word and its stems, marked by a leading caret."""
    return [word] + ["^" + word[:n] for n in STEMS if len(word) >= n]


def sentences(text: str | None) -> list[list[str]]:
    return [w for s in SENTENCE.split((text or "").lower()) if (w := s.translate(_TRIM).split())]


class NoisyOr:
    """``bias`` and word weights; :meth:`score` and :meth:`locate` need nothing else."""

    def __init__(self, bias: float, weights: dict[str, float]):
        self.bias, self.weights = bias, weights
        self.base = math.log1p(-1 / (1 + math.exp(-bias)))  # log of a plain sentence's complement
        self.known: dict[str, float] = {}

    def weight(self, word: str) -> float:
        """Sum of a word's feature weights; remembered, up to a bound."""
        if len(self.known) > 500_000:
            self.known.clear()
        got = self.known[word] = sum(self.weights.get(f, 0.0) for f in features(word))
        return got

    def parts(self, text: str | None) -> tuple[int, list[tuple[int, float]]]:
        """Number of sentences, and (index, probability) of those with a weighted word."""
        found, n, known = [], 0, self.known
        for words in sentences(text):
            z = 0.0
            for w in set(words):
                x = known.get(w)
                if x is None:
                    x = self.weight(w)
                if x:
                    z += x
            if z:
                found.append((n, 1 / (1 + math.exp(-max(-30.0, min(30.0, round(self.bias + z, 9)))))))
            n += 1
        return n, found

    def judge(self, text: str | None, least: float = 0.5) -> tuple[float, list[int]]:
        """The document's score and the indexes of the sentences that offend, from one reading."""
        n, found = self.parts(text)
        score = 1 - math.exp((n - len(found)) * self.base + sum(math.log1p(-min(p, 1 - 1e-12)) for _, p in found))
        return score, [i for i, p in found if p >= least]

    def score(self, text: str | None) -> float:
        return self.judge(text)[0]

    def locate(self, text: str | None, least: float = 0.5) -> list[int]:
        return self.judge(text, least)[1]


def ascent(sent: np.ndarray, word: np.ndarray, owner: np.ndarray, y: np.ndarray, w: np.ndarray, bias: float) -> tuple[float, np.ndarray]:
    """Mean log-likelihood of the documents' labels, and its gradient by weights and bias.

    ``sent, word`` are the pairs of a sentence and a feature in it, ``owner`` the document of each sentence.
    """
    p = 1 / (1 + np.exp(-np.clip(bias + np.bincount(sent, w[word], len(owner)), -30, 30)))
    clear = np.bincount(owner, np.log1p(-np.minimum(p, 1 - 1e-9)), len(y))
    q = np.clip(-np.expm1(clear), 1e-9, 1)
    # d loglik / d z of a sentence: p (y / q - 1) with q the document's probability, since 1 - q cancels
    g = p * (y[owner] / q[owner] - 1)
    value = float((y * np.log(q) + (1 - y) * clear).mean()) if len(y) else 0.0
    return value, np.append(np.bincount(word, g[sent], len(w)), g.sum()) / max(len(y), 1)


#: Weights of at most this size are left out of the model that travels: they move a sentence's log-odds by less.
LEAST_WEIGHT = 0.3


def fit(rows: list[tuple[str, int]], min_docs: int = 6, max_words: int = 100_000, steps: int = 120, shrink: float = 2e-4, max_share: float = 0.4, least_weight: float = LEAST_WEIGHT) -> NoisyOr:
    y = np.array([r[1] for r in rows], np.float64)
    if not len(y) or y.min() == y.max():
        rate = float(np.clip(y.mean() if len(y) else 0.0, 1e-3, 1 - 1e-3))
        return NoisyOr(math.log(rate / (1 - rate)) - 3, {})
    # words by number, sentence and document of each word; features by checksum, so that no feature's text is held
    known: dict[str, int] = {}
    token, sent, owner, doc_end = array("i"), array("i"), array("i"), [0]
    for d, (text, _) in enumerate(rows):
        for s in sentences(text):
            token.extend(known.setdefault(w, len(known)) for w in s)
            sent.extend([len(owner)] * len(s))
            owner.append(d)
        doc_end.append(len(token))
    token, sent, owner = (np.frombuffer(x, np.int32) if len(x) else np.zeros(0, np.int32) for x in (token, sent, owner))
    code = np.zeros((max(len(known), 1), 1 + len(STEMS)), np.uint32)
    for w, i in known.items():
        for j, f in enumerate(features(w)):
            code[i, j] = zlib.crc32(f.encode("utf-8", "replace"))
    value, count = np.zeros(0, np.uint32), np.zeros(0, np.int64)
    for lo in range(0, len(rows), 250):  # documents that hold each feature, summed part by part
        part = [np.unique(code[np.unique(token[i:j])]) for i, j in zip(doc_end[lo : min(lo + 250, len(rows))], doc_end[lo + 1 : lo + 251], strict=True)]
        some, times = np.unique(np.concatenate(part), return_counts=True)
        value, back = np.unique(np.concatenate([value, some]), return_inverse=True)
        count = np.bincount(back, np.concatenate([count, times]), len(value)).astype(np.int64)
    keep = np.flatnonzero((count >= min_docs) & (count <= max(max_share * len(rows), min_docs)) & (value != 0))
    keep = np.sort(value[keep[np.lexsort((value[keep], -count[keep]))][:max_words]])
    words, sents = [np.zeros(0, np.int32)], [np.zeros(0, np.int32)]
    for lo in range(0, len(rows), 250):  # parts end with a document, so with a sentence
        i, j = doc_end[lo], doc_end[min(lo + 250, len(rows))]
        c = code[token[i:j]]
        at = np.minimum(np.searchsorted(keep, c), max(len(keep) - 1, 0))
        ok = keep[at] == c if len(keep) else np.zeros(c.shape, bool)
        pairs = np.unique(np.repeat(sent[i:j].astype(np.int64), c.shape[1])[ok.ravel()] << 32 | at[ok])
        sents.append((pairs >> 32).astype(np.int32))
        words.append((pairs & 0xFFFFFFFF).astype(np.int32))
    sent, word = np.concatenate(sents), np.concatenate(words)
    del words, sents, token, code, value, count
    vocab = {}
    chosen = {int(c): j for j, c in enumerate(keep)}
    for x in known:
        for f in features(x):
            j = chosen.get(zlib.crc32(f.encode("utf-8", "replace")))
            if j is not None:
                vocab[f] = j
    del known
    w, bias, m, v = np.zeros(len(keep)), -6.0, np.zeros(len(keep) + 1), np.zeros(len(keep) + 1)
    for step in range(1, steps + 1):
        grad = ascent(sent, word, owner, y, w, bias)[1]
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad * grad
        move = 0.15 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-5)
        w, bias = w + move[:-1], bias + move[-1]
        w = np.sign(w) * np.maximum(0, np.abs(w) - 0.15 * shrink / (np.sqrt(v[:-1] / (1 - 0.99**step)) + 1e-5))
    return NoisyOr(float(bias), {x: float(w[i]) for x, i in vocab.items() if abs(w[i]) > least_weight})


def _score(model, column: str):
    def run(batches):
        scorer = NoisyOr(*model.value)
        for pdf in batches:
            judged = [scorer.judge(t) for t in pdf.pop("text")]
            pdf["score"] = [s for s, _ in judged]
            pdf["offending"] = [o for _, o in judged]
            yield pdf

    return run


def score_documents(docs: DataFrame, labels: DataFrame, max_docs: int = 5000, seed: str = "tox") -> DataFrame:
    """``doc_id, score, offending`` (indexes of offending sentences)."""
    rows = [(r["text"], r["y"]) for r in training_rows(docs, labels, "toxic", max_docs, seed).toLocalIterator()]
    model = fit(rows)
    shared = docs.sparkSession.sparkContext.broadcast((model.bias, model.weights))
    return docs.select("doc_id", "text").mapInPandas(tidied(_score(shared, "text")), "doc_id long, score double, offending array<int>")


def contract(docs: DataFrame, labels: DataFrame) -> DataFrame:
    out = score_documents(docs, labels)
    return out.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"), F.size("offending").alias("n_offending"))


ship(__name__)
