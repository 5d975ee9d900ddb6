"""Near-duplicate documents by order min-hash over five-word k-mers, verified by banded alignment.

Words are lower-cased runs between white space. Every k-mer is labelled by its occurrence number; each of
``sketches`` seeded orders picks the ``picks`` smallest labelled k-mers, and their k-mers in text order make one
bucket key: equal keys ask for common k-mers in the same order, so they follow edit similarity rather than
shared content alone. In a bucket every member is checked against the smallest id; then, in buckets whose members are still
in different components, every pair of members in different components is either ruled out by lower bounds of its
distance (lengths and bags of words) or checked. Buckets of more than ``block`` members are cut into blocks by a hash
of the id, and each pair of blocks is a task, which returns a spanning forest of its links; no pair becomes a row.

A candidate pair is linked when its words' edit distance is at most ``(1 - similarity)`` of the longer text; the
distance is computed in bit-parallel columns confined to the band which that bound allows.

Texts equal after normalising are one node from the start. Null texts and texts without words link with nothing.
Rows with null ids keep a class of their own (null); rows that share an id are one document. ``class_id`` is the
smallest id of the component.
"""

from __future__ import annotations

import functools
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from featgreedy.llm.common import components, forget, ship, small, stored, tidied

K = 5
#: Counters of a bag of words.
BAG = 256


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9FB21C651E98DF25)
    return x ^ (x >> np.uint64(28))


class Words:
    """64-bit word hashes of texts; remembers words it has met, up to a bound."""

    def __init__(self):
        self.known: dict[str, int] = {}

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").lower().split()
        known = self.known
        if len(known) > 200_000:
            known.clear()
        for w in set(words).difference(known):
            known[w] = xxhash.xxh3_64_intdigest(w)
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def word_numbers(text: str | None) -> np.ndarray:
    """A text's words as 32-bit hashes."""
    return (Words()(text) >> np.uint64(32)).astype(np.uint32)


@functools.cache
def _orders(sketches: int) -> tuple[np.ndarray, np.ndarray]:
    """Multipliers that order the k-mers, and first values of the keys."""
    odd = (np.random.default_rng(17).integers(0, 2**63, sketches, np.uint64) << np.uint64(1)) | np.uint64(1)
    return odd, _mix(np.arange(1, sketches + 1).astype(np.uint64))


def sketch(words: np.ndarray, sketches: int, picks: int) -> np.ndarray:
    """Bucket keys of one text."""
    k = min(K, len(words))
    if not k:
        return np.zeros(0, np.int64)
    grams = np.zeros(len(words) - k + 1, np.uint64)
    for i in range(k):
        grams = _mix(grams * np.uint64(0x9E3779B97F4A7C15) + words[i : len(words) - k + 1 + i])
    order = np.argsort(grams, kind="stable")
    g = grams[order]
    new = np.concatenate([[True], g[1:] != g[:-1]])
    start = np.flatnonzero(new)
    occurrence = np.empty(len(g), np.uint64)
    occurrence[order] = (np.arange(len(g)) - start[np.cumsum(new) - 1]).astype(np.uint64)
    labelled = _mix(grams + occurrence * np.uint64(0xD6E8FEB86659FD93)) | np.uint64(1)
    odd, key = _orders(sketches)
    key = key.copy()
    step = max(1, 4_000_000 // len(grams))
    for lo in range(0, sketches, step):
        x = labelled[None, :] * odd[lo : lo + step, None]
        rows = np.arange(len(x))
        at = []
        for _ in range(min(picks, len(grams))):
            at.append(x.argmin(1))
            x[rows, at[-1]] = np.uint64(2**64 - 1)
        for p in np.sort(np.stack(at), axis=0):
            key[lo : lo + step] = _mix(key[lo : lo + step] * np.uint64(0x9E3779B97F4A7C15) + grams[p])
    return key.view(np.int64)


def banded_distance(a: list[int], b: list[int], k: int) -> int:
    """Edit distance of two sequences if at most ``k``, else ``k + 1``.

    Bit ``r`` of the vectors at column ``j`` stands for row ``j - k + r``: the window slides down the diagonal,
    the distance is followed along its lower edge until the last row, and then along that row.
    """
    n, m = len(a), len(b)
    if abs(n - m) > k:
        return k + 1
    if not n or not m:
        return max(n, m)
    k = min(k, max(n, m))
    reach = min(k, n)  # rows below the diagonal that exist
    width = k + reach + 1
    full, edge = (1 << width) - 1, 1 << (width - 1)
    masks: dict[int, int] = {}
    for i, c in enumerate(a):
        masks[c] = masks.get(c, 0) | 1 << i
    plus, minus, score = full ^ ((1 << k) - 1), 0, reach
    turn = n - reach  # columns for which the lower edge lies on a row of its own
    most = k + (m - turn)
    for j in range(1, m + 1):
        lo = j - k - 1  # position in ``a`` of bit 0
        got = masks.get(b[j - 1], 0)
        eq = (got >> lo if lo >= 0 else got << -lo) & full if got else 0
        zero = ((((eq & plus) + plus) ^ plus) | eq | minus) & full
        rise = minus | ~(zero | plus) & full
        fall = zero & plus
        if j <= turn:
            score += not zero & edge
            if score > most:
                return k + 1
        else:
            bit = n - j + k
            score += (rise >> bit & 1) - (fall >> bit & 1)
        zero >>= 1
        plus = (fall | ~(zero | rise)) & full
        minus = zero & rise
    return min(score, k + 1)


def alike(a: np.ndarray, b: np.ndarray, similarity: float) -> bool:
    longest = max(len(a), len(b))
    k = int((1 - similarity) * longest + 1e-9)
    if abs(len(a) - len(b)) > k:
        return False
    same = 0
    short = min(len(a), len(b))
    head = a[:short] != b[:short]
    same = int(head.argmax()) if head.any() else short
    a, b = a[same:], b[same:]
    short = min(len(a), len(b))
    if short:
        tail = a[::-1][:short] != b[::-1][:short]
        end = int(tail.argmax()) if tail.any() else short
        a, b = a[: len(a) - end], b[: len(b) - end]
    return banded_distance(a.tolist(), b.tolist(), k) <= k


def _sketches(sketches: int, picks: int):
    def run(batches):
        words = Words()
        for batch in batches:
            ids, tags, keys = [], [], []
            for i, text in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
                w = words(text.as_py())
                if len(w):
                    ids.append(i)
                    tags.append(xxhash.xxh3_128_digest(w.tobytes()))
                    keys.append(sketch(w, sketches, picks))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(tags, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], ["id", "tag", "keys"])

    return run


def _sequences(batches):
    words = Words()
    for batch in batches:
        seqs = [(words(t.as_py()) >> np.uint64(32)).astype(np.uint32) for t in batch.column("text")]
        blobs = [zlib.compress(x.tobytes(), 1) for x in seqs]
        sizes, bags = [len(x) for x in seqs], [bag(x).tobytes() for x in seqs]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(blobs, pa.binary()), pa.array(sizes, pa.int32()), pa.array(bags, pa.binary())], ["id", "seq", "n", "bag"])


def bag(seq: np.ndarray) -> np.ndarray:
    """Counts of words by hash, cut at 255. One edit moves each one-sided difference of two bags by at most one."""
    return np.minimum(np.bincount(seq % BAG, minlength=BAG), 255).astype(np.uint8)


def bounded_pairs(task: np.ndarray, key: np.ndarray, n: np.ndarray, bags: np.ndarray, keys: np.ndarray, c: np.ndarray, own: np.ndarray, cross: np.ndarray, similarity: float):
    """Index pairs of one task (equal ``task``, neighbours, ascending ``n``), of different components, that may be alike.

    Pairs are ruled out by lengths and by the differences of their bags, both lower bounds of the edit distance. Where
    ``cross`` is set, pairs of one block belong to another task; a pair with several common ``keys`` (rows padded with
    the largest number) belongs to the bucket of the smallest.
    """
    left = np.arange(len(task) - 1)
    folded = bags.reshape(len(bags), 16, -1).sum(2, dtype=np.int32)
    none = np.iinfo(np.int64).max
    for d in range(1, len(task)):
        left = left[left + d < len(task)]
        right = left + d
        most = ((1 - similarity) * n[right] + 1e-9).astype(np.int64)
        left = left[(task[left] == task[right]) & (n[right] - n[left] <= most)]  # lengths only grow: others end here
        if not len(left):
            return
        p = left[c[left] != c[left + d]]
        p = p[~cross[p] | (own[p] != own[p + d])]
        for part in np.array_split(p, len(p) // 4000 + 1):
            for x in (folded, bags):
                gap = x[part].astype(np.int16) - x[part + d] if x is bags else x[part] - x[part + d]
                over, under = np.maximum(gap, 0).sum(1), np.maximum(-gap, 0).sum(1)
                part = part[np.maximum(over, under) <= ((1 - similarity) * n[part + d] + 1e-9).astype(np.int64)]
            for few in np.array_split(part, len(part) // 500 + 1):
                mine = keys[few]
                common = (mine[:, :, None] == keys[few + d][:, None, :]).any(2)
                few = few[np.where(common, mine, none).min(1) == key[few]]
                if len(few):
                    yield few, few + d


def _merge(similarity: float):
    """Per task, links between components (``ca``, ``cb``): a spanning forest, so pairs already joined are not checked."""

    def merged(pdf):
        task = pdf.groupby(["key", "i", "j"], sort=False).ngroup().to_numpy()
        bags = np.frombuffer(b"".join(pdf["bag"]), np.uint8).reshape(len(pdf), BAG)
        c, led, blobs = pdf["c"].to_numpy(), pdf["led"].to_numpy(), pdf["seq"].tolist()
        cross, key = (pdf["i"] != pdf["j"]).to_numpy(), pdf["key"].to_numpy()
        sizes = pdf["keys"].map(len).to_numpy()
        keys = np.full((len(pdf), sizes.max()), np.iinfo(np.int64).max)
        keys[np.arange(keys.shape[1]) < sizes[:, None]] = np.concatenate(pdf["keys"].to_list())
        root, read, out = {}, {}, []

        def find(x):
            while root.setdefault(x, x) != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        def seq(k):
            if k not in read:
                if len(read) > 2000:
                    read.clear()
                read[k] = np.frombuffer(zlib.decompress(blobs[k]), np.uint32)
            return read[k]

        for p, q in bounded_pairs(task, key, pdf["n"].to_numpy().astype(np.int64), bags, keys, c, pdf["own"].to_numpy(), cross, similarity):
            fresh = ~(led[p] | led[q])  # the first round checked the bucket's leader with everyone
            for k, m in zip(p[fresh].tolist(), q[fresh].tolist(), strict=True):
                u, v = find(c[k]), find(c[m])
                if u != v and alike(seq(k), seq(m), similarity):
                    root[max(u, v)] = min(u, v)
                    out.append((u, v))
        return pd.DataFrame(out, columns=["ca", "cb"], dtype="int64")

    def run(batches):
        held = None  # the last task's rows, which the next batch may continue
        for pdf in batches:
            pdf = pdf if held is None else pd.concat([held, pdf], ignore_index=True)
            end = pdf[["key", "i", "j"]].to_numpy()
            last = int((end == end[-1]).all(1).argmax()) if len(pdf) else 0
            held, pdf = pdf.iloc[last:], pdf.iloc[:last]
            if len(pdf):
                yield merged(pdf)
        if held is not None and len(held):
            yield merged(held)

    return run


def _verify(similarity: float):
    def run(batches):
        for pdf in batches:
            read = lambda z: np.frombuffer(zlib.decompress(z), np.uint32)
            ok = [alike(read(a), read(b), similarity) for a, b in zip(pdf["a_seq"], pdf["b_seq"], strict=True)]
            yield pd.DataFrame({"a": pdf["a"], "b": pdf["b"], "ok": ok})

    return run


def classes(docs: DataFrame, similarity: float = 0.8, sketches: int = 96, picks: int = 2, block: int = 2048) -> DataFrame:
    """``id, class_id`` for every document that has words and an id."""
    slim = docs.filter("doc_id IS NOT NULL").select("doc_id", "text")
    keyed = stored(slim.mapInArrow(tidied(_sketches(sketches, picks)), "id long, tag binary, keys array<long>"), "sketches")
    reps = stored(keyed.groupBy("tag").agg(F.min("id").alias("rep"), F.count("*").alias("n")), "reps")
    each = keyed.join(reps.select(F.col("rep").alias("id"), "tag"), ["id", "tag"]).select("id", F.explode("keys").alias("key"))
    counts = each.groupBy("key").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).filter("lo < hi").select("key")
    shared = stored(each.join(counts, "key"), "buckets")
    involved = stored(shared.select("id").distinct(), "involved")
    seqs = slim.join(small(involved.withColumnRenamed("id", "doc_id")), "doc_id", "left_semi")
    seqs = stored(seqs.mapInArrow(tidied(_sequences), "id long, seq binary, n int, bag binary").groupBy("id").agg(F.max(F.struct("seq", "n", "bag")).alias("s")).select("id", "s.*"), "sequences")
    by = lambda c: seqs.select(F.col("id").alias(c), F.col("seq").alias(f"{c}_seq"))

    def links(pairs: DataFrame) -> DataFrame:
        both = pairs.join(by("a"), "a").join(by("b"), "b")
        return stored(both.mapInPandas(tidied(_verify(similarity)), "a long, b long, ok boolean"), "checked")

    pair = (F.least("id", "lead").alias("a"), F.greatest("id", "lead").alias("b"))
    # first round: the smallest id leads its bucket
    lead = shared.groupBy("key").agg(F.min("id").alias("lead"))
    first = links(shared.join(lead, "key").filter("id <> lead").select(*pair).distinct())
    one = components(first.filter("ok").select("a", "b"), "a", "b")
    # second round, over buckets that still hold several components: all pairs of components there, block by block
    pool = shared.join(one.withColumnRenamed("node", "id"), "id", "left").select("key", F.coalesce("component", "id").alias("c"), "id")
    pool = stored(pool, "members")
    several = pool.groupBy("key").agg(F.count("*").alias("m"), F.min("id").alias("lead"), F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo < hi")
    several = several.select("key", "lead", F.ceil(F.col("m") / block).cast("int").alias("nb"))
    each = pool.join(several, "key").withColumn("own", F.pmod(F.xxhash64("id"), F.col("nb")).cast("int")).withColumn("led", F.col("id") == F.col("lead"))
    mates = F.transform(F.sequence(F.lit(0), F.col("nb") - 1), lambda o: F.struct(F.least("own", o).alias("i"), F.greatest("own", o).alias("j")))
    wide = each.filter("nb > 1").select("key", "c", "id", "led", "own", F.explode(mates).alias("ij")).select("key", "c", "id", "led", "own", "ij.i", "ij.j")
    tasks = each.filter("nb = 1").select("key", "c", "id", "led", "own", F.lit(0).alias("i"), F.lit(0).alias("j")).unionByName(wide)
    open_keys = each.groupBy("id").agg(F.collect_set("key").alias("keys"))  # at most one a sketch
    tasks = tasks.join(seqs.join(open_keys, "id"), "id").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "n", "id")
    found = stored(tasks.mapInPandas(tidied(_merge(similarity)), "ca long, cb long"), "merged")
    two = components(found, "ca", "cb")
    for done in (shared, involved, seqs, first, pool, found):
        forget(done)
    top = one.join(two.select(F.col("node").alias("component"), F.col("component").alias("top")), "component", "left").select("node", F.coalesce("top", "component").alias("component"))
    lone = two.join(one.select("node"), "node", "left_anti")
    final = top.unionByName(lone)
    nodes = reps.join(final.withColumnRenamed("node", "rep"), "rep", "left").select("tag", F.coalesce("component", "rep").alias("class_id"))
    return keyed.select("id", "tag").join(nodes, "tag").groupBy("id").agg(F.min("class_id").alias("class_id"))


def drop_near(docs: DataFrame, similarity: float = 0.8) -> DataFrame:
    """``docs`` with one document of each class, the one with the smallest id; columns as they were."""
    losers = stored(classes(docs, similarity).filter("id <> class_id").select(F.col("id").alias("doc_id")), "losers")
    out = docs.join(small(losers), "doc_id", "left_anti").select(docs.columns)
    twice = docs.groupBy("doc_id").count().filter("count > 1 AND doc_id IS NOT NULL").limit(1).count()
    if not twice:
        return out
    # of rows that share an id the first by text, then by all values, stays; rows without an id all stay
    order = F.struct("text", F.to_json(F.struct(*docs.columns)))
    one = out.filter("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min_by(F.struct(*docs.columns), order).alias("row"))
    return one.select("row.*").unionByName(out.filter("doc_id IS NULL"))


def contract(docs: DataFrame) -> DataFrame:
    """One row per document: ``doc_id, class_id, kept``."""
    got = classes(docs).withColumnRenamed("id", "doc_id")
    out = docs.select("doc_id").join(got, "doc_id", "left")
    return out.select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id")).withColumn("kept", F.col("doc_id") == F.col("class_id"))


ship(__name__)
