"""Benchmark decontamination by the pigeonhole principle and bit-parallel edit distance.

Items and documents are lower-cased with white space joined. An item of ``L`` characters may differ by
``k = floor(rate * L)`` edits; cut into ``k + 1`` pieces, at least one piece of any such occurrence is unchanged.
Exact piece hits come from one automaton over all pieces; hits of one item whose implied starts agree within
``k`` share a window, and a window is decided by the bit-parallel edit distance of the item against the best
substring of the window. Whole texts are scanned.

Items are a query set: while their bytes are within ``block_bytes`` they are one broadcast block; more items
are scanned block by block, and the blocks' findings are united. One block at a time is held by the driver and
the executors. Every item is searched; one too short for any edit must stand between word boundaries.

Null or empty texts have no hits, and empty or null items are in no text. Rows equal in id and text have equal
findings, and each keeps its own row. Items that share an id are one item with several texts. Result: one row
per row of ``docs``, the same however the items are cut into blocks.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from featgreedy.llm.common import ship, small, stored, tidied

RATE = 0.06


def plain(text: str | None) -> str:
    return " ".join((text or "").lower().split())


def pieces(item: str, k: int) -> list[tuple[int, str]]:
    n = len(item)
    cuts = [p * n // (k + 1) for p in range(k + 2)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]


def pattern_masks(pattern: str) -> dict[str, int]:
    masks: dict[str, int] = {}
    for i, c in enumerate(pattern):
        masks[c] = masks.get(c, 0) | 1 << i
    return masks


def best_distance(masks: dict[str, int], m: int, text: str, stop: int) -> int:
    """Least edit distance between a pattern of ``m`` characters and any substring of ``text``; bit-parallel columns.

    The vertical differences of a column of the distance table are kept as two bit vectors; ``stop`` is a
    distance below which the search may end.
    """
    full, top = (1 << m) - 1, 1 << (m - 1)
    up, down, score = full, 0, m
    best = score
    for c in text:
        eq = masks.get(c, 0)
        diag = (((eq & up) + up) ^ up) | eq | down
        rise = down | ~(diag | up) & full
        fall = up & diag
        if rise & top:
            score += 1
        elif fall & top:
            score -= 1
            if score < best:
                best = score
                if best <= stop:
                    break
        rise, fall = rise << 1 & full, fall << 1 & full  # a match may start anywhere: nothing enters from above
        up = (fall | ~(diag | rise)) & full
        down = rise & diag
    return best


def build(items: list[tuple[int, str]], rate: float):
    """Automaton over the pieces and, for each item text, what its check needs."""
    import ahocorasick

    auto, checks, where = ahocorasick.Automaton(), [], {}
    for item_id, t in sorted({(i, plain(text)) for i, text in items}):
        if not t:
            continue
        k = int(rate * len(t))
        for at, piece in pieces(t, k):
            where.setdefault(piece, []).append((len(checks), at))
        checks.append((len(t), k, pattern_masks(t), t, item_id))
    for piece, uses in where.items():
        auto.add_word(piece, (len(piece), uses))
    if where:
        auto.make_automaton()
    return auto if where else None, checks


def find(auto, checks, text: str) -> dict[int, int]:
    """Items that occur in ``text`` within their budgets, with their least distance."""
    found: dict[int, int] = {}
    if auto is None:
        return found
    done: dict[int, list[int]] = {}
    for end, (n, uses) in auto.iter(text):
        for x, at in uses:
            m, k, masks, whole, item_id = checks[x]
            start = end - n + 1 - at
            if found.get(item_id) == 0 or any(abs(start - s) <= k for s in done.get(x, ())):
                continue
            if not k:  # the only piece is the item
                if not (text[start - 1 : start].isalnum() and whole[0].isalnum() or text[end + 1 : end + 2].isalnum() and whole[-1].isalnum()):
                    found[item_id] = 0
                continue
            lo = max(0, start - 2 * k)  # starts within k of this one use the same window
            window = text[lo : max(0, start) + m + 3 * k + 1]
            d = 0 if whole in window else best_distance(masks, m, window, 0)
            near = done.setdefault(x, [])
            near.append(start)
            if len(near) > 64:
                del near[:32]
            if d <= k and d < found.get(item_id, k + 1):
                found[item_id] = d
    return found


def _scan(items, rate: float, hits_only: bool):
    def run(batches):
        auto, checks = build(items.value, rate)
        for pdf in batches:
            hits = [find(auto, checks, plain(t)) for t in pdf.pop("text")]
            pdf["item_ids"] = [sorted(h) for h in hits]
            pdf["distances"] = [[h[i] for i in sorted(h)] for h in hits]
            yield pdf[[bool(h) for h in hits]] if hits_only else pdf

    return run


_FOUND = "doc_id long, _t long, item_ids array<long>, distances array<int>"


def _blocks(benchmark: DataFrame, block_bytes: int):
    """Lists of items of at most ``block_bytes``, or one longer item each."""
    block, size = [], 0
    for item_id, text in benchmark.filter("item_id IS NOT NULL AND text IS NOT NULL").select("item_id", "text").toLocalIterator():
        n = len(text.encode())
        if block and size + n > block_bytes:
            yield block
            block, size = [], 0
        block.append((item_id, text))
        size += n
    yield block


def contaminated(docs: DataFrame, benchmark: DataFrame, rate: float = RATE, block_bytes: int = 8_000_000) -> DataFrame:
    """``doc_id, _t`` (digest of the text) ``, item_ids, distances, contaminated`` for every row of ``docs``."""
    spark = docs.sparkSession
    slim = docs.select("doc_id", "text", F.xxhash64("text").alias("_t"))
    blocks = _blocks(benchmark, block_bytes)
    block, after = next(blocks), next(blocks, None)
    if after is None:
        out = slim.mapInPandas(tidied(_scan(spark.sparkContext.broadcast(block), rate, False)), _FOUND)
        return out.withColumn("contaminated", F.size("item_ids") > 0)
    hits = None
    while block is not None:
        held = spark.sparkContext.broadcast(block)
        part = stored(slim.mapInPandas(tidied(_scan(held, rate, True)), _FOUND), "hits")
        held.destroy()
        hits = part if hits is None else hits.union(part)
        block, after = after, next(blocks, None) if after else None
    each = hits.select("doc_id", "_t", F.explode(F.arrays_zip("item_ids", "distances")).alias("p"))
    each = each.groupBy("doc_id", "_t", "p.item_ids").agg(F.min("p.distances").alias("distances"))
    each = each.groupBy("doc_id", "_t").agg(F.array_sort(F.collect_list(F.struct("item_ids", "distances"))).alias("p"))
    each = stored(each.select(F.col("doc_id").alias("_d"), F.col("_t").alias("_u"), F.col("p.item_ids").alias("item_ids"), F.col("p.distances").alias("distances")), "found")
    same = F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("_t") == F.col("_u"))
    none = lambda c, kind: F.coalesce(c, F.array().cast(kind)).alias(c)
    out = slim.select("doc_id", "_t").join(small(each), same, "left")
    out = out.select("doc_id", "_t", none("item_ids", "array<long>"), none("distances", "array<int>"))
    return out.withColumn("contaminated", F.size("item_ids") > 0)


def contract(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    return contaminated(docs, benchmark).select("doc_id", "contaminated", "item_ids", "distances")


ship(__name__)
