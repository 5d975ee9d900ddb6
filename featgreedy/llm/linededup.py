"""Line dedup by pairwise alignment: shared line hashes nominate pairs, patience diff aligns them, and aligned
common blocks are deleted from the later document.

Later means larger ``(doc_id, digest of the text)``. Keys are lines of at least ``min_line_words`` words and, from each
shorter line on and up to it, the shortest windows of neighbouring lines that reach ``min_block_words``; characters of
scripts without blanks count by twos. A key in more than one document nominates the pair (first document that has it,
each later one), so a key of ``n`` documents gives ``n - 1`` pairs, none of them more than a row, and no frequency cap is
needed: the rare keys of a pair and the frequent ones are treated alike. Every line of a block that two documents share
lies in a key inside that block, and the first holder of that key is asked; so a block goes whoever holds it first.
Both documents of a pair are aligned whole, as sequences of hashes of trimmed lines: lines unique in both are matched,
the longest increasing chain is kept, and gaps are aligned likewise, with equal ends joined on; a gap without such
lines is split at its longest common run. Where a key of the pair stays unaligned, because blocks changed their order
or repeat, all runs of neighbouring lines that both have are aligned. An aligned run is a block; blocks of at least
``min_block_words`` words go from the later document. All pairs are judged on the input texts.

With ``spare``, a pair whose texts are near copies by that word similarity is no pair of a text and a shared block:
its blocks stay, for an operator that drops the whole copy. Copies that lose the same blocks stay alike.

Null texts have no lines and stay null. Rows with null ids are neither later nor earlier than others and stay whole. Rows equal in id and text are not later than one another and all stay.
Texts emptied by deletion become the empty text. Lines repeated inside one document are left alone.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from featgreedy.llm.common import forget, ship, slices, small, stored, tidied, utf8

#: Numbers in the table of deletions that may be broadcast (eight bytes each at most); beyond it a shuffle join is used.
BROADCAST_CELLS = 4_000_000


def patience(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    """Aligned index pairs of equal entries, increasing in both."""
    out, work = [], [(0, len(a), 0, len(b))]
    while work:
        i, i2, j, j2 = work.pop()
        while i < i2 and j < j2 and a[i] == b[j]:
            out.append((i, j))
            i, j = i + 1, j + 1
        while i < i2 and j < j2 and a[i2 - 1] == b[j2 - 1]:
            i2, j2 = i2 - 1, j2 - 1
            out.append((i2, j2))
        if i >= i2 or j >= j2:
            continue
        once: dict[int, list[int]] = {}
        for side, seq, lo, hi in ((0, a, i, i2), (1, b, j, j2)):
            for p in range(lo, hi):
                once.setdefault(seq[p], [-1, -1, 0, 0])[side] = p
                once[seq[p]][2 + side] += 1
        unique = [(v[0], v[1]) for v in once.values() if v[2] == v[3] == 1]
        chain = _increasing(sorted(unique))
        if not chain:
            block = _longest(a, b, i, i2, j, j2)
            if block:
                x, y, n = block
                out += [(x + k, y + k) for k in range(n)]
                work += [(i, x, j, y), (x + n, i2, y + n, j2)]
            continue
        pi, pj = i, j
        for x, y in chain:
            out.append((x, y))
            work.append((pi, x, pj, y))
            pi, pj = x + 1, y + 1
        work.append((pi, i2, pj, j2))
    return sorted(out)


def _longest(a: list[int], b: list[int], i: int, i2: int, j: int, j2: int) -> tuple[int, int, int] | None:
    """The longest common run of two ranges, the first of equal ones: its starts and its length."""
    at: dict[int, list[int]] = {}
    for y in range(j, j2):
        at.setdefault(b[y], []).append(y)
    best, runs = None, {}
    for x in range(i, i2):
        here = {}
        for y in at.get(a[x], ()):
            n = here[y] = runs.get(y - 1, 0) + 1
            if best is None or n > best[2]:
                best = (x - n + 1, y - n + 1, n)
        runs = here
    return best


def _increasing(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Longest subsequence of ``pairs`` (sorted by the first) whose seconds increase."""
    import bisect

    ends, at, back = [], [], [-1] * len(pairs)
    for k, (_, y) in enumerate(pairs):
        p = bisect.bisect_left(ends, y)
        back[k] = at[p - 1] if p else -1
        if p == len(ends):
            ends.append(y)
            at.append(k)
        else:
            ends[p], at[p] = y, k
    out, k = [], at[-1] if at else -1
    while k >= 0:
        out.append(pairs[k])
        k = back[k]
    return out[::-1]


def doomed(a: list[int], b: list[int], words: list[int], least: int) -> list[int]:
    """Lines of ``b`` in aligned blocks of at least ``least`` words."""
    out, run, last = [], [], None
    for pair in [*patience(a, b), None]:
        if pair and last and pair == (last[0] + 1, last[1] + 1):
            run.append(pair[1])
        else:
            if run and sum(words[j] for j in run) >= least:
                out += run
            run = [pair[1]] if pair else []
        last = pair
    return out


def windows(lines: np.ndarray, words: np.ndarray, line_words: int, block_words: int, stop: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Keys that nominate, with the first line of each and the line after its last.

    A line of ``line_words`` is a key by itself. A shorter one begins the shortest window of neighbouring lines that
    reaches ``block_words``, and ends another, so each line of a common run of that length is in a key inside the run.
    Several texts may follow one another: ``stop`` then gives each line the end of its text.
    """
    n = len(lines)
    stop = np.full(n, n) if stop is None else stop
    begin = np.searchsorted(stop, stop, "left")  # texts follow one another, so a text's first line is the first with its end
    alone = np.flatnonzero(words >= max(line_words, 1))
    short = np.flatnonzero((words > 0) & (words < line_words))
    first, last = [alone], [alone + 1]
    for step in (1, -1):
        low, high, total = short.copy(), short + 1, words[short].astype(np.int64)
        grow, lost = np.flatnonzero(total < block_words), np.zeros(len(short), bool)
        while len(grow):
            out = high[grow] >= stop[short[grow]] if step > 0 else low[grow] <= begin[short[grow]]
            lost[grow[out]] = True
            grow = grow[~out]
            if step > 0:
                total[grow] += words[high[grow]]
                high[grow] += 1
            else:
                low[grow] -= 1
                total[grow] += words[low[grow]]
            grow = grow[total[grow] < block_words]
        first.append(low[~lost])
        last.append(high[~lost])
    first, last = np.concatenate(first), np.concatenate(last)
    key, end = lines[first].copy(), first + 1
    while len(grow := np.flatnonzero(end < last)):
        with np.errstate(over="ignore"):
            key[grow] = (key[grow] ^ (key[grow] >> 29)) * np.int64(-7046029254386353131) + lines[end[grow]]
        end[grow] += 1
    return key, first, last


def moved(a: list[int], b: list[int], words: list[int], least: int) -> list[int]:
    """Lines of ``b`` in runs of neighbouring lines, of at least ``least`` words, that ``a`` holds too, in any order."""
    at: dict[int, list[int]] = {}
    for x, c in enumerate(a):
        at.setdefault(c, []).append(x)
    upto, out, runs = np.concatenate([[0], np.cumsum(words)]), set(), {}
    for y in range(len(b) + 1):
        here = {x: runs.get(x - 1, 0) + 1 for x in at.get(b[y], ())} if y < len(b) else {}
        for x, n in runs.items():  # runs that end before ``y``
            if x + 1 not in here and upto[y] - upto[y - n] >= least:
                out.update(range(y - n, y))
        runs = here
    return sorted(out)


def _arrays(lines, words) -> tuple[np.ndarray, np.ndarray]:
    return np.asarray(lines, np.int64), np.asarray(words, np.int64)


def measured(text: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes and word counts of the trimmed lines of all texts, one after the other, and each text's offset.

    Two characters of a script written without blanks count as one word.
    """
    held = pc.split_pattern(text, "\n")
    at = held.offsets.to_numpy() - held.offsets[0].as_py()
    flat = pc.utf8_trim_whitespace(held.flatten())
    coded = flat.dictionary_encode()
    some = coded.dictionary
    values = np.fromiter((xxhash.xxh3_64_intdigest(x) for x in some.cast(pa.binary()).to_pylist()), np.uint64, len(some)).view(np.int64)
    count = pc.count_substring_regex(some, pattern=r"\S+").to_numpy().astype(np.int64)
    if (np.frombuffer(some.buffers()[2] or b"", np.uint8) >= 0xE0).any():
        other = pc.count_substring_regex(some, pattern=r"[\p{Han}\p{Hiragana}\p{Katakana}\p{Thai}\p{Lao}\p{Khmer}\p{Myanmar}]").to_numpy()
        count = np.maximum(count, (other + 1) // 2)
    which = coded.indices.to_numpy()
    return values[which], count[which], at


def _read(line_words: int, block_words: int):
    """Lines, their words and the keys of each text."""

    def run(batches):
        for batch in batches:
            for i, j in slices(utf8(batch.column("text"))[1], 2_000_000):
                part = batch.slice(i, j - i)
                lines, words, at = measured(part.column("text"))
                owner = np.repeat(np.arange(len(part)), np.diff(at))
                key, first, _ = windows(lines, words, line_words, block_words, at[1:][owner])
                order = np.lexsort((key, owner[first]))
                key, mine = key[order], owner[first][order]
                new = np.ones(len(key), bool)
                new[1:] = (key[1:] != key[:-1]) | (mine[1:] != mine[:-1])
                ends = np.concatenate([[0], np.cumsum(np.bincount(mine[new], minlength=len(part)))])
                lists = [pa.ListArray.from_arrays(pa.array(e.astype(np.int32)), pa.array(x)) for e, x in ((at, lines), (at, words.astype(np.int32)), (ends, key[new]))]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("_t"), *lists], ["doc_id", "_t", "lines", "words", "keys"])

    return run


def _open(lines, words, gone, line_words: int, block_words: int) -> np.ndarray:
    """Keys of a text of which no place has lost all its lines."""
    key, start, end = windows(*_arrays(lines, words), line_words, block_words)
    kept = np.ones(len(lines) + 1, np.int64)
    kept[np.asarray(gone, np.int64)] = 0
    upto = np.concatenate([[0], np.cumsum(kept)])
    return np.setdiff1d(key, key[upto[end] == upto[start]])


def _align(line_words: int, block_words: int, similarity: float | None):
    def run(batches):
        for pdf in batches:
            out = []
            for i, t, f, a, v, b, w in zip(*(pdf[c] for c in ("doc_id", "_t", "first", "a_lines", "a_words", "lines", "words")), strict=True):
                gone = doomed(list(a), list(b), list(w), block_words)
                if np.isin(_open(b, w, gone, line_words, block_words), windows(*_arrays(a, v), line_words, block_words)[0]).any():
                    gone = sorted({*gone, *moved(list(a), list(b), list(w), block_words)})  # blocks in another order, or repeated
                copy = False
                if similarity and gone:
                    mine, other, same = int(w.sum()), int(v.sum()), int(w[gone].sum())
                    most = (1 - similarity) * max(mine, other)
                    copy = True if mine + other - 2 * same <= most else None if abs(mine - other) <= most and same >= 0.05 * max(mine, other) else False
                if copy is not True and gone:
                    out.append((i, t, (f["doc_id"], f["_t"]), gone, copy is None))
            yield pd.DataFrame(out, columns=["doc_id", "_t", "first", "gone", "doubt"])

    return run


_ROWS = "doc_id long, _t long, lines array<long>, words array<int>, keys array<long>"
_PAIRS = "doc_id long, _t long, first struct<doc_id:long,_t:long>, gone array<int>, doubt boolean"


def find_blocks(docs: DataFrame, min_line_words: int = 5, min_block_words: int = 5, spare: float | None = None) -> DataFrame:
    """``doc_id, _t, gone`` (sorted line numbers to delete) for documents that lose lines."""
    sizes = (min_line_words, min_block_words)
    slim = docs.filter("text IS NOT NULL AND doc_id IS NOT NULL").select("doc_id", F.xxhash64("text").alias("_t"), "text")
    rows = stored(slim.mapInArrow(tidied(_read(*sizes)), _ROWS).distinct(), "lines")
    me = F.struct("doc_id", "_t")
    each = rows.select(F.explode("keys").alias("h"), me.alias("me"))
    first = each.groupBy("h").agg(F.min("me").alias("first"), F.count("*").alias("n")).filter("n > 1").drop("n")
    asked = stored(each.join(first, "h").filter("me > first"), "asked")
    a = rows.select(F.struct("doc_id", "_t").alias("first"), F.col("lines").alias("a_lines"), F.col("words").alias("a_words"))
    b = rows.select(F.struct("doc_id", "_t").alias("me"), "lines", "words")

    both = asked.select("first", "me").distinct().join(a, "first").join(b, "me")
    both = both.select("me.doc_id", "me._t", "first", "a_lines", "a_words", "lines", "words")
    got = aligned = stored(both.mapInPandas(tidied(_align(*sizes, spare)), _PAIRS), "aligned")
    if spare and got.filter("doubt").limit(1).count():
        copies = alike_pairs(slim, got.filter("doubt").select("first", me.alias("me")), spare)
        copies = stored(copies.select("first", "me.doc_id", "me._t"), "copies")
        got = got.join(copies, ["first", "doc_id", "_t"], "left_anti")
    gone = got.select("doc_id", "_t", F.explode("gone").alias("g")).groupBy("doc_id", "_t").agg(F.sort_array(F.collect_set("g")).alias("gone"))
    gone = stored(gone, "gone")
    for done in (rows, asked, aligned):
        forget(done)
    return gone


def alike_pairs(docs: DataFrame, pairs: DataFrame, similarity: float) -> DataFrame:
    """Of ``first, me`` pairs, those whose texts are near copies by the edit distance of their words."""
    from featgreedy.llm.ominhash import alike, word_numbers

    def numbers(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("k"), pa.array([word_numbers(t.as_py()).tobytes() for t in batch.column("text")], pa.binary())], ["k", "seq"])

    def check(batches):
        for pdf in batches:
            ok = [alike(np.frombuffer(x, np.uint32), np.frombuffer(y, np.uint32), similarity) for x, y in zip(pdf["a_seq"], pdf["b_seq"], strict=True)]
            yield pdf.loc[ok, ["first", "me"]]

    kind = pairs.schema["me"].dataType.simpleString()
    some = stored(pairs.select(F.explode(F.array("first", "me")).alias("k")).distinct(), "named")
    texts = docs.select(F.struct("doc_id", "_t").alias("k"), "text").join(small(some), "k", "left_semi")
    seqs = texts.mapInArrow(tidied(numbers), f"k {kind}, seq binary")  # words as numbers travel, texts stay
    seqs = stored(seqs.groupBy("k").agg(F.max("seq").alias("seq")), "numbers")
    by = lambda c, s: seqs.select(F.col("k").alias(c), F.col("seq").alias(s))
    both = pairs.join(by("first", "a_seq"), "first").join(by("me", "b_seq"), "me").select("first", "me", "a_seq", "b_seq")
    return both.mapInPandas(tidied(check), f"first {kind}, me {kind}")


#: Columns that :func:`drop_blocks` adds; input columns of these names keep their values under a leading underscore.
ADDED = ("kept_text", "n_lines", "n_removed")


def drop_blocks(docs: DataFrame, min_line_words: int = 5, min_block_words: int = 5, spare: float | None = None) -> DataFrame:
    """``docs`` plus ``kept_text, n_lines, n_removed``."""
    gone = find_blocks(docs, min_line_words, min_block_words, spare)
    docs = docs.withColumnsRenamed({c: f"_{c}" for c in docs.columns if c in ADDED})
    cells = gone.agg(F.sum(F.size("gone") + 4)).first()[0] or 0
    gone = gone.select(F.col("doc_id").alias("__fg_d"), F.col("_t").alias("__fg_u"), F.col("gone").alias("__fg_gone"))
    out = docs.join(F.broadcast(gone) if cells <= BROADCAST_CELLS else gone, (F.col("doc_id") == F.col("__fg_d")) & (F.xxhash64("text") == F.col("__fg_u")), "left")
    out = out.withColumn("__fg_l", F.split("text", "\n"))  # a step of its own, so that the lambda below reads an array
    numbers = F.sequence(F.lit(0), F.size("__fg_l") - 1)
    keep = F.concat_ws("\n", F.transform(F.array_except(numbers, "__fg_gone"), lambda i: F.get("__fg_l", i)))
    whole = F.col("__fg_gone").isNull()
    return out.select(
        *docs.columns,
        F.when(whole, F.col("text")).otherwise(keep).alias("kept_text"),
        F.when(F.col("text").isNull(), 0).otherwise(F.size("__fg_l")).alias("n_lines"),
        F.when(whole, 0).otherwise(F.size("__fg_gone")).alias("n_removed"),
    )


def contract(docs: DataFrame) -> DataFrame:
    out = drop_blocks(docs.select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("kept_text", F.lit("")), 256).alias("kept_sha256"))


ship(__name__)
