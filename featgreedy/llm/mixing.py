"""Source mixing by capped water-filling, and seeded whole and fractional repetitions; DataFrame functions only.

Sizes are counts of runs outside ``[\\x20\\x09-\\x0D]``. Targets start proportional to the sources'
weights; a source whose share exceeds ``max_epochs`` times its size is clamped there and its excess is
dealt again by weight among the rest until none exceeds its cap. Epochs = target / source size. A document
is taken ``floor(epochs)`` whole times, and once more if it lies in the seeded order before the point where
the fractional part of the target is used up. That point is found by three rounds of histograms over digits
of the seeded hash of id and text, so no source, however large, is ever sorted in one task; rows equal in both are
one counted row there, and where the point falls among them their places in a stored table decide.

Null or empty text: size 0, taken 0. Null source: a source of its own, last in order. Repeated rows take
part each by itself, so some of a number of equal rows may be taken once more than others. Empty tables give
empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from featgreedy.llm.common import BROADCAST_ROWS, stored

#: The weights that sources take in turn, by code point, null last.
WEIGHTS = (3, 1, 2)
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: str) -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def water_fill(sizes: DataFrame, share: float, max_epochs: float) -> DataFrame:
    """``source, source_size, weight`` -> plus ``target``.

    One row per source: a table of the sources' names, not of rows. With caps ``c_i`` and weights ``w_i``
    the clamped set is a prefix in the order of ``c_i / w_i``, so the level at which the pouring stops
    follows from running sums instead of a loop.
    """
    ratio = sizes.withColumn("all_size", F.sum("source_size").over(Window.partitionBy())).withColumn("cap", F.lit(float(max_epochs)) * F.col("source_size"))
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("place"))
    run = ratio.withColumn("total", F.least(F.lit(float(share)) * F.col("all_size"), F.lit(float(max_epochs)) * F.col("all_size")))
    run = run.withColumn("cap_before", F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
    run = run.withColumn("weight_left", F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
    run = run.withColumn("level", (F.col("total") - F.col("cap_before")) / F.col("weight_left"))
    # the first source in this order whose cap is not reached at its level sets the level of all after it
    level = F.first(F.when(F.col("cap") >= F.col("level") * F.col("weight"), F.col("level")), ignorenulls=True)
    run = run.withColumn("final_level", level.over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return run.withColumn(
        "target", F.coalesce(F.least(F.col("cap"), F.col("final_level") * F.col("weight")), F.col("cap"))
    ).select("source", "source_size", "target")


def mix(docs: DataFrame, share: float = 1.5, max_epochs: float = 2.0, weights=WEIGHTS, seed: str = "mix", slim_only: bool = False) -> DataFrame:
    """All columns of ``docs`` plus ``size, source_size, target, taken``; ``slim_only``: of the columns, ``doc_id`` alone.

    Texts are read once for the sizes (a small table of keys and sizes is kept) and once more for the result.
    """
    key = F.md5(F.concat(F.lit(f"{seed}|"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.lit("|"), F.md5(F.coalesce("text", F.lit("")))))
    own = {"size": "_size", "source_size": "_source_size", "target": "_target", "taken": "_taken"}
    docs = docs.withColumnsRenamed({c: own[c] for c in docs.columns if c in own})  # clashing names keep their values
    slim = stored(docs.select("doc_id", "source", word_count("text").alias("size"), key.alias("_k")), "sizes")
    base = slim
    per = stored(base.groupBy("source").agg(F.sum("size").alias("source_size")), "sources")
    few = per.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    by_name = Window.orderBy(F.col("source").isNull(), F.encode("source", "utf-8"))
    per = per.withColumn("place", F.row_number().over(by_name))
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    per = per.withColumn("weight", F.element_at(cycle, (F.pmod(F.col("place") - 1, F.lit(len(weights))) + 1).cast("int")))
    goal = water_fill(per, share, max_epochs)
    goal = goal.withColumn("_whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long"))
    goal = goal.withColumn("_left", F.col("target") - F.col("_whole") * F.col("source_size"))
    cut = goal.filter("_left > 0").select("source", F.col("_left").alias("left"))
    # three rounds: 4096 bins of the hash, then 4096 bins inside the bin where the target is met, then rows
    state = cut.withColumn("prefix", F.lit(""))
    sent = lambda t: F.broadcast(t) if few else t  # one row per source: broadcast while sources are few, else joined
    named = lambda t: sent(t.withColumnRenamed("source", "_s"))
    same = F.col("source").eqNullSafe(F.col("_s"))
    for at in (1, 4):
        inside = slim.join(named(state), same).filter(F.substring("_k", 1, at - 1) == F.col("prefix")).select("source", "size", F.substring("_k", 1, at + 2).alias("bin"), "left")
        bins = inside.groupBy("source", "left", "bin").agg(F.sum("size").alias("n"))
        upto = Window.partitionBy("source", "left").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
        bins = bins.withColumn("cum", F.sum("n").over(upto)).filter(F.col("cum") >= F.col("left"))
        state = bins.groupBy("source", "left").agg(F.min(F.struct("bin", "cum", "n")).alias("b")).select("source", (F.col("left") - (F.col("b.cum") - F.col("b.n"))).alias("left"), F.col("b.bin").alias("prefix"))
        state = state.withColumn("left", F.round("left", 6))
    # rows of one hash are equal in id and text: one row with their number, however many they are
    last = slim.join(named(state), same).filter(F.substring("_k", 1, 6) == F.col("prefix")).groupBy("source", "left", "_k", "size").agg(F.count("*").alias("m"))
    order = Window.partitionBy("source").orderBy("_k").rowsBetween(Window.unboundedPreceding, 0)
    all_of = F.col("m") * F.col("size")
    last = last.withColumn("rest", F.col("left") - (F.sum(all_of).over(order) - all_of))
    # a document on the edge is taken when its middle lies before the target; of equal ones, so many as do
    fit = F.when(F.col("size") > 0, F.least("m", F.floor(F.col("rest") / F.col("size") + 0.5))).otherwise(F.col("m"))
    last = last.withColumn("fit", fit).filter("rest >= 0 AND fit > 0")
    edge = last.groupBy("source").agg(F.max(F.struct("_k", "m", "fit")).alias("edge"))
    goal = goal.join(named(edge), same, "left").drop("_s").join(named(state.select("source", "prefix")), same, "left").drop("_s")
    goal = stored(goal, "targets")
    g = goal.select(F.col("source").alias("__fg_s"), "source_size", "target", *[F.col(c).alias(f"__fg{c}") for c in ("_whole", "_left")], *[F.col(c).alias(f"__fg_{c}") for c in ("edge", "prefix")])
    if slim_only:
        base = slim.withColumnsRenamed({"_k": "__fg_k"})
    else:
        base = docs.withColumn("size", word_count("text")).withColumn("__fg_k", key)
    bin_, cut_at, last_key = F.substring("__fg_k", 1, 6), F.col("__fg_prefix"), F.col("__fg_edge._k")
    tied = (F.col("__fg_k") == last_key) & (F.col("__fg_edge.fit") < F.col("__fg_edge.m"))
    more = F.when(F.col("__fg_left") <= 0, 0).when(bin_ < cut_at, 1).when((bin_ == cut_at) & (F.col("__fg_k") <= last_key), 1).otherwise(0)
    out = base.join(sent(g), F.col("source").eqNullSafe(F.col("__fg_s")))
    if not goal.filter("edge.fit < edge.m AND _left > 0").limit(1).count():
        out = out.withColumn("__fg_more", more)
    else:  # equal rows across the edge, kept apart by their place in a stored table
        ties = stored(out.filter(tied).withColumn("__fg_r", F.monotonically_increasing_id()), "ties")
        part = F.shiftright("__fg_r", 33)
        per_part = ties.groupBy("__fg_s", part.alias("__fg_p")).agg(F.count("*").alias("__fg_n"))
        upto = Window.partitionBy("__fg_s").orderBy("__fg_p").rowsBetween(Window.unboundedPreceding, 0)
        per_part = per_part.select(F.col("__fg_s").alias("__fg_s2"), "__fg_p", (F.sum("__fg_n").over(upto) - F.col("__fg_n")).alias("__fg_b"))
        ties = ties.withColumn("__fg_q", part).join(per_part, F.col("__fg_s").eqNullSafe(F.col("__fg_s2")) & (F.col("__fg_q") == F.col("__fg_p")))
        place = F.col("__fg_b") + F.row_number().over(Window.partitionBy("__fg_s", "__fg_q").orderBy("__fg_r"))
        ties = ties.withColumn("__fg_more", F.when(F.col("__fg_left") > 0, (place <= F.col("__fg_edge.fit")).cast("int")).otherwise(0))
        names = [*out.columns, "__fg_more"]
        out = out.filter(~F.coalesce(tied, F.lit(False))).withColumn("__fg_more", more).select(names).union(ties.select(names))
    out = out.withColumn("taken", F.col("size") * (F.col("__fg_whole") + F.col("__fg_more")))
    return out.drop(*[f"__fg_{c}" for c in ("k", "s", "whole", "left", "edge", "prefix", "more")])


def contract(docs: DataFrame) -> DataFrame:
    return mix(docs, slim_only=True).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = r"""
WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
                  md5('mix|' || coalesce(doc_id::VARCHAR, 'null') || '|' || md5(coalesce(text, ''))) AS k FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
o AS (SELECT *, row_number() OVER (ORDER BY source IS NULL, encode(source)) AS place FROM s),
w AS (SELECT *, [3.0::DOUBLE, 1.0::DOUBLE, 2.0::DOUBLE][((place - 1) % 3 + 1)::INT] AS weight, 2.0::DOUBLE * source_size AS cap,
             1.5::DOUBLE * (SELECT sum(source_size) FROM s) AS total FROM o),
r AS (SELECT *, (total - coalesce(sum(cap) OVER (ORDER BY cap / weight, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
             / sum(weight) OVER (ORDER BY cap / weight, place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS lev FROM w),
f AS (SELECT *, (SELECT r2.lev FROM r r2 WHERE r2.cap >= r2.lev * r2.weight ORDER BY r2.cap / r2.weight, r2.place LIMIT 1) AS final_level,
             (SELECT min(r2.cap / r2.weight) FROM r r2 WHERE r2.cap >= r2.lev * r2.weight) AS from_ratio FROM r),
t AS (SELECT source, source_size, CASE WHEN cap / weight >= from_ratio THEN least(cap, final_level * weight) ELSE cap END AS target FROM f),
g AS (SELECT d.*, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN floor(t.target / t.source_size) ELSE 0 END AS whole
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
c AS (SELECT *, target - whole * source_size AS rest,
             sum(size) OVER (PARTITION BY source ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - size AS before FROM g)
SELECT doc_id, size, source_size, target,
       (size * (whole + CASE WHEN rest > 0 AND before + size / 2.0 <= rest THEN 1 ELSE 0 END))::BIGINT AS taken FROM c
"""
