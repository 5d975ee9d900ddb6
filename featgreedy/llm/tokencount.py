"""Token counts through a cache keyed by digests of normalised content and of the tokenizer version.

Normalising joins runs of blanks, tabs and line ends to one blank and trims; the tokenizer gives the same
count before and after, which :func:`normalise` relies on and a test checks. The cache is a Parquet table
``(tokenizer, digest, n_tokens)``. Texts are digested in the JVM; distinct digests are joined to the cache;
only the distinct misses are encoded, and their counts are appended. Copies, however many, meet as equal
digests under partial aggregates and are encoded once.

A miss is encoded chunk by chunk between blanks, since no token of this tokenizer family spans one; each
worker remembers the counts of chunks it has met, in a table of bounded size.

Only digests are grouped: a text is encoded where it lies, if its digest is new and its row has the smallest id
of those that share it (rows equal in text and id encode each; their counts agree).

Null text counts as empty: 0 bytes, 0 tokens. Repeated rows each get their row back. The query keeps its cache at
``CACHE_SETTING`` of the session where that is set, else in a folder of its own.
"""

from __future__ import annotations

import hashlib
import os

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from featgreedy.llm.common import shared_dir, ship, small, stored, tidied

#: Session setting that names a lasting cache.
CACHE_SETTING = "spark.featgreedy.tokenCache"
SCHEMA = "tokenizer string, digest string, n_tokens long"
#: Chunk counts that one worker remembers before it starts anew.
REMEMBERED = 400_000


def normalise(text: str) -> Column:
    return F.regexp_replace(F.regexp_replace(F.coalesce(F.col(text), F.lit("")), r"[ \t\n\r]+", " "), r"^ | $", "")


def tokenizer_version(path: str) -> str:
    """Digest of the library, its version and the vocabulary file."""
    import tokenizers

    with open(path, "rb") as f:
        return hashlib.sha256(f"tokenizers {tokenizers.__version__} ".encode() + f.read()).hexdigest()


def chunk_counter(path: str):
    """A function from a list of normalised texts to their token counts."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(path)
    known: dict[str, int] = {"": 0}

    def count(texts) -> list[int]:
        out = []
        for text in texts:
            words = text.split(" ")
            new = list({w for w in words if w not in known})
            for lo in range(0, len(new), 4096):
                part = new[lo : lo + 4096]
                for w, e in zip(part, tok.encode_batch_fast(part, add_special_tokens=False), strict=True):
                    known[w] = len(e)
            out.append(sum(map(known.__getitem__, words)))
            if len(known) > REMEMBERED:
                known.clear()
                known[""] = 0
        return out

    return count


def _encode(path: str):
    def run(batches):
        count = chunk_counter(path)
        for pdf in batches:
            yield pd.DataFrame({"digest": pdf["digest"], "n_tokens": count(pdf["content"])})

    return run


def read_cache(spark: SparkSession, path: str) -> DataFrame:
    """The cache table; an empty one where nothing has been written yet."""
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    if p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p):
        return spark.read.schema(SCHEMA).parquet(path)
    return spark.createDataFrame([], SCHEMA)


def count_tokens(docs: DataFrame, tokenizer_path: str, cache_path: str, limit: int = 2048) -> DataFrame:
    """All columns of ``docs`` but the text, plus ``n_bytes, n_tokens, over_limit``; appends to the cache."""
    spark, version = docs.sparkSession, tokenizer_version(tokenizer_path)
    docs = docs.withColumnsRenamed({c: f"_{c}" for c in docs.columns if c in ("n_bytes", "n_tokens", "over_limit", "digest", "content")})
    marked = docs.withColumn("digest", F.sha2(normalise("text"), 256))
    known = read_cache(spark, cache_path).filter(F.col("tokenizer") == version).select("digest").distinct()
    keys = stored(marked.withColumn("n_bytes", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long")).drop("text"), "keys")
    # digests travel, texts stay: of equal texts one holder is encoded where it lies, of known ones none
    held = keys.groupBy("digest").agg(F.min("doc_id").alias("holder"), F.count("*").alias("n"))
    skip = held.join(known.withColumn("old", F.lit(True)), "digest", "left").filter("old OR n > 1")
    skip = stored(skip.select(F.col("digest").alias("__fg_x"), F.when(~F.coalesce("old", F.lit(False)), F.col("holder")).alias("__fg_h"), F.coalesce("old", F.lit(False)).alias("__fg_old")), "repeats")
    texts = docs.select("doc_id", normalise("text").alias("content")).withColumn("digest", F.sha2("content", 256))
    texts = texts.join(small(skip), F.col("digest") == F.col("__fg_x"), "left")
    texts = texts.filter(F.col("__fg_x").isNull() | (~F.col("__fg_old") & F.col("doc_id").eqNullSafe(F.col("__fg_h")))).select("digest", "content")
    fresh = texts.mapInPandas(tidied(_encode(tokenizer_path)), "digest string, n_tokens long")
    fresh.select(F.lit(version).alias("tokenizer"), "digest", "n_tokens").write.mode("append").parquet(cache_path)
    counts = read_cache(spark, cache_path).filter(F.col("tokenizer") == version).groupBy("digest").agg(F.max("n_tokens").alias("n_tokens"))
    out = keys.join(counts, "digest").drop("digest")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)


def contract(docs: DataFrame, cache_path: str | None = None) -> DataFrame:
    import uuid

    import public_tokenizers

    cache = cache_path or docs.sparkSession.conf.get(CACHE_SETTING, None) or f"{shared_dir(docs.sparkSession)}/featgreedy/token-cache-{uuid.uuid4().hex}"
    out = count_tokens(docs.select("doc_id", "text"), public_tokenizers.path("word_bpe_49k.json"), cache)
    return out.select("doc_id", "n_bytes", "n_tokens", "over_limit")


ship(__name__)
