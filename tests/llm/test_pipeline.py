import random

import corpus_pipeline as cp
from featgreedy.llm import queries


def tables(spark, path, docs, bench, labels):
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(bench, "item_id long, text string").write.parquet(f"{path}/benchmark.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")


def test_pipeline_takes_each_decision(spark, tmp_path):
    rng = random.Random(1)
    pool = ["".join(rng.choice("abcdefghijk") for _ in range(rng.randrange(3, 8))) for _ in range(2000)]
    say = lambda n: " ".join(rng.choice(pool) for _ in range(n)).capitalize() + "."
    good = {i: "\n".join(say(20) for _ in range(4)) for i in range(200)}
    junk = {i: say(40).upper().replace(" ", "!! ") for i in range(200, 260)}
    texts = good | junk
    notice = "this notice of seven words repeats often"
    for i in (10, 20, 30):
        texts[i] = notice + "\n" + texts[i]
    texts[300] = texts[0]  # exact copy
    near = texts[1].split(" ")
    near[10] = "changed"
    texts[301] = " ".join(near).replace("\n", " \n x ")  # near copy, no line in common
    item = say(30)
    texts[302] = say(30) + "\n" + item + "\n" + say(30)
    docs = [(i, t, "en", f"s{i % 3}", len(t)) for i, t in texts.items()]
    tables(spark, str(tmp_path), docs, [(0, item)], [(i, int(i < 200), 0) for i in texts if i < 260])
    out = cp.run(spark, str(tmp_path)).toPandas().set_index("doc_id")
    assert not set(out.index) & (set(junk) | {300, 301, 302})
    assert len(set(out.index) & set(good)) == len(good)
    assert out.loc[10, "text"].startswith(notice) and not out.loc[20, "text"].startswith(notice)
    assert (out["n_chars"] == out["text"].str.len()).all()
    for _, g in out.groupby("source"):
        assert abs(g["taken"].sum() - g["target"].iloc[0]) <= g["size"].max()
    assert [n for n, _ in cp.STAGES] == ["quality classifier", "line dedup", "near-duplicate documents", "benchmark decontamination", "source mixing"]


def test_empty_tables_and_queries(spark, tmp_path):
    tables(spark, str(tmp_path), [], [], [])
    assert cp.run(spark, str(tmp_path)).count() == 0
    names = sorted(int(k[2:].split("_")[0]) for k in queries.QUERIES)
    assert names == list(range(1, 11)) and set(queries.ORACLES) <= set(queries.QUERIES)


def test_stages_keep_columns_whose_names_clash(spark, tmp_path):
    from pyspark.sql import functions as F

    rows = [(1, "one two three four five six\nseven", "en", "a", 31), (2, "one two three four five six\neight nine ten eleven twelve", "en", "a", 55), (3, None, None, None, None), (3, None, None, None, None), (None, "", "en", "b", 0)]
    tables(spark, str(tmp_path), rows, [(1, "x")], [])
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for c in ("n_removed", "kept_text", "gone", "edge", "prefix", "_k", "component", "id", "key", "tag", "item_ids", "score", "y"):
        docs = docs.withColumn(c, F.lit(f"own {c}"))
    names = docs.columns
    for name, stage in cp.STAGES[:-1]:
        docs = stage(spark, docs, str(tmp_path))
        assert docs.columns == names, name
        assert docs.filter(" AND ".join(f"{c} = 'own {c}'" for c in names[5:])).count() == docs.count(), name
    got = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert got[2] == "eight nine ten eleven twelve" and got[3] is None
    assert cp.STAGES[-1][1](spark, docs, str(tmp_path)).filter("prefix = 'own prefix'").count() == docs.count()
