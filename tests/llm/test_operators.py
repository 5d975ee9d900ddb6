import collections
import hashlib
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from featgreedy.llm import chat, decontam, embeddup, linededup, mixing, ominhash, quality, suffix, tokencount, toxicity
from featgreedy.llm.common import components, shared_dir, slices, small, stored

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t)) for i, t, s in rows], DOCS)


def words(rng, n, size=400, letters="abcdeé"):
    pool = ["".join(rng.choice(letters) for _ in range(rng.randrange(2, 7))) for _ in range(size)]
    return lambda k=n: " ".join(rng.choice(pool) for _ in range(k))


# shared parts


def test_components_of_paths_stars_and_loops(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, i) for i in range(101, 160)] + [(200, 201), (201, 202), (202, 200), (300, 300)]
    got = dict(components(spark.createDataFrame(edges, "a long, b long"), "a", "b").collect())
    assert all(got[i] == 0 for i in range(41)) and all(got[i] == 100 for i in range(101, 160)) and got[201] == got[202] == 200
    assert 300 not in got
    assert components(spark.createDataFrame([], "a long, b long"), "a", "b").count() == 0


def test_slices_cover_rows_in_bounded_parts():
    at = np.array([0, 5, 5, 100, 101, 400])
    parts = list(slices(at, 100))
    assert [p[0] for p in parts] == [0] + [p[1] for p in parts[:-1]] and parts[-1][1] == 5


def test_stored_and_small(spark):
    df = stored(spark.range(5), "x")
    assert df.count() == 5 and df.stored_path.startswith(shared_dir(spark))
    assert "broadcast" in small(df)._jdf.queryExecution().logical().toString().lower()
    assert "broadcast" not in small(df, 2)._jdf.queryExecution().logical().toString().lower()


# 1 chat


def conversations(spark, rows):
    return spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")


def test_chat_recovers_roles_in_every_style(spark):
    rows, rng = [], random.Random(1)
    say = words(rng, 12)
    for c in range(40):
        order = (["system"] if c % 3 == 0 else []) + ["user", "assistant", "tool" if c % 4 == 0 else "user", "assistant"] * (1 + c % 3)
        rows += [(c, i, r, "\n".join(say() for _ in range(1 + (i + c) % 3)) + ("?" if r == "user" else ".")) for i, r in enumerate(order)]
    rows += [(100, i, ("user", "assistant")[i % 2], say()) for i in range(600)]  # several parts
    df = conversations(spark, rows)
    raw = chat.transcripts(df)
    assert raw.filter("conv_id = 100").count() == 3 and raw.filter("context IS NOT NULL").count() == 2
    got = chat.contract(df).collect()
    want = collections.Counter((c, i, r, hashlib.sha256(t.encode()).hexdigest()) for c, i, r, t in rows)
    assert collections.Counter((r["conv_id"], r["turn"], r["role"], r["text_sha256"]) for r in got) == want
    one = chat.parse(raw, chat.fit(chat.sample(df), chat.role_names(df))).filter("conv_id = 8").first()
    assert one["rendered"] == chat.render([(r, t) for c, _, r, t in rows if c == 8])


def test_lines_that_look_like_markers_of_another_style_are_text(spark):
    rng = random.Random(5)
    say = words(rng, 9)
    rows = []
    for c in range(60):
        rows += [(c, 0, "user", say() + "?"), (c, 1, "assistant", "Q: " + say() + "\nA: " + say() + "\nHuman: " + say())]
        rows += [(c, 2, "user", say()), (c, 3, "assistant", say())]
    df = conversations(spark, rows)
    raw = chat.transcripts(df)
    model = chat.fit(chat.sample(df))
    for r in raw.filter("transcript NOT LIKE 'Q: %' AND transcript NOT LIKE 'User: %'").collect():
        assert [x for x, _ in chat.turns(model, r["transcript"])] == ["user", "assistant"] * 2
    for r in raw.filter("transcript LIKE 'User: %'").collect():  # here ``Human:`` is of the transcript's own style
        assert "Q: " in dict(enumerate(t for _, t in chat.turns(model, r["transcript"])))[1]


def test_chat_unmarked_turn_is_found_by_line_features():
    model, pattern = chat.Model(), chat.marker_pattern()
    for _ in range(20):
        kinds, rest, _ = chat.observe(["User: short?", "a long answer " * 20], pattern)
        model.add(np.array([2, 4]), np.column_stack([kinds[:, 0], rest]))
    assert [r for r, _ in chat.turns(model.tables(), "User: again?\n" + "a long answer " * 20)] == ["user", "assistant"]


def test_chat_edges(spark):
    df = conversations(spark, [(1, 0, None, None), (None, 0, "user", "x"), (2, None, "user", ""), (2, None, "user", ""), (3, 1, " Human ", "y"), (3, 2, "", "z")])
    got = sorted((r["conv_id"], r["turn"], r["role"]) for r in chat.contract(df).collect())
    assert got == [(1, 0, "unknown"), (2, 0, "user"), (2, 1, "user"), (3, 0, "user"), (3, 1, "unknown")]
    assert chat.contract(conversations(spark, [])).count() == 0
    assert chat.turns(chat.Model().tables(), None) == []
    crowd = conversations(spark, [(1, 0, "user", f"t{i}") for i in range(50)])
    assert chat.transcripts(crowd, most=20).count() > 1 and chat.parse(chat.transcripts(crowd, most=20), chat.Model().tables()).agg(F.sum(F.size("roles"))).first()[0] == 50


def test_viterbi_equals_enumeration():
    import itertools

    rng = np.random.default_rng(2)
    model = chat.Model()
    model.move += rng.random((chat.STATES, chat.STATES))
    tables = model.tables()
    start, move, see, _ = tables
    kinds = rng.integers(0, chat.SIZES[0], (3, len(chat.STYLES)))
    rest = np.column_stack([rng.integers(0, n, 3) for n in chat.SIZES[1:]])

    def total(path, style):
        seen = np.column_stack([kinds[:, style], rest])
        s = start[path[0]] + sum(t[path[0], seen[0, f]] for f, t in enumerate(see))
        return s + sum(move[a, b] + sum(t[b, seen[i, f]] for f, t in enumerate(see)) for i, (a, b) in enumerate(zip(path, path[1:], strict=False), 1))

    paths = itertools.product(range(chat.STATES), repeat=3)
    best = max(total(p, s) for p in paths for s in range(len(chat.STYLES)))
    found = chat.viterbi(tables, kinds, rest)
    assert max(total(found, s) for s in range(len(chat.STYLES))) == pytest.approx(best)


# 2 lines


def test_patience_alignment():
    assert linededup.patience([1, 2, 3, 4], [9, 1, 2, 8, 3, 4]) == [(0, 1), (1, 2), (2, 4), (3, 5)]
    assert linededup.patience([], [1]) == []
    assert linededup.doomed([1, 2, 3], [7, 1, 2, 8, 3], [5, 4, 4, 5, 9], 8) == [1, 2, 4]
    assert linededup.doomed([1, 2, 3], [7, 1, 2, 8, 3], [5, 1, 1, 5, 1], 8) == []


def test_lines_are_asked_of_later_holders_and_in_windows(spark):
    rng = random.Random(31)
    say = words(rng, 8, 3000, "abcdefghijkl")
    p, q = [say() for _ in range(6)], [say() for _ in range(9)]
    short = [say(2) for _ in range(40)]
    han = ["".join(chr(0x4E00 + rng.randrange(3000)) for _ in range(40)) for _ in range(3)]
    own = lambda *parts: "\n".join([say(), *[x for part in parts for x in [*part, say()]]])
    rows = [own(p, p), own(p), own(p)]  # the first holder repeats the passage
    rows += [own(q, short[:3], han), own(q[4:], q[:4]), own(q[4:], q[:4])]  # two blocks in another order
    rows += [own(short[3:]), own(short[3:])]
    rows += [own(han)]
    got = {r["doc_id"]: r["n_removed"] for r in linededup.drop_blocks(docs_frame(spark, [(i, t, "s") for i, t in enumerate(rows)])).collect()}
    assert got == {0: 0, 1: 6, 2: 6, 3: 0, 4: 9, 5: 9, 6: 0, 7: 37, 8: 3}


@pytest.mark.parametrize("seed", [3, 4])
def test_lines_against_all_earlier_documents(spark, seed):
    """A line goes if it lies in a run of five words or more that some earlier document has too; none is aligned here."""
    rng = random.Random(seed)
    say = words(rng, 8, 3000, "abcdefghijkl")
    pool = [say(rng.choice([1, 2, 3, 8, 9])) for _ in range(60)]
    texts = []
    for _ in range(70):
        parts, used = [], set()
        for _ in range(rng.randrange(1, 5)):
            at, n = rng.randrange(60), rng.randrange(1, 9)
            parts += [x for x in pool[at : at + n] if x not in used] + [say()]
            used.update(pool[at : at + n])
        texts.append("\n".join(parts))
    texts += [texts[0], None, ""]
    long = say(9)
    texts += ["\n".join([long, say()]), "\n".join([long, "short x", say()]), "\n".join([long, "short x", say()])]
    rows = [(i, t, "s") for i, t in enumerate(texts)]
    got = {r["doc_id"]: r for r in linededup.drop_blocks(docs_frame(spark, rows).repartition(5)).collect()}
    for i, t in enumerate(texts):
        if t is None:
            assert got[i]["kept_text"] is None and got[i]["n_lines"] == 0
            continue
        mine, gone = t.split("\n"), set()
        for u in texts[:i]:
            theirs = (u or "").split("\n")
            for x in range(len(theirs)):
                for y in range(len(mine)):
                    n = 0
                    while x + n < len(theirs) and y + n < len(mine) and theirs[x + n] == mine[y + n]:
                        n += 1
                        if sum(len(z.split()) for z in mine[y : y + n]) >= 5:
                            gone |= set(range(y, y + n))
        assert got[i]["kept_text"] == "\n".join(x for k, x in enumerate(mine) if k not in gone), i
        assert got[i]["n_removed"] == len(gone)
    assert got[70]["kept_text"] == "" and "short x" not in got[75]["kept_text"]


def test_copies_are_spared_with_the_blocks_they_share_with_others(spark):
    rng = random.Random(8)
    say = words(rng, 9, 3000, "abcdefghijkl")
    notice, body = [say() for _ in range(3)], [say() for _ in range(12)]
    near = [x.replace(x.split(" ")[2], "changed", 1) if k % 3 == 0 else x for k, x in enumerate(body)]
    far = body[:6] + [say() for _ in range(9)]
    texts = [notice + [say() for _ in range(9)], notice + body, notice + near, far]
    df = docs_frame(spark, [(i, "\n".join(t), "s") for i, t in enumerate(texts)])
    got = {r["doc_id"]: r["n_removed"] for r in linededup.drop_blocks(df, spare=0.8).collect()}
    assert got == {0: 0, 1: 3, 2: 3, 3: 6}
    assert linededup.drop_blocks(df).filter("doc_id = 2").first()["n_removed"] == 11


def test_line_edges(spark):
    assert linededup.contract(docs_frame(spark, [])).count() == 0
    df = docs_frame(spark, [(1, "one two three four five six", "s")] * 2).withColumn("gone", F.lit(1)).withColumn("n_removed", F.lit("x"))
    out = linededup.drop_blocks(df)
    assert [(r["n_removed"], r["_n_removed"], r["gone"]) for r in out.collect()] == [(0, "x", 1)] * 2


# 3 toxicity, 9 quality


def labelled(spark, n=400):
    rng = random.Random(4)
    say, docs, labels = words(rng, 9), [], []
    for i in range(n):
        bad, junk = rng.random() < 0.25, rng.random() < 0.3
        sents = [say() + "." for _ in range(rng.randrange(1, 6))]
        if bad:
            sents[rng.randrange(len(sents))] = say(3) + " " + rng.choice(["vilest", "rottens", "scumble"]) + "."
        t = " ".join(sents)
        docs.append((i, t.upper().replace(" ", "!! ") if junk else t, "s"))
        labels.append((i, int(not junk), int(bad)))
    return docs_frame(spark, docs), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_toxicity_on_held_out_rows(spark):
    docs, labels = labelled(spark)
    got = toxicity.contract(docs, labels).join(labels, "doc_id").filter("held_out").toPandas()
    assert set(got["doc_id"].map(lambda i: zlib.crc32(str(i).encode()) % 4)) == {2}
    assert ((got["score"] >= 0.3) == (got["toxic"] == 1)).mean() > 0.95 and got["score"].between(0, 1).all()


def test_toxicity_locates_sentences_and_handles_edges(spark):
    m = toxicity.NoisyOr(-5.0, {"bad": 9.0})
    assert m.locate("All fine. This is bad! Fine again.") == [1]
    assert m.score(None) == m.score("") == 0.0
    n, parts = m.parts("one two. bad three.\n\nfour")
    assert n == 3 and m.score("one two. bad three.\n\nfour") == pytest.approx(1 - (1 - 1 / (1 + np.exp(5))) ** 2 * (1 - parts[0][1]))
    docs = docs_frame(spark, [(1, None, "s"), (2, "", None), (2, "", None), (3, "word " * 20_000, "s")])
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert toxicity.contract(docs, none).count() == 4
    assert toxicity.contract(docs_frame(spark, []), none).count() == 0
    assert quality.contract(docs, none).filter("score between 0 and 1").count() == 4


def test_gradient_of_the_noisy_or_likelihood():
    rng = np.random.default_rng(16)
    owner, y = np.repeat(np.arange(12), 3), rng.integers(0, 2, 12).astype(float)
    pairs = np.unique(rng.integers(0, [36, 9], (150, 2)), axis=0)
    sent, word, w = pairs[:, 0], pairs[:, 1], rng.standard_normal(9)

    def value(w, bias):  # each document by itself: one less the product of its sentences' complements
        total = 0.0
        for d in range(12):
            clear = 1.0
            for s in np.flatnonzero(owner == d):
                clear *= 1 - 1 / (1 + np.exp(-bias - sum(w[k] for i, k in pairs if i == s)))
            total += np.log(1 - clear) if y[d] else np.log(clear)
        return total / 12

    got, grad = toxicity.ascent(sent, word, owner, y, w, -0.4)
    assert got == pytest.approx(value(w, -0.4))
    for k in range(10):
        e = np.eye(10)[k] * 1e-6
        assert grad[k] == pytest.approx((value(w + e[:9], -0.4 + e[9]) - value(w - e[:9], -0.4 - e[9])) / 2e-6, abs=1e-6)


def test_equal_cosines_go_to_earlier_rows():
    x = np.zeros((6, quality.BUCKETS), np.float32)
    x[:, 3] = 1
    m = quality.fit(x, np.array([1, 0, 1, 1, 0, 0], np.float32), dim=4)
    assert quality.vote(m, np.eye(1, quality.BUCKETS, 3) * 2.0, 3)[0] == pytest.approx(2 / 3)


def test_quality_on_held_out_rows(spark):
    docs, labels = labelled(spark)
    got = quality.contract(docs, labels).join(labels, "doc_id").filter("held_out").toPandas()
    assert ((got["score"] >= 0.7) == (got["quality"] == 1)).mean() > 0.95
    kept = quality.keep_good(docs, labels).join(labels, "doc_id").agg(F.avg("quality")).first()[0]
    assert kept > 0.97


def test_vote_equals_plain_neighbours():
    rng = np.random.default_rng(5)
    x = np.abs(rng.standard_normal((60, quality.BUCKETS))).astype(np.float32)
    y = rng.integers(0, 2, 60).astype(np.float32)
    m = quality.fit(x.copy(), y, dim=12)
    v = np.abs(rng.standard_normal((5, quality.BUCKETS)))
    z = v @ m["basis"]
    cos = (z / np.linalg.norm(z, axis=1, keepdims=True)) @ m["z"].T
    for i in range(5):
        near = np.argsort(-cos[i])[:7]
        w = np.exp(8 * (cos[i, near] - cos[i, near].max()))
        assert quality.vote(m, v, 7)[i] == pytest.approx((w * y[near]).sum() / w.sum(), abs=1e-5)


# 4 decontamination


def test_decontamination_against_brute_force(spark):
    rng = random.Random(6)
    say = words(rng, 14, letters="abcdefghij")
    bench = [(i, say()) for i in range(12)] + [(50, "tiny"), (51, None)]
    rows = []
    for i in range(60):
        t = say(40)
        if i % 2 == 0:
            item = list(rng.choice(bench[:12])[1])
            for _ in range(rng.randrange(0, 8)):
                p = rng.randrange(len(item))
                item[p] = rng.choice(["", "z", item[p] + "q"])
            t = t[:50] + " " + "".join(item).replace(" ", "\n ", 1) + " " + t[50:]
        rows.append((i, t, "s"))
    rows += [(98, None, "s"), (99, "", "s")]
    got = {r["doc_id"]: r for r in decontam.contract(docs_frame(spark, rows), spark.createDataFrame(bench, "item_id long, text string")).collect()}

    def best(p, t):
        prev = np.zeros(len(t) + 1, int)
        tt = np.array(list(t))
        for i, c in enumerate(p, 1):
            cur = np.minimum(prev[1:] + 1, prev[:-1] + (tt != c))
            cur = np.concatenate([[i], cur])
            cur = np.minimum.accumulate(cur - np.arange(len(cur))) + np.arange(len(cur))
            prev = cur
        return prev.min()

    for i, t, _ in rows:
        want = []
        for k, b in bench:
            b = decontam.plain(b)
            if b:
                d = best(b, decontam.plain(t)) if t else 99
                if d <= int(decontam.RATE * len(b)):
                    want.append((k, d))
        assert got[i]["item_ids"] == [k for k, _ in want], i
        assert got[i]["distances"] == [d for _, d in want]
    blocks = decontam.contaminated(docs_frame(spark, rows), spark.createDataFrame(bench, "item_id long, text string"), block_bytes=300)
    assert {r["doc_id"]: r["item_ids"] for r in blocks.collect()} == {i: g["item_ids"] for i, g in got.items()}
    assert decontam.contract(docs_frame(spark, rows), spark.createDataFrame([], "item_id long, text string")).filter("contaminated").count() == 0


def test_decontamination_of_repeated_rows_and_short_items(spark):
    rng = random.Random(61)
    say = words(rng, 14, letters="abcdefghij")
    bench = [(i, say()) for i in range(6)] + [(7, "a verbatim item of 30 signs ab"), (8, "yes"), (8, "no!"), (9, ""), (10, None)]
    text = say(9) + " " + bench[2][1] + " " + say(3) + " A verbatim\titem of 30 signs ab. " + say(4)
    rows = [(5, text, "s")] * 100 + [(None, text, "s")] * 3 + [(None, None, "t")] * 2 + [(1, "yes, it is", "s"), (2, "yesterday", "s"), (3, "say no! now", "s")]
    df, items = docs_frame(spark, rows).repartition(3), spark.createDataFrame(bench, "item_id long, text string")
    whole = collections.Counter((r["doc_id"], tuple(r["item_ids"]), tuple(r["distances"]), r["contaminated"]) for r in decontam.contaminated(df, items).collect())
    assert whole[5, (2, 7), (0, 0), True] == 100 and whole[None, (2, 7), (0, 0), True] == 3 and whole[None, (), (), False] == 2
    assert whole[1, (8,), (0,), True] == whole[3, (8,), (0,), True] == whole[2, (), (), False] == 1
    parts = collections.Counter((r["doc_id"], tuple(r["item_ids"]), tuple(r["distances"]), r["contaminated"]) for r in decontam.contaminated(df, items, block_bytes=100).collect())
    assert parts == whole


# 5 mixing


def test_mixing_against_a_loop(spark):
    rng = random.Random(7)
    rows = [(i, " ".join("w" for _ in range(rng.randrange(0, 40))), s) for i, s in enumerate(["a"] * 150 + ["b"] * 12 + [None] * 40 + ["é"] * 3)]
    rows.append((500, None, "b"))
    got = mixing.contract(docs_frame(spark, rows)).toPandas().set_index("doc_id")
    size = collections.defaultdict(int)
    for _, t, s in rows:
        size[s] += len((t or "").split())
    names = sorted((s for s in size if s is not None), key=lambda s: s.encode()) + [None]
    weight = {s: (3, 1, 2)[k % 3] for k, s in enumerate(names)}
    target, left, free = {}, 1.5 * sum(size.values()), set(names)
    while True:
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if share[s] > 2 * size[s]}
        if not over:
            target |= share
            break
        for s in over:
            target[s] = 2.0 * size[s]
            left -= target[s]
        free -= over
    for i, t, s in rows:
        assert got.loc[i, "target"] == pytest.approx(target[s]) and got.loc[i, "size"] == len((t or "").split())
        assert got.loc[i, "taken"] in (0, got.loc[i, "size"], 2 * got.loc[i, "size"])
    for s in names:
        taken = sum(got.loc[i, "taken"] for i, _, x in rows if x == s)
        assert abs(taken - target[s]) <= 40
    again = mixing.contract(docs_frame(spark, rows[::-1])).toPandas().set_index("doc_id")
    assert (again["taken"].sort_index() == got["taken"].sort_index()).all()


def test_mixing_counts_equal_rows(spark):
    rows = [(7, "one two three four five six seven eight nine ten " * 2, "a")] * 160 + [(None, f"w{i} x", "b") for i in range(300)] + [(9, "y z", "c")] * 5
    df = docs_frame(spark, rows).repartition(4)
    for got in (mixing.contract(df).toPandas(), mixing.mix(df).toPandas()):
        assert len(got) == len(rows)
        for target, part in got.groupby("target"):
            assert abs(part["taken"].sum() - target) <= part["size"].max()
            assert (part["taken"] <= 2 * part["size"]).all()
    again = mixing.contract(df).toPandas()
    key = ["doc_id", "size", "source_size", "target", "taken"]
    assert sorted(map(tuple, again[key].fillna(-1).to_numpy().tolist())) == sorted(map(tuple, got[key].fillna(-1).to_numpy().tolist()))


def test_mixing_joins_when_sources_are_many(spark, monkeypatch):
    rows = [(i, "w " * (i % 7), f"s{i % 5}" if i % 11 else None) for i in range(120)]
    broadcast = mixing.contract(docs_frame(spark, rows)).toPandas().sort_values("doc_id").reset_index(drop=True)
    monkeypatch.setattr(mixing, "BROADCAST_ROWS", 2)
    joined = mixing.contract(docs_frame(spark, rows)).toPandas().sort_values("doc_id").reset_index(drop=True)
    assert broadcast.equals(joined)


def test_mixing_edges(spark):
    assert mixing.contract(docs_frame(spark, [])).count() == 0
    out = mixing.mix(docs_frame(spark, [(1, "a b", "s"), (1, "a b", "s"), (None, None, None)]).withColumn("size", F.lit("own")).withColumn("prefix", F.lit("mine")))
    assert out.filter("prefix = 'mine'").count() == out.count() == 3 and "_size" in out.columns and out.filter("size = 2").count() == 2
    assert mixing.contract(docs_frame(spark, [(1, "", "s"), (2, None, "t")])).agg(F.sum("taken")).first()[0] == 0


# 6 repeated byte strings


def repeats_by_hand(rows, length):
    count, out = collections.Counter(), []
    for _, t in rows:
        b = (t or "").encode()
        count.update(b[i : i + length] for i in range(len(b) - length + 1))
    for d, t in rows:
        b = np.frombuffer((t or "").encode(), np.uint8)
        m = np.zeros(len(b) + 1, int)
        for i in range(len(b) - length + 1):
            if count[b[i : i + length].tobytes()] > 1:
                m[i] += 1
                m[i + length] -= 1
        gone = np.cumsum(m[:-1]) > 0
        out.append((d, len(b), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(b[~gone].tobytes()).hexdigest()))
    return collections.Counter(out)


@pytest.mark.parametrize("seed,length,chunk", [(1, 200, None), (2, 64, None), (3, 200, 500)])
def test_byte_strings_against_brute_force(spark, monkeypatch, seed, length, chunk):
    if chunk:
        monkeypatch.setattr(suffix, "CHUNK", chunk)
    rng = random.Random(seed)
    say = words(rng, 150, 300)
    base = [say() for _ in range(12)]
    rows = []
    for i in range(80):
        t, k = rng.choice(base), rng.random()
        if k < 0.4:
            x = t.split(" ")
            for _ in range(rng.randrange(1, 6)):
                x[rng.randrange(len(x))] = "edit"
            t = " ".join(x)
        elif k < 0.6:
            s = rng.randrange(0, 300)
            t = say(20) + t[s : s + rng.randrange(length - 10, length + 120)] + say(20)
        elif k < 0.7:
            t = say(90)
        elif k < 0.78:
            t = "ab" * rng.randrange(0, 300)
        rows.append((i, t))
    rows += [(5, rows[5][1]), (None, base[0]), (None, None), (90, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = collections.Counter(tuple(r) for r in suffix.remove_repeats(df, length).collect())
    assert got == repeats_by_hand(rows, length)


def test_very_frequent_samples_are_dealt(spark):
    rng = random.Random(9)
    say = words(rng, 40, 3000, "abcdefghijkl")
    passage = say(60)[:230]
    rows = [(i, say() + passage + say()) for i in range(2300)]
    got = collections.Counter(tuple(r) for r in suffix.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), 200).collect())
    assert got == repeats_by_hand(rows, 200)


def test_byte_string_edges(spark):
    assert suffix.contract(docs_frame(spark, [])).count() == 0
    with pytest.raises(ValueError):
        suffix.remove_repeats(docs_frame(spark, []), 10)


# 7 tokens


def test_tokens_equal_the_library_and_the_cache_is_used(spark, tmp_path):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    rng = random.Random(10)
    say = words(rng, 30, letters="abcdÉß漢'1!")
    rows = [(i, say(), "s") for i in range(40)]
    rows += [(100, None, "s"), (101, "", "s"), (102, " \n\t a  b\r\nc d e\x1cf ́x ", "s"), (103, "<|endoftext|>x <|startoftext|> <|end oftext|>", "s"), (104, "word " * 3000, "s"), (105, "İΣΑΣ ŒUVRE don't we'll 12three", "s"), (40, rows[0][1], "t")]
    rows += [(106, rows[0][1] + "\n", "s")]
    df, cache = docs_frame(spark, rows), str(tmp_path / "cache")
    tok = Tokenizer.from_file(path)
    got = {r["doc_id"]: r for r in tokencount.contract(df, cache).collect()}
    for i, t, _ in rows:
        n = len(tok.encode(t or "", add_special_tokens=False).ids)
        assert (got[i]["n_tokens"], got[i]["n_bytes"], got[i]["over_limit"]) == (n, len((t or "").encode()), n > 2048), i
    first = spark.read.parquet(cache).count()
    assert first == len({" ".join(w for w in (t or "").replace("\r", " ").replace("\n", " ").replace("\t", " ").split(" ") if w) for _, t, _ in rows})
    tokencount.contract(df, cache).count()
    assert spark.read.parquet(cache).count() == first  # every digest was a hit
    assert tokencount.contract(docs_frame(spark, [])).count() == 0


def test_small_chunk_memory(monkeypatch):
    import public_tokenizers

    monkeypatch.setattr(tokencount, "REMEMBERED", 3)
    count = tokencount.chunk_counter(public_tokenizers.path("word_bpe_49k.json"))
    assert count(["a b c d", "a b c d"])[0] == count(["a b c d"])[0] == 4


# 8 vectors


def test_vectors_against_all_pairs(spark):
    rng = np.random.default_rng(11)
    base = rng.standard_normal((40, 16))
    rows = []
    for i in range(160):
        v = base[i % 40] + rng.choice([0.0, 0.05, 0.15, 0.3]) * rng.standard_normal(16)
        rows.append((i, [float(x) for x in v.astype(np.float32)], int(i % 3)))
    rows += [(200, rows[0][1], 0), (201, rows[0][1], 0), (202, rows[0][1], 1), (203, rows[0][1], None), (204, None, 1), (205, [0.0] * 16, 1), (206, [float("nan")] * 16, 1), (207, [None] * 16, 1), (208, [1.0, 2.0], 1), (209, [float("inf")] + [1.0] * 15, 1), (210, [], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")

    def fine(v):
        return v is not None and len(v) and all(x is not None and np.isfinite(x) for x in v) and any(v)

    ids = [r[0] for r in rows]
    link = {i: set() for i in ids}
    for i, v, a in rows:
        for j, w, b in rows:
            if i < j and a is not None and a == b and fine(v) and fine(w) and len(v) == len(w):
                v64, w64 = np.array(v, float), np.array(w, float)
                if v64 @ w64 / np.linalg.norm(v64) / np.linalg.norm(w64) >= 0.93:
                    link[i].add(j)
                    link[j].add(i)
    comp = {}
    for i in sorted(ids):
        if i not in comp:
            todo = [i]
            while todo:
                x = todo.pop()
                if x not in comp:
                    comp[x] = i
                    todo += link[x]
    for block in (4096, 8):  # the small block splits every bucket
        got = {r["vec_id"]: r for r in embeddup.near_vectors(df, block=block).collect()}
        assert len(got) == len(rows)
        for i in ids:
            assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (len(link[i]), comp[i], comp[i] == i), i
    assert embeddup.contract(spark.createDataFrame([], df.schema)).count() == 0


def test_repeated_vectors_keep_their_rows(spark):
    v, w = [1.0, 0.0, 0.0], [0.99, 0.05, 0.0]
    df = spark.createDataFrame([(1, v, 0)] * 100 + [(2, w, 0), (3, v, 1), (None, v, 0), (None, v, 0)], "vec_id long, embedding array<float>, label int")
    got = collections.Counter(tuple(r) for r in embeddup.contract(df.repartition(3)).collect())
    assert got == {(1, 1, 1, True): 100, (2, 1, 1, False): 1, (3, 0, 3, True): 1, (None, 0, None, None): 2}


def test_vector_tables_keep_recall(spark, monkeypatch):
    rng = np.random.default_rng(12)
    base = rng.standard_normal((300, 24))
    base /= np.linalg.norm(base, axis=1, keepdims=True)
    noise = rng.standard_normal((300, 24))
    noise -= (noise * base).sum(1, keepdims=True) * base
    noise /= np.linalg.norm(noise, axis=1, keepdims=True)
    near = 0.935 * base + np.sqrt(1 - 0.935**2) * noise  # barely above the threshold
    rows = [(i, [float(x) for x in v], 0) for i, v in enumerate(np.vstack([base, near]))]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumn("embedding", F.col("embedding").cast("array<float>"))
    asked = []
    plan = embeddup.plan_tables
    monkeypatch.setattr(embeddup, "plan_tables", lambda n, t, r: asked.append(plan(n, t, r, bucket=16)) or asked[-1])
    got = {r["vec_id"]: r["n_links"] for r in embeddup.near_vectors(df, recall=0.95).collect()}
    assert asked[0][0] >= 5 and asked[0][1] > 1
    assert sum(got[300 + i] > 0 for i in range(300)) / 300 > 0.9


def test_large_labels_lose_no_pair_on_the_threshold(spark):
    rng = np.random.default_rng(41)
    base = rng.standard_normal((3000, 24))
    base /= np.linalg.norm(base, axis=1, keepdims=True)
    noise = rng.standard_normal((3000, 24))
    noise -= (noise * base).sum(1, keepdims=True) * base
    noise /= np.linalg.norm(noise, axis=1, keepdims=True)
    near = 0.9301 * base + np.sqrt(1 - 0.9301**2) * noise
    x = np.vstack([base, near]).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(x)], "vec_id long, embedding array<float>, label int")
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    want = (unit @ unit.T >= 0.93).sum(1) - 1
    got = {r["vec_id"]: r["n_links"] for r in embeddup.near_vectors(df).collect()}
    assert [got[i] for i in range(len(x))] == want.tolist()


def test_estimates_are_unbiased_and_bounded():
    rng = np.random.default_rng(13)
    x = rng.standard_normal((400, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    s, f = embeddup.codes(x)
    est, half = embeddup.estimate(s, f, x @ embeddup.rotation(64, 7), 4.5)
    err = est - x @ x.T
    assert abs(err.mean()) < 0.003 and (np.abs(err) <= half + 1e-9).mean() > 0.9999


# 10 documents


def test_banded_distance_equals_the_table():
    rng = random.Random(14)

    def full(a, b):
        p = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            c = [i]
            for j, y in enumerate(b, 1):
                c.append(min(p[j] + 1, c[-1] + 1, p[j - 1] + (x != y)))
            p = c
        return p[-1]

    for _ in range(3000):
        a, b = ([rng.randrange(4) for _ in range(rng.randrange(0, 14))] for _ in range(2))
        k = rng.randrange(0, 12)
        assert ominhash.banded_distance(a, b, k) == min(full(a, b), k + 1)


def test_sketches_see_order_and_repeats():
    w = ominhash.Words()
    a = " ".join(f"w{i}" for i in range(60))
    half = a.split()
    turned = " ".join(half[30:] + half[:30])
    same = lambda x, y: (ominhash.sketch(w(x), 64, 2) == ominhash.sketch(w(y), 64, 2)).mean()
    assert same(a, a) == 1 and same(a, turned) < 0.75  # nearly the same k-mers, another order
    assert same("a b c d e f " * 9, "a b c d e f " * 2) < 1
    assert len(ominhash.sketch(w(""), 8, 2)) == 0 and len(ominhash.sketch(w("one"), 8, 2)) == 8


@pytest.mark.parametrize("n", [60, 150, 400])
@pytest.mark.parametrize("share", [0.15, 0.17, 0.19])
def test_pairs_near_the_threshold_meet_in_a_bucket(n, share):
    import inspect

    m = inspect.signature(ominhash.classes).parameters["sketches"].default
    rng = np.random.default_rng([n, int(100 * share)])
    met = pairs = 0
    while pairs < 200:
        a = rng.integers(0, 2**63, n, np.uint64)
        new, at = rng.integers(0, 2**63, n, np.uint64), rng.choice(n, int(share * n), replace=False)
        words = [[x] for x in a]
        for i in at:  # deleted, replaced, followed by another
            words[i] = [[], [new[i]], [a[i], new[i]]][rng.integers(3)]
        b = np.array([x for w in words for x in w], np.uint64)
        if ominhash.alike(a, b, 0.8):
            pairs += 1
            met += bool((ominhash.sketch(a, m, 2) == ominhash.sketch(b, m, 2)).any())
    assert met / pairs >= 0.9


def test_shapes_read_whole_words():
    assert quality.shape("a" * 60 + "!9") == "a!0" and quality.shape("Word!!") == "Aa!"


def test_rows_without_id_stay_where_an_id_repeats(spark):
    rows = [(None, "one", "s"), (None, "two", "s"), (None, None, "s"), (1, "b c d", "s"), (1, "a c d", "s"), (2, "x y z", "s")]
    got = [(r["doc_id"], r["text"]) for r in ominhash.drop_near(docs_frame(spark, rows).repartition(3)).collect()]
    assert collections.Counter(got) == collections.Counter([(None, "one"), (None, "two"), (None, None), (1, "a c d"), (2, "x y z")])


def test_hot_buckets_keep_their_linked_pairs(spark):
    """A long template puts everything into hot buckets; edits of every fourth word leave linked pairs nothing else in common."""
    rng = random.Random(29)
    say = words(rng, 60, 4000, "abcdefghijkl")
    template = say(120)
    own = [say(60).split() for _ in range(300)]
    near = {300 + i: 40 * i + 25 for i in range(6)}
    texts = [template + " " + " ".join(x) for x in own]
    texts += [template + " " + " ".join("edit" if k % 4 == 0 else w for k, w in enumerate(own[o])) for o in near.values()]
    df = docs_frame(spark, [(i, t, "s") for i, t in enumerate(texts)])
    for more in ({}, {"block": 64}):
        got = {r["id"]: r["class_id"] for r in ominhash.classes(df, **more).collect()}
        assert got == {i: near.get(i, i) for i in range(len(texts))}


def test_documents_against_brute_force(spark):
    rng = random.Random(15)
    say = words(rng, 80, 3000, "abcdefghijkl")
    rows = []
    for g in range(25):
        t = say(rng.randrange(20, 120))
        rows.append(t)
        for _ in range(rng.randrange(0, 4)):
            x = t.split()
            for _ in range(int(len(x) * rng.choice([0, 0.02, 0.06, 0.3]))):
                x[rng.randrange(len(x))] = rng.choice(["new", "other", "x y"])
            rows.append(" ".join(x))
    rows = [(i, t, "s") for i, t in enumerate(rows)] + [(900, None, "s"), (901, "", "s"), (902, " ", "s"), (903, rows[0].upper(), "s"), (904, "one", "s"), (905, "one", "s"), (None, "one", "s")]
    got = collections.Counter((r["doc_id"], r["class_id"]) for r in ominhash.contract(docs_frame(spark, rows)).collect())
    w = ominhash.Words()
    seq = {i: w(t) for i, t, _ in rows if i is not None}
    comp = {i: i for i in seq}

    def find(i):
        return i if comp[i] == i else find(comp[i])

    for i in seq:
        for j in seq:
            if i < j and len(seq[i]) and len(seq[j]) and ominhash.alike(seq[i], seq[j], 0.8):
                a, b = find(i), find(j)
                comp[max(a, b)] = min(a, b)
    want = collections.Counter((i, find(i)) for i in seq)
    want[(None, None)] = 1
    assert got == want
    kept = ominhash.drop_near(docs_frame(spark, rows))
    assert sorted(r["doc_id"] for r in kept.filter("doc_id IS NOT NULL").collect()) == sorted(i for i in seq if find(i) == i)
    assert kept.columns == docs_frame(spark, rows).columns
    assert ominhash.contract(docs_frame(spark, [])).count() == 0
    assert ominhash.drop_near(docs_frame(spark, [(1, "a b c", "s"), (1, "a b c", "s")])).count() == 1
