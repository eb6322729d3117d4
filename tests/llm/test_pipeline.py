"""The toxicity network, and the pipeline's stages against plain versions of each."""

from collections import Counter

import numpy as np
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


def toxic_corpus(spark, n=240):
    import random

    rng = random.Random(2)
    word = lambda: "".join(rng.choice(["an", "th", "ed", "or", "is"]) for _ in range(rng.randint(1, 3)))
    rows, labels = [], []
    for i in range(n):
        words = [word() for _ in range(rng.randint(5, 90))]
        if i % 4 == 0:
            words[rng.randrange(len(words))] = rng.choice(["vile", "vilest", "VILE!"])
        rows.append((i, " ".join(words), "en", "s", 0))
        labels.append((i, 0, int(i % 4 == 0)))
    rows += [(None, "a b", "en", "s", 0), (n, None, None, None, None), (n + 1, "", "en", "s", 0), (n + 2, "z" * 3000, "en", "s", 0)]
    return spark.createDataFrame(rows, COLUMNS), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_gradient():
    from private_distinct.llm import toxicity as t

    net = t.Network({"a": 1, "bad": 2})
    lower, y = [["a", "b", "bad"] * 30, ["c", "d"], []], np.array([1.0, 0, 0])

    def loss():
        at = {}
        rows = [np.array([at.setdefault(w, len(at)) + 1 for w in ws], np.int64) for ws in lower]
        index, doc = t.windows(rows)
        pad = t._closed(np.zeros((0, 3 * t.STATE), np.float32))
        tables = [np.concatenate([pad, x]) for x in net.encode_words(list(at))]
        s = t.soft_maximum(net.window_logits(tables, index.T, 0).astype(np.float64), doc, 3)[0]
        return float(np.mean(np.log1p(np.exp(s)) - y * s))

    for k, g in t._gradient(net, [t.cut_words(ws) for ws in lower], y, np.random.default_rng(0), blank=0).items():
        i = np.unravel_index(np.abs(g).argmax(), g.shape)
        old, step = net.p[k][i], 1e-2
        net.p[k][i] = old + step
        up = loss()
        net.p[k][i] = old - step
        down = loss()
        net.p[k][i] = old
        assert abs((up - down) / (2 * step) - g[i]) < 0.02 * abs(g[i]) + 1e-5, k


def test_windows_and_words_train_whole():
    from private_distinct.llm import toxicity as t

    words = [f"w{i}" for i in range(5000)]
    assert [w for ws in t.cut_words(words) for w in ws[: t.STRIDE]][:4990] == words[:4990]  # nothing between windows is lost
    some = t.cut_words(words, 64)
    assert len(some) == 64 and some == t.cut_words(words, 64) and some[-1][0] > some[0][0]
    rng = np.random.default_rng(1)
    texts = [" ".join("abcdefghijklmnopqrstuvwxy"[j % 25] for j in rng.integers(0, 25, 24)) for _ in range(120)]
    texts = [t_.replace(" ", "") + ("zz" if i % 2 else "qq") for i, t_ in enumerate(texts)]  # the 25th and 26th byte tell
    net = t.train(texts, [i % 2 for i in range(120)], steps=260)
    assert np.mean([(s >= 0.5) == i % 2 for i, s in enumerate(net.score(texts))]) >= 0.9


def test_toxicity_held_out(spark):
    from private_distinct.llm import toxicity

    docs, labels = toxic_corpus(spark)
    net = toxicity.fit(docs, labels, F.col("doc_id") % 3 != 0)
    got = toxicity.score(docs, net, ["doc_id"]).collect()
    assert len(got) == docs.count() and all(0 <= r.score <= 1 for r in got)
    twice = toxicity.score(docs.union(docs).withColumn("score", F.lit("clash")), net, ["doc_id"]).groupBy("doc_id").agg(F.count("score").alias("n"), (F.max("score") - F.min("score")).alias("d"))
    assert all(r.n == 2 and r.d < 1e-6 for r in twice.collect())
    held = [r for r in got if r.doc_id is not None and r.doc_id < 240 and r.doc_id % 3 == 0]
    assert np.mean([(r.score >= 0.5) == (r.doc_id % 4 == 0) for r in held]) >= 0.9
    none = toxicity.fit(docs, labels.limit(0), F.lit(True))
    assert {r.score < 0.5 for r in toxicity.score(docs, none, ["doc_id"]).collect()} == {True}
    assert toxicity.score(docs.limit(0), net, ["doc_id"]).count() == 0


def test_stages(spark):
    import corpus_pipeline as p
    from test_near_copies import plain as copies
    from test_suffix_dedup import plain

    given = spark.read.parquet(f"{SF}/documents.parquet")
    odd = [(None, "no id", "en", "s", 5), (5000, None, None, None, None), (5001, "", "en", "s", 0), (7, "another text of the same id", "en", "s", 0), (5002, "twice", "en", "s", 5), (5002, "twice", "en", "s", 5)]
    docs = given.union(spark.createDataFrame(odd, COLUMNS))
    docs = docs.selectExpr("*", "'a' as score", "1 as kept_text", "2 as n_removed", "3 as th", "4 as root", "5 as _tie_", "6 as k0").cache()  # clashing names
    rows = [r for r in docs.collect() if r.doc_id is not None]
    kept = p.drop_near_copies(spark, docs, SF).cache()
    assert kept.columns == docs.columns
    assert Counter(r.doc_id for r in kept.collect()) == copies(rows) + Counter([None])
    assert sum(r.doc_id == 7 for r in kept.collect()) == 1 + any(r.doc_id == 7 and r.text.startswith("another") for r in kept.collect())
    cut = p.drop_repeated_strings(spark, kept, SF)
    assert cut.columns == docs.columns
    want = Counter((d, n - gone) for d, n, gone, _, _ in plain([(r.doc_id, (r.text or "").encode()) for r in kept.collect() if r.doc_id is not None]))
    for r in cut.collect():
        assert r.doc_id is None or any(d == r.doc_id and 0 <= n - len(r.text.encode()) < 8 for d, n in want)  # bytes of cut characters go too
        assert r.n_chars == len(r.text) and r.score == "a" and (r.kept_text, r.n_removed, r.k0) == (1, 2, 6)
    assert p.drop_toxic(spark, docs, SF).columns == docs.columns


def test_stages_of_empty_tables(spark):
    import corpus_pipeline as p

    docs = spark.createDataFrame([], COLUMNS)
    for _, stage in p.STAGES:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0


def test_run(spark):
    import corpus_pipeline as p

    out = p.run(spark, SF)
    assert [n for n, _ in p.STAGES] == ["toxicity", "simhash_near_dedup", "suffix_array_dedup", "best_fit_packing"]
    assert out.count() > 0 and out.where("offset + length > 2048").count() == 0
