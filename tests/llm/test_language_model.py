"""Scores against exact counts, quantised as the filter does; ranges of the filter; hot unseen words."""

import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
TRAIN = "crc32(cast(cast(doc_id as string) as binary)) % 7 <> 2"


@pytest.fixture(scope="module")
def docs(spark):
    odd = [(900, None), (901, ""), (902, "once"), (903, "new " * 400), (903, "new " * 400), (None, "a b a b"), (904, "A a b \t x\n")]
    return spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", F.lit(1).alias("score"), F.lit("x").alias("h")).union(spark.createDataFrame([(*r, 1, "x") for r in odd], "doc_id long, text string, score int, h string")).cache()


def tokens(t):
    return [*(t or "").encode().lower().split(), None]


def plain(rows, order, base, mu):
    """Dirichlet smoothing over counts that are replaced by the mean of their level."""
    counts = [Counter() for _ in range(order)]
    for text, trained in rows:
        if trained:
            w = tokens(text)
            for k in range(order):
                counts[k].update(tuple(w[i : i + k + 1]) for i in range(len(w) - k))

    def q(c):
        if not c:
            return 0.0
        level = 1 + math.floor(math.log(c) / math.log(base) + 1e-9)
        low, high = math.ceil(base ** (level - 1) - 1e-9), math.ceil(base**level - 1e-9) - 1
        return (low + max(low, high)) / 2

    n, v = sum(counts[0].values()), len(counts[0])
    out = []
    for text, _ in rows:
        w, total = tokens(text), 0.0
        for i in range(len(w)):
            p = (q(counts[0][(w[i],)]) + 1) / (n + v + 1)
            for k in range(1, order):
                c = h = 0.0
                if i >= k:
                    c = q(counts[k][tuple(w[i - k : i + 1])])
                    h = max(c, q(counts[k - 1][tuple(w[i - k : i])]))
                p = (c + mu * p) / (h + mu)
            total += math.log10(p)
        out.append(total)
    return out


@pytest.mark.parametrize("order", [2, 3])
def test_score_equals_exact_counts(spark, docs, order):
    from private_distinct.llm import ngram_lm

    rows = [(r.text, r.t) for r in docs.withColumn("t", F.coalesce(F.expr(TRAIN), F.lit(False))).collect()]
    want = sorted(round(x, 3) for x in plain(rows, order, 1.5, 1000.0))
    for limit in (1 << 30, 1 << 20):  # one range, and several
        got = ngram_lm.score(docs, TRAIN, order=order, key_bits=400, probes=4, limit=limit, broadcast_words=50).collect()
        assert np.allclose(sorted(r.score for r in got), want, atol=2e-3, rtol=0)
    assert len(ngram_lm.build_filter(ngram_lm.materialise(ngram_lm.count_ngrams(docs, "text", order), "t"), order, 1.5, 4, 400, 1 << 20)) > 1


def test_false_positives_of_the_production_filter(spark, docs):
    from private_distinct.llm import ngram_lm

    counted = ngram_lm.materialise(ngram_lm.count_ngrams(docs, "text", 2), "t")
    bloom = ngram_lm.build_filter(counted, 2, 1.5, 3, 10.0, 128 << 20)[0].value
    strange = np.random.default_rng(0).integers(0, 2**63, 50000).astype(np.uint64)
    for order in (1, 2):
        assert np.mean(bloom.level(order, strange) > 0) < 0.03
    seen = np.unique(ngram_lm.token_hashes(" ".join(r.text or "" for r in docs.limit(50).collect())))
    assert (bloom.level(1, seen) > 0).all()
