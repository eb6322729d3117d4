"""Nearest neighbours and embedding near-duplicates against brute force."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
ODD = [
    (9000, None, 1, "x"), (9001, [], 1, "x"), (9002, [0.0] * 64, 1, "x"), (9003, [1.0, None] * 32, 1, "x"), (9004, [float("nan")] * 64, 1, "x"),
    (9005, [float("inf")] * 64, 1, "x"), (9006, [1.0] * 64, None, "x"), (9007, [1.0] * 64, 1, "x"), (9008, [1.0] * 64, 1, "x"), (9020, [2.0] * 64, 1, "x"), (9040, [3.0, 4.0], 1, "x"),
    (9007, [1.0] * 64, 1, "x"), (9060, [0.5] * 64, 1, "x"), (9060, [-0.5, 0.0] * 32, 1, "x"), (9060, [-0.5, -0.0] * 32, 1, "x"), (-1, [1.5] * 64, 1, "x"), (-20, [1.0] * 64, 1, "x"), (None, [1.0] * 64, 1, "x"),
]


def table(spark):
    given = spark.read.parquet(f"{SF}/embeddings.parquet").selectExpr("vec_id", "embedding", "label", "'x' as score", "'y' as cls", "1 as rank")
    return given.union(spark.createDataFrame([(*r, "y", 1) for r in ODD], given.schema)).cache()


def good(v):
    return v and all(x is not None and math.isfinite(x) for x in v) and any(v)


def brute(rows, k=20, every=20):
    """query -> [(id, score)] by the contract; a repeated query id asks with the vector of least bytes."""
    rows = [(i, np.array(v, np.float64)) for i, v in rows if i is not None and good(v)]
    asks = {}
    for i, v in rows:
        if i % every == 0 and ((i, len(v)) not in asks or v.tobytes() < asks[i, len(v)].tobytes()):
            asks[i, len(v)] = v
    want = {}
    for (q, d), v in asks.items():
        score = {}
        for i, w in rows:
            if i != q and len(w) == d:
                score[i] = max(score.get(i, -math.inf), float((v * w).sum()))
        want.setdefault(q, []).extend(sorted(score.items(), key=lambda x: (-x[1], x[0]))[:k])
    return {q: x for q, x in want.items() if x}


def searched(df, **options):
    from private_distinct.llm import vptree

    got = {}
    for r in sorted(vptree.nearest(df, F.col("vec_id") % 20 == 0, **options).collect(), key=lambda r: r["rank"]):
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    return got


def test_vantage_point_search(spark):
    df = table(spark)
    want = brute([(r.vec_id, r.embedding) for r in df.collect()])
    for options in ({"shard_rows": 60}, {}, {"shard_rows": 40, "pivots": 3}):
        got = searched(df, **options)
        assert {q: [i for i, _ in x] for q, x in got.items()} == {q: [i for i, _ in x] for q, x in want.items()}
        assert all(abs(s - t) <= 1e-12 * max(1, abs(t)) for q, x in got.items() for (_, s), (_, t) in zip(x, want[q]))
    assert searched(df.limit(0)) == {}


def test_relaxed_factor_searches_less(spark):
    rng = np.random.default_rng(1)
    centres = rng.standard_normal((24, 16))
    x = centres[rng.integers(0, 24, 4000)] + 0.2 * rng.standard_normal((4000, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    df = spark.createDataFrame([(i, v.tolist(), 1) for i, v in enumerate(x)], "vec_id long, embedding array<double>, label int").cache()
    want, logs = brute(list(enumerate(x.tolist()))), {}
    for factor in (1.0, 1.25):
        logs[factor] = []
        got = searched(df, factor=factor, shard_rows=250, log=logs[factor])
        hit = np.mean([len({i for i, _ in got[q]} & {i for i, _ in want[q]}) / 20 for q in want])
        assert hit == 1 if factor == 1 else hit >= 0.9
    assert dict(logs[1.0])["searches"] < dict(logs[1.0])["all"]  # shards are pruned before queries move
    assert dict(logs[1.25])["searches"] < dict(logs[1.0])["searches"]


@pytest.mark.parametrize("scale", [1e-9, 1e-160, 1e9, 1e150])
def test_search_at_any_scale(spark, scale):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((600, 8)) * scale * 10.0 ** -rng.integers(0, 3, (600, 1))
    x[300:330] = x[0]
    df = spark.createDataFrame([(i - 40, v.tolist(), 1) for i, v in enumerate(x)], "vec_id long, embedding array<double>, label int")
    want, got = brute([(i - 40, v) for i, v in enumerate(x.tolist())]), searched(df, shard_rows=100)
    assert {q: [i for i, _ in v] for q, v in got.items()} == {q: [i for i, _ in v] for q, v in want.items()}


def test_nn_descent(spark):
    from private_distinct.llm import nndescent

    df = table(spark)
    rows = [r for r in df.collect()]
    for cell_rows in (8192, 20):
        got = nndescent.near_duplicates(df, cell_rows=cell_rows).collect()
        n = len(rows)
        unit = [np.array(r.embedding) / np.linalg.norm(r.embedding) if good(r.embedding) and r.label is not None and r.vec_id is not None else None for r in rows]
        links = [set() for _ in range(n)]
        for a in range(n):
            for b in range(a):
                if unit[a] is not None and unit[b] is not None and rows[a].label == rows[b].label and len(unit[a]) == len(unit[b]) and unit[a] @ unit[b] >= 0.98:
                    links[a].add(b)
                    links[b].add(a)
        root = [math.inf if r.vec_id is None else r.vec_id for r in rows]
        for _ in range(50):
            root = [min([root[a], *(root[b] for b in links[a])]) for a in range(n)]
        root = [None if x == math.inf else x for x in root]
        want = sorted((repr(r.vec_id), len(links[a]), root[a], r.vec_id is not None and root[a] == r.vec_id) for a, r in enumerate(rows))
        assert sorted((repr(r.vec_id), r.n_links, r.component_id, r.kept) for r in got) == want
    assert nndescent.near_duplicates(df.limit(0)).count() == 0


def test_descent_makes_the_links(spark):
    """On a whole given table the descent's own joins find the links, and all of them; each label is one cell."""
    from private_distinct.llm import nndescent

    df = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet").cache()
    log = []
    got = {r.vec_id: r.n_links for r in nndescent.near_duplicates(df, log=log).collect()}
    log = dict(log)
    assert log["rounds"] >= 10 and log["joins"] > 0 and log.get("missed", 0) == 0 and log.get("whole", 0) < 0.1 * len(got)
    pdf = df.toPandas()
    for _, part in pdf.groupby("label"):
        x = np.array(part.embedding.tolist(), np.float64)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        assert ((x @ x.T >= 0.98).sum(1) - 1 == [got[i] for i in part.vec_id]).all()


def grouped_vectors(rng, n=1500, dense=400):
    x = rng.standard_normal((n, 32))
    x[:dense] = x[0] + 0.02 * rng.standard_normal((dense, 32))
    x[dense : dense + 400 : 2] = x[dense + 1 : dense + 401 : 2] + 0.02 * rng.standard_normal((200, 32))
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def test_refine_finds_links_of_dense_and_thin_groups():
    from private_distinct.llm import nndescent

    x = grouped_vectors(np.random.default_rng(0))
    i, j = nndescent.refine(x, 0.98)
    a, b = np.nonzero(np.triu(x @ x.T >= 0.98, 1))
    assert sorted(zip(i.tolist(), j.tolist())) == sorted(zip(a.tolist(), b.tolist()))
    graph = nndescent.Graph(x)
    assert sum(len(f[0]) for f in graph.links(0.98)) == len(a)
    assert graph.done["enlarged"] >= 400 and graph.done["joins"] > 0


def test_recall_across_cells(spark):
    """Cells far smaller than a label: links between cells of one table are met in another."""
    from private_distinct.llm import nndescent

    x = grouped_vectors(np.random.default_rng(3), 6000, 300)
    df = spark.createDataFrame([(i, v.tolist(), 1) for i, v in enumerate(x)], "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: r.n_links for r in nndescent.near_duplicates(df, cell_rows=400).collect()}
    true = (x @ x.T >= 0.98).sum(1) - 1
    assert sum(got.values()) >= 0.995 * true.sum() and all(got[i] <= t for i, t in enumerate(true))
