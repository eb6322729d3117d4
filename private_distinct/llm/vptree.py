"""Approximate nearest neighbours by vantage-point trees, one per shard.

Largest inner product becomes least distance by one more coordinate: vectors are scaled by a power of two so that
no norm passes 1, candidates get sqrt(1 - |x|^2) and queries 0.  At most ``PIVOTS`` sampled rows are the vantage
points of shards: each row goes to the nearest one, a cell of more than ``shard_rows`` rows is dealt further by
hash.  Each shard's tree keeps, for both children of a vantage point, the interval of their distances to it.  The
triangle inequality gives a lower bound on a query's distance to a shard or a child, which is skipped when
``factor`` times the bound passes the k-th distance found.  Factor one is exact search, larger ones skip more.

A query first searches the shard of its own cell; the distance found decides which other shards it is sent to.
Trees and queries of a shard stream through one task, tree first, queries in blocks; a tree that many queries
want is copied.  Equal vectors are one row of a tree with their k + 1 least ids, as more can be in no answer.
Trees only select: scores are computed once, on the original vectors, and order the answers, ties by id.

Edge cases: vectors that are null, empty, zero, or hold null or non-finite components and null ids take no part;
vectors of another length are not comparable and are searched apart; a repeated id is one candidate whose score is
that of its best row, and never its own answer; a repeated query id asks with its least vector; any id and any
scale of vectors will do; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import pickle

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, materialise, partitions

LEAF, SLACK, PIVOTS, BLOCK, COPY = 128, 8, 1024, 2048, 1 << 16


def usable(vector: str) -> Column:
    v = F.col(vector)
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return F.coalesce(v.isNotNull() & (F.size(v) > 0) & fine & F.exists(v, lambda x: x != 0), F.lit(False))


def lifted(y: np.ndarray) -> np.ndarray:
    """The further coordinate of scaled candidates."""
    return np.sqrt(np.maximum(1 - (y * y).sum(1), 0))


class VPTree:
    def __init__(self, ids: np.ndarray, x: np.ndarray, scale: float, keep: int):
        """Rows of one shard; each different vector keeps its ``keep`` least ids."""
        self.scale = scale
        order = np.lexsort((ids, *x.T[::-1]))
        ids, x = ids[order], x[order]
        new = np.r_[True, (x[1:] != x[:-1]).any(1)]
        of = np.cumsum(new) - 1
        once = np.r_[True, (ids[1:] != ids[:-1]) | new[1:]]  # the same row again
        ids, of, x = ids[once], of[once], x[new]
        start = np.searchsorted(of, np.arange(len(x)))
        near = np.arange(len(ids)) - start[of] < keep
        ids, of = ids[near], of[near]
        self.most = int(np.unique(ids, return_counts=True)[1].max())  # rows that share an id
        y = x / scale
        extra = lifted(y)
        at = np.arange(len(x))
        self.nodes: list[tuple] = []  # (start, end, vantage row, children, intervals); leaves have no children
        self._build(at, y, extra, 0, len(x))
        self.x, self.y, self.extra = x[at], y[at], extra[at]
        count = np.bincount(of, minlength=len(x))
        first = np.cumsum(count) - count
        self.count = count[at]
        self.start = np.cumsum(self.count) - self.count
        self.ids = ids[np.repeat(first[at] - self.start, self.count) + np.arange(len(ids))]
        self.least = self.ids[self.start]

    def _build(self, at: np.ndarray, y, extra, a: int, b: int) -> int:
        me = len(self.nodes)
        self.nodes.append((a, b, None, None, None))
        if b - a > LEAF:
            d2 = ((y[at[a:b]] - y[at[a]]) ** 2).sum(1) + (extra[at[a:b]] - extra[at[a]]) ** 2
            order = np.argsort(d2, kind="stable")  # the vantage point itself stays first
            at[a:b], d = at[a:b][order], np.sqrt(d2[order])
            mid = (a + b + 1) // 2
            spans = ((d[0], d[mid - a - 1]), (d[mid - a], d[-1]))
            vantage = (y[at[a]].copy(), float(extra[at[a]]))
            self.nodes[me] = (a, b, vantage, (self._build(at, y, extra, a, mid), self._build(at, y, extra, mid, b)), spans)
        return me

    def search(self, qids: np.ndarray, q: np.ndarray, k: int, factor: float, within: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query's place, id, score) of the k nearest of each query; ``within``: scaled scores that answers must reach."""
        n, wide = len(q), k * self.most + SLACK
        y = q / self.scale
        row, score = np.zeros((n, wide), np.int64), np.full((n, wide), -np.inf)
        q2 = (y * y).sum(1)
        least = np.full(n, -np.inf) if within is None else within - 1e-12
        alone = self.count == 1

        def distance(rows: np.ndarray, node: tuple) -> np.ndarray:
            v, e = node[2]
            return np.sqrt(np.maximum(q2[rows] - 2 * (y[rows] @ v) + v @ v + e * e, 0))

        def scan(rows: np.ndarray, a: int, b: int) -> None:
            s = y[rows] @ self.y[a:b].T
            s[(self.least[a:b] == qids[rows][:, None]) & alone[a:b]] = -np.inf
            some = s.max(1) >= score[rows, -1]
            rows, s = rows[some], s[some]
            all_rows = np.concatenate([row[rows], np.broadcast_to(np.arange(a, b), s.shape)], 1)
            all_s = np.concatenate([score[rows], s], 1)
            top = np.lexsort((self.least[all_rows], -all_s))[:, :wide]
            row[rows], score[rows] = np.take_along_axis(all_rows, top, 1), np.take_along_axis(all_s, top, 1)

        def bound(d: np.ndarray, span: tuple) -> np.ndarray:
            return np.maximum(np.maximum(span[0] - d, d - span[1]), 0)

        home = np.full(n, -1)
        todo = [(0, np.arange(n))] if within is None else []
        while todo:  # every query's own leaf first, for a k-th distance to prune by
            i, rows = todo.pop()
            node = self.nodes[i]
            if node[3] is None:
                home[rows] = i
                scan(rows, node[0], node[1])
                continue
            d = distance(rows, node)
            inner = bound(d, node[4][0]) <= bound(d, node[4][1])
            todo += [(c, r) for c, r in zip(node[3], (rows[inner], rows[~inner]), strict=True) if len(r)]
        todo = [(0, np.arange(n))]
        while todo:
            i, rows = todo.pop()
            node = self.nodes[i]
            if node[3] is None:
                rows = rows[home[rows] != i]
                if len(rows):
                    scan(rows, node[0], node[1])
                continue
            d = distance(rows, node)
            kth = farthest(q2[rows], np.maximum(score[rows, -1], least[rows]))
            for c, span in zip(node[3], node[4], strict=True):
                r = rows[factor * bound(d, span) <= kth]
                if len(r):
                    todo.append((c, r))
        i, j = np.nonzero(score > -np.inf)
        return self._answers(qids, q, i, row[i, j], k)

    def _answers(self, qids, q, i, at, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        s = (q[i] * self.x[at]).sum(1)
        n = self.count[at]
        of = np.repeat(np.arange(len(at)), n)
        ids = self.ids[self.start[at][of] + np.arange(len(of)) - (np.cumsum(n) - n)[of]]
        i, s = i[of], s[of]
        ok = ids != qids[i]
        return best(i[ok], ids[ok], s[ok], k)


def farthest(q2: np.ndarray, score: np.ndarray) -> np.ndarray:
    """Distance at which candidates reach a scaled score, with room for rounding."""
    return np.sqrt(np.maximum(np.where(np.isfinite(score), q2 + 1 - 2 * score, 8.0), 0)) + 1e-6


def best(i: np.ndarray, ids: np.ndarray, s: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best of each query: an id once, with its best score; ties to the smaller id."""
    order = np.lexsort((-s, ids, i))
    i, ids, s = i[order], ids[order], s[order]
    once = np.r_[True, (i[1:] != i[:-1]) | (ids[1:] != ids[:-1])][: len(i)]
    i, ids, s = i[once], ids[once], s[once]
    order = np.lexsort((ids, -s, i))
    i, ids, s = i[order], ids[order], s[order]
    near = np.arange(len(i)) - np.searchsorted(i, i) < k
    return i[near], ids[near], s[near]


def nearest(df: DataFrame, is_query: Column, k: int = 20, factor: float = 1.0, key: str = "vec_id", vector: str = "embedding", shard_rows: int = 8192, pivots: int = PIVOTS, log: list | None = None) -> DataFrame:
    """query_id, rank (from 1), vec_id, score of the k nearest rows to each row where ``is_query`` holds.

    ``log`` gets how many (query, shard) searches were made and how many there could have been.
    """
    spark = df.sparkSession
    wide = np.float64 if df.schema[vector].dataType.elementType.simpleString() == "double" else np.float32
    rows = df.where(usable(vector) & F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), F.col(vector).alias("v"), F.coalesce(is_query, F.lit(False)).alias("q"))

    def raw(batches):
        """Vectors as bytes, with their lengths and norms."""
        for b in batches:
            v = b.column(1)
            size = v.value_lengths().to_numpy() if b.num_rows else np.empty(0, np.int64)
            flat, first = v.flatten().to_numpy().astype(wide), np.cumsum(size) - size
            top = np.maximum.reduceat(np.abs(flat).astype(np.float64), first) if b.num_rows else size
            norm = top * np.sqrt(np.add.reduceat((flat / np.repeat(top, size)) ** 2, first)) if b.num_rows else size.astype(np.float64)
            x = pa.array([flat[i : i + n].tobytes() for i, n in zip(first.tolist(), size.tolist(), strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(size.astype(np.int32)), b.column(0), b.column(2), pa.array(np.minimum(norm, 1.7e308)), x], names=["dim", "id", "q", "norm", "x"])

    rows = materialise(rows.mapInArrow(raw, "dim int, id long, q boolean, norm double, x binary"), "vp-rows")
    found = {r["dim"]: r for r in rows.groupBy("dim").agg(F.count(F.lit(1)).alias("n"), F.max("norm").alias("reach")).collect()}  # a row for each length
    scale = {d: float(2.0 ** min(1023, max(-1022, np.ceil(np.log2(r["reach"]))))) for d, r in found.items()}
    points = {}
    for d, r in found.items():
        n = min(pivots, -(-r["n"] // shard_rows))
        some = rows.where(F.col("dim") == d).orderBy(F.xxhash64("id", F.lit(7)), "id", "x").limit(n).select("x").collect() if n > 1 else []  # ``pivots`` rows at most
        x = np.unique(np.frombuffer(b"".join(bytes(p.x) for p in some) or bytes(d * np.dtype(wide).itemsize), wide).reshape(-1, d).astype(np.float64), axis=0) / scale[d]
        points[d] = (x, lifted(x))

    def away(y: np.ndarray, extra, d: int) -> np.ndarray:
        """Distances of rows to all pivots."""
        x, e = points[d]
        return np.sqrt(np.maximum((y * y).sum(1)[:, None] - 2 * (y @ x.T) + (x * x).sum(1) + (np.subtract.outer(extra, e)) ** 2, 0))

    def assign(batches):
        for b in batches:
            dims, ids, q = b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy(zero_copy_only=False)
            for d in np.unique(dims):
                at = np.flatnonzero(dims == d)
                x = np.frombuffer(b"".join(b.column(3).take(pa.array(at)).to_pylist()), wide).reshape(-1, d).astype(np.float64)
                order = np.lexsort((ids[at], *x.T[::-1]))
                same = np.cumsum(np.r_[True, (x[order][1:] != x[order][:-1]).any(1)]) - 1
                keep = np.sort(order[(np.arange(len(order)) - np.searchsorted(same, same) <= k) | q[at][order]])
                x, at = x[keep], at[keep]
                y = x / scale[int(d)]
                far = away(y, lifted(y), int(d))
                near = far.argmin(1)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), d, np.int32)), pa.array(near.astype(np.int32)), pa.array(far[np.arange(len(at)), near]), *(b.column(c).take(pa.array(at)) for c in (1, 2, 3))], names=["dim", "pivot", "far", "id", "q", "x"])

    cells = materialise(rows.select("dim", "id", "q", "x").mapInArrow(assign, "dim int, pivot int, far double, id long, q boolean, x binary"), "vp-cells")
    discard(rows)
    sizes = {(r["dim"], r["pivot"]): r for r in cells.groupBy("dim", "pivot").agg(F.count(F.lit(1)).alias("n"), F.max("far").alias("radius")).collect()}  # ``pivots`` rows a length
    parts = {at: -(-r["n"] // shard_rows) for at, r in sizes.items()}
    nq = cells.where("q").count()
    copies = max(1, -(-nq // COPY))
    split = F.create_map(*[F.lit(x) for (d, p), m in parts.items() for x in (f"{d}/{p}", m)]) if parts else F.create_map(F.lit(""), F.lit(1))
    cells = cells.withColumn("sub", F.pmod(F.xxhash64("x"), split[F.concat_ws("/", "dim", "pivot")]).cast("int"))

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        d = int(pdf["dim"].iloc[0])
        tree = VPTree(pdf["id"].to_numpy(), np.frombuffer(b"".join(pdf["x"]), wide).reshape(-1, d).astype(np.float64), scale[d], k + 1)
        return pd.DataFrame({"dim": [d], "pivot": [pdf["pivot"].iloc[0]], "sub": [pdf["sub"].iloc[0]], "tree": [pickle.dumps(tree)]})

    place = ["dim", "pivot", "sub"]
    index = materialise(cells.select(*place, "id", "x").groupBy(*place).applyInPandas(build, "dim int, pivot int, sub int, tree binary"), "vp-trees")
    # a repeated query id asks once; its rows of equal length are told apart by their bytes
    asks = cells.where("q").groupBy("id", "dim").agg(F.min(F.struct("x", "pivot", "sub")).alias("a")).select("dim", "a.pivot", "a.sub", "id", "a.x", F.lit(None).cast("double").alias("within"))
    shape = "query_id long, vec_id long, score double, dim int, pivot int, sub int, x binary, within double"
    shards = {d: [(p, s, float(sizes[d, p]["radius"])) for (e, p), m in sorted(parts.items()) if e == d for s in range(m)] for d in found}

    def searching(first: bool):
        def run(batches):
            now, tree, held = None, None, []

            def done():
                ids = np.array([h[0] for h in held])
                d = now[0]
                q = np.frombuffer(b"".join(h[1] for h in held), wide).reshape(-1, d).astype(np.float64)
                within = None if first else np.array([h[2] for h in held], np.float64)
                i, found, s = tree.search(ids, q, k, factor, within)
                none = pa.nulls(len(i), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(found), pa.array(s), none, none, none, pa.nulls(len(i), pa.binary()), pa.nulls(len(i), pa.float64())], names=names)
                if first and len(shards[d]) > 1:
                    least = np.full(len(ids), -np.inf)  # scaled score of the k-th, where there are k
                    full = np.bincount(i, minlength=len(ids)) >= k
                    last = np.searchsorted(i, np.arange(len(ids)), side="right") - 1
                    least[full] = s[last[full]] / tree.scale / tree.scale
                    y = q / tree.scale
                    far, kth = away(y, np.zeros(len(y)), d), farthest((y * y).sum(1), least)
                    for p, sub, radius in shards[d]:
                        if (p, sub) == now[1:3]:
                            continue
                        go = np.flatnonzero(factor * np.maximum(far[:, p] - radius, 0) <= kth)
                        m = len(go)
                        yield pa.RecordBatch.from_arrays([pa.array(ids[go]), pa.nulls(m, pa.int64()), pa.nulls(m, pa.float64()), *(pa.array(np.full(m, x, np.int32)) for x in (d, p, sub)), pa.array([held[g][1] for g in go], pa.binary()), pa.array(least[go])], names=names)

            names = ["query_id", "vec_id", "score", "dim", "pivot", "sub", "x", "within"]
            for b in batches:
                cols = [b.column(j).to_pylist() for j in range(4)] + [b.column(j) for j in range(4, 8)]
                for r, (d, p, s, c) in enumerate(zip(*cols[:4], strict=True)):
                    if (d, p, s, c) != now:
                        if held:
                            yield from done()
                        now, held = (d, p, s, c), []
                    if cols[4][r].is_valid:
                        held.append((cols[4][r].as_py(), cols[5][r].as_py(), cols[6][r].as_py()))
                        if len(held) == BLOCK:
                            yield from done()
                            held = []
                    else:
                        tree = pickle.loads(cols[7][r].as_py())
            if held:
                yield from done()

        return run

    def searched(asked: DataFrame, first: bool) -> DataFrame:
        every = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))) if copies > 1 else F.lit(0)
        trees = index.select(*place, every.cast("int").alias("copy"), F.lit(None).cast("long").alias("id"), F.lit(None).cast("binary").alias("x"), F.lit(None).cast("double").alias("within"), "tree")
        mine = asked.select(*place, F.pmod(F.xxhash64("id"), F.lit(copies)).cast("int").alias("copy"), "id", "x", "within", F.lit(None).cast("binary").alias("tree"))
        both = trees.union(mine).repartition(partitions(spark), *place, "copy").sortWithinPartitions(*place, "copy", "id")  # the tree first
        return both.mapInArrow(searching(first), shape)

    near = materialise(searched(asks, True), "vp-near")
    further = near.where("vec_id is null").select("dim", "pivot", "sub", F.col("query_id").alias("id"), "x", "within")
    if log is not None:
        log += [("searches", nq + further.count()), ("all", nq * sum(parts.values()))]
    answers = near.where("vec_id is not null").select("query_id", "vec_id", "score")
    if max(map(len, shards.values()), default=0) > 1:
        answers = materialise(answers.union(searched(further, False).select("query_id", "vec_id", "score")), "vp-found")
        discard(near)
    discard(cells, index) if max(map(len, shards.values()), default=0) > 1 else None
    answers = answers.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return answers.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
