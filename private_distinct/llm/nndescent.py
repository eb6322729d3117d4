"""Embedding near-duplicates from a neighbour graph refined by NN-descent.

Equal vectors of a label are one class with a weight.  A label of up to ``cell_rows`` classes is one cell.  Larger
ones are dealt into cells of about that size by sign patterns of random directions, in as many tables as a pair
at the threshold needs to share a cell of some table with probability ``1 - MISS``; a cell that is still larger is
dealt as pairs of blocks.  Each cell's neighbour graph starts from neighbours along random projections and is
refined by joins of neighbours of neighbours until few entries change.  A list in which every entry passes the
threshold is saturated and enlarged by degrees, in the end to a comparison with the whole cell.  An audit then
compares a sixteenth of the rows with all others: if a link was missed, the descent goes on with lists of twice
the length, and after ``TRIES`` such audits the cell is compared whole, so what a cell returns has passed its audit.

A pair is counted in the first table where it shares a cell.  Cells send link counts per class and a spanning
forest, never all pairs; links of saturated rows are counted block by block and not held.

Edge cases: null labels or ids, and vectors that are null, empty, zero or hold null or non-finite components, link
with nothing and are their own component; vectors of different lengths never link; -0.0 is 0.0; repeated ids are
rows of their own that link if their vectors do; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import connected_components, discard, forest, materialise, partitions
from .vptree import usable

MISS, LIST, ROUNDS, TRIES, CHUNK = 0.002, 16, 8, 3, 256


class Graph:
    """Neighbour lists of unit rows, refined by NN-descent; ``done`` counts the steps for tests and logs."""

    def __init__(self, x: np.ndarray, k: int = LIST, seed: int = 1):
        self.x, self.n, self.rng, self.done = x, len(x), np.random.default_rng(seed), Counter()
        self.lists = np.empty((self.n, 0), np.int64)
        self.sims = np.empty((self.n, 0))
        self.enlarge(k)

    def enlarge(self, k: int) -> None:
        """Lists of length k: what is held, and neighbours along random projections."""
        self.k = k = min(k, self.n - 1)
        near = [self.lists]
        at, steps = np.arange(self.n), 4
        for _ in range(max(2, -(-k // steps))):
            order = np.argsort(self.x @ self.rng.standard_normal(self.x.shape[1]), kind="stable")
            place = np.empty(self.n, np.int64)
            place[order] = at
            near += [order[(place + s) % self.n][:, None] for s in (-2, -1, 1, 2)]
        self._keep(at, np.concatenate(near, 1), k, start=True)

    def _best(self, rows: np.ndarray, cand: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """The k nearest of each row's candidates, repeats and the row itself left out."""
        cand = np.sort(cand, 1)
        s = np.einsum("nd,nkd->nk", self.x[rows], self.x[cand], optimize=False)
        s[(cand == rows[:, None]) | np.concatenate([np.zeros((len(rows), 1), bool), cand[:, 1:] == cand[:, :-1]], 1)] = -2
        k = min(k, cand.shape[1])
        top = np.argpartition(-s, k - 1, axis=1)[:, :k]
        return np.take_along_axis(cand, top, 1), np.take_along_axis(s, top, 1)

    def _keep(self, rows: np.ndarray, cand: np.ndarray, k: int, start: bool = False) -> None:
        if start:
            self.lists, self.sims = np.empty((self.n, k), np.int64), np.empty((self.n, k))
        for i in range(0, len(rows), CHUNK):
            me = rows[i : i + CHUNK]
            self.lists[me], self.sims[me] = self._best(me, cand[i : i + CHUNK], k)

    def _both(self) -> np.ndarray:
        """Each row's list, and as many rows that have it in theirs."""
        back = self.lists.copy()
        at = self.rng.permutation(self.n * self.k)
        back[self.lists.ravel()[at], at % self.k] = at // self.k
        return np.concatenate([self.lists, back], 1)

    def descend(self, rounds: int = ROUNDS) -> None:
        """Joins of neighbours of neighbours, until less than a hundredth of the lists get better."""
        for _ in range(rounds):
            both, changed = self._both(), 0
            for i in range(0, self.n, CHUNK):
                me = np.arange(i, min(self.n, i + CHUNK))
                near = both[me]
                two = both[near[:, self.rng.permutation(2 * self.k)[:8]]].reshape(len(me), -1)
                new, got = self._best(me, np.concatenate([near, two], 1), self.k)
                changed += int((got.min(1) > self.sims[me].min(1) + 1e-12).sum())
                self.lists[me], self.sims[me] = new, got
                self.done["joins"] += two.size
            self.done["rounds"] += 1
            if changed <= self.n // 100:
                break

    def saturated(self, threshold: float) -> tuple[np.ndarray, list[np.ndarray]]:
        """Rows to be compared with the whole cell, and further pairs from lists enlarged by degrees."""
        full, lists, more = np.flatnonzero(self.sims.min(1) >= threshold), None, []
        both = self._both() if len(full) else None
        lists = self.lists[full]
        for k in (4 * self.k, 16 * self.k):
            if not len(full) or 2 * k >= self.n:
                break
            self.done["enlarged"] += len(full)
            new, still = np.empty((len(full), k), np.int64), np.zeros(len(full), bool)
            for i in range(0, len(full), 32):
                some = lists[i : i + 32]
                pool = both[some[:, self.rng.permutation(some.shape[1])[:64]]].reshape(len(some), -1)
                near, s = self._best(full[i : i + 32], np.concatenate([some, pool], 1), k)
                new[i : i + 32, : near.shape[1]], still[i : i + 32] = near, (s.min(1) >= threshold) | (near.shape[1] < k)
                a, b = np.nonzero(s >= threshold)
                keep = ~still[i : i + 32][a]
                more.append(np.stack([full[i : i + 32][a[keep]], near[a[keep], b[keep]]], 1))
            full, lists = full[still], new[still]
        return full, more

    def exact(self, rows: np.ndarray, threshold: float):
        """Pairs of some rows with the whole cell, in blocks."""
        step = max(16, min(512, (1 << 22) // self.n))
        for i in range(0, len(rows), step):
            me = rows[i : i + step]
            a, b = np.nonzero(self.x[me] @ self.x.T >= threshold)
            yield me[a], b

    def links(self, threshold: float):
        """Yields arrays (i, j) of pairs with inner product >= threshold, each pair once."""
        if self.n > 2:
            for tried in range(TRIES):
                self.descend()
                whole, more = self.saturated(threshold)
                apart = np.zeros(self.n, bool)
                apart[whole] = True
                rest = np.flatnonzero(~apart)
                hit = self.sims[rest] >= threshold
                both = np.concatenate([np.stack([np.repeat(rest, hit.sum(1)), self.lists[rest][hit]], 1), *more])
                both = both[~apart[both].any(1)]  # pairs with a saturated row come from there
                pair = np.unique(both.min(1) * self.n + both.max(1))
                audit = self.rng.choice(self.n, min(self.n, max(64, self.n // 16)), replace=False)
                missed = 0
                for i, j in self.exact(audit, threshold):
                    ok = (i != j) & ~apart[i] & ~apart[j]
                    true = np.minimum(i, j)[ok] * self.n + np.maximum(i, j)[ok]
                    found = np.isin(true, pair)
                    self.done["audited"] += len(true)
                    missed += int((~found).sum())
                self.done["missed"] += missed
                if not missed:
                    yield pair // self.n, pair % self.n
                    break
                if tried < TRIES - 1:
                    self.enlarge(2 * self.k)
            else:
                whole = np.arange(self.n)
        else:
            whole = np.arange(self.n)
        apart = np.zeros(self.n, bool)
        apart[whole] = True
        self.done["whole"] += len(whole)
        for i, j in self.exact(whole, threshold):
            once = ~apart[j] | (i < j)
            yield i[once], j[once]


def refine(x: np.ndarray, threshold: float, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """All pairs i < j of unit rows with inner product >= threshold that the descent finds."""
    found = list(Graph(x, seed=seed).links(threshold)) if len(x) > 1 else []
    i, j = (np.concatenate([f[s] for f in found] or [np.empty(0, np.int64)]) for s in (0, 1))
    return np.minimum(i, j), np.maximum(i, j)


def cell_links(x: np.ndarray, weights: np.ndarray, threshold: float, wanted: Callable) -> tuple[np.ndarray, np.ndarray, np.ndarray, Counter]:
    """Link weight of each row and forest edges from one cell; ``wanted`` says which pairs are counted here."""
    n, edges, held = np.zeros(len(x)), [], 0
    graph = Graph(x)
    for i, j in graph.links(threshold):
        ok = wanted(i, j)
        i, j = i[ok], j[ok]
        n += np.bincount(i, weights[j], len(x)) + np.bincount(j, weights[i], len(x))
        edges.append(forest(i, j))
        held += len(edges[-1][0])
        if held > 1 << 20:
            edges = [forest(*(np.concatenate([e[s] for e in edges]) for s in (0, 1)))]
            held = len(edges[0][0])
    a, b = (np.concatenate([e[s] for e in edges] or [np.empty(0, np.int64)]) for s in (0, 1))
    return n.astype(np.int64), *(forest(a, b) if len(a) else (a, b)), graph.done


def tables_for(bits: int, threshold: float) -> int:
    """Tables of so many sign bits that a pair at the threshold shares a cell of one but for ``MISS``."""
    same = 1 - math.acos(min(1.0, threshold)) / math.pi
    if bits == 0 or same >= 1:
        return 1
    return math.ceil(math.log(MISS) / math.log(1 - same**bits))


def near_duplicates(df: DataFrame, threshold: float = 0.98, key: str = "vec_id", vector: str = "embedding", label: str = "label", cell_rows: int = 8192, seed: int = 5, log: list | None = None) -> DataFrame:
    """key, n_links, component_id, kept for every row; ``log`` gets the counts of the descent's steps over all cells."""
    spark = df.sparkSession
    v = F.transform(vector, lambda x: F.when(x == 0, F.lit(0).cast(df.schema[vector].dataType.elementType)).otherwise(x))
    fine = usable(vector) & F.col(label).isNotNull() & F.col(key).isNotNull()
    rows = df.select(F.col(key).alias("key"), F.when(fine, v).alias("v"), F.col(label).alias("label"))
    rows = rows.withColumn("cls", F.when(F.col("v").isNotNull(), F.xxhash64("label", "v")))
    classes = rows.where("cls is not null").groupBy("cls", "label", "v").agg(F.min("key").alias("first"), F.count(F.lit(1)).alias("w"))
    classes = materialise(classes, "vector-classes")
    dims = [r[0] for r in classes.groupBy(F.size("v")).agg(F.count(F.lit(1))).collect()]  # lengths of vectors
    sizes = classes.groupBy("label").agg(F.count(F.lit(1)).alias("n"))
    sizes = materialise(sizes.select("label", F.greatest(F.ceil(F.log2(F.col("n") / F.lit(cell_rows))), F.lit(0)).cast("int").alias("bits")), "vector-labels")
    most = sizes.agg(F.max("bits")).first()[0] or 0
    tables = [tables_for(b, threshold) for b in range(most + 1)]
    planes = {d: np.random.default_rng(seed).standard_normal((d, max(tables) * most)) for d in dims}
    wide = np.float64 if df.schema[vector].dataType.elementType.simpleString() == "double" else np.float32

    def place(batches):
        """Each class once for each table of its label: cell, table, cls, w, vector, and its patterns in all tables."""
        for b in batches:
            vs, bits = b.column(0).to_pylist(), b.column(3).to_numpy()
            by: dict[tuple[int, int], list[int]] = {}
            for i, x in enumerate(vs):
                by.setdefault((len(x), int(bits[i])), []).append(i)
            for (d, m), at in by.items():
                for lo in range(0, len(at), 4096):
                    some = at[lo : lo + 4096]
                    x = np.array([vs[i] for i in some], wide)
                    t = tables[m]
                    up = ((x.astype(np.float64) @ planes[d][:, : t * m]) > 0).reshape(len(some), t, m)
                    sig = (up << np.arange(m)).sum(2).astype(np.int64)
                    pick, raw = pa.array(some), pa.array([r.tobytes() for r in x], pa.binary())
                    patterns = pa.array([r.tobytes() if t > 1 else b"" for r in sig], pa.binary())
                    for j in range(t):
                        yield pa.RecordBatch.from_arrays([b.column(4).take(pick), pa.array(np.full(len(some), d, np.int32)), pa.array(np.full(len(some), j, np.int32)), pa.array(sig[:, j]), b.column(1).take(pick), b.column(2).take(pick), raw, patterns], names=["label", "d", "t", "sig", "cls", "w", "x", "sigs"])

    kind = df.schema[label].dataType.simpleString()
    known = classes.join(sizes, "label").select("v", "cls", "w", "bits", "label")
    placed = known.mapInArrow(place, f"label {kind}, d int, t int, sig long, cls long, w long, x binary, sigs binary")
    placed = placed.withColumn("cell", F.xxhash64("label", "d", "t", "sig")).drop("label", "sig", "d")
    large = materialise(placed.groupBy("cell").agg(F.count(F.lit(1)).alias("m")).where(F.col("m") > 2 * cell_rows), "vector-cells")
    dealt = placed.join(large, "cell", "left")
    dealt = dealt.withColumn("parts", F.coalesce(F.ceil(F.col("m") / F.lit(cell_rows)), F.lit(1)).cast("int"))
    dealt = dealt.withColumn("block", F.pmod(F.xxhash64("cls"), F.col("parts")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    dealt = dealt.select("cell", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "t", "cls", "w", "x", "sigs")
    dealt = dealt.repartition(max(partitions(spark), 16), "cell", "lo", "hi").sortWithinPartitions("cell", "lo", "hi")

    def link(batches):
        held: list = []
        now = None
        steps: Counter = Counter()

        def done():
            if len(held) < 2:
                return
            block, table, cls, w, x, sigs = zip(*held, strict=True)
            block, cls = np.array(block), np.array(cls)
            x = np.frombuffer(b"".join(x), wide).reshape(len(held), -1).astype(np.float64)
            x /= np.abs(x).max(1, keepdims=True)
            x /= np.sqrt((x * x).sum(1, keepdims=True))
            sigs = np.frombuffer(b"".join(sigs), np.int64).reshape(len(held), -1)[:, : table[0]] if table[0] else np.empty((len(held), 0))

            def wanted(i, j):  # pairs inside a block, and pairs of an earlier table, are counted elsewhere
                return ((block[i] != block[j]) | (now[1] == now[2])) & ~(sigs[i] == sigs[j]).any(1)

            n, a, b, took = cell_links(x, np.array(w, np.float64), threshold, wanted)
            steps.update(took)
            at = np.flatnonzero(n)
            if len(at):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([cls[at], cls[a]])), pa.array(np.concatenate([n[at], np.zeros(len(a), np.int64)])), pa.array([None] * len(at) + cls[b].tolist(), pa.int64()), pa.nulls(len(at) + len(a), pa.string())], names=["a", "n", "b", "step"])

        for batch in batches:
            for cell, lo, hi, *row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (cell, lo, hi) != now:
                    if held:
                        yield from done()
                    held, now = [], (cell, lo, hi)
                held.append(row)
        if held:
            yield from done()
        if steps:
            yield pa.RecordBatch.from_arrays([pa.nulls(len(steps), pa.int64()), pa.array(list(steps.values()), pa.int64()), pa.nulls(len(steps), pa.int64()), pa.array(list(steps), pa.string())], names=["a", "n", "b", "step"])

    found = materialise(dealt.mapInArrow(link, "a long, n long, b long, step string"), "vector-links")
    if log is not None:
        log += [(r[0], r[1]) for r in found.where("step is not null").groupBy("step").agg(F.sum("n")).collect()]
    counts = found.where("a is not null").groupBy("a").agg(F.sum("n").alias("others"))
    roots = connected_components(found.where("b is not null").select("a", "b"), "vector-components")
    named = classes.select("cls", "first", "w").join(counts, F.col("cls") == counts.a, "left").join(roots, F.col("cls") == roots.node, "left")
    named = materialise(named.select("cls", "first", (F.coalesce("others", F.lit(0)) + F.col("w") - 1).alias("n_links"), F.coalesce("root", "cls").alias("root")), "vector-named")
    discard(classes, sizes, large, found, roots)
    least = named.groupBy("root").agg(F.min("first").alias("component_id"))
    named = materialise(named.join(least, "root").select("cls", "n_links", "component_id"), "vector-groups")
    out = rows.select("key", "cls").join(named, "cls", "left")
    out = out.select(F.col("key").alias(key), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "key").cast("long").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col(key) == F.col("component_id"), F.lit(False)))
