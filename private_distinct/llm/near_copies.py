"""Near copies: texts whose sets of five-word shingles have a Jaccard similarity of 0.8 or more, found exactly.

SimHash comes first: fingerprints of the five-word shingles within three bits meet through their half-radius
balls (``simhash.ball_edges``), and what meets is verified by the sets themselves.  That links most copies, but a
64-bit fingerprint is too coarse to find them all: at similarity 0.83 fingerprints of the given tables differ in
up to 17 bits.  So a second pass finds the rest.  Sets are ordered by one order of all shingles, those common in
a sample of texts last.  Of two sets of similarity t, the first size - ceil(t size) + 1 shingles of each share one,
whatever the order, so these prefixes are dealt by shingle and sets that meet are compared whole.  Shingles that
one prefix has alone are left out by a filter of repeated keys; sizes, places in the order and the numbers of
shingles in each of 256 ranges (which bound what two sets can share) rule out pairs before sets are fetched; pairs
already in one component are left out, so a large group of copies costs no square of its size.

Edge cases: null and blank texts share the empty set and are one class; a text shorter than a shingle is one
shingle; equal sets are one class; texts, sets and shingles are told apart by 64-bit hashes.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import repeats
from .common import connected_components, discard, forest, free_shuffles, materialise, partitions
from .simhash import ball_edges, majority

WORDS, SIMILARITY, SAMPLE, COMMON = 5, 0.8, 8192, 1 << 19
REACH = (4, 32, None)  # the last round compares all that is left
_POSTING = np.dtype([("shingle", "<u8"), ("cls", "<i8"), ("root", "<i8"), ("size", "<u4"), ("place", "<u4"), ("before", "<u8")])


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """Hashes of the word shingles of a whole text, repeats included."""
    found = (text or "").encode().lower().split()
    if not found:
        return np.empty(0, np.uint64)
    if len(found) <= words:
        return np.array([xxhash.xxh64_intdigest(b" ".join(found), 42)], np.uint64)
    joined = b" ".join(found)
    size = np.fromiter(map(len, found), np.int64, len(found)) + 1
    ends = np.cumsum(size) - 1
    starts = (ends + 1 - size)[: len(found) - words + 1].tolist()
    digest = xxhash.xxh64_intdigest
    return np.array([digest(joined[a:b], 42) for a, b in zip(starts, ends[words - 1 :].tolist(), strict=True)], np.uint64)


def shingle_set(text: str | None, words: int = WORDS) -> np.ndarray:
    """Sorted distinct hashes."""
    return np.unique(shingles(text, words))


def class_of(found: np.ndarray) -> int:
    return int(np.array(xxhash.xxh3_64_intdigest(found.tobytes()), np.uint64).view(np.int64))


def tally(found: np.ndarray) -> bytes:
    """How many of the shingles of a set lie in each of 256 ranges."""
    n = np.bincount((found >> np.uint64(56)).astype(np.int64), minlength=256)
    return n.astype(np.uint8 if n.max() < 256 else "<u4").tobytes()


def from_tally(raw: bytes) -> np.ndarray:
    return np.frombuffer(raw, np.uint8 if len(raw) == 256 else "<u4").astype(np.int64)


def text_hash(text: str) -> Column:
    return F.xxhash64(F.coalesce(F.col(text), F.lit("")))


def least_overlap(a: np.ndarray, b: np.ndarray, similarity: float) -> np.ndarray:
    """Shared shingles that sets of these sizes need."""
    return np.ceil(similarity / (1 + similarity) * (a + b) - 1e-9)


def similar(a: np.ndarray, b: np.ndarray, similarity: float) -> bool:
    shared = len(a) + len(b) - len(np.union1d(a, b))
    return shared >= similarity * (len(a) + len(b) - shared) - 1e-9


def common_shingles(docs: DataFrame, text: str, words: int) -> np.ndarray:
    """Shingles of more than one text of a sample, rarest first; they only set the order, not the result."""
    n = docs.count()
    some = docs.select(F.col(text).alias("t")).where(F.pmod(F.xxhash64("t"), F.lit(max(1, n // SAMPLE))) == 0).dropDuplicates(["t"])

    def run(batches):
        for b in batches:
            found = [shingle_set(x, words) for x in b.column(0).to_pylist()]
            h, c = np.unique(np.concatenate(found), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(c)], names=["h", "c"])

    top = some.mapInArrow(run, "h long, c long").groupBy("h").agg(F.sum("c").alias("c")).where("c > 1")
    rows = top.orderBy(F.desc("c"), "h").limit(COMMON).select("h").toArrow()
    return rows.column(0).to_numpy()[::-1].view(np.uint64)


def signed(docs: DataFrame, text: str, words: int, similarity: float) -> DataFrame:
    """For each row hashes of the row and of its text, its class (hash of the set), set size, fingerprint, tally and prefix in the common order."""
    common = common_shingles(docs, text, words)
    by = np.argsort(common)
    shared = docs.sparkSession.sparkContext.broadcast((common[by], by))  # at most COMMON shingles

    def run(batches):
        known, rank = shared.value
        for b in batches:
            cls, sizes, fps, tallies, prefixes = [], [], [], [], []
            for x in b.column(2):
                all_ = shingles(x.as_py(), words)
                fps.append(majority(all_))
                s = np.unique(all_)
                cls.append(class_of(s))
                sizes.append(len(s))
                tallies.append(tally(s))
                if len(known) and len(s):
                    i = np.minimum(np.searchsorted(known, s), len(known) - 1)
                    s = s[np.argsort(np.where(known[i] == s, rank[i], -1), kind="stable")]
                prefixes.append(s[: len(s) - math.ceil(similarity * len(s) - 1e-9) + 1].tobytes())
            new = [pa.array(cls, pa.int64()), pa.array(sizes, pa.int32()), pa.array(np.array(fps, np.uint64).view(np.int64)), pa.array(tallies, pa.binary()), pa.array(prefixes, pa.binary())]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *new], names=["rk", "th", "cls", "size", "fp", "tally", "prefix"])

    rows = docs.select(F.xxhash64(*docs.columns).alias("rk"), text_hash(text).alias("th"), F.col(text).alias("_text"))
    return rows.mapInArrow(run, "rk long, th long, cls long, size int, fp long, tally binary, prefix binary")


def meeting(rows: np.ndarray, similarity: float, after: int, reach: int | None) -> np.ndarray:
    """Pairs of classes, as rows (a, b), that share a shingle of their prefixes, may be similar and have different roots.

    ``reach``: each with so many next larger ones of its shingle only, so no more pairs than rows times that.
    ``after``: the reach of the round before, whose pairs were compared; a shingle's rows are the same in all rounds.
    Two classes meet at the first shingle of each run of shared ones only, so seldom in many tasks.
    """
    rows = rows[np.lexsort((rows["cls"], rows["size"], rows["shingle"]))]
    first = np.flatnonzero(np.r_[True, rows["shingle"][1:] != rows["shingle"][:-1]])
    n = np.diff(np.append(first, len(rows)))
    mixed = np.minimum.reduceat(rows["root"], first) != np.maximum.reduceat(rows["root"], first)
    rows = rows[np.repeat(mixed, n)]  # shingles of one component have nothing to add
    key, cls, root = rows["shingle"], rows["cls"], rows["root"]
    size, place = rows["size"].astype(np.int64), rows["place"].astype(np.int64)
    same, d, found, held = np.arange(len(rows)), after + 1, [np.empty((0, 2), np.int64)], 0
    while True:
        same = same[same + d < len(rows)]
        same = same[(key[same] == key[same + d]) & (size[same] >= similarity * size[same + d] - 1e-9)]  # sizes rise
        if not len(same):
            break
        i, j = same, same + d
        left = np.minimum(size[i] - place[i], size[j] - place[j])  # no more are shared if this is the first one
        run = (place[i] > 0) & (place[j] > 0) & (rows["before"][i] == rows["before"][j])  # they meet at that one
        ok = (root[i] != root[j]) & ~run & (left >= least_overlap(size[i], size[j], similarity))
        i, j = i[ok], j[ok]
        found.append(np.stack([np.minimum(cls[i], cls[j]), np.maximum(cls[i], cls[j])], 1))
        held += len(i)
        if held > 1 << 21:
            found = [np.unique(np.concatenate(found), axis=0)]
            held = len(found[0])
        d += 1
        if reach and d > reach:
            break
    return np.unique(np.concatenate(found), axis=0)


def repeated_shingles(classes: DataFrame) -> list:
    """Filters of the shingles that more than one prefix has."""
    many = max(256, 4 * partitions(classes.sparkSession))

    def keys(batches):
        held, size = [], 0
        for b in batches:
            held += [np.frombuffer(x, "<u8") for x in b.column(0).to_pylist()]
            size += sum(map(len, held[-b.num_rows :])) if b.num_rows else 0
            if size > 3 << 20:
                yield repeats.dealt(np.concatenate(held), many)
                held, size = [], 0
        if size:
            yield repeats.dealt(np.concatenate(held), many)

    return repeats.filters(classes.select("prefix").mapInArrow(keys, repeats.SCHEMA), many, "copy-shingles")


def candidates(classes: DataFrame, known: list, similarity: float, after: int, reach: int | None) -> DataFrame:
    """Distinct pairs (a, b) of ``classes`` (cls, root, size, prefix) with different roots that may be similar."""
    n = partitions(classes.sparkSession)

    def emit_for(filter_):
        def emit(batches):
            held: list[np.ndarray] = []

            def flush():
                rows = np.concatenate(held)
                held.clear()
                rows = rows[filter_.value.maybe(rows["shingle"])]
                part = ((rows["shingle"] >> np.uint64(20)) % np.uint64(n)).astype(np.int64)
                order = np.argsort(part, kind="stable")
                rows, cuts = rows[order], np.searchsorted(part[order], np.arange(n + 1))
                some = [p for p in range(n) if cuts[p] < cuts[p + 1]]
                return pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array([rows[cuts[p] : cuts[p + 1]].tobytes() for p in some], pa.binary())], names=["part", "rows"])

            size = 0
            for b in batches:
                for cls, root, length, prefix in zip(*(c.to_pylist() for c in b.columns), strict=True):
                    h = np.frombuffer(prefix, "<u8")
                    if len(h):
                        rows = np.empty(len(h), _POSTING)
                        rows["shingle"], rows["cls"], rows["root"], rows["size"], rows["place"] = h, cls, root, length, np.arange(len(h))
                        rows["before"] = np.roll(h, 1)
                        held.append(rows)
                        size += rows.nbytes
                    if size > 32 << 20:
                        yield flush()
                        size = 0
            if held:
                yield flush()

        return emit

    def meet(batches):
        by_part: dict[int, list[bytes]] = {}
        for b in batches:
            for p, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                by_part.setdefault(p, []).append(x)
        for x in by_part.values():
            pairs = meeting(np.frombuffer(b"".join(x), _POSTING), similarity, after, reach)
            x.clear()
            for i in range(0, len(pairs), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(pairs[i : i + (1 << 16), 0]), pa.array(pairs[i : i + (1 << 16), 1])], names=["a", "b"])

    postings = None
    for f in known:
        more = classes.select("cls", "root", "size", "prefix").mapInArrow(emit_for(f), "part int, rows binary")
        postings = more if postings is None else postings.union(more)
    return postings.repartition(n, "part").mapInArrow(meet, "a long, b long").distinct()


def sets_of(wanted: DataFrame, docs: DataFrame, text: str, words: int) -> DataFrame:
    """(rk, s) for the rows ``wanted`` (rk), and a few more: sets are made where the texts are read, nothing is shuffled."""
    n = max(256, 4 * partitions(docs.sparkSession))

    def keys(batches):
        for b in batches:
            if b.num_rows:
                yield repeats.dealt(repeats.mixed(b.column(0).to_numpy().view(np.uint64)), n)

    parts = repeats.filters(wanted.select("rk").mapInArrow(keys, repeats.SCHEMA), n, "copy-wanted", least=1)

    def sets_for(filter_):
        def run(batches):
            for b in batches:
                rk = b.column(0).to_numpy()
                at = np.flatnonzero(filter_.value.maybe(repeats.mixed(rk.view(np.uint64))))
                for i in range(0, len(at), 256):
                    some = pa.array(at[i : i + 256])
                    found = [shingle_set(x, words).tobytes() for x in b.column(1).take(some).to_pylist()]
                    yield pa.RecordBatch.from_arrays([b.column(0).take(some), pa.array(found, pa.binary())], names=["rk", "s"])

        return run

    made = None
    for f in parts:
        more = docs.select(F.xxhash64(*docs.columns).alias("rk"), F.col(text).alias("_text")).mapInArrow(sets_for(f), "rk long, s binary")
        made = more if made is None else made.union(more)
    return made


def links(pairs: DataFrame, classes: DataFrame, docs: DataFrame, text: str, words: int, similarity: float) -> DataFrame:
    """Forests of those ``pairs`` (a, b) of classes whose sets are similar."""

    def possible(batches):
        for b in batches:
            if b.num_rows:
                x, y = (np.array([from_tally(t) for t in b.column(i).to_pylist()]) for i in (4, 5))
                ok = np.minimum(x, y).sum(1) >= least_overlap(x.sum(1), y.sum(1), similarity)
                yield pa.RecordBatch.from_arrays([c.filter(pa.array(ok)) for c in b.columns[:4]], names=["a", "b", "ra", "rb"])

    def verify(batches):
        for b in batches:
            a, z, x, y = (c.to_pylist() for c in b.columns)
            ok = [similar(np.frombuffer(s, "<u8"), np.frombuffer(t, "<u8"), similarity) for s, t in zip(x, y, strict=True)]
            i, j = (np.array(v, np.int64)[np.array(ok, bool)] for v in (a, z))
            i, j = forest(i, j)
            yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j)], names=["a", "b"])

    spark = docs.sparkSession
    pairs = materialise(pairs, "copy-pairs")
    free_shuffles(spark)
    known = classes.select("cls", "rk", "tally")
    both = pairs.join(known.select(F.col("cls").alias("a"), F.col("rk").alias("ra"), F.col("tally").alias("x")), "a").join(known.select(F.col("cls").alias("b"), F.col("rk").alias("rb"), F.col("tally").alias("y")), "b")
    left = materialise(both.select("a", "b", "ra", "rb", "x", "y").mapInArrow(possible, "a long, b long, ra long, rb long"), "copy-possible")
    discard(pairs)
    free_shuffles(spark)
    held = materialise(sets_of(left.select(F.col("ra").alias("rk")).union(left.select("rb")).distinct(), docs, text, words), "copy-sets")
    free_shuffles(spark)
    both = left.join(held.select(F.col("rk").alias("ra"), F.col("s").alias("x")), "ra").join(held.select(F.col("rk").alias("rb"), F.col("s").alias("y")), "rb")
    out = materialise(both.select("a", "b", "x", "y").mapInArrow(verify, "a long, b long"), "copy-links")
    discard(held, left)
    free_shuffles(spark)
    return out


def groups(docs: DataFrame, text: str = "text", words: int = WORDS, similarity: float = SIMILARITY) -> DataFrame:
    """(th, root) for every distinct text of ``docs``; equal roots for near copies."""
    spark = docs.sparkSession
    rows = materialise(signed(docs, text, words, similarity), "copy-rows")
    one = rows.groupBy("cls").agg(F.first(F.struct("rk", "size", "fp", "tally", "prefix")).alias("x")).select("cls", "x.*")
    classes = materialise(one, "copy-classes")
    named = materialise(rows.select("th", "cls").distinct(), "copy-texts")
    discard(rows)
    free_shuffles(spark)
    by_print = materialise(classes.groupBy("fp").agg(F.min("cls").alias("first")), "copy-prints")
    met = ball_edges(by_print.select("fp"))
    met = met.join(by_print.select(F.col("fp").alias("a"), F.col("first").alias("x")), "a").join(by_print.select(F.col("fp").alias("b"), F.col("first").alias("y")), "b")
    equal = classes.select("fp", "cls").join(by_print, "fp").where("cls <> first").select(F.col("first").alias("x"), F.col("cls").alias("y"))
    pairs = met.select("x", "y").union(equal).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
    found = links(pairs, classes, docs, text, words, similarity)
    discard(by_print)
    roots = connected_components(found, "copies")
    known = repeated_shingles(classes)
    for after, reach in zip((0, *REACH), REACH, strict=False):  # near ones by size first: they link most of a group, and so leave few pairs
        rooted = classes.join(roots, classes.cls == roots.node, "left").select(classes.cls, "size", "prefix", F.coalesce("root", "cls").alias("root"))
        more = links(candidates(rooted, known, similarity, after, reach), classes, docs, text, words, similarity)
        discard(roots)
        found = found.union(more)
        roots = connected_components(found, "copies")
    out = materialise(named.join(roots, named.cls == roots.node, "left").select("th", F.coalesce("root", "cls").alias("root")), "copy-groups")
    discard(classes, roots, named)
    free_shuffles(spark)
    return out
