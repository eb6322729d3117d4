"""SimHash near-duplicates by meet-in-the-middle ball hashing.

A fingerprint pair within radius 3 has, in one of four 16-bit blocks, at least one differing bit unless it
differs nowhere, so with that block masked out at most two bits differ, and balls of radius 1 (half the
radius) around both meet.  Every distinct fingerprint emits, per masked block, its kept bits and all their
one-bit variants; variants are shuffled as packed arrays, colliding fingerprints are verified by their full
Hamming distance, and each task passes on a spanning forest of the links it found, not all pairs.
Connected components of these forests give the groups.

Edge cases: null and blank texts have fingerprint zero, linked like any other; repeated rows come back once
each; rows with a null id take part but never name a component; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import connected_components, forest, materialise, partitions

RADIUS, BLOCKS, WIDTH = 3, 4, 16
_BITS = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.int64)


def fingerprint(text: str | None, words_in_shingle: int = 3, seed: int = 42) -> int:
    """64-bit majority fingerprint of the word shingles of a whole text."""
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= words_in_shingle:
        return xxhash.xxh64_intdigest(joined, seed)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(size) - 1
    starts = (ends + 1 - size)[: len(words) - words_in_shingle + 1].tolist()
    digest = xxhash.xxh64_intdigest
    return majority(np.array([digest(joined[a:b], seed) for a, b in zip(starts, ends[words_in_shingle - 1 :].tolist(), strict=True)], np.uint64))


def majority(h: np.ndarray) -> int:
    """Bits that are set in over half of the hashes."""
    octets = h.view(np.uint8).reshape(-1, 8).astype(np.int64) + np.arange(8) * 256
    ones = np.bincount(octets.ravel(), minlength=2048).reshape(8, 256) @ _BITS
    bits = (ones * 2 > len(h)).ravel()
    return int(np.packbits(bits, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """``keep`` columns and ``fp`` (the fingerprint as a signed long)."""
    source = docs.select(*keep, F.col(text).alias("_text"))
    schema = docs.select(*keep, F.lit(0).cast("long").alias("fp")).schema

    def run(batches):
        for b in batches:
            fps = np.fromiter((fingerprint(x.as_py()) for x in b.column("_text")), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keep), pa.array(fps.view(np.int64))], names=[*keep, "fp"])

    return source.mapInArrow(run, schema)


def _variants() -> tuple[np.ndarray, np.ndarray]:
    """Mask and flip of each variant: 4 masked blocks x (no flip, or one of the 48 kept bits)."""
    masks, flips = [], []
    for t in range(BLOCKS):
        gone = ((1 << WIDTH) - 1) << (t * WIDTH)
        kept = [0, *(1 << i for i in range(64) if not gone >> i & 1)]
        masks += [~gone & (1 << 64) - 1] * len(kept)
        flips += kept
    return np.array(masks, np.uint64), np.array(flips, np.uint64)


def _deal(keys: np.ndarray, n: int) -> np.ndarray:
    return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)) % np.uint64(n)


def links_in(keys: np.ndarray, fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest of the fingerprints that share a key and lie within the radius."""
    order = np.argsort(keys, kind="stable")
    keys, fps = keys[order], fps[order]
    same = np.flatnonzero(keys[1:] == keys[:-1])
    a, b, d = [np.empty(0, np.uint64)], [np.empty(0, np.uint64)], 1
    held = 0
    while len(same):
        near = same[np.bitwise_count(fps[same] ^ fps[same + d]) <= RADIUS]
        a.append(fps[near])
        b.append(fps[near + d])
        held += len(near)
        if held > 1 << 21:  # a large group: keep its forest only
            x, y = forest(np.concatenate(a), np.concatenate(b))
            a, b, held = [x], [y], len(x)
        d += 1
        same = same[same + d < len(keys)]
        same = same[keys[same] == keys[same + d]]
    return forest(np.concatenate(a), np.concatenate(b))


def ball_edges(distinct: DataFrame) -> DataFrame:
    """Edges (a, b) that connect all fingerprints of column ``fp`` (distinct) within the radius."""
    spark = distinct.sparkSession
    masks, flips = _variants()
    n = max(partitions(spark), distinct.count() * len(masks) // (1 << 21) + 1)

    def emit(batches):
        held: list[list[bytes]] = [[] for _ in range(n)]
        size = 0

        def flush():
            rows = [(i, b"".join(x)) for i, x in enumerate(held) if x]
            for x in held:
                x.clear()
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], names=["part", "pairs"])

        for b in batches:
            fps = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for i in range(0, len(fps), 4096):
                f = fps[i : i + 4096]
                keys = ((f[:, None] & masks) ^ flips).ravel()
                part = _deal(keys, n)
                order = np.argsort(part.astype(np.uint16 if n < 1 << 16 else np.uint64), kind="stable")
                packed = np.empty(len(keys), np.dtype([("fp", "<u8"), ("v", "u1")]))
                packed["fp"], packed["v"] = np.repeat(f, len(masks))[order], (order % len(masks)).astype(np.uint8)
                cuts = np.searchsorted(part[order], np.arange(n + 1))
                for p in range(n):
                    if cuts[p] < cuts[p + 1]:
                        held[p].append(packed[cuts[p] : cuts[p + 1]].tobytes())
                size += packed.nbytes
                if size > 48 << 20:
                    yield flush()
                    size = 0
        if size:
            yield flush()

    def meet(batches):
        by_part: dict[int, list[bytes]] = {}
        for b in batches:
            for p, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                by_part.setdefault(p, []).append(x)
        for x in by_part.values():
            packed = np.frombuffer(b"".join(x), np.dtype([("fp", "<u8"), ("v", "u1")]))
            x.clear()
            fps, v = packed["fp"].copy(), packed["v"]
            a, b = links_in((fps & masks[v]) ^ flips[v], fps)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    return distinct.select("fp").mapInArrow(emit, "part int, pairs binary").repartition(n, "part").mapInArrow(meet, "a long, b long")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, fingerprint (16 hex digits), component_id (least key reachable by links)."""
    fps = materialise(fingerprints(docs, [key], text), "simhash")
    classes = materialise(fps.groupBy("fp").agg(F.min(key).alias("first")), "simhash-classes")
    roots = connected_components(ball_edges(classes), "simhash-links")
    known = classes.join(roots, classes.fp == roots.node, "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    known = materialise(known, "simhash-roots")
    named = known.groupBy("root").agg(F.min("first").alias("component_id"))
    named = known.join(named, "root").select("fp", "component_id")
    out = fps.join(named, "fp", "left")
    return out.select(key, F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
