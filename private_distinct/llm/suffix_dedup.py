"""Removal of repeated byte strings by external induced suffix sorting.

A byte goes if a string of ``length`` bytes that covers it also starts in a document with a smaller id.

1. The least hash of the short grams inside a window of ``length`` bytes depends on the window alone.  Runs of
   windows with the same least hash are segments, and equal windows lie in segments with equal keys.  Keys that
   occur once in the whole corpus cannot repeat; the others go into a filter sized by their number, in ranges of
   hashes where one broadcast could not hold it (``repeats``).
2. Segments with a shared key are dealt by key into shards, equal ones of a task once with their least id.  How
   many shards there are follows from the bytes of all texts.
3. A task takes its shards one after the other.  A shard's text lies in a file and is sorted externally
   (``induced``), with the common prefixes of neighbours; suffixes that share ``length`` bytes form groups, and
   each group's least id decides.  Memory is bounded by ``memory`` and some 30 bytes for each segment; all else is in
   files in Spark's own scratch folders, removed with the shard.
4. Answers meet the occurrences in a join on the segment's hash (a hot segment is a skewed join, not a group),
   and the removed ranges meet the texts by document.

Edge cases: a null text is empty; null ids count as larger than any; rows with the same id never remove each
other's bytes; texts shorter than ``length`` stay whole; an empty table gives no rows; other columns are kept
where asked for.
"""

from __future__ import annotations

import hashlib
import os
import shutil
import tempfile

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import repeats
from .common import discard, free_shuffles, materialise, partitions
from .induced import Suffixes
from .repeats import mixed

LAST = 2**63 - 1
HASHED = 1 << 17  # bytes hashed at once: eight times as much stays in a core's cache
CHUNK, SHARD_BYTES, FILTER_BYTES, MEMORY = 1 << 20, 2 << 20, 128 << 20, 96 << 20


# 1. keys of windows ------------------------------------------------------------------------------


def _sliding(x: np.ndarray, width: int, join) -> np.ndarray:
    """join over x[i : i + width] for each i, by doubling."""
    out, have, left = None, 1, width
    at = 0
    while left:
        if left & have:
            out = x if out is None else join(out[: len(x) - at], x[at:])
            at += have
            left -= have
        if left:
            x = join(x[:-have], x[have:])
            have *= 2
    return out


def gram_hashes(raw: np.ndarray, k: int) -> np.ndarray:
    """Hash of raw[i : i + k] for each i."""
    x = mixed(np.arange(256, dtype=np.uint64) + np.uint64(1))[raw]
    out, have, at, left = None, 1, 0, k
    while left:
        if left & have:
            out = x.copy() if out is None else out[: len(x) - at] * np.uint64(0x9E3779B97F4A7C15) + x[at:]
            at += have
            left -= have
        if left:
            x = x[:-have] * np.uint64(0xD1B54A32D192ED03 + 2 * have) + x[have:]
            have *= 2
    return out ^ (out >> np.uint64(31))


def segments(texts: list[bytes], length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, bytes]:
    """Runs of windows with one key: document, first window, windows, key; and the joined texts."""
    joined = b"".join(texts)
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    none = np.empty(0, np.int64)
    if len(joined) < length:
        return none, none, none, none.astype(np.uint64), joined
    k = length // 2
    keys = _sliding(gram_hashes(np.frombuffer(joined, np.uint8), k), length - k + 1, np.minimum)
    starts = np.cumsum(sizes) - sizes
    first = np.zeros(len(keys), bool)
    first[1:] = keys[1:] != keys[:-1]
    first[starts[starts < len(keys)]] = True
    at = np.flatnonzero(first)
    doc = np.searchsorted(starts, at, side="right") - 1
    end = np.minimum(np.append(at[1:], len(keys)), (starts + sizes)[doc] - length + 1)
    ok = end > at
    return doc[ok], at[ok], (end - at)[ok], keys[at[ok]], joined


def _spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Places of all bytes of ranges, one range after the other."""
    return np.repeat(starts - np.cumsum(sizes) + sizes, sizes) + np.arange(sizes.sum())


def _batches(column, step: int = CHUNK):
    """Slices of a column of binary values of about ``step`` bytes."""
    i, n = 0, len(column)
    while i < n:
        j, size = i, 0
        while j < n and size < step:
            size += len(column[j].as_buffer() or b"")
            j += 1
        yield i, [x or b"" for x in column.slice(i, j - i).to_pylist()]
        i = j


# 3. sorting --------------------------------------------------------------------------------------


def scratch_folder() -> str:
    """A folder of a worker's own on Spark's scratch disks, where the engine spills too."""
    base = os.environ.get("SPARK_LOCAL_DIRS", tempfile.gettempdir()).split(",")[0]
    return tempfile.mkdtemp(prefix="suffixes-", dir=base if os.path.isdir(base) else None)


class Shard:
    """Segments of one shard: their bytes in a file, hashes, least ids and sizes in arrays."""

    def __init__(self, folder: str):
        self.folder, self.raw = folder, os.path.join(folder, "raw")
        self.file, self.arrays = open(self.raw, "wb"), []  # noqa: SIM115  closed by answers()

    def add(self, least: np.ndarray, sizes: np.ndarray, raw: bytes) -> None:
        self.file.write(raw)
        ends, digest = np.cumsum(sizes).tolist(), xxhash.xxh3_64_intdigest
        h = np.fromiter((digest(raw[a:b]) for a, b in zip([0, *ends], ends, strict=False)), np.uint64, len(ends))
        self.arrays.append((h, least, sizes))

    def _unique(self) -> str:
        """Each content once, with its least id."""
        self.file.close()
        h, least, sizes = (np.concatenate([x[i] for x in self.arrays]) for i in range(3))
        self.arrays.clear()
        order = np.lexsort((least, h))
        kept = np.sort(order[np.r_[True, h[order][1:] != h[order][:-1]]])
        at = np.cumsum(sizes) - sizes
        self.h, self.least, self.sizes = h[kept], least[kept], sizes[kept]
        if len(kept) == len(h):
            return self.raw
        path, raw = os.path.join(self.folder, "text"), np.memmap(self.raw, np.uint8, "r")
        ends = np.cumsum(self.sizes)
        with open(path, "wb") as f:
            i = 0
            while i < len(kept):
                j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + CHUNK, side="right")))
                raw[_spread(at[kept[i:j]], self.sizes[i:j])].tofile(f)
                i = j
        del raw
        os.remove(self.raw)
        return path

    def answers(self, length: int, memory: int):
        """(segment hash, first window, windows, least id of their equals) of all windows, block by block."""
        path = self._unique()
        n, ends = int(self.sizes.sum()), np.cumsum(self.sizes)
        starts = ends - self.sizes
        group = np.memmap(os.path.join(self.folder, "group"), "<u4" if n < 2**32 - 1 else "<u8", "w+", shape=n)
        content = np.memmap(os.path.join(self.folder, "content"), "<u4", "w+", shape=n)  # of each byte
        i = 0
        while i < len(ends):
            j = max(i + 1, int(np.searchsorted(ends, starts[i] + CHUNK, side="right")))
            content[starts[i] : ends[j - 1]] = np.repeat(np.arange(i, j, dtype=np.uint32), self.sizes[i:j])
            i = j
        count, low, link = 0, LAST, 0  # groups so far; of the open one its least id; least prefix since the last window
        with open(os.path.join(self.folder, "least"), "wb") as f:
            np.zeros(1, np.int64).tofile(f)  # group 0: no window starts here
            for at, shared in Suffixes(path, length, self.folder, memory).descending():
                of = content[at]
                inside = np.flatnonzero(at + length <= ends[of])
                if not len(inside):
                    link = min(link, int(shared.min()))
                    continue
                least = np.minimum.reduceat(shared[: inside[-1] + 1], np.r_[0, inside[:-1] + 1]).astype(np.int64)
                least[0] = min(int(least[0]), link)
                link = int(shared[inside[-1] + 1 :].min(initial=255))
                ids, new = self.least[of[inside]], least < length
                group[at[inside]] = count + np.cumsum(new)
                first = np.flatnonzero(new)
                if len(first):
                    head = int(ids[: first[0]].min(initial=LAST))
                    found = np.minimum.reduceat(ids, first)
                    closed = np.r_[[min(low, head)] if count else np.empty(0, np.int64), found[:-1]]
                    closed.astype(np.int64).tofile(f)
                    low, count = int(found[-1]), count + len(first)
                else:
                    low = min(low, int(ids.min()))
            if count:
                np.array([low], np.int64).tofile(f)
        least = np.memmap(os.path.join(self.folder, "least"), np.int64, "r")
        step = max(1 << 14, min(1 << 18, memory // 128))
        for a in range(0, n, step):
            g = np.array(group[a : a + step])
            low = least[g]
            place = np.arange(a, a + len(g))
            of = np.array(content[a : a + step])
            cut = np.flatnonzero(np.r_[True, (low[1:] != low[:-1]) | ((g[1:] > 0) != (g[:-1] > 0)) | (of[1:] != of[:-1])])
            many = np.diff(np.append(cut, len(g)))
            ok = g[cut] > 0
            cut, many = cut[ok], many[ok]
            yield self.h[of[cut]], place[cut] - starts[of[cut]], many, low[cut]
        del group, least, content
        for name in ("raw", "text", "group", "least", "content"):
            if os.path.exists(os.path.join(self.folder, name)):
                os.remove(os.path.join(self.folder, name))


# the operator ------------------------------------------------------------------------------------


def repeated_ranges(docs: DataFrame, length: int = 50, shard_bytes: int = SHARD_BYTES, filter_bytes: int = FILTER_BYTES, memory: int = MEMORY) -> DataFrame:
    """(did, dh, gone): byte ranges to remove of documents given as (did, dh, body); dh: 32 bits that tell texts apart."""
    spark = docs.sparkSession
    if length < 16:
        raise ValueError("length must be 16 or more")
    total = docs.agg(F.sum(F.octet_length("body"))).first()[0] or 0
    wide = partitions(spark)
    n = max(min(wide, 64), -(-total // shard_bytes))

    def emit_keys(batches):
        held, size = [], 0
        for b in batches:
            for _, texts in _batches(b.column(0), HASHED):
                doc, _, _, keys, _ = segments(texts, length)
                if len(keys):  # a key counts once for a document
                    order = np.lexsort((doc, keys))
                    k, d = keys[order], doc[order]
                    held.append(k[np.r_[True, (k[1:] != k[:-1]) | (d[1:] != d[:-1])]])
                    size += len(held[-1])
                if size > 3 << 20:
                    yield repeats.dealt(np.concatenate(held), n)
                    held.clear()
                    size = 0
        if size:
            yield repeats.dealt(np.concatenate(held), n)

    shared = repeats.filters(docs.select("body").mapInArrow(emit_keys, repeats.SCHEMA), n, "segment-keys", filter_bytes)

    names = ["part", "sizes", "least", "bytes", "h", "did", "place"]

    def emit_segments(batches, known):
        held: list[tuple[np.ndarray, ...]] = []
        size = 0

        def flush():
            h, part, did, sizes = (np.concatenate([x[i] for x in held]) for i in range(4))
            raw = np.concatenate([x[4] for x in held])
            held.clear()
            codec = pa.Codec("zstd", 6)
            order = np.lexsort((did, h))
            order = order[np.r_[True, h[order][1:] != h[order][:-1]]]  # each content once, with its least id
            order = order[np.argsort(part[order], kind="stable")]
            at = np.cumsum(sizes) - sizes
            part, did, sizes, at = part[order], did[order], sizes[order], at[order]
            cuts = [*np.flatnonzero(np.r_[True, part[1:] != part[:-1]]), len(part)]
            cols: tuple[list, ...] = ([], [], [], [])
            for i, j in zip(cuts, cuts[1:]):
                cols[0].append(part[i])
                cols[1].append(sizes[i:j].astype("<i4").tobytes())
                cols[2].append(did[i:j].astype("<i8").tobytes())
                cols[3].append(codec.compress(raw[_spread(at[i:j], sizes[i:j])].tobytes(), asbytes=True))
            m = len(cols[0])
            return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:]), *(pa.nulls(m, pa.int64()) for _ in range(3))], names=names)

        for b in batches:
            dids, dhs = b.column(0).to_numpy(), b.column(1).to_numpy()
            for i, texts in _batches(b.column(2), HASHED):
                doc, at, count, keys, joined = segments(texts, length)
                some = np.flatnonzero(known.value.maybe(keys))
                doc, at, count, keys = doc[some], at[some], count[some], keys[some]
                m, did, sizes = len(at), dids[i + doc], count + length - 1
                digest = xxhash.xxh3_64_intdigest
                h = np.fromiter((digest(joined[x:y]) for x, y in zip(at.tolist(), (at + sizes).tolist(), strict=True)), np.uint64, m)
                starts = np.cumsum(list(map(len, texts))) - list(map(len, texts))
                place = (dhs[i + doc] << 32) | (at - starts[doc] if m else at)
                yield pa.RecordBatch.from_arrays([pa.nulls(m, pa.int32()), *(pa.nulls(m, pa.binary()) for _ in range(3)), pa.array(h.view(np.int64)), pa.array(did), pa.array(place)], names=names)
                if m:
                    order = np.lexsort((did, h))
                    order = order[np.r_[True, h[order][1:] != h[order][:-1]]]
                    raw = np.frombuffer(joined, np.uint8)[_spread(at[order], sizes[order])]
                    held.append((h[order], repeats.part_of(keys[order], n), did[order], sizes[order], raw))
                    size += len(raw) + 32 * len(order)
                if size > 64 << 20:
                    yield flush()
                    size = 0
        if held:
            yield flush()

    schema = "part int, sizes binary, least binary, bytes binary, h long, did long, place long"
    emitted = None
    for one in shared:
        more = docs.select("did", "dh", "body").mapInArrow(lambda batches, one=one: emit_segments(batches, one), schema)
        emitted = more if emitted is None else emitted.union(more)
    found = materialise(emitted, "segments")

    def resolve(batches):
        codec = pa.Codec("zstd", 6)
        folder = scratch_folder()

        def finished(shard):
            for h, first, count, low in shard.answers(length, memory):
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(first), pa.array(count), pa.array(low)], names=["h", "first", "n", "low"])

        try:
            now, shard = None, None
            for b in batches:
                for r, part in enumerate(b.column(0).to_pylist()):
                    if part != now:
                        if shard:
                            yield from finished(shard)
                        now, shard = part, Shard(folder)
                    sizes, least, raw = (b.column(i)[r].as_py() for i in (1, 2, 3))
                    sizes = np.frombuffer(sizes, "<i4").astype(np.int64)
                    shard.add(np.frombuffer(least, "<i8"), sizes, codec.decompress(raw, int(sizes.sum()), asbytes=True))
            if shard:
                yield from finished(shard)
        finally:
            shutil.rmtree(folder, ignore_errors=True)

    dealt = found.where("part is not null").select("part", "sizes", "least", "bytes").repartition(max(wide, n // 4), "part").sortWithinPartitions("part")
    answers = materialise(dealt.mapInArrow(resolve, "h long, first long, n long, low long"), "answers")
    free_shuffles(spark)
    seen = found.where("part is null").select("h", "did", "place")
    out = seen.join(answers, "h").where("did > low")
    start = F.col("place").bitwiseAND(F.lit(2**32 - 1)) + F.col("first")
    out = out.select("did", F.shiftright("place", 32).alias("dh"), start.cast("int").alias("s"), (start + F.col("n") + F.lit(length - 1)).cast("int").alias("e"))
    out = materialise(out.groupBy("did", "dh").agg(F.collect_list(F.struct("s", "e")).alias("gone")), "ranges")  # a document's own
    discard(found, answers)
    free_shuffles(spark)
    return out


def with_ranges(docs: DataFrame, keep: list[str], key: str = "doc_id", text: str = "text", length: int = 50) -> DataFrame:
    """``keep`` columns, ``_body`` (the text's bytes) and ``_gone`` (ranges to remove, not merged)."""
    body = F.coalesce(F.col(text), F.lit("")).cast("binary")
    rows = docs.select(*[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)], F.coalesce(F.col(key).cast("long"), F.lit(LAST)).alias("did"), F.shiftright(F.xxhash64(body), 32).alias("dh"), body.alias("body"))
    ranges = repeated_ranges(rows.select("did", "dh", "body"), length)
    out = rows.join(ranges, ["did", "dh"], "left")
    return out.select(*[F.col(f"k{i}").alias(c) for i, c in enumerate(keep)], F.col("body").alias("_body"), F.col("gone").alias("_gone"))


def cut(body: bytes, gone: list | None) -> tuple[bytes, int, int]:
    """Remaining bytes, number of bytes removed, number of maximal removed runs."""
    return without(body, *(np.array([g[c] for g in gone or []], np.int64) for c in ("s", "e")))


def without(body: bytes, start: np.ndarray, end: np.ndarray) -> tuple[bytes, int, int]:
    """The same for ranges as arrays."""
    if not len(start):
        return body, 0, 0
    order = np.argsort(start)
    start, reach = start[order], np.maximum.accumulate(end[order])
    first = np.r_[True, start[1:] > reach[:-1]]  # ranges that touch are one run
    start, end = start[first].tolist(), reach[np.r_[first[1:], True]].tolist()
    left = b"".join([body[a:b] for a, b in zip([0, *end], [*start, len(body)], strict=True)])
    return left, len(body) - len(left), len(start)


def remove(docs: DataFrame, keep: list[str], key: str = "doc_id", text: str = "text", length: int = 50, as_text: bool = False) -> DataFrame:
    """``keep`` columns, n_bytes, n_removed, n_spans, kept_sha256; ``as_text`` adds kept_text.

    A cut inside a character leaves stray bytes, which kept_text drops; the digest is of the exact bytes.
    """
    rows = with_ranges(docs, keep, key, text, length)
    more = [F.lit("").alias("kept_text")] if as_text else []
    schema = docs.select(*keep, *[F.lit(0).cast("long").alias(c) for c in ("n_bytes", "n_removed", "n_spans")], F.lit("").alias("kept_sha256"), *more).schema

    def run(batches):
        for b in batches:
            bodies, gone = b.column(len(keep)), b.column(len(keep) + 1)
            many = pc.fill_null(pc.list_value_length(gone), 0).to_numpy(zero_copy_only=False)
            ranges = gone.flatten()  # of no range, where a document has none
            starts, stops = (ranges.field(c).to_numpy(zero_copy_only=False) for c in ("s", "e"))
            ends = np.cumsum(many, dtype=np.int64).tolist()
            out: tuple[list, ...] = ([], [], [], [], [])
            for x, i, j in zip(bodies, [0, *ends], ends, strict=False):
                body = x.as_py()
                left, n, spans = without(body, starts[i:j], stops[i:j])
                for c, v in zip(out, (len(body), n, spans, hashlib.sha256(left).hexdigest(), left.decode(errors="ignore") if as_text else None), strict=True):
                    c.append(v)
            types = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string())
            cols = [pa.array(c, t) for c, t in zip(out, types, strict=True)][: 5 if as_text else 4]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], *cols], names=[*keep, "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text"][: len(keep) + len(cols)])

    return rows.mapInArrow(run, schema)
