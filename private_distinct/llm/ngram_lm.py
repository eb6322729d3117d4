"""N-gram language-model scores from a log-frequency Bloom filter.

Counting: each task counts its n-grams as sorted 64-bit hashes, deals them as packed arrays by hash, and each
receiver merges its range, so a frequent word sends one entry per task.  A count c is stored as its level
1 + floor(log_base c): the filter gets the n-gram once for each level up to it, and a reader probes level after
level until one is missing.  Every n-gram of the corpus is in the filter, once-seen ones too; it is sized by their
number, ``key_bits`` bits for each entry, so it grows with the input.  A filter of more than ``limit`` bytes is cut
into ranges of hashes, each broadcast by itself, and the texts are passed over once a range, each pass adding the
levels that it knows: no broadcast outgrows the limit and no n-gram is left out.
Scoring uses Dirichlet smoothing over orders: p(w|h) = (c(hw) + mu p(w|h')) / (c(h) + mu), down to an
add-one unigram; counts come from the filter only.

``base_score`` is the exact add-one unigram score.  Words up to a fixed number, the most frequent, are
broadcast with their counts; the others that the filter knows are looked up by a shuffle join, each text sending a
word once with its number.

Edge cases: a null or blank text has its end token only; a null id hashes as an empty string; with no training
rows every token has count 0; repeated rows are scored once each; an empty table gives no rows; other columns are
ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise, partitions
from .repeats import mixed

END = xxhash.xxh64_intdigest(b" end")  # a word has no space, so this is none
LOW = np.uint64((1 << 40) - 1)


def token_hashes(text: str | None) -> np.ndarray:
    """Hashes of the lower-cased words of a text, then of the end token."""
    words = (text or "").encode().lower().split()
    return np.fromiter((*map(xxhash.xxh64_intdigest, words), END), np.uint64, len(words) + 1)


def ngram_hashes(h: np.ndarray, order: int) -> np.ndarray:
    """Hash of each n-gram of this order, by its last token."""
    out = h
    for k in range(1, order):
        out = mixed(out[1:] * np.uint64(0x9E3779B97F4A7C15) + h[: len(h) - k])
    return out


def _split(texts: list) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all tokens of some texts and the number of tokens of each."""
    found = [token_hashes(t) for t in texts]
    return (np.concatenate(found) if found else np.empty(0, np.uint64)), np.array([len(x) for x in found], np.int64)


def _orders(h: np.ndarray, sizes: np.ndarray, order: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For orders 1..order: n-gram hashes that stay inside a text, and their last tokens' places."""
    ends = np.cumsum(sizes)
    inside = np.arange(len(h)) - np.repeat(ends - sizes, sizes)
    out = []
    for k in range(1, order + 1):
        at = np.flatnonzero(inside >= k - 1)
        out.append((h if k == 1 else ngram_hashes(h, k)[at - k + 1] if len(h) >= k else h[:0], at))
    return out


def _merge(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.empty(0, np.int64)
    return keys[first], np.add.reduceat(counts, first) if len(first) else counts


class LogBloom:
    """One range of the filter: count levels of n-grams by repeated membership probes.

    ``table`` has a segment of bits for each (order, part) whose part falls in this range.
    """

    def __init__(self, table: np.ndarray, first: np.ndarray, bits: np.ndarray, probes: int, ranges: int, mine: int):
        self.table, self.first, self.bits, self.probes, self.ranges, self.mine = table, first, bits, probes, ranges, mine
        self.parts = bits.shape[1]

    def level(self, order: int, h: np.ndarray) -> np.ndarray:
        """Level of each hash, 0 if unknown or of another range."""
        out = np.zeros(len(h), np.uint8)
        part = ((h >> np.uint64(40)) % np.uint64(self.parts)).astype(np.int64)
        at, level = np.flatnonzero((part % self.ranges == self.mine) & (self.bits[order - 1, part] > 0)), 1
        home, wide = self.first[order - 1, part], self.bits[order - 1, part].astype(np.uint64)
        while len(at):
            for i in range(self.probes):
                place = home[at] + probe(h[at] & LOW, level, i, wide[at]).astype(np.int64)
                at = at[(self.table[place >> 3] >> (place & 7).astype(np.uint8)) & 1 > 0]
            out[at] = level
            level += 1
        return out


def probe(low: np.ndarray, level: int, i: int, bits) -> np.ndarray:
    return mixed(low + np.uint64((level * 0x9E3779B97F4A7C15 + i * 0xD1B54A32D192ED03) % 2**64)) % (bits if isinstance(bits, np.ndarray) else np.uint64(bits))


def count_level(c: np.ndarray, base: float) -> np.ndarray:
    return 1 + np.floor(np.log(c) / np.log(base) + 1e-9).astype(np.int64)


def level_count(level: np.ndarray, base: float) -> np.ndarray:
    """Mean of the counts that share a level, 0 for level 0."""
    low = np.ceil(base ** (level - 1.0) - 1e-9)
    high = np.maximum(np.ceil(base ** np.maximum(level, 1) - 1e-9) - 1, low)
    return np.where(level > 0, (low + high) / 2, 0.0)


def segment(low: np.ndarray, level: np.ndarray, bits: int, probes: int) -> bytes:
    """Write side: the filter segment of one range of hashes."""
    table = np.zeros(bits, bool)
    for j in range(1, int(level.max(initial=0)) + 1):
        some = low[level >= j]
        for i in range(probes):
            table[probe(some, j, i, bits).astype(np.int64)] = True
    return np.packbits(table, bitorder="little").tobytes()


class Smoothing:
    """Probabilities from count levels."""

    def __init__(self, tokens: int, kinds: int, order: int, mu: float, base: float):
        self.tokens, self.kinds, self.order, self.mu, self.base = tokens, kinds, order, mu, base

    def log10p(self, levels: list[np.ndarray]) -> np.ndarray:
        """log10 probability of each token given those before it in its text; ``levels``: of its n-gram of each order."""
        lower = level_count(levels[0].astype(np.int64), self.base)
        p = (lower + 1) / (self.tokens + self.kinds + 1)
        for found in levels[1:]:
            c = level_count(found.astype(np.int64), self.base)
            context = np.r_[0.0, lower[:-1]]  # of the n-gram one shorter that ends a token earlier
            context = np.where(found == NONE, 0.0, np.maximum(context, c))
            c = np.where(found == NONE, 0.0, c)
            p = (c + self.mu * p) / (context + self.mu)
            lower = c
        return np.log10(p)


NONE = 255  # level of a place where no n-gram of the order ends


def token_levels(h: np.ndarray, sizes: np.ndarray, order: int, bloom: LogBloom) -> list[np.ndarray]:
    """Level of the n-gram of each order that ends at each token."""
    out = []
    for k, (g, at) in enumerate(_orders(h, sizes, order), 1):
        some, where = np.unique(g, return_inverse=True)  # frequent n-grams take the most probes
        levels = np.full(len(h), NONE, np.uint8)
        levels[at] = bloom.level(k, some)[where]
        out.append(levels)
    return out


def count_ngrams(docs: DataFrame, text: str, order: int, flush: int = 3 << 20) -> DataFrame:
    """ord, part, low hash bits and counts of all n-grams: rows of packed arrays, one or more per part."""
    n = partitions(docs.sparkSession)

    def packed(kind: int, keys: np.ndarray, counts: np.ndarray):
        part = ((keys >> np.uint64(40)) % np.uint64(n)).astype(np.int64)
        by = np.lexsort((keys & LOW, part))
        keys, counts, part = keys[by], counts[by], part[by]
        cuts = np.searchsorted(part, np.arange(n + 1))
        for p in range(n):
            k, c = keys[cuts[p] : cuts[p + 1]], counts[cuts[p] : cuts[p + 1]]
            if len(k):  # unigrams keep all bits as they are joined on; high bits of sorted low parts press well
                low = k & LOW
                yield kind, p, (k.tobytes() if kind == 1 else (low >> np.uint64(32)).astype(np.uint8).tobytes() + (low & np.uint64(0xFFFFFFFF)).astype("<u4").tobytes()), c.astype("<u4").tobytes()

    def rows(held: list) -> pa.RecordBatch:
        out = []
        for k, found in enumerate(held, 1):
            keys = np.concatenate(found)
            out += packed(k, *_merge(keys, np.ones(len(keys), np.int64)))
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in out], pa.int32()), pa.array([r[1] for r in out], pa.int32()), pa.array([r[2] for r in out], pa.binary()), pa.array([r[3] for r in out], pa.binary())], names=["ord", "part", "keys", "counts"])

    def emit(batches):
        held, size = [[] for _ in range(order)], 0
        for b in batches:
            texts = b.column(0)
            for i in range(0, len(texts), 512):
                h, sizes = _split(texts.slice(i, 512).to_pylist())
                for k, (g, _) in enumerate(_orders(h, sizes, order)):
                    held[k].append(g)
                size += len(h)
                if size > flush:
                    yield rows(held)
                    held, size = [[] for _ in range(order)], 0
        if size:
            yield rows(held)

    def merge(batches):
        held: dict[tuple[int, int], list] = {}
        for b in batches:
            for kind, part, keys, counts in zip(*(c.to_pylist() for c in b.columns), strict=True):
                c = np.frombuffer(counts, "<u4").astype(np.int64)
                if kind == 1:
                    k = np.frombuffer(keys, "<u8")
                else:
                    k = np.frombuffer(keys, np.uint8, len(c)).astype(np.uint64) << np.uint64(32) | np.frombuffer(keys, "<u4", len(c), len(c))
                mine = held.setdefault((kind, part), [])
                mine.append((k, c))
                if len(mine) > 16:  # keep what is held near the size of the result
                    mine[:] = [_merge(np.concatenate([x[0] for x in mine]), np.concatenate([x[1] for x in mine]))]
        for (kind, part), mine in held.items():
            k, c = _merge(np.concatenate([x[0] for x in mine]), np.concatenate([x[1] for x in mine]))
            mine.clear()
            yield pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([part], pa.int32()), pa.array([k.tobytes()], pa.binary()), pa.array([c.astype("<i8").tobytes()], pa.binary())], names=["ord", "part", "keys", "counts"])

    schema = "ord int, part int, keys binary, counts binary"
    return docs.select(text).mapInArrow(emit, schema).repartition(n, "part").mapInArrow(merge, schema)


def _levels(counted: DataFrame, base: float) -> dict[tuple[int, int], tuple[int, int]]:
    """(order, level) -> (how many n-grams, sum of their counts): a few hundred rows at any size."""

    def run(batches):
        for b in batches:
            for kind, counts in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                c = np.frombuffer(counts, "<i8")
                if len(c):
                    level = count_level(c, base)
                    n = np.bincount(level)
                    total = np.zeros(len(n), np.int64)
                    np.add.at(total, level, c)
                    at = np.flatnonzero(n)
                    yield pa.RecordBatch.from_arrays([pa.array([kind] * len(at), pa.int32()), pa.array(at, pa.int64()), pa.array(n[at], pa.int64()), pa.array(total[at], pa.int64())], names=["ord", "level", "n", "total"])

    got = counted.select("ord", "counts").mapInArrow(run, "ord int, level long, n long, total long")
    return {(r[0], r[1]): (r[2], r[3]) for r in got.groupBy("ord", "level").agg(F.sum("n"), F.sum("total")).collect()}


def build_filter(counted: DataFrame, order: int, base: float, probes: int, key_bits: float, limit: int) -> list:
    """Broadcast ranges of the filter, each of about ``limit`` bytes at most (one part is the least a range can be)."""
    spark = counted.sparkSession
    n = partitions(spark)

    def entries(batches):
        for b in batches:
            for kind, part, counts in zip(*(c.to_pylist() for c in b.columns), strict=True):
                c = np.frombuffer(counts, "<i8")
                yield pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([part], pa.int32()), pa.array([int(count_level(np.maximum(c, 1), base).sum())], pa.int64())], names=["ord", "part", "n"])

    sizes = counted.select("ord", "part", "counts").mapInArrow(entries, "ord int, part int, n long").groupBy("ord", "part").agg(F.sum("n")).collect()  # orders x parts rows
    bits = np.zeros((order, n), np.int64)
    for k, p, m in sizes:
        bits[k - 1, p] = max(64, int(m * key_bits) // 8 * 8 + 8)
    ranges = min(n, max(1, -(-int(bits.sum()) // 8 // limit)))

    def build(batches):
        for b in batches:
            for kind, part, keys, counts in zip(*(c.to_pylist() for c in b.columns), strict=True):
                level = count_level(np.maximum(np.frombuffer(counts, "<i8"), 1), base)
                table = segment(np.frombuffer(keys, "<u8") & LOW, level, int(bits[kind - 1, part]), probes)
                yield pa.RecordBatch.from_arrays([pa.array([kind - 1], pa.int32()), pa.array([part], pa.int32()), pa.array([table], pa.binary())], names=["ord", "part", "bits"])

    out = []
    for r in range(ranges):
        mine = np.where(np.arange(n) % ranges == r, bits, 0)
        first = (np.cumsum(mine.ravel()) - mine.ravel()).reshape(order, n)
        table = np.zeros(int(mine.sum()) // 8 + 8, np.uint8)
        got = counted.where(F.col("part") % ranges == r).mapInArrow(build, "ord int, part int, bits binary").toLocalIterator()
        for k, p, x in got:  # ``limit`` bytes in all
            at = int(first[k, p]) // 8
            table[at : at + len(x)] = np.frombuffer(bytes(x), np.uint8)
        out.append(spark.sparkContext.broadcast(LogBloom(table, first, mine, probes, ranges, r)))
    return out


def score(docs: DataFrame, train: str, key: str = "doc_id", text: str = "text", order: int = 2, base: float = 1.5, mu: float = 1000.0, probes: int = 3, key_bits: float = 10.0, limit: int = 128 << 20, broadcast_words: int = 1 << 20) -> DataFrame:
    """Scores of all rows by a model of the rows where the SQL condition ``train`` holds.

    Returns key, trained (boolean), n_tokens, n_known, train_tokens, base_score and score.
    """
    spark = docs.sparkSession
    sc = spark.sparkContext
    source = docs.select(F.col(key).alias("_key"), F.col(text).alias("_text"), F.coalesce(F.expr(train), F.lit(False)).alias("_train"))
    counted = materialise(count_ngrams(source.where("_train"), "_text", order), "ngrams")
    levels = _levels(counted, base)
    tokens = sum(t for (k, _), (_, t) in levels.items() if k == 1)
    kinds = sum(c for (k, _), (c, _) in levels.items() if k == 1)
    ranges = build_filter(counted, order, base, probes, key_bits, limit)
    smooth = Smoothing(tokens, kinds, order, mu, base)

    def words(batches):
        for b in batches:
            for keys, counts in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(keys, "<i8")), pa.array(np.frombuffer(counts, "<i8"))], names=["h", "c"])

    known = counted.where("ord = 1").select("keys", "counts").mapInArrow(words, "h long, c long")
    by_level = sorted(((j, c) for (o, j), (c, _) in levels.items() if o == 1), reverse=True)
    cut, total = 1, 0  # least count of the words that are broadcast
    for j, c in by_level:
        if total + c > broadcast_words:
            cut = int(np.ceil(base**j - 1e-9))
            break
        total += c

    def frequent(batches):
        for b in batches:
            for keys, counts in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                c = np.frombuffer(counts, "<i8")
                yield pa.RecordBatch.from_arrays([pa.array([np.frombuffer(keys, "<u8")[c >= cut].tobytes()], pa.binary()), pa.array([c[c >= cut].tobytes()], pa.binary())], names=["keys", "counts"])

    top = counted.where("ord = 1").select("keys", "counts").mapInArrow(frequent, "keys binary, counts binary").collect()  # broadcast_words in all
    top_keys = np.concatenate([np.frombuffer(bytes(r[0]), "<u8") for r in top] or [np.empty(0, np.uint64)])
    top_logs = np.concatenate([np.log10(np.frombuffer(bytes(r[1]), "<i8") + 1.0) for r in top] or [np.empty(0)])
    by = np.argsort(top_keys)
    shared = sc.broadcast((top_keys[by], top_logs[by]))
    del top

    def levels_so_far(texts, earlier, bloom):
        """Hashes, sizes and levels of some texts; ``earlier``: levels from the ranges before, one row of bytes a text."""
        h, sizes = _split(texts)
        found = token_levels(h, sizes, order, bloom)
        if earlier is not None:
            before = [np.frombuffer(x, np.uint8).reshape(order, -1) for x in earlier]
            found = [np.maximum(f, np.concatenate([x[k] for x in before])) for k, f in enumerate(found)]
        return h, sizes, found

    def passing(bloom):
        def run(batches):
            for b in batches:
                at = b.schema.get_field_index("_levels")
                out = []
                for i in range(0, b.num_rows, 256):
                    earlier = b.column(at).slice(i, 256).to_pylist() if at >= 0 else None
                    _, sizes, found = levels_so_far(b.column(2).slice(i, 256).to_pylist(), earlier, bloom.value)
                    ends = np.cumsum(sizes)
                    whole = np.stack(found)
                    out += [whole[:, e - m : e].tobytes() for e, m in zip(ends.tolist(), sizes.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(out, pa.binary())], names=["_row", "_key", "_text", "_train", "_levels"])

        return run

    def scored(batches):
        bloom = ranges[-1].value
        keys, logs = shared.value
        for b in batches:
            n_tok, done, logsum, n_known, rare, times = [], [], [], [], [], []
            texts, more = b.column(2), b.schema.get_field_index("_levels")
            for i in range(0, len(texts), 256):
                earlier = b.column(more).slice(i, 256).to_pylist() if more >= 0 else None
                h, sizes, found = levels_so_far(texts.slice(i, 256).to_pylist(), earlier, bloom)
                first = np.cumsum(sizes) - sizes
                done.append(np.add.reduceat(smooth.log10p(found), first))
                at = np.minimum(np.searchsorted(keys, h), len(keys) - 1) if len(keys) else np.zeros(len(h), np.int64)
                hit = keys[at] == h if len(keys) else np.zeros(len(h), bool)
                logsum.append(np.add.reduceat(np.where(hit, logs[at] if len(keys) else 0.0, 0.0), first))
                n_known.append(np.add.reduceat(hit.astype(np.int64), first))
                n_tok.append(sizes)
                ask = ~hit & (found[0] > 0)  # the filter forgets no word that was counted
                for x, y in zip(np.split(h, first[1:]), np.split(ask, first[1:]), strict=True):
                    some, n = np.unique(x[y], return_counts=True)
                    rare.append(some.view(np.int64))
                    times.append(n)
            cat = lambda x, kind: pa.array(np.concatenate(x).astype(kind) if x else np.empty(0, kind))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(3), cat(n_tok, np.int64), cat(done, np.float64), cat(logsum, np.float64), cat(n_known, np.int64), pa.array(rare, pa.list_(pa.int64())), pa.array(times, pa.list_(pa.int64()))], names=["_row", "_key", "trained", "n_tokens", "score", "logs", "n", "rare", "times"])

    kind = source.schema["_key"].dataType.simpleString()
    held = source.select(F.monotonically_increasing_id().alias("_row"), "_key", "_text", "_train")
    for bloom in ranges[:-1]:
        before, held = held, materialise(held.mapInArrow(passing(bloom), f"_row long, _key {kind}, _text string, _train boolean, _levels binary"), "lm-levels")
        if "_levels" in before.columns:
            discard(before)
    part = held.mapInArrow(scored, f"_row long, _key {kind}, trained boolean, n_tokens long, score double, logs double, n long, rare array<long>, times array<long>")
    part = materialise(part, "lm-scores")
    if len(ranges) > 1:
        discard(held)
    rest = part.select("_row", F.explode(F.arrays_zip("rare", "times")).alias("x")).select("_row", F.col("x.rare").alias("h"), F.col("x.times").alias("times"))
    rest = rest.join(known, "h").groupBy("_row").agg(F.sum(F.col("times") * F.log10(F.col("c") + 1.0)).alias("more"), F.sum("times").alias("found"))
    out = part.drop("rare", "times").join(rest, "_row", "left")
    return out.select(
        F.col("_key").alias(key),
        "trained",
        "n_tokens",
        (F.col("n") + F.coalesce("found", F.lit(0))).alias("n_known"),
        F.lit(tokens).cast("long").alias("train_tokens"),
        (F.col("logs") + F.coalesce("more", F.lit(0.0)) - F.col("n_tokens") * F.lit(float(np.log10(tokens + kinds + 1)))).alias("base_score"),
        "score",
    )
