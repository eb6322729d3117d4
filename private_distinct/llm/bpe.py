"""Byte-level BPE encoding and decoding with a two-tier lookup.

Tier one: a minimal perfect hash over the vocabulary resolves a whole pre-token that is itself a token.
Tier two, for every miss: bytes form a doubly linked list, a binary heap of (rank, place) gives the pair of least
rank, the leftmost first, and pairs are merged until none is left.  A text is cut at single spaces, where no
pre-token can cross, and the pieces seen so far are kept in a bounded memo per worker.

``lockstep`` replaces the heap for misses of up to ``LOCKSTEP_BYTES`` bytes by rows of pair ranks that are merged all
at once, with the same ids (tested); packing uses it, the encoder itself does not.

Edge cases: a null text is an empty one and has no ids; very long pre-tokens cost n log n; rows are encoded one by
one, so repeated rows and other columns do not matter; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import operator
import re
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NONE = 0xFFFFFFFF
LOCKSTEP_BYTES, LOCKSTEP_PIECES, MEMO_PIECES, SLICE_CHARS = 32, 1 << 14, 800_000, 1 << 21
_CROSSING = re.compile(r" \s")
_STOPS = frozenset(".,;:!?")
_MAYBE_SPACE = np.isin(np.arange(256), [*range(9, 14), *range(28, 33), 0xC2, 0xE1, 0xE2, 0xE3])  # first bytes of white space


def read_ranks(path: str) -> dict[bytes, int]:
    """token bytes -> rank from a file of base64 tokens and ranks."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class PerfectHash:
    """Minimal perfect hash: hash and displace, singletons placed directly."""

    def __init__(self, keys: list[bytes]):
        self.n = n = len(keys)
        self.buckets = max(1, n // 3)
        h = np.array([xxhash.xxh64_intdigest(k) for k in keys], np.uint64)
        bucket = (h % np.uint64(self.buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        cuts = np.searchsorted(bucket[order], np.arange(self.buckets + 1))
        self.shift = np.zeros(self.buckets, np.int64)
        self.slot_key = np.full(n, -1, np.int64)
        sizes = np.diff(cuts)
        for b in np.argsort(-sizes, kind="stable"):
            mine = order[cuts[b] : cuts[b + 1]]
            if len(mine) < 2:
                break
            start, tries = 0, np.arange(1, 17, dtype=np.uint64)
            while True:
                slots = self._slots(h[mine][None, :], (tries + np.uint64(start))[:, None])
                fits = (self.slot_key[slots] < 0).all(1) & (np.diff(np.sort(slots, 1), axis=1) > 0).all(1)
                if fits.any():
                    t = int(np.argmax(fits))
                    self.slot_key[slots[t]] = mine
                    self.shift[b] = start + t + 1
                    break
                start += len(tries)
                tries = np.arange(1, min(len(tries) * 4, 1 << 14) + 1, dtype=np.uint64)
        free = iter(np.flatnonzero(self.slot_key < 0))
        for b in np.flatnonzero(sizes == 1):
            at = next(free)
            self.slot_key[at] = order[cuts[b]]
            self.shift[b] = -int(at) - 1

    def _slots(self, h: np.ndarray, shift: np.ndarray) -> np.ndarray:
        x = (h ^ (shift * np.uint64(0x9E3779B97F4A7C15))) * np.uint64(0xBF58476D1CE4E5B9)
        return (((x ^ (x >> np.uint64(29))) >> np.uint64(20)) % np.uint64(self.n)).astype(np.int64)

    def find(self, h: np.ndarray) -> np.ndarray:
        """Index of the only key that can have each hash."""
        shift = self.shift[(h % np.uint64(self.buckets)).astype(np.int64)]
        slots = np.where(shift < 0, -shift - 1, self._slots(h, np.maximum(shift, 0).astype(np.uint64)))
        return self.slot_key[slots]


class ByteBPE:
    """Encoder and decoder for one vocabulary; small enough to broadcast (bounded by the vocabulary)."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, lockstep: bool = False):
        self.pattern, self.lockstep = pattern, lockstep
        self.tokens = sorted(ranks, key=ranks.get)
        self.ids = np.array([ranks[t] for t in self.tokens], np.uint32)
        self.of_id = dict(zip(self.ids.tolist(), self.tokens, strict=True))
        self.single = np.array([ranks[bytes([i])] for i in range(256)], np.uint32)
        self.perfect = PerfectHash(self.tokens)
        pairs = {}
        for t, r in ranks.items():
            for k in range(1, len(t)):
                a, b = ranks.get(t[:k]), ranks.get(t[k:])
                if a is not None and b is not None:
                    pairs[a << 32 | b] = r
        self._table(np.fromiter(pairs, np.uint64, len(pairs)), np.fromiter(pairs.values(), np.uint32, len(pairs)))
        self._fresh()

    def _table(self, keys: np.ndarray, values: np.ndarray) -> None:
        """Open addressing, filled in rounds."""
        self.mask = np.uint64((1 << max(4, int(len(keys) * 2.5).bit_length())) - 1)
        self.keys = np.full(int(self.mask) + 1, 2**64 - 1, np.uint64)
        self.values = np.full(int(self.mask) + 1, NONE, np.uint32)
        at = self._home(keys)
        while len(keys):
            empty = self.keys[at] == np.uint64(2**64 - 1)
            self.keys[at[empty]] = keys[empty]
            won = self.keys[at] == keys
            self.values[at[won]] = values[won]
            keys, values, at = keys[~won], values[~won], (at[~won] + np.uint64(1)) & self.mask

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)) & self.mask

    def pair_rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        keys = a.astype(np.uint64) << np.uint64(32) | b.astype(np.uint64)
        at = self._home(keys)
        found = self.keys[at]
        out = np.where(found == keys, self.values[at], np.uint32(NONE))
        rest = np.flatnonzero((found != keys) & (found != np.uint64(2**64 - 1)))
        while len(rest):
            at[rest] = (at[rest] + np.uint64(1)) & self.mask
            found = self.keys[at[rest]]
            hit = found == keys[rest]
            out[rest[hit]] = self.values[at[rest[hit]]]
            rest = rest[~hit & (found != np.uint64(2**64 - 1))]
        return out

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("pairs", "first", "two", "spaced", "bare", "flat", "start", "count", "split")}

    def __setstate__(self, state):
        self.__dict__ |= state
        self._fresh()

    # tier two ------------------------------------------------------------------------------------

    def merge_heap(self, piece: bytes) -> list[int]:
        """Least pair first, from a binary heap over linked bytes."""
        n, rank, two = len(piece), self.pairs.get, self.two
        sym = list(map(self.first.__getitem__, piece))
        now = [two[a << 8 | b] for a, b in zip(piece, piece[1:], strict=False)]  # rank of the pair that starts at a place
        heap = [r * n + i for i, r in enumerate(now) if r >= 0]
        heapq.heapify(heap)
        pop, push = heapq.heappop, heapq.heappush
        now.append(-1)
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        while heap:
            r, i = divmod(pop(heap), n)
            if now[i] != r:  # merged away since
                continue
            j = right[i]
            sym[i], sym[j], now[j] = r, -1, -1
            right[i] = k = right[j]
            if k < n:
                left[k] = i
                now[i] = x = rank(r << 32 | sym[k], -1)
                if x >= 0:
                    push(heap, x * n + i)
            else:
                now[i] = -1
            k = left[i]
            if k >= 0:
                now[k] = x = rank(sym[k] << 32 | r, -1)
                if x >= 0:
                    push(heap, x * n + k)
        return [s for s in sym if s >= 0]

    def merge_lockstep(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The same for many short pieces at once: all ids, and how many each has."""
        n, width = len(pieces), max(map(len, pieces)) + 1
        size = np.fromiter(map(len, pieces), np.int64, n)
        inside = np.arange(width) < size[:, None]
        raw = np.zeros((n, width), np.uint8)
        raw[inside] = np.frombuffer(b"".join(pieces), np.uint8)
        sym = self.single[raw]
        rank = np.full((n, width), NONE, np.uint32)
        both = inside[:, 1:]
        rank[:, :-1][both] = self.pair_rank(sym[:, :-1][both], sym[:, 1:][both])
        right = np.broadcast_to(np.arange(1, width + 1, dtype=np.int16), (n, width)).copy()
        left = np.broadcast_to(np.arange(-1, width - 1, dtype=np.int16), (n, width)).copy()
        alive, rows = inside.copy(), np.arange(n)
        while len(rows):
            i = rank[rows].argmin(1)
            r = rank[rows, i]
            go = r != NONE
            rows, i, r = rows[go], i[go], r[go]
            if not len(rows):
                break
            j = right[rows, i]
            sym[rows, i], alive[rows, j], rank[rows, j] = r, False, NONE
            k = right[rows, j]
            right[rows, i] = k
            end = k >= size[rows]
            rank[rows[end], i[end]] = NONE
            x, y, z = rows[~end], i[~end], k[~end]
            left[x, z] = y
            rank[x, y] = self.pair_rank(sym[x, y], sym[x, z])
            p = left[rows, i]
            x, y, z = rows[p >= 0], p[p >= 0], i[p >= 0]
            rank[x, y] = self.pair_rank(sym[x, y], sym[x, z])
        return sym[alive], alive.sum(1)

    def _encode(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """All ids of pre-tokens, and how many each has: perfect hash first, merges for the rest."""
        n = len(pieces)
        at = self.perfect.find(np.fromiter(map(xxhash.xxh64_intdigest, pieces), np.uint64, n))
        whole = np.fromiter(map(operator.eq, map(self.tokens.__getitem__, at.tolist()), pieces), bool, n)
        size = np.fromiter(map(len, pieces), np.int64, n)
        merged = [(np.flatnonzero(whole), self.ids[at[whole]], np.ones(int(whole.sum()), np.int64))]
        short = ~whole & (size <= LOCKSTEP_BYTES) & self.lockstep
        for i in np.flatnonzero(~whole & ~short).tolist():
            ids = self.merge_heap(pieces[i])
            merged.append(([i], ids, [len(ids)]))
        where = np.flatnonzero(short)
        where = where[np.argsort(size[where], kind="stable")]  # alike in length
        for k in range(0, len(where), LOCKSTEP_PIECES):  # some 500 bytes a piece meanwhile
            some = where[k : k + LOCKSTEP_PIECES]
            merged.append((some, *self.merge_lockstep([pieces[i] for i in some.tolist()])))
        place, flat, many = (np.concatenate([x[i] for x in merged]).astype(t, copy=False) for i, t in ((0, np.int64), (1, np.uint32), (2, np.int64)))
        count = np.empty(n, np.int64)
        count[place] = many
        start = np.empty(n, np.int64)
        start[place] = np.cumsum(many) - many
        return flat[_spread(start, count)], count

    def encode_pieces(self, pieces: list[bytes]) -> list[list[int]]:
        """Ids of each pre-token."""
        flat, count = self._encode(pieces)
        ends = np.cumsum(count).tolist()
        flat = flat.tolist()
        return [flat[a:b] for a, b in zip([0, *ends], ends, strict=False)]

    # texts ---------------------------------------------------------------------------------------

    def _fresh(self) -> None:
        self.spaced: dict[str, int] = {}  # chunk without its space -> number
        self.bare: dict[str, int] = {}
        self.flat, self.start, self.count = np.empty(0, np.uint32), np.empty(0, np.int64), np.empty(0, np.int32)
        self.split = regex.compile(self.pattern)
        full = self.values != NONE
        self.pairs = dict(zip(self.keys[full].tolist(), self.values[full].tolist(), strict=True))
        self.first = self.single.tolist()
        self.two = [self.pairs.get(a << 32 | b, -1) for a in self.first for b in self.first]

    def _numbers(self, spaced: list[str], bare: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of different chunks, with (the space itself left out) and without a space before; new ones are learnt."""
        found, fresh, base = [], [], len(self.start)
        for memo, chunks in ((self.spaced, spaced), (self.bare, bare)):
            number = np.fromiter(map(memo.get, chunks, repeat(-1)), np.int64, len(chunks))
            new = np.flatnonzero(number < 0)
            number[new] = base + np.arange(len(new))
            base += len(new)
            found.append(number)
            fresh.append([chunks[i] for i in new.tolist()])
        if fresh[0] or fresh[1]:
            self._learn(*fresh)
            for memo, new in ((self.bare, fresh[1]), (self.spaced, fresh[0])):
                memo |= zip(new, range(base - len(new), base), strict=True)
                base -= len(new)
        return found[0], found[1]

    def _learn(self, spaced: list[str], bare: list[str]) -> None:
        """Appends the ids of new chunks; pre-tokens that are known chunks or repeat among the new ones are not merged again."""
        pieces: dict[str, int] = {}  # new pre-token -> -1, -2, ..
        parts: list[int] = []
        sizes: list[int] = []
        as_spaced, as_bare = self.spaced.get, self.bare.get

        def add(piece: str) -> None:
            at = as_spaced(piece[1:]) if piece[0] == " " else as_bare(piece)
            parts.append(pieces.setdefault(piece, -len(pieces) - 1) if at is None else at)

        for chunks, space in ((spaced, " "), (bare, "")):
            for x in chunks:
                if x.isalpha():  # one pre-token, as most are
                    parts.append(pieces.setdefault(space + x, -len(pieces) - 1))
                    sizes.append(1)
                elif x[-1:] in _STOPS and x[:-1].isalpha():
                    add(space + x[:-1])
                    add(x[-1])
                    sizes.append(2)
                else:
                    before = len(parts)
                    for piece in self.split.findall(space + x):
                        add(piece)
                    sizes.append(len(parts) - before)
        flat, count = self._encode([p.encode() for p in pieces])
        part, size = np.array(parts, np.int64), np.array(sizes, np.int64)
        of = np.where(part < 0, len(self.start) - 1 - part, part)  # the new ones stand behind the known ones
        start = np.concatenate([self.start, len(self.flat) + np.cumsum(count) - count])[of]
        many = np.concatenate([self.count, count])[of]
        ids = np.concatenate([self.flat, flat])[_spread(start, many)]
        ends = np.r_[0, np.cumsum(many)][np.cumsum(size)]
        count = np.diff(ends, prepend=0)
        self.start = np.concatenate([self.start, len(self.flat) + ends - count])
        self.count = np.concatenate([self.count, count.astype(np.int32)])
        self.flat = np.concatenate([self.flat, ids])

    def _chunks(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Chunk numbers of all texts, and how many each has."""
        column = pa.array([t or "" for t in texts], pa.large_string())
        raw = np.frombuffer(column.buffers()[2] or b"", np.uint8)
        ends = np.frombuffer(column.buffers()[1], np.int64)[1 : len(texts) + 1]
        maybe = np.flatnonzero((raw[:-1] == 32) & _MAYBE_SPACE[raw[1:]])
        crossing = [i for i in np.unique(np.searchsorted(ends, maybe, side="right")).tolist() if _CROSSING.search(texts[i] or "")]
        bare: list[str] = []
        more = np.zeros(len(texts), np.int64)
        for i in crossing:  # cut into pre-tokens
            found = self.split.findall(texts[i])
            more[i] = len(found)
            bare += found
        if crossing:
            column = pc.if_else(pa.array(more > 0), pa.scalar("", pa.large_string()), column)
        lists = pc.split_pattern(column, " ")
        offsets = lists.offsets.to_numpy()
        words = lists.flatten()
        bare += words.take(pa.array(offsets[:-1])).to_numpy(zero_copy_only=False).tolist()  # before the first space
        coded = words.dictionary_encode()
        code = coded.indices.to_numpy()
        follows = np.ones(len(code), bool)
        follows[offsets[:-1]] = False
        used = np.zeros(len(coded.dictionary), bool)
        used[code[follows]] = True
        different = dict.fromkeys(bare)
        different.pop("", None)
        with_space, without = self._numbers(coded.dictionary.filter(pa.array(used)).to_numpy(zero_copy_only=False).tolist(), list(different))
        number_of = np.full(len(used), -1)
        number_of[used] = with_space
        number = number_of[code]
        place = dict(zip(different, without.tolist(), strict=True))
        heads = np.fromiter(map(place.get, bare, repeat(-1)), np.int64, len(bare))
        number[offsets[:-1]] = heads[len(bare) - len(texts) :]
        count = np.add.reduceat(number >= 0, offsets[:-1], dtype=np.int64)
        number = number[number >= 0]
        if crossing:
            whole = np.concatenate([number, heads[: len(bare) - len(texts)]])
            start = np.where(more > 0, len(number) + np.cumsum(more) - more, np.cumsum(count) - count)
            count += more
            number = whole[_spread(start, count)]
        return number, count

    def encode_slices(self, texts: list[str | None]):
        """Yields for slices of the texts all ids, and where each text's end."""
        i = 0
        while i < len(texts):
            if len(self.start) > MEMO_PIECES:
                self._fresh()
            j, size = i, 0
            while j < len(texts) and size < SLICE_CHARS:
                size += len(texts[j] or "")
                j += 1
            number, chunks = self._chunks(texts[i:j])
            count = self.count[number].astype(np.int64)
            yield self.flat[_spread(self.start[number], count)], np.r_[0, np.cumsum(count)][np.cumsum(chunks)]
            i = j

    def encode_all(self, texts: list[str | None]):
        """Yields the ids of each text."""
        for ids, ends in self.encode_slices(texts):
            yield from np.split(ids, ends[:-1])

    def encode(self, text: str | None) -> list[int]:
        return next(self.encode_all([text])).tolist()

    def decode(self, ids) -> bytes:
        return b"".join(map(self.of_id.__getitem__, ids))


def _spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Places of all values of ranges, one range after the other."""
    return np.repeat(starts - np.cumsum(sizes) + sizes, sizes) + np.arange(sizes.sum())


def _digests(values: pa.LargeBinaryArray, ends: np.ndarray, less: int) -> list[str]:
    """Digest of each row's values in a row, without the last ``less`` bytes."""
    offsets, raw = np.frombuffer(values.buffers()[1], np.int64), memoryview(values.buffers()[2] or b"")
    cuts = offsets[np.r_[0, ends]].tolist()
    return [hashlib.sha256(raw[a : max(a, b - less)]).hexdigest() for a, b in zip(cuts, cuts[1:], strict=False)]


def encode_digests(docs: DataFrame, ranks: dict[bytes, int], pattern: str, key: str = "doc_id", text: str = "text", ids: bool = False) -> DataFrame:
    """Per row: key, n_tokens, digest of the ids in decimal, digest of the decoded bytes; ``ids`` adds the ids."""
    shared = docs.sparkSession.sparkContext.broadcast(ByteBPE(ranks, pattern))
    more = ", ids array<int>" if ids else ""
    schema = docs.select(key).schema.simpleString()[7:-1].replace(":", " ", 1) + ", n_tokens long, ids_sha256 string, decoded_sha256 string" + more
    schema = schema.replace(key, f"`{key}`", 1)

    def run(batches):
        bpe = shared.value
        tokens, decimals = pa.array(bpe.tokens, pa.large_binary()), pa.array([b"%d," % i for i in bpe.ids.tolist()], pa.large_binary())
        for b in batches:
            out = ([], [], [], [])
            for all_ids, ends in bpe.encode_slices(b.column(1).to_pylist()):
                at = pa.array(np.searchsorted(bpe.ids, all_ids))
                out[0].extend(np.diff(ends, prepend=0).tolist())
                out[1].extend(_digests(decimals.take(at), ends, 1))
                out[2].extend(_digests(tokens.take(at), ends, 0))
                if ids:
                    out[3].extend(np.split(all_ids.astype(np.int32), ends[:-1]))
            cols = [b.column(0), pa.array(out[0], pa.int64()), pa.array(out[1], pa.string()), pa.array(out[2], pa.string())]
            names = [key, "n_tokens", "ids_sha256", "decoded_sha256"]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(out[3], pa.list_(pa.int32()))] if ids else cols, names=[*names, "ids"] if ids else names)

    return docs.select(key, F.col(text).alias("_text")).mapInArrow(run, schema)
