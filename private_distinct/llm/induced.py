"""External induced sorting of the suffixes of a text on disk, with the common prefixes of neighbours.

The text is a file, read in blocks.  Leftmost S suffixes are named by their substrings, written as symbols of
(byte, type); names in a row are then named together, recursively, until a name covers the depth asked for, so
that names order these suffixes.  L suffixes are induced from them and S suffixes from the L suffixes, bucket by bucket from the
heads of a disk-backed priority queue: its entries leave by first byte and, within a byte, by age.  An entry is
a tuple of place, the eight text bytes that hold its predecessor, and the length of the prefix that it shares with
the entry before it; so a step needs no look into the text but one in eight, and prefixes are carried: those of two
induced neighbours are one longer than the least prefix between their sources.

All that is held is bounded by ``memory``: blocks, queues (longer ones wait in files) and runs of the external
sorts; the rest is in files of ``folder``, also while shards are far larger.  Orders and prefixes are exact to ``depth``.
"""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np

ENTRY, NOT_YET = 17, -1


class DiskQueue:
    """First in, first out, of equal-typed columns; beyond what ``room`` allows they wait in files."""

    def __init__(self, folder: str, name: str, kinds: tuple = (np.int64, np.uint64, np.uint8)):
        self.path, self.kinds, self.held, self.size, self.on_disk = os.path.join(folder, name), kinds, [], 0, 0

    def push(self, *columns: np.ndarray) -> None:
        self.held.append(columns)
        self.size += len(columns[0])

    def spill(self) -> None:
        if self.size:
            for i, kind in enumerate(self.kinds):
                with open(f"{self.path}.{i}", "ab") as f:
                    for x in self.held:
                        x[i].astype(kind, copy=False).tofile(f)
            self.on_disk += self.size
            self.held, self.size = [], 0

    def _read(self, path: str, start: int, n: int) -> tuple:
        return tuple(np.fromfile(f"{path}.{i}", kind, n, offset=start * np.dtype(kind).itemsize) for i, kind in enumerate(self.kinds))

    def pop_all(self, block: int) -> Iterator[tuple]:
        """Blocks of what is queued now, oldest first; what is pushed meanwhile is left for the next call."""
        n, self.on_disk = self.on_disk, 0
        held, self.held, self.size = self.held, [], 0
        if n:
            for i in range(len(self.kinds)):
                os.replace(f"{self.path}.{i}", f"{self.path}.out.{i}")
            for a in range(0, n, block):
                yield self._read(f"{self.path}.out", a, min(block, n - a))
            for i in range(len(self.kinds)):
                os.remove(f"{self.path}.out.{i}")
        if held:
            whole = tuple(np.concatenate([x[i] for x in held]) for i in range(len(self.kinds)))
            for a in range(0, len(whole[0]), block):
                yield tuple(x[a : a + block] for x in whole)

    def backwards(self, block: int) -> Iterator[tuple]:
        """Blocks from the youngest to the oldest, each in the order of ages; empties the queue."""
        held, self.held, n, self.on_disk, self.size = self.held, [], self.on_disk, 0, 0
        if held:
            whole = tuple(np.concatenate([x[i] for x in held]) for i in range(len(self.kinds)))
            for b in range(len(whole[0]), 0, -block):
                yield tuple(x[max(0, b - block) : b] for x in whole)
        for b in range(n, 0, -block):
            yield self._read(self.path, max(0, b - block), min(block, b))
        if n:
            for i in range(len(self.kinds)):
                os.remove(f"{self.path}.{i}")

    def __bool__(self) -> bool:
        return bool(self.on_disk or self.size)


class Sorter:
    """External sort of (key, value) pairs: sorted runs, then ranges of keys that fit in memory."""

    def __init__(self, folder: str, name: str, memory: int):
        self.path, self.most, self.held, self.size, self.runs = os.path.join(folder, name), max(1024, memory // 64), [], 0, []

    def add(self, key: np.ndarray, value: np.ndarray) -> None:
        self.held.append((key, value))
        self.size += len(key)
        if self.size >= self.most:
            self._run()

    def _sorted(self, key: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        order = np.argsort(key)
        return key[order], value[order]

    def _run(self) -> None:
        pair = self._sorted(*(np.concatenate([x[i] for x in self.held]) for i in (0, 1)))
        self.held, self.size = [], 0
        name = f"{self.path}.run{len(self.runs)}"
        for i, x in enumerate(pair):
            x.tofile(f"{name}.{i}")
        self.runs.append((name, pair[0].dtype, pair[1].dtype, len(pair[0]), pair[0][:: max(1, len(pair[0]) // 64)].copy()))

    def blocks(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        if not self.runs:
            if self.size:
                held, self.held = self.held, []
                yield self._sorted(*(np.concatenate([x[i] for x in held]) for i in (0, 1)))
            return
        if self.size:
            self._run()
        files = [(np.memmap(f"{n}.0", k, "r"), np.memmap(f"{n}.1", v, "r")) for n, k, v, _, _ in self.runs]
        sample = np.sort(np.concatenate([r[4] for r in self.runs]))
        ways = max(1, 2 * sum(r[3] for r in self.runs) // self.most)
        cuts = np.unique(sample[np.linspace(0, len(sample) - 1, ways + 1).astype(int)[1:-1]]) if ways > 1 else sample[:0]
        at = [0] * len(files)
        for cut in [*cuts, None]:
            parts = []
            for i, (k, v) in enumerate(files):
                end = len(k) if cut is None else int(np.searchsorted(k, cut, side="left"))
                parts.append((k[at[i] : end], v[at[i] : end]))
                at[i] = end
            if any(len(p[0]) for p in parts):
                yield self._sorted(*(np.concatenate([p[i] for p in parts]) for i in (0, 1)))
        del files
        for n, *_ in self.runs:
            os.remove(f"{n}.0")
            os.remove(f"{n}.1")
        self.runs = []


def least_between(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """min(x[a[i] : b[i] + 1]) for each i, by a table of minima of doubling widths."""
    table, width = [x], 1
    longest = int((b - a).max(initial=0)) + 1
    while 2 * width <= longest:
        table.append(np.minimum(table[-1][:-width], table[-1][width:]))
        width *= 2
    level = np.frexp((b - a + 1).astype(np.float64))[1] - 1
    out = np.empty(len(a), x.dtype)
    for k in range(len(table)):
        some = np.flatnonzero(level == k)
        if len(some):
            out[some] = np.minimum(table[k][a[some]], table[k][b[some] + 1 - (1 << k)])
    return out


class Suffixes:
    """Suffixes of the file ``path`` in order; see the module's text."""

    def __init__(self, path: str, depth: int, folder: str, memory: int = 64 << 20):
        self.n, self.depth, self.folder, self.memory = os.path.getsize(path), depth, folder, memory
        self.block = max(1 << 10, min(1 << 16, memory // 512))
        self.room = memory // 4 // ENTRY
        pad = -self.n % 8 + 8
        with open(path, "ab") as f:
            f.write(bytes(pad + depth))  # a later read of eight bytes stays inside
        self.path = path
        self.text = np.memmap(path, np.uint8, "r")
        self.words = np.memmap(path, "<u8", "r", shape=len(self.text) // 8)
        self.levels = self.spilled = 0

    # leftmost S suffixes ---------------------------------------------------------------------------

    def _types(self) -> Iterator[tuple[int, np.ndarray, np.ndarray, bool, int]]:
        """Blocks from the end: start, bytes, whether each place is of type S, and that of the place after; its byte."""
        after, byte = False, NOT_YET
        step = 8 * self.block
        for a in range((self.n - 1) // step * step, -1, -step):
            t = np.array(self.text[a : min(self.n, a + step)])
            sign = np.sign(np.diff(np.append(t.astype(np.int16), byte)))
            known = np.flatnonzero(sign)
            nxt = np.searchsorted(known, np.arange(len(t)))
            small = np.full(len(t), after)
            inside = nxt < len(known)
            small[inside] = sign[known[nxt[inside]]] > 0
            yield a, t, small, after, byte
            after, byte = bool(small[0]), int(t[0])

    def _tokens(self) -> tuple[str, int]:
        """Files of the places of leftmost S suffixes, and of the tokens of their substrings; how many tokens."""
        marks = np.memmap(os.path.join(self.folder, "types"), np.uint8, "w+", shape=max(1, self.n + 8))
        for a, _, small, _, _ in self._types():
            marks[a : a + len(small)] = small
        path, total = os.path.join(self.folder, "tokens"), 0
        with open(f"{path}.key", "wb") as keys, open(f"{path}.at", "wb") as places:
            step, carried = 8 * self.block, np.empty(0, np.int64)
            for a in range(0, self.n, step):
                b = min(self.n, a + step)
                s = np.array(marks[max(0, a - 1) : b]).astype(bool)
                left = np.flatnonzero(s[1:] & ~s[:-1]) + max(0, a - 1) + 1
                left = np.concatenate([carried, left])
                final = b == self.n
                if len(left) < 2 and not final:
                    carried = left
                    continue
                carried = left[-1:]
                ends = np.append(left[1:], self.n - 1) if final else left[1:]
                left = left[: len(ends)]
                for i in range(0, len(left), self.block):
                    key, at = self._pieces(left[i : i + self.block], ends[i : i + self.block], marks)
                    key.tofile(keys)
                    at.tofile(places)
                    total += len(key)
        del marks
        os.remove(os.path.join(self.folder, "types"))
        return path, total

    def _pieces(self, left: np.ndarray, ends: np.ndarray, marks) -> tuple[np.ndarray, np.ndarray]:
        """Substrings from left to ends, both included, as tokens of up to seven symbols; -1 marks continued ones."""
        size = ends - left + 1
        pieces = np.where(size <= self.depth + 7, -(-size // 7), -(-(self.depth + 7) // 7))  # what is beyond the depth tells nothing
        first = np.cumsum(pieces) - pieces
        of = np.repeat(np.arange(len(left)), pieces)
        rank = np.arange(len(of)) - first[of]
        start = left[of] + 7 * rank
        key = np.zeros(len(of), np.uint64)
        for j in range(7):
            ok = 7 * rank + j < size[of]
            p = np.where(ok, start + j, 0)
            symbol = self.text[p].astype(np.uint64) * np.uint64(2) + marks[p] + np.uint64(1)
            key = key << np.uint64(9) | np.where(ok, symbol, np.uint64(0))
        return key, np.where(rank == 0, left[of], -1)

    def _ranked(self, keys: Iterator[np.ndarray], out: str, n: int) -> int:
        """Writes the rank of each key, in the order given, to a file; returns the number of different ones."""
        sorter, at = Sorter(self.folder, "byname", self.memory), 0
        for k in keys:
            sorter.add(k, np.arange(at, at + len(k)))
            at += len(k)
        small = not sorter.runs  # then a table of all ranks is no larger than what was sorted
        back, rank, last = np.empty(n, np.int64) if small else Sorter(self.folder, "byplace", self.memory), 0, None
        for k, v in sorter.blocks():
            new = np.r_[last is None or k[0] != last, k[1:] != k[:-1]]
            names = rank + np.cumsum(new)
            rank, last = int(names[-1]), k[-1]
            if small:
                back[v] = names
            else:
                back.add(v, names)
        with open(out, "wb") as f:
            for names in [back] if small else (x for _, x in back.blocks()):
                names.astype("<u4" if n < 2**32 - 1 else "<u8").tofile(f)
        return rank

    def _name(self, path: str, n: int, kinds: int, covered: int) -> None:
        """Renames until names are unique or cover the depth: some names in a row, each of ``covered`` tokens, are one."""
        if kinds == n or 2 * covered >= self.depth:  # a token covers two bytes or more
            return
        self.levels += 1
        now = np.memmap(f"{path}.name", "<u4" if n < 2**32 - 1 else "<u8", "r")
        bits = kinds.bit_length()
        ways = max(2, 64 // bits)

        def rows():
            step = self.block * 4
            for a in range(0, n, step):
                names = []
                for j in range(ways):
                    names.append(np.zeros(min(step, n - a), np.uint64))
                    later = now[a + j * covered : a + j * covered + len(names[0])]
                    names[-1][: len(later)] = later
                if ways * bits > 64:
                    yield np.rec.fromarrays(names)
                else:
                    key = names[0]
                    for x in names[1:]:
                        key = key << np.uint64(bits) | x
                    yield key

        kinds = self._ranked(rows(), f"{path}.new", n)
        del now
        os.replace(f"{path}.new", f"{path}.name")
        self._name(path, n, kinds, ways * covered)

    def leftmost(self) -> Iterator[tuple]:
        """Sorted leftmost S suffixes: places, words, common prefix with the one before."""
        path, n = self._tokens()
        if n:
            with open(f"{path}.key", "rb") as f:
                kinds = self._ranked(self._chunks(f), f"{path}.name", n)
            self._name(path, n, kinds, 1)
            sorter = Sorter(self.folder, "leftmost", self.memory)
            names, places = np.memmap(f"{path}.name", "<u4" if n < 2**32 - 1 else "<u8", "r"), np.memmap(f"{path}.at", np.int64, "r")
            for a in range(0, n, self.block * 4):
                at = np.array(places[a : a + self.block * 4])
                sorter.add(np.array(names[a : a + len(at)])[at >= 0], at[at >= 0])
            del names, places
            before = None
            for _, found in sorter.blocks():
                for a in range(0, len(found), self.block):
                    at = found[a : a + self.block]
                    yield at, self.words[(at - 1) >> 3], self.common(np.append(before if before is not None else at[:1], at[:-1]), at, before is None)
                    before = at[-1]
        for end in ("key", "at", "name"):
            if os.path.exists(f"{path}.{end}"):
                os.remove(f"{path}.{end}")

    def _chunks(self, f) -> Iterator[np.ndarray]:
        while len(x := np.fromfile(f, np.uint64, self.block * 4)):
            yield x

    def common(self, p: np.ndarray, q: np.ndarray, none_first: bool = False) -> np.ndarray:
        """Length of the common prefix of the suffixes at p and at q, up to the depth."""
        out, active = np.zeros(len(p), np.int64), np.arange(len(p))
        if none_first:
            active = active[1:]
        for j in range(0, self.depth, 8):
            if not len(active):
                break
            x, y = self._eight(p[active] + j), self._eight(q[active] + j)
            differ = x ^ y
            low = differ & (~differ + np.uint64(1))
            same = np.where(differ == 0, 8, (np.frexp(low.astype(np.float64))[1] - 1) >> 3)
            out[active] += same
            active = active[same == 8]
        end = self.n - np.maximum(p, q)
        return np.minimum(np.minimum(out, self.depth), end).astype(np.uint8)

    def _eight(self, at: np.ndarray) -> np.ndarray:
        """Eight bytes from each place, the first one lowest."""
        i, shift = at >> 3, (at & 7).astype(np.uint64) * np.uint64(8)
        high = np.where(shift > 0, self.words[np.minimum(i + 1, len(self.words) - 1)] << ((np.uint64(64) - shift) & np.uint64(63)), np.uint64(0))
        return self.words[i] >> shift | high

    # induction -------------------------------------------------------------------------------------

    def _induce(self, at, word, lcp, byte: int, up: bool, equal: bool) -> None:
        """Puts the predecessors of a block of sources, in order, into their queues."""
        before = ((word >> (((at - 1) & 7).astype(np.uint64) * np.uint64(8))) & np.uint64(255)).astype(np.int64)
        goes = (before > byte) if up else (before < byte)
        if equal:
            goes |= before == byte
        some = np.flatnonzero(goes & (at > 0))
        tail = int(lcp.min())
        if not len(some):
            self.run = np.minimum(self.run, tail)
            return
        to = before[some]
        order = np.argsort(to.astype(np.uint8), kind="stable")
        some, to = some[order], to[order]
        first = np.r_[True, to[1:] != to[:-1]]
        start = np.r_[0, some[:-1] + 1]
        start[first] = 0
        least = least_between(lcp, start, some).astype(np.int16)
        least[first] = np.minimum(least[first], self.run[to[first]])
        got = np.minimum(least + 1, self.depth).astype(np.uint8)
        self.run = np.minimum(self.run, tail)
        cuts = np.flatnonzero(first)
        last = some[np.append(cuts[1:], len(some)) - 1]  # what is left of the block for the next source
        suffix = np.append(np.minimum.accumulate(lcp[::-1])[::-1], 255).astype(np.int16)
        self.run[to[cuts]] = suffix[last + 1]
        place = at[some] - 1
        words = word[some]
        fresh = np.flatnonzero((place & 7 == 0) & (place > 0))
        words[fresh] = self.words[(place[fresh] >> 3) - 1]
        for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(to)], strict=True):
            self.queues[int(to[a])].push(place[a:b], words[a:b], got[a:b])
        self.waiting += len(place)
        if self.waiting > self.room:
            for q in self.queues:
                self.spilled += q.size
                q.spill()
            self.waiting = 0

    def _fresh(self, name: str) -> None:
        self.queues = [DiskQueue(self.folder, f"{name}{c}") for c in range(256)]
        self.run, self.waiting = np.full(256, NOT_YET, np.int16), 0

    def descending(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(places, common prefix with the one before) of all suffixes, from the greatest to the least."""
        if not self.n:
            return
        self._fresh("l")
        last = self.n - 1
        self.queues[int(self.text[last])].push(np.array([last]), self.words[[max(0, last - 1) >> 3]], np.zeros(1, np.uint8))
        self.run[int(self.text[last])] = 0  # the shortest suffix shares nothing that is longer than itself
        kept = [DiskQueue(self.folder, f"k{c}") for c in range(256)]
        seeds, seed = self.leftmost(), None
        held = 0
        for c in range(256):
            ended = None
            while self.queues[c]:
                for at, word, lcp in self.queues[c].pop_all(self.block):
                    kept[c].push(at, word, lcp)
                    ended = int(at[-1])
                    held += len(at)
                    if held > self.room:
                        for q in kept:
                            self.spilled += q.size
                            q.spill()
                        held = 0
                    self._induce(at, word, lcp, c, True, True)
            begun = False
            while True:
                seed = next(seeds, None) if seed is None else seed
                if seed is None:
                    break
                at, word, lcp = seed
                m = int(np.searchsorted(self.text[at], c, side="right"))
                if m:
                    lcp = lcp.copy()
                    if not begun:
                        lcp[0] = 0 if ended is None else self.common(np.array([ended]), at[:1])[0]
                        begun = True
                    self._induce(at[:m], word[:m], lcp[:m], c, True, False)
                seed = (at[m:], word[m:], lcp[m:]) if m < len(at) else None
                if seed is not None:
                    break
        self._fresh("s")
        for c in range(255, -1, -1):
            ended = None
            while self.queues[c]:
                for at, word, lcp in self.queues[c].pop_all(self.block):
                    yield at, lcp
                    ended = int(at[-1])
                    self._induce(at, word, lcp, c, False, True)
            link = None
            for at, word, lcp in kept[c].backwards(self.block):
                if link is None:
                    link = 0 if ended is None else int(self.common(np.array([ended]), at[-1:])[0])
                down = np.append(link, lcp[:0:-1]).astype(np.uint8)
                link = int(lcp[0])
                at, word = at[::-1], word[::-1]
                yield at, down
                self._induce(at, word, down, c, False, False)
