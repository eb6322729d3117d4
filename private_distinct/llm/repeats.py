"""Which 64-bit keys occur more than once, as Bloom filters that workers hold whole.

Tasks deal their distinct keys (40 bits of them) by hash; each receiver finds the keys that it got twice, and
these are written as a table.  Filters are sized by the number of keys written, ten bits a key.  Where that is
more than ``limit`` bytes, the hash space is cut into ranges with a filter each, and callers pass over their
input once a range: nothing is left out, and no broadcast is larger than the limit.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, free_shuffles, materialise, partitions

LIMIT, BITS_A_KEY, PROBES = 64 << 20, 10, 3
LOW = np.uint64((1 << 40) - 1)
SCHEMA = "part int, keys binary"


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def part_of(keys: np.ndarray, n: int) -> np.ndarray:
    return ((keys >> np.uint64(40)) % np.uint64(n)).astype(np.int64)


def dealt(keys: np.ndarray, n: int) -> pa.RecordBatch:
    """Keys of a task, packed by receiver; one that occurs twice here is marked."""
    keys, count = np.unique(keys, return_counts=True)
    part = part_of(keys, n)
    low = (keys & LOW) << np.uint64(1) | (count > 1).astype(np.uint64)
    order = np.lexsort((low, part))
    part, low = part[order], low[order]
    cuts = np.searchsorted(part, np.arange(n + 1))
    rows = [(p, (x >> np.uint64(32)).astype("<u2").tobytes() + (x & np.uint64(0xFFFFFFFF)).astype("<u4").tobytes()) for p in range(n) if len(x := low[cuts[p] : cuts[p + 1]])]
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], names=["part", "keys"])


def _place(low: np.ndarray, probe: int, bits: int) -> np.ndarray:
    return (mixed(low + np.uint64(probe + 1)) % np.uint64(bits)).astype(np.int64)


def _again(batches, least: int):
    """Packed low bits of the keys that a receiver got ``least`` times or more (1 or 2), in all, of each part."""
    held: dict[int, list] = {}
    for b in batches:
        for p, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            m = len(x) // 6
            held.setdefault(p, []).append(np.frombuffer(x, "<u2", m).astype(np.uint64) << np.uint64(32) | np.frombuffer(x, "<u4", m, 2 * m))
    for p, x in held.items():
        low = np.sort(np.concatenate(x))
        x.clear()
        again = np.r_[False, low[1:] >> np.uint64(1) == low[:-1] >> np.uint64(1)] | (low & np.uint64(1)).astype(bool)
        keys = np.unique((low if least < 2 else low[again]) >> np.uint64(1))
        yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([keys.astype("<u8").tobytes()], pa.binary())], names=["part", "keys"])


class Filter:
    """Filter of one range of parts; ``maybe`` is false for keys of other ranges."""

    def __init__(self, table: np.ndarray, n: int, bits: int, ranges: int, mine: int):
        self.table, self.n, self.bits, self.ranges, self.mine = table, n, bits, ranges, mine

    def maybe(self, keys: np.ndarray) -> np.ndarray:
        part = part_of(keys, self.n)
        ok = part % self.ranges == self.mine
        base, low = part // self.ranges * self.bits, keys & LOW
        for i in range(PROBES):
            at = base + _place(low, i, self.bits)
            at = np.where(ok, at, 0)
            ok &= (self.table[at >> 3] >> (at & 7).astype(np.uint8) & 1).astype(bool)
        return ok


def filters(keys: DataFrame, n: int, tag: str, limit: int = LIMIT, least: int = 2) -> list:
    """Broadcast filters, one a range, of the keys that occur twice or more (or once) among rows made by ``dealt(.., n)``."""
    spark = keys.sparkSession
    wide = partitions(spark)
    table = materialise(keys.repartition(wide, "part").mapInArrow(lambda batches: _again(batches, least), SCHEMA), tag)
    free_shuffles(spark)
    top, total = table.agg(F.max(F.octet_length("keys")), F.sum(F.octet_length("keys"))).first()
    bits = max(64, (top or 0) // 8 * BITS_A_KEY // 8 * 8 + 8)
    ranges = max(1, -(-n * bits // 8 // limit))

    def build(batches):
        for b in batches:
            for p, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                low, bit = np.frombuffer(x, "<u8"), np.zeros(bits, bool)
                for i in range(PROBES):
                    bit[_place(low, i, bits)] = True
                yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([np.packbits(bit, bitorder="little").tobytes()], pa.binary())], names=["part", "keys"])

    out = []
    for r in range(ranges):
        whole = np.zeros(-(-n // ranges) * bits // 8 + 8, np.uint8)
        if total:
            for p, x in table.where(F.col("part") % ranges == r).mapInArrow(build, SCHEMA).collect():  # ``limit`` bytes in all
                at = p // ranges * bits // 8
                whole[at : at + bits // 8] = np.frombuffer(bytes(x), np.uint8)
        out.append(spark.sparkContext.broadcast(Filter(whole, n, bits, ranges, r)))
    discard(table)
    return out
