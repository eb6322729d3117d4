"""Best-two-fit packing of tokenised documents into sequences of a fixed length.

Documents become pieces (only those longer than a sequence are cut; the first piece takes the remainder).
How many pieces have each length is a table of at most ``capacity`` rows whatever the corpus, so the packing
itself is planned over these counts: a bin is filled greedily, each time with the longest piece that fits;
then its smallest piece is replaced by two unpacked pieces that fit the expanded gap more tightly.  A filled
bin is repeated as often as the counts allow.  The plan (bounded by the lengths) is broadcast, and every piece
looks up its place by its number among the pieces of its length.

Edge cases: a null or empty text is a document of its end token only; repeated rows are packed once each; an
empty table gives no rows; other columns are ignored unless asked to be kept.
"""

from __future__ import annotations

import json
import re
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import ByteBPE
from .common import give_back_memory, materialise, numbered, small_batches

SLICE_BYTES, BATCH_ROWS = 1 << 22, 1000


def text_slices(column: pa.Array, step: int = SLICE_BYTES):
    """Texts of neighbouring rows, about ``step`` bytes together; a longer one stands alone."""
    size = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).tolist()
    i = 0
    while i < len(size):
        j, total = i + 1, size[i]
        while j < len(size) and total + size[j] <= step:
            total += size[j]
            j += 1
        yield column.slice(i, j - i).to_pylist()
        i = j


def _room(counts: np.ndarray) -> np.ndarray:
    """room[x]: the longest length <= x that is left, 0 if none."""
    return np.maximum.accumulate(np.where(counts > 0, np.arange(len(counts)), 0))


def _fill(counts: np.ndarray, first: int, capacity: int) -> list[int]:
    """One bin: the longest that fits, again and again; then the two-for-one replacement."""
    left = counts.copy()
    bin_, gap = [first], capacity - first
    left[first] -= 1
    room = _room(left)
    while gap and (x := int(room[gap])):
        bin_.append(x)
        left[x] -= 1
        if not left[x]:
            room = _room(left)
        gap -= x
    if gap and len(bin_) > 1:
        small = bin_[-1]
        space = gap + small
        a = np.arange(1, space // 2 + 1)
        b = room[space - a]
        fits = (left[a] > 0) & ((b > a) | (b == a) & (left[a] > 1))
        total = np.where(fits, a + b, 0)
        k = int(np.argmax(total)) if len(total) else 0
        if len(total) and total[k] > small:
            bin_[-1:] = [int(b[k]), int(a[k])]
    return bin_


def plan(histogram: dict[int, int], capacity: int) -> list[tuple[list[int], int]]:
    """(lengths in a bin, how many such bins) for all pieces counted in ``histogram``."""
    counts = np.zeros(capacity + 1, np.int64)
    for length, n in histogram.items():
        counts[length] = n
    out = []
    while (longest := int(_room(counts)[capacity])) > 0:
        bin_ = _fill(counts, longest, capacity)
        kinds, uses = np.unique(bin_, return_counts=True)
        times = int((counts[kinds] // uses).min())
        counts[kinds] -= times * uses
        out.append((bin_, times))
    return out


def places(planned: list[tuple[list[int], int]]) -> np.ndarray:
    """Columns length, first number, sequence, offset: runs of pieces of a length, sorted."""
    taken: dict[int, int] = {}
    rows, sequence = [], 0
    for bin_, times in planned:
        offset = 0
        for length in bin_:
            rows.append((length, taken.get(length, 0), sequence, offset))
            taken[length] = taken.get(length, 0) + times
            offset += length
        sequence += times
    return np.array(sorted(rows), np.int64).reshape(-1, 4)


def encode_pieces(docs: DataFrame, ranks: dict[bytes, int], pattern: str, capacity: int = 2048, end_id: int = 0, key: str = "doc_id", text: str = "text", keep_ids: bool = False, special: dict[str, int] | None = None) -> DataFrame:
    """key, piece, start, length, ids_crc32 (and ids) of each piece of each document.

    ``special``: strings that are one id wherever they stand in a text, as a tokenizer has them by default.
    """
    bpe_on_workers = docs.sparkSession.sparkContext.broadcast(ByteBPE(ranks, pattern, lockstep=True))
    kind = docs.select(key).schema[0].dataType.simpleString()
    schema = f"`{key}` {kind}, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if keep_ids else "")
    special = special or {}
    finder = re.compile("(" + "|".join(map(re.escape, sorted(special, key=len, reverse=True))) + ")")

    def ids_of_rows(bpe: ByteBPE, texts: list[str | None]):
        """Ids of each text, the end included."""
        parts = [finder.split(t) if t and any(x in t for x in special) else [t] for t in texts]
        encoded = bpe.encode_all([None if p in special else p for ps in parts for p in ps])
        end = np.array([end_id], np.uint32)
        for ps in parts:
            found = [np.array([special[p]], np.uint32) if p in special else ids for p, ids in zip(ps, encoded, strict=False)]
            yield np.concatenate([*found, end])
    def run(batches):
        give_back_memory()
        bpe = bpe_on_workers.value
        for b in batches:
            row, piece, start, length, crc, kept = [], [], [], [], [], []
            for i, ids in enumerate(x for texts in text_slices(b.column(1)) for x in ids_of_rows(bpe, texts)):
                at, size, k = 0, len(ids) % capacity or capacity, 0
                while at < len(ids):
                    row.append(i)
                    piece.append(k)
                    start.append(at)
                    length.append(size)
                    crc.append(zlib.crc32(ids[at : at + size].tobytes()))
                    if keep_ids:
                        kept.append(ids[at : at + size].astype(np.int32))
                    at, size, k = at + size, capacity, k + 1
            cols = [b.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))]
            names = [key, "piece", "start", "length", "ids_crc32"]
            yield pa.RecordBatch.from_arrays(cols + [pa.array(kept, pa.list_(pa.int32()))] * keep_ids, names=names + ["ids"] * keep_ids)

    return docs.select(key, F.col(text).alias("_text")).mapInArrow(run, schema)


def special_tokens(path: str) -> dict[str, int]:
    """Special strings of a tokenizer's JSON file."""
    with open(path, encoding="utf-8") as f:
        return {t["content"]: t["id"] for t in json.load(f)["added_tokens"] if t["special"]}


def pack(pieces: DataFrame, capacity: int = 2048, order: tuple[str, ...] = ("doc_id", "piece")) -> DataFrame:
    """Adds sequence_id and offset to pieces with a ``length`` column from 1 to ``capacity``."""
    with small_batches(pieces.sparkSession, BATCH_ROWS):
        pieces = materialise(pieces, "pieces")
    histogram = {r[0]: r[1] for r in pieces.groupBy("length").agg(F.count(F.lit(1))).collect()}  # at most `capacity` rows
    table = pieces.sparkSession.sparkContext.broadcast(places(plan(histogram, capacity)))
    ranked = numbered(pieces, ["length"], list(order), "_number")
    names = [c for c in ranked.columns if c != "_number"]
    schema = pieces.select(*names, F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset")).schema

    def run(batches):
        runs = table.value
        firsts = runs[:, 0] << 48 | runs[:, 1]
        for b in batches:
            number = b.column(len(names)).to_numpy()
            at = np.searchsorted(firsts, b.column(names.index("length")).to_numpy() << 48 | number, side="right") - 1
            cols = [pa.array(runs[at, 2] + number - runs[at, 1]), pa.array(runs[at, 3])]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *cols], names=[*names, "sequence_id", "offset"])

    return ranked.select(*names, "_number").mapInArrow(run, schema)
