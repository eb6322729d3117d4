"""Removal of repeated strings against a dictionary of all windows; the sorter against sorted suffixes."""

import hashlib
import itertools
import os
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"


def plain(rows, length=50):
    first = {}
    for d, t in rows:
        for i in range(len(t) - length + 1):
            w = t[i : i + length]
            first[w] = min(d, first.get(w, d))
    out = []
    for d, t in rows:
        gone = bytearray(len(t))
        for i in range(len(t) - length + 1):
            if first[t[i : i + length]] < d:
                gone[i : i + length] = b"\1" * length
        left = bytes(c for c, g in zip(t, gone) if not g)
        out.append((d, len(t), sum(gone), sum(g and not p for g, p in zip(gone, b"\0" + bytes(gone))), hashlib.sha256(left).hexdigest()))
    return sorted(out)


def in_order(text, folder, memory):
    from private_distinct.llm.induced import Suffixes

    path = folder / "text"
    path.write_bytes(text)
    sorter = Suffixes(str(path), 50, str(folder), memory)
    blocks = list(sorter.descending())
    path.unlink()
    assert not list(folder.iterdir())
    return [i for a, _ in blocks for i in a.tolist()], [x for _, b in blocks for x in b.tolist()], sorter


@pytest.mark.parametrize("memory", [1 << 26, 1 << 12])
def test_sorter(tmp_path, memory):
    rng = random.Random(5)
    for alphabet, n in ((b"ab", 500), (b"abc", 900), (bytes(range(256)), 700), (b"a", 300), (b"ab", 1), (b"a", 0), (b"a" * 40 + b"b", 2000), (b"abcdefg ", 3000)):
        t = bytes(rng.choice(alphabet) for _ in range(n)) * 2
        order, shared, sorter = in_order(t, tmp_path, memory)
        assert sorted(order) == list(range(len(t)))
        cut = [t[i : i + 50] for i in order]
        assert cut == sorted(cut, reverse=True)
        assert shared[1:] == [len(os.path.commonprefix([x, y])) for x, y in itertools.pairwise(cut)]
        if n > 2000:
            assert sorter.levels >= 2 and (memory > 1 << 12 or sorter.spilled > n)  # names were named again; queues waited on disk


def test_memory_does_not_grow_with_the_text(tmp_path):
    """Eight megabytes under a bound of eight: what Python and numpy allocate stays under twice the bound, as for one."""
    import tracemalloc

    from private_distinct.llm.induced import Suffixes

    rng = np.random.default_rng(0)
    words = [bytes(rng.integers(97, 123, rng.integers(2, 9)).astype(np.uint8)) + b" " for _ in range(3000)]
    peaks = {}
    for size in (1 << 20, 8 << 20):
        path = tmp_path / "text"
        path.write_bytes(b"".join(words[i] for i in rng.integers(0, 3000, size // 4))[:size])
        tracemalloc.start()
        n = sum(len(a) for a, _ in Suffixes(str(path), 50, str(tmp_path), 8 << 20).descending())
        peaks[size] = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        path.unlink()
        assert n == size
    assert peaks[8 << 20] < 16 << 20 and peaks[8 << 20] < 2 * peaks[1 << 20]


def test_removal(spark):
    from private_distinct.llm import suffix_dedup

    rng = random.Random(1)
    said = "".join(rng.choice("abcdé fgh") for _ in range(400))
    odd = [(900, said), (901, "x" * 700), (902, "x" * 300 + said[:120]), (903, said[60:200] + "tail" + said[10:61]), (904, None), (905, ""), (906, said[:49]), (907, said[:50]), (907, said[:50]), (907, said), (-5, said[100:170]), (None, said[:90])]
    docs = spark.createDataFrame([(*r, 7) for r in odd], "doc_id long, text string, did int")
    docs = docs.union(spark.read.parquet(f"{SF}/documents.parquet").selectExpr("doc_id", "text", "7")).cache()
    rows = [(2**63 - 1 if r.doc_id is None else r.doc_id, (r.text or "").encode()) for r in docs.collect()]
    got = suffix_dedup.remove(docs, ["doc_id", "did"], as_text=True).collect()
    assert sorted((2**63 - 1 if r.doc_id is None else r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == plain(rows)
    assert suffix_dedup.remove(docs.limit(0), ["doc_id"]).count() == 0
    # many shards, ranges of the filter and little memory change nothing
    keyed = docs.select(F.coalesce("doc_id", F.lit(suffix_dedup.LAST)).alias("did"), F.shiftright(F.xxhash64(F.col("text").cast("binary")), 32).alias("dh"), F.coalesce("text", F.lit("")).cast("binary").alias("body"))
    covered = lambda df: {(r.did, r.dh): suffix_dedup.cut(b"x" * 10**6, r.gone)[1:] for r in df.collect()}
    assert covered(suffix_dedup.repeated_ranges(keyed, 50, 1 << 14, 500, 1 << 16)) == covered(suffix_dedup.repeated_ranges(keyed))


def test_ranges_and_blocks(spark):
    """Removed ranges equal a mark for each byte; texts are hashed in blocks that fit a core's cache, with the same ranges."""
    from private_distinct.llm import suffix_dedup

    rng = random.Random(8)
    for _ in range(200):
        body = bytes(rng.choice(b"ab") for _ in range(rng.randrange(60)))
        gone = [{"s": a, "e": rng.randint(a, len(body))} for a in (rng.randint(0, len(body)) for _ in range(rng.randrange(6)))]
        gone = [g for g in gone if g["s"] < g["e"]]
        away = [any(g["s"] <= i < g["e"] for g in gone) for i in range(len(body))]
        runs = sum(x and not y for x, y in zip(away, [False, *away]))
        want = bytes(c for c, x in zip(body, away) if not x), sum(away), runs
        assert suffix_dedup.cut(body, gone) == want
        assert suffix_dedup.without(body, np.array([g["s"] for g in gone], np.int32), np.array([g["e"] for g in gone], np.int32)) == want
    texts = ["".join(rng.choice("ab ") for _ in range(400)) for _ in range(30)]
    docs = spark.createDataFrame([(i, texts[i % 30][i % 7 :]) for i in range(90)] + [(90, None), (91, "")], "doc_id long, text string").cache()
    whole = sorted(suffix_dedup.remove(docs, ["doc_id"]).collect())
    assert suffix_dedup.HASHED * 8 <= 1 << 20
    assert whole[0].n_removed == 0 and whole[60].n_removed > 300 and whole[90].n_bytes == 0
