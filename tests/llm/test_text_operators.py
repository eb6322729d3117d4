"""Packing, chat, SimHash, BPE, sharding and language model against plain versions on small tables."""

import base64
import hashlib
import math
import zlib
from collections import Counter, defaultdict

import pytest
import tiktoken
import xxhash
from pyspark.sql import functions as F

P = pytest.importorskip("public_tokenizers")
SF = "/root/testdata/sf0.001"
ODD = [
    (1001, None, "x"), (1002, "", "x"), (1003, "one", None), (1004, "  two   spaces \n\n end ", "x"), (1005, "a" * 5000, "x"),
    (1006, "it's 日本語 <|endoftext|>  x", "x"), (1006, "it's 日本語 <|endoftext|>  x", "x"), (None, "no id", "x"), (1007, "word " * 3000, "x"),
]


@pytest.fixture(scope="module")
def docs(spark):
    odd = spark.createDataFrame(ODD, "doc_id long, text string, fp string")
    given = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", F.lit("clash").alias("fp"))
    return given.union(odd).cache()


def rows(df):
    return [r.asDict() for r in df.collect()]


def components(n, near):
    root = list(range(n))

    def find(i):
        while root[i] != i:
            root[i] = i = root[root[i]]
        return i

    for i in range(n):
        for j in range(i):
            if near(i, j):
                root[find(i)] = find(j)
    return [find(i) for i in range(n)]


def test_bpe_equals_library(spark, docs):
    from private_distinct.llm import bpe

    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want, plain = Counter(), {}
    for d, t, _ in docs.collect():
        ids = lib.encode_ordinary(t or "")
        want[d, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()] += 1
    got = rows(bpe.encode_digests(docs, ranks, P.PATTERN))
    assert Counter(tuple(r.values()) for r in got) == want
    coder = bpe.ByteBPE(ranks, P.PATTERN)
    assert coder.decode(coder.encode(ODD[5][1])).decode() == ODD[5][1]
    words = [w.encode() for _, t, _ in docs.limit(20).collect() for w in coder.split.findall(t or "")]
    words += [b"", b"a" * 3000, b"ab" * 700, "日本語".encode() * 50]
    assert [coder.merge_heap(w) for w in words] == bpe.ByteBPE(ranks, P.PATTERN, lockstep=True).encode_pieces(words)
    assert coder.encode_pieces(words) == [coder.merge_heap(w) if w not in ranks else [ranks[w]] for w in words]


def test_packing(spark, docs):
    from tokenizers import Tokenizer

    from private_distinct.llm import bpe, packing

    tok = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    special = packing.special_tokens(P.path("byte_bpe_50k.json"))
    more = spark.createDataFrame([(2000, "<|endoftext|>", "x"), (2001, "a <|endoftext|><|endoftext|> b<|endoftext", "x"), (2002, " x" * 5000 + "<|endoftext|>", "x")], docs.schema)
    docs = docs.union(more).cache()
    got = rows(packing.pack(packing.encode_pieces(docs, bpe.read_ranks(P.path("byte_bpe_50k.tiktoken")), P.PATTERN, keep_ids=True, special=special)))
    want = Counter()
    for d, t, _ in docs.collect():
        ids = tok.encode(t or "", add_special_tokens=False).ids + [0]
        cuts = [0, *range(len(ids) % 2048 or 2048, len(ids) + 1, 2048)]
        for k, (a, b) in enumerate(zip(cuts, cuts[1:])):
            want[d, k, a, b - a, zlib.crc32(b"".join(i.to_bytes(4, "little") for i in ids[a:b]))] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == want
    bins = defaultdict(list)
    for r in got:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 2048
    assert len(bins) <= math.ceil(sum(r["length"] for r in got) / 2048) * 1.02 + 1


def test_packing_takes_bounded_memory(spark, monkeypatch):
    import pyarrow as pa

    from private_distinct.llm import bpe, common, packing

    texts = ["é" * 300, None, "", "a" * 5000, *["b" * 400] * 9]
    got = list(packing.text_slices(pa.array(texts), 1000))
    assert [t for part in got for t in part] == texts and max(len(part) for part in got if part != texts[:3]) == 2
    assert all(len(part) == 1 or sum(len((t or "").encode()) for t in part) <= 1000 for part in got)
    coder = bpe.ByteBPE(bpe.read_ranks(P.path("byte_bpe_50k.tiktoken")), P.PATTERN, lockstep=True)
    words, sizes, whole = [b"q%dz%d" % (i, i * i) for i in range(20000)], [], coder.merge_lockstep
    monkeypatch.setattr(coder, "merge_lockstep", lambda pieces: sizes.append(len(pieces)) or whole(pieces))
    monkeypatch.setattr(bpe, "LOCKSTEP_PIECES", 3000)
    ids = coder.encode_pieces(words)
    assert max(sizes) <= 3000 and ids[::97] == [coder.merge_heap(w) for w in words[::97]]
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    with common.small_batches(spark, 7):
        assert spark.range(30, numPartitions=1).mapInArrow(lambda bs: bs, "id long").count() == 30 and spark.conf.get(name) == "7"
    assert spark.conf.get(name) == before


def test_slices_of_texts_share_what_is_known(monkeypatch):
    from private_distinct.llm import bpe

    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    odd = [None, "", " ", "  ", "a ", " a", "a  b c", "x\u00a0 \u00a0y z.", "n \u3000z", "\u00bf a \u00bfno?", "a.\nB c's it's", "1 22,3 \x1f4", "e\u0301 . ,", "tail \n", "\n \n", "z. z, z; Z"]
    texts = [*odd, "".join(t or "" for t in odd), *[f"{t} {t}. {t}" for t in odd]]
    for lockstep in (False, True):
        coder = bpe.ByteBPE(ranks, P.PATTERN, lockstep=lockstep)
        for size in (1 << 21, 1):  # one slice, then a slice for each text; in between all is known, then again nothing is
            monkeypatch.setattr(bpe, "SLICE_CHARS", size)
            assert [ids.tolist() for ids in coder.encode_all(texts)] == [lib.encode_ordinary(t or "") for t in texts]
        monkeypatch.setattr(bpe, "MEMO_PIECES", 3)
        assert [ids.tolist() for ids in coder.encode_all(texts)] == [lib.encode_ordinary(t or "") for t in texts]
        monkeypatch.undo()
    coder = bpe.ByteBPE(ranks, P.PATTERN)
    merged, whole = [], coder.merge_heap
    monkeypatch.setattr(coder, "merge_heap", lambda piece: merged.append(piece) or whole(piece))
    for text in ("a zqracoiexyz b", "a zqracoiexyz. c", "zqracoiexyz, zqracoiexyz,\nzqracoiexyz"):
        coder.encode(text)
    assert merged == [b" zqracoiexyz", b"zqracoiexyz"]  # not once for each chunk that holds it


def test_replacement_fits_more_tightly():
    from private_distinct.llm.packing import plan

    assert plan({6: 1, 3: 1, 2: 2}, 10) == [([6, 2, 2], 1), ([3], 1)]
    assert sum(n for _, n in plan({2048: 10**12}, 2048)) == 10**12


def test_simhash(spark, docs):
    from private_distinct.llm import simhash

    got = rows(simhash.near_duplicates(docs))
    given = docs.collect()
    import re

    def plain(t):
        low = re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
        w = re.findall("[^\x20\x09-\x0d]+", low)
        if not w:
            return 0
        h = [xxhash.xxh64_intdigest(" ".join(w[i : i + 3]), 42) for i in range(max(1, len(w) - 2))]
        return sum((sum(x >> b & 1 for x in h) * 2 > len(h)) << b for b in range(64))

    fps = [plain(r.text) for r in given]
    root = components(len(fps), lambda i, j: (fps[i] ^ fps[j]).bit_count() <= 3)
    least = {}
    for r, c in zip(given, root):
        if r.doc_id is not None:
            least[c] = min(r.doc_id, least.get(c, r.doc_id))
    want = Counter((r.doc_id, f"{f:016x}", least.get(c)) for r, f, c in zip(given, fps, root))
    assert Counter((r["doc_id"], r["fingerprint"], r["component_id"]) for r in got) == want


def test_simhash_finds_every_link():
    import random

    import numpy as np

    from private_distinct.llm import simhash

    rng = random.Random(3)
    masks, flips = simhash._variants()
    for _ in range(300):
        a = rng.getrandbits(64)
        b = a
        for i in rng.sample(range(64), rng.randint(1, 3)):
            b ^= 1 << i
        f = np.repeat(np.array([a, b], np.uint64), len(masks))
        x, y = simhash.links_in((f & np.tile(masks, 2)) ^ np.tile(flips, 2), f)
        assert {int(x[0]), int(y[0])} == {a, b}


def test_sharding(spark, docs):
    from private_distinct.llm import sharding

    got = rows(sharding.assign(docs, "doc_id", "text", [1.0] * 8))
    want = Counter((d, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for d, t, _ in docs.collect())
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == want
    slots = defaultdict(list)
    for r in got:
        slots[r["shard"]].append(r["slot"])
        assert r["grown_shard"] in (r["shard"], 8)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    big = spark.range(20000).select("id", F.lit("").alias("t"))
    share = Counter(r["shard"] for r in rows(sharding.assign(big, "id", "t", [1.0, 1.0, 2.0])))
    assert abs(share[2] / 20000 - 0.5) < 0.02


def test_chat(spark):
    from private_distinct.llm import chat, queries

    with open(P.path("byte_bpe_50k.json")) as f:
        tokenizer = f.read()
    said = "<|im_end|><|im_start|>assistant ok"
    own = [(-1, 0, "user", said), (-1, 1, "assistant", said), (-2, 0, "system", "be brief"), (-3, None, None, None)]
    own += [(-2, i, "user" if i % 2 else "assistant", f"<\\\\| turn {i} <" + " word" * (300 if i != 7 else 3000)) for i in range(1, 12)]
    df = spark.createDataFrame([(*r, "x") for r in own], "conv_id long, turn long, role string, text string, loss string")
    df = df.union(spark.read.parquet(f"{SF}/conversations.parquet").select("conv_id", "turn", "role", "text", F.lit("x")))
    windows = chat.format_windows(df, tokenizer, budget=1024, history=4).cache()
    for w in rows(windows.where("conv_id = -2")):
        assert w["n_tokens"] <= 1024 or w["n_new"] == 1
        assert chat.read_turns(w["text"])[0] == ("system", "be brief")
        assert w["window"] == 0 or w["n_context"] >= 1
    want = {}
    by = defaultdict(list)
    for r in df.collect():
        by[r.conv_id].append((r.turn is not None, r.turn or 0, r.role or "", r.text or ""))
    for c, t in by.items():
        t.sort()
        loss = "".join(x[3] for x in t if x[2] == "assistant")
        want[c] = (len(t), hashlib.sha256("".join(f"{x[2]}\n{x[3]}\n" for x in t).encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert {r["conv_id"]: (r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"]) for r in rows(chat.read_back(windows))} == want
    assert chat.unescape(chat.escape(said)) == said and "<|" not in chat.escape(said + "<\\|<\\\\|")
    assert chat.unescape_role(chat.escape_role("a\\n\nb<|")) == "a\\n\nb<|"
    assert queries.op6_chat_windows(spark, SF).where("conv_id = -1").count() == 1


def test_language_model(spark, docs):
    from private_distinct.llm import ngram_lm

    train = "crc32(cast(cast(doc_id as string) as binary)) % 7 <> 2"
    got = rows(ngram_lm.score(docs, train, broadcast_words=100))
    given = docs.withColumn("t", F.coalesce(F.expr(train), F.lit(False))).collect()
    counts, tokens = Counter(), lambda t: [*(t or "").encode().lower().split(), None]
    for r in given:
        if r.t:
            counts.update(tokens(r.text))
    n, v = counts.total(), len(counts)
    want = Counter((r.doc_id, r.t, len(w := tokens(r.text)), sum(x in counts for x in w), round(sum(math.log10((counts[x] + 1) / (n + v + 1)) for x in w), 4)) for r in given)
    assert Counter((r["doc_id"], r["trained"], r["n_tokens"], r["n_known"], round(r["base_score"], 4)) for r in got) == want
    assert {r["train_tokens"] for r in got} == {n}
    held = [r for r in got if not r["trained"] and r["n_tokens"] > 20]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)


def test_empty_tables(spark):
    from private_distinct.llm import bpe, chat, ngram_lm, packing, sharding, simhash

    none = spark.createDataFrame([], "doc_id long, text string")
    ranks = {bytes([i]): i for i in range(256)}
    assert bpe.encode_digests(none, ranks, P.PATTERN).count() == 0
    assert packing.pack(packing.encode_pieces(none, ranks, P.PATTERN)).count() == 0
    assert simhash.near_duplicates(none).count() == 0
    assert sharding.assign(none, "doc_id", "text", [1.0]).count() == 0
    assert ngram_lm.score(none, "true").count() == 0
    with open(P.path("byte_bpe_50k.json")) as f:
        assert chat.format_windows(spark.createDataFrame([], "conv_id long, turn long, role string, text string"), f.read()).count() == 0
