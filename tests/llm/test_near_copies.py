"""The near-copy stage of the pipeline against all pairs of texts."""

from collections import Counter

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


def plain(rows):
    """Rows kept: the least id of each group linked by five-word Jaccard similarity >= 0.8."""
    sets = []
    for r in rows:
        w = (r.text or "").encode().lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            if a == sets[j] or len(a & sets[j]) * 5 >= len(a | sets[j]) * 4:
                root[find(i)] = find(j)
    least = {}
    for i, r in enumerate(rows):
        least.setdefault(find(i), []).append(r.doc_id)
    return Counter(min(x) for x in least.values())


def test_stage_drops_all_near_copies(spark):
    import random

    import corpus_pipeline as p

    rng = random.Random(4)
    base = [f"w{rng.randrange(5000)}" for _ in range(200)]
    odd = [(None, "no id", "en", "s", 5), (5000, None, "en", "s", 0), (5001, "", "en", "s", 0), (5002, "a b", "en", "s", 3), (5003, "A  b", "en", "s", 4)]
    odd += [(6000 + i, " ".join([*base[:i], *(f"x{i}" for _ in range(i % 3)), *base[i + i % 4 :]]), "en", "s", 0) for i in range(0, 200, 3)]
    odd += [(7000 + i, "the same line of words stands here " + " ".join(f"v{rng.randrange(9000)}" for _ in range(i % 40)), "en", "s", 0) for i in range(120)]
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("doc_id < 700").union(spark.createDataFrame(odd, COLUMNS)).cache()
    stage = dict(p.STAGES)["simhash_near_dedup"]
    kept = stage(spark, docs, "")
    assert kept.columns == docs.columns
    want = plain([r for r in docs.collect() if r.doc_id is not None])
    assert Counter(r.doc_id for r in kept.collect()) == want + Counter([None])
    assert stage(spark, docs.limit(0), "").count() == 0


def test_rounds_meet_every_pair_that_shares_a_prefix_once_it_is_due():
    import numpy as np

    from private_distinct.llm import near_copies as nc

    rng = np.random.default_rng(5)
    prefixes = [np.unique(rng.integers(1, 60, 12)).astype(np.uint64) for _ in range(150)]  # one order of all shingles
    rows = np.zeros(sum(map(len, prefixes)), nc._POSTING)
    at = 0
    for c, h in enumerate(prefixes):
        mine = rows[at : at + len(h)]
        mine["shingle"], mine["cls"], mine["root"], mine["size"] = h, c, c, 40 + c % 5
        mine["place"], mine["before"] = np.arange(len(h)), np.roll(h, 1)
        at += len(h)
    want = set()
    for i, a in enumerate(prefixes):
        for j in range(i):
            shared = np.intersect1d(a, prefixes[j])
            x, y = sorted((40 + i % 5, 40 + j % 5))
            if len(shared) and x >= 0.8 * y:
                first = shared[0]
                left = min(40 + i % 5 - np.searchsorted(a, first), 40 + j % 5 - np.searchsorted(prefixes[j], first))
                if left >= nc.least_overlap(np.array([x]), np.array([y]), 0.8)[0]:
                    want.add((j, i))
    met = [set(map(tuple, nc.meeting(rows, 0.8, a, r).tolist())) for a, r in zip((0, *nc.REACH), nc.REACH, strict=False)]
    assert all(met) and want <= set().union(*met)
