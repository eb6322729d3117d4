"""Filters of repeated keys: nothing that repeats is lost, whatever the limit on a broadcast."""

import numpy as np
import pyarrow as pa


def test_repeated_keys_pass_every_range(spark):
    from private_distinct.llm import repeats

    rng = np.random.default_rng(0)
    once, twice = rng.integers(0, 2**63, 20000).astype(np.uint64), rng.integers(0, 2**63, 3000).astype(np.uint64)
    keys = np.concatenate([once, twice, twice])

    def emit(batches):
        for b in batches:
            for i in b.column(0).to_pylist():
                yield repeats.dealt(keys[i::8], 64)

    source = spark.range(8).repartition(4)
    for limit, least in ((1 << 20, 2), (700, 2), (4000, 1)):
        found = repeats.filters(source.mapInArrow(emit, repeats.SCHEMA), 64, "test-keys", limit, least)
        assert (len(found) > 1) == (limit < 1 << 20)
        ok = np.sum([f.value.maybe(twice) for f in found], axis=0)
        assert (ok == 1).all()  # one range each
        extra = np.mean(np.sum([f.value.maybe(once) for f in found], axis=0))
        assert extra < 0.05 if least == 2 else extra == 1
    none = spark.range(0).mapInArrow(lambda bs: (pa.RecordBatch.from_arrays([pa.array([], pa.int32()), pa.array([], pa.binary())], names=["part", "keys"]) for _ in bs), repeats.SCHEMA)
    assert not repeats.filters(none, 64, "test-keys")[0].value.maybe(once).any()
