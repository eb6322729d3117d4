"""Sharding by rendezvous hashing of record keys over weighted shards.

Every (key, shard) has a pseudo-random score ``-ln(u) / weight``; the least score wins, so shard s gets
a share of rows proportional to its weight, and a further shard only takes rows into itself.  All of it
is built-in expressions; the only shuffle is the numbering of narrow rows.

Edge cases: a null text has size 1 and the checksum of an empty one; null keys form one key and so go to
one shard; repeated rows go to the same shard with slots of their own; an empty table gives no rows; other
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, numbered


def shard_scores(key: Column, weights: list[float]) -> list[Column]:
    """Score of each shard for ``key``; shard s depends on s and its weight only."""
    if not weights or min(weights) <= 0:
        raise ValueError("weights must be positive")
    unit = [(F.shiftrightunsigned(F.xxhash64(F.lit(s), key), 12) + F.lit(0.5)) * F.lit(2.0**-52) for s in range(len(weights))]
    return [-F.ln(u) / F.lit(float(w)) for u, w in zip(unit, weights, strict=True)]


def choose_shard(key: Column, weights: list[float]) -> Column:
    scores = F.array(*shard_scores(key, weights))
    return (F.array_position(scores, F.array_min(scores)) - 1).cast("int")


def assign(df: DataFrame, key: str, text: str, weights: list[float], grown_weight: float | None = None) -> DataFrame:
    """key, size, text_crc32, shard, grown_shard (with one more shard) and a gapless slot in the shard."""
    body = F.coalesce(F.col(text), F.lit("")).cast("binary")
    more = [*weights, grown_weight if grown_weight is not None else sum(weights) / len(weights)]
    narrow = df.select(
        F.col(key),
        (F.octet_length(body) + F.lit(1)).cast("long").alias("size"),
        F.crc32(body).alias("text_crc32"),
        choose_shard(F.col(key), weights).alias("shard"),
        choose_shard(F.col(key), more).alias("grown_shard"),
    )
    return numbered(materialise(narrow, "shards"), ["shard"], [key, "text_crc32"], "slot")
