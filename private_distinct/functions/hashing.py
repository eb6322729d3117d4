"""Keyed 60-bit hashes of items.

One digest gives two disjoint 60-bit slices: the first feeds the sketch, the second the thinning, so both are
independent.  ``portable`` and ``strong`` are cryptographic; ``native`` is two keyed 64-bit hashes, about three
times as fast, for use where the key is safe but speed counts; its seeds come from the secret by two labelled
one-way steps, so nothing that is stored (a key's name, a state, a ledger) tells them.  Plans and SQL texts hold
the key: ``redact`` keeps it out of what the engine prints.
"""

from __future__ import annotations

import hashlib
import hmac
import re
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 60
SPACE = 1 << BITS


@dataclass(frozen=True)
class SketchKey:
    """The secret randomness of a sketch.  Every released output needs a key of its own: see ``derive``."""

    secret: str
    family: str = "strong"

    def __post_init__(self):
        if not self.secret:
            raise ValueError("a sketch needs a secret key")
        if self.family not in ("portable", "strong", "native"):
            raise ValueError(f"unknown hash family {self.family}")

    @property
    def key_id(self) -> str:
        return hashlib.sha256(f"id:{self.secret}".encode()).hexdigest()[:16]

    @property
    def seeds(self) -> tuple[int, int]:
        """Of the two native hashes: sketch and thinning."""
        made = (hmac.new(self.secret.encode(), label, hashlib.sha256).digest()[:8] for label in (b"sketch", b"thinning"))
        return tuple(int.from_bytes(x, "big", signed=True) for x in made)

    def derive(self, output: str) -> SketchKey:
        return SketchKey(hashlib.sha256(f"{self.secret}/{output}".encode()).hexdigest(), self.family)


def canonical(items: list[Column], namespace: str = "r") -> Column:
    """Text of an item; the parts of a composite one carry their lengths, so ('a','bc') is not ('ab','c').  Null if any part is."""
    parts = [i.cast("string") for i in items]
    if len(parts) == 1:
        return F.concat(F.lit(f"{namespace}:"), parts[0])
    return F.concat(F.lit(f"{namespace}:"), *[F.concat(F.length(p).cast("string"), F.lit("."), p) for p in parts])


def group_tag(by: list[Column]) -> Column:
    """Text that names a group; put before an item's text it gives every group a hash function of its own."""
    texts = [c.cast("string") for c in by]
    return F.concat(*[F.coalesce(F.concat(F.length(t).cast("string"), F.lit("."), t, F.lit("/")), F.lit("-/")) for t in texts])


def slices(text: Column, key: SketchKey) -> tuple[Column, Column]:
    """(sketch hash, thinning hash), both uniform below 2**60."""
    if key.family == "native":
        return tuple(F.shiftrightunsigned(F.xxhash64(F.lit(seed).cast("long"), text), 4) for seed in key.seeds)
    salted = F.concat(F.lit(f"{key.secret}:"), text)
    digest = F.md5(salted) if key.family == "portable" else F.sha2(salted, 256)
    return tuple(F.conv(F.substring(digest, i, 15), 16, 10).cast("long") for i in (1, 16))


def redact(spark, *keys: SketchKey) -> None:
    """Keep these keys out of plans that the session explains, logs or shows in its interface."""
    hidden = [re.escape(x) for k in keys for x in (k.secret, *map(str, k.seeds))]
    known = spark.conf.get("spark.sql.redaction.string.regex", None)
    spark.conf.set("spark.sql.redaction.string.regex", "|".join([*([known] if known else []), *hidden]))


def local_slices(text: str, key: SketchKey) -> tuple[int, int]:
    """The same on the driver, for the digest families."""
    digest = (hashlib.md5 if key.family == "portable" else hashlib.sha256)(f"{key.secret}:{text}".encode()).hexdigest()
    return int(digest[:15], 16), int(digest[15:30], 16)


def bit_length(x: Column) -> Column:
    return F.when(x == 0, 0).otherwise(F.length(F.bin(x)))
