"""Baselines: exact counting, the engine's sketches, per-bucket hashing, and noise on the estimate."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import SPACE, SketchKey, canonical, slices


def exact_distinct(df: DataFrame, item: list[str], by: tuple = ()) -> DataFrame:
    return df.groupBy(*by).agg(F.count_distinct(*item).alias("n_distinct"))


def builtin_sketches(df: DataFrame, item: str, by: tuple = ()) -> DataFrame:
    return df.groupBy(*by).agg(F.approx_count_distinct(item).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg(item)).alias("hll"), F.theta_sketch_estimate(F.theta_sketch_agg(item)).alias("theta"))


def default_gamma(k: int) -> float:
    """Base minus one of the per-bucket registers; fitted to the published space ratios, not published itself."""
    return 12 / math.sqrt(k)


def per_bucket_state(df: DataFrame, item: list[str], k: int, key: SketchKey, gamma: float | None = None) -> DataFrame:
    """Every item hashed afresh for each of k buckets: k hashes a row, which is what makes it slow.

    Register j holds the largest geometric draw to base 1 + gamma over all items.
    """
    base = 1 + (default_gamma(k) if gamma is None else gamma)
    rows = df.select(canonical([F.col(c) for c in item]).alias("t")).where("t is not null")
    each = rows.select(F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("slot"), "t")
    h, _ = slices(F.concat(F.col("slot").cast("string"), F.lit("/"), F.col("t")), key)
    draw = 1 + F.floor(-F.ln((h + F.lit(1.0)) / F.lit(float(SPACE))) / F.lit(math.log(base)))
    return each.groupBy("slot").agg(F.max(draw.cast("long")).alias("val"))


def laplace_scale(k: int, n: float, eps: float) -> float:
    """Standard deviation of the noise that the register sketch's sensitivity, n / k at least, would need."""
    return math.sqrt(2) * n / (k * eps)


def laplace_estimate(est: DataFrame, sensitivity: float, eps: float, seed: int) -> DataFrame:
    """Noise on the estimate; private only if ``sensitivity`` bounds the sketch's, which is the caller's claim."""
    u = F.rand(seed) - 0.5
    noise = -F.signum(u) * F.ln(1 - 2 * F.abs(u)) * F.lit(sensitivity / eps)
    return est.withColumn("estimate", F.col("base_estimate") + noise)


def bitflip_fm(state: DataFrame, k: int, bitmap_len: int, flip: float, seed: int) -> DataFrame:
    """Every bit of every bitmap flipped with probability ``flip``."""
    spark = state.sparkSession
    full = spark.range(k).select(F.col("id").cast("int").alias("slot")).join(state, "slot", "left").select("slot", F.coalesce("val", F.lit(0)).cast("long").alias("val"))
    mask = sum((F.when(F.rand(seed + i) < flip, F.lit(1 << i).cast("long")).otherwise(F.lit(0).cast("long")) for i in range(bitmap_len)), F.lit(0).cast("long"))
    return full.select("slot", F.col("val").bitwiseXOR(mask).alias("val"))
