"""Experiments over many trials in one job: error and space at equal k.

A trial's number is part of every hashed item, so trials are as independent as sketches with keys of their own.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import SPACE, SketchKey, slices
from ..functions.privacy import SketchSpec, delta, estimate_threshold, min_cardinality, pi0, threshold, variance_bound
from ..operators.baselines import default_gamma
from ..operators.sketches import _with as joined
from ..operators.sketches import estimate_state, hashed, size_bits, state_of_hashes


def _per_trial(spark: SparkSession, n: int, trials: int) -> DataFrame:
    return spark.range(n).select("id", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))).alias("trial"))


def trial_states(spark: SparkSession, n: int, spec: SketchSpec, trials: int, key: SketchKey, eps: float | None = None) -> DataFrame:
    """(trial, slot, val) of n items; with ``eps``, items are thinned and joined by thinned phantoms."""
    below = threshold(eps) if eps else None
    h = hashed(_per_trial(spark, n, trials), ["trial", "id"], key, ("trial",), below)
    if eps:
        v = math.ceil(min_cardinality(spec.k_max, eps))
        h = h.union(hashed(_per_trial(spark, v, trials), ["trial", "id"], key, ("trial",), below, "p"))
    return state_of_hashes(h, spec, ("trial",))


def estimates(spark: SparkSession, n: int, spec: SketchSpec, trials: int, key: SketchKey, eps: float | None = None) -> DataFrame:
    out = estimate_state(trial_states(spark, n, spec, trials, key, eps), spec, ("trial",))
    if not eps:
        return out.select("trial", F.col("base_estimate").alias("estimate"), "pi")
    v = math.ceil(min_cardinality(spec.k_max, eps))
    return out.select("trial", (F.col("base_estimate") / F.lit(pi0(eps)) - F.lit(v)).alias("estimate"), "pi")


def error_summary(est: DataFrame, n: int) -> DataFrame:
    """Mean relative error, bias and root mean square, relative to n, over trials."""
    e = (F.col("estimate") - F.lit(n)) / F.lit(float(n))
    return est.agg(F.avg(F.abs(e)).alias("mean_relative_error"), F.avg(e).alias("bias"), F.sqrt(F.avg(e * e)).alias("rmse"), F.count(F.lit(1)).alias("trials"))


def simulated_per_bucket(spark: SparkSession, n: int, k: int, trials: int, key: SketchKey, gamma: float | None = None) -> DataFrame:
    """(trial, slot, val) of the per-bucket baseline, each register drawn from the law of its maximum over n items."""
    base = 1 + (default_gamma(k) if gamma is None else gamma)
    rows = _per_trial(spark, k, trials).select("trial", F.col("id").cast("int").alias("slot"))
    h, _ = slices(F.concat_ws("/", F.lit("max"), "trial", "slot"), key)
    u = (h + F.lit(0.5)) / F.lit(float(SPACE))
    least = -F.expm1(F.log1p(-u) / F.lit(float(n)))  # the least of n uniform draws
    return rows.withColumn("val", (1 + F.floor(-F.ln(least) / F.lit(math.log(base)))).cast("long"))


def space_summary(spark: SparkSession, n: int, k: int, trials: int, key: SketchKey, eps: float) -> DataFrame:
    """Mean measured bits of the private register sketch and of the per-bucket baseline, and their ratio."""
    ours = size_bits(trial_states(spark, n, SketchSpec("hll", k), trials, key, eps), k, ("trial",))
    theirs = size_bits(simulated_per_bucket(spark, n, k, trials, key), k, ("trial",))
    both = ours.agg(F.avg("paper_bits").alias("private_bits")).crossJoin(theirs.agg(F.avg("paper_bits").alias("per_bucket_bits")))
    return both.select("*", (F.col("per_bucket_bits") / F.col("private_bits")).alias("space_ratio"))


def violation_summary(spark: SparkSession, n: int, spec: SketchSpec, trials: int, key: SketchKey, eps: float) -> DataFrame:
    """Share of unmodified states that violate, the same told from the estimate, and the stated failure probability.

    Below the least cardinality the stated one is 1, as the theorem then says nothing.
    """
    est = estimates(spark, n, spec, trials, key)
    least = estimate_threshold(spec, eps)
    low = F.avg((F.col("estimate") < F.lit(least)).cast("double")) if least else F.lit(None).cast("double")
    return est.agg(F.avg((F.col("pi") >= F.lit(pi0(eps))).cast("double")).alias("violating"), low.alias("below_threshold"), F.lit(float(delta(spec, n, eps))).alias("delta"), F.count(F.lit(1)).alias("trials"))


def moment_summary(spark: SparkSession, n: int, spec: SketchSpec, trials: int, key: SketchKey, eps: float) -> DataFrame:
    """Bias of the private estimate with its z-score, its variance, the bound on it and its ratio to the plain one's."""
    v = math.ceil(min_cardinality(spec.k_max, eps))
    mine, plain = estimates(spark, n, spec, trials, key, eps), estimates(spark, n, spec, trials, key)
    error = F.col("estimate") - F.lit(n)
    own = mine.agg(F.avg(error).alias("bias"), F.var_samp("estimate").alias("variance"), F.count(F.lit(1)).alias("trials"))
    other = plain.agg(F.var_samp("estimate").alias("plain_variance"))
    z = F.col("bias") / F.sqrt(F.col("variance") / F.col("trials"))
    bound = F.lit(float(variance_bound(n, v, spec.rel_std_error(n) ** -2, pi0(eps))))
    return own.crossJoin(other).select("bias", z.alias("z"), "variance", bound.alias("variance_bound"), (F.col("variance") / F.col("plain_variance")).alias("variance_ratio"), "trials")


def group_moments(rows: DataFrame, item: str, by: tuple, spec: SketchSpec, trials: int, key: SketchKey, eps: float) -> DataFrame:
    """``moment_summary`` of each group of a given table: every item takes part in every trial.

    Groups and trials have hash functions of their own.  A group without items has no row; where a
    plain sketch holds all items it does not vary, and there is no ratio.
    """
    if spec.kind == "linear":
        raise ValueError("the standard error of linear counting depends on n")
    spark, within, below = rows.sparkSession, (*by, "trial"), threshold(eps)
    v, c = math.ceil(min_cardinality(spec.k_max, eps)), spec.rel_std_error(1) ** -2
    items = rows.where(F.col(item).isNotNull()).select(*by, item).distinct()
    sizes = items.groupBy(*by).agg(F.count(F.lit(1)).alias("n"))
    spread = F.explode(F.sequence(F.lit(0), F.lit(trials - 1))).alias("trial")
    tasks = 4 * spark.sparkContext.defaultParallelism  # few items make many hashes
    tried = items.repartition(tasks, item).select("*", spread)
    ghosts = sizes.select(*by, F.explode(F.sequence(F.lit(0), F.lit(v - 1))).alias(item)).select("*", spread)

    def moments(h: DataFrame, estimate, prefix: str) -> DataFrame:
        est = estimate_state(state_of_hashes(h, spec, within), spec, within).select(*by, estimate.alias("estimate"))
        return est.groupBy(*by).agg(F.avg("estimate").alias(f"{prefix}mean"), F.var_samp("estimate").alias(f"{prefix}variance"), F.count(F.lit(1)).alias(f"{prefix}trials"))

    kept = hashed(tried, ["trial", item], key, within, below, own=True).union(hashed(ghosts, ["trial", item], key, within, below, "p", own=True))
    mine = moments(kept, F.col("base_estimate") / F.lit(pi0(eps)) - F.lit(v), "")
    plain = moments(hashed(tried, ["trial", item], key, within, own=True), F.col("base_estimate"), "plain_")
    both = joined(joined(sizes, mine, by), plain.drop("plain_mean", "plain_trials"), by)
    bias = F.col("mean") - F.col("n")
    return both.select(*by, "n", bias.alias("bias"), F.try_divide(bias, F.sqrt(F.col("variance") / F.col("trials"))).alias("z"), "variance", variance_bound(F.col("n"), v, c, pi0(eps)).alias("variance_bound"), F.try_divide("variance", "plain_variance").alias("variance_ratio"), "trials")
