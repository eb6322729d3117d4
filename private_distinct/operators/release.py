"""Differentially private releases: plain, thinned, thinned with phantoms, and of sketches that exist already.

With ``by``, every group is one release under a hash function of its own.  Which groups there are is public: pass
them as ``groups``, and a listed group without items still gets a row while items of other groups are dropped; without
the list the groups of the data are taken for it.  A ``ledger`` refuses a key's second output and eps beyond its limit.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import SPACE, SketchKey
from ..functions.privacy import CUSTOM, Budget, SketchSpec, delta, min_cardinality, pi0, threshold
from .sketches import _slot_val, build_state, estimate_state, hashed, merge_states, phantoms, phantoms_of_groups, state_of_hashes


class KeyLedger:
    """Which output each key was spent on, and eps so far: a key that two outputs share protects neither.

    One object per process or service; ``entries`` (key_id -> (output, eps), no secrets) can be stored and given back.
    ``eps_limit`` bounds the sum of eps over all outputs, by composition.
    """

    def __init__(self, entries: dict[str, tuple[str, float]] | None = None, eps_limit: float | None = None):
        self.entries, self.eps_limit = dict(entries or {}), eps_limit

    @property
    def spent(self) -> float:
        return sum(eps for _, eps in self.entries.values())

    def claim(self, key: SketchKey, output: str, eps: float = 0.0) -> SketchKey:
        """The key, once; the same output may be computed again, as the same state is no second release."""
        known = self.entries.get(key.key_id)
        if known and known[0] != output:
            raise ValueError(f"this key was spent on {known[0]}; derive another one for {output}")
        if not known:
            if self.eps_limit is not None and self.spent + eps > self.eps_limit + 1e-12:
                raise ValueError(f"eps {self.spent:g} is spent, {eps:g} more pass the limit of {self.eps_limit:g}")
            self.entries[key.key_id] = (output, eps)
        return key


def _claim(ledger: KeyLedger | None, kind: str, df: DataFrame, item: list[str], spec: SketchSpec, budget: Budget, key: SketchKey, by: tuple) -> None:
    if ledger is not None:
        ledger.claim(key, f"{kind}/{spec}/{','.join(item)}/{','.join(by)}/{budget.eps:g}/{df.semanticHash()}", budget.total_eps)


def _of_groups(df: DataFrame, groups: DataFrame | None, by: tuple) -> DataFrame:
    """Items of the public groups only, a null group being one like any other."""
    if groups is None:
        return df
    listed = groups.select(*[F.col(c).alias(f"_listed_{c}") for c in by]).distinct()
    same = reduce(lambda a, b: a & b, [df[c].eqNullSafe(listed[f"_listed_{c}"]) for c in by])
    return df.join(listed, same, "left_semi")


def _with_empty(est: DataFrame, groups: DataFrame | None, by: tuple) -> DataFrame:
    """A row for every public group; one without items has an empty sketch."""
    if groups is None:
        return est
    listed = groups.select(*[F.col(c).alias(f"_listed_{c}") for c in by]).distinct()
    same = reduce(lambda a, b: a & b, [est[c].eqNullSafe(listed[f"_listed_{c}"]) for c in by])
    out = listed.join(est, same, "left")
    return out.select(*[F.col(f"_listed_{c}").alias(c) for c in by], F.coalesce("base_estimate", F.lit(0.0)).alias("base_estimate"))


def _certified(est: DataFrame, spec: SketchSpec, budget: Budget, by: tuple, p: float, v: int, d: float | None) -> DataFrame:
    return est.select(
        *by,
        "base_estimate",
        F.lit(p).alias("p"),
        F.lit(v).cast("long").alias("phantoms"),
        (F.col("base_estimate") / F.lit(p) - F.lit(v)).alias("estimate"),
        F.lit(budget.eps).alias("eps"),
        F.lit(d).cast("double").alias("delta"),
        F.lit(spec.k_max).cast("long").alias("k_max"),
        F.lit(min_cardinality(spec.k_max, budget.eps)).alias("n0"),
    )


def release_plain(df: DataFrame, item: list[str], spec: SketchSpec, budget: Budget, key: SketchKey, by: tuple = (), estimator: str = "classic", groups: DataFrame | None = None, ledger: KeyLedger | None = None) -> DataFrame:
    """The unmodified sketch: (eps, delta), delta evaluated at the declared floor, and no more than the budget's.

    Without a floor nothing bounds delta, so the budget must allow 1.  Linear counting that thins by itself below
    the bound is pure above its least cardinality.
    """
    d = delta(spec, budget.n_floor, budget.eps) if budget.n_floor else None
    if (1.0 if d is None else d) > budget.delta:
        raise ValueError(f"delta is {1.0 if d is None else d:.3g} at the declared floor, the budget allows {budget.delta:.3g}")
    _claim(ledger, "plain", df, item, spec, budget, key, by)
    state = build_state(_of_groups(df, groups, by), item, spec, key, by, None, True)
    return _certified(_with_empty(estimate_state(state, spec, by, estimator), groups, by), spec, budget, by, 1.0, 0, d)


def release_large(df: DataFrame, item: list[str], spec: SketchSpec, budget: Budget, key: SketchKey, by: tuple = (), estimator: str = "classic", groups: DataFrame | None = None, ledger: KeyLedger | None = None) -> DataFrame:
    """Items thinned by the second hash: pure eps for streams known to be large enough."""
    if budget.n_floor is None or budget.n_floor <= min_cardinality(spec.k_max, budget.eps):
        raise ValueError(f"needs a declared floor above {min_cardinality(spec.k_max, budget.eps):.0f} items")
    if spec.rate < 1:
        raise ValueError("a sketch that thins by itself is released plain")
    _claim(ledger, "large", df, item, spec, budget, key, by)
    state = build_state(_of_groups(df, groups, by), item, spec, key, by, threshold(budget.eps), True)
    return _certified(_with_empty(estimate_state(state, spec, by, estimator), groups, by), spec, budget, by, pi0(budget.eps), 0, 0.0)


def _items_and_phantoms(df: DataFrame, item: list[str], v: int, t: int, key: SketchKey, by: tuple, groups: DataFrame | None = None) -> DataFrame:
    items = hashed(_of_groups(df, groups, by), item, key, by, t, own=True)
    if by:
        return items.unionByName(phantoms_of_groups((df if groups is None else groups).select(*by).distinct(), v, key, by, t))
    return items.unionByName(phantoms(df.sparkSession, v, key, t))


def release_any(df: DataFrame, item: list[str], spec: SketchSpec, budget: Budget, key: SketchKey, by: tuple = (), estimator: str = "classic", groups: DataFrame | None = None, ledger: KeyLedger | None = None) -> DataFrame:
    """Thinned items and thinned phantoms: pure eps for any stream."""
    if spec.rate < 1:
        raise ValueError("a sketch that thins by itself is released plain")
    _claim(ledger, "any", df, item, spec, budget, key, by)
    v, t = math.ceil(min_cardinality(spec.k_max, budget.eps)), threshold(budget.eps)
    state = state_of_hashes(_items_and_phantoms(df, item, v, t, key, by, groups), spec, by)
    return _certified(estimate_state(state, spec, by, estimator), spec, budget, by, pi0(budget.eps), v, 0.0)


def _stops_within(spark, spec: SketchSpec, budget: Budget, key: SketchKey, v: int) -> int | None:
    """Least number of the first v phantoms at which their sketch does not violate; None if v are too few.

    A running window over the first phantoms that change the state: a few rows for each slot, in one job.
    """
    bound = pi0(budget.eps)
    h = hashed(spark.range(v), ["id"], key, (), None, "p", also=("id",))
    if spec.kind in ("bottomk", "adaptive"):
        # the k-th hash below the bound, or the one that leaves more than k below the level before the bound
        level = math.floor(-math.log2(bound)) + 1
        cut, need = (bound * SPACE, spec.k) if spec.kind == "bottomk" else (2.0 ** (1 - level) * SPACE, spec.k + 1)
        low = h.where(F.col("h") < F.lit(cut)).groupBy("h").agg(F.min("id").alias("id")).orderBy("id").limit(need)
        n, last = low.agg(F.count(F.lit(1)), F.max("id")).first()
        return last + 1 if n == need else None
    slot, val = _slot_val(spec)
    first = h.select("id", slot.alias("slot"), val.alias("val")).groupBy("slot", "val").agg(F.min("id").alias("id"))
    if spec.kind == "hll":
        before = Window.partitionBy("slot").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)
        seen = F.coalesce(F.max("val").over(before), F.lit(0))
        drops = first.select("id", F.greatest(F.pow(F.lit(2.0), -seen) - F.pow(F.lit(2.0), -F.col("val")), F.lit(0.0)).alias("drop"))
    elif spec.kind == "fm":  # a value has one bit, whose chance is that of its level
        place = F.log2(F.col("val").cast("double"))
        drops = first.select("id", F.pow(F.lit(2.0), -F.least(place + 1, F.lit(spec.bitmap_len - 1.0))).alias("drop"))
    else:
        drops = first.select("id", F.lit(1.0).alias("drop"))
    sums = drops.groupBy("id").agg(F.sum("drop").alias("drop")).withColumn("gone", F.sum("drop").over(Window.orderBy("id")))
    last = sums.where(1 - F.col("gone") / F.lit(float(spec.k)) < F.lit(bound)).agg(F.min("id")).first()[0]
    return None if last is None else last + 1


def stopping_count(spark, spec: SketchSpec, budget: Budget, key: SketchKey, max_items: int = 10**8) -> int:
    """Least v >= n0 at which a sketch of v phantoms does not violate: one job, as a rule, over twice the floor."""
    low = math.ceil(min_cardinality(spec.k_max, budget.eps))
    if spec.kind in CUSTOM:
        raise ValueError("a registered sketch has no stopping rule: release it with phantoms instead")
    v = 2 * low
    while (found := _stops_within(spark, spec, budget, key, v)) is None:
        v *= 2
        if v > max_items:
            raise ValueError(f"no stop within {max_items} phantoms")
    return max(low, found)


def privatise_existing(state: DataFrame, spec: SketchSpec, budget: Budget, key: SketchKey, max_items: int = 10**8) -> DataFrame:
    """Merge an existing state with a noisily started one; the certificate is as claimed by the reference."""
    v = stopping_count(state.sparkSession, spec, budget, key, max_items)
    merged = merge_states([state, state_of_hashes(phantoms(state.sparkSession, v, key), spec)], spec)
    return _certified(estimate_state(merged, spec), spec, budget, (), 1.0, v, 0.0)


def release_builtin(df: DataFrame, item: list[str], budget: Budget, key: SketchKey, rsd: float = 0.05, by: tuple = ()) -> DataFrame:
    """Thinned items and phantoms through the engine's own distinct counter, on keyed hashes."""
    k = 1 << math.ceil(2 * math.log2(1.106 / rsd))
    spec = SketchSpec("hll", k)
    v, t = math.ceil(min_cardinality(k, budget.eps)), threshold(budget.eps)
    all_ = _items_and_phantoms(df, item, v, t, key, by)
    est = all_.groupBy(*by).agg(F.approx_count_distinct("h", rsd).cast("double").alias("base_estimate"))
    return _certified(est, spec, budget, by, pi0(budget.eps), v, 0.0)
