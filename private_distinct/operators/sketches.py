"""Order-invariant sketches as aggregations.

``build_state`` gives the long form (by.., slot, val): map-side partial aggregates, one shuffle of at most
partitions x groups x slots rows.  Packed states are for storage.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import BITS, SPACE, SketchKey, bit_length, canonical, group_tag, slices
from ..functions.privacy import CUSTOM, CustomSketch, SketchSpec, register_sketch


def hll_alpha(k: int) -> float:
    return {16: 0.673, 32: 0.697, 64: 0.709}.get(k, 0.7213 / (1 + 1.079 / k))


def hashed(df: DataFrame, item: list[str], key: SketchKey, by: tuple = (), keep_below: int | None = None, namespace: str = "r", own: bool = False, also: tuple = ()) -> DataFrame:
    """(by.., also.., h) of the items, nulls dropped; ``keep_below``: thinning by the second hash.

    ``own``: a hash function for each group.  Released groups need it, as one shared by two of them protects neither;
    states of different groups then do not merge.
    """
    for c in item:
        if key.family != "native" and df.schema[c].dataType.typeName() in ("double", "float"):
            raise TypeError(f"{c}: cast floating point items to decimal first")
    cols = [F.col(c) for c in item]
    if key.family == "native":
        cols = [F.when(c == 0, F.lit(0.0)).otherwise(c) if df.schema[n].dataType.typeName() == "double" else c for n, c in zip(item, cols, strict=True)]
    text = canonical(cols, namespace)
    if own and by:
        text = F.concat(group_tag([F.col(c) for c in by]), text)
    h, thin = slices(text, key)
    out = df.where(" and ".join(f"`{c}` is not null" for c in item))
    if keep_below is not None:
        out = out.where(thin < F.lit(keep_below))
    return out.select(*by, *also, h.alias("h"))


def phantoms(spark, v: int, key: SketchKey, keep_below: int | None = None) -> DataFrame:
    return hashed(spark.range(v), ["id"], key, (), keep_below, "p")


def phantoms_of_groups(groups: DataFrame, v: int, key: SketchKey, by: tuple, keep_below: int | None = None) -> DataFrame:
    """(by.., h) of v phantoms for each row of ``groups``, under that group's own hash; made by the row, in blocks."""
    block = 4096
    first = groups.select(*by, F.explode(F.sequence(F.lit(0).cast("long"), F.lit(v - 1).cast("long"), F.lit(block).cast("long"))).alias("_first"))
    last = F.least(F.col("_first") + F.lit(block - 1), F.lit(v - 1).cast("long"))
    return hashed(first.select(*by, F.explode(F.sequence("_first", last)).alias("_phantom")), ["_phantom"], key, by, keep_below, "p", True)


def _with(left: DataFrame, right: DataFrame, by: tuple, how: str = "inner") -> DataFrame:
    """Join on the group, a null group being one like any other."""
    right = right.select(*[F.col(c).alias(f"_of_{c}") if c in by else F.col(c) for c in right.columns])
    same = reduce(lambda a, b: a & b, [left[c].eqNullSafe(right[f"_of_{c}"]) for c in by])
    return left.join(right, same, how).drop(*[f"_of_{c}" for c in by])


def _slot_val(spec: SketchSpec) -> tuple[Column, Column]:
    h, k = F.col("h"), spec.k
    slot = (h % k).cast("int")
    if own := CUSTOM.get(spec.kind):
        return own.slot(h, k).cast("int"), own.val(h, k).cast("long")
    if spec.kind == "linear":
        return slot, F.lit(1).cast("long")
    zeros = F.lit(BITS - k.bit_length() + 1) - bit_length(F.shiftright(h, k.bit_length() - 1))
    if spec.kind == "hll":
        return slot, (zeros + 1).cast("long")
    return slot, F.call_function("shiftleft", F.lit(1).cast("long"), F.least(zeros, F.lit(spec.bitmap_len - 1)).cast("int"))


def slot_merge(spec: SketchSpec):
    """The aggregate that merges values of one slot; None for sketches that keep hashes."""
    if own := CUSTOM.get(spec.kind):
        return own.merge
    return {"hll": F.max, "linear": F.max, "fm": F.bit_or}.get(spec.kind)


def _candidates(h: DataFrame, m: int, by: tuple) -> DataFrame:
    """Rows that can be among the ``m`` least distinct hashes, so that few of all hashes are shuffled.

    Hashes fall into 4 m bins by their low bits.  Minima of bins are distinct hashes, so the m-th least minimum is no
    less than the m-th least hash; where fewer bins have a hash there is no cut.
    """
    least = h.groupBy(*by, (F.col("h") % F.lit(4 * m)).alias("bin")).agg(F.min("h").alias("least"))
    if by:
        rank = F.row_number().over(Window.partitionBy(*by).orderBy("least"))
        cut = least.withColumn("rank", rank).where(F.col("rank") == m).select(*by, F.col("least").alias("cut"))
        return _with(h, cut, by, "left").where("cut is null or h <= cut").select(*by, "h")
    cut = least.orderBy("least").limit(m).agg(F.when(F.count(F.lit(1)) == m, F.max("least")).alias("cut"))
    return h.crossJoin(F.broadcast(cut)).where("cut is null or h <= cut").select("h")


def state_of_hashes(h: DataFrame, spec: SketchSpec, by: tuple = ()) -> DataFrame:
    if merge := slot_merge(spec):
        slot, val = _slot_val(spec)
        return h.select(*by, slot.alias("slot"), val.alias("val")).groupBy(*by, "slot").agg(merge("val").alias("val"))
    kept = _candidates(h.select(*by, "h"), spec.k + (spec.kind == "adaptive"), by).distinct()
    if spec.kind == "bottomk":
        order = Window.partitionBy(*by).orderBy("h")
        if by:
            ranked = kept.withColumn("slot", F.row_number().over(order))
            return ranked.where(F.col("slot") <= spec.k).select(*by, "slot", F.col("h").alias("val"))
        top = kept.orderBy("h").limit(spec.k)  # a top-k per task, then k rows
        return top.select(F.row_number().over(Window.orderBy("h")).alias("slot"), F.col("h").alias("val"))
    # adaptive: the least level at which at most k hashes stay, from a histogram of leading zeros
    zeros = kept.withColumn("z", F.lit(BITS) - bit_length(F.col("h")))
    counts = zeros.groupBy(*by, "z").agg(F.count(F.lit(1)).alias("c"))
    above = F.sum("c").over(Window.partitionBy(*by).orderBy(F.desc("z")))
    level = counts.withColumn("left", above).groupBy(*by).agg(F.coalesce(F.max(F.when(F.col("left") > spec.k, F.col("z") + 1)), F.lit(0)).cast("int").alias("slot"))
    joined = _with(zeros, level, by) if by else zeros.crossJoin(F.broadcast(level))
    return joined.where("z >= slot").select(*by, "slot", F.col("h").alias("val"))


def build_state(df: DataFrame, item: list[str], spec: SketchSpec, key: SketchKey, by: tuple = (), keep_below: int | None = None, own: bool = False) -> DataFrame:
    """A sketch with a rate thins by itself; a release that thins further does so with the same hash."""
    if spec.rate < 1:
        keep_below = min(keep_below or SPACE, math.ceil(spec.rate * SPACE))
    return state_of_hashes(hashed(df, item, key, by, keep_below, own=own), spec, by)


def merge_states(states: list[DataFrame], spec: SketchSpec, by: tuple = ()) -> DataFrame:
    """Associative, commutative and idempotent; all states must come from one key."""
    out = states[0]
    for s in states[1:]:
        out = out.unionByName(s)
    if merge := slot_merge(spec):
        return out.groupBy(*by, "slot").agg(merge("val").alias("val"))
    if spec.kind == "bottomk":
        return state_of_hashes(out.select(*by, F.col("val").alias("h")), spec, by)
    level = out.groupBy(*by).agg(F.max("slot").alias("least"))
    both = _with(out, level, by) if by else out.crossJoin(F.broadcast(level))
    deep = both.where(F.lit(BITS) - bit_length(F.col("val")) >= F.col("least")).select(*by, F.col("val").alias("h"))
    again = _with(state_of_hashes(deep, spec, by), level, by) if by else state_of_hashes(deep, spec, by).crossJoin(F.broadcast(level))
    return again.select(*by, F.greatest("slot", "least").alias("slot"), "val")


def _likeliest(levels: list[tuple[float, Column, Column]], k: int) -> tuple[Column, Column]:
    """The cardinality under which what slots show is likeliest, for independent slots with k places each.

    Each level has its chance a, how often it was seen to be reached (up) and how often seen not to be, in
    units of a (down).  With rate x of items per slot the slope of the log-likelihood is the sum of
    a (up / (e^(a x) - 1) - down), which falls in x; its root is bisected in log2 x.
    """
    rows = F.array(*[F.struct(F.lit(a).alias("a"), up.cast("double").alias("up"), down.cast("double").alias("down")) for a, up, down in levels])

    def slope(log_x: Column) -> Column:
        x = F.pow(F.lit(2.0), log_x)
        return F.aggregate("_levels", F.lit(0.0), lambda s, r: s + r.a * (r.up / F.expm1(F.least(x * r.a, F.lit(700.0))) - r.down))

    def halve(s: Column, _: Column) -> Column:
        mid = (s.lo + s.hi) / 2
        rising = slope(mid) > 0
        return F.struct(F.when(rising, mid).otherwise(s.lo).alias("lo"), F.when(rising, s.hi).otherwise(mid).alias("hi"))

    root = F.aggregate(F.sequence(F.lit(1), F.lit(64)), F.struct(F.lit(-64.0).alias("lo"), F.lit(64.0).alias("hi")), halve, lambda s: F.pow(F.lit(2.0), (s.lo + s.hi) / 2))
    seen = F.exists("_levels", lambda r: r.up > 0)
    return rows, F.when(seen, F.lit(float(k)) * root).otherwise(F.lit(0.0))


def _levels(spec: SketchSpec) -> list[tuple[float, Column, Column]]:
    k, n, zero = spec.k, F.count("slot"), F.lit(0)
    if spec.kind == "hll":
        out = [(1.0, zero, F.lit(k) - n)]
        for v in range(1, BITS - k.bit_length() + 3):
            c = F.count(F.when(F.col("val") == v, True))
            out.append((2.0 ** -min(v, BITS - k.bit_length() + 1), c, c))
        return out
    last = spec.bitmap_len - 1
    seen = [F.count(F.when(F.col("val").bitwiseAND(F.lit(1 << i).cast("long")) != 0, True)) for i in range(spec.bitmap_len)]
    return [(2.0 ** -min(i + 1, last), c, F.lit(k) - c) for i, c in enumerate(seen)]


def estimate_state(state: DataFrame, spec: SketchSpec, by: tuple = (), estimator: str = "classic") -> DataFrame:
    """(by.., base_estimate, pi, saturated); base_estimate is null where the sketch is saturated.

    ``mle``: the likeliest cardinality, for fm and hll; less error for fm, and no bump of bias at small counts for hll.
    """
    k, n = spec.k, F.count("slot")
    g = state.groupBy(*by)
    if estimator not in ("classic", "mle") or estimator == "mle" and spec.kind not in ("hll", "fm"):
        raise ValueError(f"no estimator {estimator} for {spec.kind}")
    if own := CUSTOM.get(spec.kind):
        est, pi = own.estimate(k), own.pi(k)
    elif spec.kind == "linear":
        free = 1 - n / F.lit(float(k))
        pi = free * F.lit(spec.rate)
        est = F.when(free > 0, -F.lit(float(k) / spec.rate) * F.ln(free))
    elif spec.kind == "hll":
        total = F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("val"))), F.lit(0.0)) + (F.lit(k) - n)
        pi = total / k
        raw = F.lit(hll_alpha(k) * k * k) / total
        est = F.when((raw <= 2.5 * k) & (n < k), F.lit(float(k)) * F.ln(F.lit(float(k)) / (F.lit(k) - n))).otherwise(raw)
    elif spec.kind == "fm":
        ones = F.expr("bit_count(val ^ (val + 1L)) - 1")
        last = spec.bitmap_len - 1
        missing = sum((F.when(F.col("val").bitwiseAND(F.lit(1 << i).cast("long")) == 0, F.lit(2.0 ** -min(i + 1, last))).otherwise(F.lit(0.0)) for i in range(spec.bitmap_len)), F.lit(0.0))
        pi = (F.coalesce(F.sum(missing), F.lit(0.0)) + (F.lit(k) - n)) / F.lit(float(k))
        est = F.lit(k / 0.77351) * F.pow(F.lit(2.0), F.coalesce(F.sum(ones), F.lit(0)) / F.lit(float(k)))
    elif spec.kind == "bottomk":
        kth = F.max("val") / F.lit(float(SPACE))
        pi = F.when(n < k, F.lit(1.0)).otherwise(kth)
        est = F.when(n < k, n.cast("double")).otherwise(F.lit(k - 1.0) / kth)
    else:
        pi = F.pow(F.lit(2.0), -F.coalesce(F.max("slot"), F.lit(0)))
        est = n / pi
    if estimator == "mle":
        rows, likeliest = _likeliest(_levels(spec), k)
        out = g.agg(pi.alias("pi"), rows.alias("_levels")).select(*by, likeliest.alias("base_estimate"), "pi")
        return out.withColumn("saturated", F.lit(False))
    return g.agg(est.alias("base_estimate"), pi.alias("pi")).withColumn("saturated", F.col("base_estimate").isNull())


def is_violating(eps: float) -> Column:
    """Whether a fresh item would alter the state too often: the bound itself counts."""
    from ..functions.privacy import pi0

    return F.col("pi") >= F.lit(pi0(eps))


def pack_state(state: DataFrame, spec: SketchSpec, key: SketchKey, by: tuple = ()) -> DataFrame:
    packed = F.array_sort(F.collect_list(F.struct("slot", "val"))).alias("slots")
    return state.groupBy(*by).agg(packed).select(*by, F.lit(spec.kind).alias("kind"), F.lit(spec.k).alias("k"), F.lit(key.key_id).alias("key_id"), "slots")


def unpack_state(packed: DataFrame, spec: SketchSpec, key: SketchKey, by: tuple = ()) -> DataFrame:
    """Long form; fails at run time on states of another sketch or key."""
    same = (F.col("kind") == spec.kind) & (F.col("k") == spec.k) & (F.col("key_id") == key.key_id)
    checked = F.when(same, F.col("slots")).otherwise(F.raise_error(F.lit("states of different sketches or keys do not merge")))
    return packed.select(*by, F.explode(checked).alias("x")).select(*by, "x.slot", "x.val")


def size_bits(state: DataFrame, k: int, by: tuple = ()) -> DataFrame:
    """Measured size: k log2 of the largest slot value, and whole bits for values 0..max."""
    top = F.max("val")
    return state.groupBy(*by).agg((F.lit(k) * F.log2(top)).alias("paper_bits"), (F.lit(k) * F.ceil(F.log2(top + 1))).cast("long").alias("storage_bits"))


def influential_items(df: DataFrame, item: list[str], spec: SketchSpec, key: SketchKey) -> DataFrame:
    """Number of items whose removal alone alters the state: for a diagnosis, not for release."""
    h = hashed(df, item, key).distinct()
    if spec.kind in CUSTOM:
        raise ValueError("influential items are counted for the sketches of the library only")
    if spec.kind in ("bottomk", "adaptive"):
        return build_state(df, item, spec, key).agg(F.count(F.lit(1)).alias("influential"))
    slot, val = _slot_val(spec)
    each = h.select(slot.alias("slot"), val.alias("val"))
    if spec.kind == "fm":
        alone = each.groupBy("slot", "val").agg(F.count(F.lit(1)).alias("n")).where("n = 1")
    else:
        at = Window.partitionBy("slot").orderBy(F.desc("val"))
        alone = each.groupBy("slot", "val").agg(F.count(F.lit(1)).alias("n")).withColumn("r", F.row_number().over(at)).where("r = 1 and n = 1")
    return alone.agg(F.count(F.lit(1)).alias("influential"))



def _least_fraction(k: int) -> Column:
    """Sum over slots of the least hash, as a fraction; an empty slot counts as one."""
    return F.coalesce(F.sum(F.col("val") / F.lit(float(SPACE >> (k.bit_length() - 1)))), F.lit(0.0)) + (F.lit(k) - F.count("slot"))


#: The least hash of each of k bins (k a power of two), as a registered sketch: one narrow aggregate, no distinct step.
register_sketch(
    "binmin",
    CustomSketch(
        slot=lambda h, k: h % k,
        val=lambda h, k: F.shiftright(h, k.bit_length() - 1),
        merge=F.min,
        estimate=lambda k: F.when(F.count("slot") == 0, F.lit(0.0)).otherwise(F.lit(float(k * (k - 1))) / _least_fraction(k)),
        pi=lambda k: _least_fraction(k) / F.lit(float(k)),
        bits=lambda k: 64 * k,
        k_max=lambda k: k,
        rel_std_error=lambda k: (k - 2) ** -0.5,
    ),
)
