"""Sketch states per event-time window, k small rows of state a window whatever the traffic, and their private release."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import SketchKey
from ..functions.privacy import Budget, SketchSpec, min_cardinality, pi0, threshold
from ..operators.release import KeyLedger, _certified, _of_groups
from ..operators.sketches import _slot_val, estimate_state, hashed, phantoms_of_groups, slot_merge


def stream_states(events: DataFrame, ts: str, item: list[str], spec: SketchSpec, key: SketchKey, window: str = "1 day", slide: str | None = None, watermark: str = "1 day", own: bool = True, keep_below: int | None = None) -> DataFrame:
    """(window_start, slot, val); the same plan over a stream (append mode) and over a table.

    ``own``: each window has a hash function of its own, so that windows can be released one by one; without it
    states of windows merge but at most one function of them may be released.  ``keep_below``: items thinned by the
    second hash, as ``release_windows`` needs them.

    Replays and duplicates are harmless, rows later than the watermark are dropped by the engine.
    """
    merge = slot_merge(spec)
    if merge is None:
        raise ValueError("only slot sketches aggregate over a stream")
    rows = events.withColumn("_ts", F.col(ts).cast("timestamp"))
    if rows.isStreaming:
        rows = rows.withWatermark("_ts", watermark)
    slot, val = _slot_val(spec)
    rows = rows.withColumn("_window", F.window("_ts", window, slide)).withColumn("_start", F.col("_window.start"))
    if own:
        h = hashed(rows.withColumn("_kept", F.col("_window")), item, key, ("_start",), keep_below, "r", True, ("_kept",))
    else:
        h = hashed(rows, item, key, ("_window",), keep_below).withColumnRenamed("_window", "_kept")
    out = h.select("_kept", slot.alias("slot"), val.alias("val")).groupBy("_kept", "slot").agg(merge("val").alias("val"))
    return out.select(F.col("_kept.start").alias("window_start"), "slot", "val")


def release_windows(states: DataFrame, windows: DataFrame, spec: SketchSpec, budget: Budget, key: SketchKey, estimator: str = "classic", ledger: KeyLedger | None = None) -> DataFrame:
    """Thinned states of a stream plus phantoms, one pure-eps release for each row of the public list ``windows``.

    ``states`` come from ``stream_states`` with the same spec and key, ``own`` and ``keep_below=threshold(budget.eps)``;
    ``windows`` has a window_start.  A listed window without items still gets a row, other windows are dropped.
    Eps is that of one window: an item in several of them spends it in each.  Phantoms are hashed here, once a window,
    so the stream keeps no more state than without them.
    """
    if spec.rate < 1:
        raise ValueError("a sketch that thins by itself is released plain")
    if ledger is not None:
        ledger.claim(key, f"windows/{spec}/{budget.eps:g}/{windows.semanticHash()}", budget.total_eps)
    by, merge = ("window_start",), slot_merge(spec)
    v = math.ceil(min_cardinality(spec.k_max, budget.eps))
    listed = windows.select(*by).distinct()
    slot, val = _slot_val(spec)
    added = phantoms_of_groups(listed, v, key, by, threshold(budget.eps)).select(*by, slot.alias("slot"), val.alias("val"))
    both = _of_groups(states.select(*by, "slot", "val"), listed, by).unionByName(added)
    merged = both.groupBy(*by, "slot").agg(merge("val").alias("val"))
    return _certified(estimate_state(merged, spec, by, estimator), spec, budget, by, pi0(budget.eps), v, 0.0)
