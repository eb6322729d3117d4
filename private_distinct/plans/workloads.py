"""Named workloads over the given tables, each beside its SQL.

Both use the portable hash with a fixed public key, so that another engine can recompute every register.  A real
release derives a secret key of its own for each output.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import privacy as pv
from ..functions import sqlapi
from ..functions.hashing import BITS, SPACE, SketchKey, local_slices
from ..operators import audit
from ..operators import baselines as bl
from ..operators import release as rl
from ..operators import sketches as sk
from ..sources.tables import table
from ..streaming.windows import release_windows, stream_states
from . import experiments as ex

EPS = math.log(2)
RAW = "('r:' || {})"  # text of an item, as hashed
SPECS = {k: pv.SketchSpec(k, 64 if k == "fm" else 128) for k in ("fm", "linear", "bottomk", "adaptive", "hll")}
TINY = {"linear": (3, 0), "bottomk": (2, 6), "hll": (2, 3), "fm": (1, 3)}  # kind -> k, levels
KS = [1 << i for i in range(7, 13)]  # of both experiments
GRID = [(kind, k, eps) for kind in SPECS for k in (128, 1024, 4096) for eps in (0.1, 0.5, EPS, 1.0, 2.0)]


def public_key(output: str) -> SketchKey:
    return SketchKey(f"public-{output}", "portable")


def budget(floor: int | None = None) -> pv.Budget:
    return pv.Budget(EPS, n_floor=floor)


def _rounded(df: DataFrame) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


# SQL text -------------------------------------------------------------------------------------------


def _hashes(key: SketchKey, source: str, text: str, by: str = "", below: int | None = None) -> str:
    digest = f"md5('{key.secret}:' || {text})"
    part = lambda i: f"cast('0x' || substr({digest}, {i}, 15) as bigint)"
    keep = f" and {part(16)} < {below}" if below is not None else ""
    return f"select {by}{part(1)} as h from {source} where {text} is not null{keep}"


def _tagged(by: str, text: str) -> str:
    """Text of an item of a group that has a hash function of its own."""
    parts = [f"coalesce(length({c}::varchar) || '.' || {c}::varchar || '/', '-/')" for c in by.rstrip(", ").split(", ")]
    return f"({' || '.join(parts)} || {text})"


def _state(spec: pv.SketchSpec, hashes: str, by: str = "") -> str:
    k, b = spec.k, spec.k.bit_length() - 1
    zeros = f"({BITS - b} - case when h >> {b} = 0 then 0 else length(bin(h >> {b})) end)"
    group = f"group by {by}slot" if by else "group by slot"
    part = f"partition by {by.rstrip(', ')} " if by else ""
    if spec.kind == "hll":
        return f"select {by}slot, max(val) as val from (select {by}cast(h % {k} as int) as slot, cast({zeros} + 1 as bigint) as val from ({hashes})) {group}"
    if spec.kind == "binmin":
        return f"select {by}slot, min(val) as val from (select {by}cast(h % {k} as int) as slot, h >> {b} as val from ({hashes})) {group}"
    if spec.kind == "linear":
        return f"select {by}slot, max(val) as val from (select {by}cast(h % {k} as int) as slot, cast(1 as bigint) as val from ({hashes})) {group}"
    if spec.kind == "fm":
        return f"select {by}slot, bit_or(val) as val from (select {by}cast(h % {k} as int) as slot, cast(1 as bigint) << least({zeros}, {spec.bitmap_len - 1}) as val from ({hashes})) {group}"
    if spec.kind == "bottomk":
        return f"select {by}cast(slot as int) as slot, h as val from (select {by}h, row_number() over ({part}order by h) as slot from (select distinct {by}h from ({hashes}))) where slot <= {k}"
    z = f"({BITS} - case when h = 0 then 0 else length(bin(h)) end)"
    return f"select slot, h as val from (select cast(coalesce(max(case when c > {k} then z + 1 end), 0) as int) as slot from (select z, count(*) as n, sum(count(*)) over (order by z desc) as c from (select distinct h, {z} as z from ({hashes})) group by z)), (select distinct h, {z} as z from ({hashes})) where z >= slot"


def _estimate(spec: pv.SketchSpec, state: str, by: str = "") -> str:
    k, group = spec.k, f" group by {by.rstrip(', ')}" if by else ""
    if spec.kind == "linear":
        est, pi = f"case when count(slot) < {k} then -{float(k)} * ln(1 - count(slot) / {float(k)}) end", f"1 - count(slot) / {float(k)}"
    elif spec.kind == "hll":
        total = f"(coalesce(sum(pow(2.0::double, -val)), 0) + {k} - count(slot))"
        raw = f"({sk.hll_alpha(k) * k * k!r}::double / {total})"
        est, pi = f"case when {raw} <= {2.5 * k} and count(slot) < {k} then {float(k)}::double * ln({float(k)}::double / ({k} - count(slot))) else {raw} end", f"{total} / {float(k)}::double"
    elif spec.kind == "fm":
        last = spec.bitmap_len - 1
        missing = " + ".join(f"case when val & {1 << i} = 0 then {2.0 ** -min(i + 1, last)!r}::double else 0 end" for i in range(spec.bitmap_len))
        est, pi = f"{k / 0.77351!r}::double * pow(2.0::double, coalesce(sum(bit_count(xor(val, val + 1)) - 1), 0) / {float(k)}::double)", f"(coalesce(sum({missing}), 0) + {k} - count(slot)) / {float(k)}::double"
    elif spec.kind == "binmin":
        total = f"(coalesce(sum(val / {float(SPACE >> (k.bit_length() - 1))!r}::double), 0) + {k} - count(slot))"
        est, pi = f"case when count(slot) = 0 then 0 else {float(k * (k - 1))!r}::double / {total} end", f"{total} / {float(k)}::double"
    elif spec.kind == "bottomk":
        kth = f"(max(val) / {float(SPACE)!r}::double)"
        est, pi = f"case when count(slot) < {k} then count(slot)::double else {k - 1.0} / {kth} end", f"case when count(slot) < {k} then 1.0 else {kth} end"
    else:
        pi = "pow(2.0::double, -coalesce(max(slot), 0))"
        est = f"count(slot) / {pi}"
    return f"select {by}cast({est} as double) as base_estimate, cast({pi} as double) as pi from ({state}){group}"


def _release(spec, hashes: str, p: float, v: int, d: float | None, by: str = "") -> str:
    c = f"round({p!r}::double, 6) as p, cast({v} as bigint) as phantoms, round(base_estimate / {p!r}::double - {v}, 6) as estimate, round({EPS!r}::double, 6) as eps, {'cast(null as double)' if d is None else f'round({d!r}::double, 6)'} as delta, cast({spec.k_max} as bigint) as k_max, round({pv.min_cardinality(spec.k_max, EPS)!r}::double, 6) as n0"
    return f"select {by}round(base_estimate, 6) as base_estimate, {c} from ({_estimate(spec, _state(spec, hashes, by), by)})"


def _phantom_hashes(key: SketchKey, v: int, below: int | None = None, by: str = "", groups: str = "") -> str:
    source = f"(select {by}g.i as id from {groups + ', ' if groups else ''}(select unnest(range({v})) as i) g)"
    return _hashes(key, source, _tagged(by, "'p:' || id") if by else "('p:' || id)", by, below)


def _local_stop(spec: pv.SketchSpec, key: SketchKey) -> int:
    """The stopping count, item by item in plain Python: what the SQL side states as a constant."""
    n0, bound = math.ceil(pv.min_cardinality(spec.k_max, EPS)), pv.pi0(EPS)
    slots: dict[int, float] = {}
    hashes: list[int] = []
    b, v = spec.k.bit_length() - 1, 0
    while True:
        h = local_slices(f"p:{v}", key)[0]
        v += 1
        zeros = BITS - b - (h >> b).bit_length()
        if spec.kind == "hll":
            slots[h % spec.k] = min(slots.get(h % spec.k, 1.0), 2.0 ** -(zeros + 1))
        elif spec.kind == "linear":
            slots[h % spec.k] = 0.0
        elif spec.kind == "fm":
            level = min(zeros, spec.bitmap_len - 1)
            slots[h % spec.k, level] = 2.0 ** -min(level + 1, spec.bitmap_len - 1)
        else:
            hashes.append(h)
        if v >= n0:
            if spec.kind in ("hll", "linear"):
                pi = (sum(slots.values()) + spec.k - len(slots)) / spec.k
            elif spec.kind == "fm":
                pi = 1 - sum(slots.values()) / spec.k
            elif spec.kind == "bottomk":
                pi = sorted(set(hashes))[spec.k - 1] / SPACE
            else:
                level = 0
                while sum(h >> (BITS - level) == 0 for h in set(hashes)) > spec.k:
                    level += 1
                pi = 2.0**-level
            if pi < bound:
                return v


# the registry ---------------------------------------------------------------------------------------

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def _add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    _QUERIES[name] = query
    if sql:
        _SQL[name] = sql


def _sketches() -> None:
    t, item, text = "lineitem", ["l_orderkey"], "('r:' || l_orderkey)"
    bound, thin = pv.pi0(EPS), pv.threshold(EPS)
    for kind, spec in SPECS.items():
        key = public_key(kind)
        v = math.ceil(pv.min_cardinality(spec.k_max, EPS))
        small = pv.SketchSpec("fm", 16) if kind == "fm" else spec  # a floor that the smallest table meets
        floor = 1400
        plain, kept = _hashes(key, t, text), _hashes(key, t, text, below=thin)
        _add(f"state_{kind}", lambda s, d, spec=spec, key=key: sk.build_state(table(s, d, t), item, spec, key).select("slot", "val"), _state(spec, plain))
        _add(f"plain_{kind}", lambda s, d, spec=small, key=key: _rounded(rl.release_plain(table(s, d, t), item, spec, pv.Budget(EPS, 1.0, floor), key)), _release(small, plain, 1.0, 0, pv.delta(small, floor, EPS)))
        _add(f"large_{kind}", lambda s, d, spec=small, key=key: _rounded(rl.release_large(table(s, d, t), item, spec, budget(floor), key)), _release(small, kept, bound, 0, 0.0))
        _add(f"any_{kind}", lambda s, d, spec=spec, key=key: _rounded(rl.release_any(table(s, d, t), item, spec, budget(), key)), _release(spec, f"{kept} union all {_phantom_hashes(key, v, thin)}", bound, v, 0.0))
        stop = _local_stop(spec, key)
        _add(f"convert_{kind}", lambda s, d, spec=spec, key=key: _rounded(rl.privatise_existing(sk.build_state(table(s, d, t), item, spec, key), spec, budget(), key)), _release(spec, f"{plain} union all {_phantom_hashes(key, stop)}", 1.0, stop, 0.0))
        _add(f"pi_and_violation_{kind}", lambda s, d, spec=spec, key=key: _rounded(sk.estimate_state(sk.build_state(table(s, d, t), item, spec, key), spec).select("pi", sk.is_violating(EPS).alias("violating"))), f"select round(pi, 6) as pi, pi >= {bound!r} as violating from ({_estimate(spec, _state(spec, plain))})")

        def parts(s, d, spec=spec, key=key):
            df = table(s, d, t)
            cut = [df.where(f"l_returnflag = '{f}'") for f in "ANR"]
            return sk.merge_states([sk.build_state(x, item, spec, key) for x in cut], spec).select("slot", "val")

        _add(f"merge_split_union_{kind}", parts, _state(spec, plain))

        def thrice(s, d, spec=spec, key=key):
            df = table(s, d, t)
            twice = df.union(df).repartition(7).union(df.orderBy(F.desc("l_orderkey")))
            return sk.build_state(twice, item, spec, key).select("slot", "val")

        _add(f"dup_invariance_{kind}", thrice, _state(spec, plain))
    key = public_key("hll")
    small = pv.SketchSpec("linear", 128)
    _add("influential_items", lambda s, d: sk.influential_items(table(s, d, "events"), ["user_id"], small, key), f"select count(*) as influential from (select h % 128 as slot from (select distinct h from ({_hashes(key, 'events', chr(40) + chr(39) + 'r:' + chr(39) + ' || user_id)')})) group by 1 having count(*) = 1)")


def _grouped() -> None:
    spec, thin, bound = SPECS["hll"], pv.threshold(EPS), pv.pi0(EPS)
    v = math.ceil(pv.min_cardinality(spec.k_max, EPS))
    for name, t, item, by in (("grouped_event_type", "events", "user_id", "event_type"), ("grouped_priority", "orders", "o_custkey", "o_orderpriority")):
        key = public_key(name)
        hashes = f"{_hashes(key, t, _tagged(by, RAW.format(item)), f'{by}, ', thin)} union all {_phantom_hashes(key, v, thin, f'{by}, ', f'(select distinct {by} from {t})')}"
        _add(name, lambda s, d, t=t, item=item, by=by, key=key: _rounded(rl.release_any(table(s, d, t), [item], spec, budget(), key, (by,))), _release(spec, hashes, bound, v, 0.0, f"{by}, "))
    star_key = public_key("segment")
    star = "(select r_name, c_mktsegment, o_custkey from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)"

    def segments(s, d):
        c, n, r = (table(s, d, x) for x in ("customer", "nation", "region"))
        rows = table(s, d, "orders").join(c, F.col("o_custkey") == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
        return _rounded(rl.release_any(rows, ["o_custkey"], spec, budget(), star_key, ("r_name", "c_mktsegment")))

    by = "r_name, c_mktsegment, "
    hashes = f"{_hashes(star_key, star, _tagged(by, RAW.format('o_custkey')), by, thin)} union all {_phantom_hashes(star_key, v, thin, by, f'(select distinct r_name, c_mktsegment from {star})')}"
    _add("region_segment_customers", segments, _release(spec, hashes, bound, v, 0.0, by))
    word_key = public_key("words")
    _add("words_per_lang", lambda s, d: _rounded(sk.estimate_state(sk.build_state(table(s, d, "documents").select("lang", F.explode(F.split(F.lower("text"), " ")).alias("w")), ["w"], spec, word_key, ("lang",)), spec, ("lang",)).drop("saturated")), f"select lang, round(base_estimate, 6) as base_estimate, round(pi, 6) as pi from ({_estimate(spec, _state(spec, _hashes(word_key, '(select lang, unnest(string_split(lower(text), chr(32))) as w from documents)', chr(40) + chr(39) + 'r:' + chr(39) + ' || w)', 'lang, '), 'lang, '), 'lang, ')})")
    roll_key = public_key("rollup")

    def rollup(s, d):
        fine = sk.build_state(table(s, d, "lineitem"), ["l_orderkey"], spec, roll_key, ("l_returnflag", "l_linestatus"))
        up = sk.merge_states([fine.drop("l_linestatus")], spec, ("l_returnflag",))
        return _rounded(sk.estimate_state(up, spec, ("l_returnflag",)).drop("saturated"))

    _add("rollup_internal", rollup, f"select l_returnflag, round(base_estimate, 6) as base_estimate, round(pi, 6) as pi from ({_estimate(spec, _state(spec, _hashes(roll_key, 'lineitem', chr(40) + chr(39) + 'r:' + chr(39) + ' || l_orderkey)', 'l_returnflag, '), 'l_returnflag, '), 'l_returnflag, ')})")
    key = public_key("stream")
    _add("stream_windows_batch", lambda s, d: stream_states(table(s, d, "events"), "ts", ["user_id"], spec, key).select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "slot", "val"), _state(spec, _hashes(key, "(select date_trunc('day', ts)::timestamp as window_start, user_id from events)", _tagged("window_start", RAW.format("user_id")), "window_start, "), "window_start, "))


def _more_tables() -> None:
    """States stored by group and privatised later; overlaps; list-valued items."""
    spec, thin, bound = SPECS["hll"], pv.threshold(EPS), pv.pi0(EPS)
    v = math.ceil(pv.min_cardinality(spec.k_max, EPS))
    key = public_key("stored")
    stop = _local_stop(spec, key)

    def stored(s, d):
        fine = sk.build_state(table(s, d, "lineitem"), ["l_orderkey"], spec, key, ("l_returnflag",))
        back = sk.unpack_state(sk.pack_state(fine, spec, key, ("l_returnflag",)), spec, key, ("l_returnflag",))
        return _rounded(rl.privatise_existing(sk.merge_states([back.drop("l_returnflag")], spec), spec, budget(), key))

    _add("stored_states_converted", stored, _release(spec, f"{_hashes(key, 'lineitem', RAW.format('l_orderkey'))} union all {_phantom_hashes(key, stop)}", 1.0, stop, 0.0))
    label_key = public_key("labelled")
    for name, how, word in (("documents_labelled", "left_semi", "in"), ("documents_unlabelled", "left_anti", "not in")):
        source = f"(select doc_id from documents where doc_id {word} (select doc_id from labels where doc_id is not null))"
        one = label_key.derive(name)
        hashes = f"{_hashes(one, source, RAW.format('doc_id'), below=thin)} union all {_phantom_hashes(one, v, thin)}"
        _add(name, lambda s, d, how=how, one=one: _rounded(rl.release_any(table(s, d, "documents").join(table(s, d, "labels"), "doc_id", how), ["doc_id"], spec, budget(), one)), _release(spec, hashes, bound, v, 0.0))
    both_key = public_key("overlap")

    def overlap(s, d):
        a, b = (sk.build_state(table(s, d, t), ["text"], spec, both_key) for t in ("documents", "benchmark"))
        one = [sk.estimate_state(x, spec).select(F.col("base_estimate").alias(n)) for x, n in ((a, "a"), (b, "b"), (sk.merge_states([a, b], spec), "both"))]
        rows = one[0].crossJoin(one[1]).crossJoin(one[2])
        return _rounded(rows.select("a", "b", "both", (F.col("a") + F.col("b") - F.col("both")).alias("overlap")))

    ha, hb = (_hashes(both_key, t, RAW.format("text")) for t in ("documents", "benchmark"))
    part = lambda h, n: f"(select base_estimate as {n} from ({_estimate(spec, _state(spec, h))}))"
    _add("text_overlap_diagnostic", overlap, f"select round(a, 6) as a, round(b, 6) as b, round(u, 6) as both, round(a + b - u, 6) as overlap from {part(ha, 'a')}, {part(hb, 'b')}, {part(f'{ha} union all {hb}', 'u')}")
    role_key = public_key("roles")
    hashes = f"{_hashes(role_key, 'conversations', _tagged('role', RAW.format('conv_id')), 'role, ', thin)} union all {_phantom_hashes(role_key, v, thin, 'role, ', '(select distinct role from conversations)')}"
    _add("conversations_per_role", lambda s, d: _rounded(rl.release_any(table(s, d, "conversations"), ["conv_id"], spec, budget(), role_key, ("role",))), _release(spec, hashes, bound, v, 0.0, "role, "))
    vector_key = public_key("vectors")

    def vectors(s, d):
        steps = F.transform("embedding", lambda x: F.floor(x.cast("double") * 100).cast("string"))
        rows = table(s, d, "embeddings").select("label", F.concat_ws(",", steps).alias("steps"))
        return _rounded(sk.estimate_state(sk.build_state(rows, ["steps"], spec, vector_key, ("label",)), spec, ("label",)).drop("saturated"))

    steps = "(select label, array_to_string(list_transform(embedding, lambda x: cast(floor(x::double * 100) as bigint)), ',') as steps from embeddings)"
    _add("rounded_vectors_per_label", vectors, f"select label, round(base_estimate, 6) as base_estimate, round(pi, 6) as pi from ({_estimate(spec, _state(spec, _hashes(vector_key, steps, RAW.format('steps'), 'label, '), 'label, '), 'label, ')})")


def _any_by(name: str, rows: Callable, source: str, item: str, by: tuple) -> None:
    """A grouped release of ``item`` beside its SQL over ``source``, which has the same columns."""
    spec, thin, bound, key = SPECS["hll"], pv.threshold(EPS), pv.pi0(EPS), public_key(name)
    v, cols = math.ceil(pv.min_cardinality(SPECS["hll"].k_max, EPS)), "".join(f"{c}, " for c in by)
    groups = f"(select distinct {cols.rstrip(', ')} from {source})"
    hashes = f"{_hashes(key, source, _tagged(cols, RAW.format(item)), cols, thin)} union all {_phantom_hashes(key, v, thin, cols, groups)}"
    _add(name, lambda s, d: _rounded(rl.release_any(rows(s, d), [item], spec, budget(), key, by)), _release(spec, hashes, bound, v, 0.0, cols))


def _wider() -> None:
    """Days, joins, cubes, hosts and copies of texts; likelihood estimators; registered sketches; Spark SQL."""
    spec = SPECS["hll"]
    day = lambda s, d: table(s, d, "events").select(F.to_date("ts").alias("day"), "user_id")
    _any_by("grouped_day", day, "(select ts::date as day, user_id from events)", "user_id", ("day",))
    _any_by("nation_suppliers", lambda s, d: table(s, d, "supplier").join(table(s, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")), "(select n_name, s_suppkey from supplier join nation on s_nationkey = n_nationkey)", "s_suppkey", ("n_name",))
    host = lambda s, d: table(s, d, "pages").select(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))

    def whole(name: str, rows: Callable, source: str, item: str) -> None:
        key = public_key(name)
        v, thin, bound = math.ceil(pv.min_cardinality(spec.k_max, EPS)), pv.threshold(EPS), pv.pi0(EPS)
        hashes = f"{_hashes(key, source, RAW.format(item), below=thin)} union all {_phantom_hashes(key, v, thin)}"
        _add(name, lambda s, d: _rounded(rl.release_any(rows(s, d), [item], spec, budget(), key)), _release(spec, hashes, bound, v, 0.0))

    whole("url_hosts", host, "(select regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host from pages)", "host")
    whole("text_copies", lambda s, d: table(s, d, "documents"), "documents", "text")

    cube_key = public_key("cube")
    cuts = [("l_returnflag", "l_linestatus"), ("l_returnflag",), ("l_linestatus",), ()]

    def cube(s, d):
        fine = sk.build_state(table(s, d, "lineitem"), ["l_orderkey"], spec, cube_key, cuts[0])
        name = lambda c, by: F.col(c) if c in by else F.lit(None).cast("string").alias(c)
        levels = [sk.estimate_state(sk.merge_states([fine.select(*by, "slot", "val")], spec, by), spec, by).select(name("l_returnflag", by), name("l_linestatus", by), "base_estimate", "pi") for by in cuts]
        return _rounded(reduce(DataFrame.unionByName, levels))

    def cell(by: tuple) -> str:
        cols = "".join(f"{c}, " for c in by)
        shown = ", ".join(c if c in by else f"cast(null as varchar) as {c}" for c in cuts[0])
        return f"select {shown}, round(base_estimate, 6) as base_estimate, round(pi, 6) as pi from ({_estimate(spec, _state(spec, _hashes(cube_key, 'lineitem', RAW.format('l_orderkey'), cols), cols), cols)})"

    _add("cube_internal", cube, " union all ".join(cell(by) for by in cuts))
    week_key = public_key("weeks")

    def weeks(s, d):
        fine = sk.build_state(table(s, d, "events").withColumn("week", F.date_trunc("week", "ts")), ["user_id"], spec, week_key, ("week",))
        return sk.merge_states([fine.drop("week")], spec).select("slot", "val")

    _add("merge_equals_whole", weeks, _state(spec, _hashes(week_key, "events", RAW.format("user_id"))))
    for kind in ("hll", "fm"):
        one, key = SPECS[kind], public_key(kind)
        state = _state(one, _hashes(key, "lineitem", RAW.format("l_orderkey")))
        _add(f"mle_{kind}", lambda s, d, one=one, key=key: _rounded(sk.estimate_state(sk.build_state(table(s, d, "lineitem"), ["l_orderkey"], one, key), one, (), "mle")), _mle(one, state))
    own, own_key = pv.SketchSpec("binmin", 128), public_key("binmin")
    v, thin = math.ceil(pv.min_cardinality(own.k_max, EPS)), pv.threshold(EPS)
    hashes = f"{_hashes(own_key, 'lineitem', RAW.format('l_orderkey'), below=thin)} union all {_phantom_hashes(own_key, v, thin)}"
    _add("any_registered", lambda s, d: _rounded(rl.release_any(table(s, d, "lineitem"), ["l_orderkey"], own, budget(), own_key)), _release(own, hashes, pv.pi0(EPS), v, 0.0))

    def by_sql(s, d):
        sqlapi.register(s)
        return _rounded(s.sql(sqlapi.sql_release_any("{lines}", "l_orderkey", public_key("hll").secret, 128, EPS), lines=table(s, d, "lineitem")))

    _add("sql_release", by_sql, f"select base_estimate, estimate from ({_SQL['any_hll']})")

    def curve(s, d):
        sqlapi.register(s)
        first = table(s, d, "orders").where("o_orderdate is not null and o_custkey is not null").groupBy("o_custkey").agg(F.min(F.to_date("o_orderdate")).alias("day"))
        daily = first.groupBy("day").agg(F.count(F.lit(1)).alias("new"))  # one row a day from here on
        so_far = daily.select("day", F.sum("new").over(Window.orderBy("day")).alias("n"))
        return _rounded(s.sql(f"select day, t.* from {{so_far}} as c, lateral private_delta_curve('hll', 128, {EPS!r}D, c.n, c.n, 1) as t", so_far=so_far))

    days = "(select day, cast(sum(count(*)) over (order by day) as bigint) as n from (select min(o_orderdate::date) as day from orders where o_orderdate is not null and o_custkey is not null group by o_custkey) group by day)"
    _add("delta_curve", curve, f"select day, n, round({pv.min_cardinality(128, EPS)!r}::double, 6) as n0, round(case when n <= {pv.min_cardinality(128, EPS)!r} then 1 else least(1, 128 * exp(-{pv.pi0(EPS)!r}::double * n / 128)) end, 6) as delta from {days}")


def _mle(spec: pv.SketchSpec, state: str) -> str:
    k, b = spec.k, spec.k.bit_length() - 1
    if spec.kind == "hll":
        levels = f"select 1.0::double as a, 0.0::double as up, ({k} - count(slot))::double as down from s union all select pow(2.0::double, -least(val, {BITS - b})), count(*)::double, count(*)::double from s group by val"
    else:
        last = spec.bitmap_len - 1
        levels = " union all ".join(f"select {2.0 ** -min(i + 1, last)!r}::double as a, c::double as up, ({k} - c)::double as down from (select count(*) as c from s where val & {1 << i} <> 0)" for i in range(spec.bitmap_len))
    slope = "list_sum(list_transform(l, lambda r: r.a * (r.up / (exp(least(pow(2.0::double, (lo + hi) / 2) * r.a, 700)) - 1) - r.down)))"
    return f"with recursive s as materialized ({state}), l as materialized (select list({{'a': a, 'up': up, 'down': down}} order by a) as l from ({levels}) where up > 0 or down > 0), b as (select 0 as i, -64.0::double as lo, 64.0::double as hi union all select i + 1, case when f > 0 then (lo + hi) / 2 else lo end, case when f > 0 then hi else (lo + hi) / 2 end from (select i, lo, hi, {slope} as f from b, l where i < 64)) select round({float(k)}::double * pow(2.0::double, (lo + hi) / 2), 6) as base_estimate, round(pi, 6) as pi, false as saturated from b, ({_estimate(spec, 'select * from s')}) where i = 64"


def _audits() -> None:
    """Every hash function of tiny sketches of each order's parts; thinned ones above the least cardinality stay within eps."""
    source, group, item = "lineitem", "l_orderkey", "l_partkey"

    def add(name: str, kind: str, k: int, levels: int, rate: float) -> None:
        _add(name, lambda s, d: _rounded(audit.bayes_factors_of_groups(table(s, d, source), group, item, kind, k, levels, rate)), audit.bayes_groups_sql(source, group, item, kind, k, levels, rate))

    for kind, (k, levels) in TINY.items():
        add(f"bayes_{kind}", kind, k, levels, 1.0)
    add("bayes_thinned", "linear", 2, 0, pv.pi0(0.4))


def _experiments() -> None:
    n, trials, key = 1 << 20, 10, SketchKey("experiment", "native")

    def errors(s, d):
        out = [ex.error_summary(ex.estimates(s, n, pv.SketchSpec("hll", k), trials, key, eps), n).select(F.lit(k).alias("k"), F.lit(name).alias("method"), "*") for k in KS for name, eps in (("plain", None), ("private", EPS))]
        return reduce(DataFrame.union, out)

    def space(s, d):
        return reduce(DataFrame.union, [ex.space_summary(s, n, k, trials, key, EPS).select(F.lit(k).alias("k"), "*") for k in KS])

    def violations(s, d):
        out = []
        for kind in ("hll", "linear", "bottomk"):
            spec = pv.SketchSpec(kind, 128)
            for m in (1.02, 1.25, 1.5):
                size = math.ceil(m * pv.min_cardinality(spec.k_max, EPS)) if kind != "linear" else math.ceil(m * 88)
                out.append(ex.violation_summary(s, size, spec, 200, key, EPS).select(F.lit(kind).alias("kind"), F.lit(size).alias("n"), "*"))
        return reduce(DataFrame.union, out)

    def moments(s, d):
        return ex.group_moments(table(s, d, "lineitem"), "l_suppkey", ("l_returnflag",), pv.SketchSpec("bottomk", 64), 200, key, EPS)

    _add("experiment_violation", violations)
    _add("experiment_bias_variance", moments)
    _add("experiment_error", errors)
    _add("experiment_space", space)


def _baselines() -> None:
    _add("baseline_exact", lambda s, d: bl.exact_distinct(table(s, d, "lineitem"), ["l_orderkey"]), "select count(distinct l_orderkey) as n_distinct from lineitem")
    _add("baseline_exact_by_type", lambda s, d: bl.exact_distinct(table(s, d, "events"), ["user_id"], ("event_type",)), "select event_type, count(distinct user_id) as n_distinct from events group by 1")
    _add("baseline_builtin", lambda s, d: bl.builtin_sketches(table(s, d, "lineitem"), "l_orderkey"))
    key, k = public_key("bucket"), 64
    base = math.log(1 + bl.default_gamma(k))
    text = "(j || '/r:' || user_id)"
    sql = f"select slot, max(val) as val from (select cast(j as int) as slot, cast(1 + floor(-ln((h + 1.0::double) / {float(SPACE)!r}::double) / {base!r}::double) as bigint) as val from ({_hashes(key, '(select distinct user_id from events), (select unnest(range(64)) as j)', text, 'j, ')})) group by slot"
    _add("baseline_per_bucket", lambda s, d: bl.per_bucket_state(table(s, d, "events").select("user_id").distinct(), ["user_id"], k, key), sql)
    _add("builtin_private", lambda s, d: rl.release_builtin(table(s, d, "lineitem"), ["l_orderkey"], budget(), public_key("own")))
    hll, text = SPECS["hll"], "('r:' || l_orderkey)"
    state = _state(hll, _hashes(public_key("hll"), "lineitem", text))
    _add("size_paper_bits", lambda s, d: _rounded(sk.size_bits(sk.build_state(table(s, d, "lineitem"), ["l_orderkey"], hll, public_key("hll")), hll.k)), f"select round({hll.k} * log2(max(val)::double), 6) as paper_bits, cast({hll.k} * ceil(log2(max(val) + 1.0::double)) as bigint) as storage_bits from ({state})")
    values = ", ".join(f"('{kind}', {k}, {e!r}::double, {pv.SketchSpec(kind, k).k_max})" for kind, k, e in GRID)

    def grid(s, d):
        rows = [(kind, k, float(e), pv.SketchSpec(kind, k).k_max, pv.pi0(e), pv.min_cardinality(pv.SketchSpec(kind, k).k_max, e), pv.prior_floor(pv.SketchSpec(kind, k).k_max, e), bl.laplace_scale(k, 1e6, e)) for kind, k, e in GRID]
        return _rounded(s.createDataFrame(rows, "kind string, k long, eps double, k_max long, pi0 double, n0 double, prior_floor double, laplace_sd double"))

    _add("params_grid", grid, f"select kind, cast(k as bigint) as k, round(eps, 6) as eps, cast(k_max as bigint) as k_max, round(1 - exp(-eps), 6) as pi0, round(k_max / (1 - exp(-eps)), 6) as n0, round(8 * (k_max / (1 - exp(-eps))), 6) as prior_floor, round(sqrt(2.0::double) * 1e6 / (k * eps), 6) as laplace_sd from (values {values}) as g(kind, k, eps, k_max)")

    grid_of_years = [(kind, eps) for kind in SPECS for eps in (0.5, EPS, 1.0)]
    _add("delta_grid", lambda s, d: _failure_chances(s, d, "year", grid_of_years).select("kind", "eps", F.col("period").alias("year"), "n", (F.col("n") / F.col("n0")).alias("n_over_n0"), "delta"))


def _failure_chances(s: SparkSession, d: str, period: str, grid: list[tuple[str, float]]) -> DataFrame:
    """(kind, eps, period, n, n0, delta): chances that an unmodified sketch of a period's customers violates the bound."""
    sqlapi.register(s)
    orders = table(s, d, "orders").where("o_orderdate is not null")
    counts = orders.groupBy(F.to_date(F.date_trunc(period, "o_orderdate")).alias("period")).agg(F.countDistinct("o_custkey").alias("n"))
    values = ", ".join(f"('{kind}', {float(eps)!r}D)" for kind, eps in grid)
    return s.sql(f"select g.kind, g.eps, c.period, t.* from {{counts}} as c cross join (values {values}) as g(kind, eps), lateral private_delta_curve(g.kind, 128, g.eps, c.n, c.n, 1) as t", counts=counts)


def _properties() -> None:
    """Size, error, influential items, floor and a bound on ln delta of every sketch; exact failure probabilities."""
    rows, values = [], []
    for kind, k, eps in GRID:
        spec = pv.SketchSpec(kind, k)
        n0 = pv.min_cardinality(spec.k_max, eps)
        for m in (2, 8, 32):
            rows.append((kind, k, float(eps), m, spec.size_bits, spec.k_max, n0, spec.rel_std_error(1.0), pv.ln_delta_bound(spec, math.ceil(m * n0), eps)))
            values.append(f"('{kind}', {k}, {float(eps)!r}::double, {m})")
    schema = "kind string, k long, eps double, n_over_n0 long, size_bits long, k_max long, n0 double, rel_std_error double, ln_delta_bound double"
    x, v, b0 = "(k / n)", "ceil(-log2(q))", "ceil(k * (1 - q))"
    mu0 = f"list_sum(list_transform(range({b0}::bigint), lambda i: k::double / (k - i)))"
    bound = f"""case kind when 'hll' then least(0, ln(k) - q * n / k) when 'fm' then least(0, ln(k * {v}) - pow(2.0::double, -{v}) * n / k)
      when 'linear' then case when n > {mu0} then least(0, ln({mu0} / n) - {b0} / k / {mu0} * n + {b0} / k) else 0 end
      else -n * ({x} * ln({x} / q) + (1 - {x}) * ln((1 - {x}) / (1 - q))) end"""
    sql = f"""select kind, k::bigint as k, round(eps, 6) as eps, m::bigint as n_over_n0, bits::bigint as size_bits, k_max::bigint as k_max, round(n0, 6) as n0,
      round(case kind when 'fm' then 0.649 when 'adaptive' then 1.2 when 'hll' then 1.04 else 1 end / sqrt(k), 6) as rel_std_error, round(({bound})::double, 6) as ln_delta_bound
      from (select *, ceil(m * n0)::double as n from (select *, k_max / q as n0 from (select kind, k, eps, m, 1 - exp(-eps) as q,
      case kind when 'fm' then 32 * k when 'linear' then k when 'hll' then 5 * k else 64 * k end as bits, case kind when 'fm' then 32 * k else k end as k_max from (values {', '.join(values)}) as g(kind, k, eps, m))))"""
    _add("property_table", lambda s, d: _rounded(s.createDataFrame(rows, schema)), sql)
    for kind in ("hll", "fm", "bottomk", "adaptive"):
        spec, steps = pv.SketchSpec(kind, 128), (0.1, 0.5, EPS, 1.0, 2.0)
        least = f"case when n <= {spec.k_max} / q then 1 else {{}} end"
        if kind == "hll":
            d = "least(1, 128 * exp(-q * n / 128))"
        elif kind == "fm":
            d = "least(1, 128 * ceil(-log2(q)) * exp(-pow(2.0::double, -ceil(-log2(q))) * n / 128))"
        else:
            d = "list_sum(list_transform(range(129), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln(q) + (n - i) * ln(1 - q))))"
        values = ", ".join(f"({float(e)!r}::double)" for e in steps)
        months = "(select date_trunc('month', o_orderdate)::date as month, count(distinct o_custkey)::double as n from orders where o_orderdate is not null group by 1)"
        sql = f"select month, round(eps, 6) as eps, n::bigint as n, round(({least.format(d)})::double, 6) as delta from (select month, eps, n, 1 - exp(-eps) as q from {months}, (values {values}) as g(eps))"
        _add(f"delta_grid_{kind}", lambda s, d, grid=[(kind, e) for e in steps]: _rounded(_failure_chances(s, d, "month", grid).select(F.col("period").alias("month"), "eps", "n", "delta")), sql)


def _thinned_linear() -> None:
    """Linear counting that thins by itself, below the bound: pure, and with a range beyond its slots."""
    spec, key = pv.SketchSpec("linear", 128, rate=0.25), public_key("thinned-linear")
    state = _state(pv.SketchSpec("linear", 128), _hashes(key, "lineitem", RAW.format("l_orderkey"), below=math.ceil(0.25 * SPACE)))
    est = f"select base_estimate / 0.25::double as base_estimate from ({_estimate(pv.SketchSpec('linear', 128), state)})"
    n0 = pv.min_cardinality(128, EPS)
    sql = f"select round(base_estimate, 6) as base_estimate, 1.0::double as p, 0::bigint as phantoms, round(base_estimate, 6) as estimate, round({EPS!r}::double, 6) as eps, 0.0::double as delta, 128::bigint as k_max, round({n0!r}::double, 6) as n0 from ({est})"
    _add("plain_linear_thinned", lambda s, d: _rounded(rl.release_plain(table(s, d, "lineitem"), ["l_orderkey"], spec, budget(1400), key)), sql)


def _public_groups() -> None:
    """Groups from a public list: one without items has its phantoms only, items of others are dropped."""
    spec, thin, bound, key = SPECS["hll"], pv.threshold(EPS), pv.pi0(EPS), public_key("listed")
    v = math.ceil(pv.min_cardinality(spec.k_max, EPS))
    listed = ("1-URGENT", "5-LOW", "6-NONE")
    values = "(select unnest([{}]) as o_orderpriority)".format(", ".join(f"'{x}'" for x in listed))
    source = f"(select * from orders where o_orderpriority in (select o_orderpriority from {values}))"
    hashes = f"{_hashes(key, source, _tagged('o_orderpriority', RAW.format('o_custkey')), 'o_orderpriority, ', thin)} union all {_phantom_hashes(key, v, thin, 'o_orderpriority, ', values)}"

    def query(s, d):
        groups = s.createDataFrame([(x,) for x in listed], "o_orderpriority string")
        return _rounded(rl.release_any(table(s, d, "orders"), ["o_custkey"], spec, budget(), key, ("o_orderpriority",), groups=groups))

    _add("grouped_public_list", query, _release(spec, hashes, bound, v, 0.0, "o_orderpriority, "))


def _private_stream() -> None:
    """Private windows of a stream, over a table: the public list has a day without events, which has its phantoms only."""
    spec, thin, bound, key = SPECS["hll"], pv.threshold(EPS), pv.pi0(EPS), public_key("private-stream")
    v = math.ceil(pv.min_cardinality(spec.k_max, EPS))
    days = "(select unnest(generate_series(timestamp '2024-01-01', timestamp '2024-02-01', interval 1 day)) as window_start)"
    source = f"(select date_trunc('day', ts)::timestamp as window_start, user_id from events where date_trunc('day', ts) in (select window_start from {days}))"
    hashes = f"{_hashes(key, source, _tagged('window_start', RAW.format('user_id')), 'window_start, ', thin)} union all {_phantom_hashes(key, v, thin, 'window_start, ', days)}"

    def query(s, d):
        windows = s.sql("select explode(sequence(timestamp'2024-01-01', timestamp'2024-02-01', interval 1 day)) as window_start")
        states = stream_states(table(s, d, "events"), "ts", ["user_id"], spec, key, keep_below=thin)
        out = release_windows(states, windows, spec, budget(), key)
        return _rounded(out.withColumn("window_start", F.col("window_start").cast("timestamp_ntz")))

    _add("stream_private_windows", query, _release(spec, hashes, bound, v, 0.0, "window_start, "))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    if not _QUERIES:
        _sketches()
        _grouped()
        _more_tables()
        _wider()
        _audits()
        _baselines()
        _experiments()
        _properties()
        _thinned_linear()
        _public_groups()
        _private_stream()
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    queries()
    return dict(_SQL)
