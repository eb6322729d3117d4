"""Workloads against SQL on another engine; privacy facts against enumeration; streams against tables."""

import itertools
import math

import pytest

from private_distinct.functions import privacy as pv
from private_distinct.functions.hashing import SketchKey
from private_distinct.operators import release as rl
from private_distinct.operators import sketches as sk
from private_distinct.plans import workloads as wl

SF = "/root/testdata/sf0.001"
EPS = math.log(2)


@pytest.fixture(scope="module")
def duck():
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "orders", "lineitem", "events", "documents", "labels", "benchmark", "conversations", "embeddings"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", ["state_fm", "state_bottomk", "state_adaptive", "stored_states_converted", "documents_labelled", "documents_unlabelled", "text_overlap_diagnostic", "conversations_per_role", "rounded_vectors_per_label", "plain_linear", "any_hll", "convert_bottomk", "merge_split_union_adaptive", "dup_invariance_fm", "grouped_event_type", "region_segment_customers", "words_per_lang", "rollup_internal", "stream_windows_batch", "stream_private_windows", "baseline_per_bucket", "params_grid", "grouped_day", "nation_suppliers", "cube_internal", "merge_equals_whole", "mle_hll", "mle_fm", "any_registered", "sql_release", "delta_curve", "bayes_linear", "bayes_bottomk", "bayes_thinned", "property_table", "delta_grid_hll", "delta_grid_fm", "delta_grid_bottomk", "delta_grid_adaptive", "plain_linear_thinned", "grouped_public_list", "convert_hll", "convert_fm", "convert_linear", "convert_adaptive"])
def test_workload_equals_sql(spark, duck, name):
    got = wl.queries()[name](spark, SF)
    cols = sorted(got.columns)
    r = duck.execute(wl.oracle_sql()[name])
    names = [x[0] for x in r.description]
    want = sorted(repr(tuple(x[names.index(c)] for c in cols)) for x in r.fetchall())
    assert sorted(names) == cols
    assert sorted(repr(tuple(x[c] for c in cols)) for x in got.collect()) == want


def test_parameters():
    assert pv.min_cardinality(128, EPS) == pytest.approx(256)
    assert [pv.min_n_for_delta(pv.SketchSpec("hll", k), EPS, 1e-9) for k in (128, 1024, 4096)] == [6548, 56637, 237905]
    assert pv.log_binom_cdf(64, 740, pv.pi0(2.0)) == pytest.approx(-1146.44, abs=0.01)
    assert pv.occupancy_cdf(128, 89, 64) == pytest.approx(0.396, abs=0.001)
    with pytest.raises(ValueError):
        pv.delta(pv.SketchSpec("bottomk", 64), 740, 2.0, "printed")
    for kind in ("bottomk", "adaptive"):
        spec = pv.SketchSpec(kind, 64)
        assert pv.delta(spec, 400, EPS) <= pv.delta(spec, 400, EPS, "bound")


def test_thinned_linear_counting_is_private():
    """All hashes of a tiny sketch: removing one item changes no state's chance by more than the bound."""
    k, n, eps = 3, 12, 0.5
    rate = pv.pi0(eps)
    assert n > pv.min_cardinality(k, eps)

    def states(m):
        out = {frozenset(): 1.0}
        for _ in range(m):
            new = {}
            for s, p in out.items():
                new[s] = new.get(s, 0) + p * (1 - rate)
                for b in range(k):
                    new[s | {b}] = new.get(s | {b}, 0) + p * rate / k
            out = new
        return out

    a, b = states(n), states(n - 1)
    assert max(abs(math.log(a[s] / b[s])) for s in b) <= eps + 1e-9  # equality at the empty state: the real threshold is strict
    small, less = states(1), states(0)
    assert set(small) != set(less)  # too few items: some state tells them apart


def test_refusals(spark):
    df = spark.createDataFrame([(1.5,)], "x double")
    with pytest.raises(ValueError):
        SketchKey("")
    with pytest.raises(TypeError):
        sk.build_state(df, ["x"], wl.SPECS["hll"], SketchKey("s"))
    with pytest.raises(ValueError):
        rl.release_large(df, ["x"], wl.SPECS["hll"], pv.Budget(EPS, n_floor=256), SketchKey("s"))
    assert sk.build_state(df, ["x"], wl.SPECS["hll"], SketchKey("s", "native")).count() == 1


def test_pack_and_composites(spark):
    spec, key = wl.SPECS["hll"], SketchKey("s")
    df = spark.createDataFrame([("a", "bc"), ("ab", "c"), (None, "x"), ("", "é")], "x string, y string")
    state = sk.build_state(df, ["x", "y"], spec, key)
    assert sum(r.val > 0 for r in state.collect()) == 3
    packed = sk.pack_state(state, spec, key)
    assert sk.unpack_state(packed, spec, key).exceptAll(state).count() == 0
    with pytest.raises(Exception, match="do not merge"):
        sk.unpack_state(packed, spec, SketchKey("other")).collect()
    empty = rl.release_any(df.limit(0), ["x"], spec, pv.Budget(EPS), key).first()
    assert empty.phantoms == 256 and abs(empty.estimate) < 200


def test_thinned_hash_list_is_unbiased(spark):
    spec, n = pv.SketchSpec("bottomk", 64), 600
    errors = [rl.release_any(spark.range(n), ["id"], spec, pv.Budget(EPS), SketchKey(f"k{i}")).first().estimate - n for i in range(16)]
    mean = sum(errors) / len(errors)
    sd = math.sqrt(sum((e - mean) ** 2 for e in errors) / (len(errors) - 1))
    assert abs(mean) < 4 * sd / math.sqrt(len(errors))
    assert sd**2 < 4 * pv.variance_bound(n, 128, 64, pv.pi0(EPS))


def test_stream_equals_table(spark, tmp_path):
    from private_distinct.streaming.windows import stream_states

    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    spec, key = wl.SPECS["hll"], SketchKey("s")
    late = spark.createDataFrame([(-1, -1)], "event_id long, user_id long").selectExpr("event_id", "user_id", "timestamp_ntz'2031-01-01' as ts", "'' as event_type", "0D as value", "'' as props")
    late.write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    q = stream_states(stream, "ts", ["user_id"], spec, key).writeStream.outputMode("append").format("memory").queryName("states").option("checkpointLocation", str(tmp_path / "cp")).start()
    q.processAllAvailable()
    q.stop()
    want = stream_states(events, "ts", ["user_id"], spec, key)
    got = spark.table("states").where("window_start < '2030-01-01'")
    assert got.count() == want.count() and got.exceptAll(want).count() == 0


def test_private_stream_ignores_replays_and_late_rows(spark, tmp_path):
    from private_distinct.streaming.windows import release_windows, stream_states

    events = spark.read.parquet(f"{SF}/events.parquet")
    src = str(tmp_path / "in")
    events.union(events.limit(300)).write.parquet(src)  # rows given again
    odd = "event_id long, user_id long, day string"
    at = lambda user, day: spark.createDataFrame([(-1, user, day)], odd).selectExpr("event_id", "user_id", "cast(day as timestamp_ntz) as ts", "'' as event_type", "0D as value", "'' as props").write.mode("append").parquet(src)
    at(-1, "2031-01-01")  # moves the watermark past all windows
    spec, key, budget = wl.SPECS["hll"], SketchKey("s"), wl.budget()
    thin = pv.threshold(budget.eps)
    start = lambda: stream_states(spark.readStream.schema(events.schema).parquet(src), "ts", ["user_id"], spec, key, keep_below=thin).writeStream.outputMode("append").format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "cp")).start()
    for user in (None, 10**9, 10**9 + 1):  # stopped and taken up again, with rows that are late by years
        if user:
            at(user, "2024-01-05")
        q = start()
        q.processAllAvailable()
        q.stop()
    windows = spark.sql("select explode(sequence(timestamp'2024-01-01', timestamp'2024-02-01', interval 1 day)) as window_start")
    ledger = rl.KeyLedger()
    got = release_windows(spark.read.parquet(str(tmp_path / "out")), windows, spec, budget, key, ledger=ledger)
    want = release_windows(stream_states(events, "ts", ["user_id"], spec, key, keep_below=thin), windows, spec, budget, key)
    assert sorted(got.collect()) == sorted(want.collect()) and want.count() == 32
    with pytest.raises(ValueError):
        ledger.claim(key, "another output")


def test_plans_stay_native(spark):
    df = spark.read.parquet(f"{SF}/lineitem.parquet")
    for kind in ("hll", "linear", "fm"):
        plan = sk.build_state(df, ["l_orderkey"], wl.SPECS[kind], SketchKey("s", "native"))._jdf.queryExecution().executedPlan().toString()
        assert "ObjectHashAggregate" not in plan and "Python" not in plan and plan.count("Exchange hashpartitioning") == 1
        assert "ReadSchema: struct<l_orderkey:bigint>" in plan


def test_cut_keeps_the_least_hashes(spark):
    for n in (3, 40, 5000):
        for kind in ("bottomk", "adaptive"):
            spec, key = pv.SketchSpec(kind, 16), SketchKey("cut")
            df = spark.range(n).selectExpr("id", "id % 3 as g")
            for g in (None, 0, 1, 2):
                rows = df if g is None else df.where(f"g = {g}")
                all_ = sorted({r.h for r in sk.hashed(rows, ["id"], key).collect()})
                level = next(j for j in range(60) if sum(h >> (60 - j) == 0 for h in all_) <= 16)
                want = all_[:16] if kind == "bottomk" else [h for h in all_ if h >> (60 - level) == 0]
                got = sk.build_state(df, ["id"], spec, key) if g is None else sk.build_state(df, ["id"], spec, key, ("g",)).where(f"g = {g}")
                assert sorted(r.val for r in got.collect()) == want


def test_experiments(spark):
    from private_distinct.plans import experiments as ex

    n, key, ratios = 1 << 14, SketchKey("e", "native"), []
    for k in (128, 1024):
        spec = pv.SketchSpec("hll", k)
        for eps in (None, EPS):
            r = ex.error_summary(ex.estimates(spark, n, spec, 8, key, eps), n).first()
            assert r.trials == 8 and r.rmse < 4 * (spec.rel_std_error(n) if eps is None else math.sqrt(pv.variance_bound(n, 2 * k, k / 1.04**2, 0.5)) / n)
        ratios.append(ex.space_summary(spark, n, k, 8, key, EPS).first().space_ratio)
    assert 1 < ratios[0] < ratios[1]


def test_groups_have_hashes_of_their_own(spark):
    """Two groups of the same items: equal states under one hash, as good as independent ones in a release."""
    spec, key = wl.SPECS["hll"], SketchKey("s")
    df = spark.range(400).selectExpr("id", "explode(array('a', 'b', null)) as g")
    shared, own = (sk.build_state(df, ["id"], spec, key, ("g",), None, o).collect() for o in (False, True))
    by = lambda rows, g: {(r.slot, r.val) for r in rows if r.g == g}
    assert by(shared, "a") == by(shared, "b") == by(shared, None)
    assert len(by(own, "a") & by(own, "b")) < 80 and len(by(own, "a") & by(own, None)) < 80
    out = rl.release_any(df, ["id"], spec, pv.Budget(EPS, max_groups_per_unit=3), key, ("g",)).collect()
    assert len(out) == 3 and len({r.estimate for r in out}) == 3 and all(abs(r.estimate - 400) < 250 for r in out)
    for kind in ("adaptive", "bottomk"):
        assert rl.release_any(df, ["id"], pv.SketchSpec(kind, 16), pv.Budget(EPS), key, ("g",)).count() == 3
    assert pv.Budget(EPS, max_groups_per_unit=3).total_eps == pytest.approx(3 * EPS)


def test_phantoms_of_groups_are_whole(spark):
    groups = spark.createDataFrame([("a",), (None,)], "g string")
    for v in (1, 4096, 4097, 10000):
        rows = sk.phantoms_of_groups(groups, v, SketchKey("s"), ("g",))
        assert sorted(r.n for r in rows.distinct().groupBy("g").count().withColumnRenamed("count", "n").collect()) == [v, v]


def test_ledger_refuses_a_second_output():
    ledger, key = rl.KeyLedger(), SketchKey("s")
    assert ledger.claim(key, "users") is key and ledger.claim(key, "users") is key
    with pytest.raises(ValueError, match="spent"):
        ledger.claim(key, "orders")
    with pytest.raises(ValueError):
        rl.KeyLedger(ledger.entries).claim(key, "orders")
    assert ledger.claim(key.derive("orders"), "orders").secret not in str(ledger.entries)


def test_releases_spend_keys_and_eps(spark):
    spec, budget, df = wl.SPECS["hll"], pv.Budget(1.0), spark.range(500)
    ledger, key = rl.KeyLedger(eps_limit=2.5), SketchKey("spent")
    for _ in range(2):  # the same output again is no second release
        rl.release_any(df, ["id"], spec, budget, key, ledger=ledger)
    with pytest.raises(ValueError, match="spent on"):
        rl.release_any(df.where("id > 3"), ["id"], spec, budget, key, ledger=ledger)
    rl.release_any(df.where("id > 3"), ["id"], spec, budget, key.derive("b"), ledger=ledger)
    with pytest.raises(ValueError, match="limit"):
        rl.release_any(df.where("id > 4"), ["id"], spec, budget, key.derive("c"), ledger=ledger)
    assert ledger.spent == 2.0 and key.secret not in str(ledger.entries)
    with pytest.raises(ValueError, match="delta"):
        rl.release_plain(df, ["id"], spec, pv.Budget(EPS, n_floor=400), SketchKey("p"))
    with pytest.raises(ValueError, match="delta"):
        rl.release_plain(df, ["id"], spec, pv.Budget(EPS, delta=0.1), SketchKey("p"))


def test_stored_values_do_not_tell_the_native_seeds(spark):
    from private_distinct.functions import hashing

    key, spec = SketchKey("native secret", "native"), wl.SPECS["hll"]
    seen = str(sk.pack_state(sk.build_state(spark.range(100), ["id"], spec, key), spec, key).collect()) + str(rl.KeyLedger().claim(key, "x").key_id)
    assert all(str(s) not in seen for s in key.seeds) and len(set(key.seeds)) == 2
    assert not {int(key.key_id, 16) % (1 << 62) + i for i in (0, 1)} & set(key.seeds)
    assert key.seeds != SketchKey("other", "native").seeds and len(set(key.seeds) | set(key.derive("y").seeds)) == 4
    plain, before = SketchKey("visible-secret"), spark.conf.get("spark.sql.redaction.string.regex", None)
    hashing.redact(spark, plain, key)
    for k in (plain, key):
        text = sk.build_state(spark.range(100), ["id"], spec, k)._sc._jvm.PythonSQLUtils.explainString(sk.build_state(spark.range(100), ["id"], spec, k)._jdf.queryExecution(), "extended")
        assert k.secret not in text and all(str(s) not in text for s in k.seeds)
    spark.conf.unset("spark.sql.redaction.string.regex") if before is None else spark.conf.set("spark.sql.redaction.string.regex", before)


def test_linear_counting_with_a_rate(spark):
    assert pv.linear_floor(128, EPS)[0] == 64 and pv.linear_floor(128, EPS)[1] == pytest.approx(88.2, abs=0.2)
    for rate in (0.6, 1.0):
        spec = pv.SketchSpec("linear", 64, rate=rate)
        for n in (150, 200, 300):
            exact = pv.delta(spec, n, EPS)
            assert exact <= math.exp(pv.ln_delta_bound(spec, n, EPS)) + 1e-12
    thin = pv.SketchSpec("linear", 64, rate=0.3)
    assert pv.delta(thin, 200, EPS) == 0 and pv.delta(thin, 100, EPS) == 1
    est = [sk.estimate_state(sk.build_state(spark.range(300), ["id"], thin, SketchKey(f"r{i}")), thin).first() for i in range(12)]
    assert abs(sum(r.base_estimate for r in est) / 12 - 300) < 4 * 300 * thin.rel_std_error(300) / 12**0.5
    assert all(r.pi <= 0.3 for r in est)
    with pytest.raises(ValueError):
        pv.SketchSpec("hll", 64, rate=0.5)
    with pytest.raises(ValueError):
        rl.release_any(spark.range(9), ["id"], thin, pv.Budget(EPS), SketchKey("s"))


def test_registered_sketch(spark):
    spec = pv.SketchSpec("binmin", 64)
    df, key = spark.range(5000), SketchKey("s")
    state = sk.build_state(df, ["id"], spec, key)
    assert sk.merge_states([sk.build_state(df.where(f"id % 3 = {i}"), ["id"], spec, key) for i in range(3)], spec).exceptAll(state).count() == 0
    assert abs(sk.estimate_state(state, spec).first().base_estimate - 5000) < 4 * 5000 * spec.rel_std_error(5000)
    assert spec.k_max == 64 and pv.k_max_from_bits(spec.size_bits) == 64 * 64
    with pytest.raises(ValueError):
        pv.delta(spec, 5000, EPS)
    with pytest.raises(ValueError):
        pv.register_sketch("hll", pv.CUSTOM["binmin"])


def test_likeliest_estimate(spark):
    """Against a plain search; less error than the classic bitmap estimate; none of the register sketch's bump."""
    key = SketchKey("s", "native")
    rows = spark.range(2500).selectExpr("id", "explode(sequence(1, 48)) as trial")
    for kind in ("fm", "hll"):
        spec = pv.SketchSpec(kind, 64)
        state = sk.build_state(rows, ["trial", "id"], spec, key, ("trial",)).cache()
        got = {e: [r.base_estimate for r in sk.estimate_state(state, spec, ("trial",), e).collect()] for e in ("classic", "mle")}
        rmse = {e: math.sqrt(sum((x / 2500 - 1) ** 2 for x in v) / len(v)) for e, v in got.items()}
        assert rmse["mle"] < (0.649 if kind == "fm" else 1.04) / 8 * 1.5
        assert kind == "hll" or rmse["mle"] < rmse["classic"]
    state = state.where("trial = 1").drop("trial")
    vals = {r.slot: r.val for r in state.collect()}

    def loglik(n):
        out = 0.0
        for j in range(64):
            v = vals.get(j, 0)
            out += -n / 64 if v == 0 else -n / 64 * 2.0**-v + math.log(-math.expm1(-n / 64 * 2.0**-v))
        return out

    n = sk.estimate_state(state, spec, (), "mle").first().base_estimate
    assert loglik(n) >= max(loglik(n * 0.999), loglik(n * 1.001))
    empty = sk.estimate_state(state.limit(0), spec, (), "mle").first()
    assert empty.base_estimate == 0 and empty.pi == 1
    with pytest.raises(ValueError):
        sk.estimate_state(state, wl.SPECS["linear"], (), "mle")


def test_audit_bounds(spark):
    """Thinned and above the least cardinality: every ratio within eps. Not thinned: some state goes below it."""
    from private_distinct.operators import audit

    eps = 0.4
    assert 7 > pv.min_cardinality(2, eps)
    thinned = audit.bayes_factors(spark, "linear", 2, 0, 7, pv.pi0(eps)).collect()
    assert all(not r.reveals and abs(r.ln_ratio) <= eps + 1e-9 for r in thinned)
    plain = audit.bayes_factors(spark, "linear", 2, 0, 7).collect()
    assert any(r.p_with == 0 or r.ln_ratio < -eps for r in plain)
    assert sum(r.p_with for r in plain) == pytest.approx(1)


@pytest.fixture(scope="module")
def few(spark, tmp_path_factory):
    """A folder of small tables with nulls and repeats."""
    d = str(tmp_path_factory.mktemp("few"))
    lines = [(1, 1), (1, 2), (1, 2), (2, 1), (2, 3), (3, 7), (None, 1), (None, 2), (None, 3), (4, None)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").selectExpr("*", "l_partkey as l_suppkey", "if(l_orderkey = 2, 'A', 'B') as l_returnflag").write.parquet(f"{d}/lineitem.parquet")
    orders = [(i, 1995 + (i >= 1000)) for i in range(3000)] * 2 + [(7, 1995), (None, 1995)]
    spark.createDataFrame(orders, "o_custkey long, year int").selectExpr("o_custkey", "make_timestamp_ntz(year, 3, 4, 5, 6, 7) as o_orderdate").union(spark.sql("select 9999L, cast(null as timestamp_ntz)")).write.parquet(f"{d}/orders.parquet")
    return d


@pytest.mark.parametrize("name", ["bayes_bottomk", "bayes_fm", "bayes_hll", "bayes_linear", "bayes_thinned"])
def test_audit_reads_the_table(spark, few, name):
    """Two groups of two items, one of one, one (of a null key) of three; every size's chances sum to one."""
    import duckdb

    got = wl.queries()[name](spark, few).collect()
    assert {(r.n, r.n_groups) for r in got} == {(1, 1), (2, 2), (3, 1)}
    for n in (1, 2, 3):
        for p in ("p_with", "p_without"):
            assert sum(r[p] for r in got if r.n == n) == pytest.approx(1, abs=1e-4)
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{few}/lineitem.parquet/*.parquet'")
    r = con.execute(wl.oracle_sql()[name])
    at = [[x[0] for x in r.description].index(c) for c in got[0].asDict()]
    assert sorted(map(repr, (tuple(x[i] for i in at) for x in r.fetchall()))) == sorted(repr(tuple(x)) for x in got)


def test_delta_curve_reads_the_table(spark, few):
    """Customers so far after each day with new ones; orders without a date or a customer count for none."""
    got = sorted(tuple(r) for r in wl.queries()["delta_curve"](spark, few).collect())
    want = [(d, n, 256.0, round(pv.delta(wl.SPECS["hll"], n, EPS), 6)) for d, n in (("1995-03-04", 1000), ("1996-03-04", 3000))]
    assert [(str(d), *x) for d, *x in got] == want


@pytest.mark.parametrize("name", ["delta_grid", "delta_grid_adaptive", "delta_grid_bottomk", "delta_grid_fm", "delta_grid_hll"])
def test_failure_chances_read_the_table(spark, few, name):
    """Every period of the orders, with its different customers, at every eps."""
    got = [r.asDict() for r in wl.queries()[name](spark, few).collect()]
    period = "year" if name == "delta_grid" else "month"
    kinds = list(wl.SPECS) if name == "delta_grid" else [name.removeprefix("delta_grid_")]
    steps = (0.5, EPS, 1.0) if name == "delta_grid" else (0.1, 0.5, EPS, 1.0, 2.0)
    assert {(r[period].year, r["n"]) for r in got} == {(1995, 1000), (1996, 2000)} and len(got) == 2 * len(kinds) * len(steps)
    for kind, eps, n in itertools.product(kinds, steps, (1000, 2000)):
        spec = pv.SketchSpec(kind, 128)
        row = [r for r in got if r["n"] == n and abs(r["eps"] - eps) < 1e-6 and r.get("kind", kind) == kind]
        assert [r["delta"] for r in row] == [pytest.approx(pv.delta(spec, n, eps), abs=1e-6)]


def test_occupancy_of_many_items():
    """Cut short once nothing can be seen of it, with the same result before."""
    assert pv.occupancy_cdf(128, 10**9, 64) < 1e-280


def test_moments_read_the_table(spark, few):
    from private_distinct.plans import experiments as ex

    got = {r.l_returnflag: r for r in wl.queries()["experiment_bias_variance"](spark, few).collect()}
    assert {f: (r.n, r.trials) for f, r in got.items()} == {"A": (2, 200), "B": (4, 200)}
    many = spark.range(4500).selectExpr("if(id < 3000, 'a', null) as g", "id % 1500 as x")
    for r in ex.group_moments(many, "x", ("g",), pv.SketchSpec("bottomk", 64), 100, SketchKey("g", "native"), EPS).collect():
        assert r.n == 1500 and abs(r.z) < 4 and r.variance < 2 * r.variance_bound and r.variance_ratio < 2.5


def test_audit_by_binary_digits(spark):
    """Chances of large groups equal those item by item; no group gives no row."""
    from private_distinct.operators import audit

    for kind, k, levels in (("bottomk", 2, 6), ("linear", 3, 0)):
        got = {(r.n, r.state): r.p for r in audit.chances_of_sizes(spark, kind, k, levels, [0, 1, 6, 13]).collect()}
        for n in (0, 1, 6):
            want = {r.state: r.p for r in audit.state_chances(spark, kind, k, levels, n).collect()}
            assert {s: p for (m, s), p in got.items() if m == n} == pytest.approx(want)
    none = spark.createDataFrame([], "g long, x long")
    assert audit.bayes_factors_of_groups(none, "g", "x", "hll", 2, 3).count() == 0


def test_thresholds_and_violations(spark):
    from private_distinct.plans import experiments as ex

    assert pv.estimate_threshold(pv.SketchSpec("linear", 128), EPS) == pytest.approx(88.72, abs=0.01)
    assert pv.estimate_threshold(pv.SketchSpec("hll", 128), EPS) is None  # 2 alpha k is under 5 k / 2
    assert pv.estimate_threshold(pv.SketchSpec("hll", 128), 0.25) > 2.5 * 128
    spec = pv.SketchSpec("bottomk", 64)
    r = ex.violation_summary(spark, 140, spec, 200, SketchKey("v", "native"), EPS).first()
    assert r.violating == r.below_threshold and abs(r.violating - r.delta) < 0.15
    m = ex.moment_summary(spark, 2048, spec, 100, SketchKey("m", "native"), EPS).first()
    assert abs(m.z) < 4 and m.variance < 2 * m.variance_bound and m.variance_ratio < 2.5


def test_registry():
    assert set(wl.oracle_sql()) <= set(wl.queries())
    assert all(a != b for a, b in itertools.pairwise(sorted(wl.queries())))
