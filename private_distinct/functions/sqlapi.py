"""SQL surface: temporary functions, so that a release can be written in Spark SQL, and a table of failure chances."""

from __future__ import annotations

from pyspark.sql import SparkSession

from .hashing import BITS, SPACE
from .privacy import SketchSpec, delta, min_cardinality

SCALARS = {
    "private_pi0(eps double) returns double": "-expm1(-eps)",
    "private_n0(k_max bigint, eps double) returns double": "k_max / -expm1(-eps)",
    "private_threshold(eps double) returns bigint": f"cast(ceil(-expm1(-eps) * {float(SPACE)!r}D) as bigint) - 1",
    # the two slices of one digest, as in the portable family
    "private_hash(secret string, txt string) returns bigint": "cast(conv(substring(md5(concat(secret, ':', txt)), 1, 15), 16, 10) as bigint)",
    "private_thin(secret string, txt string) returns bigint": "cast(conv(substring(md5(concat(secret, ':', txt)), 16, 15), 16, 10) as bigint)",
    "private_hll_slot(h bigint, k int) returns int": "cast(h % k as int)",
    "private_hll_value(h bigint, k int) returns bigint": f"cast({BITS + 1} - cast(log2(k) as int) - case when h div k = 0 then 0 else length(bin(h div k)) end as bigint)",
}


def delta_rows(kind: str, k: int, eps: float, from_n: int, to_n: int, step: int):
    """(n, n0, delta) for each n; depends on parameters only."""
    spec = SketchSpec(kind, k)
    for n in range(from_n, to_n + 1, max(1, step)):
        yield n, float(min_cardinality(spec.k_max, eps)), float(delta(spec, n, eps))


class _DeltaCurve:
    def eval(self, kind, k, eps, from_n, to_n, step):
        yield from delta_rows(kind, k, float(eps), from_n, to_n, step)


def register(spark: SparkSession) -> None:
    """Define the functions in this session."""
    from pyspark.sql.functions import udtf

    for head, body in SCALARS.items():
        spark.sql(f"create or replace temporary function {head} return {body}")
    spark.udtf.register("private_delta_curve", udtf(_DeltaCurve, returnType="n bigint, n0 double, delta double"))


def sql_release_any(source: str, item: str, secret: str, k: int, eps: float) -> str:
    """Spark SQL text of the release with thinned items and phantoms, register sketch; ``register`` comes first."""
    from ..operators.sketches import hll_alpha

    return f"""
with texts as (
  select concat('r:', cast({item} as string)) as t from {source} where {item} is not null
  union all select concat('p:', cast(id as string)) from (select explode(ids) as id from (select sequence(0L, cast(ceil(private_n0({k}, {eps!r}D)) as bigint) - 1) as ids))
), hashes as (
  select private_hash('{secret}', t) as h from texts where private_thin('{secret}', t) < private_threshold({eps!r}D)
), slots as (
  select private_hll_slot(h, {k}) as slot, max(private_hll_value(h, {k})) as val from hashes group by 1
), sums as (
  select coalesce(sum(pow(2.0D, -val)), 0) + {k} - count(slot) as total, {k} - count(slot) as empty from slots
), base as (
  select case when {hll_alpha(k) * k * k!r}D / total <= {2.5 * k!r}D and empty > 0 then {float(k)!r}D * ln({float(k)!r}D / empty) else {hll_alpha(k) * k * k!r}D / total end as base_estimate from sums
)
select base_estimate, base_estimate / private_pi0({eps!r}D) - ceil(private_n0({k}, {eps!r}D)) as estimate from base"""
