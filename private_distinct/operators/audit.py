"""Exact privacy audit of tiny sketches: every hash function is enumerated, so chances of states have no error.

All sketches are bit masks joined by OR: a register is held in unary, a hash list as the set of values seen, cut
to the k least.  The tables of chances have one row for each state and each size that groups of a given table have,
which are few whatever the number of groups.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def outcomes(kind: str, k: int, levels: int, rate: float = 1.0) -> list[tuple[int, float]]:
    """(mask, chance) of where one item goes; ``levels``: bits of a bitmap, register values, or values of a hash."""
    if kind == "linear":
        each = [(1 << j, 1 / k) for j in range(k)]
    elif kind == "bottomk":
        each = [(1 << j, 1 / levels) for j in range(levels)]
    elif kind in ("fm", "hll"):
        each = []
        for j in range(k):
            for i in range(levels):
                mask = (1 << i) if kind == "fm" else (1 << (i + 1)) - 1
                each.append((mask << (j * levels), 2.0 ** -min(i + 1, levels - 1) / k))
    else:
        raise ValueError(f"no enumeration for {kind}")
    return [(m, rate * p) for m, p in each] + ([(0, 1 - rate)] if rate < 1 else [])


def kept_bits(kind: str, k: int, mask: str) -> str:
    """SQL, the same on both engines: the k lowest set bits of a hash list, all bits of another sketch."""
    if kind != "bottomk":
        return mask
    rest = mask
    for _ in range(k):
        rest = f"({rest} & ({rest} - 1))"
    return f"({mask} - {rest})"


def state_chances(spark: SparkSession, kind: str, k: int, levels: int, n: int, rate: float = 1.0) -> DataFrame:
    """(state, p) over all hash functions, for n different items."""
    one = F.broadcast(spark.createDataFrame(outcomes(kind, k, levels, rate), "mask long, q double"))  # k x levels rows
    out = spark.createDataFrame([(0, 1.0)], "state long, p double")
    for _ in range(n):
        joined = out.crossJoin(one).select((F.col("state").bitwiseOR(F.col("mask"))).alias("m"), (F.col("p") * F.col("q")).alias("p"))
        out = joined.select(F.expr(kept_bits(kind, k, "m")).alias("state"), "p").groupBy("state").agg(F.sum("p").alias("p"))
    return out


def bayes_factors(spark: SparkSession, kind: str, k: int, levels: int, n: int, rate: float = 1.0) -> DataFrame:
    """For each state its chance with n items and with one item less, and the log of their ratio.

    A state that only one of the two can reach tells them apart: its ratio is null and ``reveals`` is true.
    """
    a = state_chances(spark, kind, k, levels, n, rate).withColumnRenamed("p", "p_with")
    b = state_chances(spark, kind, k, levels, n - 1, rate).withColumnRenamed("p", "p_without")
    both = a.join(b, "state", "full")
    return both.select("state", F.coalesce("p_with", F.lit(0.0)).alias("p_with"), F.coalesce("p_without", F.lit(0.0)).alias("p_without"), F.ln(F.col("p_with") / F.col("p_without")).alias("ln_ratio"), (F.col("p_with").isNull() | F.col("p_without").isNull()).alias("reveals"))


def group_sizes(rows: DataFrame, group: str, item: str) -> list[tuple[int, int]]:
    """(different items, groups that have so many) of a table; groups without items, whom no item can leave, are left out."""
    sizes = rows.groupBy(group).agg(F.countDistinct(item).alias("n")).where("n > 0")
    return [tuple(r) for r in sizes.groupBy("n").agg(F.count(F.lit(1))).collect()]  # some root of the rows at most


def chances_of_sizes(spark: SparkSession, kind: str, k: int, levels: int, sizes: list[int], rate: float = 1.0) -> DataFrame:
    """(n, state, p) over all hash functions, for each number of items: sketches merge, so n items take its binary digits."""
    def step(a: DataFrame, b: DataFrame, by: tuple) -> DataFrame:
        both = a.crossJoin(F.broadcast(b)).select(*by, F.col("state").bitwiseOR(F.col("mask")).alias("m"), (F.col("p") * F.col("q")).alias("p"))
        return both.select(*by, F.expr(kept_bits(kind, k, "m")).alias("state"), "p").groupBy(*by, "state").agg(F.sum("p").alias("p"))

    def fixed(df: DataFrame) -> DataFrame:  # else the plan doubles in each round
        return spark.createDataFrame(df.collect(), df.schema)

    out = spark.createDataFrame([(n, 0, 1.0) for n in sizes], "n long, state long, p double")
    power = spark.createDataFrame([(0, 1.0)], "state long, p double")
    power = fixed(step(power, spark.createDataFrame(outcomes(kind, k, levels, rate), "mask long, q double"), ()))
    for bit in range(max(sizes, default=0).bit_length()):
        one = power.toDF("mask", "q")
        out = fixed(step(out.where(F.expr(f"(n >> {bit}) & 1 = 1")), one, ("n",)).union(out.where(F.expr(f"(n >> {bit}) & 1 = 0"))))
        power = fixed(step(power, one, ()))
    return out


def bayes_factors_of_groups(rows: DataFrame, group: str, item: str, kind: str, k: int, levels: int, rate: float = 1.0) -> DataFrame:
    """The audit for the sketch of each group's items: a group of n against the same group with one item less.

    Groups of one size have the same chances, so there is one row for each size, with its number of groups, and state.
    """
    spark, sizes = rows.sparkSession, group_sizes(rows, group, item)
    chances = chances_of_sizes(spark, kind, k, levels, sorted({m for n, _ in sizes for m in (n, n - 1)}), rate)
    a = chances.withColumnRenamed("p", "p_with")
    b = chances.select((F.col("n") + 1).alias("n"), "state", F.col("p").alias("p_without"))
    both = spark.createDataFrame(sizes, "n long, n_groups long").join(a.join(b, ["n", "state"], "full"), "n")
    return both.select("n", "n_groups", "state", F.coalesce("p_with", F.lit(0.0)).alias("p_with"), F.coalesce("p_without", F.lit(0.0)).alias("p_without"), F.ln(F.col("p_with") / F.col("p_without")).alias("ln_ratio"), (F.col("p_with").isNull() | F.col("p_without").isNull()).alias("reveals"))


def bayes_groups_sql(source: str, group: str, item: str, kind: str, k: int, levels: int, rate: float = 1.0) -> str:
    """The same in SQL, item by item, values rounded to six digits."""
    values = ", ".join(f"({m}, {p!r}::double)" for m, p in outcomes(kind, k, levels, rate))
    return f"""with recursive one as (select cast(mask as bigint) as mask, q from (values {values}) as o(mask, q)),
      sizes as materialized (select n, count(*) as n_groups from (select count(distinct {item}) as n from {source} group by {group}) where n > 0 group by n),
      c as (select 0::bigint as n, 0::bigint as state, 1.0::double as p
        union all select n + 1 as n, {kept_bits(kind, k, "m")} as state, sum(p) as p from (select n, state | mask as m, p * q as p from c cross join one where n < (select max(n) from sizes)) group by 1, 2)
      select n, n_groups, state, round(coalesce(a.p, 0), 6) as p_with, round(coalesce(b.p, 0), 6) as p_without, round(ln(a.p / b.p), 6) as ln_ratio, a.p is null or b.p is null as reveals
      from c a full join (select n + 1 as n, state, p from c) b using (n, state) join sizes using (n)"""
