"""Relational operators around the joins: thin, with their cost stated where it is not obvious."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# ---- projection and filter ----


def project(df: DataFrame, variables: list[str]) -> DataFrame:
    """Set projection; one shuffle."""
    return df.select(*variables).distinct()


def rename(df: DataFrame, mapping: dict[str, str]) -> DataFrame:
    return df.withColumnsRenamed(mapping)


def derive(df: DataFrame, **exprs: str) -> DataFrame:
    return df.withColumns({k: F.expr(e) for k, e in exprs.items()})


def restrict(df: DataFrame, keys: DataFrame) -> DataFrame:
    """Tuples whose part on the keys' columns is listed. keys: a bounded list, broadcast."""
    return df.join(F.broadcast(keys), keys.columns, "left_semi")


def case_when(df: DataFrame, name: str, cases: list[tuple[str, object]], default) -> DataFrame:
    out: Column | None = None
    for cond, value in cases:
        out = F.when(F.expr(cond), value) if out is None else out.when(F.expr(cond), value)
    return df.withColumn(name, out.otherwise(default))


# ---- joins ----


def cartesian(a: DataFrame, b: DataFrame, most: int = 1_000_000) -> DataFrame:
    """Cross product with a side that is checked to be small and broadcast."""
    if b.limit(most + 1).count() > most:
        raise ValueError(f"the right side has more than {most} rows")
    return a.crossJoin(F.broadcast(b))


def semi_join(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    """Two rounds: distinct keys on the right, then the filter; a hot key loads only the streamed side, which AQE may split."""
    return left.join(right.select(*on).distinct(), on, "left_semi")


def anti_join(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(right.select(*on).distinct(), on, "left_anti")


def theta_join(a: DataFrame, b: DataFrame, cond: str) -> DataFrame:
    """Nested loop; b is a bounded side."""
    return a.join(F.broadcast(b), F.expr(cond))


def range_join(a: DataFrame, b: DataFrame, point: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of a whose point lies in [low, high] of b: both fall into bins of a stated width, intervals into all that they touch."""
    left = a.withColumn("__bin", F.floor(F.col(point) / width))
    right = b.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return left.join(right, "__bin").where(F.col(point).between(F.col(low), F.col(high))).drop("__bin")


def asof_join(a: DataFrame, b: DataFrame, key: str, ts: str, value: str, order: str) -> DataFrame:
    """For each row of a the last value of b at or before it, for the same key: both sides in one sorted pass instead of a range join. Of rows
    of one time those of b come first; order breaks ties."""
    left = a.select(key, ts, order, F.lit(1).alias("__side"), F.lit(None).cast(b.schema[value].dataType).alias("__v"))
    right = b.select(key, ts, order, F.lit(0).alias("__side"), F.col(value).alias("__v"))
    w = Window.partitionBy(key).orderBy(ts, "__side", order).rowsBetween(Window.unboundedPreceding, 0)
    return left.unionByName(right).withColumn(f"last_{value}", F.last("__v", ignorenulls=True).over(w)).where("__side = 1").drop("__side", "__v")


def interval_join(a: DataFrame, b: DataFrame, key: str, ts: str, seconds: int, prefix: str = "b_") -> DataFrame:
    """Pairs of one key whose times differ by at most so many seconds after a. Times fall into bins of that length, so a hot key is spread."""
    bins = lambda d: F.floor(F.unix_timestamp(d[ts]) / seconds)
    right = b.select([F.col(c).alias(f"{prefix}{c}") for c in b.columns])
    left = a.withColumn("__bin", F.explode(F.array(bins(a), bins(a) + 1)))
    right = right.withColumn("__bin", F.floor(F.unix_timestamp(f"{prefix}{ts}") / seconds))
    cond = (F.col(key) == F.col(f"{prefix}{key}")) & (left["__bin"] == right["__bin"])
    later = F.unix_timestamp(f"{prefix}{ts}") - F.unix_timestamp(ts)
    return left.join(right, cond).where(later.between(0, seconds)).select(*a.columns, *[f"{prefix}{c}" for c in b.columns])


def self_join(df: DataFrame, names: list[dict[str, str]]) -> list[DataFrame]:
    """Copies of a relation under different variables."""
    return [df.select([F.col(c).alias(m[c]) for c in df.columns]) for m in names]


# ---- aggregation ----


def hash_agg(df: DataFrame, keys: list[str], **aggs: str) -> DataFrame:
    return df.groupBy(*keys).agg(*[F.expr(e).alias(k) for k, e in aggs.items()])


def grouping_sets(df: DataFrame, keys: list[str], kind: str = "cube", **aggs: str) -> DataFrame:
    grouped = {"cube": df.cube, "rollup": df.rollup}[kind](*keys)
    return grouped.agg(F.grouping_id().cast("long").alias("gid"), *[F.expr(e).alias(k) for k, e in aggs.items()])


def pivot(df: DataFrame, keys: list[str], column: str, values: list, agg: str) -> DataFrame:
    """Stated values, so that no job is needed to find them."""
    return df.groupBy(*keys).pivot(column, values).agg(F.expr(agg))


# ---- windows, order, sets ----


def rank(df: DataFrame, part: list[str], order: list[Column], kind: str = "row_number", name: str = "rk") -> DataFrame:
    fn = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank, "percent_rank": F.percent_rank}.get(kind)
    col = F.ntile(int(kind.removeprefix("ntile"))) if fn is None else fn()
    return df.withColumn(name, col.over(Window.partitionBy(*part).orderBy(*order)))


def frame_agg(df: DataFrame, part: list[str], order: list[str], agg: str, name: str, rows: tuple[int, int] | None = None) -> DataFrame:
    w = Window.partitionBy(*part).orderBy(*order)
    return df.withColumn(name, F.expr(agg).over(w.rowsBetween(*rows) if rows else w))


def top_k(df: DataFrame, order: list[Column], k: int) -> DataFrame:
    """Each task keeps k rows."""
    return df.orderBy(*order).limit(k)


def top_k_per_group(df: DataFrame, part: list[str], order: list[Column], k: int) -> DataFrame:
    return rank(df, part, order).where(F.col("rk") <= k)
