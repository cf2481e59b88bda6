"""Degrees and their uniformisation: parts of a relation in which every subset of variables has degrees within a factor of two.

Buckets are half open, (2^(i-1), 2^i], so parts are disjoint; bucket 0 is degree 1. With clamp, degrees of at most n / p share the bucket LIGHT: no
share can be chosen that makes them heavy. Then fewer than p keys of a subset and signature are not light, so their table is small, and
the tag is a broadcast join of proven size without a shuffle of the relation.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from fractions import Fraction
from functools import reduce
from itertools import combinations, product

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

LIGHT = -1
#: Above so many combinations of parts, buckets are merged.
MAX_COMBOS = 256


def degree(df: DataFrame, of: list[str], given: list[str] | None = None) -> DataFrame:
    """given, deg: distinct values of ``of`` beside each value of ``given``; without ``given``, the tuples beside each value of ``of``."""
    if given is None:
        return df.groupBy(*of).agg(F.count("*").alias("deg"))
    return df.groupBy(*given).agg(F.count_distinct(*of).alias("deg"))


def sum_by_key(df: DataFrame, key: list[str], method: str = "join", name: str = "cnt") -> DataFrame:
    """Every tuple with the count of its key. "join": partial counts joined back, which AQE may split at hot keys; "window": one
    task for each key, for small data only."""
    if method == "window":
        return df.withColumn(name, F.count("*").over(Window.partitionBy(*key)))
    return df.join(df.groupBy(*key).agg(F.count("*").alias(name)), key)


def degree_bucket(deg: Column) -> Column:
    """The least i with 2^i >= deg, without floats."""
    return F.when(deg <= 1, 0).otherwise(F.length(F.bin(deg - 1))).cast("int")


def subsets_in_order(variables: list[str]) -> list[tuple[str, ...]]:
    """Proper nonempty subsets by size."""
    v = sorted(variables)
    return [s for k in range(1, len(v)) for s in combinations(v, k)]


def bucket_name(subset: tuple[str, ...]) -> str:
    return "b_" + "_".join(subset)


def coarsen(bucket: Column, base: int) -> Column:
    """``base`` neighbouring buckets as the largest of them; the factor two of a part's degrees becomes 2^base."""
    return bucket if base == 1 else (F.ceil(bucket / base) * base).cast("int")


def uniformize(df: DataFrame, variables: list[str], n: int, p: int, clamp: bool = True, method: str = "join", tops: dict[str, int] | None = None, base: int = 1) -> DataFrame:
    """df with a bucket column for each proper subset of the variables, by increasing size, each inside the parts made before. tops: what no degree of
    a variable exceeds, if known; where that is light, no part has a heavier one and nothing is counted. base: buckets merged into one."""
    spark = df.sparkSession
    done: list[tuple[str, ...]] = []
    heavy_sets: set[tuple[str, ...]] = set()
    for u in subsets_in_order(variables):
        name = bucket_name(u)
        if not clamp:
            df = sum_by_key(df, [*map(bucket_name, done), *u], method, "__c").withColumn(name, coarsen(degree_bucket(F.col("__c")), base)).drop("__c")
            done.append(u)
            continue
        # a set with a light subset is light, so only tuples that are heavy in all subsets are counted
        inside = [s for s in done if set(s) < set(u)]
        found = []
        if heavy_sets.issuperset(inside) and (tops is None or all(tops[v] > n // p for v in u)):
            rows = df
            for s in inside:
                rows = rows.where(F.col(bucket_name(s)) != LIGHT)
            keys = [*(bucket_name(s) for s in done if s in heavy_sets), *u]
            heavy = rows.groupBy(*keys).agg(F.count("*").alias("__c")).where(F.col("__c") > n // p)
            found = heavy.collect()  # fewer than p for each signature
        if found:
            heavy_sets.add(u)
            df = df.join(F.broadcast(spark.createDataFrame(found, heavy.schema)), keys, "left").withColumn(name, F.coalesce(coarsen(degree_bucket(F.col("__c")), base), F.lit(LIGHT))).drop("__c")
        else:
            df = df.withColumn(name, F.lit(LIGHT))
        done.append(u)
    return df.select(*sorted(variables), *[F.col(bucket_name(u)).cast("int").alias(bucket_name(u)) for u in done])


@dataclass(frozen=True)
class Signature:
    """One part of a relation: the bucket of each subset, and how many tuples it has."""

    buckets: tuple[tuple[tuple[str, ...], int], ...]
    count: int

    def condition(self) -> Column:
        cond = F.lit(True)
        for u, b in self.buckets:
            cond = cond & (F.col(bucket_name(u)) == b)
        return cond

    def slack(self, m: int, k: int) -> dict[frozenset[str], Fraction]:
        """log_p(n / sigma) of each subset that is not light, for n = 2^m and p = 2^k."""
        return {frozenset(u): Fraction(m - b, k) for u, b in self.buckets if b != LIGHT} if k else {}


def signature_counts(tagged: DataFrame, variables: list[str]) -> DataFrame:
    return tagged.groupBy(*[bucket_name(u) for u in subsets_in_order(variables)]).agg(F.count("*").alias("cnt"))


def signatures(tagged: DataFrame, variables: list[str]) -> list[Signature]:
    order = subsets_in_order(variables)
    if not order:
        return [Signature((), tagged.count())]
    rows = signature_counts(tagged, variables).collect()
    return sorted((Signature(tuple((u, r[bucket_name(u)]) for u in order), r["cnt"]) for r in rows), key=lambda s: s.buckets)


def part_bound(n: int, arity: int) -> int:
    """At most so many parts of a relation."""
    return max(1, n.bit_length()) ** (2**arity)


def with_part(tagged: DataFrame, variables: list[str], parts: list[Signature], name: str = "__part") -> DataFrame:
    """The variables and the number of the part, its place in ``parts``."""
    if len(parts) == 1:
        return tagged.select(*variables, F.lit(0).alias(name))
    names = [bucket_name(u) for u in subsets_in_order(variables)]
    rows = [(i, *(b for _, b in s.buckets)) for i, s in enumerate(parts)]
    table = tagged.sparkSession.createDataFrame(rows, f"{name} int, " + ", ".join(f"`{b}` int" for b in names))
    return tagged.join(F.broadcast(table), names).select(*variables, name)


Apart = dict[tuple[str, str], set[tuple[int, int]]]


def parts_apart(parted: dict[str, DataFrame], parts: dict[str, list[Signature]]) -> Apart:
    """Pairs of parts of two relations that are both heavy in a common variable and have no such value in common, so that no combination with both has
    a result. Fewer than p values of a part are compared; one row for each pair of parts comes to the driver."""
    jobs, able = [], {}
    for v in sorted({u[0] for s in parts.values() for x in s for u, b in x.buckets if b != LIGHT and len(u) == 1}):
        heavy = {r: [i for i, x in enumerate(s) if dict(x.buckets).get((v,), LIGHT) != LIGHT] for r, s in parts.items()}
        heavy = {r: i for r, i in heavy.items() if i}
        values = {r: parted[r].where(F.col("__part").isin(i)).select(v, F.col("__part")).distinct() for r, i in heavy.items()}
        for r, s in combinations(sorted(heavy), 2):
            able[v, r, s] = set(product(heavy[r], heavy[s]))
            jobs.append(values[r].withColumnRenamed("__part", "i").join(values[s].withColumnRenamed("__part", "j"), v).select(F.lit(v).alias("v"), F.lit(r).alias("r"), F.lit(s).alias("s"), "i", "j").distinct())
    if jobs:
        for x in reduce(DataFrame.unionAll, jobs).collect():
            able[x["v"], x["r"], x["s"]].discard((x["i"], x["j"]))
    out: Apart = {}
    for (_, r, s), pairs in able.items():
        out.setdefault((r, s), set()).update(pairs)
    return out


def combos(parts: dict[str, list[Signature]], apart: Apart | None = None) -> Iterator[dict[str, Signature]]:
    """Every choice of one part from each relation without a pair that is apart; empty parts have no signature."""
    names, apart = sorted(parts), apart or {}

    def extend(chosen: list[int]) -> Iterator[dict[str, Signature]]:
        k = len(chosen)
        if k == len(names):
            yield {r: parts[r][i] for r, i in zip(names, chosen, strict=True)}
            return
        for i in range(len(parts[names[k]])):
            if not any((j, i) in apart.get((names[x], names[k]), ()) for x, j in enumerate(chosen)):
                yield from extend([*chosen, i])

    return extend([])


def violations(part: DataFrame, variables: list[str], sigma: dict[frozenset[str], int]) -> DataFrame:
    """x, y, given, most: pairs X inside Y whose degree of Y given X exceeds 2 sigma(X) / sigma(Y); empty for a uniform part."""
    full = frozenset(variables)
    sigma = sigma | {full: 1}
    out = None
    for y in [frozenset(s) for s in subsets_in_order(variables)] + [full]:
        for x in [frozenset(s) for s in subsets_in_order(variables)]:
            if x < y and x in sigma and y in sigma:
                most = 2 * sigma[x] / sigma[y]
                d = degree(part, sorted(y - x), sorted(x)).agg(F.max("deg").alias("given")).select(F.lit(",".join(sorted(x))).alias("x"), F.lit(",".join(sorted(y))).alias("y"), "given", F.lit(float(most)).alias("most")).where("given > most")
                out = d if out is None else out.unionByName(d)
    return out


def heavy_candidates(df: DataFrame, keys: list[str], threshold: int, method: str = "exact", cells: int = 1 << 16) -> DataFrame:
    """Keys with more than threshold tuples, and their exact counts. "exact": partial counts, then the filter. "sketch": for keys too many to be
    counted each, tuples are counted by a hash of the key in ``cells`` cells first; a key can only be heavy in a heavy cell, so only these are counted
    by key. The cells' table is of fixed size, so it is broadcast."""
    if method == "sketch":
        cell = F.pmod(F.xxhash64(*keys), F.lit(cells))
        full = df.groupBy(cell.alias("__cell")).agg(F.count("*").alias("__n")).where(F.col("__n") > threshold).select("__cell")
        df = df.withColumn("__cell", cell).join(F.broadcast(full), "__cell", "left_semi").drop("__cell")
    return df.groupBy(*keys).agg(F.count("*").alias("cnt")).where(F.col("cnt") > threshold)


def partition_check(df: DataFrame, tagged: DataFrame, variables: list[str]) -> dict[str, bool]:
    """Whether the parts are a partition: no tuple is lost or new, and none is in two parts."""
    here, there = df.select(*variables), tagged.select(*variables)
    return {"nothing is lost": here.exceptAll(there).isEmpty(), "nothing is new or twice": there.exceptAll(here).isEmpty()}
