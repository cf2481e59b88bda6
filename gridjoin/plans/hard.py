"""Instances that bounds are shown on: products, sparse products, lifted instances, and the worked triangle and bow-tie."""

from __future__ import annotations

from fractions import Fraction
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridjoin.functions.hypergraph import Edge, Hypergraph
from gridjoin.functions.measures import min_vertex_cover


def domains(h: Hypergraph, n: int) -> dict[str, int]:
    """n^v values of each variable, v its balanced vertex cover."""
    return {x: max(1, round(n ** float(v))) for x, v in min_vertex_cover(h).items()}


def _name(e: Edge) -> str:
    return "".join(sorted(e))


def density(h: Hypergraph) -> dict[str, str]:
    """Edges whose cover is more than one are sparse, the others dense."""
    v = min_vertex_cover(h)
    return {_name(e): "sparse" if sum((v[x] for x in e), Fraction(0)) > 1 else "dense" for e in h.edges}


def product_instance(spark: SparkSession, h: Hypergraph, sizes: dict[str, int]) -> dict[str, DataFrame]:
    """All tuples over domains of stated sizes."""
    return {_name(e): reduce(lambda a, b: a.crossJoin(b), [spark.range(sizes[x]).withColumnRenamed("id", x) for x in sorted(e)]) for e in h.edges}


def chances(h: Hypergraph, n: int) -> dict[str, float]:
    """The share of each edge's product that a sparse instance keeps."""
    v = min_vertex_cover(h)
    return {_name(e): min(1.0, n ** float(1 - sum((v[x] for x in e), Fraction(0)))) for e in h.edges}


def kept_by_rule(e: Edge, i: int, chance: float) -> str:
    """A condition that keeps about this share of an edge's product, in arithmetic that other engines repeat."""
    terms = " + ".join(f"{x} * {7_919 + 104_729 * (k + 1) + 31 * i}" for k, x in enumerate(sorted(e)))
    return f"(({terms}) % 15485863 * 48271 + {i}) % 2147483647 % 1000000 < {round(chance * 1_000_000)}"


def sparse_product_instance(spark: SparkSession, h: Hypergraph, n: int, seed: int = 7, exact: bool | str = False) -> dict[str, DataFrame]:
    """Edges of cover one are products; of others about n tuples stay. They are drawn, not filtered from the product, unless exact ("rule": filtered by
    kept_by_rule)."""
    sizes, v, out = domains(h, n), min_vertex_cover(h), {}
    for i, e in enumerate(h.edges):
        xs = sorted(e)
        whole = 1
        for x in xs:
            whole *= sizes[x]
        chance = min(1.0, n ** float(1 - sum((v[x] for x in e), Fraction(0))))
        if chance >= 1:
            out[_name(e)] = product_instance(spark, Hypergraph.of([e]), sizes)[_name(e)]
        elif exact == "rule":
            out[_name(e)] = product_instance(spark, Hypergraph.of([e]), sizes)[_name(e)].where(kept_by_rule(e, i, chance))
        elif exact:
            all_ = product_instance(spark, Hypergraph.of([e]), sizes)[_name(e)]
            out[_name(e)] = all_.where(F.pmod(F.xxhash64(F.lit(seed + i), *xs), F.lit(1 << 30)) < int(chance * (1 << 30)))
        else:
            # draws with replacement: as many as leave whole * chance distinct tuples on average
            from math import log1p

            draws = max(1, round(-whole * log1p(-chance)))
            ids = spark.range(draws).select(F.pmod(F.xxhash64(F.lit(seed + i), "id"), F.lit(whole)).alias("t"))
            step, cols = 1, []
            for x in xs:
                cols.append(F.expr(f"(t div {step}) % {sizes[x]}").alias(x))
                step *= sizes[x]
            out[_name(e)] = ids.distinct().select(*cols)
    return out


def lift_instance(frames: dict[frozenset[str], DataFrame], h: Hypergraph, s: frozenset[str]) -> dict[str, DataFrame]:
    """From an instance of the reduced induced hypergraph on s to one of h: other variables hold one constant, an edge
    that lost out in the reduction is the projection of one that holds it."""
    out = {}
    for e in h.edges:
        inside = e & s
        if inside:
            host = next(f for f in frames if inside <= f)
            df = frames[host].select(*sorted(inside)).distinct()
            for x in sorted(e - s):
                df = df.withColumn(x, F.lit(0).cast("long"))
        else:
            some = next(iter(frames.values()))
            df = some.sparkSession.range(1).select(*[F.lit(0).cast("long").alias(x) for x in sorted(e)])
        out[_name(e)] = df
    return out


def triangle_instance(spark: SparkSession, n: int, p: int) -> dict[str, DataFrame]:
    """x has p^(1/6) values beside all y and z in two relations; the third is a matching of y and z."""
    heavy = max(2, round(p ** (1 / 6)))
    side = max(1, n // heavy)
    return {
        "xy": spark.range(heavy).withColumnRenamed("id", "x").crossJoin(spark.range(side).withColumnRenamed("id", "y")),
        "yz": spark.range(n).select(F.expr(f"id % {side}").alias("y"), F.expr(f"(id * 7919 + id div {side}) % {side}").alias("z")).distinct(),
        "xz": spark.range(heavy).withColumnRenamed("id", "x").crossJoin(spark.range(side).withColumnRenamed("id", "z")),
    }


def bowtie_instance(spark: SparkSession, n: int, p: int) -> dict[str, DataFrame]:
    """The worked bow-tie as data: z is heavy in zw by few values and w in vw by some more, the other relations are light. The worked slack exponents ask
    for 1 / 25 of log p, which powers of two as degrees do not have at this size, so the least that they have takes their place: two values of z, four of w."""
    step = max(1, n // p)
    many = lambda a, b, k: spark.range(n).select((F.col("id") % (n // 4)).alias(a), ((F.col("id") * k + F.expr(f"id div {n // 4}")) % (n // 4)).alias(b)).distinct()
    few = lambda a, b, m: spark.range(n).select((F.col("id") % (n // m)).alias(a), F.expr(f"(id div {n // m}) * {step}").alias(b)).distinct()
    zw = spark.range(n).select(F.expr(f"(id div {n // 2}) * {step}").alias("z"), (F.col("id") % (n // 2)).alias("w"))
    return {"xy": many("x", "y", 3), "yz": many("y", "z", 5), "xz": many("x", "z", 7), "zv": many("z", "v", 11), "zw": zw, "vw": few("v", "w", 4)}


def bowtie_slack(variant: str = "printed") -> dict[tuple[str, frozenset[str]], Fraction]:
    """Slack exponents of the worked bow-tie; "repaired" gives the step sizes that three covers need. The exponents."""
    w = {"printed": Fraction(1, 5), "repaired": Fraction(3, 25)}[variant]
    return {("zw", frozenset("z")): Fraction(1, 25), ("vw", frozenset("w")): w}


def witness_check(outputs: DataFrame, received: dict[tuple[str, ...], DataFrame], cell: str) -> DataFrame:
    """Outputs of a cell that lack a projection among the tuples the cell received; empty for a tuple-based algorithm."""
    bad = None
    for vs, df in received.items():
        miss = outputs.join(df.select(cell, *vs), [cell, *vs], "left_anti")
        bad = miss if bad is None else bad.unionByName(miss)
    return bad
