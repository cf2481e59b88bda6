"""The algorithms that the cover-mix join is compared with."""

from __future__ import annotations

from fractions import Fraction
from functools import reduce
from itertools import combinations
from math import prod

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridjoin.functions.hypergraph import Hypergraph
from gridjoin.functions.measures import min_vertex_cover
from gridjoin.plans.combined import TASK
from gridjoin.plans.covermix import MAX_BROADCAST, empty_result
from gridjoin.plans.degrees import heavy_candidates
from gridjoin.plans.grid import CELL, Size, fitted_shares, grid_join, join_order, large, local_join, one_exchange, replicate, sizes, whole_everywhere
from gridjoin.plans.query import Atom, JoinQuery, natural_join, power_of_two
from gridjoin.plans.weights import integer_shares, joint_shares
from gridjoin.sources.tables import staged, staged_together


def cover_shares(h: Hypergraph, p: int) -> dict[str, int]:
    """Shares from the balanced minimum vertex cover, normalised to use p machines."""
    cover = min_vertex_cover(h)
    norm = sum(cover.values(), Fraction(0))
    return integer_shares({x: c / norm for x, c in cover.items()}, p) if norm else {}


def hypercube_join(query: JoinQuery, p: int, shares: str | dict[str, int] = "cover") -> DataFrame:
    """One round on data without skew. shares: "cover", "equal", or stated ones."""
    query = query.normalized()
    if len(query.atoms) == 1:
        return query.atoms[0].df.select(*query.variables)
    cover = shares == "cover"
    if shares == "equal":
        v = query.variables
        shares = integer_shares({x: Fraction(1, len(v)) for x in v}, p)
    frames = staged_together([a.df for a in query.atoms], "atom")
    known = sizes(frames)
    return sized_grid(frames, p, known) if cover else grid_join(frames, shares, sizes=known)


def sized_grid(frames: list[DataFrame], p: int, known: list[Size]) -> DataFrame:
    """A grid with the shares of a vertex cover of the relations that are not small enough to go to every machine; where all have to be parted and are large, a cover for
    relations of one size would copy some of them in vain, so shares are fitted to the sizes."""
    whole = whole_everywhere(known, p)
    rest = {frozenset(f.columns): known[i].rows for i, f in enumerate(frames) if i not in whole}
    shares = joint_shares(rest, p) if whole else fitted_shares(known, p, sorted(set().union(*rest))) if large(known) else cover_shares(Hypergraph.of(rest), p)
    return grid_join(frames, shares, sizes=known, whole=whole)


def written(query: JoinQuery) -> JoinQuery:
    """The query with its relations as written tables, for methods that read each of them many times."""
    frames = staged_together([a.df for a in query.atoms], "atom")
    return JoinQuery([a.with_frame(df) for a, df in zip(query.atoms, frames, strict=True)])


def cascade_join(query: JoinQuery, hint: str | None = None) -> DataFrame:
    """Pairwise joins as Catalyst plans them."""
    query = query.normalized()
    frames = join_order([a.df for a in query.atoms])
    return reduce(lambda a, b: natural_join(a, b, hint), frames).select(*query.variables)


def cascade_count(query: JoinQuery, by: tuple[str, ...]) -> DataFrame:
    """by, cnt: how many results of the join each value of ``by`` has. Pairwise joins; a variable that only two relations hold and that ``by`` leaves out goes as
    soon as these are joined, and the tuples left carry how many they stand for, so no later join moves them one by one. That is done while it makes a
    schema that no relation has already; of such variables the one with the smallest join by counts is first. Relations are written once, as their sizes are asked."""
    query = query.normalized()
    if _inner(dict(zip(map(id, query.atoms), (set(a.vars) for a in query.atoms), strict=True)), by) is None:
        return cascade_join(query).groupBy(*by).agg(F.count("*").alias("cnt"))
    spark = query.atoms[0].df.sparkSession
    # each before the next, and what it shuffled may go before the next begins
    frames, sizes = {}, {}
    for a in query.atoms:
        frames[a.name] = staged(a.df, "atom")
        spark.sparkContext._jvm.System.gc()
        r = frames[a.name].agg(F.count("*").alias("__n"), *[F.approx_count_distinct(v).alias(v) for v in a.vars]).first()
        sizes[a.name] = r.asDict()
    while (able := _inner({k: set(f.columns) - {CNT} for k, f in frames.items()}, by)) is not None:

        def expected(x: tuple[str, str, str]) -> float:
            v, r, s = x
            return sizes[r]["__n"] * sizes[s]["__n"] / max(1, sizes[r][v], sizes[s][v])

        v, r, s = min(able, key=lambda x: (expected(x), x))
        left = sorted((set(frames[r].columns) | set(frames[s].columns)) - {v, CNT})
        a, b = (f if CNT in f.columns else f.withColumn(CNT, F.lit(1).cast("long")) for f in (frames[r], frames[s]))
        shared = [c for c in a.columns if c in b.columns and c != CNT]
        joined = a.join(b.withColumnRenamed(CNT, "__more"), shared).groupBy(*left).agg(F.sum(F.col(CNT) * F.col("__more")).alias(CNT))
        name = f"{r}*{s}"
        most = 1
        for x in left:
            most *= max(sizes[r].get(x, 0), sizes[s].get(x, 0), 1)
        sizes[name] = {x: max(sizes[r].get(x, 0), sizes[s].get(x, 0)) for x in left} | {"__n": min(most, expected((v, r, s)))}
        frames = {k: f for k, f in frames.items() if k not in (r, s)} | {name: joined}
    counts = [f.withColumnRenamed(CNT, f"{CNT}{i}") if CNT in f.columns else f for i, f in enumerate(frames.values())]
    carried = [c for f in counts for c in f.columns if c.startswith(CNT)]
    joined = reduce(natural_join, join_order(counts))
    return joined.groupBy(*by).agg(F.sum(reduce(lambda x, y: x * y, map(F.col, carried))).alias("cnt"))


CNT = "__cnt"


def _inner(schemas: dict, by: tuple[str, ...]) -> list[tuple] | None:
    """variable, relation, relation: variables outside ``by`` that two relations hold, whose join without it has a schema that no other relation covers."""
    out = []
    for v in sorted(set().union(*schemas.values()) - set(by)):
        having = [k for k, s in schemas.items() if v in s]
        if len(schemas) > 2 and len(having) == 2:
            left = schemas[having[0]] | schemas[having[1]]
            if not any(left - {v} <= s for k, s in schemas.items() if k not in having):
                out.append((v, *having))
    return out or None


def acyclic_join(query: JoinQuery) -> DataFrame:
    """Full reducer: semi-joins up and down the join tree, then joins; no intermediate has a tuple that no result has."""
    query = query.normalized()
    tree = query.hypergraph.join_tree()
    if tree is None:
        raise ValueError("the query has a cycle")
    frames = {frozenset(a.vars): a.df for a in query.atoms}
    shared = lambda a, b: sorted(a & b)
    for e, parent in tree:
        if parent is not None:
            frames[parent] = frames[parent].join(frames[e].select(*shared(e, parent)).distinct(), shared(e, parent), "left_semi")
    for e, parent in reversed(tree):
        if parent is not None:
            frames[e] = frames[e].join(frames[parent].select(*shared(e, parent)).distinct(), shared(e, parent), "left_semi")
    out = None
    for e, _ in reversed(tree):
        out = frames[e] if out is None else natural_join(out, frames[e])
    return out.select(*query.variables)


def heavy_values(query: JoinQuery, threshold: int) -> dict[str, DataFrame]:
    """Values of each variable that more than threshold tuples of some relation have; fewer than relations * n / threshold rows."""
    out = {}
    for v in query.variables:
        parts = [heavy_candidates(a.df, [v], threshold).select(v) for a in query.atoms if v in a.vars]
        rows = reduce(DataFrame.unionByName, parts).distinct().collect()
        if rows:
            out[v] = query.atoms[0].df.sparkSession.createDataFrame(rows, parts[0].schema)
    return out


def by_pattern(query: JoinQuery, heavy: dict[str, DataFrame]) -> dict[frozenset[str], list[Atom]]:
    """For each set of heavy variables the tuples that are heavy in just these; a broadcast of bounded size tags them."""
    tagged = {}
    for a in query.atoms:
        df = a.df
        for v in a.vars:
            if v in heavy:
                df = df.join(F.broadcast(heavy[v].withColumn(f"__h_{v}", F.lit(True))), v, "left").withColumn(f"__h_{v}", F.coalesce(f"__h_{v}", F.lit(False)))
        tagged[a.name] = df
    out = {}
    names = sorted(heavy)
    for k in range(len(names) + 1):
        for pattern in map(frozenset, combinations(names, k)):
            atoms = []
            for a in query.atoms:
                df = tagged[a.name]
                for v in a.vars:
                    if v in heavy:
                        df = df.where(F.col(f"__h_{v}") if v in pattern else ~F.col(f"__h_{v}"))
                atoms.append(Atom(a.name, df.select(*a.vars)))
            out[pattern] = atoms
    met = _met(tagged, query, names)
    return {p: atoms for p, atoms in out.items() if p in met}


def _met(tagged: dict[str, DataFrame], query: JoinQuery, names: list[str]) -> set[frozenset[str]]:
    """The patterns in which no relation is empty: one count of each relation's flags, at most two to the number of its heavy variables rows each."""
    jobs = []
    for a in query.atoms:
        mine = [v for v in names if v in a.vars]
        jobs.append(tagged[a.name].groupBy(F.concat_ws(",", F.lit(""), *[F.when(F.col(f"__h_{v}"), v) for v in mine]).alias("__heavy")).count().select(F.lit(a.name).alias("__atom"), "__heavy"))
    found = {(r["__atom"], frozenset(x for x in r["__heavy"].split(",") if x)) for r in reduce(DataFrame.unionAll, jobs).collect()}
    every = [frozenset(p) for k in range(len(names) + 1) for p in combinations(names, k)]
    return {p for p in every if all((a.name, p & frozenset(a.vars)) in found for a in query.atoms)}


def one_round_skew_join(query: JoinQuery, p: int, threshold: int | None = None) -> DataFrame:
    """One round on any data: each pattern of heavy variables is a query of its own, with shares for the light ones; the patterns share the machines."""
    query = written(query.normalized())
    n = max(query.counts().values(), default=0)
    patterns = by_pattern(query, heavy_values(query, threshold or max(1, (1 << power_of_two(n)) // p)))
    results, known = [], sizes([a.df for a in query.atoms])
    for pattern, atoms in patterns.items():
        light = query.hypergraph.induced(set(query.variables) - pattern)
        shares = cover_shares(light, p) if light.edges else {}
        # the relations' sizes bound those of their parts
        results.append(grid_join([a.df for a in atoms], shares, sizes=known))
    return reduce(DataFrame.unionByName, results).select(*query.variables) if results else empty_result(query)


def dedicated_heavy_join(query: JoinQuery, p: int, threshold: int | None = None) -> DataFrame:
    """Each assignment of the heavy variables owns a block of machines: relations are cut down to it, then a grid of the rest runs in the block. The
    cells of all blocks are spread over at most p tasks (or as many as the session's shuffles have)."""
    query = written(query.normalized())
    n = max(query.counts().values(), default=0)
    patterns = by_pattern(query, heavy_values(query, threshold or max(1, (1 << power_of_two(n)) // p)))
    spark = query.atoms[0].df.sparkSession
    one_exchange(spark)
    results = []
    for pattern, atoms in patterns.items():
        if not pattern:
            # the relations' sizes bound those of their light tuples
            results.append(sized_grid([a.df for a in atoms], p, sizes([a.df for a in query.atoms])))
            continue
        pieces = [a.df.select(*sorted(set(a.vars) & pattern)).distinct() for a in atoms if set(a.vars) & pattern]
        # numbered as they are written
        listed = staged(reduce(natural_join, sorted(pieces, key=lambda d: len(d.columns))).withColumn("__block", F.monotonically_increasing_id()), "blocks")
        count = listed.count()
        if not count:
            continue
        small = F.broadcast if count <= MAX_BROADCAST else (lambda d: d)
        light = query.hypergraph.induced(set(query.variables) - pattern)
        shares = {v: 1 for v in query.variables} | (cover_shares(light, max(1, p // count)) if light.edges else {})
        tasks = min(prod(shares.values()) * count, max(p, int(spark.conf.get("spark.sql.shuffle.partitions"))))
        frames = []
        for a in atoms:
            mine = [v for v in a.vars if v in pattern]
            # a relation without a heavy variable goes to every block, as the method has it
            df = a.df.join(small(listed.select("__block", *mine).distinct()), mine) if mine else a.df.crossJoin(small(listed.select("__block")))
            df = replicate(df, query.variables, shares).withColumn(TASK, F.pmod(F.xxhash64("__block", CELL), F.lit(tasks)).cast("int"))
            frames.append(df.repartitionById(tasks, F.col(TASK)))
        results.append(local_join(frames).select(*query.variables))
    return reduce(DataFrame.unionByName, results).select(*query.variables) if results else empty_result(query)


def triangle_two_case_join(query: JoinQuery, p: int) -> DataFrame:
    """Triangle: a heavy value of one variable is joined by semi-joins around the opposite relation, light ones in a grid."""
    query = query.normalized()
    if len(query.atoms) != 3 or sorted(len(a.vars) for a in query.atoms) != [2, 2, 2] or len(query.variables) != 3:
        raise ValueError("not a triangle")
    n = max(query.counts().values(), default=0)
    heavy = heavy_values(query, max(1, (1 << power_of_two(n)) // p))
    results, atoms = [], list(query.atoms)
    for v, values in sorted(heavy.items()):
        opposite = next(a for a in atoms if v not in a.vars)
        beside = [a for a in atoms if v in a.vars]
        small = F.broadcast(values)
        part = opposite.df.crossJoin(small)
        for a in beside:
            part = part.join(a.df.join(small, v, "left_semi"), list(a.vars), "left_semi")
        results.append(part.select(*query.variables))
        atoms = [a if v not in a.vars else a.with_frame(a.df.join(small, v, "left_anti")) for a in atoms]
    results.append(grid_join([a.df for a in atoms], cover_shares(query.hypergraph, p)))
    return reduce(DataFrame.unionByName, results).select(*query.variables)
