"""The grid shuffle: cells are points of a grid with one axis for each variable; a tuple goes to all cells that agree with its coordinates.

Each cell is one reduce task (repartitionById), every frame is shuffled once, and joins on (cell, shared variables) add no exchange while
spark.sql.requireAllClusterKeysForCoPartition is false, which is set here. It is a runtime setting, and it only lets Spark keep an existing partitioning.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from itertools import combinations, combinations_with_replacement
from math import ceil, inf, prod

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from gridjoin.functions.hypergraph import Hypergraph

CELL = "__cell"
#: Rows up to which relations are hashed in a cell, all of them together: a cell has no tuple twice, so these maps fit a task's memory however the cells fall.
MAX_HASHED = 1_000_000
#: Relations up to which all orders of joins are compared.
MAX_ORDERED = 10
#: Rows up to which relations go to every machine as a whole, all of them together; joins of them alone, too.
MAX_WHOLE = 1_000_000


@dataclass(frozen=True)
class Size:
    """Tuples of a relation and about how many values each variable has; ``bound`` where a frame has no more tuples than that."""

    rows: float
    values: dict[str, float]
    bound: bool = True

    def distinct(self, variables: list[str]) -> float:
        return min(self.rows, prod(max(1.0, self.values[v]) for v in variables))

    def joined(self, other: Size) -> Size:
        shared = [v for v in self.values if v in other.values]
        rows = self.rows * other.rows / max(1.0, self.distinct(shared), other.distinct(shared))
        values = {v: min(s.values[v] for s in (self, other) if v in s.values) for v in self.values | other.values}
        return Size(rows, values, False)


def sizes(frames: list[DataFrame]) -> list[Size]:
    """The frames' sizes, in one job that keeps no values; they should be written tables, as each is read."""
    names = sorted({c for f in frames for c in f.columns})
    parts = [f.agg(F.lit(i).alias("__frame"), F.count("*").alias("__rows"), *[(F.approx_count_distinct(v) if v in f.columns else F.lit(None).cast("long")).alias(v) for v in names]) for i, f in enumerate(frames)]
    out = {r["__frame"]: Size(r["__rows"], {v: r[v] for v in frames[r["__frame"]].columns}) for r in reduce(DataFrame.unionAll, parts).collect()}
    return [out[i] for i in range(len(frames))]


def whole_everywhere(sizes: list[Size], p: int) -> frozenset[int]:
    """Places of the relations that each machine gets whole: those that have no more tuples together than a machine's part of the largest relation, which then stay out
    of the grid, so the others are not copied along their variables. None where all are small, or where the others would fall apart."""
    largest = int(max((s.rows for s in sizes), default=0))
    if largest <= MAX_HASHED or len(sizes) > MAX_ORDERED:
        return frozenset()
    room, out = min(MAX_WHOLE, (1 << (largest - 1).bit_length()) // p), set()
    for i in sorted(range(len(sizes)), key=lambda i: sizes[i].rows):
        if sizes[i].bound and sizes[i].rows <= room:
            room -= int(sizes[i].rows)
            out.add(i)
    rest = Hypergraph.of(s.values for i, s in enumerate(sizes) if i not in out)
    return frozenset(out) if len(rest.components()) == 1 else frozenset()


def large(sizes: list[Size]) -> bool:
    """Whether shares follow sizes: some relation may not fit a task's memory."""
    return max((s.rows for s in sizes), default=0) > MAX_HASHED


def cell_load(sizes: list[Size], shares: dict[str, int]) -> float:
    """Expected tuples in the fullest cell. An axis parts a relation no further than the variable's values can be dealt evenly: three values on two coordinates leave two thirds on one."""
    parts = lambda values, share: max(1.0, values) / ceil(max(1.0, values) / share)
    return sum(s.rows / prod(parts(n, shares.get(v, 1)) for v, n in s.values.items()) for s in sizes)


def fitted_shares(sizes: list[Size], p: int, able: list[str]) -> dict[str, int]:
    """Shares for relations of these sizes, powers of two on the axes in ``able`` that multiply to p (rounded down to one): those with the least load of a cell and, of equal
    ones, with the fewest tuples sent."""
    best = None
    for axes in combinations_with_replacement(sorted(able), p.bit_length() - 1):
        shares = {v: 1 << axes.count(v) for v in able}
        cost = cell_load(sizes, shares), sum(s.rows * prod(k for v, k in shares.items() if v not in s.values) for s in sizes)
        if best is None or cost < best[0]:
            best = cost, shares
    return best[1] if best else {}


def coordinate(value: Column, share: int, seed: int, hash: str = "xx") -> Column:
    """hash: "xx" for any type; "portable" for integers, in arithmetic that other engines repeat."""
    if share == 1:
        return F.lit(0)
    if hash == "portable":
        return F.pmod(F.pmod(value, F.lit(1_000_003)) * F.lit(7_919 + 2 * seed) + F.lit(104_729 * (seed + 1)), F.lit(15_485_863)) % share
    return F.pmod(F.xxhash64(F.lit(seed), value), F.lit(share))


def replicate(df: DataFrame, variables: list[str], shares: dict[str, int], hash: str = "xx") -> DataFrame:
    """df with its cells: fixed coordinates for the frame's variables, every value of the others. ``variables`` is the order of the axes."""
    step, base, free = 1, F.lit(0), [0]
    for seed, v in enumerate(variables):
        if v in df.columns:
            base = base + coordinate(F.col(v), shares[v], seed, hash) * step
        else:
            free = [f + step * k for f in free for k in range(shares[v])]
        step *= shares[v]
    base = base.cast("int")
    if len(free) == 1:
        return df.withColumn(CELL, base)
    return df.withColumn(CELL, F.explode(F.transform(F.array(*[F.lit(f) for f in free]), lambda f: f + base)))


def to_cells(df: DataFrame, cells: int) -> DataFrame:
    """One task for each cell."""
    return df.repartitionById(cells, F.col(CELL))


def one_exchange(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")


def placed(frames: list[DataFrame], shares: dict[str, int], hash: str = "xx") -> list[DataFrame]:
    variables = sorted(shares)
    cells = prod(shares.values())
    return [to_cells(replicate(f, variables, shares, hash), cells) for f in frames]


def join_order(frames: list[DataFrame]) -> list[DataFrame]:
    """Each frame after one that it shares most variables with, so that joins stay equi-joins where they can."""
    left, out = list(frames[1:]), [frames[0]]
    seen = set(frames[0].columns)
    while left:
        nxt = max(left, key=lambda f: (len(seen & set(f.columns)), -len(f.columns)))
        left.remove(nxt)
        out.append(nxt)
        seen |= set(nxt.columns)
    return out


def local_join(frames: list[DataFrame], hint: str | None = "merge") -> DataFrame:
    """Joins inside the cells. A cell may be larger than a task's memory, so frames are sorted, which spills, and not hashed, which fails. The cell is the
    last key: sorts compare by the first one, and a task has few cells."""
    frames = join_order(frames)
    out = frames[0]
    for f in frames[1:]:
        shared = sorted((c for c in out.columns if c in f.columns), key=lambda c: c == CELL)
        out = out.join(f.hint(hint) if hint else f, shared)
    return out


def join_tree(sizes: list[Size], whole: frozenset[int] = frozenset()) -> int | tuple:
    """The order of pairwise joins, as a tree over places in ``sizes``, with the fewest expected tuples between the joins; both sides of a join may be joins, but those
    of relations in ``whole`` alone have to stay small and to share variables."""
    every = range(len(sizes))
    best: dict[frozenset[int], tuple[float, int | tuple, Size]] = {frozenset([i]): (0.0, i, s) for i, s in enumerate(sizes)}
    for k in range(2, len(sizes) + 1):
        for group in map(frozenset, combinations(every, k)):
            first, found = min(group), None
            for j in range(k - 1):
                for rest in combinations(sorted(group - {first}), j):
                    a = frozenset([first, *rest])
                    (x, left, m), (y, right, n) = best[a], best[group - a]
                    size = m.joined(n)
                    # of equal ones, that with the least to sort
                    cost = (x + y + size.rows, m.rows + n.rows)
                    if group <= whole and (size.rows > MAX_WHOLE or m.values.keys().isdisjoint(n.values)):
                        cost = (inf, inf)
                    if found is None or cost < found[0]:
                        found = cost, (left, right), size
            best[group] = found[0][0], found[1], found[2]
    return best[frozenset(every)][1]


def sized_join(frames: list[DataFrame], sizes: list[Size], whole: frozenset[int] = frozenset()) -> DataFrame:
    """local_join in the order of join_tree. Relations that are small as a whole are hashed, so what meets them is not sorted; all others are merged. Those in
    ``whole`` have no cells and are broadcast."""
    room, hashed = MAX_HASHED, set()
    for i in sorted(range(len(sizes)), key=lambda i: sizes[i].rows):
        if i not in whole and sizes[i].bound and sizes[i].rows <= room:
            room -= int(sizes[i].rows)
            hashed.add(i)

    def everywhere(tree: int | tuple) -> bool:
        return tree in whole if isinstance(tree, int) else all(map(everywhere, tree))

    def build(tree: int | tuple) -> DataFrame:
        if isinstance(tree, int):
            return frames[tree]
        left, right = sorted(tree, key=lambda t: (everywhere(t), t in hashed, isinstance(t, int)))
        a, b = build(left), build(right)
        shared = sorted((c for c in a.columns if c in b.columns), key=lambda c: c == CELL)
        if everywhere(right):
            return a.join(F.broadcast(b), shared) if shared else a.crossJoin(F.broadcast(b))
        return a.join(b.hint("shuffle_hash" if right in hashed else "merge"), shared)

    return build(join_tree(sizes, whole))


def _attribute_at_a_time(tables: list[pa.Table], order: list[str]) -> pa.Table:
    """Join of one cell, a variable at a time: the values that all tables with it still allow, by intersecting sorted columns."""
    frames = [{c: t.column(c).to_numpy(zero_copy_only=False) for c in t.column_names} for t in tables]
    rows = [np.arange(t.num_rows) for t in tables]
    out: list[tuple] = []

    def extend(depth: int, chosen: list, live: list[np.ndarray]) -> None:
        if depth == len(order):
            out.append(tuple(chosen))
            return
        v = order[depth]
        having = [i for i, f in enumerate(frames) if v in f]
        values = None
        for i in sorted(having, key=lambda i: len(live[i])):
            mine = np.unique(frames[i][v][live[i]])
            values = mine if values is None else np.intersect1d(values, mine, assume_unique=True)
            if not len(values):
                return
        for x in values:
            extend(depth + 1, [*chosen, x], [live[i][frames[i][v][live[i]] == x] if i in having else live[i] for i in range(len(frames))])

    extend(0, [], rows)
    names = {f: t.schema.field(f) for t in tables for f in t.column_names}
    return pa.Table.from_arrays([pa.array([r[k] for r in out], names[v].type) for k, v in enumerate(order)], names=order)


def generic_join(frames: list[DataFrame], shares: dict[str, int]) -> DataFrame:
    """The local join attribute by attribute, which is worst-case optimal in memory: cells are grouped in Arrow."""
    variables = sorted(shares)
    spark = frames[0].sparkSession
    kinds = {f.name: f.dataType.simpleString() for d in frames for f in d.schema}
    tagged = None
    for k, f in enumerate(frames):
        row = replicate(f, variables, shares).select(F.lit(k).alias("__atom"), CELL, *[F.col(v) if v in f.columns else F.lit(None).cast(kinds[v]).alias(v) for v in variables])
        tagged = row if tagged is None else tagged.unionByName(row)
    schema = ", ".join(f"`{v}` {kinds[v]}" for v in variables)
    have = [[v for v in variables if v in f.columns] for f in frames]
    arrow = to_arrow_schema(spark.createDataFrame([], schema).schema)

    def run(t: pa.Table) -> pa.Table:
        atom = t.column("__atom").to_numpy()
        tables = [t.filter(pa.array(atom == k)).select(cols) for k, cols in enumerate(have)]
        if any(not x.num_rows for x in tables):
            return arrow.empty_table()
        return _attribute_at_a_time(tables, variables).cast(arrow)

    return tagged.groupBy(CELL).applyInArrow(run, schema)


def grid_join(frames: list[DataFrame], shares: dict[str, int], local: str = "catalyst", hash: str = "xx", sizes: list[Size] | None = None, whole: frozenset[int] = frozenset()) -> DataFrame:
    """Natural join of frames in one grid; every result is made in exactly one cell. sizes: of the frames, if known, for the order of the joins in a cell. whole: places
    of frames that are broadcast and not placed, for shares that leave out the variables of these alone."""
    variables = sorted({c for f in frames for c in f.columns})
    shares = {v: shares.get(v, 1) for v in variables}
    one_exchange(frames[0].sparkSession)
    if local == "generic":
        return generic_join(frames, shares)
    if len(frames) == 1:
        return frames[0].select(*variables)
    if whole:
        apart = {i: f for i, f in enumerate(frames) if i not in whole}
        held = {c for f in apart.values() for c in f.columns}
        # a single frame meets the others where it lies
        cells = placed(list(apart.values()), {v: s for v, s in shares.items() if v in held}, hash) if len(apart) > 1 else list(apart.values())
        at = dict(zip(apart, cells, strict=True))
        return sized_join([at.get(i, f) for i, f in enumerate(frames)], sizes, whole).select(*variables)
    inside = placed(frames, shares, hash)
    return (local_join(inside) if sizes is None or len(sizes) > MAX_ORDERED else sized_join(inside, sizes)).select(*variables)


def grid_precondition(df: DataFrame, shares: dict[str, int], n: int) -> bool:
    """Whether each subset of the frame's variables has degrees of at most n / its shares."""
    from .degrees import subsets_in_order

    for u in subsets_in_order(df.columns):
        top = df.groupBy(*u).count().agg(F.max("count")).first()[0] or 0
        if top > n / prod(shares[v] for v in u):
            return False
    return True
