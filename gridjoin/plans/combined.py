"""All combinations of parts in one plan.

Combinations with the same weights, heavy sets and guards are run together as a block: for each relation a set of parts, so that the block's combinations
are all choices from these sets. Degree bounds of a union of parts are sums over its parts, which are polylogarithmically many, so loads keep their
exponent, while a tuple goes to each block once and not to each combination.

Blocks that join the same heavy sets and use the same guards form a shape. A shape is planned once, however many blocks it has: tuples meet a small table
on their part, carry the block from there on, and one grid has the cells of all blocks. How many shapes there are hangs on the query alone;
the number of blocks also on the data.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable
from dataclasses import dataclass
from functools import reduce
from itertools import product
from math import prod
from typing import TYPE_CHECKING

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .grid import CELL, local_join, one_exchange

if TYPE_CHECKING:
    from .covermix import Combo, Plan

PART, BLOCK, TASK = "__part", "__block", "__task"
#: Combinations looked at, at most, to make a block larger.
LOOK = 1 << 14
HeavySet = tuple[frozenset[str], str]


@dataclass(frozen=True)
class Shape:
    heavy_sets: tuple[HeavySet, ...]
    guards: tuple[tuple[str, str], ...]


def covering(sets: Iterable[HeavySet], wanted: frozenset[str] | None = None) -> tuple[HeavySet, ...]:
    """A few heavy sets that hold all variables in ``wanted`` (without it: all that any of them holds). The degree bound of their join holds for any such choice."""
    sets = sorted(sets, key=lambda x: (sorted(x[0]), x[1]))
    left = set().union(*(u for u, _ in sets)) if wanted is None else set(wanted)
    out: list[HeavySet] = []
    while left:
        best = max(sets, key=lambda x: (len(x[0] & left), -len(x[0])))
        if not best[0] & left:
            raise ValueError(f"no heavy set holds {sorted(left)}")
        out.append(best)
        left -= best[0]
    return tuple(sorted(out, key=lambda x: (sorted(x[0]), x[1])))


@dataclass
class Block:
    """Combinations that run together: the plan of one of them, which all share, and the parts of each relation."""

    combo: Combo
    parts: dict[str, tuple[int, ...]]


def blocks(plan: Plan) -> list[Block]:
    """Every combination of the plan in just one block. Combinations that were left out as they have no result may be in any."""
    names = sorted(plan.ids)
    place = {tuple(plan.ids[r][c.parts[r]] for r in names): c for c in plan.combos}
    same: dict[tuple, set[tuple[int, ...]]] = defaultdict(set)
    for at, c in place.items():
        same[tuple(sorted(c.mix.weights.items())), tuple(c.mix.heavy_sets), tuple(sorted(c.guards.items()))].add(at)
    out = []
    for left in same.values():
        while left:
            start = min(left)
            sets = [[i] for i in start]
            for k, r in enumerate(names):
                for i in range(len(plan.ids[r])):
                    if i != start[k] and prod(map(len, sets)) <= LOOK:
                        more = list(product(*([i] if j == k else x for j, x in enumerate(sets))))
                        if all(m in left or m not in place for m in more) and any(m in left for m in more):
                            sets[k].append(i)
            left -= set(product(*sets))
            out.append(Block(place[start], {r: tuple(sorted(x)) for r, x in zip(names, sets, strict=True)}))
    return out


def shapes(found: list[Block]) -> dict[Shape, list[int]]:
    out: dict[Shape, list[int]] = defaultdict(list)
    for i, b in enumerate(found):
        out[Shape(covering(b.combo.mix.heavy_sets), tuple(sorted(b.combo.guards.items())))].append(i)
    return dict(out)


class Tables:
    """The frames that the shapes of a plan share."""

    def __init__(self, plan: Plan, most: int):
        self.plan, self.most = plan, most
        self.spark = plan.query.atoms[0].df.sparkSession
        self.vars = {a.name: a.vars for a in plan.query.atoms}
        self.blocks = blocks(plan)
        self.first = [0]
        for b in self.blocks:
            self.first.append(self.first[-1] + b.combo.machines)

    @property
    def cells(self) -> int:
        return self.first[-1]

    def tasks(self) -> int:
        """Cells of many blocks share tasks: no more than p, or than the session's shuffles have."""
        return min(self.cells, max(self.plan.p, int(self.spark.conf.get("spark.sql.shuffle.partitions"))))

    def own(self, r: str, members: list[int]) -> DataFrame:
        """A relation's tuples, in each block that has their part."""
        rows = [(part, i) for i in members for part in self.blocks[i].parts[r]]
        listed = self.spark.createDataFrame(rows, f"{PART} int, {BLOCK} int")
        return self.plan.parted[r].join(F.broadcast(listed), PART).select(BLOCK, *self.vars[r])

    def small(self, df: DataFrame, bound: float) -> DataFrame:
        return F.broadcast(df) if bound <= self.most else df

    def heavy_relation(self, members: list[int], sets: Iterable[HeavySet]) -> DataFrame:
        """The heavy values of each block: its parts' projections joined. A part has at most 2p values of a heavy set."""
        out = None
        for u, r in sets:
            values = self.own(r, members).select(BLOCK, *sorted(u)).distinct()
            values = self.small(values, 2 * self.plan.p * sum(len(self.blocks[i].parts[r]) for i in members))
            out = values if out is None else out.join(values, [BLOCK, *(x for x in sorted(u) if x in out.columns)])
        return out

    def placed(self, frame: DataFrame, members: list[int]) -> DataFrame:
        """A frame's tuples at all cells of their block that agree with them."""
        order = self.plan.query.variables
        have = [v for v in order if v in frame.columns]
        rows = []
        for i in members:
            shares, step, steps, free = self.blocks[i].combo.shares, 1, {}, [0]
            for v in order:
                share = shares.get(v, 1)
                if v in have:
                    steps[v] = step
                else:
                    free = [f + step * k for f in free for k in range(share)]
                step *= share
            rows.append((i, self.first[i], free, [shares.get(v, 1) for v in have], [steps[v] for v in have]))
        grids = self.spark.createDataFrame(rows, f"{BLOCK} int, __first int, __free array<int>, __shares array<int>, __steps array<int>")
        at: Column = F.col("__first")
        for k, v in enumerate(have):
            at = at + F.pmod(F.xxhash64(F.lit(order.index(v)), F.col(v)), F.col("__shares")[k].cast("long")).cast("int") * F.col("__steps")[k]
        frame = frame.join(F.broadcast(grids), BLOCK).withColumn("__at", at).select(*have, "__at", F.explode("__free").alias("__f"))
        frame = frame.select(*have, (F.col("__at") + F.col("__f")).alias(CELL)).withColumn(TASK, F.col(CELL) % self.tasks())
        return frame.repartitionById(self.tasks(), F.col(TASK))


def intermediates(t: Tables, shape: Shape, members: list[int], heavy: str = "global", self_guard: str = "join") -> list[DataFrame]:
    """The frames that the grid joins, for all blocks of a shape. Options as for one combination."""
    H = frozenset().union(*(u for u, _ in shape.heavy_sets))
    bound = sum(prod(len(t.blocks[i].parts[r]) for r in {r for _, r in shape.heavy_sets}) * 2 ** len(H) * t.plan.p ** float(sum((t.blocks[i].combo.mix.exponents[x] for x in H), t.blocks[i].combo.mix.delta * 0)) for i in members)
    own = {r: t.own(r, members) for r in t.vars}

    def filtered(rel: DataFrame) -> DataFrame:
        for r, vs in t.vars.items():
            if set(vs) <= H:
                keys = [BLOCK, *vs]
                rel = rel.join(own[r].join(t.small(rel.select(*keys).distinct(), bound), keys, "left_semi"), keys, "left_semi")
        return rel

    whole = filtered(t.heavy_relation(members, shape.heavy_sets)) if H and heavy == "global" else None
    groups: dict[str, list[str]] = defaultdict(list)
    for r, s in shape.guards:
        groups[s].append(r)
    out, done = [], False
    for s, guarded in groups.items():
        frame = own[s]
        touch = H & frozenset(t.vars[s]).union(*(t.vars[r] for r in guarded))
        direct = self_guard == "direct" and guarded == [s]
        if H and not direct and (touch or heavy == "global"):
            mine = whole if heavy == "global" else t.heavy_relation(members, covering(shape.heavy_sets, touch))
            frame = frame.join(t.small(mine, bound), [BLOCK, *(v for v in t.vars[s] if v in mine.columns)])
            done = done or heavy == "global"
        for r in guarded:
            if r != s:
                frame = frame.join(own[r], [BLOCK, *t.vars[r]], "left_semi")
        out.append(frame)
    if H and heavy == "global" and not done:
        out.append(whole)
    if H and heavy != "global":
        for r, vs in t.vars.items():
            if set(vs) <= H:
                out.append(t.heavy_relation(members, covering(shape.heavy_sets, frozenset(vs))).join(own[r], [BLOCK, *vs], "left_semi"))
    return out


def run(plan: Plan, most: int, heavy: str = "global", self_guard: str = "join") -> DataFrame:
    """The union of all combinations' results; parts are disjoint, so it has no duplicates."""
    t = Tables(plan, most)
    one_exchange(t.spark)
    results = []
    for shape, members in shapes(t.blocks).items():
        frames = intermediates(t, shape, members, heavy, self_guard)
        joined = local_join([t.placed(f, members) for f in frames]) if len(frames) > 1 else frames[0]
        results.append(joined.select(*plan.query.variables))
    return reduce(DataFrame.unionByName, results)


def product_in_grid(results: list[DataFrame], p: int, most: int, stage) -> DataFrame:
    """The product of results without common variables. Results of at most ``most`` rows are broadcast; others meet in a grid with an axis for each, where a
    row has its own coordinate on its axis and is sent to all coordinates of the others."""
    staged = [stage(r) for r in results]
    sizes = [r.count() for r in staged]
    largest = max(range(len(staged)), key=lambda i: sizes[i])
    wide = [i for i in range(len(staged)) if i == largest or sizes[i] > most]
    # shares by size, p of them in all
    shares = dict.fromkeys(wide, 1)
    while len(wide) > 1 and prod(shares.values()) * 2 <= p:
        shares[max(wide, key=lambda i: sizes[i] / shares[i])] *= 2
    cells, step, placed = prod(shares.values()), 1, []
    for i in wide:
        others = [0]
        inner = 1
        for j in wide:
            if j != i:
                others = [o + inner * k for o in others for k in range(shares[j])]
            inner *= shares[j]
        own = F.pmod(F.xxhash64(*staged[i].columns), F.lit(shares[i])).cast("int") * step
        placed.append(staged[i].withColumn(CELL, F.explode(F.transform(F.array(*map(F.lit, others)), lambda o, own=own: o + own))))
        step *= shares[i]
    if len(wide) > 1:
        one_exchange(staged[0].sparkSession)
        out = reduce(lambda a, b: a.join(b.hint("merge"), CELL), [f.repartitionById(cells, F.col(CELL)) for f in placed]).drop(CELL)
    else:
        out = staged[largest]
    for i, r in enumerate(staged):
        if i not in wide:
            out = out.crossJoin(F.broadcast(r))
    return out
