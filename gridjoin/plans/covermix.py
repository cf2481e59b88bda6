"""The cover-mix join: degrees, a mix of vertex covers for each combination of parts, heavy values broadcast, guarded intermediates, one grid shuffle.

For each combination: variables in heavy sets form H. Their projections, at most 2p values each, are joined to the heavy relation, which is broadcast behind a
check of its bound. Each relation with light variables is replaced by its guard joined with the heavy relation and filtered by the relation;
relations that share a guard filter one intermediate, as equal schemas intersect. Relations with only heavy variables filter the heavy relation. The
intermediates meet in one grid with shares p^v. Parts are disjoint and cells are exact, so the union over combinations has no duplicates.

Where relations have several parts, combinations whose heavy values do not meet are left out, buckets are merged until at most MAX_COMBOS are left, and all
of them run in one plan (combined.py).
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable
from dataclasses import dataclass, field
from fractions import Fraction
from functools import reduce
from itertools import islice
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridjoin.functions.hypergraph import Hypergraph
from gridjoin.functions.measures import kappa
from gridjoin.sources.tables import staged, staged_together

from .combined import PART, covering, product_in_grid
from .combined import run as run_combined
from .degrees import LIGHT, MAX_COMBOS, Signature, combos, parts_apart, signatures, subsets_in_order, uniformize, with_part
from .grid import Size, cell_load, fitted_shares, grid_join, large, sizes, whole_everywhere
from .query import Atom, JoinQuery, max_machines, natural_join, power_of_two
from .weights import Mix, build_mix, find_guards, integer_shares, joint_shares, search_delta

#: Rows up to which a heavy relation is broadcast.
MAX_BROADCAST = 1_000_000


@dataclass
class Combo:
    """One choice of parts with its plan."""

    parts: dict[str, Signature]
    mix: Mix
    guards: dict[str, str]
    shares: dict[str, int]
    p: int

    @property
    def machines(self) -> int:
        return prod(self.shares.values())


@dataclass
class Plan:
    query: JoinQuery
    hypergraph: Hypergraph
    n: int
    p: int
    tagged: dict[str, DataFrame]
    combos: list[Combo] = field(default_factory=list)
    #: Where there are several combinations: each relation with the number of its part, and the numbers.
    parted: dict[str, DataFrame] = field(default_factory=dict)
    ids: dict[str, dict[Signature, int]] = field(default_factory=dict)
    #: Buckets merged into one.
    base: int = 1

    @property
    def m(self) -> int:
        return power_of_two(self.n)

    @property
    def k(self) -> int:
        return power_of_two(self.p)

    def rows(self) -> list[dict]:
        """The plan in words, one row for each combination."""
        out = []
        for i, c in enumerate(self.combos):
            out.append(
                {
                    "combo": i,
                    "n": self.n,
                    "p": self.p,
                    "kappa": str(kappa(self.hypergraph).value),
                    "steps": " ".join(f"{''.join(sorted(s))}:{w}" for s, w in c.mix.steps),
                    "weights": " ".join(f"{x}={w}" for x, w in sorted(c.mix.weights.items())),
                    "heavy": ",".join(sorted(c.mix.heavy)),
                    "heavy_sets": " ".join(f"{{{','.join(sorted(u))}}}@{r}" for u, r in c.mix.heavy_sets),
                    "guards": " ".join(f"{r}<-{s}" for r, s in sorted(c.guards.items())),
                    "shares": " ".join(f"{x}={s}" for x, s in sorted(c.shares.items())),
                    "predicted_load": round(self.n / self.p ** float(1 / kappa(self.hypergraph).value), 3),
                }
            )
        return out


def plan_combo(h: Hypergraph, atoms: dict[str, frozenset[str]], parts: dict[str, Signature], m: int, k: int, delta: str | Fraction = "kappa") -> Combo:
    slack = {(r, u): e for r, s in parts.items() for u, e in s.slack(m, k).items()}
    mix = search_delta(h, slack) if delta == "search" else build_mix(h, slack, None if delta == "kappa" else delta)
    guards = find_guards(atoms, mix)
    return Combo(parts, mix, guards, integer_shares(mix.exponents, 1 << k, mix.heavy), 1 << k)


def preprocess(query: JoinQuery, p: int, delta: str | Fraction = "kappa", clamp: bool = True, lower_p: bool = True, normalized: bool = False, most: int = MAX_COMBOS) -> Plan:
    """Sizes, parts and one plan for each combination. p becomes a power of two, and no larger than the cube root of n allows unless lower_p is False."""
    query = query if normalized else query.normalized()
    # every relation is read by the counts, by a job for each subset that may be heavy, and by the join
    frames = staged_together([a.df for a in query.atoms], "atom")
    query = JoinQuery([a.with_frame(df) for a, df in zip(query.atoms, frames, strict=True)])
    tops = query.tops(max(1 << 10, min(1 << 16, 64 * p)))
    counts = {a: c for a, (c, _) in tops.items()}
    n = 1 << power_of_two(max(counts.values(), default=0))
    p = 1 << (max(1, p).bit_length() - 1)
    p = min(p, max_machines(n)) if lower_p else p
    h = query.hypergraph
    heavy = {a for a, (_, t) in tops.items() if any(c > n // p for c in t.values())}
    plan = Plan(query, h, n, p, {})
    base = 1
    while True:
        plan.base = base
        plan.tagged = {a.name: uniformize(a.df, list(a.vars), n, p, clamp, tops=tops[a.name][1], base=base) for a in query.atoms}
        if min(counts.values(), default=0) == 0:
            return plan
        # a relation without a heavy value has one part, of known size
        found = {a.name: [Signature(tuple((u, LIGHT) for u in subsets_in_order(list(a.vars))), counts[a.name])] if clamp and a.name not in heavy else signatures(plan.tagged[a.name], list(a.vars)) for a in query.atoms}
        apart = None
        if any(len(s) > 1 for s in found.values()):
            parted = {a.name: with_part(plan.tagged[a.name], list(a.vars), found[a.name], PART) for a in query.atoms}
            plan.parted = {r: staged(df, "parts") if len(found[r]) > 1 else df for r, df in parted.items()}
            plan.ids = {r: {x: i for i, x in enumerate(s)} for r, s in found.items()}
            apart = parts_apart(plan.parted, found)
        # no base beyond 2^6 merges more
        chosen = list(islice(combos(found, apart), most + 1 if base < 64 else None))
        if len(chosen) <= most or base >= 64:
            break
        base *= 2
    atoms = {a.name: frozenset(a.vars) for a in query.atoms}
    plan.combos = [plan_combo(h, atoms, parts, plan.m, plan.k, delta) for parts in chosen]
    return plan


def heavy_relation(parts: dict[str, DataFrame], sets: Iterable[tuple[frozenset[str], str]]) -> DataFrame | None:
    """Join of the projections on heavy sets; None without any."""
    pieces = [parts[r].select(*sorted(u)).distinct() for u, r in sets]
    return reduce(natural_join, sorted(pieces, key=lambda d: len(d.columns))) if pieces else None


def heavy_bound(combo: Combo, h: Hypergraph) -> float:
    """The heavy relation has at most 2^|H| p^(v(H)) tuples."""
    v = combo.mix.exponents
    return 2 ** len(combo.mix.heavy) * combo.p ** float(sum((v[x] for x in combo.mix.heavy), Fraction(0)))


def intermediates(plan: Plan, combo: Combo, heavy: str = "global", self_guard: str = "join") -> list[DataFrame]:
    """The frames that the grid joins. heavy: "global" joins the whole heavy relation to each guard; "per_relation" joins it to a heavy relation of its own, of
    the few heavy sets that hold the heavy variables of the guarded relations. self_guard: "join", or "direct" to send relations that guard themselves as they are."""
    parts = {a.name: plan.tagged[a.name].where(combo.parts[a.name].condition()).select(*a.vars) for a in plan.query.atoms}
    by_vars = {a.name: frozenset(a.vars) for a in plan.query.atoms}
    mix, H = combo.mix, combo.mix.heavy
    fits = heavy_bound(combo, plan.hypergraph) <= MAX_BROADCAST
    small = F.broadcast if fits else (lambda d: d)
    own = lambda wanted: heavy_relation(parts, covering(mix.heavy_sets, wanted))
    inside = [r for r, vs in by_vars.items() if vs <= H]
    whole = heavy_relation(parts, mix.heavy_sets) if heavy == "global" else None
    if whole is not None:
        for r in inside:
            vs = sorted(by_vars[r])
            whole = whole.join(parts[r].join(small(whole.select(*vs).distinct()), vs, "left_semi"), vs, "left_semi")
    groups: dict[str, list[str]] = defaultdict(list)
    for r, s in combo.guards.items():
        groups[s].append(r)
    out, done = [], False
    for s, guarded in groups.items():
        frame = parts[s]
        direct = self_guard == "direct" and guarded == [s]
        touch = H & (by_vars[s] | frozenset().union(*(by_vars[r] for r in guarded)))
        if H and not direct and (touch or heavy == "global"):
            mine = whole if heavy == "global" else own(touch)
            shared = [c for c in frame.columns if c in mine.columns]
            # without a common variable every tuple meets every heavy value, as the bound of the intermediate allows
            frame = frame.join(small(mine), shared) if shared else frame.crossJoin(small(mine))
            done = done or heavy == "global"
        for r in guarded:
            if r != s:
                frame = frame.join(parts[r], sorted(by_vars[r]), "left_semi")
        out.append(frame)
    if whole is not None and not done:
        out.append(whole)
    if heavy != "global":
        out += [own(by_vars[r]).join(parts[r], sorted(by_vars[r]), "left_semi") for r in inside]
    return out


def run_combo(plan: Plan, combo: Combo, heavy: str = "global", self_guard: str = "join", local: str = "catalyst") -> DataFrame:
    frames = intermediates(plan, combo, heavy, self_guard)
    if combo.mix.heavy or len(frames) < 2 or local != "catalyst":
        return grid_join(frames, combo.shares, local)
    # without heavy values the frames are relations, some of them filtered
    named = {frozenset(a.vars): a for a in plan.query.atoms}
    known = sizes([named[frozenset(f.columns)].df for f in frames])
    shares, whole = spread(plan, known)
    return grid_join(frames, shares, sizes=known, whole=whole)


def spread(plan: Plan, known: list[Size]) -> tuple[dict[str, int], frozenset[int]]:
    """Shares for relations of these sizes where no combination has heavy values, and the places of relations that every machine gets whole. Large relations are parted
    along variables that are light in all of them, as no shares make these heavy; the mix's own shares stay where they load a cell less."""
    combo = plan.combos[0]
    if not large(known):
        return combo.shares, frozenset()
    name = {frozenset(a.vars): a.name for a in plan.query.atoms}
    whole = whole_everywhere(known, combo.p)
    apart = [s for i, s in enumerate(known) if i not in whole]
    if whole and all(b == LIGHT for c in plan.combos for x in c.parts.values() for _, b in x.buckets):
        return joint_shares({frozenset(s.values): s.rows for s in apart}, combo.p), whole
    heavy = {v for c in plan.combos for s in apart for u, b in c.parts[name[frozenset(s.values)]].buckets if b != LIGHT and len(u) == 1 for v in u}
    able = sorted({v for s in apart for v in s.values if sum(v in t.values for t in apart) > 1} - heavy)
    shares = fitted_shares(apart, combo.p, able)
    load = cell_load(apart, shares) + sum(known[i].rows for i in whole)
    return (shares, whole) if (able or len(apart) == 1) and load <= cell_load(known, combo.shares) else (combo.shares, frozenset())


def empty_result(query: JoinQuery) -> DataFrame:
    kinds = {f.name: f.dataType.simpleString() for a in query.atoms for f in a.df.schema}
    return query.atoms[0].df.sparkSession.createDataFrame([], ", ".join(f"`{v}` {kinds[v]}" for v in query.variables))


def cover_mix_join(query: JoinQuery, p: int, delta: str | Fraction = "kappa", heavy: str = "global", self_guard: str = "join", local: str = "catalyst", clamp: bool = True, most: int = MAX_COMBOS) -> DataFrame:
    """Natural join of the query, columns in order of their names. Disconnected queries are joined by component, and the components in a grid."""
    query = query.normalized()
    parts = query.hypergraph.components()
    if len(parts) > 1:
        results = [cover_mix_join(JoinQuery([a for a in query.atoms if set(a.vars) <= set(c.vertices)]), p, delta, heavy, self_guard, local, clamp, most) for c in parts]
        return product_in_grid(results, p, MAX_BROADCAST, lambda df: staged(df, "component")).select(*query.variables)
    if len(query.atoms) == 1:
        return query.atoms[0].df.select(*query.variables)
    plan = preprocess(query, p, delta, clamp, normalized=True, most=most)
    if not plan.combos:
        return empty_result(query)
    if len(plan.combos) == 1:
        return run_combo(plan, plan.combos[0], heavy, self_guard, local).select(*query.variables)
    if not any(c.mix.heavy for c in plan.combos) and local == "catalyst":
        # parts only matter for heavy values; without any, large relations meet whole in one grid if that loads a cell less
        frames = [a.df for a in plan.query.atoms]
        known = sizes(frames)
        shares, whole = spread(plan, known)
        if whole or shares is not plan.combos[0].shares:
            return grid_join(frames, shares, sizes=known, whole=whole).select(*query.variables)
    return run_combined(plan, MAX_BROADCAST, heavy, self_guard)


__all__ = ["Atom", "Combo", "Plan", "cover_mix_join", "heavy_bound", "heavy_relation", "intermediates", "plan_combo", "preprocess", "run_combo"]
