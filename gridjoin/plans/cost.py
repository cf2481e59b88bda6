"""Loads and their bounds: tuples received by a cell, rounds, machines, and the figures that theory gives for them."""

from __future__ import annotations

from collections import Counter
from dataclasses import asdict, dataclass
from fractions import Fraction
from functools import reduce
from itertools import combinations
from math import prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridjoin.functions.hypergraph import Hypergraph
from gridjoin.functions.measures import boat_inside, kappa, phi, psi_star, rho_star, tau_star

from .covermix import Combo, Plan, heavy_relation, intermediates
from .grid import CELL, coordinate, replicate


@dataclass
class LoadReport:
    max_load: int
    mean_load: float
    sent: int
    tuples_in: int
    machines: int
    rounds: int
    predicted: float

    @property
    def ratio(self) -> float:
        return self.max_load / self.predicted if self.predicted else 0.0

    @property
    def replication(self) -> float:
        return self.sent / self.tuples_in if self.tuples_in else 0.0

    @property
    def skew(self) -> float:
        return self.max_load / self.mean_load if self.mean_load else 0.0

    def row(self) -> dict:
        return asdict(self) | {"ratio": self.ratio, "replication": self.replication, "skew": self.skew}


def cell_counts(frames: list[DataFrame], shares: dict[str, int], hash: str = "xx") -> DataFrame:
    """cell, cnt: tuples that each cell receives in the grid round."""
    variables = sorted(shares)
    parts = [replicate(f, variables, shares, hash).select(CELL) for f in frames]
    return reduce(DataFrame.unionByName, parts).groupBy(F.col(CELL).alias("cell")).agg(F.count("*").alias("cnt"))


def _report(counts: DataFrame, tuples_in: int, machines: int, rounds: int, predicted: float) -> LoadReport:
    r = counts.agg(F.max("cnt"), F.sum("cnt")).first()
    most, sent = r[0] or 0, r[1] or 0
    return LoadReport(most, sent / machines if machines else 0.0, sent, tuples_in, machines, rounds, predicted)


def grid_load(frames: list[DataFrame], shares: dict[str, int], n: int, p: int, h: Hypergraph, hash: str = "xx") -> LoadReport:
    """The one round of a grid join."""
    return _report(cell_counts(frames, shares, hash), sum(f.count() for f in frames), prod(shares.values()), 1, predicted_load(tau_star(h).value, n, p))


def combo_load(plan: Plan, combo: Combo, hash: str = "xx") -> LoadReport:
    """The grid round of one combination of the cover-mix join; rounds are those of its plan."""
    frames = intermediates(plan, combo)
    rounds = max((x.round for x in round_loads(plan, combo, hash)), default=1)
    return _report(cell_counts(frames, combo.shares, hash), sum(f.count() for f in frames), combo.machines, rounds, predicted_load(kappa(plan.hypergraph).value, plan.n, plan.p))


@dataclass
class RoundLoad:
    """Tuples that machines receive in one round; filters of different intermediates in one round have a row each."""

    round: int
    kind: str
    what: str
    machines: int
    max_load: int
    sent: int


def _dealt(frames: list[DataFrame], keys: list[str], p: int, hash: str) -> tuple[int, int]:
    """Most tuples of one of p machines, and all, when the frames are dealt by their keys."""
    at = reduce(Column.__add__, [coordinate(F.col(v), p, seed, hash) * (seed + 1) for seed, v in enumerate(sorted(keys))]) % p
    r = reduce(DataFrame.unionAll, [f.select(at.alias("m")) for f in frames]).groupBy("m").count().agg(F.max("count"), F.sum("count")).first()
    return r[0] or 0, r[1] or 0


def round_loads(plan: Plan, combo: Combo, hash: str = "xx") -> list[RoundLoad]:
    """Measured loads of every round after the degrees: the broadcast of the heavy sets, the semi-joins (both sides dealt by the key, then the next
    filter of the same intermediate), and the grid. hash: as for coordinates."""
    parts = {a.name: plan.tagged[a.name].where(combo.parts[a.name].condition()).select(*a.vars) for a in plan.query.atoms}
    out, now = [], 0
    if combo.mix.heavy_sets:
        now = 1
        values = sum(parts[r].select(*sorted(u)).distinct().count() for u, r in combo.mix.heavy_sets)
        out.append(RoundLoad(1, "broadcast", "heavy sets", plan.p, values, values * plan.p))
    whole = heavy_relation(parts, combo.mix.heavy_sets)
    last = now
    for s in sorted(set(combo.guards.values())):
        frame, step = parts[s], now
        if whole is not None:
            shared = [c for c in frame.columns if c in whole.columns]
            frame = frame.join(F.broadcast(whole), shared) if shared else frame.crossJoin(F.broadcast(whole))
        for r in sorted(r for r, g in combo.guards.items() if g == s and r != s):
            step += 1
            most, sent = _dealt([frame, parts[r]], parts[r].columns, plan.p, hash)
            out.append(RoundLoad(step, "semi-join", f"{s} by {r}", plan.p, most, sent))
            frame = frame.join(parts[r], parts[r].columns, "left_semi")
        last = max(last, step)
    frames = intermediates(plan, combo)
    if len(frames) > 1:  # one intermediate is the result where it stands
        counts = cell_counts(frames, combo.shares, hash).agg(F.max("cnt"), F.sum("cnt")).first()
        out.append(RoundLoad(last + 1, "grid", "intermediates", combo.machines, counts[0] or 0, counts[1] or 0))
    return out


def plan_rounds(df: DataFrame) -> int:
    """Rounds of a physical plan: most exchanges, broadcasts among them, on a way from a scan to the result."""
    depth, path = 0, []
    for line in df._jdf.queryExecution().executedPlan().toString().splitlines():
        body = line.lstrip(" :+-*(0123456789)")
        if not body or body.startswith("AdaptiveSparkPlan"):
            continue
        indent = len(line) - len(line.lstrip(" :+-"))
        while path and path[-1][0] >= indent:
            path.pop()
        path.append((indent, body.startswith(("Exchange", "BroadcastExchange"))))
        depth = max(depth, sum(x for _, x in path))
    return depth


def sizes(plan: Plan, combo: Combo) -> list[tuple[str, int, float]]:
    """Sizes that the load bound rests on, each with its bound: heavy sets, the heavy relation and its degrees, and guards joined with it."""
    parts = {a.name: plan.tagged[a.name].where(combo.parts[a.name].condition()).select(*a.vars) for a in plan.query.atoms}
    whole, H = heavy_relation(parts, combo.mix.heavy_sets), sorted(combo.mix.heavy)
    if whole is None:
        return []
    out = [(f"heavy set {{{','.join(sorted(u))}}} of {r}", parts[r].select(*sorted(u)).distinct().count(), float(heavy_set_bound(plan.p))) for u, r in combo.mix.heavy_sets]
    out.append(("heavy relation", whole.count(), heavy_relation_bound(plan, combo)))
    for given in (c for k in range(1, len(H)) for c in combinations(H, k)):
        out.append((f"heavy relation given {','.join(given)}", whole.groupBy(*given).count().agg(F.max("count")).first()[0] or 0, heavy_relation_bound(plan, combo, frozenset(given))))
    for s in sorted(set(combo.guards.values())):
        shared = [c for c in parts[s].columns if c in H]
        joined = parts[s].join(F.broadcast(whole), shared) if shared else parts[s].crossJoin(F.broadcast(whole))
        out.append((f"{s} joined", joined.count(), intermediate_bound(plan, combo, s)))
    return out


def check_machines(plan: Plan) -> dict[int, tuple[int, float]]:
    """Combinations whose grid has more than p cells, with their cells and p to the norm; there are none."""
    return {i: (c.machines, machines_used(c.mix.exponents, c.p)) for i, c in enumerate(plan.combos) if c.machines > c.p or machines_used(c.mix.exponents, c.p) > c.p * (1 + 1e-9)}


def predicted_load(number: Fraction, n: int, p: int) -> float:
    """n / p^(1 / number)."""
    return n / p ** float(1 / number) if number else float(n)


def machines_used(exponents: dict[str, Fraction], p: int) -> float:
    return p ** float(sum(exponents.values(), Fraction(0)))


def heavy_set_bound(p: int) -> int:
    """Values of a heavy set: p, doubled by the buckets' factor."""
    return 2 * p


def heavy_relation_bound(plan: Plan, combo: Combo, given: frozenset[str] = frozenset()) -> float:
    """Degree of the heavy relation for fixed values of ``given``."""
    v, H = combo.mix.exponents, combo.mix.heavy
    return 2 ** len(H) * plan.p ** float(sum((v[x] for x in H - given), Fraction(0)))


def intermediate_bound(plan: Plan, combo: Combo, guard: str) -> float:
    v, H = combo.mix.exponents, combo.mix.heavy
    mine = frozenset(next(a.vars for a in plan.query.atoms if a.name == guard))
    return plan.n * 2 ** len(H) * plan.p ** float(sum((v[x] for x in H - mine), Fraction(0)))


def lower_bound(h: Hypergraph, n: int, p: int) -> float:
    """The larger of the bound by output size and, where a boat of k stands inside the hypergraph, n / p^(1/k)."""
    number = rho_star(h).value
    k = boat_inside(h) if len(h.vertices) <= 12 else 0
    return predicted_load(max(number, Fraction(k)), n, p)


def output_bound(h: Hypergraph, n: int) -> float:
    return float(n) ** float(rho_star(h).value)


def conjectured_bound(h: Hypergraph, n: int, p: int) -> float:
    """A conjecture, for reduced hypergraphs: no algorithm has a load below n / p^(1 / tau)."""
    return predicted_load(tau_star(h.reduced()).value, n, p)


def expected_output(h: Hypergraph, n: int, chances: list[float]) -> float:
    """Of a sparse product instance: n^tau times the product of its edges' densities."""
    return float(n) ** float(tau_star(h).value) * prod(chances)


def machine_output(h: Hypergraph, load: float, chances: list[float]) -> float:
    """Results that one machine which receives ``load`` tuples of each relation of a sparse product instance makes at most, on average."""
    return load ** float(tau_star(h).value) * prod(chances)


def acyclic_load(tuples_in: int, tuples_out: int, p: int) -> tuple[float, float]:
    """Loads of acyclic joins: of the full reducer, and of the output-sensitive improvement that is not executed here."""
    return (tuples_in + tuples_out) / p, (tuples_in + (tuples_in * tuples_out) ** 0.5) / p


def packing_load(h: Hypergraph, n: int, p: int) -> float:
    """Of the algorithm with a load by the generalised vertex packing and the arity, n / p^(2 / (arity * phi)); not executed here."""
    return predicted_load(phi(h).value * h.arity / 2, n, p)


@dataclass
class RunReport:
    """One run of a plan: seconds, result rows, the exchanges and rounds that were planned, and over its stages the bytes read, shuffled and spilled
    and the most that a stage's operators held in memory."""

    seconds: float
    rows: int
    exchanges: dict[str, int]
    rounds: int = 0
    input_bytes: int = 0
    shuffle_bytes: int = 0
    spilled_bytes: int = 0
    peak_memory: int = 0


def _stages(spark) -> dict[int, tuple[int, int, int, int]]:
    """Input, shuffled, spilled bytes and peak execution memory of the stages that the session's status store still holds."""
    sc = spark.sparkContext
    none = sc._jvm.java.util.ArrayList()
    found = sc._jsc.sc().statusStore().stageList(none, False, False, sc._gateway.new_array(sc._jvm.double, 0), none)
    every = (found.apply(i) for i in range(found.size()))
    return {s.stageId(): (s.inputBytes(), s.shuffleWriteBytes(), s.memoryBytesSpilled() + s.diskBytesSpilled(), s.peakExecutionMemory()) for s in every}


def measure(df: DataFrame) -> RunReport:
    """Runs a plan into the noop sink; rows are counted on the way."""
    import time

    from pyspark.sql import Observation

    seen, before = Observation(), set(_stages(df.sparkSession))
    began = time.time()
    df.observe(seen, F.count(F.lit(1)).alias("rows")).write.format("noop").mode("overwrite").save()
    took = time.time() - began
    ran = [v for k, v in _stages(df.sparkSession).items() if k not in before]
    read, shuffled, spilled = (sum(v[i] for v in ran) for i in range(3))
    return RunReport(took, seen.get["rows"], dict(exchanges(df)), plan_rounds(df), read, shuffled, spilled, max((v[3] for v in ran), default=0))


def bounds_row(name: str, h: Hypergraph, n: int, p: int) -> dict:
    return {
        "family": name,
        "load_kappa": predicted_load(kappa(h).value, n, p),
        "load_psi": predicted_load(psi_star(h).value, n, p),
        "load_rho": predicted_load(rho_star(h).value, n, p),
        "load_tau": predicted_load(tau_star(h).value, n, p),
        "load_phi": packing_load(h, n, p),
        "lower": lower_bound(h, n, p),
        "conjectured": conjectured_bound(h, n, p),
        "output": output_bound(h, n),
    }


def exchanges(df: DataFrame) -> Counter:
    """Exchange nodes of the physical plan before it runs, by kind; "grid" are those to the cells of a grid."""
    text = df._jdf.queryExecution().executedPlan().toString()
    kinds = {"grid": "Exchange shufflepartitionidpassthrough", "REPARTITION_BY_NUM": "REPARTITION_BY_NUM", "REPARTITION_BY_COL": "REPARTITION_BY_COL", "ENSURE_REQUIREMENTS": "ENSURE_REQUIREMENTS", "BroadcastExchange": "BroadcastExchange"}
    return Counter({k: text.count(t) for k, t in kinds.items()})
