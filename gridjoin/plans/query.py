"""Natural join queries over DataFrames."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ByteType, IntegerType, MapType, ShortType

from gridjoin.functions.hypergraph import Hypergraph


@dataclass(frozen=True)
class Atom:
    """A relation: its columns are the variables."""

    name: str
    df: DataFrame

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(self.df.columns)

    def with_frame(self, df: DataFrame) -> Atom:
        return Atom(self.name, df)


class JoinQuery:
    """Atoms joined on all shared variables, with set semantics. The same table may stand under several names (a self-join by copies)."""

    def __init__(self, atoms: dict[str, DataFrame] | Iterable[Atom]):
        self.atoms = [Atom(k, v) for k, v in atoms.items()] if isinstance(atoms, dict) else list(atoms)
        if len({a.name for a in self.atoms}) != len(self.atoms):
            raise ValueError("atom names repeat")

    @property
    def variables(self) -> list[str]:
        return sorted({v for a in self.atoms for v in a.vars})

    @property
    def hypergraph(self) -> Hypergraph:
        return Hypergraph.of(a.vars for a in self.atoms)

    def validate(self) -> None:
        kinds: dict[str, str] = {}
        for a in self.atoms:
            for f in a.df.schema:
                if isinstance(f.dataType, MapType):
                    raise TypeError(f"{a.name}.{f.name}: maps cannot be join variables")
                if kinds.setdefault(f.name, f.dataType.simpleString()) != f.dataType.simpleString():
                    raise TypeError(f"variable {f.name} is {kinds[f.name]} and {f.dataType.simpleString()}")

    def normalized(self, distinct: bool = True) -> JoinQuery:
        """Small integers widened, nulls of shared variables dropped in the scan, duplicates removed, atoms of one schema intersected."""
        uses = Counter(v for a in self.atoms for v in a.vars)
        groups: dict[frozenset[str], list[Atom]] = {}
        for a in self.atoms:
            df = a.df.select([F.col(f.name).cast("long").alias(f.name) if isinstance(f.dataType, ByteType | ShortType | IntegerType) else F.col(f.name) for f in a.df.schema])
            for v in a.vars:
                if uses[v] > 1:
                    df = df.where(F.col(v).isNotNull())
            groups.setdefault(frozenset(a.vars), []).append(a.with_frame(df.distinct() if distinct else df))
        out = []
        for group in groups.values():
            order = group[0].vars
            df = reduce(lambda x, y: x.intersect(y.df.select(*order)), group[1:], group[0].df)
            out.append(Atom("&".join(a.name for a in group), df))
        query = JoinQuery(out)
        query.validate()
        return query

    def absorbed(self) -> JoinQuery:
        """Atoms whose variables lie inside another's become semi-joins on it."""
        atoms = list(self.atoms)
        for a in sorted(self.atoms, key=lambda a: len(a.vars)):
            host = next((b for b in atoms if b.name != a.name and set(a.vars) < set(b.vars)), None)
            if host is not None:
                atoms[atoms.index(host)] = host.with_frame(host.df.join(next(x for x in atoms if x.name == a.name).df, list(a.vars), "left_semi"))
                atoms = [x for x in atoms if x.name != a.name]
        return JoinQuery(atoms)

    def counts(self) -> dict[str, int]:
        """Tuples of each atom, in one job."""
        parts = [a.df.select(F.lit(a.name).alias("atom")) for a in self.atoms]
        found = {r["atom"]: r["count"] for r in reduce(DataFrame.unionAll, parts).groupBy("atom").count().collect()}
        return {a.name: found.get(a.name, 0) for a in self.atoms}

    def tops(self, cells: int = 1 << 16) -> dict[str, tuple[int, dict[str, int]]]:
        """Tuples of each atom, and for each of its variables a number that no degree exceeds: the most tuples in one of ``cells`` cells that values are hashed to. One
        pass over the atoms for all variables; only cells are shuffled, so a variable of many values costs no more than one of few."""
        parts, names = [], []
        for a in self.atoms:
            keys = []
            for v in a.vars:
                keys.append(F.pmod(F.xxhash64(v), F.lit(cells)) + F.lit(len(names) * cells))
                names.append((a.name, v))
            parts.append(a.df.select(F.explode(F.array(*keys)).alias("cell")))
        counts = reduce(DataFrame.unionAll, parts).groupBy("cell").count()
        found = {r["at"]: (r["n"], r["most"]) for r in counts.groupBy(F.expr(f"cell div {cells}").alias("at")).agg(F.sum("count").alias("n"), F.max("count").alias("most")).collect()}
        out: dict[str, tuple[int, dict[str, int]]] = {a.name: (0, {}) for a in self.atoms}
        for i, (atom, v) in enumerate(names):
            n, most = found.get(i, (0, 0))
            out[atom] = (n, out[atom][1] | {v: most})
        return out


def natural_join(a: DataFrame, b: DataFrame, hint: str | None = None) -> DataFrame:
    shared = [c for c in a.columns if c in b.columns]
    b = b.hint(hint) if hint else b
    return a.join(b, shared) if shared else a.crossJoin(b)


def power_of_two(n: int) -> int:
    """The least exponent whose power of two is n or more."""
    return max(0, (max(1, n) - 1).bit_length())


def max_machines(n: int) -> int:
    """The largest power of two p with p^3 <= n."""
    k = 0
    while (1 << (3 * (k + 1))) <= n:
        k += 1
    return 1 << k
