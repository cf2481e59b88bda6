"""Join workloads: the shapes that the measures are stated for, as relations projected from the given tables, with their SQL."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridjoin.functions.hypergraph import Hypergraph
from gridjoin.plans.query import JoinQuery

from .tables import source, source_sql

#: Expressions of variables that several workloads share; both engines read them.
COLS = {
    "c": "o_custkey", "o": "l_orderkey", "p": "l_partkey", "s": "l_suppkey", "l": "CAST(l_linenumber AS BIGINT)", "f": "l_returnflag", "t": "l_linestatus",
}


@dataclass(frozen=True)
class Relation:
    source: str
    columns: tuple[tuple[str, str], ...]
    where: str = ""

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(v for v, _ in self.columns)

    def frame(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        df = source(spark, sf_dir, self.source)
        df = df.where(self.where) if self.where else df
        return df.selectExpr(*[f"{e} AS {v}" for v, e in self.columns])

    def sql(self) -> str:
        return f"SELECT DISTINCT {', '.join(f'{e} AS {v}' for v, e in self.columns)} FROM {source_sql(self.source)}" + (f" WHERE {self.where}" if self.where else "")


def rel(table: str, variables: str | None = None, where: str = "", **columns: str) -> Relation:
    """Variables by their letters in COLS, or stated columns."""
    cols = {v: COLS[v] for v in variables} if variables else columns
    if variables and table == "orders":
        cols |= {v: "o_orderkey" for v in variables if v == "o"}
    return Relation(table, tuple(cols.items()), where)


@dataclass(frozen=True)
class Workload:
    name: str
    atoms: dict[str, Relation]
    #: variables to group the result by where only counts are returned
    by: tuple[str, ...] | None = None

    @property
    def variables(self) -> list[str]:
        return sorted({v for r in self.atoms.values() for v in r.vars})

    @property
    def hypergraph(self) -> Hypergraph:
        return Hypergraph.of(r.vars for r in self.atoms.values())

    def query(self, spark: SparkSession, sf_dir: str) -> JoinQuery:
        return JoinQuery({k: r.frame(spark, sf_dir) for k, r in self.atoms.items()})

    def result(self, joined: DataFrame) -> DataFrame:
        if self.by is None:
            return joined.select(*self.variables)
        return joined.groupBy(*self.by).agg(F.count("*").alias("cnt"))

    def join_sql(self) -> str:
        """The natural join, as a FROM clause."""
        left, seen, text = dict(self.atoms), set(), ""
        while left:
            k = max(left, key=lambda k: (len(seen & set(left[k].vars)), -list(self.atoms).index(k)))
            r = left.pop(k)
            shared = sorted(seen & set(r.vars))
            part = f"({r.sql()}) AS {k}"
            text = part if not text else f"{text} JOIN {part} USING ({', '.join(shared)})" if shared else f"{text} CROSS JOIN {part}"
            seen |= set(r.vars)
        return text

    def sql(self) -> str:
        if self.by is None:
            return f"SELECT {', '.join(self.variables)} FROM {self.join_sql()}"
        return f"SELECT {', '.join(self.by)}, count(*) AS cnt FROM {self.join_sql()} GROUP BY {', '.join(self.by)}"


def _pairs(source: str, variables: str, size: int) -> dict[str, Relation]:
    from itertools import combinations

    return {f"r_{''.join(c)}": rel(source, "".join(c)) for c in combinations(variables, size)}


_Y = "l_orderkey * 100000 + l_partkey"
_LINE = "l_orderkey * 8 + l_linenumber"
_CUST = {"c": "c_custkey", "n": "CAST(c_nationkey AS BIGINT)"}
_SUPP = {"s": "s_suppkey", "n": "CAST(s_nationkey AS BIGINT)"}
_K = "CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT)"
_EDGE = ("CAST(c_nationkey AS BIGINT)", "CAST(s_nationkey AS BIGINT)")
_W05 = {"cust": rel("customer", **_CUST), "ord": rel("orders", "co"), "line": rel("lineitem", "os"), "supp": rel("supplier", **_SUPP)}
_DOCS = {"ls": rel("documents", g="lang", u="source"), "sq": rel("doclabels", u="source", q="CAST(quality AS BIGINT)"), "lq": rel("doclabels", g="lang", q="CAST(quality AS BIGINT)")}



def _few(c: str) -> str:
    """Each value about half as often as the next."""
    return f"CAST(length(bin({c})) AS BIGINT)"


def _some(c: str) -> str:
    """A third of the values fall on few, the others are many."""
    return f"CASE WHEN {c} % 3 = 0 THEN {_few(c)} ELSE {c} + 100 END"


WORKLOADS: dict[str, Workload] = {
    w.name: w
    for w in [
        Workload("w01", {"ord": rel("orders", "co"), "line": rel("lineitem", "op")}),
        Workload("w02", _pairs("lo", "cps", 2), by=("s",)),
        Workload("w03", {"r": rel("lineitem", x="l_linestatus", y=_Y), "s": rel("lineitem", y=_Y, z="l_partkey"), "t": rel("lineitem", x="l_linestatus", z="l_partkey")}),
        Workload("w03b", {"r": rel("lineitem", "to"), "s": rel("lineitem", "op"), "t": rel("lineitem", "tp")}),
        Workload("w03c", {"r": rel("status_pairs", x="l_linestatus", y="y"), "s": rel("lineitem", y=_Y, z="l_partkey"), "t": rel("status_parts", x="l_linestatus", z="l_partkey")}),
        Workload("w04", {k: rel("lo", k[2:]) for k in ("r_ps", "r_so", "r_po", "r_oc", "r_ol", "r_cl")}, by=("s",)),
        Workload("w05", _W05),
        Workload("w06", _W05 | {"nat": rel("nation", n="CAST(n_nationkey AS BIGINT)", r="CAST(n_regionkey AS BIGINT)")}),
        Workload("w07", {"ord": rel("orders", "co"), "op": rel("lineitem", "op"), "ps": rel("lineitem", "ps"), "supp": rel("supplier", **_SUPP), "cust": rel("customer", **_CUST)}),
        Workload("w08", _pairs("lo", "cpsl", 2), by=("s",)),
        Workload("w09", _pairs("lo", "pslf", 3)),
        Workload("w10", _pairs("lo", "cpsf", 3)),
        Workload("w11", {k: rel("lo", k[2:]) for k in ("r_ps", "r_cf", "r_pc", "r_sf")}, by=("s",)),
        Workload("w12", {k: rel("lo", k[2:]) for k in ("r_psl", "r_ctf", "r_pc", "r_st", "r_lf")}, by=("l", "f")),
        Workload("w13", {k: rel("lo", k[2:]) for k in ("r_pslo", "r_ctfo", "r_pco", "r_sto", "r_lfo")}),
        Workload(
            "w14",
            {
                "ab": rel("customer", a="c_custkey", b="CAST(c_nationkey AS BIGINT)"),
                "bcde": rel("supply", b="CAST(n_nationkey AS BIGINT)", c="s_suppkey", d="CAST(floor(s_acctbal / 2000) AS BIGINT)", e="CAST(n_regionkey AS BIGINT)"),
                "bef": rel("clients", b="CAST(n_nationkey AS BIGINT)", e="CAST(n_regionkey AS BIGINT)", f="c_mktsegment"),
                "efg": rel("orders_of", e="CAST(n_regionkey AS BIGINT)", f="c_mktsegment", g="o_orderpriority"),
                "gh": rel("orders_of", g="o_orderpriority", h="o_orderstatus"),
                "gi": rel("orders_of", g="o_orderpriority", i="CAST(year(o_orderdate) AS BIGINT)"),
                "hi": rel("orders_of", h="o_orderstatus", i="CAST(year(o_orderdate) AS BIGINT)"),
            },
            by=("e", "g"),
        ),
        Workload("w15", {"reg": rel("region", r="CAST(r_regionkey AS BIGINT)", g="r_name"), "nat": rel("nation", n="CAST(n_nationkey AS BIGINT)", r="CAST(n_regionkey AS BIGINT)"), "cust": rel("customer", **_CUST), "ord": rel("orders", "co"), "line": rel("lineitem", "ol")}),
        Workload("w16", {f"r_p{v}": rel("lo", f"p{v}") for v in "csf"}, by=("f",)),
        Workload("w17", {"rich": rel("customer", None, "c_acctbal > 0", c="c_custkey"), "ord": rel("orders", "co"), "back": rel("lineitem", "o", "l_returnflag = 'R'")}),
        Workload("w18", {"nat": rel("nation", n="CAST(n_nationkey AS BIGINT)", r="CAST(n_regionkey AS BIGINT)")} | _DOCS),
        Workload("w19", {"ut": rel("events", u="user_id", y="event_type"), "yk": rel("events", y="event_type", k=_K), "uk": rel("events", u="user_id", k=_K)}),
        Workload("w20", {k: rel("trade", **{k[1]: _EDGE[0], k[2]: _EDGE[1]}) for k in ("eab", "ebc", "eac")}),
        Workload("w21", {"ud": rel("events", u="user_id", d="CAST(dayofyear(ts) AS BIGINT)"), "dy": rel("events", d="CAST(dayofyear(ts) AS BIGINT)", y="event_type"), "yk": rel("events", y="event_type", k=_K), "uk": rel("events", u="user_id", k=_K)}, by=("y",)),
        Workload("w22", {"ct": rel("conversations", c="conv_id", t="turn"), "tr": rel("conversations", t="turn", r="role"), "cr": rel("conversations", c="conv_id", r="role")}),
        Workload("w23", {"doc": rel("doctokens", d="doc_id", w="w"), "item": rel("itemtokens", w="w", i="item_id")}),
        Workload("w24", {"one": rel("embeddings", a="vec_id", g="CAST(label AS BIGINT)"), "two": rel("embeddings", b="vec_id", g="CAST(label AS BIGINT)")}),
        Workload("w25", {"back": rel("lineitem", "op", "l_returnflag = 'R'"), "open": rel("lineitem", "op", "l_linestatus = 'O'"), "ord": rel("orders", "co")}),
        Workload("w26", _DOCS),
        # relations with values of many degrees: a few, about ten, and more than a hundred combinations of parts
        Workload("w27", {"r": rel("lineitem", x=_few("l_linenumber"), y=_LINE), "s": rel("lineitem", y=_LINE, z="l_partkey"), "t": rel("lineitem", x=_few("l_linenumber"), z="l_partkey")}),
        Workload("w28", {k: rel("lo", **{v: {"x": _few("l_partkey"), "y": _LINE, "z": "l_orderkey", "v": _LINE, "w": _few("o_custkey")}[v] for v in k[2:]}) for k in ("r_xy", "r_yz", "r_xz", "r_zv", "r_zw", "r_vw")}, by=("x", "w")),
        Workload("w29", {f"r_{''.join(c)}": rel("lineitem", **{v: {"a": _few("l_partkey"), "b": "l_orderkey", "c": _few("l_orderkey"), "d": "l_suppkey"}[v] for v in c}) for c in ("abc", "abd", "acd", "bcd")}, by=("a", "c")),
        Workload("w30", {"r": rel("lineitem", x=_few("l_partkey"), y=_some("l_orderkey")), "s": rel("lo", y=_few("o_custkey"), z=_some("(l_orderkey + l_partkey)")), "t": rel("lineitem", z=_few("l_orderkey"), x=_some("(l_partkey + 7 * l_orderkey)"))}),
    ]
}
