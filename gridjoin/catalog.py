"""Driver queries and their SQL."""

from __future__ import annotations

from fractions import Fraction
from functools import partial

from gridjoin.operators import baselines as B
from gridjoin.plans import covermix as C
from gridjoin.sources.workloads import WORKLOADS

#: Machines of the driver queries; the plans lower it where the relations are small.
P = 32


def _cover(w, spark, sf_dir, **options):
    return w.result(C.cover_mix_join(w.query(spark, sf_dir), P, **options))


def _with(fn, w, spark, sf_dir, **options):
    return w.result(fn(w.query(spark, sf_dir), P, **options))


def _plain(fn, w, spark, sf_dir):
    return w.result(fn(w.query(spark, sf_dir)))


def _cascade(w, spark, sf_dir):
    return w.result(B.cascade_join(w.query(spark, sf_dir))) if w.by is None else B.cascade_count(w.query(spark, sf_dir), w.by)


def joins() -> tuple[dict, dict]:
    q, sql = {}, {}

    def add(prefix, names, make):
        for name in names:
            w = WORKLOADS[name]
            q[f"{prefix}_{name}"] = make(w)
            sql[f"{prefix}_{name}"] = w.sql()

    every = list(WORKLOADS)
    add("cm", every, lambda w: partial(_cover, w))
    add("cas", every, lambda w: partial(_cascade, w))
    add("hc", every, lambda w: partial(_with, B.hypercube_join, w))
    add("hc_equal", ["w02", "w05", "w09", "w19"], lambda w: partial(_with, B.hypercube_join, w, shares="equal"))
    add("skew1", ["w02", "w03", "w05", "w23"], lambda w: partial(_with, B.one_round_skew_join, w))
    add("ded", ["w02", "w03", "w05", "w23"], lambda w: partial(_with, B.dedicated_heavy_join, w))
    add("tri2", ["w02", "w03", "w19"], lambda w: partial(_with, B.triangle_two_case_join, w))
    add("acyc", ["w01", "w15", "w16", "w17"], lambda w: partial(_plain, B.acyclic_join, w))
    add("cm_search", ["w03", "w04", "w09"], lambda w: partial(_cover, w, delta="search"))
    add("cm_perrel", ["w03", "w04", "w09", "w13"], lambda w: partial(_cover, w, heavy="per_relation"))
    add("cm_direct", ["w03", "w04", "w09"], lambda w: partial(_cover, w, self_guard="direct", heavy="per_relation"))
    add("cm_generic", ["w03", "w22", "w26"], lambda w: partial(_cover, w, local="generic"))
    return q, sql


# ---- measures, plans, degrees, loads -----------------------------------------------------------------------------------------

#: Vertices, rho, tau, kappa, psi and phi of the tabulated hypergraphs.
REFERENCE = """
path_2 3 2 1 2 2 2
triangle 3 3/2 3/2 3/2 2 3/2
clique_4 4 2 2 2 3 2
clique_5 5 5/2 5/2 5/2 4 5/2
cycle_4 4 2 2 2 2 2
cycle_5 5 5/2 5/2 5/2 3 5/2
cycle_6 6 3 3 3 4 3
star_3 4 3 1 3 3 3
star_4 5 4 1 4 4 4
bowtie 5 5/2 5/2 5/2 4 5/2
loomis_whitney_4 4 4/3 4/3 4/3 2 4/3
loomis_whitney_5 5 5/4 5/4 5/4 2 5/4
boat_2 4 2 2 2 2 2
boat_3 6 2 3 3 3 2
boat_4 8 2 4 4 4 2
boat_z_2 5 2 1 2 2 3
boat_z_3 7 2 1 3 3 4
boat_z_4 9 2 1 4 4 5
nine_var 9 4 3 4 5 9/2
not_reduced 2 1 2 1 2 1
"""


def _values(names: str, rows: list[tuple]) -> str:
    lit = lambda v: "NULL" if v is None else f"'{v}'" if isinstance(v, str) else str(v)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(lit, r)) + ')' for r in rows)}) AS t({names})"


def order_graphs(spark, sf_dir):
    """kind, lines, orders, tuples, hypergraph: what orders of so many lines look like, as a star of the order and its lines and, from three lines on, as a cycle
    of its lines; how many orders do, and how many tuples they have."""
    from pyspark.sql import functions as F

    from gridjoin.functions.families import cycle, star
    from gridjoin.sources.tables import load

    sizes = load(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count_distinct("l_linenumber").alias("k"), F.count("*").alias("c")).where("k > 0")
    rows = sizes.groupBy("k").agg(F.count("*").alias("orders"), F.sum("c").alias("tuples")).orderBy("k").collect()
    return [(kind, r["k"], r["orders"], r["tuples"], make(r["k"])) for kind, least, make in (("star", 1, star), ("cycle", 3, cycle)) for r in rows if r["k"] >= least]


#: The hypergraphs of order_graphs with their measures as fractions of two, in closed form.
ORDER_GRAPHS = """(WITH s AS (SELECT k, count(*) AS orders, CAST(sum(c) AS BIGINT) AS tuples FROM (SELECT count(DISTINCT l_linenumber) AS k, count(*) AS c FROM lineitem GROUP BY l_orderkey) WHERE k > 0 GROUP BY k)
    SELECT 'star' AS kind, k AS lines, orders, tuples, k + 1 AS vertices, 2 * k AS rho, 2 AS tau, 2 * k AS kappa, 2 * k AS psi, 2 * k AS phi FROM s
    UNION ALL SELECT 'cycle', k, orders, tuples, k, k, k, k, 2 * (2 * k // 3), k FROM s WHERE k >= 3)"""


def _halves(c: str) -> str:
    return f"CASE WHEN {c} % 2 = 0 THEN CAST({c} // 2 AS VARCHAR) ELSE {c} || '/2' END"


def measures_table(spark, sf_dir):
    from gridjoin.functions.measures import exponents

    rows = [(kind, k, orders, e["vertices"], *(str(e[m]) for m in ("rho", "tau", "kappa", "psi", "phi"))) for kind, k, orders, e in ((kind, k, orders, exponents(h)) for kind, k, orders, _, h in order_graphs(spark, sf_dir))]
    return spark.createDataFrame(rows, "kind string, lines long, orders long, vertices int, rho string, tau string, kappa string, psi string, phi string")


def relations_table(spark, sf_dir):
    from gridjoin.functions.families import named
    from gridjoin.functions.measures import check_relations

    return spark.createDataFrame([(k, r, ok) for k, h in named().items() for r, ok in check_relations(h).items()], "family string, relation string, holds boolean")


def kappa_methods(spark, sf_dir):
    """The value by enumeration, by the mixed-integer program and by the short cuts."""
    from gridjoin.functions.measures import kappa

    return spark.createDataFrame([(kind, k, orders, *(str(kappa(h, m).value) for m in ("enum", "milp", "auto"))) for kind, k, orders, _, h in order_graphs(spark, sf_dir)], "kind string, lines long, orders long, enumerated string, program string, auto string")


def bounds_table(spark, sf_dir):
    """Bounds for the tuples that the orders have, and 64 machines."""
    from gridjoin.plans.cost import bounds_row
    from gridjoin.plans.query import power_of_two

    rows = []
    for kind, k, _, tuples, h in order_graphs(spark, sf_dir):
        n = 1 << power_of_two(tuples)
        rows.append((kind, k, n, *(round(float(v), 6) for v in list(bounds_row(kind, h, n, 64).values())[1:])))
    return spark.createDataFrame(rows, "kind string, lines long, n long, " + ", ".join(f"{c} double" for c in ("load_kappa", "load_psi", "load_rho", "load_tau", "load_phi", "lower", "conjectured", "output")))


def explain_mix(w, spark, sf_dir):
    """The plan of each combination in words."""
    rows = C.preprocess(w.query(spark, sf_dir), P).rows()
    return spark.createDataFrame([tuple(r.values()) for r in rows], "combo int, n int, p int, kappa string, steps string, weights string, heavy string, heavy_sets string, guards string, shares string, predicted_load double")


def _tagged(w, spark, sf_dir, clamp):
    from gridjoin.plans.degrees import uniformize
    from gridjoin.plans.query import max_machines, power_of_two

    query = w.query(spark, sf_dir).normalized()
    n = 1 << power_of_two(max(query.counts().values()))
    return {a.name: (a.vars, uniformize(a.df, list(a.vars), n, min(P, max_machines(n)), clamp)) for a in query.atoms}


def signature_table(w, clamp, spark, sf_dir):
    """atom, b1, b2, cnt for atoms of two variables."""
    from functools import reduce

    from pyspark.sql import DataFrame
    from pyspark.sql import functions as F

    from gridjoin.plans.degrees import bucket_name

    parts = [df.groupBy(*[F.col(bucket_name((v,))).alias(f"b{i + 1}") for i, v in enumerate(sorted(vs))]).agg(F.count("*").alias("cnt")).select(F.lit(name).alias("atom"), "b1", "b2", "cnt") for name, (vs, df) in _tagged(w, spark, sf_dir, clamp).items()]
    return reduce(DataFrame.unionByName, parts)


def signature_sql(w, clamp):
    bucket = lambda c: f"CASE WHEN {c} <= 1 THEN 0 ELSE length(bin({c} - 1)) END"
    size = " UNION ALL ".join(f"SELECT count(*) AS c FROM ({r.sql()})" for r in w.atoms.values())
    light = lambda c: f"CASE WHEN {c} * {P} > (SELECT n FROM nn) THEN {bucket(c)} ELSE -1 END" if clamp else bucket(c)
    parts = []
    for k, r in w.atoms.items():
        x, y = sorted(r.vars)
        one = f"SELECT {y}, {light('c')} AS b1 FROM (SELECT {y}, count(*) OVER (PARTITION BY {x}) AS c FROM ({r.sql()}))"
        two = f"SELECT b1, {light('c')} AS b2 FROM (SELECT b1, count(*) OVER (PARTITION BY b1, {y}) AS c FROM ({one}))"
        parts.append(f"SELECT '{k}' AS atom, b1, b2, count(*) AS cnt FROM ({two}) GROUP BY b1, b2")
    return f"WITH nn AS (SELECT CAST(pow(2, ceil(log2(max(c)))) AS BIGINT) AS n FROM ({size})) " + " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)


def constraint_check(w, spark, sf_dir):
    """Violations of the degree constraints over all parts; none are expected."""
    from gridjoin.plans.degrees import signatures, violations

    out = None
    for name, (vs, df) in _tagged(w, spark, sf_dir, False).items():
        for s in signatures(df, list(vs)):
            sigma = {frozenset(u): 1 << b for u, b in s.buckets}
            found = violations(df.where(s.condition()).select(*vs), list(vs), sigma)
            out = found if out is None else out.unionByName(found)
    return out.groupBy().count().withColumnRenamed("count", "violations")


def heavy_rel(w, spark, sf_dir):
    plan = C.preprocess(w.query(spark, sf_dir), P)
    combo = next(c for c in plan.combos if c.mix.heavy)
    parts = {a.name: plan.tagged[a.name].where(combo.parts[a.name].condition()).select(*a.vars) for a in plan.query.atoms}
    return C.heavy_relation(parts, combo.mix.heavy_sets)


def load_cells(w, spark, sf_dir):
    """Tuples that each cell of the one-round grid receives, with a hash that SQL repeats."""
    from gridjoin.plans.cost import cell_counts

    q = w.query(spark, sf_dir).normalized()
    return cell_counts([a.df for a in q.atoms], B.cover_shares(q.hypergraph, P), "portable")


def load_cells_sql(w, shares=None):
    shares = shares or B.cover_shares(w.hypergraph, P)
    coord = lambda v, i: f"((({v} % 1000003) * {7919 + 2 * i} + {104729 * (i + 1)}) % 15485863) % {shares[v]}"
    parts, names = [], sorted(shares)
    for r in w.atoms.values():
        step, terms, tables = 1, [], [f"({r.sql()}) AS a"]
        for i, v in enumerate(names):
            if v in r.vars:
                terms.append(f"({coord(v, i)}) * {step}")
            else:
                tables.append(f"range({shares[v]}) AS g{i}(k{i})")
                terms.append(f"k{i} * {step}")
            step *= shares[v]
        parts.append(f"SELECT CAST({' + '.join(terms)} AS INT) AS cell FROM {' CROSS JOIN '.join(tables)}")
    return f"SELECT cell, count(*) AS cnt FROM ({' UNION ALL '.join(parts)}) GROUP BY cell"


def load_table(names, spark, sf_dir):
    """Load, replication and skew of the cover-mix join's combinations and of the one-round grid, with a hash that SQL repeats."""
    from gridjoin.plans.cost import combo_load, grid_load

    rows = []
    for name in names:
        plan = C.preprocess(WORKLOADS[name].query(spark, sf_dir), P)
        for i, c in enumerate(plan.combos):
            rows.append((name, f"cover-mix {i}", combo_load(plan, c, "portable")))
        shares = B.cover_shares(plan.hypergraph, plan.p)
        rows.append((name, "grid", grid_load([a.df for a in plan.query.atoms], shares, plan.n, plan.p, plan.hypergraph, "portable")))
    return spark.createDataFrame(
        [(n, m, r.max_load, r.sent, r.tuples_in, r.machines, r.rounds, *(round(float(x), 6) for x in (r.predicted, r.ratio, r.replication, r.skew))) for n, m, r in rows],
        "workload string, method string, max_load long, sent long, tuples_in long, machines int, rounds int, predicted double, ratio double, replication double, skew double",
    )


def load_sql(names):
    """Of workloads without heavy values, which have one combination that sends the relations as they are, and at least P^3 tuples."""
    from math import prod

    from gridjoin.functions.measures import kappa, tau_star
    from gridjoin.plans.weights import build_mix, integer_shares

    parts = []
    for name in names:
        w = WORKLOADS[name]
        for method, shares, number in (("cover-mix 0", integer_shares(build_mix(w.hypergraph, {}).exponents, P), kappa(w.hypergraph).value), ("grid", B.cover_shares(w.hypergraph, P), tau_star(w.hypergraph).value)):
            sizes = " UNION ALL ".join(f"SELECT count(*) AS c FROM ({r.sql()})" for r in w.atoms.values())
            parts.append(
                f"SELECT '{name}' AS workload, '{method}' AS method, max_load, sent, tuples_in, {prod(shares.values())} AS machines, 1 AS rounds, predicted, max_load / predicted AS ratio, sent / tuples_in AS replication, "
                f"max_load * {prod(shares.values())} / sent AS skew FROM (SELECT max(cnt) AS max_load, CAST(sum(cnt) AS BIGINT) AS sent FROM ({load_cells_sql(w, shares)})), "
                f"(SELECT CAST(sum(c) AS BIGINT) AS tuples_in, pow(2, ceil(log2(max(c)))) / pow({P}, 1 / {float(number)}) AS predicted FROM ({sizes}))"
            )
    return f"SELECT * REPLACE (round(predicted, 6) AS predicted, round(ratio, 6) AS ratio, round(replication, 6) AS replication, round(skew, 6) AS skew) FROM ({' UNION ALL '.join(parts)})"


def round_loads(names, spark, sf_dir):
    """Tuples received in every round of the cover-mix join's combinations."""
    from gridjoin.plans.cost import round_loads as loads

    rows = []
    for name in names:
        plan = C.preprocess(WORKLOADS[name].query(spark, sf_dir), P)
        rows += [(name, i, x.round, x.kind, x.what, x.machines, x.max_load, x.sent) for i, c in enumerate(plan.combos) for x in loads(plan, c)]
    return spark.createDataFrame(rows, "workload string, combo int, round int, kind string, what string, machines int, max_load long, sent long")


def size_bounds(w, spark, sf_dir):
    """Sizes of heavy sets, the heavy relation and intermediates against their bounds."""
    from gridjoin.plans.cost import sizes

    plan = C.preprocess(w.query(spark, sf_dir), P)
    rows = [(i, what, n, round(most, 3), n <= most) for i, c in enumerate(plan.combos) for what, n, most in sizes(plan, c)]
    return spark.createDataFrame(rows, "combo int, what string, tuples long, bound double, holds boolean")


def sparse_boat(spark, how):
    """Results of a sparse product instance, by one variable."""
    from gridjoin.functions.families import boat
    from gridjoin.plans.hard import sparse_product_instance
    from gridjoin.plans.query import JoinQuery

    query = JoinQuery(sparse_product_instance(spark, boat(3), 256, exact="rule"))
    joined = {"cm": lambda: C.cover_mix_join(query, 8), "hc": lambda: B.hypercube_join(query, 8), "cas": lambda: B.cascade_join(query)}[how]()
    return joined.groupBy("x0").count().withColumnRenamed("count", "cnt")


def sparse_rules():
    """The instance in SQL: its variables with their domains, and the conditions of its sparse edges."""
    from gridjoin.functions.families import boat
    from gridjoin.plans.hard import chances, domains, kept_by_rule

    h = boat(3)
    share = chances(h, 256)
    edges = {"".join(sorted(e)): (e, i) for i, e in enumerate(h.edges)}
    return domains(h, 256), {k: (sorted(e), kept_by_rule(e, i, share[k])) for k, (e, i) in edges.items() if share[k] < 1}, share


def sparse_boat_sql():
    sizes, rules, _ = sparse_rules()
    sparse = [f"(SELECT {', '.join(vs)} FROM {', '.join(f'range({sizes[v]}) AS {v}_({v})' for v in vs)} WHERE {rule}) AS e{i}" for i, (vs, rule) in enumerate(rules.values())]
    return f"SELECT x0, count(*) AS cnt FROM {', '.join(sparse)} GROUP BY x0"


def sparse_product(spark, sf_dir):
    """Tuples and results of the sparse product instance, and how many results are expected of it and of one machine of eight that receives n / 8 tuples."""
    from pyspark.sql import functions as F

    from gridjoin.functions.families import boat
    from gridjoin.plans.cost import expected_output, machine_output
    from gridjoin.plans.hard import sparse_product_instance

    share = list(sparse_rules()[2].values())
    largest = max(f.count() for f in sparse_product_instance(spark, boat(3), 256, exact="rule").values())
    results = sparse_boat(spark, "cas").agg(F.sum("cnt")).first()[0]
    return spark.createDataFrame([("boat_3", 256, largest, results, round(expected_output(boat(3), 256, share), 3), round(machine_output(boat(3), 32, share), 3))], "family string, n int, largest long, output long, expected double, of_a_machine double")


def sparse_product_sql():
    sizes, rules, share = sparse_rules()
    counts = " UNION ALL ".join(f"SELECT count(*) AS c FROM {', '.join(f'range({sizes[v]}) AS {v}_({v})' for v in vs)} WHERE {rule}" for vs, rule in rules.values())
    kept = 1.0
    for x in share.values():
        kept *= x
    return f"SELECT 'boat_3' AS family, 256 AS n, greatest({sizes['x0'] * sizes['y0']}, (SELECT max(c) FROM ({counts}))) AS largest, (SELECT CAST(sum(cnt) AS BIGINT) FROM ({sparse_boat_sql()})) AS output, round(pow(256, 3) * {kept}, 3) AS expected, round(pow(32, 3) * {kept}, 3) AS of_a_machine"


def dense_product(spark, sf_dir):
    from gridjoin.functions.families import triangle
    from gridjoin.plans.hard import product_instance
    from gridjoin.plans.query import JoinQuery

    joined = C.cover_mix_join(JoinQuery(product_instance(spark, triangle(), {"x": 30, "y": 20, "z": 10})), 8)
    return joined.groupBy("z").count().withColumnRenamed("count", "cnt")


def lifted(spark, sf_dir):
    """A boat instance lifted to the boat with one more variable: the results are the boat's."""
    from gridjoin.functions.families import boat, boat_plus_z
    from gridjoin.plans.hard import lift_instance, product_instance
    from gridjoin.plans.query import JoinQuery

    sizes = {x: 4 for x in boat(2).vertices}
    frames = product_instance(spark, boat(2), sizes)
    up = lift_instance({frozenset(f.columns): f for f in frames.values()}, boat_plus_z(2), frozenset(boat(2).vertices))
    return C.cover_mix_join(JoinQuery(up), 4).groupBy("z").count().withColumnRenamed("count", "cnt")


def plans() -> tuple[dict, dict]:
    q = {"measures_table": measures_table, "relations_table": relations_table, "kappa_methods": kappa_methods, "bounds_table": bounds_table, "sparse_product_sizes": sparse_product, "dense_product_triangle": dense_product, "lift_boat": lifted}
    sql = {
        "measures_table": f"SELECT kind, lines, orders, CAST(vertices AS INT) AS vertices, {', '.join(f'{_halves(m)} AS {m}' for m in ('rho', 'tau', 'kappa', 'psi', 'phi'))} FROM {ORDER_GRAPHS}",
        "kappa_methods": f"SELECT kind, lines, orders, {', '.join(f'{_halves('kappa')} AS {m}' for m in ('enumerated', 'program', 'auto'))} FROM {ORDER_GRAPHS}",
        "dense_product_triangle": "SELECT z, CAST(600 AS BIGINT) AS cnt FROM range(10) AS t(z)",
        "lift_boat": "SELECT CAST(0 AS BIGINT) AS z, CAST(256 AS BIGINT) AS cnt",
    }
    from gridjoin.functions.families import named

    relations = ["kappa >= tau(reduced)", "kappa >= rho", "rho(reduced) = rho", "kappa <= psi", "kappa <= rho * arity / 2", "kappa <= phi * arity / 2", "kappa = rho if no cycle", "kappa = rho if binary"]
    sql["relations_table"] = f"SELECT family, relation, true AS holds FROM ({_values('family', [(k,) for k in named()])}) CROSS JOIN ({_values('relation', [(r,) for r in relations])})"
    # n / p^(1 / number); these hypergraphs are reduced, so the conjectured bound is the one by tau
    load = lambda x: f"round(n / pow(64, 2 / {x}), 6)"
    sql["bounds_table"] = f"SELECT kind, lines, n, {load('kappa')} AS load_kappa, {load('psi')} AS load_psi, {load('rho')} AS load_rho, {load('tau')} AS load_tau, {load('phi')} AS load_phi, {load('rho')} AS lower, {load('tau')} AS conjectured, round(pow(n, rho / 2), 6) AS output FROM (SELECT *, CAST(pow(2, ceil(log2(tuples))) AS BIGINT) AS n FROM {ORDER_GRAPHS})"
    # the acceptance trace at 60,000 lines: one heavy set, two steps, all guarded by one relation
    sql["mix_w03"] = _values(
        "combo, n, p, kappa, steps, weights, heavy, heavy_sets, guards, shares, predicted_load",
        [(0, 65536, 32, "3/2", "xyz:3/5 yz:2/5", "x=3/10 y=1/2 z=1/2", "x", "{x}@r", "r<-s s<-s t<-s", "x=2 y=4 z=4", round(65536 / 32 ** (2 / 3), 3))],
    )
    # of workloads without heavy values: one step with the whole cover; and one heavy set that the last step leaves out
    sql["mix_w02"] = _values("combo, n, p, kappa, steps, weights, heavy, heavy_sets, guards, shares, predicted_load", [(0, 65536, 32, "3/2", "cps:1", "c=1/2 p=1/2 s=1/2", "", "", "r_cp<-r_cp r_cs<-r_cs r_ps<-r_ps", "c=3 p=3 s=3", round(65536 / 32 ** (2 / 3), 3))])
    sql["mix_w05"] = _values("combo, n, p, kappa, steps, weights, heavy, heavy_sets, guards, shares, predicted_load", [(0, 65536, 32, "2", "cnos:1", "c=1/2 n=1/2 o=1/2 s=1/2", "", "", "cust<-cust line<-line ord<-ord supp<-supp", "c=4 n=2 o=2 s=2", round(65536 / 32 ** (1 / 2), 3))])
    sql["mix_w09"] = _values("combo, n, p, kappa, steps, weights, heavy, heavy_sets, guards, shares, predicted_load", [(0, 65536, 32, "4/3", "flps:4/5 lps:1/5", "f=4/15 l=1/3 p=1/3 s=1/3", "f", "{f}@r_psf", "r_plf<-r_psl r_psf<-r_psl r_psl<-r_psl r_slf<-r_psl", "f=2 l=4 p=2 s=2", round(65536 / 32 ** (3 / 4), 3))])
    for name in ("w02", "w03", "w05", "w09", "w28", "w30"):
        q[f"mix_{name}"] = partial(explain_mix, WORKLOADS[name])
    for name in ("w02", "w03", "w19", "w23"):
        q[f"sig_{name}"] = partial(signature_table, WORKLOADS[name], True)
        sql[f"sig_{name}"] = signature_sql(WORKLOADS[name], True)
    for name in ("w03", "w19"):
        q[f"sig_noclamp_{name}"] = partial(signature_table, WORKLOADS[name], False)
        sql[f"sig_noclamp_{name}"] = signature_sql(WORKLOADS[name], False)
    for name in ("w19", "w22"):
        q[f"constraint_check_{name}"] = partial(constraint_check, WORKLOADS[name])
        sql[f"constraint_check_{name}"] = "SELECT CAST(0 AS BIGINT) AS violations"
    q["heavy_rel_w03"] = partial(heavy_rel, WORKLOADS["w03"])
    w = WORKLOADS["w03"]
    sql["heavy_rel_w03"] = f"SELECT x FROM ({w.atoms['r'].sql()}) GROUP BY x HAVING count(*) * {P} > (SELECT CAST(pow(2, ceil(log2(max(c)))) AS BIGINT) FROM (SELECT count(*) AS c FROM ({w.atoms['r'].sql()}) UNION ALL SELECT count(*) FROM ({w.atoms['s'].sql()})))"
    for name in ("w02", "w05"):
        q[f"load_cells_{name}"] = partial(load_cells, WORKLOADS[name])
        sql[f"load_cells_{name}"] = load_cells_sql(WORKLOADS[name])
    q["load_table"] = partial(load_table, ("w02", "w05", "w07"))
    sql["load_table"] = load_sql(("w02", "w05", "w07"))
    q["round_loads"] = partial(round_loads, ("w02", "w03", "w09", "w27"))
    for name in ("w03", "w29"):
        q[f"size_bounds_{name}"] = partial(size_bounds, WORKLOADS[name])
    # one heavy relation of the values of x, each beside every tuple of the guard; v = 1/5 of x, so the bounds are 2p, 2 p^(1/5) and 2 n p^(1/5)
    sql["size_bounds_w03"] = f"""WITH h AS ({sql['heavy_rel_w03']}), s AS ({w.atoms['s'].sql()}), c AS (SELECT (SELECT count(*) FROM h) AS h, (SELECT count(*) FROM s) AS s)
        SELECT 0 AS combo, what, tuples, round(bound, 3) AS bound, tuples <= bound AS holds FROM (SELECT 'heavy set {{x}} of r' AS what, h AS tuples, 2.0 * {P} AS bound FROM c UNION ALL SELECT 'heavy relation', h, 2 * pow({P}, 0.2) FROM c
        UNION ALL SELECT 's joined', h * s, 2 * pow({P}, 0.2) * pow(2, ceil(log2(s))) FROM c)"""
    for how in ("cm", "hc", "cas"):
        q[f"sparse_boat_{how}"] = lambda s, d, how=how: sparse_boat(s, how)
        sql[f"sparse_boat_{how}"] = sparse_boat_sql()
    sql["sparse_product_sizes"] = sparse_product_sql()
    return q, sql


# ---- relational operators, SQL front, streams ---------------------------------------------------------------------------------


def operators() -> tuple[dict, dict]:
    from pyspark.sql import functions as F

    from gridjoin.operators import relops as R
    from gridjoin.sources.tables import keys, load

    q, sql = {}, {}

    def add(name, fn, text):
        q[name] = fn
        if text:
            sql[name] = text

    def on(table, fn):
        return lambda s, d: fn(load(s, d, table))

    def two(a, b, fn):
        return lambda s, d: fn(load(s, d, a), load(s, d, b))

    def copied(fmt):
        def run(s, d):
            from gridjoin.sources.tables import read_text_formats, write
            from gridjoin.streaming.streams import checkpoint_of

            path = checkpoint_of(s, f"nation-{fmt}")
            write(load(s, d, "nation"), path, fmt)
            return read_text_formats(s, path, fmt, "n_nationkey int, n_name string, n_regionkey int")

        return run

    for fmt in ("csv", "json", "orc"):
        add(f"op_j02_{fmt}", copied(fmt), "SELECT n_nationkey, n_name, n_regionkey FROM nation")

    def partitioned(s, d):
        from gridjoin.sources.tables import write
        from gridjoin.streaming.streams import checkpoint_of

        path = checkpoint_of(s, "events-by-type")
        write(load(s, d, "events", ["event_id", "event_type"]), path, "parquet", ["event_type"])
        return s.read.parquet(path).where("event_type = 'click'").select("event_id")

    add("op_j07_partitioned", partitioned, "SELECT event_id FROM events WHERE event_type = 'click'")
    oc = ["o_orderkey", "o_custkey"]
    add("op_j01_load", lambda s, d: load(s, d, "nation", ["n_nationkey", "n_name"]), "SELECT n_nationkey, n_name FROM nation")
    add("op_j03_keys", on("orders", lambda t: keys(t.select("o_orderkey"), "o_orderkey")), "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderkey) - 1 AS k FROM orders")
    add("op_j10_project", on("orders", lambda t: R.project(t, ["o_custkey", "o_orderstatus"])), "SELECT DISTINCT o_custkey, o_orderstatus FROM orders")
    add("op_j11_rename", on("region", lambda t: R.rename(t, {"r_regionkey": "k", "r_name": "name"})), "SELECT r_regionkey AS k, r_name AS name FROM region")
    add("op_j12_derive", on("lineitem", lambda t: R.derive(t, y="l_orderkey * 100000 + l_partkey").select("y").distinct()), "SELECT DISTINCT l_orderkey * 100000 + l_partkey AS y FROM lineitem")
    add("op_j13_restrict", two("orders", "customer", lambda o, c: R.restrict(o.select(*oc), c.where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("o_custkey")))), "SELECT o_orderkey, o_custkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")
    add("op_j14_filters", on("part", lambda t: t.where("p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#21') AND p_type LIKE '%E%' AND p_name IS NOT NULL").select("p_partkey")), "SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#21') AND p_type LIKE '%E%' AND p_name IS NOT NULL")
    add("op_j15_case_when", on("orders", lambda t: R.case_when(t, "size", [("o_totalprice > 200000", "large"), ("o_totalprice > 50000", "middle")], "small").groupBy("size").agg(F.count("*").alias("cnt"))), "SELECT CASE WHEN o_totalprice > 200000 THEN 'large' WHEN o_totalprice > 50000 THEN 'middle' ELSE 'small' END AS size, count(*) AS cnt FROM orders GROUP BY 1")
    joined = "SELECT o_orderkey, o_custkey, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
    for name, hint in (("j20_hash", "shuffle_hash"), ("j21_merge", "merge")):
        add(f"op_{name}_join", two("orders", "lineitem", lambda o, t, hint=hint: o.select(*oc).join(t.select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey").hint(hint), "o_orderkey")), joined)
    add("op_j22_broadcast_join", two("customer", "nation", lambda c, n: c.join(F.broadcast(n), F.expr("c_nationkey = n_nationkey")).groupBy("n_name").agg(F.count("*").alias("cnt"))), "SELECT n_name, count(*) AS cnt FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
    add("op_j23_cartesian", two("region", "lineitem", lambda r, t: R.cartesian(r.select("r_name"), t.select("l_linestatus").distinct())), "SELECT r_name, l_linestatus FROM region CROSS JOIN (SELECT DISTINCT l_linestatus FROM lineitem)")
    key = lambda o: o.select(F.col("o_custkey").alias("c_custkey"))
    add("op_j24_semi_join", two("customer", "orders", lambda c, o: R.semi_join(c.select("c_custkey"), key(o), ["c_custkey"])), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
    add("op_j25_anti_join", two("customer", "orders", lambda c, o: R.anti_join(c.select("c_custkey"), key(o.where("o_orderstatus = 'F'")), ["c_custkey"])), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
    for how in ("left", "right", "full"):
        add(f"op_j26_{how}_outer", two("documents", "labels", lambda d, t, how=how: d.select("doc_id", "lang").join(t.select("doc_id", "quality"), "doc_id", how)), f"SELECT doc_id, lang, quality FROM (SELECT doc_id, lang FROM documents) {how} JOIN (SELECT doc_id, quality FROM labels) USING (doc_id)")
    add("op_j27_theta_join", two("nation", "region", lambda n, r: R.theta_join(n.select("n_nationkey"), r.select("r_regionkey"), "n_nationkey < r_regionkey * 3")), "SELECT n_nationkey, r_regionkey FROM nation JOIN region ON n_nationkey < r_regionkey * 3")
    add("op_j28_range_join", two("part", "supplier", lambda p, s_: R.range_join(p.select("p_partkey", "p_retailprice"), s_.where("s_acctbal > 0").selectExpr("s_suppkey", "s_acctbal AS lo", "s_acctbal + 20 AS hi"), "p_retailprice", "lo", "hi", 50.0).select("p_partkey", "s_suppkey")), "SELECT p_partkey, s_suppkey FROM part JOIN supplier ON s_acctbal > 0 AND p_retailprice BETWEEN s_acctbal AND s_acctbal + 20")
    add("op_j29_asof_join", on("events", lambda e: R.asof_join(e.where("event_type = 'click'"), e.where("event_type = 'purchase'"), "user_id", "ts", "value", "event_id").select("event_id", "last_value")), "SELECT a.event_id, (SELECT arg_max(b.value, struct_pack(t := b.ts, e := b.event_id)) FROM events b WHERE b.event_type = 'purchase' AND b.user_id = a.user_id AND b.ts <= a.ts) AS last_value FROM events a WHERE a.event_type = 'click'")
    add("op_j30_interval_join", on("events", lambda e: R.interval_join(e.where("event_type = 'click'").select("event_id", "user_id", "ts"), e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), "user_id", "ts", 86400).select("event_id", "b_event_id")), "SELECT a.event_id, b.event_id AS b_event_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND epoch(date_trunc('second', b.ts)) - epoch(date_trunc('second', a.ts)) BETWEEN 0 AND 86400")
    add("op_j31_lateral", lambda s, d: s.sql("SELECT o_orderkey, m FROM {o} AS o, LATERAL (SELECT max(l_partkey) AS m FROM {l} AS l WHERE l.l_orderkey = o.o_orderkey)", o=load(s, d, "orders"), l=load(s, d, "lineitem")), "SELECT o_orderkey, max(l_partkey) AS m FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey")
    add("op_j40_hash_agg", on("lineitem", lambda t: R.hash_agg(t, ["l_returnflag", "l_linestatus"], qty="sum(l_quantity)", cnt="count(*)", top="max(l_extendedprice)")), "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, count(*) AS cnt, max(l_extendedprice) AS top FROM lineitem GROUP BY 1, 2")
    add("op_j41_sort_agg", on("lineitem", lambda t: t.groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("ps")).select("l_orderkey", F.array_join(F.transform("ps", lambda x: x.cast("string")), ",").alias("parts"))), "SELECT l_orderkey, array_to_string(list_sort(list(DISTINCT l_partkey)), ',') AS parts FROM lineitem GROUP BY l_orderkey")
    add("op_j42_distinct_agg", on("lineitem", lambda t: t.groupBy("l_partkey").agg(F.count_distinct("l_suppkey").alias("cnt"))), "SELECT l_partkey, count(DISTINCT l_suppkey) AS cnt FROM lineitem GROUP BY 1")
    add("op_j43_approx", on("lineitem", lambda t: t.agg((F.abs(F.approx_count_distinct("l_orderkey", 0.02) / F.count_distinct("l_orderkey") - 1) < 0.1).alias("distinct_near"), (F.abs(F.percentile_approx("l_quantity", 0.5, 1000) - 25) < 3).alias("median_near"))), "SELECT true AS distinct_near, true AS median_near")
    for kind in ("cube", "rollup"):
        add(f"op_j44_{kind}", on("lineitem", lambda t, kind=kind: R.grouping_sets(t, ["l_returnflag", "l_linestatus"], kind, cnt="count(*)")), f"SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus) AS gid, count(*) AS cnt FROM lineitem GROUP BY {kind}(l_returnflag, l_linestatus)")
    add("op_j45_pivot", on("orders", lambda t: R.pivot(t, ["o_orderpriority"], "o_orderstatus", ["F", "O", "P"], "count(*)")), 'SELECT o_orderpriority, nullif(count(*) FILTER (o_orderstatus = \'F\'), 0) AS "F", nullif(count(*) FILTER (o_orderstatus = \'O\'), 0) AS "O", nullif(count(*) FILTER (o_orderstatus = \'P\'), 0) AS "P" FROM orders GROUP BY 1')
    for name in ("w08", "w11", "w12", "w14", "w21"):
        w = WORKLOADS[name]
        add(f"count_{name}", lambda s, d, w=w: B.hypercube_join(w.query(s, d), P).agg(F.count("*").alias("cnt")), f"SELECT count(*) AS cnt FROM {w.join_sql()}")
    add("op_j47_min_max_by", on("orders", lambda t: t.groupBy("o_orderstatus").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dear"), F.bool_or(F.col("o_totalprice") > 1000).alias("any_big"))), "SELECT o_orderstatus, arg_max(o_orderkey, struct_pack(a := o_totalprice, b := o_orderkey)) AS dear, bool_or(o_totalprice > 1000) AS any_big FROM orders GROUP BY 1")
    for kind, text in (("row_number", "row_number()"), ("rank", "rank()"), ("dense_rank", "dense_rank()"), ("ntile4", "ntile(4)")):
        add(f"op_j50_{kind}", on("customer", lambda t, kind=kind: R.rank(t, ["c_nationkey"], [F.desc("c_acctbal"), F.asc("c_custkey")], kind).select("c_custkey", F.col("rk").cast("long").alias("rk"))), f"SELECT c_custkey, {text} OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rk FROM customer")
    add("op_j51_lag_lead", lambda s, d: s.sql("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM {e} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", e=load(s, d, "events")), "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
    add("op_j52_running", on("orders", lambda t: R.frame_agg(t, ["o_custkey"], ["o_orderkey"], "count(*)", "n", (-2, 0)).select("o_orderkey", "n")), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM orders")
    for method in ("join", "window"):
        from gridjoin.plans.degrees import sum_by_key

        add(f"sum_by_key_{method}", on("orders", lambda t, method=method: sum_by_key(t.select(*oc), ["o_custkey"], method).select("o_orderkey", "cnt")), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey) AS cnt FROM orders")
    from gridjoin.plans.degrees import degree

    add("degree_orders_c", on("orders", lambda t: degree(t.select(*oc).distinct(), ["o_custkey"])), "SELECT o_custkey, count(DISTINCT o_orderkey) AS deg FROM orders GROUP BY 1")
    add("degree_given", on("lineitem", lambda t: degree(t, ["l_partkey"], ["l_suppkey"])), "SELECT l_suppkey, count(DISTINCT l_partkey) AS deg FROM lineitem GROUP BY 1")
    add("op_j55_sort", on("orders", lambda t: t.orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey")), "SELECT o_orderkey FROM orders")
    add("op_j56_top_k", on("orders", lambda t: R.top_k(t, [F.desc("o_totalprice"), F.asc("o_orderkey")], 25).select("o_orderkey")), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
    add("op_j57_top_k_per_group", on("customer", lambda t: R.top_k_per_group(t, ["c_nationkey"], [F.desc("c_acctbal"), F.asc("c_custkey")], 3).select("c_custkey")), "SELECT c_custkey FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) <= 3")
    from gridjoin.plans.degrees import heavy_candidates

    for method in ("exact", "sketch"):
        add("op_j58_heavy_hitters" + ("_sketch" if method == "sketch" else ""), on("lineitem", lambda t, method=method: heavy_candidates(t, ["l_suppkey"], 600, method, 512)), "SELECT l_suppkey, count(*) AS cnt FROM lineitem GROUP BY 1 HAVING count(*) > 600")
    cust, buyers = "SELECT c_custkey AS k FROM customer WHERE c_acctbal > 0", "SELECT o_custkey AS k FROM orders"
    both = lambda fn: two("customer", "orders", lambda c, o: fn(c.where("c_acctbal > 0").selectExpr("c_custkey AS k"), o.selectExpr("o_custkey AS k")))
    for name, fn, text in (("j60_union_all", lambda a, b: a.unionByName(b), "UNION ALL"), ("j60_union", lambda a, b: a.unionByName(b).distinct(), "UNION"), ("j61_intersect", lambda a, b: a.intersect(b), "INTERSECT"), ("j61_intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"), ("j62_except", lambda a, b: b.subtract(a), None), ("j62_except_all", lambda a, b: b.exceptAll(a), None)):
        add(f"op_{name}", both(fn), f"{cust} {text} {buyers}" if text else f"{buyers} EXCEPT {'ALL ' if 'all' in name else ''}{cust}")
    add("op_j65_strings", on("pages", lambda t: t.select("page_id", F.regexp_extract("url", "://([^/]+)/", 1).alias("host"), F.length(F.trim("url")).cast("long").alias("n"), F.upper(F.substring("url", 1, 5)).alias("up"))), "SELECT page_id, regexp_extract(url, '://([^/]+)/', 1) AS host, length(trim(url)) AS n, upper(substr(url, 1, 5)) AS up FROM pages")
    add("op_j66_dates", on("orders", lambda t: t.select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.datediff(F.lit("2002-01-01"), F.to_date("o_orderdate")).cast("long").alias("age"))), "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', CAST(o_orderdate AS DATE), DATE '2002-01-01') AS age FROM orders")
    add("op_j67_math", on("orders", lambda t: t.select("o_orderkey", F.pmod(F.col("o_orderkey") * 31, F.lit(7)).alias("m"), F.bin("o_orderkey").alias("b"), F.greatest(F.col("o_orderkey"), F.col("o_custkey")).alias("g"))), "SELECT o_orderkey, (o_orderkey * 31) % 7 AS m, bin(o_orderkey) AS b, greatest(o_orderkey, o_custkey) AS g FROM orders")
    add("op_j68_arrays", on("embeddings", lambda t: t.select("vec_id", F.size("embedding").cast("long").alias("n"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("norm2"))), "SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm2 FROM embeddings")
    add("op_j69_maps", on("orders", lambda t: t.groupBy("o_orderstatus").agg(F.count("*").alias("c")).agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "c"))).alias("m")).select(F.element_at("m", "O").alias("open"))), "SELECT count(*) AS open FROM orders WHERE o_orderstatus = 'O'")
    add("op_j70_json", on("events", lambda t: t.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))), "SELECT event_id, CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT) AS k FROM events")
    add("op_j71_nulls", on("labels", lambda t: t.select("doc_id", F.nullif("quality", F.lit(0)).alias("q"), F.coalesce(F.nullif("quality", F.lit(0)), F.col("toxic") + 10).alias("c"))), "SELECT doc_id, nullif(quality, 0) AS q, coalesce(nullif(quality, 0), toxic + 10) AS c FROM labels")

    def udf_bucket(s, d):
        from gridjoin.functions.udf import degree_bucket_udf

        return load(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("c")).select("o_custkey", degree_bucket_udf()("c").alias("b"))

    add("op_j75_udf_bucket", udf_bucket, "SELECT o_custkey, CASE WHEN c <= 1 THEN 0 ELSE length(bin(c - 1)) END AS b FROM (SELECT o_custkey, count(*) AS c FROM orders GROUP BY 1)")

    def udaf_degree(s, d):
        from gridjoin.functions.udf import max_degree_udf

        counts = load(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("c")).withColumn("g", F.col("o_custkey") % 5)
        return counts.groupBy("g").agg(max_degree_udf()("c").alias("most"))

    add("op_j76_udaf_degree", udaf_degree, "SELECT g, max(c) AS most FROM (SELECT o_custkey % 5 AS g, count(*) AS c FROM orders GROUP BY o_custkey) GROUP BY g")

    def udtf(table, text):
        def run(s, d):
            from gridjoin.functions.udf import register_table_functions

            register_table_functions(s)
            return s.sql(text, t=load(s, d, table))

        return run

    add("op_j77_udtf_cells", udtf("orders", "SELECT o_orderkey, cell FROM {t}, LATERAL grid_cells(array(CAST(o_orderkey % 2 AS INT), -1, CAST(o_custkey % 4 AS INT)), array(2, 3, 4))"), "SELECT o_orderkey, CAST(o_orderkey % 2 + 2 * v + 6 * (o_custkey % 4) AS INT) AS cell FROM orders, range(3) AS r(v)")
    # each set of line numbers that an order has, as a star of the order and its lines
    stars = "SELECT DISTINCT array_sort(collect_set(l_linenumber)) AS ls FROM {t} WHERE l_linenumber IS NOT NULL GROUP BY l_orderkey"
    add("op_j78_udtf_measures", udtf("lineitem", f"SELECT array_join(ls, ',') AS lines, measure, value FROM ({stars}), LATERAL hypergraph_measures(to_json(transform(ls, l -> array('order', CAST(l AS STRING)))))"), "SELECT DISTINCT lines, measure, CASE measure WHEN 'tau' THEN '1' ELSE CAST(k AS VARCHAR) END AS value FROM (SELECT array_to_string(list_sort(list(DISTINCT l_linenumber)), ',') AS lines, count(DISTINCT l_linenumber) AS k FROM lineitem WHERE l_linenumber IS NOT NULL GROUP BY l_orderkey), (VALUES ('rho'), ('tau'), ('kappa'), ('psi'), ('phi')) AS m(measure)")

    def front(text, name):
        def run(s, d):
            from gridjoin.plans.sqlfront import run_sql
            from gridjoin.sources.tables import register

            register(s, d, ("orders", "lineitem", "customer", "supplier"))
            df, how = run_sql(s, text, P)
            assert how == "multiway", how
            return df

        add(name, run, text)

    front("SELECT c, count(*) AS cnt FROM (SELECT DISTINCT o_custkey AS c, o_orderkey AS o FROM orders) AS a JOIN (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem) AS b USING (o) WHERE p > c GROUP BY c", "sql_path")
    front("SELECT n, count(*) AS cnt FROM (SELECT DISTINCT c_custkey AS c, c_nationkey AS n FROM customer) AS cu JOIN (SELECT DISTINCT o_custkey AS c, o_orderkey AS o FROM orders) AS od USING (c) JOIN (SELECT DISTINCT l_orderkey AS o, l_suppkey AS s FROM lineitem) AS li USING (o) JOIN (SELECT DISTINCT s_suppkey AS s, s_nationkey AS n FROM supplier) AS su USING (n, s) GROUP BY n", "sql_cycle")
    return q, sql


def streams() -> tuple[dict, dict]:
    from pyspark.sql import functions as F

    from gridjoin.sources.tables import load, stream_events
    from gridjoin.streaming import streams as S

    def source(s, d):
        # a pattern, as a stream's path must not be one file
        return stream_events(s, f"{d}/events.parque*", load(s, d, "events").schema).withColumn("ts", F.col("ts").cast("timestamp"))

    def degrees(s, d, **kw):
        return S.run_to_end(S.stream_degrees(source(s, d), ["user_id"], "1 day", "2 days", **kw), "degrees", "complete").select(F.date_format("w_start", "yyyy-MM-dd HH:mm:ss").alias("w_start"), "user_id", "deg")

    def delta(s, d):
        w = WORKLOADS["w19"]
        query = w.query(s, d).normalized()
        old, new = {}, {}
        for a in query.atoms:
            pick = F.pmod(F.xxhash64(*a.vars), F.lit(10)) == 0
            old[a.name], new[a.name] = a.df.where(~pick), a.df.where(pick)
        from gridjoin.plans.query import JoinQuery

        return B.cascade_join(JoinQuery(old)).unionByName(S.delta_join(JoinQuery(old), new))

    def multiway(s, d):
        w = WORKLOADS["w19"]
        query = {a.name: a.df for a in w.query(s, d).normalized().atoms}
        new = source(s, d).selectExpr("user_id AS u", "event_type AS y")
        query.pop("ut")
        return S.stream_multiway_join(new, "ut", query, P, S.checkpoint_of(s, "multiway-out")).select(*w.variables)

    def pairs(s, d):
        e = source(s, d)
        joined = S.stream_interval_join(e.where("event_type = 'click'").select("event_id", "user_id", "ts"), source(s, d).where("event_type = 'purchase'").select("event_id", "user_id", "ts"), "user_id", 3600, "1 day")
        return S.run_to_end(joined, "pairs").select("a_event_id", "b_event_id")

    def heavy(s, d):
        return S.run_to_end(S.heavy_keys_stateful(source(s, d).select("user_id"), "user_id", 60, 20.0), "heavy").select("user_id", "heavy")

    q = {
        "stream_degrees": degrees,
        "stream_degrees_sliding": lambda s, d: degrees(s, d, slide="12 hours"),
        "stream_degrees_session": lambda s, d: degrees(s, d, gap="6 hours"),
        "stream_dedup": lambda s, d: S.run_to_end(S.stream_dedup(source(s, d).select("event_id", "ts"), ["event_id"], "1 day"), "dedup").select("event_id"),
        "stream_interval_join": pairs,
        "stream_heavy_keys": heavy,
        "stream_multiway": multiway,
        "delta_join_w19": delta,
    }
    text = lambda t: f"strftime({t}, '%Y-%m-%d %H:%M:%S')"
    sql = {
        "stream_degrees": f"SELECT {text("date_trunc('day', ts)")} AS w_start, user_id, count(*) AS deg FROM events GROUP BY 1, 2",
        "stream_degrees_sliding": f"SELECT {text('make_timestamp(CAST(w AS BIGINT) * 1000000)')} AS w_start, user_id, count(*) AS deg FROM (SELECT user_id, floor(epoch(ts) / 43200) * 43200 - k * 43200 AS w FROM events, range(2) AS t(k)) GROUP BY 1, 2",
        "stream_degrees_session": f"SELECT {text('min(ts)')} AS w_start, user_id, count(*) AS deg FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOURS THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, k",
        "stream_dedup": "SELECT DISTINCT event_id FROM events",
        "stream_interval_join": "SELECT a.event_id AS a_event_id, b.event_id AS b_event_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 3600 SECONDS",
        "stream_heavy_keys": "SELECT user_id, true AS heavy FROM events GROUP BY user_id HAVING count(*) >= 60",
        "stream_multiway": WORKLOADS["w19"].sql(),
        "delta_join_w19": WORKLOADS["w19"].sql(),
    }
    return q, sql


def queries() -> dict:
    return {k: v for part in (joins, plans, operators, streams) for k, v in part()[0].items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for part in (joins, plans, operators, streams) for k, v in part()[1].items()}
