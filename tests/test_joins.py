"""Join algorithms against a brute-force natural join, on random skewed relations and on degenerate ones."""

import random
from collections import Counter
from fractions import Fraction
from itertools import product

import pytest
from pyspark.sql import functions as F

from gridjoin.operators import baselines as B
from gridjoin.plans import covermix as C
from gridjoin.plans import degrees as D
from gridjoin.plans.combined import blocks, product_in_grid, shapes
from gridjoin.plans.combined import run as run_combined
from gridjoin.plans import cost
from gridjoin.plans.cost import exchanges
from gridjoin.plans.grid import CELL, grid_join, grid_precondition, placed, replicate
from gridjoin.plans.hard import bowtie_instance, chances, lift_instance, product_instance, sparse_product_instance, triangle_instance, witness_check
from gridjoin.plans.query import JoinQuery, max_machines, natural_join
from gridjoin.plans.sqlfront import run_sql
from gridjoin.functions import families


def frame(spark, names, rows):
    return spark.createDataFrame(rows or [], ", ".join(f"{n} long" for n in names)) if rows else spark.createDataFrame([], ", ".join(f"{n} long" for n in names))


def brute(relations):
    out = [{}]
    for names, rows in relations.values():
        new = []
        for r in {tuple(r) for r in rows}:
            if None in [v for n, v in zip(names, r, strict=True) if sum(n in ns for ns, _ in relations.values()) > 1]:
                continue
            for o in out:
                if all(o.get(n, v) == v for n, v in zip(names, r, strict=True)):
                    new.append(o | dict(zip(names, r, strict=True)))
        out = new
    return sorted({tuple(o[k] for k in sorted(o)) for o in out})


def rows_of(df):
    return sorted(tuple(r) for r in df.select(*sorted(df.columns)).collect())


def skewed(rng, names, n, heavy=2):
    return [[rng.choice([0, 1]) if i == heavy and rng.random() < 0.7 else int(rng.paretovariate(1.1)) % 30 for i, _ in enumerate(names)] for _ in range(n)]


SHAPES = {
    "triangle": ["xy", "yz", "xz"],
    "path": ["xy", "yz"],
    "bowtie": ["xy", "yz", "xz", "zv", "zw", "vw"],
    "lw4": ["abc", "abd", "acd", "bcd"],
    "star": ["hx", "hy", "hz"],
    "not_reduced": ["x", "xy", "y"],
    "apart": ["ab", "cd"],
}


@pytest.mark.parametrize("shape", SHAPES)
def test_cover_mix_equals_brute_force(spark, shape):
    rng = random.Random(shape)
    relations = {f"r{i}": (list(e), skewed(rng, e, 60, 0)) for i, e in enumerate(SHAPES[shape])}
    q = JoinQuery({k: frame(spark, n, r) for k, (n, r) in relations.items()})
    expected = brute(relations)
    got = rows_of(C.cover_mix_join(q, 8))
    assert got == expected and len(got) == len(set(got))
    assert rows_of(B.cascade_join(q)) == expected


def test_parts_with_heavy_values_at_a_forced_p(spark):
    rng = random.Random(1)
    relations = {"r": (["x", "y"], [[i % 2, i] for i in range(64)]), "s": (["y", "z"], [[i, rng.randint(0, 9)] for i in range(64)]), "t": (["x", "z"], [[i % 2, i % 10] for i in range(40)])}
    q = JoinQuery({k: frame(spark, n, r) for k, (n, r) in relations.items()}).normalized()
    plan = C.preprocess(q, 16, lower_p=False, normalized=True)
    assert any(c.mix.heavy for c in plan.combos)
    for c in plan.combos:
        assert c.machines <= 16
        if c.mix.heavy:
            parts = {a.name: plan.tagged[a.name].where(c.parts[a.name].condition()).select(*a.vars) for a in q.atoms}
            assert C.heavy_relation(parts, c.mix.heavy_sets).count() <= C.heavy_bound(c, plan.hypergraph)
    for options in ({}, {"heavy": "per_relation"}, {"self_guard": "direct"}):
        got = []
        for c in plan.combos:
            got += rows_of(C.run_combo(plan, c, **options))
        assert sorted(got) == brute(relations)


def test_baselines(spark):
    rng = random.Random(2)
    relations = {f"r{i}": (list(e), skewed(rng, e, 80, 0)) for i, e in enumerate(SHAPES["triangle"])}
    q = JoinQuery({k: frame(spark, n, r) for k, (n, r) in relations.items()})
    expected = brute(relations)
    for fn in (lambda: B.hypercube_join(q, 8), lambda: B.hypercube_join(q, 8, "equal"), lambda: B.hypercube_join(q, 8, {"x": 2, "y": 2, "z": 2}), lambda: B.one_round_skew_join(q, 8, 10), lambda: B.dedicated_heavy_join(q, 8, 10), lambda: B.triangle_two_case_join(q, 8)):
        assert rows_of(fn()) == expected
    with pytest.raises(ValueError):
        B.acyclic_join(q)


def test_degenerate(spark):
    rows = [[None, 1], [1, 1], [1, 1], [2, None], [2, 3]]
    relations = {"a": (["x", "y"], rows), "b": (["y", "z"], [[1, 5], [None, 6], [3, 7]])}
    q = JoinQuery({k: frame(spark, n, r) for k, (n, r) in relations.items()})
    expected = [(1, 1, 5), (2, 3, 7)]
    got = [r for r in rows_of(C.cover_mix_join(q, 4).where("x IS NOT NULL"))]
    assert got == expected
    empty = JoinQuery({"a": frame(spark, "xy", rows), "b": frame(spark, "yz", [])})
    assert C.cover_mix_join(empty, 4).count() == 0 and C.cover_mix_join(empty, 4).columns == ["x", "y", "z"]
    one = JoinQuery({"a": frame(spark, "xy", [[1, 2], [1, 2]])})
    assert rows_of(C.cover_mix_join(one, 1)) == [(1, 2)]
    mixed = JoinQuery({"a": spark.createDataFrame([(1, "é")], "x int, y string"), "b": spark.createDataFrame([("é", 2)], "y string, z long")})
    assert rows_of(C.cover_mix_join(mixed, 2)) == [(1, "é", 2)]
    with pytest.raises(TypeError):
        JoinQuery({"a": spark.createDataFrame([(1, "a")], "x int, y string"), "b": frame(spark, "yz", [[1, 2]])}).normalized()


def test_degree_parts(spark):
    rng = random.Random(3)
    df = frame(spark, "xy", [[int(rng.paretovariate(0.8)) % 20, i] for i in range(200)]).distinct()
    tagged = D.uniformize(df, ["x", "y"], 256, 8, clamp=False)
    assert tagged.count() == df.count() and rows_of(tagged.select("x", "y")) == rows_of(df)
    parts = D.signatures(tagged, ["x", "y"])
    assert sum(s.count for s in parts) == df.count() and len(parts) <= D.part_bound(256, 2)
    for s in parts:
        sigma = {frozenset(u): 1 << b for u, b in s.buckets}
        assert D.violations(tagged.where(s.condition()).select("x", "y"), ["x", "y"], sigma).count() == 0
    exact = frame(spark, "xy", [[0, i] for i in range(8)] + [[1, i] for i in range(9)])
    found = {r["x"]: r["b_x"] for r in D.uniformize(exact, ["x", "y"], 32, 4, clamp=False).collect()}
    assert found == {0: 3, 1: 4}  # a power of two stands in one bucket only
    assert rows_of(D.sum_by_key(exact, ["x"], "join")) == rows_of(D.sum_by_key(exact, ["x"], "window"))


def test_grid_plan_and_witness(spark):
    frames = list(triangle_instance(spark, 128, 64).values())
    shares = {"x": 2, "y": 2, "z": 2}
    cells = [r[0] for r in placed(frames, shares)[0].select(F.spark_partition_id(), CELL).distinct().groupBy(CELL).count().select("count").collect()]
    assert set(cells) == {1}
    received = {tuple(f.columns): replicate(f, ["x", "y", "z"], shares) for f in frames}
    out = None
    for r in received.values():
        out = r if out is None else out.join(r, [c for c in out.columns if c in r.columns])
    assert witness_check(out, received, CELL).count() == 0
    assert grid_precondition(frames[1], shares, 128 * 4) and not grid_precondition(frames[0], {"x": 64, "y": 1}, 128)
    assert max_machines(65536) == 32


def test_hard_instances(spark):
    h = families.triangle()
    dense = product_instance(spark, h, {"x": 4, "y": 5, "z": 6})
    assert B.cascade_join(JoinQuery(dense)).count() == 120
    sparse = sparse_product_instance(spark, families.boat(2), 256)
    assert max(f.count() for f in sparse.values()) <= 512
    boat = families.boat(2)
    frames = product_instance(spark, boat, {x: 3 for x in boat.vertices})
    up = lift_instance({frozenset(f.columns): f for f in frames.values()}, families.boat_plus_z(2), frozenset(boat.vertices))
    assert B.cascade_join(JoinQuery(up)).count() == 81 and C.cover_mix_join(JoinQuery(up), 4).count() == 81


def test_sql_front(spark):
    frame(spark, "xy", [[1, 2], [3, 4]]).createOrReplaceTempView("ta")
    frame(spark, "yz", [[2, 5], [4, 6]]).createOrReplaceTempView("tb")
    df, how = run_sql(spark, "SELECT x, z FROM ta AS a JOIN tb AS b USING (y) WHERE x > 1", 4)
    assert how == "multiway" and rows_of(df) == [(3, 6)]
    df, how = run_sql(spark, "SELECT x FROM ta LEFT JOIN tb USING (y)")
    assert how != "multiway" and df.count() == 2


def test_absorbed(spark):
    q = JoinQuery({"a": frame(spark, "x", [[1]]), "b": frame(spark, "xy", [[1, 2], [3, 4]])})
    small = q.absorbed()
    assert len(small.atoms) == 1 and rows_of(small.atoms[0].df) == [(1, 2)]
    assert natural_join(frame(spark, "a", [[1]]), frame(spark, "b", [[2]])).count() == 1


def test_run_report_and_loads(spark):
    from gridjoin.plans.cost import acyclic_load, combo_load, measure, output_bound

    q = JoinQuery({k: f for k, f in triangle_instance(spark, 512, 64).items()})
    report = measure(B.hypercube_join(q, 8))
    assert report.rows == B.cascade_join(q).count() and report.exchanges["grid"] == 3
    assert report.shuffle_bytes > 0 and report.spilled_bytes == 0 and report.peak_memory > 0 and report.rounds >= 2  # the distinct, and the grid
    plan = C.preprocess(q, 8, lower_p=False)
    for c in plan.combos:
        load = combo_load(plan, c)
        assert load.machines <= 8 and load.max_load <= load.sent and load.skew >= 1
    assert report.rows <= output_bound(plan.hypergraph, plan.n) and acyclic_load(100, 400, 10) == (50.0, 30.0)


def test_constraint_check_reads_every_part(spark, monkeypatch):
    """Eight parts; the last in order holds five tuples of one y where its bucket allows two."""
    from gridjoin import catalog

    x, y = D.bucket_name(("x",)), D.bucket_name(("y",))
    rows = [(b, b, b, 0) for b in range(7)] + [(10 + i, 99, 7, 0) for i in range(5)]
    tagged = spark.createDataFrame(rows, f"x long, y long, {x} int, {y} int")
    monkeypatch.setattr(catalog, "_tagged", lambda *a: {"r": (("x", "y"), tagged)})
    assert catalog.constraint_check(None, spark, "").collect()[0]["violations"] == 1


def zipf(spark, names, n, seed):
    """The first column's values have degrees n/2, n/4, ...; of the second's, a third fall on few values too."""
    few = lambda c: F.length(F.bin(c + 1)).cast("long")
    x, y = (F.pmod(F.xxhash64(F.lit(seed + k), "id"), F.lit(n)) for k in (0, 50))
    return spark.range(n).select(few(x).alias(names[0]), F.when(y % 3 == 0, few(y)).otherwise(y).alias(names[1])).distinct()


@pytest.fixture(scope="module")
def zipf_query(spark):
    frames = {k: spark.createDataFrame(zipf(spark, k, 3000, i).collect(), f"{k[0]} long, {k[1]} long") for i, k in enumerate(("xy", "yz", "zx"))}
    return JoinQuery(frames), rows_of(B.cascade_join(JoinQuery(frames)))


def test_many_combinations_in_one_plan(spark, zipf_query):
    """However many combinations: one grid exchange for each frame of a shape, and the results of plain joins."""
    query, expected = zipf_query
    seen = {}
    for p in (8, 64):
        plan = C.preprocess(query, p, lower_p=False)
        found = blocks(plan)
        kinds = shapes(found)
        seen[p] = len(plan.combos)
        assert sum(map(len, kinds.values())) == len(found) < len(plan.combos) and any(c.mix.heavy for c in plan.combos)
        held = Counter(c for b in found for c in product(*(b.parts[r] for r in sorted(b.parts))))
        assert all(held[tuple(plan.ids[r][c.parts[r]] for r in sorted(plan.ids))] == 1 for c in plan.combos)
        for options in ({}, {"heavy": "per_relation", "self_guard": "direct"}) if p == 8 else ({},):
            df = run_combined(plan, C.MAX_BROADCAST, **options)
            assert rows_of(df) == expected
        assert exchanges(run_combined(plan, C.MAX_BROADCAST))["grid"] <= sum(len(dict(k.guards)) + 1 for k in kinds) <= 4 * len(kinds)
    assert seen[8] >= 8 and seen[64] >= 100 and len(kinds) < 30


def test_buckets_are_merged_beyond_the_limit(spark, zipf_query):
    query, expected = zipf_query
    whole = C.preprocess(query, 32, lower_p=False)
    plan = C.preprocess(query, 32, lower_p=False, most=20)
    assert plan.base > 1 and len(plan.combos) <= 20 < len(whole.combos)
    assert rows_of(run_combined(plan, 0)) == expected  # without broadcasts of heavy relations too


def test_parts_that_do_not_meet_are_left_out(spark):
    """x is heavy in both relations, by values of two degrees each, and only one value is common."""
    r = [[1, i] for i in range(40)] + [[2, i] for i in range(20)] + [[100 + i, i] for i in range(30)]
    s = [[1, i] for i in range(20)] + [[3, i] for i in range(40)] + [[200 + i, i] for i in range(30)]
    query = JoinQuery({"r": frame(spark, "xy", r), "s": frame(spark, "xz", s)})
    plan = C.preprocess(query, 16, lower_p=False)
    sizes = [len(plan.ids[k]) for k in ("r", "s")]
    assert sizes == [3, 3] and len(plan.combos) == 6  # of the four pairs of heavy parts one meets
    assert rows_of(run_combined(plan, 100)) == brute({"r": (["x", "y"], r), "s": (["x", "z"], s)})


def test_components_meet_in_a_grid(spark):
    a, b, c = (frame(spark, n, [[i, 10 * i] for i in range(m)]) for n, m in (("ab", 7), ("cd", 5), ("ef", 3)))
    expected = sorted((i, 10 * i, j, 10 * j, k, 10 * k) for i in range(7) for j in range(5) for k in range(3))
    for most in (0, 4, 100):
        df = product_in_grid([a, b, c], 8, most, lambda x: x)
        assert rows_of(df) == expected
        assert exchanges(df)["grid"] == (0 if most == 100 else 2 if most == 4 else 3)


def test_cells_are_joined_by_sorts_that_spill(spark):
    """A hashed cell that is larger than a task's memory fails."""
    rng = random.Random(9)
    r, s, t = (frame(spark, n, [[rng.randrange(9), rng.randrange(9)] for _ in range(40)]).distinct() for n in ("xy", "yz", "zx"))
    joined = grid_join([r, s, t], {"x": 2, "y": 2, "z": 2})
    wide = product_in_grid([r, t.toDF("v", "w")], 4, 0, lambda df: df)
    assert rows_of(joined) == rows_of(natural_join(natural_join(r, s), t).select("x", "y", "z")) and wide.count() == r.count() * t.count()
    for df in (joined, wide):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "ShuffledHashJoin" not in plan


def test_no_shared_folder_off_local(spark, monkeypatch):
    from types import SimpleNamespace

    from gridjoin.sources import tables

    far = SimpleNamespace(conf=SimpleNamespace(get=lambda k, d: d), sparkContext=SimpleNamespace(master="spark://host:7077"))
    with pytest.raises(ValueError, match="checkpoint"):
        tables.shared_dir(far)


def test_loads_of_all_rounds_and_sizes(spark, zipf_query):
    """The bounds that the load rests on hold on data; each round's tuples are counted, and the plan has no more rounds than these and the degrees' tags."""
    query, _ = zipf_query
    plan = C.preprocess(query, 32, lower_p=False)
    heavy = [c for c in plan.combos if c.mix.heavy]
    assert heavy and not cost.check_machines(plan)
    for c in (heavy[0], max(heavy, key=lambda c: len(c.mix.heavy))):
        found = cost.sizes(plan, c)
        assert len(found) >= 3 and all(n <= most for _, n, most in found)
        loads = cost.round_loads(plan, c)
        assert [x.round for x in loads] == sorted(x.round for x in loads) and loads[0].kind == "broadcast" and loads[0].max_load <= 2 * 32 * len(c.mix.heavy_sets)
        assert all(x.max_load <= x.sent <= x.max_load * x.machines for x in loads)
    light = next(c for c in plan.combos if not c.mix.heavy)
    assert [x.kind for x in cost.round_loads(plan, light)] == ["grid"]
    r, s = (frame(spark, n, [[i, i] for i in range(9)]) for n in ("xy", "yz"))
    assert cost.plan_rounds(grid_join([r, s], {"x": 2, "y": 2, "z": 2})) == 1 and cost.plan_rounds(r) == 0
    assert cost.plan_rounds(r.join(F.broadcast(s), "y").groupBy("x").count()) == 2


def test_parts_are_a_partition(spark):
    rng = random.Random(4)
    df = frame(spark, "xy", [[int(rng.paretovariate(0.8)) % 20, i] for i in range(200)]).distinct()
    tagged = D.uniformize(df, ["x", "y"], 256, 8)
    assert all(D.partition_check(df, tagged, ["x", "y"]).values())
    assert D.partition_check(df, tagged.limit(100), ["x", "y"]) == {"nothing is lost": False, "nothing is new or twice": True}
    assert not D.partition_check(df, tagged.union(tagged.limit(1)), ["x", "y"])["nothing is new or twice"]
    exact = rows_of(D.heavy_candidates(df, ["x"], 8))
    assert exact and all(rows_of(D.heavy_candidates(df, ["x"], 8, "sketch", cells)) == exact for cells in (1, 4, 1 << 10))


def test_worked_bow_tie_as_data(spark):
    """z becomes heavy in zw by the first step, w in vw by the second; the results are those of plain joins in every variant."""
    query = JoinQuery(bowtie_instance(spark, 4096, 1024))
    plan = C.preprocess(query, 1024, lower_p=False)
    mix = next(c.mix for c in plan.combos if {"z", "w"} <= c.mix.heavy)
    assert [x for _, x in mix.steps] == [Fraction(1, 2), Fraction(1, 2)] and [sorted(v) for v, _ in mix.steps] == [list("vwxyz"), list("vwxy")]
    assert {(tuple(u), r) for u, r in mix.heavy_sets} == {(("z",), "zw"), (("w",), "vw")}
    query = JoinQuery(bowtie_instance(spark, 256, 32))
    expected = rows_of(B.cascade_join(query))
    assert expected and rows_of(C.cover_mix_join(query, 32)) == expected


def test_sparse_product_sizes(spark):
    h = families.boat(3)
    share = list(chances(h, 256).values())
    assert sorted(share) == [1 / 16, 1 / 16, 1, 1, 1] and cost.expected_output(h, 256, share) == 65536
    assert cost.machine_output(h, 32, share) == 128
    frames = sparse_product_instance(spark, h, 256, exact="rule")
    assert abs(B.cascade_join(JoinQuery(frames)).count() - 65536) < 0.25 * 65536


def events(spark, path, rows):
    spark.createDataFrame(rows, "u long, ts timestamp").coalesce(1).write.mode("append").parquet(path)


def test_late_rows_and_sessions(spark, tmp_path):
    from datetime import datetime

    from gridjoin.sources.tables import stream_events
    from gridjoin.streaming import streams as S

    path, day = str(tmp_path / "in"), lambda d, h=0: datetime(2024, 1, d, h)
    events(spark, path, [(1, day(1)), (1, day(1, 5)), (2, day(9))])
    events(spark, path, [(1, day(8, 1)), (3, day(20))])  # within two days of the latest
    events(spark, path, [(1, day(2)), (3, day(20, 1)), (4, day(30))])  # the first is late by far
    source = lambda: stream_events(spark, path, spark.read.parquet(path).schema)
    got = S.run_to_end(S.stream_degrees(source(), ["u"], "1 day", "2 days"), "late").select("u", F.dayofmonth("w_start").alias("d"), "deg")
    assert rows_of(got.select("d", "deg", "u")) == [(1, 2, 1), (8, 1, 1), (9, 1, 2), (20, 2, 3)]
    sessions = S.run_to_end(S.stream_degrees(source(), ["u"], "1 day", "2 days", gap="6 hours"), "sessions")
    assert (2, 1) in rows_of(sessions.select("deg", "u")) and (2, 3) in rows_of(sessions.select("deg", "u"))


def test_stream_multiway_over_two_files(spark, tmp_path):
    """A tuple that returns in a later batch repeats no result."""
    from gridjoin.sources.tables import stream_events
    from gridjoin.streaming import streams as S

    path = str(tmp_path / "in")
    for rows in ([[1, 1], [2, 1]], [[2, 1], [3, 2], [None, 1]], [[1, 1], [3, 2]]):
        frame(spark, "uy", rows).coalesce(1).write.mode("append").parquet(path)
    new = stream_events(spark, path, spark.read.parquet(path).schema)
    got = S.stream_multiway_join(new, "uy", {"yk": frame(spark, "yk", [[1, 5], [2, 6], [2, 7]]), "uk": frame(spark, "uk", [[1, 5], [2, 5], [3, 7]])}, 4, str(tmp_path / "out"))
    assert rows_of(got.select("k", "u", "y")) == [(5, 1, 1), (5, 2, 1), (7, 3, 2)]


def test_order_graphs_follow_the_table(spark, tmp_path):
    """Measures, values and bounds are of the hypergraphs that the given lines make."""
    from gridjoin import catalog

    lines = [(1, 1), (1, 2), (1, 3), (2, 1), (3, 5), (3, 5)]
    spark.createDataFrame(lines, "l_orderkey long, l_linenumber int").write.parquet(f"{tmp_path}/lineitem.parquet")
    q = catalog.queries()
    assert [(r["kind"], r["lines"], r["orders"], r["rho"], r["psi"]) for r in q["measures_table"](spark, str(tmp_path)).collect()] == [("star", 1, 2, "1", "1"), ("star", 3, 1, "3", "3"), ("cycle", 3, 1, "3/2", "2")]
    assert [(r["orders"], r["enumerated"], r["program"], r["auto"]) for r in q["kappa_methods"](spark, str(tmp_path)).collect()] == [(2, "1", "1", "1"), (1, "3", "3", "3"), (1, "3/2", "3/2", "3/2")]
    assert [(r["kind"], r["n"], r["output"]) for r in q["bounds_table"](spark, str(tmp_path)).collect()] == [("star", 4, 4.0), ("star", 4, 64.0), ("cycle", 4, 8.0)]


def test_keys_number_the_rows_of_a_table(spark, tmp_path):
    from gridjoin import catalog

    spark.createDataFrame([(7 * k % 101,) for k in range(101)], "o_orderkey long").repartition(5).write.parquet(f"{tmp_path}/orders.parquet")
    assert rows_of(catalog.queries()["op_j03_keys"](spark, str(tmp_path))) == [(k, k) for k in range(101)]


def test_table_functions_read_tables(spark, tmp_path):
    from gridjoin import catalog

    spark.createDataFrame([(5, 3)], "o_orderkey long, o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame([(1, 2), (1, 4), (2, 4), (2, 2)], "l_orderkey long, l_linenumber int").write.parquet(f"{tmp_path}/lineitem.parquet")
    q = catalog.queries()
    assert rows_of(q["op_j77_udtf_cells"](spark, str(tmp_path))) == [(19, 5), (21, 5), (23, 5)]
    assert rows_of(q["op_j78_udtf_measures"](spark, str(tmp_path))) == [("2,4", m, "1" if m == "tau" else "2") for m in ("kappa", "phi", "psi", "rho", "tau")]


def test_cascade_count_drops_variables_as_it_goes(spark):
    """No plan joins more than two relations before the tuples of one variable are summed, and counts are whole."""
    rng = random.Random(12)
    q = JoinQuery({n: frame(spark, n, [[rng.randrange(6), rng.randrange(6)] for _ in range(25)]) for n in ("ps", "cf", "pc", "sf")})
    found = B.cascade_count(q, ("s",))
    assert rows_of(found.withColumnRenamed("cnt", "a")) == rows_of(B.cascade_join(q).groupBy("s").agg(F.count("*").alias("a")))
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Aggregate") >= 2 and plan.count("Join Inner") == 3


def test_small_relations_are_hashed_and_joins_follow_sizes(spark):
    """A cycle of five whose two middle relations meet many times over: they are joined last, on all that they share by then, and small relations are not sorted."""
    from gridjoin.operators.baselines import hypercube_join
    from gridjoin.plans.grid import MAX_HASHED, Size, join_tree

    a, b = Size(36e6, {"o": 9e6, "p": 1e6}), Size(36e6, {"p": 1e6, "s": 6e4})
    cycle = [Size(9e6, {"c": 9e5, "o": 9e6}), a, b, Size(6e4, {"s": 6e4, "n": 25}), Size(9e5, {"c": 9e5, "n": 25})]
    assert sorted(map(str, join_tree(cycle))) == ["((0, 4), 1)", "(2, 3)"]
    assert cycle[4].rows <= MAX_HASHED < cycle[0].rows and not a.joined(b).bound
    rows = [(i % 7, i % 11, i % 5, i % 3) for i in range(400)]
    base = spark.createDataFrame(rows, "a int, b int, c int, d int")
    query = JoinQuery({"ab": base.select("a", "b"), "bc": base.select("b", "c"), "cd": base.select("c", "d"), "da": base.select("d", "a").where("a < 5")})
    got = hypercube_join(query, 8)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert plan.count("ShuffledHashJoin") == 2 and plan.count("SortMergeJoin") == 1
    want = {(a, b, c, d) for a in range(5) for b in range(11) for c in range(5) for d in range(3)}
    assert {tuple(r) for r in got.collect()} == want


def test_small_relations_go_to_every_machine(spark, monkeypatch):
    """Large relations are not copied along the variables of small ones, which are broadcast; results are the same, also with nulls and with a value in many tuples."""
    from gridjoin.plans import grid
    from gridjoin.plans.grid import Size, join_tree, whole_everywhere

    n = 36_000_000
    cycle = [Size(9e6, {"c": 9e5, "o": 9e6}), Size(n, {"o": 9e6, "s": 6e4}), Size(6e4, {"s": 6e4, "n": 25}), Size(9e5, {"c": 9e5, "n": 25})]
    assert whole_everywhere(cycle, 32) == {2, 3}
    # the two small ones alone would meet too many times
    assert "(2, 3)" not in str(join_tree(cycle, frozenset({2, 3}))) and "(3, 2)" not in str(join_tree(cycle, frozenset({2, 3})))
    assert not whole_everywhere([Size(n, {"a": 5, "b": 5}), Size(5, {"b": 5, "c": 5}), Size(n, {"c": 5, "d": 5})], 32)  # the others would fall apart
    monkeypatch.setattr(grid, "MAX_HASHED", 100)
    rng = random.Random(31)
    some = lambda names, m, top: spark.createDataFrame([(rng.randrange(top), rng.randrange(9) if rng.random() < 0.9 else None) for _ in range(m)], f"{names[0]} int, {names[1]} int")
    co = spark.createDataFrame([(rng.randrange(30), o) for o in range(300)], "c int, o int")
    os = spark.createDataFrame([(rng.randrange(300), rng.randrange(12)) for _ in range(900)], "o int, s int")
    chain = JoinQuery({"co": co, "os": os, "cn": some("cn", 30, 30), "nr": some("nr", 9, 9)})
    ring = JoinQuery({"co": co, "os": os, "cn": some("cn", 30, 30), "sn": some("sn", 20, 12)})
    bag = lambda df: Counter(tuple(r) for r in df.select(*sorted(df.columns)).collect())
    for q in (chain, ring):
        want = bag(B.cascade_join(q))
        for join in (lambda q: B.hypercube_join(q, 4), lambda q: C.cover_mix_join(q, 4), lambda q: B.dedicated_heavy_join(q, 4, 10_000), lambda q: B.dedicated_heavy_join(q, 4, 60)):
            assert bag(join(q)) == want and want
        plan = B.hypercube_join(q, 4)._jdf.queryExecution().executedPlan().toString()
        assert plan.count("BroadcastHashJoin") == 2 and "explode" not in plan


def test_no_axis_for_variables_of_one_relation():
    """A path of three: the variables at its ends would copy the middle relation; the smaller outer relation takes the larger number of copies."""
    from gridjoin.plans.weights import joint_shares

    rows = {frozenset("co"): 9e6, frozenset("op"): 36e6, frozenset("ps"): 36e6}
    assert joint_shares(rows, 32) == {"o": 5, "p": 6}
    assert joint_shares({frozenset("co"): 9e6, frozenset("os"): 36e6}, 32) == {"o": 32}
    assert joint_shares({frozenset("co"): 9e6}, 32) == {}


def test_shares_follow_sizes_and_degrees(spark, monkeypatch):
    """Large relations are parted along variables that are light in all of them, also beside a variable of few values, in one plan or with several parts; results are whole."""
    from gridjoin.plans import grid
    from gridjoin.plans.grid import Size, cell_load, fitted_shares

    n = 36_000_000
    four = [Size(n, {"p": 1.2e6, "s": 6e4, "l": 7}), Size(n, {"p": 1.2e6, "s": 6e4, "f": 3}), Size(n / 2, {"p": 1.2e6, "l": 7, "f": 3}), Size(n / 30, {"s": 6e4, "l": 7, "f": 3})]
    assert fitted_shares(four, 32, list("pslf")) == {"p": 16, "s": 2, "l": 1, "f": 1}
    # three values on four coordinates leave a cell in four empty
    assert cell_load(four[3:], {"f": 4}) == n / 30 / 3 and cell_load(four[3:], {"f": 2}) == n / 45
    assert fitted_shares(four, 32, []) == {}
    monkeypatch.setattr(grid, "MAX_HASHED", 100)
    base = spark.createDataFrame([(7919 * i % 600, i // 7 % 40, i % 7, i % 5, min(i % 12 // 4 * (i % 5), 3)) for i in range(3500)], "p long, s long, l long, f long, k long")
    whole = JoinQuery({v: base.select(*v).distinct() for v in ("psl", "psf", "plf", "slf")})
    chain = JoinQuery({"op": base.selectExpr("p * 40 + s AS o", "p"), "ok": base.selectExpr("p * 40 + s AS o", "k")})
    bag = lambda df: Counter(tuple(r) for r in df.select(*sorted(df.columns)).collect())
    assert bag(B.hypercube_join(whole, 16)) == bag(B.cascade_join(whole))
    # k has heavy values, and its relation two parts
    plan = C.preprocess(chain, 16)
    assert len(plan.combos) > 1 and not any(c.mix.heavy for c in plan.combos)
    assert C.spread(plan, grid.sizes([a.df for a in plan.query.atoms])) == ({"o": 16}, frozenset())
    got = C.cover_mix_join(chain, 16)
    assert bag(got) == bag(B.cascade_join(chain)) and "explode" not in got._jdf.queryExecution().executedPlan().toString()
