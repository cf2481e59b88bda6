"""Mixes of covers on the worked instances, and their invariants on random slacks."""

import random
from fractions import Fraction as Fr
from math import prod

import pytest

from gridjoin.functions import families as f
from gridjoin.functions.measures import kappa
from gridjoin.plans.hard import bowtie_slack
from gridjoin.plans.weights import build_mix, check_mix, find_guards, integer_shares, search_delta


def atoms(h):
    return {"".join(sorted(e)): e for e in h.edges}


def test_triangle():
    h = f.triangle()
    mix = build_mix(h, {("xy", frozenset("x")): Fr(1, 6), ("xz", frozenset("x")): Fr(1, 6)})
    assert [s for _, s in mix.steps] == [Fr(1, 2), Fr(1, 2)]
    assert mix.weights == {"x": Fr(1, 4), "y": Fr(1, 2), "z": Fr(1, 2)} and mix.norm == Fr(5, 4)
    assert mix.heavy == frozenset("x") and set(find_guards(atoms(h), mix).values()) == {"yz"}


def test_triangle_of_the_two_valued_variable():
    mix = build_mix(f.triangle(), {("xy", frozenset("x")): Fr(1, 5)})
    assert [s for _, s in mix.steps] == [Fr(3, 5), Fr(2, 5)] and mix.norm == Fr(13, 10)
    shares = integer_shares(mix.exponents, 32, mix.heavy)
    assert prod(shares.values()) <= 32 and shares["x"] == 2


@pytest.mark.parametrize("variant", ["printed", "repaired"])
def test_bowtie(variant):
    h = f.bowtie()
    mix = build_mix(h, bowtie_slack(variant))
    assert mix.norm == Fr(21, 10) and mix.heavy == frozenset("wz")
    guards = find_guards({k: frozenset(k) for k in ("xy", "yz", "xz", "zv", "zw", "vw")}, mix)
    assert guards == {"xy": "xy", "yz": "xy", "xz": "xy", "zv": "vw", "vw": "vw"}
    if variant == "repaired":
        assert mix.weights == {"x": Fr(1, 2), "y": Fr(1, 2), "z": Fr(1, 10), "v": Fr(7, 10), "w": Fr(3, 10)}


@pytest.mark.parametrize("tie", ["balanced", "vertex"])
def test_invariants(tie):
    rng = random.Random(11)
    for h in (f.triangle(), f.bowtie(), f.loomis_whitney(4), f.boat(3), f.cycle(5), f.nine_var()):
        for _ in range(15):
            slack = {}
            for name, e in atoms(h).items():
                for x in e:
                    if rng.random() < 0.4:
                        slack[(name, frozenset([x]))] = Fr(rng.randint(0, 8), 8)
            mix = build_mix(h, slack, tie=tie)
            assert all(check_mix(h, atoms(h), slack, mix).values()), (str(h), slack)
            found = search_delta(h, slack, 10)
            assert found.norm <= found.delta <= kappa(h).value
