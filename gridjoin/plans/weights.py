"""Share exponents as a mix of vertex covers, exact.

v(U), the sum of a weight vector over a set U of variables of a relation, makes U light if it is below the slack e(U) = log_p(n / sigma(U)), heavy from
there on; the vector is consistent if no set exceeds its slack. A mix starts from zero and adds, again and again, the largest multiple of the
balanced vertex cover of what is not heavy yet, reduced, that stays consistent.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from fractions import Fraction
from itertools import combinations
from math import prod

from gridjoin.functions.hypergraph import Hypergraph
from gridjoin.functions.measures import kappa, min_vertex_cover

Slack = dict[tuple[str, frozenset[str]], Fraction]


@dataclass
class Mix:
    delta: Fraction
    steps: list[tuple[frozenset[str], Fraction]] = field(default_factory=list)
    weights: dict[str, Fraction] = field(default_factory=dict)
    heavy_sets: list[tuple[frozenset[str], str]] = field(default_factory=list)

    @property
    def heavy(self) -> frozenset[str]:
        return frozenset().union(*(u for u, _ in self.heavy_sets)) if self.heavy_sets else frozenset()

    @property
    def exponents(self) -> dict[str, Fraction]:
        return {x: w / self.delta for x, w in self.weights.items()}

    @property
    def norm(self) -> Fraction:
        return sum(self.weights.values(), Fraction(0))


def total(w: dict[str, Fraction], u: frozenset[str]) -> Fraction:
    return sum((w[x] for x in u), Fraction(0))


def classify(slack: Slack, v: dict[str, Fraction]) -> dict[tuple[str, frozenset[str]], str]:
    return {k: "light" if total(v, k[1]) < e else "heavy" if total(v, k[1]) == e else "inconsistent" for k, e in slack.items()}


def is_consistent(slack: Slack, v: dict[str, Fraction]) -> bool:
    return all(total(v, u) <= e for (_, u), e in slack.items())


def heavy_sets(slack: Slack, v: dict[str, Fraction]) -> list[tuple[frozenset[str], str]]:
    return sorted(((u, r) for (r, u), e in slack.items() if total(v, u) >= e), key=lambda x: (sorted(x[0]), x[1]))


def max_step(slack: Slack, w: dict[str, Fraction], cover: dict[str, Fraction], delta: Fraction, left: Fraction) -> Fraction:
    """The largest multiple of the cover that keeps all sets consistent and the coefficients' sum at most one."""
    step = left
    for (_, u), e in slack.items():
        c = sum((cover.get(x, Fraction(0)) for x in u), Fraction(0))
        if c > 0:
            step = min(step, (delta * e - total(w, u)) / c)
    return step


def build_mix(h: Hypergraph, slack: Slack, delta: Fraction | None = None, tie: str = "balanced") -> Mix:
    delta = kappa(h).value if delta is None else delta
    mix = Mix(delta, weights={x: Fraction(0) for x in h.vertices})
    mix.heavy_sets = heavy_sets(slack, mix.weights)  # a value in every tuple has no slack at all
    left = Fraction(1)
    while left > 0:
        light = frozenset(h.vertices) - mix.heavy
        if not light:
            break
        cover = min_vertex_cover(h.induced(light).reduced(), tie)
        step = max_step(slack, mix.weights, cover, delta, left)
        for x, c in cover.items():
            mix.weights[x] += step * c
        mix.steps.append((light, step))
        left -= step
        before = mix.heavy
        mix.heavy_sets = heavy_sets(slack, mix.exponents)
        if left > 0 and mix.heavy == before:
            raise ArithmeticError("a step made no variable heavy")
    return mix


def search_delta(h: Hypergraph, slack: Slack, rounds: int = 30) -> Mix:
    """The least delta, by bisection, whose mix has at most that norm: all machines are used and the load falls."""
    high = kappa(h).value
    best, low = build_mix(h, slack, high), Fraction(0)
    for _ in range(rounds):
        middle = ((low + high) / 2).limit_denominator(1 << 20)
        if middle <= 0 or middle >= high:
            break
        mix = build_mix(h, slack, middle)
        if mix.norm <= middle:
            best, high = mix, middle
        else:
            low = middle
    return best


def find_guards(atoms: dict[str, frozenset[str]], mix: Mix) -> dict[str, str]:
    """For each atom with light variables an atom that holds these and has weight one or more; the atom itself first, then the smallest."""
    out = {}
    for r, vs in atoms.items():
        light = vs - mix.heavy
        if light:
            able = [s for s, us in atoms.items() if light <= us and total(mix.weights, us) >= 1]
            if not able:
                raise ArithmeticError(f"no guard for {r}")
            out[r] = min(able, key=lambda s: (s != r, len(atoms[s]), s))
    return out


def integer_shares(v: dict[str, Fraction], p: int, last: frozenset[str] = frozenset()) -> dict[str, int]:
    """Shares p^v rounded down, then raised one at a time where most was lost while their product is at most p; variables in ``last`` are raised last."""
    real = {x: float(p) ** float(e) for x, e in v.items()}
    shares = {x: max(1, int(r + 1e-9)) for x, r in real.items()}
    product = 1
    for s in shares.values():
        product *= s
    while True:
        able = [x for x in shares if v[x] > 0 and product // shares[x] * (shares[x] + 1) <= p]
        if not able:
            return shares
        x = min(able, key=lambda y: (y in last, shares[y] / real[y], y))
        product = product // shares[x] * (shares[x] + 1)
        shares[x] += 1


def joint_shares(rows: dict[frozenset[str], float], p: int) -> dict[str, int]:
    """Shares for relations of so many rows, from a minimum vertex cover without variables that one relation alone has: these may always give their weight to a shared one of
    theirs, and an axis of theirs would only copy all the others. Where rounding makes shares uneven, they lie so that the fewest tuples are sent."""
    h = Hypergraph.of(rows)
    held = [x for x in h.vertices if sum(x in e for e in h.edges) > 1]
    if not held:
        return {}
    cover = min_vertex_cover(h.induced(held))
    norm = sum(cover.values(), Fraction(0))
    shares = integer_shares({x: c / norm for x, c in cover.items()}, p)
    sent = lambda s: sum(n * prod(k for x, k in s.items() if x not in e) for e, n in rows.items())
    while True:
        swaps = [shares | {x: shares[y], y: shares[x]} for x, y in combinations(sorted(shares), 2) if cover.get(x) == cover.get(y)]
        best = min(swaps, key=sent, default=shares)
        if sent(best) >= sent(shares):
            return shares
        shares = best


def check_mix(h: Hypergraph, atoms: dict[str, frozenset[str]], slack: Slack, mix: Mix) -> dict[str, bool]:
    return {
        "coefficients sum to at most one": sum(s for _, s in mix.steps) <= 1,
        "consistent": is_consistent(slack, mix.exponents),
        "norm at most kappa": mix.norm <= kappa(h).value,
        "guards exist": bool(find_guards(atoms, mix)) or frozenset(h.vertices) <= mix.heavy,
    }
