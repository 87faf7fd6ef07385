"""Probability of a monotone formula in disjunctive normal form: exact solvers, sampling and bounds.

Formulas are lists of explanations (iterables of variables); ``pi`` maps a variable to its probability.  Every exact
solver raises ``Budget`` where its work would exceed the budget given, so that no answer is ever wrong.
"""

from __future__ import annotations

import itertools
import math
import random
import time
from collections import Counter
from collections.abc import Iterable

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

Formula = frozenset[frozenset[int]]


class Budget(Exception):
    """More work than allowed."""


class Timeout(Budget):
    """More time than allowed."""


def in_time(deadline: float | None) -> None:
    if deadline is not None and time.monotonic() > deadline:
        raise Timeout("out of time")


def absorbed(dnf: Iterable[Iterable[int]]) -> Formula:
    """The minimal explanations; each is looked up under its rarest variable, so that few pairs are compared."""
    every = sorted({frozenset(x) for x in dnf}, key=len)
    if not every or len(every[0]) == len(every[-1]):
        return frozenset(every)
    if not every[0]:
        return frozenset([every[0]])
    uses = Counter(v for e in every for v in e)
    kept: list[frozenset[int]] = []
    under: dict[int, list[frozenset[int]]] = {}
    for e in every:
        if not any(k <= e for v in e for k in under.get(v, ())):
            kept.append(e)
            under.setdefault(min(e, key=lambda v: (uses[v], v)), []).append(e)
    return frozenset(kept)


def product(values: Iterable[float]) -> float:
    """In ascending order, so that the last digits do not depend on how facts are numbered."""
    return math.prod(sorted(values))


def closed(dnf, pi, budget=None) -> float:
    """Explanations without a common variable are independent."""
    f = absorbed(dnf)
    if f and sum(map(len, f)) != len(frozenset().union(*f)):
        raise Budget("explanations share variables")
    return 1 - product(1 - product(pi[v] for v in e) for e in f)


def worlds(dnf, pi, budget=1 << 20) -> float:
    """Sum over all assignments of the variables."""
    f = absorbed(dnf)
    names = sorted(frozenset().union(*f)) if f else []
    if 1 << len(names) > budget:
        raise Budget(f"{len(names)} variables")
    masks = [sum(1 << names.index(v) for v in e) for e in f]
    total = 0.0
    for world in range(1 << len(names)):
        if any(world & m == m for m in masks):
            total += math.prod(pi[v] if world >> i & 1 else 1 - pi[v] for i, v in enumerate(names))
    return total


def incl_excl(dnf, pi, budget=1 << 15) -> float:
    """Alternating sum over the non-empty sets of explanations."""
    f = sorted(absorbed(dnf), key=sorted)
    if 1 << len(f) > budget:
        raise Budget(f"{len(f)} explanations")
    total = 0.0
    for k in range(1, len(f) + 1):
        for some in itertools.combinations(f, k):
            total += (-1) ** (k + 1) * math.prod(pi[v] for v in frozenset().union(*some))
    return total


def dd(dnf, pi, budget=200_000, order="freq", deadline=None) -> float:
    """Ordered, reduced decision diagram: variables are decided in one global order, equal rests share a node.

    Facts that all explanations share are factored out and parts without a common fact split first, as often as that
    goes; each rest has a diagram of its own.  Of large rests, worlds of weight below ``SLIGHT`` are left out.
    """
    left = [budget]

    def solve(f: Formula) -> float:
        """An independent or of the parts, of a single one too: the terms and roundings of a sum over groups."""
        if not f:
            return 0.0
        if frozenset() in f:
            return 1.0
        return 1 - product(1 - part(x) for x in components(f))

    def part(f: Formula) -> float:
        common = frozenset.intersection(*f)
        if not common:
            if order == "freq" and 16 < len(f) <= 5 * budget:  # as good as certain, or of few worlds of weight
                if seldom_none(f, pi) < SLIGHT:
                    return 1.0
                try:
                    return 1 - none_true(f, pi, 50 * budget)
                except Budget:
                    pass
            small, weights = merged(f, pi)
            return _diagram(small, weights, left, order, deadline)
        rest = 1.0 if len(f) == 1 else solve(frozenset(e - common for e in f))
        return product(pi[v] for v in common) * rest

    certain = {v for v, p in pi.items() if p >= 1}
    return solve(absorbed(frozenset(e) - certain for e in dnf))


#: A world of less weight than this is not looked into: a hundred thousand of them stay below any digit that is shown.
SLIGHT = 1e-13


def seldom_none(f: Formula, pi) -> float:
    """An upper bound of the probability that no explanation is true, from some of them that are independent.

    Each of these shares one fact with others, a centre, and no other; centres take them in turn.
    """
    counts = Counter(v for e in f for v in e)
    around: dict[int, list[tuple[float, list[int]]]] = {}
    for e in f:
        centre = max(e, key=lambda v: (counts[v], -v))
        rest = sorted(e - {centre})
        around.setdefault(centre, []).append((math.prod(pi[v] for v in rest), rest))
    left = {c: sorted(own) for c, own in around.items()}
    none, used = dict.fromkeys(around, 1.0), set(around)
    while left:
        for c in sorted(left):
            while left[c]:
                p, rest = left[c].pop()
                if used.isdisjoint(rest):
                    used.update(rest)
                    none[c] *= 1 - p
                    break
            else:
                del left[c]
    return math.prod(1 - pi[c] * (1 - x) for c, x in none.items())


def none_true(f: Formula, pi, most: int = 10_000_000) -> float:
    """The probability that no explanation is true, where each has at most two facts that others have too, one of either
    of two sides: worlds of the smaller side, down to slight ones, in which facts of the other side are independent.
    """
    counts = Counter(v for e in f for v in e)
    shared = {e: [v for v in e if counts[v] > 1] for e in f}
    if any(len(own) > 2 for own in shared.values()):
        raise Budget("more than two shared facts in an explanation")
    near: dict[int, set[int]] = {}
    for own in shared.values():
        for v in own:
            near.setdefault(v, set()).update(u for u in own if u != v)
    side: dict[int, int] = {}
    for start in sorted(near):
        todo = [] if start in side else [start]
        side.setdefault(start, 0)
        while todo:
            v = todo.pop()
            for u in near[v]:
                if u not in side:
                    side[u] = 1 - side[v]
                    todo.append(u)
                elif side[u] == side[v]:
                    raise Budget("not two sides")
    smaller = min((0, 1), key=lambda x: (sum(s == x for s in side.values()), x))
    decided = sorted((v for v, s in side.items() if s == smaller), key=lambda v: (-pi[v], v))
    column, chance, always = {}, [], []
    miss: dict[int, dict[int, float]] = {v: {} for v in decided}
    for e, own in shared.items():
        key = next((v for v in own if side[v] != smaller), e)
        if key not in column:
            column[key] = len(column)
            chance.append(1.0 if key is e else pi[key])
            always.append(1.0)
        at, p = column[key], product(pi[v] for v in e if v not in own)
        maker = next((v for v in own if side[v] == smaller), None)
        if maker is None:
            always[at] *= 1 - p
        else:
            miss[maker][at] = miss[maker].get(at, 1.0) * (1 - p)
    true = np.array(chance)
    weight, none = np.ones(1), np.array([always])
    for v in decided:
        # more true facts only lower it
        some = weight * np.prod(1 - true * (1 - none), axis=1) >= SLIGHT
        weight, none = weight[some], none[some]
        if 2 * none.size > most:
            raise Budget("more worlds than allowed")
        then = none.copy()
        at = list(miss[v])
        then[:, at] *= np.array([miss[v][x] for x in at])
        weight, none = np.concatenate([weight * (1 - pi[v]), weight * pi[v]]), np.concatenate([none, then])
    return float(np.sum(weight * np.prod(1 - true * (1 - none), axis=1)))


def merged(f: Formula, pi) -> tuple[Formula, dict[int, float]]:
    """The formula with fewer facts, and their probabilities: the probability of the whole stays as it is.

    Facts that stand in the same explanations become one, true if all of them are; facts that could take each other's
    place in every explanation become one, true if any of them is.  Both are repeated as long as they find something.
    """
    weights = {v: pi[v] for e in f for v in e}
    while True:
        inside: dict[int, set[frozenset[int]]] = {}
        for e in f:
            for v in e:
                inside.setdefault(v, set()).add(e)
        together: dict[frozenset, list[int]] = {}
        for v in sorted(inside):
            together.setdefault(frozenset(inside[v]), []).append(v)
        gone = {v for own in together.values() for v in own[1:]}
        if gone:
            for own in together.values():
                weights[own[0]] = product(weights[v] for v in own)
            f = frozenset(e - gone for e in f)
            continue
        instead: dict[frozenset, list[int]] = {}
        for v in sorted(inside):
            instead.setdefault(frozenset(e - {v} for e in inside[v]), []).append(v)
        gone = {v for own in instead.values() for v in own[1:]}
        if not gone:
            return f, weights
        for own in instead.values():
            if len(own) > 1:
                weights[own[0]] = 1 - product(1 - weights[v] for v in own)
        f = frozenset(e for e in f if not e & gone)


def _diagram(f: Formula, pi, left: list[int], order: str, deadline: float | None) -> float:
    counts = Counter(v for e in f for v in e)
    if order == "freq":
        ranked = sorted(counts, key=lambda v: (-counts[v], v))
    else:
        ranked = list(dict.fromkeys(v for e in sorted(f, key=sorted) for v in sorted(e)))
    place = {v: i for i, v in enumerate(ranked)}
    start = frozenset(frozenset(place[v] for v in e) for e in f)
    value: dict[Formula, float] = {frozenset(): 0.0, frozenset([frozenset()]): 1.0}
    stack = [start]
    while stack:
        g = stack[-1]
        if g in value:
            stack.pop()
            continue
        left[0] -= 1
        if left[0] < 0:
            raise Budget("more nodes than allowed")
        in_time(deadline)
        v = min(min(e) for e in g)
        low = frozenset(e for e in g if v not in e)
        high = absorbed(e - {v} for e in g)
        missing = [x for x in (low, high) if x not in value]
        if missing:
            stack += missing
        else:
            p = pi[ranked[v]]
            value[g] = p * value[high] + (1 - p) * value[low]
            stack.pop()
    return value[start]


def components(f: Formula) -> list[Formula]:
    """Parts without a common variable."""
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while root.setdefault(x, x) != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for e in f:
        first = next(iter(e))
        for v in e:
            root[find(v)] = find(first)
    parts: dict[int, list[frozenset[int]]] = {}
    for e in f:
        parts.setdefault(find(next(iter(e))), []).append(e)
    return [frozenset(p) for p in parts.values()]


def dtree(dnf, pi, budget=200_000, deadline=None) -> float:
    """Independent or, common factors as independent and, else a case split on the most frequent variable."""
    memo: dict[Formula, float] = {}

    def solve(f: Formula) -> float:
        if not f:
            return 0.0
        if frozenset() in f:
            return 1.0
        if f in memo:
            return memo[f]
        if len(memo) > budget:
            raise Budget(f"{budget} nodes")
        in_time(deadline)
        common = frozenset.intersection(*f)
        if common:
            p = math.prod(pi[v] for v in sorted(common)) * solve(absorbed(e - common for e in f))
        elif len(parts := components(f)) > 1:
            p = 1 - math.prod(1 - solve(x) for x in sorted(parts, key=lambda x: sorted(map(sorted, x))))
        else:
            counts = Counter(v for e in f for v in e)
            v = max(counts, key=lambda x: (counts[x], -x))
            p = pi[v] * solve(absorbed(e - {v} for e in f)) + (1 - pi[v]) * solve(frozenset(e for e in f if v not in e))
        memo[f] = p
        return p

    # certain facts would only tie parts together that are independent
    certain = {v for v, p in pi.items() if p >= 1}
    return solve(absorbed(frozenset(e) - certain for e in dnf))


def cnf_clauses(f: Formula, encoding: str = "two_sided") -> tuple[list[frozenset[int]], int]:
    """Clauses over variables 1.. (negative: negated) of the formula, with auxiliary variables after the base ones."""
    ranked = sorted(frozenset().union(*f)) if f else []
    place = {v: i + 1 for i, v in enumerate(ranked)}
    n = len(ranked)
    if encoding == "negate":
        return [frozenset(-place[v] for v in e) for e in f], n
    clauses, names = [], []
    for i, e in enumerate(sorted(f, key=sorted)):
        z = n + 1 + i
        names.append(z)
        clauses += [frozenset((-z, place[v])) for v in e]
        if encoding == "two_sided":
            clauses.append(frozenset([z, *(-place[v] for v in e)]))
    clauses.append(frozenset(names))
    return clauses, n


def cnf(dnf, pi, budget=200_000, encoding="two_sided", deadline=None) -> float:
    """Weighted counting by search with unit propagation, component split and cache.

    ``two_sided`` definitions leave the auxiliaries no choice, so that counts are kept; ``relaxed`` has one side only and
    counts projected on the base variables; ``negate`` counts the negation, which is a conjunction already.
    """
    f = absorbed(dnf)
    if not f:
        return 0.0
    if frozenset() in f:
        return 1.0
    ranked = sorted(frozenset().union(*f))
    clauses, n = cnf_clauses(f, encoding)
    weight = {i + 1: pi[v] for i, v in enumerate(ranked)}
    memo: dict[frozenset, float] = {}

    def assign(cs, literal):
        out = set()
        for c in cs:
            if literal in c:
                continue
            c = c - {-literal}
            if not c:
                return None
            out.add(c)
        return frozenset(out)

    def literal_weight(x: int) -> float:
        v = abs(x)
        return (weight[v] if x > 0 else 1 - weight[v]) if v in weight else 1.0

    def satisfiable(cs) -> bool:
        while True:
            unit = next((c for c in cs if len(c) == 1), None)
            if unit is None:
                break
            cs = assign(cs, next(iter(unit)))
            if cs is None:
                return False
        if not cs:
            return True
        v = abs(next(iter(next(iter(cs)))))
        return any(s is not None and satisfiable(s) for s in (assign(cs, v), assign(cs, -v)))

    def count(cs) -> float:
        factor = 1.0
        while True:
            unit = next((c for c in cs if len(c) == 1 and (encoding != "relaxed" or abs(next(iter(c))) in weight)), None)
            if unit is None:
                break
            x = next(iter(unit))
            cs = assign(cs, x)
            if cs is None:
                return 0.0
            factor *= literal_weight(x)
        if not cs:
            return factor
        if cs in memo:
            return factor * memo[cs]
        if len(memo) > budget:
            raise Budget(f"{budget} nodes")
        in_time(deadline)
        parts = components(frozenset(frozenset(map(abs, c)) for c in cs))
        if len(parts) > 1:
            total = 1.0
            for part in parts:
                names = frozenset().union(*part)
                total *= count(frozenset(c for c in cs if abs(next(iter(c))) in names))
        else:
            uses = Counter(abs(x) for c in cs for x in c)
            base = [v for v in uses if v in weight] if encoding == "relaxed" else list(uses)
            if not base:  # only auxiliaries are left: any way to satisfy them will do
                total = 1.0 if satisfiable(cs) else 0.0
            else:
                v = max(base, key=lambda x: (uses[x], -x))
                total = 0.0
                for x in (v, -v):
                    rest = assign(cs, x)
                    if rest is not None:
                        total += literal_weight(x) * count(rest)
        memo[cs] = total
        return factor * total

    found = count(frozenset(clauses))
    return 1 - found if encoding == "negate" else found


def mc(dnf, pi, epsilon=0.05, delta=0.05, seed=1, budget=2_000_000, deadline=None) -> float:
    """Coverage sampling: worlds drawn through one explanation, counted where that is the first true one.

    Within a factor of 1 +- epsilon but for a chance of delta; where that needs more draws than ``budget``: Budget.
    """
    f = sorted(absorbed(dnf), key=sorted)
    if not f:
        return 0.0
    rng = random.Random(seed)
    names = sorted(frozenset().union(*f))
    weights = [math.prod(pi[v] for v in e) for e in f]
    total = sum(weights)
    n = math.ceil(3 * len(f) * math.log(2 / delta) / epsilon**2)
    if n > budget:
        raise Budget(f"{n} draws")
    good = 0
    for _ in range(n):
        in_time(deadline)
        i = rng.choices(range(len(f)), weights)[0]
        world = {v for v in names if v in f[i] or rng.random() < pi[v]}
        good += not any(f[j] <= world for j in range(i))
    return min(1.0, total * good / n)


def bounds(dnf, pi, width=1e-3, budget=5000) -> tuple[float, float]:
    """Lower and upper bound from a partial d-tree: leaves are bounded by their best explanation and by their sum."""
    left = [budget]

    def leaf(f: Formula) -> tuple[float, float]:
        ps = [math.prod(pi[v] for v in e) for e in f]
        return max(ps), min(1.0, 1 - math.prod(1 - p for p in ps) if len(f) == len(components(f)) else sum(ps))

    def solve(f: Formula) -> tuple[float, float]:
        if not f:
            return 0.0, 0.0
        if frozenset() in f:
            return 1.0, 1.0
        low, high = leaf(f)
        left[0] -= 1
        if high - low <= width or left[0] <= 0:
            return low, high
        parts = components(f)
        if len(parts) > 1:
            each = [solve(x) for x in parts]
            return 1 - math.prod(1 - a for a, _ in each), 1 - math.prod(1 - b for _, b in each)
        counts = Counter(v for e in f for v in e)
        v = max(counts, key=lambda x: (counts[x], -x))
        a, b = solve(absorbed(e - {v} for e in f)), solve(frozenset(e for e in f if v not in e))
        return pi[v] * a[0] + (1 - pi[v]) * b[0], pi[v] * a[1] + (1 - pi[v]) * b[1]

    return solve(absorbed(dnf))


SOLVERS = {"closed": closed, "worlds": worlds, "incl_excl": incl_excl, "dd": dd, "dtree": dtree, "cnf": cnf, "mc": mc}
#: Status of an answer whose formula has more explanations than this.
DISJUNCT_CAP = 1_000_000


def solve_one(dnf, fids, pis, solver: str, options: dict) -> tuple[float | None, float, str, int]:
    """Probability (None: over budget), lower bound, status and nanoseconds."""
    began = time.perf_counter_ns()
    pi = dict(zip(fids, pis, strict=True))
    lower = max((math.prod(pi[v] for v in e) for e in dnf), default=0.0)
    if len(dnf) > options.get("disjunct_cap", DISJUNCT_CAP):
        return None, lower, "disjunct_cap", time.perf_counter_ns() - began
    own = {k: v for k, v in options.items() if k not in ("disjunct_cap", "timeout")}
    if options.get("timeout") is not None and solver in ("dd", "dtree", "cnf", "mc", "auto"):
        own["deadline"] = time.monotonic() + options["timeout"]
    try:
        if solver == "bounds":
            low, high = bounds(dnf, pi, **own)
            return low, low, "ok" if high - low <= own.get("width", 1e-3) else "node_cap", time.perf_counter_ns() - began
        if solver in ("dd", "auto"):  # the closed form is tried first
            try:
                p = closed(dnf, pi)
            except Budget:
                p = dd(dnf, pi, **own) if solver == "dd" or len(dnf) > 40 else dtree(dnf, pi, deadline=own.get("deadline"))
        else:
            p = SOLVERS[solver](dnf, pi, **own)
        return p, p, "ok", time.perf_counter_ns() - began
    except Timeout:
        return None, lower, "timeout", time.perf_counter_ns() - began
    except (Budget, RecursionError):
        return None, lower, "node_cap", time.perf_counter_ns() - began


def dnf_prob(dnf: Column, fids: Column, pis: Column, solver: str = "dd", **options) -> Column:
    """struct(prob, lower, status, nanos) of a formula whose variables and their probabilities stand in two arrays."""

    @F.pandas_udf("prob double, lower double, status string, nanos long")
    def run(d: pd.Series, f: pd.Series, p: pd.Series) -> pd.DataFrame:
        rows = [solve_one([tuple(e) for e in x], list(y), list(z), solver, options) for x, y, z in zip(d, f, p, strict=True)]
        return pd.DataFrame(rows, columns=["prob", "lower", "status", "nanos"])

    return run(dnf, fids, pis)
