import random

import pytest

from provspark.functions import solvers as s


def formulas(n=40, seed=0):
    rng = random.Random(seed)
    for _ in range(n):
        names = range(rng.randint(2, 8))
        yield [rng.sample(list(names), rng.randint(1, min(4, len(names)))) for _ in range(rng.randint(1, 7))], {v: rng.uniform(0.05, 0.95) for v in names}


def test_exact_solvers_agree():
    for dnf, pi in formulas():
        exact = s.worlds(dnf, pi)
        for solve in (s.incl_excl, s.dd, s.dtree, s.cnf, lambda d, p: s.cnf(d, p, encoding="relaxed"), lambda d, p: s.cnf(d, p, encoding="negate"), lambda d, p: s.dd(d, p, order="first_seen")):
            assert solve(dnf, pi) == pytest.approx(exact, abs=1e-9)
        low, high = s.bounds(dnf, pi)
        assert low - 1e-9 <= exact <= high + 1e-9


def test_sampling_is_near():
    for dnf, pi in formulas(5, 3):
        assert s.mc(dnf, pi) == pytest.approx(s.worlds(dnf, pi), rel=0.15)


def test_budgets_never_answer_wrongly():
    dnf = [[i, i + 1] for i in range(30)]
    pi = dict.fromkeys(range(31), 0.5)
    assert s.solve_one(dnf, list(pi), list(pi.values()), "worlds", {})[2] == "node_cap"
    assert s.solve_one(dnf, list(pi), list(pi.values()), "dd", {"budget": 3})[0] is None
    assert s.solve_one(dnf, list(pi), list(pi.values()), "dd", {"disjunct_cap": 2})[2] == "disjunct_cap"


def test_edges():
    assert s.dd([], {}) == 0 and s.dtree([[]], {}) == 1 and s.cnf([[]], {}) == 1
    with pytest.raises(s.Budget):
        s.closed([[1, 2], [2, 3]], {1: 0.5, 2: 0.5, 3: 0.5})


def test_shared_facts_are_factored_out_and_parts_split():
    import time

    n = 400
    dnf, pi = [(0, 2 * i + 1, 2 * i + 2) for i in range(n)], {i: 0.01 + (i % 7) / 10 for i in range(2 * n + 1)}
    began = time.perf_counter()
    got = s.dd(dnf, pi)
    assert time.perf_counter() - began < 0.05
    rest = 1.0
    for i in range(n):
        rest *= 1 - pi[2 * i + 1] * pi[2 * i + 2]
    assert abs(got - pi[0] * (1 - rest)) < 1e-9


def test_statuses():
    chain, pi = [(i, i + 1) for i in range(40)], {i: 0.5 for i in range(41)}
    solve = lambda solver, **options: s.solve_one(chain, list(pi), list(pi.values()), solver, options)[2]
    assert solve("dd") == "ok" and solve("dd", budget=3) == "node_cap" and solve("dd", timeout=-1) == "timeout"
    assert solve("mc", epsilon=1e-4) == "node_cap" and solve("dd", disjunct_cap=5) == "disjunct_cap"
