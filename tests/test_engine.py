import random

import pytest
from pyspark.sql import functions as F

from provspark.plans.baselines import circuit, formula_fixpoint, set_fixpoint, topk_fixpoint, worlds
from provspark.plans.reason import base_probabilities, lineage, probabilities, reason
from provspark.rules import normalize
from provspark.workloads import base as w


def model(formulas, program):
    got = probabilities(formulas, base_probabilities(normalize(program))).collect()
    return {(r["a0"], r["a1"]): round(r["prob"], 6) for r in got}


EXAMPLE = {("a", "b"): 0.78, ("a", "c"): 0.79, ("b", "b"): 0.48, ("b", "c"): 0.6, ("c", "b"): 0.8, ("c", "c"): 0.48}


def test_running_example(spark):
    program = w.reach_example(spark)
    result = reason(program)
    assert result.counts() == [(1, 1, 4, 4), (2, 1, 4, 4), (3, 0, 12, 0)]
    assert model(lineage(result, "p"), program) == EXAMPLE


def test_baselines_on_the_example(spark):
    program = w.reach_example(spark)
    naive = formula_fixpoint(program, "naive")
    assert [x["instances"] for x in naive.log] == [4, 8, 16]
    assert model(naive.of("p").select("a0", "a1", "dnf"), program) == EXAMPLE
    top = model(topk_fixpoint(program, 1).of("p").select("a0", "a1", "dnf"), program)
    assert top["a", "b"] == 0.56 and top["a", "c"] == 0.7
    assert set_fixpoint(program).of("p").count() == set_fixpoint(program, "naive").of("p").count() == 6


@pytest.mark.parametrize(("n", "t", "kept"), [(3, 10, [3, 3, 2, 0]), (3, 1, [3, 1, 1, 0]), (10, 10, [10, 1, 1, 0])])
def test_collapse_example(spark, n, t, kept):
    program = w.collapse_example(spark, n)
    result = reason(program, collapse=t)
    assert [k for *_, k in result.counts()] == kept
    got = model(lineage(result, "r", F.col("a1") == 1), program)
    assert got["a", 1] == {3: 0.444444, 10: 0.508632}[n]


def test_termination_with_folds(spark):
    assert [k for *_, k in reason(w.complete_graph(spark, 3), collapse=1).counts()] == [6, 9, 3, 0]


def test_circuit_of_the_collapse_example(spark):
    kinds = {r["kind"]: r["count"] for r in circuit(w.collapse_example(spark, 3)).gates.groupBy("kind").count().collect()}
    assert kinds == {"and": 7, "inner_or": 4 + 1 - 1, "outer_or": 4, "leaf": 4}


@pytest.mark.parametrize("seed", [1, 2])
def test_random_programs_agree_with_all_worlds(spark, seed):
    rng = random.Random(seed)
    edges = sorted({(rng.randrange(4), rng.randrange(4)) for _ in range(7)})
    text = "".join(f"{rng.uniform(0.1, 0.9):.3f}::e({a},{b}). " for a, b in edges)
    program = w.program(spark, text + "p(X,Y) :- e(X,Y). p(X,Y) :- p(X,Z), e(Z,Y).")
    exact = {(r["a0"], r["a1"]): round(r["prob"], 6) for r in worlds(program, "p").collect()}
    for collapse in (None, 2):
        assert model(lineage(reason(program, collapse=collapse), "p"), program) == exact


def chain(spark, n, rule):
    from provspark.rules import Program, rules
    from provspark.sources.tables import facts

    edges = spark.range(n).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    return Program(rules(f"p(X,Y) :- e(X,Y). {rule}"), {"e": facts("e", edges, ["a", "b"], 0.5, unique=True)})


def test_fixpoints_end_by_themselves_or_say_so(spark):
    from provspark.plans.compile import RoundLimit

    assert set_fixpoint(chain(spark, 130, "p(X,Y) :- p(X,Z), p(Z,Y).")).of("p").count() == 130 * 131 // 2
    short = chain(spark, 8, "p(X,Y) :- p(X,Z), e(Z,Y).")
    for run in (set_fixpoint, formula_fixpoint, circuit, reason):
        with pytest.raises(RoundLimit):
            run(short, most_rounds=3)


def test_nothing_derived_is_an_empty_table(spark):
    from provspark.plans.answer import answer
    from provspark.rules import Query

    program = w.reach_example(spark)
    for magic in ("guard", None):
        got = answer(program, Query.parse("q(Y) :- p('z',Y)."), magic=magic).table
        assert got.count() == 0 and got.columns[:2] == ["a0", "prob"]


def test_rules_that_differ_in_constants_run_as_one_plan(spark):
    from provspark.plans.compile import shapes
    from provspark.rules import Program

    facts_ = "0.5::t(1,'a'). 0.4::t(2,'b'). 0.3::t(2,'a'). 0.2::t(3,'c'). "
    program = w.program(spark, facts_ + "is(X,'A') :- t(X,'a'). is(X,'B') :- t(X,'b'). is(X,'C') :- t(X,'c'). any(X) :- is(X,'A'). any(X) :- is(X,'B').")
    assert [len(s.ids) for s in shapes(program.rules)] == [3, 2]
    merged = reason(program)
    alone = {r: reason(Program([x for x in program.rules if x.id == r], program.facts)).of("is").count() for r in ("r1", "r2", "r3")}
    by = {r["rule"]: r["count"] for r in merged.of("is").groupBy("rule").count().collect()}
    assert by == alone == {"r1": 2, "r2": 1, "r3": 1}
    got = {r["a0"]: round(r["prob"], 6) for r in probabilities(lineage(merged, "any"), base_probabilities(program)).collect()}
    assert got == {1: 0.5, 2: round(1 - 0.6 * 0.7, 6)}


def test_answers_of_too_many_trees_have_a_status(spark):
    result = reason(w.collapse_example(spark, 10), collapse=10)
    got = {r["a1"]: (r["status"], len(r["dnf"])) for r in lineage(result, "r", cap=5).collect()}
    assert got[1] == ("disjunct_cap", 0) and got[2] == ("ok", 1) and len(got) == 10
