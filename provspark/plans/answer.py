"""Query answering in three phases - reasoning, lineage collection, probability - with or without rewriting."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..rules import Program, Query, adorned, firing, normalize
from ..sources.tables import empty, fact_id, side_by_side, stored
from .baselines import set_strata
from .compile import argument_types, arguments
from .reason import PlanResult, base_probabilities, lineage, probabilities, reason


@dataclass
class Answers:
    table: DataFrame
    result: PlanResult
    phases: dict[str, float] = field(default_factory=dict)
    formulas: DataFrame | None = None


#: Unfolded trees of an answer beyond which its formula is not built.
DISJUNCT_CAP = 1_000_000


def _seed(program: Program, name: str) -> DataFrame:
    spark = next(iter(program.facts.values())).sparkSession
    start = spark.range(1).select(F.lit(0).alias("a0"), F.lit(1.0).alias("pi"))
    return start.withColumn("fid", fact_id(name, [F.col("a0")]))


def guarded(program: Program, query: Query) -> Program:
    """The program rewritten for the query, with demand computed first as certain sets.

    Demand facts are a superset of what any world needs, so they enter as certain base facts, which change no probability.
    Rules that their constants keep from making anything are left out first.
    """
    program = normalize(program)
    out, demand, seed = adorned(program, query)
    base = {**program.facts, seed: _seed(program, seed)}
    at_work = firing([*demand, *out], set(base))
    names = {r.id for r in at_work}
    out, demand = [r for r in out if r.id in names], [r for r in demand if r.id in names]
    if not any(r.head.pred == query.head.pred for r in out):
        return Program([query.rule()], {**program.facts, **_empty_bodies(program, query)})
    used = [a.pred for r in at_work for a in r.body]
    # what several rules read is made once
    shared = [p for p in base if p != seed and used.count(p) > 1]
    base = {p: df for p, df in base.items() if p in used} | dict(zip(shared, side_by_side(lambda p: stored(base[p], p), shared), strict=True))
    needs = set_strata(Program([*demand, *out], base))
    names = {r.head.pred for r in demand}
    found = [name for name in names if name in needs.tables]

    def guard(name: str) -> DataFrame:
        args = arguments(needs.tables[name])
        return stored(needs.tables[name].select(*args).withColumn("pi", F.lit(1.0)).withColumn("fid", fact_id(name, [F.col(a) for a in args])), "demand")

    guards = dict(zip(found, side_by_side(guard, found), strict=True))
    # rules without demand, and rules over predicates that no rule is left for, make nothing
    known, kept = {**{p: df for p, df in base.items() if p != seed}, **guards}, list(out)
    while True:
        heads = {r.head.pred for r in kept}
        live = [r for r in kept if all(a.pred in known or a.pred in heads for a in r.body)]
        if len(live) == len(kept):
            break
        kept = live
    if not any(r.head.pred == query.head.pred for r in kept):
        return Program([query.rule()], {**program.facts, **_empty_bodies(program, query)})
    return Program(kept, known, frozenset(guards))


def _empty_bodies(program: Program, query: Query) -> dict[str, DataFrame]:
    """Empty tables for the derived atoms of a query that nothing can answer."""
    spark, types = next(iter(program.facts.values())).sparkSession, argument_types(program)
    return {a.pred: empty(spark, a.pred, types[a.pred]) for a in query.body if a.pred not in program.facts}


def answer(program: Program, query: Query, solver: str = "dd", magic: str | None = "guard", collapse: float | None = 10, max_depth: int | None = None, cap: int | None = DISJUNCT_CAP, **options) -> Answers:
    """Probability of each answer; no answers are an empty table.

    ``magic``: ``guard`` computes the demand first as certain sets, ``rules`` runs the rewritten rules with their demand
    rules as one program, None runs the rules as they are.  Answers of more than ``cap`` unfolded trees have no formula,
    but a status.
    """
    if magic == "guard":
        program = guarded(program, query)
    elif magic == "rules":
        program = normalize(program)
        out, demand, seed = adorned(program, query)
        program = Program([*demand, *out], {**program.facts, seed: _seed(program, seed)})
    elif magic is None:
        program = normalize(program).with_rules([*normalize(program).rules, query.rule()])
    else:
        raise ValueError(f"unknown rewriting {magic!r}")
    began = time.perf_counter()
    result = reason(program, collapse=collapse, max_depth=max_depth)
    reasoned = time.perf_counter()
    formulas = stored(lineage(result, query.head.pred, cap=cap), "lineage")
    collected = time.perf_counter()
    table = stored(probabilities(formulas, base_probabilities(result.program), solver, **options), "answers")
    return Answers(table, result, {"reasoning": reasoned - began, "lineage": collected - reasoned, "probability": time.perf_counter() - collected}, formulas)
