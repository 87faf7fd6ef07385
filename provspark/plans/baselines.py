"""The methods that the plan-graph engine is compared with.

* ``set_fixpoint``: ordinary Datalog, naive or semi-naive;
* ``formula_fixpoint``: formulas in rounds (derive, disjoin per fact, merge with the old formula, test equivalence), for
  all instantiations, for those that touch a changed fact only, or in the rewritten form with auxiliary predicates; with
  ``k`` the approximate variant that keeps the k most probable explanations of a fact;
* ``circuit``: a provenance circuit with two or-gates per fact and an and-gate per instantiation, and its evaluation;
* ``worlds``: the definition itself, by enumeration of all possible worlds of few facts.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.dnf import dnf_absorb, dnf_and, dnf_or
from ..rules import Program, Rule, normalize, strata
from ..sources.tables import fact_id, side_by_side, stored, stored_count
from .compile import Shape, argument_types, arguments, derived_positions, head_columns, join_body, rounds, shapes, union


@dataclass
class Fixpoint:
    """Tables per derived predicate, and a log of rounds."""

    tables: dict[str, DataFrame] = field(default_factory=dict)
    log: list[dict] = field(default_factory=list)
    program: Program | None = None

    def of(self, pred: str) -> DataFrame:
        """Facts of a predicate; no rows where nothing was derived."""
        if pred in self.tables or self.program is None:
            return self.tables[pred]
        spark = next(iter(self.program.facts.values())).sparkSession
        args = ", ".join(f"a{i} {t}" for i, t in enumerate(argument_types(self.program)[pred]))
        return spark.createDataFrame([], f"{args}, fid bigint, dnf array<array<bigint>>")


def _variants(rule: Rule, derived: set[str], delta: bool, first: bool) -> list[int | None]:
    """Body positions that must read the last changes; None: everything."""
    spots = derived_positions(rule, derived)
    if first or not delta:
        return [None] if first and not spots or not first else []
    return list(spots)


def set_fixpoint(program: Program, mode: str = "delta", most_rounds: int | None = None, extra: tuple[str, ...] = ()) -> Fixpoint:
    """Least model without probabilities; ``extra`` columns (a world, say) are join keys of every atom.

    Where more than ``most_rounds`` rounds would be needed: RoundLimit.
    """
    program = normalize(program)
    derived, out = program.derived, Fixpoint(program=program)
    plans = [Shape(r, [r.id]) for r in program.rules] if extra else shapes(program.rules)
    known: dict[str, DataFrame] = {}
    last: dict[str, DataFrame] = {}
    older: dict[str, DataFrame] = {}
    for depth in rounds(1, most_rounds):
        fresh: dict[str, list[DataFrame]] = {}
        for shape in plans:
            rule = shape.rule
            for spot in _variants(rule, derived, mode == "delta", depth == 1):
                inputs = []
                for i, atom in enumerate(rule.body):
                    if atom.pred not in derived:
                        inputs.append(program.facts[atom.pred])
                    elif spot is None:
                        inputs.append(known.get(atom.pred))
                    else:
                        inputs.append(last.get(atom.pred) if i == spot else older.get(atom.pred) if i < spot else known.get(atom.pred))
                if any(x is None for x in inputs):
                    continue
                order = None if spot is None else [spot, *(i for i in range(len(rule.body)) if i != spot)]
                rows = join_body(rule, [(df, []) for df in inputs], extra, order) if extra else shape.joined([(df, []) for df in inputs], order)
                fresh.setdefault(rule.head.pred, []).append(rows.select(*head_columns(rule), *extra))
        def made(item, depth=depth):
            pred, frames = item
            rows = union(frames).distinct()
            if pred in known:
                rows = rows.join(known[pred], rows.columns, "left_anti")
            return (pred, *stored_count(rows, f"set-{depth}"))

        new, total = {}, 0
        for pred, rows, n in side_by_side(made, list(fresh.items())):
            if n:
                new[pred], total = rows, total + n
        out.log.append({"depth": depth, "new": total})
        if not total:
            break
        older = dict(known)
        for pred, rows in new.items():
            known[pred] = union([known[pred], rows]) if pred in known else rows
        last = new
    out.tables = known
    return out


def set_strata(program: Program) -> Fixpoint:
    """Least model without probabilities, stratum by stratum: rounds for groups of predicates that need each other only."""
    program = normalize(program)
    out = Fixpoint(program=program)

    def made(group: set[str]) -> dict[str, DataFrame]:
        known = {**program.facts, **out.tables}
        own = [r for r in program.rules if r.head.pred in group and all(a.pred in known or a.pred in group for a in r.body)]
        if any(a.pred in group for r in own for a in r.body):
            return set_fixpoint(Program(own, {a.pred: known[a.pred] for r in own for a in r.body if a.pred not in group})).tables if any(all(a.pred in known for a in r.body) for r in own) else {}
        frames = [s.joined([(known[a.pred], []) for a in s.rule.body]).select(*head_columns(s.rule)) for s in shapes(own)]
        if not frames:
            return {}
        rows, n = stored_count(union(frames).distinct(), "stratum")
        return {next(iter(group)): rows} if n else {}

    for level in strata(program.rules):
        for tables in side_by_side(made, level):
            out.tables |= tables
    return out


def formula_fixpoint(program: Program, mode: str = "naive", k: int | None = None, depth_limit: int | None = None, check: bool = True, most_rounds: int | None = None, below: dict[str, DataFrame] | None = None) -> Fixpoint:
    """Facts with absorbed formulas.

    ``mode``: ``naive`` recomputes every instantiation each round; ``delta`` those with a changed fact; ``rewritten`` has
    for each rule an auxiliary predicate of the heads that a changed fact reaches, recomputes those heads alone (a
    semi-join of the rule with it) and merges by outer join.  ``check`` False runs ``depth_limit`` rounds without any
    equivalence test.  ``k`` keeps the k most probable explanations; ``below`` are formulas of the strata below.  More than ``most_rounds`` rounds: RoundLimit.
    The log counts instances, updates, equivalence tests, formulas kept equal to another one of the round (``copies``),
    joins, and the seconds of deriving and of disjoining, merging and comparing.
    """
    if mode not in ("naive", "delta", "rewritten"):
        raise ValueError(f"unknown mode {mode!r}")
    if not check and depth_limit is None:
        raise ValueError("without equivalence tests a number of rounds is needed")
    program = normalize(program)
    derived, out = program.derived, Fixpoint(program=program)
    weights = stored(union([df.select("fid", "pi") for df in program.facts.values() if "pi" in df.columns]).dropDuplicates(["fid"]), "weights") if k else None
    base = {p: df.withColumn("dnf", F.array(F.array("fid"))) for p, df in program.facts.items()} | (below or {})
    known: dict[str, DataFrame] = {}
    changed: dict[str, DataFrame] = {}
    for depth in rounds(1, most_rounds):
        if depth_limit is not None and depth > depth_limit:
            break
        began, fresh, joins = time.perf_counter(), {}, 0
        for rule in program.rules:
            spots = derived_positions(rule, derived)
            if not spots:
                variants = [None] if depth == 1 or mode == "naive" else []
            else:
                variants = [] if depth == 1 else spots if mode == "delta" else [None]
            reached = None
            if mode == "rewritten" and spots and depth > 1:
                heads = []
                for spot in spots:
                    own = changed.get(rule.body[spot].pred)
                    tables = [known.get(a.pred) if a.pred in derived else base[a.pred] for a in rule.body]
                    if own is None or any(t is None for t in tables):
                        continue
                    tables[spot] = tables[spot].join(own, "fid", "left_semi")
                    heads.append(join_body(rule, [(t, []) for t in tables], order=[spot, *(i for i in range(len(rule.body)) if i != spot)]).select(*head_columns(rule)))
                    joins += len(rule.body)
                if not heads:
                    continue
                reached = stored(union(heads).distinct(), f"reached-{depth}")
            for spot in variants:
                inputs = []
                for i, atom in enumerate(rule.body):
                    if atom.pred not in derived:
                        inputs.append(base[atom.pred])
                        continue
                    table = known.get(atom.pred)
                    if spot is not None and table is not None:
                        own = changed.get(atom.pred)
                        if i == spot:
                            table = None if own is None else table.join(own, "fid", "left_semi")
                        elif i < spot and own is not None:
                            table = table.join(own, "fid", "left_anti")
                    inputs.append(table)
                if any(x is None for x in inputs):
                    continue
                rows = join_body(rule, [(df, ["dnf"]) for df in inputs], order=None if spot is None else [spot, *(i for i in range(len(rule.body)) if i != spot)])
                joins += len(rule.body) - 1
                product = F.col("dnf_0")
                for i in range(1, len(rule.body)):
                    product = dnf_and(product, F.col(f"dnf_{i}"))
                rows = rows.select(*head_columns(rule), dnf_absorb(product).alias("dnf"))
                if reached is not None:
                    rows = rows.join(reached, arguments(rows), "left_semi")
                    joins += 1
                fresh.setdefault(rule.head.pred, []).append(rows)
        instances, updates, new_known, new_changed, tests, copies, deriving = 0, 0, dict(known), {}, 0, 0, 0.0
        for pred, frames in fresh.items():
            since = time.perf_counter()
            rows = stored(union(frames), f"derive-{depth}")
            instances += rows.count()
            deriving += time.perf_counter() - since
            joins += pred in known
            args = arguments(rows)
            grouped = rows.groupBy(*args).agg(dnf_absorb(F.flatten(F.collect_list("dnf"))).alias("fresh"))
            grouped = grouped.withColumn("fid", fact_id(pred, [F.col(a) for a in args]))
            if pred in known:
                old = known[pred].select(*args, "fid", F.col("dnf").alias("old"))
                merged = grouped.join(old, [*args, "fid"], "full_outer")
                value = F.when(F.col("fresh").isNull(), F.col("old")).when(F.col("old").isNull(), F.col("fresh"))
                merged = merged.withColumn("dnf", value.otherwise(dnf_absorb(dnf_or(F.col("old"), F.col("fresh")))))
            else:
                merged = grouped.withColumn("old", F.lit(None).cast("array<array<bigint>>")).withColumn("dnf", F.col("fresh"))
            if k:
                merged = _best(merged, args, weights, k)
            merged = stored(merged.withColumn("moved", ~F.col("dnf").eqNullSafe(F.col("old"))), f"merged-{depth}")
            n, total, same = merged.agg(F.count_if("moved"), F.count("*"), F.count_if(F.col("old").isNotNull() & F.col("fresh").isNotNull() & ~F.col("moved"))).first()
            tests += total if check else 0
            copies += same
            new_known[pred] = merged.select(*args, "fid", "dnf")
            if n:
                new_changed[pred] = merged.where("moved").select("fid")
                updates += n
        known, changed = new_known, new_changed
        out.log.append({"depth": depth, "instances": instances, "updates": updates, "tests": tests, "copies": copies, "joins": joins, "deriving": deriving, "seconds": time.perf_counter() - began})
        if check and not updates or below is not None and not any(derived_positions(r, derived) for r in program.rules):
            break
    out.tables = known
    return out


def _best(df: DataFrame, args: list[str], weights: DataFrame, k: int) -> DataFrame:
    """Only the k most probable explanations of each fact; ties go by the ids in order.  Most facts have no more."""
    df = stored(df, "unranked")
    fits = F.coalesce(F.size("dnf") <= k, F.lit(True))
    few, df = df.where(fits), df.where(~fits)
    each = df.select(*args, "fid", F.explode("dnf").alias("e"))
    parts = each.withColumn("at", F.explode_outer("e")).join(weights.withColumnRenamed("fid", "at"), "at", "left")
    scored = parts.groupBy("fid", "e").agg(F.product(F.coalesce("pi", F.lit(1.0))).alias("score"))
    ranked = scored.withColumn("rank", F.row_number().over(Window.partitionBy("fid").orderBy(F.desc("score"), "e"))).where(F.col("rank") <= k)
    top = ranked.groupBy("fid").agg(F.array_sort(F.collect_list("e")).alias("dnf"))
    return few.unionByName(df.drop("dnf").join(top, "fid"))


def topk_fixpoint(program: Program, k: int = 30, **options) -> Fixpoint:
    """Stratum by stratum, each read at its fixpoint; with options (a number of rounds, say) all predicates round by round."""
    if options:
        return formula_fixpoint(program, mode="naive", k=k, **options)
    program = normalize(program)
    out = Fixpoint(program=program)
    for level in strata(program.rules):
        for group in level:
            known = {**program.facts, **out.tables}
            own = [r for r in program.rules if r.head.pred in group and all(a.pred in known or a.pred in group for a in r.body)]
            if not own:
                continue
            part = formula_fixpoint(Program(own, known), mode="naive", k=k, below=out.tables)
            out.tables |= part.tables
            out.log += part.log
    return out


@dataclass
class Circuit:
    """Gates (gate, kind, fid, depth) and wires (src, dst)."""

    gates: DataFrame
    wires: DataFrame
    log: list[dict]
    ands: DataFrame
    facts: dict[str, DataFrame]

    def lineage(self, pred: str) -> DataFrame:
        """a0.., dnf: the circuit evaluated bottom up, gate by gate, until no formula grows any more.

        Rules are not joined again: an and-gate is the product of the formulas of its body, an or-gate their union.
        """
        bodies = self.ands.select("gate", "fid", F.size("body").alias("n"), F.posexplode("body").alias("at", "part"))
        derived = self.ands.select("fid").distinct()
        leaves = bodies.select(F.col("part").alias("fid")).distinct().join(derived, "fid", "left_anti")
        known = stored(leaves.select("fid", F.array(F.array("fid")).alias("dnf")), "gates-known")
        mark = None
        while True:
            fed = bodies.join(known.select(F.col("fid").alias("part"), "dnf"), "part").groupBy("gate", "fid", "n").agg(F.collect_list("dnf").alias("dnfs")).where(F.size("dnfs") == F.col("n"))
            empty = F.array(F.array().cast("array<bigint>"))
            product = dnf_absorb(F.aggregate("dnfs", empty, lambda s, x: dnf_and(s, x)))
            either = fed.select("fid", product.alias("dnf")).groupBy("fid").agg(dnf_absorb(F.flatten(F.collect_list("dnf"))).alias("dnf"))
            known = stored(either.unionByName(leaves.select("fid", F.array(F.array("fid")).alias("dnf"))), "gates-known")
            now = known.agg(F.count("*"), F.sum(F.xxhash64("fid", "dnf").cast("decimal(38,0)"))).first()
            if now == mark:
                break
            mark = now
        own = self.facts[pred]
        return own.join(known, "fid").select(*arguments(own), "dnf")


def circuit(program: Program, most_rounds: int | None = None) -> Circuit:
    """Semi-naive rounds; an instantiation is an and-gate once, a fact has an inner and an outer or-gate.

    Outer gates of a round read inner gates of the round before, which keeps the graph free of cycles.
    """
    program = normalize(program)
    derived, log = program.derived, []
    known: dict[str, DataFrame] = {}
    last: dict[str, DataFrame] = {}
    older: dict[str, DataFrame] = {}
    ands: list[DataFrame] = []
    for depth in rounds(1, most_rounds):
        fresh: dict[str, list[DataFrame]] = {}
        for rule in program.rules:
            for spot in _variants(rule, derived, True, depth == 1):
                inputs = []
                for i, atom in enumerate(rule.body):
                    if atom.pred not in derived:
                        inputs.append(program.facts[atom.pred])
                    else:
                        inputs.append(known.get(atom.pred) if spot is None else last.get(atom.pred) if i == spot else older.get(atom.pred) if i < spot else known.get(atom.pred))
                if any(x is None for x in inputs):
                    continue
                rows = join_body(rule, [(df, ["fid"]) for df in inputs])
                args = head_columns(rule)
                body = F.array(*(f"fid_{i}" for i in range(len(rule.body))))
                rows = rows.select(*args, body.alias("body"), F.xxhash64(F.lit(rule.id), body).alias("gate"))
                fresh.setdefault(rule.head.pred, []).append(rows.withColumn("fid", fact_id(rule.head.pred, [F.col(f"a{i}") for i in range(len(args))])).withColumn("depth", F.lit(depth)))
        new, total = {}, 0
        for pred, frames in fresh.items():
            rows = stored(union(frames), f"gates-{depth}")
            n = rows.count()
            ands.append(rows.select("gate", "fid", "body", "depth"))
            facts = rows.select(*arguments(rows), "fid").distinct()
            if pred in known:
                facts = facts.join(known[pred], "fid", "left_anti")
            facts = stored(facts, f"facts-{depth}")
            total += n
            if not facts.isEmpty():
                new[pred] = facts
        log.append({"depth": depth, "instances": total})
        if not new:
            break
        older = dict(known)
        for pred, rows in new.items():
            known[pred] = union([known[pred], rows]) if pred in known else rows
        last = new
    every = stored(union(ands).dropDuplicates(["gate", "fid"]), "ands")
    facts = every.select("fid").distinct()
    leaves = every.select(F.explode("body").alias("fid")).distinct().join(facts, "fid", "left_anti")
    gates = union(
        [
            every.select("gate", F.lit("and").alias("kind"), "fid", "depth"),
            facts.select(F.xxhash64("fid", F.lit("inner")).alias("gate"), F.lit("inner_or").alias("kind"), "fid", F.lit(0).alias("depth")),
            facts.select(F.xxhash64("fid", F.lit("outer")).alias("gate"), F.lit("outer_or").alias("kind"), "fid", F.lit(0).alias("depth")),
            leaves.select(F.col("fid").alias("gate"), F.lit("leaf").alias("kind"), "fid", F.lit(0).alias("depth")),
        ]
    )
    into = every.select(F.col("gate").alias("src"), F.xxhash64("fid", F.lit("inner")).alias("dst"))
    used = every.select("gate", F.explode("body").alias("fid")).join(facts.withColumn("is_fact", F.lit(True)), "fid", "left")
    source = F.when(F.col("is_fact"), F.xxhash64("fid", F.lit("outer"))).otherwise(F.col("fid"))
    through = facts.select(F.xxhash64("fid", F.lit("inner")).alias("src"), F.xxhash64("fid", F.lit("outer")).alias("dst"))
    return Circuit(gates, union([into, used.select(source.alias("src"), F.col("gate").alias("dst")), through]), log, every, known)


def worlds(program: Program, pred: str, most_facts: int = 16) -> DataFrame:
    """a0.., prob of the facts of ``pred``: the sum of the worlds that with the rules entail them."""
    program = normalize(program)
    every = union([df.select("fid", "pi") for df in program.facts.values()]).dropDuplicates(["fid"])
    uncertain = [r["fid"] for r in every.where("pi < 1").orderBy("fid").limit(most_facts + 1).collect()]
    if len(uncertain) > most_facts:
        raise ValueError(f"more than {most_facts} uncertain facts")
    spark = every.sparkSession
    places = spark.createDataFrame([(f, i) for i, f in enumerate(uncertain)], "fid bigint, place int")
    ids = spark.range(1 << len(uncertain)).withColumnRenamed("id", "world")
    weights = every.join(places, "fid")
    on = F.expr("(world >> place) & 1") == 1
    pr = stored(ids.join(weights).groupBy("world").agg(F.product(F.when(on, F.col("pi")).otherwise(1 - F.col("pi"))).alias("pr")) if uncertain else ids.withColumn("pr", F.lit(1.0)), "worlds")
    inside = {}
    for name, df in program.facts.items():
        placed = df.join(F.broadcast(places), "fid", "left")
        inside[name] = placed.join(F.broadcast(ids), F.col("place").isNull() | on).select(*arguments(df), "world")
    model = set_fixpoint(Program(program.rules, inside), extra=("world",)).of(pred)
    return model.join(pr, "world").groupBy(*arguments(model)).agg(F.sum("pr").alias("prob"))
