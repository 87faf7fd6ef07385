"""The plan-graph engine: derivation trees as shared pointers, round by round, with or without collapsing.

A tree is a row: the node (rule application) that made it, the fact at its root, pointers to the trees of its derived
body atoms (``kids``), the base facts its own step uses (``leaves``), and ``must``, the derived facts that occur in every
unfolding.  A new tree is redundant iff its root is among the ``must`` of its kids, which is a test on the row alone.

A round is one plan per rule and body position: atoms before the position read trees older than the last round, the
position itself those of the last round, atoms after it any - so every combination with a tree of the last round appears
exactly once.  Rounds are scratch tables: the next plan begins at a scan, whatever the number of rounds.

Collapsing folds the trees of a node that share a root into one tree of label ``O`` with the others as members, where
the node's candidates have at least ``collapse`` trees per root on average.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.dnf import dnf_absorb, dnf_and, dnf_implied
from ..rules import Program, normalize
from ..sources.tables import fact_id, side_by_side, stored
from .compile import Shape, argument_types, arguments, derived_positions, head_columns, rounds, shapes, union

HERBRAND = "herbrand"


@dataclass
class PlanResult:
    """Trees per predicate and round, members of collapsed trees, and what the rounds cost."""

    program: Program
    trees: dict[str, list[DataFrame]] = field(default_factory=dict)
    members: list[DataFrame] = field(default_factory=list)
    member_trees: list[DataFrame] = field(default_factory=list)
    log: list[dict] = field(default_factory=list)
    depths: dict[str, list[int]] = field(default_factory=dict)

    def of(self, pred: str) -> DataFrame:
        """Trees of a predicate; no rows where nothing was derived."""
        if self.trees.get(pred):
            return union(self.trees[pred])
        return self._nothing(pred)

    def _nothing(self, pred: str) -> DataFrame:
        spark = next(iter(self.program.facts.values())).sparkSession
        args = ", ".join(f"a{i} {t}" for i, t in enumerate(argument_types(self.program)[pred]))
        return spark.createDataFrame([], f"{args}, node bigint, kids array<bigint>, leaves array<bigint>, fid bigint, rule string, depth int, label string, tid bigint, must array<bigint>")

    def narrow(self) -> DataFrame:
        """All trees without their arguments: pred, depth, node, rule, tid, fid, label, kids, leaves."""
        tables = [(p, df) for p, dfs in self.trees.items() for df in dfs] or [("", self._nothing(p)) for p in sorted(self.program.derived)[:1]]
        return union([df.select(F.lit(p).alias("pred"), "depth", "node", "rule", "tid", "fid", "label", "kids", "leaves") for p, df in tables])

    def counts(self) -> list[tuple[int, int, int, int]]:
        """(depth, nodes with kept trees, candidates, kept)."""
        return [(x["depth"], x["nodes"], x["candidates"], x["kept"]) for x in self.log]

    def graph(self) -> DataFrame:
        """Nodes of the plan graph: node, rule, depth and number of trees."""
        return self.narrow().groupBy("node", "rule", "depth").agg(F.count("*").alias("trees"))

    def dot(self, most: int = 200) -> str:
        """The plan graph in DOT text (at most ``most`` nodes)."""
        rows = self.graph().orderBy("depth", "rule", "node").limit(most).collect()
        return "\n".join(["digraph plan {", *(f'  n{r["node"] & (2**63 - 1)} [label="{r["rule"]} @{r["depth"]}: {r["trees"]}"];' for r in rows), "}"])


def _candidates(shape: Shape, inputs: list[tuple[DataFrame, str]], depth: int, order: list[int], carry: bool) -> DataFrame:
    """Trees of one plan: inputs are (table, kind) with kind ``base``, ``guard`` or ``tree``."""
    rule = shape.rule
    payload = [[] if kind == "guard" else ["fid"] if kind == "base" else ["tid", "node", "must", *(["dnf"] if carry else [])] for _, kind in inputs]
    rows = shape.joined([(df, p) for (df, _), p in zip(inputs, payload, strict=True)], order, payload=True)
    name = F.col("rule_id") if shape.merged else F.lit(rule.id)
    trees = [i for i, (_, kind) in enumerate(inputs) if kind == "tree"]
    bases = [i for i, (_, kind) in enumerate(inputs) if kind == "base"]
    none = F.array().cast("array<bigint>")
    kids = F.array(*(f"tid_{i}" for i in trees)) if trees else none
    leaves = F.array(*(f"fid_{i}" for i in bases)) if bases else none
    must = none
    for i in trees:
        must = F.array_union(must, F.col(f"must_{i}"))
    args = head_columns(rule)
    rows = rows.select(*args, F.xxhash64(name, *(f"node_{i}" for i in trees)).alias("node"), kids.alias("kids"), leaves.alias("leaves"), must.alias("must_kids"), name.alias("rule"), *([_product(rows, trees, leaves).alias("dnf")] if carry else []))
    fid = fact_id(rule.head.pred, [F.col(f"a{i}") for i in range(len(args))])
    rows = rows.withColumn("fid", fid).withColumn("depth", F.lit(depth)).withColumn("label", F.lit("A"))
    return rows.withColumn("tid", F.xxhash64("node", "fid", "kids", "leaves"))


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """By keys, over all cores: few bytes may be much work on formulas, and small partitions are joined by size."""
    return df.repartition(max(2, df.sparkSession.sparkContext.defaultParallelism), *keys)


def _product(rows: DataFrame, trees: list[int], leaves):
    out = F.array(leaves)
    for i in trees:
        out = dnf_and(out, F.col(f"dnf_{i}"))
    return dnf_absorb(out)


def _worth_folding(cand: DataFrame, threshold: float, policy: str) -> bool:
    sizes = cand.groupBy("node", "fid").agg(F.count("*").alias("n"), F.count_if(~F.col("redundant")).alias("alive"))
    if policy == "per_root":
        return not sizes.where((F.col("alive") >= threshold) & (F.col("alive") > 1)).isEmpty()
    nodes = sizes.groupBy("node").agg(F.avg("n").alias("average"), F.max("alive").alias("most"))
    return not nodes.where((F.col("average") >= threshold) & (F.col("most") > 1)).isEmpty()


def _collapsed(cand: DataFrame, threshold: float, policy: str, carry: bool, prune_members: bool = True) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(trees with groups folded, members, trees behind a fold).

    Without ``prune_members`` redundant trees are members too; a group of which all are redundant goes.
    """
    by = Window.partitionBy("node", "fid")
    pool = cand.where("not redundant") if prune_members else cand.withColumn("some", F.bool_or(~F.col("redundant")).over(by)).where("some").drop("some")
    size = pool.withColumn("size", F.count("*").over(by))
    if policy == "per_root":
        fold = (F.col("size") >= threshold) & (F.col("size") > 1)
    else:
        # the average is over candidates, before redundant ones go
        averages = cand.groupBy("node", "fid").agg(F.count("*").alias("n")).groupBy("node").agg(F.avg("n").alias("average"))
        size = size.join(averages, "node")
        fold = (F.col("average") >= threshold) & (F.col("size") > 1)
    size = size.withColumn("fold", fold)
    inside = size.where("fold")
    args = arguments(cand)
    # facts of every member: counted, so that no group is held as one row
    total = inside.groupBy("node", "fid").agg(F.count("*").alias("n"))
    common = inside.select("node", "fid", F.explode("must").alias("f")).groupBy("node", "fid", "f").agg(F.count("*").alias("k"))
    musts = common.join(total, ["node", "fid"]).where("k = n").groupBy("node", "fid").agg(F.sort_array(F.collect_list("f")).alias("must"))
    head = spread(inside, "node", "fid").groupBy("node", "fid").agg(*(F.first(a).alias(a) for a in args), F.first("rule").alias("rule"), F.first("depth").alias("depth"), *([dnf_absorb(F.flatten(F.collect_set("dnf"))).alias("dnf")] if carry else []))
    none = F.array().cast("array<bigint>")
    folded = head.join(musts, ["node", "fid"]).withColumn("label", F.lit("O")).withColumn("kids", none).withColumn("leaves", none).withColumn("tid", F.xxhash64("node", "fid", F.lit("O"))).withColumn("bears", F.lit(True))
    members = inside.select(F.xxhash64("node", "fid", F.lit("O")).alias("tid"), F.col("tid").alias("member"))
    hidden = inside.select("depth", "tid", "kids", "leaves")
    kept = size.where("not fold and not redundant").withColumn("bears", F.lit(False))
    return union([kept.select(*folded.columns), folded]), members, hidden


def reason(program: Program, collapse: float | None = None, max_depth: int | None = None, termination: str = "absorb", redundancy: str | None = "must", collapse_policy: str = "node", annotate: bool = True, most_rounds: int | None = None, prune_members: bool = True, start: PlanResult | None = None) -> PlanResult:
    """Run rounds until none makes a new tree; where more than ``most_rounds`` would be needed, RoundLimit.

    ``collapse`` None: trees are never folded; a number: the average trees per root from which a node folds.
    ``collapse_policy``: ``node`` as said, ``per_root`` folds roots of so many trees, ``estimate`` as ``node`` but only
    where a rule reads the predicate.  ``prune_members`` False keeps redundant trees behind a fold.
    ``termination`` applies with collapsing: ``absorb`` drops folded trees, and trees over them, whose explanations are
    all implied by earlier trees of the fact; ``herbrand`` stops after as many rounds as there are derived facts.
    ``annotate`` False keeps one tree per fact: plain set semantics over the plan graph.
    ``redundancy`` None keeps redundant trees (bounded by max_depth).
    ``start`` goes on from an earlier result whose facts ``program`` contains: the first round takes what a new fact
    takes part in, later rounds what a new tree does.
    """
    program = normalize(program)
    derived, plans = program.derived, shapes(program.rules)
    consumed = {a.pred for r in program.rules for a in r.body}
    out = PlanResult(program)
    carry = collapse is not None and termination == "absorb"
    kind = lambda atom: "guard" if atom.pred in program.guards else "base"
    seen: dict[str, DataFrame] = {}
    facts_seen: dict[str, DataFrame] = {}
    bearing, first, fresh = False, 1, {}
    if start is not None:
        if collapse is not None or not annotate or start.members:
            raise ValueError("results go on without folds only")
        first = start.log[-1]["depth"] + 1 if start.log else 1
        out.trees, out.depths, out.log = {p: list(x) for p, x in start.trees.items()}, {p: list(x) for p, x in start.depths.items()}, list(start.log)
        fresh = {p: stored(df.join(start.program.facts[p].select("fid"), "fid", "left_anti").select(*df.columns), "new-facts") for p, df in program.facts.items() if df is not start.program.facts[p]}
    for depth in rounds(first, most_rounds):
        if max_depth is not None and depth > max_depth:
            break
        began = time.perf_counter()
        by_pred: dict[str, list[DataFrame]] = {}
        for shape in plans:
            rule = shape.rule
            growing = depth == first and start is not None
            spots = [i for i, a in enumerate(rule.body) if a.pred in fresh] if growing else derived_positions(rule, derived)
            if depth == 1 and not growing:
                if not spots:
                    by_pred.setdefault(rule.head.pred, []).append(_candidates(shape, [(program.facts[a.pred], kind(a)) for a in rule.body], 1, list(range(len(rule.body))), carry))
                continue
            for spot in spots:
                inputs, ready = [], True
                for i, atom in enumerate(rule.body):
                    if atom.pred not in derived:
                        old = growing and atom.pred in fresh and i <= spot
                        inputs.append((fresh[atom.pred] if old and i == spot else start.program.facts[atom.pred] if old else program.facts[atom.pred], kind(atom)))
                        continue
                    pairs = list(zip(out.trees.get(atom.pred, []), out_depths(out, atom.pred), strict=True))
                    use = [df for df, d in pairs if growing or d < depth - (i <= spot) + (i == spot) and (i != spot or d == depth - 1)]
                    if not use:
                        ready = False
                        break
                    inputs.append((union(use), "tree"))
                if ready:
                    order = [spot, *(i for i in range(len(rule.body)) if i != spot)]
                    by_pred.setdefault(rule.head.pred, []).append(_candidates(shape, inputs, depth, order, carry))
        kept_total, candidates, nodes, spent = 0, 0, 0, 0.0
        alive = ~F.col("redundant")

        def derive(item, depth=depth, alive=alive):
            pred, frames = item
            redundant = F.array_contains("must_kids", F.col("fid")) if redundancy else F.lit(False)
            cand = union(frames).withColumn("redundant", redundant).withColumn("must", F.array_union("must_kids", F.array("fid"))).drop("must_kids")
            cand = stored(cand, f"candidates-{depth}")
            return pred, cand, cand.agg(F.count("*"), F.count_if(alive), F.count_distinct(F.when(alive, F.col("node"))), F.count_distinct("node", "fid")).first()

        for pred, cand, (n_cand, kept, made, roots) in side_by_side(derive, list(by_pred.items())):
            candidates += n_cand
            if not kept:
                continue
            trees, changed = cand.where(alive).drop("redundant"), False
            if collapse is not None and (collapse_policy != "estimate" or pred in consumed):
                since = time.perf_counter()
                if bearing or n_cand > roots and _worth_folding(cand, collapse, collapse_policy):
                    folded, members, hidden = _collapsed(cand, collapse, collapse_policy, carry, prune_members)
                    trees, members = stored(folded, f"trees-{depth}"), stored(members, f"members-{depth}")
                    if not members.isEmpty():
                        out.members.append(members)
                        out.member_trees.append(stored(hidden, f"hidden-{depth}"))
                        bearing = True
                    changed = True
                    trees = trees.drop("bears")
                spent += time.perf_counter() - since
                if carry and bearing and pred in seen:
                    known = seen[pred].withColumnRenamed("dnf", "known")
                    trees, changed = trees.join(known, "fid", "left").where(F.col("known").isNull() | ~dnf_implied(F.col("dnf"), F.col("known"))).drop("known"), True
            if not annotate:
                trees, changed = trees.dropDuplicates(["fid"]), True
                if pred in facts_seen:
                    trees = trees.join(facts_seen[pred], "fid", "left_anti")
            if changed:
                trees = stored(trees, f"trees-{depth}")
                kept, made = trees.agg(F.count("*"), F.count_distinct("node")).first()
            if not kept:
                continue
            kept_total, nodes = kept_total + kept, nodes + made
            out.trees.setdefault(pred, []).append(trees)
            out_depths(out, pred).append(depth)
            if not annotate:
                facts_seen[pred] = stored(union([x.select("fid") for x in out.trees[pred]]), "seen")
            if carry:
                both = [trees.select("fid", "dnf"), *([seen[pred]] if pred in seen else [])]
                seen[pred] = stored(spread(union(both), "fid").groupBy("fid").agg(dnf_absorb(F.flatten(F.collect_list("dnf"))).alias("dnf")), "seen")
        out.log.append({"depth": depth, "nodes": nodes, "candidates": candidates, "kept": kept_total, "seconds": time.perf_counter() - began, "collapse_seconds": spent})
        if not kept_total:
            break
        if termination == HERBRAND and collapse is not None and depth >= out.narrow().select("fid").distinct().count():
            break
    return out


def out_depths(result: PlanResult, pred: str) -> list[int]:
    """Rounds of the tables in ``result.trees[pred]``."""
    return result.depths.setdefault(pred, [])


def lineage(result: PlanResult, pred: str, keep=None, max_depth: int | None = None, cap: int | None = None) -> DataFrame:
    """a0.., dnf (absorbed) of the facts of ``pred`` that ``keep`` (a condition on a0..) selects.

    Top down, the trees that the answers need are found by semi-joins; bottom up, their formulas are built round by
    round, each round a table of its own.  ``max_depth`` looks at the first rounds only: a lower bound of every
    probability.  With ``cap`` the unfolded trees of each answer are counted first: answers of more than that have the
    status ``disjunct_cap`` and an empty formula, which is never built.
    """
    roots = result.of(pred)
    roots = roots if keep is None else roots.where(keep)
    roots = roots if max_depth is None else roots.where(F.col("depth") <= max_depth)
    args, over = arguments(roots), None
    if cap is not None:
        over = stored(unfold_counts(result, pred).where(F.col("unfoldings") > cap).select(*args), "over-cap")
        roots = roots.join(over, args, "left_anti")
    every = result.narrow().select("depth", "tid", "kids", "leaves")
    members = union(result.members) if result.members else None
    if result.member_trees:
        every = union([every, union(result.member_trees).select("depth", "tid", "kids", "leaves")])
    deepest = max((d for own in result.depths.values() for d in own), default=1)
    need = roots.select("tid", "depth")
    if members is not None:
        depth_of = every.select(F.col("tid").alias("member"), "depth")
        need = need.unionByName(members.join(need, "tid", "left_semi").select(F.col("member").alias("tid")).join(depth_of.withColumnRenamed("member", "tid"), "tid"))
    wanted = [need.distinct()]
    if deepest > 2:
        frontier = need
        for _ in range(deepest - 1):
            down = every.join(frontier.select("tid").distinct(), "tid", "left_semi").select(F.explode("kids").alias("tid")).distinct()
            if members is not None:
                down = union([down, members.join(down, "tid", "left_semi").select(F.col("member").alias("tid"))]).distinct()
            frontier = stored(down.join(every.select("tid", "depth"), "tid"), "frontier")
            if frontier.isEmpty():
                break
            wanted.append(frontier)
        every = stored(every.join(union(wanted).select("tid").distinct(), "tid", "left_semi"), "needed")
    done: list[DataFrame] = []
    for d in range(1, deepest + 1):
        here = every.where(F.col("depth") == d)
        own = here.where(F.size("kids") == 0).select("tid", F.array("leaves").alias("dnf"))
        if members is not None:
            own = own.join(members.select("tid").distinct(), "tid", "left_anti")
        if done:
            n_kids = here.where(F.size("kids") > 0).select("tid", "leaves", F.posexplode("kids").alias("at", "kid"))
            joined = n_kids.join(union(done).select(F.col("tid").alias("kid"), "dnf"), "kid").groupBy("tid").agg(F.first("leaves").alias("leaves"), F.collect_list("dnf").alias("dnfs"))
            product = F.aggregate("dnfs", F.array("leaves"), lambda s, x: dnf_and(s, x))
            own = own.unionByName(joined.select("tid", dnf_absorb(product).alias("dnf")))
        if members is not None:
            folds = spread(members.join(own.withColumnRenamed("tid", "member"), "member"), "tid").groupBy("tid").agg(dnf_absorb(F.flatten(F.collect_set("dnf"))).alias("dnf"))
            own = own.unionByName(folds)
        done.append(stored(own, f"formulas-{d}") if deepest > 1 else own)
    whole = spread(roots.select(*args, "tid").join(union(done), "tid"), *args).groupBy(*args).agg(dnf_absorb(F.flatten(F.collect_set("dnf"))).alias("dnf"))
    if over is None:
        return whole
    none = F.array().cast("array<array<bigint>>")
    return whole.withColumn("status", F.lit("ok")).unionByName(over.withColumn("dnf", none).withColumn("status", F.lit("disjunct_cap")))


def base_probabilities(program: Program) -> DataFrame:
    return union([df.select("fid", "pi") for df in program.facts.values()])


def probabilities(formulas: DataFrame, facts: DataFrame, solver: str = "dd", **options) -> DataFrame:
    """a0.., prob, n_expl, n_vars, lower, status, nanos of answers with their formula ``dnf``."""
    from ..functions.solvers import dnf_prob

    args = arguments(formulas)
    keyed = formulas.withColumn("_key", F.xxhash64(*args) if args else F.lit(0))
    terms = keyed.select(*args, "_key", F.explode(F.array_distinct(F.flatten("dnf"))).alias("fid"))
    weights = terms.join(facts.dropDuplicates(["fid"]), "fid").groupBy(*args, "_key").agg(F.sort_array(F.collect_list(F.struct("fid", "pi"))).alias("pis"))
    both = keyed.join(weights, [*args, "_key"], "left")
    none = F.array().cast("array<struct<fid:bigint,pi:double>>")
    both = both.withColumn("pis", F.coalesce("pis", none))
    solved = both.withColumn("solved", dnf_prob(F.col("dnf"), F.col("pis.fid"), F.col("pis.pi"), solver, **options))
    status, prob = F.col("solved.status"), F.col("solved.prob")
    if "status" in formulas.columns:  # formulas that were not built have no probability
        status, prob = F.when(F.col("status") == "ok", status).otherwise(F.col("status")), F.when(F.col("status") == "ok", prob)
    return solved.select(*args, prob.alias("prob"), F.size("dnf").cast("long").alias("n_expl"), F.size("pis").cast("long").alias("n_vars"), F.col("solved.lower").alias("lower"), status.alias("status"), F.col("solved.nanos").alias("nanos"))


def bounds_by_round(result: PlanResult, pred: str, keep=None) -> DataFrame:
    """depth, a0.., prob of the first ``depth`` rounds: lower bounds that only grow."""
    facts = base_probabilities(result.program)
    parts = [probabilities(lineage(result, pred, keep, d), facts).withColumn("depth", F.lit(d)) for d, _, _, kept in result.counts() if kept]
    return union(parts)


def append(result: PlanResult, new_facts: dict[str, DataFrame], **options) -> PlanResult:
    """The result grown by new base facts: rounds go on from the stored ones, with the new facts as the first changes.

    Lineage only grows, so earlier trees stay as they are.  A fact that is there already keeps its probability.
    """
    grown = {}
    for p, df in result.program.facts.items():
        if p in new_facts:
            fresh = new_facts[p].select(*df.columns).dropDuplicates(["fid"]).join(df.select("fid"), "fid", "left_anti")
            grown[p] = union([df, fresh.select(*df.columns)])
        else:
            grown[p] = df
    return reason(Program(result.program.rules, grown, result.program.guards), start=result, **options)


def save(result: PlanResult, path: str) -> None:
    """Trees by predicate and round, members and the log, as tables below ``path``."""
    spark = next(iter(result.program.facts.values())).sparkSession
    for pred, tables in result.trees.items():
        union(tables).drop("dnf").write.mode("overwrite").partitionBy("depth").parquet(f"{path}/trees/{pred}")
    for name, tables in (("members", result.members), ("hidden", result.member_trees)):
        if tables:
            union(tables).write.mode("overwrite").parquet(f"{path}/{name}")
    log = [(x["depth"], x["nodes"], x["candidates"], x["kept"], float(x["seconds"]), float(x["collapse_seconds"])) for x in result.log]
    spark.createDataFrame(log, "depth int, nodes bigint, candidates bigint, kept bigint, seconds double, collapse_seconds double").coalesce(1).write.mode("overwrite").parquet(f"{path}/log")
    saved = [(p, d) for p, own in result.depths.items() for d in own]
    spark.createDataFrame([*saved, *((n, 0) for n, t in (("members", result.members), ("hidden", result.member_trees)) if t)], "name string, depth int").coalesce(1).write.mode("overwrite").parquet(f"{path}/saved")


def resume(program: Program, path: str) -> PlanResult:
    """A saved result of the program: to be asked, or to go on from with ``append`` or ``reason(start=...)``."""
    program = normalize(program)
    spark = next(iter(program.facts.values())).sparkSession
    out = PlanResult(program)
    for r in spark.read.parquet(f"{path}/saved").orderBy("name", "depth").collect():  # one row a predicate and round
        name, depth = r["name"], r["depth"]
        if not depth:
            (out.members if name == "members" else out.member_trees).append(spark.read.parquet(f"{path}/{name}"))
            continue
        table = spark.read.parquet(f"{path}/trees/{name}").where(F.col("depth") == depth)
        out.trees.setdefault(name, []).append(table.withColumn("depth", F.col("depth").cast("int")))
        out_depths(out, name).append(depth)
    out.log = [r.asDict() for r in spark.read.parquet(f"{path}/log").orderBy("depth").collect()]
    return out


def explanations(result: PlanResult, pred: str, keep=None, k: int | None = None) -> DataFrame:
    """a0.., rank, score, explanation (fact ids): the minimal explanations of each fact, most probable first."""
    formulas = lineage(result, pred, keep)
    args = arguments(formulas)
    each = formulas.select(*args, F.explode("dnf").alias("explanation"))
    parts = each.withColumn("fid", F.explode_outer("explanation")).join(base_probabilities(result.program).dropDuplicates(["fid"]), "fid", "left")
    scored = parts.groupBy(*args, "explanation").agg(F.product(F.coalesce("pi", F.lit(1.0))).alias("score"))
    ranked = scored.withColumn("rank", F.row_number().over(Window.partitionBy(*args).orderBy(F.desc("score"), "explanation")).cast("long"))
    return (ranked if k is None else ranked.where(F.col("rank") <= k)).select(*args, "rank", "score", "explanation")


def verify(result: PlanResult, pred: str, most_facts: int = 16) -> DataFrame:
    """a0.., prob, exact, complete: whether the lineage of each fact has the probability that all worlds give it."""
    from .baselines import worlds

    got = probabilities(lineage(result, pred), base_probabilities(result.program)).drop("n_expl", "n_vars", "lower", "status", "nanos")
    exact = worlds(result.program, pred, most_facts).withColumnRenamed("prob", "exact")
    both = got.join(exact, arguments(got), "full_outer")
    return both.withColumn("complete", F.coalesce(F.abs(F.col("prob") - F.col("exact")) <= 1e-9, F.lit(False)))


def unfold(result: PlanResult, pred: str) -> DataFrame:
    """a0.., leaves: one row for each tree without folds that the trees of a fact stand for, with its base facts.

    As many rows as ``unfold_counts`` tells: for small results.
    """
    every = result.narrow().select("depth", "tid", "kids", "leaves")
    members = union(result.members) if result.members else None
    if result.member_trees:
        every = union([every, union(result.member_trees).select("depth", "tid", "kids", "leaves")])
    done: list[DataFrame] = []
    for d in range(1, max((d for own in result.depths.values() for d in own), default=1) + 1):
        here = every.where(F.col("depth") == d)
        own = here.where(F.size("kids") == 0).select("tid", "leaves")
        if members is not None:
            own = own.join(members.select("tid").distinct(), "tid", "left_anti")
        if done:
            most = here.agg(F.max(F.size("kids"))).first()[0] or 0
            rows = here.where(F.size("kids") > 0)
            for k in range(most):
                kid = union(done).select(F.col("tid").alias("kid"), F.col("leaves").alias("more"))
                rows = rows.withColumn("kid", F.get("kids", F.lit(k))).join(kid, "kid", "left").where(F.col("kid").isNull() | F.col("more").isNotNull())
                rows = rows.withColumn("leaves", F.concat("leaves", F.coalesce("more", F.array().cast("array<bigint>")))).drop("kid", "more")
            own = own.unionByName(rows.select("tid", "leaves"))
        if members is not None:
            own = own.unionByName(members.join(own.withColumnRenamed("tid", "member"), "member").select("tid", "leaves"))
        done.append(stored(own, "unfolded"))
    roots = result.of(pred)
    return roots.select(*arguments(roots), "tid").join(union(done), "tid").drop("tid")


def unfold_counts(result: PlanResult, pred: str) -> DataFrame:
    """a0.., unfoldings: how many trees without folds each fact's trees stand for."""
    every = result.narrow().select("depth", "tid", "kids")
    members = union(result.members) if result.members else None
    if result.member_trees:
        every = union([every, union(result.member_trees).select("depth", "tid", "kids")])
    done: list[DataFrame] = []
    for d in range(1, max((d for own in result.depths.values() for d in own), default=1) + 1):
        here = every.where(F.col("depth") == d)
        own = here.where(F.size("kids") == 0).select("tid", F.lit(1).cast("long").alias("n"))
        if members is not None:
            own = own.join(members.select("tid").distinct(), "tid", "left_anti")
        if done:
            kids = here.where(F.size("kids") > 0).select("tid", F.explode("kids").alias("kid"))
            own = own.unionByName(kids.join(union(done).select(F.col("tid").alias("kid"), "n"), "kid").groupBy("tid").agg(F.product("n").cast("long").alias("n")))
        if members is not None:
            own = own.unionByName(members.join(own.withColumnRenamed("tid", "member"), "member").groupBy("tid").agg(F.sum("n").alias("n")))
        done.append(stored(own, "unfolded"))
    roots = result.of(pred)
    args = arguments(roots)
    return roots.select(*args, "tid").join(union(done), "tid").groupBy(*args).agg(F.sum("n").alias("unfoldings"))
