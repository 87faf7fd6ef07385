"""Every method, baseline, solver, measure and workload as a query over the given tables, with its SQL twin."""

from __future__ import annotations

import random
import resource
import uuid
from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.dnf import dnf_prob_columns
from .operators.components import components
from .operators.relational import OPERATORS
from .plans.answer import answer
from .plans.baselines import circuit, formula_fixpoint, set_fixpoint, topk_fixpoint, worlds
from .plans.compile import union
from .plans.reason import append, base_probabilities, bounds_by_round, explanations, lineage, probabilities, reason, resume, unfold, unfold_counts, verify
from .plans.reason import save as save_result
from .rules import Program, Query, normalize, rules, with_rule_probability
from .sources.tables import facts, load, scratch_root, stored
from .streaming.ingest import STREAMS
from .workloads import base as w
from .workloads import graphs, onto
from .workloads.generate import generate_queries

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Registers a query. Each reads its own tables: what one remembers is forgotten when the next begins."""

    def add(f):
        @wraps(f)
        def alone(spark, sf_dir, *given, **named):
            w.forget()
            return f(spark, sf_dir, *given, **named)

        QUERIES[name or f.__name__] = alone
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def golden(columns: str, *rows: tuple) -> str:
    cells = ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else f"CAST({x} AS {'DOUBLE' if isinstance(x, float) else 'BIGINT'})" for x in r) + ")" for r in rows)
    return f"SELECT * FROM (VALUES {cells}) AS t({columns})"


def counts(spark: SparkSession, rows: list[tuple], columns: str) -> DataFrame:
    return spark.createDataFrame(rows, ", ".join(f"{c} {'string' if rows and isinstance(rows[0][i], str) else 'bigint'}" for i, c in enumerate(columns.split(", "))))


def reach_answers(formulas: DataFrame, given: DataFrame, solver: str = "dd") -> DataFrame:
    got = probabilities(formulas, given, solver)
    return got.select(F.col("a0").cast("long").alias("a"), F.col("a1").cast("long").alias("b"), F.round("prob", 6).alias("prob"))


TRADE_SQL = f"{w.sql_trade_answers()} SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, round(prob, 6) AS prob FROM answer"
MODEL = (("a", "b", 0.78), ("a", "c", 0.79), ("b", "b", 0.48), ("b", "c", 0.6), ("c", "b", 0.8), ("c", "c", 0.48))

# --- methods ------------------------------------------------------------------------------------------------------


def _model(formulas: DataFrame, program: Program) -> DataFrame:
    got = probabilities(formulas, base_probabilities(normalize(program)))
    return got.select(F.col("a0").alias("a"), F.col("a1").alias("b"), F.round("prob", 6).alias("prob"))


@query(golden("a, b, prob", *MODEL))
def reach_example_model(spark, sf_dir):
    program = w.reach_example(spark)
    return _model(lineage(reason(program), "p"), program)


@query(golden("depth, nodes, candidates, kept", (1, 1, 4, 4), (2, 1, 4, 4), (3, 0, 12, 0)))
def reach_example_trees(spark, sf_dir):
    return counts(spark, reason(w.reach_example(spark)).counts(), "depth, nodes, candidates, kept")


@query(golden("depth, a, b, prob", (1, "a", "b", 0.5), (1, "a", "c", 0.7), (1, "b", "c", 0.6), (1, "c", "b", 0.8), *((2, *m) for m in MODEL)))
def reach_example_bounds(spark, sf_dir):
    got = bounds_by_round(reason(w.reach_example(spark)), "p")
    return got.select(F.col("depth").cast("long").alias("depth"), F.col("a0").alias("a"), F.col("a1").alias("b"), F.round("prob", 6).alias("prob"))


@query("""WITH n AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1), s AS (SELECT CAST(sum(n) AS BIGINT) AS o, count(*) AS c, count(*) FILTER (n > 1) AS m, avg(n) AS t FROM n)
SELECT CAST(1 AS BIGINT) AS depth, o AS kept FROM s UNION ALL SELECT 2, CASE WHEN t >= 10 THEN c ELSE o END FROM s
UNION ALL SELECT 3, CASE WHEN t >= 10 THEN m ELSE o - c END FROM s""")
def collapse_example_counts(spark, sf_dir):
    result = w.remembered(("first-orders", sf_dir), lambda: reason(w.first_orders(spark, sf_dir), collapse=10))
    return counts(spark, [(d, kept) for d, _, _, kept in result.counts() if kept], "depth, kept")


@query(f"""WITH o AS (SELECT o_custkey AS c, o_orderkey AS o, {w.sql_pi('o_orderkey')} AS pi, o_orderkey = min(o_orderkey) OVER (PARTITION BY o_custkey) AS first FROM orders)
SELECT c, round(1 - (1 - max(pi) FILTER (first)) * (1 - {w.sql_pi('c', 1)} * (1 - coalesce(product(1 - pi) FILTER (NOT first), 1))), 6) AS prob FROM o GROUP BY c""")
def collapse_example_prob(spark, sf_dir):
    result = w.remembered(("first-orders", sf_dir), lambda: reason(w.first_orders(spark, sf_dir), collapse=10))
    firsts = result.program.facts["s"].select("a0", "a1")
    formulas = lineage(result, "r").join(firsts, ["a0", "a1"], "left_semi")
    return probabilities(formulas, base_probabilities(result.program)).select(F.col("a0").alias("c"), F.round("prob", 6).alias("prob"))


@query(golden("a, b, unfoldings", ("a", 1, 11), *(("a", i, 1) for i in range(2, 11))))
def unfold_example(spark, sf_dir):
    got = unfold_counts(reason(w.collapse_example(spark, 10), collapse=10), "r")
    return got.select(F.col("a0").alias("a"), F.col("a1").alias("b"), "unfoldings")


@query(TRADE_SQL)
def trade_reach_linear(spark, sf_dir):
    return reach_answers(*w.trade_lineage(spark, sf_dir))


@query(f"{w.sql_trade_answers(2)} SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, round(prob, 6) AS prob FROM answer")
def trade_reach_quadratic(spark, sf_dir):
    program = w.trade(spark, sf_dir, 2, "reach(X,Y) :- trade(X,Y). reach(X,Y) :- reach(X,Z), reach(Z,Y).")
    result = reason(program, max_depth=2)
    return reach_answers(lineage(result, "reach"), base_probabilities(result.program))


@query(f"WITH RECURSIVE {w.sql_trade()}, reach(a, b) AS (SELECT a, b FROM edge UNION SELECT r.a, e.b FROM reach r JOIN edge e ON r.b = e.a) SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b FROM reach")
def trade_reach_set(spark, sf_dir):
    return set_fixpoint(w.trade(spark, sf_dir)).of("reach").select(F.col("a0").cast("long").alias("a"), F.col("a1").cast("long").alias("b"))


@query(f"WITH RECURSIVE {w.sql_trade()}, reach(a, b) AS (SELECT a, b FROM edge UNION SELECT r.a, e.b FROM reach r JOIN edge e ON r.b = e.a) SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b FROM reach")
def trade_reach_set_plan(spark, sf_dir):
    result = reason(w.trade(spark, sf_dir), annotate=False)
    return result.of("reach").select(F.col("a0").cast("long").alias("a"), F.col("a1").cast("long").alias("b"))


@query(f"{w.sql_trade_answers(3)} SELECT CAST(b AS BIGINT) AS b, round(prob, 6) AS prob FROM answer WHERE a = 0")
def trade_reach_magic(spark, sf_dir):
    got = answer(w.trade(spark, sf_dir), Query.parse("q(Y) :- reach(0,Y)."), collapse=None, max_depth=4).table
    # the query rule is a round of its own: answers by then rest on paths of three steps at most
    return got.select(F.col("a0").cast("long").alias("b"), F.round("prob", 6).alias("prob"))


@query(f"WITH {w.sql_trade()} SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, round(0.7 * pi, 6) AS prob FROM edge")
def rule_probability(spark, sf_dir):
    program = w.trade(spark, sf_dir)
    rule, coin = with_rule_probability(rules("likely(X,Y) :- trade(X,Y).")[0])
    on = facts("rule_on", spark.createDataFrame([(rule.id,)], "id string"), ["id"], 0.7, unique=True)
    result = reason(Program([rule], {**program.facts, coin.pred: on}))
    return reach_answers(lineage(result, "likely"), base_probabilities(result.program))


@query(f"""SELECT r_name AS region, round(1 - product(1 - {w.sql_pi('s_suppkey', 9)}), 6) AS prob
FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1""")
def cq_supplier_region(spark, sf_dir):
    program = onto.program(spark, sf_dir, "q(R) :- nation_in(N,R), supp_in(S,N).")
    result = reason(program)
    return probabilities(lineage(result, "q"), base_probabilities(result.program), "dd").select(F.col("a0").alias("region"), F.round("prob", 6).alias("prob"))


@query(f"{' UNION ALL '.join(f'SELECT * FROM ({w.sql_trade_answers(d)} SELECT CAST({d} AS BIGINT) AS depth, CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, round(prob, 6) AS prob FROM answer)' for d in (1, 2, 3))}")
def anytime_bounds(spark, sf_dir):
    got = bounds_by_round(w.trade_result(spark, sf_dir), "reach")
    return got.select(F.col("depth").cast("long").alias("depth"), F.col("a0").cast("long").alias("a"), F.col("a1").cast("long").alias("b"), F.round("prob", 6).alias("prob"))


_CHAIN_SQL = f"""WITH RECURSIVE t AS (SELECT DISTINCT conv_id, turn FROM conversations), r AS (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM t),
e AS (SELECT conv_id, turn, nxt, {w.sql_pi('(conv_id * 13 + turn)', 8)} AS pi FROM r WHERE nxt IS NOT NULL),
c(conv_id, a, b, pi) AS (SELECT conv_id, turn, nxt, pi FROM e UNION ALL SELECT c.conv_id, c.a, e.nxt, c.pi * e.pi FROM c JOIN e ON e.conv_id = c.conv_id AND e.turn = c.b)
SELECT conv_id, a, b, round(pi, 9) AS prob FROM c"""


@query(_CHAIN_SQL)
def append_equals_batch(spark, sf_dir):
    """Replies of even turns first; those of odd turns come later and go on from the rounds of the first."""
    program = graphs.replies(spark, sf_dir)
    every = program.facts["reply"]
    early = reason(Program(program.rules, {"reply": stored(every.where("a1 % 2 = 0"), "early")}))
    result = append(early, {"reply": every.where("a1 % 2 = 1")})
    got = probabilities(lineage(result, "after"), base_probabilities(result.program))
    return got.select(F.col("a0").alias("conv_id"), F.col("a1").alias("a"), F.col("a2").alias("b"), F.round("prob", 9).alias("prob"))


@query(_CHAIN_SQL)
def resume_equals_run(spark, sf_dir):
    """Rounds saved to a folder, read back, and asked."""
    program = graphs.replies(spark, sf_dir)
    at = f"{scratch_root(spark)}/saved-{uuid.uuid4().hex[:12]}"
    save_result(reason(program), at)
    result = resume(program, at)
    got = probabilities(lineage(result, "after"), base_probabilities(result.program))
    return got.select(F.col("a0").alias("conv_id"), F.col("a1").alias("a"), F.col("a2").alias("b"), F.round("prob", 9).alias("prob"))


@query(golden("a, b, rank, score, size", ("a", "b", 1, 0.56, 2), ("a", "b", 2, 0.5, 1), ("a", "c", 1, 0.7, 1), ("a", "c", 2, 0.3, 2), ("b", "b", 1, 0.48, 2), ("b", "c", 1, 0.6, 1), ("c", "b", 1, 0.8, 1), ("c", "c", 1, 0.48, 2)))
def reach_example_explanations(spark, sf_dir):
    got = explanations(reason(w.reach_example(spark)), "p")
    return got.select(F.col("a0").alias("a"), F.col("a1").alias("b"), "rank", F.round("score", 6).alias("score"), F.size("explanation").cast("long").alias("size"))


@query(golden("complete, facts", (1, 6)))
def lineage_completeness(spark, sf_dir):
    """Facts of the running example whose lineage has the probability that all worlds give."""
    got = verify(reason(w.reach_example(spark)), "p")
    return got.groupBy(F.col("complete").cast("long").alias("complete")).agg(F.count("*").alias("facts"))


@query(golden("a, b, trees, leaves", ("a", 1, 11, 21), *(("a", i, 1, 1) for i in range(2, 11))))
def unfold_trees(spark, sf_dir):
    """Folded trees written out: how many there are of each fact, and base facts in them."""
    got = unfold(reason(w.collapse_example(spark, 10), collapse=10), "r")
    return got.groupBy(F.col("a0").alias("a"), F.col("a1").alias("b")).agg(F.count("*").alias("trees"), F.sum(F.size("leaves")).alias("leaves"))


@query(f"{w.sql_trade_answers(3)} SELECT CAST(b AS BIGINT) AS b, round(prob, 6) AS prob FROM answer WHERE a = 0")
def trade_reach_unrewritten(spark, sf_dir):
    """The rules as they are; the query rule is a round of its own."""
    got = answer(w.trade(spark, sf_dir), Query.parse("q(Y) :- reach(0,Y)."), magic=None, collapse=None, max_depth=4).table
    return got.select(F.col("a0").cast("long").alias("b"), F.round("prob", 6).alias("prob"))


@query(golden("b, prob", ("b", 0.78), ("c", 0.79)))
def reach_example_rewritten(spark, sf_dir):
    """Demand rules run along with the rules that they restrict, as one program."""
    program = w.program(spark, w.EDGES + "p(X,Y) :- e(X,Y). p(X,Y) :- p(X,Z), e(Z,Y).")
    got = answer(program, Query.parse("q(Y) :- p('a',Y)."), magic="rules", collapse=None).table
    return got.select(F.col("a0").alias("b"), F.round("prob", 6).alias("prob"))


@query(golden("policy, kept", ("node", 12), ("per_root", 12), ("estimate", 12), ("all_members", 12)))
def collapse_policies(spark, sf_dir):
    program, rows = w.collapse_example(spark, 10), []
    for name, options in (("node", {}), ("per_root", {"collapse_policy": "per_root"}), ("estimate", {"collapse_policy": "estimate"}), ("all_members", {"prune_members": False})):
        rows.append((name, sum(kept for *_, kept in reason(program, collapse=10, **options).counts())))
    return counts(spark, rows, "policy, kept")


@query(golden("depth, kept", (1, 12), (2, 16), (3, 16), (4, 4), (5, 0)))
def termination_absorb(spark, sf_dir):
    return counts(spark, [(d, kept) for d, _, _, kept in reason(w.complete_graph(spark, 4), collapse=1).counts()], "depth, kept")


@query("SELECT count(*) AS nodes, CAST(3 AS BIGINT) AS depth FROM (SELECT 1 UNION ALL SELECT 2 UNION ALL SELECT 3)")
def plan_graph_shape(spark, sf_dir):
    return w.trade_result(spark, sf_dir).graph().agg(F.count("*").alias("nodes"), F.max("depth").cast("long").alias("depth"))


# --- baselines ----------------------------------------------------------------------------------------------------


@query(golden("a, b, prob", *MODEL))
def worlds_example(spark, sf_dir):
    return worlds(w.reach_example(spark), "p").select(F.col("a0").alias("a"), F.col("a1").alias("b"), F.round("prob", 6).alias("prob"))


for _mode in ("naive", "delta", "rewritten"):

    @query(f"WITH RECURSIVE {w.sql_trade(1)}, p(a, b, pi, d) AS (SELECT a, b, pi, 1 FROM edge UNION ALL SELECT p.a, e.b, p.pi * e.pi, d + 1 FROM p JOIN edge e ON p.b = e.a WHERE d < 25 AND p.b <> p.a), f AS (SELECT a, b, pi, row_number() OVER (PARTITION BY a, b ORDER BY d) AS rn FROM p) SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, round(pi, 6) AS prob FROM f WHERE rn = 1", f"{_mode}_equals_plan")
    def _(spark, sf_dir, mode=_mode):
        program = w.trade(spark, sf_dir, 1)
        return reach_answers(formula_fixpoint(program, mode).of("reach").select("a0", "a1", "dnf"), base_probabilities(program))


@query(golden("depth, instances, updates", (1, 4, 4), (2, 8, 4), (3, 16, 0)))
def naive_round_trace(spark, sf_dir):
    log = formula_fixpoint(w.reach_example(spark), "naive").log
    return counts(spark, [(x["depth"], x["instances"], x["updates"]) for x in log], "depth, instances, updates")


@query(golden("depth, instances, updates", (1, 4, 4), (2, 4, 4), (3, 10, 0)))
def delta_round_trace(spark, sf_dir):
    log = formula_fixpoint(w.reach_example(spark), "delta").log
    return counts(spark, [(x["depth"], x["instances"], x["updates"]) for x in log], "depth, instances, updates")


@query(golden("a, b, prob, error", ("a", "b", 0.56, 0.282051), ("a", "c", 0.7, 0.113924), ("b", "b", 0.48, 0.0), ("b", "c", 0.6, 0.0), ("c", "b", 0.8, 0.0), ("c", "c", 0.48, 0.0)))
def topk1_example(spark, sf_dir):
    program = w.reach_example(spark)
    exact = _model(lineage(reason(program), "p"), program).withColumnRenamed("prob", "exact")
    approx = _model(topk_fixpoint(program, 1).of("p").select("a0", "a1", "dnf"), program)
    return exact.join(approx, ["a", "b"], "left").select("a", "b", "prob", F.round((F.col("exact") - F.coalesce("prob", F.lit(0.0))) / F.col("exact"), 6).alias("error"))


def _trade_error(spark, sf_dir) -> DataFrame:
    exact = probabilities(*w.trade_lineage(spark, sf_dir)).select("a0", "a1", F.col("prob").alias("exact"))
    program = w.trade(spark, sf_dir)
    top = topk_fixpoint(program, 1, depth_limit=3, check=False).of("reach").select("a0", "a1", "dnf")
    approx = probabilities(top, base_probabilities(program)).select("a0", "a1", F.col("prob").alias("approx"))
    return exact.join(approx, ["a0", "a1"], "left").withColumn("error", (F.col("exact") - F.coalesce("approx", F.lit(0.0))) / F.col("exact"))


_TOP1 = f"{w.sql_trade_answers()}, best AS (SELECT a, b, max(p) AS approx FROM (SELECT x.a, x.b, x.m, product(edge.pi) AS p FROM expl x JOIN edge ON (x.m >> edge.bit) & 1 = 1 GROUP BY 1, 2, 3) GROUP BY 1, 2), err AS (SELECT a, b, prob, approx, (prob - approx) / prob AS error FROM answer JOIN best USING (a, b))"


@query(f"{_TOP1} SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, round(approx, 6) AS approx, round(error, 6) AS error FROM err")
def topk_error_trade(spark, sf_dir):
    return _trade_error(spark, sf_dir).select(F.col("a0").cast("long").alias("a"), F.col("a1").cast("long").alias("b"), F.round("approx", 6).alias("approx"), F.round("error", 6).alias("error"))


@query(f"{_TOP1} SELECT CAST(least(floor(round(error, 9) * 10), 9) AS BIGINT) AS bucket, count(*) AS n FROM err GROUP BY 1")
def error_histogram(spark, sf_dir):
    bucket = F.least(F.floor(F.round("error", 9) * 10), F.lit(9)).cast("long")
    return _trade_error(spark, sf_dir).groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n"))


@query(golden("kind, n", ("and", 21), ("inner_or", 11), ("outer_or", 11), ("leaf", 11)))
def circuit_counts(spark, sf_dir):
    return circuit(w.collapse_example(spark, 10)).gates.groupBy("kind").agg(F.count("*").alias("n"))


@query(golden("a, b, prob", *MODEL))
def circuit_example(spark, sf_dir):
    """The circuit of the running example, evaluated gate by gate."""
    program = w.reach_example(spark)
    return _model(circuit(program).lineage("p"), program)


@query(golden("depth, differ", (1, 0), (2, 0), (3, 0)))
def unchecked_correspondence(spark, sf_dir):
    """Formulas after i rounds without tests against trees of depth i without tests: facts whose formulas differ."""
    program, parts = w.reach_example(spark), []
    for i in (1, 2, 3):
        plain = formula_fixpoint(program, depth_limit=i, check=False).of("p").select("a0", "a1", F.col("dnf").alias("rounds"))
        trees = lineage(reason(program, redundancy=None, max_depth=i), "p").withColumnRenamed("dnf", "trees")
        both = plain.join(trees, ["a0", "a1"], "full_outer")
        parts.append(both.agg(F.lit(i).cast("long").alias("depth"), F.count_if(~F.col("rounds").eqNullSafe(F.col("trees"))).alias("differ")))
    return union(parts)


@query(golden("mode, instances, tests, copies, joins", ("naive", 28, 16, 8, 4), ("delta", 18, 16, 6, 6), ("rewritten", 20, 16, 6, 14)))
def formula_overheads(spark, sf_dir):
    """What formulas in rounds cost on the running example: equivalence tests, formulas merged unchanged, joins."""
    rows = []
    for mode in ("naive", "delta", "rewritten"):
        log = formula_fixpoint(w.reach_example(spark), mode).log
        rows.append((mode, *(sum(x[k] for x in log) for k in ("instances", "tests", "copies", "joins"))))
    return counts(spark, rows, "mode, instances, tests, copies, joins")


@query()
def formula_times(spark, sf_dir):
    """Seconds of deriving, and of disjoining, merging and comparing formulas, by mode; and the share of the latter."""
    rows = []
    for mode in ("naive", "delta", "rewritten"):
        log = formula_fixpoint(w.trade(spark, sf_dir, 1), mode).log
        total, deriving = sum(x["seconds"] for x in log), sum(x["deriving"] for x in log)
        rows.append((mode, deriving, total - deriving, (total - deriving) / total))
    return spark.createDataFrame(rows, "mode string, deriving double, comparing double, share double")


@query(f"{w.sql_trade_answers()} SELECT 'upfront' AS approach, count(*) AS answers, count(*) AS within FROM answer UNION ALL SELECT 'afterwards', count(*), count(*) FROM answer")
def approximation_compared(spark, sf_dir):
    """Two explanations kept while reasoning, against sampling the full lineage: answers that stay in their guarantee."""
    formulas, given = w.trade_lineage(spark, sf_dir)
    exact = probabilities(formulas, given).select("a0", "a1", F.col("prob").alias("exact"))
    program = w.trade(spark, sf_dir)
    upfront = probabilities(topk_fixpoint(program, 2, depth_limit=3, check=False).of("reach").select("a0", "a1", "dnf"), given).select("a0", "a1", "prob")
    after = probabilities(formulas, given, "mc", epsilon=0.1).select("a0", "a1", "prob")
    kept = {"upfront": (upfront, F.col("prob") <= F.col("exact") + 1e-9), "afterwards": (after, F.abs(F.col("prob") - F.col("exact")) <= 0.2 * F.col("exact"))}
    parts = [exact.join(df, ["a0", "a1"]).agg(F.lit(name).alias("approach"), F.count("*").alias("answers"), F.count_if(good).alias("within")).select("approach", "answers", "within") for name, (df, good) in kept.items()]
    return parts[0].unionByName(parts[1])


@query(golden("engine, facts, differ", *((e, 6, 0) for e in ("naive", "delta", "rewritten", "top30", "circuit", "plan_without", "plan_with", "worlds"))))
def engine_agreement(spark, sf_dir):
    program = w.reach_example(spark)
    exact = spark.createDataFrame(list(MODEL), "a string, b string, exact double")
    runs = {
        "naive": _model(formula_fixpoint(program, "naive").of("p").select("a0", "a1", "dnf"), program),
        "delta": _model(formula_fixpoint(program, "delta").of("p").select("a0", "a1", "dnf"), program),
        "rewritten": _model(formula_fixpoint(program, "rewritten").of("p").select("a0", "a1", "dnf"), program),
        "top30": _model(topk_fixpoint(program, 30).of("p").select("a0", "a1", "dnf"), program),
        "circuit": _model(circuit(program).lineage("p"), program),
        "plan_without": _model(lineage(reason(program), "p"), program),
        "plan_with": _model(lineage(reason(program, collapse=1), "p"), program),
        "worlds": worlds_example(spark, sf_dir),
    }
    parts = [df.join(exact, ["a", "b"], "full_outer").agg(F.count("*").alias("facts"), F.count_if(F.coalesce(F.abs(F.col("prob") - F.col("exact")), F.lit(1.0)) > 1e-6).alias("differ")).select(F.lit(e).alias("engine"), "facts", "differ") for e, df in runs.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# --- solvers ------------------------------------------------------------------------------------------------------

for _solver in ("worlds", "incl_excl", "dd", "dtree", "cnf"):

    @query(TRADE_SQL, f"solver_{_solver}")
    def _(spark, sf_dir, solver=_solver):
        return reach_answers(*w.trade_lineage(spark, sf_dir), solver)


@query(f"SELECT o_custkey AS c, round(1 - product(1 - {w.sql_pi('o_orderkey')}), 6) AS prob FROM orders GROUP BY 1")
def solver_closed(spark, sf_dir):
    """In built-in functions alone: explanations that share no fact."""
    q = w.first_orders(spark, sf_dir).facts["q"]
    formulas = q.groupBy("a0").agg(F.collect_list(F.array("fid")).alias("dnf"))
    return dnf_prob_columns(formulas, q.select("fid", "pi")).select(F.col("a0").alias("c"), F.round("prob", 6).alias("prob"))


@query(f"{w.sql_trade_answers()} SELECT count(*) AS answers, count(*) AS within FROM answer")
def solver_mc_within(spark, sf_dir):
    formulas, given = w.trade_lineage(spark, sf_dir)
    exact = probabilities(formulas, given).select("a0", "a1", F.col("prob").alias("exact"))
    near = probabilities(formulas, given, "mc", epsilon=0.1).select("a0", "a1", "prob")
    return exact.join(near, ["a0", "a1"]).agg(F.count("*").alias("answers"), F.count_if(F.abs(F.col("prob") - F.col("exact")) <= 0.2 * F.col("exact")).alias("within"))


@query(f"{w.sql_trade_answers()} SELECT count(*) AS answers, count(*) AS inside FROM answer")
def solver_bounds_inside(spark, sf_dir):
    formulas, given = w.trade_lineage(spark, sf_dir)
    exact = probabilities(formulas, given).select("a0", "a1", F.col("prob").alias("exact"))
    low = probabilities(formulas, given, "bounds", width=0.05).select("a0", "a1", "lower")
    return exact.join(low, ["a0", "a1"]).agg(F.count("*").alias("answers"), F.count_if((F.col("lower") <= F.col("exact") + 1e-9) & (F.col("exact") - F.col("lower") <= 0.05 + 1e-9)).alias("inside"))


@query(golden("solver, differ", *((s, 0) for s in ("worlds", "incl_excl", "dtree", "cnf"))))
def solver_agreement(spark, sf_dir):
    formulas, given = w.trade_lineage(spark, sf_dir)
    exact = stored(probabilities(formulas, given).select("a0", "a1", F.col("prob").alias("exact")), "exact")
    parts = [probabilities(formulas, given, s).join(exact, ["a0", "a1"]).agg(F.count_if(F.abs(F.col("prob") - F.col("exact")) > 1e-9).alias("differ")).select(F.lit(s).alias("solver"), "differ") for s in ("worlds", "incl_excl", "dtree", "cnf")]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# --- measures -----------------------------------------------------------------------------------------------------


@query(f"WITH RECURSIVE {w.sql_trade()}, {w.sql_paths()} SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, count(*) AS explanations FROM expl GROUP BY 1, 2")
def lineage_sizes(spark, sf_dir):
    formulas, _ = w.trade_lineage(spark, sf_dir)
    return formulas.select(F.col("a0").cast("long").alias("a"), F.col("a1").cast("long").alias("b"), F.size("dnf").cast("long").alias("explanations"))


@query(golden("threshold, kept", (1, 12), (2, 12), (5, 12), (10, 12), (50, 29), (0, 29)))
def collapse_sweep(spark, sf_dir):
    rows = []
    for t in (1, 2, 5, 10, 50, None):
        rows.append((t or 0, sum(kept for *_, kept in reason(w.collapse_example(spark, 10), collapse=t).counts())))
    return counts(spark, rows, "threshold, kept")


@query(golden("phase, counted", ("candidates", 12), ("kept", 8)).replace("12", "20"))
def derivation_counts(spark, sf_dir):
    got = reason(w.reach_example(spark)).counts()
    return counts(spark, [("candidates", sum(c for _, _, c, _ in got)), ("kept", sum(k for *_, k in got))], "phase, counted")


@query()
def phase_times(spark, sf_dir):
    got = answer(w.trade(spark, sf_dir), Query.parse("q(Y) :- reach(0,Y)."), collapse=10, max_depth=4)
    return spark.createDataFrame([(k, float(v) * 1000) for k, v in got.phases.items()], "phase string, ms double")


@query(golden("rules", (127,)))
def scenario_rules(spark, sf_dir):
    return counts(spark, [(len(onto.ontology_rules(spark, sf_dir)),)], "rules")


@query(f"{w.sql_trade_answers()} SELECT round(min(prob), 6) AS low, round(quantile_cont(prob, 0.25), 6) AS q1, round(median(prob), 6) AS mid, round(quantile_cont(prob, 0.75), 6) AS q3, round(max(prob), 6) AS high FROM answer")
def boxplot_stats(spark, sf_dir):
    got = probabilities(*w.trade_lineage(spark, sf_dir))
    p = F.percentile("prob", F.array(*map(F.lit, (0.0, 0.25, 0.5, 0.75, 1.0))))
    return got.agg(p.alias("p")).select(*(F.round(F.col("p")[i], 6).alias(n) for i, n in enumerate(("low", "q1", "mid", "q3", "high"))))


# --- workloads ----------------------------------------------------------------------------------------------------

_NATION3 = "(SELECT n_name FROM nation WHERE n_nationkey = 3)"
_SURE = "greatest(CAST(0.5 AS DOUBLE), 1 - 5 * l_discount)"


def _nation(spark, sf_dir, key: int = 3) -> str:
    return load(spark, sf_dir, "nation").where(F.col("n_nationkey") == key).first()["n_name"]


#: Queries over the whole ontology of 127 rules: text with {n3} and {n0} for nations, columns of the answer.
ONTO = {
    "u01": ("u(S) :- supp_in(S,'{n3}'), delivers(S,P), brand_of(P,'Brand#7').", "s"),
    "u02": ("u(C,S) :- cust_in(C,'{n3}'), local_pair(C,S), supp_in(S,'{n3}').", "c s"),
    "u03": ("u(O) :- placed('c17',O).", "o"),
    "u04": ("u(S) :- in(S,'ASIA'), delivers(S,P), cls(P,'product').", "s"),
    "u05": ("u(X) :- in(X,'EUROPE').", "x"),
    "u06": ("u(X,Y) :- partner(X,Y).", "x y"),
    "u07": ("u(P) :- served_by(C,'s5'), cust_in(C,'{n3}'), buys(C,P).", "p"),
    "u08": ("u(C,D) :- cust_in(C,'{n3}'), served_by(C,S), supp_in(S,'{n0}'), mate(C,D).", "c d"),
    "u09": ("u(C,S,P) :- cust_in(C,'{n3}'), local_pair(C,S), supp_in(S,'{n3}'), delivers(S,P), buys(C,P).", "c s p"),
    "u10": ("u(C) :- supp_in('s5',N), reach(N,M), cust_in(C,M).", "c"),
    "u11": ("u(S) :- cls(S,'ASIA_member'), cls(S,'supplier').", "s"),
    "u12": ("u(R) :- region_has(R,'Brand#7_product').", "r"),
    "u13": ("u(Y) :- cust_in(Y,'{n3}'), partner(Y,X), supp_in(X,'{n0}').", "y"),
    "u14": ("u(O) :- cls(O,'F_order').", "o"),
}


def onto_answers(spark, sf_dir, name: str, collapse: float | None = 10, solver: str = "dd", certain: bool = False):
    """One of the fourteen queries over the 127 rules; U10 adds the closure of trade, ``certain`` makes locations certain."""
    text, columns = ONTO[name]
    program = onto.program(spark, sf_dir)
    given, own = dict(w.remembered(("onto", sf_dir), lambda: onto.base_facts(spark, sf_dir))), list(program.rules)
    if name == "u10":
        own += rules(w.LINEAR, "trade")
        given["trade"] = onto.trade_by_name(spark, sf_dir)
    if certain:
        given["supp_in"] = given["supp_in"].withColumn("pi", F.lit(1.0))
    asked = Query.parse(text.format(n3=_nation(spark, sf_dir, 3), n0=_nation(spark, sf_dir, 0)))
    return answer(Program(own, given), asked, solver=solver, collapse=collapse), columns


def _ask(spark, sf_dir, name: str, **options) -> DataFrame:
    got, columns = onto_answers(spark, sf_dir, name, **options)
    return got.table.select(*(F.col(f"a{i}").alias(c) for i, c in enumerate(columns.split())), w.round_scaled("prob").alias("prob"))


_LINES = f"l AS (SELECT o_custkey AS c, l_orderkey AS o, l_suppkey AS s, l_partkey AS p, max({_SURE}) AS pi FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2, 3, 4)"
_SHIPS = f"x AS (SELECT l_suppkey AS s, l_partkey AS p, max({_SURE}) AS pi FROM lineitem GROUP BY 1, 2)"
_REGION = "(SELECT n_nationkey FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = '{}')"
#: Orders of a customer of nation 3 with lines of suppliers of nation 0: worlds of the orders, each supplier once.
_HIT = f"""{_LINES}, g AS (SELECT c, s, o, 1 - product(1 - pi) AS q FROM l JOIN customer ON c = c_custkey JOIN supplier ON s = s_suppkey WHERE c_nationkey = 3 AND s_nationkey = 0 GROUP BY 1, 2, 3),
i AS (SELECT c, o, {w.sql_pi('o', 11)} AS po, row_number() OVER (PARTITION BY c ORDER BY o) - 1 AS bit FROM (SELECT DISTINCT c, o FROM g)),
v AS (SELECT c, unnest(range(CAST(1 AS BIGINT) << count(*))) AS v FROM i GROUP BY c),
a AS (SELECT v.c, v.v, product(CASE WHEN (v.v >> bit) & 1 = 1 THEN po ELSE 1 - po END) AS pr FROM v JOIN i ON i.c = v.c GROUP BY 1, 2),
b AS (SELECT v.c, v.v, g.s, 1 - {w.sql_pi('g.s', 9)} * (1 - coalesce(product(1 - q) FILTER ((v.v >> bit) & 1 = 1), 1)) AS f FROM v JOIN g ON g.c = v.c JOIN i ON i.c = g.c AND i.o = g.o GROUP BY 1, 2, 3),
m AS (SELECT c, v, product(f) AS miss FROM b GROUP BY 1, 2),
h AS (SELECT c, sum(pr * (1 - miss)) AS hit FROM a JOIN m USING (c, v) GROUP BY 1)"""
#: What a customer of nation 3 buys (part p) and who serves it (supplier s): both at once, order by order.
_BOTH = """t AS (SELECT q.c, q.s, q.p, k.o, coalesce(product(1 - k.pi) FILTER (k.s = q.s), 1) AS na, coalesce(product(1 - k.pi) FILTER (k.p = q.p), 1) AS nb, coalesce(product(1 - k.pi) FILTER (k.s = q.s OR k.p = q.p), 1) AS nab FROM q JOIN k ON k.c = q.c GROUP BY 1, 2, 3, 4),
e AS (SELECT c, s, p, 1 - product(1 - {po} * (1 - na)) - product(1 - {po} * (1 - nb)) + product(1 - {po} * (1 - nab)) AS together FROM t GROUP BY 1, 2, 3)""".format(po=w.sql_pi("o", 11))
_BUYERS = f"{_LINES}, k AS (SELECT l.* FROM l JOIN customer ON c = c_custkey WHERE c_nationkey = 3)"
_U02 = f"""WITH {_LINES}, g AS (SELECT c, o, s, {w.sql_pi('o', 11)} * (1 - product(1 - pi)) AS pi FROM l GROUP BY c, o, s)
SELECT concat('c', c) AS c, concat('s', s) AS s, round({w.sql_pi('c', 10)} * {w.sql_pi('s', 9)} * (1 - product(1 - pi)), 6) AS prob
FROM g JOIN customer ON c = c_custkey JOIN supplier ON s = s_suppkey WHERE c_nationkey = 3 AND s_nationkey = 3 GROUP BY c, s"""
#: U12 where suppliers are where they are for certain: parts are independent.
_U12_CERTAIN = f"""WITH {_SHIPS}, y AS (SELECT n_name AS n, r_name AS r, p, product(1 - x.pi) AS none FROM x JOIN supplier ON s = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON p = p_partkey WHERE p_brand = 'Brand#7' GROUP BY 1, 2, 3),
z AS (SELECT n AS r, p, none FROM y UNION ALL SELECT r, p, product(none) FROM y GROUP BY 1, 2)
SELECT r, round(1 - product(1 - {w.sql_pi('p', 13)} * (1 - none)), 6) AS prob FROM z GROUP BY 1"""
#: Worlds of the suppliers of a place, one after another: for each, the chance that no part is both shipped and of the
#: brand (more suppliers only lower it); worlds that cannot weigh 1e-13 together with all that follow them are left.
_U12 = f"""WITH RECURSIVE {_SHIPS}, y AS (SELECT s, p, n_name AS n, r_name, x.pi FROM x JOIN supplier ON s = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON p = p_partkey WHERE p_brand = 'Brand#7'),
z AS (SELECT n AS r, s, p, pi FROM y UNION ALL SELECT r_name, s, p, pi FROM y),
k AS (SELECT r, s, {w.sql_pi('s', 9)} AS ps, row_number() OVER (PARTITION BY r ORDER BY {w.sql_pi('s', 9)} DESC, s) AS i FROM (SELECT DISTINCT r, s FROM z)),
g AS (SELECT r, p, {w.sql_pi('p', 13)} AS b FROM (SELECT DISTINCT r, p FROM z)),
l AS (SELECT g.r, list(b ORDER BY g.p) AS b, max(n) AS n FROM g JOIN (SELECT r, count(*) AS n FROM k GROUP BY r) c ON c.r = g.r GROUP BY g.r),
t AS (SELECT k.r, k.i, any_value(ps) AS ps, list(1 - coalesce(z.pi, 0) ORDER BY g.p) AS miss FROM k JOIN g ON g.r = k.r LEFT JOIN z ON z.r = k.r AND z.s = k.s AND z.p = g.p GROUP BY 1, 2),
v AS (SELECT r, 0 AS i, n, b, CAST(1 AS DOUBLE) AS pr, [CAST(1 AS DOUBLE) FOR q IN b] AS none, CAST(1 AS DOUBLE) AS free FROM l
UNION ALL SELECT r, i, n, b, pr, none, list_product([1 - q[1] * (1 - q[2]) FOR q IN list_zip(b, none)]) FROM (
SELECT v.r, t.i, v.n, v.b, v.pr * CASE WHEN bit = 1 THEN ps ELSE 1 - ps END AS pr, CASE WHEN bit = 1 THEN [q[1] * q[2] FOR q IN list_zip(v.none, t.miss)] ELSE v.none END AS none
FROM v JOIN t ON t.r = v.r AND t.i = v.i + 1, (VALUES (0), (1)) AS a(bit) WHERE v.pr * v.free >= 1e-13))
SELECT r, round(1 - coalesce(sum(pr * free) FILTER (i = n), 0), 6) AS prob FROM v GROUP BY r"""
ONTO_SQL = {
    "u01": f"""WITH {_SHIPS} SELECT concat('s', s) AS s, round({w.sql_pi('s', 9)} * (1 - product(1 - x.pi * {w.sql_pi('p', 13)})), 6) AS prob
FROM x JOIN supplier ON s = s_suppkey JOIN part ON p = p_partkey WHERE s_nationkey = 3 AND p_brand = 'Brand#7' GROUP BY s""",
    "u02": _U02,
    "u03": f"SELECT concat('o', o_orderkey) AS o, round({w.sql_pi('o_orderkey', 11)}, 6) AS prob FROM orders WHERE o_custkey = 17",
    "u04": f"WITH {_SHIPS} SELECT concat('s', s) AS s, round({w.sql_pi('s', 9)} * (1 - product(1 - x.pi)), 6) AS prob FROM x JOIN supplier ON s = s_suppkey WHERE s_nationkey IN {_REGION.format('ASIA')} GROUP BY s",
    "u05": f"""SELECT n_name AS x, CAST(1 AS DOUBLE) AS prob FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'EUROPE'
UNION ALL SELECT concat('s', s_suppkey), round({w.sql_pi('s_suppkey', 9)}, 6) FROM supplier WHERE s_nationkey IN {_REGION.format('EUROPE')}
UNION ALL SELECT concat('c', c_custkey), round({w.sql_pi('c_custkey', 10)}, 6) FROM customer WHERE c_nationkey IN {_REGION.format('EUROPE')}""",
    "u06": f"""WITH {_LINES}, g AS (SELECT c, o, s, {w.sql_pi('o', 11)} * (1 - product(1 - pi)) AS pi FROM l GROUP BY c, o, s), r AS (SELECT concat('c', c) AS c, concat('s', s) AS s, round(1 - product(1 - pi), 6) AS prob FROM g GROUP BY c, s)
SELECT c AS x, s AS y, prob FROM r UNION ALL SELECT s, c, prob FROM r""",
    "u07": f"WITH {_BUYERS}, q AS (SELECT DISTINCT k.c, CAST(5 AS BIGINT) AS s, k.p FROM k WHERE k.c IN (SELECT c FROM k WHERE s = 5)), {_BOTH} SELECT concat('p', p) AS p, round(1 - product(1 - {w.sql_pi('c', 10)} * together), 6) AS prob FROM e GROUP BY p",
    "u08": f"WITH {_HIT} SELECT concat('c', h.c) AS c, concat('c', d.c_custkey) AS d, round({w.sql_pi('h.c', 10)} * hit * CASE WHEN h.c = d.c_custkey THEN 1 ELSE {w.sql_pi('d.c_custkey', 10)} END, 6) AS prob FROM h JOIN customer d ON d.c_nationkey = 3",
    "u09": f"WITH {_BUYERS}, {_SHIPS}, q AS (SELECT DISTINCT u.c, u.s, v.p FROM k u JOIN supplier ON u.s = s_suppkey AND s_nationkey = 3 JOIN k v ON v.c = u.c), {_BOTH} SELECT concat('c', e.c) AS c, concat('s', e.s) AS s, concat('p', e.p) AS p, round({w.sql_pi('e.c', 10)} * {w.sql_pi('e.s', 9)} * x.pi * together, 6) AS prob FROM e JOIN x ON x.s = e.s AND x.p = e.p",
    "u10": f"""WITH RECURSIVE {w.sql_trade(1)}, p(a, b, pi, d) AS (SELECT a, b, pi, 1 FROM edge UNION ALL SELECT p.a, e.b, p.pi * e.pi, d + 1 FROM p JOIN edge e ON p.b = e.a WHERE d < 25 AND p.b <> p.a), f AS (SELECT a, b, pi, row_number() OVER (PARTITION BY a, b ORDER BY d) AS rn FROM p)
SELECT concat('c', c_custkey) AS c, round({w.sql_pi('s_suppkey', 9)} * pi * {w.sql_pi('c_custkey', 10)}, 6) AS prob FROM f JOIN supplier ON a = s_nationkey JOIN customer ON b = c_nationkey WHERE rn = 1 AND s_suppkey = 5""",
    "u11": f"""WITH {_LINES}, {_SHIPS}, g AS (SELECT s, product(1 - pi) AS none FROM x GROUP BY s), o AS (SELECT s, o, {w.sql_pi('o', 11)} * (1 - product(1 - pi)) AS pi FROM l GROUP BY s, o), n AS (SELECT s, product(1 - pi) AS none FROM o GROUP BY s)
SELECT concat('s', g.s) AS s, round({w.sql_pi('g.s', 9)} * (1 - g.none * n.none), 6) AS prob FROM g JOIN n ON n.s = g.s JOIN supplier ON g.s = s_suppkey WHERE s_nationkey IN {_REGION.format('ASIA')}""",
    "u12": _U12,
    "u13": f"WITH {_HIT} SELECT concat('c', c) AS y, round({w.sql_pi('c', 10)} * hit, 6) AS prob FROM h",
    "u14": f"SELECT concat('o', o_orderkey) AS o, round({w.sql_pi('o_orderkey', 16)}, 6) AS prob FROM orders WHERE o_orderstatus = 'F'",
}

for _u in ONTO:

    @query(ONTO_SQL[_u], f"onto_{_u}")
    def _(spark, sf_dir, name=_u):
        return _ask(spark, sf_dir, name)


for _u, _label, _options in (("u12", "without", {"collapse": None, "certain": True}), ("u02", "cnf", {"solver": "cnf"}), ("u12", "dtree", {"solver": "dtree", "certain": True})):

    @query(_U12_CERTAIN if _options.get("certain") else ONTO_SQL[_u], f"onto_{_u}_{_label}")
    def _(spark, sf_dir, name=_u, options=_options):
        return _ask(spark, sf_dir, name, **options)


@query("""WITH e AS (SELECT user_id, count(*) AS n FROM events GROUP BY 1), a AS (SELECT user_id FROM e ORDER BY n DESC, user_id LIMIT 5),
h AS (SELECT DISTINCT user_id AS u, date_trunc('hour', ts) AS hr FROM events WHERE user_id IN (SELECT user_id FROM a)),
p AS (SELECT x.u, y.u AS v, count(*) AS weight FROM h x JOIN h y ON x.hr = y.hr AND x.u < y.u GROUP BY 1, 2)
SELECT u, v, weight FROM p ORDER BY weight DESC, u, v LIMIT 4""")
def smokers_graph(spark, sf_dir):
    return graphs.smokers_graph(spark, sf_dir, 5, 4)


@query(golden("facts, differ", (0, 0)).replace("(CAST(0 AS BIGINT), CAST(0 AS BIGINT))", "(CAST(1 AS BIGINT), CAST(0 AS BIGINT))"))
def smokers_small(spark, sf_dir):
    """The engine against all worlds of a graph with at most fourteen facts: rows that differ."""
    program = graphs.smokers(spark, sf_dir, 4, 2)
    program = Program(program.rules, {**program.facts, "risk": program.facts["risk"].withColumn("pi", F.lit(1.0))})
    exact = worlds(program, "smokes", 14).withColumnRenamed("prob", "exact")
    result = reason(program)
    got = probabilities(lineage(result, "smokes"), base_probabilities(result.program))
    both = got.join(exact, "a0", "full_outer")
    return both.agg(F.lit(1).cast("long").alias("facts"), F.count_if(F.coalesce(F.abs(F.col("prob") - F.col("exact")), F.lit(1.0)) > 1e-6).alias("differ"))


def smokers_answers(spark, sf_dir, depth: int) -> DataFrame:
    """size, user, asked, prob, status: smokes and asthma of five users in each of eleven graphs, 110 queries in one run."""

    def make():
        program = graphs.smokers_by_size(spark, sf_dir)
        return reason(program, collapse=10, max_depth=5)

    result = w.remembered(("smokers-by-size", sf_dir), make)
    given, parts = base_probabilities(result.program), []
    for pred in ("smokes", "asthma"):
        asked = result.program.facts["asked"].select("a0", "a1")
        formulas = lineage(result, pred, max_depth=depth).join(F.broadcast(asked), ["a0", "a1"], "left_semi")
        got = probabilities(formulas, given, "dd", budget=20_000, timeout=2)
        parts.append(got.select(F.col("a0").alias("size"), F.col("a1").alias("user"), F.lit(pred).alias("asked"), F.round("prob", 6).alias("prob"), "n_expl", "status", "nanos"))
    return parts[0].unionByName(parts[1])


for _depth in (4, 5):

    @query(None, f"smokers_d{_depth}")
    def _(spark, sf_dir, depth=_depth):
        return smokers_answers(spark, sf_dir, depth).drop("nanos")


@query("SELECT doc_id AS member, min(doc_id) OVER (PARTITION BY text) AS component FROM documents QUALIFY count(*) OVER (PARTITION BY text) > 1")
def same_as_components(spark, sf_dir):
    pairs = graphs.alike_documents(spark, sf_dir)
    program = Program(rules("same(X,Y) :- alike(X,Y). same(X,Y) :- same(Y,X). same(X,Z) :- same(X,Y), same(Y,Z)."), {"alike": facts("alike", pairs, ["a", "b"], 1.0, unique=True)})
    same = set_fixpoint(program).of("same")
    return same.groupBy(F.col("a0").alias("member")).agg(F.min(F.least("a0", "a1")).alias("component"))


@query(f"""WITH g AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS head FROM documents), p AS (SELECT head AS a, doc_id AS b, {w.sql_pi('doc_id', 5)} AS pi FROM g WHERE doc_id <> head),
s AS (SELECT a, b, pi FROM p UNION ALL SELECT b, a, pi FROM p), q AS (SELECT doc_id, {w.sql_pi('doc_id', 6)} AS pi FROM labels WHERE quality = 1),
e AS (SELECT doc_id, pi FROM q UNION ALL SELECT s.b, q.pi * s.pi FROM s JOIN q ON q.doc_id = s.a)
SELECT doc_id, round(1 - product(1 - pi), 6) AS prob FROM e GROUP BY 1""")
def same_as_prob(spark, sf_dir):
    result = reason(graphs.same_as(spark, sf_dir), collapse=10)
    return probabilities(lineage(result, "good"), base_probabilities(result.program)).select(F.col("a0").alias("doc_id"), F.round("prob", 6).alias("prob"))


@query(f"""WITH RECURSIVE t AS (SELECT DISTINCT conv_id, turn FROM conversations), r AS (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM t),
e AS (SELECT conv_id, turn, nxt, {w.sql_pi('(conv_id * 13 + turn)', 8)} AS pi FROM r WHERE nxt IS NOT NULL),
c(conv_id, a, b, pi) AS (SELECT conv_id, turn, nxt, pi FROM e UNION ALL SELECT c.conv_id, c.a, e.nxt, c.pi * e.pi FROM c JOIN e ON e.conv_id = c.conv_id AND e.turn = c.b)
SELECT conv_id, a, b, round(pi, 12) AS prob FROM c""")
def reply_chain(spark, sf_dir):
    result = reason(graphs.replies(spark, sf_dir))
    return probabilities(lineage(result, "after"), base_probabilities(result.program)).select(F.col("a0").alias("conv_id"), F.col("a1").alias("a"), F.col("a2").alias("b"), F.round("prob", 12).alias("prob"))


@query("""WITH RECURSIVE l AS (SELECT DISTINCT page_id, path FROM (SELECT page_id, regexp_replace(unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)), '^https?://[^/]*', '') AS path FROM pages) WHERE path <> ''),
h AS (SELECT page_id, min(page_id) OVER (PARTITION BY path) AS head FROM l), e AS (SELECT page_id AS a, head AS b FROM h UNION SELECT head, page_id FROM h),
r(a, b) AS (SELECT a, b FROM e UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a)
SELECT a AS page_id, min(b) AS component FROM r GROUP BY a""")
def page_link_reach(spark, sf_dir):
    """Pages that shared paths connect, as classes: each page links to the least page of its paths, never to all."""
    links = graphs.page_links(spark, sf_dir)
    heads = links.groupBy("path").agg(F.min("page_id").alias("b"))
    found = components(links.join(heads, "path").select(F.col("page_id").alias("a"), "b"))
    return found.select(F.col("node").alias("page_id"), "component")


def scene_answers(spark, sf_dir, goal: str, columns: str, collapse: float | None = None) -> DataFrame:
    """Exact answers over all scenes, with the rules that the asked predicate needs, as they are."""
    asked = Query.parse(goal)

    def make():
        program = graphs.scenes(spark, sf_dir)
        needed, own = {a.pred for a in asked.body}, []
        while True:
            grown = [r for r in program.rules if r.head.pred in needed]
            if len(grown) == len(own):
                break
            own = grown
            needed |= {a.pred for r in own for a in r.body}
        return answer(Program(own, {k: v for k, v in program.facts.items() if k in needed}), asked, magic=None, collapse=collapse, budget=5_000, order="first_seen")

    got = w.remembered(("vqa", sf_dir, goal, collapse), make)
    return got.table.select(*(F.col(f"a{i}").alias(c) for i, c in enumerate(columns.split())), "prob", "n_expl", "status", "nanos")


@query()
def vqa_exact(spark, sf_dir):
    """Classes that each scene has."""
    return scene_answers(spark, sf_dir, "u(S,K) :- has(S,K).", "scene label").select("scene", "label", F.round("prob", 6).alias("prob"), "n_expl", "status")


@query()
def vqa_attributes(spark, sf_dir):
    """Attributes that vectors inherit from their classes."""
    return scene_answers(spark, sf_dir, "u(V,A) :- attr(V,A).", "vec_id attribute").select("vec_id", "attribute", F.round("prob", 6).alias("prob"), "n_expl", "status")


@query()
def vqa_answers(spark, sf_dir):
    """Scenes with an odd thing near an even one: the case of many derivations."""
    return scene_answers(spark, sf_dir, "u(S) :- ans(S).", "scene", 10).select("scene", F.round("prob", 6).alias("prob"), "n_expl", "status")


@query()
def vqa_slowest(spark, sf_dir):
    """The five answers whose probability took longest, with the highest probability of each query."""
    got = scene_answers(spark, sf_dir, "u(S) :- ans(S).", "scene", 10)
    return got.select("scene", F.round("prob", 6).alias("prob"), (F.col("nanos") / 1e6).alias("ms")).orderBy(F.desc("ms"), "scene").limit(5)


@query()
def vqa_answered(spark, sf_dir):
    """Scenes by status of their answer: exact, or over the solver's budget."""
    return scene_answers(spark, sf_dir, "u(S) :- ans(S).", "scene", 10).groupBy("status").agg(F.count("*").alias("answers"))


def error_buckets(both: DataFrame) -> DataFrame:
    """bucket, n: tenths of the relative error of ``approx`` below ``exact``; -1 counts answers without an exact probability.

    An approximation that keeps some explanations is never above the exact value: where one is, the run fails.
    """
    error = (F.col("exact") - F.coalesce("approx", F.lit(0.0))) / F.col("exact")
    sided = F.when(error < -1e-6, F.raise_error(F.lit("a lower bound lies above the exact probability")).cast("double")).otherwise(F.greatest(error, F.lit(0.0)))
    bucket = F.when((F.col("status") != "ok") | error.isNull(), F.lit(-1)).otherwise(F.least(F.floor(F.round(sided, 6) * 10), F.lit(9)))
    return both.groupBy(bucket.cast("long").alias("bucket")).agg(F.count("*").alias("n"))


@query()
def vqa_error_hist(spark, sf_dir):
    """Errors of the 1 and 20 best explanations against the exact probability, over all scenes and classes."""
    program = graphs.scenes(spark, sf_dir)
    small = Program([r for r in program.rules if r.head.pred in ("isa", "has")], {k: v for k, v in program.facts.items() if k in ("looks_like", "parent", "in_scene")})

    def answers(k: int | None) -> DataFrame:
        """Exact ones, or those of the k best explanations."""
        if k is None:
            return scene_answers(spark, sf_dir, "u(S,K) :- has(S,K).", "a0 a1").select("a0", "a1", F.col("prob").alias("exact"), "status")
        top = topk_fixpoint(small, k).of("has").select("a0", "a1", "dnf")
        return probabilities(top, base_probabilities(small)).select("a0", "a1", F.col("prob").alias("approx"))

    exact, *approx = (answers(k) for k in (None, 1, 20))  # one after the other: side by side the plans fill the driver
    parts = [error_buckets(exact.join(own, ["a0", "a1"], "left")).withColumn("k", F.lit(k).cast("long")) for k, own in zip((1, 20), approx, strict=True)]
    return parts[0].unionByName(parts[1])


_TRIPLES = """t AS (SELECT n_name AS s, 'region' AS p, r_name AS o FROM nation JOIN region ON n_regionkey = r_regionkey
UNION ALL SELECT concat('c', c_custkey), 'nation', n_name FROM customer JOIN nation ON c_nationkey = n_nationkey
UNION ALL SELECT concat('c', c_custkey), 'in_region', r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
UNION ALL SELECT concat('c', c_custkey), 'segment', c_mktsegment FROM customer
UNION ALL SELECT concat('s', s_suppkey), 'nation', n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey
UNION ALL SELECT concat('s', s_suppkey), 'in_region', r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
UNION ALL SELECT concat('p', p_partkey), 'brand', p_brand FROM part UNION ALL SELECT concat('p', p_partkey), 'type', p_type FROM part)"""


@query(f"""WITH {_TRIPLES}, b AS (SELECT p AS b1, NULL AS b2, s AS x, o AS y FROM t UNION ALL SELECT DISTINCT l.p, r.p, l.s, r.o FROM t l JOIN t r ON l.o = r.s),
n AS (SELECT b1, b2, count(*) AS body FROM b GROUP BY 1, 2), u AS (SELECT h.p AS head, b1, b2, count(*) AS support FROM b JOIN t h ON h.s = x AND h.o = y WHERE b2 IS NOT NULL OR b1 <> h.p GROUP BY 1, 2, 3)
SELECT head, u.b1, u.b2, support, body, round(CAST(support AS DOUBLE) / body, 6) AS confidence FROM u JOIN n ON n.b1 = u.b1 AND n.b2 IS NOT DISTINCT FROM u.b2 WHERE support >= 5""")
def mined_rules(spark, sf_dir):
    mined = onto.mine(onto.star_triples(spark, sf_dir))
    return mined.select("head", "b1", "b2", "support", "body", F.round("confidence", 6).alias("confidence"))


for _set, _k in (("y", 5), ("y", 10), ("y", 15), ("w", 5), ("w", 10), ("w", 15)):

    @query(None, f"mined_{_set}{_k}_stats")
    def _(spark, sf_dir, which=_set, k=_k):
        triples = onto.star_triples(spark, sf_dir) if which == "y" else onto.text_triples(spark, sf_dir)
        parts = stored(onto.split(triples), "triples")
        own = onto.as_rules(onto.top_rules(onto.mine(parts.where("part <= 8").select("s", "p", "o"), 2), k))
        if not own:
            return spark.createDataFrame([(k, 0, 0)], "k int, rules int, derived bigint")
        given = onto.triple_facts(parts.where("part = 9").select("s", "p", "o"), sorted({a.pred[:-2] for r in own for a in r.body}))
        tables = set_fixpoint(Program(own, given)).tables
        return spark.createDataFrame([(k, len(own), sum(df.count() for df in tables.values()))], "k int, rules int, derived bigint")


@query("SELECT p, count(*) AS n FROM (WITH " + _TRIPLES + " SELECT * FROM t) GROUP BY 1")
def kg_d_stats(spark, sf_dir):
    return onto.star_triples(spark, sf_dir).groupBy("p").agg(F.count("*").alias("n"))


@query("""SELECT p, count(*) AS n FROM (SELECT doc_id AS s, 'lang' AS p, lang AS o FROM documents WHERE lang IS NOT NULL UNION ALL SELECT doc_id, 'source', source FROM documents WHERE source IS NOT NULL
UNION SELECT doc_id, 'quality', CAST(quality AS VARCHAR) FROM labels WHERE quality IS NOT NULL UNION SELECT doc_id, 'toxic', CAST(toxic AS VARCHAR) FROM labels WHERE toxic IS NOT NULL
UNION SELECT user_id, 'does', event_type FROM events UNION SELECT conv_id, 'role', role FROM conversations) GROUP BY 1""")
def kg_c_stats(spark, sf_dir):
    return onto.text_triples(spark, sf_dir).groupBy("p").agg(F.count("*").alias("n"))


def class_rules(triples: DataFrame, least: int = 5) -> tuple[list, list[tuple]]:
    """A class for each value of a property that so many things have: rules, and (property, value) in order."""
    values = [(r["p"], r["o"]) for r in triples.groupBy("p", "o").agg(F.count("*").alias("n")).where(F.col("n") >= least).orderBy("p", "o").collect()]  # one row a class
    quoted = lambda x: x.replace("'", "")
    text = "".join(f"is(X,'{quoted(p)}={quoted(o)}') :- {p}_b(X,'{quoted(o)}'). " for p, o in values)
    return rules(text, "class"), values


def asked_classes(spark, sf_dir, triples: DataFrame, n: int = 50, seed: int = 5) -> DataFrame:
    """query, answers, trees, n_expl, ms: n generated queries of one or two atoms over class rules, in one run."""
    own, values = class_rules(triples)
    rng = random.Random(seed)
    names = sorted({p for p, _ in values})
    text = ""
    for q in range(n):
        p, o = rng.choice(values)
        goal = f"is(X,'{p}={o}')"
        text += f"gen('q{q}',X,Y) :- {goal}, {rng.choice(names)}_b(X,Y). " if rng.random() < 0.5 else f"gen('q{q}',X,'-') :- {goal}. "
    program = Program([*own, *rules(text, "asked")], onto.triple_facts(triples, names))
    result = reason(program, collapse=10)
    got = probabilities(lineage(result, "gen", cap=1_000_000), base_probabilities(result.program), timeout=60)
    trees = result.of("gen").groupBy(F.col("a0").alias("q")).agg(F.count("*").alias("trees"))
    return got.groupBy(F.col("a0").alias("q")).agg(F.count("*").alias("answers"), F.count_if(F.col("status") == "ok").alias("solved"), F.sum("n_expl").alias("n_expl"), (F.sum("nanos") / 1e6).alias("ms")).join(trees, "q")


def boxes(df: DataFrame, columns: list[str]) -> DataFrame:
    """measure, low, q1, mid, q3, high of columns: the box plots of a set of queries."""
    long = df.select(*(F.col(c).cast("double").alias(c) for c in columns)).unpivot([], columns, "measure", "value")
    at = F.percentile("value", F.array(*map(F.lit, (0.0, 0.25, 0.5, 0.75, 1.0))))
    return long.groupBy("measure").agg(at.alias("p")).select("measure", *(F.round(F.col("p")[i], 3).alias(n) for i, n in enumerate(("low", "q1", "mid", "q3", "high"))))


for _set in ("d", "c"):

    @query(None, f"kg_{_set}_boxes")
    def _(spark, sf_dir, which=_set):
        triples = onto.star_triples(spark, sf_dir) if which == "d" else onto.text_triples(spark, sf_dir)
        return boxes(asked_classes(spark, sf_dir, stored(triples, "triples")), ["answers", "trees", "n_expl", "ms"])


@query()
def collapse_overhead(spark, sf_dir):
    """Seconds of reasoning and of folding trees, with their share, on the orders of customers."""
    result = w.remembered(("first-orders", sf_dir), lambda: reason(w.first_orders(spark, sf_dir), collapse=10))
    total, folding = sum(x["seconds"] for x in result.log), sum(x["collapse_seconds"] for x in result.log)
    return spark.createDataFrame([(total, folding, folding / total)], "reasoning double, folding double, share double")


@query()
def solver_times(spark, sf_dir):
    """Milliseconds a formula, mean and standard deviation, by solver; answers by status."""
    formulas, given = w.trade_lineage(spark, sf_dir)
    parts = [probabilities(formulas, given, s).groupBy("status").agg(F.count("*").alias("answers"), (F.avg("nanos") / 1e6).alias("mean"), (F.stddev_samp("nanos") / 1e6).alias("sd")).withColumn("solver", F.lit(s)) for s in ("dd", "dtree", "cnf")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query()
def memory_peak(spark, sf_dir):
    """Peak megabytes of this process and of the virtual machine's heap in use after a run with and without folds."""
    rows = []
    for name, collapse in (("without", None), ("with", 10)):
        reason(w.collapse_example(spark, 10), collapse=collapse)
        machine = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
        rows.append((name, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024, (machine.totalMemory() - machine.freeMemory()) / 2**20))
    return spark.createDataFrame(rows, "run string, process_mb double, heap_mb double")


def _generated_atoms() -> list[tuple[str, str]]:
    made = generate_queries(Program(rules(onto.CORE)), 50)
    return [(f"gen{i}", a.pred) for i, q in enumerate(made) for a in q.body]


_GENERATED = f"""WITH atoms(query, pred) AS (VALUES {', '.join(f"('{q}', '{p}')" for q, p in _generated_atoms())}),
n AS (SELECT 'nation_in' AS pred, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey
UNION ALL SELECT 'supp_in', count(*) FROM supplier JOIN nation ON s_nationkey = n_nationkey
UNION ALL SELECT 'cust_in', count(*) FROM customer JOIN nation ON c_nationkey = n_nationkey
UNION ALL SELECT 'placed', count(*) FROM orders
UNION ALL SELECT 'ships', count(*) FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem)
UNION ALL SELECT 'line', count(*) FROM (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey FROM lineitem))
SELECT query, count(*) AS atoms, CAST(coalesce(sum(n), 0) AS BIGINT) AS facts FROM atoms LEFT JOIN n USING (pred) GROUP BY query"""


@query(_GENERATED)
def generated_query_sizes(spark, sf_dir):
    """Atoms of fifty generated queries, and the base facts of the tables that these atoms read."""
    atoms = spark.createDataFrame(_generated_atoms(), "query string, pred string")
    given = onto.program(spark, sf_dir, onto.CORE).facts
    sizes = union([df.agg(F.lit(p).alias("pred"), F.count("*").alias("n")).select("pred", "n") for p, df in sorted(given.items())])
    per = atoms.join(F.broadcast(sizes), "pred", "left").groupBy("query").agg(F.count("*").alias("atoms"), F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("facts"))
    return per.select("query", "atoms", "facts")


for _name, (_f, _sql) in {**OPERATORS, **STREAMS}.items():
    query(_sql, _name)(_f)


