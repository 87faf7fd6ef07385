"""Fact views over the given tables, and the examples whose every value is known."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.reason import PlanResult, base_probabilities, lineage, reason
from ..rules import Program, parse, rules
from ..sources.tables import facts, from_atoms, hash_pi, load, stored

EDGES = "0.5::e('a','b'). 0.6::e('b','c'). 0.7::e('a','c'). 0.8::e('c','b'). "
QUADRATIC = "p(X,Y) :- e(X,Y). p(X,Y) :- p(X,Z), p(Z,Y)."
COLLAPSE = "r(X,Y) :- q(X,Y). t(X) :- r(X,Y). r(X,Y) :- t(X), s(X,Y)."
LINEAR = "reach(X,Y) :- trade(X,Y). reach(X,Y) :- reach(X,Z), trade(Z,Y)."

_memo: dict = {}


def remembered(key: tuple, make):
    """Results shared by the queries of a session, by input path and parameters; ``forget()`` drops them."""
    if key not in _memo:
        _memo[key] = make()
    return _memo[key]


def forget() -> None:
    _memo.clear()


def program(spark: SparkSession, text: str) -> Program:
    own, given = parse(text)
    return Program(own, from_atoms(spark, given))


def reach_example(spark: SparkSession) -> Program:
    return program(spark, EDGES + QUADRATIC)


def collapse_example(spark: SparkSession, n: int) -> Program:
    return program(spark, "".join(f"{i / (2 * n)}::q('a',{i}). " for i in range(1, n + 1)) + "0.5::s('a',1). " + COLLAPSE)


def complete_graph(spark: SparkSession, n: int) -> Program:
    return program(spark, "".join(f"0.5::e({i},{j}). " for i in range(n) for j in range(n) if i != j) + "p(X,Y) :- e(X,Y). p(X,Y) :- p(X,Z), e(Z,Y).")


def first_orders(spark: SparkSession, sf_dir: str) -> Program:
    """q(c,o): orders of a customer; s(c,o): the customer's first order."""
    orders = load(spark, sf_dir, "orders").select("o_custkey", "o_orderkey")
    q = facts("q", orders, ["o_custkey", "o_orderkey"], hash_pi(F.col("o_orderkey")), unique=True)
    first = orders.groupBy("o_custkey").agg(F.min("o_orderkey").alias("o"))
    s = facts("s", first, ["o_custkey", "o"], hash_pi(F.col("o_custkey"), 1), unique=True)
    return Program(rules(COLLAPSE), {"q": q, "s": s})


def trade_edges(spark: SparkSession, sf_dir: str, partners: int = 2) -> DataFrame:
    """a, b, pi: for each supplying nation the partner nations of most revenue."""
    supplier = load(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").alias("a"))
    customer = load(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").alias("b"))
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_extendedprice")
    flows = lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"]).join(customer, F.col("o_custkey") == F.col("c_custkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).where("a <> b")
    total = flows.groupBy("a", "b").agg(F.round(F.sum("l_extendedprice"), 2).alias("revenue"))
    ranked = total.withColumn("rn", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("revenue"), "b"))).where(F.col("rn") <= partners)
    pi = ((F.col("a").cast("long") * 7919 + F.col("b").cast("long") * 104729) % 997 + 1).cast("double") / F.lit(1000.0)
    return ranked.select("a", "b", pi.alias("pi"))


def trade(spark: SparkSession, sf_dir: str, partners: int = 2, text: str = LINEAR) -> Program:
    edges = remembered(("edges", sf_dir, partners), lambda: stored(facts("trade", trade_edges(spark, sf_dir, partners), ["a", "b"], F.col("pi"), unique=True), "trade"))
    return Program(rules(text), {"trade": edges})


def trade_result(spark: SparkSession, sf_dir: str, partners: int = 2, max_depth: int | None = 3, collapse: float | None = None) -> PlanResult:
    return remembered(("trade", sf_dir, partners, max_depth, collapse), lambda: reason(trade(spark, sf_dir, partners), collapse=collapse, max_depth=max_depth))


def trade_lineage(spark: SparkSession, sf_dir: str, partners: int = 2, max_depth: int = 3) -> tuple[DataFrame, DataFrame]:
    result = trade_result(spark, sf_dir, partners, max_depth)
    return remembered(("lineage", sf_dir, partners, max_depth), lambda: stored(lineage(result, "reach"), "lineage")), base_probabilities(result.program)


# --- SQL twins ----------------------------------------------------------------------------------------------------


def sql_pi(key: str, salt: int = 0) -> str:
    return f"(CAST(({key} * 7919 + {104729 * salt}) % 997 + 1 AS DOUBLE) / CAST(1000 AS DOUBLE))"


def sql_trade(partners: int = 2) -> str:
    """CTEs flow, edge(a, b, pi, bit)."""
    return f"""flow AS (
  SELECT s_nationkey AS a, c_nationkey AS b, round(sum(l_extendedprice), 2) AS revenue
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
  WHERE s_nationkey <> c_nationkey GROUP BY 1, 2
), ranked AS (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY revenue DESC, b) AS rn FROM flow),
edge AS (
  SELECT a, b, CAST((CAST(a AS BIGINT) * 7919 + CAST(b AS BIGINT) * 104729) % 997 + 1 AS DOUBLE) / 1000 AS pi,
         row_number() OVER (ORDER BY a, b) - 1 AS bit
  FROM ranked WHERE rn <= {partners}
)"""


def sql_paths(depth: int = 3) -> str:
    """CTEs path, expl(a, b, m): minimal sets of edges, as bit masks, that lead from a to b in at most depth steps."""
    return f"""path(a, b, m, d) AS (
  SELECT a, b, CAST(1 AS UBIGINT) << bit, 1 FROM edge
  UNION ALL SELECT p.a, e.b, p.m | (CAST(1 AS UBIGINT) << e.bit), p.d + 1 FROM path p JOIN edge e ON p.b = e.a WHERE p.d < {depth}
), every_m AS (SELECT DISTINCT a, b, m FROM path),
expl AS (
  SELECT a, b, m, row_number() OVER (PARTITION BY a, b ORDER BY m) AS i FROM every_m x
  WHERE NOT EXISTS (SELECT 1 FROM every_m y WHERE y.a = x.a AND y.b = x.b AND y.m <> x.m AND y.m & x.m = y.m)
)"""


def sql_incl_excl() -> str:
    """CTE answer(a, b, prob, n_expl) from expl and edge, by signed sums over sets of explanations."""
    return """chosen(a, b, i, m, sign) AS (
  SELECT a, b, i, m, 1 FROM expl
  UNION ALL SELECT c.a, c.b, e.i, c.m | e.m, -c.sign FROM chosen c JOIN expl e ON e.a = c.a AND e.b = c.b AND e.i > c.i
), weighed AS (
  SELECT c.a, c.b, c.i, c.m, c.sign, c.rn, product(edge.pi) AS w
  FROM (SELECT *, row_number() OVER () AS rn FROM chosen) c JOIN edge ON (c.m >> edge.bit) & 1 = 1 GROUP BY ALL
), answer AS (SELECT a, b, sum(sign * w) AS prob FROM weighed GROUP BY a, b)"""


def sql_trade_answers(depth: int = 3, partners: int = 2) -> str:
    return f"WITH RECURSIVE {sql_trade(partners)}, {sql_paths(depth)}, {sql_incl_excl()}"


def rounded(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in columns})


def round_scaled(column: str | Column, digits: int = 6) -> Column:
    """Half away from zero of the scaled double, as the SQL twins round; ``F.round`` goes by decimal digits instead, so
    that a sum or product that is half a unit in theory may end on the other side."""
    value, scale = F.col(column) if isinstance(column, str) else column, F.lit(10.0**digits)
    scaled = F.abs(value) * scale
    whole = F.floor(scaled).cast("double")
    return F.signum(value) * F.when(scaled - whole >= 0.5, whole + 1).otherwise(whole) / scale
