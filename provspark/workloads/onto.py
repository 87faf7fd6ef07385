"""Business ontology over the star tables: facts, generated rules, queries; triples and mined rules."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..rules import Program, Rule, rules
from ..sources.tables import facts, hash_pi, load
from .base import remembered, trade_edges

CORE = """
in(S,N) :- supp_in(S,N). in(C,N) :- cust_in(C,N). in(N,R) :- nation_in(N,R). in(X,Z) :- in(X,Y), nation_in(Y,Z).
buys(C,P) :- placed(C,O), line(O,P,S). served_by(C,S) :- placed(C,O), line(O,P,S). serves(S,C) :- served_by(C,S).
partner(X,Y) :- serves(X,Y). partner(X,Y) :- partner(Y,X). delivers(S,P) :- ships(S,P).
cls(S,'supplier') :- delivers(S,P). cls(P,'product') :- delivers(S,P). cls(C,'customer') :- buys(C,P). cls(S,'supplier') :- served_by(C,S).
local_pair(C,S) :- served_by(C,S), in(C,N), in(S,N). region_has(R,K) :- in(S,R), delivers(S,P), cls(P,K). mate(X,Y) :- cust_in(X,N), cust_in(Y,N).
"""


def entity(kind: str, column: str):
    return F.concat(F.lit(kind), F.col(column).cast("string"))


def base_facts(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    nation = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    names = F.broadcast(nation.select("n_nationkey", "n_name"))
    customer = load(spark, sf_dir, "customer").join(names, F.col("c_nationkey") == F.col("n_nationkey"))
    supplier = load(spark, sf_dir, "supplier").join(names, F.col("s_nationkey") == F.col("n_nationkey"))
    orders, part, line = load(spark, sf_dir, "orders"), load(spark, sf_dir, "part"), load(spark, sf_dir, "lineitem")
    sure = F.greatest(F.lit(0.5), F.lit(1.0) - F.lit(5.0) * F.col("l_discount"))
    return {
        "nation_in": facts("nation_in", nation, ["n_name", "r_name"], 1.0, unique=True),
        "supp_in": facts("supp_in", supplier, [entity("s", "s_suppkey"), "n_name"], hash_pi(F.col("s_suppkey"), 9), unique=True),
        "cust_in": facts("cust_in", customer, [entity("c", "c_custkey"), "n_name"], hash_pi(F.col("c_custkey"), 10), unique=True),
        "placed": facts("placed", orders, [entity("c", "o_custkey"), entity("o", "o_orderkey")], hash_pi(F.col("o_orderkey"), 11), unique=True),
        "ships": facts("ships", line, [entity("s", "l_suppkey"), entity("p", "l_partkey")], sure),
        "line": facts("line", line, [entity("o", "l_orderkey"), entity("p", "l_partkey"), entity("s", "l_suppkey")], sure),
        "type_of": facts("type_of", part, [entity("p", "p_partkey"), "p_type"], hash_pi(F.col("p_partkey"), 12), unique=True),
        "brand_of": facts("brand_of", part, [entity("p", "p_partkey"), "p_brand"], hash_pi(F.col("p_partkey"), 13), unique=True),
        "size_class": facts("size_class", part, [entity("p", "p_partkey"), F.concat(F.lit("size"), F.expr("CAST((p_size - 1) div 10 AS string)"))], hash_pi(F.col("p_partkey"), 14), unique=True),
        "segment": facts("segment", load(spark, sf_dir, "customer"), [entity("c", "c_custkey"), "c_mktsegment"], hash_pi(F.col("c_custkey"), 15), unique=True),
        "status": facts("status", orders, [entity("o", "o_orderkey"), "o_orderstatus"], hash_pi(F.col("o_orderkey"), 16), unique=True),
        "priority": facts("priority", orders, [entity("o", "o_orderkey"), "o_orderpriority"], hash_pi(F.col("o_orderkey"), 17), unique=True),
    }


def ontology_rules(spark: SparkSession, sf_dir: str) -> list[Rule]:
    """127 rules: the core, and class rules generated from the values of the tables."""
    part = load(spark, sf_dir, "part")
    values = lambda df, c: [r[0] for r in df.select(c).distinct().orderBy(c).collect()]  # noqa: E731  a handful of codes
    text = []
    for pred, column, kinds in (("type_of", "p_type", values(part, "p_type")), ("brand_of", "p_brand", values(part, "p_brand")), ("size_class", "", [f"size{i}" for i in range(5)])):
        for k in kinds:
            text.append(f"cls(P,'{k}_product') :- {pred}(P,'{k}'). cls(P,'product') :- cls(P,'{k}_product').")
    for k in values(load(spark, sf_dir, "customer"), "c_mktsegment"):
        text.append(f"cls(C,'{k}_customer') :- segment(C,'{k}'). cls(C,'customer') :- cls(C,'{k}_customer').")
    orders = load(spark, sf_dir, "orders")
    for pred, column in (("priority", "o_orderpriority"), ("status", "o_orderstatus")):
        for k in values(orders, column):
            text.append(f"cls(O,'{k}_order') :- {pred}(O,'{k}'). cls(O,'order') :- cls(O,'{k}_order').")
    for k in values(load(spark, sf_dir, "region"), "r_name"):
        text.append(f"cls(X,'{k}_member') :- in(X,'{k}').")
    out = rules(CORE + "\n".join(text))
    brands = values(part, "p_brand")
    room = 127 - len(out)
    return out + rules("\n".join(f"touches(N,'{b}') :- in(S,N), delivers(S,P), brand_of(P,'{b}')." for b in brands[: max(0, room)]), "t")


def program(spark: SparkSession, sf_dir: str, text: str | None = None, also: tuple[str, ...] = ()) -> Program:
    """The ontology, or other rules over its facts; ``also`` names base predicates that only a query uses."""
    given = remembered(("onto", sf_dir), lambda: base_facts(spark, sf_dir))
    own = rules(text) if text else ontology_rules(spark, sf_dir)
    used = {a.pred for r in own for a in r.body} | set(also)
    return Program(own, {k: v for k, v in given.items() if k in used})


def trade_by_name(spark: SparkSession, sf_dir: str, partners: int = 1) -> DataFrame:
    """trade(n, m) by the names of nations: the partners of most revenue."""
    names = load(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    edges = trade_edges(spark, sf_dir, partners)
    left, right = names.toDF("a", "n"), names.toDF("b", "m")
    return facts("trade", edges.join(F.broadcast(left), "a").join(F.broadcast(right), "b"), ["n", "m"], F.col("pi"), unique=True)


def star_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """s, p, o of the star tables, with two properties that follow from others."""
    nation = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    customer = load(spark, sf_dir, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    supplier = load(spark, sf_dir, "supplier").join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey"))
    part = load(spark, sf_dir, "part")
    make = lambda df, s, p, o: df.select(s.alias("s"), F.lit(p).alias("p"), F.col(o).alias("o"))
    parts = [
        make(nation, F.col("n_name"), "region", "r_name"),
        make(customer, entity("c", "c_custkey"), "nation", "n_name"),
        make(customer, entity("c", "c_custkey"), "in_region", "r_name"),
        make(customer, entity("c", "c_custkey"), "segment", "c_mktsegment"),
        make(supplier, entity("s", "s_suppkey"), "nation", "n_name"),
        make(supplier, entity("s", "s_suppkey"), "in_region", "r_name"),
        make(part, entity("p", "p_partkey"), "brand", "p_brand"),
        make(part, entity("p", "p_partkey"), "type", "p_type"),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def text_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """s, p, o of documents, labels, events and conversations."""
    docs = load(spark, sf_dir, "documents")
    doc = F.concat(F.lit("d"), F.col("doc_id").cast("string"))
    labels = load(spark, sf_dir, "labels")
    events = load(spark, sf_dir, "events").select("user_id", "event_type").distinct()
    talk = load(spark, sf_dir, "conversations").select("conv_id", "role").distinct()
    parts = [
        docs.select(doc.alias("s"), F.lit("lang").alias("p"), F.col("lang").alias("o")),
        docs.select(doc.alias("s"), F.lit("source").alias("p"), F.col("source").alias("o")),
        labels.select(doc.alias("s"), F.lit("quality").alias("p"), F.col("quality").cast("string").alias("o")),
        labels.select(doc.alias("s"), F.lit("toxic").alias("p"), F.col("toxic").cast("string").alias("o")),
        events.select(F.concat(F.lit("u"), F.col("user_id").cast("string")).alias("s"), F.lit("does").alias("p"), F.col("event_type").alias("o")),
        talk.select(F.concat(F.lit("v"), F.col("conv_id").cast("string")).alias("s"), F.lit("role").alias("p"), F.col("role").alias("o")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.dropna().distinct()


def mine(triples: DataFrame, min_support: int = 5) -> DataFrame:
    """head, b1, b2 (null: one atom), support, body, confidence of closed path rules of one or two atoms.

    The body of a rule is counted by distinct end pairs; support are those that the head has too.
    """
    pairs = triples.select("p", "s", "o").distinct()
    one = pairs.select(F.col("p").alias("b1"), F.lit(None).cast("string").alias("b2"), F.col("s").alias("x"), F.col("o").alias("y"))
    right = pairs.select(F.col("p").alias("b2"), F.col("s").alias("z"), F.col("o").alias("y"))
    two = pairs.select(F.col("p").alias("b1"), F.col("s").alias("x"), F.col("o").alias("z")).join(right, "z").select("b1", "b2", "x", "y").distinct()
    bodies = one.unionByName(two)
    sizes = bodies.groupBy("b1", "b2").agg(F.count("*").alias("body"))
    heads = pairs.select(F.col("p").alias("head"), F.col("s").alias("x"), F.col("o").alias("y"))
    support = bodies.join(heads, ["x", "y"]).where(F.col("b2").isNotNull() | (F.col("b1") != F.col("head"))).groupBy("head", "b1", "b2").agg(F.count("*").alias("support"))
    same = support["b1"].eqNullSafe(sizes["b1"]) & support["b2"].eqNullSafe(sizes["b2"])
    out = support.where(F.col("support") >= min_support).join(F.broadcast(sizes), same).select("head", support["b1"], support["b2"], "support", "body")
    return out.withColumn("confidence", F.col("support") / F.col("body"))


def top_rules(mined: DataFrame, k: int) -> DataFrame:
    by = Window.partitionBy("head").orderBy(F.desc("confidence"), F.desc("support"), "b1", F.col("b2").asc_nulls_first())
    return mined.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k)


def as_rules(mined: DataFrame) -> list[Rule]:
    """Rules of the engine; a mined rule is a handful of names, not data."""
    out = []
    for i, r in enumerate(mined.orderBy("head", "rank").collect()):
        body = f"{r['b1']}_b(X,Y)" if r["b2"] is None else f"{r['b1']}_b(X,Z), {r['b2']}_b(Z,Y)"
        out += rules(f"{r['head']}_d(X,Y) :- {body}.", f"m{i}_")
    return out


def split(triples: DataFrame) -> DataFrame:
    """Triples with part 0-9 by hash: 0-7 train, 8 valid, 9 test."""
    return triples.withColumn("part", F.pmod(F.crc32(F.concat_ws("|", "s", "p", "o").cast("binary")), F.lit(10)))


def triple_facts(triples: DataFrame, names: list[str]) -> dict[str, DataFrame]:
    return {f"{p}_b": facts(f"{p}_b", triples.where(F.col("p") == p), ["s", "o"], hash_pi(F.crc32(F.concat("s", "o").cast("binary")), 1)) for p in names}
