"""Graph workloads: smokers, same-as, scenes, page links, reply chains."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.dnf import cosine, softmax
from ..rules import Program, rules
from ..sources.tables import facts, hash_pi, load, stored
from .base import remembered

SMOKERS = "smokes(X) :- stress(X). smokes(Y) :- friend(X,Y), influences(X,Y), smokes(X). friend(X,Y) :- known(X,Y). friend(X,Y) :- known(Y,X). asthma(X) :- smokes(X), risk(X)."
SMOKERS_BY_SIZE = "smokes(G,X) :- stress(G,X). smokes(G,Y) :- friend(G,X,Y), influences(G,X,Y), smokes(G,X). friend(G,X,Y) :- known(G,X,Y). friend(G,X,Y) :- known(G,Y,X). asthma(G,X) :- smokes(G,X), risk(G,X)."
SAME_AS = "same(X,Y) :- alike(X,Y). same(X,Y) :- alike(Y,X). good(X) :- quality(X). good(Y) :- quality(X), same(X,Y)."
SCENES = "isa(V,L) :- looks_like(V,L). isa(V,K) :- isa(V,L), parent(L,K). has(S,K) :- in_scene(V,S), isa(V,K). attr(V,A) :- isa(V,K), attr_of(K,A). pair(S,K,M) :- in_scene(V,S), in_scene(U,S), near(V,U), isa(V,K), isa(U,M). ans(S) :- pair(S,'odd','even')."
REPLIES = "after(C,T,U) :- reply(C,T,U). after(C,T,V) :- after(C,T,U), reply(C,U,V)."


def shared_hours(spark: SparkSession, sf_dir: str, n: int) -> tuple[DataFrame, DataFrame]:
    """(user_id, rank) of the n most active users, and (u, v, weight): hours that pairs of them share."""
    events = load(spark, sf_dir, "events").select("user_id", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("hour"))
    active = events.groupBy("user_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "user_id").limit(n)
    active = active.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), "user_id"))).select("user_id", "rank")  # n rows
    hours = events.join(F.broadcast(active.select("user_id")), "user_id").distinct()
    other = hours.withColumnRenamed("user_id", "v")
    return active, hours.withColumnRenamed("user_id", "u").join(other, "hour").where("u < v").groupBy("u", "v").agg(F.count("*").alias("weight"))


def smokers_graph(spark: SparkSession, sf_dir: str, n: int, most_edges: int | None = None) -> DataFrame:
    """u, v, weight: the n most active users and the pairs that share most hours; at most 2n undirected edges."""
    _, pairs = shared_hours(spark, sf_dir, n)
    return pairs.orderBy(F.desc("weight"), "u", "v").limit(most_edges or 2 * n).select("u", "v", "weight")


def smokers_by_size(spark: SparkSession, sf_dir: str, sizes: range = range(10, 21), asked: int = 5) -> Program:
    """The smokers rules over graphs of all sizes at once: every predicate has the size as its first argument."""

    def make() -> Program:
        active, pairs = (stored(df, "smokers") for df in shared_hours(spark, sf_dir, sizes[-1]))
        size = spark.range(sizes[0], sizes[-1] + 1).withColumnRenamed("id", "g")
        people = active.join(F.broadcast(size), F.col("rank") <= F.col("g"))
        left, right = (people.select("g", F.col("user_id").alias(c)) for c in "uv")
        inside = pairs.join(left, "u").join(right, ["g", "v"])
        edges = inside.withColumn("rn", F.row_number().over(Window.partitionBy("g").orderBy(F.desc("weight"), "u", "v"))).where(F.col("rn") <= 2 * F.col("g"))
        edges = stored(edges.select("g", "u", "v"), "smokers")
        both = edges.unionByName(edges.select("g", F.col("v").alias("u"), F.col("u").alias("v")))
        given = {
            "known": facts("known", edges, ["g", "u", "v"], hash_pi(F.col("u") * 31 + F.col("v"), 1), unique=True),
            "influences": facts("influences", both, ["g", "u", "v"], hash_pi(F.col("u") * 17 + F.col("v"), 2), unique=True),
            "stress": facts("stress", people, ["g", "user_id"], hash_pi(F.col("user_id"), 3), unique=True),
            "risk": facts("risk", people, ["g", "user_id"], hash_pi(F.col("user_id"), 4), unique=True),
            "asked": facts("asked", people.where(F.col("rank") <= asked), ["g", "user_id"], 1.0, unique=True),
        }
        return Program(rules(SMOKERS_BY_SIZE), {k: stored(v, k) for k, v in given.items()})

    return remembered(("smokers-by-size-program", sf_dir, sizes, asked), make)


def smokers(spark: SparkSession, sf_dir: str, n: int, most_edges: int | None = None) -> Program:
    def make() -> Program:
        edges = stored(smokers_graph(spark, sf_dir, n, most_edges), "smokers")
        people = edges.select("u").union(edges.select("v")).distinct().withColumnRenamed("u", "p")
        both = edges.select("u", "v").union(edges.select("v", "u"))
        given = {
            "known": facts("known", edges, ["u", "v"], hash_pi(F.col("u") * 31 + F.col("v"), 1), unique=True),
            "influences": facts("influences", both, ["u", "v"], hash_pi(F.col("u") * 17 + F.col("v"), 2), unique=True),
            "stress": facts("stress", people, ["p"], hash_pi(F.col("p"), 3), unique=True),
            "risk": facts("risk", people, ["p"], hash_pi(F.col("p"), 4), unique=True),
        }
        return Program(rules(SMOKERS), {k: stored(v, k) for k, v in given.items()})

    return remembered(("smokers", sf_dir, n, most_edges), make)


def alike_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """a, b: documents with one text - each with the first of its group, so that groups are stars."""
    docs = load(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("h"))
    heads = docs.groupBy("h").agg(F.min("doc_id").alias("a"))
    return docs.join(heads, "h").where("doc_id <> a").select("a", F.col("doc_id").alias("b"))


def same_as(spark: SparkSession, sf_dir: str) -> Program:
    pairs = alike_documents(spark, sf_dir)
    good = load(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    return Program(rules(SAME_AS), {"alike": facts("alike", pairs, ["a", "b"], hash_pi(F.col("b"), 5), unique=True), "quality": facts("quality", good, ["doc_id"], hash_pi(F.col("doc_id"), 6))})


def looks_like(spark: SparkSession, sf_dir: str, top: int = 3) -> DataFrame:
    """v, label, pi: soft-max of the cosine to label centroids, the best labels of each vector."""
    vecs = load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"), "label")
    parts = vecs.select("label", F.posexplode("e").alias("at", "x")).groupBy("label", "at").agg(F.avg("x").alias("x"))
    centroids = parts.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda s: s["x"]).alias("c")).agg(F.array_sort(F.collect_list(F.struct("label", "c"))).alias("all"))
    scored = vecs.crossJoin(F.broadcast(centroids)).select("vec_id", F.transform("all", lambda s: s["label"]).alias("labels"), F.transform("all", lambda s: cosine(F.col("e"), s["c"]) * 10).alias("z"))
    soft = scored.select("vec_id", F.arrays_zip("labels", softmax(F.col("z")).alias("p")).alias("lp"))
    best = soft.select("vec_id", F.slice(F.sort_array(F.transform("lp", lambda s: F.struct(F.round(s["p"], 3).alias("p"), (-s["labels"]).alias("l"))), asc=False), 1, top).alias("lp"))
    return best.select("vec_id", F.explode("lp").alias("s")).select("vec_id", (-F.col("s.l")).cast("int").alias("label"), F.greatest(F.lit(0.001), F.least(F.lit(0.999), F.col("s.p"))).alias("pi"))


def scenes(spark: SparkSession, sf_dir: str, most_scenes: int | None = None, size: int = 10) -> Program:
    """Scenes of ten vectors; labels roll up to parity and to a root."""

    def make() -> Program:
        look = stored(looks_like(spark, sf_dir), "looks")
        vecs = load(spark, sf_dir, "embeddings").select("vec_id").withColumn("scene", F.expr(f"vec_id div {size}"))
        if most_scenes is not None:
            vecs = vecs.where(F.col("scene") < most_scenes)
        near = vecs.alias("x").join(vecs.alias("y"), F.expr("x.scene = y.scene and (y.vec_id = x.vec_id + 1 or x.vec_id = y.vec_id + 1)")).select(F.col("x.vec_id").alias("v"), F.col("y.vec_id").alias("u"))
        names = look.select(F.col("label").cast("string").alias("l")).distinct()
        parity = F.when(F.col("l").cast("int") % 2 == 1, "odd").otherwise("even")
        parents = names.select("l", parity.alias("k")).union(spark.createDataFrame([("odd", "thing"), ("even", "thing")], "l string, k string"))
        inside = look.join(vecs, "vec_id").select("vec_id", F.col("label").cast("string").alias("label"), "pi")
        given = {
            "looks_like": facts("looks_like", inside, ["vec_id", "label"], F.col("pi"), unique=True),
            "parent": facts("parent", parents, ["l", "k"], 1.0),
            "in_scene": facts("in_scene", vecs, ["vec_id", "scene"], 1.0, unique=True),
            "near": facts("near", near, ["v", "u"], hash_pi(F.col("v") * 31 + F.col("u"), 7), unique=True),
            "attr_of": facts("attr_of", parents.where("l = 'odd' or l = 'even'"), ["l", "k"], 0.9),
        }
        return Program(rules(SCENES), {k: stored(v, k) for k, v in given.items()})

    return remembered(("scenes", sf_dir, most_scenes, size), make)


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page, path: links of pages, by path without host."""
    pages = load(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    return pages.select("page_id", F.regexp_replace("href", "^https?://[^/]*", "").alias("path")).where("path <> ''").distinct()


def replies(spark: SparkSession, sf_dir: str) -> Program:
    turns = load(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    after = turns.withColumn("after", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))).dropna()
    return Program(rules(REPLIES), {"reply": facts("reply", after, ["conv_id", "turn", "after"], hash_pi(F.col("conv_id") * 13 + F.col("turn"), 8), unique=True)})
