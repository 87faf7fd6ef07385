"""Sources and sinks: the given tables, fact views with probabilities, triples, scratch tables and saved results."""

from __future__ import annotations

import tempfile
import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..rules import Atom, Fact, RuleError, RuleTypeError

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str) -> None:
    """Temporary views of all tables, for SQL."""
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_facts(spark: SparkSession, fmt: str, path: str, schema: str, **options) -> DataFrame:
    """A fact file in any format Spark reads (csv, json, orc, parquet, text)."""
    return spark.read.format(fmt).options(**options).schema(schema).load(path)


def read_triples(spark: SparkSession, path: str) -> DataFrame:
    """Tab-separated subject, property, object."""
    return spark.read.option("sep", "\t").schema("s string, p string, o string").csv(path)


def scratch_root(spark: SparkSession) -> str:
    """The shared folder that the cluster names; a folder of this machine where it is unset, as in tests."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    if not found:
        found = f"file://{tempfile.mkdtemp(prefix='scratch-')}"
        spark.conf.set("spark.checkpoint.dir", found)
    return found


def stored(df: DataFrame, name: str = "step") -> DataFrame:
    """Write to a scratch table and read it back: the next plan begins at a scan, and lost executors cost no rework."""
    path = f"{scratch_root(df.sparkSession)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stored_count(df: DataFrame, name: str = "step") -> tuple[DataFrame, int]:
    """As ``stored``, with the number of rows, counted while they are written."""
    seen = Observation()
    table = stored(df.observe(seen, F.count(F.lit(1)).alias("n")), name)
    return table, int(seen.get["n"])


def side_by_side(work, items: list) -> list:
    """work(item) of all items, as jobs that run at the same time: rounds are many small tables."""
    if len(items) < 2:
        return [work(x) for x in items]
    with ThreadPoolExecutor(min(8, len(items))) as pool:
        return list(pool.map(work, items))


def save(df: DataFrame, path: str, *partition_by: str) -> None:
    df.write.mode("overwrite").partitionBy(*partition_by).parquet(path)


def hash_pi(key: Column, salt: int = 0) -> Column:
    """A probability in (0, 0.997], the same bit for bit in any engine; stands in for a uniform draw."""
    return ((key.cast("long") * 7919 + F.lit(104729 * salt)) % 997 + 1).cast("double") / F.lit(1000).cast("double")


def uniform_pi(seed: int = 0) -> Column:
    return F.lit(1.0) - F.rand(seed)


def fact_id(pred: str, args: list[Column]) -> Column:
    return F.xxhash64(F.lit(pred), *args)


def facts(pred: str, df: DataFrame, args: list[str | Column], pi: Column | float = 1.0, unique: bool = False) -> DataFrame:
    """A base predicate: columns a0.., pi, fid.  Rows with a null argument are no facts; repeated facts keep the larger pi."""
    cols = [F.col(a) if isinstance(a, str) else a for a in args]
    value = pi if isinstance(pi, Column) else F.lit(float(pi))
    out = df.select(*(c.alias(f"a{i}") for i, c in enumerate(cols)), value.cast("double").alias("pi"))
    names = [f"a{i}" for i in range(len(cols))]
    out = out.dropna(subset=names)
    if not unique:
        out = out.groupBy(*names).agg(F.max("pi").alias("pi"))
    return out.withColumn("fid", fact_id(pred, [F.col(n) for n in names]))


def validated(df: DataFrame) -> DataFrame:
    """Fails while running where a probability is outside (0, 1]."""
    ok = (F.col("pi") > 0) & (F.col("pi") <= 1)
    return df.withColumn("pi", F.when(ok, F.col("pi")).otherwise(F.raise_error(F.lit("a probability is outside (0, 1]")).cast("double")))


def from_atoms(spark: SparkSession, given: list[Fact]) -> dict[str, DataFrame]:
    """Base predicates of inline facts."""
    by: dict[str, list[Fact]] = {}
    for f in given:
        if not 0 < f.pi <= 1:
            raise RuleError(f"{f.atom}: {f.pi} is no probability in (0, 1]")
        by.setdefault(f.atom.pred, []).append(f)
    out = {}
    for pred, own in by.items():
        kinds = [{type(f.atom.args[i]) for f in own} for i in range(len(own[0].atom.args))]
        if any(len(k) > 1 for k in kinds):
            raise RuleTypeError(f"{pred} mixes types")
        sql = {int: "bigint", float: "double", str: "string"}
        schema = ", ".join(f"a{i} {sql[k.pop()]}" for i, k in enumerate(kinds)) + ", pi double"
        rows = list(dict.fromkeys((*f.atom.args, f.pi) for f in own))
        if len({r[:-1] for r in rows}) < len(rows):
            raise RuleError(f"{pred}: one fact with two probabilities")
        df = spark.createDataFrame(rows, schema)
        out[pred] = df.withColumn("fid", fact_id(pred, [F.col(c) for c in df.columns[:-1]]))
    return out


def empty(spark: SparkSession, pred: str, types: list[str]) -> DataFrame:
    return spark.createDataFrame([], ", ".join([*(f"a{i} {t}" for i, t in enumerate(types)), "pi double", "fid bigint"]))


def atom_of(pred: str, *args) -> Atom:
    return Atom(pred, tuple(args))
