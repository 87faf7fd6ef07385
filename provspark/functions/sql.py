"""Functions of the engine for SQL: a formula's probability, its explanations as rows, noisy-or as an aggregate."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .solvers import absorbed, solve_one


@F.pandas_udf("double")
def dnf_probability(dnf: pd.Series, fids: pd.Series, pis: pd.Series) -> pd.Series:
    return pd.Series([solve_one([tuple(e) for e in d], list(f), list(p), "auto", {})[0] for d, f, p in zip(dnf, fids, pis, strict=True)], dtype="float64")


@F.pandas_udf("double")
def noisy_or_agg(p: pd.Series) -> float:
    return float(1 - (1 - p).prod())


@F.udtf(returnType="explanation array<bigint>, size int")
class MinimalExplanations:
    """The absorbed explanations of a formula, one a row, shortest first."""

    def eval(self, dnf: list[list[int]]) -> Iterator[tuple]:
        for e in sorted(absorbed(dnf), key=lambda x: (len(x), sorted(x))):
            yield sorted(e), len(e)


_FORMULA = "ARRAY<ARRAY<BIGINT>>"
#: Formulas in SQL, by built-in functions alone.
SQL_FUNCTIONS = {
    "dnf_or": "array_union(a, b)",
    "dnf_and": "flatten(transform(a, x -> transform(b, y -> array_sort(array_union(x, y)))))",
    "dnf_absorb": "array_sort(filter(array_distinct(transform(a, e -> array_sort(array_distinct(e)))), e -> NOT exists(a, f -> size(array_distinct(f)) < size(e) AND size(array_except(f, e)) = 0)))",
}


def register(spark: SparkSession) -> None:
    for name, body in SQL_FUNCTIONS.items():
        arguments = f"a {_FORMULA}" + ("" if name == "dnf_absorb" else f", b {_FORMULA}")
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {_FORMULA} RETURN {body}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION dnf_equal(a {_FORMULA}, b {_FORMULA}) RETURNS BOOLEAN RETURN dnf_absorb(a) <=> dnf_absorb(b)")
    spark.udf.register("dnf_probability", dnf_probability)
    spark.udf.register("noisy_or_agg", noisy_or_agg)
    spark.udtf.register("minimal_explanations", MinimalExplanations)
