"""From a rule body to a join: the one place where rules become DataFrames, shared by all engines."""

from __future__ import annotations

import re
from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..rules import Atom, Rule, RuleTypeError, Var


class RoundLimit(RuntimeError):
    """A fixpoint was not reached in the rounds allowed."""


def rounds(first: int, most: int | None):
    """first, first + 1, ...: where more than ``most`` rounds are asked for, RoundLimit."""
    depth = first
    while most is None or depth <= most:
        yield depth
        depth += 1
    raise RoundLimit(f"not at the fixpoint after {most} rounds")


@dataclass
class Shape:
    """Rules that differ in their constants only, run as one plan: the constants are a small table of parameters."""

    rule: Rule
    ids: list[str]
    constants: list[tuple] = field(default_factory=list)

    @property
    def merged(self) -> bool:
        return len(self.ids) > 1

    def parameters(self, spark) -> DataFrame:
        """rule, a0..: as many rows as rules."""
        return F.broadcast(spark.createDataFrame([(i, *c) for i, c in zip(self.ids, self.constants, strict=True)], ["rule", *(f"a{i}" for i in range(len(self.constants[0])))]))

    def joined(self, inputs: Sequence[tuple[DataFrame, Sequence[str]]], order: Sequence[int] | None = None, payload: bool = False) -> DataFrame:
        """The body's join; with ``payload`` a merged shape has its rules' ids in ``rule_id``."""
        if not self.merged:
            return join_body(self.rule, inputs, order=order)
        names = tuple(Var(f"_k{i}") for i in range(len(self.constants[0])))
        wide = Rule(self.rule.id, self.rule.head, (*self.rule.body, Atom("_parameters", names)))
        at = len(self.rule.body)
        order = list(order or range(at))
        spark = inputs[0][0].sparkSession
        return join_body(wide, [*inputs, (self.parameters(spark), ["rule"] if payload else [])], order=[order[0], at, *order[1:]] if _meets(wide, order[0], at) else [*order, at]).withColumnsRenamed({f"rule_{at}": "rule_id"})


def _meets(rule: Rule, i: int, j: int) -> bool:
    return bool(set(rule.body[i].variables) & set(rule.body[j].variables))


def shapes(rules: Sequence[Rule]) -> list[Shape]:
    """Rules grouped by what is left when constants are taken out; only bodies with a constant are merged."""
    groups: dict[tuple, list[tuple[Rule, Rule, tuple]]] = {}
    for rule in rules:
        constants: list = []
        names: dict[str, Var] = {}

        def bare(atom: Atom, constants=constants, names=names) -> Atom:
            args = []
            for a in atom.args:
                if isinstance(a, Var):
                    args.append(names.setdefault(a.name, Var(f"V{len(names)}")))
                else:
                    args.append(Var(f"_k{len(constants)}"))
                    constants.append(a)
            return Atom(atom.pred, tuple(args))

        body = tuple(bare(a) for a in rule.body)
        in_body = len(constants)
        plain = Rule(rule.id, bare(rule.head), body)
        key = (plain.head, plain.body, tuple(type(c) for c in constants)) if in_body else (rule.id, rule)
        groups.setdefault(key, []).append((rule, plain, tuple(constants)))
    out = []
    for own in groups.values():
        if len(own) == 1:
            out.append(Shape(own[0][0], [own[0][0].id]))
        else:
            out.append(Shape(own[0][1], [r.id for r, _, _ in own], [c for _, _, c in own]))
    return out


def argument_types(program) -> dict[str, list[str]]:
    """Column types of every predicate, carried from the facts through the rules (unknown ones are strings)."""
    types = {p: [df.schema[a].dataType.simpleString() for a in arguments(df)] for p, df in program.facts.items()}
    for _ in range(len(program.rules) + 1):
        for rule in program.rules:
            known = {a.name: t for atom in rule.body for a, t in zip(atom.args, types.get(atom.pred, ()), strict=False) if isinstance(a, Var)}
            own = [known.get(a.name) if isinstance(a, Var) else {int: "bigint", float: "double"}.get(type(a), "string") for a in rule.head.args]
            if None not in own:
                types.setdefault(rule.head.pred, own)
    for rule in program.rules:
        types.setdefault(rule.head.pred, ["string"] * len(rule.head.args))
    return types


def arguments(df: DataFrame) -> list[str]:
    return sorted((c for c in df.columns if re.fullmatch(r"a\d+", c)), key=lambda c: int(c[1:]))


def atom_rows(atom: Atom, df: DataFrame, payload: Sequence[str], tag: str, shared: Sequence[str] = ()) -> DataFrame:
    """Rows of df that fit the atom: a column per variable, payload columns with a tag, shared columns by their name.

    Constants become filters that reach the scan; a variable that repeats becomes an equality.
    """
    keep, first = None, {}
    for i, a in enumerate(atom.args):
        test: Column | None = None
        if not isinstance(a, Var):
            test = F.col(f"a{i}") == F.lit(a)
        elif a.name in first:
            test = F.col(f"a{i}") == F.col(f"a{first[a.name]}")
        else:
            first[a.name] = i
        if test is not None:
            keep = test if keep is None else keep & test
    df = df if keep is None else df.where(keep)
    return df.select(*(F.col(f"a{i}").alias(f"v_{v}") for v, i in first.items()), *(F.col(p).alias(f"{p}_{tag}") for p in payload), *shared)


def join_body(rule: Rule, inputs: Sequence[tuple[DataFrame, Sequence[str]]], shared: Sequence[str] = (), order: Sequence[int] | None = None) -> DataFrame:
    """Join of the body: inputs are (table, payload columns) per atom; ``shared`` columns are join keys everywhere.

    Atoms are joined in ``order`` (the changed one first); of the rest, one that shares a variable goes before one that
    does not, so that a product is taken only where the rule has one.
    """
    left = list(order or range(len(rule.body)))
    out: DataFrame | None = None
    while left:
        have = set(out.columns) if out is not None else set()
        at = next((i for i in left if out is None or any(f"v_{v}" in have for v in rule.body[i].variables)), left[0])
        left.remove(at)
        df, payload = inputs[at]
        rows = atom_rows(rule.body[at], df, payload, str(at), shared)
        if out is None:
            out = rows
            continue
        keys = [f"v_{v}" for v in rule.body[at].variables if f"v_{v}" in have] + list(shared)
        for k in keys:
            if _kind(out, k) != _kind(rows, k):
                raise RuleTypeError(f"{rule}: {k[2:]} is {out.schema[k].dataType.simpleString()} and {rows.schema[k].dataType.simpleString()}")
        out = out.join(rows, keys) if keys else out.crossJoin(rows)
    return out


def _kind(df: DataFrame, column: str) -> str:
    kind = df.schema[column].dataType.simpleString()
    return "number" if kind in ("int", "bigint", "smallint", "tinyint") else kind


def head_columns(rule: Rule, prefix: str = "a") -> list[Column]:
    return [(F.col(f"v_{a.name}") if isinstance(a, Var) else F.lit(a)).alias(f"{prefix}{i}") for i, a in enumerate(rule.head.args)]


def derived_positions(rule: Rule, derived: set[str]) -> list[int]:
    return [i for i, a in enumerate(rule.body) if a.pred in derived]


def union(frames: Sequence[DataFrame]) -> DataFrame:
    """Union by name; integers of different width meet as longs."""
    frames = list(frames)
    kinds = [{f.schema[c].dataType.simpleString() for f in frames} for c in frames[0].columns]
    for c, k in zip(frames[0].columns, kinds, strict=True):
        if len(k) > 1:
            if not k <= {"int", "bigint", "smallint", "tinyint"}:
                raise RuleTypeError(f"{c} is {' and '.join(sorted(k))}")
            frames = [f.withColumn(c, F.col(c).cast("long")) for f in frames]
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out
