"""Rules, programs and queries: parsing, checks, normal form, rule probabilities and query-directed rewriting.

Syntax: upper-case names are variables, ``'quoted'`` or lower-case names and numbers are constants, ``%`` begins a
comment, ``0.7::`` before a rule or fact is its probability.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace
from typing import Any


class RuleError(ValueError):
    """An unsafe, ill-typed or ill-formed rule."""


class RuleTypeError(RuleError):
    """Columns of different types meet in one variable."""


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class Atom:
    pred: str
    args: tuple[Any, ...]

    @property
    def variables(self) -> list[str]:
        return list(dict.fromkeys(a.name for a in self.args if isinstance(a, Var)))

    def __str__(self) -> str:
        return f"{self.pred}({', '.join(a.name if isinstance(a, Var) else repr(a) for a in self.args)})"


@dataclass(frozen=True)
class Rule:
    id: str
    head: Atom
    body: tuple[Atom, ...]
    prob: float | None = None

    def __str__(self) -> str:
        return f"{self.head} :- {', '.join(map(str, self.body))}."


@dataclass(frozen=True)
class Fact:
    atom: Atom
    pi: float = 1.0


@dataclass
class Program:
    """Rules over base predicates; ``facts`` maps each of these to a table of columns a0.., pi, fid.

    ``guards`` are base predicates of certain facts that a rule's head determines: they stand in no explanation.
    """

    rules: list[Rule]
    facts: dict[str, Any] = field(default_factory=dict)
    guards: frozenset[str] = frozenset()

    @property
    def derived(self) -> set[str]:
        return {r.head.pred for r in self.rules}

    def with_rules(self, rules: list[Rule]) -> Program:
        return Program(rules, self.facts, self.guards)


_TOKEN = re.compile(r"\s*(?:(%[^\n]*)|('(?:[^'\\]|\\.)*')|(-?\d+\.\d+|-?\d+)|([A-Za-z_]\w*)|(:-|::|[(),.]))")


def _tokens(text: str) -> list[tuple[str, str]]:
    out, at, text = [], 0, text.rstrip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise RuleError(f"cannot read {text[at : at + 30]!r}")
        kind = ("comment", "string", "number", "name", "sign")[m.lastindex - 1]
        if kind != "comment":
            out.append((kind, m[m.lastindex]))
        at = m.end()
    return out


class _Reader:
    def __init__(self, text: str):
        self.items, self.at = _tokens(text), 0

    def peek(self) -> str:
        return self.items[self.at][1] if self.at < len(self.items) else ""

    def take(self, wanted: str | None = None) -> tuple[str, str]:
        if self.at >= len(self.items) or wanted and self.items[self.at][1] != wanted:
            raise RuleError(f"expected {wanted or 'more'}, found {self.peek() or 'the end'}")
        self.at += 1
        return self.items[self.at - 1]

    def term(self) -> Any:
        kind, value = self.take()
        if kind == "string":
            return value[1:-1].replace("\\'", "'")
        if kind == "number":
            return float(value) if "." in value else int(value)
        if kind != "name":
            raise RuleError(f"{value!r} is no term")
        return Var(value) if value[0].isupper() or value[0] == "_" else value

    def atom(self) -> Atom:
        name, args = self.take()[1], []
        self.take("(")
        while True:
            args.append(self.term())
            if self.take()[1] == ")":
                return Atom(name, tuple(args))


def parse(text: str, prefix: str = "r") -> tuple[list[Rule], list[Fact]]:
    """Rules and facts of a text; rules are numbered with ``prefix``."""
    reader, rules, facts = _Reader(text), [], []
    while reader.at < len(reader.items):
        prob = None
        if reader.at + 1 < len(reader.items) and reader.items[reader.at + 1][1] == "::":
            prob = float(reader.take()[1])
            reader.take("::")
        head = reader.atom()
        if reader.take()[1] == ":-":
            body = [reader.atom()]
            while reader.take()[1] == ",":
                body.append(reader.atom())
            rules.append(checked(Rule(f"{prefix}{len(rules) + 1}", head, tuple(body), prob)))
        else:
            if head.variables:
                raise RuleError(f"{head} is no fact")
            facts.append(Fact(head, 1.0 if prob is None else prob))
    return rules, facts


def rules(text: str, prefix: str = "r") -> list[Rule]:
    return parse(text, prefix)[0]


def checked(rule: Rule) -> Rule:
    bound = {v for a in rule.body for v in a.variables}
    loose = [v for v in rule.head.variables if v not in bound]
    if loose:
        raise RuleError(f"{rule}: {', '.join(loose)} in the head only")
    if not rule.body:
        raise RuleError(f"{rule}: no body")
    return rule


def check_program(program: Program) -> None:
    arity: dict[str, int] = {p: sum(bool(re.fullmatch(r"a\d+", c)) for c in df.columns) for p, df in program.facts.items()}
    for rule in program.rules:
        for atom in (rule.head, *rule.body):
            if arity.setdefault(atom.pred, len(atom.args)) != len(atom.args):
                raise RuleError(f"{atom} has {len(atom.args)} arguments, {atom.pred} has {arity[atom.pred]}")
    known = set(program.facts) | program.derived
    for rule in program.rules:
        for atom in rule.body:
            if atom.pred not in known:
                raise RuleError(f"{rule}: nothing is known of {atom.pred}")


def normalize(program: Program) -> Program:
    """Plan-graph normal form: a predicate with both facts and rules gets a bridge rule from its facts."""
    check_program(program)
    both = sorted(program.derived & set(program.facts))
    facts = {(f"{p}__base" if p in both else p): df for p, df in program.facts.items()}
    bridges = []
    for p in both:
        n = sum(bool(re.fullmatch(r"a\d+", c)) for c in program.facts[p].columns)
        xs = tuple(Var(f"X{i}") for i in range(n))
        bridges.append(Rule(f"bridge_{p}", Atom(p, xs), (Atom(f"{p}__base", xs),)))
    return Program([*program.rules, *bridges], facts, program.guards)


def with_rule_probability(rule: Rule, scope: str = "rule") -> tuple[Rule, Atom]:
    """The rule with an extra base atom: one coin for the rule, or one per head binding (scope ``grounding``)."""
    args = (rule.id,) if scope == "rule" else (rule.id, *rule.head.args)
    coin = Atom(f"coin_{rule.id}" if scope == "grounding" else "rule_on", args)
    return replace(rule, body=(*rule.body, coin), prob=None), coin


@dataclass(frozen=True)
class Query:
    """A conjunctive query: a fresh head predicate over the program."""

    head: Atom
    body: tuple[Atom, ...]

    @staticmethod
    def parse(text: str) -> Query:
        rule = rules(text)[0]
        return Query(rule.head, rule.body)

    def rule(self) -> Rule:
        return checked(Rule(f"query_{self.head.pred}", self.head, self.body))


def adorned(program: Program, query: Query) -> tuple[list[Rule], list[Rule], str]:
    """Query-directed rewriting: (rules on demand-carrying predicates, demand rules, seed predicate).

    Bindings pass from atom to atom: next is one that shares a bound variable, of these one with most bound places, left
    to right.  A predicate p with bound positions b becomes ``p__bf..``; ``need_p__bf`` holds the bindings that the query asks for.
    """
    derived = program.derived
    done: set[tuple[str, str]] = set()
    todo: list[tuple[str, str]] = []
    out, demand = [], []

    def name(pred: str, pattern: str) -> str:
        return f"{pred}__{pattern}"

    def body_of(rule: Rule, bound: set[str], guard: Atom | None) -> tuple[Atom, ...]:
        body: list[Atom] = [guard] if guard else []
        left = list(rule.body)
        while left:
            atom = min(left, key=lambda a: (not bound & set(a.variables), -sum(not isinstance(x, Var) or x.name in bound for x in a.args)))
            left.remove(atom)
            if atom.pred in derived:
                pattern = "".join("b" if not isinstance(a, Var) or a.name in bound else "f" for a in atom.args)
                if (atom.pred, pattern) not in done:
                    done.add((atom.pred, pattern))
                    todo.append((atom.pred, pattern))
                keys = tuple(a for a, x in zip(atom.args, pattern, strict=True) if x == "b")
                need = Atom(f"need_{name(atom.pred, pattern)}", keys or (0,))
                if body:
                    demand.append(Rule(f"demand{len(demand) + 1}", need, tuple(body)))
                else:
                    demand.append(Rule(f"demand{len(demand) + 1}", need, (Atom("need_seed", (0,)),)))
                atom = Atom(name(atom.pred, pattern), atom.args)
            body.append(atom)
            bound |= set(atom.variables)
        return tuple(body)

    goal = query.rule()
    top = Rule(goal.id, goal.head, body_of(goal, set(), None))
    out.append(top)
    while todo:
        pred, pattern = todo.pop(0)
        for rule in (r for r in program.rules if r.head.pred == pred):
            keys = tuple(a for a, x in zip(rule.head.args, pattern, strict=True) if x == "b")
            guard = Atom(f"need_{name(pred, pattern)}", keys or (0,))
            bound = {a.name for a in keys if isinstance(a, Var)}
            body = body_of(rule, bound, guard)
            out.append(Rule(f"{rule.id}__{pattern}", Atom(name(pred, pattern), rule.head.args), body, rule.prob))
    return out, demand, "need_seed"


def _plain(value: Any) -> Any:
    """A constant as joins compare it: numbers of all types, and texts that read as numbers, by their value."""
    try:
        number = float(value)
    except (TypeError, ValueError):
        return value
    return number if number == number else "nan"


def firing(rules: list[Rule], base: set[str]) -> list[Rule]:
    """The rules that can make a fact, by the constants that rules alone can put at each place of a derived predicate.

    A place of a base predicate, or one that a variable bound there reaches, may hold anything (None).
    """
    values: dict[str, list[set | None]] = {}
    fired: set[int] = set()
    while True:
        before = (len(fired), sum(len(v) if v is not None else 1_000_000 for own in values.values() for v in own))
        for at, rule in enumerate(rules):
            bound: dict[str, set | None] = {}
            for atom in rule.body:
                own = [None] * len(atom.args) if atom.pred in base else values.get(atom.pred)
                if own is None:
                    break
                for arg, v in zip(atom.args, own, strict=True):
                    if isinstance(arg, Var):
                        known = bound.get(arg.name)
                        bound[arg.name] = known if v is None else set(v) if known is None else known & v
                        if bound[arg.name] is not None and not bound[arg.name]:
                            break
                    elif v is not None and _plain(arg) not in v:
                        break
                else:
                    continue
                break
            else:
                fired.add(at)
                head = [bound.get(a.name) if isinstance(a, Var) else {_plain(a)} for a in rule.head.args]
                old = values.get(rule.head.pred)
                values[rule.head.pred] = head if old is None else [None if a is None or b is None else a | b for a, b in zip(old, head, strict=True)]
        if before == (len(fired), sum(len(v) if v is not None else 1_000_000 for own in values.values() for v in own)):
            return [r for at, r in enumerate(rules) if at in fired]


def strata(rules: list[Rule]) -> list[list[set[str]]]:
    """Derived predicates in groups that depend on each other, in levels of which each reads earlier ones only."""
    reads: dict[str, set[str]] = {r.head.pred: set() for r in rules}
    for r in rules:
        reads[r.head.pred] |= {a.pred for a in r.body if a.pred in reads}
    reach = {}
    for p in reads:
        seen, todo = set(), [p]
        while todo:
            new = reads[todo.pop()] - seen
            seen |= new
            todo += new
        reach[p] = seen
    groups: list[set[str]] = []
    for p in reads:
        if not any(p in g for g in groups):
            groups.append({p} | {q for q in reach[p] if p in reach[q]})
    out, done = [], set()
    while len(done) < len(reads):
        level = [g for g in groups if not g & done and set().union(*(reads[p] for p in g)) <= done | g]
        out.append(level)
        done |= set().union(*level)
    return out
