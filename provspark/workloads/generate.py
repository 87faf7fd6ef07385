"""Random conjunctive queries over a program: seeded walks over atoms that share a variable."""

from __future__ import annotations

import random

from ..rules import Atom, Program, Query, Var


def generate_queries(program: Program, n: int = 50, atoms: tuple[int, int] = (1, 4), seed: int = 0) -> list[Query]:
    rng = random.Random(seed)
    arity = {a.pred: len(a.args) for r in program.rules for a in (r.head, *r.body)}
    preds = sorted(arity)
    out = []
    for q in range(n):
        body, names = [], 0
        for i in range(rng.randint(*atoms)):
            pred = rng.choice(preds)
            args = [Var(f"X{names + j}") for j in range(arity[pred])]
            names += arity[pred]
            if i:
                known = [v for a in body for v in a.variables]
                args[rng.randrange(len(args))] = Var(rng.choice(known))
            body.append(Atom(pred, tuple(args)))
        free = list(dict.fromkeys(v for a in body for v in a.variables))
        out.append(Query(Atom(f"gen{q}", tuple(Var(v) for v in sorted(rng.sample(free, min(2, len(free)))))), tuple(body)))
    return out
