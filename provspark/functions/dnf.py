"""Monotone formulas in disjunctive normal form, as sorted arrays of sorted arrays of fact ids, in built-in functions.

Absorbed formulas are canonical: two monotone formulas are equivalent if and only if these arrays are equal.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

DNF = "array<array<bigint>>"


#: Explanations of more facts than this are compared one by one: they have too many subsets.
PRINTED = 8


def _print(e: Column) -> Column:
    """A hash of an explanation as a set; as with fact ids, equal hashes count as equal sets."""
    return F.aggregate(e, F.lit(0).cast("bigint"), lambda h, x: h.bitwiseXOR(F.xxhash64(x)))


def _subset_prints(e: Column) -> Column:
    """Hashes of all subsets of an explanation, its own the last."""
    none = F.array(F.lit(0).cast("bigint"))
    return F.aggregate(F.transform(e, lambda x: F.xxhash64(x)), none, lambda own, h: F.concat(own, F.transform(own, lambda p: p.bitwiseXOR(h))))


def _smaller_prints(e: Column) -> Column:
    return bound(_subset_prints(e), lambda all: F.slice(all, 1, F.size(all) - 1))


def dnf_absorb(a: Column) -> Column:
    """Sorted distinct disjuncts of which none contains another."""
    # sorted, equal ones are neighbours: array_distinct would compare each with each
    ordered = F.array_sort(F.transform(a, lambda e: F.array_sort(F.array_distinct(e))))
    once = bound(ordered, lambda all: F.filter(all, lambda e, i: (i == 0) | (e != F.get(all, i - 1))))

    def minimal(every: Column) -> Column:
        sizes = F.transform(every, F.size)
        # by size, each is compared with the smaller ones kept so far, up to the first fact that it lacks
        ordered = F.array_sort(F.transform(every, lambda e: F.struct(F.size(e).alias("n"), e.alias("e"))))
        within = lambda f, s: (F.size(f) < s["n"]) & F.forall(f, lambda x: F.array_contains(s["e"], x))
        least = F.aggregate(ordered, F.array().cast(DNF), lambda kept, s: F.when(F.exists(kept, lambda f: within(f, s)), kept).otherwise(F.concat(kept, F.array(s["e"]))))
        # many with few facts each: the subsets of all are looked up at once, and mostly none is there
        below = F.array_intersect(F.flatten(F.transform(every, _smaller_prints)), F.transform(every, _print))
        looked_up = bound(below, lambda found: F.when(F.size(found) == 0, every).otherwise(F.filter(every, lambda e: ~F.arrays_overlap(_smaller_prints(e), found))))
        # disjuncts of one size cannot contain each other: nothing to compare
        few_facts = (F.array_max(sizes) <= PRINTED) & (F.size(every) > 12)
        return F.when(F.array_min(sizes) == F.array_max(sizes), every).when(few_facts, looked_up).otherwise(least)

    return F.array_sort(bound(once, minimal))


def dnf_and(a: Column, b: Column) -> Column:
    return F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: F.array_sort(F.array_union(x, y)))))


def dnf_or(a: Column, b: Column) -> Column:
    return F.array_union(a, b)


def dnf_equal(a: Column, b: Column) -> Column:
    return dnf_absorb(a).eqNullSafe(dnf_absorb(b))


def dnf_implied(a: Column, b: Column) -> Column:
    """Whether every disjunct of a contains one of b."""
    # those that b has as they are need no search; of the others, subsets are looked up
    few_facts = F.forall(a, lambda e: F.size(e) <= PRINTED)
    looked_up = bound(F.transform(b, _print), lambda known: F.forall(a, lambda e: F.arrays_overlap(_subset_prints(e), known)))
    own = F.size(F.array_except(F.transform(a, _print), F.transform(b, _print))) == 0
    searched = F.forall(a, lambda e: F.exists(b, lambda f: F.size(F.array_except(f, e)) == 0))
    return F.when(own, F.lit(True)).when(few_facts, looked_up).otherwise(searched)


def dnf_vars(a: Column) -> Column:
    return F.array_sort(F.array_distinct(F.flatten(a)))


def one() -> Column:
    """The formula that is always true."""
    return F.array(F.array().cast("array<bigint>"))


def single(fid: Column) -> Column:
    return F.array(F.array(fid))


def union_agg(column: str) -> Column:
    """Absorbed disjunction over a group."""
    return dnf_absorb(F.flatten(F.collect_set(column)))


def noisy_or(p: Column) -> Column:
    return F.lit(1.0) - F.product(F.lit(1.0) - p)


def noisy_and(p: Column) -> Column:
    return F.product(p)


def expl_score(e: Column, pis: Column) -> Column:
    """Product of the probabilities (a map by fact id) of an explanation."""
    return F.aggregate(e, F.lit(1.0), lambda s, x: s * pis[x])


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda u, v: u.cast("double") * v), F.lit(0.0), lambda s, z: s + z)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def bound(a: Column, f) -> Column:
    """f of a, with a computed once: an expression that a lambda uses is computed again for every element."""
    return F.transform(F.array(a), f)[0]


def softmax(a: Column) -> Column:
    def shares(e: Column) -> Column:
        return bound(F.aggregate(e, F.lit(0.0), lambda s, y: s + y), lambda total: F.transform(e, lambda x: x / total))

    def powers(z: Column) -> Column:
        return bound(F.array_max(z), lambda most: F.transform(z, lambda x: F.exp(x - most)))

    return bound(a, lambda z: bound(powers(z), shares))


def dnf_prob_columns(formulas, facts):
    """``prob`` of formulas whose explanations share no fact, in built-in functions: joins and products."""
    keys = [c for c in formulas.columns if c != "dnf"]
    each = formulas.select(*keys, F.posexplode("dnf").alias("e", "fids")).select(*keys, "e", F.explode("fids").alias("fid"))
    weighed = each.join(facts, "fid").groupBy(*keys, "e").agg(F.product("pi").alias("p"))
    return weighed.groupBy(*keys).agg(noisy_or(F.col("p")).alias("prob"))
