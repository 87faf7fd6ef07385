"""Exact Jaccard self-join of word n-gram sets by universe partition and the pigeonhole principle.

Sizes fall into bands such that a set and any partner of it lie in the same band or in neighbouring ones; the space of a
band joins its sets with each other and with those of the band above.  In a space, a hash deals the universe of n-grams
into segments.  Two sets with a similarity of t differ in at most H elements, so some of M > H segments are equal - or,
if M > H / 2, some differ by one element at most, which the one-deletion neighbourhoods of both catch.  For each space
the cheaper of the two allocations is taken, by the number of signatures that it makes.

Segments of one element or none say little and make large buckets.  A set leaves them out where enough others remain
for the pigeonhole argument; where even the non-empty segments don't suffice, the set adds the elements of its prefix
(in hash order) as signatures, which meets every partner that is in the same case.

Sets that are equal are one class from the start.  Classes are met in buckets of packed arrays: each class is compared
with the least of its group, verified on the whole sets, and the links contracted to components.  Only groups that still hold
several components are then compared pair by pair, across components, behind an exact bound on the difference.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, ids_and_texts, slices, stored
from .components import components

#: Contract: five words, 80 % - compared in whole numbers.
WORDS, SHARE, OF = 5, 80, 100
#: Signatures that a bucket should hold, that a task packs at a time, and classes a task remembers to have packed.
PER_BUCKET, PACKED, REMEMBERED = 1 << 20, 1 << 20, 1 << 20
#: Coarse counts of a set, for the bound on the difference.
CELLS = 512
#: Nearest members of other components that a member is compared with before all that the bound allows.
NEAREST = 3
#: Bits of the filter on candidate documents: a size that does not grow.
FILTER_BITS = 1 << 26

_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * _B
    x = (x ^ (x >> np.uint64(29))) * _A
    return x ^ (x >> np.uint64(32))


@lru_cache(maxsize=1)
def bands(most: int = 1 << 34) -> np.ndarray:
    """Least size of each band: partners of a band's sets lie at most one band above."""
    lows = [1]
    while lows[-1] < most:
        lows.append(max(lows[-1] + 1, OF * (lows[-1] - 1) // SHARE + 1))
    return np.array(lows, np.int64)


def difference(a, b):
    """Most elements in which sets of sizes a and b that link can differ."""
    return (OF - SHARE) * (a + b) // (OF + SHARE)


@lru_cache(maxsize=4096)
def allocation(band: int) -> tuple[int, int]:
    """(segments, deletions 0 or 1) of a band's space: the allocation of fewer signatures."""
    low, high = int(bands()[band]), int(bands()[band + 1]) - 1
    most = int(difference(high, OF * high // SHARE))

    def segments(need: int, few: int) -> int:
        m = need
        while True:  # room for the segments of at most ``few`` elements that a set of least size is likely to have
            load = low / m
            share = np.exp(-load) * (1 + load * few)
            if m >= need + m * share + 2 * np.sqrt(m * share) or m > 4 * need + 8:
                return m
            m += max(1, m // 64)

    exact, near = segments(most + 1, 0), segments(most // 2 + 1, 1)
    return (exact, 0) if exact <= near + high or high > 64 else (near, 1)


class Sets:
    """The n-gram sets of a slice of texts: ``items[starts[i]:starts[i + 1]]`` are the hashes of text i, ascending."""

    def __init__(self, texts: pa.Array, n: int = WORDS):
        words = Words(texts)
        coded = pd.util.hash_array(words.values.to_numpy(zero_copy_only=False)) if len(words.values) else np.zeros(0, np.uint64)
        hashes = coded.astype(np.uint64)[words.codes]
        multipliers = mixed(np.arange(1, n + 1, dtype=np.uint64) * _A) | np.uint64(1)
        grams = np.zeros(max(0, len(hashes) - n + 1), np.uint64)
        for k in range(n):
            grams += hashes[k : k + len(grams)] * multipliers[k]
        grams = mixed(grams)
        parts, sizes = [], np.zeros(len(words.counts), np.int64)
        for i, (a, count) in enumerate(zip(words.starts.tolist(), words.counts.tolist(), strict=False)):
            if count >= n:
                parts.append(np.unique(grams[a : a + count - n + 1]))
            elif count:  # the whole short text is one element, told apart by its length
                parts.append(mixed((hashes[a : a + count] * multipliers[:count]).sum(keepdims=True, dtype=np.uint64) + np.uint64(count)))
            else:
                continue
            sizes[i] = len(parts[-1])
        self.items = np.concatenate(parts) if parts else np.zeros(0, np.uint64)
        self.sizes = sizes
        self.starts = np.concatenate([[0], np.cumsum(sizes)])

    def classes(self) -> np.ndarray:
        """A hash of each set (0: empty)."""
        out = np.zeros(len(self.sizes), np.uint64)
        full = self.sizes > 0
        if full.any():
            out[full] = mixed(np.add.reduceat(mixed(self.items + _A), self.starts[:-1][full]) + self.sizes[full].astype(np.uint64)) | np.uint64(1)
        return out

    def cells(self) -> np.ndarray:
        owner = np.repeat(np.arange(len(self.sizes)), self.sizes)
        flat = owner * CELLS + (self.items >> np.uint64(40)).astype(np.int64) % CELLS
        return np.minimum(np.bincount(flat, minlength=len(self.sizes) * CELLS), 255).astype(np.uint8).reshape(-1, CELLS)


def signatures(sets: Sets, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(position in which, signature) of the sets at ``which``."""
    lows = bands()
    band = np.searchsorted(lows, sets.sizes[which], "right") - 1
    owners, found = [], []
    for up in (0, 1):  # the space of the set's own band, and that of the band below
        space = band - up
        for s in np.unique(space[space >= 0]).tolist():
            at = np.flatnonzero(space == s)
            who, sig = _in_space(sets, which[at], s, up)
            owners.append(at[who])
            found.append(sig)
    return (np.concatenate(owners), np.concatenate(found)) if owners else (np.zeros(0, np.int64), np.zeros(0, np.uint64))


def _in_space(sets: Sets, which: np.ndarray, space: int, up: int) -> tuple[np.ndarray, np.ndarray]:
    segments, deletions = allocation(space)
    sizes = sets.sizes[which]
    high = int(bands()[space + 1]) - 1
    differ = difference(sizes, np.minimum(sizes, high) if up else OF * sizes // SHARE)
    starts = sets.starts[which]
    inner = np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    items = sets.items[np.repeat(starts, sizes) + inner]
    owner = np.repeat(np.arange(len(which)), sizes)
    cell = owner * segments + (mixed(items + np.uint64(space)) >> np.uint64(20)).astype(np.int64) % segments
    codes = mixed(items + _B)
    n_cells = len(which) * segments
    load = np.bincount(cell, minlength=n_cells)
    low = np.bincount(cell, (codes & np.uint64(0xFFFFFFFF)).astype(float), n_cells)
    top = np.bincount(cell, (codes >> np.uint64(32)).astype(float), n_cells)
    total = low.astype(np.uint64) + (top.astype(np.uint64) << np.uint64(32))
    salt = mixed(np.full(segments, space, np.uint64) * _A + np.arange(segments, dtype=np.uint64))
    per_set = load.reshape(-1, segments)
    none, few = (per_set == 0).sum(1), (per_set <= 1).sum(1)
    room = segments - (differ // 2 if deletions else differ) - 1
    least = np.where(few <= room, 2, 1) if not deletions else np.ones(len(which), np.int64)
    short = (few if deletions else none) > room
    use = np.flatnonzero(load >= np.repeat(least, segments))
    owners, found = [use // segments], [mixed(total[use] + salt[use % segments])]
    if deletions:
        many = np.flatnonzero(load[cell] >= 2)
        owners.append(owner[many])
        found.append(mixed(total[cell[many]] - codes[many] + salt[cell[many] % segments]))
    if short.any():  # the prefix, in hash order, has no band
        prefix = sizes - (SHARE * sizes + OF - 1) // OF + 1
        pick = np.flatnonzero(np.repeat(short, sizes) & (inner < np.repeat(prefix, sizes)))
        owners.append(owner[pick])
        found.append(mixed(items[pick] + _A))
    return np.concatenate(owners), np.concatenate(found)


_SIGNED = "bucket int, doc_id long, n long, class long, cells binary, pack binary"


def _sign(n_buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            sig, who = (np.concatenate([h[i] for h in held]) for i in (0, 1))
            bucket = (sig >> np.uint64(32)) % np.uint64(n_buckets)
            order = np.argsort(bucket, kind="stable")
            used, begins = np.unique(bucket[order], return_index=True)
            short, who = (sig & np.uint64(0xFFFFFFFF)).astype("<u4")[order], who.astype("<u8")[order]
            ends = [*begins[1:].tolist(), len(order)]
            packs = [short[a:b].tobytes() + who[a:b].tobytes() for a, b in zip(begins.tolist(), ends, strict=True)]
            k = len(packs)
            return pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.binary()), pa.array(packs, pa.binary())], ["bucket", "doc_id", "n", "class", "cells", "pack"])

        for batch in slices(batches):
            sets = Sets(pc.fill_null(batch.column("text"), ""))
            classes, k = sets.classes(), batch.num_rows
            spread = (classes % np.uint64(n_buckets)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(spread), batch.column("doc_id"), pa.array(sets.sizes), pa.array(classes.view(np.int64)), pa.array([x.tobytes() for x in sets.cells()], pa.binary()), pa.nulls(k, pa.binary())], ["bucket", "doc_id", "n", "class", "cells", "pack"])
            first = np.unique(classes, return_index=True)[1]
            fresh = np.array([i for i in first.tolist() if classes[i] and int(classes[i]) not in seen], np.int64)
            if len(seen) > REMEMBERED:
                seen.clear()
            seen.update(classes[fresh].tolist())
            if len(fresh):
                who, sig = signatures(sets, fresh)
                held.append((sig, classes[fresh][who]))
                size += len(sig)
            if size >= PACKED:
                yield flush()
                held, size = [], 0
        if held:
            yield flush()

    return run


_MET = "kind string, doc_id long, n long, class long, other long, cells binary, members binary"


def _meet_bucket(packs: list[bytes]) -> tuple[np.ndarray, np.ndarray, list[bytes], np.ndarray]:
    """Pairs (class, least class of its group), and the groups of three or more with that least class."""
    sig = np.concatenate([np.frombuffer(p, "<u4", len(p) // 12) for p in packs])
    who = np.concatenate([np.frombuffer(p, "<u8", len(p) // 12, len(p) // 12 * 4) for p in packs])
    order = np.argsort(sig, kind="stable")
    sig, who = sig[order], who[order]
    same = sig[1:] == sig[:-1]
    keep = np.concatenate([same, [False]]) | np.concatenate([[False], same])
    sig, who = sig[keep], who[keep]
    order = np.lexsort((who, sig))
    sig, who = sig[order], who[order]
    fresh = np.ones(len(sig), bool)
    fresh[1:] = (sig[1:] != sig[:-1]) | (who[1:] != who[:-1])
    sig, who = sig[fresh], who[fresh]
    begins = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]])) if len(sig) else np.zeros(0, np.int64)
    sizes = np.diff(np.append(begins, len(sig)))
    head = np.repeat(who[begins], sizes)
    apart = who != head
    pairs = np.unique(np.stack([who[apart], head[apart]]), axis=1) if apart.any() else np.zeros((2, 0), np.uint64)
    large = np.flatnonzero(sizes >= 3)
    if not len(large):
        return pairs[0], pairs[1], [], np.zeros(0, np.uint64)
    prints = np.add.reduceat(mixed(who), begins)[large] + sizes[large].astype(np.uint64)
    once = large[np.unique(prints, return_index=True)[1]]
    return pairs[0], pairs[1], [who[begins[g] : begins[g] + sizes[g]].tobytes() for g in once.tolist()], who[begins[once]]


def _met(kind: str, rows: int, /, **columns) -> pa.RecordBatch:
    types = {"doc_id": pa.int64(), "n": pa.int64(), "class": pa.int64(), "other": pa.int64(), "cells": pa.binary(), "members": pa.binary()}
    return pa.RecordBatch.from_arrays([pa.array([kind] * rows), *(columns.get(c, pa.nulls(rows, t)) for c, t in types.items())], ["kind", *types])


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come by bucket; documents pass through, packs of a bucket are joined when the next one begins."""
    bucket, packs = None, []

    def joined() -> Iterator[pa.RecordBatch]:
        a, b, groups, heads = _meet_bucket(packs)
        if len(a):
            yield _met("pair", len(a), **{"class": pa.array(a.view(np.int64)), "other": pa.array(b.view(np.int64))})
        if groups:
            yield _met("group", len(groups), other=pa.array(heads.view(np.int64)), members=pa.array(groups, pa.binary()))

    for batch in batches:
        packed = pc.is_valid(batch.column("pack"))
        plain = batch.filter(pc.invert(packed))
        if plain.num_rows:
            yield _met("doc", plain.num_rows, **{c: plain.column(c) for c in ("doc_id", "n", "class", "cells")})
        rest = batch.filter(packed)
        for b, pack in zip(rest.column("bucket").to_pylist(), rest.column("pack").to_pylist(), strict=True):
            if b != bucket:
                if packs:
                    yield from joined()
                bucket, packs = b, []
            packs.append(pack)
    if packs:
        yield from joined()


def shared(a: np.ndarray, b: np.ndarray) -> int:
    """Common elements of two ascending arrays without repeats."""
    if len(a) > len(b):
        a, b = b, a
    at = np.searchsorted(b, a)
    return int((b[np.minimum(at, len(b) - 1)] == a).sum()) if len(b) else 0


def links(a: np.ndarray, b: np.ndarray) -> bool:
    both = shared(a, b)
    return OF * both >= SHARE * (len(a) + len(b) - both)


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The sets of both sides again, whole, as 64-bit hashes of their elements; a right side that repeats is cut up once."""
    for batch in slices(batches, "a_text", 4 << 20):
        a, b = batch.column("a"), batch.column("b").to_numpy(zero_copy_only=False)
        _, first, at = np.unique(b, return_index=True, return_inverse=True)
        left, right = Sets(batch.column("a_text")), Sets(batch.column("b_text").take(pa.array(first)))
        side = lambda x, i: x.items[x.starts[i] : x.starts[i + 1]]
        good = [links(side(left, i), side(right, j)) for i, j in enumerate(at.tolist())]
        yield pa.RecordBatch.from_arrays([a, batch.column("b"), pa.array(good)], ["a", "b", "good"])


def _place(column: str):
    return F.pmod(F.xxhash64(column), F.lit(FILTER_BITS)) + 1


def _bits(ids: DataFrame) -> np.ndarray:
    """A filter of FILTER_BITS bits on longs: no false negatives, and a row per 32768 bits for the driver at most."""
    parts = ids.select(F.bitmap_bucket_number(_place("id")).alias("part"), F.bitmap_bit_position(_place("id")).alias("bit"))
    out = np.zeros(FILTER_BITS // 8, np.uint8)
    for r in parts.groupBy("part").agg(F.bitmap_construct_agg("bit").alias("bits")).collect():
        out[(r["part"] - 1) * 4096 : r["part"] * 4096] = np.frombuffer(r["bits"], np.uint8)
    return out


def _chosen(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = shared.value
        for batch in batches:
            at = batch.column("place").to_numpy(zero_copy_only=False) - 1
            on = bits[at >> 3] >> (at & 7).astype(np.uint8) & 1
            yield batch.select(["doc_id", "text"]).filter(pa.array(on.astype(bool)))

    return run


def verified(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs (a, b) of doc_ids with ``good``: whether their sets link, by comparison of the whole sets.

    A filter of fixed size keeps most other texts out of the shuffle; the semi-join behind it is exact.
    """
    ids = stored(pairs.select(F.col("a").alias("id")).unionByName(pairs.select(F.col("b").alias("id"))).distinct(), "candidates")
    bits = docs.sparkSession.sparkContext.broadcast(_bits(ids))
    some = docs.select("doc_id", "text", _place("doc_id").alias("place")).mapInArrow(_chosen(bits), "doc_id long, text string")
    texts = stored(some.join(ids.withColumnRenamed("id", "doc_id"), "doc_id", "left_semi"), "candidate-texts")
    sides = pairs.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("a_text")), "a").join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("b_text")), "b")
    return sides.select("a", "b", "a_text", "b_text").sortWithinPartitions("b").mapInArrow(_verify, "a long, b long, good boolean")


_PAIRS = "a long, b long"


def _across(nearest: int | None):
    """Pairs of a group across components whose sizes and coarse counts allow a link: the nearest few, or all.

    Members of the group's largest component are not the ones to look from: the others look at them.
    """

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("rep", kind="stable")
        rep, comp, n = (frame[c].to_numpy(np.int64) for c in ("rep", "component", "n"))
        cells = np.frombuffer(b"".join(frame["cells"]), np.uint8).reshape(-1, CELLS)
        names, sizes = np.unique(comp, return_counts=True)
        minor = comp != names[sizes.argmax()]
        out = []
        for i in np.flatnonzero(minor).tolist():
            rest = np.flatnonzero((comp != comp[i]) & (~minor | (np.arange(len(rep)) < i)) & (OF * np.minimum(n, n[i]) >= SHARE * np.maximum(n, n[i])))
            apart = (np.maximum(cells[rest], cells[i]) - np.minimum(cells[rest], cells[i])).sum(1, dtype=np.int64)
            near = apart <= difference(n[rest], n[i])
            rest, apart = rest[near], apart[near]
            if nearest is not None:
                rest = rest[np.argsort(apart, kind="stable")[:nearest]]
            out += [(max(rep[i], rep[j]), min(rep[i], rep[j])) for j in rest]
        return pd.DataFrame(out, columns=["a", "b"], dtype=np.int64)

    return run


def joined(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (the smallest doc_id reachable by links).

    Null and empty texts have an empty set and are linked with nothing.  Rows that share a doc_id are expected to be
    copies; a doc_id with several texts takes part with each.  A row without a doc_id belongs to the component of the
    rows with an equal set (null without any), and no link leads over it.
    """
    rows = ids_and_texts(docs)
    spark = docs.sparkSession
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = int(max(int(spark.conf.get("spark.sql.shuffle.partitions")), size // 10 // PER_BUCKET + 1))
    signed = rows.mapInArrow(_sign(buckets), _SIGNED).repartition(buckets, "bucket").sortWithinPartitions("bucket")
    met = stored(signed.mapInArrow(_meet, _MET), "met")
    found = met.where("kind = 'doc'").select("doc_id", "n", "class", "cells")
    classes = stored(found.where("n > 0").groupBy("class").agg(F.min("doc_id").alias("rep"), F.max("n").alias("n"), F.max("cells").alias("cells")), "classes")
    reps = classes.select("class", "rep")
    pairs = met.where("kind = 'pair'").select("class", "other").distinct()
    pairs = pairs.join(reps.withColumnRenamed("rep", "a"), "class").join(reps.select(F.col("class").alias("other"), F.col("rep").alias("b")), "other").select("a", "b")
    checked = stored(verified(rows, stored(pairs, "pairs")), "checked")
    good = checked.where("good").select("a", "b")
    comps = stored(components(good), "components")
    # groups of a failed comparison may still hold several components: nearest members first, in the largest group of
    # each head, then all pairs that the bound allows
    loose = checked.where("not good").join(reps.select(F.col("rep").alias("b"), F.col("class").alias("other")), "b").select("other").distinct()
    groups = met.where("kind = 'group'").join(loose, "other", "left_semi").select("other", F.xxhash64("members").alias("group"), "members").dropDuplicates(["group"])
    groups = stored(groups, "groups")
    compared = checked.select("a", "b")
    for nearest in (NEAREST, NEAREST, None):
        labelled = classes.join(comps, classes["rep"] == comps["node"], "left").select("class", "rep", "n", "cells", F.coalesce("component", "rep").alias("component"))
        members = stored(groups.select("group", "members").mapInArrow(_unpack, "group long, class long").join(labelled.select("class", "component"), "class"), "members")
        open_groups = members.groupBy("group").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low <> high").select("group")
        open_groups = stored(open_groups, "open-groups")
        if open_groups.isEmpty():
            break
        if nearest is not None:
            heads = groups.join(open_groups, "group", "left_semi").groupBy("other").agg(F.max_by("group", F.struct(F.octet_length("members"), "group")).alias("group"))
            open_groups = heads.select("group").distinct()
        inside = members.join(open_groups, "group", "left_semi").select("group", "class").join(labelled, "class")
        more = inside.select("group", "rep", "component", "n", "cells").groupBy("group").applyInPandas(_across(nearest), _PAIRS).distinct()
        more = stored(more.join(compared, ["a", "b"], "left_anti"), "more-pairs")
        if more.isEmpty():
            continue
        again = stored(verified(rows, more).where("good").select("a", "b"), "checked-again")
        compared = compared.unionByName(more)
        comps = stored(components(comps.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(again)), "components")
    own = found.join(reps, "class", "left").join(comps, F.col("rep") == F.col("node"), "left")
    return own.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "rep", "doc_id").alias("component_id"))


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for group, members in zip(batch.column("group").to_pylist(), batch.column("members").to_pylist(), strict=True):
            who = np.frombuffer(members, "<i8")
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(who), group, np.int64)), pa.array(who)], ["group", "class"])


def deduplicated(docs: DataFrame) -> DataFrame:
    """docs with one row of each component, that of smallest doc_id (null last), and every row without words.

    Rows are told apart by a number of their own, so rows without a doc_id and rows that share one are handled like any
    other: of repeated rows one stays.  The columns are those of docs, whatever their names.
    """
    held = docs.select("text", F.col("doc_id").cast("long").alias("doc_id"), F.struct("*").alias("_document"))
    held = stored(held.withColumn("_row", F.monotonically_increasing_id()), "numbered")
    own = joined(held.select(F.col("_row").alias("doc_id"), "text")).select(F.col("doc_id").alias("_row"), "n_shingles", "component_id")
    keys = own.join(held.select("_row", "doc_id"), "_row")
    first = keys.where("n_shingles > 0").groupBy("component_id").agg(F.min_by("_row", F.struct(F.col("doc_id").isNull(), "doc_id", "_row")).alias("_row")).select("_row")
    kept = first.unionByName(keys.where("n_shingles = 0").select("_row"))
    return held.join(kept, "_row", "left_semi").select("_document.*")
