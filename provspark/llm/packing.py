"""Packing of token documents into fixed-length sequences by a configuration linear program.

Only the histogram of piece lengths reaches the driver (at most ``capacity`` figures, whatever the corpus).  A
configuration is a multiset of lengths that fits one sequence.  The covering program - fewest sequences such that every
length is covered - is solved by multiplicative weights: a length weighs less the more of it is covered, a knapsack
dynamic program over the ``PRICED`` lengths of most weight finds the configuration worth most (partial pricing), and the
average of the configurations found, scaled to cover, is the fractional solution.  Its full configurations are rounded
down to whole uses, then up, in order of use, as long as the pieces last; what is left is a smaller program, solved and
rounded the same way, until the pieces left are fewer than one in ``REST``, which go by best fit into the room left in the
sequences placed and into new ones.

Pieces take their places by rank within their length, found with one search in the table of places.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ids_and_texts, slices, stored, text_arrow
from .subwords import encode_texts

#: Lengths that a knapsack prices, and how much more of it a longer one is worth; how strongly weights fall with what is
#: covered; one in so many pieces may be left to best fit; a configuration is full with so little room.
PRICED, POWER, FALL, REST, LOOSE = 64, 1.3, 1.0, 12, 2

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, task long, rank long"


def knapsack(value: np.ndarray, most: np.ndarray, capacity: int) -> Counter:
    """The most valuable multiset that fits: value[k] is the worth of an item of size k, most[k] how many there are."""
    items = []  # (size, worth, multiple): multiples by doubling, so that any number up to most[k] can be put together
    for k in np.flatnonzero((value > 0) & (most > 0)).tolist():
        left, times = min(int(most[k]), capacity // k), 1
        while left > 0:
            times = min(times, left)
            items.append((k * times, float(value[k]) * times, k, times))
            left, times = left - times, times * 2
    best, taken = np.zeros(capacity + 1), np.zeros((len(items), capacity + 1), bool)
    for i, (size, worth, _, _) in enumerate(items):
        gain = best[: capacity + 1 - size] + worth
        better = taken[i, size:]
        np.greater(gain, best[size:] + 1e-12, out=better)
        np.copyto(best[size:], gain, where=better)
    found, room = Counter(), capacity
    for i in range(len(items) - 1, -1, -1):
        if taken[i, room]:
            found[items[i][2]] += items[i][3]
            room -= items[i][0]
    return found


def fractional(need: np.ndarray, capacity: int, rng: np.random.Generator) -> list[tuple[Counter, float]]:
    """Fractional covering solution: configurations and how often each is used, the full and most used ones first."""
    kinds = np.flatnonzero(need)
    covered = np.zeros(len(kinds))
    place = {int(x): i for i, x in enumerate(kinds)}
    used: dict[tuple, float] = {}
    while len(open_ := np.flatnonzero(covered < 1)):
        priced = open_
        if len(open_) > PRICED:  # a quarter of them the longest, the others drawn among those least covered
            rest, top = open_[: -(PRICED // 4)], open_[-(PRICED // 4) :]
            priced = np.append(rest[np.argpartition(covered[rest] + rng.random(len(rest)), PRICED - len(top))[: PRICED - len(top)]], top)
        worth, most = np.zeros(capacity + 1), np.zeros(capacity + 1, np.int64)
        worth[kinds[priced]] = (kinds[priced] / capacity) ** POWER * np.exp(-FALL * covered[priced])
        most[kinds[priced]] = need[kinds[priced]]
        config = knapsack(worth, most, capacity)
        times = min(need[x] / n for x, n in config.items())
        key = tuple(sorted(config.items()))
        used[key] = used.get(key, 0.0) + times
        for x, n in config.items():
            covered[place[x]] += n * times / need[x]
    # the average, scaled so that the length covered least is covered once
    scale = 1 / covered.min() if len(kinds) else 1.0
    full = lambda key: capacity - sum(x * n for x, n in key) <= LOOSE
    return [(Counter(dict(key)), times * scale) for key, times in sorted(used.items(), key=lambda x: (not full(x[0]), -x[1], x[0]))]


def configurations(need: np.ndarray, capacity: int, seed: int = 17) -> tuple[Counter, np.ndarray]:
    """Whole uses of configurations by repeated solving and rounding, and the pieces they leave."""
    left, chosen, rng = need.astype(np.int64).copy(), Counter(), np.random.default_rng(seed)
    enough, loose = int(need.sum()) // REST, LOOSE
    while left.sum() > enough:
        before, solution = int(left.sum()), fractional(left, capacity, rng)
        for up in (False, True):
            for config, times in solution:
                if capacity - sum(x * n for x, n in config.items()) > loose:
                    continue
                whole = min(int(np.ceil(times) if up else times), *(int(left[x]) // n for x, n in config.items()))
                if whole > 0:
                    chosen[tuple(sorted(config.elements(), reverse=True))] += whole
                    for x, n in config.items():
                        left[x] -= n * whole
        if before - left.sum() < before // 10:
            loose = 2 * loose + 1  # few full configurations are left
            if loose > capacity:
                break
    return chosen, left


@dataclass
class Plan:
    """Whole configurations of exact lengths and how often each is used; pieces that the program placed."""

    chosen: list[tuple[list[int], int]]
    placed: int


def plan(need: np.ndarray, capacity: int) -> Plan:
    """Covers ``need`` (pieces by length) exactly."""
    sequences, left = configurations(need, capacity)
    return Plan(best_fit(sequences, left, capacity), int(need.sum() - left.sum()))


def best_fit(sequences: Counter, left: np.ndarray, capacity: int) -> list[tuple[list[int], int]]:
    """Pieces ``left`` by length, longest first, each into the sequence of least room that holds it, or a new one."""
    rooms: list[dict[tuple, int]] = [{} for _ in range(capacity + 1)]
    for config, times in sequences.items():
        rooms[capacity - sum(config)][config] = times
    occupied = np.array([bool(r) for r in rooms])
    for x in np.flatnonzero(left)[::-1].tolist():
        n = int(left[x])
        while n:
            ahead = np.flatnonzero(occupied[x:])
            if len(ahead):
                room = x + int(ahead[0])
                config, times = next(iter(rooms[room].items()))
            else:
                room, config, times = capacity, (), n
            many = 1 if config else max(1, capacity // x)
            # as many copies of the sequence as there are pieces, as many pieces in each as go in by best fit anyway
            each = min(many, room // x, n)
            copies = min(times, n // each)
            if config:
                rooms[room][config] -= copies
                if not rooms[room][config]:
                    del rooms[room][config]
                    occupied[room] = bool(rooms[room])
            grown = (*config, *[x] * each)
            rooms[room - x * each][grown] = rooms[room - x * each].get(grown, 0) + copies
            occupied[room - x * each] = True
            n -= each * copies
    return [(sorted(config, reverse=True), times) for by in rooms for config, times in by.items()]


def places(chosen: list[tuple[list[int], int]]) -> dict[str, np.ndarray]:
    """For runs of ranks within a length: the first sequence and the offset; sorted by (length, first rank)."""
    seen: Counter = Counter()
    rows, sequence = [], 0
    for config, times in chosen:
        offset = 0
        for x in config:
            rows.append((x, seen[x], sequence, offset))
            seen[x] += times
            offset += x
        sequence += times
    table = np.array(sorted(rows), np.int64).reshape(-1, 4)
    return {"key": table[:, 0] << 44 | table[:, 1], "rank": table[:, 1], "sequence": table[:, 2], "offset": table[:, 3]}


def _cut(path: str, end_id: int, capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(capacity + 1, np.int64)
        task = None
        for batch in slices(batches):
            if task is None:
                task = batch.column("task")[0].as_py()
            ids, counts = encode_texts(text_arrow(batch), path)
            ids = np.insert(ids, np.cumsum(counts), end_id).astype("<u4")
            counts = counts + 1
            pieces = -(-counts // capacity)
            doc = np.repeat(np.arange(len(counts)), pieces)
            piece = np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
            start = piece * capacity
            length = np.minimum(capacity, counts[doc] - start)
            begin = (np.cumsum(counts) - counts)[doc] + start
            crc = [zlib.crc32(ids[a:b]) for a, b in zip(begin.tolist(), (begin + length).tolist(), strict=True)]
            order = np.argsort(length, kind="stable")
            ordered = length[order]
            runs = np.searchsorted(ordered, ordered)
            rank = np.empty(len(doc), np.int64)
            rank[order] = seen[ordered] + np.arange(len(doc)) - runs
            seen += np.bincount(length, minlength=capacity + 1)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(pa.array(doc)), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array(np.full(len(doc), task), pa.int64()), pa.array(rank)], PIECES.replace(" long", "").replace(" int", "").split(", "))

    return run


def _place(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for batch in batches:
            length, rank = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            at = np.searchsorted(table["key"], length << 44 | rank, "right") - 1
            kept = [batch.column(c) for c in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(table["sequence"][at] + rank - table["rank"][at]), pa.array(table["offset"][at])], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, tokenizer: str, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null texts are the end id alone.  Documents longer than ``capacity`` are cut into full pieces and a rest; no other
    is cut.  Repeated rows are packed as often as they occur.  Empty tables give no rows.
    """
    spark = docs.sparkSession
    cut = ids_and_texts(docs).withColumn("task", F.spark_partition_id().cast("long")).mapInArrow(_cut(tokenizer, end_id, capacity), PIECES)
    pieces = stored(cut, "pieces")
    counts = pieces.groupBy("task", "length").agg(F.count("*").alias("n"))
    need = np.zeros(capacity + 1, np.int64)
    for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect():  # one row a length
        need[r["length"]] = r["n"]
    table = spark.sparkContext.broadcast(places(plan(need, capacity).chosen))
    before = counts.select("task", "length", F.coalesce(F.sum("n").over(Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    ranked = pieces.join(before, ["task", "length"]).withColumn("rank", F.col("rank") + F.col("before"))
    return ranked.drop("task", "before").mapInArrow(_place(table), "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
