"""Document fingerprints by a randomised edit embedding.

A pointer walks over a text's characters; at output step t it writes the character it stands on, then moves on or stays
by a bit drawn for (t, character).  All texts share the bits, so two texts near in edit distance fall back into step and
their outputs are near in Hamming distance.  The walk starts afresh every ``SEGMENT`` characters, which bounds the steps
and lets all segments of a batch walk together.

A fingerprint samples the outputs at ``SLOTS`` places, a byte each.  A slot's place is the one of least random priority
below the length of the output, so that texts of different lengths share most places; those places are the records of a
sequence of priorities, which are drawn as such and hold for any length.  The likeness of two fingerprints is the share
of equal bytes, corrected for chance.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ids_and_texts, slices, stored

SEGMENT, SLOTS, SEED = 1024, 128, 20_011
STEPS = 2 * SEGMENT
#: Outputs hashed into the byte of a slot.
GRAM = 4
#: Segments that walk together.
TOGETHER = 4096
SLICE = 4 << 20


@lru_cache(maxsize=1)
def _randomness() -> tuple[np.ndarray, list[np.ndarray]]:
    """Bits by (step, character class), and the records of each slot's priorities."""
    rng = np.random.default_rng(SEED)
    bits = rng.integers(0, 2, (STEPS, 256), dtype=np.int64)
    bits[:, 0] = 0  # behind the end the pointer stays
    records = []
    for _ in range(SLOTS):
        place, least, own = 0, rng.random(), [0]
        while place < 1 << 42:
            place += max(1, int(np.ceil(np.log(rng.random()) / np.log1p(-least)))) if least > 1e-15 else 1 << 42
            least *= rng.random()
            own.append(place)
        records.append(np.array(own))
    return bits, records


def classes(text: str) -> np.ndarray:
    """Character classes 1 to 255."""
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    return ((codes * np.uint64(0x9E3779B1) >> np.uint64(15)) % np.uint64(255) + np.uint64(1)).astype(np.uint8)


def walk(chars: np.ndarray, begins: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Outputs [segment, step] of the walks over chars[begin:begin + length]."""
    bits, _ = _randomness()
    out = np.zeros((len(begins), STEPS), np.uint8)
    padded = np.append(chars, np.uint8(0))
    order = np.argsort(-lengths, kind="stable")
    for a in range(0, len(order), TOGETHER):
        some = order[a : a + TOGETHER]
        at, end = begins[some].copy(), begins[some] + lengths[some]
        walked = np.zeros((STEPS, len(some)), np.uint8)
        longest = int(lengths[some].max(initial=0))
        live = len(some)
        for t in range(STEPS):
            if t % 64 == 0:  # pointers only move on, so those that have ended stay so; lengths fall along the order
                alive = np.flatnonzero(at[:live] < end[:live])
                live = int(alive[-1]) + 1 if len(alive) else 0
                if not live or t > 2 * longest + 4096:
                    break
            c = padded[np.where(at[:live] < end[:live], at[:live], -1)]
            walked[t, :live] = c
            at[:live] += bits[t][c]
        out[some] = walked.T
    return out


class Segments:
    """Texts cut into segments; ``fingerprints`` samples the walks of any list of segments per text."""

    def __init__(self):
        self.chars: list[np.ndarray] = []
        self.lengths: list[int] = []

    def add(self, chars: np.ndarray) -> range:
        first = len(self.lengths)
        for a in range(0, len(chars), SEGMENT):
            self.chars.append(chars[a : a + SEGMENT])
            self.lengths.append(len(self.chars[-1]))
        return range(first, len(self.lengths))

    def walks(self) -> np.ndarray:
        lengths = np.array(self.lengths, np.int64)
        chars = np.concatenate(self.chars) if self.chars else np.zeros(0, np.uint8)
        return walk(chars, np.cumsum(lengths) - lengths, lengths)


def sample(outputs: np.ndarray, parts: list[np.ndarray], sizes: np.ndarray) -> np.ndarray:
    """Fingerprints [text, slot]; parts: the segments of each text, sizes: its characters."""
    _, records = _randomness()
    prints = np.zeros((len(parts), SLOTS), np.uint8)
    full = np.flatnonzero(sizes)
    if not len(full):
        return prints
    flat = np.concatenate([parts[i] for i in full])
    base = np.cumsum([len(parts[i]) for i in full]) - [len(parts[i]) for i in full]
    length = 2 * sizes[full]
    multipliers = np.array([3, 257, 65_539, 16_777_259], np.uint64)
    for k, own in enumerate(records):
        place = own[np.searchsorted(own, length - 1, "right") - 1]
        segment = flat[base + place // STEPS]
        step = np.minimum(place % STEPS, STEPS - GRAM)
        value = np.zeros(len(full), np.uint64)
        for g in range(GRAM):
            value = (value + outputs[segment, step + g]) * np.uint64(0x9E3779B97F4A7C15) + multipliers[g]
        prints[full, k] = (value >> np.uint64(50)).astype(np.uint8)
    return prints


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """0 to 1: equal bytes beyond those of chance."""
    chance = 1 / 256
    return np.clip(((a == b).mean(-1) - chance) / (1 - chance), 0, 1)


def edited(text: str, following: str) -> str:
    """The last third replaced by as many first characters of the text that follows (or all it has)."""
    third = len(text) // 3
    return text[: len(text) - third] + following[:third]


def compare(texts: list[str], following: list[str]) -> dict[str, list]:
    """Columns of the report for texts, each with the one that follows it."""
    segments, own, changed, sizes, changed_sizes = Segments(), [], [], [], []
    hashes, next_at = [], []
    everything = texts + following[-1:]
    for text in everything:
        chars = classes(text)
        own.append(np.array(segments.add(chars), np.int64))
        sizes.append(len(chars))
    for i, (text, after) in enumerate(zip(texts, following, strict=True)):
        new = edited(text, after)
        hashes.append(hashlib.sha256(new.encode("utf-8", "surrogatepass")).hexdigest())
        shared = (len(text) - len(text) // 3) // SEGMENT  # segments before the edit walk as they did
        changed.append(np.concatenate([own[i][:shared], np.array(segments.add(classes(new[shared * SEGMENT :])), np.int64)]))
        changed_sizes.append(len(new))
        next_at.append(i + 1)
    outputs = segments.walks()
    prints = sample(outputs, own, np.array(sizes, np.int64))
    other = sample(outputs, changed, np.array(changed_sizes, np.int64))
    n, sizes = len(texts), np.array(sizes)
    nexts = prints[next_at] if n else prints[:0]
    one_empty = lambda a, b: (a == 0) != (b == 0)
    near_edited = np.where(one_empty(sizes[:n], np.array(changed_sizes, int)), 0.0, likeness(prints[:n], other))
    near_next = np.where(one_empty(sizes[:n], sizes[1 : n + 1]), 0.0, likeness(prints[:n], nexts))
    return {"n_chars": sizes[:n].tolist(), "edited_sha256": hashes, "fingerprint": [x.tobytes().hex() for x in prints[:n]], "edited_fingerprint": [x.tobytes().hex() for x in other], "near_edited": near_edited.tolist(), "near_next": near_next.tolist()}


_REPORT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
_TYPES = {"n_chars": pa.int64(), "near_edited": pa.float64(), "near_next": pa.float64()}
_ROWS = f"kind string, task long, {_REPORT}, text string"


def _columns(found: dict[str, list]) -> dict[str, pa.Array]:
    return {k: pa.array(v, _TYPES.get(k, pa.string())) for k, v in found.items()}


def _neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Reports of a task's documents but its last; its first and last text, for the tasks beside it."""
    task, held = None, None

    def lone(kind: str, doc_id, text: str) -> pa.RecordBatch:
        none = {k: [None] for k in ("n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next")}
        return pa.RecordBatch.from_pydict({"kind": pa.array([kind]), "task": pa.array([task], pa.int64()), "doc_id": pa.array([doc_id], pa.int64()), **_columns(none), "text": pa.array([text], pa.string())})

    for batch in slices(batches, most=SLICE):
        ids, texts = batch.column("doc_id").to_pylist(), pc.fill_null(batch.column("text"), "").to_pylist()
        if held is None:
            task = batch.column("task")[0].as_py()
            yield lone("first", ids[0], texts[0])
        else:
            ids, texts = [held[0], *ids], [held[1], *texts]
        held = ids[-1], texts[-1]
        if len(ids) > 1:
            n = len(ids) - 1
            yield pa.RecordBatch.from_pydict({"kind": pa.array(["done"] * n), "task": pa.array([task] * n, pa.int64()), "doc_id": pa.array(ids[:-1], pa.int64()), **_columns(compare(texts[:-1], texts[1:])), "text": pa.nulls(n, pa.string())})
    if held is not None:
        yield lone("last", *held)


def _pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for doc_id, text, after in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "text", "following")), strict=True):
            yield pa.RecordBatch.from_pydict({"doc_id": pa.array([doc_id], pa.int64()), **_columns(compare([text], [after]))})


def with_neighbours(docs: DataFrame) -> DataFrame:
    """Fingerprints of all texts, of their edited texts, and likenesses; the next document is that of the next lower id.

    Null texts are empty; two empty texts are alike (1), an empty and another one are not (0).  Rows that share a doc_id
    are ordered by text.  Equal texts have equal fingerprints.
    """
    ordered = ids_and_texts(docs).repartitionByRange(F.desc("doc_id")).sortWithinPartitions(F.desc("doc_id"), F.desc("text"))
    rows = stored(ordered.withColumn("task", F.spark_partition_id().cast("long")).mapInArrow(_neighbours, _ROWS), "fingerprints")
    firsts = rows.where("kind = 'first'").select("task", F.col("text").alias("following"))
    # one row a task: which task follows; the first follows the last
    tasks = firsts.select("task", F.coalesce(F.lead("task").over(Window.orderBy("task")), F.min("task").over(Window.partitionBy(F.lit(0)))).alias("after"))
    lasts = rows.where("kind = 'last'").select("task", "doc_id", "text").join(tasks, "task")
    edges = lasts.join(firsts.withColumnRenamed("task", "after"), "after").select("doc_id", "text", "following").mapInArrow(_pairs, _REPORT)
    return rows.where("kind = 'done'").drop("kind", "task", "text").unionByName(edges)


def _prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, most=SLICE):
        texts = pc.fill_null(batch.column("text"), "").to_pylist()
        segments, sizes = Segments(), np.array([len(x) for x in texts], np.int64)
        parts = [np.array(segments.add(classes(x)), np.int64) for x in texts]
        prints = sample(segments.walks(), parts, sizes)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sizes), pa.array([x.tobytes() for x in prints], pa.binary())], ["doc_id", "n_chars", "fingerprint"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, fingerprint (binary, one byte a slot)."""
    return ids_and_texts(docs).mapInArrow(_prints, "doc_id long, n_chars long, fingerprint binary")


def near_pairs(docs: DataFrame, least: float = 0.8, band: int = 4) -> DataFrame:
    """Pairs (doc_id, other, likeness) with a likeness of at least ``least``.

    Bands of ``band`` slots gather candidates.  Within a bucket every document is compared with the bucket's document
    of least id only, so a group of copies gives a star and not all its pairs.
    """
    prints = stored(fingerprints(docs).where("n_chars > 0"), "prints")
    bands = prints.select("doc_id", F.explode(F.transform(F.sequence(F.lit(0), F.lit(SLOTS // band - 1)), lambda b: F.xxhash64(b, F.substring(F.hex("fingerprint"), b * (2 * band) + 1, F.lit(2 * band))))).alias("bucket"))
    heads = bands.groupBy("bucket").agg(F.min("doc_id").alias("other"), F.count("*").alias("n")).where("n > 1").select("bucket", "other")
    pairs = bands.join(heads, "bucket").where("doc_id <> other").select("doc_id", "other").distinct()
    sides = pairs.join(prints.select("doc_id", F.col("fingerprint").alias("a")), "doc_id").join(prints.select(F.col("doc_id").alias("other"), F.col("fingerprint").alias("b")), "other")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, SLOTS) for c in "ab")
            like = likeness(a, b)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("other"), pa.array(like)], ["doc_id", "other", "likeness"]).filter(pa.array(like >= least))

    return sides.select("doc_id", "other", "a", "b").mapInArrow(verify, "doc_id long, other long, likeness double")
