"""Token-id files: frequency-ranked ids in a byte-aligned variable-length code with separate control bytes.

Format, little-endian.  An id is replaced by its rank in the corpus, 0 the most frequent.  Ranks are taken four at a
time: a control byte holds, two bits each from the lowest up, the number of bytes less one of the four ranks; their
bytes stand in a stream of their own.  The last group of a block is filled with zeros.  A block holds whole documents,
with their doc_ids, their lengths and the number of ids in all blocks before it.  Blocks are rows of a Parquet table,
ordered by that number, beside a table of ``(rank, id, n)``.

Decoding looks the 256 control bytes up in a table of lengths and of gather offsets, so that it is a handful of
numpy operations for a whole block.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ids_and_texts, scratch_path, slices, stored, text_arrow
from .subwords import encode_texts, encoder

#: Ids in a block; a longer document makes a longer block.
BLOCK_IDS = 1 << 18

_CODES = np.arange(256)
#: Bytes of each of the four ranks, by control byte.
LENGTHS = np.stack([(_CODES >> (2 * k) & 3) + 1 for k in range(4)], 1).astype(np.int64)


def encode_ranks(ranks: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes and data bytes of ranks below 2**32."""
    padded = np.zeros(-(-len(ranks) // 4) * 4, np.uint32)
    padded[: len(ranks)] = ranks
    extra = (padded >= 1 << 8).astype(np.uint8) + (padded >= 1 << 16) + (padded >= 1 << 24)
    control = extra.reshape(-1, 4) @ np.array([1, 4, 16, 64], np.uint8)
    as_bytes = padded.astype("<u4").view(np.uint8).reshape(-1, 4)
    return control.astype(np.uint8).tobytes(), as_bytes[np.arange(4) <= extra[:, None]].tobytes()


def decode_ranks(control: bytes, data: bytes, n: int) -> np.ndarray:
    """The first n ranks."""
    lengths = LENGTHS[np.frombuffer(control, np.uint8)].ravel()
    begins = np.cumsum(lengths) - lengths
    stream = np.concatenate([np.frombuffer(data, np.uint8), np.zeros(4, np.uint8)])
    out = stream[begins].astype(np.uint32)
    for k in (1, 2, 3):
        longer = np.flatnonzero(lengths > k)
        out[longer] |= stream[begins[longer] + k].astype(np.uint32) << np.uint32(8 * k)
    return out[:n]


def _tokenise(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before = 0
        for batch in slices(batches):
            ids, counts = encode_texts(text_arrow(batch), path)
            ids = np.insert(ids, np.cumsum(counts), end_id)
            edges = np.concatenate([[0], np.cumsum(counts + 1)])
            blob = pa.Array.from_buffers(pa.large_binary(), len(counts), [None, pa.py_buffer((edges * ids.itemsize).astype(np.int64).tobytes()), pa.py_buffer(ids.tobytes())])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("shard"), pa.array(before + edges[:-1], pa.int64()), pa.array(counts + 1, pa.int64()), blob.cast(pa.binary())], ["doc_id", "shard", "before", "n", "ids"])
            before += int(edges[-1])

    return run


def _frequencies(kind: str, vocabulary: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(vocabulary, np.int64)
        for batch in batches:
            for x in batch.column("ids").to_pylist():
                counts += np.bincount(np.frombuffer(x, kind), minlength=vocabulary) if len(x) > 20_000 else 0
            short = b"".join(x for x in batch.column("ids").to_pylist() if len(x) <= 20_000)
            counts += np.bincount(np.frombuffer(short, kind), minlength=vocabulary)
        used = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(counts[used])], ["id", "n"])

    return run


def _blocks(kind: str, ranks, starts, block_ids: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank_of, start_of = ranks.value, starts.value
        held: list[tuple[int, int, int, int, bytes]] = []

        def cut() -> pa.RecordBatch:
            control, data = encode_ranks(rank_of[np.frombuffer(b"".join(x[4] for x in held), kind)])
            shard, before, n = held[0][1], held[0][2], [x[3] for x in held]
            return pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int64()), "first": pa.array([start_of[shard] + before], pa.int64()), "n_ids": pa.array([sum(n)], pa.int64()), "doc_ids": pa.array([[x[0] for x in held]], pa.list_(pa.int64())), "lengths": pa.array([n], pa.list_(pa.int64())), "control": pa.array([control], pa.binary()), "data": pa.array([data], pa.binary())})

        size = 0
        for batch in batches:
            for x in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "shard", "before", "n", "ids")), strict=True):
                # a task may read parts of several shards: a block never joins what doesn't follow
                if held and (size >= block_ids or x[1] != held[-1][1] or x[2] != held[-1][2] + held[-1][3]):
                    yield cut()
                    held, size = [], 0
                held.append(x)
                size += x[3]
        if held:
            yield cut()

    return run


BLOCK_SCHEMA = "shard long, first long, n_ids long, doc_ids array<long>, lengths array<long>, control binary, data binary"


def write_token_files(docs: DataFrame, path: str, tokenizer: str, end_id: int = 2, block_ids: int = BLOCK_IDS) -> None:
    """Write ids of all texts in ascending doc_id order to ``path``/blocks and the ranks to ``path``/ranks.

    Null texts are empty; rows that share a doc_id follow each other, ordered by text; rows without doc_id come first.
    """
    spark = docs.sparkSession
    vocabulary, kind = encoder(tokenizer).library.get_vocab_size(), encoder(tokenizer).kind.str
    ordered = ids_and_texts(docs).repartitionByRange("doc_id").withColumn("shard", F.spark_partition_id().cast("long"))
    ordered = ordered.sortWithinPartitions("doc_id", "text")
    tokens = stored(ordered.mapInArrow(_tokenise(tokenizer, end_id), "doc_id long, shard long, before long, n long, ids binary"), "token-ids")
    counts = tokens.select("ids").mapInArrow(_frequencies(kind, vocabulary), "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    ranked = sorted(((r["n"], -r["id"]) for r in counts.collect()), reverse=True)  # one row an id of the vocabulary at most
    rank_of = np.zeros(max(vocabulary, 1), np.uint32)
    rank_of[[-i for _, i in ranked]] = np.arange(len(ranked))
    spark.createDataFrame([(k, -i, n) for k, (n, i) in enumerate(ranked)], "rank long, id long, n long").write.parquet(f"{path}/ranks")
    totals = tokens.groupBy("shard").agg(F.sum("n").alias("n")).collect()  # one row a shard
    starts, before = {}, 0
    for r in sorted(totals):
        starts[r["shard"]], before = before, before + r["n"]
    share = spark.sparkContext.broadcast
    tokens.mapInArrow(_blocks(kind, share(rank_of), share(starts), block_ids), BLOCK_SCHEMA).write.option("compression", "none").parquet(f"{path}/blocks")


def _decode(ranked):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        id_of = ranked.value
        for batch in batches:
            for r in batch.to_pylist():
                ids = id_of[decode_ranks(r["control"], r["data"], r["n_ids"])].astype("<u4")
                lengths = np.array(r["lengths"], np.int64)
                edges = np.concatenate([[0], np.cumsum(lengths)])
                crc = [zlib.crc32(ids[a:b]) for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(r["doc_ids"], pa.int64()), pa.array(r["first"] + edges[:-1], pa.int64()), pa.array(lengths), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return run


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, decoded from the files."""
    blocks = spark.read.schema(BLOCK_SCHEMA).parquet(f"{path}/blocks")
    ranked = spark.read.parquet(f"{path}/ranks").collect()  # one row an id of the vocabulary at most
    id_of = np.zeros(max(1, len(ranked)), np.uint32)
    for r in ranked:
        id_of[r["rank"]] = r["id"]
    return blocks.mapInArrow(_decode(spark.sparkContext.broadcast(id_of)), "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_files(docs: DataFrame, tokenizer: str, end_id: int = 2) -> DataFrame:
    """Write the files to the shared scratch folder, then report what they hold."""
    path = scratch_path(docs.sparkSession, "token-files")
    write_token_files(docs, path, tokenizer, end_id)
    return read_token_files(docs.sparkSession, path)
