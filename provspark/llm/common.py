"""Shared plumbing of the training-data operators: inputs, scratch tables, Arrow slices, words.

Conventions that hold for every operator of this subpackage:

* null texts count as empty texts, extra columns are ignored, and columns are picked by name, so clashing
  names in other tables do no harm;
* an empty table gives an empty result of the stated schema;
* scratch tables go to the folder that ``spark.checkpoint.dir`` names, which driver and executors share.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text handled at once by the Arrow operators; one longer document is still handled whole.
SLICE_BYTES = 8 << 20
#: Fixed by the contracts: ASCII white space separates words.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
SPACE_PATTERN = r"[\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The shared folder the cluster names; where it is unset, a folder of this machine, if all work is done there."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    if not found:
        found = f"file://{tempfile.mkdtemp(prefix='scratch-')}"
        spark.conf.set("spark.checkpoint.dir", found)
    return found


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex[:12]}"


def stored(df: DataFrame, name: str, partition_by: str | None = None) -> DataFrame:
    """Write df to a scratch table and read it back: cuts lineage, survives lost executors."""
    path = scratch_path(df.sparkSession, name)
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def ids_and_texts(docs: DataFrame, *more: str) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"), *more)


def crc_mod(column: str, modulus: int):
    """crc32 of the id written as text, modulo ``modulus``; ids that are null fall in class 0."""
    return F.coalesce(F.crc32(F.col(column).cast("string").cast("binary")) % modulus, F.lit(0))


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut batches so that the strings of ``column`` in each slice stay near ``most`` bytes."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(column))), 0).to_numpy(zero_copy_only=False)
        block = np.cumsum(sizes, dtype=np.int64) // most
        cuts = np.flatnonzero(np.diff(block)) + 1
        for a, b in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
            yield batch.slice(a, b - a)


class Words:
    """Words of a slice of texts, coded by their distinct values.

    ``codes[starts[i]:starts[i + 1]]`` are the codes of text i, ``values`` the distinct words.
    """

    def __init__(self, texts: pa.Array, lower: bool = True):
        if lower:
            texts = pc.ascii_lower(texts)
        split = pc.ascii_split_whitespace(texts)
        flat = split.values if isinstance(split, (pa.ListArray, pa.LargeListArray)) else split.flatten()
        offsets = split.offsets.to_numpy().astype(np.int64)
        flat, offsets = flat.slice(offsets[0], offsets[-1] - offsets[0]), offsets - offsets[0]
        full = pc.greater(pc.binary_length(flat), 0)
        if not pc.all(full).as_py() and len(flat):
            mask = full.to_numpy(zero_copy_only=False)
            offsets = np.concatenate([[0], np.cumsum(mask)])[offsets]
            flat = flat.filter(full)
        coded = flat.dictionary_encode()
        self.codes = coded.indices.to_numpy(zero_copy_only=False)
        self.values = coded.dictionary
        self.starts = offsets
        self.counts = np.diff(offsets)

    def rows(self) -> np.ndarray:
        """The text's number for each word."""
        return np.repeat(np.arange(len(self.counts)), self.counts)

    def sums(self, per_word: np.ndarray) -> np.ndarray:
        """Sum of ``per_word`` (one figure, or a row of them, per word) over each text."""
        totals = np.zeros((len(self.counts), *per_word.shape[1:]))
        full = self.counts > 0
        if full.any():
            totals[full] = np.add.reduceat(per_word, self.starts[:-1][full], axis=0)
        return totals


def text_arrow(batch: pa.RecordBatch) -> pa.Array:
    return pc.fill_null(batch.column("text"), "")
