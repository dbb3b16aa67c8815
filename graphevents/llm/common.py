"""Helpers that the corpus operators share.

Words are runs of characters other than the six ASCII blanks (space, tab, newline, vertical tab, form feed,
carriage return); on UTF-8 bytes that is exactly what ``bytes.split()`` yields.
"""

from __future__ import annotations

import contextlib
import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Java / Python pattern of one word.
WORD = r"[^\x20\x09-\x0D]+"
#: Bytes of text that one numpy kernel call works on; a longer document is a call of its own.
CHUNK_BYTES = 1 << 18


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_count(text) -> F.Column:
    """Words of a text column as long; null has none. Deleting words and blanks' tails leaves one mark a word."""
    marks = F.regexp_replace(F.coalesce(text, F.lit("")), WORD, "x")
    return F.length(F.translate(marks, " \t\n\x0b\x0c\r", "")).cast("long")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: ``spark.checkpoint.dir``; a temporary one only where none is set (tests)."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(found or tempfile.mkdtemp(prefix="checkpoints-"))
        found = sc.getCheckpointDir()
    return found


def stored(df: DataFrame) -> DataFrame:
    """``df`` written as Parquet to the shared folder and read again: cuts lineage, survives a lost executor, and is
    far smaller than a checkpoint of rows."""
    path = f"{shared_dir(df.sparkSession)}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete what ``stored`` wrote for these frames, and shuffle files that nothing needs any more."""
    spark = None
    for df in frames:
        spark, path = df.sparkSession, getattr(df, "_stored_at", None)
        if path:
            p = spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
    if spark:
        free_shuffles(spark)


@contextlib.contextmanager
def bucketed(df: DataFrame, key: str) -> Iterator[DataFrame]:
    """``df`` as a table bucketed by ``key``: later joins on the key read it in place and move only their other side. The table is dropped
    at the end, so what is made from it must be stored before."""
    spark, name = df.sparkSession, f"bucketed_{uuid.uuid4().hex}"
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    try:
        df.repartition(n, key).write.bucketBy(n, key).format("parquet").saveAsTable(name)
        free_shuffles(spark)
        yield spark.table(name)
    finally:
        spark.sql(f"drop table if exists {name} purge")


def free_shuffles(spark: SparkSession) -> None:
    """Let the context cleaner drop shuffle files of finished jobs that nothing refers to."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def slices(batches: Iterator[pa.RecordBatch], column: str, most: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Batches of about ``most`` bytes of ``column``; no row is cut. What is made from a piece is small, so neither the Python worker nor
    the reader on the other side ever holds more than the piece that came in and one that goes out."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = np.nan_to_num(pc.binary_length(texts_of(batch, column)).to_numpy(zero_copy_only=False).astype("float64")) + 64
        part = (np.cumsum(sizes) // most).astype("int64")
        cuts = np.flatnonzero(np.diff(part)) + 1
        for a, b in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
            yield batch.slice(a, b - a)
        del batch
        pa.default_memory_pool().release_unused()  # a worker that waits holds nothing


def texts_of(batch: pa.RecordBatch, column: str) -> pa.Array:
    """A text column of a batch; ``row.document.text`` names a field inside structs, so a whole row need not carry its text twice."""
    first, *inner = column.split(".")
    array = batch.column(first)
    for name in inner:
        array = array.field(name)
    return array


def with_text(docs: DataFrame, keep: list, whole: bool) -> tuple[DataFrame, str]:
    """``row`` (a struct of ``keep``) and, unless ``keep`` begins with the whole document, ``raw``; and where the text is found."""
    if whole:
        return docs.select(F.struct(*keep).alias("row")), "row.document.text"
    return docs.select(F.struct(*keep).alias("row"), F.col("text").alias("raw")), "raw"


def document(docs: DataFrame) -> F.Column:
    """All columns of ``docs`` as one struct named ``document``: names can't clash with a helper's."""
    return F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("document")


_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mixed(x: np.ndarray) -> np.ndarray:
    """The 64-bit finaliser of splitmix, elementwise."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= _M1
    x ^= x >> np.uint64(27)
    x *= _M2
    x ^= x >> np.uint64(31)
    return x


_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    base, inverse = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 1 << 64)
    have = _POWERS.get(0)
    if have is None or len(have[0]) < n:
        size = max(n, CHUNK_BYTES + (1 << 18))
        up, down = np.full(size, base, np.uint64), np.full(size, inverse, np.uint64)
        up[0] = down[0] = 1
        have = (np.multiply.accumulate(up), np.multiply.accumulate(down))
        if size <= CHUNK_BYTES * 4:
            _POWERS[0] = have
    return have


def word_hashes(texts: list[bytes], seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of every word of ``texts`` and the word offsets of each text (one more than texts).

    Works on all bytes at once: each byte becomes a random number, weighted by a power of its place, and prefix sums
    give each word's sum. Equal words have equal hashes on every machine.
    """
    data = np.frombuffer(b" ".join([*texts, b""]), np.uint8)
    starts_of = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])]).astype(np.int64)
    blank = (data == 32) | ((data >= 9) & (data <= 13))
    edge = np.flatnonzero(np.diff(np.concatenate([[True], blank, [True]]).view(np.int8)))
    begin, end = edge[0::2], edge[1::2]
    rng = np.random.Generator(np.random.PCG64(seed))
    values = rng.integers(1, 1 << 63, 256, dtype=np.uint64)
    up, down = _powers(len(data) + 1)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(values[data] * up[: len(data)])])
    hashes = mixed((sums[end] - sums[begin]) * down[begin])
    return hashes, np.searchsorted(begin, starts_of).astype(np.int64)
