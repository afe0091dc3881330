"""What the training-data operators share: where to keep intermediate tables, and how to walk whole texts in bounded memory."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text handled at once inside a Python worker (a single longer text is a block of its own).
BLOCK_BYTES = 1 << 18


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``, which all executors share; a temporary one where none is set and all runs in one process (tests)."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no folder that driver and executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="stagewise-"))
    return sc._jsc.sc().getCheckpointDir().get()


#: Bytes of rows that a Python worker is sent at once; a single longer row is a batch of its own. Rows alone would not bound it.
BATCH_BYTES = 4 << 20


def small_batches(df: DataFrame) -> DataFrame:
    """The frame itself; its session cuts what it sends to Python workers by bytes, too."""
    if not 0 < df.sparkSession._jsparkSession.sessionState().conf().arrowMaxBytesPerBatch() <= BATCH_BYTES:
        df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)
    return df


#: What a worker keeps from task to task, by the module that keeps it.
KEPT: dict[str, dict] = {}


def tidied(run: Callable) -> Callable:
    """The function for ``mapInArrow``, whose worker first drops what other operators' tasks left, and in the end gives back the memory it does not use.

    Workers outlive their tasks and wait for the next ones beside the executor's heap.
    """
    owner = run.__module__

    def lean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        drop_others(owner)
        yield from run(batches)
        give_back()

    return lean


# these two are sent to workers by name, so that they meet the workers' own tables


def drop_others(owner: str) -> None:
    for module, cache in KEPT.items():
        if module != owner:
            cache.clear()


def give_back() -> None:
    _POWERS.update(base=np.ones(1, np.uint64), inverse=np.ones(1, np.uint64))
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def stash(df: DataFrame) -> DataFrame:
    """Write a frame as Parquet to the shared folder and read it back: lineage ends there and lost executors cost nothing."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of a small side are sent to every executor up to this many bytes of them, which are counted first; beyond it both sides are shuffled.
SEND_BYTES = 32 << 20


def sent_if_small(df: DataFrame, row_bytes: int, limit: int = SEND_BYTES) -> DataFrame:
    """A written frame with the hint to send it whole, if its counted rows of about ``row_bytes`` are within the limit."""
    return F.broadcast(df) if df.count() * row_bytes <= limit else df


def unused(name: str, *frames: DataFrame) -> str:
    """The name, lengthened until no frame has a column of it."""
    taken = {c.lower() for f in frames for c in f.columns}
    while name in taken:
        name += "_"
    return name


def columns_of(df: DataFrame) -> list[Column]:
    """All columns, whatever they are called."""
    return [F.col("`" + c.replace("`", "``") + "`") for c in df.columns]


def fold_of(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(parts)).cast("int")


def text_blocks(batch: pa.RecordBatch, column: str, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int, list[bytes]]]:
    """Rows ``lo..hi`` of a batch with their texts as UTF-8 (null as empty), so that a block holds about ``limit`` bytes."""
    values = batch.column(batch.schema.get_field_index(column)).cast(pa.binary())
    sizes = np.asarray(pc.fill_null(pc.binary_length(values), 0), dtype=np.int64)
    lo = 0
    while lo < len(sizes):
        hi = lo + max(1, int(np.searchsorted(np.cumsum(sizes[lo : lo + 4096]), limit, side="right")))
        yield lo, hi, [x or b"" for x in values.slice(lo, hi - lo).to_pylist()]
        lo = hi


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of unsigned 64-bit integers (xor-shift and multiply)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_POWERS: dict[str, np.ndarray] = {"base": np.ones(1, np.uint64), "inverse": np.ones(1, np.uint64)}


def _powers(which: str, n: int) -> np.ndarray:
    """The first ``n`` powers modulo 2**64; the table is as long as the longest block met."""
    have = _POWERS[which]
    if len(have) < n:
        step = np.full(max(n, 2 * len(have)), _BASE if which == "base" else _INVERSE, np.uint64)
        step[0] = 1
        have = _POWERS[which] = np.multiply.accumulate(step)
    return have[:n]


def span_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Polynomial hash of each ``values[start:end]``, in time independent of the spans' lengths."""
    sums = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values.astype(np.uint64) * _powers("base", len(values)), out=sums[1:])
    width = (ends - starts).astype(np.uint64)
    return mix64((sums[ends] - sums[starts]) * _powers("inverse", len(values) + 1)[starts] + width)


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True


def word_spans(texts: list[bytes]) -> tuple[bytes, np.ndarray, np.ndarray, np.ndarray]:
    """The texts joined by a line end; where each word (``[^\\x20\\x09-\\x0D]+``) starts and ends in it; the number of words of each text."""
    joined = b"\n".join(texts) + b"\n"
    space = _SPACE[np.frombuffer(joined, np.uint8)]
    edge = np.flatnonzero(np.diff(space, prepend=True))
    starts, ends = edge[0::2], edge[1::2]
    stops = np.cumsum([len(x) + 1 for x in texts])
    counts = np.diff(np.searchsorted(starts, stops), prepend=0)
    return joined, starts, ends, counts
