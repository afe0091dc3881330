"""Line dedup: runs of lines that already stood earlier are deleted.

Lines are hashed, and of each window of ``run`` lines the line of least hash (the rightmost of equals) is its fingerprint. Equal
windows choose the same fingerprint in the same place, so no repeated run of ``run`` lines or more is missed. Places are joined
by fingerprint and each is extended both ways as far as a window through it can reach. Places whose whole extension is equal form
a class: the earliest keeps it, the others lose it. Only where one fingerprint has several classes, that is at the ends of
repeated runs, the windows of the classes' earliest places are compared one by one. Places are never paired with each other, so
the work is linear in their number however many documents share a run.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BLOCK_BYTES, small_batches, stash, table, text_blocks, tidied
from .substring_dedup import digest, digest_columns, winnow

#: A shorter repeat than this many lines is left alone.
RUN_LINES = 3
WIDTH = 16


def lines_of(text: bytes) -> list[bytes]:
    """What is compared: the lines that are not blank, without white space (0x20, 0x09-0x0D) at their ends."""
    return [line for line in map(bytes.strip, text.split(b"\n")) if line]


def _places(texts: list[bytes], run: int):
    """For each fingerprint: text number, line, extension lo..hi, hash, digest of the extension; and the digests of its windows."""
    lines = [lines_of(t) for t in texts]
    counts = np.array([len(x) for x in lines], np.int64)
    if counts.max(initial=0) < run:
        return None
    firsts = np.cumsum(counts) - counts
    doc = np.repeat(np.arange(len(texts)), counts)
    digests = b"".join(digest(line) for of in lines for line in of)
    hashes = np.frombuffer(digests, "<u8")[::2]
    best = winnow(hashes, run)
    best = best[doc[: len(best)] == doc[run - 1 :]]
    chosen = best[np.diff(best, prepend=-1) != 0]
    of = doc[chosen]
    lo = np.maximum(firsts[of], chosen - run + 1)
    hi = np.minimum(firsts[of] + counts[of], chosen + run)
    view = memoryview(digests)
    span = lambda a, b, salt=0: digest(view[WIDTH * a : WIDTH * b], salt)
    whole = [span(a, b, c) for a, b, c in zip(lo.tolist(), hi.tolist(), (chosen - lo).tolist(), strict=True)]
    windows = [[span(i, i + run) for i in range(a, b - run + 1)] for a, b in zip(lo.tolist(), hi.tolist(), strict=True)]
    return of, chosen - firsts[of], lo - firsts[of], hi - firsts[of], hashes[chosen].view(np.int64), whole, windows


def places(docs: DataFrame, run: int = RUN_LINES) -> DataFrame:
    """(place struct<k, v, at>, lo, hi, seed, e1, e2, windows) of ``docs(k, v, t)``; lines are numbered from 0, blank ones not counted."""
    kind = docs.schema["k"].dataType.simpleString()
    names = ["k", "v", "at", "lo", "hi", "seed", "e1", "e2", "windows"]

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, _, texts in text_blocks(batch, "t"):
                found = _places(texts, run)
                if found:
                    of, at, lo, hi, seed, whole, windows = found
                    rows = pa.array(of + a)
                    ints = [pa.array(x, pa.int32()) for x in (at, lo, hi)]
                    yield pa.record_batch(
                        [batch.column(0).take(rows), batch.column(1).take(rows), *ints, pa.array(seed), *digest_columns(whole), pa.array(windows, pa.list_(pa.binary()))], names=names
                    )

    found = docs.transform(small_batches).mapInArrow(tidied(find), f"k {kind}, v long, at int, lo int, hi int, seed long, e1 long, e2 long, windows array<binary>")
    return found.select(F.struct("k", "v", "at").alias("place"), "lo", "hi", "seed", "e1", "e2", "windows")


def repeated_runs(docs: DataFrame, run: int = RUN_LINES) -> DataFrame:
    """(k, v, lo, hi): spans of ``run`` lines or more that also stand at an earlier place, by ``k``, ``v`` and line; ``docs`` is (k, v, t).

    Spans may overlap; together they cover each line of each such window and no other line.
    """
    # what is joined back is written first: both sides are then shuffled for the join alone, and adaptive execution can split hot keys
    found = stash(places(docs, run))
    seeds = stash(found.groupBy("seed").agg(F.min("place").alias("a"), F.max("place").alias("z")).where("a < z").select("seed"))
    shared = stash(found.join(seeds, "seed"))
    classes = stash(shared.groupBy("seed", "e1", "e2").agg(F.min("place").alias("owner")))
    several = classes.groupBy("seed").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("seed", F.lit(True).alias("edge"))
    owned = stash(classes.join(several, "seed", "left"))
    settled = shared.join(owned, ["seed", "e1", "e2"])
    inner = settled.where("owner < place").select("place.k", "place.v", "lo", "hi")
    windows = stash(settled.where("owner = place and edge").select("place.k", "place.v", "lo", F.posexplode("windows").alias("i", "w")).select("k", "v", (F.col("lo") + F.col("i")).alias("lo"), "w"))
    here = F.struct("k", "v", "lo")
    first = stash(windows.groupBy("w").agg(F.min(here).alias("a"), F.max(here).alias("z")).where("a < z").select("w", "a"))
    outer = windows.join(first, "w").where(F.col("a") < here).select("k", "v", "lo", (F.col("lo") + run).alias("hi"))
    return inner.unionByName(outer)


def _packed(docs: DataFrame) -> DataFrame:
    """The texts as zstd frames, for the way through a shuffle."""
    kind = docs.schema["k"].dataType.simpleString()

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        zip_ = zstandard.ZstdCompressor(level=1).compress
        for batch in batches:
            for a, b, texts in text_blocks(batch, "t"):
                part = batch.slice(a, b - a)
                yield pa.record_batch([part.column(0), part.column(1), pa.array(map(zip_, texts), pa.binary())], names=["k", "v", "z"])

    return docs.transform(small_batches).mapInArrow(tidied(pack), f"k {kind}, v long, z binary")


def cut_lines(text: bytes, spans: list[tuple[int, int]]) -> tuple[int, int, bytes]:
    """(lines, lines removed, what is left): the kept lines as they were, blank ones among them, joined by line ends."""
    lines = text.split(b"\n")
    full = np.array([bool(line.strip()) for line in lines])
    mark = np.zeros(int(full.sum()) + 1, np.int64)
    for lo, hi in spans:
        mark[lo] += 1
        mark[hi] -= 1
    gone = np.zeros(len(lines), bool)
    gone[full] = np.cumsum(mark)[:-1] > 0
    return int(full.sum()), int(gone.sum()), b"\n".join(line for line, g in zip(lines, gone.tolist(), strict=True) if not g) if gone.any() else text


def _cut(rows: DataFrame) -> DataFrame:
    """(k, n_lines, n_removed, kept) of ``rows(k, z, spans)``."""
    kind = rows.schema["k"].dataType.simpleString()
    names = ["n_lines", "n_removed", "kept"]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            out: list[tuple[int, int, bytes]] = []
            lo = size = 0
            for row in range(batch.num_rows):
                spans = batch.column(2)[row].as_py() or []
                out.append(cut_lines(unpack(batch.column(1)[row].as_py()), [(s["lo"], s["hi"]) for s in spans]))
                size += len(out[-1][2])
                if size >= BLOCK_BYTES or row == batch.num_rows - 1:
                    n, removed, kept = zip(*out, strict=True)
                    yield pa.record_batch([batch.column(0).slice(lo, row + 1 - lo), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())], names=["k", *names])
                    out, lo, size = [], row + 1, 0

    return rows.transform(small_batches).mapInArrow(tidied(cut), f"k {kind}, n_lines long, n_removed long, kept string")


def without_repeated_runs(docs: DataFrame, key: str = "doc_id", text: str = "text", run: int = RUN_LINES) -> DataFrame:
    """One row per input row: key, n_lines, n_removed, kept (the text without its repeated runs).

    Lines end at a line feed; white space at a line's ends is not compared, and blank lines are neither compared, counted nor
    removed. A line goes when a window of ``run`` lines that covers it also starts at an earlier place: in a row of smaller key, or
    further up in the same text. Windows are judged on the input, so the first place of each line stays. A null text counts as
    empty, a null key as the smallest; rows that repeat key and text are marked alike, rows of one key with different texts
    stand in the order of the texts' hashes. An empty table gives an empty result; other columns of the input play no part.
    """
    rows = docs.select(F.col(key).alias("k"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("v"), F.col(text).alias("t"))
    spans = repeated_runs(rows, run).groupBy(F.col("k").alias("of"), F.col("v").alias("ov")).agg(F.collect_set(F.struct("lo", "hi")).alias("spans"))
    packed = _packed(rows)
    told = packed.join(spans, packed.k.eqNullSafe(spans.of) & (packed.v == spans.ov), "left")
    return _cut(told.select("k", "z", "spans")).withColumnRenamed("k", key)


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = without_repeated_runs(table(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", "n_lines", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op7_single_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every line that already stood earlier is deleted, whatever its neighbours are."""
    found = without_repeated_runs(table(spark, sf_dir, "documents", "doc_id", "text"), run=1)
    return found.select("doc_id", "n_lines", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


OP7_SQL = r"""
WITH pieces AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS i FROM documents
), lines AS (
  SELECT doc_id, i, trim(line, chr(32) || chr(9) || chr(11) || chr(12) || chr(13)) AS x FROM pieces
), numbered AS (
  SELECT doc_id, i, x, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS p FROM lines WHERE x <> ''
), windows AS (
  SELECT doc_id, p, x || chr(10) || lead(x, 1) OVER (PARTITION BY doc_id ORDER BY p) || chr(10) || lead(x, 2) OVER (PARTITION BY doc_id ORDER BY p) AS g FROM numbered
), later AS (
  SELECT doc_id, p FROM (SELECT doc_id, p, row_number() OVER (PARTITION BY g ORDER BY doc_id, p) AS nth FROM windows WHERE g IS NOT NULL) WHERE nth > 1
), gone AS (
  SELECT DISTINCT doc_id, unnest([p, p + 1, p + 2]) AS p FROM later
), marked AS (
  SELECT pieces.doc_id, pieces.i, line, numbered.p IS NOT NULL AS counts, gone.p IS NOT NULL AS removed
  FROM pieces LEFT JOIN numbered ON pieces.doc_id = numbered.doc_id AND pieces.i = numbered.i
  LEFT JOIN gone ON numbered.doc_id = gone.doc_id AND numbered.p = gone.p
)
SELECT doc_id, count(*) FILTER (WHERE counts) AS n_lines, count(*) FILTER (WHERE removed) AS n_removed,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE NOT removed), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""

OP7_SINGLE_SQL = r"""
WITH pieces AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS i FROM documents
), trimmed AS (
  SELECT doc_id, i, line, trim(line, chr(32) || chr(9) || chr(11) || chr(12) || chr(13)) AS x FROM pieces
), marked AS (
  SELECT doc_id, i, line, x <> '' AS counts, x <> '' AND row_number() OVER (PARTITION BY x ORDER BY doc_id, i) > 1 AS removed FROM trimmed
)
SELECT doc_id, count(*) FILTER (WHERE counts) AS n_lines, count(*) FILTER (WHERE removed) AS n_removed,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE NOT removed), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
