"""Repeated passages by seed and extend.

Seeds are winnowed anchors: of the word ``SEED_WORDS``-grams that lie in one window of ``window`` words, the one of least hash
(the rightmost of equals). Two places that hold the same window choose the same seed in it, so no repeat of that length is
missed. Each seed is extended both ways as far as a window through it can reach. Places whose whole extension is equal form a
class, and a class is settled by its smallest document at once; only where one seed has several classes, that is at the edges of
repeats, single windows are compared. Places are never paired with each other, so the work is linear in their number however
many documents share a passage.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import small_batches, span_hashes, stash, table, text_blocks, tidied, word_spans

WINDOW_WORDS, SEED_WORDS = 50, 10


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minima of all ``width`` consecutive values, by doubling."""
    have = 1
    while 2 * have <= width:
        x = np.minimum(x[:-have], x[have:])
        have *= 2
    return x if have == width else np.minimum(x[: len(x) - (width - have)], x[width - have :])


def winnow(grams: np.ndarray, width: int) -> np.ndarray:
    """For each run of ``width`` grams the place of its least hash, the rightmost of equals."""
    low = np.uint64(0xFFFFFFFF)
    order = (grams & ~low) | (low - np.arange(len(grams), dtype=np.uint64))
    return (low - (sliding_min(order, width) & low)).astype(np.int64)


def digest(data: memoryview, seed: int = 0) -> bytes:
    return xxhash.xxh3_128_digest(data, seed)


def digest_columns(digests: list[bytes]) -> tuple[pa.Array, pa.Array]:
    both = np.frombuffer(b"".join(digests), "<i8").reshape(-1, 2)
    return pa.array(both[:, 0]), pa.array(both[:, 1])


def _seeds(texts: list[bytes], window: int, seed_words: int):
    """For each seed of the texts: text number, extension lo..hi in words of that text, gram hash, digest of the extension."""
    joined, starts, ends, counts = word_spans([b" ".join(t.split()) for t in texts])
    firsts = np.cumsum(counts) - counts
    if counts.max(initial=0) < window:
        return None
    doc = np.repeat(np.arange(len(texts)), counts)
    words = span_hashes(np.frombuffer(joined, np.uint8), starts, ends)
    at = np.arange(len(words) - seed_words + 1)
    grams = span_hashes(words, at, at + seed_words)
    best = winnow(grams, window - seed_words + 1)
    whole = doc[: len(best)] == doc[window - 1 : window - 1 + len(best)]
    best = best[whole]
    chosen = best[np.diff(best, prepend=-1) != 0]
    of = doc[chosen]
    lo = np.maximum(firsts[of], chosen - (window - seed_words))
    hi = np.minimum(firsts[of] + counts[of], chosen + window)
    view = memoryview(joined)
    spans = zip(starts[lo].tolist(), ends[hi - 1].tolist(), (chosen - lo).tolist(), strict=True)
    return of, lo - firsts[of], hi - firsts[of], grams[chosen].view(np.int64), [digest(view[a:b], s) for a, b, s in spans]


def seed_places(docs: DataFrame, window: int = WINDOW_WORDS, seed_words: int = SEED_WORDS) -> DataFrame:
    """(k, v, lo, hi, seed, e1, e2) of ``docs(k, v, t)``."""
    kind = docs.schema["k"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, _, texts in text_blocks(batch, "t"):
                found = _seeds(texts, window, seed_words)
                if found:
                    of, lo, hi, seed, digests = found
                    rows = pa.array(of + a)
                    yield pa.record_batch(
                        [batch.column(0).take(rows), batch.column(1).take(rows), pa.array(lo, pa.int32()), pa.array(hi, pa.int32()), pa.array(seed), *digest_columns(digests)],
                        names=["k", "v", "lo", "hi", "seed", "e1", "e2"],
                    )

    return docs.transform(small_batches).mapInArrow(tidied(run), f"k {kind}, v long, lo int, hi int, seed long, e1 long, e2 long")


def _packed(docs: DataFrame) -> DataFrame:
    """The texts as zstd frames of their words, for the way through a shuffle."""
    kind = docs.schema["k"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=1)
        for batch in batches:
            for a, b, texts in text_blocks(batch, "t"):
                part = batch.slice(a, b - a)
                yield pa.record_batch([part.column(0), part.column(1), pa.array([pack.compress(b" ".join(t.split())) for t in texts], pa.binary())], names=["k", "v", "z"])

    return docs.transform(small_batches).mapInArrow(tidied(run), f"k {kind}, v long, z binary")


def _window_digests(need: DataFrame, window: int) -> DataFrame:
    """(k, v, at, w1, w2) for the windows inside the ``spans`` of each row of ``need(k, v, z, spans)``; one row a window."""
    kind = need.schema["k"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            for row in range(batch.num_rows):
                joined, starts, ends, _ = word_spans([unpack.decompress(batch.column(2)[row].as_py())])
                spans = batch.column(3)[row].values
                lo, hi = (np.asarray(spans.field(i)) for i in (0, 1))
                mark = np.zeros(len(starts) + 1, np.int64)
                np.add.at(mark, lo, 1)
                np.add.at(mark, hi - window + 1, -1)
                at = np.flatnonzero(np.cumsum(mark)[:-1])
                view = memoryview(joined)
                digests = [digest(view[a:b]) for a, b in zip(starts[at].tolist(), ends[at + window - 1].tolist(), strict=True)]
                here = pa.array(np.full(len(at), row))
                yield pa.record_batch([batch.column(0).take(here), batch.column(1).take(here), pa.array(at, pa.int32()), *digest_columns(digests)], names=["k", "v", "at", "w1", "w2"])

    return need.transform(small_batches).mapInArrow(tidied(run), f"k {kind}, v long, at int, w1 long, w2 long")


def _cut(rows: DataFrame) -> DataFrame:
    """What is left of each text of ``rows(k, z, spans)`` after its spans are cut out."""
    kind = rows.schema["k"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            out: list[tuple[int, int, str]] = []
            for row in range(batch.num_rows):
                data, spans = unpack.decompress(batch.column(1)[row].as_py()), batch.column(2)[row]
                words = data.split()
                n, left = len(words), data
                if spans.is_valid:
                    mark = np.zeros(n + 1, np.int64)
                    np.add.at(mark, np.asarray(spans.values.field(0)), 1)
                    np.add.at(mark, np.asarray(spans.values.field(1)), -1)
                    keep = np.flatnonzero(np.cumsum(mark)[:-1] == 0).tolist()
                    left, words = b" ".join([words[i] for i in keep]), keep
                out.append((n, n - len(words), hashlib.sha256(left).hexdigest()))
            n, removed, sha = zip(*out, strict=True) if out else ((), (), ())
            yield pa.record_batch([batch.column(0), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(sha, pa.string())], names=["k", "n_words", "n_removed", "kept_sha256"])

    return rows.transform(small_batches).mapInArrow(tidied(run), f"k {kind}, n_words long, n_removed long, kept_sha256 string")


def repeated_spans(docs: DataFrame, window: int = WINDOW_WORDS, seed_words: int = SEED_WORDS) -> DataFrame:
    """(k, v, lo, hi): spans of words, of ``window`` or more, that also stand in a document of smaller ``k``; ``docs`` is (k, v, t).

    Spans may overlap; together they cover each word of each such window and no other word.
    """
    places = stash(seed_places(docs, window, seed_words))
    # what is joined back is written first: both sides are then shuffled for the join alone, and adaptive execution can split hot
    # keys. A seed is an edge if its places differ in their extension
    seeds = stash(
        places.groupBy("seed").agg(F.min("k").alias("first"), F.max("k").alias("last"), ((F.min("e1") < F.max("e1")) | (F.min("e2") < F.max("e2"))).alias("edge"))
        .where("first < last").select("seed", "edge")
    )
    shared = stash(places.join(seeds, "seed"))
    classes = stash(shared.groupBy("seed", "e1", "e2").agg(F.min("k").alias("owner")))
    settled = stash(shared.join(classes, ["seed", "e1", "e2"]).select("k", "v", "lo", "hi", "owner", "edge"))
    inner = settled.where("owner < k").select("k", "v", "lo", "hi")
    edges = settled.where("owner = k and edge").groupBy("k", "v").agg(F.collect_set(F.struct("lo", "hi")).alias("spans"))
    windows = stash(_window_digests(_packed(docs).join(edges, ["k", "v"]).select("k", "v", "z", "spans"), window))
    first = stash(windows.groupBy("w1", "w2").agg(F.min("k").alias("first"), F.max("k").alias("last")).where("first < last").drop("last"))
    outer = windows.join(first, ["w1", "w2"]).where("first < k").select("k", "v", F.col("at").alias("lo"), (F.col("at") + window).cast("int").alias("hi"))
    return inner.unionByName(outer)


def cut_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW_WORDS, seed_words: int = SEED_WORDS) -> DataFrame:
    """One row per input row: key, n_words, n_removed, kept_sha256.

    Words are runs of ``[^\\x20\\x09-\\x0D]``, unchanged. A word goes when a window of ``window`` words that covers it also starts in a
    document of smaller key; windows are judged on the input. A null text has no words; a null key neither loses words nor
    takes any from others; rows of one key do not take words from each other. An empty table gives an empty result.
    """
    rows = docs.select(F.col(key).alias("k"), F.coalesce(F.xxhash64(text), F.lit(0)).alias("v"), F.col(text).alias("t"))
    spans = repeated_spans(rows, window, seed_words).groupBy("k", "v").agg(F.collect_set(F.struct("lo", "hi")).alias("spans"))
    return _cut(_packed(rows).join(spans, ["k", "v"], "left").select("k", "z", "spans")).withColumnRenamed("k", key)


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut_repeats(table(spark, sf_dir, "documents", "doc_id", "text"))


OP10_SQL = r"""
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), starts AS (
  SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS s FROM w WHERE len(ws) >= 50
), grams AS (
  SELECT doc_id, s, array_to_string(ws[s : s + 49], ' ') AS g FROM starts
), hit AS (
  SELECT doc_id, s FROM (SELECT doc_id, s, min(doc_id) OVER (PARTITION BY g) AS m FROM grams) WHERE m < doc_id
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(s, s + 50)) AS p FROM hit
), gl AS (
  SELECT doc_id, list(p) AS ps FROM gone GROUP BY doc_id
)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(len(ps), 0) AS BIGINT) AS n_removed,
       sha256(coalesce(array_to_string(CASE WHEN ps IS NULL THEN ws ELSE list_filter(ws, lambda x, i: NOT list_contains(ps, i)) END, ' '), '')) AS kept_sha256
FROM w LEFT JOIN gl ON w.doc_id = gl.doc_id
"""
