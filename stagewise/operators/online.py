"""Filters that learn keys after they were built.

A segment has a Bloom filter of its positives and an edge map that is exact on the positives and the negatives that the Bloom filter
lets through. Beside its bits a segment keeps the keys of the edge map alone, about two for each positive, in columns that a probe does
not read. New negatives are probed first: only those that pass reach their segments, all others cost nothing. New positives set
bits of the Bloom filter and become edges. No table of all keys is kept, and segments without news stay as they are.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import key64, segment_col
from ..plans.storage import keep
from .cells import pack, read_np
from .elementary import MAX_TRIES, Built, bloom_bits, bloom_shape, nodes_np, test_bloom, two_colour
from .filters import _ARROW, SEGMENT_KEYS, SEGMENT_TYPE, FilterHandle, Spec, Stage, _handle, normalise

ONLINE_TYPE = f"{SEGMENT_TYPE}, pos array<long>, passed array<long>"
_SCHEMA = pa.schema([*_ARROW, ("pos", pa.list_(pa.int64())), ("passed", pa.list_(pa.int64()))])


def _edges(pos: np.ndarray, passed: np.ndarray, built: Built | None, seed: int) -> Built:
    """The edge map of a segment's keys: with the seed and size at hand if these still do, else with others."""
    keys = np.concatenate([pos, passed])
    want = np.arange(len(keys)) < len(pos)
    need = max(14, math.ceil(2.33 * len(keys)) + 8)
    m, s = (built.m, built.seed) if built else (math.ceil(1.25 * need), seed)  # some room for keys to come
    for t in range(MAX_TRIES):
        if m >= need:
            bits = two_colour(*nodes_np(keys, s, m), want.astype(np.int8), m)
            if bits is not None:
                return Built(s, m, 1, pack(bits, 1))
        s, m = seed + 16 * (t + 1), max(m, math.ceil((1.25 if t < 8 else 1.6) * need))
    raise RuntimeError("no acyclic edge map found")


def _segment(seg: int, old: dict | None, yes: np.ndarray, no: np.ndarray, eps: float, room: float) -> dict:
    """A segment's row after it has learnt positives and negatives; ``old`` is None for a new one."""
    seed = 1 + 100_003 * seg
    stage = lambda d: Built(d["seed"], d["m"], d["width"], np.asarray(d["words"], np.int64))
    if old:
        bloom, edges = map(stage, old["stages"])
        pos, passed = np.asarray(old["pos"], np.int64), np.asarray(old["passed"], np.int64)
        n, u = old["n"], old["u"]
    else:
        m, k = bloom_shape(math.ceil(room * max(1, len(yes))), eps)
        bloom, edges = Built(seed, m, k, pack(np.zeros(m, np.uint8), 1)), None
        pos, passed, n, u = np.zeros(0, np.int64), np.zeros(0, np.int64), 0, 0
    yes = np.setdiff1d(yes, pos)
    if len(yes):
        cells = read_np(bloom.words, np.arange(bloom.m), 1)
        cells[bloom_bits(yes, bloom.seed, bloom.m, bloom.width).ravel()] = 1
        bloom = Built(bloom.seed, bloom.m, bloom.width, pack(cells, 1))
    pos, passed = np.union1d(pos, yes), np.setdiff1d(passed, yes)
    no = np.setdiff1d(np.setdiff1d(no, pos), passed)
    passed = np.union1d(passed, no[test_bloom(bloom, no)])
    edges = _edges(pos, passed, edges, seed + 1000)
    return {"seg": seg, "n": len(pos), "u": u + len(yes) + len(no), "stages": [bloom.row(), edges.row()], "tail": None, "survivors": [u - n, len(passed)], "pos": pos, "passed": passed}


@dataclass
class OnlineFilter:
    handle: FilterHandle
    eps: float
    room: float

    def probe(self, df: DataFrame, keys: Sequence[str], out: str = "hit", **how) -> DataFrame:
        return self.handle.probe(df, keys, out, **how)

    def bits(self) -> int:
        return self.handle.bits()

    def include(self, df: DataFrame, keys: Sequence[str]) -> OnlineFilter:
        """New positives. Negatives that the grown Bloom filter now lets through are wrong until they are excluded again."""
        return self._learnt(df.select(key64(df, keys).alias("k"), F.lit(True).alias("is_pos")))

    def exclude(self, df: DataFrame, keys: Sequence[str]) -> OnlineFilter:
        """New negatives; keys that are positive stay so. Those that the Bloom filter rejects anyway are not moved."""
        coarse = FilterHandle(Spec("and", self.handle.spec.stages[:1]), self.handle.parts, self.handle.segments, self.handle.n, self.handle.u, 1, self.handle.hashes, self.handle.bytes_, None, self.handle.hashes_at)
        passing = coarse.probe(df.select(key64(df, keys).alias("k")).distinct(), ["k"], "passes").where("passes")
        return self._learnt(passing.select("k", F.lit(False).alias("is_pos")))

    def _learnt(self, news: DataFrame) -> OnlineFilter:
        eps, room, parts = self.eps, self.room, self.handle.parts
        news = keep(news.where("k is not null").distinct().withColumn("seg", segment_col(F.col("k"), parts)))
        touched = news.select("seg").distinct()
        old = self.handle.segments

        def run(rows: pa.Table, fresh: pa.Table) -> pa.Table:
            k, p = np.asarray(fresh["k"].combine_chunks()), np.asarray(fresh["is_pos"].combine_chunks()).astype(bool)
            row = rows.to_pylist()[0] if rows.num_rows else None
            return pa.Table.from_pylist([_segment(fresh["seg"][0].as_py(), row, k[p], k[~p], eps, room)], schema=_SCHEMA)

        changed = old.join(F.broadcast(touched), "seg", "left_semi").groupBy("seg").cogroup(news.groupBy("seg")).applyInArrow(run, ONLINE_TYPE)
        segments = old.join(F.broadcast(touched), "seg", "left_anti").select(*[f.name for f in _SCHEMA]).unionByName(changed)
        return OnlineFilter(_handle(self.handle.spec, parts, segments, None), eps, room)


def online(df: DataFrame, keys: Sequence[str], label: str, eps: float | None = None, room: float = 2.0, segment_keys: int = SEGMENT_KEYS) -> OnlineFilter:
    """An exact filter of the labelled keys that can learn more; ``room``: positives that its Bloom filter is sized for, as a multiple of those at hand."""
    members = keep(normalise(df, keys, label))
    sizes = members.agg(F.count(F.lit(1)).alias("u"), F.coalesce(F.sum(F.col("is_pos").cast("long")), F.lit(0)).alias("n")).first()
    lam = (sizes["u"] - sizes["n"]) / max(1, sizes["n"])
    rate = eps or 2.0 ** -max(1, math.floor(math.log2(max(2.0, lam))))
    parts = max(1, math.ceil(sizes["u"] / segment_keys))

    def run(rows: pa.Table) -> pa.Table:
        k, p = np.asarray(rows["k"].combine_chunks()), np.asarray(rows["is_pos"].combine_chunks()).astype(bool)
        return pa.Table.from_pylist([_segment(rows["seg"][0].as_py(), None, k[p], k[~p], rate, room)], schema=_SCHEMA)

    segments = members.withColumn("seg", segment_col(F.col("k"), parts)).groupBy("seg").applyInArrow(run, ONLINE_TYPE)
    return OnlineFilter(_handle(Spec("and", (Stage("bloom", rate), Stage("edge_map"))), parts, segments, None), rate, room)
