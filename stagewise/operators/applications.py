"""What the filters are used for: static dictionaries, random-access code stores, two-table stores, sorted runs, learned filters."""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF, NGram, RegexTokenizer
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import theory
from ..functions.hashing import below_col, below_np, hash_col, hash_np, key64, segment_col
from ..plans.storage import keep
from . import filters
from .cells import pack, read_col
from .elementary import Built, bloom_bits, build_counting, test_counting
from .filters import FilterHandle

# --- Boolean functions ---------------------------------------------------------------------------------------------------------


def dictionary_encode(df: DataFrame, x: str, bit: str, **how) -> FilterHandle:
    return filters.staged(df, [x], bit, **how)


def dictionary_eval(handle: FilterHandle, df: DataFrame, x: str, out: str = "bit") -> DataFrame:
    return handle.probe(df, [x], out)


# --- random-access code stores ---------------------------------------------------------------------------------------------------

CODE_STRIDE = 64  # a code of more than 64 bits would take an alphabet of astronomic skew


def huffman_code(df: DataFrame, symbol: str) -> dict[str, str]:
    """Symbol to bits. The heavier branch gets 0, so ones are the minority; ties go by symbol. One row a distinct symbol comes to the driver."""
    counts = sorted((r["c"], r["s"]) for r in df.groupBy(F.col(symbol).alias("s")).agg(F.count(F.lit(1)).alias("c")).collect())
    heap = [(c, s, [s]) for c, s in counts]
    code = {s: "" for _, s in counts}
    if len(heap) == 1:
        return {counts[0][1]: "0"}
    while len(heap) > 1:
        light, heavy = heapq.heappop(heap), heapq.heappop(heap)
        for bit, group in (("1", light[2]), ("0", heavy[2])):
            for s in group:
                code[s] = bit + code[s]
        heapq.heappush(heap, (light[0] + heavy[0], min(light[1], heavy[1]), light[2] + heavy[2]))
    return code


def _code_map(code: dict[str, str]) -> Column:
    return F.create_map(*[F.lit(x) for pair in sorted(code.items()) for x in pair])


def huffman_bits(df: DataFrame, position: str, symbol: str, code: dict[str, str]) -> DataFrame:
    """(key, bit): bit j of the symbol at position i under the key i * 64 + j."""
    bits = F.try_element_at(_code_map(code), F.col(symbol))
    return df.select(F.col(position).alias("i"), F.posexplode(F.split(bits, "")).alias("j", "b")).where("b <> ''").select(
        (F.col("i") * CODE_STRIDE + F.col("j")).alias("key"), (F.col("b") == "1").alias("bit")
    )


@dataclass
class CodeStore:
    handle: FilterHandle
    code: dict[str, str]

    def get(self, positions: DataFrame, position: str) -> DataFrame:
        """``positions`` with the symbol stored at each: as many probes as the longest code has bits."""
        longest = max(map(len, self.code.values()))
        asked = positions.select(F.col(position).alias("i")).distinct()
        probes = asked.select("i", F.explode(F.sequence(F.lit(0), F.lit(longest - 1))).alias("j")).withColumn("key", F.col("i") * CODE_STRIDE + F.col("j"))
        bits = self.handle.probe(probes, ["key"]).groupBy("i").agg(F.sort_array(F.collect_list(F.struct("j", "hit"))).alias("bs"))
        text = F.concat_ws("", F.transform("bs", lambda b: F.when(b["hit"], "1").otherwise("0")))
        by_code = F.create_map(*[F.lit(x) for s, c in sorted(self.code.items()) for x in (c, s)])
        prefixes = F.transform(F.sequence(F.lit(1), F.lit(longest)), lambda n: F.try_element_at(by_code, F.substring(F.col("text"), F.lit(1), n)))
        found = bits.withColumn("text", text).select(F.col("i").alias(position), F.get(F.filter(prefixes, lambda s: s.isNotNull()), F.lit(0)).alias("symbol"))
        return positions.join(found, position, "left")


def huffman_store(df: DataFrame, position: str, symbol: str, kind: str = "staged", **how) -> CodeStore:
    code = huffman_code(df, symbol)
    bits = huffman_bits(df, position, symbol, code)
    build = {"staged": filters.staged, "shared": filters.shared, "single": lambda d, k, b, **h: filters.single(d, k, b, "retrieval", **h)}[kind]
    return CodeStore(build(bits, ["key"], "bit", **how), code)


def huffman_blocks(df: DataFrame, position: str, symbol: str, block: int = 4096) -> tuple[DataFrame, dict[str, str]]:
    """(block, n, bits): plain coding, which only a decoder from the block's start can read."""
    code = huffman_code(df, symbol)
    coded = df.select(F.floor(F.col(position) / block).alias("block"), F.col(position).alias("i"), F.try_element_at(_code_map(code), F.col(symbol)).alias("c"))
    return coded.groupBy("block").agg(F.count(F.lit(1)).alias("n"), F.concat_ws("", F.transform(F.sort_array(F.collect_list(F.struct("i", "c"))), lambda x: x["c"])).alias("bits")), code


def huffman_decode(blocks: DataFrame, code: dict[str, str], block: int = 4096) -> DataFrame:
    """(i, symbol) of whole blocks, bit after bit; ``block`` is a multiple of the positions' start."""
    back = {c: s for s, c in code.items()}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out: list[tuple[int, str]] = []
            for b, bits in zip(batch["block"], batch["bits"], strict=True):
                at, word = int(b) * block, ""
                for bit in bits:
                    word += bit
                    if word in back:
                        out.append((at, back[word]))
                        at, word = at + 1, ""
            yield pd.DataFrame(out, columns=["i", "symbol"])

    return blocks.select("block", "bits").mapInPandas(run, "i long, symbol string")


def flipped(handle: FilterHandle, bits: int, seed: int = 1) -> FilterHandle:
    """The filter with ``bits`` payload bits of each segment's last stage flipped, at places chosen by the seed."""

    def run(rows: pa.Table) -> pa.Table:
        row = rows.to_pylist()[0]
        stage = row["stages"][-1]
        words = np.asarray(stage["words"], np.int64).view(np.uint64).copy()
        at = np.random.default_rng(seed + row["seg"]).choice(stage["m"] * stage["width"], bits, replace=False)
        np.bitwise_xor.at(words, at >> 6, np.uint64(1) << (at & 63).astype(np.uint64))
        stage["words"] = words.view(np.int64).tolist()
        return pa.Table.from_pylist([row], schema=filters._ARROW)

    columns = [f.name for f in filters._ARROW]
    return filters._handle(handle.spec, handle.parts, handle.segments.select(*columns).groupBy("seg").applyInArrow(run, filters.SEGMENT_TYPE), handle.keys)


# --- two tables with predicted location -------------------------------------------------------------------------------------------


def two_table_build(df: DataFrame, key: str, load: float = 0.4, segment_keys: int = filters.SEGMENT_KEYS) -> DataFrame:
    """(k, seg, tbl, bucket, seed, buckets): each key in its bucket of table 1 or 2, one key a bucket; placed by eviction inside a segment.

    ``seed`` and ``buckets`` are those of the segment: with them a key's two buckets follow from the key.
    """
    keys = keep(df.select(key64(df, [key]).alias("k")).where("k is not null").distinct())
    parts = max(1, math.ceil(keys.count() / segment_keys))

    def run(rows: pa.Table) -> pa.Table:
        k = np.sort(np.asarray(rows["k"].combine_chunks()))
        buckets = max(1, math.ceil(len(k) / (2 * load)))
        for seed in range(1, 65):
            at = [below_np(hash_np(100 * seed + t, k), buckets).tolist() for t in (0, 1)]
            table: list[dict[int, int]] = [{}, {}]
            where = {}
            for i in range(len(k)):
                x, t = i, 0
                for _ in range(400):
                    y = table[t].get(at[t][x])
                    table[t][at[t][x]] = x
                    where[x] = t
                    if y is None:
                        break
                    x, t = y, 1 - t
                else:
                    break
            else:
                t = np.array([where[i] for i in range(len(k))])
                b = np.where(t == 0, at[0], at[1])
                same = {"seed": np.full(len(k), seed, np.int32), "buckets": np.full(len(k), buckets, np.int64)}
                return pa.table({"k": k, "seg": np.full(len(k), rows["seg"][0].as_py(), np.int32), "tbl": t.astype(np.int32) + 1, "bucket": b.astype(np.int64), **same})
        raise RuntimeError("no placement found")

    return keep(keys.withColumn("seg", segment_col(F.col("k"), parts)).groupBy("seg").applyInArrow(run, "k long, seg int, tbl int, bucket long, seed int, buckets long"))


@dataclass
class TwoTableStore:
    """Rows in their buckets; a read fetches one bucket of one table and compares the key that lies there."""

    rows: DataFrame  # seg, tbl, bucket, key, value
    layout: DataFrame  # seg, seed, buckets: one row a segment
    parts: int

    def _read(self, asked: DataFrame, table: Column) -> DataFrame:
        """``asked(key, k, seg, seed, buckets, ...)`` with what lies in the key's bucket of the table: ``held`` and ``value``."""
        spot = lambda t: below_col(hash_col((F.col("seed") * 100 + t).cast("long"), F.col("k")), F.col("buckets"))
        at = asked.withColumn("tbl", table).withColumn("bucket", F.when(F.col("tbl") == 1, spot(0)).otherwise(spot(1)))
        return at.join(self.rows.withColumnRenamed("key", "held"), ["seg", "tbl", "bucket"], "left")

    def get(self, asked: DataFrame, key: str, handle: FilterHandle | None = None) -> DataFrame:
        """(key, value, reads) of the distinct keys asked for: the predicted table is read, and the other one if another key lies there."""
        keys = asked.select(F.col(key).alias("key"), key64(asked, [key]).alias("k")).distinct()
        known = keys.withColumn("seg", segment_col(F.col("k"), self.parts)).join(F.broadcast(self.layout) if self.parts <= LAYOUT_ROWS else self.layout, "seg")
        guessed = handle.probe(known, ["k"], "second") if handle else known.withColumn("second", F.lit(False))
        one = keep(self._read(guessed, F.when(F.col("second"), 2).otherwise(1)))
        right = F.col("held").eqNullSafe(F.col("key"))
        found = one.where(right).select("key", "value", F.lit(1).alias("reads"))
        again = self._read(one.where(~right).drop("tbl", "bucket", "held", "value"), F.when(F.col("second"), 1).otherwise(2))
        return found.unionByName(again.select("key", F.when(right, F.col("value")).alias("value"), F.lit(2).alias("reads")))


#: Segments whose layout is sent to every executor (20 bytes each); beyond, it is shuffled.
LAYOUT_ROWS = 1 << 20


def two_table_store(df: DataFrame, key: str, value: str, placed: DataFrame, parts: int) -> TwoTableStore:
    """``df``'s keys and values, of any type, in the buckets that ``placed`` gives to their 64-bit keys."""
    rows = df.select(F.col(key).alias("key"), F.col(value).alias("value"), key64(df, [key]).alias("k")).where("k is not null")
    stored = keep(rows.join(placed.select("k", "seg", "tbl", "bucket"), "k").select("seg", "tbl", "bucket", "key", "value"))
    return TwoTableStore(stored, keep(placed.select("seg", "seed", "buckets").distinct()), parts)


def predictor(placed: DataFrame, kind: str = "alternating", rounds: int | None = None, tail: str | None = None, bits_per_bucket: int = 8, **how) -> FilterHandle:
    """A filter of the second table's keys. ``rounds``: layers trained so far; ``bloom``, ``blocked``, ``counting``: the baselines of equal space."""
    labelled = placed.select("k", (F.col("tbl") == 2).alias("second"))
    if kind == "alternating":
        return filters.alternating(labelled, ["k"], "second", max_layers=rounds or filters.MAX_LAYERS, tail=tail, **how)
    # the others at equal space: as many bits as the locking baseline has for all keys; a counter takes four
    sizes = labelled.agg(F.count(F.lit(1)).alias("u"), F.sum(F.col("second").cast("long")).alias("n")).first()
    cells = bits_per_bucket * sizes["u"] / (4 if kind == "counting" else 1)
    return filters.single(labelled, ["k"], "second", kind, max(1e-6, 2 ** (-theory.LN2 * cells / max(1, sizes["n"]))), **how)


class _Layers:
    """The layers of an alternating filter of Bloom filters, empty at first, which wrong answers fill."""

    def __init__(self, n: int, lam: float, delta: float = 0.5, seed: int = 1):
        plan = theory.layer_plan(max(1, n), max(1.0, lam), delta) + [(0, delta * delta, 64.0)] * 8
        self.shape = [(seed + 1000 * i, max(64, math.ceil(bits)), max(1, round(-math.log2(rate)))) for i, (_, rate, bits) in enumerate(plan)]
        self.bits = [np.zeros(m, bool) for _, m, _ in self.shape]

    def spots(self, keys: np.ndarray) -> list[np.ndarray]:
        return [bloom_bits(keys, *shape).T for shape in self.shape]

    def decided(self, spots: list[np.ndarray]) -> np.ndarray:
        """The layer that says no, counted from 0; the answer is "positive" where it is odd."""
        at = np.full(len(spots[0]), len(self.bits))
        for i in reversed(range(len(self.bits))):
            at[~self.bits[i][spots[i]].all(1)] = i
        return at

    def positive(self, at: np.ndarray) -> np.ndarray:
        return np.where(at < len(self.bits), at % 2 == 1, len(self.bits) % 2 == 1)

    def teach(self, spots: list[np.ndarray], truth: np.ndarray) -> int:
        """Keys that are answered wrongly go into the layer that decided, and into the next ones, until the answer is right; returns how many were wrong."""
        first = None
        for _ in range(len(self.bits)):
            at = self.decided(spots)
            bad = (self.positive(at) != truth) & (at < len(self.bits))
            first = int(bad.sum()) if first is None else first
            if not bad.any():
                break
            for i in np.unique(at[bad]):
                self.bits[i][spots[i][bad & (at == i)].ravel()] = True
        return first or 0

    def dumps(self) -> bytes:
        return b"".join(np.packbits(b).tobytes() for b in self.bits)

    def loads(self, data: bytes) -> None:
        at = 0
        for i, (_, m, _) in enumerate(self.shape):
            size = -(-m // 8)
            self.bits[i] = np.unpackbits(np.frombuffer(data, np.uint8, size, at), count=m).astype(bool)
            at += size

    def rows(self) -> list[dict]:
        return [Built(s, m, k, pack(b.astype(np.uint8), 1)).row() for (s, m, k), b in zip(self.shape, self.bits, strict=True)]


def trained_layers(data: bytes | None, n: int, lam: float, seed: int, delta: float = 0.5) -> _Layers:
    """Layers for about ``n`` positives, empty or as they were written."""
    layers = _Layers(n, lam, delta, seed)
    if data is not None:
        layers.loads(data)
    return layers


#: Keys that are asked, and answered, before the predictor learns from its mistakes.
TRAINING_BATCH = 256


def adaptive_train(placed: DataFrame, rounds: int = 8, delta: float = 0.5) -> tuple[FilterHandle, DataFrame]:
    """A predictor trained online by passes over the keys, and (round, u, wrong, error_rate) after each pass.

    The layers have the sizes of an alternating filter but begin empty.
    """

    def run(rows: pa.Table) -> pa.Table:
        k, second = np.asarray(rows["k"].combine_chunks()), np.asarray(rows["tbl"].combine_chunks()) == 2
        order = np.argsort(k)
        k, second = k[order], second[order]
        n, seg = max(1, int(second.sum())), rows["seg"][0].as_py()
        layers = _Layers(n, (len(k) - n) / n, delta, 1 + 100_003 * seg)
        spots, wrong = layers.spots(k), []
        for _ in range(rounds):
            for lo in range(0, len(k), TRAINING_BATCH):
                layers.teach([s[lo : lo + TRAINING_BATCH] for s in spots], second[lo : lo + TRAINING_BATCH])
            wrong.append(int((layers.positive(layers.decided(spots)) != second).sum()))
        return pa.Table.from_pylist([{"seg": seg, "n": n, "u": len(k), "stages": layers.rows(), "tail": None, "survivors": wrong}], schema=filters._ARROW)

    segments = placed.select("k", "tbl", "seg").groupBy("seg").applyInArrow(run, filters.SEGMENT_TYPE)
    members = placed.select("k", (F.col("tbl") == 2).alias("is_pos"))
    parts = (placed.agg(F.max("seg")).first()[0] or 0) + 1
    handle = filters._handle(filters.Spec("alternate", (filters.Stage("bloom"),), False, None, delta), parts, segments, members)
    each = handle.segments.select("u", F.posexplode("survivors").alias("i", "wrong")).groupBy((F.col("i") + 1).alias("round"))
    return handle, each.agg(F.sum("u").alias("u"), F.sum("wrong").alias("wrong")).withColumn("error_rate", F.col("wrong") / F.col("u"))


def two_table_get(placed: DataFrame, handle: FilterHandle | None, df: DataFrame, key: str) -> DataFrame:
    """``df`` with tbl, bucket and the reads of a lookup: one if the predicted table is right, else two; without a predictor table 1 comes first."""
    asked = df.withColumn("k", key64(df, [key]))
    guessed = handle.probe(asked, ["k"], "second") if handle else asked.withColumn("second", F.lit(False))
    found = guessed.join(placed.select("k", "tbl", "bucket"), "k", "left")
    right = F.col("second") == (F.col("tbl") == 2)
    return found.withColumn("reads", F.when(right, 1).otherwise(2)).drop("second", "k")


def locking_predictor(placed: DataFrame, bits_per_bucket: int = 8, load: float = 0.4) -> DataFrame:
    """(seg, moved, n2, bits): keys of table 1 that a counting filter of table 2 would misplace are locked into table 2 until none is left."""

    def run(rows: pa.Table) -> pa.Table:
        k, t = np.asarray(rows["k"].combine_chunks()), np.asarray(rows["tbl"].combine_chunks())
        one, two, moved = k[t == 1], k[t == 2], 0
        cells = max(16, math.ceil(bits_per_bucket * len(k) / (2 * load) / 4))
        eps = min(0.5, 2 ** (-theory.LN2 * cells / max(1, len(two))))
        f = build_counting(two, two[:0], eps, 1)
        while len(one):
            bad = test_counting(f, one)
            if not bad.any():
                break
            moved += int(bad.sum())
            one, two = one[~bad], np.concatenate([two, one[bad]])
            f = build_counting(two, two[:0], eps, 1)
        return pa.table({"seg": np.array([rows["seg"][0].as_py()], np.int32), "moved": [moved], "n2": [len(two)], "bits": [4 * f.m]})

    return placed.select("k", "tbl", "seg").groupBy("seg").applyInArrow(run, "seg int, moved long, n2 long, bits long")


def locking_blocks(df: DataFrame, key: str, load: float = 0.4, segment_keys: int = filters.SEGMENT_KEYS) -> tuple[DataFrame, DataFrame]:
    """The locking baseline: ((k, seg, tbl, bucket, stash), (seg, seed, buckets, words)).

    Each bucket of table 1 has a block of two four-bit counters of the keys that lie in table 2 but have their first bucket here; a key
    uses one of the two. A key stays in table 1 only where its counter is zero, so a counter above zero always means table 2. Keys
    whose bucket in table 2 is taken lie in its stash.
    """
    keys = keep(df.select(key64(df, [key]).alias("k")).where("k is not null").distinct())
    parts = max(1, math.ceil(keys.count() / segment_keys))

    def place(k: np.ndarray, seg: int) -> tuple[np.ndarray, ...]:
        buckets, seed = max(1, math.ceil(len(k) / (2 * load))), 1 + seg
        one, two, side = (below_np(hash_np(100 * seed + t, k), n) for t, n in ((0, buckets), (1, buckets), (2, 2)))
        counter = 2 * one + side
        alone = np.flatnonzero(np.bincount(counter, minlength=2 * buckets)[counter] == 1)
        first = alone[np.unique(one[alone], return_index=True)[1]]  # of two keys with a counter each, one stays
        t = np.full(len(k), 2, np.int32)
        t[first] = 1
        late = np.ones(len(k), bool)
        rest = np.flatnonzero(t == 2)
        late[rest[np.unique(two[rest], return_index=True)[1]]] = False
        late[first] = False
        cells = np.minimum(15, np.bincount(counter[rest], minlength=2 * buckets)).astype(np.uint64)
        return t, np.where(t == 1, one, two), late, cells, seed, buckets

    def items(rows: pa.Table) -> pa.Table:
        k, seg = np.sort(np.asarray(rows["k"].combine_chunks())), rows["seg"][0].as_py()
        t, bucket, late, *_ = place(k, seg)
        return pa.table({"k": k, "seg": np.full(len(k), seg, np.int32), "tbl": t, "bucket": bucket, "stash": late})

    def blocks(rows: pa.Table) -> pa.Table:
        k, seg = np.sort(np.asarray(rows["k"].combine_chunks())), rows["seg"][0].as_py()
        *_, cells, seed, buckets = place(k, seg)
        return pa.table({"seg": np.array([seg], np.int32), "seed": np.array([seed], np.int64), "buckets": np.array([buckets], np.int64), "words": pa.array([pack(cells, 4)], pa.list_(pa.int64()))})

    dealt = keys.withColumn("seg", segment_col(F.col("k"), parts)).groupBy("seg")
    return keep(dealt.applyInArrow(items, "k long, seg int, tbl int, bucket long, stash boolean")), keep(dealt.applyInArrow(blocks, "seg int, seed long, buckets long, words array<long>"))


def locking_guess(items: DataFrame, blocks: DataFrame) -> DataFrame:
    """``items`` with ``second``: whether the key's counter says table 2."""
    spot = lambda t, n: below_col(hash_col(F.col("seed") * 100 + t, F.col("k")), n)
    counter = spot(0, F.col("buckets")) * 2 + spot(2, F.lit(2))
    return items.join(blocks, "seg").select(*[items[c] for c in items.columns], (read_col(F.col("words"), counter, 4) > 0).alias("second"))


# --- sorted runs ---------------------------------------------------------------------------------------------------------------


def cut_runs(df: DataFrame, runs: int, order: Sequence[str]) -> DataFrame:
    """``df`` with a run number 1..runs, later rows in later runs; cut at quantiles of the first order column, so nothing is sorted in one place."""
    x = F.col(order[0]).cast("double") if dict(df.dtypes)[order[0]] not in ("timestamp_ntz", "timestamp") else F.unix_micros(F.col(order[0]).cast("timestamp")).cast("double")
    cuts = df.select(x.alias("x")).agg(F.percentile_approx("x", [i / runs for i in range(1, runs)], 100_000).alias("c")).first()["c"] if runs > 1 else []
    number = F.lit(1)
    for c in cuts or []:
        number = number + (x > c).cast("int")
    return df.withColumn("run", number)


def runs_compact(runs: DataFrame, key: str, threshold: int, order: str = "run") -> DataFrame:
    """Tiered compaction: every ``threshold`` consecutive runs become one, of each key the newest row stays, by run and then by ``order``."""
    tier = F.floor((F.col("run") - 1) / threshold).cast("int") + 1
    newest = F.row_number().over(Window.partitionBy(key, "__tier").orderBy(F.desc("run"), F.desc(order)))
    return runs.withColumn("__tier", tier).withColumn("__n", newest).where("__n = 1").drop("__n", "run").withColumnRenamed("__tier", "run")


def runs_levels(runs: DataFrame, key: str, threshold: int, order: str = "run") -> DataFrame:
    """Tiered compaction through all levels: whenever a level has ``threshold`` runs they become one run of the next level.

    After N flushes level l holds the l-th digit of N in base ``threshold``; the oldest flushes lie deepest. The rows get ``level`` and
    ``tier``, the number of the run in the order of age, and of each key of a run the newest row stays.
    """
    flushes = runs.agg(F.max("run")).first()[0] or 0
    level, tier, below, number = F.lit(0), F.lit(0), 0, 0
    top = 0
    while threshold ** (top + 1) <= flushes:
        top += 1
    for depth in range(top, -1, -1):  # oldest first
        for _ in range(flushes // threshold**depth % threshold):
            number += 1
            here = (F.col("run") > below) & (F.col("run") <= below + threshold**depth)
            level, tier = F.when(here, depth).otherwise(level), F.when(here, number).otherwise(tier)
            below += threshold**depth
    newest = F.row_number().over(Window.partitionBy(key, "tier").orderBy(F.desc("run"), F.desc(order)))
    return runs.withColumn("level", level).withColumn("tier", tier).withColumn("__n", newest).where("__n = 1").drop("__n")


def runs_filters(runs: DataFrame, key: str, first: str = "bloom", second: str = "edge_map", scope: str = "others", **how) -> FilterHandle:
    """One filter over (run, key): positive where the run holds the key, negative where only later runs do.

    ``scope`` "later": negatives are the keys of later runs, which is all a run can learn after it was written; a key is paired with
    the runs up to its last one. "others": negatives are the keys of earlier runs, too.
    """
    own = runs.select("run", F.col(key).alias("key")).distinct()
    last = own.groupBy("key").agg(F.max("run").alias("last"))
    upto = F.lit(own.agg(F.max("run")).first()[0] or 1) if scope == "others" else F.col("last")
    pairs = last.select("key", F.explode(F.sequence(F.lit(1), upto)).alias("run"))
    labelled = pairs.join(own.withColumn("mine", F.lit(True)), ["run", "key"], "left").select("run", "key", F.coalesce("mine", F.lit(False)).alias("mine"))
    return filters.staged(labelled, ["run", "key"], "mine", first=first, second=second, **how)


def runs_get(runs: DataFrame, key: str, queries: DataFrame, handle: FilterHandle | None, order: str = "newest") -> DataFrame:
    """(key, found_run, reads, wasted): the runs that the filter says yes to are read one after another.

    ``order`` "newest": from the last run back until the key is found. "first": from the first run on until it is found, for keys that
    lie in one run only. "oldest": from the first run on until a run does not hold the key, after which no later run can if negatives
    are the keys of later runs; the last run that held it has its newest row. Only runs that the filter says yes to are shuffled.
    """
    own = runs.select("run", F.col(key).alias("key")).distinct()
    asked = queries.select(F.col(key).alias("key")).distinct()
    pairs = asked.select("key", F.explode(F.sequence(F.lit(1), F.lit(own.agg(F.max("run")).first()[0] or 1))).alias("run"))
    yes = handle.probe(pairs, ["run", "key"]).where("hit").select("key", "run") if handle else pairs
    told = yes.join(own.withColumn("mine", F.lit(True)), ["run", "key"], "left").select("key", F.struct("run", F.coalesce("mine", F.lit(False)).alias("mine")).alias("h"))
    found = told.unionByName(asked.select("key", F.lit(None).cast(told.schema["h"].dataType).alias("h"))).groupBy("key").agg(F.sort_array(F.collect_list("h")).alias("hits"))
    if order == "newest":
        last = F.array_max(F.transform(F.filter("hits", lambda h: h["mine"]), lambda h: h["run"]))
        opened = F.filter("hits", lambda h: F.col("found_run").isNull() | (h["run"] >= F.col("found_run")))
    elif order == "first":
        last = F.array_min(F.transform(F.filter("hits", lambda h: h["mine"]), lambda h: h["run"]))
        opened = F.filter("hits", lambda h: F.col("found_run").isNull() | (h["run"] <= F.col("found_run")))
    else:
        miss = F.array_min(F.transform(F.filter("hits", lambda h: ~h["mine"]), lambda h: h["run"]))
        last = F.array_max(F.transform(F.filter("hits", lambda h: h["mine"] & (F.col("miss").isNull() | (h["run"] < F.col("miss")))), lambda h: h["run"]))
        opened = F.filter("hits", lambda h: F.col("miss").isNull() | (h["run"] <= F.col("miss")))
        found = found.withColumn("miss", miss)
    return found.withColumn("found_run", last).select("key", "found_run", F.size(opened).alias("reads"), F.size(F.filter(opened, lambda h: ~h["mine"])).alias("wasted"))


# --- learned filters -------------------------------------------------------------------------------------------------------------


@dataclass
class LearnedFilter:
    model: object
    threshold: float
    backup: FilterHandle
    features: object

    def probe(self, df: DataFrame, key: str) -> DataFrame:
        scored = self.features(df)
        scored = self.model.transform(scored).withColumn("p", _second(F.col("probability")))
        hit = F.col("p") >= self.threshold
        return self.backup.probe(scored, [key], "spare").withColumn("hit", hit | F.col("spare")).select(*[c for c in df.columns], "hit")


def _second(v: Column) -> Column:
    from pyspark.ml.functions import vector_to_array

    return F.get(vector_to_array(v), F.lit(1))


def text_features(df: DataFrame, text: str = "text", dims: int = 1 << 12) -> DataFrame:
    """Hashed words and pairs of words of a whole key text, by built-in transformers."""
    whole = df.withColumn("__t", F.lower(F.coalesce(F.col(text), F.lit(""))))
    words = RegexTokenizer(inputCol="__t", outputCol="__w", pattern=r"\s+").transform(whole)
    pairs = NGram(n=2, inputCol="__w", outputCol="__p").transform(words)
    both = pairs.withColumn("__f", F.concat("__w", "__p"))
    return HashingTF(numFeatures=dims, inputCol="__f", outputCol="features", binary=True).transform(both).drop("__t", "__w", "__p", "__f")


def learned_model(df: DataFrame, key: str, text: str, label: str, train_share: float = 0.5):
    """A classifier fitted on a share of the keys, and (key, label, p) of all; features are computed once."""
    data = keep(text_features(df, text).select(key, F.col(label).cast("double").alias("label"), "features"))
    train = data.where(F.pmod(F.xxhash64(F.lit(3), key), F.lit(1000)) < int(1000 * train_share))
    model = LogisticRegression(maxIter=20, regParam=0.05).fit(train)
    return model, keep(model.transform(data).select(key, "label", _second(F.col("probability")).alias("p")))


def learned_backup(model, scored: DataFrame, key: str, text: str, fpr: float = 0.01, backup: str = "staged") -> LearnedFilter:
    """A threshold that lets ``fpr`` (half of it with a Bloom backup) of the negatives through, and a backup filter of the positives below it."""
    share = fpr / 2 if backup == "bloom" else fpr
    cut = scored.where("label = 0").agg(F.percentile("p", 1 - share).alias("c")).first()["c"]
    threshold = float(np.nextafter(cut if cut is not None else 1.0, 2.0))
    rest = scored.where(F.col("p") < threshold).select(key, (F.col("label") == 1).alias("positive"))
    if backup == "bloom":
        handle = filters.single(rest, [key], "positive", "bloom", fpr / 2)
    elif backup == "retrieval":
        handle = filters.single(rest, [key], "positive", "retrieval")
    else:
        handle = filters.staged(rest, [key], "positive")
    return LearnedFilter(model, threshold, handle, lambda d: text_features(d, text))


def learned_build(df: DataFrame, key: str, text: str, label: str, fpr: float = 0.01, train_share: float = 0.5, backup: str = "staged") -> LearnedFilter:
    """The classifier and its backup in one go."""
    return learned_backup(*learned_model(df, key, text, label, train_share), key, text, fpr, backup)
