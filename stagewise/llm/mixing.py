"""Mixing sources to target weights by subset-sum budget fitting.

Documents are counted by exact length. A source's target is met by whole passes over it and, for the rest, by a subset of its
documents, found by bounded-knapsack dynamic programming over lengths; of a large budget, an even share of each length comes first. Which
documents of a length are taken is settled by a seeded hash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import columns_of, small_batches, stash, table, text_blocks, tidied, unused

WEIGHTS, SHARE, MAX_REPEATS, SEED = (5, 2, 1), 1.5, 2, 42
#: What is left of a budget, in words, when the exact choice begins.
EXACT_WORDS = 1 << 16


def measured(docs: DataFrame, key: str, text: str, source: str) -> DataFrame:
    """(k, known, src, size): words of each whole text; ``known`` is false for a null source."""
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = [len(t.split()) for _, _, block in text_blocks(batch, "t") for t in block]
            yield pa.record_batch([*batch.columns[:3], pa.array(sizes, pa.int64())], names=["k", "known", "src", "size"])

    columns = F.col(key).alias("k"), F.col(source).isNotNull().alias("known"), F.coalesce(F.col(source).cast("string"), F.lit("")).alias("src"), F.col(text).alias("t")
    return docs.select(*columns).transform(small_batches).mapInArrow(tidied(run), f"k {kind}, known boolean, src string, size long")


def targets(sizes: dict[tuple[bool, str], int], weights=WEIGHTS, share: float = SHARE, most: float = MAX_REPEATS) -> dict[tuple[bool, str], float]:
    """Words to take of each source: the budget by weight, but at most ``most`` times a source, the excess going to the others."""
    names = sorted(sizes, key=lambda s: (not s[0], s[1]))
    weight = {s: float(weights[i % len(weights)]) for i, s in enumerate(names)}
    left, open_, out = share * sum(sizes.values()), set(names), {}
    while open_:
        unit = left / sum(weight[s] for s in names if s in open_)
        full = [s for s in names if s in open_ and unit * weight[s] > most * sizes[s]]
        if not full:
            out |= {s: unit * weight[s] for s in names if s in open_}
            break
        for s in full:
            out[s] = float(most * sizes[s])
            left -= out[s]
            open_.discard(s)
    return out


def fit_budget(lengths: np.ndarray, counts: np.ndarray, budget: int, exact: int = EXACT_WORDS) -> np.ndarray:
    """How many documents of each length to take, so that the words come as near below ``budget`` as can be.

    A budget of up to ``exact`` words is left to the knapsack alone, whose choice is the best there is. Of a larger one all but
    about ``exact`` words are an even share of each length, and the knapsack has what is left of every length for the rest.
    """
    lengths, counts = lengths.astype(np.int64), counts.astype(np.int64)
    total = int((lengths * counts).sum())
    if budget <= 0 or not total:
        return np.zeros(len(lengths), np.int64)
    if budget >= total:
        return np.where(lengths > 0, counts, 0)
    take = np.where(lengths > 0, np.floor(counts * (max(0, budget - exact) / total)).astype(np.int64), 0)
    left = budget - int((lengths * take).sum())
    order = np.argsort(-lengths, kind="stable")
    for i in order:  # longest first, down to what the exact choice can handle
        if left <= exact:
            break
        if lengths[i] > 0:
            more = min(int(counts[i] - take[i]), (left - exact // 2) // int(lengths[i]))
            take[i] += more
            left -= more * int(lengths[i])
    # bounded knapsack: ``step_to[b]`` is the step by which b words were first made up, -1 if they cannot be; each step takes a
    # power-of-two share of a length's count, so the steps before it never contain it
    step_to, steps = np.full(left + 1, -1, np.int32), []
    step_to[0] = 0
    for i, n, words in ((i, n, n * int(lengths[i])) for i in order[::-1] if lengths[i] > 0 for n in _shares(int(counts[i] - take[i]))):
        if words > left:
            continue
        fresh = np.flatnonzero((step_to[: left + 1 - words] >= 0) & (step_to[words:] < 0)) + words
        step_to[fresh] = len(steps)
        steps.append((i, n, words))
        if step_to[left] >= 0:
            break
    at = int(np.flatnonzero(step_to >= 0)[-1])
    while at:
        i, n, words = steps[step_to[at]]
        take[i] += n
        at -= words
    return take


def _shares(count: int) -> Iterator[int]:
    """1, 2, 4, ... and a rest, which add up to ``count``."""
    bunch = 1
    while count > 0:
        yield min(bunch, count)
        count -= bunch
        bunch *= 2


def mix(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", weights=WEIGHTS, share: float = SHARE, most: int = MAX_REPEATS, seed: int = SEED) -> DataFrame:
    """One row per input row: key, size, source_size, target, taken; ``taken`` is ``size`` times the repeats of the document.

    Sources stand in the order of their code points, null last, and get the weights in turn. A source without words has target
    0. Null and empty texts have size 0 and are never taken. The choice depends on keys, sizes and the seed only, so reruns
    agree; rows that repeat key and size are alike, and which of them is taken makes no difference to the result. An empty table gives
    an empty result.
    """
    sized = stash(measured(docs, key, text, source))
    counted = stash(sized.groupBy("known", "src", "size").agg(F.count(F.lit(1)).alias("n")))
    # one row a source: the mix is configured by source
    words = {(r["known"], r["src"]): int(r["words"]) for r in counted.groupBy("known", "src").agg(F.sum(F.col("n") * F.col("size")).alias("words")).collect()}
    goal = targets(words, weights, share, most)

    def plan(rows: pd.DataFrame) -> pd.DataFrame:
        s = (bool(rows["known"].iloc[0]), rows["src"].iloc[0])
        rows = rows.sort_values("size", ignore_index=True)
        passes = min(most, int(goal[s] // words[s])) if words[s] else 0
        rest = int(goal[s] - passes * words[s]) if passes < most else 0
        rows["extra"] = fit_budget(rows["size"].to_numpy(), rows["n"].to_numpy(), rest)
        return rows.assign(passes=passes, source_size=words[s], target=goal[s])[["known", "src", "size", "n", "extra", "passes", "source_size", "target"]]

    planned = stash(
        counted.groupBy("known", "src").applyInPandas(plan, "known boolean, src string, size long, n long, extra long, passes long, source_size long, target double")
    )
    length = ["known", "src", "size"]
    told = sized.join(planned, length)
    columns = [F.col("k").alias(key), "size", "source_size", "target"]
    taken = lambda times: (F.col("size") * times).cast("long").alias("taken")
    whole = told.where("extra = 0 or extra = n").select(*columns, taken(F.col("passes") + F.when(F.col("extra") > 0, 1).otherwise(0)))
    # the documents of a length in the order of their hash: dealt into about as many buckets as a bucket has rows, so that no
    # task holds a length's rows together, however many there are
    part = told.where("extra > 0 and extra < n").withColumn("h", F.xxhash64(F.lit(seed), "k")).withColumn("bucket", bucket_of(F.col("h"), F.ceil(F.sqrt("n"))))
    slot = [*length, "bucket"]
    before = part.groupBy(*slot).agg(F.count(F.lit(1)).alias("m")).select(
        *slot, F.coalesce(F.sum("m").over(Window.partitionBy(*length).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before")
    )
    place = F.row_number().over(Window.partitionBy(*slot).orderBy("h", "k"))
    chosen = part.withColumn("place", place).join(before, slot).select(
        *columns, taken(F.col("passes") + F.when(F.col("before") + F.col("place") <= F.col("extra"), 1).otherwise(0))
    )
    return whole.unionByName(chosen)


def bucket_of(h: Column, buckets: Column) -> Column:
    """Buckets in the order of the hash: the top 31 bits, scaled."""
    top = F.shiftrightunsigned(h, 33)
    return F.floor(top * buckets / F.lit(float(1 << 31))).cast("long")


def mixed(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", **how) -> DataFrame:
    """The mix itself: each row as often as it is taken, all columns as they were, whatever they are called.

    Null and empty texts are never taken. Rows that share a key are taken alike, as often as the one of them taken most. A null
    key is a key like any other, a null source a source like any other. An empty table gives an empty result.
    """
    k, times, copy = (unused(name, docs) for name in ("mix_key", "mix_times", "mix_copy"))
    taken = (
        mix(docs, key, text, source, **how).where("taken > 0")
        .groupBy(F.col(key).alias(k)).agg(F.max((F.col("taken") / F.col("size")).cast("int")).alias(times))
    )
    found = docs.join(taken, F.col(key).eqNullSafe(F.col(k)))
    return found.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(times)))).select(*columns_of(docs))


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents", "doc_id", "text", "source"))
