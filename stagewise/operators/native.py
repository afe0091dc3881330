"""Filters built and checked with DataFrame expressions alone: Bloom words by bit_or, relational peeling, Spark's own sketch, plain joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import below_col, hash_col, key64, portable_hash
from ..plans.storage import keep


def bloom_words(df: DataFrame, key: str, bits: int, hashes: int, seed: int = 1) -> DataFrame:
    """(word, bits): the words of a Bloom filter; each task combines its own before the shuffle."""
    k = key64(df, [key])
    spots = F.array(*[below_col(hash_col(seed + i // 2, k), F.lit(bits), i % 2) for i in range(hashes)])
    return df.where(F.col(key).isNotNull()).select(F.explode(spots).alias("b")).groupBy(F.shiftright("b", 6).alias("word")).agg(
        F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("b").bitwiseAND(F.lit(63)).cast("int"))).alias("bits")
    )


def bloom_union(a: DataFrame, b: DataFrame) -> DataFrame:
    """Words of the union of two filters of one shape: insertion is the union with the new keys' words."""
    return a.unionByName(b).groupBy("word").agg(F.bit_or("bits").alias("bits"))


def bloom_hits(df: DataFrame, key: str, words: DataFrame, bits: int, hashes: int, seed: int = 1) -> DataFrame:
    """``df`` with ``hit``, for an integer key; probes meet words by a shuffle on the word's number, so the filter may be of any size."""
    asked = df.select(F.col(key).alias("__k")).where("__k is not null").distinct().select("__k", F.explode(_spots(bits, hashes, seed)).alias("b"))
    seen = asked.withColumn("word", F.shiftright("b", 6)).join(words, "word", "left")
    bit = F.call_function("shiftrightunsigned", F.coalesce("bits", F.lit(0).cast("long")), F.col("b").bitwiseAND(F.lit(63)).cast("int")).bitwiseAND(F.lit(1))
    answer = seen.groupBy("__k").agg((F.min(bit) == 1).alias("hit"))
    return df.join(answer, df[key] == answer["__k"], "left").select(*[df[c] for c in df.columns], F.coalesce("hit", F.lit(False)).alias("hit"))


def _spots(bits: int, hashes: int, seed: int) -> Column:
    return F.array(*[below_col(hash_col(seed + i // 2, F.col("__k").cast("long")), F.lit(bits), i % 2) for i in range(hashes)])


def counting_words(df: DataFrame, key: str, cells: int, hashes: int, sign: str | None = None, seed: int = 1) -> DataFrame:
    """(cell, n): counters after inserting (sign 1) and deleting (sign -1) keys; they saturate at 15."""
    k = key64(df, [key])
    spots = F.array(*[below_col(hash_col(seed + i // 2, k), F.lit(cells), i % 2) for i in range(hashes)])
    s = F.col(sign) if sign else F.lit(1)
    return df.where(F.col(key).isNotNull()).select(F.explode(spots).alias("cell"), s.alias("s")).groupBy("cell").agg(F.greatest(F.lit(0), F.least(F.lit(15), F.sum("s"))).alias("n")).where("n > 0")


def jvm_bloom_bits(df: DataFrame, column: str, n: int, eps: float) -> int:
    """Size of Spark's own Bloom sketch of a column, as a cross-check."""
    return df._jdf.stat().bloomFilter(column, n, float(eps)).bitSize()


def portable_bloom(df: DataFrame, key: str, bits: int, hashes: int) -> DataFrame:
    """(bit) of a Bloom filter whose hashes any SQL engine can compute."""
    spots = F.array(*[F.pmod(portable_hash(F.col(key), i), F.lit(bits)) for i in range(hashes)])
    return df.where(F.col(key).isNotNull()).select(F.explode(spots).alias("bit")).distinct()


def peel_relational(df: DataFrame, key: str, cells: int, seed: int = 1, max_rounds: int = 400) -> DataFrame:
    """(k, slot, round): peeling as joins; a check for small inputs, as each round is a shuffle."""
    block = cells // 3
    k = df.select(F.col(key).cast("long").alias("k")).distinct()
    left = keep(k.select("k", F.explode(F.array(*[(below_col(hash_col(seed + i, F.col("k")), F.lit(block)) + i * block) for i in range(3)])).alias("slot")))
    out = None
    for round_ in range(max_rounds):
        single = left.groupBy("slot").agg(F.count(F.lit(1)).alias("n"), F.min("k").alias("k")).where("n = 1").groupBy("k").agg(F.min("slot").alias("slot")).withColumn("round", F.lit(round_))
        single = keep(single)
        if single.isEmpty():
            break
        out = single if out is None else out.unionByName(single)
        left = keep(left.join(single.select("k"), "k", "left_anti"))
    if not left.isEmpty():
        raise RuntimeError("keys are left: peel again with another seed or more cells")
    return out if out is not None else k.select("k", F.lit(0).cast("long").alias("slot"), F.lit(0).alias("round")).limit(0)


def assign_relational(peeled: DataFrame, values: DataFrame, cells: int, seed: int = 1) -> DataFrame:
    """(slot, v): cells whose xor over a key's three slots is the key's value, filled round by round from the last peeled on.

    ``peeled`` is what ``peel_relational`` gives, ``values`` is (k, v). The cells of one round are those of no other, so a round is one
    join of its keys' other slots with the cells filled so far.
    """
    block = cells // 3
    rounds = peeled.agg(F.max("round")).first()[0]
    slots = F.explode(F.array(*[(below_col(hash_col(seed + i, F.col("k")), F.lit(block)) + i * block) for i in range(3)]))
    own = keep(peeled.join(values, "k"))
    filled = own.select("slot", "v").limit(0)
    for round_ in range(rounds if rounds is not None else -1, -1, -1):
        now = own.where(F.col("round") == round_)
        others = now.select("k", "v", F.col("slot").alias("own"), slots.alias("slot")).where("slot <> own")
        seen = others.join(filled.withColumnRenamed("v", "c"), "slot", "left").groupBy("own", "v").agg(F.bit_xor(F.coalesce("c", F.lit(0).cast("long"))).alias("x"))
        filled = keep(filled.unionByName(seen.select(F.col("own").alias("slot"), F.col("v").bitwiseXOR(F.col("x")).alias("v"))))
    return filled


def read_relational(keys: DataFrame, filled: DataFrame, cells: int, seed: int = 1) -> DataFrame:
    """(k, v): the xor over the three slots of each key."""
    block = cells // 3
    slots = F.explode(F.array(*[(below_col(hash_col(seed + i, F.col("k")), F.lit(block)) + i * block) for i in range(3)]))
    return keys.select("k", slots.alias("slot")).join(filled, "slot", "left").groupBy("k").agg(F.bit_xor(F.coalesce("v", F.lit(0).cast("long"))).alias("v"))


def portable_hits(df: DataFrame, key: str, bits: DataFrame, size: int, hashes: int) -> DataFrame:
    """``df`` with ``hit`` by a portable Bloom filter of any size: a key's bits meet the set ones by a shuffle."""
    spots = F.explode(F.array(*[F.pmod(portable_hash(F.col("__k"), i), F.lit(size)) for i in range(hashes)]))
    asked = df.select(F.col(key).alias("__k")).distinct().select("__k", spots.alias("bit"))
    answer = asked.join(bits.withColumn("set", F.lit(True)), "bit", "left").groupBy("__k").agg((F.count("set") == F.count(F.lit(1))).alias("hit"))
    return df.join(answer, df[key].eqNullSafe(answer["__k"]), "left").select(*[df[c] for c in df.columns], F.coalesce("hit", F.lit(False)).alias("hit"))


def portable_counters(df: DataFrame, key: str, size: int, hashes: int, sign: str) -> DataFrame:
    """(cell, n): counters of a portable counting filter that are not zero after inserting (sign 1) and deleting (sign -1) keys."""
    spots = F.explode(F.array(*[F.pmod(portable_hash(F.col(key), i), F.lit(size)) for i in range(hashes)]))
    return df.where(F.col(key).isNotNull()).select(spots.alias("cell"), F.col(sign).alias("s")).groupBy("cell").agg(F.sum("s").cast("long").alias("n")).where("n <> 0")
