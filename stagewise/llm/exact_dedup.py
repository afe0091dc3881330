"""Exact dedup by content-defined chunk recipes, in DataFrame functions only.

A text is cut where its own characters say so, so equal passages are cut alike wherever they stand. Each distinct chunk gets an
identifier that is verified against the chunk's characters, a text becomes the ordered list of its identifiers, and only these
short lists are compared and moved; no document text is ever shuffled whole.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import columns_of, sent_if_small, stash, table, unused

#: Chunks end behind white space that follows a full stop or similar sign; the bounds are in characters.
CHUNK_MIN, CHUNK_MAX = 1024, 8192
CUT_BEHIND = r"(?<=[.!?;:\x29\x22][ \n])"


def fold_ascii(text: Column) -> Column:
    """Lower-case A-Z only; null counts as empty. Plain ASCII takes the quick way, which gives the same there."""
    text = F.coalesce(text, F.lit(""))
    return F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(
        F.translate(text, string.ascii_uppercase, string.ascii_lowercase)
    )


def chunks(text: Column, least: int = CHUNK_MIN, most: int = CHUNK_MAX) -> Column:
    """The text as an array of content-defined chunks, which joined give the text again; empty for the empty text."""
    pattern = f"(?s)(?:.{{{least},{most}}}?{CUT_BEHIND}|.{{1,{most}}})"
    return F.regexp_extract_all(text, F.lit(pattern), F.lit(0))


def chunk_hash(chunk: Column) -> Column:
    return F.xxhash64(chunk)


def recipes(docs: DataFrame, key: str = "doc_id", text: str = "text", hash_fn=chunk_hash) -> DataFrame:
    """(key, recipe array<struct<h, alt>>, text_sha256): the ordered verified chunk identifiers of each row.

    ``h`` identifies a chunk unless two different chunks share it; then ``alt`` tells them apart (the chunk's rank among those).
    Chunks are grouped by their characters, so whether an ``h`` is shared is known, not assumed; only the documents that hold a
    shared ``h`` take the second way, and usually there are none.
    """
    norm = docs.select(F.col(key).alias("k"), fold_ascii(F.col(text)).alias("t"))
    plain = stash(
        norm.select(
            "k",
            F.sha2(F.col("t"), 256).alias("text_sha256"),
            F.transform(chunks(F.col("t")), hash_fn).alias("hs"),
        )
    )
    # only an identifier that occurs again can be shared; a chunk's text travels for these alone, and once for each task that meets it
    again = stash(plain.select(F.explode("hs").alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h"))
    texts = (
        norm.select(F.explode(chunks(F.col("t"))).alias("c")).select(hash_fn(F.col("c")).alias("h"), "c")
        .join(sent_if_small(again, 32), "h", "left_semi").groupBy("h", "c").agg(F.lit(1).alias("one"))
    )
    shared = stash(
        texts.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h")
    )
    bare = F.transform("hs", lambda h: F.struct(h.alias("h"), F.lit(0).alias("alt")))
    if shared.isEmpty():
        return plain.select(F.col("k").alias(key), bare.alias("recipe"), "text_sha256")
    ranked = (
        texts.join(shared, "h", "left_semi")
        .groupBy("h").agg(F.array_sort(F.collect_set("c")).alias("cs"))
        .select("h", F.posexplode("cs").alias("alt", "c"))
    )
    # a row is known by its key, null or not, and the hash of its text, so repeated keys with other texts stay apart
    row = F.to_json(F.struct("k", "text_sha256")).alias("row")
    pieces = norm.withColumn("text_sha256", F.sha2(F.col("t"), 256)).select(row, F.posexplode(chunks(F.col("t"))).alias("pos", "c")).withColumn("h", hash_fn(F.col("c")))
    touched = pieces.join(shared, "h", "left_semi").select("row").distinct()
    mended = (
        pieces.dropDuplicates(["row", "pos", "c"]).join(touched, "row", "left_semi")
        .join(ranked, ["h", "c"], "left")
        .groupBy("row")
        .agg(F.array_sort(F.collect_list(F.struct("pos", "h", F.coalesce("alt", F.lit(0)).alias("alt")))).alias("r"))
        .select("row", F.transform("r", lambda x: F.struct(x.h.alias("h"), x.alt.alias("alt"))).alias("mended"))
    )
    return plain.withColumn("row", row).join(mended, "row", "left").select(
        F.col("k").alias(key), F.coalesce("mended", bare).alias("recipe"), "text_sha256"
    )


def exact_groups(docs: DataFrame, key: str = "doc_id", text: str = "text", hash_fn=chunk_hash) -> DataFrame:
    """One row per input row: key, keep_id, group_size, kept, text_sha256.

    Texts are equal when they are identical after lower-casing A-Z; a null text counts as empty, and empty texts are equal. Of
    equal texts the row with the largest key stays (a null key is the smallest). Rows that repeat both key and text are all
    marked alike. An empty table gives an empty result; other columns of the input play no part.
    """
    found = stash(recipes(docs, key, text, hash_fn).select(F.col(key).alias("k"), "recipe", "text_sha256"))
    # counts and maxima are combined before the shuffle, so a text that a third of all rows share costs a row a task
    groups = found.groupBy("recipe").agg(F.max("k").alias("keep_id"), F.count(F.lit(1)).alias("group_size")).select(
        F.col("recipe").alias("r"), "keep_id", "group_size"
    )
    # single rows need no partner: they answer for themselves. The groups are written first, so that both sides of the join are
    # shuffled for it alone and adaptive execution can split a hot one
    repeated = stash(groups.where("group_size > 1"))
    return found.join(repeated, found.recipe == repeated.r, "left").select(
        F.col("k").alias(key),
        F.when(F.col("r").isNull(), F.col("k")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        F.when(F.col("r").isNull(), F.lit(True)).otherwise(F.col("k").eqNullSafe(F.col("keep_id"))).alias("kept"),
        "text_sha256",
    )


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The input without its copies, all columns as they were, whatever they are called.

    Of equal texts the row with the largest key stays, a null key being the smallest; of rows that repeat key and text one stays. Null
    and empty texts are equal. An empty table gives an empty result.
    """
    k, sha = (unused(name, docs) for name in ("dedup_key", "dedup_sha"))
    told = stash(exact_groups(docs.select(key, text), key, text).select(F.col(key).alias(k), F.unhex("text_sha256").alias(sha), "kept"))
    gone = stash(told.where("not kept").select(k, sha).distinct())
    again = stash(told.where("kept").groupBy(k, sha).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(k, sha))
    named = docs.withColumn(k, F.col(key)).withColumn(sha, F.unhex(F.sha2(fold_ascii(F.col(text)), 256)))
    of = lambda rows: [named[k].eqNullSafe(rows[k]), named[sha] == rows[sha]]
    left = named.join(sent_if_small(gone, 128), of(gone), "left_anti")
    if not again.isEmpty():
        more = left.join(again, [left[k].eqNullSafe(again[k]), left[sha] == again[sha]], "left_semi").dropDuplicates([k, sha])
        left = left.join(again, [left[k].eqNullSafe(again[k]), left[sha] == again[sha]], "left_anti").unionByName(more)
    return left.select(*columns_of(docs))


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(table(spark, sf_dir, "documents", "doc_id", "text"))


OP9_SQL = """
WITH n AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents
)
SELECT doc_id,
       max(doc_id) OVER (PARTITION BY t) AS keep_id,
       count(*) OVER (PARTITION BY t) AS group_size,
       doc_id = max(doc_id) OVER (PARTITION BY t) AS kept,
       sha256(t) AS text_sha256
FROM n
"""
