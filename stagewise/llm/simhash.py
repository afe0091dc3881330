"""Near-duplicate groups by SimHash fingerprints, paired through the anchor points of a covering code.

``simhash_groups`` links fingerprints by their distance alone. ``similar_groups`` links texts whose sets of word shingles have a
Jaccard similarity of at least a bound, counted exactly: fingerprints that meet at an anchor are candidates there, and since texts
near the bound lie about ten bits apart, which no covering code reaches at a bearable number of copies, bands of minimum hashes of
the same shingles give the other candidates.
"""

from __future__ import annotations

import functools
import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import columns_of, sent_if_small, small_batches, stash, table, text_blocks, tidied, unused

BITS = 64
SHINGLE, MAX_DISTANCE, SEED = 4, 4, 42


def shingle_hashes(text: bytes, width: int = SHINGLE, seed: int = SEED) -> Iterator[np.ndarray]:
    """The XXH64 of the text's word shingles, repeats included, in blocks; none for a text without words.

    Words are what stands between the bytes 0x20 and 0x09-0x0D, which is how ``bytes.split`` cuts; ``bytes.lower`` changes A-Z alone.
    """
    words = text.lower().split()
    n = max(1, len(words) - width + 1) if words else 0
    digest = xxhash.xxh64_intdigest
    for lo in range(0, n, 1 << 16):
        hi = min(n, lo + (1 << 16))
        yield np.fromiter((digest(b" ".join(words[i : i + width]), seed) for i in range(lo, hi)), np.uint64, hi - lo)


def majority(blocks: list[np.ndarray]) -> int:
    """64 majority votes over hashes; zero without any."""
    votes, n = np.zeros(BITS, np.int64), sum(map(len, blocks))
    for hashes in blocks:
        votes += np.unpackbits(hashes.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * votes > n).tobytes(), "big")


def fingerprint(text: bytes, width: int = SHINGLE, seed: int = SEED) -> int:
    """64 majority votes over the XXH64 of the text's word shingles; zero for a text without words."""
    return majority(list(shingle_hashes(text, width, seed)))


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = SHINGLE) -> DataFrame:
    """(k, fp long) for every row."""
    kind = docs.schema[key].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = [fingerprint(t, width) for _, _, block in text_blocks(batch, "t") for t in block]
            yield pa.record_batch([batch.column(0), pa.array(np.array(prints, np.uint64).view(np.int64))], names=["k", "fp"])

    return docs.select(F.col(key).alias("k"), F.col(text).alias("t")).transform(small_batches).mapInArrow(tidied(run), f"k {kind.simpleString()}, fp long")


# --- the covering code -------------------------------------------------------------------------------------------------------
#
# 64 bits are cut into pieces; fingerprints at distance d agree in some piece to within floor(d / pieces) bits. On a piece of b
# bits the anchors are the words whose first 2**r - 1 bits are in the Hamming code of that length (its other bits are free):
# a perfect code, so each word has exactly one anchor within distance 1, its home. Two words within t bits of each other meet at
# the home of either, if the other is sent to every anchor within 1 + t.


@functools.cache
def _piece(bits: int, radius: int) -> tuple[tuple[int, ...], tuple[int, ...], tuple[tuple[int, ...], ...]]:
    """Masks of the parity checks; by syndrome, the way to the home anchor and the ways to all anchors within ``radius``."""
    r = (bits + 1).bit_length() - 1
    length = (1 << r) - 1
    masks = tuple(sum(1 << (j - 1) for j in range(1, length + 1) if j >> i & 1) for i in range(r))
    home = tuple(0 if s == 0 else 1 << (s - 1) for s in range(1 << r))
    ways: list[list[int]] = [[] for _ in range(1 << r)]
    for weight in range(radius + 1):
        for places in itertools.combinations(range(bits), weight):
            s = functools.reduce(lambda a, p: a ^ (p + 1 if p < length else 0), places, 0)
            ways[s].append(sum(1 << p for p in places))
    return masks, home, tuple(map(tuple, ways))


def _syndrome(x: Column, masks: tuple[int, ...]) -> Column:
    parity = lambda m: F.bit_count(x.bitwiseAND(F.lit(m))) % 2
    return sum((parity(m) * (1 << i) for i, m in enumerate(masks[1:], 1)), parity(masks[0])).cast("int")


def _longs(values) -> Column:
    return F.expr("array(" + ",".join(f"{v}L" for v in values) + ")")


def piece_bounds(pieces: int) -> list[tuple[int, int]]:
    cuts = [BITS * i // pieces for i in range(pieces + 1)]
    return list(zip(cuts, cuts[1:], strict=False))


def near_pairs(points: DataFrame, distance: int = MAX_DISTANCE, pieces: int = 3) -> DataFrame:
    """Pairs (a < b) of the distinct ``fp`` of ``points`` that differ in at most ``distance`` bits; a pair may appear for more than one piece."""
    homes, members = [], []
    for i, (lo, hi) in enumerate(piece_bounds(pieces)):
        bits = hi - lo
        masks, home, ways = _piece(bits, 1 + distance // pieces)
        x = F.shiftrightunsigned(F.col("fp"), lo).bitwiseAND(F.lit((1 << bits) - 1))
        at = points.withColumn("x", x).withColumn("s", _syndrome(F.col("x"), masks))
        homes.append(at.select(F.lit(i).alias("piece"), F.col("x").bitwiseXOR(F.element_at(_longs(home), F.col("s") + 1)).alias("anchor"), F.col("fp").alias("a")))
        nested = F.expr("array(" + ",".join("array(" + ",".join(f"{v}L" for v in w) + ")" for w in ways) + ")")
        members.append(
            at.select("fp", "x", F.explode(F.element_at(nested, F.col("s") + 1)).alias("way"))
            .select(F.lit(i).alias("piece"), F.col("x").bitwiseXOR(F.col("way")).alias("anchor"), F.col("fp").alias("b"))
        )
    union = lambda xs: functools.reduce(DataFrame.unionByName, xs)
    h, m = union(homes), union(members)
    return h.join(m, ["piece", "anchor"]).where((F.col("a") < F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= distance)).select("a", "b")


def component_labels(edges: DataFrame, max_rounds: int = 200) -> DataFrame:
    """(node, root): the smallest node of each connected component, for the nodes that have an edge.

    Alternating large-star and small-star steps: every step is a combine of links by key, the number of links never grows, and
    the number of rounds is logarithmic in practice. A round is written to the shared folder, so a lost executor costs no history.
    """
    links = stash(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    for _ in range(max_rounds):
        both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        # large star: larger neighbours go to the least of the neighbourhood
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        # small star: smaller neighbours and the node itself go to the least neighbour
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
            .unionByName(low.select("u", F.col("m").alias("v")))
            .where("u <> v").distinct()
        )
        before, links = links, stash(small)
        if links.count() == before.count() and links.join(before, ["u", "v"], "left_anti").isEmpty():  # either has no repeats
            break
    else:
        raise RuntimeError(f"links still move after {max_rounds} rounds")
    return links.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root")).unionByName(
        links.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    )


def simhash_groups(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = SHINGLE, distance: int = MAX_DISTANCE, pieces: int = 3) -> DataFrame:
    """(key, fingerprint string, component_id): one row per input row.

    Fingerprints link when they differ in at most ``distance`` bits, and ``component_id`` is the smallest key reachable. Equal
    fingerprints are one point, so copies are never paired with each other. Null and wordless texts have fingerprint zero and
    link like any other; null keys are ignored as names of a component unless nothing else is there; an empty table gives an
    empty result. No partner is capped: ``pieces`` changes cost alone (three: few copies of a point; two: fewer chance meetings).
    """
    prints = stash(fingerprints(docs, key, text, width))
    points = stash(prints.groupBy("fp").agg(F.min("k").alias("first_k")))
    labels = component_labels(near_pairs(points.select("fp"), distance, pieces))
    named = _named(points, labels, "fp")
    return prints.join(named, prints.fp == named.p, "left").select(
        F.col("k").alias(key), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id"
    )


def _named(points: DataFrame, labels: DataFrame, name: str) -> DataFrame:
    """(p, component_id) of ``points(name, first_k)``. What is joined back is written first, so that adaptive execution can split a large component."""
    rooted = stash(points.join(labels, points[name] == labels.node).select(name, "first_k", "root"))
    roots = stash(rooted.groupBy("root").agg(F.min("first_k").alias("component_id")))
    linked = rooted.join(roots, "root").select(F.col(name).alias("p"), "component_id")
    alone = points.join(labels, points[name] == labels.node, "left_anti").select(F.col(name).alias("p"), F.col("first_k").alias("component_id"))
    return linked.unionByName(alone)


# --- links by exact similarity ---------------------------------------------------------------------------------------------------
#
# Texts with one set of shingles are one point, named by the set's digest. A band is the hash of ROWS minimum hashes: two points of
# similarity s share one with probability s ** ROWS, and one of BANDS with 1 - (1 - s ** ROWS) ** BANDS (0.998 at 0.8). Points of a
# band are all paired only in small groups. In a larger one each is compared with the group's centre; what is then still in different components is found by the rare shingles that alike sets must share.

SIMILAR_WORDS, SIMILARITY = 5, 0.8
BANDS, ROWS, ALL_PAIRS = 16, 5, 16
#: Points of one shingle that one task compares with others of it.
GROUP_BLOCK = 1_024
_SALTS = np.random.default_rng(7).integers(0, 1 << 63, (2, BANDS * ROWS), np.uint64)


def minimum_hashes(distinct: np.ndarray) -> np.ndarray:
    """The least of the hashes under each of BANDS * ROWS scramblings."""
    least = np.full(BANDS * ROWS, ~np.uint64(0))
    for lo in range(0, len(distinct), 4096):
        least = np.minimum(least, ((distinct[lo : lo + 4096, None] ^ _SALTS[0]) * (_SALTS[1] | np.uint64(1))).min(0))
    return least


def set_digest(distinct: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(distinct.tobytes())


def _distinct(blocks: list[np.ndarray]) -> np.ndarray:
    return np.unique(np.concatenate(blocks)) if blocks else np.zeros(0, np.uint64)


def profiles(docs: DataFrame, key: str, text: str, width: int) -> DataFrame:
    """(k, v binary, n, fp, bands array<long>) for every row: the digest and size of its set of shingles, its fingerprint, its bands."""
    kind = docs.schema[key].dataType.simpleString()
    names = ["k", "v", "n", "fp", "bands"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, texts in text_blocks(batch, "t"):
                v, n, fp, bands = [], [], [], []
                for t in texts:
                    blocks = list(shingle_hashes(t, width))
                    distinct = _distinct(blocks)
                    least = minimum_hashes(distinct)
                    v.append(set_digest(distinct))
                    n.append(len(distinct))
                    fp.append(majority(blocks))
                    bands.append([xxhash.xxh64_intdigest(least[i * ROWS : (i + 1) * ROWS].tobytes(), i) for i in range(BANDS if blocks else 0)])
                flat = pa.array(np.array([x for b in bands for x in b], np.uint64).view(np.int64))
                ends = pa.array(np.cumsum([0, *map(len, bands)]), pa.int32())
                yield pa.record_batch([batch.column(0).slice(lo, hi - lo), pa.array(v, pa.binary()), pa.array(n, pa.int32()), pa.array(np.array(fp, np.uint64).view(np.int64)), pa.ListArray.from_arrays(ends, flat)], names=names)

    return docs.select(F.col(key).alias("k"), F.col(text).alias("t")).transform(small_batches).mapInArrow(tidied(run), f"k {kind}, v binary, n int, fp long, bands array<long>")


def _shingle_sets(rows: DataFrame, width: int) -> DataFrame:
    """(v, s array<long>) of ``rows(v, t)``, of those whose set has the digest ``v``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, texts in text_blocks(batch, "t"):
                sets = [_distinct(list(shingle_hashes(t, width))) for t in texts]
                mine = [set_digest(x) == v for x, v in zip(sets, batch.column(0).slice(lo, hi - lo).to_pylist(), strict=True)]
                kept = [x.view(np.int64) for x, own in zip(sets, mine, strict=True) if own]
                yield pa.record_batch([batch.column(0).slice(lo, hi - lo).filter(pa.array(mine)), pa.array(kept, pa.list_(pa.int64()))], names=["v", "s"])

    return rows.transform(small_batches).mapInArrow(tidied(run), "v binary, s array<long>")


def _compared(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """``pairs`` with the exact similarity of the sets of ``a`` and ``b``."""
    one, two = sets.select(F.col("v").alias("a"), F.col("s").alias("sa")), sets.select(F.col("v").alias("b"), F.col("s").alias("sb"))
    both = F.size(F.array_intersect("sa", "sb"))
    return pairs.join(one, "a").join(two, "b").withColumn("similarity", both / (F.size("sa") + F.size("sb") - both)).drop("sa", "sb")


def similar_groups(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = SIMILAR_WORDS, similarity: float = SIMILARITY, distance: int = MAX_DISTANCE, pieces: int = 3) -> DataFrame:
    """(key, component_id): one row per input row; ``component_id`` is the smallest key reachable over links of at least ``similarity``.

    A candidate is linked only if the Jaccard similarity of the two sets of shingles, counted exactly, reaches the bound. Texts of
    equal sets are one point, so copies are never paired; texts without words are equal to each other and like no other. A null key
    names a component only if nothing else is there; rows that repeat key and text are told alike; an empty table gives an empty
    result. No partner is capped.
    """
    prints = stash(profiles(docs, key, text, width))
    own = [F.first(F.get("bands", F.lit(i))).alias(f"b{i}") for i in range(BANDS)]  # numbers, so that they are combined without a sort
    points = stash(prints.groupBy("v").agg(F.min("k").alias("first_k"), F.first("n").alias("n"), F.first("fp").alias("fp"), *own).where("n > 0"))
    reach = F.least("na", "nb") >= F.lit(similarity) * F.greatest("na", "nb")  # sets of more different sizes cannot be so alike
    # each fingerprint, by its first point, with the least one that it is linked to; and the other points of a fingerprint with the first
    of_fp = stash(points.groupBy("fp").agg(F.min("v").alias("a"), F.count(F.lit(1)).alias("points")))
    linked = component_labels(near_pairs(of_fp.select("fp"), distance, pieces)).where("node <> root")
    name = lambda c: of_fp.select(F.col("fp").alias(c), F.col("a").alias(f"v{c}"))
    near = linked.join(name("node"), "node").join(name("root"), "root").select(F.col("vnode").alias("a"), F.col("vroot").alias("b"))
    same = points.select("v", "fp").join(of_fp.where("points > 1"), "fp").where("a <> v").select("a", F.col("v").alias("b"))
    # bands that several points share
    banded = points.select("v", "n", F.explode(F.array(*[f"b{i}" for i in range(BANDS)])).alias("band"))
    shared = stash(banded.groupBy("band").agg(F.count(F.lit(1)).alias("points")).where("points > 1"))
    members = stash(banded.join(shared, "band"))
    small = members.where(F.col("points") <= ALL_PAIRS).groupBy("band").agg(F.collect_list(F.struct("v", "n")).alias("vs"))  # of ALL_PAIRS points at most
    small = small.select(F.col("vs"), F.explode("vs").alias("x")).select("x", F.explode("vs").alias("y")).where("x.v < y.v").select(
        F.col("x.v").alias("a"), F.col("x.n").alias("na"), F.col("y.v").alias("b"), F.col("y.n").alias("nb")
    ).where(reach).select("a", "b")
    # the centre of a band is the point that shares its bands with the most others, which is the one that the others are copies of
    crowded = members.where(F.col("points") > ALL_PAIRS).groupBy("v").agg(F.first("n").alias("n"), F.sum("points").alias("met"), F.collect_list(F.struct("band", "points")).alias("of"))
    crowded = stash(crowded.select("v", "n", "met", F.inline("of")))
    centres = crowded.groupBy("band").agg(F.max(F.struct("met", "v")).alias("most")).select("band", F.col("most.v").alias("centre"))
    large = stash(crowded.join(centres, "band").select("band", "centre", "v"))
    star = large.where("centre <> v").select(F.col("centre").alias("a"), F.col("v").alias("b"))
    ordered = lambda df: df.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    pairs = stash(ordered(functools.reduce(DataFrame.unionByName, (near, same, small, star))))
    # the sets of the points that are in a pair, from one row of each
    needed = stash(pairs.select(F.explode(F.array("a", "b")).alias("v")).distinct().join(points.select("v", "first_k"), "v"))
    rows = docs.select(F.col(key).alias("k"), F.col(text).alias("t"))
    sets = stash(_shingle_sets(rows.join(sent_if_small(needed, 64), rows.k.eqNullSafe(needed.first_k)).select("v", "t"), width).dropDuplicates(["v"]))
    told = stash(_compared(pairs, sets))
    links = told.where(F.col("similarity") >= similarity).select("a", "b")
    labels = stash(component_labels(links))
    if not large.isEmpty():
        links = links.unionByName(_links_in_large_groups(large, told, labels, sets, similarity))
        labels = stash(component_labels(links))
    named = _named(points.select("v", "first_k"), labels, "v")
    wordless = prints.where("n = 0").agg(F.min("k").alias("component_id")).select(F.lit(set_digest(np.zeros(0, np.uint64))).alias("p"), "component_id")
    named = named.unionByName(wordless)
    return prints.select("k", "v").join(named, prints.v == named.p, "left").select(F.col("k").alias(key), "component_id")


def _parts_in_common(points: DataFrame, sets: DataFrame, similarity: float, rounds: int = 2) -> DataFrame:
    """Those of ``points(v, ...)`` that can have a link, with ``n``, the size of the set, and ``common``, the part that others of them meet, too.

    What two sets share is in this part of both, so a point with less than ``similarity`` of its set in it is like no other; without
    such points less is met, hence the rounds.
    """
    left = stash(points.join(sets, "v").withColumn("n", F.size("s")).withColumnRenamed("s", "common"))
    for _ in range(rounds):
        once = left.select("v", F.explode("common").alias("x")).groupBy("x").agg(F.count(F.lit(1)).alias("times"), F.first("v").alias("v")).where("times = 1")
        own = once.groupBy("v").agg(F.collect_list("x").alias("own"))  # at most the point's own set
        common = F.when(F.col("own").isNull(), F.col("common")).otherwise(F.array_except("common", "own"))
        left = stash(left.join(own, "v", "left").withColumn("common", common).drop("own").where(F.size("common") >= F.lit(similarity) * F.col("n") - 1e-9))
    return left


def _links_in_large_groups(large: DataFrame, told: DataFrame, labels: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Links that join the components of large groups which are left after the comparison with the groups' centres.

    Alike sets share a share ``similarity`` of either, so of the shingles met twice, the rarest first, they have one among so many
    that fewer are left than they share; only points that meet there are candidates. Points of one common part are a class: sizes and
    common parts settle the similarity, which is larger for smaller sets, so a point that is like one of a class is like its smallest,
    too, and the smallest of two classes are alike if any of theirs are. Each point is compared with the smallest of a class alone,
    its own included, and no component is missed.

    First, each is compared with the point of the most frequent shingles that it meets. Two points share no more than their common
    parts, and, about one such point, no more than what either shares with it and what either has in common with others besides.
    """
    placed = large.join(labels, large.v == labels.node, "left").select("band", "v", F.coalesce("root", "v").alias("root"))
    open_ = placed.groupBy("band").agg(F.min("root").alias("x"), F.max("root").alias("y")).where("x < y").select("band")
    parts = _parts_in_common(placed.join(open_, "band").select("v", "root").distinct(), sets, similarity)
    each = stash(parts.select("v", F.explode("common").alias("x")))
    met = each.groupBy("x").agg(F.count(F.lit(1)).alias("times"))
    ranked = each.join(met, "x").groupBy("v").agg(F.sort_array(F.collect_list(F.struct("times", "x"))).alias("xs"), F.sum("times").alias("usual"))
    first = F.size("xs") - F.ceil(F.lit(similarity) * F.col("n") - 1e-9) + 1
    told_of = parts.select("v", "root", "n", F.size("common").alias("size"), F.md5(F.array_join("common", ",").cast("binary")).alias("c"))
    at = stash(ranked.join(told_of, "v").withColumn("usual", F.col("usual") / F.col("n")).withColumn("xs", F.slice("xs", F.lit(1), first.cast("int"))))
    meets = at.select("v", "usual", F.inline("xs"))
    tops = meets.groupBy("x").agg(F.max(F.struct("usual", "v")).alias("top"))
    hubs = stash(meets.join(tops, "x").groupBy("v").agg(F.max("top").alias("top")).select("v", F.col("top.v").alias("hub")))
    ordered = lambda df, x, y: df.select(F.least(x, y).alias("a"), F.greatest(x, y).alias("b")).distinct()
    asked = stash(_compared(stash(ordered(hubs.where("v <> hub"), "v", "hub")), sets))
    links = asked.where(F.col("similarity") >= similarity).select("a", "b")
    root = lambda i: told_of.select(F.col("v").alias(i), F.col("root").alias(f"r{i}"))
    merged = component_labels(links.join(root("a"), "a").join(root("b"), "b").select(F.col("ra").alias("a"), F.col("rb").alias("b"))).withColumnRenamed("root", "merged")
    alike = F.when(F.col("v") == F.col("hub"), 1.0).otherwise(F.col("similarity"))
    hubs = hubs.withColumn("a", F.least("v", "hub")).withColumn("b", F.greatest("v", "hub")).join(asked, ["a", "b"], "left").select("v", "hub", alike.alias("alike"))
    hubs = hubs.join(told_of.select(F.col("v").alias("hub"), F.col("n").alias("nh")), "hub")
    least = told_of.groupBy("c").agg(F.min(F.struct("n", "v")).alias("m")).select(F.col("m.v").alias("v"), F.lit(True).alias("least"))
    at = at.join(hubs, "v").join(least, "v", "left").join(merged, at.root == merged.node, "left").withColumn("root", F.coalesce("merged", "root"))
    at = at.withColumn("shared", F.round(F.col("alike") * (F.col("n") + F.col("nh")) / (1 + F.col("alike"))).cast("int"))
    at = stash(at.select("v", "n", "root", "size", "hub", "shared", (F.col("size") - F.col("shared")).alias("besides"), "least", F.inline("xs")).withColumn("blocks", F.ceil(F.col("times") / GROUP_BLOCK).cast("int")))
    block = F.pmod(F.xxhash64("v"), F.col("blocks")).cast("int")
    side = lambda i: [F.col(c).alias(c + i) for c in ("v", "n", "root", "size", "hub", "shared", "besides")]
    one = at.select("x", block.alias("block"), *side("a"))
    two = at.where("least").select("x", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), *side("b"))
    both = F.least("sizea", "sizeb", F.when(F.col("huba") == F.col("hubb"), F.least("shareda", "sharedb") + F.least("besidesa", "besidesb")))
    most = both * (1 + similarity) >= F.lit(similarity) * (F.col("na") + F.col("nb")) - 1e-9
    pairs = ordered(one.join(two, ["x", "block"]).where((F.col("roota") != F.col("rootb")) & most), "va", "vb")
    seen = told.select("a", "b").unionByName(asked.select("a", "b"))
    found = _compared(stash(pairs.join(seen, ["a", "b"], "left_anti")), sets).where(F.col("similarity") >= similarity).select("a", "b")
    return links.unionByName(found)


def keep_one_of_group(docs: DataFrame, key: str = "doc_id", text: str = "text", similarity: float | None = None, **how) -> DataFrame:
    """The rows whose key names their component, all columns as they were, whatever they are called.

    Components are those of ``similar_groups`` if a ``similarity`` is given, else those of ``simhash_groups``. Rows that repeat a key
    that stays are all kept; null and wordless texts are a group of their own kind; an empty table gives an empty result.
    """
    groups = simhash_groups(docs, key, text, **how) if similarity is None else similar_groups(docs, key, text, similarity=similarity, **how)
    k = unused("group_key", docs)
    stays = groups.select(F.col(key).alias(k), F.col(key).eqNullSafe(F.col("component_id")).alias("stays")).groupBy(k).agg(F.max("stays").alias("stays"))
    gone = stash(stays.where("not stays").select(k))
    return docs.join(sent_if_small(gone, 48), docs[key].eqNullSafe(gone[k]), "left_anti").select(*columns_of(docs))


def op6_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_groups(table(spark, sf_dir, "documents", "doc_id", "text"))
