"""The training-data operators against brute force, on small awkward tables."""

import collections
import gc
import hashlib
import math
import random
import re
import time
import tracemalloc
import zlib

import numpy as np
import pytest
import public_tokenizers
import tiktoken
import xxhash
import zstandard
from pyspark.sql import functions as F

from stagewise.llm import byte_bpe, common, exact_dedup, ftrl, language_id, line_dedup, mixing, quality, registry, simhash, substring_dedup, topk, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
RANKS = byte_bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))


def awkward():
    dice = random.Random(3)
    words = ["alpha", "beta", "gamma", "delta", "été", "übung", "ñandú", "x" * 30, "Stop.", "\U0001f600"]
    passage = " ".join(dice.choice(words) for _ in range(70))
    out = [
        (1, None, "en", "a", None), (2, "", "en", None, 0), (3, " \t\n\x0b\x0c\r ", None, "a", 7), (4, "Same Text.", "en", "b", 10), (5, "same text.", "en", "b", 10),
        (6, "SAME TEXT.", None, None, 10), (7, "É same", "fr", "c", 6), (8, "é same", "fr", "c", 6), (None, "no key", "en", "a", 6), (9, "one two three", "en", "a", 13),
        (10, "word " * 20_000, "en", "a", 100_000), (11, "word " * 20_000, "en", "a", 100_000), (12, "123 !!! 456", None, "c", 11), (13, "\x1c\x85   odd", "en", "c", 8),
    ]
    for i in range(20, 50):
        left, right = (" ".join(dice.choice(words) + str(dice.randrange(50)) for _ in range(dice.randrange(40))) for _ in range(2))
        out.append((i, f"{left} {passage} {right}" if i % 2 else f"{left}  {right}", "en", f"s{i % 3}", 1))
    for i in range(50, 60):
        t = passage.split()
        t[i - 50] = "changed"
        out.append((i, " ".join(t), "en", "z", 1))
    return out


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(awkward(), SCHEMA).repartition(3).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def words_of(text):
    return (text or "").encode().split()


# --- exact dedup -----------------------------------------------------------------------------------------------------------------


def fold(t):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")


@pytest.mark.parametrize("hash_fn", [exact_dedup.chunk_hash, lambda c: F.pmod(F.xxhash64(c), F.lit(3))], ids=["usual", "colliding"])
def test_exact_groups(docs, hash_fn):
    by = collections.defaultdict(list)
    for d, t, *_ in awkward():
        by[fold(t)].append(d)
    want = {(d, max((x for x in by[fold(t)] if x is not None), default=None), len(by[fold(t)]), hashlib.sha256(fold(t).encode()).hexdigest()) for d, t, *_ in awkward()}
    got = exact_dedup.exact_groups(docs, hash_fn=hash_fn).collect()
    assert {(r["doc_id"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in got} == want
    assert len(got) == len(awkward()) and all(r["kept"] == (r["doc_id"] == r["keep_id"]) for r in got)


def test_chunks_join_to_the_text(docs):
    both = docs.select(F.coalesce("text", F.lit("")).alias("t")).withColumn("cs", exact_dedup.chunks(F.col("t"), 4, 16))
    assert both.where(F.concat_ws("", "cs") != F.col("t")).count() == 0
    assert both.where(F.exists("cs", lambda c: F.length(c) > 16)).count() == 0


def test_exact_dedup_is_native(docs):
    plan = exact_dedup.exact_groups(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_keep_one_keeps_columns_and_repeated_rows_once(docs):
    twice = docs.unionByName(docs).withColumn("h", F.lit(1)).withColumn("k", F.lit(2))
    kept = exact_dedup.keep_one(twice)
    assert kept.columns == twice.columns
    assert kept.count() == len({fold(t) for _, t, *_ in awkward()})


CLASHING = ("__key", "__sha", "__times", "__kept_sha", "__copy", "dedup_key", "DEDUP_SHA", "mix_key", "mix_times", "mix_copy", "group_key", "k", "t", "size", "a.b")


@pytest.mark.parametrize("keep", [exact_dedup.keep_one, simhash.keep_one_of_group, mixing.mixed], ids=["exact", "near", "mix"])
def test_columns_of_any_name_stay_as_they_were(docs, keep):
    marked = docs.withColumns({c: F.concat(F.lit(c), "doc_id") for c in CLASHING})
    kept = keep(marked)
    assert kept.columns == marked.columns and kept.count() == keep(docs).count()
    wrong = F.lit(False)
    for c in CLASHING:
        wrong = wrong | ~F.col(f"`{c}`").eqNullSafe(F.concat(F.lit(c), "doc_id"))
    assert kept.where(wrong).count() == 0


def test_only_chunks_met_again_are_compared(spark):
    one, two = ("sentence one. " * 400), ("sentence two. " * 400)
    rows = [(1, one + two), (2, two + one), (3, one + two), (4, one), (5, "alone")]
    got = {r["doc_id"]: (r["keep_id"], r["group_size"]) for r in exact_dedup.exact_groups(spark.createDataFrame(rows, "doc_id long, text string"), hash_fn=lambda c: F.lit(7).cast("long")).collect()}
    assert got == {1: (3, 2), 2: (2, 1), 3: (3, 2), 4: (4, 1), 5: (5, 1)}


# --- simhash -----------------------------------------------------------------------------------------------------------------------


def plain_fingerprint(text, width=4):
    w = [bytes(c + 32 if 65 <= c <= 90 else c for c in x) for x in words_of(text)]
    if not w:
        return 0
    hs = [xxhash.xxh64_intdigest(b" ".join(w[i : i + width]), 42) for i in range(max(1, len(w) - width + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def components(prints, distance):
    label = dict.fromkeys(prints)
    for p in prints:
        if label[p] is None:
            label[p], todo = p, [p]
            while todo:
                x = todo.pop()
                for q in prints:
                    if label[q] is None and (x ^ q).bit_count() <= distance:
                        label[q] = p
                        todo.append(q)
    return label


def test_simhash_groups(docs):
    prints = {i: plain_fingerprint(t) for i, (_, t, *_) in enumerate(awkward())}
    label = components(sorted(set(prints.values())), 4)
    ids = collections.defaultdict(list)
    for i, (d, *_) in enumerate(awkward()):
        if d is not None:
            ids[label[prints[i]]].append(d)
    want = {(d, f"{prints[i]:016x}", min(ids[label[prints[i]]], default=None)) for i, (d, *_) in enumerate(awkward())}
    assert {tuple(r) for r in simhash.simhash_groups(docs).select("doc_id", "fingerprint", "component_id").collect()} == want


@pytest.mark.parametrize("pieces", [2, 3])
def test_anchors_lose_no_pair(spark, pieces):
    dice = random.Random(pieces)
    points = [dice.getrandbits(64) for _ in range(40)]
    for p in list(points):
        for d in range(1, 7):
            points.append(p ^ sum(1 << b for b in dice.sample(range(64), d)))
    points = sorted(set(points))
    signed = [p - (1 << 64) if p >> 63 else p for p in points]
    got = {tuple(r) for r in simhash.near_pairs(spark.createDataFrame([(s,) for s in signed], "fp long"), 4, pieces).collect()}
    want = {(a, b) for a in signed for b in signed if a < b and ((a ^ b) & (2**64 - 1)).bit_count() <= 4}
    assert got == want


def test_chain_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 200), (200, 150)], "a long, b long")
    got = {r["node"]: r["root"] for r in simhash.component_labels(edges).collect()}
    assert got == {**dict.fromkeys(range(61), 0), 100: 100, 150: 100, 200: 100}


def similar_components(rows, bound, width=5):
    """Smallest key of each component of texts whose shingle sets are at least ``bound`` alike, pair by pair."""
    sets = []
    for _, t in rows:
        w = [bytes(c + 32 if 65 <= c <= 90 else c for c in x) for x in words_of(t)]
        sets.append(frozenset(tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))) if w else frozenset())
    near = {i: [j for j in range(len(rows)) if sets[i] == sets[j] or len(sets[i] & sets[j]) >= bound * len(sets[i] | sets[j])] for i in range(len(rows))}
    out, seen = {}, set()
    for i in near:
        if i not in seen:
            group, todo = {i}, [i]
            while todo:
                for j in near[todo.pop()]:
                    if j not in group:
                        group.add(j)
                        todo.append(j)
            seen |= group
            least = min((rows[j][0] for j in group if rows[j][0] is not None), default=None)
            out |= dict.fromkeys(group, least)
    return [(k, out[i]) for i, (k, _) in enumerate(rows)]


@pytest.mark.parametrize(("all_pairs", "block"), [(16, 1024), (2, 4)])
def test_similar_groups(spark, monkeypatch, all_pairs, block):
    monkeypatch.setattr(simhash, "ALL_PAIRS", all_pairs)
    monkeypatch.setattr(simhash, "GROUP_BLOCK", block)
    dice = random.Random(6)
    base = [f"w{dice.randrange(400)}" for _ in range(160)]
    rows = [(d, t) for d, t, *_ in awkward()]
    for i in range(100, 160):  # up to five words of a hundred and sixty are others, or words are missing at an end
        w = list(base)
        for _ in range(i % 6):
            w[dice.randrange(160)] = f"other{dice.randrange(9999)}"
        rows.append((i, " ".join(w[i % 4 * 3 :])))
    rows += rows[-2:]
    got = simhash.similar_groups(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    assert collections.Counter(map(tuple, got)) == collections.Counter(similar_components(rows, 0.8))


def test_large_groups_are_not_paired(spark, monkeypatch):
    """Copies of one passage with words of their own: components as pair by pair, comparisons about as many as points."""
    dice = random.Random(8)
    passages = [[f"w{dice.randrange(10**6)}" for _ in range(60)] for _ in range(2)]
    texts = [p[i % 3 :] + [f"own{dice.randrange(10**9)}" for _ in range(dice.randrange(4, 15))] for p in passages for i in range(150)]
    rows = [(i, " ".join(w)) for i, w in enumerate(texts)]
    asked, compared = [], simhash._compared
    monkeypatch.setattr(simhash, "_compared", lambda pairs, sets: asked.append(pairs.count()) or compared(pairs, sets))
    got = simhash.similar_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(map(tuple, got)) == sorted(similar_components(rows, 0.8))
    assert sum(asked[1:]) < 4 * len(rows)  # of 2 * 150 * 149 / 2 pairs


def test_near_copies_go_with_all_columns(docs, empty):
    clash = {c: F.lit(1) for c in ("group_key", "v", "k", "a.b", "__key", "component_id")}
    kept = simhash.keep_one_of_group(docs.withColumns(clash), similarity=0.8)
    assert kept.columns == [*docs.columns, *clash]
    want = similar_components([(d, t) for d, t, *_ in awkward()], 0.8)
    assert sorted(map(str, (r["doc_id"] for r in kept.collect()))) == sorted(str(k) for k, c in want if k == c)
    assert simhash.keep_one_of_group(empty, similarity=0.8).count() == simhash.similar_groups(empty).count() == 0


# --- substrings ----------------------------------------------------------------------------------------------------------------------


def cut(window):
    first = {}
    for d, t, *_ in awkward():
        w = words_of(t)
        for i in range(len(w) - window + 1):
            g = b" ".join(w[i : i + window])
            if d is not None:
                first[g] = min(first.get(g, d), d)
    out = set()
    for d, t, *_ in awkward():
        w, gone = words_of(t), set()
        for i in range(len(w) - window + 1):
            if d is not None and first[b" ".join(w[i : i + window])] < d:
                gone |= set(range(i, i + window))
        out.add((d, len(w), len(gone), hashlib.sha256(b" ".join(x for i, x in enumerate(w) if i not in gone)).hexdigest()))
    return out


@pytest.mark.parametrize(("window", "seed"), [(50, 10), (12, 5), (6, 6)])
def test_substrings(docs, window, seed):
    got = substring_dedup.cut_repeats(docs, window=window, seed_words=seed)
    assert {tuple(r) for r in got.collect()} == cut(window)


def test_sliding_min():
    x = np.random.default_rng(1).integers(0, 99, 100).astype(np.uint64)
    for w in (1, 2, 5, 41):
        assert (substring_dedup.sliding_min(x, w) == np.lib.stride_tricks.sliding_window_view(x, w).min(1)).all()


# --- lines -----------------------------------------------------------------------------------------------------------------------


def awkward_lines():
    dice = random.Random(8)
    pool = [f"line {i}" for i in range(12)] + ["", " ", "été", "same", "same"]
    shared = [f"shared {i}" for i in range(9)]
    out = [
        (1, None), (2, ""), (3, "\n\n\n"), (4, " \n\t\r\n"), (5, "one"), (6, "a\nb\nc"), (7, " a \r\nb\t\n\nc\n"), (None, "a\nb\nc\nd"), (8, "x\n" * 40), (9, "p\nq\n" * 9),
        (10, "x" * 3_000_000 + "\na\nb\nc"), (11, "\n".join(map(str, range(5000)))), (12, "\n".join(map(str, range(2500, 7000)))), (13, "a\nb\u0085\nc\x1c\nb"), (13, "a\nb\nc\nother"),
    ]
    for i in range(20, 60):
        cut = sorted(dice.sample(range(10), 2))
        out.append((i, "\n".join(dice.choices(pool, k=dice.randrange(9)) + shared[cut[0] : cut[1]] + dice.choices(pool, k=dice.randrange(9)))))
    return out + out[-3:]


def without_runs(rows, run, order):
    """By the definition, place by place; rows that repeat key and text are one."""
    trim = " \t\r\x0b\x0c"
    first, parts = set(), {}
    for k, t in sorted(set(rows), key=order):
        lines = (t or "").split("\n")
        full = [i for i, x in enumerate(lines) if x.strip(trim)]
        gone = set()
        for i in range(len(full) - run + 1):
            window = tuple(lines[j].strip(trim) for j in full[i : i + run])
            if window in first:
                gone |= set(full[i : i + run])
            first.add(window)
        parts[k, t] = (k, len(full), len(gone), "\n".join(x for i, x in enumerate(lines) if i not in gone))
    return collections.Counter(parts[r] for r in rows)


@pytest.mark.parametrize("run", [1, 2, 3, 6])
def test_lines(spark, run):
    rows = awkward_lines()
    df = spark.createDataFrame([(k, t, 1, 2) for k, t in rows], "doc_id long, text string, seed int, spans int").repartition(4)
    hashes = {(r["doc_id"], r["text"]): r["h"] for r in df.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h")).collect()}
    got = line_dedup.without_repeated_runs(df, run=run)
    assert collections.Counter(map(tuple, got.collect())) == without_runs(rows, run, lambda r: (r[0] is not None, r[0] or 0, hashes[r]))


def test_single_repeated_lines_go(spark, tmp_path):
    docs = [(1, "one\nlicence"), (2, "two\n licence \ntwo"), (3, "licence"), (4, None)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = registry.QUERIES["op7_single_line_dedup"](spark, str(tmp_path)).orderBy("doc_id").collect()
    assert [(r["n_lines"], r["n_removed"]) for r in got] == [(2, 0), (3, 2), (1, 1), (0, 0)]


# --- tokens --------------------------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def codec():
    return byte_bpe.Codec(RANKS, public_tokenizers.PATTERN)


@pytest.fixture(scope="module")
def reference():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=RANKS, special_tokens={})


def test_encoding_equals_reference(codec, reference):
    dice, tokens = random.Random(5), sorted(RANKS)
    for i in range(1500):
        if i % 3 == 0:
            s = "".join(chr(dice.choice([dice.randrange(32, 127), dice.randrange(0x2FF), dice.randrange(0x10FFFF)])) for _ in range(40))
        elif i % 3 == 1:
            s = b"".join(dice.choice(tokens) for _ in range(9)).decode("utf8", "replace")
        else:
            s = "".join(dice.choice("aab th\n\t\x1c\x85's<|endoftext|>") for _ in range(dice.randrange(300)))
        s = s.encode("utf8", "replace").decode()
        ids = np.frombuffer(codec.encode(s), "<u4").tolist()
        assert ids == reference.encode_ordinary(s)
        assert codec.decode_text(ids) == s


def test_pair_rule_is_the_definition(codec):
    t, dice = codec.pieces.transducer, random.Random(7)
    for _ in range(3000):
        a, b = dice.randrange(len(RANKS)), dice.choice([dice.randrange(300), dice.randrange(len(RANKS))])
        assert t.follows(a, b) == (byte_bpe.merge_by_rank(t.bytes_of[a] + t.bytes_of[b], RANKS) == [a, b])


def test_full_tables_are_emptied(monkeypatch, reference):
    for name in ("MAX_TRANSITIONS", "MAX_PAIRS", "MAX_PIECES"):
        monkeypatch.setattr(byte_bpe, name, 20)
    small = byte_bpe.Codec(RANKS, public_tokenizers.PATTERN)
    for s in ("the quick brown fox " * 5, "unbelievable antidisestablishmentarianism", "z" * 500):
        assert np.frombuffer(small.encode(s), "<u4").tolist() == reference.encode_ordinary(s)


def test_states_are_bounded_by_bytes(monkeypatch, reference):
    monkeypatch.setattr(byte_bpe, "STATE_BYTES", 300)
    small = byte_bpe.Codec(RANKS, public_tokenizers.PATTERN)
    for s in ("the quick brown fox " * 5, "unbelievable antidisestablishmentarianism", "z" * 500):
        assert np.frombuffer(small.encode(s), "<u4").tolist() == reference.encode_ordinary(s)
        assert len(small.pieces.transducer.kept) < 600


def test_tables_are_compact(monkeypatch):
    """Full ones of each worker stand beside an executor's heap; here with a twentieth of the bounds, so that filling them takes little time."""
    for name in ("MAX_TRANSITIONS", "MAX_PAIRS", "MAX_PIECES"):
        monkeypatch.setattr(byte_bpe, name, getattr(byte_bpe, name) // 20)
    dice = random.Random(3)
    words = ["".join(dice.choices("etaoinshrdlu", k=dice.randrange(3, 11))) for _ in range(8_000)]
    tracemalloc.start()
    small = byte_bpe.Codec(RANKS, public_tokenizers.PATTERN)
    for w in words:
        small.encode(w)
    gc.collect()
    size = tracemalloc.get_traced_memory()[0]
    tracemalloc.stop()
    assert size < 16 << 20


@pytest.mark.parametrize("text", ["a" * 5_000_000, "ab" * 300_000, "é" * 200_000, "qwertyuiopasdfghjklzxcvbnm" * 20_000])
def test_long_pieces_take_linear_time(codec, monkeypatch, text):
    monkeypatch.setattr(byte_bpe, "MAX_TRANSITIONS", 50)  # the tables are emptied within the piece, too
    began = time.monotonic()
    ids = codec.encode(text)
    assert time.monotonic() - began < 60
    ids = np.frombuffer(ids, "<u4")
    assert b"".join(codec.decode(ids.tolist())) == text.encode()
    pairs = {(a, b) for a, b in zip(ids[:-1].tolist(), ids[1:].tolist(), strict=True)}
    assert all(codec.pieces.transducer.follows(a, b) for a, b in pairs)  # which makes the sequence the encoding


def test_stream_cuts_at_characters():
    data = "aé€\U0001f600z".encode() + b"\xf0\x9f"
    for step in range(1, 6):
        s = byte_bpe.Utf8Stream()
        parts = [s.feed(data[i : i + step]) for i in range(0, len(data), step)]
        "".join(p.decode() for p in parts)
        assert b"".join(parts) + s.finish() == data


def test_round_trip_query(docs, reference):
    got = byte_bpe.round_trip(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).collect()
    want = set()
    for d, t, *_ in awkward():
        ids = reference.encode_ordinary(t or "")
        want.add((d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert {tuple(r) for r in got} == want


# --- top-k -----------------------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize(("size", "block", "scale"), [(120, 4096, 256), (60, 3, 256), (40, 4096, 1 << 24), (3, 4096, 256)])
def test_top_k(spark, monkeypatch, size, block, scale):
    monkeypatch.setattr(topk, "QUERY_BLOCK", block)
    dice = np.random.default_rng(size)
    vectors = {i * 10: (np.round(dice.normal(size=6), 1) if i % 4 else np.ones(6)).tolist() for i in range(size)}
    rows = [(i, v) for i, v in vectors.items()] + [(5, None), (15, [1.0, None, 1.0, 1.0, 1.0, 1.0]), (25, [float("nan")] * 6), (None, [1.0] * 6), (35, [float("inf")] * 6), (45, [1.0, 2.0])]
    got = topk.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3), lambda v: v % 50 == 0, scale=scale)
    ints = {i: [int(np.floor(scale * x)) for x in v] for i, v in vectors.items()}
    want = set()
    for q in (i for i in ints if i % 50 == 0):
        best = sorted(((-sum(a * b for a, b in zip(ints[q], v, strict=True)), i) for i, v in ints.items() if i != q))[:5]
        want |= {(q, r, i, -s) for r, (s, i) in enumerate(best, 1)}
    assert {tuple(r) for r in got.collect()} == want


# --- mixing ------------------------------------------------------------------------------------------------------------------------------


def test_targets_reshare_the_excess():
    sizes = {(True, "a"): 10, (True, "b"): 1000, (True, "c"): 1000, (False, ""): 0}
    t = mixing.targets(sizes)
    assert t[(True, "a")] == 20 and t[(False, "")] == 0
    assert sum(t.values()) == pytest.approx(1.5 * 2010)
    assert t[(True, "b")] == pytest.approx(2 * t[(True, "c")])


@pytest.mark.parametrize("seed", range(6))
def test_budget_is_met_where_it_can_be(seed):
    dice = np.random.default_rng(seed)
    lengths = np.unique(dice.integers(0, 40, 12))
    counts = dice.integers(1, 5, len(lengths))
    total = int((lengths * counts).sum())
    for budget in (0, 1, total // 3, total - 1, total, total + 5):
        take = mixing.fit_budget(lengths, counts, budget)
        assert (take <= counts).all() and (take >= 0).all()
        assert int((lengths * take).sum()) <= budget
        if 1 in lengths:
            assert int((lengths * take).sum()) >= min(budget, total) - 3
    big = mixing.fit_budget(np.arange(1, 3000), np.full(2999, 50), 100_000_001)
    assert int((np.arange(1, 3000) * big).sum()) == 100_000_001


def best_sum(lengths, counts, budget):
    sums = {0}
    for length, n in zip(lengths.tolist(), counts.tolist(), strict=True):
        sums = {s + length * i for s in sums for i in range(n + 1) if s + length * i <= budget}
    return max(sums)


@pytest.mark.parametrize("seed", range(40))
def test_budget_is_the_best_subset_sum(seed):
    dice = np.random.default_rng(seed)
    lengths = np.unique(dice.integers(0, 30, 6))
    counts = dice.integers(1, 8, len(lengths))
    for budget in {int(b) for b in dice.integers(0, int((lengths * counts).sum()) + 3, 12)}:
        take = mixing.fit_budget(lengths, counts, budget)
        assert (take >= 0).all() and (take <= counts).all()
        assert int((lengths * take).sum()) == best_sum(lengths, counts, budget)
        some = mixing.fit_budget(lengths, counts, budget, exact=40)  # an even share first
        assert budget - 30 < int((lengths * some).sum()) <= budget or int((lengths * some).sum()) == best_sum(lengths, counts, budget)


def test_budgets_that_an_even_share_would_miss():
    for lengths, count, budget in (([7, 10], 3, 20), ([3, 5], 10, 41)):
        take = mixing.fit_budget(np.array(lengths), np.full(2, count), budget)
        assert int((np.array(lengths) * take).sum()) == budget


def test_mix(docs):
    got = mixing.mix(docs).collect()
    again = mixing.mix(docs.repartition(7)).collect()
    assert sorted(map(str, got)) == sorted(map(str, again))
    size = collections.Counter()
    source = {d: s for d, _, _, s, _ in awkward()}
    for d, t, _, s, _ in awkward():
        size[s] += len(words_of(t))
    taken = collections.Counter()
    for r in got:
        assert r["taken"] in (0, r["size"], 2 * r["size"]) and r["source_size"] == size[source[r["doc_id"]]]
        taken[source[r["doc_id"]], r["target"]] += r["taken"]
    assert all(n <= t + 1e-6 for (_, t), n in taken.items())
    assert len(got) == len(awkward())


def test_mix_takes_near_the_target(spark):
    dice = random.Random(8)
    rows = [(i, "w " * dice.randrange(1, 60), "en", f"s{i % 5}", 0) for i in range(600)] + [(1000 + i, "w " * 30, "en", "s0", 0) for i in range(400)]
    got = mixing.mix(spark.createDataFrame(rows, SCHEMA)).groupBy("source_size", "target").agg(F.sum("taken").alias("t")).collect()
    assert all(r["target"] - r["t"] < 1.0 for r in got)


# --- classifiers -------------------------------------------------------------------------------------------------------------------------


def labelled(spark, n=900):
    dice, rows, labels = random.Random(4), [], []
    en = ["the", "and", "river", "house", "garden", "quickly", "walks", "under", "bright", "morning"]
    fr = ["le", "et", "rivière", "maison", "jardin", "vite", "marche", "sous", "brillant", "matin"]
    for i in range(n):
        lang = "en" if dice.random() < 0.6 else "fr"
        w = [dice.choice(en if lang == "en" else fr) for _ in range(dice.randrange(5, 40))]
        toxic, bad = dice.random() < 0.2, dice.random() < 0.3
        if toxic:
            w.insert(dice.randrange(len(w)), dice.choice(["vileword", "foulterm"]))
        text = " ".join(w)
        rows.append((i, text.upper().replace(" ", "!! ") if bad else text, lang, "s", len(text)))
        labels.append((i, int(not bad), int(toxic)))
    return spark.createDataFrame(rows, SCHEMA), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def held(df, parts, rest):
    return df.where(common.fold_of(F.col("doc_id"), parts) == rest)


def test_fold_is_crc32(spark):
    got = {r["id"]: r["f"] for r in spark.range(50).select("id", common.fold_of(F.col("id"), 5).alias("f")).collect()}
    assert got == {i: zlib.crc32(str(i).encode()) % 5 for i in range(50)}


def test_toxicity(spark, docs, empty):
    d, labels = labelled(spark)
    model = toxicity.fit(d, labels.where(common.fold_of(F.col("doc_id"), 4) != 2))
    assert len(model.at) < 500
    seen = held(toxicity.score(d, model).join(labels, "doc_id"), 4, 2)
    assert seen.where("predicted = toxic").count() / seen.count() > 0.97
    got = {r["doc_id"]: r["score"] for r in toxicity.score(docs, model).collect()}
    assert len(got) == len({x[0] for x in awkward()}) and all(0 <= s <= 1 for s in got.values())
    assert toxicity.reject_toxic(docs.withColumn("score", F.lit(2)), model).columns == [*docs.columns, "score"]
    assert toxicity.score(empty, toxicity.fit(empty, labels.limit(0))).count() == 0


def test_quality(spark, docs, empty):
    d, labels = labelled(spark)
    model = quality.fit(d, labels.where(common.fold_of(F.col("doc_id"), 5) != 0))
    seen = held(toxicity.score(d, model).join(labels, "doc_id"), 5, 0)
    assert seen.where("predicted = quality").count() / seen.count() > 0.93
    assert all(0 <= r["score"] <= 1 for r in toxicity.score(docs, model).collect())
    assert toxicity.score(empty, quality.fit(empty, labels.limit(0))).count() == 0


def test_quality_without_what_it_needs(spark, docs):
    label = lambda rows: spark.createDataFrame(rows, "doc_id long, quality int")
    absent = [(10_000 + i, i % 2) for i in range(90)]
    for rows in ([], absent, [(4, 1), (5, 1)], [(4, 1), (5, 0)], [*absent, (4, 1)], [(1, 1), (2, 1), (3, 0), (None, 0)], [(4, None), (5, 2)]):
        scores = {r["score"] for r in toxicity.score(docs, quality.fit(docs, label(rows))).collect()}
        assert scores == {0.5}, rows
    assert quality.platt(np.zeros(0), np.zeros(0)) == (0.0, 0.0)


def test_training_bytes_are_bounded(spark):
    d, labels = labelled(spark)
    all_ = toxicity.labelled_texts(d, labels, "toxic", "doc_id", "text", 10_000, 1 << 30)
    some = toxicity.labelled_texts(d, labels, "toxic", "doc_id", "text", 10_000, 20_000)
    size = lambda x: x.agg(F.sum(F.octet_length("t"))).first()[0]
    assert all_.count() == 900 and 10_000 < size(some) < 30_000 < size(all_)


def plain_ftrl(rows, targets, order, alpha, beta, l1, l2):
    """Coordinate by coordinate, after the published update."""
    z, n, classes = collections.defaultdict(float), collections.defaultdict(float), len(targets[0])

    def weight(f, c):
        if abs(z[f, c]) <= (0 if f == "bias" else l1):
            return 0.0
        return -(z[f, c] - math.copysign(0 if f == "bias" else l1, z[f, c])) / ((beta + math.sqrt(n[f, c])) / alpha + (0 if f == "bias" else l2))

    for i in order:
        x = [*rows[i], ("bias", 1.0)]
        m = [sum(weight(f, c) * v for f, v in x) for c in range(classes)]
        p = [1 / (1 + math.exp(-m[0]))] if classes == 1 else [math.exp(a - max(m)) / sum(math.exp(b - max(m)) for b in m) for a in m]
        for c in range(classes):
            old = {f: weight(f, c) for f, _ in x}
            for f, v in x:
                g = (p[c] - targets[i][c]) * v
                sigma = (math.sqrt(n[f, c] + g * g) - math.sqrt(n[f, c])) / alpha
                z[f, c] += g - sigma * old[f]
                n[f, c] += g * g
    return weight


@pytest.mark.parametrize("classes", [1, 3])
def test_ftrl_is_the_published_update(classes):
    dice = random.Random(classes)
    rows = [[(f, dice.random()) for f in sorted(dice.sample(range(20), dice.randrange(6)))] for _ in range(80)]
    targets = [[1.0 if dice.randrange(max(2, classes)) == c else 0.0 for c in range(classes)] for _ in rows]
    model = ftrl.FtrlLogistic(20, classes, alpha=0.3, l1=0.1, l2=0.5)
    for x, y in zip(rows, targets, strict=True):
        model.learn(np.array([f for f, _ in x], np.int64), np.array([v for _, v in x]), np.array(y) if classes > 1 else y[0])
    w, b = model.weights()
    weight = plain_ftrl(rows, targets, range(len(rows)), 0.3, model.beta, 0.1, 0.5)
    for c in range(classes):
        assert b[c] == pytest.approx(weight("bias", c), abs=1e-9)
        assert [w[f, c] for f in range(20)] == pytest.approx([weight(f, c) for f in range(20)], abs=1e-9)


def test_toxicity_scores_by_hand(spark, docs):
    """A text's score is the logistic of the bias and the weights of its distinct words, stems and pairs."""
    d, labels = labelled(spark)
    model = toxicity.fit(d, labels)
    weights = dict(zip(model.at.tolist(), model.weight.tolist(), strict=True))
    for r in toxicity.score(docs.unionByName(docs), model).join(docs.select("doc_id", "text").dropDuplicates(["doc_id"]), "doc_id").where("doc_id not in (10, 11)").collect():
        found = set()
        words = re.findall(r"[0-9a-z\x80-\U0010ffff]+", "".join(c.lower() if c < "\x80" else c for c in r["text"] or ""))
        for i, w in enumerate(words):  # each feature by itself, from a text that holds nothing else
            alone = toxicity.word_features([w.encode()])[1].tolist()
            found |= set(alone)
            for gap in (1, 2):
                if i + gap < len(words):
                    both = " ".join([w, *(["zzz"] if gap == 2 else []), words[i + gap]])
                    found.add(toxicity.word_features([both.encode()])[1][(9 if gap == 2 else 6) + (2 if gap == 2 else 0)])
        margin = model.bias + sum(weights.get(f, 0.0) for f in found)
        assert r["score"] == pytest.approx(1 / (1 + math.exp(-margin)), abs=1e-6)


def test_quality_scores_by_hand(spark, docs):
    d, labels = labelled(spark)
    model = quality.fit(d, labels)
    size = lambda text, words: len(zstandard.ZstdCompressor(level=quality.LEVEL, dict_data=zstandard.ZstdCompressionDict(words), write_content_size=False, write_checksum=False, write_dict_id=False).compress(text))
    for r in toxicity.score(docs, model).join(docs.select("doc_id", "text"), "doc_id").where("doc_id <> 11").collect():
        t = (r["text"] or "").encode()
        saved = sum(size(t[i : i + 4096], model.bad) - size(t[i : i + 4096], model.good) for i in range(0, len(t), 4096)) / max(1, len(t))
        assert r["score"] == pytest.approx(1 / (1 + math.exp(-(model.slope * saved + model.shift))), abs=1e-2)


def test_language_scores_by_hand(spark, docs):
    """Margins are the mean over a text's character 1- to 3-grams of the weight times idf, scaled, and the bias."""
    d, _ = labelled(spark)
    model = language_id.fit(d)
    for r in language_id.identify(docs, model).join(docs.select("doc_id", F.lower("text").alias("text")), "doc_id").where("doc_id not in (10, 11) and lang_pred <> 'und'").collect():
        grams = [r["text"][i : i + n] for n in (1, 2, 3) for i in range(len(r["text"]) - n + 1)]
        at = [int(language_id.gram_features([g.encode()])[len(g) - 1][0][0]) for g in grams]
        m = [(language_id.SCALE * sum(float(model.table[f, c]) for f in at) / len(at) + model.bias[c]) / model.temperature for c in range(len(model.languages))]
        p = [math.exp(x - max(m)) / sum(math.exp(y - max(m)) for y in m) for x in m]
        assert r["lang_pred"] == model.languages[p.index(max(p))] and r["score"] == pytest.approx(max(p), abs=1e-6)


def test_language(spark, docs, empty):
    d, _ = labelled(spark)
    model = language_id.fit(d.where(common.fold_of(F.col("doc_id"), 5) != 0))
    seen = held(language_id.identify(d, model).join(d.select("doc_id", "lang"), "doc_id"), 5, 0)
    assert seen.where("lang_pred = lang").count() / seen.count() > 0.98
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language_id.identify(docs, model).collect()}
    assert all(got[i][0] == "und" for i in (1, 2, 3, 12)) and all(0 <= s <= 1 for _, s in got.values())
    assert language_id.identify(empty, language_id.fit(empty)).count() == 0


def test_document_frequencies(spark):
    rows = ["abab", "ab", "ba é", ""]
    df, total = language_id.document_frequencies(spark.createDataFrame([(t,) for t in rows], "t string").repartition(2))
    assert total == 4
    assert sum(df) == sum(len({(n, t[i : i + n]) for n in (1, 2, 3) for i in range(len(t) - n + 1)}) for t in rows)


# --- every operator on an empty table ---------------------------------------------------------------------------------------------------


def test_empty_tables(spark, empty):
    assert exact_dedup.exact_groups(empty).count() == 0
    assert simhash.simhash_groups(empty).count() == 0
    assert substring_dedup.cut_repeats(empty).count() == 0
    assert byte_bpe.round_trip(empty, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).count() == 0
    assert mixing.mix(empty).count() == 0
    assert line_dedup.without_repeated_runs(empty).count() == 0
    assert topk.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>"), lambda v: v % 50 == 0).count() == 0
