import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from stagewise.functions.hashing import below_col, below_np, hash_col, hash_np
from stagewise.operators import applications as A
from stagewise.operators import cells
from stagewise.operators import elementary as E
from stagewise.operators import filters as X
from stagewise.operators import native as N
from stagewise.operators import online as O


@pytest.fixture(scope="module")
def keys(spark):
    return spark.range(6000).select((F.col("id") * 7919 - 1000).alias("k"), (F.col("id") % 9 == 0).alias("y")).persist()


def wrong(handle, df, cols=("k",)):
    r = handle.probe(df, list(cols)).agg(F.sum((F.col("y") & ~F.col("hit")).cast("int")), F.sum((~F.col("y") & F.col("hit")).cast("int"))).first()
    return tuple(r)


def test_hashes_agree(spark):
    k = np.array([0, 1, -1, 2**62, -(2**63)], np.int64)
    df = spark.createDataFrame([(int(x),) for x in k], "k long").select("k", hash_col(9, F.col("k")).alias("h"), below_col(hash_col(9, F.col("k")), F.lit(1000), 1).alias("b"))
    got = {r["k"]: (r["h"], r["b"]) for r in df.collect()}
    h = hash_np(9, k)
    assert [got[int(x)] for x in k] == list(zip(h.view(np.int64).tolist(), below_np(h, 1000, 1).tolist(), strict=True))


@pytest.mark.parametrize("width", [1, 3, 4, 7, 13, 32])
def test_cells_round_trip(spark, width):
    values = np.random.default_rng(width).integers(0, 1 << width, 200).astype(np.uint64)
    words = cells.pack(values, width)
    assert (cells.read_np(words, np.arange(200), width) == values).all()
    df = spark.range(200).withColumn("w", F.array(*[F.lit(int(w)) for w in words]))
    got = df.select("id", cells.read_col(F.col("w"), F.col("id"), width).alias("v")).orderBy("id").collect()
    assert [r["v"] for r in got] == values.tolist()


def test_three_keys_on_five_cells():
    slots = np.array([[0, 1, 1], [1, 2, 3], [2, 3, 4]])
    rounds = E.peel(slots, 5)
    values = np.array([1, 0, 1], np.uint64)
    table = E.fill(slots, 5, rounds, values)
    assert (np.bitwise_xor.reduce(table[slots], 0) == values).all()
    assert E.peel(np.array([[0, 0], [1, 1], [2, 2]]), 5) is None


@pytest.mark.parametrize("kind", sorted(E.KINDS))
def test_kinds_build_test_and_probe_alike(spark, keys, kind):
    h = X.single(keys, ["k"], "y", kind, 0.0 if E.KINDS[kind].exact else 0.05, segment_keys=2500)
    fn, fp = wrong(h, keys)
    assert fn == 0
    assert fp == 0 if E.KINDS[kind].exact else fp < 600
    assert h.confusion().first()["fp"] == fp


@pytest.mark.parametrize("layout", ["uniform", "coupled"])
@pytest.mark.parametrize("strategy", ["a", "b"])
def test_staged_is_exact(keys, layout, strategy):
    h = X.staged(keys, ["k"], "y", layout=layout, strategy=strategy, segment_keys=2500)
    assert wrong(h, keys) == (0, 0)
    assert len(h.spec.stages) == 2


def test_ways_of_building_agree(keys):
    for h in (X.staged_pushdown(keys, ["k"], "y", segment_keys=2500), X.alternating(keys, ["k"], "y"), X.alternating(keys, ["k"], "y", tail="colour_map", max_layers=3), X.staged(keys, ["k"], "y", first="bloom", second="edge_map")):
        assert wrong(h, keys) == (0, 0)
        assert h.probe(keys, ["k"], strategy="shuffle").where("hit").count() == keys.where("y").count()


def test_one_and_two_sided_errors(keys):
    assert wrong(X.alternating(keys, ["k"], "y", max_layers=3), keys)[0] == 0
    assert wrong(X.alternating(keys, ["k"], "y", max_layers=2), keys)[1] == 0


def test_space_near_plan(keys):
    h = X.staged(keys, ["k"], "y")
    assert h.bits() / h.n == pytest.approx(1.23 * (3 + 1 + 8 / 8), rel=0.12)
    assert h.bits() < X.single(keys, ["k"], "y", "retrieval").bits()


def test_saved_filters_answer_alike(spark, keys, tmp_path):
    X.save(X.staged(keys, ["k"], "y"), str(tmp_path / "f"))
    assert wrong(X.load(spark, str(tmp_path / "f")), keys) == (0, 0)


def test_edge_cases(spark):
    schema = "k long, y boolean"
    assert X.staged(spark.createDataFrame([], schema), ["k"], "y").probe(spark.createDataFrame([(1, True)], schema), ["k"]).first()["hit"] is False
    every = spark.createDataFrame([(i, True) for i in range(50)], schema)
    assert wrong(X.staged(every, ["k"], "y"), every) == (0, 0)
    none = spark.createDataFrame([(i, False) for i in range(50)], schema)
    assert wrong(X.staged(none, ["k"], "y"), none)[1] == 0
    both = spark.createDataFrame([(1, True), (1, False), (2, False), (2, False), (None, True), (3, None)], schema)
    got = {r["k"]: r["hit"] for r in X.staged(both, ["k"], "y").probe(both, ["k"]).collect()}
    assert got == {1: True, 2: False, None: False, 3: False}


@pytest.mark.parametrize("expr", ["cast(id as string)", "named_struct('a', id, 'b', 'x')", "map('a', id)", "cast(id as decimal(20,3))", "timestamp_seconds(id)", "date_add(date'2000-01-01', cast(id as int))", "concat('\U0001f600', id)"])
def test_keys_of_any_type(spark, expr):
    df = spark.range(400).selectExpr(f"{expr} as k", "id % 5 = 0 as y")
    assert wrong(X.staged(df, ["k"], "y"), df) == (0, 0)


def test_updates_touch_their_segments_only(spark, keys):
    h = X.staged(keys, ["k"], "y", first="bloom", second="edge_map", segment_keys=500)
    fresh = spark.createDataFrame([(10**12 + i,) for i in range(5)], "k long")
    later = h.updated(include=fresh)
    assert later.probe(fresh, ["k"]).where("not hit").count() == 0
    assert wrong(later, keys) == (0, 0)
    kept = h.segments.select("seg", F.xxhash64("stages").alias("a")).join(later.segments.select("seg", F.xxhash64("stages").alias("b")), "seg").where("a = b").count()
    assert kept >= h.parts - 5


def test_probe_needs_no_python(keys):
    plan = X.staged(keys, ["k"], "y").probe(keys, ["k"])._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Python" not in plan and "Arrow" not in plan


def test_native_bloom_agrees_with_itself(spark, keys):
    pos = keys.where("y").select("k")
    words = N.bloom_union(N.bloom_words(pos, "k", 1 << 13, 4), N.bloom_words(pos.limit(0), "k", 1 << 13, 4))
    hits = N.bloom_hits(keys, "k", words, 1 << 13, 4)
    assert hits.where("y and not hit").count() == 0
    assert hits.where("not y and hit").count() < 600


def test_relational_peel_agrees_with_arrays(spark):
    df = spark.range(300).withColumnRenamed("id", "k")
    got = N.peel_relational(df, "k", 450)
    assert got.count() == got.select("slot").distinct().count() == 300


def test_code_of_three_symbols(spark):
    df = spark.createDataFrame([("a",)] * 5 + [("b",)] * 2 + [("c",)], "s string")
    code = A.huffman_code(df, "s")
    assert code == {"a": "0", "b": "10", "c": "11"}


def test_rare_symbol_is_cheap(spark):
    df = spark.range(1024).select(F.col("id").alias("i"), F.when(F.col("id") == 500, "rare").otherwise("usual").alias("s"))
    store = A.huffman_store(df, "i", "s")
    assert store.handle.bits() < 1024 / 4
    assert store.get(spark.createDataFrame([(500,), (501,)], "i long"), "i").orderBy("i").collect()[0]["symbol"] == "rare"


def test_training_reduces_errors(spark):
    placed = A.two_table_build(spark.range(4000).withColumnRenamed("id", "k"), "k", 0.4)
    handle, errors = A.adaptive_train(placed)
    wrong_ = [r["wrong"] for r in errors.orderBy("round").collect()]
    seen = handle.confusion().first()
    assert seen["fn"] + seen["fp"] == wrong_[-1]
    assert wrong_[-1] < wrong_[0] / 5
    assert A.predictor(placed).confusion().first()["error_rate"] == 0
    moved = A.locking_predictor(placed).agg(F.sum("moved")).first()[0]
    assert moved >= 0


def test_runs(spark):
    df = spark.range(700).select(F.col("id").alias("t"), (F.col("id") % 100).alias("k"))
    runs = A.cut_runs(df, 7, ["t"])
    assert runs.select("run").distinct().count() == 7
    got = A.runs_get(runs, "k", df, A.runs_filters(runs, "k")).agg(F.max("reads"), F.max("wasted"), F.min("found_run")).first()
    assert tuple(got) == (1, 0, 7)
    blind = A.runs_get(runs, "k", spark.createDataFrame([(-5,)], "k long"), None).first()
    assert blind["reads"] == 7 and blind["wasted"] == 7


def test_text_features_see_whole_texts(spark):
    long = "word " * 1000
    got = A.text_features(spark.createDataFrame([(long + "apples",), (long + "pears",), (None,)], "text string")).collect()
    assert got[0]["features"] != got[1]["features"] and got[2]["features"].numNonzeros() <= 1


def test_plans_count_distinct_keys(spark):
    """Repeats of the positives do not swap the roles or cost a bit."""
    df = spark.range(2000).select(F.col("id").alias("k"), (F.col("id") % 9 == 0).alias("y"))
    repeated = df.where("y").select("k", "y", F.explode(F.sequence(F.lit(1), F.lit(40)))).drop("col").unionByName(df)
    once, often = X.staged(df, ["k"], "y"), X.staged(repeated, ["k"], "y")
    assert once.bits() == often.bits() and not often.spec.negate


def test_columns_of_any_name_are_kept(spark, keys):
    h = X.staged(keys, ["k"], "y", segment_keys=2500)
    df = keys.select("k", "y", *[F.lit(c).alias(c) for c in ("__k", "__s", "__seg", "__f", "__row", "__0_words", "a.b")], F.create_map(F.lit(1), "k").alias("m"))
    for strategy in ("broadcast", "shuffle"):
        got = h.probe(df, ["k"], strategy=strategy)
        assert got.columns == [*df.columns, "hit"] and got.where("hit <> y or `a.b` <> 'a.b' or __seg <> '__seg'").count() == 0
    with pytest.raises(ValueError, match="hit"):
        h.probe(df.withColumn("hit", F.lit(1)), ["k"])


@pytest.mark.parametrize(("layout", "j"), [("uniform", 4), ("coupled", 3), ("coupled", 4)])
def test_compact_tables(spark, layout, j):
    df = spark.range(40_000).select(F.xxhash64("id").alias("k"), (F.col("id") % 5 == 0).alias("y"))
    h = X.staged(df, ["k"], "y", layout=layout, j=j, compact=True)
    assert h.parts == 1 and wrong(h, df) == (0, 0)


@pytest.mark.parametrize("share", [2, 3, 9, 40])
def test_shared_blocks(spark, share):
    df = spark.range(6000).select((F.col("id") * 31 - 7).alias("k"), (F.col("id") % share == 0).alias("y"))
    h = X.shared(df, ["k"], "y", segment_keys=2500)
    assert wrong(h, df) == (0, 0)
    assert wrong(X.shared(df.withColumn("y", ~F.col("y")), ["k"], "y"), df.withColumn("y", ~F.col("y"))) == (0, 0)


def test_generated_code_is_small_enough_to_be_compiled(spark, keys):
    """The virtual machine interprets methods of more than 8,000 bytes."""
    tool = getattr(getattr(spark._jvm.org.apache.spark.sql.execution.debug, "package$"), "MODULE$")
    for h in (X.staged(keys, ["k"], "y"), X.staged(keys, ["k"], "y", layout="coupled", j=4), X.shared(keys, ["k"], "y"), X.alternating(keys, ["k"], "y", tail="retrieval", max_layers=4), X.single(keys, ["k"], "y", "bloom", 0.01), X.single(keys, ["k"], "y", "cuckoo", 0.01)):
        df = h.probe(keys, ["k"]).groupBy().agg(F.count("hit"))
        df.collect()
        sizes = [int(x) for x in re.findall(r"maxMethodCodeSize:(\d+)", tool.codegenString(df._jdf.queryExecution().executedPlan()))]
        assert sizes and max(sizes) < 8000


def test_cascades_deeper_than_written_out(keys):
    h = X.alternating(keys, ["k"], "y")
    assert h.layers > X.UNROLLED and wrong(h, keys) == (0, 0)
    assert h.probe_depth(keys, ["k"]).agg(F.max("depth")).first()[0] <= h.layers


def test_online_filters_learn(spark, keys):
    early, late = keys.where("k % 2 = 0"), keys.where("k % 2 <> 0")
    h = O.online(early, ["k"], "y", segment_keys=700)
    assert wrong(h, early) == (0, 0)
    more = h.include(late.where("y"), ["k"])
    assert wrong(more, keys.where("y"))[0] == 0
    more = more.exclude(keys.where("not y"), ["k"])
    assert wrong(more, keys) == (0, 0)
    again = more.exclude(keys.where("not y"), ["k"]).include(keys.where("y"), ["k"])  # nothing new
    assert wrong(again, keys) == (0, 0) and again.bits() == more.bits()
    one = h.exclude(spark.createDataFrame([(10**12,)], "k long"), ["k"])
    same = one.handle.segments.select("seg", F.xxhash64("stages").alias("a")).join(h.handle.segments.select("seg", F.xxhash64("stages").alias("b")), "seg").where("a = b").count()
    assert same >= h.handle.parts - 1
    fresh = O.online(spark.createDataFrame([], "k long, y boolean"), ["k"], "y").include(keys.where("y"), ["k"])
    assert wrong(fresh, keys.where("y")) == (0, 0)


def test_store_reads_what_it_stored(spark):
    rows = spark.range(3000).select(F.concat(F.lit("key-"), "id").alias("key"), F.concat(F.lit("value-"), F.col("id") * 7).alias("value"))
    placed = A.two_table_build(rows, "key", 0.4, segment_keys=1000)
    parts = placed.agg(F.max("seg")).first()[0] + 1
    store = A.two_table_store(rows, "key", "value", placed, parts)
    asked = rows.select("key").union(spark.createDataFrame([("nothing",)], "key string"))
    got = {r["key"]: (r["value"], r["reads"]) for r in store.get(asked, "key", A.predictor(placed)).collect()}
    assert len(got) == 3001 and got["nothing"] == (None, 2)
    assert all(v == (f"value-{int(k[4:]) * 7}", 1) for k, v in got.items() if k != "nothing")


def test_runs_know_of_later_runs(spark):
    df = spark.range(900).select(F.col("id").alias("t"), (F.col("id") % 300).alias("k"), F.col("id").alias("one"))
    runs = A.cut_runs(df, 9, ["t"])
    f = A.runs_filters(runs, "k", scope="later")
    got = A.runs_get(runs, "k", df, f, "oldest").agg(F.min("found_run"), F.max("found_run"), F.max("wasted")).first()
    assert got[0] >= 7 and got[1] == 9 and got[2] <= 1
    single = A.runs_get(runs, "one", df, A.runs_filters(runs, "one", scope="later"), "first").agg(F.max("reads"), F.max("wasted")).first()
    assert tuple(single) == (1, 0)


def test_levels_by_threshold(spark):
    runs = spark.range(140).select((F.col("id") % 14 + 1).cast("int").alias("run"), F.col("id").alias("k"))
    tiers = A.runs_levels(runs, "k", 3).groupBy("run").agg(F.max("level").alias("l"), F.max("tier").alias("t")).orderBy("run").collect()
    assert [(r["l"], r["t"]) for r in tiers] == [(2, 1)] * 9 + [(1, 2)] * 3 + [(0, 3), (0, 4)]


def test_written_folders_can_be_deleted(spark, keys):
    from pathlib import Path

    from stagewise.plans import storage

    h = X.single(keys, ["k"], "y", "bloom", 0.1)
    folder = Path(storage._WRITTEN[-1].removeprefix("file:"))
    assert h.bits() > 0 and folder.exists()
    assert storage.forget(spark) > 0 and not folder.exists() and not storage._WRITTEN


def test_bits_of_a_segment_hold_their_rate(spark):
    """More positives than the bits of one segment are enough for: the rate stays, in more segments."""
    df = spark.range(30_000).select("id", (F.col("id") % 5 == 0).alias("y"))
    r = X.single(df, ["id"], "y", "bloom", 0.05, {"bits": 20_000}).confusion().first()
    assert r["fn"] == 0 and r["fpr"] < 0.08
