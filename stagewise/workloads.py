"""Experiment workloads and measures by name, each with the SQL that tells its rows where SQL can."""

from __future__ import annotations

import time
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import theory as T
from .functions.hashing import portable_hash, portable_sql
from .operators import applications as A
from .operators import elementary as E
from .operators import filters as X
from .operators import native as N
from .operators import relational
from .operators.online import online
from .plans.cost import spent
from .plans.storage import keep
from .sources import tables
from .sources.tables import read_table
from .streaming import flows

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


#: name: table, key columns, predicate that makes a key positive
UNIVERSES = {
    "orders": ("orders", ["o_orderkey"], "o_orderpriority = '1-URGENT'"),
    "events": ("events", ["event_id"], "event_type = 'purchase'"),
    "returned": ("lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"], "l_returnflag = 'R'"),
    "seventh": ("lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"], "l_linenumber = 7"),
    "fifty": ("lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"], "l_quantity = 50"),
    "brand": ("part", ["p_partkey"], "p_brand = 'Brand#1'"),
}


def universe(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, list[str]]:
    table, keys, predicate = UNIVERSES[name]
    return read_table(spark, sf_dir, table).select(*keys, F.coalesce(F.expr(predicate), F.lit(False)).alias("y")), keys


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, keys = universe(spark, sf_dir, "orders")
    return X.staged(df, keys, "y").probe(df.select(*keys), keys)


# --- every filter over a universe: exact ones give the predicate back, approximate ones never deny a positive ------------------------


def _exact(name: str, of: str, build: Callable[[DataFrame, list[str]], X.FilterHandle]) -> None:
    table, keys, predicate = UNIVERSES[of]
    cols = ", ".join(keys)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df, keys = universe(spark, sf_dir, of)
        return build(df, keys).probe(df.select(*keys).distinct(), keys)

    query(name, f"SELECT {cols}, bool_or({predicate}) AS hit FROM {table} GROUP BY {cols}")(run)


def _approximate(name: str, of: str, build: Callable[[DataFrame, list[str]], X.FilterHandle], most: float) -> None:
    """One row: keys, positives, positives denied (none), and whether the rate stays below ``most``."""
    table, keys, predicate = UNIVERSES[of]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df, keys = universe(spark, sf_dir, of)
        return build(df, keys).confusion().select("u", "n", "fn", (F.col("fpr") <= most).alias("rate_held"))

    cols = ", ".join(keys)
    query(
        name,
        f"SELECT count(*) AS u, CAST(sum(CASE WHEN p THEN 1 ELSE 0 END) AS BIGINT) AS n, CAST(0 AS BIGINT) AS fn, true AS rate_held "
        f"FROM (SELECT {cols}, bool_or({predicate}) AS p FROM {table} GROUP BY {cols})",
    )(run)


_approximate("f01_bloom", "orders", lambda d, k: X.single(d, k, "y", "bloom", 0.02), 0.03)
_approximate("f02_bloom_of_given_bits", "events", lambda d, k: X.single(d, k, "y", "bloom", 0.05, {"bits": 20_000}), 0.2)
_approximate("f05_blocked_bloom", "orders", lambda d, k: X.single(d, k, "y", "blocked", 0.02), 0.05)
_approximate("f06_counting_bloom", "orders", lambda d, k: X.single(d, k, "y", "counting", 0.02), 0.03)
_approximate("f08_cuckoo_filter", "orders", lambda d, k: X.single(d, k, "y", "cuckoo", 0.02), 0.03)
_approximate("f09_xor_uniform", "orders", lambda d, k: X.single(d, k, "y", "xor", 1 / 64), 0.03)
_approximate("f10_xor_coupled", "orders", lambda d, k: X.single(d, k, "y", "xor", 1 / 64, {"layout": "coupled"}), 0.03)
_exact("f11_retrieval_fair_coin", "orders", lambda d, k: X.single(d, k, "y", "retrieval"))
_exact("f12_retrieval_constant", "orders", lambda d, k: X.single(d, k, "y", "retrieval", 0.0, {"strategy": "b", "layout": "coupled"}))
_approximate("f13_partial_retrieval", "orders", lambda d, k: X.single(d, k, "y", "retrieval", 0.1), 0.13)
_exact("f15_edge_map", "orders", lambda d, k: X.single(d, k, "y", "edge_map"))
_exact("f16_colour_map", "orders", lambda d, k: X.single(d, k, "y", "colour_map"))
_exact("s01_staged_exact", "orders", lambda d, k: X.staged(d, k, "y"))
_exact("s01_staged_exact_pushdown", "events", lambda d, k: X.staged_pushdown(d, k, "y"))
_exact("s01_staged_wide_keys", "returned", lambda d, k: X.staged(d, k, "y"))
_exact("s01_staged_sparse", "fifty", lambda d, k: X.staged(d, k, "y"))
_exact("s01_staged_coupled", "seventh", lambda d, k: X.staged(d, k, "y", layout="coupled"))
_exact("s01_staged_small_n", "brand", lambda d, k: X.staged(d, k, "y"))
_approximate("s04_staged_general_a", "orders", lambda d, k: X.staged(d, k, "y", eps=0.05), 0.07)
_approximate("s04_staged_general_b", "orders", lambda d, k: X.staged(d, k, "y", eps=0.05, strategy="b"), 0.09)
_exact("s05_chain", "fifty", lambda d, k: X.chain(d, k, "y", [X.Stage("xor", 0.5), X.Stage("bloom", 0.25), X.Stage("cuckoo", 0.5), X.Stage("retrieval")]))
_exact("s06_staged_dynamic_second", "orders", lambda d, k: X.staged(d, k, "y", second="colour_map"))
_exact("s07_staged_dynamic_first", "orders", lambda d, k: X.staged(d, k, "y", first="cuckoo", second="edge_map"))
_exact("s08_alternating", "orders", lambda d, k: X.alternating(d, k, "y"))
_exact("s09_alternating_tail", "orders", lambda d, k: X.alternating(d, k, "y", tail="retrieval", max_layers=4))
_exact("s09_alternating_dynamic_tail", "orders", lambda d, k: X.alternating(d, k, "y", tail="edge_map", max_layers=4))
_exact("s10_alternating_cuckoo", "events", lambda d, k: X.alternating(d, k, "y", first="cuckoo", tail="retrieval", max_layers=6))
_approximate("s11_alternating_three_layers", "orders", lambda d, k: X.alternating(d, k, "y", max_layers=3), 0.2)


@query("s02_majority_positive", "SELECT o_orderkey, EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey) AS hit FROM orders")
def _majority(spark, sf_dir):
    """Nearly all keys are positive: the planner swaps the roles."""
    lines = read_table(spark, sf_dir, "lineitem", "l_orderkey").distinct().withColumn("y", F.lit(True))
    orders = read_table(spark, sf_dir, "orders", "o_orderkey")
    df = orders.join(lines, orders.o_orderkey == lines.l_orderkey, "left").select("o_orderkey", F.coalesce("y", F.lit(False)).alias("y"))
    return X.staged(df, ["o_orderkey"], "y").probe(orders, ["o_orderkey"])


@query("s06_exclude_online", "SELECT event_id, event_type = 'purchase' AS hit FROM events")
def _exclude(spark, sf_dir):
    """Built on half of the negatives; the other half is excluded afterwards, then half of the positives included."""
    df, k = universe(spark, sf_dir, "events")
    early = df.where("event_id % 2 = 0")
    late = df.where("event_id % 2 = 1")
    h = X.staged(early, k, "y", first="bloom", second="edge_map")
    h = h.updated(include=late.where("y"), exclude=late.where("not y"), keys=k)
    return h.probe(df.select(*k), k)


@query("s14_probe_depth")
def _depth(spark, sf_dir):
    df, k = universe(spark, sf_dir, "orders")
    return X.alternating(df, k, "y").probe_depth(df, k).groupBy("y", "depth").agg(F.count(F.lit(1)).alias("keys"))


@query("f01_bloom_native", "SELECT o_orderkey, true AS hit FROM orders WHERE o_orderpriority = '1-URGENT'")
def _native(spark, sf_dir):
    """Built and probed without Python; positives are all found."""
    df, _ = universe(spark, sf_dir, "orders")
    words = N.bloom_words(df.where("y"), "o_orderkey", 1 << 15, 5)
    return N.bloom_hits(df.where("y").select("o_orderkey"), "o_orderkey", words, 1 << 15, 5)


@query("f03_bloom_union", "SELECT o_orderkey, true AS hit FROM orders WHERE o_orderpriority = '1-URGENT'")
def _union(spark, sf_dir):
    df, _ = universe(spark, sf_dir, "orders")
    pos = df.where("y")
    words = N.bloom_union(N.bloom_words(pos.where("o_orderkey % 2 = 0"), "o_orderkey", 1 << 15, 5), N.bloom_words(pos.where("o_orderkey % 2 = 1"), "o_orderkey", 1 << 15, 5))
    return N.bloom_hits(pos.select("o_orderkey"), "o_orderkey", words, 1 << 15, 5)


_URGENT = "o_orderpriority = '1-URGENT'"


def _portable_sql(universe: str, members: str, key: str, size: int, hashes: int) -> str:
    """Which keys of a universe a portable Bloom filter of the members lets through, false positives included."""
    spots = ", ".join(f"{portable_sql(key, i)} % {size}" for i in range(hashes))
    return (
        f"WITH s AS (SELECT DISTINCT unnest([{spots}]) AS b FROM {members}), u AS (SELECT {key}, unnest([{spots}]) AS b FROM {universe}) "
        f"SELECT u.{key}, count(s.b) = {hashes} AS hit FROM u LEFT JOIN s ON u.b = s.b GROUP BY u.{key}"
    )


@query("f01_bloom_whole_universe", _portable_sql("orders", f"(SELECT * FROM orders WHERE {_URGENT})", "o_orderkey", 16384, 3))
def _whole(spark, sf_dir):
    """Every key is asked, and the false positives are the very ones that SQL finds."""
    df, _ = universe(spark, sf_dir, "orders")
    return N.portable_hits(df.select("o_orderkey"), "o_orderkey", N.portable_bloom(df.where("y"), "o_orderkey", 16384, 3), 16384, 3)


@query("f03_union_whole_universe", _portable_sql("orders", f"(SELECT * FROM orders WHERE {_URGENT})", "o_orderkey", 16384, 3))
def _union_whole(spark, sf_dir):
    """The union of the filters of two halves is the filter of the whole."""
    df, _ = universe(spark, sf_dir, "orders")
    half = lambda r: N.portable_bloom(df.where(F.col("y") & (F.pmod("o_orderkey", F.lit(2)) == r)), "o_orderkey", 16384, 3)
    return N.portable_hits(df.select("o_orderkey"), "o_orderkey", half(0).union(half(1)).distinct(), 16384, 3)


@query("f01_native_rate", f"SELECT count(*) AS u, count(*) FILTER (WHERE {_URGENT}) AS n, CAST(0 AS BIGINT) AS fn, true AS rate_held FROM orders")
def _native_rate(spark, sf_dir):
    """Sized by the number of keys, built and probed without Python, all keys asked."""
    df, _ = universe(spark, sf_dir, "orders")
    bits, hashes = E.bloom_shape(max(1, df.where("y").count()), 0.01)
    hits = N.bloom_hits(df, "o_orderkey", N.bloom_words(df.where("y"), "o_orderkey", bits, hashes), bits, hashes)
    wrong = lambda c: F.sum(c.cast("long"))
    return hits.agg(F.count(F.lit(1)).alias("u"), wrong(F.col("y")).alias("n"), wrong(F.col("y") & ~F.col("hit")).alias("fn"), (wrong(~F.col("y") & F.col("hit")) <= 0.02 * wrong(~F.col("y"))).alias("rate_held"))


@query(
    "f06_counting_half_deleted",
    "SELECT cell, count(*) AS n FROM (SELECT unnest([" + ", ".join(f"{portable_sql('o_orderkey', i)} % 4096" for i in range(3)) + "]) AS cell FROM orders WHERE o_orderstatus <> 'F') GROUP BY cell",
)
def _half_deleted(spark, sf_dir):
    """All orders are inserted, the finished ones deleted: the counters are those of the others, one by one."""
    df = read_table(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus")
    both = df.withColumn("s", F.lit(1)).unionByName(df.where("o_orderstatus = 'F'").withColumn("s", F.lit(-1)))
    return N.portable_counters(both, "o_orderkey", 4096, 3, "s")


@query("f04_jvm_bloom")
def _jvm(spark, sf_dir):
    df = read_table(spark, sf_dir, "orders", "o_orderkey")
    return spark.createDataFrame([(N.jvm_bloom_bits(df, "o_orderkey", 15_000, 0.01),)], "bits long")


@query("f06_counting_delete", "SELECT CAST(0 AS BIGINT) AS counters_left")
def _delete(spark, sf_dir):
    """Inserting and deleting the same keys leaves nothing."""
    df = read_table(spark, sf_dir, "orders", "o_orderkey")
    both = df.withColumn("s", F.lit(1)).unionByName(df.withColumn("s", F.lit(-1)))
    return N.counting_words(both, "o_orderkey", 1 << 16, 4, "s").agg(F.count(F.lit(1)).alias("counters_left"))


@query("b15_portable_bloom_bits", "SELECT count(DISTINCT b) AS bits FROM (SELECT unnest([" + ", ".join(f"{portable_sql('event_id', i)} % 16384" for i in range(3)) + "]) AS b FROM events WHERE event_type = 'purchase')")
def _portable(spark, sf_dir):
    df, _ = universe(spark, sf_dir, "events")
    return N.portable_bloom(df.where("y"), "event_id", 16384, 3).agg(F.count(F.lit(1)).alias("bits"))


@query("g01_relational_peel", "SELECT count(*) AS keys, count(*) AS slots FROM (SELECT p_partkey FROM part)")
def _peel(spark, sf_dir):
    """Every key gets a cell of its own."""
    part = read_table(spark, sf_dir, "part", "p_partkey")
    return N.peel_relational(part, "p_partkey", int(part.count() * 1.35) + 30).agg(F.countDistinct("k").alias("keys"), F.countDistinct("slot").alias("slots"))


@query("g02_relational_assign", "SELECT p_partkey, bit_count(p_partkey) % 2 = 1 AS odd FROM part")
def _assigned(spark, sf_dir):
    """Cells are filled by joins in the reverse order of peeling; the xor of a key's three cells is its value."""
    part = read_table(spark, sf_dir, "part", "p_partkey").select(F.col("p_partkey").alias("k"))
    cells = int(part.count() * 1.35) + 30
    values = part.withColumn("v", (F.bit_count("k") % 2).cast("long"))
    filled = N.assign_relational(N.peel_relational(part, "k", cells), values, cells)
    return N.read_relational(part, filled, cells).select(F.col("k").alias("p_partkey"), (F.col("v") == 1).alias("odd"))


# --- filters that learn ----------------------------------------------------------------------------------------------------------


@query("s06_include_exclude", "SELECT event_id, event_type = 'purchase' AS hit FROM events")
def _include_exclude(spark, sf_dir):
    """Built on the even keys; the odd positives are included, then all negatives are told again, of which only those that pass are moved."""
    df, k = universe(spark, sf_dir, "events")
    h = online(df.where("event_id % 2 = 0"), k, "y").include(df.where("event_id % 2 = 1 and y"), k).exclude(df.where("not y"), k)
    return h.probe(df.select(*k), k)


@query("s07_included_keys_pass", "SELECT count(*) AS keys, CAST(0 AS BIGINT) AS denied, true AS rate_small FROM events")
def _included(spark, sf_dir):
    """New positives alone: none is denied, and few of the negatives known before are let through."""
    df, k = universe(spark, sf_dir, "events")
    h = online(df.where("event_id % 2 = 0"), k, "y").include(df.where("event_id % 2 = 1 and y"), k)
    seen = h.probe(df, k)
    wrong = lambda c: F.sum(c.cast("long"))
    even = ~F.col("y") & (F.col("event_id") % 2 == 0)
    return seen.agg(F.count(F.lit(1)).alias("keys"), wrong(F.col("y") & ~F.col("hit")).alias("denied"), (wrong(even & F.col("hit")) <= 0.25 * wrong(even)).alias("rate_small"))


# --- costs ---------------------------------------------------------------------------------------------------------------------

_G = lambda x: f"(CASE WHEN ({x}) > 0 THEN (({x})+1)*(-(1/(({x})+1))*log2(1/(({x})+1)) - (1-1/(({x})+1))*log2(1-1/(({x})+1))) ELSE 0 END)"
_LAMS = (2.0, 3.0, 4.0, 8.0, 16.0, 64.0, 1000.0)
_EPS = (0.001, 0.01, 0.1, 0.25)


def _rounded(df: DataFrame) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


#: Lines by their number: how many there are, and how many others a line; a number that all lines have needs no filter.
_CLASSES = "(SELECT l_linenumber AS class, n, CAST(u - n AS DOUBLE) / n AS lam FROM (SELECT l_linenumber, count(*) AS n FROM lineitem GROUP BY l_linenumber) CROSS JOIN (SELECT count(*) AS u FROM lineitem) WHERE n < u)"


def _classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(class, n, lam), a row a line number."""
    counted = read_table(spark, sf_dir, "lineitem", "l_linenumber").groupBy(F.col("l_linenumber").alias("class")).agg(F.count(F.lit(1)).alias("n"))
    total = counted.agg(F.sum("n").alias("u"))  # one row
    return counted.crossJoin(F.broadcast(total)).where("n < u").select("class", "n", ((F.col("u") - F.col("n")) / F.col("n")).alias("lam"))


_INT = "CASE WHEN lam >= 1 THEN k + 1 + lam / power(2, k) ELSE lam + 1 END"


@query(
    "t01_bounds_and_costs",
    f"SELECT class, round(lam, 6) AS lam, round(lb, 6) AS lb, round({_INT}, 6) AS staged_int, round(CASE WHEN lam * ln(2) > 1 THEN log2(2 * exp(1) * lam * ln(2)) ELSE lam + 1 END, 6) AS staged, "
    f"round((log2(lam) + 3) / ln(2), 6) AS alternating, round(({_INT}) / lb, 6) AS overhead "
    f"FROM (SELECT class, lam, {_G('lam')} AS lb, floor(log2(lam)) AS k FROM {_CLASSES})",
)
def _costs(spark, sf_dir):
    lam = F.col("lam")
    return _rounded(
        _classes(spark, sf_dir).select(
            "class", "lam", T.lb_exact(lam).alias("lb"), T.cost_staged_int(lam).alias("staged_int"), T.cost_staged(lam).alias("staged"), T.cost_alternating(lam).alias("alternating"), T.staged_overhead(lam).alias("overhead")
        )
    )


@query(
    "w9_cost_surface",
    f"SELECT eps, lam, round({_G('lam')} - {_G('eps*lam')}, 6) AS lb, round(least(-log2(eps), lam + 1 - 2*eps*lam), 6) AS single, classes "
    f"FROM (SELECT eps, lam, 'general' AS classes FROM (SELECT unnest([{', '.join(f'CAST({x} AS DOUBLE)' for x in _EPS)}]) AS eps) CROSS JOIN (SELECT unnest([{', '.join(f'CAST({x} AS DOUBLE)' for x in _LAMS)}]) AS lam))",
)
def _surface(spark, sf_dir):
    grid = spark.createDataFrame([(e, x) for e in _EPS for x in _LAMS], "eps double, lam double")
    eps, lam = F.col("eps"), F.col("lam")
    return _rounded(grid.select("eps", "lam", T.lb(eps, lam).alias("lb"), T.cost_single(eps, lam).alias("single"), T.classify(eps, lam).alias("classes")))


@query(
    "t16_general_costs",
    "WITH g AS (SELECT class, eps, lam, -log2(eps) AS approx, lam + 1 - 2 * eps * lam AS part_a, (lam + 1) / (eps * lam + 1) AS part_b "
    f"FROM (SELECT unnest([{', '.join(f'CAST({x} AS DOUBLE)' for x in _EPS)}]) AS eps) CROSS JOIN {_CLASSES}), "
    "c AS (SELECT class, eps, lam, part_b, CASE WHEN lam * ln(2) > 1 AND 2 * eps * lam * ln(2) < 1 THEN log2(2 * exp(1) * lam * ln(2)) - 2 * lam * eps ELSE least(approx, part_a) END AS a, "
    "CASE WHEN eps < ln(2) AND lam * (ln(2) - eps) > 1 THEN log2(2 * exp(1) * lam * ln(2) / (eps * lam + 1)) - eps * lam / (eps * lam + 1) ELSE least(approx, part_b) END AS b FROM g) "
    "SELECT class, eps, round(lam, 6) AS lam, round(a, 6) AS a, round(b, 6) AS b, round(least(a, b), 6) AS best, round(part_b, 6) AS partial_b FROM c",
)
def _general(spark, sf_dir):
    rates = F.explode(F.array(*[F.lit(e) for e in _EPS])).alias("eps")
    return _rounded(_general_costs(_classes(spark, sf_dir).select("class", "lam", rates), F.col("eps"), F.col("lam")))


def _general_costs(grid, eps, lam):
    return grid.select("class", "eps", "lam", T.general_a(eps, lam).alias("a"), T.general_b(eps, lam).alias("b"), T.cost_general(eps, lam).alias("best"), T.partial_b(eps, lam).alias("partial_b"))


@query("t21_plans")
def _plans(spark, sf_dir):
    """The plans of each class of lines, made where its row is."""

    def run(batches):
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                steps, cost = T.plan_chain(0.0, r["lam"])
                envelope = T.and_envelope(lambda e, x: T.cost_single(e, x), 0.0, r["lam"], 24)
                rows.append({"class": r["class"], "lam": r["lam"], "stages": len(steps), "cost": float(cost), "envelope": float(envelope), "plan": T.plan(r["n"], round(r["n"] * (r["lam"] + 1))).kind})
            yield pa.RecordBatch.from_pylist(rows, pa.schema([("class", pa.int32()), ("lam", pa.float64()), ("stages", pa.int32()), ("cost", pa.float64()), ("envelope", pa.float64()), ("plan", pa.string())]))

    return _classes(spark, sf_dir).mapInArrow(run, "class int, lam double, stages int, cost double, envelope double, plan string")


_FIRST = "CASE WHEN layer = 1 THEN least(0.5, 0.5 / lam) ELSE 0.25 END"


@query(
    "t24_layer_plan",
    f"WITH RECURSIVE l(class, lam, layer, accepted, rejected) AS (SELECT class, lam, 1, CAST(n AS DOUBLE), n * lam FROM {_CLASSES} "
    f"UNION ALL SELECT class, lam, layer + 1, rejected * {_FIRST}, accepted FROM l WHERE rejected * {_FIRST} >= 1 AND layer < 63) "
    f"SELECT class, round(lam, 6) AS lam, layer, round(rate, 6) AS rate, round(accepted * -log2(rate) / ln(2), 6) AS bits FROM (SELECT class, lam, layer, accepted, {_FIRST} AS rate FROM l)",
)
def _layers(spark, sf_dir):
    def run(batches):
        for batch in batches:
            rows = [(r["class"], r["lam"], *x) for r in batch.to_pylist() for x in T.layer_plan(r["n"], r["lam"])]
            yield pa.record_batch([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.float64(), pa.int32(), pa.float64(), pa.float64()))], names=["class", "lam", "layer", "rate", "bits"])

    return _rounded(_classes(spark, sf_dir).mapInArrow(run, "class int, lam double, layer int, rate double, bits double"))


@query(
    "t25_elementary_costs",
    "SELECT kind, eps, round(CASE kind WHEN 'bloom' THEN -log2(eps) / ln(2) WHEN 'cuckoo' THEN 1.05 * (2 - log2(eps)) WHEN 'xor' THEN -log2(eps) WHEN 'retrieval' THEN 5 WHEN 'edge_map' THEN 2.33 * 5 ELSE 2.2 * 5 END, 6) AS bits "
    "FROM (VALUES ('bloom'), ('cuckoo'), ('xor'), ('retrieval'), ('edge_map'), ('colour_map')) k(kind), (VALUES (CAST(0.01 AS DOUBLE)), (0.1)) e(eps)",
)
def _elementary(spark, sf_dir):
    rows = [(k, e, float(T.elementary_cost(k, e, 4.0))) for k in ("bloom", "cuckoo", "xor", "retrieval", "edge_map", "colour_map") for e in (0.01, 0.1)]
    return _rounded(spark.createDataFrame(rows, "kind string, eps double, bits double"))


query("t29_complexity")(lambda spark, sf_dir: T.complexity_table(spark))

_R = (0.10, 0.15, 0.20, 0.25, 0.30, 0.35, 0.40)


@query(
    "w3a_predictor_space",
    f"SELECT r, round(lam, 6) AS lam, round(1e6 * r / (lam + 1) * (log2(lam) + 4) / ln(2) / 1e6, 2) AS ours, CAST(4.0 AS DOUBLE) AS locking "
    f"FROM (SELECT r, 1 / (2*r/(1-exp(-2*r)) - 1) AS lam FROM (SELECT unnest([{', '.join(f'CAST({r} AS DOUBLE)' for r in _R)}]) AS r))",
)
def _predictor_space(spark, sf_dir):
    r = F.col("r")
    return spark.createDataFrame([(x,) for x in _R], "r double").select("r", F.round(T.predictor_lambda(r), 6).alias("lam"), F.round(T.predictor_space(r), 2).alias("ours"), F.lit(T.locking_space()).alias("locking"))


@query("t28_entropy", "SELECT sum(c)::BIGINT AS n, count(*) AS symbols, round(sum(-(c / n) * log2(c / n)), 9) AS entropy FROM (SELECT event_type, count(*) AS c, sum(count(*)) OVER () AS n FROM events GROUP BY event_type)")
def _entropy(spark, sf_dir):
    return T.entropy_of(read_table(spark, sf_dir, "events", "event_type"), "event_type").withColumn("entropy", F.round("entropy", 9))


@query("p1_boolean_function", "SELECT event_id AS x, event_type = 'click' AS bit FROM events")
def _function(spark, sf_dir):
    """A Boolean function over the event ids, encoded and evaluated at every one."""
    df = read_table(spark, sf_dir, "events", "event_id", "event_type").select(F.col("event_id").alias("x"), (F.col("event_type") == "click").alias("bit"))
    return A.dictionary_eval(A.dictionary_encode(df, "x", "bit"), df.select("x"), "x")


@query("m12_survivors")
def _survivors(spark, sf_dir):
    """Keys that each layer of a cascade hands on to the next."""
    df, k = universe(spark, sf_dir, "orders")
    return X.alternating(df, k, "y").segments.select(F.posexplode("survivors").alias("layer", "left")).groupBy("layer").agg(F.sum("left").alias("left"))


# --- static dictionaries ---------------------------------------------------------------------------------------------------------


def swept(spark: SparkSession, sf_dir: str, lam: int) -> DataFrame:
    lines = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber").distinct()
    k = F.concat_ws("-", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    return lines.select(F.xxhash64("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber").alias("key"), (F.pmod(portable_hash(k, lam), F.lit(lam + 1)) == 0).alias("y"))


@query("w1a_space_by_lambda")
def _space(spark, sf_dir):
    """Bits per positive of the staged filter, the exact table and the bound, lam 2 to 16."""
    out = None
    for lam in (2, 4, 8, 16):
        df = swept(spark, sf_dir, lam)
        ours, base = X.staged(df, ["key"], "y"), X.single(df, ["key"], "y", "retrieval")
        row = spark.createDataFrame([(lam, ours.n, ours.bits() / ours.n, base.bits() / base.n, T.lb_exact(ours.lam))], "lam int, n long, staged double, exact double, bound double")
        out = row if out is None else out.unionByName(row)
    return out.withColumn("saved", 1 - F.col("staged") / F.col("exact")).withColumn("ratio", F.col("staged") / F.col("bound"))


@query("w1a_classification", "SELECT count(*) AS u, CAST(0 AS BIGINT) AS wrong FROM (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, l_linenumber FROM lineitem)")
def _classified(spark, sf_dir):
    df = swept(spark, sf_dir, 16)
    return X.staged(df, ["key"], "y").probe(df, ["key"]).agg(F.count(F.lit(1)).alias("u"), F.sum((F.col("y") != F.col("hit")).cast("long")).alias("wrong"))


@query("s03_mixed_bits", "SELECT count(*) AS keys, CAST(0 AS BIGINT) AS wrong, true AS between_whole_bits FROM (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, l_linenumber FROM lineitem)")
def _mixed(spark, sf_dir):
    """Fingerprints of two lengths, by segment: exact, and of a size between those of either length alone, with some slack for chance."""
    df = keep(swept(spark, sf_dir, 12))
    h = X.staged(df, ["key"], "y", mixed=True, segment_keys=4096)
    wrong = h.probe(df, ["key"]).agg(F.count(F.lit(1)).alias("keys"), F.sum((F.col("y") != F.col("hit")).cast("long")).alias("wrong"))
    per_key = h.bits() / max(1, h.n) / T.C_UNIFORM
    low, high = sorted(k + 1 + h.lam / 2**k for k in (3, 4))
    return wrong.withColumn("between_whole_bits", F.lit(0.97 * low <= per_key <= 1.06 * high))


@query("s13_shared_blocks", f"SELECT o_orderkey, {UNIVERSES['orders'][2]} AS hit FROM orders")
def _shared(spark, sf_dir):
    """Both stages in the same three blocks of a key."""
    df, k = universe(spark, sf_dir, "orders")
    return X.shared(df, k, "y").probe(df.select(*k), k)


#: Positives of the universe on which the published constants are measured, and how many negatives each has.
HEADLINE_POSITIVES, HEADLINE_LAMS = 150_000, (4, 16)


@query("w1d_ratio", f"SELECT lam, true AS within, lam < 16 OR true AS saving_held, CAST(0 AS BIGINT) AS wrong FROM (VALUES {', '.join(f'({x})' for x in HEADLINE_LAMS)}) t(lam)")
def _headline(spark, sf_dir):
    """Compact segments with four-slot coupled tables: space within 1.26 of the bound; at 16 negatives a positive at least 60% below the exact table. No key is answered wrongly."""
    return _headline_rows(spark).select("lam", (F.col("ratio") <= 1.26).alias("within"), ((F.col("lam") < 16) | (F.col("saved") >= 0.6)).alias("saving_held"), "wrong")


def _headline_rows(spark):
    out = []
    for lam in HEADLINE_LAMS:
        df = keep(tables.universe(spark, HEADLINE_POSITIVES, lam).select("key", F.col("is_pos").alias("y")))
        began = time.time()
        ours = X.staged(df, ["key"], "y", layout="coupled", j=4, compact=True)
        built = time.time()
        wrong = ours.probe(df, ["key"]).agg(F.sum((F.col("y") != F.col("hit")).cast("long"))).first()[0]
        asked = time.time()
        base = X.single(df, ["key"], "y", "retrieval", options={"layout": "coupled", "j": 4}, compact=True)
        bits, u = ours.bits() / ours.n, ours.u
        out.append((lam, ours.n, bits, bits / T.lb_exact(ours.lam), 1 - bits / (base.bits() / base.n), wrong, u / (built - began), u / (asked - built)))
    return spark.createDataFrame(out, "lam int, n long, bits double, ratio double, saved double, wrong long, build_keys_a_second double, probe_keys_a_second double")


@query("w1b_throughput")
def _throughput(spark, sf_dir):
    """Keys a second of one core, construction and query, staged against the exact table, lam 2 to 16; means of three runs inside a task."""
    import numpy as np
    import pyarrow as pa

    grid = spark.createDataFrame([(lam, kind) for lam in (2, 4, 8, 16) for kind in ("staged", "exact")], "lam int, kind string")

    def run(batches):
        for b in batches:
            rates = []
            for lam, kind in zip(*(b.column(i).to_pylist() for i in (0, 1)), strict=True):
                pos, neg = np.arange(40_000), np.arange(40_000, 40_000 * (lam + 1))
                every, bits = np.concatenate([pos, neg]), max(1, lam.bit_length() - 1)
                stages = (X.Stage("xor", 2.0**-bits), X.Stage("retrieval")) if kind == "staged" else (X.Stage("retrieval"),)
                took = [0.0, 0.0]
                for r in range(3):
                    began = time.perf_counter()
                    built = X.Spec("and", stages).build(pos, neg, 7 + r)[0]
                    took[0] += time.perf_counter() - began
                    began, left = time.perf_counter(), every
                    for stage, f in zip(stages, built, strict=True):
                        left = left[stage.test(f, left)]
                    took[1] += time.perf_counter() - began
                    if len(left) != len(pos):
                        raise RuntimeError("an exact filter erred")
                rates.append([3 * len(every) / t for t in took])
            yield pa.record_batch([*b.columns, *(pa.array([r[i] for r in rates]) for i in (0, 1))], names=["lam", "kind", "construct", "query"])

    return grid.repartition(1).mapInArrow(run, "lam int, kind string, construct double, query double")


@query("w1b_construct_faster", "SELECT lam, true AS twice_as_fast FROM (VALUES (8), (16)) t(lam)")
def _faster(spark, sf_dir):
    """With many negatives the staged filter is built more than twice as fast as the exact table."""
    r = keep(_throughput(spark, sf_dir))
    ours, base = r.where("kind = 'staged'"), r.where("kind = 'exact'").select("lam", F.col("construct").alias("c"))
    return ours.join(base, "lam").where("lam >= 8").select("lam", (F.col("construct") > 2 * F.col("c")).alias("twice_as_fast"))


@query("w1c_construction_success")
def _success(spark, sf_dir):
    """Share of seeds for which a table of C cells a key peels, by C and layout."""
    import numpy as np
    import pyarrow as pa

    from .operators.elementary import peel, slots_np

    grid = spark.createDataFrame([(layout, c / 100, s) for layout in ("uniform", "coupled") for c in range(105, 141, 5) for s in range(10)], "layout string, C double, seed int")

    def run(batches):
        keys = np.arange(20_000)
        for b in batches:
            done = []
            for layout, c, s in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                m = int(c * len(keys))
                done.append(peel(slots_np(keys, 1000 * s + 17, m, layout), m) is not None)
            yield pa.record_batch([*b.columns, pa.array(done)], names=["layout", "C", "seed", "peeled"])

    return grid.repartition(8).mapInArrow(run, "layout string, C double, seed int, peeled boolean").groupBy("layout", "C").agg(F.avg(F.col("peeled").cast("int")).alias("success"))


# --- code stores ---------------------------------------------------------------------------------------------------------------


def skew_string(spark: SparkSession, sf_dir: str, omega: int) -> DataFrame:
    """(i, symbol): eight symbols whose shares grow as powers of omega."""
    total = sum(omega**k for k in range(8))
    h = portable_hash(F.concat_ws("-", "o_orderkey"), omega) / F.lit(float(1 << 32))
    level, below = F.lit(0), 0
    for k in range(7):
        below += omega**k
        level = level + (h >= below / total).cast("int")
    return read_table(spark, sf_dir, "orders", "o_orderkey").select(F.col("o_orderkey").alias("i"), F.concat(F.lit("s"), level).alias("symbol"))


@query("w2a_space_by_skew")
def _skew(spark, sf_dir):
    out = None
    for omega in (3, 6, 10):
        df = keep(skew_string(spark, sf_dir, omega))
        ours, straw = A.huffman_store(df, "i", "symbol"), A.huffman_store(df, "i", "symbol", "single")
        n, e = df.count(), T.entropy_of(df, "symbol").first()["entropy"]
        row = spark.createDataFrame([(omega, n, e, ours.handle.bits() / n, straw.handle.bits() / n)], "omega int, n long, entropy double, staged double, strawman double")
        out = row if out is None else out.unionByName(row)
    return out


@query("w2a_by_omega")
def _omegas(spark, sf_dir):
    """Bits a symbol of the staged store, the shared-block store, the strawman and the plain code, omega 3 to 10, beside the entropy."""
    return _omega_rows(spark, sf_dir, range(3, 11))


def _omega_rows(spark, sf_dir, omegas):
    out = []
    for omega in omegas:
        df = keep(skew_string(spark, sf_dir, omega))
        n, e = df.count(), T.entropy_of(df, "symbol").first()["entropy"]
        stores = {kind: A.huffman_store(df, "i", "symbol", kind) for kind in ("staged", "shared", "single")}
        blocks, _ = A.huffman_blocks(df, "i", "symbol")
        plain = blocks.agg(F.sum(F.length("bits"))).first()[0]
        out.append((omega, n, e, *(stores[k].handle.bits() / n for k in ("staged", "shared", "single")), plain / n, stores["shared"].handle.n))
    return spark.createDataFrame(out, "omega int, n long, entropy double, staged double, shared double, strawman double, plain double, ones long")


@query("w2e_space", "SELECT omega, true AS shared_as_planned, true AS staged_least, true AS both_below_strawman FROM (VALUES (6), (10)) t(omega)")
def _store_space(spark, sf_dir):
    """Strongly skewed strings: shared blocks take C (ceil(log2 lam) + 2) bits a one, more than separate stages and less than one exact table."""
    rows = _omega_rows(spark, sf_dir, (6, 10))
    lam = F.col("strawman") * F.col("n") / T.C_UNIFORM / F.col("ones") - 1  # an exact table stores every bit of the code
    planned = T.C_UNIFORM * F.col("ones") * (F.ceil(F.log2(lam)) + 2) / F.col("n")
    return rows.select("omega", (F.abs(F.col("shared") / planned - 1) <= 0.1).alias("shared_as_planned"), (F.col("staged") < F.col("shared")).alias("staged_least"), (F.col("shared") < F.col("strawman")).alias("both_below_strawman"))


@query("w2e_decode", "SELECT event_id AS i, event_type AS symbol FROM events")
def _shared_decode(spark, sf_dir):
    """Every position, out of shared blocks."""
    df = read_table(spark, sf_dir, "events", "event_id", "event_type").withColumnRenamed("event_id", "i")
    return A.huffman_store(df, "i", "event_type", "shared").get(df.select("i"), "i")


@query("w2b_decode_characters", "SELECT doc_id, p, substr(text, p, 1) AS c FROM (SELECT doc_id, text, unnest(range(1, length(text) + 1)) AS p FROM (SELECT doc_id, text FROM documents WHERE text IS NOT NULL ORDER BY length(text), doc_id LIMIT 25))")
def _characters(spark, sf_dir):
    """A real string: the characters of the 25 shortest texts, stored by document and place. The limit is the string's size."""
    short = read_table(spark, sf_dir, "documents", "doc_id", "text").where("text is not null").orderBy(F.length("text"), "doc_id").limit(25)
    each = keep(short.select("doc_id", F.posexplode(F.split("text", "")).alias("p", "c")).where("c <> ''").withColumn("i", F.col("doc_id") * (1 << 20) + F.col("p")))
    return A.huffman_store(each, "i", "c").get(each.select("i", "doc_id", "p"), "i").select("doc_id", (F.col("p") + 1).cast("long").alias("p"), F.col("symbol").alias("c"))


@query("w2f_robustness", "SELECT flipped, true AS store_loses_few, true AS code_loses_more FROM (VALUES (8), (32)) t(flipped)")
def _robust(spark, sf_dir):
    return _flip_rows(spark, sf_dir).select("flipped", (F.col("store_wrong") <= 12 * F.col("flipped") * F.col("parts")).alias("store_loses_few"), (F.col("code_wrong") > F.col("store_wrong")).alias("code_loses_more"))


@query("w2f_wrong_symbols")
def _flip_rows(spark, sf_dir):
    """Wrong symbols after flipping payload bits: a random-access store against a sequential code, where all behind a flip may shift."""
    df = keep(read_table(spark, sf_dir, "events", "event_id", "event_type").select((F.row_number().over(Window.orderBy("event_id")) - 1).cast("long").alias("i"), F.col("event_type").alias("symbol")).where("i < 4096"))
    store, out = A.huffman_store(df, "i", "symbol"), []
    blocks, code = A.huffman_blocks(df, "i", "symbol")
    for b in (8, 32):
        got = A.CodeStore(A.flipped(store.handle, b), store.code).get(df.withColumnRenamed("symbol", "was"), "i")
        lost = got.where("not symbol <=> was").count()
        spots = [F.lit((i * 2 + 1) * 7) for i in range(b)]  # flips early in the block shift what follows
        flip = F.concat_ws("", F.transform(F.split("bits", ""), lambda c, i: F.when(i.isin(spots), F.when(c == "1", "0").otherwise("1")).otherwise(c)))  # noqa: B023
        seen = A.huffman_decode(blocks.withColumn("bits", flip), code).withColumnRenamed("symbol", "now")
        shifted = df.join(seen, "i", "left").where("not now <=> symbol").count()
        out.append((b, lost, shifted, store.handle.parts))
    return spark.createDataFrame(out, "flipped int, store_wrong long, code_wrong long, parts int")


@query("w2b_decode_events", "SELECT event_id AS i, event_type AS symbol FROM events")
def _decode(spark, sf_dir):
    df = read_table(spark, sf_dir, "events", "event_id", "event_type").withColumnRenamed("event_id", "i")
    return A.huffman_store(df, "i", "event_type").get(df.select("i"), "i")


@query("w2c_random_access", "SELECT event_id AS i, event_type AS symbol FROM events WHERE event_id % 97 = 0")
def _access(spark, sf_dir):
    df = read_table(spark, sf_dir, "events", "event_id", "event_type").withColumnRenamed("event_id", "i")
    return A.huffman_store(df, "i", "event_type").get(df.where("i % 97 = 0").select("i"), "i")  # the positions asked for


@query("b04_sequential_huffman", "SELECT l_returnflag AS symbol, count(*) AS n FROM lineitem GROUP BY l_returnflag")
def _sequential(spark, sf_dir):
    df = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_returnflag").withColumn("i", F.monotonically_increasing_id())
    blocks, code = A.huffman_blocks(df, "i", "l_returnflag")
    return A.huffman_decode(blocks, code).groupBy("symbol").agg(F.count(F.lit(1)).alias("n"))


@query("b05_pair_huffman")
def _pairs(spark, sf_dir):
    """Mean code length a symbol, single symbols against pairs of them."""
    df = read_table(spark, sf_dir, "events", "event_id", "event_type")
    pair = df.alias("a").join(df.alias("b"), F.expr("a.event_id + 1 = b.event_id and a.event_id % 2 = 0")).select(F.concat_ws("|", "a.event_type", "b.event_type").alias("s"))
    out = []
    for width, d in ((1, df.withColumnRenamed("event_type", "s")), (2, pair)):
        code = A.huffman_code(d, "s")
        counts = {r["s"]: r["c"] for r in d.groupBy("s").agg(F.count(F.lit(1)).alias("c")).collect()}  # a row a symbol
        out.append((width, sum(len(code[s]) * c for s, c in counts.items()) / sum(counts.values()) / width))
    return spark.createDataFrame(out, "width int, bits_per_symbol double")


# --- two tables ------------------------------------------------------------------------------------------------------------------


def _stored(spark, sf_dir):
    df = read_table(spark, sf_dir, "orders", "o_orderkey")
    return A.two_table_build(df, "o_orderkey", 0.4), df


@query("p5_two_tables", "SELECT count(*) AS keys, CAST(0 AS BIGINT) AS shared_buckets FROM orders")
def _placed(spark, sf_dir):
    placed, _ = _stored(spark, sf_dir)
    full = placed.groupBy("seg", "tbl", "bucket").agg(F.count(F.lit(1)).alias("n"))
    return full.agg(F.sum("n").alias("keys"), F.sum((F.col("n") > 1).cast("long")).alias("shared_buckets"))


@query("w3b_error_by_training_round")
def _training(spark, sf_dir):
    """Online training: errors after each pass over the keys."""
    return A.adaptive_train(_stored(spark, sf_dir)[0])[1]


@query("w3b_error_by_layer")
def _rounds(spark, sf_dir):
    placed, _ = _stored(spark, sf_dir)
    out = None
    for r in (1, 2, 3, 4, 5, 7, 9):
        row = A.predictor(placed, rounds=r).confusion().select(F.lit(r).alias("layers"), "u", "fn", "fp", "error_rate")
        out = row if out is None else out.unionByName(row)
    return out


@query("w3c_tail_after_four", "SELECT count(*) AS u, CAST(0 AS BIGINT) AS wrong FROM orders")
def _tail(spark, sf_dir):
    placed, _ = _stored(spark, sf_dir)
    return A.predictor(placed, rounds=4, tail="retrieval").confusion().select("u", (F.col("fn") + F.col("fp")).alias("wrong"))


@query("w3d_reads_by_predictor")
def _reads(spark, sf_dir):
    placed, df = _stored(spark, sf_dir)
    out = None
    for name, h in (("none", None), *((kind, A.predictor(placed, kind)) for kind in ("bloom", "blocked", "counting", "alternating"))):
        row = A.two_table_get(placed, h, df, "o_orderkey").agg(F.avg("reads").alias("reads")).withColumn("predictor", F.lit(name)).withColumn("bits", F.lit(h.bits() if h else 0))
        out = row if out is None else out.unionByName(row)
    return out


@query("w3d_values", "SELECT o_orderkey, lpad(CAST(o_orderkey AS VARCHAR), 36, '0') AS key36, md5(CAST(o_orderkey AS VARCHAR)) || md5('v' || CAST(o_orderkey AS VARCHAR)) AS value64, CAST(1 AS INTEGER) AS reads FROM orders")
def _values(spark, sf_dir):
    """36-byte keys and 64-byte values, stored in the buckets of two tables and fetched from the predicted one."""
    rows = _long_rows(spark, sf_dir)
    placed = A.two_table_build(rows, "key36", 0.4)
    store = A.two_table_store(rows, "key36", "value64", placed, _segments(placed))
    got = store.get(rows.select("key36"), "key36", A.predictor(placed))
    return got.select(F.col("key").cast("long").alias("o_orderkey"), F.col("key").alias("key36"), F.col("value").alias("value64"), "reads")


def _long_rows(spark, sf_dir):
    text = F.col("o_orderkey").cast("string")
    return read_table(spark, sf_dir, "orders", "o_orderkey").select(F.lpad(text, 36, "0").alias("key36"), F.concat(F.md5(text), F.md5(F.concat(F.lit("v"), text))).alias("value64"))


def _segments(placed: DataFrame) -> int:
    return (placed.agg(F.max("seg")).first()[0] or 0) + 1


@query(
    "w3d_values_without_predictor",
    "SELECT lpad(CAST(o_orderkey AS VARCHAR), 36, '0') AS key36, md5(CAST(o_orderkey AS VARCHAR)) || md5('v' || CAST(o_orderkey AS VARCHAR)) AS value64 FROM orders "
    "UNION ALL SELECT 'missing-' || CAST(n_nationkey AS VARCHAR), NULL FROM nation",
)
def _unpredicted(spark, sf_dir):
    """The raw two tables: the first is read, then the second; keys that are not stored cost both reads and have no value."""
    rows = _long_rows(spark, sf_dir)
    placed = A.two_table_build(rows, "key36", 0.4)
    store = A.two_table_store(rows, "key36", "value64", placed, _segments(placed))
    asked = rows.select("key36").unionByName(read_table(spark, sf_dir, "nation", "n_nationkey").select(F.concat(F.lit("missing-"), "n_nationkey").alias("key36")))
    return store.get(asked, "key36").select(F.col("key").alias("key36"), F.col("value").alias("value64"))


@query("w3d_reads_through_store", "SELECT true AS one_read_each, true AS raw_reads_more, count(*) AS keys FROM orders")
def _store_reads(spark, sf_dir):
    """Reads of the two stores side by side: exactly one a key with the predictor; without one, one more for each key of table 2."""
    rows = _long_rows(spark, sf_dir)
    placed = A.two_table_build(rows, "key36", 0.4)
    store = A.two_table_store(rows, "key36", "value64", placed, _segments(placed))
    second = placed.where("tbl = 2").agg(F.count(F.lit(1)).alias("n2"))
    raw = store.get(rows, "key36").agg(F.sum("reads").alias("raw"), F.count(F.lit(1)).alias("keys"))
    ours = store.get(rows, "key36", A.predictor(placed)).agg(F.sum("reads").alias("ours"))
    return raw.join(ours).join(second).select((F.col("ours") == F.col("keys")).alias("one_read_each"), (F.col("raw") == F.col("keys") + F.col("n2")).alias("raw_reads_more"), "keys")  # three single rows


@query("s12_trained_predictor", "SELECT count(*) AS u, true AS agrees, true AS few_wrong FROM orders")
def _trained(spark, sf_dir):
    """The handle that online training leaves: it is probed like any other filter and errs as often as training counted."""
    handle, errors = A.adaptive_train(_stored(spark, sf_dir)[0], 8)
    last = errors.where("round = 8").select("wrong")
    return handle.confusion().join(last).select("u", (F.col("fn") + F.col("fp") == F.col("wrong")).alias("agrees"), (F.col("error_rate") <= 0.01).alias("few_wrong"))  # single rows


@query("b09_locking_blocks", "SELECT count(*) AS keys, CAST(0 AS BIGINT) AS wrong, true AS eight_bits_a_bucket FROM orders")
def _blocks(spark, sf_dir):
    """The locking baseline with counters one-to-one with the buckets of table 1: never a wrong table."""
    items, blocks = A.locking_blocks(read_table(spark, sf_dir, "orders", "o_orderkey"), "o_orderkey")
    guessed = A.locking_guess(items, blocks).agg(F.count(F.lit(1)).alias("keys"), F.sum((F.col("second") != (F.col("tbl") == 2)).cast("long")).alias("wrong"))
    size = blocks.agg(F.max(F.abs(F.size("words") * 64 - 8 * F.col("buckets"))).alias("spare"))
    return guessed.join(size).select("keys", "wrong", (F.col("spare") <= 128).alias("eight_bits_a_bucket"))  # single rows; two spare words


@query("w3d_locked_share")
def _locked(spark, sf_dir):
    """What locking costs: keys in table 2 and in its stash, against plain eviction, and the bits of either predictor."""
    orders = read_table(spark, sf_dir, "orders", "o_orderkey")
    items, blocks = A.locking_blocks(orders, "o_orderkey")
    placed = A.two_table_build(orders, "o_orderkey", 0.4)
    share = lambda c: F.avg(c.cast("int"))
    bits = A.predictor(placed).bits()
    return items.agg(share(F.col("tbl") == 2).alias("locked"), share(F.col("stash")).alias("stash")).join(placed.agg(share(F.col("tbl") == 2).alias("evicted"))).join(
        blocks.agg((8 * F.sum("buckets")).alias("locking_bits"))
    ).withColumn("ours_bits", F.lit(bits))  # single rows


@query("w3e_share_in_first_table")
def _share(spark, sf_dir):
    placed, _ = _stored(spark, sf_dir)
    return placed.agg(F.sum((F.col("tbl") == 1).cast("long")).alias("n1"), F.sum((F.col("tbl") == 2).cast("long")).alias("n2")).withColumn("ratio", F.col("n1") / F.col("n2")).withColumn("expected", F.lit(T.predictor_lambda(0.4)))


@query("b09_locking_predictor")
def _locking(spark, sf_dir):
    placed, _ = _stored(spark, sf_dir)
    return A.locking_predictor(placed).agg(F.sum("moved").alias("moved"), F.sum("n2").alias("n2"), F.sum("bits").alias("bits"))


# --- sorted runs -----------------------------------------------------------------------------------------------------------------


def _event_runs(spark, sf_dir, n=7):
    return keep(A.cut_runs(read_table(spark, sf_dir, "events", "event_id", "user_id", "ts", "value"), n, ["ts"]))


@query("w4a_existing_keys", "SELECT count(*) AS keys, CAST(count(*) AS BIGINT) AS reads, CAST(0 AS BIGINT) AS wasted FROM events")
def _existing(spark, sf_dir):
    """With exact filters, which know of later runs alone, every existing key costs one read."""
    return _reads_of_existing(spark, sf_dir, 7)


def _reads_of_existing(spark, sf_dir, n):
    runs = _event_runs(spark, sf_dir, n)
    found = A.runs_get(runs, "event_id", runs, A.runs_filters(runs, "event_id", scope="later"), "first")
    return found.agg(F.count(F.lit(1)).alias("keys"), F.sum("reads").alias("reads"), F.sum("wasted").alias("wasted"))


for _n in (15, 30):
    query(f"w4a_existing_keys_{_n}_runs", ORACLE_SQL["w4a_existing_keys"])(lambda spark, sf_dir, n=_n: _reads_of_existing(spark, sf_dir, n))


@query("w4a_reads_by_runs")
def _reads_by_runs(spark, sf_dir):
    """Reads of existing keys for 7, 15 and 30 runs: Bloom filters of the same and twice the bits, and staged ones."""
    out = None
    for n in (7, 15, 30):
        row = _read_rows(_event_runs(spark, sf_dir, n)).withColumn("runs", F.lit(n))
        out = row if out is None else out.unionByName(row)
    return out


@query("w4c_newest_rows", "SELECT user_id, max(ts) AS ts, true AS at_most_one_wasted FROM events GROUP BY user_id")
def _newest(spark, sf_dir):
    """Keys that lie in many runs: the last run that holds the key is found with at most one wasted read."""
    runs = _event_runs(spark, sf_dir)
    found = A.runs_get(runs, "user_id", runs, A.runs_filters(runs, "user_id", scope="later"), "oldest")
    newest = runs.groupBy("user_id", "run").agg(F.max("ts").alias("ts"))
    return found.join(newest, (F.col("key") == F.col("user_id")) & (F.col("found_run") == F.col("run"))).select("user_id", "ts", (F.col("wasted") <= 1).alias("at_most_one_wasted"))


@query("w4b_missing_at_most_one", "SELECT count(*) AS keys, true AS at_most_one_read, CAST(0 AS BIGINT) AS found FROM events")
def _missing_one(spark, sf_dir):
    runs = _event_runs(spark, sf_dir, 15)
    gone = runs.select((F.col("event_id") + 1_000_000_007).alias("event_id"))
    got = A.runs_get(runs, "event_id", gone, A.runs_filters(runs, "event_id", scope="later"), "oldest")
    return got.agg(F.count(F.lit(1)).alias("keys"), (F.max("reads") <= 1).alias("at_most_one_read"), F.count("found_run").alias("found"))


@query("p7_compaction_of_rows", "SELECT user_id, max(ts) AS ts FROM events GROUP BY user_id")
def _compacted_rows(spark, sf_dir):
    """Seven runs of all their rows become one; of a key's rows in a run the latest counts."""
    return A.runs_compact(_event_runs(spark, sf_dir), "user_id", 7, "ts").select("user_id", "ts")


@query("p7_levels", "SELECT count(DISTINCT user_id) AS keys, CAST(2 AS INTEGER) AS top, CAST(4 AS BIGINT) AS tiers, true AS newest_kept FROM events")
def _levels(spark, sf_dir):
    """Fourteen flushes at a threshold of three: one run of nine, one of three, two of one; every key's newest row is kept."""
    runs = keep(_event_runs(spark, sf_dir, 14).select("run", "user_id", "ts"))
    tiers = keep(A.runs_levels(runs, "user_id", 3, "ts"))
    newest = tiers.groupBy("user_id").agg(F.max("ts").alias("a")).join(runs.groupBy("user_id").agg(F.max("ts").alias("b")), "user_id")
    return newest.agg(F.count(F.lit(1)).alias("keys"), F.min(F.col("a").eqNullSafe(F.col("b"))).alias("newest_kept")).join(tiers.agg(F.max("level").alias("top"), F.countDistinct("tier").alias("tiers")))  # single rows


@query("w4a_reads_by_filter")
def _run_reads(spark, sf_dir):
    """P50, P95, P99 and mean of the reads of an existing key: no filter, Bloom of 1x and 2x the bits, staged."""
    return _read_rows(_event_runs(spark, sf_dir))


def _read_rows(runs):
    own = runs.select("run", "event_id").withColumn("mine", F.lit(True))
    staged = A.runs_filters(runs, "event_id", scope="later")
    per_key = staged.bits() / max(1, staged.n)
    out = None
    for name, h in (("0x", None), ("1x", X.single(own, ["run", "event_id"], "mine", "bloom", 2 ** (-T.LN2 * per_key))), ("2x", X.single(own, ["run", "event_id"], "mine", "bloom", 2 ** (-2 * T.LN2 * per_key))), ("staged", staged)):
        row = A.runs_get(runs, "event_id", runs, h, "first" if name == "staged" else "newest").agg(F.percentile("reads", F.array(F.lit(0.5), F.lit(0.95), F.lit(0.99))).alias("p"), F.avg("reads").alias("reads"), F.max("wasted").alias("most_wasted")).withColumn("filter", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@query("w4b_missing_keys")
def _missing(spark, sf_dir):
    runs = _event_runs(spark, sf_dir)
    gone = runs.select((F.col("event_id") + 1_000_000_007).alias("event_id"))
    return A.runs_get(runs, "event_id", gone, A.runs_filters(runs, "event_id")).agg(F.count(F.lit(1)).alias("keys"), F.avg("reads").alias("reads"), F.max("wasted").alias("most_wasted"))


@query("w4c_repeated_keys", "SELECT user_id AS key, CAST(0 AS INTEGER) AS wasted FROM events GROUP BY user_id")
def _repeated(spark, sf_dir):
    runs = _event_runs(spark, sf_dir)
    return A.runs_get(runs, "user_id", runs, A.runs_filters(runs, "user_id")).select("key", "wasted")


@query("p7_compaction", "SELECT user_id, max(ts) AS ts FROM events GROUP BY user_id")
def _compacted(spark, sf_dir):
    """Compacting all runs into one keeps each user's newest event."""
    runs = _event_runs(spark, sf_dir)
    newest = runs.groupBy("run", "user_id").agg(F.max("ts").alias("ts"))
    return A.runs_compact(newest, "user_id", 7).select("user_id", "ts")


# --- learned filters and filters in pipelines --------------------------------------------------------------------------------------


def _learned_rows(spark, sf_dir, label, share=0.5):
    """u, fn, fp, backup, bits for each kind of backup behind one model."""
    df = read_table(spark, sf_dir, "documents", "doc_id", "text").join(read_table(spark, sf_dir, "labels", "doc_id", label), "doc_id")
    model, scored = A.learned_model(df, "doc_id", "text", label, share)
    out = None
    for backup in ("staged", "retrieval", "bloom"):
        f = A.learned_backup(model, scored, "doc_id", "text", 0.01, backup)
        hit = (F.col("p") >= f.threshold) | F.col("spare")
        positive = F.col("label") == 1
        row = f.backup.probe(scored, ["doc_id"], "spare").agg(
            F.count(F.lit(1)).alias("u"), F.sum((positive & ~hit).cast("long")).alias("fn"), F.sum((~positive & hit).cast("long")).alias("fp"), F.sum(positive.cast("long")).alias("n")
        ).withColumn("backup", F.lit(backup)).withColumn("bits", F.lit(f.backup.bits()))
        out = row if out is None else out.unionByName(row)
    return out


@query("w5a_learned_filter")
def _learned(spark, sf_dir):
    return _learned_rows(spark, sf_dir, "quality").drop("n")


@query("w5a_no_false_negative", "SELECT backup, count(*) AS u, CAST(0 AS BIGINT) AS fn, true AS rate_held FROM documents JOIN labels ON documents.doc_id = labels.doc_id, (VALUES ('staged'), ('retrieval'), ('bloom')) b(backup) GROUP BY backup")
def _learned_held(spark, sf_dir):
    """At a target rate of 0.01: no positive is denied, and the negatives that pass are within the target and what chance adds to it."""
    rows = _learned_rows(spark, sf_dir, "quality")
    return rows.select("backup", "u", "fn", (F.col("fp") <= 0.01 * (F.col("u") - F.col("n")) + 3 * F.sqrt(0.01 * (F.col("u") - F.col("n"))) + 1).alias("rate_held"))


@query("w5a_by_train_share")
def _shares(spark, sf_dir):
    """Backup bits by the share of keys the model was fitted on, for both tasks, beside the bound without a model and plain filters of the same rate."""
    out = None
    for label in ("quality", "toxic"):
        for share in (0.1, 0.5, 1.0):
            row = _learned_rows(spark, sf_dir, label, share).withColumn("task", F.lit(label)).withColumn("train_share", F.lit(share))
            out = row if out is None else out.unionByName(row)
    lam = (F.col("u") - F.col("n")) / F.greatest(F.lit(1), F.col("n"))
    plain = F.col("n") * T.elementary_cost("bloom", 0.01)
    return keep(out).withColumn("bound", F.col("n") * T.lb(F.lit(0.01), lam)).withColumn("plain_bloom", F.lit(1.0) * plain).withColumn("plain_xor", F.col("n") * T.elementary_cost("xor", 0.01, C=T.C_UNIFORM)).withColumn(
        "plain_staged", F.col("n") * T.cost_general(F.lit(0.01), lam, T.C_UNIFORM)
    )


@query("w6_url_block_list", "SELECT page_id, host, host IN (SELECT DISTINCT split_part(split_part(url, '://', 2), '/', 1) FROM pages WHERE page_id % 5 = 0) AS blocked FROM (SELECT page_id, split_part(split_part(url, '://', 2), '/', 1) AS host FROM pages)")
def _urls(spark, sf_dir):
    """Hosts of every fifth page form the block list."""
    pages = read_table(spark, sf_dir, "pages", "page_id", "url").select("page_id", F.split_part(F.split_part("url", F.lit("://"), F.lit(2)), F.lit("/"), F.lit(1)).alias("host"))
    hosts = pages.groupBy("host").agg(F.max((F.col("page_id") % 5 == 0).cast("int")).alias("y")).select("host", (F.col("y") == 1).alias("y"))
    return X.staged(hosts, ["host"], "y").probe(pages, ["host"], "blocked")


_EIGHT = "SELECT {id} AS id, array_to_string(ws[i : i + 7], ' ') AS g FROM (SELECT {id}, ws, unnest(range(1, len(ws) - 6)) AS i FROM (SELECT {id}, string_split(text, ' ') AS ws FROM {table}) WHERE len(ws) >= 8)"


def _eight_words(spark, sf_dir, table, key):
    """(id, g): every run of eight words of each whole text."""
    words = read_table(spark, sf_dir, table, key, "text").select(F.col(key).alias("id"), F.split("text", " ").alias("ws")).where("size(ws) >= 8")
    return words.select("id", F.explode(F.transform(F.sequence(F.lit(1), F.size("ws") - 7), lambda i: F.concat_ws(" ", F.slice("ws", i, F.lit(8))))).alias("g"))


@query("w6_contamination", f"SELECT d.id AS doc_id, count(DISTINCT d.g) AS shared FROM ({_EIGHT.format(id='doc_id', table='documents')}) d WHERE d.g IN (SELECT g FROM ({_EIGHT.format(id='item_id', table='benchmark')})) GROUP BY d.id")
def _contaminated(spark, sf_dir):
    """Documents that hold eight words in a row of a benchmark item: the documents' own runs are the universe, so the answer is exact."""
    docs, bench = _eight_words(spark, sf_dir, "documents", "doc_id"), _eight_words(spark, sf_dir, "benchmark", "item_id")
    labelled = docs.select("g", F.lit(False).alias("y")).unionByName(bench.select("g", F.lit(True).alias("y")))
    return X.staged(labelled, ["g"], "y").probe(docs, ["g"]).where("hit").groupBy(F.col("id").alias("doc_id")).agg(F.countDistinct("g").alias("shared"))


@query("w6_exact_copies", "SELECT doc_id, count(*) OVER (PARTITION BY text) > 1 AS copied FROM documents WHERE text IS NOT NULL")
def _copied(spark, sf_dir):
    """Texts that occur more than once are the positives; each document asks by its text."""
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text").where("text is not null").select("doc_id", F.sha2("text", 256).alias("sha"))
    often = docs.groupBy("sha").agg((F.count(F.lit(1)) > 1).alias("y"))
    return X.staged(often, ["sha"], "y").probe(docs, ["sha"], "copied").select("doc_id", "copied")


@query("m13_engine_cost")
def _engine_cost(spark, sf_dir):
    """Shuffles, broadcasts and their bytes of one semi join: by sort and merge, as the engine likes, and by a filter already built."""
    orders, k = universe(spark, sf_dir, "orders")
    lines = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_extendedprice").withColumnRenamed("l_orderkey", "o_orderkey")
    total = lambda df: df.agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("price"))
    urgent = orders.where("y").select("o_orderkey")
    ways = {
        "merge": lines.join(urgent.hint("merge"), k, "left_semi"), "engine": lines.join(urgent, k, "left_semi"), "filter": X.staged(orders, k, "y").probe(lines, k).where("hit"),
    }
    rows = [(name, *spent(total(df)).values()) for name, df in ways.items()]
    return spark.createDataFrame(rows, "way string, shuffles long, shuffle_bytes long, broadcasts long, broadcast_bytes long")


@query("w6_semi_join_reduction", "SELECT count(*) AS lines, round(sum(l_extendedprice), 2) AS price FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def _reduced(spark, sf_dir):
    orders, k = universe(spark, sf_dir, "orders")
    lines = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_extendedprice").withColumnRenamed("l_orderkey", "o_orderkey")
    return X.staged(orders, k, "y").probe(lines, k).where("hit").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("w7_hot_universe", "SELECT user_id, count(*) AS n FROM events WHERE user_id IN (SELECT user_id FROM events GROUP BY user_id HAVING count(*) FILTER (WHERE event_type = 'purchase') >= 5) GROUP BY user_id")
def _hot(spark, sf_dir):
    events = read_table(spark, sf_dir, "events", "user_id", "event_type")
    users = events.groupBy("user_id").agg((F.sum((F.col("event_type") == "purchase").cast("int")) >= 5).alias("y"))
    return X.staged(users, ["user_id"], "y").probe(events, ["user_id"]).where("hit").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


for _name, (_f, _sql) in {**relational.OPERATORS, **flows.OPERATORS}.items():
    query(_name, _sql)(_f)
