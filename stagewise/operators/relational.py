"""The relational operators around the filters, each with the SQL that tells the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import portable_hash, portable_sql
from ..functions.sqlsurface import register, register_explain
from ..plans.storage import shared_folder
from ..sources.tables import read_table, round_trip
from . import filters as X
from .cells import pack

OPERATORS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def op(name: str, sql: str | None = None):
    def add(f):
        OPERATORS[f"op_{name}"] = (f, sql)
        return f

    return add


_t = read_table


# --- sources and sinks -----------------------------------------------------------------------------------------------------------

for _kind in ("csv", "json", "orc", "parquet"):

    @op(f"source_{_kind}", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
    def _source(s, d, kind=_kind):
        return round_trip(_t(s, d, "nation", "n_nationkey", "n_name", "n_regionkey"), kind, f"{shared_folder(s)}/nation_{kind}")


@op("source_pruned", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 100000")
def _pruned(s, d):
    return _t(s, d, "orders", "o_orderkey", "o_totalprice").where("o_totalprice > 100000")


@op("sink_partitioned", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _partitioned(s, d):
    path = f"{shared_folder(s)}/events_by_type"
    _t(s, d, "events", "event_id", "event_type").repartition("event_type").write.mode("overwrite").partitionBy("event_type").parquet(path)
    return s.read.parquet(path).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@op("filter_saved_and_loaded", "SELECT o_orderkey, o_orderpriority = '1-URGENT' AS hit FROM orders")
def _saved(s, d):
    orders = _t(s, d, "orders", "o_orderkey", "o_orderpriority").withColumn("y", F.col("o_orderpriority") == "1-URGENT")
    path = f"{shared_folder(s)}/saved_filter"
    X.save(X.staged(orders, ["o_orderkey"], "y"), path)
    return X.load(s, path).probe(orders.select("o_orderkey"), ["o_orderkey"])


# --- rows ------------------------------------------------------------------------------------------------------------------------


@op("project", "SELECT l_orderkey AS k, l_linenumber AS line, round(l_extendedprice * (1 - l_discount), 4) AS net, CAST(l_quantity AS BIGINT) AS q FROM lineitem")
def _project(s, d):
    return _t(s, d, "lineitem").select(F.col("l_orderkey").alias("k"), F.col("l_linenumber").alias("line"), F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), F.col("l_quantity").cast("long").alias("q"))


@op("predicates", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 50000 AND 150000 AND o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '%URGENT' AND o_custkey IS NOT DISTINCT FROM o_custkey")
def _predicates(s, d):
    c = F.col
    return _t(s, d, "orders").where(c("o_totalprice").between(50000, 150000) & c("o_orderstatus").isin("O", "F") & c("o_orderpriority").like("%URGENT") & c("o_custkey").eqNullSafe(c("o_custkey"))).select("o_orderkey")


@op("case_when", "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS band FROM part")
def _case(s, d):
    return _t(s, d, "part", "p_partkey", "p_size").select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("band"))


@op("membership_predicate", "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_partkey IN (SELECT p_partkey FROM part WHERE p_brand = 'Brand#1')")
def _member(s, d):
    part = _t(s, d, "part", "p_partkey", "p_brand").withColumn("y", F.coalesce(F.col("p_brand") == "Brand#1", F.lit(False))).withColumnRenamed("p_partkey", "l_partkey")
    return X.staged(part, ["l_partkey"], "y").probe(_t(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_partkey"), ["l_partkey"]).where("hit").drop("hit")


@op("sample_by_hash", f"SELECT doc_id FROM documents WHERE {portable_sql('doc_id', 5)} % 10 = 0")
def _sample(s, d):
    return _t(s, d, "documents", "doc_id").where(F.pmod(portable_hash(F.col("doc_id"), 5), F.lit(10)) == 0)


# --- joins -----------------------------------------------------------------------------------------------------------------------


def _joined(s, d, hint=None, how="inner"):
    o, l = _t(s, d, "orders", "o_orderkey", "o_custkey"), _t(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_quantity")
    return o.join(l.hint(hint) if hint else l, o.o_orderkey == l.l_orderkey, how)


@op("join_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def _broadcast(s, d):
    c, n = _t(s, d, "customer", "c_custkey", "c_nationkey"), _t(s, d, "nation", "n_nationkey", "n_name")  # 25 nations, whatever the scale
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).select("c_custkey", "n_name")


for _hint in ("merge", "shuffle_hash"):

    @op(f"join_{_hint}", "SELECT o_custkey, count(*) AS n, sum(l_quantity) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey")
    def _hinted(s, d, hint=_hint):
        return _joined(s, d, hint).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"))


for _how, _sqlhow in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):

    @op(f"join_{_how}_outer", f"SELECT count(*) AS n, count(o_orderkey) AS orders, count(l_orderkey) AS lines FROM orders {_sqlhow} JOIN lineitem ON o_orderkey = l_orderkey")
    def _outer(s, d, how=_how):
        return _joined(s, d, None, how).agg(F.count(F.lit(1)).alias("n"), F.count("o_orderkey").alias("orders"), F.count("l_orderkey").alias("lines"))


for _how, _word in (("left_semi", ""), ("left_anti", "NOT ")):

    @op(f"join_{_how[5:]}", f"SELECT o_orderkey FROM orders WHERE {_word}EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
    def _exists(s, d, how=_how):
        return _joined(s, d, None, how).select("o_orderkey")


@op("join_range", "SELECT b.band, count(*) AS n FROM part p JOIN (SELECT unnest(range(0, 10)) AS band) b ON p.p_retailprice >= 900 + b.band * 100 AND p.p_retailprice < 1000 + b.band * 100 GROUP BY b.band")
def _range(s, d):
    """A range join by bins: price and band meet on the bin's number."""
    bands = s.range(10).select(F.col("id").alias("band"), (900 + F.col("id") * 100).alias("lo"), (1000 + F.col("id") * 100).alias("hi"))
    binned = bands.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / 50), F.floor((F.col("hi") - 1) / 50))))
    part = _t(s, d, "part", "p_retailprice").withColumn("bin", F.floor(F.col("p_retailprice") / 50))
    return part.join(binned, "bin").where("p_retailprice >= lo and p_retailprice < hi").groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@op("join_theta", "SELECT a.r_regionkey AS a, b.n_nationkey AS b FROM region a JOIN nation b ON a.r_regionkey < b.n_regionkey")
def _theta(s, d):
    a, b = _t(s, d, "region"), _t(s, d, "nation")
    return a.join(F.broadcast(b), a.r_regionkey < b.n_regionkey).select(a.r_regionkey.alias("a"), b.n_nationkey.alias("b"))


@op("join_cross", "SELECT r_regionkey, n_nationkey FROM region CROSS JOIN nation")
def _cross(s, d):
    """Five regions by 25 nations, whatever the scale."""
    return _t(s, d, "region", "r_regionkey").crossJoin(F.broadcast(_t(s, d, "nation", "n_nationkey")))


@op("join_as_of", "SELECT v.event_id, p.event_id AS purchase FROM (SELECT * FROM events WHERE event_type = 'view') v ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY user_id, ts) p ON v.user_id = p.user_id AND v.ts >= p.ts")
def _as_of(s, d):
    """The last purchase before each view of the same user: a union and a window, no self-join."""
    e = _t(s, d, "events", "event_id", "user_id", "ts", "event_type").where("event_type in ('view', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("purchase", last).where("event_type = 'view'").select("event_id", "purchase")


@op("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _interval(s, d):
    e = _t(s, d, "events", "event_id", "user_id", "ts")
    a, b = e.alias("a"), e.alias("b")
    return a.join(b, F.expr("a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")).select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b"))


@op("join_by_filter", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem SEMI JOIN (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F') o ON l_orderkey = o_orderkey")
def _semi_by_filter(s, d):
    """An exact filter instead of a semi join; its universe is the order keys, which every line has."""
    o = _t(s, d, "orders", "o_orderkey", "o_orderstatus").select(F.col("o_orderkey").alias("l_orderkey"), (F.col("o_orderstatus") == "F").alias("y"))
    return X.staged(o, ["l_orderkey"], "y").probe(_t(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"), ["l_orderkey"]).where("hit").drop("hit")


@op("join_prefiltered", "SELECT c_mktsegment, count(*) AS n FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderpriority = '1-URGENT' GROUP BY c_mktsegment")
def _prefiltered(s, d):
    """A small approximate filter drops most lines before they are shuffled; the join makes it exact."""
    o = _t(s, d, "orders", "o_orderkey", "o_custkey", "o_orderpriority")
    urgent = o.where("o_orderpriority = '1-URGENT'")
    f = X.single(urgent.withColumn("y", F.lit(True)), ["o_orderkey"], "y", "bloom", 0.02)
    lines = f.probe(_t(s, d, "lineitem", "l_orderkey"), ["l_orderkey"]).where("hit").drop("hit")
    c = _t(s, d, "customer", "c_custkey", "c_mktsegment")
    return lines.join(urgent, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("c_custkey") == F.col("o_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


# --- aggregates ------------------------------------------------------------------------------------------------------------------


@op("aggregate", "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q, min(l_tax) AS lo, max(l_tax) AS hi, round(avg(l_discount), 9) AS disc FROM lineitem GROUP BY ALL")
def _aggregate(s, d):
    return _t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"), F.round(F.avg("l_discount"), 9).alias("disc"))


@op("aggregate_string", "SELECT p_brand, max(p_type) AS hi, min(p_name) AS lo FROM part GROUP BY p_brand")
def _strings(s, d):
    return _t(s, d, "part").groupBy("p_brand").agg(F.max("p_type").alias("hi"), F.min("p_name").alias("lo"))


@op("count_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS c, count(DISTINCT o_orderpriority) AS p FROM orders GROUP BY o_orderstatus")
def _distinct(s, d):
    return _t(s, d, "orders").groupBy("o_orderstatus").agg(F.countDistinct("o_custkey").alias("c"), F.countDistinct("o_orderpriority").alias("p"))


@op("approximate")
def _approximate(s, d):
    return _t(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median"))


@op("percentiles", "SELECT event_type, round(quantile_cont(value, 0.5), 9) AS p50, round(quantile_cont(value, 0.95), 9) AS p95, round(quantile_cont(value, 0.99), 9) AS p99 FROM events GROUP BY event_type")
def _percentiles(s, d):
    return _t(s, d, "events").groupBy("event_type").agg(*[F.round(F.percentile("value", p / 100), 9).alias(f"p{p}") for p in (50, 95, 99)])


@op("bitwise", "SELECT o_orderstatus, bit_or(o_custkey) AS o, bit_and(o_custkey) AS a, bit_xor(o_custkey) AS x FROM orders GROUP BY o_orderstatus")
def _bitwise(s, d):
    return _t(s, d, "orders").groupBy("o_orderstatus").agg(F.bit_or("o_custkey").alias("o"), F.bit_and("o_custkey").alias("a"), F.bit_xor("o_custkey").alias("x"))


@op("cube", "SELECT l_returnflag AS f, l_linestatus AS st, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def _cube(s, d):
    return _t(s, d, "lineitem").select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("st")).cube("f", "st").agg(F.count(F.lit(1)).alias("n"))


@op("rollup", "SELECT l_returnflag AS f, l_linestatus AS st, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def _rollup(s, d):
    return _t(s, d, "lineitem").select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("st")).rollup("f", "st").agg(F.count(F.lit(1)).alias("n"))


@op("grouping_sets", "SELECT l_returnflag AS f, l_linestatus AS st, GROUPING(l_returnflag, l_linestatus) AS level, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
def _grouping_sets(s, d):
    sets = _t(s, d, "lineitem", "l_returnflag", "l_linestatus").select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("st"))
    return sets.groupingSets([["f", "st"], ["f"], []], "f", "st").agg(F.grouping_id("f", "st").alias("level"), F.count(F.lit(1)).alias("n"))


@op("pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(*) FILTER (WHERE event_type = 'purchase') AS purchases FROM events GROUP BY user_id")
def _pivot(s, d):
    p = _t(s, d, "events", "user_id", "event_type").groupBy("user_id").pivot("event_type", ["view", "purchase"]).count()
    return p.select("user_id", F.coalesce("view", F.lit(0)).alias("views"), F.coalesce("purchase", F.lit(0)).alias("purchases"))


@op("arg_max", "SELECT user_id, max_by(event_id, ts) AS last, min_by(event_id, ts) AS first FROM (SELECT user_id, event_id, ts FROM events) GROUP BY user_id")
def _arg_max(s, d):
    return _t(s, d, "events").groupBy("user_id").agg(F.max_by("event_id", "ts").alias("last"), F.min_by("event_id", "ts").alias("first"))


# --- windows, order, sets ----------------------------------------------------------------------------------------------------------

_BY_CUSTOMER = "OVER (PARTITION BY o_custkey ORDER BY o_orderkey)"


@op("window_ranks", f"SELECT o_orderkey, CAST(row_number() {_BY_CUSTOMER} AS INTEGER) AS rn, CAST(ntile(4) {_BY_CUSTOMER} AS INTEGER) AS nt, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS INTEGER) AS dr, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS INTEGER) AS rk FROM orders")
def _ranks(s, d):
    w, v = Window.partitionBy("o_custkey").orderBy("o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderstatus")
    return _t(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.ntile(4).over(w).alias("nt"), F.dense_rank().over(v).alias("dr"), F.rank().over(v).alias("rk"))


@op("window_neighbours", "SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id) OVER w AS next, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _neighbours(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return _t(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("prev"), F.lead("event_id").over(w).alias("next"), F.first("event_id").over(w).alias("first"))


@op("window_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS moving FROM events")
def _running(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return _t(s, d, "events").select("event_id", F.round(F.sum("value").over(w), 6).alias("moving"))


@op("window_time_range", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW), 6) AS last_hour FROM events")
def _time_range(s, d):
    """A frame by time: rows of the same instant are in it, too."""
    e = _t(s, d, "events", "event_id", "user_id", "ts", "value").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return e.select("event_id", F.round(F.sum("value").over(w), 6).alias("last_hour"))


@op("top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def _top(s, d):
    return _t(s, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@op("top_k_by_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def _top_group(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(s, d, "orders").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("o_custkey", "o_orderkey")


@op("sort", "SELECT c_custkey, c_mktsegment FROM customer ORDER BY c_mktsegment, c_acctbal DESC, c_custkey")
def _sort(s, d):
    return _t(s, d, "customer").orderBy(F.asc_nulls_last("c_mktsegment"), F.desc("c_acctbal"), "c_custkey").select("c_custkey", "c_mktsegment")


for _fn, _word in (("union", "UNION"), ("intersect", "INTERSECT"), ("exceptAll", "EXCEPT ALL"), ("unionAll", "UNION ALL"), ("subtract", "EXCEPT"), ("intersectAll", "INTERSECT ALL")):

    @op(f"set_{_fn}", f"SELECT c_custkey AS k FROM customer {_word} SELECT o_custkey AS k FROM orders")
    def _set(s, d, fn=_fn):
        a, b = _t(s, d, "customer").select(F.col("c_custkey").alias("k")), _t(s, d, "orders").select(F.col("o_custkey").alias("k"))
        return a.union(b).distinct() if fn == "union" else getattr(a, fn)(b)


@op("set_except_by_filter", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')")
def _except_by_filter(s, d):
    c = _t(s, d, "customer", "c_custkey")
    pending = _t(s, d, "orders", "o_custkey", "o_orderstatus").where("o_orderstatus = 'P'").select(F.col("o_custkey").alias("c_custkey")).distinct().withColumn("y", F.lit(True))
    f = X.staged(c.join(pending, "c_custkey", "left").select("c_custkey", F.coalesce("y", F.lit(False)).alias("y")), ["c_custkey"], "y")
    return f.probe(c, ["c_custkey"]).where("not hit").select("c_custkey")


@op("set_intersect_by_filter", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')")
def _intersect_by_filter(s, d):
    """Pending customers that are in the customer table: its keys are the universe, so the answer is exact."""
    c = _t(s, d, "customer", "c_custkey")
    pending = _t(s, d, "orders", "o_custkey", "o_orderstatus").where("o_orderstatus = 'P'").select(F.col("o_custkey").alias("c_custkey"), F.lit(True).alias("y"))
    labelled = c.withColumn("y", F.lit(False)).unionByName(pending)  # a key of both classes counts as positive
    return X.staged(labelled, ["c_custkey"], "y").probe(c, ["c_custkey"]).where("hit").select("c_custkey")


# --- functions ---------------------------------------------------------------------------------------------------------------------


@op("strings", "SELECT page_id, upper(substr(url, 1, 5)) AS head, lpad(CAST(page_id AS VARCHAR), 8, '0') AS padded, length(url) AS n, split_part(url, '/', 3) AS host, replace(url, 'http', 'x') AS replaced, regexp_replace(url, '[0-9]+', '#', 'g') AS masked FROM pages")
def _string_functions(s, d):
    u = F.col("url")
    return _t(s, d, "pages", "page_id", "url").select(
        "page_id", F.upper(F.substring(u, 1, 5)).alias("head"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("padded"), F.length(u).cast("long").alias("n"),
        F.split_part(u, F.lit("/"), F.lit(3)).alias("host"), F.replace(u, F.lit("http"), F.lit("x")).alias("replaced"), F.regexp_replace(u, "[0-9]+", "#").alias("masked"),
    )


@op("shingles", "SELECT item_id, count(DISTINCT g) AS shingles FROM (SELECT item_id, unnest(list_transform(range(1, len(ws) - 6), lambda i: array_to_string(ws[i:i+7], ' '))) AS g FROM (SELECT item_id, string_split(text, ' ') AS ws FROM benchmark)) GROUP BY item_id")
def _shingles(s, d):
    w = _t(s, d, "benchmark", "item_id", "text").select("item_id", F.split("text", " ").alias("ws")).where(F.size("ws") >= 8)
    grams = F.transform(F.sequence(F.lit(1), F.size("ws") - 7), lambda i: F.concat_ws(" ", F.slice("ws", i, F.lit(8))))
    return w.select("item_id", F.explode(grams).alias("g")).groupBy("item_id").agg(F.countDistinct("g").alias("shingles"))


@op("dates", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(o_orderdate AS DATE) + 30 AS due FROM orders")
def _dates(s, d):
    o = F.col("o_orderdate")
    return _t(s, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.trunc(o, "month").alias("month"), F.year(o).alias("y"), F.date_add(o.cast("date"), 30).alias("due"))


@op("math", "SELECT p_partkey, round(log2(p_retailprice), 9) AS lg, round(exp(p_size / 50.0), 9) AS e, CAST(p_size % 7 AS INTEGER) AS m, CAST(floor(p_retailprice) AS BIGINT) AS f FROM part")
def _math(s, d):
    return _t(s, d, "part").select("p_partkey", F.round(F.log2("p_retailprice"), 9).alias("lg"), F.round(F.exp(F.col("p_size") / 50.0), 9).alias("e"), (F.col("p_size") % 7).alias("m"), F.floor("p_retailprice").alias("f"))


@op("hashes", f"SELECT o_orderkey, md5(CAST(o_orderkey AS VARCHAR)) AS md5, {portable_sql('o_orderkey', 1)} AS h, CAST(bit_count(o_orderkey) AS INTEGER) AS ones FROM orders")
def _hashes(s, d):
    k = F.col("o_orderkey")
    return _t(s, d, "orders", "o_orderkey").select("o_orderkey", F.md5(k.cast("string")).alias("md5"), portable_hash(k, 1).alias("h"), F.bit_count(k).alias("ones"))


@op("arrays", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 6) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def _arrays(s, d):
    e = F.col("embedding")
    return _t(s, d, "embeddings").select("vec_id", F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 6).alias("norm"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"))


_MEAN = "SELECT i, avg(x) AS m FROM (SELECT unnest(range(1, len(embedding) + 1)) AS i, unnest(embedding) AS x FROM embeddings) GROUP BY i"


@op(
    "vector_products",
    f"WITH m AS ({_MEAN}), e AS (SELECT vec_id, unnest(range(1, len(embedding) + 1)) AS i, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings), "
    "p AS (SELECT vec_id, sum(x * m) AS dot, sqrt(sum(x * x)) * sqrt(sum(m * m)) AS norms FROM e JOIN m USING (i) GROUP BY vec_id) SELECT vec_id, round(dot, 5) AS dot, round(dot / norms, 5) AS cosine FROM p",
)
def _products(s, d):
    """Dot product and cosine of each vector with the mean vector, which is one row."""
    e = _t(s, d, "embeddings", "vec_id", "embedding").where("embedding is not null")
    each = e.select(F.posexplode("embedding").alias("i", "x")).groupBy("i").agg(F.avg(F.col("x").cast("double")).alias("m"))
    mean = each.agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "m"))), lambda r: r["m"]).alias("m"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda t, x: t + x)
    both = e.join(F.broadcast(mean)).select("vec_id", dot("embedding", "m").alias("dot"), (F.sqrt(dot("embedding", "embedding")) * F.sqrt(dot("m", "m"))).alias("norms"))
    return both.select("vec_id", F.round("dot", 5).alias("dot"), F.round(F.col("dot") / F.col("norms"), 5).alias("cosine"))


@op("json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def _json(s, d):
    return _t(s, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@op("maps", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views FROM events GROUP BY user_id")
def _maps(s, d):
    counts = _t(s, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("view")), F.lit(0)).alias("views"))


@op("nested", "SELECT conv_id, count(*) AS turns, CAST(sum(length(text)) AS BIGINT) AS chars FROM conversations GROUP BY conv_id")
def _nested(s, d):
    packed = _t(s, d, "conversations").groupBy("conv_id").agg(F.collect_list(F.struct("turn", "role", "text")).alias("turns"))
    return packed.select("conv_id", F.inline("turns")).groupBy("conv_id").agg(F.count(F.lit(1)).alias("turns"), F.sum(F.length("text")).alias("chars"))


@op("decimals", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DECIMAL(28, 2)) AS price FROM lineitem GROUP BY l_returnflag")
def _decimals(s, d):
    return _t(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("price"))


@op("subqueries", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def _subqueries(s, d):
    _t(s, d, "orders").createOrReplaceTempView("stagewise_orders")
    return s.sql("SELECT o_orderkey FROM stagewise_orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM stagewise_orders i WHERE i.o_custkey = o.o_custkey)")


_LAYERS = (
    "WITH RECURSIVE keys AS (SELECT o_orderpriority AS class, count(*) AS n FROM {orders} GROUP BY o_orderpriority), "
    "layer(class, i, rate, expected) AS (SELECT class, 1, CAST(0.125 AS DOUBLE), n * CAST(0.125 AS DOUBLE) FROM keys "
    "UNION ALL SELECT class, i + 1, rate * CAST(0.25 AS DOUBLE), expected * CAST(0.25 AS DOUBLE) FROM layer WHERE i < 8) SELECT class, i, rate, expected FROM layer"
)


@op("recursive", _LAYERS.format(orders="orders"))
def _recursive(s, d):
    """Rate of each layer and the orders of each priority that are expected to pass it; the recursion starts from a row a priority."""
    _t(s, d, "orders", "o_orderpriority").createOrReplaceTempView("stagewise_layered")
    return s.sql(_LAYERS.format(orders="stagewise_layered"))


@op("sql_functions", "SELECT o_orderkey, o_orderpriority = '1-URGENT' AS hit FROM orders")
def _sql(s, d):
    """A registered filter in SQL: a join with its view and its predicate."""
    orders = _t(s, d, "orders", "o_orderkey", "o_orderpriority").withColumn("y", F.col("o_orderpriority") == "1-URGENT")
    orders.createOrReplaceTempView("stagewise_o")
    predicate = register(s, "urgent", X.staged(orders, ["o_orderkey"], "y"))
    return s.sql(f"SELECT o_orderkey, {predicate('o_orderkey')} AS hit FROM stagewise_o LEFT JOIN filter_urgent f ON f.seg = segment_of_urgent(o_orderkey)")


@op("grouped_python", "SELECT o_orderstatus, bit_or(o_custkey) AS words FROM orders GROUP BY o_orderstatus")
def _udaf(s, d):
    """A grouped Arrow function that ORs words, equal to the built-in."""
    import numpy as np
    import pyarrow as pa

    def fold(t: pa.Table) -> pa.Table:
        return pa.table({"o_orderstatus": [t["o_orderstatus"][0].as_py()], "words": [int(np.bitwise_or.reduce(np.asarray(t["words"])))]})

    # combined by task before the groups meet, so a group's size does not matter
    part = _t(s, d, "orders").groupBy("o_orderstatus", F.spark_partition_id().alias("p")).agg(F.bit_or("o_custkey").alias("words"))
    return part.select("o_orderstatus", "words").groupBy("o_orderstatus").applyInArrow(fold, T.StructType([T.StructField("o_orderstatus", T.StringType()), T.StructField("words", T.LongType())]))


_SPOTS = ", ".join(f"{portable_sql('o_custkey', i)} % 4096" for i in range(3))


@op("bloom_aggregate", f"SELECT o_orderstatus, count(DISTINCT b) AS bits FROM (SELECT o_orderstatus, unnest([{_SPOTS}]) AS b FROM orders) GROUP BY o_orderstatus")
def _bloom_aggregate(s, d):
    """A grouped function over series that builds a small Bloom filter, task by task; the words of the tasks are ORed by the built-in."""
    import numpy as np

    @F.pandas_udf("array<long>", functionType=F.PandasUDFType.GROUPED_AGG)
    def bloom(spots):
        cells = np.zeros(4096, np.uint8)
        cells[np.concatenate([np.asarray(x, np.int64) for x in spots])] = 1
        return pack(cells, 1)[:64].tolist()

    spots = F.array(*[F.pmod(portable_hash(F.col("o_custkey"), i), F.lit(4096)) for i in range(3)])
    # groups of a bounded number of rows, so that no group is held whole
    part = _t(s, d, "orders", "o_orderstatus", "o_custkey").groupBy("o_orderstatus", F.spark_partition_id().alias("p"), F.pmod(F.xxhash64("o_custkey"), F.lit(64)).alias("h")).agg(bloom(spots).alias("words"))
    words = part.select("o_orderstatus", F.posexplode("words").alias("i", "w")).groupBy("o_orderstatus", "i").agg(F.bit_or("w").alias("w"))
    return words.groupBy("o_orderstatus").agg(F.sum(F.bit_count("w")).alias("bits"))


@op("arrow_function", "SELECT o_orderkey, (o_orderkey % 1000) * 7 + 1 AS v FROM orders")
def _arrow(s, d):
    """A scalar function over Arrow arrays and an iterator of batches, one after the other."""
    import pyarrow as pa
    import pyarrow.compute as pc

    def seven(x):
        return pc.multiply(x, 7)

    seven.__annotations__ = {"x": pa.Array, "return": pa.Array}  # types, not their names, as the engine reads them
    times_seven = F.arrow_udf(seven, "long")

    def plus_one(batches):
        for b in batches:
            yield pa.record_batch([b.column(0), pc.add(b.column(1), 1)], names=["o_orderkey", "v"])

    o = _t(s, d, "orders", "o_orderkey")
    return o.select("o_orderkey", times_seven(F.col("o_orderkey") % 1000).alias("v")).mapInArrow(plus_one, "o_orderkey long, v long")


@op("explain_filter", "SELECT stage, kind, true AS near_plan FROM (VALUES (0, 'xor'), (1, 'retrieval')) t(stage, kind)")
def _explained(s, d):
    """A table function in SQL that says what each stage of a saved filter takes, planned and actual."""
    orders = _t(s, d, "orders", "o_orderkey", "o_orderpriority").withColumn("y", F.col("o_orderpriority") == "1-URGENT")
    h = X.staged(orders, ["o_orderkey"], "y")
    register_explain(s, "urgent", h)
    return s.sql("SELECT stage, kind, bits BETWEEN 0.8 * planned AND 1.25 * planned AS near_plan FROM explain_filter(TABLE(stages_of_urgent))")
