"""Relational operators over the given tables: each a query with the SQL that must give the same rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from . import sources
from .operators.salted import salted_count, salted_join
from .sources import table

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def _query(sql: str | None):
    def add(f: Query) -> Query:
        _QUERIES[f.__name__] = f
        if sql:
            _SQL[f.__name__] = sql
        return f

    return add


def _orders(spark, d):
    return table(spark, d, "orders")


def _kind(how: str, sql: str) -> None:
    def run(spark, d):
        c = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
        o = _orders(spark, d).select("o_custkey", "o_orderkey").where("o_orderkey % 3 = 0")
        return c.join(o, F.col("c_custkey") == F.col("o_custkey"), how).na.fill(-1).na.fill("none")

    run.__name__ = f"join_{how.replace('left_', '')}" if how.startswith("left_") else f"join_{how}"
    _query(sql)(run)


_O = "(SELECT o_custkey, o_orderkey FROM orders WHERE o_orderkey % 3 = 0)"
for _how, _word in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):
    _kind(_how, f"SELECT coalesce(c_custkey, -1) AS c_custkey, coalesce(c_mktsegment, 'none') AS c_mktsegment, coalesce(o_custkey, -1) AS o_custkey, coalesce(o_orderkey, -1) AS o_orderkey FROM customer {_word} {_O} o ON c_custkey = o_custkey")
_kind("left_semi", f"SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey IN (SELECT o_custkey FROM {_O})")
_kind("left_anti", f"SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM {_O})")


@_query("SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross(spark, d):
    """Two tables of fixed size."""
    return table(spark, d, "region").select("r_name").crossJoin(table(spark, d, "nation").select("n_name"))


@_query("SELECT l_orderkey, l_linenumber, l_partkey, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_extendedprice > 20 * p_retailprice GROUP BY ALL")
def join_theta(spark, d):
    line, part = table(spark, d, "lineitem"), table(spark, d, "part").select("p_partkey", "p_retailprice")
    met = line.join(part, (F.col("l_partkey") == F.col("p_partkey")) & (F.col("l_extendedprice") > 20 * F.col("p_retailprice")))
    return met.groupBy("l_orderkey", "l_linenumber", "l_partkey").agg(F.count("*").alias("n"))


@_query("""SELECT a.event_id, count(*) AS near FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id
  AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000 GROUP BY 1""")
def join_range(spark, d):
    """Events of the same user within an hour: hours as equality keys, each event looking into its own and both neighbours."""
    e = table(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour = 3_600_000_000
    b = e.select(F.col("event_id").alias("other"), F.col("user_id").alias("u"), F.col("t").alias("s"), F.floor(F.col("t") / hour).alias("h"))
    a = e.withColumn("g", F.explode(F.sequence(F.floor(F.col("t") / hour) - 1, F.floor(F.col("t") / hour) + 1)))
    met = a.join(b, (F.col("user_id") == F.col("u")) & (F.col("g") == F.col("h")) & (F.col("event_id") != F.col("other")) & (F.abs(F.col("t") - F.col("s")) <= hour))
    return met.groupBy("event_id").agg(F.count("*").alias("near"))


@_query("""SELECT e.event_id, coalesce(p.event_id, -1) AS purchase FROM events e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) p
  ON e.user_id = p.user_id AND e.ts > p.ts""")
def join_asof(spark, d):
    """Each event's last earlier purchase of the same user, by one window instead of a range join."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    earlier = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(Window.unboundedPreceding, -1)
    bought = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    return e.select("event_id", F.coalesce(F.max(bought).over(earlier)["event_id"], F.lit(-1)).alias("purchase"))


@_query("""WITH p AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem WHERE l_partkey < 200)
  SELECT a.l_partkey AS part, b.l_partkey AS other, count(*) AS n FROM p a JOIN p b USING (l_orderkey) WHERE a.l_partkey < b.l_partkey GROUP BY 1, 2""")
def join_self_two_hop(spark, d):
    """Pairs of low-numbered parts that orders hold together."""
    p = table(spark, d, "lineitem").where("l_partkey < 200").select("l_orderkey", F.col("l_partkey").alias("part")).distinct()
    return p.join(p.withColumnRenamed("part", "other"), "l_orderkey").where("part < other").groupBy("part", "other").agg(F.count("*").alias("n"))


@_query("SELECT o_orderkey, x.i AS i, x.i * o_custkey AS v FROM orders, LATERAL (SELECT unnest(range(0, o_orderkey % 3)) AS i) x")
def join_lateral(spark, d):
    n = F.col("o_orderkey") % 3
    rows = _orders(spark, d).where(n > 0).select("o_orderkey", "o_custkey", F.explode(F.sequence(F.lit(0).cast("long"), n - 1)).alias("i"))
    return rows.select("o_orderkey", "i", (F.col("i") * F.col("o_custkey")).alias("v"))


@_query("SELECT event_type, count(*) AS n, CAST(sum(c_custkey) AS BIGINT) AS total FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def join_salted(spark, d):
    met = salted_join(table(spark, d, "events").select("user_id", "event_type"), table(spark, d, "customer").select(F.col("c_custkey").alias("user_id")), "user_id", 8)
    return met.groupBy("event_type").agg(F.count("*").alias("n"), F.sum("user_id").alias("total"))


@_query("SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, max(l_partkey) AS top FROM lineitem WHERE l_shipdate < TIMESTAMP '1998-09-02' GROUP BY 1, 2")
def agg_basic(spark, d):
    return table(spark, d, "lineitem").where("l_shipdate < timestamp '1998-09-02'").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"), F.max("l_partkey").alias("top"))


@_query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1")
def agg_distinct(spark, d):
    return table(spark, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders"))


@_query("SELECT TRUE AS near FROM region LIMIT 1")
def agg_approx_distinct(spark, d):
    """Whether the sketch lies within a tenth of the exact count."""
    n = table(spark, d, "lineitem").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("a"), F.countDistinct("l_orderkey").alias("b"))
    return n.select((F.abs(F.col("a") - F.col("b")) * 10 <= F.col("b")).alias("near"))


_SEG = "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY"


@_query(f"{_SEG} ROLLUP (o_orderstatus, o_orderpriority)")
def agg_rollup(spark, d):
    return _orders(spark, d).rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@_query(f"{_SEG} CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark, d):
    return _orders(spark, d).cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@_query(f"{_SEG} GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def agg_grouping_sets(spark, d):
    return _orders(spark, d).groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@_query("SELECT user_id % 10 AS u, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'purchase') AS purchase FROM events GROUP BY 1")
def agg_pivot(spark, d):
    pivot = table(spark, d, "events").groupBy((F.col("user_id") % 10).alias("u")).pivot("event_type", ["click", "purchase"]).agg(F.count("event_id"))
    return pivot.na.fill(0)


@_query("SELECT o_custkey, arg_min(o_orderkey, (o_orderdate, o_orderkey)) AS first, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS last FROM orders GROUP BY 1")
def agg_minmax_by(spark, d):
    at = F.struct("o_orderdate", "o_orderkey")
    return _orders(spark, d).groupBy("o_custkey").agg(F.min_by("o_orderkey", at).alias("first"), F.max_by("o_orderkey", at).alias("last"))


@_query("SELECT l_returnflag, CAST(quantile_disc(l_quantity, 0.5) AS BIGINT) AS mid FROM lineitem GROUP BY 1")
def agg_percentile(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.expr("percentile_disc(0.5) within group (order by l_quantity)").cast("long").alias("mid"))


@_query("SELECT l_suppkey, count(*) FILTER (WHERE l_quantity > 40) AS big, bool_or(l_returnflag = 'R') AS some, bool_and(l_quantity > 0) AS every FROM lineitem GROUP BY 1")
def agg_filter(spark, d):
    r = table(spark, d, "lineitem").groupBy("l_suppkey")
    return r.agg(F.count_if(F.col("l_quantity") > 40).alias("big"), F.bool_or(F.col("l_returnflag") == "R").alias("some"), F.bool_and(F.col("l_quantity") > 0).alias("every"))


@_query("SELECT c_nationkey, string_agg(DISTINCT c_mktsegment, ',' ORDER BY c_mktsegment) AS segments FROM customer GROUP BY 1")
def agg_collect(spark, d):
    return table(spark, d, "customer").groupBy("c_nationkey").agg(F.array_join(F.array_sort(F.collect_set("c_mktsegment")), ",").alias("segments"))


@_query("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def agg_salted(spark, d):
    return salted_count(table(spark, d, "events"), "event_type", 16)


_W = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"


def _customer():
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


@_query(f"SELECT o_orderkey, CAST(row_number() {_W}) AS INTEGER) AS rn, CAST(rank() {_W}) AS INTEGER) AS rk, CAST(dense_rank() {_W}) AS INTEGER) AS dr FROM orders")
def win_rank(spark, d):
    w = _customer()
    return _orders(spark, d).select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


@_query(f"SELECT o_orderkey, CAST(ntile(4) {_W}) AS INTEGER) AS q FROM orders")
def win_ntile(spark, d):
    return _orders(spark, d).select("o_orderkey", F.ntile(4).over(_customer()).alias("q"))


@_query(f"SELECT o_orderkey, lag(o_orderkey, 1, -1) {_W}) AS before, lead(o_orderkey, 2, -1) {_W}) AS after FROM orders")
def win_lag_lead(spark, d):
    return _orders(spark, d).select("o_orderkey", F.lag("o_orderkey", 1, -1).over(_customer()).alias("before"), F.lead("o_orderkey", 2, -1).over(_customer()).alias("after"))


@_query(f"SELECT o_orderkey, CAST(sum(o_orderkey) {_W}) AS BIGINT) AS total FROM orders")
def win_running(spark, d):
    return _orders(spark, d).select("o_orderkey", F.sum("o_orderkey").over(_customer()).alias("total"))


@_query(f"SELECT o_orderkey, CAST(sum(o_orderkey) {_W} ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS total FROM orders")
def win_rows_frame(spark, d):
    return _orders(spark, d).select("o_orderkey", F.sum("o_orderkey").over(_customer().rowsBetween(-2, 1)).alias("total"))


@_query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM events")
def win_range_frame(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000)).rangeBetween(-86400, 0)
    return table(spark, d, "events").select("event_id", F.count("*").over(w).alias("day"))


@_query(f"SELECT o_orderkey, first(o_orderkey) {_W}) AS first, last(o_orderkey) {_W} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM orders")
def win_first_last(spark, d):
    whole = _customer().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _orders(spark, d).select("o_orderkey", F.first("o_orderkey").over(_customer()).alias("first"), F.last("o_orderkey").over(whole).alias("last"))


@_query("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def win_topk_per_group(spark, d):
    rn = F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return _orders(spark, d).withColumn("rn", rn).where("rn <= 2").select("o_custkey", "o_orderkey")


@_query("SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, l_partkey LIMIT 20")
def sort_topk_hubs(spark, d):
    return table(spark, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_partkey").limit(20)


@_query("SELECT o_orderkey FROM orders ORDER BY o_orderdate, o_orderkey LIMIT 10 OFFSET 25")
def sort_limit_offset(spark, d):
    return _orders(spark, d).orderBy("o_orderdate", "o_orderkey").offset(25).limit(10).select("o_orderkey")


_A, _B = "SELECT o_custkey % 500 AS k FROM orders WHERE o_orderkey % 2 = 0", "SELECT o_custkey % 500 AS k FROM orders WHERE o_orderkey % 3 = 0"


def _halves(spark, d):
    k = (F.col("o_custkey") % 500).alias("k")
    return _orders(spark, d).where("o_orderkey % 2 = 0").select(k), _orders(spark, d).where("o_orderkey % 3 = 0").select(k)


def _set(name: str, sql: str, f: Callable[[DataFrame, DataFrame], DataFrame]) -> None:
    def run(spark, d):
        return f(*_halves(spark, d))

    run.__name__ = f"set_{name}"
    _query(sql)(run)


_set("union", f"{_A} UNION {_B}", lambda a, b: a.union(b).distinct())
_set("union_all", f"{_A} UNION ALL {_B}", lambda a, b: a.unionByName(b))
_set("intersect", f"{_A} INTERSECT {_B}", lambda a, b: a.intersect(b))
_set("intersect_all", f"{_A} INTERSECT ALL {_B}", lambda a, b: a.intersectAll(b))
_set("except", f"{_A} EXCEPT {_B}", lambda a, b: a.subtract(b))
_set("except_all", f"{_A} EXCEPT ALL {_B}", lambda a, b: a.exceptAll(b))
_set("distinct", f"SELECT DISTINCT k FROM ({_A})", lambda a, b: a.dropDuplicates())


@_query("""SELECT p_partkey, upper(p_name) AS u, substr(p_type, 1, 3) AS s, length(p_name) AS n, replace(p_brand, '#', '-') AS b, md5(p_name) AS h, lpad(CAST(p_size AS VARCHAR), 4, '0') AS p,
  regexp_extract(p_brand, '[0-9]+') AS d, string_split(p_name, ' ')[1] AS w, CAST(instr(p_name, 'a') AS INTEGER) AS i FROM part""")
def fn_string(spark, d):
    c = F.col
    return table(spark, d, "part").select(
        "p_partkey", F.upper("p_name").alias("u"), F.substring("p_type", 1, 3).alias("s"), F.length("p_name").cast("long").alias("n"), F.regexp_replace("p_brand", "#", "-").alias("b"), F.md5(c("p_name").cast("binary")).alias("h"),
        F.lpad(c("p_size").cast("string"), 4, "0").alias("p"), F.regexp_extract("p_brand", "[0-9]+", 0).alias("d"), F.split("p_name", " ")[0].alias("w"), F.instr("p_name", "a").alias("i"),
    )


@_query("""SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(epoch(date_trunc('month', o_orderdate)) AS BIGINT) AS t, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS n,
  CAST(epoch(o_orderdate + INTERVAL 2 MONTH) AS BIGINT) AS a FROM orders""")
def fn_date(spark, d):
    date = F.col("o_orderdate")
    return _orders(spark, d).select(
        "o_orderkey", F.year(date).cast("long").alias("y"), F.month(date).cast("long").alias("m"), F.unix_seconds(F.date_trunc("month", date).cast("timestamp")).alias("t"), F.datediff(date, F.lit("1992-01-01")).cast("long").alias("n"),
        F.unix_seconds((date + F.expr("interval 2 months")).cast("timestamp")).alias("a"),
    )


@_query("SELECT p_partkey, CAST(ceil(p_size / 7) AS BIGINT) AS c, CAST(floor(p_size / 7) AS BIGINT) AS f, p_size % 7 AS m, p_partkey & 15 AS b, greatest(p_size, 10) AS g, round(sqrt(p_size), 6) AS s, round(log2(p_size), 6) AS l FROM part")
def fn_math(spark, d):
    s = F.col("p_size")
    return table(spark, d, "part").select("p_partkey", F.ceil(s / 7).alias("c"), F.floor(s / 7).alias("f"), (s % 7).alias("m"), F.col("p_partkey").bitwiseAND(15).alias("b"), F.greatest(s, F.lit(10)).alias("g"), F.round(F.sqrt(s), 6).alias("s"), F.round(F.log2(s), 6).alias("l"))


@_query("""WITH a AS (SELECT l_orderkey, list_sort(list(l_partkey)) AS p FROM lineitem GROUP BY 1)
  SELECT l_orderkey, len(p) AS n, p[1] AS first, CAST(list_sum(p) AS BIGINT) AS total, coalesce(CAST(list_sum(list_filter(p, lambda x: x % 2 = 0)) AS BIGINT), 0) AS even, len(list_distinct(p)) AS kinds FROM a""")
def fn_array(spark, d):
    a = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_list("l_partkey")).alias("p"))
    add = lambda c: F.aggregate(c, F.lit(0).cast("long"), lambda s, x: s + x)
    even = F.filter("p", lambda x: x % 2 == 0)
    return a.select("l_orderkey", F.size("p").cast("long").alias("n"), F.element_at("p", 1).alias("first"), add("p").alias("total"), add(even).alias("even"), F.size(F.array_distinct("p")).cast("long").alias("kinds"))


@_query("SELECT event_id, CAST(len(json_keys(props)) AS BIGINT) AS n, json_keys(props)[1] AS k, json_extract_string(props, '$.' || json_keys(props)[1]) AS v FROM events")
def fn_json(spark, d):
    """Number of properties, the first one's name and its value as text."""
    keys = F.json_object_keys("props")
    return table(spark, d, "events").select("event_id", F.size(keys).cast("long").alias("n"), keys[0].alias("k"), F.from_json("props", "map<string,string>")[keys[0]].alias("v"))


@_query("SELECT o_orderstatus, list_sort(map_keys(m))[1] AS k, CAST(list_sum(map_values(m)) AS BIGINT) AS n FROM (SELECT o_orderstatus, map_from_entries(list((o_orderpriority, n))) AS m FROM (SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY 1, 2) GROUP BY 1)")
def fn_map(spark, d):
    counts = _orders(spark, d).groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))
    m = counts.groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m"))
    return m.select("o_orderstatus", F.array_sort(F.map_keys("m"))[0].alias("k"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda s, x: s + x).alias("n"))


@_query("SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal BETWEEN 0 AND 5000 THEN 'some' ELSE 'much' END AS k, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS s, c_mktsegment IN ('AUTOMOBILE', 'MACHINERY') AS i, c_name LIKE '%9' AS l FROM customer")
def fn_conditional(spark, d):
    b, s = F.col("c_acctbal"), F.col("c_mktsegment")
    return table(spark, d, "customer").select("c_custkey", F.when(b < 0, "debt").when(b.between(0, 5000), "some").otherwise("much").alias("k"), F.coalesce(F.nullif(s, F.lit("BUILDING")), F.lit("none")).alias("s"), s.isin("AUTOMOBILE", "MACHINERY").alias("i"), F.col("c_name").like("%9").alias("l"))


@F.pandas_udf(LongType())
def _cost(quantity: pd.Series, size: pd.Series) -> pd.Series:
    return (quantity * 3 + size).astype("int64")


@F.arrow_udf(LongType())
def _arrow_cost(quantity, size):
    import pyarrow.compute as pc

    return pc.add(pc.multiply(quantity.cast("int64"), 3), size.cast("int64"))


_COST = "SELECT l_partkey, CAST(sum(CAST(l_quantity AS BIGINT) * 3 + p_size) AS BIGINT) AS cost FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1"


def _costs(spark, d, f):
    line = table(spark, d, "lineitem").join(table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return line.groupBy("l_partkey").agg(F.sum(f("l_quantity", "p_size")).alias("cost"))


@_query(_COST)
def udf_pandas(spark, d):
    """An edge cost that a user supplies, in batches."""
    line = table(spark, d, "lineitem").join(table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return line.select("l_partkey", _cost("l_quantity", "p_size").alias("c")).groupBy("l_partkey").agg(F.sum("c").alias("cost"))


@_query(_COST)
def udf_arrow(spark, d):
    line = table(spark, d, "lineitem").join(table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return line.select("l_partkey", _arrow_cost("l_quantity", "p_size").alias("c")).groupBy("l_partkey").agg(F.sum("c").alias("cost"))


@_query(_COST)
def udf_sql(spark, d):
    """The same cost as a SQL function of the session."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_cost(q DOUBLE, s INT) RETURNS BIGINT RETURN CAST(q AS BIGINT) * 3 + s")
    return _costs(spark, d, lambda q, s: F.expr(f"edge_cost({q}, {s})"))


def _round_trip(kind: str) -> None:
    def run(spark, d):
        edges = table(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst")).agg(F.count("*").alias("w"))
        folder = (spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/.checkpoints").rstrip("/")
        path = f"{folder}/edges-{kind}-{uuid.uuid4().hex}"
        sources.write_edges(edges, path, kind)
        return sources.read_edges(spark, path, kind)

    run.__name__ = f"src_{kind}"
    _query("SELECT l_suppkey AS src, l_partkey AS dst, count(*) AS w FROM lineitem GROUP BY 1, 2")(run)


for _k in ("csv", "json", "orc", "parquet", "arcs", "pairs"):
    _round_trip(_k)


@_query("SELECT l_suppkey AS src, count(*) AS n FROM lineitem GROUP BY 1")
def sink_bucketed(spark, d):
    """Aggregation in place over a bucketed table."""
    edges = table(spark, d, "lineitem").select(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"))
    name = f"edges_{uuid.uuid4().hex}"
    sources.write_bucketed(edges, name, 8)
    return spark.table(name).groupBy("src").agg(F.count("*").alias("n"))


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
