"""Relational operators, sources, sinks and functions that a user of the methods needs, one small query each."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from thriftline.functions.money import cents, day, quantity
from thriftline.operators import costmodel, keycodec, placement, relational, topk_merge
from thriftline.sources import io
from thriftline.sources.catalog import load

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


_N = "CAST(count(*) AS BIGINT) AS n"
_n = lambda: F.count("*").alias("n")

# ---- sources and sinks ----


@query("scan_parquet", "SELECT s_suppkey, s_name, s_nationkey FROM supplier")
def scan_parquet(spark, sf_dir):
    return load(spark, sf_dir, "supplier").select("s_suppkey", "s_name", "s_nationkey")


@query("scan_pruned", "SELECT l_orderkey, CAST(l_quantity AS BIGINT) AS qty FROM lineitem WHERE l_shipdate >= TIMESTAMP '2001-06-01' AND l_returnflag = 'R'")
def scan_pruned(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").where((F.col("l_shipdate") >= day("2001-06-01")) & (F.col("l_returnflag") == "R")).select("l_orderkey", quantity().alias("qty"))


for _kind in ("csv", "json", "orc"):

    @query(f"scan_{_kind}_roundtrip", "SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer")
    def roundtrip(spark, sf_dir, kind=_kind):
        return io.round_trip(load(spark, sf_dir, "customer"), kind)


@query("scan_text_roundtrip", "SELECT CAST(c_custkey AS VARCHAR) || '|' || c_name AS value FROM customer")
def scan_text(spark, sf_dir):
    return io.round_trip(load(spark, sf_dir, "customer").select(F.concat_ws("|", "c_custkey", "c_name").alias("value")), "text")


@query("scan_partition_discovered", f"SELECT o_orderstatus, {_N}, CAST(max(o_orderkey) AS BIGINT) AS last FROM orders WHERE o_orderstatus <> 'P' GROUP BY 1")
def scan_partition_discovered(spark, sf_dir):
    path = io.partitioned(load(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus"), "o_orderstatus")[1]
    # No schema is given: the column comes from the folders' names, and the filter leaves whole folders out.
    return spark.read.parquet(path).where("o_orderstatus <> 'P'").groupBy("o_orderstatus").agg(_n(), F.max("o_orderkey").alias("last"))


@query("scan_sampled", "SELECT o_orderkey, o_custkey FROM orders WHERE (o_orderkey % 2147483648) * 2654435761 % 1000 < 50")
def scan_sampled(spark, sf_dir):
    """A sampling operator: a twentieth of the keys by their hash, the same rows on every run and every placement."""
    return load(spark, sf_dir, "orders").where(costmodel.in_pilot("o_orderkey", 50)).select("o_orderkey", "o_custkey")


@query("sink_partitioned_roundtrip", "SELECT o_orderkey, o_orderkey % 4 AS shard FROM orders WHERE o_orderkey % 4 = 2")
def sink_partitioned(spark, sf_dir):
    rows = load(spark, sf_dir, "orders").select("o_orderkey", placement.key_shard("o_orderkey", 4).alias("shard"))
    return io.partitioned(rows, "shard")[0].where("shard = 2")


@query("sink_bucketed_roundtrip", f"SELECT o_orderpriority, {_N} FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def sink_bucketed(spark, sf_dir):
    import uuid

    tag = uuid.uuid4().hex[:12]
    lines = placement.store_bucketed(load(spark, sf_dir, "lineitem").select("l_orderkey"), f"lines_{tag}", "l_orderkey", 8)
    orders = placement.store_bucketed(load(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority"), f"orders_{tag}", "o_orderkey", 8)
    return lines.join(orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(_n())


# ---- projections and filters ----


@query("proj_money", "SELECT o_orderkey, CAST(round(o_totalprice*100) AS BIGINT) AS total_c, CASE WHEN o_totalprice >= 250000 THEN 'large' WHEN o_totalprice >= 100000 THEN 'middle' ELSE 'small' END AS size FROM orders")
def proj_money(spark, sf_dir):
    return load(spark, sf_dir, "orders").select("o_orderkey", cents("o_totalprice").alias("total_c"), F.when(F.col("o_totalprice") >= 250000, "large").when(F.col("o_totalprice") >= 100000, "middle").otherwise("small").alias("size"))


@query("filter_compound", "SELECT p_partkey FROM part WHERE (p_size BETWEEN 5 AND 15 AND p_type <> 'PROMO') OR p_retailprice < 905")
def filter_compound(spark, sf_dir):
    return load(spark, sf_dir, "part").where((F.col("p_size").between(5, 15) & (F.col("p_type") != "PROMO")) | (F.col("p_retailprice") < 905)).select("p_partkey")


@query("filter_in", "SELECT c_custkey FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')")
def filter_in(spark, sf_dir):
    return load(spark, sf_dir, "customer").where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY")).select("c_custkey")


@query("filter_like", "SELECT s_suppkey FROM supplier WHERE s_name LIKE '%7_'")
def filter_like(spark, sf_dir):
    return load(spark, sf_dir, "supplier").where(F.col("s_name").like("%7_")).select("s_suppkey")


@query("filter_date_range", f"SELECT o_orderstatus, {_N} FROM orders WHERE o_orderdate >= TIMESTAMP '1999-01-01' AND o_orderdate < TIMESTAMP '1999-02-01' GROUP BY 1")
def filter_date_range(spark, sf_dir):
    return load(spark, sf_dir, "orders").where((F.col("o_orderdate") >= day("1999-01-01")) & (F.col("o_orderdate") < day("1999-02-01"))).groupBy("o_orderstatus").agg(_n())


@query("filter_null_safe", f"SELECT quality IS NOT DISTINCT FROM NULL AS unknown, {_N} FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1")
def filter_null_safe(spark, sf_dir):
    joined = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id", "left")
    return joined.groupBy(F.col("quality").eqNullSafe(F.lit(None)).alias("unknown")).agg(_n())


# ---- joins ----


def _whole_join(name: str, how: str, sql: str):
    @query(f"join_{name}_whole", sql)
    def join(spark, sf_dir):
        return load(spark, sf_dir, "documents").select("doc_id", "lang").join(load(spark, sf_dir, "labels"), "doc_id", how)


_whole_join("inner", "inner", "SELECT doc_id, lang, quality, toxic FROM documents JOIN labels USING (doc_id)")
_whole_join("left", "left", "SELECT doc_id, lang, quality, toxic FROM documents LEFT JOIN labels USING (doc_id)")
_whole_join("right", "right", "SELECT doc_id, lang, quality, toxic FROM documents RIGHT JOIN labels USING (doc_id)")
_whole_join("full", "full", "SELECT doc_id, lang, quality, toxic FROM documents FULL JOIN labels USING (doc_id)")
_whole_join("semi", "left_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
_whole_join("anti", "left_anti", "SELECT doc_id, lang FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")


def _hinted(name: str, hint: str):
    @query(f"join_{name}", f"SELECT c_mktsegment, {_N} FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
    def join(spark, sf_dir):
        return load(spark, sf_dir, "orders").join(load(spark, sf_dir, "customer").hint(hint), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(_n())


for _name, _hint in (("broadcast", "broadcast"), ("merge", "merge"), ("hash", "shuffle_hash")):
    _hinted(_name, _hint)


@query("join_cross_tiny", "SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross_tiny(spark, sf_dir):
    return placement.replicate(load(spark, sf_dir, "region")).crossJoin(load(spark, sf_dir, "nation")).select("r_name", "n_name")


@query("join_theta", "SELECT n_nationkey, CAST(count(r_regionkey) AS BIGINT) AS n FROM nation LEFT JOIN region ON r_regionkey < n_regionkey GROUP BY 1")
def join_theta(spark, sf_dir):
    return load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("r_regionkey") < F.col("n_regionkey"), "left").groupBy("n_nationkey").agg(F.count("r_regionkey").alias("n"))


_ALL_SPANS = "(SELECT ts AS start_ts, ts + INTERVAL 600 SECOND AS stop_ts, event_id AS span_id FROM events WHERE event_type = 'error')"


@query("join_interval_all", f"SELECT span_id, {_N} FROM events JOIN {_ALL_SPANS} ON ts >= start_ts AND ts < stop_ts GROUP BY 1")
def join_interval_all(spark, sf_dir):
    events = load(spark, sf_dir, "events")
    spans = events.where("event_type = 'error'").select(F.col("ts").alias("start_ts"), (F.col("ts") + F.expr("interval 600 seconds")).alias("stop_ts"), F.col("event_id").alias("span_id"))
    return relational.interval(events.select("ts"), "ts", spans, "start_ts", "stop_ts", 600).groupBy("span_id").agg(_n())


@query("join_asof", """SELECT event_id, user_id, (SELECT max(v.event_id) FROM events v WHERE v.user_id = e.user_id AND v.event_type = 'view' AND v.ts <= e.ts) AS view_id FROM events e WHERE event_type = 'purchase'""")
def join_asof(spark, sf_dir):
    events = load(spark, sf_dir, "events")
    bought = events.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    views = events.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("view_id")).withColumnRenamed("ts", "view_ts")
    return relational.asof(bought, views, "user_id", "ts", "view_ts", ["view_id"]).select("event_id", "user_id", "view_id")


@query("join_lateral", "SELECT n_nationkey, c_custkey FROM (SELECT n_nationkey, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM nation JOIN customer ON c_nationkey = n_nationkey) WHERE r <= 2")
def join_lateral(spark, sf_dir):
    load(spark, sf_dir, "customer").createOrReplaceTempView("_customer")
    load(spark, sf_dir, "nation").createOrReplaceTempView("_nation")
    return spark.sql("select n_nationkey, c_custkey from _nation, lateral (select c_custkey from _customer where c_nationkey = n_nationkey order by c_acctbal desc, c_custkey limit 2)")


@query("join_salted", f"SELECT p_brand, {_N} FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def join_salted(spark, sf_dir):
    joined = relational.salted(load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey"), load(spark, sf_dir, "part").select("p_partkey", "p_brand"), ("l_partkey", "p_partkey"))
    return joined.groupBy("p_brand").agg(_n())


# ---- aggregates ----

_PRICE = "CAST(round(o_totalprice*100) AS BIGINT)"


def _agg(name: str, sql: str, f):
    query(f"agg_{name}", sql)(f)


_agg("basic", f"SELECT o_orderstatus, {_N}, CAST(sum({_PRICE}) AS BIGINT) AS s, min({_PRICE}) AS lo, max({_PRICE}) AS hi, CAST(sum({_PRICE}) AS DOUBLE) / count(*) AS mean FROM orders GROUP BY 1",
     lambda spark, sf_dir: load(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(_n(), F.sum(cents("o_totalprice")).alias("s"), F.min(cents("o_totalprice")).alias("lo"), F.max(cents("o_totalprice")).alias("hi"), (F.sum(cents("o_totalprice")).cast("double") / F.count("*")).alias("mean")))
_agg("distinct", "SELECT o_orderpriority, CAST(count(DISTINCT o_custkey) AS BIGINT) AS n FROM orders GROUP BY 1", lambda spark, sf_dir: load(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.count_distinct("o_custkey").alias("n")))
_agg("filter", "SELECT o_orderpriority, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS f FROM orders GROUP BY 1", lambda spark, sf_dir: load(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("f")))
_agg("having", f"SELECT o_custkey, {_N} FROM orders GROUP BY 1 HAVING count(*) > 15", lambda spark, sf_dir: load(spark, sf_dir, "orders").groupBy("o_custkey").agg(_n()).where("n > 15"))
_agg("rollup", f"SELECT o_orderstatus, o_orderpriority, {_N} FROM orders GROUP BY ROLLUP (1, 2)", lambda spark, sf_dir: load(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority").agg(_n()))
_agg("cube", f"SELECT o_orderstatus, o_orderpriority, {_N} FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)", lambda spark, sf_dir: load(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(_n()))
_agg("grouping_sets", f"SELECT l_returnflag, l_linestatus, {_N} FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
     lambda spark, sf_dir: load(spark, sf_dir, "lineitem").groupingSets([("l_returnflag",), ("l_linestatus",), ()], "l_returnflag", "l_linestatus").agg(_n()))
_agg("pivot", "SELECT o_orderpriority, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS \"F\", CAST(count(*) FILTER (o_orderstatus = 'O') AS BIGINT) AS \"O\" FROM orders GROUP BY 1",
     lambda spark, sf_dir: load(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1))).na.fill(0))
_agg("max_by", "SELECT c_mktsegment, arg_max(c_custkey, CAST(round(c_acctbal*100) AS BIGINT) * 1000000 - c_custkey) AS best FROM customer GROUP BY 1", lambda spark, sf_dir: load(spark, sf_dir, "customer").groupBy("c_mktsegment").agg(F.max_by("c_custkey", cents("c_acctbal") * 1000000 - F.col("c_custkey")).alias("best")))
_agg("two_level", f"SELECT n_orders, {_N} FROM (SELECT o_custkey, CAST(count(*) AS BIGINT) AS n_orders FROM orders GROUP BY 1) GROUP BY 1", lambda spark, sf_dir: load(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n_orders")).groupBy("n_orders").agg(_n()))
_agg("median", "SELECT o_orderstatus, quantile_cont(o_totalprice, 0.5) AS mid FROM orders GROUP BY 1", lambda spark, sf_dir: load(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.percentile("o_totalprice", F.lit(0.5)).alias("mid")))
query("agg_approx_within", "SELECT CAST(count(DISTINCT o_custkey) AS BIGINT) AS exact, true AS within FROM orders")(
    lambda spark, sf_dir: load(spark, sf_dir, "orders").agg(F.approx_count_distinct("o_custkey", 0.02).alias("a"), F.count_distinct("o_custkey").alias("exact")).select("exact", (F.abs(F.col("a") - F.col("exact")) <= 0.06 * F.col("exact")).alias("within"))
)
query("agg_approx_distinct")(lambda spark, sf_dir: load(spark, sf_dir, "orders").agg(F.approx_count_distinct("o_custkey", 0.02).alias("approx"), F.count_distinct("o_custkey").alias("exact")))

# ---- windows ----


@query("win_distribution", """SELECT c_custkey, percent_rank() OVER (PARTITION BY c_mktsegment ORDER BY CAST(round(c_acctbal*100) AS BIGINT)) AS share_below, cume_dist() OVER (PARTITION BY c_mktsegment ORDER BY CAST(round(c_acctbal*100) AS BIGINT)) AS share_up_to FROM customer""")
def win_distribution(spark, sf_dir):
    rows = load(spark, sf_dir, "customer").withColumn("c", cents("c_acctbal"))
    by = W.partitionBy("c_mktsegment").orderBy("c")
    return rows.select("c_custkey", F.percent_rank().over(by).alias("share_below"), F.cume_dist().over(by).alias("share_up_to"))


_W = "OVER (PARTITION BY c_mktsegment ORDER BY CAST(round(c_acctbal*100) AS BIGINT) DESC, c_custkey)"


def _win(name: str, sql: str, columns):
    @query(f"win_{name}", f"SELECT c_custkey, {sql} FROM customer")
    def win(spark, sf_dir):
        order = W.partitionBy("c_mktsegment").orderBy(F.col("bal").desc(), "c_custkey")
        return load(spark, sf_dir, "customer").withColumn("bal", cents("c_acctbal")).select("c_custkey", *[c.alias(n) for n, c in columns(order).items()])


_B = "CAST(round(c_acctbal*100) AS BIGINT)"
_win("rank", f"CAST(row_number() {_W} AS BIGINT) AS rn, CAST(rank() OVER (PARTITION BY c_mktsegment ORDER BY c_nationkey) AS BIGINT) AS rk, CAST(dense_rank() OVER (PARTITION BY c_mktsegment ORDER BY c_nationkey) AS BIGINT) AS dr, percent_rank() {_W} AS pr, cume_dist() {_W} AS cd",
     lambda o: {"rn": F.row_number().over(o).cast("long"), "rk": F.rank().over(W.partitionBy("c_mktsegment").orderBy("c_nationkey")).cast("long"), "dr": F.dense_rank().over(W.partitionBy("c_mktsegment").orderBy("c_nationkey")).cast("long"), "pr": F.percent_rank().over(o), "cd": F.cume_dist().over(o)})
_win("ntile", f"CAST(ntile(7) {_W} AS BIGINT) AS tile", lambda o: {"tile": F.ntile(7).over(o).cast("long")})
_win("lag", f"lag({_B}, 1) {_W} AS before, lead({_B}, 2) {_W} AS after", lambda o: {"before": F.lag("bal", 1).over(o), "after": F.lead("bal", 2).over(o)})
_win("running", f"CAST(sum({_B}) {_W[:-1]} ROWS UNBOUNDED PRECEDING) AS BIGINT) AS total", lambda o: {"total": F.sum("bal").over(o.rowsBetween(W.unboundedPreceding, 0))})
_win("moving", f"CAST(sum({_B}) {_W[:-1]} ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS around", lambda o: {"around": F.sum("bal").over(o.rowsBetween(-2, 2))})
_win("range_frame", "CAST(count(*) OVER (PARTITION BY c_mktsegment ORDER BY c_custkey RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS BIGINT) AS near", lambda o: {"near": F.count("*").over(W.partitionBy("c_mktsegment").orderBy("c_custkey").rangeBetween(-100, 0))})
_win("first_last", f"first_value(c_custkey) {_W} AS top, last_value(c_custkey) {_W[:-1]} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS bottom", lambda o: {"top": F.first("c_custkey").over(o), "bottom": F.last("c_custkey").over(o.rowsBetween(W.unboundedPreceding, W.unboundedFollowing))})

# ---- order, sets, subqueries ----

query("sort_limit", "SELECT o_orderkey FROM orders ORDER BY o_orderdate DESC, o_orderkey LIMIT 25")(lambda spark, sf_dir: load(spark, sf_dir, "orders").orderBy(F.col("o_orderdate").desc(), "o_orderkey").limit(25).select("o_orderkey"))
query("sort_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 40")(lambda spark, sf_dir: load(spark, sf_dir, "orders").orderBy("o_orderkey").offset(40).limit(10).select("o_orderkey"))


def _status_set(name: str, sql: str, f):
    @query(f"set_{name}_status", sql)
    def run(spark, sf_dir):
        return f(*(load(spark, sf_dir, "orders").where(F.col("o_orderstatus") == status).select(F.col("o_custkey").alias("k")) for status in ("F", "O")))


_T = ("SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F'", "SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'O'")
_status_set("union", f"{_T[0]} UNION {_T[1]}", lambda a, b: a.union(b).distinct())
_status_set("union_all", f"SELECT k, {_N} FROM ({_T[0]} UNION ALL {_T[1]}) GROUP BY 1", lambda a, b: a.unionAll(b).groupBy("k").agg(_n()))
_status_set("intersect", f"{_T[0]} INTERSECT {_T[1]}", lambda a, b: a.intersect(b))
_status_set("intersect_all", f"{_T[0]} INTERSECT ALL {_T[1]}", lambda a, b: a.intersectAll(b))
_status_set("except", f"{_T[0]} EXCEPT {_T[1]}", lambda a, b: a.subtract(b))
_status_set("except_all", f"{_T[0]} EXCEPT ALL {_T[1]}", lambda a, b: a.exceptAll(b))


@query("sub_scalar", "SELECT s_suppkey FROM supplier WHERE s_acctbal > (SELECT quantile_cont(s_acctbal, 0.9) FROM supplier)")
def sub_scalar(spark, sf_dir):
    suppliers = load(spark, sf_dir, "supplier")
    return suppliers.where(F.col("s_acctbal") > suppliers.select(F.percentile("s_acctbal", F.lit(0.9))).scalar()).select("s_suppkey")


@query("sub_exists", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def sub_exists(spark, sf_dir):
    return load(spark, sf_dir, "customer").join(load(spark, sf_dir, "orders").where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("sub_correlated_min", "SELECT p_partkey FROM part p WHERE p_retailprice = (SELECT min(p_retailprice) FROM part q WHERE q.p_brand = p.p_brand)")
def sub_correlated_min(spark, sf_dir):
    part = load(spark, sf_dir, "part")
    least = part.groupBy(F.col("p_brand").alias("b")).agg(F.min("p_retailprice").alias("m"))
    return part.join(least, (F.col("p_brand") == F.col("b")) & (F.col("p_retailprice") == F.col("m")), "left_semi").select("p_partkey")


# ---- functions ----

query("fn_string", "SELECT s_suppkey, upper(substr(s_name, 1, 4)) AS head, regexp_extract(s_name, '([0-9]+)$', 1) AS digits, CAST(length(s_name) AS BIGINT) AS len, replace(s_name, '#', '-') AS dashed FROM supplier")(
    lambda spark, sf_dir: load(spark, sf_dir, "supplier").select("s_suppkey", F.upper(F.substring("s_name", 1, 4)).alias("head"), F.regexp_extract("s_name", "([0-9]+)$", 1).alias("digits"), F.length("s_name").cast("long").alias("len"), F.replace("s_name", F.lit("#"), F.lit("-")).alias("dashed")))
query("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(quarter(o_orderdate) AS BIGINT) AS q, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS days FROM orders")(
    lambda spark, sf_dir: load(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.quarter("o_orderdate").cast("long").alias("q"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("long").alias("days")))
query("fn_math", "SELECT p_partkey, CAST(floor(sqrt(p_size)) AS BIGINT) AS root, CAST(p_size % 7 AS BIGINT) AS rest, CAST(abs(p_size - 25) AS BIGINT) AS far, CAST(greatest(p_size, 10) AS BIGINT) AS g FROM part")(
    lambda spark, sf_dir: load(spark, sf_dir, "part").select("p_partkey", F.floor(F.sqrt("p_size")).alias("root"), (F.col("p_size") % 7).cast("long").alias("rest"), F.abs(F.col("p_size") - 25).cast("long").alias("far"), F.greatest("p_size", F.lit(10)).cast("long").alias("g")))
query("fn_array", "SELECT vec_id, CAST(len(embedding) AS BIGINT) AS n, CAST(list_max(embedding) AS DOUBLE) AS hi, CAST(list_sort(embedding)[1] AS DOUBLE) AS lo FROM embeddings")(
    lambda spark, sf_dir: load(spark, sf_dir, "embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), F.array_max("embedding").cast("double").alias("hi"), F.array_sort("embedding")[0].cast("double").alias("lo")))
query("fn_map", f"SELECT o_custkey, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS f FROM orders GROUP BY 1")(
    lambda spark, sf_dir: load(spark, sf_dir, "orders").groupBy("o_custkey", "o_orderstatus").agg(_n()).groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m")).select("o_custkey", F.coalesce(F.element_at("m", "F"), F.lit(0)).cast("long").alias("f")))
query("fn_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")(
    lambda spark, sf_dir: load(spark, sf_dir, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k")))
query("fn_bits", "SELECT p_partkey, CAST(p_partkey & 255 AS BIGINT) AS low, CAST(p_partkey >> 3 AS BIGINT) AS cut, CAST(bit_count(p_partkey) AS BIGINT) AS ones, CAST(length(bin(p_partkey)) AS BIGINT) AS width FROM part")(
    lambda spark, sf_dir: load(spark, sf_dir, "part").select("p_partkey", F.col("p_partkey").bitwiseAND(255).alias("low"), F.shiftright("p_partkey", 3).alias("cut"), F.bit_count("p_partkey").cast("long").alias("ones"), F.length(F.bin("p_partkey")).cast("long").alias("width")))
query("fn_url_host", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages")(lambda spark, sf_dir: load(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host")))

# ---- Arrow and table functions ----


@query("udf_pack_size", """WITH d AS (SELECT DISTINCT o_custkey % 8 AS s, o_custkey AS key FROM orders), g AS (SELECT s, key - coalesce(lag(key) OVER (PARTITION BY s ORDER BY key), 0) AS gap FROM d)
 SELECT s, CAST(sum(1 + (CASE WHEN gap >= 128 THEN 1 ELSE 0 END) + (CASE WHEN gap >= 16384 THEN 1 ELSE 0 END) + (CASE WHEN gap >= 2097152 THEN 1 ELSE 0 END)) AS BIGINT) AS bytes FROM g GROUP BY 1""")
def udf_pack_size(spark, sf_dir):
    blocks = keycodec.packed(load(spark, sf_dir, "orders").withColumn("s", F.pmod("o_custkey", F.lit(8))), "o_custkey", "s", chunk=1 << 40)
    return blocks.select(F.col("by").alias("s"), F.length("data").cast("long").alias("bytes"))


@query("udaf_kbest", "SELECT o_orderstatus, o_orderkey FROM (SELECT o_orderstatus, o_orderkey, row_number() OVER (PARTITION BY o_orderstatus ORDER BY CAST(round(o_totalprice*100) AS BIGINT) DESC, o_orderkey) AS r FROM orders) WHERE r <= 4")
def udaf_kbest(spark, sf_dir):
    rows = load(spark, sf_dir, "orders").select("o_orderstatus", "o_orderkey", cents("o_totalprice").alias("c"))
    return topk_merge.kbest(rows, ["o_orderstatus"], "c", "o_orderkey", 4).select("o_orderstatus", F.explode("best").alias("b")).select("o_orderstatus", "b.o_orderkey")


@query("udtf_unpack_keys", "SELECT DISTINCT o_custkey AS key FROM orders")
def udtf_unpack_keys(spark, sf_dir):
    from thriftline.functions import udfs

    udfs.register(spark)
    keycodec.packed(load(spark, sf_dir, "orders").withColumn("s", F.lit(0)), "o_custkey", "s").createOrReplaceTempView("_packed_keys")
    return spark.sql("select u.key from _packed_keys, lateral unpack_keys(data) u")


@query("udtf_pairing", """WITH m AS (SELECT l_orderkey % 6 AS s, l_suppkey % 6 AS d, count(*) AS n FROM lineitem GROUP BY 1, 2)
 SELECT r AS round, u, (r - u + 6) % 6 AS v, CAST(coalesce(n, 0) AS BIGINT) AS n_rows FROM range(6) a(r) CROSS JOIN range(6) b(u) LEFT JOIN m ON s = u AND d = (r - u + 6) % 6""")
def udtf_pairing(spark, sf_dir) -> DataFrame:
    """The rounds in which lines go to the shards of their suppliers, with the rows that a shard sends in each."""
    from thriftline.functions import udfs

    udfs.register(spark)
    shard = lambda key: placement.key_shard(key, 6)
    load(spark, sf_dir, "lineitem").groupBy(shard("l_orderkey").alias("s"), shard("l_suppkey").alias("d")).agg(_n()).createOrReplaceTempView("_sent")
    return spark.sql("select cast(round as bigint) as round, cast(u as bigint) as u, cast(v as bigint) as v, coalesce(n, 0) as n_rows from pairing_rounds(6) left join _sent on s = u and d = v")
