"""The decision-support workloads on the given tables, each with the variants of its remote filter or top-k.

Money is exact: whole units of 1/10,000.  A line is late if it ships more than 90 days after the order's date.  Dates, substitutes for
columns that are not given, and parameters are those of FIXTURES.md.
"""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from thriftline.functions.money import SQL_OFFERS, SQL_REV4, cents, day, quantity, rev4, whole
from thriftline.operators import collectives, costmodel, deferred, semifilter, topk_baselines, topk_bounds, topk_lazy, topk_merge
from thriftline.operators.placement import held, key_shard, placed
from thriftline.shipping import written
from thriftline.sources.catalog import load

SHARDS = 8
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


def variants(prefix: str, names: tuple[str, ...], sql: str):
    """Registers f(spark, sf_dir, variant) once for each variant; all share one definition in SQL."""

    def register(f):
        for name in names:
            query(f"{prefix}_{name}", sql)(lambda spark, sf_dir, name=name: f(spark, sf_dir, name))
        return f

    return register


# ---- one table ----


@query("q01", f"""SELECT l_returnflag, l_linestatus, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS sum_qty,
 CAST(sum(CAST(round(l_extendedprice*100) AS BIGINT)) AS BIGINT) AS sum_base_c, CAST(sum({SQL_REV4}) AS BIGINT) AS sum_disc4,
 CAST(sum({SQL_REV4}*(100+CAST(round(l_tax*100) AS BIGINT))) AS BIGINT) AS sum_charge6, CAST(count(*) AS BIGINT) AS n,
 CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE)/count(*) AS avg_qty
 FROM lineitem WHERE l_shipdate <= TIMESTAMP '2001-08-03' GROUP BY 1, 2""")
def q01(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem").where(F.col("l_shipdate") <= day("2001-08-03"))
    charge = rev4() * (100 + cents("l_tax"))
    return lines.groupBy("l_returnflag", "l_linestatus").agg(
        F.sum(quantity()).alias("sum_qty"), whole(cents("l_extendedprice")).alias("sum_base_c"), whole(rev4()).alias("sum_disc4"), whole(charge).alias("sum_charge6"), F.count("*").alias("n"), (F.sum(quantity()).cast("double") / F.count("*")).alias("avg_qty")
    )


# ---- cheapest supplier: late request for the supplier's region, late columns ----


@query("q02", f"""WITH offers AS ({SQL_OFFERS}), good AS (SELECT o.*, s.s_name, s.s_acctbal, n.n_name FROM offers o JOIN part ON p_partkey = ps_partkey JOIN supplier s ON s_suppkey = ps_suppkey
 JOIN nation n ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey WHERE p_size = 15 AND p_type = 'STANDARD' AND r_name = 'EUROPE'),
 best AS (SELECT *, min(ps_cost_c) OVER (PARTITION BY ps_partkey) AS m FROM good)
 SELECT CAST(round(s_acctbal*100) AS BIGINT) AS acctbal_c, n_name, s_name, ps_partkey AS p_partkey, ps_cost_c FROM best WHERE ps_cost_c = m ORDER BY s_acctbal DESC, n_name, s_name, ps_partkey LIMIT 100""")
def q02(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = load(spark, sf_dir, "part").where((F.col("p_size") == 15) & (F.col("p_type") == "STANDARD")).select("p_partkey")
    # Offers of the wanted parts are found before offers are formed, so the scan's rows shrink first.
    wanted = load(spark, sf_dir, "lineitem").join(parts, F.col("l_partkey") == F.col("p_partkey"), "left_semi")
    quantity_ = F.col("l_quantity").cast("long")
    offers = wanted.groupBy(F.col("l_partkey").alias("ps_partkey"), F.col("l_suppkey").alias("ps_suppkey")).agg(F.min(F.floor(cents("l_extendedprice") / quantity_)).cast("long").alias("ps_cost_c"))
    nations = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region").where("r_name = 'EUROPE'")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name")
    suppliers = load(spark, sf_dir, "supplier").join(F.broadcast(nations), F.col("s_nationkey") == F.col("n_nationkey"))
    near = semifilter.late(offers, "ps_suppkey", suppliers, "s_suppkey", F.lit(True))
    least = near.groupBy(F.col("ps_partkey").alias("_p")).agg(F.min("ps_cost_c").alias("_m"))
    best = near.join(least, (F.col("ps_partkey") == F.col("_p")) & (F.col("ps_cost_c") == F.col("_m")), "left_semi")
    named = semifilter.fetch(best, "ps_suppkey", suppliers, "s_suppkey", ["s_acctbal", "s_name", "n_name"])
    top = topk_merge.gather(named, [F.col("s_acctbal").desc(), F.col("n_name"), F.col("s_name"), F.col("ps_partkey")], 100)
    return top.select(cents("s_acctbal").alias("acctbal_c"), "n_name", "s_name", F.col("ps_partkey").alias("p_partkey"), "ps_cost_c")


# ---- unshipped orders: five ways to the customers' segment ----

Q03 = f"""SELECT o_orderkey, CAST(sum({SQL_REV4}) AS BIGINT) AS rev4, CAST(o_orderdate AS TIMESTAMP) AS o_orderdate FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON c_custkey = o_custkey
 WHERE c_mktsegment = 'BUILDING' AND o_orderdate < TIMESTAMP '1998-03-15' AND l_shipdate > TIMESTAMP '1998-03-15' GROUP BY o_orderkey, o_orderdate ORDER BY rev4 DESC, o_orderkey LIMIT 10"""


def _building():
    return F.col("c_mktsegment") == "BUILDING"


def open_orders(spark: SparkSession, sf_dir: str, stored: tuple[DataFrame, DataFrame] | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    orders, lines = stored or (load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem"))
    orders = orders.where(F.col("o_orderdate") < day("1998-03-15")).select("o_orderkey", "o_custkey", "o_orderdate")
    lines = lines.where(F.col("l_shipdate") > day("1998-03-15"))
    return orders, lines, load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")


def order_revenue(orders: DataFrame, lines: DataFrame) -> DataFrame:
    """Revenue of orders; lines are summed by order first, and the sums meet their orders by the same key, so the join adds no exchange of lines."""
    revenue = lines.groupBy("l_orderkey").agg(F.sum(rev4()).alias("rev4"))
    return revenue.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("o_orderkey", "o_custkey", "rev4", "o_orderdate")


@query("q03_held", Q03)
def q03_held(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The segment stands beside the orders since they were placed, so the query asks no other shard and reads no customers."""
    stored = held(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "customer", "c_custkey", ["c_mktsegment"])
    orders, lines, _ = open_orders(spark, sf_dir, (stored.where(_building()), placed(spark, sf_dir, "lineitem", "l_orderkey")))
    top = topk_merge.gather(order_revenue(orders, lines), [F.col("rev4").desc(), F.col("o_orderkey")], 10)
    return top.select("o_orderkey", "rev4", "o_orderdate")


@variants("q03", ("bitset", "repl", "late", "packed", "auto", "lazy", "lazy_pruned", "placed"), Q03)
def q03(spark: SparkSession, sf_dir: str, variant: str) -> DataFrame:
    orders, lines, customers = open_orders(spark, sf_dir, _placed(spark, sf_dir) if variant == "placed" else None)
    if variant.startswith("lazy"):
        rows = order_revenue(orders, lines).withColumn("shard", key_shard("o_orderkey", SHARDS))
        found = topk_lazy.run(rows, "rev4", "o_orderkey", "o_custkey", customers, "c_custkey", _building(), 10, chunk=50, prune_every=1 if variant == "lazy_pruned" else 0)
        return found.df.select("o_orderkey", "rev4", "o_orderdate")
    name = {"repl": "replicated", "placed": "bitset"}.get(variant, variant)
    kept = semifilter.VARIANTS[name](orders, "o_custkey", customers, "c_custkey", _building())
    top = topk_merge.gather(order_revenue(kept, lines), [F.col("rev4").desc(), F.col("o_orderkey")], 10)
    return top.select("o_orderkey", "rev4", "o_orderdate")


# ---- priorities of orders with a late line: one join of co-partitioned tables ----


Q04 = """SELECT o_orderpriority, CAST(count(*) AS BIGINT) AS n FROM orders WHERE o_orderdate >= TIMESTAMP '1997-07-01' AND o_orderdate < TIMESTAMP '1997-10-01'
 AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_shipdate > o_orderdate + INTERVAL 90 DAY) GROUP BY 1"""


def _late_orders(orders: DataFrame, lines: DataFrame) -> DataFrame:
    orders = orders.where((F.col("o_orderdate") >= day("1997-07-01")) & (F.col("o_orderdate") < day("1997-10-01")))
    lines = lines.select("l_orderkey", "l_shipdate")
    late = orders.join(lines, (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") > F.col("o_orderdate") + F.expr("interval 90 days")), "left_semi")
    return late.groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("q04", Q04)
def q04(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _late_orders(load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem"))


def _placed(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Orders and lines that were dealt by order key when they were loaded."""
    return placed(spark, sf_dir, "orders", "o_orderkey"), placed(spark, sf_dir, "lineitem", "l_orderkey")


@query("q04_placed", Q04)
def q04_placed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The join moves nothing: both tables were placed by order key once."""
    return _late_orders(*_placed(spark, sf_dir))


# ---- revenue of nations: small side to all, large side by request with payload ----


@query("q05", f"""SELECT n_name, CAST(sum({SQL_REV4}) AS BIGINT) AS rev4 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey
 JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey WHERE r_name = 'ASIA' AND c_nationkey = s_nationkey
 AND o_orderdate >= TIMESTAMP '1997-01-01' AND o_orderdate < TIMESTAMP '1998-01-01' GROUP BY 1""")
def q05(spark: SparkSession, sf_dir: str) -> DataFrame:
    nations = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region").where("r_name = 'ASIA'")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name")
    suppliers = load(spark, sf_dir, "supplier").join(F.broadcast(nations), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "s_nationkey", "n_name")
    orders = load(spark, sf_dir, "orders").where((F.col("o_orderdate") >= day("1997-01-01")) & (F.col("o_orderdate") < day("1998-01-01"))).select("o_orderkey", "o_custkey")
    placed = semifilter.fetch(orders, "o_custkey", load(spark, sf_dir, "customer"), "c_custkey", ["c_nationkey"]).select("o_orderkey", "c_nationkey")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", rev4().alias("rev4"))
    # The supplier side goes to all if it fits, so that lines of other regions are gone before lines meet orders.
    side = F.broadcast(suppliers) if suppliers.count() * 64 <= costmodel.BUDGET_BYTES else suppliers
    near = lines.join(side, F.col("l_suppkey") == F.col("s_suppkey"))
    joined = near.join(placed, (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("c_nationkey") == F.col("s_nationkey")))
    return joined.groupBy("n_name").agg(whole(F.col("rev4")).alias("rev4"))


# ---- important stock: no local filter, so a bitset; the total goes to all ----


@query("q11", f"""WITH offers AS ({SQL_OFFERS}), mine AS (SELECT ps_partkey, ps_cost_c*ps_qty AS v FROM offers JOIN supplier ON s_suppkey = ps_suppkey JOIN nation ON n_nationkey = s_nationkey WHERE n_name = 'NATION_6'),
 t AS (SELECT CAST(sum(v) AS HUGEINT) AS total, (SELECT count(*) FROM part) AS parts FROM mine) SELECT ps_partkey, CAST(sum(v) AS BIGINT) AS value_c FROM mine, t GROUP BY ps_partkey, total, parts HAVING sum(v) * parts > 2 * total""")
def q11(spark: SparkSession, sf_dir: str) -> DataFrame:
    # The fraction 1e-5 / SF, with SF being parts / 200,000, so value * parts > 2 * total.
    nation = F.broadcast(load(spark, sf_dir, "nation").where("n_name = 'NATION_6'"))
    suppliers = load(spark, sf_dir, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey")
    # The filter only needs the supplier, so it goes below the forming of offers.
    lines = semifilter.bitset(load(spark, sf_dir, "lineitem"), "l_suppkey", suppliers, "s_suppkey", F.lit(True))
    from thriftline.sources.catalog import offers as formed

    # The values are needed twice, for their total and for the cut, but formed once.
    values = written(formed(lines).groupBy("ps_partkey").agg(F.sum(F.col("ps_cost_c") * F.col("ps_qty")).alias("value_c")))
    parts = load(spark, sf_dir, "part").agg(F.count("*").alias("parts"))
    exact = F.col("value_c").cast("decimal(38,0)")
    both = collectives.allreduce(values, F.sum(exact), "total").crossJoin(F.broadcast(parts))
    return both.where(exact * F.col("parts") > 2 * F.col("total")).select("ps_partkey", "value_c")


# ---- histogram of orders per customer: keys move to the customers' owners ----


Q13 = """SELECT n_orders, CAST(count(*) AS BIGINT) AS n_customers FROM (SELECT c_custkey, CAST(count(o_orderkey) AS BIGINT) AS n_orders FROM customer
 LEFT JOIN orders ON o_custkey = c_custkey AND o_orderpriority <> '1-URGENT' AND o_orderstatus <> 'P' GROUP BY 1) GROUP BY 1"""


@query("q13", Q13)
def q13(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _histogram(spark, sf_dir, lambda orders: orders)


@query("q13_handover", Q13)
def q13_handover(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys as they are move to the customers' owners, which count them without another exchange; ``q13`` moves sums of each task instead."""
    return _histogram(spark, sf_dir, lambda orders: collectives.handover(orders.select("o_custkey"), "o_custkey"))


def _histogram(spark: SparkSession, sf_dir: str, moved) -> DataFrame:
    orders = load(spark, sf_dir, "orders").where((F.col("o_orderpriority") != "1-URGENT") & (F.col("o_orderstatus") != "P"))
    per = moved(orders).groupBy("o_custkey").agg(F.count("*").alias("n"))
    customers = load(spark, sf_dir, "customer").select("c_custkey").join(per, F.col("c_custkey") == F.col("o_custkey"), "left")
    return customers.groupBy(F.coalesce("n", F.lit(0)).cast("long").alias("n_orders")).agg(F.count("*").alias("n_customers"))


# ---- promotion share: the part's type by request, two sums ----


@query("q14", f"""SELECT CAST(sum(CASE WHEN p_type = 'PROMO' THEN {SQL_REV4} ELSE 0 END) AS BIGINT) AS promo4, CAST(sum({SQL_REV4}) AS BIGINT) AS total4 FROM lineitem JOIN part ON p_partkey = l_partkey
 WHERE l_shipdate >= TIMESTAMP '1997-09-01' AND l_shipdate < TIMESTAMP '1997-10-01'""")
def q14(spark: SparkSession, sf_dir: str) -> DataFrame:
    month = (F.col("l_shipdate") >= day("1997-09-01")) & (F.col("l_shipdate") < day("1997-10-01"))
    lines = load(spark, sf_dir, "lineitem").where(month).groupBy("l_partkey").agg(F.sum(rev4()).alias("rev4"))
    typed = semifilter.fetch(lines, "l_partkey", load(spark, sf_dir, "part"), "p_partkey", ["p_type"])
    return collectives.reduce(typed, whole(F.when(F.col("p_type") == "PROMO", F.col("rev4")).otherwise(0)).alias("promo4"), whole(F.col("rev4")).alias("total4"))


# ---- best supplier of a quarter: bounds, full values, full values by the schedule ----

Q15 = f"""WITH r AS (SELECT l_suppkey, CAST(sum({SQL_REV4}) AS BIGINT) AS total FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1996-04-01' GROUP BY 1)
 SELECT s_suppkey, s_name, CAST(round(s_acctbal*100) AS BIGINT) AS acctbal_c, total FROM r JOIN supplier ON s_suppkey = l_suppkey WHERE total = (SELECT max(total) FROM r)"""


def quarter_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").where((F.col("l_shipdate") >= day("1996-01-01")) & (F.col("l_shipdate") < day("1996-04-01")))


def quarter_partials(spark: SparkSession, sf_dir: str, shards: int = SHARDS) -> DataFrame:
    """(shard, key, val): revenue by supplier on each shard of lines."""
    lines = quarter_lines(spark, sf_dir)
    return lines.groupBy(key_shard("l_orderkey", shards).alias("shard"), F.col("l_suppkey").alias("key")).agg(F.sum(rev4()).alias("val"))


@variants("q15", ("bounds", "bounds_residual", "full", "full_scheduled", "ta", "uniform"), Q15)
def q15(spark: SparkSession, sf_dir: str, variant: str) -> DataFrame:
    rows = quarter_lines(spark, sf_dir).select(F.col("l_suppkey").alias("key"), rev4().alias("val"))
    if variant == "bounds":
        best = topk_bounds.run_rows(rows, 1).df
        return _named_suppliers(spark, sf_dir, best)
    if variant == "full":
        return _named_suppliers(spark, sf_dir, topk_baselines.full(rows, 1))
    partials = quarter_partials(spark, sf_dir)
    if variant == "bounds_residual":
        best = topk_bounds.run(partials, 1, residual=True).df
    elif variant == "full_scheduled":
        # The same values, dealt to the owners of the keys one round after another.
        owned = partials.withColumn("owner", key_shard("key", SHARDS))
        rounds = collectives.exchange_rounds(owned, "shard", "owner", SHARDS)
        best = topk_baselines.full(functools.reduce(DataFrame.unionAll, rounds).select("key", "val"), 1)
    elif variant == "ta":
        best = topk_baselines.threshold_algorithm(partials, 1).df
    else:
        best = topk_baselines.uniform_threshold(partials, SHARDS, 1).df
    return _named_suppliers(spark, sf_dir, best)


def _named_suppliers(spark: SparkSession, sf_dir: str, best: DataFrame) -> DataFrame:
    named = deferred.attach(best, "key", load(spark, sf_dir, "supplier"), "s_suppkey", ["s_suppkey", "s_name", "s_acctbal"])
    return named.select("s_suppkey", "s_name", cents("s_acctbal").alias("acctbal_c"), F.col("total"))


# ---- large orders: local top-k, remote columns at the end ----

Q18 = """WITH big AS (SELECT l_orderkey, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem GROUP BY 1 HAVING sum(CAST(l_quantity AS BIGINT)) > 250)
 SELECT c_name, c_custkey, o_orderkey, CAST(o_orderdate AS TIMESTAMP) AS o_orderdate, CAST(round(o_totalprice*100) AS BIGINT) AS total_c, qty FROM big JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey
 ORDER BY total_c DESC, o_orderdate, o_orderkey LIMIT 100"""


@variants("q18", ("late_columns", "early_columns", "tree", "placed"), Q18)
def q18(spark: SparkSession, sf_dir: str, variant: str) -> DataFrame:
    stored, lines = _placed(spark, sf_dir) if variant == "placed" else (load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem"))
    big = lines.groupBy("l_orderkey").agg(F.sum(quantity()).alias("qty")).where("qty > 250")
    orders = stored.select("o_orderkey", "o_custkey", "o_orderdate", cents("o_totalprice").alias("total_c"))
    rows = big.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).drop("l_orderkey")
    customers = load(spark, sf_dir, "customer")
    order = [F.col("total_c").desc(), F.col("o_orderdate"), F.col("o_orderkey")]
    columns = ["c_name", "c_custkey"]
    if variant == "early_columns":
        out = topk_merge.gather(deferred.eager(rows, "o_custkey", customers, "c_custkey", columns), order, 100)
    elif variant == "tree":
        top = topk_merge.tree(rows.withColumn("shard", key_shard("o_orderkey", SHARDS)), order, 100, fanin=2, shards=SHARDS)
        out = deferred.attach(top, "o_custkey", customers, "c_custkey", columns, bound=100)
    else:
        out = deferred.attach(topk_merge.gather(rows, order, 100), "o_custkey", customers, "c_custkey", columns, bound=100)
    return out.select("c_name", "c_custkey", "o_orderkey", "o_orderdate", "total_c", "qty")


# ---- suppliers alone to blame: the nation filter three ways, keyed merge of counts ----

Q21 = """WITH late AS (SELECT l_orderkey, l_suppkey, bool_or(l_shipdate > o_orderdate + INTERVAL 90 DAY) AS is_late FROM lineitem JOIN orders ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F' GROUP BY 1, 2),
 one AS (SELECT l_orderkey, count(*) AS suppliers, count(*) FILTER (is_late) AS late, max(CASE WHEN is_late THEN l_suppkey END) AS suppkey FROM late GROUP BY 1 HAVING count(*) > 1 AND count(*) FILTER (is_late) = 1)
 SELECT s_name, CAST(count(*) AS BIGINT) AS numwait FROM one JOIN supplier ON s_suppkey = suppkey JOIN nation ON n_nationkey = s_nationkey WHERE n_name = 'NATION_9' GROUP BY 1 ORDER BY numwait DESC, s_name LIMIT 100"""


@variants("q21", ("bitset", "repl", "late", "auto", "first"), Q21)
def q21(spark: SparkSession, sf_dir: str, variant: str) -> DataFrame:
    orders = load(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey", "o_orderdate")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_shipdate")
    delay = F.col("l_shipdate") > F.col("o_orderdate") + F.expr("interval 90 days")
    # Distinct suppliers of an order are two for certain if least and greatest differ; so no list of them is needed.
    late_supplier = F.when(delay, F.col("l_suppkey"))
    nation = F.broadcast(load(spark, sf_dir, "nation").where("n_name = 'NATION_9'").select("n_nationkey"))
    suppliers = load(spark, sf_dir, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey"), "left").select("s_suppkey", "s_name", F.col("n_nationkey").isNotNull().alias("wanted"))
    if variant == "first":
        # Suppliers are filtered first: only orders with a late line of one of them are aggregated at all.
        blamed = semifilter.replicated(lines, "l_suppkey", suppliers, "s_suppkey", F.col("wanted")).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).where(delay)
        orders = orders.join(blamed.select(F.col("l_orderkey").alias("_blamed")).distinct(), F.col("o_orderkey") == F.col("_blamed"), "left_semi")
    alone = (
        lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
        .groupBy("l_orderkey")
        .agg(F.min("l_suppkey").alias("a"), F.max("l_suppkey").alias("b"), F.min(late_supplier).alias("la"), F.max(late_supplier).alias("lb"))
        .where("a <> b and la = lb")
        .groupBy(F.col("la").alias("suppkey"))
        .agg(F.count("*").alias("numwait"))
    )
    name = {"repl": "replicated", "first": "late"}.get(variant, variant)
    mine = semifilter.VARIANTS[name](alone, "suppkey", suppliers, "s_suppkey", F.col("wanted"))
    named = semifilter.fetch(mine, "suppkey", suppliers, "s_suppkey", ["s_name"])
    return topk_merge.gather(named, [F.col("numwait").desc(), F.col("s_name")], 100).select("s_name", "numwait")
