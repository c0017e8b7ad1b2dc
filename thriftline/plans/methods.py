"""One query for each method and variant outside the workloads: placement, codecs, remote filters, top-k, collectives, models."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from thriftline.functions.money import SQL_REV4, cents, rev4
from thriftline.operators import collectives, costmodel, deferred, keycodec, pairing, placement, semifilter, topk_baselines, topk_bounds, topk_lazy, topk_merge
from thriftline.operators.placement import SPREAD, key_shard
from thriftline.plans.workloads import Q03, Q18, SHARDS, open_orders, order_revenue, quarter_partials
from thriftline.sources import catalog
from thriftline.sources.catalog import load
from thriftline.shipping import durable, written

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


SQL_HASH = "(({key} % 2147483648) * 2654435761 >> 8) % {p}"

# ---- data distribution ----


def _counts(df: DataFrame) -> DataFrame:
    return df.groupBy("shard").agg(F.count("*").alias("n"))


@query("place_hash", f"SELECT CAST({SQL_HASH.format(key='l_orderkey', p=8)} AS BIGINT) AS shard, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY 1")
def place_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _counts(placement.place(load(spark, sf_dir, "lineitem"), "l_orderkey", SHARDS))


@query("place_modulus", "SELECT o_orderkey % 8 AS shard, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1")
def place_modulus(spark, sf_dir):
    return _counts(placement.place(load(spark, sf_dir, "orders"), "o_orderkey", SHARDS, "modulus"))


@query("place_range", "SELECT CAST(floor(c_custkey * 8 / (SELECT max(c_custkey) + 1 FROM customer)) AS BIGINT) AS shard, CAST(count(*) AS BIGINT) AS n FROM customer GROUP BY 1")
def place_range(spark, sf_dir):
    customers = load(spark, sf_dir, "customer")
    keys = customers.agg(F.max("c_custkey")).first()[0] + 1
    return _counts(placement.place(customers, "c_custkey", SHARDS, "range", keys=keys))


@query("place_bounds", "SELECT CAST((CASE WHEN p_partkey >= 100 THEN 1 ELSE 0 END) + (CASE WHEN p_partkey >= 150 THEN 1 ELSE 0 END) + (CASE WHEN p_partkey >= 1000 THEN 1 ELSE 0 END) AS BIGINT) AS shard, CAST(count(*) AS BIGINT) AS n FROM part GROUP BY 1")
def place_bounds(spark, sf_dir):
    return _counts(placement.place(load(spark, sf_dir, "part"), "p_partkey", 4, "range", bounds=[100, 150, 1000]))


@query("place_round_robin", "SELECT shard, CAST(count(*) AS BIGINT) AS n, CAST(sum(event_id) AS BIGINT) AS keys FROM (SELECT event_id, (row_number() OVER (ORDER BY event_id) - 1) % 8 AS shard FROM events) GROUP BY 1")
def place_round_robin(spark, sf_dir):
    dealt = placement.place(load(spark, sf_dir, "events"), "event_id", SHARDS, "round_robin")
    return dealt.groupBy("shard").agg(F.count("*").alias("n"), F.sum("event_id").alias("keys"))


@query("copartition_join", f"SELECT o_orderpriority, CAST(count(*) AS BIGINT) AS n, CAST(sum({SQL_REV4}) AS BIGINT) AS rev4 FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def copartition_join(spark, sf_dir):
    lines, orders = placement.colocate(load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders"), "l_orderkey", "o_orderkey", SHARDS)
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum(rev4()).alias("rev4"))


@query("fk_local_fraction", """SELECT 'lineitem-orders' AS edge, CAST(count(*) AS BIGINT) AS n_rows, CAST(count(*) FILTER (l_orderkey % 8 = o_orderkey % 8) AS BIGINT) AS local_rows FROM lineitem JOIN orders ON l_orderkey = o_orderkey
 UNION ALL SELECT 'orders-customer', count(*), count(*) FILTER (o_orderkey % 8 = o_custkey % 8) FROM orders UNION ALL SELECT 'lineitem-supplier', count(*), count(*) FILTER (l_orderkey % 8 = l_suppkey % 8) FROM lineitem""")
def fk_local_fraction(spark, sf_dir):
    lines, orders = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders")
    shard = lambda key: key_shard(key, SHARDS)
    solid = placement.local_fraction(lines, shard("l_orderkey"), shard("l_orderkey")).select(F.lit("lineitem-orders").alias("edge"), "*")
    remote = placement.local_fraction(orders, shard("o_custkey"), shard("o_orderkey")).select(F.lit("orders-customer").alias("edge"), "*")
    return solid.unionAll(remote).unionAll(placement.local_fraction(lines, shard("l_suppkey"), shard("l_orderkey")).select(F.lit("lineitem-supplier").alias("edge"), "*"))


@query("imbalance_range_vs_hash", f"""WITH o AS (SELECT o_orderkey AS k FROM orders WHERE o_orderkey < (SELECT max(o_orderkey) + 1 FROM orders) // 4), m AS (SELECT max(o_orderkey) + 1 AS n FROM orders),
 r AS (SELECT 'range' AS how, floor(k * 8 / n) AS s FROM o, m UNION ALL SELECT 'hash', {SQL_HASH.format(key='k', p=8)} FROM o), c AS (SELECT how, s, count(*) AS n FROM r GROUP BY 1, 2)
 SELECT how, CAST(8 AS BIGINT) AS shards, CAST(sum(n) AS BIGINT) AS n_rows, CAST(max(n) AS BIGINT) AS largest, max(n) * 8 / CAST(sum(n) AS DOUBLE) AS over_mean FROM c GROUP BY 1""")
def imbalance_range_vs_hash(spark, sf_dir):
    orders = load(spark, sf_dir, "orders").select("o_orderkey")
    keys = orders.agg(F.max("o_orderkey")).first()[0] + 1
    condition = F.col("o_orderkey") < keys // 4
    ranged = placement.imbalance(placement.place(orders, "o_orderkey", SHARDS, "range", keys=keys), condition, SHARDS)
    hashed = placement.imbalance(placement.place(orders, "o_orderkey", SHARDS), condition, SHARDS)
    return ranged.select(F.lit("range").alias("how"), "*").unionAll(hashed.select(F.lit("hash").alias("how"), "*"))


@query("replication_cost", """SELECT name, n_rows, n_rows * 8 AS replicated_rows FROM (SELECT 'customer' AS name, CAST(count(*) AS BIGINT) AS n_rows FROM customer UNION ALL SELECT 'part', count(*) FROM part
 UNION ALL SELECT 'supplier', count(*) FROM supplier UNION ALL SELECT 'nation', count(*) FROM nation UNION ALL SELECT 'region', count(*) FROM region)""")
def replication_cost(spark, sf_dir):
    parts = [load(spark, sf_dir, t).agg(F.count("*").alias("n_rows")).select(F.lit(t).alias("name"), "n_rows") for t in ("customer", "part", "supplier", "nation", "region")]
    out = parts[0]
    for part in parts[1:]:
        out = out.unionAll(part)
    return out.withColumn("replicated_rows", F.col("n_rows") * SHARDS)


@query("replicate_tiny", "SELECT n_name, CAST(count(*) AS BIGINT) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def replicate_tiny(spark, sf_dir):
    nation = placement.replicate(load(spark, sf_dir, "nation"))
    return load(spark, sf_dir, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("join_index_orders_customer", "SELECT o_custkey % 8 AS parent_shard, CAST(count(DISTINCT o_custkey) AS BIGINT) AS n FROM orders GROUP BY 1")
def join_index_orders_customer(spark, sf_dir):
    return catalog.join_index(load(spark, sf_dir, "orders"), "o_custkey", SHARDS).groupBy("parent_shard").agg(F.count("*").alias("n"))


def _edge_sql(e: catalog.FkEdge) -> str:
    table = lambda name: "(SELECT DISTINCT l_partkey AS ps_partkey, l_suppkey AS ps_suppkey FROM lineitem)" if name == "offers" else name
    here = "true" if e.parent in catalog.REPLICATED else f"{e.fk} % {SHARDS} = {catalog.PLACED_BY[e.child]} % {SHARDS}"
    return f"""SELECT '{e.child}' AS child, '{e.fk}' AS fk, '{e.parent}' AS parent, '{e.pk}' AS pk, count(*) FILTER ({here}) = count(*) AS is_local, CAST(count(*) AS BIGINT) AS n_rows,
 CAST(count(*) FILTER ({here}) AS BIGINT) AS n_local, CAST(count(DISTINCT {e.fk}) AS BIGINT) AS n_keys, CAST(count(*) FILTER ({e.fk} IS NOT NULL AND k IS NULL) AS BIGINT) AS n_orphans
 FROM {table(e.child)} c LEFT JOIN (SELECT DISTINCT {e.pk} AS k FROM {table(e.parent)} p) ON {e.fk} = k"""


@query("fk_edges", " UNION ALL ".join(_edge_sql(e) for e in catalog.EDGES))
def fk_edges(spark, sf_dir):
    return catalog.measured_edges(spark, sf_dir, SHARDS)


# ---- key codecs ----


@query("bitset_counts", "SELECT CAST(CASE WHEN o_custkey <= 0 THEN 0 ELSE 1 + (o_custkey - 1) // 32768 END AS BIGINT) AS bucket, CAST(count(DISTINCT o_custkey) AS BIGINT) AS n FROM orders GROUP BY 1")
def bitset_counts(spark, sf_dir):
    return keycodec.to_bitset(load(spark, sf_dir, "orders"), "o_custkey").select("bucket", F.bitmap_count("bits").alias("n"))


@query("bitset_roundtrip", "SELECT DISTINCT c_custkey AS key FROM customer WHERE c_mktsegment = 'BUILDING'")
def bitset_roundtrip(spark, sf_dir):
    return keycodec.from_bitset(keycodec.to_bitset(load(spark, sf_dir, "customer").where("c_mktsegment = 'BUILDING'"), "c_custkey"))


_GAPS = 'WITH d AS (SELECT DISTINCT o_custkey % 8 AS "by", o_custkey AS key FROM orders), g AS (SELECT "by", key, key - coalesce(lag(key) OVER (PARTITION BY "by" ORDER BY key), 0) AS gap FROM d) '
_VARINT = "1" + "".join(f" + (CASE WHEN gap >= {1 << 7 * p} THEN 1 ELSE 0 END)" for p in range(1, 9))


@query("delta_gaps", _GAPS + 'SELECT "by", CAST(count(*) AS BIGINT) AS n, CAST(sum(gap) AS BIGINT) AS total, CAST(max(gap) AS BIGINT) AS largest FROM g GROUP BY 1')
def delta_gaps(spark, sf_dir):
    gaps = keycodec.deltas(load(spark, sf_dir, "orders").withColumn("owner", key_shard("o_custkey", SHARDS)), "o_custkey", "owner")
    return gaps.groupBy("by").agg(F.count("*").alias("n"), F.sum("gap").alias("total"), F.max("gap").alias("largest"))


@query("delta_roundtrip", 'SELECT DISTINCT o_custkey % 8 AS "by", o_custkey AS key FROM orders')
def delta_roundtrip(spark, sf_dir):
    orders = load(spark, sf_dir, "orders").withColumn("owner", key_shard("o_custkey", SHARDS))
    return keycodec.unpacked(keycodec.packed(orders, "o_custkey", "owner"))


def _code_roundtrip(code: str):
    @query(f"{code}_roundtrip", ORACLES["delta_roundtrip"])
    def roundtrip(spark, sf_dir):
        orders = load(spark, sf_dir, "orders").withColumn("owner", key_shard("o_custkey", SHARDS))
        return keycodec.unpacked(keycodec.packed(orders, "o_custkey", "owner", code=code), code)


for _name in ("bitpack", "elias_gamma", "raw", "block"):
    _code_roundtrip(_name)


def _wire(code: str, size: str):
    @query(f"wire_bytes_{code}", _GAPS + f'SELECT "by", CAST(count(*) AS BIGINT) AS n_keys, CAST({size} AS BIGINT) AS bytes FROM g GROUP BY 1')
    def wire(spark, sf_dir):
        return keycodec.wire_bytes(load(spark, sf_dir, "orders").withColumn("owner", key_shard("o_custkey", SHARDS)), "o_custkey", "owner", code)


_wire("raw", "count(*) * 8")
_wire("varint", f"sum({_VARINT})")
_wire("bitpack", "(count(*) * length(bin(max(gap))) + 7) // 8")
_wire("elias_gamma", "(sum(2 * length(bin(gap + 1)) - 1) + 7) // 8")


@query("wire_bytes_sorted_vs_not", _GAPS + f"SELECT CAST(sum({_VARINT}) AS BIGINT) AS sorted_bytes, (SELECT CAST(sum(" + _VARINT.replace("gap", "o_custkey") + ") AS BIGINT) FROM (SELECT DISTINCT o_custkey FROM orders)) AS unsorted_bytes FROM g")
def wire_bytes_sorted_vs_not(spark, sf_dir):
    orders = load(spark, sf_dir, "orders").withColumn("owner", key_shard("o_custkey", SHARDS))
    ordered = keycodec.wire_bytes(orders, "o_custkey", "owner").agg(F.sum("bytes").alias("sorted_bytes"))
    # Without a sort keys have no small gaps: each travels as it is.
    plain = orders.select("o_custkey").distinct().agg(F.sum(keycodec.varint_size(F.col("o_custkey"))).alias("unsorted_bytes"))
    return ordered.crossJoin(plain)


@query("dictionary_codes", "SELECT value, CAST(row_number() OVER (ORDER BY value) - 1 AS BIGINT) AS code FROM (SELECT DISTINCT o_orderpriority AS value FROM orders)")
def dictionary_codes(spark, sf_dir):
    return keycodec.dictionary(load(spark, sf_dir, "orders"), "o_orderpriority")


# ---- remote filters ----


def _semi(name: str):
    @query(f"semi_{name}_orders", "SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")
    def semi(spark, sf_dir):
        f = semifilter.VARIANTS[name]
        return f(load(spark, sf_dir, "orders"), "o_custkey", load(spark, sf_dir, "customer"), "c_custkey", F.col("c_mktsegment") == "BUILDING").select("o_orderkey")

    @query(f"semi_{name}_lines", "SELECT l_orderkey, l_linenumber, l_partkey, CAST(count(*) AS BIGINT) AS n FROM lineitem WHERE l_partkey IN (SELECT p_partkey FROM part WHERE p_type = 'PROMO' AND p_size < 10) GROUP BY 1, 2, 3")
    def lines(spark, sf_dir):
        f = semifilter.VARIANTS[name]
        kept = f(load(spark, sf_dir, "lineitem"), "l_partkey", load(spark, sf_dir, "part"), "p_partkey", (F.col("p_type") == "PROMO") & (F.col("p_size") < 10))
        return kept.groupBy("l_orderkey", "l_linenumber", "l_partkey").agg(F.count("*").alias("n"))


for _name in semifilter.VARIANTS:
    _semi(_name)


@query("fetch_nation_for_orders", "SELECT c_nationkey, CAST(count(*) AS BIGINT) AS n FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1")
def fetch_nation_for_orders(spark, sf_dir):
    named = semifilter.fetch(load(spark, sf_dir, "orders"), "o_custkey", load(spark, sf_dir, "customer"), "c_custkey", ["c_nationkey"])
    return named.groupBy("c_nationkey").agg(F.count("*").alias("n"))


@query("pilot_selectivity", f"SELECT CAST(count(*) AS BIGINT) AS n, CAST(count(*) FILTER (c_mktsegment = 'BUILDING') AS BIGINT) AS hit FROM customer WHERE (c_custkey % 2147483648) * {SPREAD} % 1000 < 100")
def pilot_selectivity(spark, sf_dir):
    n, hit = costmodel.pilot(load(spark, sf_dir, "customer"), F.col("c_mktsegment") == "BUILDING", "c_custkey", 100)
    return spark.createDataFrame([(n, hit)], "n long, hit long")


_COSTS = """SELECT attribute, asking, value, n, m, gamma, p, CAST(round(n / p * log2(greatest(m * p / n, 1.0))) AS BIGINT) AS late_bits, CAST(round(gamma * m * log2(1 / gamma)) AS BIGINT) AS bitset_bits, n / p AS reply_bits FROM (
 SELECT '{attribute}' AS attribute, asking, CAST(n AS DOUBLE) AS n, value, CAST(m AS DOUBLE) AS m, CAST(hits AS DOUBLE) / m AS gamma, CAST(2 ** d AS DOUBLE) AS p
 FROM (SELECT {by} AS asking, count(DISTINCT {fk}) AS n FROM {child} GROUP BY 1), (SELECT {attribute} AS value, count(*) AS hits FROM {parent} GROUP BY 1), (SELECT count(*) AS m FROM {parent}), range(8) t(d)) WHERE n > 0"""
#: Attributes of remote rows that a filter may ask for, and by what the asking rows are told apart.
_FILTERS = (
    dict(child="orders", fk="o_custkey", by="o_orderpriority", parent="customer", attribute="c_mktsegment"),
    dict(child="lineitem", fk="l_partkey", by="l_returnflag", parent="part", attribute="p_brand"),
)


@query("filter_cost_grid", " UNION ALL ".join(_COSTS.format(**f) for f in _FILTERS))
def filter_cost_grid(spark, sf_dir):
    """Bits of both filters for each group of asking rows, each value of the remote attribute and up to 128 shards, in whole bits."""
    n, m, gamma, p = (F.col(c) for c in ("n", "m", "gamma", "p"))
    costs = None
    for f in _FILTERS:
        asking = load(spark, sf_dir, f["child"]).groupBy(F.col(f["by"]).alias("asking")).agg(F.count_distinct(f["fk"]).cast("double").alias("n")).where("n > 0")
        values = load(spark, sf_dir, f["parent"]).groupBy(F.col(f["attribute"]).alias("value")).agg(F.count("*").alias("hits"))
        values = collectives.allreduce(values, F.sum("hits").cast("double"), "m").withColumn("gamma", F.col("hits") / F.col("m"))
        grid = asking.crossJoin(F.broadcast(values)).crossJoin(spark.range(8).select(F.pow(F.lit(2.0), "id").alias("p")))
        bits = [F.round(costmodel.late_cost(n, m, p)).cast("long").alias("late_bits"), F.round(costmodel.bitset_cost(m, gamma)).cast("long").alias("bitset_bits"), (n / p).alias("reply_bits")]
        found = grid.select(F.lit(f["attribute"]).alias("attribute"), "asking", "value", "n", "m", "gamma", "p", *bits)
        costs = found if costs is None else costs.unionAll(found)
    return costs


# ---- top-k of local groups ----

_TOP_ORDERS = "SELECT o_orderkey, CAST(round(o_totalprice*100) AS BIGINT) AS total_c FROM orders"


def _orders(spark, sf_dir) -> tuple[DataFrame, list]:
    rows = load(spark, sf_dir, "orders").select("o_orderkey", cents("o_totalprice").alias("total_c"), key_shard("o_orderkey", SHARDS).alias("shard"))
    return rows, [F.col("total_c").desc(), F.col("o_orderkey")]


@query("topk_local", f"SELECT o_orderkey, total_c, shard FROM (SELECT *, o_orderkey % 8 AS shard, row_number() OVER (PARTITION BY o_orderkey % 8 ORDER BY total_c DESC, o_orderkey) AS r FROM ({_TOP_ORDERS})) WHERE r <= 5")
def topk_local(spark, sf_dir):
    rows, by = _orders(spark, sf_dir)
    return topk_merge.local(rows, by, 5)


def _topk(name: str):
    @query(f"topk_{name}", f"{_TOP_ORDERS} ORDER BY total_c DESC, o_orderkey LIMIT 20")
    def top(spark, sf_dir):
        rows, by = _orders(spark, sf_dir)
        if name == "gather":
            return topk_merge.gather(rows, by, 20).drop("shard")
        if name == "tree":
            return topk_merge.tree(rows, by, 20, fanin=2, shards=SHARDS).drop("shard")
        if name == "select":
            # The k-th score by counting, then the cut among the few rows that reach it.
            kth = topk_merge.threshold_select(rows, "total_c", 20)
            return topk_merge.gather(rows.where(F.col("total_c") >= kth), by, 20).drop("shard")
        best = topk_merge.kbest(rows.withColumn("one", F.lit(1)), ["one"], "total_c", "o_orderkey", 20)
        return best.select(F.explode("best").alias("b")).select("b.o_orderkey", "b.total_c")


for _name in ("gather", "tree", "select", "udaf"):
    _topk(_name)


@query("topk_ties", "WITH n AS (SELECT o_custkey, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1) SELECT * FROM n WHERE n >= (SELECT min(n) FROM (SELECT n FROM n ORDER BY n DESC LIMIT 5))")
def topk_ties(spark, sf_dir):
    return topk_merge.with_ties(load(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")), F.col("n"), 5)


@query("topk_kbest_by_segment", """SELECT c_mktsegment, c_custkey, acctbal_c FROM (SELECT c_mktsegment, c_custkey, CAST(round(c_acctbal*100) AS BIGINT) AS acctbal_c, row_number() OVER (PARTITION BY c_mktsegment ORDER BY CAST(round(c_acctbal*100) AS BIGINT) DESC, c_custkey) AS r FROM customer) WHERE r <= 3""")
def topk_kbest_by_segment(spark, sf_dir):
    rows = load(spark, sf_dir, "customer").select("c_mktsegment", "c_custkey", cents("c_acctbal").alias("acctbal_c"))
    return topk_merge.kbest(rows, ["c_mktsegment"], "acctbal_c", "c_custkey", 3).select("c_mktsegment", F.explode("best").alias("b")).select("c_mktsegment", "b.c_custkey", "b.acctbal_c")


# ---- lazy top-k ----

_DOCS = "SELECT doc_id, n_chars FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND toxic = 0 ORDER BY n_chars DESC, doc_id LIMIT 10"


def _lazy_docs(spark, sf_dir, **more):
    docs = load(spark, sf_dir, "documents").select("doc_id", "n_chars", F.col("doc_id").alias("fk"), key_shard("doc_id", SHARDS).alias("shard"))
    labels = load(spark, sf_dir, "labels").withColumnRenamed("doc_id", "labelled")
    return topk_lazy.run(docs, "n_chars", "doc_id", "fk", labels, "labelled", (F.col("quality") == 1) & (F.col("toxic") == 0), **{"k": 10} | more)


@query("topk_lazy_docs", _DOCS)
def topk_lazy_docs(spark, sf_dir):
    return _lazy_docs(spark, sf_dir).df.select("doc_id", "n_chars")


@query("topk_lazy_pruned", _DOCS)
def topk_lazy_pruned(spark, sf_dir):
    return _lazy_docs(spark, sf_dir, prune_every=1, chunk=5).df.select("doc_id", "n_chars")


@query("topk_lazy_exhaust", "SELECT doc_id, n_chars FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND toxic = 0")
def topk_lazy_exhaust(spark, sf_dir):
    return _lazy_docs(spark, sf_dir, k=1_000_000, chunk=64, growth=4.0).df.select("doc_id", "n_chars")


@query("topk_eager", _DOCS)
def topk_eager(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select("doc_id", "n_chars")
    labels = load(spark, sf_dir, "labels").withColumnRenamed("doc_id", "labelled")
    return topk_lazy.eager(docs, "n_chars", "doc_id", "doc_id", labels, "labelled", (F.col("quality") == 1) & (F.col("toxic") == 0), 10)


@query("topk_lazy_q3", Q03)
def topk_lazy_q3(spark, sf_dir):
    orders, lines, customers = open_orders(spark, sf_dir)
    rows = order_revenue(orders, lines).withColumn("shard", key_shard("o_orderkey", SHARDS))
    found = topk_lazy.run(rows, "rev4", "o_orderkey", "o_custkey", customers, "c_custkey", F.col("c_mktsegment") == "BUILDING", 10, chunk=20, growth=1.0)
    return found.df.select("o_orderkey", "rev4", "o_orderdate")


_ASKED = """WITH r AS (SELECT doc_id, n_chars, doc_id % 8 AS shard, row_number() OVER (PARTITION BY doc_id % 8 ORDER BY n_chars DESC, doc_id) AS place,
 doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0) AS good FROM documents),
 c AS (SELECT *, count(*) FILTER (good) OVER (PARTITION BY shard ORDER BY place) AS have FROM r), s AS (SELECT shard, count(*) AS size FROM r GROUP BY 1),
 h AS (SELECT 'fixed' AS policy, i AS round, 10 * i AS high FROM range(1, (SELECT max(size) // 10 + 2 FROM s)) t(i)
  UNION ALL SELECT p, i, CAST(10 * (2 ** i - 1) AS BIGINT) FROM range(1, (SELECT CAST(ceil(log2(max(size))) AS BIGINT) + 1 FROM s)) t(i), (VALUES ('doubling'), ('pruned')) u(p)),
 b AS (SELECT policy, round, count(*) AS n, min(n_chars) AS kth FROM (SELECT policy, round, n_chars, row_number() OVER (PARTITION BY policy, round ORDER BY n_chars DESC) AS o FROM h JOIN r ON good AND place <= high) WHERE o <= 10 GROUP BY 1, 2),
 e AS (SELECT h.policy, h.round, s.shard, least(high, size) AS asked, have >= 10 OR size <= high OR (h.policy = 'pruned' AND b.n = 10 AND nxt.n_chars < b.kth) AS stops
  FROM h CROSS JOIN s JOIN c ON c.shard = s.shard AND c.place = least(high, size) LEFT JOIN r AS nxt ON nxt.shard = s.shard AND nxt.place = high + 1 LEFT JOIN b ON b.policy = h.policy AND b.round = h.round),
 f AS (SELECT policy, shard, min(round) AS round, min(asked) AS asked FROM e WHERE stops GROUP BY 1, 2)
 SELECT 'eager' AS policy, CAST(count(*) AS BIGINT) AS asked, 1 AS rounds FROM documents UNION ALL SELECT policy, CAST(sum(asked) AS BIGINT), CAST(max(round) AS INTEGER) FROM f GROUP BY 1"""


@query("lazy_asked_keys", _ASKED)
def lazy_asked_keys(spark, sf_dir):
    """Keys asked for by each chunk policy, beside all keys."""
    total = load(spark, sf_dir, "documents").count()
    rows = [("eager", total, 1)]
    for name, more in (("fixed", {"chunk": 10, "growth": 1.0}), ("doubling", {"chunk": 10}), ("pruned", {"chunk": 10, "prune_every": 1})):
        found = _lazy_docs(spark, sf_dir, **more)
        rows.append((name, found.asked, found.rounds))
    return spark.createDataFrame(rows, "policy string, asked long, rounds int")


# ---- top-k over distributed sums ----


def _part_partials(spark, sf_dir, shards: int = 4) -> DataFrame:
    return load(spark, sf_dir, "lineitem").groupBy(key_shard("l_orderkey", shards).alias("shard"), F.col("l_partkey").alias("key")).agg(F.sum(rev4()).alias("val"))


_QUARTER = f"WITH p AS (SELECT l_orderkey % 8 AS shard, l_suppkey AS key, CAST(sum({SQL_REV4}) AS BIGINT) AS val FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1996-04-01' GROUP BY 1, 2)"
_PARTS = f"WITH p AS (SELECT l_orderkey % 4 AS shard, l_partkey AS key, CAST(sum({SQL_REV4}) AS BIGINT) AS val FROM lineitem GROUP BY 1, 2)"


def _best(k: int) -> str:
    return f" SELECT * FROM (SELECT key, CAST(sum(val) AS BIGINT) AS total FROM p GROUP BY 1) WHERE total >= (SELECT min(total) FROM (SELECT CAST(sum(val) AS BIGINT) AS total FROM p GROUP BY key ORDER BY 1 DESC LIMIT {k}))"


def _part_rows(spark, sf_dir) -> DataFrame:
    return load(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("key"), rev4().alias("val"))


def _event_rows(spark, sf_dir) -> DataFrame:
    return load(spark, sf_dir, "events").where("event_type = 'purchase'").select(F.col("user_id").alias("key"), cents("value").alias("val"))


def _bounded(name: str, source, k: int, width: int, sql: str, run_=topk_bounds.run_rows, **more):
    @query(name, sql + _best(k))
    def run(spark, sf_dir):
        return run_(source(spark, sf_dir), k, width=width, **more).df.select("key", "total")


_EVENTS = "WITH p AS (SELECT user_id AS key, CAST(round(value*100) AS BIGINT) AS val FROM events WHERE event_type = 'purchase')"
_bounded("topk_bounds_part", _part_rows, 10, 8, _PARTS)
_bounded("topk_bounds_part_w12", _part_rows, 100, 12, _PARTS)
_bounded("topk_bounds_shards", _part_partials, 10, 8, _PARTS, topk_bounds.run)
_bounded("topk_bounds_residual", _part_partials, 10, 8, _PARTS, topk_bounds.run, residual=True)
_bounded("topk_bounds_events", _event_rows, 10, 8, _EVENTS)


@query("topk_full_part", _PARTS + _best(10))
def topk_full_part(spark, sf_dir):
    return topk_baselines.full(_part_rows(spark, sf_dir), 10)


@query("topk_ta", _PARTS + _best(10))
def topk_ta(spark, sf_dir):
    return topk_baselines.threshold_algorithm(_part_partials(spark, sf_dir), 10).df


@query("topk_tput", _PARTS + _best(10))
def topk_tput(spark, sf_dir):
    return topk_baselines.uniform_threshold(_part_partials(spark, sf_dir), 4, 10).df


def _coded(width: int) -> str:
    return f""", c AS (SELECT *, greatest(length(bin(max(val) OVER (PARTITION BY shard, key // 1024))) - {width}, 0) AS shift FROM p), e AS (SELECT shard, key, val, CAST(shift AS BIGINT) AS shift, val >> shift AS code, (val >> shift) << shift AS lo, ((val >> shift) << shift) + (1::BIGINT << shift) - 1 AS hi FROM c)"""


@query("bounds_encode", _QUARTER + _coded(8) + " SELECT shard, key, shift, code, lo, hi FROM e")
def bounds_encode(spark, sf_dir):
    return topk_bounds.code_columns(quarter_partials(spark, sf_dir), 8, 1024).select("shard", "key", "shift", "code", "lo", "hi")


@query("bounds_blocks", _QUARTER + _coded(8) + " SELECT shard, CAST(key // 1024 AS BIGINT) AS grp, CAST(max(shift) AS BIGINT) AS shift, CAST(count(*) AS BIGINT) AS n, CAST(count(*) AS BIGINT) AS code_bytes, CAST(128 AS BIGINT) AS present_bytes FROM e GROUP BY 1, 2")
def bounds_blocks(spark, sf_dir):
    blocks = topk_bounds.encode(quarter_partials(spark, sf_dir), 8, 1024)
    return blocks.select("shard", "grp", F.col("shift").cast("long").alias("shift"), F.col("n").cast("long").alias("n"), F.length("codes").cast("long").alias("code_bytes"), F.length("present").cast("long").alias("present_bytes"))


@query("bounds_intervals", _QUARTER + _coded(8) + " SELECT key, CAST(sum(lo) AS BIGINT) AS lo, CAST(sum(hi) AS BIGINT) AS hi FROM e GROUP BY 1")
def bounds_intervals(spark, sf_dir):
    return topk_bounds.decode_sum(topk_bounds.encode(quarter_partials(spark, sf_dir), 8, 1024), 8, 1024)


@query("bounds_survivors", _QUARTER + _coded(8) + ", b AS (SELECT key, CAST(sum(lo) AS BIGINT) AS lo, CAST(sum(hi) AS BIGINT) AS hi FROM e GROUP BY 1) SELECT * FROM b WHERE hi >= (SELECT min(lo) FROM (SELECT lo FROM b ORDER BY lo DESC LIMIT 3))")
def bounds_survivors(spark, sf_dir):
    return topk_bounds.survivors(topk_bounds.decode_sum(topk_bounds.encode(quarter_partials(spark, sf_dir), 8, 1024), 8, 1024), 3)


def _sweep_sql() -> str:
    parts = []
    for w in (4, 6, 8, 12, 16):
        parts.append(f"SELECT {w} AS width, CAST(count(*) AS BIGINT) AS survivors FROM b{w} WHERE hi >= (SELECT min(lo) FROM (SELECT lo FROM b{w} ORDER BY lo DESC LIMIT 10))")
    tables = []
    for w in (4, 6, 8, 12, 16):
        tables.append(_coded(w).replace(", c AS", f", c{w} AS").replace("e AS", f"e{w} AS").replace("FROM c)", f"FROM c{w})") + f", b{w} AS (SELECT key, sum(lo) AS lo, sum(hi) AS hi FROM e{w} GROUP BY 1)")
    return _PARTS + "".join(tables) + " " + " UNION ALL ".join(parts)


@query("bounds_width_sweep", _sweep_sql())
def bounds_width_sweep(spark, sf_dir):
    partials, out = durable(_part_partials(spark, sf_dir)), None
    for w in (4, 6, 8, 12, 16):
        kept = topk_bounds.survivors(topk_bounds.decode_sum(topk_bounds.encode(partials, w), w), 10)
        row = kept.agg(F.lit(w).alias("width"), F.count("*").alias("survivors"))
        out = row if out is None else out.unionAll(row)
    return out


def _wire_bits_sql() -> str:
    """A block has its codes in whole bytes, 128 bytes of presence and one of shift; full values have 64 bits each."""
    parts, tables = [], []
    for w in (8, 12):
        tables.append(_coded(w).replace(", c AS", f", c{w} AS").replace("e AS", f"e{w} AS").replace("FROM c)", f"FROM c{w})") + f", b{w} AS (SELECT key, sum(lo) AS lo, sum(hi) AS hi FROM e{w} GROUP BY 1)")
        best = f"(SELECT CAST(count(*) AS BIGINT) FROM b{w} WHERE hi >= (SELECT min(lo) FROM (SELECT lo FROM b{w} ORDER BY lo DESC LIMIT 10)))"
        parts.append(f"SELECT {w} AS width, CAST(count(*) * {8 if w <= 8 else 16} + count(DISTINCT (shard, key // 1024)) * {8 * 129} AS BIGINT) AS bits, CAST(64 * count(*) AS BIGINT) AS full_bits, {best} AS survivors FROM e{w}")
    return _PARTS + "".join(tables) + " " + " UNION ALL ".join(parts)


@query("bounds_wire_bits", _wire_bits_sql())
def bounds_wire_bits(spark, sf_dir):
    """Bits of the first exchange by width, beside full values."""
    rows = []
    for w in (8, 12):
        found = topk_bounds.run(_part_partials(spark, sf_dir), 10, width=w)
        rows.append((w, found.bits, found.full_bits, found.survivors.count()))
    return spark.createDataFrame(rows, "width int, bits long, full_bits long, survivors long")


_TOUCHED = _PARTS + """, r AS (SELECT *, row_number() OVER (PARTITION BY shard ORDER BY val DESC, key) AS place FROM p), t AS (SELECT key, sum(val) AS total, count(*) AS parts, min(place) AS place FROM r GROUP BY 1),
 d AS (SELECT CAST(64 * 2 ** i AS BIGINT) AS depth FROM range((SELECT CAST(ceil(log2(greatest(max(place) / 64.0, 1))) AS BIGINT) + 1 FROM r)) x(i)),
 seen AS (SELECT depth, total, parts, row_number() OVER (PARTITION BY depth ORDER BY total DESC) AS o FROM d JOIN t ON place <= depth),
 a AS (SELECT depth, count(*) AS keys, min(total) FILTER (o <= 10) AS kth, sum(parts) AS touched FROM seen GROUP BY 1),
 f AS (SELECT place AS depth, sum(val) AS frontier FROM r GROUP BY 1),
 stop AS (SELECT a.depth, touched FROM a LEFT JOIN f ON f.depth = a.depth WHERE a.depth >= (SELECT max(place) FROM r) OR (keys >= 10 AND kth > coalesce(frontier, 0)) ORDER BY 1 LIMIT 1),
 u AS (SELECT sum(val) AS s FROM r WHERE place <= 10 GROUP BY key ORDER BY 1 DESC LIMIT 10), v AS (SELECT min(s) AS t1, greatest(1, min(s) // 4) AS cut FROM u),
 g AS (SELECT key, sum(val) AS lo, sum(val) + (4 - count(*)) * (any_value(cut) - 1) AS hi FROM p, v WHERE val >= cut GROUP BY 1),
 l AS (SELECT greatest(any_value(t1), CASE WHEN count(*) = 10 THEN min(lo) ELSE 0 END) AS least FROM (SELECT lo FROM g ORDER BY lo DESC LIMIT 10), v),
 n AS (SELECT CAST(count(*) AS BIGINT) AS parts FROM p)
 SELECT 'full' AS method, parts AS sorted_accesses, CAST(0 AS BIGINT) AS random_accesses FROM n
 UNION ALL SELECT 'threshold', CAST(count(*) AS BIGINT), CAST(any_value(touched) - count(*) AS BIGINT) FROM r, stop WHERE place <= depth
 UNION ALL SELECT 'uniform', CAST(count(*) FILTER (val >= cut) AS BIGINT), CAST(count(*) FILTER (val < cut AND key IN (SELECT key FROM g, l WHERE hi >= least)) AS BIGINT) FROM p, v"""


@query("topk_access_counts", _TOUCHED)
def topk_access_counts(spark, sf_dir):
    """Parts touched by the threshold algorithms, beside all parts."""
    partials = _part_partials(spark, sf_dir)
    a, b = topk_baselines.threshold_algorithm(partials, 10), topk_baselines.uniform_threshold(partials, 4, 10)
    rows = [("full", partials.count(), 0), ("threshold", a.sorted_accesses, a.random_accesses), ("uniform", b.sorted_accesses, b.random_accesses)]
    return spark.createDataFrame(rows, "method string, sorted_accesses long, random_accesses long")


# ---- collectives and schedules ----


@query("coll_gather", "SELECT c_mktsegment, CAST(count(*) AS BIGINT) AS n FROM customer GROUP BY 1")
def coll_gather(spark, sf_dir):
    return collectives.gather(load(spark, sf_dir, "customer").groupBy("c_mktsegment").agg(F.count("*").alias("n")))


@query("coll_allgather", "SELECT r_name, CAST(count(*) AS BIGINT) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def coll_allgather(spark, sf_dir):
    region = collectives.allgather(load(spark, sf_dir, "region"))
    return load(spark, sf_dir, "nation").join(region, F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("coll_scatter", "SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20)")
def coll_scatter(spark, sf_dir):
    root = load(spark, sf_dir, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20).select("o_custkey")
    return collectives.scatter(F.broadcast(root), "o_custkey", load(spark, sf_dir, "customer").select("c_custkey", "c_name"), "c_custkey")


@query("coll_exchange", "SELECT o_custkey % 8 AS owner, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1")
def coll_exchange(spark, sf_dir):
    moved = collectives.exchange(load(spark, sf_dir, "orders").select("o_custkey", key_shard("o_custkey", SHARDS).alias("owner")), "owner", SHARDS)
    # Every partition now holds the rows of its own number only.
    return moved.where(F.spark_partition_id() == F.col("owner")).groupBy("owner").agg(F.count("*").alias("n"))


@query("coll_reduce", "SELECT CAST(count(*) AS BIGINT) AS n, CAST(max(o_orderkey) AS BIGINT) AS last, CAST(sum(CAST(round(o_totalprice*100) AS BIGINT)) AS BIGINT) AS total_c FROM orders")
def coll_reduce(spark, sf_dir):
    return collectives.reduce(load(spark, sf_dir, "orders"), F.count("*").alias("n"), F.max("o_orderkey").alias("last"), F.sum(cents("o_totalprice")).alias("total_c"))


@query("coll_allreduce", "SELECT s_suppkey, CAST(round(s_acctbal*100) AS BIGINT) AS acctbal_c, (SELECT CAST(max(CAST(round(s_acctbal*100) AS BIGINT)) AS BIGINT) FROM supplier) AS best FROM supplier")
def coll_allreduce(spark, sf_dir):
    return collectives.allreduce(load(spark, sf_dir, "supplier").select("s_suppkey", cents("s_acctbal").alias("acctbal_c")), F.max("acctbal_c"), "best")


@query("pairing_schedule", """WITH m AS (SELECT o_orderkey % 12 AS s, o_custkey % 12 AS d, count(*) AS n FROM orders GROUP BY 1, 2)
 SELECT r AS round, u, (r - u + 12) % 12 AS v, CAST(coalesce(n, 0) AS BIGINT) AS n_rows FROM range(12) a(r) CROSS JOIN range(12) b(u) LEFT JOIN m ON s = u AND d = (r - u + 12) % 12""")
def pairing_schedule(spark, sf_dir):
    """The schedule by which orders go to the shards of their customers, with the rows that a shard sends in each round."""
    sent = load(spark, sf_dir, "orders").groupBy(key_shard("o_orderkey", 12).alias("u"), key_shard("o_custkey", 12).alias("v")).agg(F.count("*").alias("n"))
    return pairing.schedule(spark, 12).join(sent, ["u", "v"], "left").select("round", "u", "v", F.coalesce("n", F.lit(0)).alias("n_rows"))


_MATRIX = "SELECT o_orderkey % 8 AS src, o_custkey % 8 AS dst, CAST(count(*) * 8 AS BIGINT) AS volume FROM orders GROUP BY 1, 2"


def _matrix(spark, sf_dir):
    return load(spark, sf_dir, "orders").groupBy(key_shard("o_orderkey", SHARDS).alias("src"), key_shard("o_custkey", SHARDS).alias("dst")).agg((F.count("*") * 8).alias("volume"))


@query("exchange_matrix", _MATRIX)
def exchange_matrix(spark, sf_dir):
    return _matrix(spark, sf_dir)


@query("pairing_makespan", f"""WITH m AS ({_MATRIX}), a AS (SELECT src AS s, volume AS v FROM m WHERE src <> dst), b AS (SELECT dst AS s, volume AS v FROM m WHERE src <> dst)
 SELECT (SELECT CAST(sum(x) AS BIGINT) FROM (SELECT max(volume) AS x FROM m WHERE src <> dst GROUP BY (src + dst) % 8)) AS scheduled,
 CAST(greatest((SELECT max(t) FROM (SELECT sum(v) AS t FROM a GROUP BY s)), (SELECT max(t) FROM (SELECT sum(v) AS t FROM b GROUP BY s))) AS BIGINT) AS busiest""")
def pairing_makespan(spark, sf_dir):
    matrix = _matrix(spark, sf_dir)
    scheduled = pairing.makespan(matrix, SHARDS).select("scheduled")
    moved = matrix.where("src <> dst")
    sent, got = moved.groupBy("src").agg(F.sum("volume").alias("v")), moved.groupBy("dst").agg(F.sum("volume").alias("v"))
    return scheduled.crossJoin(sent.select("v").unionAll(got.select("v")).agg(F.max("v").alias("busiest")))


# ---- late materialization ----


@query("late_mat_q15", _QUARTER + ", t AS (SELECT key, CAST(sum(val) AS BIGINT) AS total FROM p GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 5) SELECT key, total, s_name FROM t JOIN supplier ON s_suppkey = key")
def late_mat_q15(spark, sf_dir):
    best = topk_baselines.full(quarter_partials(spark, sf_dir), 5, ties=False)
    return deferred.attach(best, "key", load(spark, sf_dir, "supplier"), "s_suppkey", ["s_name"], bound=5).select("key", "total", "s_name")


def _mat(name: str, variant: str):
    @query(name, Q18)
    def mat(spark, sf_dir):
        from thriftline.plans.workloads import q18

        return q18(spark, sf_dir, variant)


_mat("late_mat_q18", "late_columns")
_mat("early_mat_q18", "early_columns")


# ---- the same methods on the other tables ----


@query("terms_topk_bounds", """WITH w AS (SELECT doc_id, unnest(string_split_regex(lower(text), '[ \\t-\\r]+')) AS term FROM documents), p AS (SELECT term, CAST(count(*) AS BIGINT) AS total FROM w WHERE term <> '' GROUP BY 1)
 SELECT term, total FROM p WHERE total >= (SELECT min(total) FROM (SELECT total FROM p ORDER BY total DESC LIMIT 10))""")
def terms_topk_bounds(spark, sf_dir):
    """String keys travel as dense ids; the few best get their words back."""
    words = load(spark, sf_dir, "documents").select(key_shard("doc_id", SHARDS).alias("shard"), F.explode(F.split(F.lower("text"), "[ \\t-\\r]+")).alias("term")).where("term <> ''")
    return _best_named(words.groupBy("shard", "term").agg(F.count("*").alias("val")), "term", 10, 4)


def _best_named(sums: DataFrame, name: str, k: int, width: int = 8) -> DataFrame:
    sums = written(sums)
    ids = written(keycodec.dense_ids(sums, name)).withColumnRenamed("value", name)
    partials = sums.join(ids, name).select("shard", "key", "val")
    return topk_bounds.run(partials, k, width=width).df.join(ids, "key").select(name, "total")


@query("hosts_topk_bounds", """WITH p AS (SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, CAST(sum(strlen(html)) AS BIGINT) AS total FROM pages GROUP BY 1)
 SELECT host, total FROM p WHERE total >= (SELECT min(total) FROM (SELECT total FROM p ORDER BY total DESC LIMIT 5))""")
def hosts_topk_bounds(spark, sf_dir):
    pages = load(spark, sf_dir, "pages").select(key_shard("page_id", SHARDS).alias("shard"), F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host"), F.octet_length("html").cast("long").alias("size"))
    return _best_named(pages.groupBy("shard", "host").agg(F.sum("size").alias("val")), "host", 5)


@query("conv_topk_tree", "SELECT conv_id, CAST(sum(length(text)) AS BIGINT) AS chars FROM conversations GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 15")
def conv_topk_tree(spark, sf_dir):
    sums = load(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.sum(F.length("text")).cast("long").alias("chars"))
    rows = sums.withColumn("shard", key_shard("conv_id", SHARDS))
    return topk_merge.tree(rows, [F.col("chars").desc(), F.col("conv_id")], 15, fanin=4, shards=SHARDS).select("conv_id", "chars")


@query("embed_topk", """WITH q AS (SELECT embedding AS e FROM embeddings WHERE vec_id = 0), s AS (SELECT vec_id, CAST(round(list_dot_product(CAST(embedding AS DOUBLE[]), CAST(e AS DOUBLE[])) * 10000) AS BIGINT) AS score FROM embeddings, q)
 SELECT vec_id, score FROM s ORDER BY score DESC, vec_id LIMIT 10""")
def embed_topk(spark, sf_dir):
    vectors = load(spark, sf_dir, "embeddings")
    probe = [float(x) for x in vectors.where("vec_id = 0").first()["embedding"]]
    dot = F.aggregate(F.zip_with("embedding", F.array(*[F.lit(x) for x in probe]), lambda a, b: a.cast("double") * b), F.lit(0.0), lambda s, x: s + x)
    rows = vectors.select("vec_id", F.round(dot * 10000).cast("long").alias("score"), key_shard("vec_id", SHARDS).alias("shard"))
    return topk_merge.tree(rows, [F.col("score").desc(), F.col("vec_id")], 10, shards=SHARDS).select("vec_id", "score")


@query("embed_label_counts", "SELECT label, CAST(count(*) AS BIGINT) AS n, CAST(min(len(embedding)) AS BIGINT) AS dims FROM embeddings GROUP BY 1")
def embed_label_counts(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").groupBy("label").agg(F.count("*").alias("n"), F.min(F.size("embedding")).cast("long").alias("dims"))


