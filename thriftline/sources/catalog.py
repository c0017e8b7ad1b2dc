"""Schemas, tables and foreign-key edges of the given star schema."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Column types as Spark reads them; ``load`` fails on a table that lacks a column or has it in another type.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}
#: Tables of constant size, replicated to every shard.
REPLICATED = ("region", "nation")
#: The key that places the rows of a table with foreign keys.
PLACED_BY = {"lineitem": "l_orderkey", "offers": "ps_partkey", "customer": "c_custkey", "supplier": "s_suppkey", "nation": "n_nationkey", "orders": "o_orderkey"}


@dataclass(frozen=True)
class FkEdge:
    """A foreign key; ``local`` if child rows live on the shard of their parent."""

    child: str
    fk: str
    parent: str
    pk: str
    local: bool


EDGES = (
    FkEdge("lineitem", "l_orderkey", "orders", "o_orderkey", True),
    FkEdge("offers", "ps_partkey", "part", "p_partkey", True),
    FkEdge("customer", "c_nationkey", "nation", "n_nationkey", True),
    FkEdge("supplier", "s_nationkey", "nation", "n_nationkey", True),
    FkEdge("nation", "n_regionkey", "region", "r_regionkey", True),
    FkEdge("orders", "o_custkey", "customer", "c_custkey", False),
    FkEdge("offers", "ps_suppkey", "supplier", "s_suppkey", False),
    FkEdge("lineitem", "l_partkey", "offers", "ps_partkey", False),
    FkEdge("lineitem", "l_suppkey", "supplier", "s_suppkey", False),
)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A base table, checked against its schema, or the derived ``offers``."""
    if name == "offers":
        return offers(load(spark, sf_dir, "lineitem"))
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    found = dict(df.dtypes)
    for column in SCHEMAS[name].split(", "):
        key, kind = column.split(" ", 1)
        if found.get(key) != kind:
            raise TypeError(f"{name}.{key} is {found.get(key)}, not {kind}")
    return df


def offers(lineitem: DataFrame) -> DataFrame:
    """One row for each part and supplier: cheapest unit cost in cents and quantity; stands in for the table that is not given."""
    quantity = F.col("l_quantity").cast("long")
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    return lineitem.groupBy(F.col("l_partkey").alias("ps_partkey"), F.col("l_suppkey").alias("ps_suppkey")).agg(F.min(F.floor(cents / quantity)).cast("long").alias("ps_cost_c"), F.sum(quantity).alias("ps_qty"))


def edges() -> tuple[FkEdge, ...]:
    return EDGES


def edge(child: str, parent: str) -> FkEdge:
    return next(e for e in EDGES if (e.child, e.parent) == (child, parent))


def edges_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(e.child, e.fk, e.parent, e.pk, e.local) for e in EDGES], "child string, fk string, parent string, pk string, is_local boolean")


def measured_edges(spark: SparkSession, sf_dir: str, shards: int) -> DataFrame:
    """Each edge as the tables hold it: child rows, those on the shard of their parent, distinct foreign keys, and rows whose parent is missing.

    An edge is local if all its rows are.  Keys of both ends meet by key, so none is sent to all.
    """
    ends = None
    for e in EDGES:
        here = F.lit(True) if e.parent in REPLICATED else F.pmod(F.col(e.fk), F.lit(shards)) == F.pmod(F.col(PLACED_BY[e.child]), F.lit(shards))
        name = [F.lit(e.child).alias("child"), F.lit(e.fk).alias("fk")]
        child = load(spark, sf_dir, e.child).select(*name, F.col(e.fk).cast("long").alias("key"), F.lit(1).alias("n"), here.cast("int").alias("here"), F.lit(False).alias("known"))
        parent = load(spark, sf_dir, e.parent).select(*name, F.col(e.pk).cast("long").alias("key"), F.lit(0).alias("n"), F.lit(0).alias("here"), F.lit(True).alias("known"))
        ends = child.unionAll(parent) if ends is None else ends.unionAll(child).unionAll(parent)
    keys = ends.groupBy("child", "fk", "key").agg(F.sum("n").alias("n"), F.sum("here").alias("here"), F.max("known").alias("known"))
    asked = F.col("key").isNotNull() & (F.col("n") > 0)
    found = keys.groupBy("child", "fk").agg(F.sum("n").alias("n_rows"), F.coalesce(F.sum("here"), F.lit(0)).alias("n_local"), F.count_if(asked).alias("n_keys"), F.coalesce(F.sum(F.when(asked & ~F.col("known"), F.col("n"))), F.lit(0)).alias("n_orphans"))
    named = edges_table(spark).drop("is_local").join(found, ["child", "fk"], "left").na.fill(0)
    return named.select("child", "fk", "parent", "pk", (F.col("n_local") == F.col("n_rows")).alias("is_local"), "n_rows", "n_local", "n_keys", "n_orphans")


def join_index(child: DataFrame, fk: str, shards: int) -> DataFrame:
    """Each distinct foreign key with the shard that owns its parent row."""
    return child.select(F.col(fk).alias("parent_key")).where(F.col("parent_key").isNotNull()).distinct().withColumn("parent_shard", F.pmod("parent_key", F.lit(shards)).cast("long"))
