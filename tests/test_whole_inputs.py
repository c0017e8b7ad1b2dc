"""Queries that read whole tables, against plain counts of all their rows."""

import datetime


def test_interval_join_takes_every_error_as_a_span(spark, sf):
    from thriftline.plans import surface

    events = [(r["event_id"], r["ts"], r["event_type"]) for r in spark.read.parquet(f"{sf}/events.parquet").collect()]
    errors = [(i, t) for i, t, kind in events if kind == "error"]
    expected = {i: sum(t <= u < t + datetime.timedelta(seconds=600) for _, u, _ in events) for i, t in errors}
    assert {r["span_id"]: r["n"] for r in surface.QUERIES["join_interval_all"](spark, sf).collect()} == expected


def test_joins_and_sets_read_whole_tables(spark, sf):
    from thriftline.plans import surface

    rows = lambda name: [tuple(r) for r in surface.QUERIES[name](spark, sf).collect()]
    docs = {r["doc_id"] for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id").collect()}
    labels = {r["doc_id"] for r in spark.read.parquet(f"{sf}/labels.parquet").select("doc_id").collect()}
    expected = {"inner": docs & labels, "left": docs, "right": labels, "full": docs | labels, "semi": docs & labels, "anti": docs - labels}
    for how, ids in expected.items():
        assert {r[0] for r in rows(f"join_{how}_whole")} == ids
    orders = [(r["o_custkey"], r["o_orderstatus"]) for r in spark.read.parquet(f"{sf}/orders.parquet").collect()]
    f, o = ({k for k, status in orders if status == wanted} for wanted in "FO")
    assert f & o and f - o
    for name, keys in {"union": f | o, "union_all": f | o, "intersect": f & o, "intersect_all": f & o, "except": f - o}.items():
        assert {r[0] for r in rows(f"set_{name}_status")} == keys


def test_scheduled_exchange_deals_pairs_round_by_round(spark, sf):
    from pyspark.sql import functions as F

    from thriftline.operators import collectives, pairing
    from thriftline.operators.placement import key_shard
    from thriftline.plans import workloads

    owned = workloads.quarter_partials(spark, sf).withColumn("owner", key_shard("key", 8))
    rounds = [r.select("shard", "owner", "key", "val").collect() for r in collectives.exchange_rounds(owned, "shard", "owner", 8)]
    assert len(rounds) == 8
    for step, rows in enumerate(rounds):
        assert rows and all(r["owner"] == pairing.partner(step, r["shard"], 8) for r in rows)
    dealt = sorted(tuple(r) for rows in rounds for r in rows)
    assert dealt == sorted(tuple(r) for r in owned.select("shard", "owner", "key", F.col("val")).collect())


def test_salted_join_sends_no_copies_through_the_driver(spark, sf):
    from thriftline import registry

    df = registry.QUERIES["join_salted"](spark, sf)
    df.collect()
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Broadcast" not in plan


def test_pairing_schedule_carries_every_order(spark, sf):
    from thriftline import registry

    rows = registry.QUERIES["pairing_schedule"](spark, sf).collect()
    assert len(rows) == 144 and all((r["u"] + r["v"]) % 12 == r["round"] for r in rows)
    assert sum(r["n_rows"] for r in rows) == spark.read.parquet(f"{sf}/orders.parquet").count()


def test_udtf_pairing_carries_every_line(spark, sf):
    from thriftline import registry

    rows = registry.QUERIES["udtf_pairing"](spark, sf).collect()
    assert len(rows) == 36 and all((r["u"] + r["v"]) % 6 == r["round"] for r in rows)
    assert sum(r["n_rows"] for r in rows) == spark.read.parquet(f"{sf}/lineitem.parquet").count()


def test_filter_costs_are_those_of_the_tables(spark, sf):
    import math

    from thriftline import registry

    rows = registry.QUERIES["filter_cost_grid"](spark, sf).where("attribute = 'c_mktsegment'").collect()
    customers = [r["c_mktsegment"] for r in spark.read.parquet(f"{sf}/customer.parquet").collect()]
    orders = [(r["o_orderpriority"], r["o_custkey"]) for r in spark.read.parquet(f"{sf}/orders.parquet").collect()]
    assert {(r["asking"], r["value"], r["p"]) for r in rows} == {(a, c, 2.0**d) for a, _ in orders for c in customers for d in range(8)}
    for r in rows:
        n, m, hits = len({k for a, k in orders if a == r["asking"]}), len(customers), customers.count(r["value"])
        assert (r["n"], r["m"], r["gamma"]) == (n, m, hits / m)
        assert abs(r["late_bits"] - n / r["p"] * math.log2(max(m * r["p"] / n, 1))) <= 0.51 and abs(r["bitset_bits"] - hits * math.log2(m / hits)) <= 0.51


def test_edges_are_measured_on_the_tables(spark, sf):
    from thriftline import registry
    from thriftline.sources import catalog

    rows = {(r["child"], r["fk"], r["parent"], r["pk"]): r for r in registry.QUERIES["fk_edges"](spark, sf).collect()}
    assert {k: r["is_local"] for k, r in rows.items()} == {(e.child, e.fk, e.parent, e.pk): e.local for e in catalog.EDGES}
    lines = spark.read.parquet(f"{sf}/lineitem.parquet")
    row = rows["lineitem", "l_suppkey", "supplier", "s_suppkey"]
    assert (row["n_rows"], row["n_keys"]) == (lines.count(), lines.select("l_suppkey").distinct().count())
