"""Methods beyond their queries: worked examples, bounds, equal results of variants, edge cases and plan shapes."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from thriftline.operators import collectives, costmodel, deferred, keycodec, pairing, placement, planner, relational, semifilter, topk_baselines, topk_bounds, topk_lazy, topk_merge
from thriftline.sources import catalog

PARTS = "shard long, key long, val long"


def random_parts(spark, seed, shards=5, keys=300, high=1 << 40):
    rng = random.Random(seed)
    rows = [(s, k, rng.choice([0, rng.randrange(high), rng.randrange(1000)])) for s in range(shards) for k in range(keys) if rng.random() < 0.7]
    return spark.createDataFrame(rows, PARTS), rows


def best_of(rows, k):
    sums = {}
    for _, key, val in rows:
        sums[key] = sums.get(key, 0) + val
    kth = sorted(sums.values(), reverse=True)[:k]
    return {(a, b) for a, b in sums.items() if kth and b >= kth[-1]}


def test_worked_blocks(spark):
    parts = spark.createDataFrame([(0, 0, 13), (0, 1, 200), (0, 2, 255), (1, 0, 100), (1, 1, 0), (1, 2, 7)], PARTS)
    got = {(r["shard"], r["key"]): (r["shift"], r["code"], r["lo"], r["hi"]) for r in topk_bounds.code_columns(parts, 4, 1024).collect()}
    assert got == {(0, 0): (4, 0, 0, 15), (0, 1): (4, 12, 192, 207), (0, 2): (4, 15, 240, 255), (1, 0): (3, 12, 96, 103), (1, 1): (3, 0, 0, 7), (1, 2): (3, 0, 0, 7)}
    sums = {r["key"]: (r["lo"], r["hi"]) for r in topk_bounds.decode_sum(topk_bounds.encode(parts, 4), 4).collect()}
    assert sums == {0: (96, 118), 1: (192, 214), 2: (240, 262)}
    assert [r["key"] for r in topk_bounds.survivors(topk_bounds.decode_sum(topk_bounds.encode(parts, 4), 4), 1).collect()] == [2]


@pytest.mark.parametrize("width, group, k", [(1, 16, 3), (8, 1024, 1), (8, 7, 20), (12, 64, 1000), (16, 1024, 5)])
def test_bounds_are_sound_and_exact(spark, width, group, k):
    parts, rows = random_parts(spark, width + k)
    sums = {}
    for _, key, val in rows:
        sums[key] = sums.get(key, 0) + val
    bounds = {r["key"]: (r["lo"], r["hi"]) for r in topk_bounds.decode_sum(topk_bounds.encode(parts, width, group), width, group).collect()}
    assert bounds.keys() == sums.keys() and all(bounds[x][0] <= sums[x] <= bounds[x][1] for x in sums)
    for residual in (False, True):
        found = topk_bounds.run(parts, k, width, group, residual=residual)
        assert {(r["key"], r["total"]) for r in found.df.collect()} == best_of(rows, k)


def test_wider_codes_leave_no_more_survivors(spark):
    parts, _ = random_parts(spark, 9)
    counts = [topk_bounds.survivors(topk_bounds.decode_sum(topk_bounds.encode(parts, w), w), 5).count() for w in (4, 8, 12, 16)]
    assert counts == sorted(counts, reverse=True)


@pytest.mark.parametrize("rows", [[], [(0, 1, 5)], [(s, k, 77) for s in range(4) for k in range(50)], [(0, k, -k) for k in range(20)], [(s, k, 0) for s in range(3) for k in range(5)]])
def test_extreme_parts(spark, rows):
    parts = spark.createDataFrame(rows, PARTS)
    for k in (1, 3, 100):
        assert {(r["key"], r["total"]) for r in topk_bounds.run(parts, k).df.collect()} == best_of(rows, k)
        if all(v >= 0 for _, _, v in rows):
            assert {(r["key"], r["total"]) for r in topk_baselines.uniform_threshold(parts, 4, k).df.collect()} == best_of(rows, k)
            assert {(r["key"], r["total"]) for r in topk_baselines.threshold_algorithm(parts, k, 4).df.collect()} == best_of(rows, k)


def test_baselines_agree(spark):
    parts, rows = random_parts(spark, 21)
    for k in (1, 7):
        assert {(r["key"], r["total"]) for r in topk_baselines.full(parts, k).collect()} == best_of(rows, k)
        assert {(r["key"], r["total"]) for r in topk_baselines.threshold_algorithm(parts, k, 8).df.collect()} == best_of(rows, k)
        assert {(r["key"], r["total"]) for r in topk_baselines.uniform_threshold(parts, 5, k).df.collect()} == best_of(rows, k)


def test_key_sets_round_trip(spark):
    keys = np.array([0, 1, 5, 127, 128, 300, 1 << 33])
    assert keycodec.unpack_keys(keycodec.pack_keys(keys)).tolist() == keys.tolist()
    assert len(keycodec.pack_keys(keys)) == 1 + 1 + 1 + 1 + 1 + 2 + 5
    rng = np.random.default_rng(0)
    many = np.unique(rng.integers(0, 1 << 62, 5000))
    assert (keycodec.unpack_keys(keycodec.pack_keys(many)) == many).all()
    assert keycodec.unpack_keys(keycodec.pack_keys(np.zeros(0, np.int64))).tolist() == []
    df = spark.createDataFrame([(int(k) % 3, int(k)) for k in keys] * 2 + [(1, None)], "by long, key long")
    assert sorted(r["key"] for r in keycodec.unpacked(keycodec.packed(df, "key", "by")).collect()) == keys.tolist()
    small = df.where("key < 100000")
    assert sorted(r["key"] for r in keycodec.from_bitset(keycodec.to_bitset(small, "key")).collect()) == keys[:-1].tolist()
    ids = keycodec.dense_ids(spark.createDataFrame([(f"v{i % 40}",) for i in range(100)] + [(None,)], "v string"), "v", 7).collect()
    assert sorted(r["key"] for r in ids) == list(range(40))


@pytest.mark.parametrize("shards", [1, 2, 4, 7, 16])
def test_pairing(spark, shards):
    rows = {(r["round"], r["u"]): r["v"] for r in pairing.schedule(spark, shards).collect()}
    assert all(rows[r, v] == u and v == pairing.partner(r, u, shards) for (r, u), v in rows.items())
    assert len({(u, v) for (_, u), v in rows.items()}) == shards * shards
    if shards == 4:
        rounds = [{tuple(sorted((u, rows[r, u]))) for u in range(4)} for r in range(4)]
        assert rounds == [{(0, 0), (1, 3), (2, 2)}, {(0, 1), (2, 3)}, {(0, 2), (1, 1), (3, 3)}, {(0, 3), (1, 2)}]


def test_cost_model():
    assert costmodel.bits_late(1024, 1024, 4) == 512 and costmodel.bits_bitset(1024, 0.25) == 512
    assert costmodel.bits_bitset(100, 0) == costmodel.bits_late(0, 10, 2) == 0
    assert costmodel.bits_bitset_entropy(100, 1) == 0 and costmodel.bits_bitset_entropy(1000, 0.2) > costmodel.bits_bitset(1000, 0.2)
    assert costmodel.choose_filter(1e9, 1000, 0.5, 2) == "bitset"
    assert costmodel.choose_filter(1e6, 1e12, 0.5, 1000) == "late"
    # Asking gets cheaper than the bitset as shards grow with the data.
    choices = [costmodel.choose_filter(72_000_000 * p, 15_000_000 * p, 0.2, p, budget_bytes=1 << 40) for p in (1, 128, 1000)]
    assert choices[0] == "bitset" and choices[-1] == "late"
    assert costmodel.choose_topk(100, 0, 8) == "full" and costmodel.choose_topk(1 << 40, 0, 8) == "bounds" and costmodel.choose_topk(1 << 40, -1, 8) == "full"
    assert costmodel.worth_compressing(1e9, 4, 1e9, 1e8) and not costmodel.worth_compressing(1e9, 1.1, 1e8, 1e9)


@pytest.mark.parametrize("variant", list(semifilter.VARIANTS))
@pytest.mark.parametrize("gamma", ["none", "some", "all"])
def test_filters_drop_nulls(spark, variant, gamma):
    local = spark.createDataFrame([(1, 0), (2, 1), (3, None), (4, 40_000), (5, 99), (6, 1)], "id long, fk long")
    remote = spark.createDataFrame([(0, "a"), (1, "a"), (2, "b"), (40_000, None), (7, "a")], "pk long, attr string")
    condition = {"none": F.col("attr") == "z", "some": F.col("attr") == "a", "all": F.coalesce(F.col("attr"), F.lit("x")) != "z"}[gamma]
    expected = {"none": [], "some": [1, 2, 6], "all": [1, 2, 4, 6]}[gamma]
    assert sorted(r["id"] for r in semifilter.VARIANTS[variant](local, "fk", remote, "pk", condition).collect()) == expected
    assert semifilter.VARIANTS[variant](local.limit(0), "fk", remote, "pk", condition).count() == 0


def test_bitset_beyond_its_budget_is_shuffled(spark):
    local, remote = spark.range(1000).selectExpr("id", "id * 7 as fk"), spark.range(5000).selectExpr("id as pk", "id % 2 = 0 as ok")
    small = semifilter.bitset(local, "fk", remote, "pk", F.col("ok"), budget_bytes=0)
    assert "BroadcastHashJoin" not in semifilter.bitset(local, "fk", remote, "pk", F.col("ok"), budget_bytes=0).hint("merge")._jdf.queryExecution().optimizedPlan().toString()
    assert small.count() == sum(1 for i in range(1000) if i * 7 < 5000 and i % 2 == 0)


@pytest.mark.parametrize("policy", [{}, {"chunk": 1, "growth": 1.0}, {"chunk": 3, "prune_every": 1}])
def test_lazy_top_k(spark, policy):
    rng = random.Random(1)
    rows = [(i, rng.randint(0, 30), rng.choice([None, rng.randrange(20)]), i % 3) for i in range(120)]
    df = spark.createDataFrame(rows, "key long, score long, fk long, shard long")
    remote = spark.createDataFrame([(i, i % 4 == 0) for i in range(20)], "pk long, ok boolean")
    passing = sorted((-s, k) for k, s, f, _ in rows if f is not None and f % 4 == 0)
    for k in (0, 1, 5, 500):
        found = topk_lazy.run(df, "score", "key", "fk", remote, "pk", F.col("ok"), k, **policy)
        assert [(-r["score"], r["key"]) for r in found.df.collect()] == passing[:k]
        assert found.asked <= len(rows)
    assert topk_lazy.run(df, "score", "key", "fk", remote, "pk", F.lit(False), 2, **policy).df.count() == 0


def test_top_k_merges(spark):
    rows = spark.createDataFrame([(i, i % 7, (i * 37) % 50) for i in range(200)], "key long, shard long, score long")
    by = [F.col("score").desc(), F.col("key")]
    expected = [tuple(r) for r in topk_merge.gather(rows, by, 9).select("key", "score").collect()]
    for fanin in (2, 3, 8):
        got = topk_merge.tree(rows, by, 9, fanin, shards=7).select("key", "score").collect()
        assert sorted(map(tuple, got)) == sorted(expected)
    ties = spark.createDataFrame([(9,), (8,), (8,), (7,)], "s long")
    assert sorted(r["s"] for r in topk_merge.with_ties(ties, F.col("s"), 2).collect()) == [8, 8, 9]
    for k in (1, 17, 200):
        assert topk_merge.threshold_select(rows, "score", k, ways=4) == sorted((r["score"] for r in rows.collect()), reverse=True)[k - 1]
    assert topk_merge.threshold_select(rows.limit(0), "score", 3) is None


def test_placement(spark):
    rows = spark.range(1000).withColumnRenamed("id", "key")
    for how, more in (("hash", {}), ("modulus", {}), ("round_robin", {}), ("range", {"keys": 1000}), ("range", {})):
        counts = [r["count"] for r in placement.place(rows, "key", 8, how, **more).groupBy("shard").count().collect()]
        assert len(counts) == 8 and sum(counts) == 1000 and max(counts) <= 200
    assert [r["rank"] for r in placement.ranked(rows, "key", 64).orderBy("key").collect()] == list(range(1000))
    with pytest.raises(ValueError):
        placement.replicate(rows)
    with pytest.raises(ValueError):
        collectives.allgather(rows, budget_bytes=100)


def test_copartitioned_join_moves_nothing_more(spark, sf):
    lines, orders = placement.colocate(catalog.load(spark, sf, "lineitem"), catalog.load(spark, sf, "orders"), "l_orderkey", "o_orderkey", 4)
    joined = lines.join(orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_orderkey").count()
    assert joined._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") == 2


def test_bucketed_tables_join_without_exchange(spark):
    for name, key in (("bucket_a", "a"), ("bucket_b", "b")):
        placement.store_bucketed(spark.range(100).withColumnRenamed("id", key), name, key, 4)
    plan = spark.table("bucket_a").join(spark.table("bucket_b").hint("merge"), F.col("a") == F.col("b"))._jdf.queryExecution().executedPlan().toString()
    spark.sql("drop table bucket_a")
    spark.sql("drop table bucket_b")
    assert "Exchange" not in plan


def test_planner_and_catalog(spark, sf):
    local = [catalog.edge("lineitem", "orders")]
    assert planner.classify(local) == "local" and planner.classify([*local, catalog.edge("orders", "customer")]) == "remote"
    assert [len(x) for x in planner.split(catalog.edges())] == [5, 4]
    with pytest.raises(TypeError):
        catalog.SCHEMAS["region"], kept = "r_regionkey bigint", catalog.SCHEMAS["region"]
        try:
            catalog.load(spark, sf, "region")
        finally:
            catalog.SCHEMAS["region"] = kept


def test_scans_are_pruned_and_pushed(spark, sf):
    from thriftline import registry

    plan = registry.QUERIES["q14"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate)" in plan or "GreaterThanOrEqual(l_shipdate" in plan
    assert "l_comment" not in plan and "l_returnflag" not in plan


def test_joins_beyond_spark(spark):
    a = spark.createDataFrame([(1, 5, "x"), (1, 9, "y"), (2, 1, "z"), (None, 3, "n")], "k long, t long, v string")
    b = spark.createDataFrame([(1, 4, 40), (1, 5, 50), (1, 8, 80), (2, 2, 20)], "k long, u long, w long")
    got = {r["v"]: r["w"] for r in relational.asof(a, b, "k", "t", "u", ["w"]).collect()}
    assert got == {"x": 50, "y": 80, "z": None, "n": None}
    hot = spark.createDataFrame([(i, 0 if i < 90 else i) for i in range(100)], "l_orderkey long, f long")
    assert relational.salted(hot, spark.createDataFrame([(i,) for i in range(100)], "p long"), ("f", "p"), 4).count() == 100


def test_deferred_columns(spark):
    result, source = spark.createDataFrame([(3, 1), (5, 2)], "id long, s long"), spark.range(10).selectExpr("id as key", "concat('n', id) as name")
    for bound in (None, 10):
        assert sorted(r["name"] for r in deferred.attach(result, "id", source, "key", ["name"], bound).collect()) == ["n3", "n5"]


def test_meters(spark):
    from thriftline import meters

    found = meters.timed(spark, lambda: spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count(), 2)
    assert found["wall_max"] >= found["wall_mean"] > 0 and meters.blend(1, 2) == pytest.approx(1.4)


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_codes_are_made_before_the_first_exchange(spark, sf):
    from thriftline.operators import topk_bounds
    from thriftline.plans import methods

    rows = methods._part_rows(spark, sf)
    assert "Exchange" not in _plan(topk_bounds.code_rows(rows))
    sums = {r["key"]: r["total"] for r in rows.groupBy("key").agg(F.sum("val").alias("total")).collect()}
    for width, group in ((3, 7), (8, 1024), (12, 100)):
        bounds = topk_bounds.decode_sum(topk_bounds.code_rows(rows.repartition(5), width, group), width, group).collect()
        assert {r["key"] for r in bounds} == set(sums) and all(r["lo"] <= sums[r["key"]] <= r["hi"] for r in bounds)


def test_bounds_exchange_fewer_bytes_than_full_sums(spark):
    from thriftline import meters
    from thriftline.operators import topk_baselines, topk_bounds
    from thriftline.shipping import written

    rows = written(spark.range(400_000, numPartitions=4).select((F.col("id") % 100_000).alias("key"), (F.pmod(F.xxhash64("id"), F.lit(1 << 44)) + F.when(F.col("id") % 100_000 < 5, 1 << 46).otherwise(0)).alias("val")))

    def moved(run):
        meters.barrier(spark)
        before = meters.totals(spark)["shuffle_bytes"]
        best = sorted(tuple(r) for r in run().select("key", "total").collect())
        meters.barrier(spark)
        return best, meters.totals(spark)["shuffle_bytes"] - before

    (a, full), (b, coded) = moved(lambda: topk_baselines.full(rows, 5)), moved(lambda: topk_bounds.run_rows(rows, 5).df)
    assert a == b and 2 * coded < full


def test_negative_values_and_nulls_are_summed_in_full(spark):
    from thriftline.operators import topk_bounds

    rows = spark.createDataFrame([(1, -5), (1, 9), (2, 3), (None, 7), (3, None), (-4, 1 << 40)], "key long, val long")
    assert sorted(tuple(r) for r in topk_bounds.run_rows(rows.where("key is not null and val is not null"), 2).df.collect()) == [(-4, 1 << 40), (1, 4)]
    assert topk_bounds.run_rows(rows.limit(0), 2).df.count() == 0


def test_placed_tables_are_joined_without_an_exchange(spark, sf):
    from thriftline.plans import workloads

    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        # The only exchange is that of the counts.
        assert _plan(workloads.q04_placed(spark, sf)).count("Exchange hashpartitioning") == 1
        assert _plan(workloads.q04(spark, sf)).count("Exchange hashpartitioning") == 3
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


@pytest.mark.parametrize("ordered", [True, False])
def test_packed_requests_and_replies(spark, ordered):
    from thriftline.operators import keycodec, semifilter

    keys = [0, -1, -32768, 1, 32768, 32769, 70_000, 10**9, None, 5, 5]
    local = spark.createDataFrame([(k, n) for n, k in enumerate(keys)], "fk long, n long").repartition(3)
    remote = spark.createDataFrame([(k, k % 2 == 0) for k in (0, -1, -32768, 1, 32768, 32769, 70_000, 10**9, 5, 8)], "pk long, ok boolean")
    got = sorted(r["n"] for r in semifilter.packed(local, "fk", remote, "pk", F.col("ok"), ordered).collect())
    assert got == sorted(n for n, k in enumerate(keys) if k is not None and k % 2 == 0)
    asked = keycodec.requests(local, "fk", ordered)
    assert "Exchange" not in _plan(keycodec.requests(local.coalesce(1), "fk", ordered)).split("MapInArrow")[0] and asked.agg(F.sum("n")).first()[0] >= 9


def test_meters_have_all_fields(spark):
    from thriftline import meters

    found = meters.timed(spark, lambda: spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count(), 1)
    assert set(found) == {"wall_mean", "wall_max", "wall_median", "blend", "shuffle_bytes", "cpu_s", "comm_share"} and found["shuffle_bytes"] > 0


@pytest.mark.parametrize("code", keycodec.CODES)
@pytest.mark.parametrize("keys", [[], [0], [7], [0, 1, 2, 3], [5, 6, 1 << 20, (1 << 40) + 3], list(range(3, 5000, 7))])
def test_codes_give_back_what_they_took(code, keys):
    data = keycodec.pack_keys(np.array(keys, np.int64), code)
    assert keycodec.unpack_keys(data, code).tolist() == keys


def test_sizes_of_codes():
    gaps = np.array([0, 1, 2, 3, 4, 100])
    assert len(keycodec.encode_bitpack(gaps)) == 9 + -(-len(gaps) * 7 // 8)
    assert len(keycodec.encode_elias_gamma(gaps)) == 8 + -(-sum(2 * (g + 1).bit_length() - 1 for g in gaps.tolist()) // 8)


def test_unsorted_keys_are_compressed_by_blocks_or_left_as_they_are():
    keys = [9, 3, 3, 1 << 50, -4] * 400
    for code in ("raw", "block"):
        assert keycodec.unpack_keys(keycodec.pack_keys(np.array(keys), code), code).tolist() == keys
    assert len(keycodec.pack_keys(np.array(keys), "block")) < 8 * len(keys) / 4


def test_handover_is_the_only_exchange_of_orders(spark, sf):
    from thriftline.plans import workloads

    plan = _plan(workloads.q13_handover(spark, sf))
    assert plan.count("REPARTITION_BY_COL") == 1
    assert "partial_count(1)" not in plan.split("REPARTITION_BY_COL")[1].split("FileScan")[0]


def test_held_attribute_asks_no_customers(spark, sf):
    from thriftline.plans import workloads

    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        plan = _plan(workloads.q03_held(spark, sf))
        assert plan.count("FileScan") == 2 and "c_custkey" not in plan and "Exchange hashpartitioning" not in plan and "BroadcastExchange" not in plan
        assert _plan(workloads.q03(spark, sf, "bitset")).count("FileScan") == 3
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_request_answers_each_key_once(spark):
    keys = spark.createDataFrame([(1,), (1,), (3,), (None,), (9,)], "fk long")
    remote = spark.createDataFrame([(1, "a"), (2, "b"), (3, "c")], "pk long, name string")
    assert sorted(tuple(r) for r in collectives.request(keys, "fk", remote, "pk", ["name"]).collect()) == [(1, "a"), (3, "c")]
