"""The experiments: weak scaling, thread speed-up, three ways to the best supplier, throughput of codes and of the exchange.

``python -m thriftline.studies NAME...`` runs some or all and prints a JSON line each.  Absolute seconds are those of one machine; what
"""

from __future__ import annotations

import json
import subprocess
import sys
import time

ROOT = "/root/testdata"
SCALING = ("q01", "q03_bitset", "q03_repl", "q03_lazy", "q04", "q13", "q15_bounds", "q15_full", "q18_late_columns", "q21_bitset", "q21_repl", "q21_late")


def _session(cores: int):
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(max(2, cores))).config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def _times(cores: int, sf: str, names) -> dict:
    from thriftline import meters, registry

    spark, out = _session(cores), {}
    for name in names:
        registry.QUERIES[name](spark, f"{ROOT}/{sf}").count()
        found = meters.timed(spark, lambda name=name: registry.QUERIES[name](spark, f"{ROOT}/{sf}"), 3)
        out[name] = {k: round(v, 4) for k, v in found.items()}
    spark.stop()
    return out


def _apart(*arguments: str) -> dict:
    """A study in a process of its own: a Spark application has one number of cores."""
    done = subprocess.run([sys.executable, "-m", "thriftline.studies", "--times", *arguments], capture_output=True, text=True, check=True)
    return json.loads(done.stdout.strip().splitlines()[-1])


def weak_scaling() -> dict:
    """Ten times the data on more cores each time."""
    return {f"{sf} on {cores}": _apart(str(cores), sf, *SCALING) for cores, sf in ((1, "sf0.001"), (2, "sf0.01"), (8, "sf0.1"))}


def thread_speedup() -> dict:
    one, many = _apart("1", "sf0.1", *SCALING), _apart("8", "sf0.1", *SCALING)
    return {k: round(one[k]["wall_median"] / many[k]["wall_median"], 2) for k in SCALING}


def three_ways() -> dict:
    """Bits and seconds of full values, full values by the schedule and bounds, for the supplier and the part domain."""
    return _apart("8", "sf0.1", "q15_full", "q15_full_scheduled", "q15_bounds", "topk_full_part", "topk_bounds_part")


def codes() -> dict:
    """Bytes of parts coded and decoded in a second, and of keys exchanged."""
    from pyspark.sql import functions as F

    from thriftline.operators import topk_bounds
    from thriftline.shipping import written
    from thriftline.sources.io import discard

    spark = _session(8)
    parts = written(spark.range(1 << 23).select(F.pmod("id", F.lit(8)).alias("shard"), F.floor(F.col("id") / 8).alias("key"), F.pmod(F.xxhash64("id"), F.lit(1 << 40)).alias("val")))
    size, out = 8 * (1 << 23), {}
    begin = time.perf_counter()
    blocks = written(topk_bounds.encode(parts))
    out["encode_mb_s"] = round(size / 1e6 / (time.perf_counter() - begin), 1)
    begin = time.perf_counter()
    discard(topk_bounds.decode_sum(blocks))
    out["decode_mb_s"] = round(size / 1e6 / (time.perf_counter() - begin), 1)
    begin = time.perf_counter()
    discard(parts.select("key").repartition(8, "key"))
    out["exchange_mb_s"] = round(size / 1e6 / (time.perf_counter() - begin), 1)
    out["code_bytes_over_full"] = round(blocks.agg(F.sum(F.length("codes") + F.length("present"))).first()[0] / size, 4)
    spark.stop()
    return out


STUDIES = {"weak_scaling": weak_scaling, "thread_speedup": thread_speedup, "three_ways": three_ways, "codes": codes}


def main(arguments: list[str]) -> None:
    if arguments[:1] == ["--times"]:
        print(json.dumps(_times(int(arguments[1]), arguments[2], arguments[3:])))
        return
    for name in arguments or STUDIES:
        print(json.dumps({name: STUDIES[name]()}), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
