"""Arrow functions and table functions around the methods, usable from SQL after ``register``."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from thriftline.operators import keycodec, pairing
from thriftline.shipping import ship


@pandas_udf("long")
def packed_size(keys: pd.Series) -> pd.Series:
    """Bytes of a sorted array of keys as variable-length gaps."""
    return keys.map(lambda k: len(keycodec.pack_keys(sorted(set(k)))))


@udtf(returnType="key: bigint")
class UnpackKeys:
    """The keys of one packed block."""

    def eval(self, data: bytes):
        for key in keycodec.unpack_keys(data).tolist():
            yield (key,)


@udtf(returnType="round: int, u: int, v: int")
class PairingRounds:
    """The 1-factor schedule of so many shards."""

    def eval(self, shards: int):
        for r in range(shards):
            for u in range(shards):
                yield r, u, pairing.partner(r, u, shards)


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Makes the functions known to SQL, and the tables of a folder as views."""
    ship(spark)
    spark.udf.register("packed_size", packed_size)
    spark.udtf.register("unpack_keys", UnpackKeys)
    spark.udtf.register("pairing_rounds", PairingRounds)
    if sf_dir:
        from thriftline.sources.catalog import SCHEMAS, load

        for name in SCHEMAS:
            load(spark, sf_dir, name).createOrReplaceTempView(name)



