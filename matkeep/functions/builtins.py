"""User functions as rule built-ins, a grouped aggregate, and a table function. Rules never look inside them."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DataType, LongType, StringType, StructType


def register_builtin(spark: SparkSession, name: str, fn: Callable, kind: str | DataType, arrow: bool = True) -> None:
    """Makes ``fn`` callable by name in rule expressions; ``arrow`` functions take and give pandas Series."""
    spark.udf.register(name, F.pandas_udf(fn, kind) if arrow else F.udf(fn, kind))


def after_first_dot(h: pd.Series) -> pd.Series:
    return h.str.partition(".")[2]


@F.pandas_udf(LongType())
def fingerprint(v: pd.Series) -> int:
    """Order-free fingerprint of a group: a sum of scrambled members, within 62 bits."""
    return int(sum((int(x) * 2654435761 % 4294967291) for x in v) % (1 << 62))


@F.udtf(returnType=StructType().add("suffix", StringType()))
class Suffixes:
    """All dot suffixes of a host."""

    def eval(self, host: str):
        while host:
            yield (host,)
            host = host.partition(".")[2]


def cosine(a: str, b: str) -> Column:
    """Cosine of two numeric arrays of equal length."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(F.col(a), F.col(b)) / F.sqrt(dot(F.col(a), F.col(a)) * dot(F.col(b), F.col(b)))


def nearest(df: DataFrame, key: str, vector: str, block: int = 4096) -> DataFrame:
    """For each vector its nearest other by cosine, ties by key: columns i, j.

    Vectors are compared in blocks held by the executors; only the best of each block leaves it. ``block`` bounds what a
    task holds. All pairs are compared, so this is for tables of up to some millions of vectors.
    """
    import numpy as np

    numbered = df.select(F.col(key).cast("long").alias("k"), F.col(vector).alias("v")).withColumn("b", F.pmod(F.xxhash64("k"), F.lit(max(1, -(-df.count() // block)))))
    right = numbered.groupBy("b").agg(F.collect_list(F.struct("k", "v")).alias("r"))
    left = numbered.groupBy("b").agg(F.collect_list(F.struct("k", "v")).alias("l")).withColumnRenamed("b", "c")

    def best(batches):
        for pdf in batches:
            for _, row in pdf.iterrows():
                lk, rk = (np.array([x["k"] for x in row[s]], dtype=np.int64) for s in "lr")
                lv, rv = (np.array([x["v"] for x in row[s]], dtype=np.float64) for s in "lr")
                lv, rv = (m / np.linalg.norm(m, axis=1, keepdims=True) for m in (lv, rv))
                order = np.argsort(rk)
                sims = lv @ rv[order].T
                sims[lk[:, None] == rk[order][None, :]] = -np.inf
                at = sims.argmax(1)
                yield pd.DataFrame({"i": lk, "j": rk[order][at], "s": sims[np.arange(len(lk)), at]})

    # Blocks meet, not rows: their number is the table's size over ``block``.
    found = left.crossJoin(right).mapInPandas(best, "i long, j long, s double").where("s > double('-infinity')")
    return found.groupBy("i").agg(F.max_by("j", F.struct("s", -F.col("j"))).alias("j"))
