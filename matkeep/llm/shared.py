"""Helpers the operators share: table access, lineage cuts in the shared folder, global row numbers."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, as the session names it.

    Only where the session names none (single-machine tests) is a temporary folder made and set.
    """
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local") or "cluster" in spark.sparkContext.master:
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        named = tempfile.mkdtemp(prefix="matkeep-")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back, so that its lineage ends there."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Text that is taken from a batch at a time; what a worker builds from it is handed on before more is read.
SLICE_BYTES = 1 << 20


def sliced(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    """Batches (a column, the texts, more) in slices of about a megabyte of text, one row at least."""
    for batch in batches:
        sizes = np.cumsum(np.diff(_offsets(batch.column(1))))
        start = 0
        while start < batch.num_rows:
            before = int(sizes[start - 1]) if start else 0
            end = max(start + 1, int(np.searchsorted(sizes, before + SLICE_BYTES, side="right")))
            part = batch.slice(start, end - start)
            yield tuple(part.columns)
            start = end


def _offsets(texts: pa.Array) -> np.ndarray:
    """Where each text begins and ends among the bytes."""
    kind = np.int64 if pa.types.is_large_string(texts.type) else np.int32
    return np.frombuffer(texts.buffers()[1], dtype=kind, count=texts.offset + len(texts) + 1)[texts.offset :]


def list_column(parts: list[np.ndarray], kind: pa.DataType) -> pa.ListArray:
    ends = np.concatenate([[0], np.cumsum([len(x) for x in parts])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(parts) if parts else [], kind))


def unused(name: str, *frames: DataFrame) -> str:
    """``name``, or it with signs in front, so that no column of the frames has it, whatever the letter case."""
    taken = {c.lower() for df in frames for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def global_index(df: DataFrame, order: list[str], name: str) -> tuple[DataFrame, int]:
    """Number all rows from 0 in the order of ``order``; also the count of rows.

    One range shuffle; a hot value is split as long as ``order`` ends in something that differs between its rows.
    The numbers come from each range's sorted position plus the rows in the ranges before it; only one number
    for each range (at most ``spark.sql.shuffle.partitions``) is brought to the driver.
    """
    spark = df.sparkSession
    n = partitions(spark)
    cols = [F.col(c).asc_nulls_first() for c in order]
    placed = cut(
        df.repartitionByRange(n, *cols).sortWithinPartitions(*cols).withColumn("_at", F.monotonically_increasing_id()),
        "ranked",
    )
    part = F.shiftright("_at", 33).cast("int")
    sizes = {r["p"]: r["n"] for r in placed.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()}
    total, starts = 0, []
    for p in range(max(sizes, default=-1) + 1):
        starts.append(total)
        total += sizes.get(p, 0)
    start = F.element_at(F.array(*[F.lit(s).cast("long") for s in starts]), part + 1) if starts else F.lit(0).cast("long")
    inside = F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    return placed.withColumn(name, start + inside).drop("_at"), total


def text_or_empty(col: str | Column = "text") -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))
