"""A bounded, balanced sample of labelled documents for fitting classifiers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import text_or_empty


#: Tasks that a sample is dealt to.
SAMPLE_TASKS = 8


def fold(doc_id: Column, folds: int) -> Column:
    """crc32 of the id as text, modulo ``folds``; a null id counts as empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % folds


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, folds: int, held_out: int, per_class: int) -> tuple[DataFrame, dict[int, int]]:
    """Texts with ``label`` (0 or 1) from outside the held-out fold, and how many labels of each class there are.

    At most ``per_class`` rows of each class, the first by a hash of their id, so the sample is the same in every run
    and its size does not grow with the input. Rows with a null label or id are left out; of an id's several labels the
    larger counts, of its several texts the smallest by hash.
    """
    rows = labels.select("doc_id", F.col(label).cast("int").alias("label")).where(F.col("doc_id").isNotNull() & F.col("label").isin(0, 1))
    rows = rows.where(fold(F.col("doc_id"), folds) != held_out).groupBy("doc_id").agg(F.max("label").alias("label"))
    sizes = {r["label"]: r["n"] for r in rows.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    order = F.xxhash64("doc_id", F.lit("sample"))
    of_class = lambda c: rows.where(F.col("label") == c).orderBy(order, "doc_id").limit(per_class)
    chosen = of_class(0).unionByName(of_class(1))
    # At most 2 * per_class ids and labels are broadcast.
    found = docs.select("doc_id", text_or_empty().alias("text")).join(F.broadcast(chosen), "doc_id")
    return found, sizes
