"""Sharding along a Hilbert curve over document metadata.

Several metadata dimensions (language, source, size) are quantised in an order-preserving way, the cells are
numbered along a Hilbert curve, rows are ordered by that number, and the order is cut into runs. Rows near one
another in any dimension tend to share a run, so per-file minimum and maximum statistics prune on every dimension.

Only DataFrame functions are used. The text is read once, to measure it; what is shuffled is a short row of
numbers for each document.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .shared import cut, global_index, text_or_empty, unused

#: Bits of each dimension after quantisation.
BITS = 5


def hilbert_index(axes: list[Column], bits: int) -> Column:
    """Position of a cell on the Hilbert curve; ``axes`` are integer columns in [0, 2**bits).

    Works on an array state with higher-order functions, so the expression stays small for any number of axes.
    """
    n = len(axes)

    def flip_or_swap(state: Column, axis: int, q: Column) -> Column:
        low = q - 1
        first, here = state[0], state[axis]
        swapped = first.bitwiseXOR(here).bitwiseAND(low)
        new_first = F.when(here.bitwiseAND(q) != 0, first.bitwiseXOR(low)).otherwise(first.bitwiseXOR(swapped))
        if axis == 0:
            return F.array(F.when(first.bitwiseAND(q) != 0, first.bitwiseXOR(low)).otherwise(first), *[state[j] for j in range(1, n)])
        new_here = F.when(here.bitwiseAND(q) != 0, here).otherwise(here.bitwiseXOR(swapped))
        return F.array(new_first, *[new_here if j == axis else state[j] for j in range(1, n)])

    # Undo the curve's rotations from the top bit down: one fold step for each (bit, axis).
    steps = F.array(*[F.struct(F.lit(1 << b).cast("long").alias("q"), F.lit(a).alias("axis")) for b in range(bits - 1, 0, -1) for a in range(n)])

    def step(state: Column, s: Column) -> Column:
        out = state
        for a in range(n - 1, -1, -1):
            out = F.when(s["axis"] == a, flip_or_swap(state, a, s["q"])).otherwise(out)
        return out

    start = F.array(*[a.cast("long") for a in axes])
    turned = F.aggregate(steps, start, step)
    gray = F.aggregate(
        F.sequence(F.lit(1), F.lit(n - 1)),
        turned,
        lambda s, i: F.transform(s, lambda v, j: F.when(j == i, v.bitwiseXOR(F.element_at(s, i))).otherwise(v)),
    )
    # The last axis tells which lower bits are inverted in all axes.
    last = F.element_at(gray, n)
    inverted = reduce(
        lambda t, b: t.bitwiseXOR(F.when(last.bitwiseAND(F.lit(1 << b).cast("long")) != 0, F.lit((1 << b) - 1).cast("long")).otherwise(F.lit(0).cast("long"))),
        range(bits - 1, 0, -1),
        F.lit(0).cast("long"),
    )
    final = F.transform(gray, lambda v: v.bitwiseXOR(inverted))
    # Interleave: bit b of axis a is bit b*n + (n-1-a) of the index.
    bit_steps = F.array(*[F.struct(F.lit(a + 1).alias("axis"), F.lit(b).alias("bit")) for b in range(bits - 1, -1, -1) for a in range(n)])
    state = F.struct(final.alias("v"), F.lit(0).cast("long").alias("h"))
    folded = F.aggregate(
        bit_steps,
        state,
        lambda s, t: F.struct(
            s["v"].alias("v"),
            (s["h"] * 2 + F.call_function("shiftright", F.element_at(s["v"], t["axis"]), t["bit"]).bitwiseAND(F.lit(1).cast("long"))).alias("h"),
        ),
    )
    return folded["h"]


def ordered_prefix(col: str) -> Column:
    """The first seven bytes as a number that sorts as the strings do (scheme and ``www.`` of addresses left out)."""
    bare = F.regexp_replace(F.coalesce(F.col(col).cast("string"), F.lit("")), r"^[a-z]+://(www\.)?", "")
    return F.conv(F.rpad(F.substring(F.hex(F.encode(bare, "UTF-8")), 1, 14), 14, "0"), 16, 10).cast("long")


def _quantised(col: str, cuts: list) -> Column:
    """How many of the ascending cut points lie below the value."""
    found = F.array(*[F.lit(c) for c in cuts]) if cuts else F.array().cast("array<long>")
    return F.size(F.filter(found, lambda c: c < F.col(col))).cast("long")


def hilbert_shards(docs: DataFrame, shards: int = 16, bits: int = BITS) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard and the curve position ``cell``.

    Law ``rows``: shard row counts are at most one apart. ``size`` is the UTF-8 bytes of the text plus 1, a null text
    counts as empty. Ties on the curve go by text checksum, then doc_id, so equal texts of one cell stay together and a
    cell of any size can be cut. Null metadata sort first. Repeated rows are kept as rows of their own. An empty input
    gives an empty result. Other columns of ``docs`` are not read.
    """
    rows = docs.select(
        "doc_id",
        (F.octet_length(text_or_empty()).cast("long") + 1).alias("size"),
        F.crc32(text_or_empty()).alias("text_crc32"),
        ordered_prefix("lang").alias("_lang"),
        ordered_prefix("source").alias("_source"),
    )
    rows = cut(rows, "shard-rows")
    steps = (1 << bits) - 1
    shares = [i / (steps + 1) for i in range(1, steps + 1)]
    dims = ["_lang", "_source", "size"]
    points = rows.agg(*[F.percentile_approx(d, shares, 10_000).alias(d) for d in dims]).first()
    axes = [_quantised(d, points[d] or []) for d in dims]
    celled = rows.select("doc_id", "size", "text_crc32", hilbert_index(axes, bits).alias("cell"))
    ranked, total = global_index(celled, ["cell", "text_crc32", "doc_id"], "_rank")
    small, larger = divmod(total, shards)
    edge = larger * (small + 1)
    rank = F.col("_rank")
    shard = F.when(rank < edge, F.floor(rank / (small + 1))).otherwise(F.lit(larger) + F.floor((rank - edge) / max(small, 1)))
    placed = ranked.withColumn("shard", shard.cast("int"))
    first = F.col("shard") * F.lit(small).cast("long") + F.least(F.col("shard"), F.lit(larger))
    return placed.select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("rows").alias("law"),
        "shard",
        (rank - first).cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
        "cell",
    )


def write_shards(docs: DataFrame, placed: DataFrame, path: str) -> None:
    """Write the documents, all columns, as one folder ``shard=`` for each shard, in slot order within each file.

    A document and its place meet by doc_id, null included, and text checksum; repeated rows by their number among
    themselves. A column of ``docs`` named shard or slot keeps its values under the name ``own_shard`` or ``own_slot``.
    """
    own = docs.withColumnsRenamed({c: unused(f"own_{c.lower()}", docs) for c in docs.columns if c.lower() in ("shard", "slot")})
    names = {c: unused(f"_{c}", own) for c in ("id", "crc", "nth")}
    keyed = _numbered(own.withColumn(names["crc"], F.crc32(text_or_empty())), "doc_id", names["crc"], names["nth"])
    where = placed.select(F.col("doc_id").alias(names["id"]), F.col("text_crc32").alias("_crc_there"), "shard", "slot")
    where = _numbered(where, names["id"], "_crc_there", "_nth_there")
    met = keyed["doc_id"].eqNullSafe(where[names["id"]]) & (keyed[names["crc"]] == where["_crc_there"]) & (keyed[names["nth"]] == where["_nth_there"])
    out = keyed.join(where, met).select(*own.columns, "shard", "slot")
    out.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def _numbered(df: DataFrame, key: str, crc: str, name: str) -> DataFrame:
    """Numbers the rows of one id and checksum; which of equal rows is which does not matter."""
    return df.withColumn(name, F.row_number().over(W.partitionBy(key, crc).orderBy(F.lit(0))))


def shard_statistics(docs: DataFrame, placed: DataFrame) -> DataFrame:
    """Per shard the number of rows and the bounds a reader prunes with.

    Rows of ``docs`` and ``placed`` meet as in ``write_shards``, so repeated and null ids count once for each row.
    """
    own = docs.select(F.col("doc_id").alias("_id"), F.crc32(text_or_empty()).alias("_crc"), "lang", "source")
    own = _numbered(own, "_id", "_crc", "_nth")
    there = _numbered(placed.select("doc_id", "text_crc32", "shard", "size"), "doc_id", "text_crc32", "_n")
    joined = there.join(own, there["doc_id"].eqNullSafe(own["_id"]) & (there["text_crc32"] == own["_crc"]) & (there["_n"] == own["_nth"]))
    return joined.groupBy("shard").agg(
        F.count(F.lit(1)).alias("n_rows"),
        *[f(c).alias(f"{n}_{c}") for c in ("lang", "source", "size") for n, f in (("min", F.min), ("max", F.max))],
    )
