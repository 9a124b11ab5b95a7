"""Shards as runs of a Hilbert curve over document metadata.

Source, language and size are quantised, each cell gets its place on a Hilbert
curve, rows are put in curve order across the cluster, and the order is cut
into runs of equal row counts. Rows near in all dimensions land in the same
file, so a reader's filter on any of them prunes files by their ranges.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from edgeconn.plans.staging import stage

BITS = 6


def hilbert_index(axes: list, bits: int):
    """Place on the Hilbert curve of each point; axes: equal-length arrays of
    integers below 2**bits (transposed Gray-code construction, published)."""
    import numpy as np

    x = [np.asarray(a, np.int64).copy() for a in axes]
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(len(x)):
            high = (x[i] & q) != 0
            swap = np.where(high, 0, (x[0] ^ x[i]) & p)
            x[0] = np.where(high, x[0] ^ p, x[0] ^ swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, len(x)):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        t = np.where(x[-1] & q, t ^ (q - 1), t)
        q >>= 1
    x = [a ^ t for a in x]
    out = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for a in x:
            out = (out << 1) | ((a >> b) & 1)
    return out


def hilbert(*cols: str, bits: int = BITS) -> Column:
    @F.pandas_udf("long")
    def index(*axes: pd.Series) -> pd.Series:
        return pd.Series(hilbert_index([a.to_numpy() for a in axes], bits))

    return index(*cols)


def in_order(df: DataFrame, order: list[str], weight: str | None = None) -> DataFrame:
    """``df`` with ``before`` long: the rows (or summed weight) that come
    before each row in the order of the columns.

    Rows are dealt into ranges of the order and written once; each range is
    counted by itself, and only one sum per range is accumulated apart. Ties
    follow the input's order. No task gets more than a range.
    """
    amount = F.col(weight) if weight else F.lit(1).cast("long")
    keyed = df.withColumn("_tie", F.monotonically_increasing_id()).withColumn("_amount", amount)
    ranged = keyed.repartitionByRange(*order, "_tie").withColumn("_range", F.spark_partition_id())
    held = stage(ranged, "order").df
    totals = held.groupBy("_range").agg(F.sum("_amount").alias("_sum"))
    base = totals.select("_range", (F.sum("_sum").over(Window.orderBy("_range")) - F.col("_sum")).alias("_base"))  # a row per range
    inside = Window.partitionBy("_range").orderBy(*order, "_tie").rowsBetween(Window.unboundedPreceding, 0)
    out = held.join(F.broadcast(base), "_range")
    return out.withColumn("before", F.col("_base") + F.sum("_amount").over(inside) - F.col("_amount")).drop("_tie", "_amount", "_range", "_base")


def value_codes(df: DataFrame, col: str, bits: int = BITS) -> DataFrame:
    """(col, code): each distinct value's equal-depth cell, in value order.

    A value starts where the rows of lesser values end, so codes keep the
    order of values and split rows about evenly; a null comes first.
    """
    counts = df.groupBy(col).agg(F.count(F.lit(1)).alias("n"))
    placed = in_order(counts, [col], "n")
    total = counts.agg(F.sum("n").alias("all"))
    return placed.crossJoin(F.broadcast(total)).select(col, F.floor(F.col("before") * (1 << bits) / F.col("all")).cast("long").alias("code"))  # total: one row


def size_code(size: Column, bits: int = BITS) -> Column:
    """Three cells for each doubling of the size, from 8 bytes on."""
    return F.least(F.greatest(F.floor(3 * F.log2(size / 8.0)), F.lit(0)), F.lit((1 << bits) - 1)).cast("long")


def shard(docs: DataFrame, shards: int = 24, id_col: str = "doc_id") -> DataFrame:
    """(id, size, text_crc32, curve, shard, slot), one row per row.

    size: UTF-8 bytes of the text (null: none) plus 8. Shards are numbered
    along the curve and their counts differ by one at most; slots run from 0
    without a gap. Within a cell rows go by the text's checksum, so equal texts
    of equal metadata lie together, then by id. Null metadata is a value of its
    own that comes first. Repeated rows stay.
    """
    size = (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long")
    rows = docs.select(F.col(id_col).alias("id"), "source", "lang", size.alias("size"), F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("text_crc32"))
    rows = stage(rows, "shard-meta").df
    for col in ("source", "lang"):
        codes = value_codes(rows, col).withColumnsRenamed({col: f"{col}_value", "code": f"{col}_code"})
        rows = rows.join(codes, rows[col].eqNullSafe(codes[f"{col}_value"]), "left").drop(f"{col}_value")
    rows = rows.withColumn("size_code", size_code(F.col("size"))).withColumn("curve", hilbert("source_code", "lang_code", "size_code"))
    placed = in_order(rows.select("id", "size", "text_crc32", "curve"), ["curve", "text_crc32", "id"])
    n = placed.agg(F.count(F.lit(1)).alias("n"))
    base, more = F.floor(F.col("n") / shards), F.col("n") % shards
    head = more * (base + 1)
    inside = F.col("before") < head
    no = F.when(inside, F.floor(F.col("before") / (base + 1))).otherwise(more + F.floor((F.col("before") - head) / F.greatest(base, F.lit(1))))
    slot = F.when(inside, F.col("before") % (base + 1)).otherwise((F.col("before") - head) % F.greatest(base, F.lit(1)))
    return placed.crossJoin(F.broadcast(n)).select("id", "size", "text_crc32", "curve", no.cast("int").alias("shard"), slot.cast("long").alias("slot"))  # n: one row
