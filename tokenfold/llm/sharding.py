"""Contiguous shards of equal bytes from global prefix sums.

Rows are ordered by document id. Each range partition gets a running sum of its
sizes, the partitions' totals give each partition its offset, and the global
prefix sum is cut at equal targets. Only ids, sizes and checksums move; the text
does not. The totals are one row for each partition, so the driver's share is
bounded by the number of partitions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import settle, table

SHARDS = 24
#: Bytes that each row counts beside its text.
ROW_BYTES = 8


def _base(totals: DataFrame, keys: list[str], sums: dict[str, str], order: list[str]) -> DataFrame:
    """Exclusive running sums over a table that has a row for each partition (and shard)."""
    w = Window.partitionBy(F.lit(0)).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return totals.select(*keys, *(F.coalesce(F.sum(c).over(w), F.lit(0)).alias(name) for name, c in sums.items()))


def byte_shards(df: DataFrame, shards: int = SHARDS, key: str = "doc_id", text: str = "text", row_bytes: int = ROW_BYTES, extra: dict[str, Column] | None = None) -> DataFrame:
    """Shard and slot of each row: key, size, shard, slot and the extra columns.

    A row's shard is that of the middle of its bytes in the global order, so a
    row longer than a shard's target leaves some shard empty rather than being
    cut. Null keys come first, null texts count row_bytes; rows with equal keys
    and texts get slots in an arbitrary but settled order. An empty table gives
    no rows. Other columns of the input are dropped, so no name can clash.
    """
    spark = df.sparkSession
    columns = {"_key": F.col(key), "_size": (F.coalesce(F.octet_length(F.col(text)), F.lit(0)) + row_bytes).cast("long")} | {f"_x{i}": c for i, c in enumerate((extra or {}).values())}
    slim = df.select(*(c.alias(n) for n, c in columns.items()))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ordered = ["_key", "_size", *(f"_x{i}" for i in range(len(extra or {})))]
    ranged = settle(slim.repartitionByRange(parts, *ordered).withColumn("_part", F.spark_partition_id()), "ranges")

    totals = ranged.groupBy("_part").agg(F.sum("_size").alias("_bytes"))
    whole = totals.agg(F.sum("_bytes")).first()[0] or 0
    before = _base(totals, ["_part"], {"_from": "_bytes"}, ["_part"])
    inside = Window.partitionBy("_part").orderBy(*ordered)
    start = F.col("_from") + F.sum("_size").over(inside.rowsBetween(Window.unboundedPreceding, 0)) - F.col("_size")
    # twice the middle of the row against twice the total, in decimals so that no product overflows
    middle = (2 * start + F.col("_size")).cast("decimal(38,0)") * shards
    shard = F.least(F.lit(shards - 1), F.floor(middle / F.lit(2 * max(whole, 1)).cast("decimal(20,0)"))).cast("int")
    placed = ranged.join(F.broadcast(before), "_part").withColumn("_shard", shard).withColumn("_row", F.row_number().over(inside))

    # A slot counts the rows of its shard in earlier partitions and those before it in its own.
    share = settle(placed.groupBy("_shard", "_part").agg(F.count("*").alias("_rows"), F.min("_row").alias("_first")), "shares")
    w = Window.partitionBy("_shard").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    slots = share.select("_shard", "_part", "_first", F.coalesce(F.sum("_rows").over(w), F.lit(0)).alias("_slot"))
    out = placed.join(F.broadcast(slots), ["_shard", "_part"])
    return out.select(
        F.col("_key").alias(key), F.col("_size").alias("size"), F.col("_shard").alias("shard"),
        (F.col("_slot") + F.col("_row") - F.col("_first")).cast("long").alias("slot"),
        *(F.col(f"_x{i}").alias(n) for i, n in enumerate(extra or {})),
    )


def op10_byte_prefix_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    crc = F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary"))
    out = byte_shards(docs, SHARDS, extra={"text_crc32": crc})
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
