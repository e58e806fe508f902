"""Tables and prompts built from them."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Words of a prompt, and symbols of markup.
WORD, SYMBOL = r"[^\x20\x09-\x0d]+", r"[A-Za-z0-9_]+|[^A-Za-z0-9_\x20\x09-\x0d]"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the folder that driver and executors share; a temporary one in a local session that names none."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = f"file://{tempfile.gettempdir()}"
    return f"{root}/{name}-{uuid.uuid4().hex}"


def settle(df: DataFrame, name: str) -> DataFrame:
    """A result written to the shared folder and read again, so that later steps see the same rows."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spread(df: DataFrame, always: bool = False) -> DataFrame:
    """Rows over all cores, where a scan has fewer partitions; always: without looking, for frames behind a shuffle."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    if always:
        return df.repartition(max(cores, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    return df if df.rdd.getNumPartitions() >= cores else df.repartition(cores)


def words(text: str, pattern: str = WORD):
    return F.regexp_extract_all(F.col(text), F.lit(pattern), F.lit(0))


def prompts(df: DataFrame, key: str, text: str = "text", pattern: str = WORD) -> DataFrame:
    """Wide prompts: seq_id and the ordered array of its tokens. Null texts are prompts without a token."""
    return df.select(F.col(key).alias("seq_id"), F.coalesce(words(text, pattern), F.array().cast("array<string>")).alias("tokens"))


def document_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prompts(table(spark, sf_dir, "documents"), "doc_id")


def _counted(name: str):
    """Tokens of the rows before each one in its partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before = 0
        for batch in batches:
            size = pc.fill_null(pc.list_value_length(batch.column("tokens")), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            ends = before + np.cumsum(size)
            yield batch.append_column(name, pa.array(ends - size))
            before = int(ends[-1]) if len(ends) else before

    return run


def packed(df: DataFrame, order: str, length: int, continuation: int = 0) -> DataFrame:
    """Sequences of `length` tokens (and a continuation) cut from all texts in order: seq_id, tokens, continuation.

    A text's place is its place in its range of the order and the sum of the ranges before,
    a row for each, so that no running count spans the corpus. Only the last sequence can
    be short. Rows of equal keys stand in an arbitrary but settled order.
    """
    step, n = length + continuation, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.select(order, "tokens").repartitionByRange(n, order).sortWithinPartitions(order)
    kind = ranged.schema[order].dataType.simpleString()
    base = settle(ranged.mapInArrow(_counted("_own"), f"`{order}` {kind}, tokens array<string>, _own long").withColumn("_part", F.spark_partition_id()), "ranged")
    totals = base.groupBy("_part").agg(F.sum(F.size("tokens")).alias("_size"))
    earlier = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each partition
    counted = base.join(F.broadcast(totals.select("_part", F.coalesce(F.sum("_size").over(earlier), F.lit(0)).alias("_from"))), "_part").withColumn("_before", F.col("_from") + F.col("_own"))
    first, last = F.floor(F.col("_before") / step), F.floor((F.col("_before") + F.size("tokens") - 1) / step)
    cut = counted.filter(F.size("tokens") > 0).withColumn("seq_id", F.explode(F.sequence(first, last)))
    low = F.greatest(F.col("seq_id") * step - F.col("_before"), F.lit(0)).cast("int")
    high = F.least((F.col("seq_id") + 1) * step - F.col("_before"), F.size("tokens")).cast("int")
    # by number: what follows is heavy, so small parts are not joined
    parts = cut.repartition(n, "seq_id").groupBy("seq_id").agg(F.array_sort(F.collect_list(F.struct(F.col("_before").alias("b"), F.slice("tokens", low + 1, high - low).alias("t")))).alias("p"))
    whole = parts.withColumn("tokens", F.flatten(F.transform("p", lambda p: p["t"])))
    return whole.select("seq_id", F.slice("tokens", 1, length).alias("tokens"), F.slice("tokens", length + 1, max(continuation, 1)).alias("continuation") if continuation else F.array().cast("array<string>").alias("continuation"))


def json_like(spark: SparkSession, sf_dir: str, per_prompt: int = 200) -> DataFrame:
    """Orders with their lines as JSON records, a prompt for each run of order keys."""
    lines = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct("l_linenumber", "l_partkey", "l_returnflag", "l_linestatus"))).alias("lines"))
    both = table(spark, sf_dir, "orders").join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    record = F.to_json(F.struct("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority", "lines"))
    return _joined(both.select("o_orderkey", record.alias("r")), "o_orderkey", per_prompt)


def table_like(spark: SparkSession, sf_dir: str, per_prompt: int = 4000) -> DataFrame:
    """Lines of orders as rows with bars, a prompt for each run of order keys."""
    li = table(spark, sf_dir, "lineitem")
    line = F.concat_ws(" | ", *(F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_linestatus")))
    return _joined(li.select("l_orderkey", F.concat(line, F.lit(" |")).alias("r"), "l_linenumber"), "l_orderkey", per_prompt // 4)


def code_like(spark: SparkSession, sf_dir: str, per_prompt: int = 20) -> DataFrame:
    """Markup and scripts of pages, a prompt for each run of pages."""
    return _joined(table(spark, sf_dir, "pages").select("page_id", F.col("html").alias("r")), "page_id", per_prompt)


def _joined(df: DataFrame, key: str, per_prompt: int) -> DataFrame:
    grouped = df.groupBy(F.floor(F.col(key) / per_prompt).alias("seq_id")).agg(F.array_sort(F.collect_list(F.struct(F.col(key).alias("k"), "r"))).alias("rs"))
    return grouped.select("seq_id", F.concat_ws("\n", F.transform("rs", lambda r: r["r"])).alias("text"))
