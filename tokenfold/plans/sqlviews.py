"""Queries whose one text both engines read, over views that each engine builds in its own way."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tokenfold.registry import query
from tokenfold.sources.tables import document_prompts, table

_TOK = r"""tok AS (
  SELECT seq_id, pos, token, n, CAST('0x' || substr(md5(token), 1, 8) AS BIGINT) % (SELECT count(*) FROM embeddings) AS tok_id
  FROM (SELECT doc_id AS seq_id, CAST(unnest(range(0, len(ws))) AS INTEGER) AS pos, unnest(ws) AS token, CAST(len(ws) AS INTEGER) AS n
        FROM (SELECT doc_id, regexp_extract_all(text, '[^\x20\x09-\x0d]+') AS ws FROM documents)))"""
_VEC = """vec AS (
  SELECT CAST(vec_id AS INTEGER) AS i, CAST(unnest(range(0, len(embedding))) AS INTEGER) AS j, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings)"""


def tok(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of documents: seq_id, pos, token, n (tokens of the prompt), tok_id (a row of the frozen table)."""
    size = table(spark, sf_dir, "embeddings").count()  # from the footers
    wide = document_prompts(spark, sf_dir)
    long = wide.select("seq_id", F.size("tokens").alias("n"), F.posexplode("tokens").alias("pos", "token"))
    return long.select("seq_id", "pos", "token", "n", (F.conv(F.substring(F.md5("token"), 1, 8), 16, 10).cast("long") % size).alias("tok_id"))


def vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numbers of the frozen table: i (row), j (dimension), x."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").cast("int").alias("i"), F.posexplode("embedding").alias("j", "x")).withColumn("x", F.col("x").cast("double"))


_VIEWS: dict[str, tuple[Callable, str]] = {"tok": (tok, _TOK), "vec": (vec, _VEC)}


def view(name: str, build: Callable[[SparkSession, str], DataFrame], text: str) -> None:
    """Another view that both engines build in their own way; its text may use those before it."""
    _VIEWS[name] = (build, text)


TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def prepared(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> None:
    for name in names:
        (_VIEWS[name][0](spark, sf_dir) if name in _VIEWS else table(spark, sf_dir, name)).createOrReplaceTempView(name)


def both(name: str, text: str, views: str, spark_text: str | None = None) -> None:
    """Register a query by its text. views: names apart by spaces, tables among them."""
    names = tuple(views.split())
    ctes = ",\n".join(_VIEWS[v][1] for v in names if v in _VIEWS)

    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        prepared(spark, sf_dir, names)
        return spark.sql(spark_text or text)

    build.__name__, build.__doc__ = name, f"{name}: one SQL text over {views}."
    query(name, f"WITH {ctes}\nSELECT * FROM ({text}) AS q" if ctes else text)(build)
