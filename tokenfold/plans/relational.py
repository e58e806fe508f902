"""Scans, joins, aggregates, windows and functions around the methods, each with its oracle."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tokenfold.plans.sqlviews import _TOK, both, tok
from tokenfold.registry import query
from tokenfold.sources.records import RepeatedRecords
from tokenfold.sources.tables import scratch, table


# -- scans and sinks ----------------------------------------------------------------------------------------------

both("scan_parquet", "SELECT doc_id, lang, source, n_chars FROM documents", "documents")


@query("scan_json_roundtrip", "SELECT conv_id, turn, role, text FROM conversations")
def scan_json_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, path = table(spark, sf_dir, "conversations"), scratch(spark, "roundtrip")
    df.write.json(path)
    return spark.read.schema(df.schema).json(path).select("conv_id", "turn", "role", "text")


@query("scan_csv_roundtrip", "SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer")
def scan_csv_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, path = table(spark, sf_dir, "customer"), scratch(spark, "roundtrip")
    df.write.option("header", True).csv(path)
    return spark.read.schema(df.schema).option("header", True).csv(path)


@query("scan_orc_roundtrip", "SELECT p_partkey, p_name, p_size FROM part WHERE p_size > 10")
def scan_orc_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "roundtrip")
    table(spark, sf_dir, "part").write.orc(path)
    return spark.read.orc(path).filter("p_size > 10").select("p_partkey", "p_name", "p_size")


@query("sink_partitioned_roundtrip", "SELECT lang, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents WHERE lang IN ('en', 'de') GROUP BY lang")
def sink_partitioned_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "roundtrip")
    table(spark, sf_dir, "documents").write.partitionBy("lang").parquet(path)
    return spark.read.parquet(path).filter(F.col("lang").isin("en", "de")).groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("sink_bucketed_join", "SELECT o_orderkey, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def sink_bucketed_join(spark: SparkSession, sf_dir: str, buckets: int = 16) -> DataFrame:
    """Both sides written in buckets of the order key once; the join and the counts then need no shuffle."""
    sides = []
    for name, key, columns in (("orders", "o_orderkey", ["o_orderkey"]), ("lineitem", "l_orderkey", ["l_orderkey", "l_quantity"])):
        kept = f"bucketed_{name}_{uuid.uuid4().hex}"
        rows = table(spark, sf_dir, name).select(*columns).repartition(buckets, key)  # a file for each bucket
        rows.write.bucketBy(buckets, key).sortBy(key).option("path", scratch(spark, "bucketed")).saveAsTable(kept)
        sides.append(spark.table(kept))
    orders, lines = sides
    joined = orders.hint("merge").join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("o_orderkey").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("source_python_prompts", "SELECT i AS seq_id, rtrim(repeat('record ' || i || ' field ' || (i % 7) || ' ; ', CAST(1 + i % 5 AS INTEGER))) AS text FROM range(0, 1000) r(i)")
def source_python_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prompts that repeat a record, from a Python data source: made where they are read, a task for each range of ids."""
    spark.dataSource.register(RepeatedRecords)
    return spark.read.format(RepeatedRecords.name()).option("rows", 1000).option("parts", 8).load()


both("scan_html_text", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n FROM pages", "pages", "SELECT page_id, cast(length(regexp_replace(html, '<[^>]*>', '')) AS BIGINT) AS n FROM pages")

# -- filters, joins -----------------------------------------------------------------------------------------------

both("filter_predicates", "SELECT doc_id, lang FROM documents WHERE lang IN ('en', 'fr') AND n_chars BETWEEN 500 AND 5000 AND source LIKE 'src1%' AND text IS NOT NULL", "documents")
both("project_prompt_struct", "SELECT conv_id, turn, concat_ws(': ', role, text) AS prompt, length(text) AS n FROM conversations", "conversations", "SELECT conv_id, turn, concat_ws(': ', role, text) AS prompt, cast(length(text) AS BIGINT) AS n FROM conversations")


@query("join_broadcast_vocab", f"""WITH {_TOK}
SELECT t.seq_id, t.pos, t.token, v.vec_id, v.label, v.norm FROM tok t JOIN (
  SELECT vec_id, label, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 6) AS norm FROM embeddings) v ON v.vec_id = t.tok_id""")
def join_broadcast_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each token of the documents with its row of the vocabulary. A row's norm is taken once and sent out, not its vector."""
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x))
    words = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.round(norm, 6).alias("norm"))
    found = tok(spark, sf_dir)
    return found.join(F.broadcast(words), found["tok_id"] == words["vec_id"]).select("seq_id", "pos", "token", "vec_id", "label", "norm")


_LINES = "SELECT o_orderkey, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM {hint} orders o JOIN lineitem l ON o.o_orderkey = l.l_orderkey GROUP BY o_orderkey"
for _name, _hint in (("join_sort_merge", "MERGE(l)"), ("join_shuffle_hash", "SHUFFLE_HASH(o)")):
    both(_name, _LINES.format(hint=""), "orders lineitem", _LINES.format(hint="").replace("SELECT", f"SELECT /*+ {_hint} */", 1))
both("join_semi", "SELECT doc_id, lang FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)", "documents labels")
both("join_anti", "SELECT doc_id, lang FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)", "documents labels")
both("join_left_outer", "SELECT d.doc_id, l.quality, l.toxic FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id", "documents labels")
both("join_full_outer", "SELECT c.c_custkey, o.o_orderkey FROM customer c FULL OUTER JOIN orders o ON o.o_custkey = c.c_custkey", "customer orders")
both("join_range_spans", "SELECT d.doc_id, b.low FROM documents d JOIN (SELECT 0 AS low, 512 AS high UNION ALL SELECT 512, 2048 UNION ALL SELECT 2048, 1000000) b ON d.n_chars >= b.low AND d.n_chars < b.high", "documents")
_TS = {"duckdb": "epoch_us({0})", "spark": "unix_micros(cast({0} AS TIMESTAMP))"}
_ASOF = """SELECT event_id, user_id, before_id FROM (
  SELECT event_id, user_id, event_type, {last} OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before_id FROM events) e WHERE event_type = 'purchase'"""
both("join_asof", _ASOF.format(last="last_value(CASE WHEN event_type <> 'purchase' THEN event_id END IGNORE NULLS)"), "events", _ASOF.format(last="last_value(CASE WHEN event_type <> 'purchase' THEN event_id END) IGNORE NULLS"))
_BIN = "SELECT event_id, user_id, {us} AS us, cast(floor({us} / 600000000.0) AS BIGINT) AS bin FROM events"
_INTERVAL = "SELECT a.event_id AS first_id, b.event_id AS second_id FROM ({e}) a JOIN (SELECT event_id, user_id, us, bin FROM ({e}) x UNION ALL SELECT event_id, user_id, us, bin - 1 FROM ({e}) y) b ON b.user_id = a.user_id AND b.bin = a.bin AND b.us > a.us AND b.us <= a.us + 600000000"
both("join_interval", _INTERVAL.format(e=_BIN.format(us=_TS["duckdb"].format("ts"))), "events", _INTERVAL.format(e=_BIN.format(us=_TS["spark"].format("ts"))))

# -- aggregates ---------------------------------------------------------------------------------------------------

both("agg_hash", "SELECT lang, source, count(*) AS n, round(avg(n_chars), 6) AS mean, max(n_chars) AS longest FROM documents GROUP BY lang, source", "documents")
both("agg_collect_members", "SELECT conv_id, array_to_string(list(CAST(turn AS VARCHAR) ORDER BY turn), ',') AS turns FROM conversations GROUP BY conv_id", "conversations", "SELECT conv_id, array_join(transform(array_sort(collect_list(turn)), t -> cast(t AS STRING)), ',') AS turns FROM conversations GROUP BY conv_id")
both("agg_distinct_tokens", "SELECT seq_id, count(DISTINCT tok_id) AS ids, count(DISTINCT token) AS words FROM tok GROUP BY seq_id", "documents embeddings tok")
both("agg_approx_distinct", "SELECT lang, true AS within FROM documents GROUP BY lang", "documents", "SELECT lang, abs(approx_count_distinct(doc_id, 0.02) - count(DISTINCT doc_id)) <= 0.1 * count(DISTINCT doc_id) AS within FROM documents GROUP BY lang")
both("agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())", "documents")
both("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", "lineitem")
both("agg_rollup", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)", "lineitem")


@query("agg_pivot", "SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["en", "fr"]).agg(F.count(F.lit(1))).na.fill(0, ["en", "fr"])


@query("unpivot_results", "SELECT doc_id, 'quality' AS label, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def unpivot_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "label", "value")


# -- windows, sorts, sets -----------------------------------------------------------------------------------------

both("win_ranking", "SELECT doc_id, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER (PARTITION BY lang ORDER BY n_chars) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY lang ORDER BY n_chars) AS INTEGER) AS dr, round(percent_rank() OVER (PARTITION BY lang ORDER BY n_chars), 6) AS pr FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id)", "documents")
both("win_ntile", "SELECT doc_id, CAST(ntile(8) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS INTEGER) AS part FROM documents", "documents")
both("win_lag_lead", "SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after, first_value(role) OVER w AS first FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)", "conversations")
both("win_rows_frame", "SELECT doc_id, CAST(sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN 3 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS near FROM documents", "documents")
both("win_range_frame", "SELECT doc_id, count(*) OVER (PARTITION BY source ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS alike FROM documents", "documents")
both("sort_limit", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20", "documents")
both("topk_per_group", "SELECT lang, doc_id, n_chars FROM (SELECT lang, doc_id, n_chars, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS rn FROM documents) r WHERE rn <= 10", "documents")
both("set_union", "SELECT doc_id FROM documents UNION SELECT doc_id FROM labels", "documents labels")
both("set_intersect", "SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels", "documents labels")
both("set_except", "SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels", "documents labels")

# -- functions ----------------------------------------------------------------------------------------------------

both("fn_string", "SELECT doc_id, lower(substr(text, 1, 40)) AS head, md5(text) AS digest, length(text) AS n, length(text) - length(replace(text, ' ', '')) AS spaces FROM documents", "documents", "SELECT doc_id, lower(substr(text, 1, 40)) AS head, md5(text) AS digest, cast(length(text) AS BIGINT) AS n, cast(length(text) - length(replace(text, ' ', '')) AS BIGINT) AS spaces FROM documents")
both("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS first_day FROM orders", "orders")
both("fn_math", "SELECT l_orderkey, l_linenumber, round(exp(-l_discount) + ln(1 + l_tax) + sqrt(l_quantity), 6) AS v, round(atan2(l_quantity, 1 + l_tax), 6) AS a FROM lineitem", "lineitem")
both("fn_bits_hamming", "SELECT event_id, CAST(bit_count(xor(event_id, user_id)) AS INTEGER) AS hamming FROM events", "events", "SELECT event_id, CAST(bit_count(event_id ^ user_id) AS INTEGER) AS hamming FROM events")
both("fn_array_vector", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 6) AS sq, len(embedding) AS n FROM embeddings", "embeddings", "SELECT vec_id, round(aggregate(embedding, 0D, (a, x) -> a + cast(x AS DOUBLE) * x), 6) AS sq, cast(size(embedding) AS BIGINT) AS n FROM embeddings")
both("fn_map_metrics", "SELECT doc_id, quality + toxic AS total FROM labels", "labels", "SELECT doc_id, m['quality'] + m['toxic'] AS total FROM (SELECT doc_id, map('quality', quality, 'toxic', toxic) AS m FROM labels) x")
both("fn_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events", "events", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events")
both("sql_subqueries", "WITH m AS (SELECT lang, avg(n_chars) AS mean FROM documents GROUP BY lang) SELECT d.doc_id FROM documents d JOIN m ON m.lang = d.lang WHERE d.n_chars > m.mean AND d.n_chars < (SELECT max(n_chars) FROM documents) AND EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)", "documents labels")
