"""Workloads on cost, frontier, scaling, structured prompts, short prompts and single settings."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tokenfold.functions import kernels, schedule
from tokenfold.functions.reader import READERS
from tokenfold.operators import backends, evaluation, studies
from tokenfold.options import CompressOptions
from tokenfold.plans.sqlviews import _TOK
from tokenfold.plans.workloads import RHOS, SUFFIX, _target, contexts, documents, retrieval_style, short_prompts
from tokenfold.registry import implement, query
from tokenfold.sources import tables

BACKENDS = ("chunk", "local", "adaptive", "global")
_COST = ("preprocess_s", "prefill_s", "total_s", "reference_s")


def _means(rows: DataFrame, *keys: str) -> DataFrame:
    return rows.groupBy(*keys).agg(
        F.count("*").alias("n"), (F.sum("n_tokens") / F.sum("n_macro")).alias("actual_ratio"), *(F.avg(c).alias(c) for c in _COST),
        (F.sum("reference_s") / F.sum("total_s")).alias("speedup"), F.max("peak_mb").alias("peak_mb"), *(F.avg(m).alias(m) for m in evaluation.MEASURES),
    )


# -- cost ---------------------------------------------------------------------------------------------------------


def grid_cost(spark: SparkSession, sf_dir: str, where: str = "lang = 'en'", length: int = 4096) -> DataFrame:
    rows = studies.measure(contexts(spark, sf_dir, where, length), backends.frozen_table(spark, sf_dir), evaluation.grid(BACKENDS, RHOS), READERS["flat"])
    return _means(rows, "backend", "rho")


@query("w_latency")
def w_latency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds to compress, to read what is left, and both, beside those of reading the packed prompt itself."""
    return grid_cost(spark, sf_dir).select("backend", "rho", "n", "actual_ratio", *_COST, "speedup", "peak_mb")


@query("w_frontier")
def w_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality against total time on the engine's own rows: a point is on the frontier if none is faster and as good."""
    rows = tables.settle(grid_cost(spark, sf_dir, length=2048).select("backend", "rho", "total_s", "cosine", "kl", "ppl_ratio"), "frontier")
    other = rows.select(F.col("total_s").alias("t"), F.col("kl").alias("k"))  # one row for each point of the grid
    better = rows.join(F.broadcast(other), (F.col("t") <= F.col("total_s")) & (F.col("k") <= F.col("kl")) & ((F.col("t") < F.col("total_s")) | (F.col("k") < F.col("kl"))), "left_semi")
    return rows.join(F.broadcast(better.select("backend", "rho", F.lit(True).alias("beaten"))), ["backend", "rho"], "left").select(*rows.columns, F.col("beaten").isNull().alias("on_frontier"))


SCALING = (2884, 5780, 11546, 23092)


def scaling_contexts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first packed context of each length of the scaling study."""
    parts = [contexts(spark, sf_dir, "lang = 'en'", n).filter(F.size("tokens") == n).orderBy("seq_id").limit(1) for n in SCALING]  # the study's own four sequences
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("w_scaling")
def w_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cost over context lengths at a ratio of 4; the reference reads at most 8192 tokens."""
    rows = studies.measure(tables.spread(scaling_contexts(spark, sf_dir), always=True), backends.frozen_table(spark, sf_dir), evaluation.grid(BACKENDS, (4,)), READERS["flat"])
    return _means(rows, "backend", "rho", "n_tokens", "n_macro", "n_reference")


@implement("w_scaling_counts")
def w_scaling_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lengths before and after of the scaling study's contexts, by chunks of 4."""
    rows = studies.summaries(scaling_contexts(spark, sf_dir), backends.frozen_table(spark, sf_dir), [("chunk", CompressOptions(backend="chunk"))])
    return rows.select(F.col("n_tokens").alias("n_context"), (F.col("n_tokens") - SUFFIX).alias("body"), "n_macro", F.least("n_tokens", F.lit(8192)).alias("n_reference"))


# -- structured prompts -------------------------------------------------------------------------------------------

_SOURCES: dict[str, Callable] = {"json": tables.json_like, "code": tables.code_like, "table": tables.table_like, "retrieval": retrieval_style}


def _structured(spark: SparkSession, sf_dir: str, source: str, continuation: int = 64) -> DataFrame:
    """Prompts of markup symbols; the last ones of each are what the reader is asked for."""
    df = tables.spread(tables.prompts(_SOURCES[source](spark, sf_dir), "seq_id", pattern=tables.SYMBOL), always=True).filter(F.size("tokens") > 2 * continuation)
    n = F.size("tokens") - continuation
    return df.select("seq_id", F.slice("tokens", F.lit(1), n).alias("tokens"), F.slice("tokens", n + 1, F.lit(continuation)).alias("continuation"))


def _stress_quality(source: str) -> None:
    @query(f"w_stress_quality_{source}")
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Quality of each backend at ratios of 8 and 16 where far repetitions carry the meaning."""
        rows = evaluation.evaluate(_structured(spark, sf_dir, source), backends.frozen_table(spark, sf_dir), evaluation.grid(BACKENDS, (8, 16)), {"flat": READERS["flat"]})
        return rows.groupBy("backend", "rho").agg(F.count("*").alias("n"), (F.sum("n_tokens") / F.sum("n_macro")).alias("actual_ratio"), *(F.avg(m).alias(m) for m in evaluation.MEASURES))


for _source in _SOURCES:
    _stress_quality(_source)


@query("route_share_by_source")
def route_share_by_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows on the spectral path by kind of prompt and ratio."""
    e, out = backends.frozen_table(spark, sf_dir), None
    configs = [("adaptive", CompressOptions(rho=r)) for r in RHOS]
    for kind in ("documents", *_SOURCES):
        df = documents(spark, sf_dir) if kind == "documents" else _structured(spark, sf_dir, kind)
        rows = studies.summaries(df, e, configs).select(F.lit(kind).alias("source"), "*")
        out = rows if out is None else out.unionByName(rows)
    return out.groupBy("source", "rho").agg(F.sum("n_windows").alias("n_windows"), F.sum("n_spectral").alias("n_spectral"), (F.sum("n_spectral") / F.sum("n_windows")).alias("share"), F.avg("mean_score").alias("mean_score"))


# -- short prompts ------------------------------------------------------------------------------------------------

_SCHEMES = ("max", "median", "mean")


def _pass(rows: DataFrame, *keys: str) -> DataFrame:
    near = F.col("cosine") > 0.999
    return rows.groupBy(*keys).agg(
        F.count("*").alias("n"), F.avg(F.col("monotone").cast("double")).alias("monotone"), F.avg("cosine").alias("cosine"), F.avg(near.cast("double")).alias("near"),
        F.avg(F.col("same_first").cast("double")).alias("same_first"), F.avg("same_text").alias("same_text"), F.avg(F.col("holds_answer").cast("double")).alias("holds_answer"),
        F.avg((F.col("monotone") & near & F.col("same_first")).cast("double")).alias("passed"),
    )


@query("k1_checks")
def k1_checks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chunks at a ratio of 2 on short prompts by position scheme: order, direction of the next logits, greedy continuation."""
    configs = [(s, CompressOptions(rho=2, backend="chunk", position_scheme=s)) for s in _SCHEMES]
    return _pass(studies.checks(short_prompts(spark, sf_dir), backends.frozen_table(spark, sf_dir), configs, READERS["masked"]), "scheme")


@query("abl_position_pass")
def abl_position_pass(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same shares by scheme, backend and ratio, under a reader that sees positions."""
    configs = [(s, CompressOptions(rho=r, backend=b, position_scheme=s)) for s in _SCHEMES for b in ("chunk", "local") for r in (1, 2, 4)]
    return _pass(studies.checks(short_prompts(spark, sf_dir), backends.frozen_table(spark, sf_dir), configs, READERS["masked"]), "scheme", "backend", "rho")


@query("greedy_continuation", """
SELECT conv_id AS seq_id, CAST(16 AS INTEGER) AS steps, true AS same FROM conversations
GROUP BY conv_id HAVING count(*) FILTER (WHERE role = 'user') > 0 AND count(*) FILTER (WHERE role = 'assistant') > 0
 AND len(regexp_extract_all(arg_min(text, turn) FILTER (WHERE role = 'user'), '[^\\x20\\x09-\\x0d]+')) > 0
 AND len(regexp_extract_all(arg_min(text, turn) FILTER (WHERE role = 'assistant'), '[^\\x20\\x09-\\x0d]+')) > 0""")
def greedy_continuation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """At a ratio of one the greedy continuation is the prompt's own."""
    rows = studies.checks(short_prompts(spark, sf_dir), backends.frozen_table(spark, sf_dir), [("max", CompressOptions(rho=1))], READERS["masked"], 16)
    return rows.select("seq_id", F.lit(16).alias("steps"), ((F.col("same_text") == 1) & F.col("monotone")).alias("same"))


# -- single settings ----------------------------------------------------------------------------------------------


@query("prefix_kept", f"""WITH {_TOK}, l AS (SELECT seq_id, count(*) AS n FROM tok GROUP BY seq_id)
SELECT seq_id, CAST(n AS INTEGER) AS n_tokens, CAST(CASE WHEN n <= 20 THEN n ELSE 20 + greatest(1, ceil((n - 20) / 4.0)) END AS INTEGER) AS n_macro, true AS ends_kept FROM l""")
def prefix_kept(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With a prefix of 8 and a suffix of 12 both come back token for token."""

    def rows(r, vocabulary, norm):
        n = len(r.tokens)
        if not n:
            return
        x = vocabulary(list(r.tokens))
        m = kernels.compress(x, CompressOptions(rho=4, backend="chunk", prefix=8, suffix=12), norm)
        a, b = min(n, 8), min(n, 12)
        same = np.array_equal(m.x[:a], x[:a]) and np.array_equal(m.x[-b:], x[-b:]) and m.pos[:a].tolist() == list(range(a)) and m.pos[-b:].tolist() == list(range(n - b, n))
        yield (r.seq_id, n, len(m.pos), bool(same))

    return backends._with_vectors(documents(spark, sf_dir), backends.frozen_table(spark, sf_dir), CompressOptions(), "seq_id long, n_tokens int, n_macro int, ends_kept boolean", rows)


@query("dense_backend", f"""WITH w AS (SELECT * FROM (VALUES (0)) v(x)), b AS (SELECT item_id AS seq_id, len(regexp_extract_all(text, '[^\\x20\\x09-\\x0d]+')) AS n FROM benchmark)
SELECT seq_id, CAST(n AS INTEGER) AS n_tokens, CAST({_target(4)} AS INTEGER) AS n_macro, 0 AS late_members FROM b WHERE n > 0""")
def dense_backend(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The exact kernel's eigenvectors as a backend for prompts of a bounded length."""
    df = tables.spread(tables.prompts(tables.table(spark, sf_dir, "benchmark"), "item_id"))
    return backends.summarise(df, backends.frozen_table(spark, sf_dir), CompressOptions(rho=4, backend="dense")).select("seq_id", "n_tokens", "n_macro", "late_members")


@query("abl_bits_before")
def abl_bits_before(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Codes that a window has before they are fitted to its budget, by ratio and number of bits."""

    def rows(r, vocabulary, norm):
        x = vocabulary(list(r.tokens))
        x = x[: len(x) // 16 * 16]
        if not len(x):
            return
        z = kernels.coordinates(kernels.rff(x.reshape(-1, 16, x.shape[1]), 256), CompressOptions())
        for rho in RHOS:
            budget = 16 // rho
            for extra in (0, 1, 2):
                bits = schedule.bits_for_target(budget) + extra
                found = np.array([len(np.unique(c)) for c in kernels.simhash(z, bits)])
                yield (r.seq_id, rho, bits, budget, len(found), int(found.sum()), int((found < budget).sum()), int((found > budget).sum()))

    made = backends._with_vectors(contexts(spark, sf_dir, "lang = 'en'", 1024), backends.frozen_table(spark, sf_dir), CompressOptions(), "seq_id long, rho int, bits int, budget int, windows long, codes long, too_few long, too_many long", rows)
    return made.groupBy("rho", "bits", "budget").agg(F.sum("windows").alias("windows"), (F.sum("codes") / F.sum("windows")).alias("mean_codes"), (F.sum("too_few") / F.sum("windows")).alias("split_share"), (F.sum("too_many") / F.sum("windows")).alias("merge_share"))


@query("abl_row_agreement")
def abl_row_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups under the plain operator and under the one divided by its row sums: pairs treated alike, and distortion of both."""

    def rows(r, vocabulary, norm):
        x = vocabulary(list(r.tokens))
        out = {}
        for kind in ("none", "row"):
            labels = kernels.group_body(x, CompressOptions(rho=4, backend="local", suffix=0, kernel_norm=kind)).labels
            m = kernels.fuse(x, np.arange(len(x)), kernels.dense_labels(labels), CompressOptions(renorm="none"))
            group = np.empty(len(x), np.int64)
            for i, own in enumerate(m.members):
                group[own] = i
            out[kind] = labels, float(((x - m.x[group]) ** 2).sum())
        whole = len(x) // 16 * 16
        a, b = (out[k][0][:whole].reshape(-1, 16) for k in ("none", "row"))
        same = (a[:, :, None] == a[:, None, :]) == (b[:, :, None] == b[:, None, :])
        yield (r.seq_id, int(same.size), int(same.sum()), out["none"][1], out["row"][1], len(x))

    made = backends._with_vectors(contexts(spark, sf_dir, "lang = 'en'", 1024), backends.frozen_table(spark, sf_dir), CompressOptions(), "seq_id long, pairs long, alike long, plain double, row double, n long", rows)
    return made.agg(F.count("*").alias("n"), (F.sum("alike") / F.sum("pairs")).alias("agreement"), (F.sum("plain") / F.sum("n")).alias("distortion_plain"), (F.sum("row") / F.sum("n")).alias("distortion_row"))


@query("k2_energy_tokens")
def k2_energy_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Energy at ranks of 4 to 32 over packed contexts of 2048 document tokens."""

    def rows(r, vocabulary, norm):
        phi = kernels.rff(vocabulary(list(r.tokens)), 256)
        for rank in (4, 8, 16, 32):
            yield (r.seq_id, rank, *(kernels.energy_fraction(phi, replace(CompressOptions(), rank=rank), n) for n in ("trace", "frobenius")))

    made = backends._with_vectors(contexts(spark, sf_dir, "lang = 'en'", 2048), backends.frozen_table(spark, sf_dir), CompressOptions(), "seq_id long, rank int, trace_share double, frobenius_share double", rows)
    return made.groupBy("rank").agg(F.count("*").alias("n"), F.avg("trace_share").alias("trace_share"), F.avg("frobenius_share").alias("frobenius_share"), F.min("trace_share").alias("least"))
