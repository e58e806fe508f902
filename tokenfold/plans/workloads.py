"""Backends, spectral checks, quality grids and ablations: the array kernels over the given tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, LongType, StructType

from tokenfold.functions import kernels, schedule
from tokenfold.functions.reader import READERS
from tokenfold.operators import backends, evaluation, onesequence, studies
from tokenfold.options import CompressOptions
from tokenfold.plans import stages  # noqa: F401  its texts are the oracles of the functions below
from tokenfold.plans.sqlviews import _TOK, prepared
from tokenfold.registry import _SQL, query
from tokenfold.sources import tables

SUFFIX, RHOS = 12, (2, 4, 8, 16)
_N = "(SELECT seq_id, count(*) AS n FROM tok GROUP BY seq_id)"


def _target(rho: float) -> str:
    return f"CASE WHEN n <= {SUFFIX} THEN n ELSE {SUFFIX} + greatest(1, CAST(ceil((n - {SUFFIX}) / {float(rho)}) AS BIGINT)) END"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wide prompts of documents in at least as many partitions as there are cores."""
    return tables.spread(tables.document_prompts(spark, sf_dir))


def counts(name: str, opts: CompressOptions, route: str = "") -> None:
    """Register the lengths and causal faults of a backend on documents, against their closed forms."""
    chosen = "seq_id, CAST(n AS INTEGER) AS n_tokens, CAST({m} AS INTEGER) AS n_macro, 0 AS late_members, 0 AS unordered{route}"
    sql = f"WITH {_TOK} SELECT {chosen.format(m=_target(opts.rho), route=route)} FROM {_N} t"
    names = ["seq_id", "n_tokens", "n_macro", "late_members", "unordered", *([] if not route else ["n_windows", "n_spectral"])]

    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        return backends.summarise(documents(spark, sf_dir), backends.frozen_table(spark, sf_dir), opts).select(*names)

    build.__name__, build.__doc__ = name, f"{name}: {opts.backend} at a ratio of {opts.rho}."
    query(name, sql)(build)


_WINDOWS = "CAST(CASE WHEN n <= {s} THEN 1 ELSE ceil((n - {s}) / 16.0) END AS INTEGER)".format(s=SUFFIX)
_ALL_SPECTRAL = f", {_WINDOWS} AS n_windows, CASE WHEN n <= {SUFFIX} THEN 0 ELSE {_WINDOWS} END AS n_spectral"
for _rho in RHOS:
    counts(f"local_lsh_rho{_rho}", CompressOptions(rho=_rho, backend="local"), _ALL_SPECTRAL)
    counts(f"local_lsh_as_printed_rho{_rho}", CompressOptions(rho=_rho, backend="local").as_printed(), _ALL_SPECTRAL)
    counts(f"adaptive_rho{_rho}", CompressOptions(rho=_rho))
counts("adaptive_bypass", CompressOptions(rho=16), _ALL_SPECTRAL)
counts("global_lsh", CompressOptions(rho=8, backend="global"))
counts("global_lsh_as_printed", CompressOptions(rho=8, backend="global").as_printed())
counts("raw_lsh", CompressOptions(rho=4, backend="raw_lsh"))
counts("random_backend", CompressOptions(rho=4, backend="random"))
counts("adjust_exact_length", CompressOptions(rho=4, backend="local", bits=2))


@query("compress_macro_tokens", f"""WITH {_TOK}, body AS (SELECT seq_id, pos, n, CASE WHEN pos < n - {SUFFIX} THEN pos // 4 ELSE n + pos END AS g FROM tok)
SELECT seq_id, CAST(row_number() OVER (PARTITION BY seq_id ORDER BY max(pos)) - 1 AS INTEGER) AS out_pos, max(pos) AS mpos, CAST(count(*) AS INTEGER) AS n_members, min(pos) AS first_pos, max(pos) AS last_pos
FROM body GROUP BY seq_id, g""")
def compress_macro_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The macro-tokens that the array kernel makes by chunks of 4."""
    made = backends.compress(documents(spark, sf_dir), backends.frozen_table(spark, sf_dir), CompressOptions(rho=4, backend="chunk"))
    return made.select("seq_id", "out_pos", "mpos", "n_members", "first_pos", "last_pos")


# -- identity -----------------------------------------------------------------------------------------------------


def _identity(name: str, opts: CompressOptions) -> None:
    @query(name, f"WITH {_TOK} SELECT seq_id, CAST(n AS INTEGER) AS n_tokens, CAST(n AS INTEGER) AS n_macro, true AS unchanged FROM {_N} t")
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        got = backends.summarise(documents(spark, sf_dir), backends.frozen_table(spark, sf_dir), opts)
        same = (F.col("distortion") < 1e-18) & (F.col("late_members") == 0) & (F.col("unordered") == 0)
        return got.select("seq_id", "n_tokens", "n_macro", same.alias("unchanged"))


_identity("identity_gap", CompressOptions(rho=1))
_identity("identity_forced", CompressOptions(rho=1, identity_test=True))

# -- spectral checks on one small sequence, the frozen table ------------------------------------------------------
# Where the exact side costs the square of the sequence, the check runs as one task and the table's size is checked.
# The others need only products of the features' columns, which are added where the vectors lie.


def one(name: str, schema: str, sql: str | None = None) -> Callable:
    """Register a check of the frozen table's vectors, run as one task on an executor."""

    def add(check: Callable[[np.ndarray], list[tuple]]) -> Callable:
        def build(spark: SparkSession, sf_dir: str) -> DataFrame:
            return onesequence.on_table(spark, backends.frozen_table(spark, sf_dir), check, schema)

        build.__name__, build.__doc__ = name, check.__doc__
        query(name, sql)(build)
        return check

    return add


def spanned(name: str, schema: str, opts: CompressOptions = CompressOptions(), dims: int = 256) -> Callable:
    """Register a check of all vectors of the frozen table from the products of their features; it gets the vectors, their number and the products."""

    def add(check: Callable[[DataFrame, int, np.ndarray], list[tuple]]) -> Callable:
        def build(spark: SparkSession, sf_dir: str) -> DataFrame:
            df = onesequence.numbered(spark, sf_dir)
            n, products = onesequence.products(df, onesequence.with_start(dims, opts), dims + (opts.start == "random"))
            return spark.createDataFrame(check(df, n, products) if n else [], schema)

        build.__name__, build.__doc__ = name, check.__doc__
        query(name)(build)
        return check

    return add


def _features(x: np.ndarray, dims: int = 256) -> np.ndarray:
    return kernels.rff(x, dims)


@query("kernel_sup_error")
def kernel_sup_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest error of the features' products against the Gaussian kernel over all pairs, with the bound at 5 per cent."""
    e, sizes = backends.frozen_table(spark, sf_dir), (64, 256, 1024)

    def errors(x: np.ndarray, y: np.ndarray) -> list[tuple]:
        exact = kernels.gaussian_kernel(x, y)
        return [(d, float(np.abs(_features(x, d) @ _features(y, d).T - exact).max())) for d in sizes]

    found = onesequence.over_pairs(spark, e, errors, "dims int, gap double").groupBy("dims").agg(F.max("gap").alias("sup_error"))
    bounds = spark.createDataFrame([(d, schedule.rff_eps(max(1, len(e)), d, 0.05)) for d in sizes], "dims int, eps double")
    return found.join(F.broadcast(bounds), "dims").select("dims", "sup_error", "eps", (F.col("sup_error") <= F.col("eps")).alias("within"))


@one("lanczos_tridiagonal", "j int, alpha double, beta double")
def lanczos_tridiagonal(x: np.ndarray) -> list[tuple]:
    """The tridiagonal matrix of 16 steps on the implicit operator."""
    t = kernels.lanczos(_features(x)[None], CompressOptions())[1][0]
    return [(j, float(t[j, j]), float(t[j, j + 1]) if j + 1 < len(t) else 0.0) for j in range(len(t))]


@one("lanczos_gram", "j int, alpha double, gap double")
def lanczos_gram(x: np.ndarray) -> list[tuple]:
    """The same numbers from products of the features alone, with their gap to the row form."""
    phi, opts = _features(x), CompressOptions()
    t, g = kernels.lanczos(phi[None], opts)[1][0], kernels.lanczos_from_gram(phi.T @ phi, opts)
    return [(j, float(g[j, j]), float(abs(g[j, j] - t[j, j]))) for j in range(len(g))]


@spanned("gram_eigen", "j int, value double, residual double")
def gram_eigen(df: DataFrame, n: int, gram: np.ndarray) -> list[tuple]:
    """Leading eigenpairs of the operator by the small product matrix, with their residuals over all vectors."""
    values, vectors = kernels.gram_eigen(gram, 16)
    scaled = vectors / np.sqrt(values)
    left = gram @ scaled

    def squares(i: np.ndarray, x: np.ndarray) -> pd.DataFrame:
        phi = _features(x)
        return pd.DataFrame({"j": np.arange(len(values)), "square": ((phi @ left - phi @ scaled * values) ** 2).sum(axis=0)})

    got = onesequence.by_row(df, squares, "j int, square double").groupBy("j").agg(F.sum("square").alias("square")).collect()
    square = {r["j"]: r["square"] for r in got}
    return [(j, float(values[j]), float(np.sqrt(square[j]))) for j in range(len(values))]


@one("lanczos_invariants", "check_name string, holds boolean", "SELECT * FROM (VALUES ('orthonormal', true), ('residual', true), ('ritz_below_top', true)) v(check_name, holds)")
def lanczos_invariants(x: np.ndarray) -> list[tuple]:
    """The basis is orthonormal and the recurrence holds in all but its last column."""
    phi = _features(x)
    q, t = (m[0] for m in kernels.lanczos(phi[None], CompressOptions()))
    left = phi @ (phi.T @ q) - q @ t
    top = np.linalg.eigvalsh(phi.T @ phi)[-1]
    return [("orthonormal", bool(np.abs(q.T @ q - np.eye(q.shape[1])).max() < 1e-10)), ("residual", bool(np.abs(left[:, :-1]).max() < 1e-8)), ("ritz_below_top", bool(np.linalg.eigvalsh(t)[-1] <= top + 1e-8))]


@one("ritz_interlacing", "j int, below boolean, above_bound boolean", "SELECT CAST(range AS INTEGER) AS j, true AS below, true AS above_bound FROM range(0, 8)")
def ritz_interlacing(x: np.ndarray) -> list[tuple]:
    """Ritz values lie under their eigenvalues and over the Chebyshev bound of the first ones."""
    return [(j, low, high) for j, _, _, _, low, high in kernels.ritz_bounds(_features(x), CompressOptions(start="range"), 8)]


@spanned("krylov_bounds", "j int, eigenvalue double, ritz double, bound double")
def krylov_bounds(df: DataFrame, n: int, gram: np.ndarray) -> list[tuple]:
    """Eigenvalues, Ritz values and lower bounds."""
    return [row[:4] for row in kernels.ritz_bounds_in_span(gram, CompressOptions(start="range"), n, 8)]


def _coordinates(name: str, **change) -> None:
    opts = replace(CompressOptions(), **change)
    columns = onesequence.with_start(256, opts)

    @query(name)
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Norm and largest coordinate of each vector in the spectral space: one pass for the space, one for the rows."""
        df, schema = onesequence.numbered(spark, sf_dir), "i int, norm double, first double"
        n, products = onesequence.products(df, columns, 256 + (opts.start == "random"))
        if not n:
            return spark.createDataFrame([], schema)
        to = kernels.projection(products, 256, opts, n)

        def rows(i: np.ndarray, x: np.ndarray) -> pd.DataFrame:
            z = columns(i, x) @ to
            return pd.DataFrame({"i": i, "norm": np.linalg.norm(z, axis=1), "first": np.abs(z).max(axis=1)})

        return onesequence.by_row(df, rows, schema)


_coordinates("spectral_coordinates", start="random", weighting="none", drop_top=False)
_coordinates("coords_weighted", weighting="full", drop_top=False)
_coordinates("coords_drop_top")


@one("spectral_cosine_gap", "rank int, largest double, mean double")
def spectral_cosine_gap(x: np.ndarray) -> list[tuple]:
    """How far cosines in the spectral space are from the kernel."""
    exact, phi, out = kernels.gaussian_kernel(x), _features(x, 512), []
    for rank in (4, 16, 64):
        z = kernels.coordinates(phi[None], CompressOptions(rank=rank, drop_top=False))[0]
        z = z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-12)
        gap = np.abs(z @ z.T - exact)
        out.append((rank, float(gap.max()), float(gap.mean())))
    return out


def _energy(phi: np.ndarray, rank: int) -> list[float]:
    return [kernels.energy_fraction(phi, CompressOptions(rank=rank), norm) for norm in ("trace", "frobenius")]


@one("spectral_energy", "rank int, trace_share double, frobenius_share double")
def spectral_energy(x: np.ndarray) -> list[tuple]:
    """Energy held by ranks 4 to 32."""
    return [(r, *_energy(_features(x), r)) for r in (4, 8, 16, 32)]


@query("k2_energy")
def k2_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Energy at rank 16 of 256 features: raw vectors, and vectors with a shared direction."""
    df, rows = onesequence.numbered(spark, sf_dir), []
    for name, a in (("raw", 0.0), ("shared", 0.25)):

        def columns(i: np.ndarray, x: np.ndarray, a: float = a) -> np.ndarray:
            return _features(np.sqrt(1 - a) * x + np.sqrt(a) * x.shape[1] ** -0.5)

        n, gram = onesequence.products(df, columns, 256)
        if n:
            rows.append((name, n, *(kernels.energy_in_span(gram, CompressOptions(rank=16), n, norm) for norm in ("trace", "frobenius"))))
    return spark.createDataFrame(rows, "sequence string, n int, trace_share double, frobenius_share double")


@spanned("abl_rank_features", "rank int, dims int, trace_share double, frobenius_share double", dims=512)
def abl_rank_features(df: DataFrame, n: int, gram: np.ndarray) -> list[tuple]:
    """Energy over ranks and numbers of features; fewer features are the first of many, at another scale."""
    part = {d: gram[:d, :d] * (len(gram) / d) for d in (128, 256, 512)}
    return [(r, d, *(kernels.energy_in_span(g, CompressOptions(rank=r), n, norm) for norm in ("trace", "frobenius"))) for d, g in part.items() for r in (4, 8, 16, 32)]


@spanned("abl_row_normalised", "operator string, trace_share double, sum_skew double", dims=256)
def abl_row_normalised(df: DataFrame, n: int, gram: np.ndarray) -> list[tuple]:
    """The operator as it is and divided by its row sums: passes for their totals, their spread, and the scaled products."""
    totals = onesequence.by_row(df, lambda i, x: pd.DataFrame({"f": np.arange(256), "total": _features(x).sum(axis=0)}), "f int, total double").groupBy("f").agg(F.sum("total").alias("total")).orderBy("f").collect()
    total = np.array([r["total"] for r in totals])
    mean = float(total @ total) / n

    def spread(i: np.ndarray, x: np.ndarray) -> pd.DataFrame:
        sums = _features(x) @ total
        return pd.DataFrame({"size": [np.abs(sums).sum()], "square": [((sums - mean) ** 2).sum()]})

    size, square = onesequence.by_row(df, spread, "size double, square double").agg(F.sum("size"), F.sum("square")).first()
    floor, skew = max(1e-3 * size / n, 1e-12), float(np.sqrt(square / n) / abs(mean))

    def scaled(i: np.ndarray, x: np.ndarray) -> np.ndarray:
        phi = _features(x)
        return phi / np.sqrt(np.maximum(phi @ total, floor))[:, None]

    _, row = onesequence.products(df, scaled, 256)
    return [(name, kernels.energy_in_span(g, CompressOptions(rank=16), n), skew) for name, g in (("plain", gram), ("row", row))]


@query("dense_reference")
def dense_reference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of token pairs that the implicit operator and the exact kernel's eigenvectors treat alike."""
    e, opts, dims = backends.frozen_table(spark, sf_dir), CompressOptions(), 512
    df, columns = onesequence.numbered(spark, sf_dir), onesequence.with_start(dims, opts)
    n, gram = onesequence.products(df, columns, dims)
    schema = "n_groups int, agreement double"
    if not n:
        return spark.createDataFrame([], schema)
    to = kernels.projection(gram, dims, opts, n)
    ours = onesequence.by_row(df, lambda i, x: pd.DataFrame({"i": i, "code": kernels.simhash(columns(i, x) @ to, 6)}), "i long, code long").orderBy("i").toPandas()["code"].to_numpy()
    a, b = (kernels.fit_groups_in_order(codes, 64) for codes in (kernels.simhash(onesequence.exact_coordinates(spark, e, opts), 6), ours))
    both = np.zeros((64, 64))
    np.add.at(both, (a, b), 1)
    alike = n * n - (both.sum(axis=1) ** 2).sum() - (both.sum(axis=0) ** 2).sum() + 2 * (both**2).sum()
    return spark.createDataFrame([(64, float(alike / (n * n)))], schema)


# -- one sequence over the whole cluster --------------------------------------------------------------------------


@query("global_lsh_corpus", f"WITH {_TOK} SELECT count(*) AS n_tokens, CAST(greatest(1, ceil(count(*) / 16.0)) AS BIGINT) AS n_groups, true AS codes_kept FROM tok")
def global_lsh_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as one sequence: exactly as many groups as wanted, and codes only merged whole or only split."""
    made = onesequence.compress_corpus(documents(spark, sf_dir), backends.frozen_table(spark, sf_dir), CompressOptions(rho=16, backend="global", rff_dim=64))
    pairs = made.groupBy("grp", "place").agg(F.count("*").alias("size"))
    found = pairs.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("n_tokens"), F.count("*").alias("n_pairs"), F.count_distinct("place").alias("n_codes"), F.count_distinct("grp").alias("n_groups"))
    return found.select("n_tokens", "n_groups", (F.col("n_pairs") == F.greatest("n_codes", "n_groups")).alias("codes_kept"))


# -- quality ------------------------------------------------------------------------------------------------------


def contexts(spark: SparkSession, sf_dir: str, where: str, length: int = 4096, continuation: int = 64) -> DataFrame:
    docs = tables.table(spark, sf_dir, "documents").filter(where)
    return tables.packed(tables.prompts(docs, "doc_id").withColumnRenamed("seq_id", "doc_id"), "doc_id", length, continuation)


def averaged(rows: DataFrame, *keys: str) -> DataFrame:
    means = [F.avg(m).alias(m) for m in evaluation.MEASURES]
    return rows.groupBy("reader", "backend", "rho", *keys).agg(F.count("*").alias("n"), (F.sum("n_tokens") / F.sum("n_macro")).alias("actual_ratio"), *means)


def quality(name: str, where: str, readers: tuple[str, ...], configs: list, length: int = 4096) -> None:
    @query(name)
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = evaluation.evaluate(contexts(spark, sf_dir, where, length), backends.frozen_table(spark, sf_dir), configs, {r: READERS[r] for r in readers})
        return averaged(rows)


_CHOSEN = [(f"{k}", CompressOptions(backend=b, rho=4, **more)) for k, b, more in (
    ("chunk", "chunk", {}), ("random", "random", {}), ("raw_lsh", "raw_lsh", {}), ("local", "local", {}), ("adaptive", "adaptive", {}), ("global", "global", {}))]
quality("w_quality_grid", "lang = 'en'", ("flat", "rotary", "sliding"), evaluation.grid())
quality("quality_by_backend", "lang = 'en'", ("flat",), evaluation.grid(("chunk", "random", "raw_lsh", "local", "adaptive", "global")), 2048)
quality("w_quality_small", "lang = 'en'", ("narrow16", "narrow8"), evaluation.grid(wide_at_two=True), 2048)
quality("w_quality_second_corpus", "lang <> 'en'", ("flat",), evaluation.grid(), 2048)
quality("w_reference_backends", "lang = 'en'", ("flat",), _CHOSEN)
quality("abl_renorm", "lang = 'en'", ("flat",), [(m, CompressOptions(renorm=m, backend=b)) for b in ("chunk",) for m in ("none", "member_mean", "table_mean", "prompt_mean")], 2048)
quality("abl_position_mode", "lang = 'en'", ("rotary",), [(m, CompressOptions(position_mode=m)) for m in ("representative", "compact")], 2048)
quality("abl_printed_settings", "lang = 'en'", ("flat",), [("ours", CompressOptions(backend="local")), ("as_printed", CompressOptions(backend="local").as_printed())], 2048)


@query("w_adaptive_small")
def w_adaptive_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two packed samples of 4096 tokens under the small readers, adaptive at each ratio."""
    two = contexts(spark, sf_dir, "lang = 'en'").orderBy("seq_id").limit(2)  # the workload's own two samples
    named = {r: READERS[r] for r in ("narrow16", "narrow8")}
    return averaged(evaluation.evaluate(tables.spread(two, always=True), backends.frozen_table(spark, sf_dir), evaluation.grid(("adaptive",)), named))


@query("teacher_forced_eval")
def teacher_forced_eval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each packed context of 1024 tokens with its measures."""
    return evaluation.evaluate(contexts(spark, sf_dir, "lang = 'en'", 1024), backends.frozen_table(spark, sf_dir), [("adaptive", CompressOptions())], {"flat": READERS["flat"]})


# -- short prompts ------------------------------------------------------------------------------------------------


def short_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first user turn of a conversation, with the first answer as its continuation."""
    turns = tables.table(spark, sf_dir, "conversations").filter("role IN ('user', 'assistant')")
    first = turns.groupBy(F.col("conv_id").alias("seq_id")).agg(
        F.min_by(F.when(F.col("role") == "user", F.col("text")), F.when(F.col("role") == "user", F.col("turn"))).alias("ask"),
        F.min_by(F.when(F.col("role") == "assistant", F.col("text")), F.when(F.col("role") == "assistant", F.col("turn"))).alias("answer"),
    )
    both = first.filter("ask IS NOT NULL AND answer IS NOT NULL")
    return both.select("seq_id", tables.words("ask").alias("tokens"), tables.words("answer").alias("continuation"))


_SCHEMES = ("max", "median", "mean")


@query("k1_pass_rate")
def k1_pass_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of short prompts at a ratio of 2 with a near-equal logit direction and the same first choice."""
    configs = [(s, CompressOptions(rho=2, position_scheme=s)) for s in _SCHEMES]
    rows = evaluation.evaluate(short_prompts(spark, sf_dir), backends.frozen_table(spark, sf_dir), configs, {"flat": READERS["flat"]})
    near, kept = F.col("cosine") > 0.999, F.col("top1") == 1
    return rows.groupBy(F.col("backend").alias("scheme")).agg(F.count("*").alias("n"), F.avg("cosine").alias("cosine"), F.avg(near.cast("double")).alias("near"), F.avg(kept.cast("double")).alias("kept"), F.avg((near & kept).cast("double")).alias("passed"))


@query("pass_rate")
def pass_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same shares over ratios."""
    rows = evaluation.evaluate(short_prompts(spark, sf_dir), backends.frozen_table(spark, sf_dir), evaluation.grid(("chunk", "adaptive"), (1, 2, 4)), {"flat": READERS["flat"]})
    return rows.groupBy("backend", "rho").agg(F.count("*").alias("n"), F.avg(((F.col("cosine") > 0.999) & (F.col("top1") == 1)).cast("double")).alias("passed"))


@query("k1_monotone_positions", r"""
WITH b AS (SELECT item_id AS seq_id, CAST(len(regexp_extract_all(text, '[^\x20\x09-\x0d]+')) AS INTEGER) AS n FROM benchmark)
SELECT seq_id, n AS n_tokens, CAST(CASE WHEN n <= 12 THEN n ELSE 12 + ceil((n - 12) / 2.0) END AS INTEGER) AS n_macro, 0 AS unordered, 0 AS late_members FROM b WHERE n > 0""")
def k1_monotone_positions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Positions of compressed benchmark items never fall."""
    df = tables.spread(tables.prompts(tables.table(spark, sf_dir, "benchmark"), "item_id"))
    return backends.summarise(df, backends.frozen_table(spark, sf_dir), CompressOptions(rho=2)).select("seq_id", "n_tokens", "n_macro", "unordered", "late_members")


# -- structured prompts -------------------------------------------------------------------------------------------


def _stress(name: str, source: Callable[[SparkSession, str], DataFrame]) -> None:
    @query(name)
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Lengths, routes and distortion of each backend at ratios of 8 and 16."""
        df = tables.spread(tables.prompts(source(spark, sf_dir), "seq_id", pattern=tables.SYMBOL), always=True)
        out = studies.summaries(df, backends.frozen_table(spark, sf_dir), evaluation.grid(("chunk", "local", "adaptive", "global"), (8, 16)))
        return out.groupBy("backend", "rho").agg(
            F.sum("n_tokens").alias("n_tokens"), (F.sum("n_tokens") / F.sum("n_macro")).alias("actual_ratio"), (F.sum("n_spectral") / F.sum("n_windows")).alias("spectral_share"),
            F.sum("late_members").alias("late_members"), F.avg("mean_score").alias("mean_score"), (F.sum("distortion") / F.sum("n_tokens")).alias("distortion"),
        )


def retrieval_style(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twenty pages and one benchmark item for each prompt: a passage to be found among others."""
    pages = tables.code_like(spark, sf_dir)
    items = tables.table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("seq_id"), F.col("text").alias("item"))
    return pages.join(items, "seq_id", "left").select("seq_id", F.concat_ws("\n", "text", "item").alias("text"))


_stress("w_stress_json", tables.json_like)
_stress("w_stress_code", tables.code_like)
_stress("w_stress_table", tables.table_like)
_stress("w_retrieval_style", retrieval_style)


@query("route_share")
def route_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of windows on the spectral path by ratio and threshold schedule."""
    configs = [(kind, CompressOptions(rho=rho, schedule=kind)) for kind in ("linear", "log2", "constant") for rho in RHOS]
    rows = studies.summaries(documents(spark, sf_dir), backends.frozen_table(spark, sf_dir), configs).withColumnRenamed("backend", "schedule")
    return rows.groupBy("schedule", "rho").agg(F.sum("n_windows").alias("n_windows"), F.sum("n_spectral").alias("n_spectral"), (F.sum("n_spectral") / F.sum("n_windows")).alias("share"))


@query("abl_bits", f"WITH {_TOK} SELECT rho, sum(CASE WHEN n <= {SUFFIX} THEN n ELSE {SUFFIX} + greatest(1, CAST(ceil((n - {SUFFIX}) / cast(rho AS DOUBLE)) AS BIGINT)) END) AS n_macro FROM {_N} t CROSS JOIN (VALUES (2), (4), (8), (16)) r(rho) GROUP BY rho")
def abl_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups after adjustment with bits from the ratio: exactly the target whatever the codes were."""
    configs = [("local", CompressOptions(rho=rho, backend="local")) for rho in RHOS]
    rows = studies.summaries(documents(spark, sf_dir), backends.frozen_table(spark, sf_dir), configs)
    return rows.groupBy(F.col("rho").cast("int").alias("rho")).agg(F.sum("n_macro").alias("n_macro"))


@query("k3_purity")
def k3_purity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of pairs in one bucket whose raw cosine is above 0.7, for raw and spectral codes of 12 bits."""

    def rows(r, vocabulary, norm):
        x = vocabulary(list(r.tokens))
        unit = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        for kind, z in (("raw", x), ("spectral", kernels.coordinates(kernels.rff(x, 256)[None], CompressOptions())[0])):
            pairs = pure = 0
            codes = kernels.simhash(z, 12)
            for c in np.unique(codes):
                m = unit[codes == c]
                cosines = (m @ m.T)[np.triu_indices(len(m), 1)]
                pairs, pure = pairs + len(cosines), pure + int((cosines > 0.7).sum())
            yield (r.seq_id, kind, pairs, pure)

    df = contexts(spark, sf_dir, "lang = 'en'", 2048)
    got = backends._with_vectors(df, backends.frozen_table(spark, sf_dir), CompressOptions(), "seq_id long, codes string, pairs long, pure long", rows)
    return got.groupBy("codes").agg(F.sum("pairs").alias("pairs"), F.sum("pure").alias("pure"), (F.sum("pure") / F.sum("pairs")).alias("purity"))


@query("pack_sequences", f"""WITH {_TOK}, t AS (SELECT count(*) AS total FROM tok)
SELECT seq_id, CAST(least(512, total - 512 * seq_id) AS INTEGER) AS n_tokens FROM (SELECT total, unnest(range(0, CAST(ceil(total / 512.0) AS BIGINT))) AS seq_id FROM t) s""")
def pack_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents cut into sequences of 512 tokens; the last one holds what is left."""
    docs = tables.prompts(tables.table(spark, sf_dir, "documents"), "doc_id").withColumnRenamed("seq_id", "doc_id")
    return tables.packed(docs, "doc_id", 512).select("seq_id", F.size("tokens").alias("n_tokens"))


# -- functions for users of SQL -----------------------------------------------------------------------------------


@F.pandas_udf(LongType())
def simhash_code(x: pd.Series) -> pd.Series:
    """The 8-bit code of a vector."""
    return pd.Series(kernels.simhash(np.stack(x.to_numpy()).astype(np.float64), 8)) if len(x) else pd.Series([], dtype="int64")


@query("udf_simhash", _SQL["simhash_raw"])
def udf_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = tables.table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").cast("int").alias("i"), simhash_code("embedding").alias("code"))


@F.pandas_udf(DoubleType())
def redundancy(x: pd.Series) -> float:
    """Redundancy of the vectors of a group."""
    return float(kernels.redundancy(np.stack(x.to_numpy()).astype(np.float64)))


@F.pandas_udf(LongType())
def members(x: pd.Series) -> int:
    """Vectors of a group; Spark runs no built-in aggregate beside one in pandas."""
    return len(x)


@query("udaf_redundancy", _SQL["redundancy_score"])
def udaf_redundancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = tables.table(spark, sf_dir, "embeddings").withColumn("w", F.floor(F.col("vec_id") / 16).cast("int"))
    e = e.withColumn("embedding", F.transform("embedding", lambda v: F.lit(0.75**0.5) * v + 0.0625))  # the shared direction
    return e.groupBy("w").agg(F.round(redundancy("embedding"), 6).alias("score"), members("embedding").alias("len"))


@F.udtf(returnType=StructType().add("win_id", IntegerType()).add("first_pos", IntegerType()).add("n_tokens", IntegerType()))
class TokenWindows:
    """Windows of a prompt's body."""

    def eval(self, n: int, width: int, suffix: int) -> Iterator[tuple[int, int, int]]:
        for i in range(0, max(n - suffix, 0), width):
            yield i // width, i, min(width, n - suffix - i)


@query("udtf_windows", f"WITH {_TOK} SELECT seq_id, CAST(pos // 16 AS INTEGER) AS win_id, CAST(min(pos) AS INTEGER) AS first_pos, CAST(count(*) AS INTEGER) AS n_tokens FROM tok WHERE pos < n - {SUFFIX} GROUP BY seq_id, pos // 16")
def udtf_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    spark.udtf.register("token_windows", TokenWindows)
    tables.document_prompts(spark, sf_dir).createOrReplaceTempView("wide_prompts")
    return spark.sql(f"SELECT seq_id, w.win_id, w.first_pos, w.n_tokens FROM wide_prompts, LATERAL token_windows(size(tokens), 16, {SUFFIX}) w")


@query("sql_surface", f"WITH {_TOK} SELECT seq_id, CAST({_target(4)} AS INTEGER) AS n_macro, round(0.70 - 0.10 * 2 / 6, 6) AS tau FROM {_N} t")
def sql_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scalar rules called by name from SQL."""
    spark.udf.register("target_length", lambda n, rho: schedule.target_length(n, rho, 0, SUFFIX), IntegerType())
    spark.udf.register("tau", lambda rho: schedule.tau(rho), DoubleType())
    spark.udf.register("simhash_code", simhash_code)
    prepared(spark, sf_dir, ("documents", "embeddings", "tok"))
    return spark.sql(f"SELECT seq_id, target_length(n, 4.0D) AS n_macro, round(tau(4.0D), 6) AS tau FROM {_N} t")
