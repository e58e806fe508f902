"""The library's own kernels and rules behind the query keys whose SQL text is an oracle only.

Prompts stay wide rows: what depends on a prompt's length alone is worked out from its
length, so no token is shuffled. The frozen table is read in blocks of neighbouring rows.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tokenfold.functions import kernels, reader, rng, schedule
from tokenfold.operators import backends
from tokenfold.options import CompressOptions
from tokenfold.plans import stages  # noqa: F401  its texts are the oracles
from tokenfold.registry import implement
from tokenfold.sources import tables

SUFFIX, RHOS, BLOCK = 12, (2, 4, 8, 16), 64
Rows = Iterator[pd.DataFrame]


def _names(schema: str) -> list[str]:
    return [c.strip().split(" ")[0] for c in schema.split(", ")]


def _frame(schema: str, *columns) -> pd.DataFrame:
    return pd.DataFrame(dict(zip(_names(schema), columns, strict=True)))


def lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.spread(tables.document_prompts(spark, sf_dir)).select("seq_id", F.size("tokens").alias("n"))


def by_length(name: str, schema: str) -> Callable:
    """Register rows made from each prompt's id and number of tokens; prompts without a token give none."""

    def add(make: Callable[[int, int], pd.DataFrame]) -> Callable:
        def run(batches: Rows) -> Rows:
            for batch in batches:
                made = [make(seq, n) for seq, n in zip(batch["seq_id"].tolist(), batch["n"].tolist(), strict=True) if n]
                yield pd.concat(made) if made else pd.DataFrame(columns=_names(schema))

        def build(spark: SparkSession, sf_dir: str) -> DataFrame:
            return lengths(spark, sf_dir).mapInPandas(run, schema)

        build.__name__, build.__doc__ = name, make.__doc__
        implement(name)(build)
        return make

    return add


# -- regions, windows, budgets ------------------------------------------------------------------------------------


@implement("tokenize_documents")
def tokenize_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens with their places."""
    return tables.document_prompts(spark, sf_dir).select("seq_id", F.posexplode("tokens").alias("pos", "token"))


def with_table(name: str, schema: str) -> Callable:
    """Register rows made from each prompt's tokens and the frozen table; vectors are those of the table, unchanged."""

    def add(make: Callable) -> Callable:
        def build(spark: SparkSession, sf_dir: str) -> DataFrame:
            sent = spark.sparkContext.broadcast(backends.frozen_table(spark, sf_dir))

            def run(batches: Rows) -> Rows:
                vocabulary = kernels.Vocabulary(sent.value, anisotropy=0.0)
                for batch in batches:
                    made = [make(seq, list(tokens), vocabulary) for seq, tokens in zip(batch["seq_id"].tolist(), batch["tokens"], strict=True) if len(tokens)]
                    yield pd.concat(made) if made else pd.DataFrame(columns=_names(schema))

            return tables.spread(tables.document_prompts(spark, sf_dir)).mapInPandas(run, schema)

        build.__name__, build.__doc__ = name, make.__doc__
        implement(name)(build)
        return make

    return add


_EMBED = "seq_id long, pos int, tok_id long, total double, norm double"


@with_table("embed_tokens", _EMBED)
def embed_tokens(seq: int, tokens: list[str], v: kernels.Vocabulary) -> pd.DataFrame:
    """Sum and norm of each token's vector."""
    x = v(tokens)
    return _frame(_EMBED, seq, np.arange(len(tokens)), [v.id(t) for t in tokens], np.round(x.sum(axis=1), 6), np.round(np.linalg.norm(x, axis=1), 6))


_IDENTITY = "seq_id long, pos int, mpos int, tok_id long"


@with_table("identity_bypass", _IDENTITY)
def identity_bypass(seq: int, tokens: list[str], v: kernels.Vocabulary) -> pd.DataFrame:
    """A ratio of one: every token is its own macro-token at its own place."""
    m = kernels.compress(v(tokens), CompressOptions(rho=1))
    return _frame(_IDENTITY, seq, m.first, m.pos, [v.id(t) for t in tokens])


_REGIONS = "seq_id long, pos int, region string"


@by_length("mark_regions", _REGIONS)
def mark_regions(seq: int, n: int) -> pd.DataFrame:
    """Prefix, body or suffix for each place."""
    return _frame(_REGIONS, seq, np.arange(n), schedule.regions(n, 0, SUFFIX))


_WINDOWS = "seq_id long, win_id int, first_pos int, n_tokens long"


@by_length("split_windows", _WINDOWS)
def split_windows(seq: int, n: int) -> pd.DataFrame:
    """Windows of 16 over the body."""
    first = np.arange(0, max(n - SUFFIX, 0), 16)
    return _frame(_WINDOWS, seq, np.arange(len(first)), first, np.minimum(16, n - SUFFIX - first))


_TARGET = "seq_id long, rho int, n long, n_macro long"


@by_length("target_length", _TARGET)
def target_length(seq: int, n: int) -> pd.DataFrame:
    """Tokens after compression at each ratio."""
    return _frame(_TARGET, seq, RHOS, n, [schedule.target_length(n, r, 0, SUFFIX) for r in RHOS])


@implement("actual_ratio")
def actual_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens before over tokens after, of the corpus and as the prompts' mean."""

    def run(batches: Rows) -> Rows:
        for batch in batches:
            n = batch["n"][batch["n"] > 0].tolist()
            yield pd.DataFrame([(r, k, schedule.target_length(k, r, 0, SUFFIX)) for r in RHOS for k in n], columns=["rho", "n", "m"])

    rows = lengths(spark, sf_dir).mapInPandas(run, "rho int, n long, m long")
    return rows.groupBy("rho").agg(F.round(F.sum("n") / F.sum("m"), 6).alias("ratio"), F.round(F.avg(F.col("n") / F.col("m")), 6).alias("mean_ratio"))


def _bits(n: int, rho: float) -> int:
    return schedule.bits_for_target(max(1, math.ceil(max(n - SUFFIX, 1) / rho)))


_BITS = "seq_id long, rho int, bits int"


@by_length("bits_for_target", _BITS)
def bits_for_target(seq: int, n: int) -> pd.DataFrame:
    """Bits that name as many codes as the body's groups."""
    return _frame(_BITS, seq, RHOS, [_bits(n, r) for r in RHOS])


_BUCKET = "seq_id long, rho int, size double"


@by_length("expected_bucket_size", _BUCKET)
def expected_bucket_size(seq: int, n: int) -> pd.DataFrame:
    """Tokens to a code."""
    return _frame(_BUCKET, seq, RHOS, [round(n / 2 ** _bits(n, r), 6) for r in RHOS])


_BUDGETS = "seq_id long, win_id int, len long, budget int"


def _budgets(rho: int) -> None:
    @by_length("window_budgets" if rho == 4 else f"window_budgets_rho{rho}", _BUDGETS)
    def budgets(seq: int, n: int) -> pd.DataFrame:
        """Groups of each window."""
        body = max(n - SUFFIX, 0)
        first = np.arange(0, body, 16)
        return _frame(_BUDGETS, seq, np.arange(len(first)), np.minimum(16, body - first), schedule.budgets(body, max(1, math.ceil(body / rho)), 16))


# -- chunks and positions -----------------------------------------------------------------------------------------


def chunked(n: int, rho: float, **more) -> kernels.Macro:
    """Chunks of a prompt by places alone: its vectors play no part in them."""
    return kernels.compress(np.zeros((n, 1)), CompressOptions(rho=rho, backend="chunk", **more))


def _group(m: kernels.Macro, n: int, rho: int) -> np.ndarray:
    return np.where(m.first >= n - SUFFIX, 1_000_000_000 + m.first, m.first // rho)


_CHUNK = "seq_id long, out_pos int, mpos int, n_members long, first_pos int, last_pos int"


def _chunks(rho: int) -> None:
    @by_length(f"chunk_rho{rho}", _CHUNK)
    def chunk(seq: int, n: int) -> pd.DataFrame:
        """Macro-tokens by runs of neighbours, in causal order."""
        m = chunked(n, rho)
        return _frame(_CHUNK, seq, np.arange(len(m.pos)), m.pos, m.size, m.first, m.last)


for _rho in RHOS:
    _budgets(_rho)
    _chunks(_rho)

_BUDGETED = "seq_id long, win_id int, g int, mpos int, n_members long"


@by_length("chunk_budgeted", _BUDGETED)
def chunk_budgeted(seq: int, n: int) -> pd.DataFrame:
    """Runs of neighbours within windows, as many as each window's budget."""
    body = n - SUFFIX
    if body <= 0:
        return pd.DataFrame(columns=_names(_BUDGETED))
    labels = kernels.group_body(np.zeros((body, 1)), CompressOptions(rho=4, backend="chunk_budgeted")).labels
    m = kernels.fuse(np.zeros((body, 1)), np.arange(body), labels, CompressOptions())
    window = m.first // 16
    before = np.concatenate([[0], np.cumsum(np.bincount(window))])[window]
    return _frame(_BUDGETED, seq, window, np.arange(len(window)) - before, m.pos, m.size)


_POSITION = "seq_id long, grp int, mpos int"


def _position(scheme: str) -> None:
    @by_length(f"position_{scheme}", _POSITION)
    def position(seq: int, n: int) -> pd.DataFrame:
        """Positions of chunks of 4 under one scheme."""
        m = chunked(n, 4, position_scheme=scheme)
        return _frame(_POSITION, seq, _group(m, n, 4), m.pos)


for _scheme in ("max", "mean", "median"):
    _position(_scheme)


_REPRESENTATIVE, _COMPACT, _ORDER = "seq_id long, mpos int, first_pos int", "seq_id long, mpos int, cpos int", "seq_id long, grp int, place int"


@by_length("positions_representative", _REPRESENTATIVE)
def positions_representative(seq: int, n: int) -> pd.DataFrame:
    """Positions that stand for a group's members."""
    m = chunked(n, 8)
    return _frame(_REPRESENTATIVE, seq, m.pos, m.first)


@by_length("positions_compact", _COMPACT)
def positions_compact(seq: int, n: int) -> pd.DataFrame:
    """Positions counted anew."""
    m = chunked(n, 8, position_mode="compact")
    return _frame(_COMPACT, seq, m.last, m.pos)


@by_length("macro_order", _ORDER)
def macro_order(seq: int, n: int) -> pd.DataFrame:
    """Places of groups in causal order."""
    m = chunked(n, 2)
    return _frame(_ORDER, seq, _group(m, n, 2), np.arange(1, len(m.pos) + 1))


_ASSEMBLED = "seq_id long, n_macro long, kept long, n_tokens long"


@by_length("assemble_prompt", _ASSEMBLED)
def assemble_prompt(seq: int, n: int) -> pd.DataFrame:
    """Lengths of the whole prompt after compression."""
    m = chunked(n, 4)
    return pd.DataFrame([(seq, len(m.pos), int((m.first >= n - SUFFIX).sum()), int(m.size.sum()))], columns=_names(_ASSEMBLED))


def _late(spark: SparkSession, sf_dir: str, rhos: tuple[int, ...]) -> DataFrame:
    """Macro-tokens that stand before one of their members, and neighbours out of order, by scheme and ratio."""

    def run(batches: Rows) -> Rows:
        for batch in batches:
            rows = []
            for n in batch["n"][batch["n"] > 0].tolist():
                for scheme in ("max", "mean", "median"):
                    for rho in rhos:
                        m = chunked(n, rho, position_scheme=scheme)
                        by_first = m.pos[np.argsort(m.first, kind="stable")]
                        rows.append((scheme, rho, int((m.last > m.pos).sum()), int((np.diff(by_first) < 0).sum()), len(m.pos)))
            made = pd.DataFrame(rows, columns=["scheme", "rho", "late", "unordered", "n"])
            yield made.groupby(["scheme", "rho"], as_index=False).sum()

    return lengths(spark, sf_dir).mapInPandas(run, "scheme string, rho int, late long, unordered long, n long")


@implement("causal_violations")
def causal_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Late members and order of macro-tokens by position scheme."""
    return _late(spark, sf_dir, (4,)).groupBy("scheme").agg(F.sum("late").alias("late"), F.sum("unordered").alias("unordered"))


@implement("abl_position_scheme")
def abl_position_scheme(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Late members by scheme and ratio."""
    return _late(spark, sf_dir, RHOS).groupBy("scheme", "rho").agg(F.sum("late").alias("late"), F.round(F.sum("late") / F.sum("n"), 6).alias("share"))


@implement("position_gaps")
def position_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often neighbouring macro-tokens are so far apart."""

    def run(batches: Rows) -> Rows:
        for batch in batches:
            gaps = [np.diff(chunked(n, 8).pos) for n in batch["n"].tolist() if n > 1]
            gap, times = np.unique(np.concatenate(gaps) if gaps else np.empty(0, int), return_counts=True)
            yield pd.DataFrame({"gap": gap, "n": times})

    return lengths(spark, sf_dir).mapInPandas(run, "gap int, n long").groupBy("gap").agg(F.sum("n").alias("n"))


@implement("uncompressed_truncated")
def uncompressed_truncated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first 8192 tokens as they are."""
    kept = F.least("n", F.lit(8192))
    return lengths(spark, sf_dir).filter("n > 0").select("seq_id", kept.cast("long").alias("n_kept"), (kept - 1).cast("int").alias("last_pos"))


_RANDOM = "seq_id long, first_pos int, last_pos int, n_members long"


@by_length("random_groups", _RANDOM)
def random_groups(seq: int, n: int) -> pd.DataFrame:
    """Groups by random ranks, as many as at a ratio of 4."""
    body = n - SUFFIX
    if body <= 0:
        return pd.DataFrame(columns=_names(_RANDOM))
    labels = kernels.group_body(np.zeros((body, 1)), CompressOptions(rho=4, backend="random")).labels
    m = kernels.fuse(np.zeros((body, 1)), np.arange(body), kernels.dense_labels(labels), CompressOptions(suffix=0))
    return _frame(_RANDOM, seq, m.first, m.last, m.size)


# -- vectors of the frozen table as one sequence ------------------------------------------------------------------


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("int").alias("i"), "embedding")


def _array(frame: pd.DataFrame, column: str = "embedding") -> np.ndarray:
    return np.stack(frame[column].to_numpy()).astype(np.float64)


def by_block(name: str, schema: str) -> Callable:
    """Register rows made from blocks of BLOCK neighbouring vectors, which hold whole groups and windows."""

    def add(make: Callable[[np.ndarray, np.ndarray, float], pd.DataFrame]) -> Callable:
        def build(spark: SparkSession, sf_dir: str) -> DataFrame:
            df = vectors(spark, sf_dir)
            norms = df.select(F.avg(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))))).first()[0] or 1.0

            def run(block: pd.DataFrame) -> pd.DataFrame:
                block = block.sort_values("i")
                return make(block["i"].to_numpy(), _array(block), norms)

            return df.groupBy(F.floor(F.col("i") / BLOCK).alias("block")).applyInPandas(run, schema)

        build.__name__, build.__doc__ = name, make.__doc__
        implement(name)(build)
        return make

    return add


def _fused(i: np.ndarray, x: np.ndarray, renorm: str, norms: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
    """Numbers and vectors of the fused groups of 4."""
    m = kernels.fuse(x, i, kernels.dense_labels(i // 4), CompressOptions(renorm=renorm), norms)
    return m.first // 4, m.x


_FUSED = "g int, j int, x double"


def _long(g: np.ndarray, x: np.ndarray) -> pd.DataFrame:
    return _frame(_FUSED, np.repeat(g, x.shape[1]), np.tile(np.arange(x.shape[1]), len(g)), np.round(x.reshape(-1), 6))


@by_block("fuse_mean", _FUSED)
def fuse_mean(i: np.ndarray, x: np.ndarray, _: float) -> pd.DataFrame:
    """Means of groups."""
    return _long(*_fused(i, x, "none"))


@by_block("restore_norm", _FUSED)
def restore_norm(i: np.ndarray, x: np.ndarray, _: float) -> pd.DataFrame:
    """Means with the mean norm of their members."""
    return _long(*_fused(i, x, "member_mean"))


@by_block("renorm_table", _FUSED)
def renorm_table(i: np.ndarray, x: np.ndarray, norms: float) -> pd.DataFrame:
    """Means with the mean norm of the table."""
    return _long(*_fused(i, x, "table_mean", norms))


@by_block("renorm_off", "g int, norm double")
def renorm_off(i: np.ndarray, x: np.ndarray, _: float) -> pd.DataFrame:
    """Norms of plain means."""
    g, y = _fused(i, x, "none")
    return pd.DataFrame({"g": g, "norm": np.round(np.linalg.norm(y, axis=1), 6)})


@by_block("norm_collapse", "g int, collapse double")
def norm_collapse(i: np.ndarray, x: np.ndarray, _: float) -> pd.DataFrame:
    """Norms of plain means over those of their members."""
    (g, y), (_, z) = _fused(i, x, "none"), _fused(i, x, "member_mean")
    return pd.DataFrame({"g": g, "collapse": np.round(np.linalg.norm(y, axis=1) / np.linalg.norm(z, axis=1), 6)})


@by_block("distortion", "g int, distortion double")
def distortion(i: np.ndarray, x: np.ndarray, _: float) -> pd.DataFrame:
    """Squared distances of members to their mean."""
    g, y = _fused(i, x, "none")
    at = kernels.dense_labels(i // 4)
    return pd.DataFrame({"g": g, "distortion": np.round(np.bincount(at, ((x - y[at]) ** 2).sum(axis=1)), 6)})


@implement("renorm_prompt")
def renorm_prompt(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Norms of plain means, and the mean norm of the sequence, which is one number for all."""

    def run(block: pd.DataFrame) -> pd.DataFrame:
        block = block.sort_values("i")
        x = _array(block)
        (g, y), (_, z) = _fused(block["i"].to_numpy(), x, "none"), _fused(block["i"].to_numpy(), x, "member_mean")
        return pd.DataFrame({"g": g, "before": np.linalg.norm(y, axis=1), "own": np.linalg.norm(z, axis=1)})

    rows = vectors(spark, sf_dir).groupBy(F.floor(F.col("i") / BLOCK).alias("block")).applyInPandas(run, "g int, before double, own double")
    rows = tables.settle(rows, "norms")
    return rows.crossJoin(F.broadcast(rows.agg(F.round(F.avg("own"), 6).alias("after")))).select("g", F.round("before", 6).alias("before"), "after")  # one row


def _windows(i: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Numbers, scores and lengths of windows of 16 vectors with a shared direction."""
    y = np.sqrt(0.75) * x + 0.5 / np.sqrt(x.shape[1])
    w = i // 16
    own = np.unique(w)
    return own, np.array([kernels.redundancy(y[w == k]) for k in own]), np.array([(w == k).sum() for k in own])


@by_block("redundancy_score", "w int, score double, len long")
def redundancy_score(i: np.ndarray, x: np.ndarray, _: float) -> pd.DataFrame:
    """Mean cosine of a window's vectors to their centroid."""
    w, score, n = _windows(i, x)
    return pd.DataFrame({"w": w, "score": np.round(score, 6), "len": n})


_ROUTE = "w int, rho double, route string"


@by_block("route_windows", _ROUTE)
def route_windows(i: np.ndarray, x: np.ndarray, _: float) -> pd.DataFrame:
    """The path of each window by ratio."""
    w, score, n = _windows(i, x)
    return pd.concat([_frame(_ROUTE, w, float(r), np.where((n > 4) & (score >= schedule.tau(r)), "spectral", "chunk")) for r in (2, 4, 6, 8, 12, 16)])


@implement("route_constant_tau")
def route_constant_tau(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows on each path under one threshold for all ratios."""

    def run(block: pd.DataFrame) -> pd.DataFrame:
        _, score, n = _windows(block["i"].to_numpy(), _array(block))
        return pd.DataFrame({"route": np.where((n > 4) & (score >= schedule.tau(4, schedule="constant")), "spectral", "chunk")})

    rows = vectors(spark, sf_dir).groupBy(F.floor(F.col("i") / BLOCK).alias("block")).applyInPandas(run, "route string")
    return rows.groupBy("route").agg(F.count("*").alias("n"))


def listed(name: str, schema: str) -> Callable:
    """Register rows of a rule that reads no table."""

    def add(make: Callable[[], list[tuple]]) -> Callable:
        def build(spark: SparkSession, sf_dir: str) -> DataFrame:
            return spark.createDataFrame(make(), schema)

        build.__name__, build.__doc__ = name, make.__doc__
        implement(name)(build)
        return make

    return add


@listed("tau_schedule", "rho double, linear double, log_form double")
def tau_schedule() -> list[tuple]:
    """Thresholds over ratios."""
    return [(float(r), round(schedule.tau(r), 6), round(schedule.tau(r, schedule="log2"), 6)) for r in (2, 4, 6, 8, 12, 16)]


# -- kernels and features -----------------------------------------------------------------------------------------


#: Numbers of a product with the table that a task holds at once.
MOST_CELLS = 1 << 20


def rows_at_once(width: int) -> int:
    """Rows of one side whose products with `width` of the other are formed at once: fewer the more there are, so that memory does not grow with them."""
    return max(1, min(512, MOST_CELLS // max(1, width)))


def against_table(name: str, schema: str, make: Callable[[np.ndarray, np.ndarray], np.ndarray], column: str, whole: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> None:
    """Register a number for each vector and each row of the frozen table: products of a few vectors with a few rows at once, no join.

    make: the exponents of a tile; whole: what each vector's exponents are lessened by, from
    the whole table. Rows leave by k within a tile, so that both numbers of a pair are runs
    or short patterns where they are written.
    """

    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        sent = spark.sparkContext.broadcast(backends.frozen_table(spark, sf_dir))

        def run(batches: Rows) -> Rows:
            for batch in batches:
                for low in range(0, len(batch), 512):
                    part = batch[low : low + 512]
                    i, x, e = part["i"].to_numpy(), _array(part), sent.value
                    less = 0.0 if whole is None else whole(x, e)
                    for first in range(0, len(e), step := rows_at_once(len(x))):
                        z = np.exp(make(x, e[first : first + step]) - less).T
                        yield pd.DataFrame({"i": np.tile(i, len(z)), "k": np.repeat(np.arange(first, first + len(z)), len(i)), column: np.round(z.reshape(-1), 6)})

        return tables.spread(vectors(spark, sf_dir)).mapInPandas(run, schema)

    build.__name__, build.__doc__ = name, f"{name}: every vector against the frozen table."
    implement(name)(build)


def _scaled(x: np.ndarray, e: np.ndarray) -> np.ndarray:
    return x @ e.T / np.sqrt(x.shape[1])


def _gap(x: np.ndarray, e: np.ndarray) -> np.ndarray:
    gap = (x * x).sum(1)[:, None] + (e * e).sum(1)[None] - 2 * x @ e.T
    return -gap / (2 * np.sqrt(x.shape[1]))


def log_total(x: np.ndarray, e: np.ndarray) -> np.ndarray:
    """Logarithm of the sum of each vector's softmax kernel over the table, tile by tile."""
    most, total = np.full((len(x), 1), -np.inf), np.zeros((len(x), 1))
    for first in range(0, len(e), step := rows_at_once(len(x))):
        z = _scaled(x, e[first : first + step])
        above = np.maximum(most, z.max(axis=1, keepdims=True))
        total = total * np.exp(most - above) + np.exp(z - above).sum(axis=1, keepdims=True)
        most = above
    return most + np.log(total)


against_table("exact_kernel", "i int, k int, kernel double", _scaled, "kernel")
against_table("exact_gaussian_kernel", "i int, k int, kernel double", _gap, "kernel")
against_table("exact_attention_rows", "i int, k int, weight double", _scaled, "weight", log_total)

DIMS = 32


@implement("rff_params")
def rff_params(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frequencies of each dimension of the table's vectors, and phases."""
    width = vectors(spark, sf_dir).select(F.max(F.size("embedding"))).first()[0] or 0
    omega, phase = rng.normals(0, "omega", width, 64), rng.uniforms(0, "phase", 1, 64)[0]
    return spark.createDataFrame([(j, f, round(float(omega[j, f]), 6), round(float(phase[f]), 6)) for j in range(width) for f in range(64)], "j long, f long, omega double, phase double")


@implement("start_vector")
def start_vector(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One normal number for each place."""

    def run(batches: Rows) -> Rows:
        for batch in batches:
            i = batch["i"].to_numpy()
            yield pd.DataFrame({"i": i, "v": np.round(rng.normals(0, "token", int(i.max()) + 1 if len(i) else 0, 1)[i, 0], 6)})

    return vectors(spark, sf_dir).select("i").mapInPandas(run, "i int, v double")


def _features(df: DataFrame, schema: str, make: Callable[[np.ndarray, np.ndarray], pd.DataFrame], kernel: str = "gaussian") -> DataFrame:
    """Rows made from the vectors' numbers and features, batch by batch."""

    def run(batches: Rows) -> Rows:
        for batch in batches:
            if len(batch):
                yield make(batch["i"].to_numpy(), kernels.rff(_array(batch), DIMS, 0, kernel))

    return df.mapInPandas(run, schema)


def _phi(name: str, kernel: str) -> None:
    @implement(name)
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Features of every vector."""
        return _features(vectors(spark, sf_dir), "i int, f int, phi double", lambda i, p: pd.DataFrame({"i": np.repeat(i, DIMS), "f": np.tile(np.arange(DIMS), len(i)), "phi": np.round(p.reshape(-1), 6)}), kernel)


_phi("rff_features", "gaussian")
_phi("rff_features_softmax", "softmax")


def _totals(df: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Sums of the features, plain and weighted by the cosine of the place: DIMS numbers each, added where they lie first."""
    rows = _features(df, "f int, total double, weighted double", lambda i, p: pd.DataFrame({"f": np.arange(DIMS), "total": p.sum(0), "weighted": (p * np.cos(i)[:, None]).sum(0)}))
    got = rows.groupBy("f").agg(F.sum("total").alias("total"), F.sum("weighted").alias("weighted")).orderBy("f").collect()
    return np.array([r["total"] for r in got] or [0.0] * DIMS), np.array([r["weighted"] for r in got] or [0.0] * DIMS)


def _product(name: str, schema: str, make: Callable) -> None:
    """Register rows from products of the implicit operator; make: places, products with ones and with the cosines."""

    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = vectors(spark, sf_dir)
        total, weighted = _totals(df)
        return _features(df, schema, lambda i, p: make(i, p @ total, p @ weighted))

    build.__name__, build.__doc__ = name, f"{name}: through the features, never through the kernel."
    implement(name)(build)


_product("row_sum_estimate", "i int, row_sum double", lambda i, s, a: pd.DataFrame({"i": i, "row_sum": np.round(s, 6)}))
_product("implicit_matvec", "i int, av double", lambda i, s, a: pd.DataFrame({"i": i, "av": np.round(a, 6)}))
_product("normalized_matvec", "i int, v double", lambda i, s, a: pd.DataFrame({"i": i[s > 1], "v": np.round(a[s > 1] / s[s > 1], 4)}))


@implement("row_sum_skew")
def row_sum_skew(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How uneven the row sums are."""
    df = vectors(spark, sf_dir)
    total, _ = _totals(df)
    sums = _features(df, "s double", lambda i, p: pd.DataFrame({"s": p @ total}))
    return sums.agg(*(F.round(x, 6).alias(n) for x, n in ((F.stddev_samp("s") / F.avg("s"), "variation"), (F.max("s") / F.avg("s"), "highest"), (F.min("s") / F.avg("s"), "lowest"))))


@implement("gram_matrix")
def gram_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Products of the features, added where the vectors lie first."""
    f, h = np.divmod(np.arange(DIMS * DIMS), DIMS)
    rows = _features(vectors(spark, sf_dir), "f int, h int, g double", lambda i, p: pd.DataFrame({"f": f, "h": h, "g": (p.T @ p).reshape(-1)}))
    return rows.groupBy("f", "h").agg(F.round(F.sum("g"), 6).alias("g"))


_GRID = [(float(n), float(d), e) for n in (64, 2048, 16384) for d in (128, 256, 512) for e in (0.1, 0.5, 1.0)]


@listed("rff_tail_bound", "n double, d double, e double, chance double, eps double")
def rff_tail_bound() -> list[tuple]:
    """Chance of an error, and the error of a chance."""
    return [(n, d, e, round(schedule.rff_tail(n, d, e), 6), round(schedule.rff_eps(n, d, 0.05), 6)) for n, d, e in _GRID]


@implement("matvec_bound")
def matvec_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of a product with the operator, for vectors as long as the table's longest."""
    longest = vectors(spark, sf_dir).select(F.max(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))))).first()[0] or 0.0
    rows = sorted({(n, d) for n, d, _ in _GRID})
    return spark.createDataFrame([(n, d, round(schedule.matvec_bound(n, longest, d, 0.05), 4)) for n, d in rows], "n double, d double, bound double")


# -- hashing ------------------------------------------------------------------------------------------------------


def _codes(spark: SparkSession, sf_dir: str, bits: int = 8) -> DataFrame:
    def run(batches: Rows) -> Rows:
        for batch in batches:
            if len(batch):
                yield pd.DataFrame({"i": batch["i"], "code": kernels.simhash(_array(batch), bits)})

    return vectors(spark, sf_dir).mapInPandas(run, "i int, code long")


@implement("simhash_raw")
def simhash_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Codes of the vectors' signs."""
    return _codes(spark, sf_dir)


@implement("hash_clusters")
def hash_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of equal codes."""
    return _codes(spark, sf_dir).groupBy("code").agg(F.min("i").alias("first_pos"), F.max("i").alias("last_pos"), F.count("*").alias("n_members"))


@implement("bucket_histogram")
def bucket_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of groups of equal codes."""
    return _codes(spark, sf_dir).groupBy("code").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("n"))


@implement("bucket_purity")
def bucket_purity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs within a code of 6 bits, and those of them with a product above 0.7: one matrix product for each code."""

    def run(bucket: pd.DataFrame) -> pd.DataFrame:
        x = _array(bucket)
        dots = (x @ x.T)[np.triu_indices(len(x), 1)]
        return pd.DataFrame({"pairs": [len(dots)], "pure": [int((dots > 0.7).sum())]})

    both = _codes(spark, sf_dir, 6).join(vectors(spark, sf_dir), "i")
    return both.groupBy("code").applyInPandas(run, "pairs long, pure long").agg(F.sum("pairs").alias("pairs"), F.sum("pure").alias("pure"))


def neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each vector with the next one."""
    e = vectors(spark, sf_dir)
    return e.join(e.select((F.col("i") - 1).alias("i"), F.col("embedding").alias("next")), "i")


def _law(name: str, schema: str, bits: tuple[int, ...]) -> None:
    @implement(name)
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Cosine of each vector to the next one, and the chance that all bits of their codes agree."""

        def run(batches: Rows) -> Rows:
            for batch in batches:
                if len(batch):
                    x, y = _array(batch), _array(batch, "next")
                    cosines = (x * y).sum(axis=1) / np.maximum(np.linalg.norm(x, axis=1) * np.linalg.norm(y, axis=1), 1e-300)
                    rows = [(i, round(c, 6), b, round(schedule.collision(c, b), 6)) for i, c in zip(batch["i"].tolist(), cosines.tolist(), strict=True) for b in bits]
                    yield pd.DataFrame(rows, columns=["i", "c", "b", "p"])[_names(schema)]

        return neighbours(spark, sf_dir).mapInPandas(run, schema)


_law("collision_law", "i int, c double, p double", (1,))
_law("collision_law_bits", "i int, c double, b int, p double", (1, 4, 8, 12))


@implement("collision_rate")
def collision_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of 400 one-bit hashes on which neighbours agree."""

    def run(batches: Rows) -> Rows:
        planes = rng.normals(0, "rate", 64, 400)
        for batch in batches:
            if len(batch):
                same = (_array(batch) @ planes >= 0) == (_array(batch, "next") @ planes >= 0)
                yield pd.DataFrame({"i": batch["i"], "rate": np.round(same.mean(axis=1), 6)})

    return neighbours(spark, sf_dir).mapInPandas(run, "i int, rate double")


# -- measures -----------------------------------------------------------------------------------------------------

_MEASURES = "i int, cosine double, top1 double, top10 double, label_accuracy double, kl double, delta_nll double, ppl_ratio double"


def measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All measures of each vector, times 8, as logits against the next one's."""

    def run(batches: Rows) -> Rows:
        for batch in batches:
            rows = []
            for i, a, b in zip(batch["i"].tolist(), batch["embedding"], batch["next"], strict=True):
                a, b = 8.0 * np.asarray(a, np.float64)[None], 8.0 * np.asarray(b, np.float64)[None]
                got = reader.compare(a, b, np.array([i % a.shape[1]]))
                rows.append((i, *(got[m] for m in _names(_MEASURES)[1:])))
            yield pd.DataFrame(rows, columns=_names(_MEASURES))

    return neighbours(spark, sf_dir).mapInPandas(run, _MEASURES)


def _measure(name: str, column: str) -> None:
    @implement(name)
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        """One measure of pairs of logit vectors."""
        return measured(spark, sf_dir).selectExpr("i", column)


_measure("kl_divergence", "round(kl, 6) AS kl")
_measure("logit_cosine", "round(cosine, 6) AS cosine")
_measure("delta_nll", "round(delta_nll, 6) AS delta")
_measure("topk_overlap", "cast(round(top10 * 10) AS bigint) AS shared")


@implement("ppl_ratio")
def ppl_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean ratio of perplexities, and the ratio of mean losses."""
    return measured(spark, sf_dir).agg(F.round(F.avg("ppl_ratio"), 6).alias("ppl_ratio"), F.round(F.exp(F.avg("delta_nll")), 6).alias("of_mean"))


@implement("top1_agreement")
def top1_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of pairs with one first choice."""
    return measured(spark, sf_dir).agg(F.round(F.avg("top1"), 6).alias("top1"))


@implement("label_accuracy")
def label_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of pairs whose second vector chooses the label."""
    return measured(spark, sf_dir).agg(F.round(F.avg("label_accuracy"), 6).alias("accuracy"))


# -- cost models --------------------------------------------------------------------------------------------------


@implement("op_cost_model")
def op_cost_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Operations of each prompt by settings: those of a token times its tokens."""
    grid = [(d, f, r, b, schedule.op_count("local", d, f, r, b), schedule.op_count("chunk", d)) for d in (64, 4096) for f in (128, 256, 512) for r in (4, 16, 32) for b in (8, 12)]
    each = spark.createDataFrame(grid, "d int, f int, r int, b int, spectral long, chunk long")
    rows = lengths(spark, sf_dir).filter("n > 0").crossJoin(F.broadcast(each))
    return rows.select("seq_id", "d", "f", "r", "b", (F.col("n") * F.col("spectral")).alias("spectral"), (F.col("n") * F.col("chunk")).alias("chunk"))


_PREFILL = "seq_id long, n long, rho int, share double"


@by_length("prefill_cost_model", _PREFILL)
def prefill_cost_model(seq: int, n: int) -> pd.DataFrame:
    """Share of the reader's work on each prompt that is left at each ratio."""
    return _frame(_PREFILL, seq, n, RHOS, [round(schedule.prefill_cost(schedule.target_length(n, r)) / schedule.prefill_cost(n), 6) for r in RHOS])
