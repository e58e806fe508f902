"""Compression of wide prompts: one row in, its macro-tokens out, with no shuffle.

Prompts carry token strings; vectors exist only inside the Arrow kernel, which looks
them up in the frozen table. The table is sent out after a check of its size, so what
moves is bounded by it and by the prompts' tokens.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import islice

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tokenfold.functions import kernels
from tokenfold.options import CompressOptions
from tokenfold.sources.tables import table

#: Bytes of a frozen table that may be sent to every executor.
MOST_TABLE_BYTES = 512 << 20
MACRO = "seq_id long, out_pos int, mpos int, n_members int, first_pos int, last_pos int, members array<int>, x array<float>"
SUMMARY = "seq_id long, n_tokens int, n_macro int, n_windows int, n_spectral int, mean_score double, late_members int, unordered int, distortion double"


def frozen_table(spark: SparkSession, sf_dir: str) -> np.ndarray:
    """The embedding table in the order of its ids. A table beyond the bound is refused, not cut."""
    df = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    rows, width = df.agg(F.count("*"), F.coalesce(F.max(F.size("embedding")), F.lit(0))).first()
    if rows * width * 8 > MOST_TABLE_BYTES:
        raise ValueError(f"the frozen table has {rows} x {width} numbers, more than {MOST_TABLE_BYTES} bytes; raise MOST_TABLE_BYTES or shard the vocabulary")
    column = df.orderBy("vec_id").select("embedding").toArrow().column(0).combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(rows, width)


#: Rows that a task holds at once; a row can carry a vector and its members.
MOST_ROWS = 4096


def framed(rows: Iterator[tuple], names: list[str]) -> Iterator[pd.DataFrame]:
    """All rows in frames of at most MOST_ROWS, made as they are taken."""
    while part := list(islice(rows, MOST_ROWS)):
        yield pd.DataFrame(part, columns=names)


def _with_vectors(df: DataFrame, e: np.ndarray, opts: CompressOptions, schema: str, make, extra: tuple[str, ...] = ()) -> DataFrame:
    sent = df.sparkSession.sparkContext.broadcast(e)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        vocabulary = kernels.Vocabulary(sent.value, opts.anisotropy, opts.subword)
        norm = float(np.linalg.norm(sent.value, axis=1).mean()) if len(sent.value) else 1.0
        names = [c.strip().split(" ")[0] for c in schema.split(", ")]
        for batch in batches:
            yield from framed((row for r in batch.itertuples(index=False) for row in make(r, vocabulary, norm)), names)

    return df.select("seq_id", "tokens", *extra).mapInPandas(run, schema)


def compress(df: DataFrame, e: np.ndarray, opts: CompressOptions) -> DataFrame:
    """Macro-tokens of each prompt in causal order.

    Null or empty prompts give none. At a ratio of one or less the vectors and
    positions come back unchanged, as groups of one.
    """

    def make(r, vocabulary, norm):
        if r.tokens is None or not len(r.tokens):
            return
        tokens = list(r.tokens)
        m = kernels.compress(vocabulary(tokens), opts, norm, vocabulary.features(tokens, opts))
        for i in range(len(m.pos)):
            yield (r.seq_id, i, int(m.pos[i]), int(m.size[i]), int(m.first[i]), int(m.last[i]), m.members[i].tolist(), m.x[i].astype(np.float32))

    return _with_vectors(df, e, opts, MACRO, make)


def summarise(df: DataFrame, e: np.ndarray, opts: CompressOptions) -> DataFrame:
    """One row for each prompt: lengths, routes, order and distortion, without its vectors."""

    def make(r, vocabulary, norm):
        n = 0 if r.tokens is None else len(r.tokens)
        if not n:
            return
        tokens = list(r.tokens)
        x = vocabulary(tokens)
        m = kernels.compress(x, opts, norm, vocabulary.features(tokens, opts))
        group = np.empty(n, np.int64)
        for i, own in enumerate(m.members):
            group[own] = i
        apart = float(((x - m.x[group]) ** 2).sum())
        has = [s for s in m.routes if s is not None]
        scores = kernels.redundancy(x[: n // opts.window * opts.window].reshape(-1, opts.window, x.shape[1])) if n >= opts.window else np.zeros(1)
        yield (r.seq_id, n, len(m.pos), len(has), sum(s in ("spectral", "raw") for s in has), float(scores.mean()), int((m.last > m.pos).sum()), int((np.diff(m.pos) < 0).sum()), apart)

    return _with_vectors(df, e, opts, SUMMARY, make)
