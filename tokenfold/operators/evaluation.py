"""Teacher-forced evaluation: original and compressed contexts predict one continuation."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from tokenfold.functions import kernels, reader as readers
from tokenfold.options import CompressOptions

MEASURES = ("cosine", "top1", "top10", "label_accuracy", "kl", "delta_nll", "ppl_ratio")
QUALITY = "seq_id long, reader string, backend string, rho double, n_tokens int, n_macro int, " + ", ".join(f"{m} double" for m in MEASURES)


def evaluate(df: DataFrame, e: np.ndarray, configs: list[tuple[str, CompressOptions]], named: dict[str, readers.Reader], label=None) -> DataFrame:
    """Quality of each configuration for each prompt (seq_id, tokens, continuation) and reader.

    configs: a name with options; a prompt without a continuation is left out.
    """
    sent = df.sparkSession.sparkContext.broadcast(e)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        table = sent.value
        norm = float(np.linalg.norm(table, axis=1).mean()) if len(table) else 1.0
        words: dict = {}
        for batch in batches:
            rows = []
            for r in batch.itertuples(index=False):
                if r.tokens is None or not len(r.tokens) or not len(r.continuation):
                    continue
                full, kept = {}, {}
                for name, opts in configs:
                    v = words.setdefault((opts.anisotropy, opts.subword), kernels.Vocabulary(table, opts.anisotropy, opts.subword))
                    x, after = v(list(r.tokens)), v(list(r.continuation))
                    target = np.array([v.id(t) for t in r.continuation])
                    m = kernels.compress(x, opts, norm, kept=kept.setdefault((v.a, v.subword), {}))
                    for key, model in named.items():
                        if (key, v.a, v.subword) not in full:
                            own = readers.reading(readers.logits(model, table, v.u, x, np.arange(len(x)), after))
                            full[key, v.a, v.subword] = own, readers.shares(own)
                        b = readers.logits(model, table, v.u, m.x, m.pos, after)
                        own, p = full[key, v.a, v.subword]
                        got = readers.compare(own, b, target, p=p)
                        rows.append((r.seq_id, key, name, float(opts.rho), len(x), len(m.pos), *(got[k] for k in MEASURES)))
            yield pd.DataFrame(rows, columns=[c.strip().split(" ")[0] for c in QUALITY.split(", ")])

    return df.select("seq_id", "tokens", "continuation").mapInPandas(run, QUALITY)


def grid(backends: tuple[str, ...] = ("chunk", "local", "adaptive"), rhos: tuple[float, ...] = (2, 4, 8, 16), base: CompressOptions = CompressOptions(), wide_at_two: bool = False) -> list[tuple[str, CompressOptions]]:
    """Backends by ratios; wide_at_two: windows of 32 at a ratio of 2, as for the small models."""
    return [(b, replace(base, backend=b, rho=r, window=32 if wide_at_two and r == 2 else base.window)) for b in backends for r in rhos]
