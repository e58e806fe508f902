"""What a compression costs and loses, measured prompt by prompt in one pass over all configurations."""

from __future__ import annotations

import resource
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from tokenfold.functions import kernels, reader as readers
from tokenfold.operators.evaluation import MEASURES
from tokenfold.options import CompressOptions

Configs = list[tuple[str, CompressOptions]]
COSTS = ("preprocess_s", "prefill_s", "total_s", "reference_s", "peak_mb")
MEASURED = "seq_id long, backend string, rho double, n_tokens int, n_macro int, n_reference int, " + ", ".join(f"{m} double" for m in (*COSTS, *MEASURES))
SUMMARIES = "seq_id long, backend string, rho double, n_tokens int, n_macro int, n_windows int, n_spectral int, mean_score double, late_members int, distortion double"
CHECKED = "seq_id long, scheme string, backend string, rho double, n_tokens int, n_macro int, monotone boolean, cosine double, same_first boolean, same_text double, holds_answer boolean"


def _names(schema: str) -> list[str]:
    return [c.strip().split(" ")[0] for c in schema.split(", ")]


#: Prompts whose windows or continuations are taken at once.
TOGETHER = 32


def _per_prompt(df: DataFrame, e: np.ndarray, schema: str, make, *columns: str, together: int = 0) -> DataFrame:
    """Rows made from each prompt; make gets the row (together: lists of so many), the vocabularies by options, the table and its mean norm."""
    sent = df.sparkSession.sparkContext.broadcast(e)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        table, words = sent.value, {}
        norm = float(np.linalg.norm(table, axis=1).mean()) if len(table) else 1.0

        def vocabulary(opts: CompressOptions) -> kernels.Vocabulary:
            return words.setdefault((opts.anisotropy, opts.subword), kernels.Vocabulary(table, opts.anisotropy, opts.subword))

        for batch in batches:
            prompts = [r for r in batch.itertuples(index=False) if r.tokens is not None and len(r.tokens)]
            if together:
                prompts = [prompts[i : i + together] for i in range(0, len(prompts), together)]
            rows = [row for r in prompts for row in make(r, vocabulary, table, norm)]
            yield pd.DataFrame(rows, columns=_names(schema))

    return df.select("seq_id", "tokens", *columns).mapInPandas(run, schema)


def measure(df: DataFrame, e: np.ndarray, configs: Configs, reader: readers.Reader, window: int = 8192) -> DataFrame:
    """Cost and quality of each configuration for each prompt (seq_id, tokens, continuation).

    preprocess_s is the compression, prefill_s one masked pass of the reader over what is
    left, total_s both; reference_s is that pass over the prompt itself, cut at the reader's
    window. Quality compares with the prompt so cut. peak_mb is the worker's largest
    memory so far. Prompts without a continuation have null measures.
    """

    def make(r, vocabulary, table, norm):
        full, cut = None, len(r.tokens[:window])
        for name, opts in configs:
            v = vocabulary(opts)
            x, after = v(list(r.tokens)), v(list(r.continuation)) if len(r.continuation) else None
            start = time.perf_counter()
            m = kernels.compress(x, opts, norm)
            pre = time.perf_counter() - start
            start = time.perf_counter()
            readers.prefill(m.x, m.pos, reader.beta)
            fill = time.perf_counter() - start
            if full is None:
                start = time.perf_counter()
                readers.prefill(x[:cut], np.arange(cut), reader.beta)
                full = time.perf_counter() - start, None if after is None else readers.logits(reader, table, v.u, x[:cut], np.arange(cut), after)
            got = {}
            if after is not None:
                b = readers.logits(reader, table, v.u, m.x, m.pos, after)
                got = readers.compare(full[1], b, np.array([v.id(t) for t in r.continuation]))
            peak = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024
            yield (r.seq_id, name, float(opts.rho), len(x), len(m.pos), cut, pre, fill, pre + fill, full[0], peak, *(got.get(k) for k in MEASURES))

    return _per_prompt(df, e, MEASURED, make, "continuation")


def summaries(df: DataFrame, e: np.ndarray, configs: Configs) -> DataFrame:
    """Lengths, routes, late members and distortion of each configuration for each prompt."""

    hashed = next((o for _, o in configs if o.backend == "local" and 1 < o.rho <= o.window), None)

    def make_all(prompts, vocabulary, table, norm):
        shared: list[dict] = [{} for _ in prompts]
        if hashed is not None:
            v, bodies, own = vocabulary(hashed), [], []
            for r, kept in zip(prompts, shared, strict=True):
                a, b = hashed.prefix, len(r.tokens) - hashed.suffix
                if b > a:
                    kept["features"] = v.features(list(r.tokens), hashed)
                    bodies.append(kept["features"][a:b])
                    own.append(kept.setdefault((v.a, v.subword), {}).setdefault((a, b), {}))
            kernels.share_coordinates(bodies, own, hashed)
        for r, kept in zip(prompts, shared, strict=True):
            yield from make(r, kept, vocabulary, norm)

    def make(r, kept, vocabulary, norm):
        tokens, known, scores = list(r.tokens), {}, {}
        if "features" in kept:
            known[(hashed.anisotropy, hashed.subword), hashed.rff_dim, hashed.seed, hashed.kernel] = kept.pop("features")
        for name, opts in configs:
            v = vocabulary(opts)
            word = v.a, v.subword
            if word not in known:
                known[word] = v(tokens)
            x = known[word]
            way = word, opts.rff_dim, opts.seed, opts.kernel
            phi = v.features(tokens, opts) if known.get(way) is None else known[way]
            known[way] = phi
            m = kernels.compress(x, opts, norm, phi, kept.setdefault(word, {}))
            group = np.empty(len(x), np.int64)
            if len(x):
                group[np.concatenate(m.members)] = np.repeat(np.arange(len(m.size)), m.size)
            whole = len(x) // opts.window * opts.window
            if (word, opts.window) not in scores:
                scores[word, opts.window] = kernels.redundancy(x[:whole].reshape(-1, opts.window, x.shape[1])).mean() if whole else 1.0
            score = scores[word, opts.window]
            routes = [s for s in m.routes if s not in (None, "kept")]  # a prompt that is all suffix has no window
            yield (r.seq_id, name, float(opts.rho), len(x), len(m.pos), len(routes), sum(s in ("spectral", "raw") for s in routes), float(score), int((m.last > m.pos).sum()), float(((x - m.x[group]) ** 2).sum()))

    return _per_prompt(df, e, SUMMARIES, make_all, together=TOGETHER)


def checks(df: DataFrame, e: np.ndarray, configs: Configs, reader: readers.Reader, steps: int = 16) -> DataFrame:
    """The short-prompt checks: order of positions, direction of the next logits, and greedy continuations.

    same_text is the share of greedy tokens that equal the prompt's own, place by place;
    holds_answer whether the answer's first token is among them. Prompts (seq_id, tokens,
    continuation) without an answer give no row.
    """

    def make_all(prompts, vocabulary, table, norm):
        done, asked = [], {}
        for r in prompts:
            if not len(r.continuation):
                continue
            kept, own = {}, {}
            for name, opts in configs:
                v = vocabulary(opts)
                word = v.a, v.subword
                contexts = asked.setdefault(word, (v, []))[1]
                if word not in own:
                    x = v(list(r.tokens))
                    own[word] = x, len(contexts)
                    contexts.append((x, np.arange(len(x))))
                x, full = own[word]
                m = kernels.compress(x, opts, norm, kept=kept.setdefault(word, {}))
                at = full
                if m.x is not x:  # else the prompt itself, which is continued once
                    at = len(contexts)
                    contexts.append((m.x, m.pos))
                done.append((r, name, opts, word, full, at, len(x), len(m.pos), bool((np.diff(m.pos) >= 0).all())))
        said, products = {}, {}
        for word, (v, contexts) in asked.items():
            said[word] = readers.continued(reader, table, v, contexts, steps)
            products[word] = readers.products(reader, table, v.u)
        for r, name, opts, word, full, at, n, m, rises in done:
            (a, mine), (b, other), g = said[word][full], said[word][at], products[word]
            cosine = float(a @ g @ b / max(np.sqrt(max(a @ g @ a, 0.0) * max(b @ g @ b, 0.0)), 1e-12))
            same = float(np.mean([p == q for p, q in zip(mine, other, strict=True)]))
            yield (r.seq_id, name, opts.backend, float(opts.rho), n, m, rises, cosine, mine[0] == other[0], same, asked[word][0].id(r.continuation[0]) in other)

    return _per_prompt(df, e, CHECKED, make_all, "continuation", together=TOGETHER)
