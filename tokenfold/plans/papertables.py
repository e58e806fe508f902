"""Analyses of backends by model and ratio, measured on the windows of a given table.

Every window of 16 neighbouring vectors of embeddings is averaged in groups of `rho`: as
they stand (chunk), in the order of their raw codes (raw_lsh), or by the route of the
window's score (adaptive). A vector's loss is one less its cosine to the mean of its
group, its label stands for the model, and work is counted in operations: a product per
hash bit, one pass for a mean or a score, and the reader's prefill of the groups.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tokenfold.functions import kernels, schedule
from tokenfold.functions.schedule import tau_sql
from tokenfold.plans.native import BLOCK, RHOS, _array, _windows
from tokenfold.plans.sqlviews import both, view
from tokenfold.plans.stages import _SCORE, _WINDOW, _code
from tokenfold.sources.tables import table

BACKENDS = ("none", "chunk", "raw_lsh", "adaptive")
BITS, WINDOW = 8, 16
_MEASURED = "model int, backend string, rho int, n long, loss double, likelihood double, ops long, prefill long"


def _measure(block: pd.DataFrame) -> pd.DataFrame:
    """Sums over whole windows by model, backend and ratio."""
    block = block.sort_values("i")
    i, raw, label = block["i"].to_numpy(), _array(block), block["label"].to_numpy()
    x = np.sqrt(0.75) * raw + 0.5 / 8
    own, score, size = _windows(i, raw)
    w = np.searchsorted(own, i // WINDOW)
    place = i % WINDOW
    order, hashed = np.lexsort((i, kernels.simhash(raw, BITS), w)), np.empty(len(i), np.int64)
    hashed[order] = np.arange(len(i)) - np.repeat(np.cumsum(size) - size, size)
    norms, first = np.sqrt((x * x).sum(axis=1)), np.diff(w, prepend=-1) > 0
    models, model = np.unique(label, return_inverse=True)
    d, out = x.shape[1], []

    def losses(key: np.ndarray) -> np.ndarray:
        _, group, n = np.unique(w * WINDOW + key, return_inverse=True, return_counts=True)
        mean = np.zeros((len(n), d))
        np.add.at(mean, group, x)
        mean = (mean / n[:, None])[group]
        return 1 - (x * mean).sum(axis=1) / np.maximum(norms * np.sqrt((mean * mean).sum(axis=1)), 1e-300)

    for rho in (1, *RHOS):
        made = {"none": (np.zeros(len(i)), np.zeros(len(i), np.int64))}
        if rho > 1:
            chunk, raw_lsh = losses(place // rho), losses(hashed // rho)
            routed = ((size > 4) & (score >= schedule.tau(rho)))[w]
            made = {"chunk": (chunk, np.full(len(i), d)), "raw_lsh": (raw_lsh, np.full(len(i), d * BITS)), "adaptive": (np.where(routed, raw_lsh, chunk), np.where(routed, d + d * BITS, d + d))}
        left = -(-size // rho)
        prefill = np.where(first, (64 * left * left + 4096 * left)[w], 0)
        for backend, (loss, ops) in made.items():
            sums = [np.bincount(model, weights=v, minlength=len(models)) for v in (np.ones(len(i)), loss, np.exp(loss), ops, prefill)]
            out.append(pd.DataFrame({"model": models, "backend": backend, "rho": rho, "n": sums[0].astype(np.int64), "loss": sums[1], "likelihood": sums[2], "ops": sums[3].astype(np.int64), "prefill": sums[4].astype(np.int64)}))
    return pd.concat(out)


def measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sums over all vectors by model, backend and ratio: n, loss, likelihood (of exp(loss)), ops and prefill."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("int").alias("i"), "embedding", F.col("label").cast("int").alias("label"))
    parts = e.groupBy(F.floor(F.col("i") / BLOCK)).applyInPandas(_measure, _MEASURED)
    return parts.groupBy("model", "backend", "rho").agg(*(F.sum(c).alias(c) for c in ("n", "loss", "likelihood", "ops", "prefill")))


_RHO = " UNION ALL ".join(f"SELECT {r} AS rho" for r in (1, *RHOS))
_KIND = " UNION ALL ".join(f"SELECT '{b}' AS backend" for b in BACKENDS)
_MEASURED_SQL = f"""win AS MATERIALIZED ({_WINDOW}),
ranked AS MATERIALIZED (SELECT i, CAST(floor(i / 16.0) AS INTEGER) AS w, i % 16 AS place, row_number() OVER (PARTITION BY CAST(floor(i / 16.0) AS INTEGER) ORDER BY code, i) - 1 AS hashed FROM ({_code("duckdb", BITS)}) c),
routed AS MATERIALIZED (SELECT w, len, rho, len > 4 AND score >= {tau_sql("cast(rho AS DOUBLE)")} AS spectral FROM ({_SCORE}) s CROSS JOIN ({_RHO}) r),
keyed AS MATERIALIZED (
  SELECT r.i, r.w, t.len, t.rho, k.backend, CASE WHEN k.backend = 'raw_lsh' OR (k.backend = 'adaptive' AND t.spectral) THEN CAST(floor(r.hashed / t.rho) AS INTEGER) ELSE CAST(floor(r.place / t.rho) AS INTEGER) END AS key,
         CASE k.backend WHEN 'none' THEN 0 WHEN 'chunk' THEN 64 WHEN 'raw_lsh' THEN 64 * {BITS} ELSE 64 + CASE WHEN t.spectral THEN 64 * {BITS} ELSE 64 END END AS ops
  FROM ranked r JOIN routed t ON t.w = r.w JOIN ({_KIND}) k ON (k.backend = 'none') = (t.rho = 1)),
fused AS MATERIALIZED (SELECT k.w, k.rho, k.backend, k.key, v.j, avg(v.x) AS x FROM keyed k JOIN win v ON v.i = k.i WHERE k.rho > 1 GROUP BY k.w, k.rho, k.backend, k.key, v.j),
lost AS MATERIALIZED (
  SELECT k.i, k.rho, k.backend, 1 - sum(v.x * f.x) / greatest(sqrt(sum(v.x * v.x)) * sqrt(sum(f.x * f.x)), 1.0E-300) AS loss
  FROM keyed k JOIN win v ON v.i = k.i JOIN fused f ON f.w = k.w AND f.rho = k.rho AND f.backend = k.backend AND f.key = k.key AND f.j = v.j GROUP BY k.i, k.rho, k.backend
  UNION ALL SELECT i, rho, backend, 0.0E0 FROM keyed WHERE rho = 1),
measured AS MATERIALIZED (
  SELECT CAST(e.label AS INTEGER) AS model, k.backend, k.rho, count(*) AS n, sum(l.loss) AS loss, sum(exp(l.loss)) AS likelihood, CAST(sum(k.ops) AS BIGINT) AS ops,
         CAST(sum(CASE WHEN k.i = h.head THEN 64 * power(ceil(k.len / cast(k.rho AS DOUBLE)), 2) + 4096 * ceil(k.len / cast(k.rho AS DOUBLE)) ELSE 0 END) AS BIGINT) AS prefill
  FROM keyed k JOIN lost l ON l.i = k.i AND l.rho = k.rho AND l.backend = k.backend JOIN embeddings e ON e.vec_id = k.i JOIN (SELECT w, min(i) AS head FROM ranked GROUP BY w) h ON h.w = k.w
  GROUP BY e.label, k.backend, k.rho)"""
view("measured", measured, _MEASURED_SQL)

_Q = "(SELECT model, backend, rho, round(loss / n, 6) AS dnll, round(likelihood / n, 6) AS ppl FROM measured WHERE rho > 1)"
_T = "(SELECT backend, rho, CAST(sum(ops) + sum(prefill) AS BIGINT) AS total, round(sum(loss) / sum(n), 6) AS dnll FROM measured GROUP BY backend, rho)"
_BEST = f"SELECT model, rho, max(CASE WHEN backend = 'chunk' THEN ppl END) AS chunk, min(CASE WHEN backend <> 'chunk' THEN ppl END) AS spectral FROM {_Q} q GROUP BY model, rho"
_OVER = "embeddings vec measured"

both("paper_ppl_gap", f"SELECT CASE WHEN rho <= 4 THEN 'low' ELSE 'high' END AS band, round(avg(chunk - spectral), 4) AS gap FROM ({_BEST}) b GROUP BY 1", _OVER)
both("paper_transition", f"""
SELECT model, rho, CASE WHEN spectral < chunk THEN 'spectral' ELSE 'chunk' END AS winner, round(chunk - spectral, 3) AS gap,
       CAST(min(CASE WHEN spectral < chunk THEN rho END) OVER (PARTITION BY model) AS INTEGER) AS first_spectral FROM ({_BEST}) b""", _OVER)
both("paper_jensen", f"SELECT model, backend, rho, round(ppl - exp(dnll), 3) AS above, ppl + 0.0006 + 0.0006 * exp(dnll) >= exp(dnll) AS holds FROM {_Q} q", _OVER)
both("paper_pareto", f"""
SELECT a.backend, a.rho, a.total, a.dnll, CASE WHEN a.backend = 'none' THEN 'reference' WHEN count(b.total) > 0 THEN 'dominated' ELSE 'frontier' END AS status
FROM {_T} a LEFT JOIN {_T} b ON b.total <= a.total AND b.dnll <= a.dnll AND (b.total < a.total OR b.dnll < a.dnll)
GROUP BY a.backend, a.rho, a.total, a.dnll""", _OVER)
both("paper_routing_savings", "SELECT a.model, a.rho, round(1 - a.ops / cast(l.ops AS DOUBLE), 4) AS saved FROM measured a JOIN measured l ON l.model = a.model AND l.rho = a.rho WHERE a.backend = 'adaptive' AND l.backend = 'raw_lsh'", _OVER)
both("paper_best_backend", f"SELECT model, rho, backend, ppl FROM (SELECT model, rho, backend, ppl, row_number() OVER (PARTITION BY model, rho ORDER BY ppl, backend) AS place FROM {_Q} q) r WHERE place = 1", _OVER)
