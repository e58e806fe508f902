"""Pipeline stages, kernels, hashing and measures as declarative queries."""

from __future__ import annotations

from tokenfold.functions.rng import normal_sql, uniform_sql
from tokenfold.functions.schedule import collision_sql, tau_sql
from tokenfold.plans.sqlviews import both

SUFFIX, RHOS = 12, (2, 4, 8, 16)

# -- tokens, regions, windows, budgets ----------------------------------------------------------------------------

both("tokenize_documents", "SELECT seq_id, pos, token FROM tok", "documents embeddings tok")
both("embed_tokens", """
SELECT t.seq_id, t.pos, t.tok_id, v.total, v.norm
FROM tok t JOIN (SELECT i, round(sum(x), 6) AS total, round(sqrt(sum(x * x)), 6) AS norm FROM vec GROUP BY i) v ON v.i = t.tok_id""", "documents embeddings tok vec")
both("mark_regions", f"""
SELECT seq_id, pos, CASE WHEN pos >= n - {SUFFIX} THEN 'suffix' ELSE 'body' END AS region FROM tok""", "documents embeddings tok")
both("split_windows", f"""
SELECT seq_id, CAST(floor(pos / 16.0) AS INTEGER) AS win_id, CAST(min(pos) AS INTEGER) AS first_pos, count(*) AS n_tokens
FROM tok WHERE pos < n - {SUFFIX} GROUP BY seq_id, CAST(floor(pos / 16.0) AS INTEGER)""", "documents embeddings tok")
_LENGTHS = "SELECT seq_id, count(*) AS n FROM tok GROUP BY seq_id"
_TARGETS = "SELECT 2 AS rho UNION ALL SELECT 4 UNION ALL SELECT 8 UNION ALL SELECT 16"
both("target_length", f"""
SELECT seq_id, rho, n, CAST(CASE WHEN n <= {SUFFIX} THEN n ELSE {SUFFIX} + greatest(1, ceil((n - {SUFFIX}) / cast(rho AS DOUBLE))) END AS BIGINT) AS n_macro
FROM ({_LENGTHS}) l CROSS JOIN ({_TARGETS}) r""", "documents embeddings tok")
both("actual_ratio", f"""
SELECT rho, round(sum(n) / cast(sum(m) AS DOUBLE), 6) AS ratio, round(avg(n / cast(m AS DOUBLE)), 6) AS mean_ratio FROM (
  SELECT rho, n, CASE WHEN n <= {SUFFIX} THEN n ELSE {SUFFIX} + greatest(1, ceil((n - {SUFFIX}) / cast(rho AS DOUBLE))) END AS m
  FROM ({_LENGTHS}) l CROSS JOIN ({_TARGETS}) r) x GROUP BY rho""", "documents embeddings tok")
both("bits_for_target", f"""
SELECT seq_id, rho, CAST(greatest(1, ceil(log2(greatest(1, ceil(greatest(n - {SUFFIX}, 1) / cast(rho AS DOUBLE)))))) AS INTEGER) AS bits
FROM ({_LENGTHS}) l CROSS JOIN ({_TARGETS}) r""", "documents embeddings tok")
both("expected_bucket_size", f"""
SELECT seq_id, rho, round(n / pow(2, greatest(1, ceil(log2(greatest(1, ceil(greatest(n - {SUFFIX}, 1) / cast(rho AS DOUBLE))))))), 6) AS size
FROM ({_LENGTHS}) l CROSS JOIN ({_TARGETS}) r""", "documents embeddings tok")
for _rho in RHOS:
    both("window_budgets" if _rho == 4 else f"window_budgets_rho{_rho}", f"""
SELECT seq_id, win_id, len, CAST(floor(least(16 * (win_id + 1), nb) * m / nb) - floor(16 * win_id * m / nb) AS INTEGER) AS budget FROM (
  SELECT seq_id, CAST(floor(pos / 16.0) AS INTEGER) AS win_id, count(*) AS len, cast(max(n) - {SUFFIX} AS DOUBLE) AS nb, greatest(1, ceil((max(n) - {SUFFIX}) / {_rho}.0)) AS m
  FROM tok WHERE pos < n - {SUFFIX} GROUP BY seq_id, CAST(floor(pos / 16.0) AS INTEGER)) w""", "documents embeddings tok")

# -- chunking and macro-tokens ------------------------------------------------------------------------------------


def _groups(rho: int) -> str:
    return f"CASE WHEN pos >= n - {SUFFIX} THEN 1000000000 + pos ELSE CAST(floor(pos / {rho}.0) AS INTEGER) END"


def _macro(rho: int, position: str = "max(pos)") -> str:
    return f"""SELECT seq_id, {_groups(rho)} AS grp, CAST({position} AS INTEGER) AS mpos, count(*) AS n_members, CAST(min(pos) AS INTEGER) AS first_pos, CAST(max(pos) AS INTEGER) AS last_pos
FROM tok GROUP BY seq_id, {_groups(rho)}"""


for _rho in RHOS:
    both(f"chunk_rho{_rho}", f"SELECT seq_id, CAST(row_number() OVER (PARTITION BY seq_id ORDER BY mpos, first_pos) - 1 AS INTEGER) AS out_pos, mpos, n_members, first_pos, last_pos FROM ({_macro(_rho)}) m", "documents embeddings tok")
both("chunk_budgeted", f"""
SELECT seq_id, win_id, g, CAST(max(pos) AS INTEGER) AS mpos, count(*) AS n_members FROM (
  SELECT t.seq_id, t.pos, b.win_id, CAST(floor((t.pos - 16 * b.win_id) * b.budget / cast(b.len AS DOUBLE)) AS INTEGER) AS g
  FROM (SELECT seq_id, pos, CAST(floor(pos / 16.0) AS INTEGER) AS win_id FROM tok WHERE pos < n - {SUFFIX}) t JOIN (
    SELECT seq_id, win_id, len, floor(least(16 * (win_id + 1), nb) * m / nb) - floor(16 * win_id * m / nb) AS budget FROM (
      SELECT seq_id, CAST(floor(pos / 16.0) AS INTEGER) AS win_id, count(*) AS len, cast(max(n) - {SUFFIX} AS DOUBLE) AS nb, greatest(1, ceil((max(n) - {SUFFIX}) / 4.0)) AS m
      FROM tok WHERE pos < n - {SUFFIX} GROUP BY seq_id, CAST(floor(pos / 16.0) AS INTEGER)) w) b ON b.seq_id = t.seq_id AND b.win_id = t.win_id) x
GROUP BY seq_id, win_id, g""", "documents embeddings tok")
both("position_max", f"SELECT seq_id, grp, mpos FROM ({_macro(4)}) m", "documents embeddings tok")
both("position_mean", f"SELECT seq_id, grp, mpos FROM ({_macro(4, 'floor(avg(pos) + 0.5)')}) m", "documents embeddings tok")
_MEDIAN = f"""SELECT seq_id, {_groups(4)} AS grp, CAST(%s AS INTEGER) AS mpos FROM tok GROUP BY seq_id, {_groups(4)}"""
both("position_median", _MEDIAN % "quantile_disc(pos, 0.5)", "documents embeddings tok", _MEDIAN % "percentile_disc(0.5) WITHIN GROUP (ORDER BY pos)")
both("positions_representative", f"SELECT seq_id, mpos, first_pos FROM ({_macro(8)}) m", "documents embeddings tok")
both("positions_compact", f"SELECT seq_id, mpos, CAST(row_number() OVER (PARTITION BY seq_id ORDER BY mpos, first_pos) - 1 AS INTEGER) AS cpos FROM ({_macro(8)}) m", "documents embeddings tok")
both("macro_order", f"SELECT seq_id, grp, CAST(rank() OVER (PARTITION BY seq_id ORDER BY mpos, first_pos) AS INTEGER) AS place FROM ({_macro(2)}) m", "documents embeddings tok")
both("assemble_prompt", f"SELECT seq_id, count(*) AS n_macro, CAST(sum(CASE WHEN grp >= 1000000000 THEN 1 ELSE 0 END) AS BIGINT) AS kept, CAST(sum(n_members) AS BIGINT) AS n_tokens FROM ({_macro(4)}) m GROUP BY seq_id", "documents embeddings tok")
_SCHEMES = (("max", "max(pos)"), ("mean", "floor(avg(pos) + 0.5)"), ("median", "quantile_disc(pos, 0.5)"))
_UNORDERED = "CASE WHEN mpos < lag(mpos) OVER (PARTITION BY seq_id ORDER BY first_pos) THEN 1 ELSE 0 END"
both("causal_violations", "SELECT scheme, CAST(sum(late) AS BIGINT) AS late, CAST(sum(unordered) AS BIGINT) AS unordered FROM (" + " UNION ALL ".join(
    f"SELECT '{n}' AS scheme, CASE WHEN last_pos > mpos THEN 1 ELSE 0 END AS late, {_UNORDERED} AS unordered FROM ({_macro(4, p)}) m{i}" for i, (n, p) in enumerate(_SCHEMES)) + ") x GROUP BY scheme", "documents embeddings tok")
both("abl_position_scheme", "SELECT scheme, rho, CAST(sum(late) AS BIGINT) AS late, round(avg(late), 6) AS share FROM (" + " UNION ALL ".join(
    f"SELECT '{n}' AS scheme, {r} AS rho, CASE WHEN last_pos > mpos THEN 1 ELSE 0 END AS late FROM ({_macro(r, p)}) m{i}_{r}" for i, (n, p) in enumerate(_SCHEMES) for r in RHOS) + ") x GROUP BY scheme, rho", "documents embeddings tok")
both("position_gaps", f"""
SELECT gap, count(*) AS n FROM (SELECT mpos - lag(mpos) OVER (PARTITION BY seq_id ORDER BY mpos, first_pos) AS gap FROM ({_macro(8)}) m) g WHERE gap IS NOT NULL GROUP BY gap""", "documents embeddings tok")
both("identity_bypass", "SELECT seq_id, pos, pos AS mpos, tok_id FROM tok", "documents embeddings tok")
both("uncompressed_truncated", "SELECT seq_id, count(*) AS n_kept, CAST(max(pos) AS INTEGER) AS last_pos FROM tok WHERE pos < 8192 GROUP BY seq_id", "documents embeddings tok")
both("random_groups", f"""
SELECT seq_id, CAST(min(pos) AS INTEGER) AS first_pos, CAST(max(pos) AS INTEGER) AS last_pos, count(*) AS n_members FROM (
  SELECT seq_id, pos, CAST(floor((rank() OVER (PARTITION BY seq_id ORDER BY {uniform_sql(0, 'random', 'pos', '0', 'duckdb')}, pos) - 1) * greatest(1, ceil((n - {SUFFIX}) / 4.0)) / (n - {SUFFIX})) AS INTEGER) AS grp
  FROM tok WHERE pos < n - {SUFFIX}) g GROUP BY seq_id, grp""", "documents embeddings tok")
both("w_scaling_counts", "SELECT len AS n_context, len - 12 AS body, CAST(12 + ceil((len - 12) / 4.0) AS INTEGER) AS n_macro, least(len, 8192) AS n_reference FROM (SELECT 2884 AS len UNION ALL SELECT 5780 UNION ALL SELECT 11546 UNION ALL SELECT 23092) x", "embeddings")

# -- fused vectors over the frozen table taken as one sequence ----------------------------------------------------

_MEMBERS = "SELECT CAST(floor(i / 4.0) AS INTEGER) AS g, i, j, x FROM vec"
_MEAN = f"SELECT g, j, avg(x) AS x FROM ({_MEMBERS}) m GROUP BY g, j"
_NORMS = f"SELECT g, avg(norm) AS eta FROM (SELECT g, i, sqrt(sum(x * x)) AS norm FROM ({_MEMBERS}) m GROUP BY g, i) n GROUP BY g"
_HAVE = f"SELECT g, sqrt(sum(x * x)) AS have FROM ({_MEAN}) f GROUP BY g"
both("fuse_mean", f"SELECT g, j, round(x, 6) AS x FROM ({_MEAN}) f", "embeddings vec")
both("renorm_off", f"SELECT g, round(have, 6) AS norm FROM ({_HAVE}) h", "embeddings vec")
both("restore_norm", f"SELECT f.g, f.j, round(f.x * n.eta / h.have, 6) AS x FROM ({_MEAN}) f JOIN ({_NORMS}) n ON n.g = f.g JOIN ({_HAVE}) h ON h.g = f.g", "embeddings vec")
_TABLE = "SELECT avg(norm) AS eta FROM (SELECT i, sqrt(sum(x * x)) AS norm FROM vec GROUP BY i) t"
both("renorm_table", f"SELECT f.g, f.j, round(f.x * n.eta / h.have, 6) AS x FROM ({_MEAN}) f CROSS JOIN ({_TABLE}) n JOIN ({_HAVE}) h ON h.g = f.g", "embeddings vec")
both("renorm_prompt", f"SELECT h.g, round(h.have, 6) AS before, round(avg(n.eta) OVER (PARTITION BY 1), 6) AS after FROM ({_HAVE}) h JOIN ({_NORMS}) n ON n.g = h.g", "embeddings vec")
both("norm_collapse", f"SELECT h.g, round(h.have / n.eta, 6) AS collapse FROM ({_HAVE}) h JOIN ({_NORMS}) n ON n.g = h.g", "embeddings vec")
both("distortion", f"SELECT m.g, round(sum((m.x - f.x) * (m.x - f.x)), 6) AS distortion FROM ({_MEMBERS}) m JOIN ({_MEAN}) f ON f.g = m.g AND f.j = m.j GROUP BY m.g", "embeddings vec")
_WINDOW = "SELECT CAST(floor(i / 16.0) AS INTEGER) AS w, i, j, sqrt(0.75) * x + 0.5 / 8 AS x FROM vec"
_SCORE = f"""SELECT c.w, avg(c.cosine) AS score, count(*) AS len FROM (
  SELECT m.w, m.i, sum(m.x * f.x) / (sqrt(sum(m.x * m.x)) * sqrt(sum(f.x * f.x))) AS cosine
  FROM ({_WINDOW}) m JOIN (SELECT w, j, avg(x) AS x FROM ({_WINDOW}) q GROUP BY w, j) f ON f.w = m.w AND f.j = m.j GROUP BY m.w, m.i) c GROUP BY c.w"""
both("redundancy_score", f"SELECT w, round(score, 6) AS score, len FROM ({_SCORE}) s", "embeddings vec")
_RHO_TAU = " UNION ALL ".join(f"SELECT {r}.0 AS rho" for r in (2, 4, 6, 8, 12, 16))
both("route_windows", f"SELECT w, rho, CASE WHEN len <= 4 OR score < {tau_sql('cast(rho AS DOUBLE)')} THEN 'chunk' ELSE 'spectral' END AS route FROM ({_SCORE}) s CROSS JOIN (SELECT cast(rho AS DOUBLE) AS rho FROM ({_RHO_TAU}) q) r", "embeddings vec")
both("route_constant_tau", f"SELECT CASE WHEN len <= 4 OR score < 0.70 THEN 'chunk' ELSE 'spectral' END AS route, count(*) AS n FROM ({_SCORE}) s GROUP BY 1", "embeddings vec")
both("tau_schedule", f"SELECT cast(rho AS DOUBLE) AS rho, round({tau_sql('cast(rho AS DOUBLE)')}, 6) AS linear, round({tau_sql('cast(rho AS DOUBLE)', 'log2')}, 6) AS log_form FROM ({_RHO_TAU}) r", "embeddings")

# -- kernels ------------------------------------------------------------------------------------------------------

_PAIRS = "SELECT a.i, b.i AS k, sum(a.x * b.x) AS dot, sum((a.x - b.x) * (a.x - b.x)) AS gap FROM vec a JOIN vec b ON a.j = b.j GROUP BY a.i, b.i"
both("exact_kernel", f"SELECT i, k, round(exp(dot / 8), 6) AS kernel FROM ({_PAIRS}) p", "embeddings vec")
both("exact_gaussian_kernel", f"SELECT i, k, round(exp(-gap / 16), 6) AS kernel FROM ({_PAIRS}) p", "embeddings vec")
both("exact_attention_rows", f"SELECT i, k, round(exp(dot / 8) / sum(exp(dot / 8)) OVER (PARTITION BY i), 6) AS weight FROM ({_PAIRS}) p", "embeddings vec")


def _phi(engine: str, dims: int = 32) -> str:
    """Features of the frozen table with parameters from counters: i, f, phi."""
    number = "explode(sequence(0, {n}))" if engine == "spark" else "unnest(range(0, {n} + 1))"
    d = f"SELECT {number.format(n=63)} AS j"
    f = f"SELECT {number.format(n=dims - 1)} AS f"
    omega = f"SELECT j, f, {normal_sql(0, 'omega', 'j', 'f', engine)} / sqrt(8.0) AS w FROM ({d}) d CROSS JOIN ({f}) e"
    phase = f"SELECT f, 2 * pi() * {uniform_sql(0, 'phase', '0', 'f', engine)} AS b FROM ({f}) e"
    return f"SELECT v.i, o.f, sqrt(2.0 / {dims}) * cos(sum(v.x * o.w) + max(p.b)) AS phi, sum(v.x * v.x) AS sq FROM vec v JOIN ({omega}) o ON o.j = v.j JOIN ({phase}) p ON p.f = o.f GROUP BY v.i, o.f"


def _features(name: str, text: str) -> None:
    """text: a query over {phi}."""
    both(name, text.format(phi=_phi("duckdb")), "embeddings vec", text.format(phi=_phi("spark")))


_params = "SELECT CAST(j AS BIGINT) AS j, f, round({n}, 6) AS omega, round({u}, 6) AS phase FROM (SELECT DISTINCT j FROM vec) a CROSS JOIN (SELECT {f} AS f) b"
both(
    "rff_params",
    _params.format(n=normal_sql(0, "omega", "j", "f", "duckdb"), u=uniform_sql(0, "phase", "0", "f", "duckdb"), f="unnest(range(0, 64))"),
    "embeddings vec",
    _params.format(n=normal_sql(0, "omega", "j", "f"), u=uniform_sql(0, "phase", "0", "f"), f="explode(sequence(0L, 63L))"),
)
both("start_vector", f"SELECT i, round({normal_sql(0, 'token', 'i', '0', 'duckdb')}, 6) AS v FROM (SELECT DISTINCT i FROM vec) t", "embeddings vec", f"SELECT i, round({normal_sql(0, 'token', 'i', '0')}, 6) AS v FROM (SELECT DISTINCT i FROM vec) t")
_features("rff_features", "SELECT i, CAST(f AS INTEGER) AS f, round(phi, 6) AS phi FROM ({phi}) p")
_features("rff_features_softmax", "SELECT i, CAST(f AS INTEGER) AS f, round(phi * exp(sq / 16), 6) AS phi FROM ({phi}) p")
_features("row_sum_estimate", "SELECT p.i, round(sum(p.phi * t.total), 6) AS row_sum FROM ({phi}) p JOIN (SELECT f, sum(phi) AS total FROM ({phi}) q GROUP BY f) t ON t.f = p.f GROUP BY p.i")
_features("implicit_matvec", "SELECT p.i, round(sum(p.phi * t.total), 6) AS av FROM ({phi}) p JOIN (SELECT f, sum(phi * cos(i)) AS total FROM ({phi}) q GROUP BY f) t ON t.f = p.f GROUP BY p.i")
_features("normalized_matvec", "SELECT i, round(av / row_sum, 4) AS v FROM (SELECT p.i, sum(p.phi * t.total) AS row_sum, sum(p.phi * t.weighted) AS av FROM ({phi}) p JOIN (SELECT f, sum(phi) AS total, sum(phi * cos(i)) AS weighted FROM ({phi}) q GROUP BY f) t ON t.f = p.f GROUP BY p.i) x WHERE row_sum > 1")
_features("row_sum_skew", "SELECT round(stddev_samp(s) / avg(s), 6) AS variation, round(max(s) / avg(s), 6) AS highest, round(min(s) / avg(s), 6) AS lowest FROM (SELECT p.i, sum(p.phi * t.total) AS s FROM ({phi}) p JOIN (SELECT f, sum(phi) AS total FROM ({phi}) q GROUP BY f) t ON t.f = p.f GROUP BY p.i) x")
_features("gram_matrix", "SELECT CAST(a.f AS INTEGER) AS f, CAST(b.f AS INTEGER) AS h, round(sum(a.phi * b.phi), 6) AS g FROM ({phi}) a JOIN ({phi}) b ON a.i = b.i GROUP BY a.f, b.f")
_GRID = "SELECT cast(n AS DOUBLE) AS n, cast(d AS DOUBLE) AS d, cast(e AS DOUBLE) AS e FROM (SELECT 64 AS n UNION ALL SELECT 2048 UNION ALL SELECT 16384) a CROSS JOIN (SELECT 128 AS d UNION ALL SELECT 256 UNION ALL SELECT 512) b CROSS JOIN (SELECT 0.1 AS e UNION ALL SELECT 0.5 UNION ALL SELECT 1.0) c"
both("rff_tail_bound", f"SELECT n, d, e, round(least(1.0, 2 * n * n * exp(-d * e * e / 8)), 6) AS chance, round(sqrt(8 / d * ln(2 * n * n / 0.05)), 6) AS eps FROM ({_GRID}) g", "embeddings")
both("matvec_bound", f"SELECT n, d, round(2 * n * c * sqrt(2 / d * ln(2 * n / 0.05)), 4) AS bound FROM (SELECT DISTINCT n, d FROM ({_GRID}) g) h CROSS JOIN (SELECT max(norm) AS c FROM (SELECT i, sqrt(sum(x * x)) AS norm FROM vec GROUP BY i) q) m", "embeddings vec")

# -- hashing ------------------------------------------------------------------------------------------------------


def _code(engine: str, bits: int) -> str:
    """Codes of the raw vectors: i, code."""
    number = "explode(sequence(0, {n}))" if engine == "spark" else "unnest(range(0, {n} + 1))"
    plane = f"SELECT j, h, {normal_sql(0, 'plane', 'j', 'h', engine)} AS r FROM (SELECT {number.format(n=63)} AS j) a CROSS JOIN (SELECT {number.format(n=bits - 1)} AS h) b"
    return f"SELECT i, CAST(sum(CASE WHEN s >= 0 THEN pow(2, h) ELSE 0 END) AS BIGINT) AS code FROM (SELECT v.i, p.h, sum(v.x * p.r) AS s FROM vec v JOIN ({plane}) p ON p.j = v.j GROUP BY v.i, p.h) q GROUP BY i"


def _hashed(name: str, text: str, bits: int = 8) -> None:
    both(name, text.format(code=_code("duckdb", bits)), "embeddings vec", text.format(code=_code("spark", bits)))


_hashed("simhash_raw", "SELECT i, code FROM ({code}) c")
_hashed("hash_clusters", "SELECT code, CAST(min(i) AS INTEGER) AS first_pos, CAST(max(i) AS INTEGER) AS last_pos, count(*) AS n_members FROM ({code}) c GROUP BY code")
_hashed("bucket_histogram", "SELECT size, count(*) AS n FROM (SELECT code, count(*) AS size FROM ({code}) c GROUP BY code) b GROUP BY size")
_hashed("bucket_purity", """SELECT count(*) AS pairs, CAST(sum(CASE WHEN dot > 0.7 THEN 1 ELSE 0 END) AS BIGINT) AS pure FROM (
  SELECT a.i, b.i AS k, sum(x.x * y.x) AS dot FROM ({code}) a JOIN ({code}) b ON a.code = b.code AND a.i < b.i JOIN vec x ON x.i = a.i JOIN vec y ON y.i = b.i AND y.j = x.j GROUP BY a.i, b.i) p""", 6)
_COSINE = "SELECT a.i, sum(a.x * b.x) / greatest(sqrt(sum(a.x * a.x)) * sqrt(sum(b.x * b.x)), 1.0E-300) AS c FROM vec a JOIN vec b ON b.i = a.i + 1 AND b.j = a.j GROUP BY a.i"
both("collision_law", f"SELECT i, round(c, 6) AS c, round({collision_sql('c', '1')}, 6) AS p FROM ({_COSINE}) x", "embeddings vec")
both("collision_law_bits", f"SELECT i, round(c, 6) AS c, b, round({collision_sql('c', 'b')}, 6) AS p FROM ({_COSINE}) x CROSS JOIN (SELECT 1 AS b UNION ALL SELECT 4 UNION ALL SELECT 8 UNION ALL SELECT 12) y", "embeddings vec")



def _rate(engine: str) -> str:
    """Share of 400 one-bit hashes on which neighbours of the table agree, beside the law."""
    number = "explode(sequence(0, {n}))" if engine == "spark" else "unnest(range(0, {n} + 1))"
    plane = f"SELECT j, h, {normal_sql(0, 'rate', 'j', 'h', engine)} AS r FROM (SELECT {number.format(n=63)} AS j) a CROSS JOIN (SELECT {number.format(n=399)} AS h) b"
    sign = f"SELECT v.i, p.h, CASE WHEN sum(v.x * p.r) >= 0 THEN 1 ELSE 0 END AS s FROM vec v JOIN ({plane}) p ON p.j = v.j GROUP BY v.i, p.h"
    return f"SELECT a.i, round(avg(CASE WHEN a.s = b.s THEN 1.0E0 ELSE 0.0E0 END), 6) AS rate FROM ({sign}) a JOIN ({sign}) b ON b.i = a.i + 1 AND b.h = a.h GROUP BY a.i"


both("collision_rate", _rate("duckdb"), "embeddings vec", _rate("spark"))

# -- measures on pairs of logit vectors: neighbours of the frozen table -------------------------------------------

_PAIR = "SELECT a.i, a.j, a.x * 8 AS p, b.x * 8 AS q FROM vec a JOIN vec b ON b.i = a.i + 1 AND b.j = a.j"
_SOFT = f"SELECT i, j, p - ln(sum(exp(p)) OVER (PARTITION BY i)) AS lp, q - ln(sum(exp(q)) OVER (PARTITION BY i)) AS lq FROM ({_PAIR}) x"
both("kl_divergence", f"SELECT i, round(sum(exp(lp) * (lp - lq)), 6) AS kl FROM ({_SOFT}) s GROUP BY i", "embeddings vec")
both("logit_cosine", f"SELECT i, round(sum(p * q) / (sqrt(sum(p * p)) * sqrt(sum(q * q))), 6) AS cosine FROM ({_PAIR}) s GROUP BY i", "embeddings vec")
both("delta_nll", f"SELECT i, round(lp - lq, 6) AS delta FROM ({_SOFT}) s WHERE j = i % 64", "embeddings vec")
both("ppl_ratio", f"SELECT round(avg(exp(d)), 6) AS ppl_ratio, round(exp(avg(d)), 6) AS of_mean FROM (SELECT i, lp - lq AS d FROM ({_SOFT}) s WHERE j = i % 64) x", "embeddings vec")
_TOP = f"SELECT i, j, rank() OVER (PARTITION BY i ORDER BY p DESC, j) AS rp, rank() OVER (PARTITION BY i ORDER BY q DESC, j) AS rq FROM ({_PAIR}) x"
both("topk_overlap", f"SELECT i, CAST(sum(CASE WHEN rp <= 10 AND rq <= 10 THEN 1 ELSE 0 END) AS BIGINT) AS shared FROM ({_TOP}) t GROUP BY i", "embeddings vec")
both("top1_agreement", f"SELECT round(avg(CASE WHEN rq = 1 THEN 1.0E0 ELSE 0.0E0 END), 6) AS top1 FROM ({_TOP}) t WHERE rp = 1", "embeddings vec")
both("label_accuracy", f"SELECT round(avg(CASE WHEN j = i % 64 THEN 1.0E0 ELSE 0.0E0 END), 6) AS accuracy FROM ({_TOP}) t WHERE rq = 1", "embeddings vec")

# -- cost models --------------------------------------------------------------------------------------------------

both("op_cost_model", f"SELECT seq_id, d, f, r, b, n * (f * (d + r) + r * b) AS spectral, n * d AS chunk FROM ({_LENGTHS}) l CROSS JOIN (SELECT 64 AS d UNION ALL SELECT 4096) a CROSS JOIN (SELECT 128 AS f UNION ALL SELECT 256 UNION ALL SELECT 512) x CROSS JOIN (SELECT 4 AS r UNION ALL SELECT 16 UNION ALL SELECT 32) y CROSS JOIN (SELECT 8 AS b UNION ALL SELECT 12) z", "documents embeddings tok")
_LEFT = f"CASE WHEN n <= {SUFFIX} THEN n ELSE {SUFFIX} + greatest(1, ceil((n - {SUFFIX}) / cast(rho AS DOUBLE))) END"
both("prefill_cost_model", f"SELECT seq_id, n, rho, round((m * m * 64.0E0 + m * 4096.0E0) / (n * n * 64.0E0 + n * 4096.0E0), 6) AS share FROM (SELECT seq_id, n, rho, cast({_LEFT} AS DOUBLE) AS m FROM ({_LENGTHS}) l CROSS JOIN ({_TARGETS}) r) c", "documents embeddings tok")
