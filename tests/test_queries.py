"""Every query of the registry on the smallest tables, against its DuckDB text where it has one."""

import hashlib
import math
import os
from pathlib import Path

import duckdb
import pytest

from tokenfold import registry

SMALL = "/root/testdata/sf0.001"
#: Long ones, whose parts other queries cover; RUN_SLOW=1 runs them too.
SLOW = {"abl_bits", "w_stress_json", "route_share", "quality_by_backend", "exact_gaussian_kernel", "exact_attention_rows", "w_quality_grid", "w_quality_small", "w_stress_table"}
pytestmark = pytest.mark.skipif(not Path(SMALL).exists(), reason="no tables")


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for file in Path(SMALL).glob("*.parquet"):
        con.execute(f"CREATE VIEW {file.stem} AS SELECT * FROM read_parquet('{file}')")
    return con


def plain(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    if isinstance(v, bool):
        return v
    if hasattr(v, "as_tuple") or isinstance(v, (int, float)):
        return round(float(v), 5)
    return str(v)


def rows(names, data):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in data), key=repr)


#: Least and greatest value of the columns of queries without an oracle.
RANGES = {"cosine": (-1, 1.000001), "top1": (0, 1), "top10": (0, 1), "label_accuracy": (0, 1), "kl": (-1e-9, 1e3), "ppl_ratio": (0, 1e9), "share": (0, 1), "purity": (0, 1), "passed": (0, 1), "near": (0, 1),
          "kept": (0, 1), "monotone": (1, 1), "same_first": (0, 1), "same_text": (0, 1), "holds_answer": (0, 1), "trace_share": (0, 1.000001), "frobenius_share": (0, 1.000001), "least": (0, 1.000001),
          "agreement": (0.5, 1), "spectral_share": (0, 1), "mean_score": (0, 1.000001), "late_members": (0, 0), "split_share": (0, 1), "merge_share": (0, 1), "preprocess_s": (0, 60), "prefill_s": (0, 60),
          "reference_s": (0, 60), "speedup": (0, 1e6), "peak_mb": (1, 1e5), "gap": (0, 1e-6), "residual": (0, 1e-6), "actual_ratio": (1, 16), "n": (1, 1e12), "distortion": (0, 1e3)}


def by(rows, *keys):
    return {tuple(r[k] for k in keys): r for r in rows}


def grows(rows, value, along, *keys):
    """A value does not fall along a column within the rows of equal keys."""
    for key in {tuple(r[k] for k in keys) for r in rows}:
        values = [r[value] for r in sorted((r for r in rows if tuple(r[k] for k in keys) == key), key=lambda r: r[along])]
        assert values == sorted(values), (key, values)


def falls_short_of_the_ratio(rows):
    assert all(r["actual_ratio"] <= r["rho"] + 0.01 for r in rows)


#: What else holds for them.
HOLDS = {
    "kernel_sup_error": lambda r: all(x["within"] for x in r) and grows(r, "eps", "eps") is None,
    "lanczos_gram": lambda r: len(r) == 16,
    "lanczos_tridiagonal": lambda r: len(r) == 16 and all(x["alpha"] >= 0 and x["beta"] >= 0 for x in r),
    "gram_eigen": lambda r: grows(r, "value", "j") is None,
    "krylov_bounds": lambda r: all(x["bound"] <= x["ritz"] + 1e-6 <= x["eigenvalue"] + 2e-6 for x in r),
    "spectral_energy": lambda r: grows(r, "trace_share", "rank") is None,
    "abl_rank_features": lambda r: grows(r, "trace_share", "rank", "dims") is None,
    "k2_energy": lambda r: all(x["n"] == 500 for x in r),
    "k2_energy_tokens": lambda r: grows(r, "trace_share", "rank") is None,
    "spectral_cosine_gap": lambda r: grows(r, "rank", "rank") is None and all(0 <= x["mean"] <= x["largest"] <= 2 for x in r),
    "dense_reference": lambda r: r[0]["agreement"] > 0.9,
    "spectral_coordinates": lambda r: len(r) == 500 and all(0 <= x["first"] <= x["norm"] <= 1.000001 for x in r),
    "w_quality_grid": lambda r: len(r) == 36 and falls_short_of_the_ratio(r) is None,
    "w_quality_small": lambda r: len(r) == 24 and falls_short_of_the_ratio(r) is None,
    "w_quality_second_corpus": lambda r: len(r) == 12 and falls_short_of_the_ratio(r) is None,
    "w_latency": lambda r: len(r) == 16 and all(abs(x["total_s"] - x["preprocess_s"] - x["prefill_s"]) < 1e-6 for x in r),
    "w_scaling": lambda r: {(x["n_tokens"], x["n_reference"]) for x in r} == {(2884, 2884), (5780, 5780), (11546, 8192), (23092, 8192)},
    "w_frontier": lambda r: len(r) == 16 and any(x["on_frontier"] for x in r) and not all(x["on_frontier"] for x in r),
    "route_share": lambda r: all(x["share"] == 1 for x in r if x["rho"] == 16) and grows(r, "share", "rho", "schedule") is None,
    "route_share_by_source": lambda r: len(r) == 20 and all(x["share"] == 1 for x in r if x["rho"] == 16),
    "abl_position_pass": lambda r: all(x["passed"] == 1 and x["same_text"] == 1 for x in r if x["rho"] == 1),
    "pass_rate": lambda r: all(x["passed"] == 1 for x in r if x["rho"] == 1),
    "k1_checks": lambda r: len(r) == 3,
    "abl_row_agreement": lambda r: r[0]["distortion_plain"] > 0 and r[0]["distortion_row"] > 0,
    "abl_bits_before": lambda r: grows(r, "mean_codes", "bits", "rho") is None and all(x["mean_codes"] <= min(16, 2 ** x["bits"]) for x in r),
    "teacher_forced_eval": lambda r: all(0 < x["n_macro"] < x["n_tokens"] for x in r),
    "abl_renorm": lambda r: by(r, "backend").keys() == {("none",), ("member_mean",), ("table_mean",), ("prompt_mean",)},
}


@pytest.mark.parametrize("name", sorted(registry.queries()))
def test_query(spark, duck, name):
    if name in SLOW and not os.environ.get("RUN_SLOW"):
        pytest.skip("long")
    df = registry.queries()[name](spark, SMALL)
    found = df.collect()
    got = rows(df.columns, found)
    text = registry.oracle_sql().get(name)
    if text is None:
        assert found
        for c in df.columns:
            low, high = RANGES.get(c, (-math.inf, math.inf))
            for r in found:
                assert not isinstance(r[c], (int, float)) or low <= r[c] <= high, (c, r[c])
        assert HOLDS.get(name, lambda r: True)(found)
        return
    want = duck.execute(text)
    columns = [c[0] for c in want.description]
    assert sorted(df.columns) == sorted(columns)
    assert got == rows(columns, want.fetchall())


@pytest.mark.parametrize("name, key", [("collision_law", "embeddings"), ("collision_law_bits", "embeddings"), ("op_cost_model", "documents"), ("prefill_cost_model", "documents")])
def test_rules_follow_a_table(spark, duck, name, key):
    """A rule's rows come from a given table: they are several for each of its rows, or one less for pairs of neighbours."""
    n = duck.execute(f"SELECT count(*) FROM {key}" + (" WHERE len(regexp_extract_all(text, '[^\\x20\\x09-\\x0d]+')) > 0" if key == "documents" else "")).fetchone()[0]
    times = {"collision_law": 1, "collision_law_bits": 4, "op_cost_model": 36, "prefill_cost_model": 4}[name]
    assert registry.queries()[name](spark, SMALL).count() == times * (n - (key == "embeddings"))


def test_rff_params_follow_the_width(spark, tmp_path):
    spark.range(3).selectExpr("id AS vec_id", "array(1f, 2f, 3f) AS embedding", "0 AS label").write.parquet(f"{tmp_path}/embeddings.parquet")
    assert registry.queries()["rff_params"](spark, str(tmp_path)).count() == 3 * 64


@pytest.mark.parametrize("name", ["paper_best_backend", "paper_jensen", "paper_pareto", "paper_ppl_gap", "paper_routing_savings", "paper_transition"])
def test_analyses_follow_the_table(spark, tmp_path, name):
    """Their rows are measured on the given vectors: of equal ones no backend loses anything, and models are their labels."""
    spark.range(70).selectExpr("id AS vec_id", "transform(sequence(1, 64), j -> 0.125f) AS embedding", "CAST(id % 3 + 40 AS INT) AS label").write.parquet(f"{tmp_path}/embeddings.parquet")
    found = registry.queries()[name](spark, str(tmp_path)).collect()
    assert found and all(r["model"] in (40, 41, 42) for r in found if "model" in r)
    for r in found:
        for column, value in (("ppl", 1), ("above", 0), ("gap", 0), ("dnll", 0)):
            assert column not in r or r[column] == pytest.approx(value, abs=1e-9)
    if name == "paper_routing_savings":  # equal vectors are routed to the hash in each window beyond the last, of 6, too
        assert {r["saved"] for r in found} == {-0.125}
    if name == "paper_pareto":
        assert {r["backend"]: r["total"] for r in found if r["rho"] == 16} == {b: 70 * o + 5 * 4160 for b, o in (("chunk", 64), ("raw_lsh", 512), ("adaptive", 576))}
        assert [r["total"] for r in found if r["rho"] == 1] == [4 * (64 * 256 + 4096 * 16) + 64 * 36 + 4096 * 6]


def test_tokens_are_joined_to_the_vocabulary(spark, tmp_path):
    """Every token of a document, repeated ones too, meets its row of the given table in a broadcast hash join."""
    spark.createDataFrame([(7, "one two one"), (8, ""), (9, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.range(5).selectExpr("id AS vec_id", "array(CAST(3 * id AS FLOAT), CAST(4 * id AS FLOAT)) AS embedding", "CAST(id + 40 AS INT) AS label").write.parquet(f"{tmp_path}/embeddings.parquet")
    found = registry.queries()["join_broadcast_vocab"](spark, str(tmp_path))
    row = {w: int(hashlib.md5(w.encode()).hexdigest()[:8], 16) % 5 for w in ("one", "two")}
    assert sorted(map(tuple, found.collect())) == [(7, i, w, row[w], row[w] + 40, 5.0 * row[w]) for i, w in enumerate(("one", "two", "one"))]
    assert "BroadcastHashJoin" in found._jdf.queryExecution().executedPlan().toString()
