"""Checks of the frozen table on more vectors than one exact task takes."""

from dataclasses import replace

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from tokenfold import registry
from tokenfold.functions import kernels
from tokenfold.operators import backends, onesequence
from tokenfold.options import CompressOptions
from tokenfold.plans import native

N = 8300  # more than kernels.MOST_EXACT


@pytest.fixture(scope="module")
def x():
    v = np.random.default_rng(3).normal(size=(N, 64))
    return (v / np.linalg.norm(v, axis=1, keepdims=True)).astype(np.float32).astype(np.float64)


@pytest.fixture(scope="module")
def phi(x):
    return kernels.rff(x, 256)


@pytest.fixture(scope="module")
def folder(spark, x, tmp_path_factory):
    path = tmp_path_factory.mktemp("large")
    (path / "embeddings.parquet").mkdir()
    for part, ids in enumerate(np.array_split(np.random.default_rng(1).permutation(N), 5)):
        rows = pa.table({"vec_id": ids, "embedding": pa.array(list(x[ids].astype(np.float32)), pa.list_(pa.float32())), "label": pa.array([0] * len(ids), pa.int32())})
        pq.write_table(rows, path / "embeddings.parquet" / f"part-{part}.parquet")
    return str(path)


def got(spark, folder, name, *order):
    return registry.queries()[name](spark, folder).orderBy(*order).collect()


def test_gram_eigen(spark, folder, phi):
    values = np.linalg.eigvalsh(phi.T @ phi)[-16:]
    rows = got(spark, folder, "gram_eigen", "j")
    assert np.allclose([r["value"] for r in rows], values, rtol=1e-10)
    assert max(r["residual"] for r in rows) < 1e-7


def test_krylov_bounds(spark, folder, phi):
    want = kernels.ritz_bounds(phi, CompressOptions(start="range"), 8)
    rows = got(spark, folder, "krylov_bounds", "j")
    assert np.allclose([tuple(r) for r in rows], [r[:4] for r in want], rtol=1e-6)


@pytest.mark.parametrize("name, change", [("spectral_coordinates", dict(start="random", weighting="none", drop_top=False)), ("coords_weighted", dict(weighting="full", drop_top=False)), ("coords_drop_top", {})])
def test_coordinates(spark, folder, phi, name, change):
    z = kernels.coordinates(phi[None], replace(CompressOptions(), **change))[0]
    rows = got(spark, folder, name, "i")
    assert [r["i"] for r in rows] == list(range(N))
    assert np.allclose([r["norm"] for r in rows], np.linalg.norm(z, axis=1), rtol=1e-8, atol=1e-10)
    assert np.allclose([r["first"] for r in rows], np.abs(z).max(axis=1), rtol=1e-8, atol=1e-10)


def test_ids_with_gaps(spark, folder, phi, tmp_path):
    """Places count from 0 in the order of the ids, whatever the ids are."""
    few = spark.read.parquet(f"{folder}/embeddings.parquet").filter("vec_id < 40").selectExpr("vec_id * 7 - 20 AS vec_id", "embedding", "label")
    few.write.parquet(f"{tmp_path}/embeddings.parquet")
    z = kernels.coordinates(phi[None, :40], replace(CompressOptions(), start="random", weighting="none", drop_top=False))[0]
    rows = got(spark, str(tmp_path), "spectral_coordinates", "i")
    assert [r["i"] for r in rows] == list(range(40))
    assert np.allclose([r["norm"] for r in rows], np.linalg.norm(z, axis=1), rtol=1e-8)


def test_k2_energy(spark, folder, x):
    rows = {r["sequence"]: r for r in got(spark, folder, "k2_energy", "sequence")}
    for name, v in (("raw", x), ("shared", np.sqrt(0.75) * x + 0.5 / 8)):
        want = [kernels.energy_fraction(kernels.rff(v, 256), CompressOptions(rank=16), norm) for norm in ("trace", "frobenius")]
        assert rows[name]["n"] == N and np.allclose([rows[name]["trace_share"], rows[name]["frobenius_share"]], want, rtol=1e-10)


def test_abl_rank_features(spark, folder, x):
    rows = {(r["rank"], r["dims"]): r for r in got(spark, folder, "abl_rank_features", "rank", "dims")}
    assert len(rows) == 12
    for rank, dims in ((4, 128), (32, 256), (16, 512)):
        want = [kernels.energy_fraction(kernels.rff(x, dims), CompressOptions(rank=rank), norm) for norm in ("trace", "frobenius")]
        assert np.allclose(rows[rank, dims][2:], want, rtol=1e-10)


def test_abl_row_normalised(spark, folder, phi):
    sums = phi @ phi.sum(axis=0)
    scaled = phi / np.sqrt(np.maximum(sums, max(1e-3 * np.abs(sums).mean(), 1e-12)))[:, None]
    rows = {r["operator"]: r for r in got(spark, folder, "abl_row_normalised", "operator")}
    for name, p in (("plain", phi), ("row", scaled)):
        assert np.allclose(rows[name][1:], (kernels.energy_fraction(p, CompressOptions(rank=16)), sums.std() / abs(sums.mean())), rtol=1e-9)


def test_kernel_sup_error(spark, folder, x):
    exact = kernels.gaussian_kernel(x)
    for r in got(spark, folder, "kernel_sup_error", "dims"):
        if r["dims"] < 1024:
            phi = kernels.rff(x, r["dims"])
            assert abs(r["sup_error"] - np.abs(phi @ phi.T - exact).max()) < 1e-12
        assert r["within"]


def test_exact_coordinates(spark, x):
    """More vectors than one task takes: the residuals of the exact kernel, and the one-task path on fewer."""
    few, opts = x[:600], CompressOptions(weighting="none", drop_top=False)
    most, onesequence.MOST_EXACT = onesequence.MOST_EXACT, 500
    try:
        z = onesequence.exact_coordinates(spark, few, opts)
    finally:
        onesequence.MOST_EXACT = most
    want = kernels.dense_coordinates(few, opts)
    assert np.allclose(np.abs((z * want).sum(axis=0)), 1, atol=1e-6)


def test_dense_reference(spark, folder):
    (row,) = got(spark, folder, "dense_reference", "n_groups")
    assert row["n_groups"] == 64 and 0.5 < row["agreement"] < 1


def test_products_with_a_large_table_stay_small():
    assert all(native.rows_at_once(n) * n <= native.MOST_CELLS for n in (500, 2000, 51282, 1 << 20))
    assert native.rows_at_once(0) == 512 and native.rows_at_once(1 << 22) == 1


def test_rows_leave_in_bounded_frames():
    """Frames are bounded whatever a batch gives, rows are made only when they are taken, and none is lost."""
    made = []
    frames = backends.framed(((made.append(i) or i, 2 * i) for i in range(10_000)), ["a", "b"])
    first = next(frames)
    assert len(first) == len(made) == backends.MOST_ROWS
    rest = list(frames)
    assert max(map(len, rest)) <= backends.MOST_ROWS and len(first) + sum(map(len, rest)) == 10_000


def test_kernels_of_a_larger_table(spark, tmp_path, x, monkeypatch):
    """Vectors taken a few at a time give the whole kernel."""
    monkeypatch.setattr(native, "MOST_CELLS", 1000)
    (tmp_path / "embeddings.parquet").mkdir()
    pq.write_table(pa.table({"vec_id": np.arange(300), "embedding": pa.array(list(x[:300].astype(np.float32)), pa.list_(pa.float32()))}), tmp_path / "embeddings.parquet" / "part.parquet")
    e = x[:300]
    for name, want in (("exact_kernel", np.exp(e @ e.T / 8)), ("exact_attention_rows", np.exp(e @ e.T / 8) / np.exp(e @ e.T / 8).sum(axis=1, keepdims=True)), ("exact_gaussian_kernel", kernels.gaussian_kernel(e))):
        rows = got(spark, str(tmp_path), name, "i", "k")
        assert np.abs(np.array([r[2] for r in rows]).reshape(300, 300) - want).max() < 1e-6


@pytest.mark.parametrize("name", ["exact_attention_rows", "exact_gaussian_kernel", "exact_kernel"])
def test_pairs_are_written_in_runs(spark, tmp_path, x, name):
    """One number of a pair stays for many rows and the other follows a short pattern, so neither takes disk beside the value."""
    (tmp_path / "embeddings.parquet").mkdir()
    e = x[:600]
    pq.write_table(pa.table({"vec_id": np.arange(len(e)), "embedding": pa.array(list(e.astype(np.float32)), pa.list_(pa.float32()))}), tmp_path / "embeddings.parquet" / "part.parquet")
    registry.queries()[name](spark, str(tmp_path)).write.parquet(f"{tmp_path}/out")
    runs = n = 0
    for file in (tmp_path / "out").glob("*.parquet"):
        k = pq.read_table(file)["k"].to_numpy()
        runs, n = runs + np.count_nonzero(np.diff(k, prepend=-1)), n + len(k)
    assert n == len(e) ** 2 and runs < n / 32
