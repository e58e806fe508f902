"""Array kernels and rules against numpy and worked numbers."""

import math
from pathlib import Path
from types import SimpleNamespace

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest

from tokenfold.functions import kernels, reader, rng, schedule
from tokenfold.operators import evaluation, onesequence, studies
from tokenfold.options import CompressOptions
from tokenfold.plans import relational
from tokenfold.sources.records import RepeatedRecords
from tokenfold.streaming import streams


def table(n=96, d=64, seed=0):
    x = np.random.default_rng(seed).normal(size=(n, d))
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def together(labels):
    labels = np.asarray(labels)
    return labels[:, None] == labels


# -- rules --------------------------------------------------------------------------------------------------------


def test_lengths_bits_and_budgets():
    assert [schedule.target_length(n, 4) for n in (0, 12, 13, 16, 17, 112)] == [0, 12, 13, 13, 14, 37]
    assert schedule.target_length(100, 1) == 100
    assert schedule.target_length(100, 0.5) == 100
    assert [schedule.bits_for_target(m) for m in (1, 2, 3, 512, 513)] == [1, 1, 2, 9, 10]
    assert [schedule.chunk_width(r) for r in (1, 1.5, 2, 2.5)] == [1, 2, 2, 3]
    for body, target in ((1, 1), (33, 9), (100, 25), (160, 7)):
        got = schedule.budgets(body, target, 16)
        assert sum(got) == target and len(got) == math.ceil(body / 16)
    assert schedule.regions(6, 2, 3) == ["prefix", "prefix", "body", "suffix", "suffix", "suffix"]
    assert schedule.regions(2, 2, 3) == ["suffix", "suffix"]


def test_thresholds():
    assert [round(schedule.tau(r), 6) for r in (1, 2, 5, 8, 12, 16, 99)] == [0.7, 0.7, 0.65, 0.6, 0.575, 0.55, 0.55]
    assert schedule.tau(9, schedule="constant") == 0.70
    assert schedule.tau(4, schedule="log2") == pytest.approx(0.65)


def test_bounds_and_costs():
    assert schedule.op_count("local", 4096, 256, 16, 8) == 1052800
    assert [round(schedule.collision(c, b), 6) for c, b in ((1, 8), (0, 1), (0, 8), (-1, 1))] == [1, 0.5, round(2**-8, 6), 0]
    assert schedule.rff_tail(64, 256, schedule.rff_eps(64, 256, 0.05)) == pytest.approx(0.05)
    assert schedule.prefill_cost(2) == 64 * 4 + 4096 * 2


def test_numbers_do_not_depend_on_how_many_are_drawn():
    few, many = rng.uniforms(3, "t", 5, 4), rng.uniforms(3, "t", 50, 4)
    assert np.array_equal(few, many[:5])
    assert np.array_equal(rng.normals(3, "t", 5, 4), rng.normals(3, "t", 50, 4)[:5])
    assert abs(rng.normals(1, "n", 200, 50).mean()) < 0.05


@pytest.mark.parametrize("change", [{"backend": "x"}, {"rho": 0}, {"window": 0}, {"renorm": "x"}, {"schedule": "x"}])
def test_options_are_checked(change):
    with pytest.raises(ValueError, match="must be"):
        CompressOptions(**change)


# -- operator -----------------------------------------------------------------------------------------------------


def test_features_estimate_the_kernel():
    x = table()
    exact = kernels.gaussian_kernel(x)
    gaps = [np.abs((p := kernels.rff(x, d)) @ p.T - exact).max() for d in (64, 512, 4096)]
    assert gaps[0] > gaps[1] > gaps[2] and gaps[2] < schedule.rff_eps(len(x), 4096, 0.05)
    soft = kernels.rff(x, 4096, kernel="softmax")
    assert np.abs(soft @ soft.T - np.exp(x @ x.T / 8)).max() < 0.2


@pytest.mark.parametrize("start", ["range", "random"])
@pytest.mark.parametrize("norm", ["none", "row"])
def test_lanczos_against_dense(start, norm):
    phi = kernels.rff(table(40), 128)
    opts = CompressOptions(rank=40, start=start, kernel_norm=norm)
    q, t = (m[0] for m in kernels.lanczos(phi[None], opts))
    if norm == "row":
        s = phi @ phi.sum(0)
        phi = phi / np.sqrt(np.maximum(s, 1e-3 * np.abs(s).mean()))[:, None]
    assert np.abs(q.T @ q - np.eye(40)).max() < 1e-8
    assert np.allclose(np.linalg.eigvalsh(t), np.linalg.eigvalsh(phi @ phi.T), atol=1e-8)


def test_lanczos_stops_where_the_range_ends():
    x = np.repeat(table(3), 8, axis=0)  # three distinct vectors
    q, t = (m[0] for m in kernels.lanczos(kernels.rff(x, 64)[None], CompressOptions(rank=10)))
    assert (np.linalg.norm(q, axis=0) > 0.5).sum() == 3
    assert np.isfinite(t).all() and np.abs(t[3:, 3:]).max() < 1e-8


def test_equal_tokens_have_equal_coordinates():
    x = np.tile(table(32), (4, 1))
    z = kernels.coordinates(kernels.rff(x, 256)[None], CompressOptions())[0]
    codes = kernels.simhash(z, 8)
    assert all(len(set(codes[i::32])) == 1 for i in range(32))


def test_weights_and_the_leading_direction():
    phi = kernels.rff(table(64), 256)[None]
    plain = kernels.coordinates(phi, CompressOptions(weighting="none", drop_top=False))[0]
    full = kernels.coordinates(phi, CompressOptions(weighting="full", drop_top=False))[0]
    half = kernels.coordinates(phi, CompressOptions(weighting="sqrt", drop_top=False))[0]
    values = np.linalg.norm(full, axis=0)
    assert np.allclose(np.linalg.norm(plain, axis=0), 1) and np.allclose(np.linalg.norm(half, axis=0) ** 2, values)
    assert (np.diff(values) > 0).all()
    assert np.allclose(kernels.coordinates(phi, CompressOptions())[0], half[:, :-1])
    assert kernels.coordinates(phi, CompressOptions(top_k=5))[0].shape[1] == 4


def test_products_alone_give_the_same_matrix():
    phi = kernels.rff(table(200), 64)
    t, g = kernels.lanczos(phi[None], CompressOptions())[1][0], kernels.lanczos_from_gram(phi.T @ phi, CompressOptions())
    assert np.abs(t - g).max() < 1e-6
    values, vectors = kernels.gram_eigen(phi.T @ phi, 8)
    assert np.allclose(values, np.linalg.eigvalsh(phi @ phi.T)[-8:])
    v = phi @ vectors / np.sqrt(values)
    assert np.allclose(phi @ (phi.T @ v), v * values, atol=1e-8)


def test_energy_grows_with_rank_and_ends_at_one():
    phi = kernels.rff(table(40), 64)
    for norm in ("trace", "frobenius"):
        got = [kernels.energy_fraction(phi, CompressOptions(rank=r), norm) for r in (2, 8, 40)]
        assert got == sorted(got) and got[2] == pytest.approx(1, abs=1e-6)


def test_ritz_values_lie_between_their_bounds():
    assert all(low and high for *_, low, high in kernels.ritz_bounds(kernels.rff(table(200), 128), CompressOptions(), 6))


def test_dense_coordinates_follow_the_exact_kernel():
    x = table(60)
    z = kernels.dense_coordinates(x, CompressOptions(rank=60, drop_top=False))
    assert np.allclose(z @ z.T, kernels.gaussian_kernel(x), atol=1e-8)
    with pytest.raises(ValueError, match="at most"):
        kernels.dense_coordinates(np.zeros((kernels.MOST_EXACT + 1, 2)), CompressOptions())


# -- groups -------------------------------------------------------------------------------------------------------


def test_gray_order_changes_one_bit():
    codes = np.arange(64)
    by_rank = codes[np.argsort(kernels.gray_rank(codes))]
    assert all(bin(a ^ b).count("1") == 1 for a, b in zip(by_rank, by_rank[1:], strict=False))


def test_zero_counts_as_positive():
    assert kernels.simhash(np.zeros((1, 8)), 6)[0] == 63


@pytest.mark.parametrize("target", [1, 2, 5, 16])
def test_groups_are_fitted_exactly(target):
    rng_ = np.random.default_rng(target)
    codes, z = rng_.integers(0, 6, 16), rng_.normal(size=(16, 3))
    for got in (kernels.fit_groups(codes, z, target), kernels.fit_groups_in_order(codes, target)):
        assert sorted(set(got)) == list(range(target))
    if target > len(set(codes)):  # splits only: tokens of different codes stay apart
        assert not (together(kernels.fit_groups(codes, z, target)) & ~together(codes)).any()
        assert not (together(kernels.fit_groups_in_order(codes, target)) & ~together(codes)).any()


@pytest.mark.parametrize("target", [1, 3, 17, 40, 41, 90, 299, 300])
def test_corpus_groups_are_those_of_the_kernel(spark, target):
    codes = np.random.default_rng(target).zipf(1.3, 300) % 64
    codes[:100] = 5  # a third of all tokens share a code, so it spans partitions
    place = kernels.gray_rank(codes)
    rows = [(i // 50, i % 50, int(p)) for i, p in enumerate(place)]
    got = {(r["seq_id"], r["pos"]): (r["place"], r["grp"]) for r in onesequence.fit_corpus(spark.createDataFrame(rows, "seq_id long, pos int, place long"), target).collect()}
    assert len(got) == 300 and {g for _, g in got.values()} == set(range(target))
    want = kernels.fit_groups_in_order(codes, target)
    assert (kernels.dense_labels(np.array([got[i // 50, i % 50][1] for i in range(300)])) == want).all()
    assert len(set(got.values())) == max(target, len(set(place)))  # codes merge whole or split, never both


@pytest.mark.parametrize("target", [3, 12, 90])
def test_corpus_groups_of_whole_prompts(spark, target):
    """Prompts in several ranges, with empty ones and equal ids: the groups of one sequence in the order of ids."""
    rng = np.random.default_rng(4)
    sizes = [0, 3, 40, 1, 0, 25, 60, 7, 90, 2, 33]
    prompts = [(i * 5 - 9, rng.integers(0, 20, n).tolist()) for i, n in enumerate(sizes)]
    made = onesequence.fit_prompts(spark.createDataFrame(prompts[::-1], "seq_id long, places array<long>"), target)
    got = sorted((r["seq_id"], r["pos"], r["place"], r["grp"]) for r in made.collect())
    place = np.concatenate([np.array(p, np.int64) for _, p in prompts])
    assert [r[:3] for r in got] == [(i, k, c) for i, p in prompts for k, c in enumerate(p)]
    assert {r[3] for r in got} == set(range(target))
    codes = place ^ (place >> 1)  # whose Gray ranks are the places
    assert (kernels.dense_labels(np.array([r[3] for r in got])) == kernels.fit_groups_in_order(codes, target)).all()


def test_groups_of_a_code_beyond_64_bits():
    codes = np.array([[5], [1 << 40], [7], [1 << 39], [1 << 41]])
    rows = pa.record_batch({"seq_id": pa.array([1, 2]), "places": pa.array([[5], [5, 5]], pa.list_(pa.int64()))})
    assert onesequence._in_order(rows, codes).column("grp").to_pylist() == [7 + (((1 << 40) + k) << 39 >> 41) for k in range(3)]
    assert codes[1, 0] == (1 << 40) + 3


@pytest.mark.parametrize("subword", ["none", "trigram"])
def test_vectors_of_many_words(subword):
    v = kernels.Vocabulary(np.random.default_rng(0).normal(size=(50, 8)), 0.25, subword)
    words = ["a", "abc", "abcd", "quite a long one", "\ud800bcd", "abcd"]
    assert np.allclose(v.vectors(words), [v.vector(w) for w in words], rtol=0, atol=1e-15)
    assert v.vectors([]).shape == (0, 8)


def test_no_token_makes_no_corpus_group(spark):
    assert onesequence.fit_corpus(spark.createDataFrame([], "seq_id long, pos int, place long"), 1).count() == 0
    assert kernels.fit_groups_in_order(np.empty(0, np.int64), 1).tolist() == []


def test_the_largest_splits_and_the_smallest_joins_its_nearest():
    assert kernels.fit_groups(np.zeros(5, int), np.zeros((5, 1)), 2).tolist() == [0, 0, 0, 1, 1]
    z = np.array([[0.0], [0.1], [5.0], [5.1], [4.0]])
    assert kernels.fit_groups(np.array([0, 0, 1, 1, 2]), z, 2).tolist() == [0, 0, 1, 1, 1]


def test_redundancy():
    assert kernels.redundancy(np.ones((1, 16, 4)))[0] == pytest.approx(1)
    assert kernels.redundancy(np.eye(16)[None])[0] == pytest.approx(0.25)
    assert np.isfinite(kernels.redundancy(np.zeros((1, 4, 4)))).all()


def test_fused_vectors_and_positions():
    x, labels = np.array([[3.0, 0.0], [0.0, 4.0]]), np.zeros(2, int)
    norm = {"none": (1.5, 2.0), "member_mean": (2.1, 2.8), "table_mean": (0.6, 0.8), "prompt_mean": (2.1, 2.8)}
    for mode, want in norm.items():
        assert np.allclose(kernels.fuse(x, np.arange(2), labels, CompressOptions(renorm=mode)).x, [want])
    pos = np.array([1, 2, 5, 9])
    for scheme, want in {"max": 9, "median": 2, "mean": 4}.items():
        assert kernels.fuse(np.ones((4, 2)), pos, np.zeros(4, int), CompressOptions(position_scheme=scheme)).pos.tolist() == [want]
    zero = kernels.fuse(np.array([[1.0, 0.0], [-1.0, 0.0]]), np.arange(2), labels, CompressOptions())
    assert np.isfinite(zero.x).all()
    late = kernels.fuse(np.ones((4, 2)), np.arange(4), np.array([0, 1, 1, 0]), CompressOptions())
    assert late.pos.tolist() == [2, 3] and late.first.tolist() == [1, 0]
    assert kernels.fuse(np.ones((4, 2)), np.arange(4), np.array([0, 1, 1, 0]), CompressOptions(position_mode="compact")).pos.tolist() == [0, 1]


# -- whole prompts ------------------------------------------------------------------------------------------------

ALL = ("chunk", "chunk_budgeted", "random", "raw_lsh", "local", "adaptive", "global", "dense")


@pytest.mark.parametrize("backend", ALL)
@pytest.mark.parametrize("rho", [1.5, 2, 2.5, 4, 8, 16])
@pytest.mark.parametrize("n", [0, 1, 12, 13, 29, 100])
def test_lengths_order_and_members(backend, rho, n):
    opts = CompressOptions(backend=backend, rho=rho, prefix=2)
    m = kernels.compress(table(max(n, 1), 8)[:n], opts)
    body = max(0, n - 14)
    groups = math.ceil(body / (schedule.chunk_width(rho) if backend == "chunk" else rho))
    assert len(m.pos) == n - body + groups
    assert sorted(np.concatenate([*m.members, np.empty(0, int)]).tolist()) == list(range(n))
    assert (np.diff(m.pos) >= 0).all() and (m.last <= m.pos).all()


def test_ends_come_back_unchanged():
    x = table(60, 8)
    m = kernels.compress(x, CompressOptions(backend="local", rho=4, prefix=5, suffix=7))
    assert np.array_equal(m.x[:5], x[:5]) and np.array_equal(m.x[-7:], x[-7:])


@pytest.mark.parametrize("rho", [1, 0.5])
def test_a_ratio_of_one_changes_no_bit(rho):
    x = table(50, 8)
    for forced in (False, True):
        m = kernels.compress(x, CompressOptions(rho=rho, identity_test=forced))
        assert np.allclose(m.x, x, atol=0 if not forced else 1e-15) and m.pos.tolist() == list(range(50))


def test_routes():
    same, other = np.ones((16, 8)), np.concatenate([np.eye(8), -np.eye(8)])
    x = np.concatenate([same, other, same[:4], np.zeros((12, 8))])
    got = kernels.group_body(x[:36], CompressOptions(rho=4))
    assert got.routes.tolist() == ["spectral", "chunk", "chunk"]  # a tiny window is never hashed
    assert kernels.group_body(np.concatenate([x[:32], same[:5]]), CompressOptions(rho=4)).routes[-1] == "spectral"
    score = kernels.redundancy(other[None])[0]
    at = CompressOptions(rho=4, threshold=float(score), schedule="constant")
    assert kernels.group_body(other, at).routes.tolist() == ["spectral"]  # the threshold itself is enough
    assert set(kernels.group_body(x, CompressOptions(rho=16)).routes) == {"spectral"}
    a, b = (kernels.group_body(x, CompressOptions(rho=16, backend=k)).labels for k in ("adaptive", "local"))
    assert np.array_equal(a, b)


def test_far_repetitions_meet_by_hash_and_never_by_chunks():
    x = np.tile(table(64), (4, 1))
    again = np.arange(64, 128)
    for rho in (16, 64):  # codes are merged, not split
        hashed = kernels.group_body(x, CompressOptions(backend="global", rho=rho)).labels
        assert (hashed[:64] == hashed[again]).all()
    chunks = kernels.group_body(x, CompressOptions(backend="chunk", rho=4)).labels
    assert not (chunks[:64] == chunks[again]).any()


# -- reader -------------------------------------------------------------------------------------------------------


def test_measures_of_equal_and_of_other_logits():
    a = np.random.default_rng(0).normal(size=(5, 64))
    same = reader.compare(a, a, np.zeros(5, int))
    assert same["kl"] == pytest.approx(0) and same["cosine"] == pytest.approx(1) and same["top1"] == same["top10"] == same["ppl_ratio"] == 1
    b = a + np.random.default_rng(1).normal(size=a.shape)
    got, la, lb = reader.compare(a, b, np.arange(5)), reader.log_softmax(a), reader.log_softmax(b)
    assert got["kl"] == pytest.approx(float((np.exp(la) * (la - lb)).sum(1).mean())) and got["kl"] > 0
    assert got["delta_nll"] == pytest.approx(float((la - lb)[np.arange(5), np.arange(5)].mean()))


def test_a_masked_pass_sees_no_later_position():
    x, pos = table(30, 8), np.arange(30)
    whole = reader.prefill(x, pos, block=7)
    changed = x.copy()
    changed[20:] = table(10, 8, 5)
    assert np.allclose(reader.prefill(changed, pos)[:20], whole[:20]) and np.allclose(whole[0], x[0])
    assert not np.allclose(reader.prefill(x, np.zeros(30))[0], x[0])


def test_greedy_continuations():
    e = table(50, 16)
    v = kernels.Vocabulary(e)
    x = v([f"w{i}" for i in range(20)])
    for name in ("flat", "masked"):
        first, said = reader.greedy(reader.READERS[name], e, v, x, np.arange(20), 6)
        again = [int(z.argmax()) for z in reader.logits(reader.READERS[name], e, v.u, x, np.arange(20), np.array([np.sqrt(0.75) * e[i] + 0.5 * v.u for i in said]))]
        assert said == again and said[0] == int(first.argmax())


class _State:
    """What fill_windows needs of a group's state."""

    def __init__(self, value=None, timed_out=False):
        self.value, self.hasTimedOut, self.waits = value, timed_out, None

    exists = property(lambda self: self.value is not None)
    get = property(lambda self: self.value)

    def update(self, value):
        self.value = value

    def remove(self):
        self.value = None

    def setTimeoutDuration(self, ms):
        self.waits = ms


def test_windows_fill_over_batches_and_end_at_the_timeout():
    def turn(n, tokens):
        return pd.DataFrame({"turn": [n], "tokens": [tokens]})

    state = _State()
    first = pd.concat(streams.fill_windows((7,), iter([turn(1, [f"b{i}" for i in range(10)]), turn(0, [f"a{i}" for i in range(10)]), turn(2, None)]), state))
    assert first.values.tolist() == [[7, 0, "a0", 16]]
    assert state.value == (1, ["b6", "b7", "b8", "b9"])
    assert state.waits == 3_600_000
    state.hasTimedOut = True
    assert pd.concat(streams.fill_windows((7,), iter([]), state)).values.tolist() == [[7, 1, "b6", 4]]
    assert not state.exists
    full = _State((1, []), timed_out=True)
    assert list(streams.fill_windows((7,), iter([]), full)) == [] and not full.exists


def test_records_split_into_ranges_without_loss():
    for rows, parts in ((0, 3), (5, 8), (9000, 2)):
        reader = RepeatedRecords({"rows": str(rows), "parts": str(parts)}).reader(None)
        made = [r for p in reader.partitions() for batch in reader.read(p) for r in batch.to_pylist()]
        assert [r["seq_id"] for r in made] == list(range(rows))
        assert all(r["text"].count("record") == 1 + r["seq_id"] % 5 for r in made)
    with pytest.raises(ValueError):
        RepeatedRecords({"rows": "5", "parts": "0"}).reader(None)


@pytest.mark.skipif(not Path("/root/testdata/sf0.001").exists(), reason="no tables")
def test_bucketed_sides_join_without_a_shuffle(spark):
    df = relational.sink_bucketed_join(spark, "/root/testdata/sf0.001", 4)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan


def test_windows_fit_as_one_by_one():
    """Stacked windows get the groups that each gets alone, and features from the memo change none."""
    rng = np.random.default_rng(0)
    for _ in range(100):
        length, k = int(rng.integers(1, 17)), int(rng.integers(1, 6))
        m = int(rng.integers(1, length + 1))
        codes, z = rng.integers(0, int(rng.integers(1, 20)), (5, length)), rng.normal(size=(5, length, k))
        assert kernels.fit_windows(codes, z, m).tolist() == [kernels.fit_groups(c, y, m).tolist() for c, y in zip(codes, z, strict=True)]
    v = kernels.Vocabulary(rng.normal(size=(50, 64)))
    tokens = [f"w{i}" for i in rng.integers(0, 40, 90)]
    for opts in (CompressOptions(backend="local"), CompressOptions(rho=16)):
        a, b = kernels.compress(v(tokens), opts), kernels.compress(v(tokens), opts, 1.0, v.features(tokens, opts))
        assert [m.tolist() for m in a.members] == [m.tolist() for m in b.members]


def test_greedy_reads_a_context_once(monkeypatch):
    """Each step adds one prediction to those before: the same as reading everything anew, with one masked pass over the context."""
    rng = np.random.default_rng(1)
    v = kernels.Vocabulary(rng.normal(size=(80, 64)))
    x, calls, prefill = v([f"w{i}" for i in range(20)]), [], reader.prefill
    monkeypatch.setattr(reader, "prefill", lambda *a: calls.append(1) or prefill(*a))
    first, said = reader.greedy(reader.READERS["masked"], v.table, v, x, np.arange(20), 6)
    assert len(calls) == 1
    whole = reader.logits(reader.READERS["masked"], v.table, v.u, x, np.arange(20), np.array([np.sqrt(0.75) * v.table[i] + 0.5 * v.u for i in said]))
    assert np.allclose(first, whole[0]) and whole.argmax(axis=1).tolist() == said


def test_first_choices_without_sorting():
    rng = np.random.default_rng(2)
    z = rng.integers(0, 6, (40, 30)).astype(float)  # many ties
    for k in (1, 10, 30, 50):
        assert np.array_equal(reader._top(z, k), np.argsort(-z, axis=1, kind="stable")[:, :k])


@pytest.mark.parametrize("name", ["flat", "sliding", "narrow16", "masked"])
def test_contexts_are_continued_together(name):
    """Contexts of any lengths get what each gets alone, step by step from the whole table, and the first of equal rows."""
    rng = np.random.default_rng(4)
    e = rng.normal(size=(1300, 64))
    e[700:] = e[:600]  # every choice has an equal one behind it, in another tile
    v, model = kernels.Vocabulary(e), reader.READERS[name]
    contexts = [(v([f"w{i}" for i in rng.integers(0, 99, n)]), np.sort(rng.integers(0, 60, n))) for n in (1, 2, 17, 40, 3)]
    got = reader.continued(model, e, v, contexts, 5)
    g = reader.products(model, e, v.u)
    for (x, pos), (h, said) in zip(contexts, got, strict=True):
        after = np.array([np.sqrt(0.75) * e[i] + 0.5 * v.u for i in said])
        z = reader.logits(model, e, v.u, x, pos, after)
        assert said == [int(np.flatnonzero(row > row.max() - 1e-9)[0]) for row in z] and max(said) < 700
        assert model.gain**2 * (h @ g @ h) == pytest.approx(z[0] @ z[0])


def test_a_prompt_is_continued_once(monkeypatch):
    """Options that leave a prompt as it is share its continuation, and all prompts of a call go over the table together."""
    calls = []
    monkeypatch.setattr(reader, "first_choices", lambda e, h, f=reader.first_choices: calls.append(len(h)) or f(e, h))
    frame = pd.DataFrame({"seq_id": [1, 2], "tokens": [["a"] * 5, [f"t{i}" for i in range(40)]], "continuation": [["b"], ["c"]]})
    df = SimpleNamespace(sparkSession=SimpleNamespace(sparkContext=SimpleNamespace(broadcast=lambda e: SimpleNamespace(value=e))), select=lambda *a: SimpleNamespace(mapInPandas=lambda run, schema: run))
    configs = [(s, CompressOptions(rho=r, backend="chunk", position_scheme=s)) for s in ("max", "mean") for r in (1, 2)]
    (rows,) = studies.checks(df, np.random.default_rng(5).normal(size=(50, 64)), configs, reader.READERS["masked"], 3)(iter([frame]))
    assert len(rows) == 8 and (rows[rows["rho"] == 1]["same_text"] == 1).all()
    assert calls == [4, 4, 4]  # both prompts, and the second at a ratio of 2 by each scheme


def test_ratios_share_coordinates(monkeypatch):
    """Windows are hashed anew for each ratio, but their coordinates are those of the body and made once; groups stay."""
    calls = []
    monkeypatch.setattr(kernels, "coordinates", lambda phi, opts, f=kernels.coordinates: calls.append(len(phi)) or f(phi, opts))
    v = kernels.Vocabulary(np.random.default_rng(6).normal(size=(50, 64)))
    x, kept = v([f"w{i}" for i in range(70)]), {}
    all_opts = [CompressOptions(rho=r, backend="local", position_scheme=s) for r in (2, 4, 8, 16) for s in ("max", "mean")]
    shared = [kernels.compress(x, o, kept=kept) for o in all_opts]
    assert calls == [3, 1]  # whole windows and the last one
    for o, m in zip(all_opts, shared, strict=True):
        alone = kernels.compress(x, o)
        assert [a.tolist() for a in alone.members] == [a.tolist() for a in m.members] and alone.pos.tolist() == m.pos.tolist()


def test_near_rows_share_a_pass():
    """First choices of rows that differ by little or nothing are those of the whole product."""
    rng = np.random.default_rng(7)
    e = table(3000, 64, 8)
    base = rng.normal(size=(30, 64))
    h = np.concatenate([base, base * (1 + 1e-3), base + 0.005 * rng.normal(size=base.shape), base, 0 * base[:1]])
    assert len(np.unique(reader._leaders(h))) == 31
    assert np.array_equal(reader.first_choices(e, h), (h @ e.T).argmax(axis=1))


def test_the_original_is_read_once(monkeypatch):
    """What is compared of the prompt's own logits is taken once for all configurations."""
    calls = []
    monkeypatch.setattr(reader, "_top", lambda z, k, f=reader._top: calls.append(len(z)) or f(z, k))
    frame = pd.DataFrame({"seq_id": [1], "tokens": [[f"t{i}" for i in range(60)]], "continuation": [["b", "c", "d"]]})
    df = SimpleNamespace(sparkSession=SimpleNamespace(sparkContext=SimpleNamespace(broadcast=lambda e: SimpleNamespace(value=e))), select=lambda *a: SimpleNamespace(mapInPandas=lambda run, schema: run))
    configs = [(m, CompressOptions(renorm=m, backend="chunk")) for m in ("none", "member_mean", "table_mean", "prompt_mean")]
    (rows,) = evaluation.evaluate(df, table(50), configs, {"flat": reader.READERS["flat"]})(iter([frame]))
    assert len(rows) == 4 and calls == [3] * 5


def test_measures_follow_the_definitions():
    rng = np.random.default_rng(9)
    a, b, target = rng.normal(size=(6, 40)), rng.normal(size=(6, 40)), rng.integers(0, 40, 6)
    la, lb = reader.log_softmax(a), reader.log_softmax(b)
    got, at = reader.compare(a, b, target), np.arange(6)
    assert got["kl"] == pytest.approx((np.exp(la) * (la - lb)).sum(axis=1).mean(), abs=1e-12)
    assert got["delta_nll"] == pytest.approx((la[at, target] - lb[at, target]).mean(), abs=1e-12)
    assert got["ppl_ratio"] == pytest.approx(np.exp((la[at, target] - lb[at, target]).mean()))


def test_windows_of_prompts_are_taken_together(monkeypatch):
    """Coordinates of all prompts' windows of one length are made in one call for all ratios, and rows are those of each prompt alone."""
    calls = []
    monkeypatch.setattr(kernels, "coordinates", lambda phi, opts, f=kernels.coordinates: calls.append(phi.shape[:2]) or f(phi, opts))
    tokens = [[f"w{i % 31}" for i in range(n)] for n in (3, 15, 28, 12 + 48, 12 + 35, 12 + 3)]
    frame = pd.DataFrame({"seq_id": range(len(tokens)), "tokens": tokens})
    df = SimpleNamespace(sparkSession=SimpleNamespace(sparkContext=SimpleNamespace(broadcast=lambda e: SimpleNamespace(value=e))), select=lambda *a: SimpleNamespace(mapInPandas=lambda run, schema: run))
    configs = [("local", CompressOptions(rho=r, backend="local")) for r in (2, 4, 8, 16)]
    (rows,) = studies.summaries(df, e := table(50), configs)(iter([frame]))
    assert sorted(calls) == [(3, 3), (6, 16)]
    v = kernels.Vocabulary(e, 0.25, "trigram")
    for r in rows.itertuples():
        m = kernels.compress(v(tokens[r.seq_id]), CompressOptions(rho=r.rho, backend="local"), 1.0)
        group = np.empty(r.n_tokens, int)
        for i, own in enumerate(m.members):
            group[own] = i
        assert r.n_macro == len(m.pos) and r.distortion == pytest.approx(((v(tokens[r.seq_id]) - m.x[group]) ** 2).sum())
