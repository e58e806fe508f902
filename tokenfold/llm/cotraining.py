"""Co-training of two views of a document, text and metadata.

Both views start from the labelled rows. In each round each view gives the other the
unlabelled documents of which it is surest, as further examples. Afterwards each
view is calibrated on labelled rows that neither has seen, and the calibrated log
odds are combined. Fitting reads at most `labelled` labelled rows, those with the
least hashes of their ids; each round scores all unlabelled documents where they lie
and takes the surest of each class among them.
"""

from __future__ import annotations

import re
from collections.abc import Generator, Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import MEMO_WORDS, WORD, settle, table, texts


@dataclass(frozen=True)
class CoTraining:
    #: Labelled documents that fitting gathers.
    labelled: int = 6000
    #: Bounds nothing: all unlabelled documents take part. Callers may still name it.
    pool: int = 4000
    rounds: int = 3
    #: Examples that a view gives in a round, of each class, and how sure it must be.
    gives: int = 200
    sure: float = 0.95
    #: Most of its error that may be left of the class's share in the labelled rows.
    gain: float = 0.1
    bits: int = 16
    held_out: float = 0.3
    steps: int = 100
    l2: float = 1e-5


_STRIP = re.compile(r"^\W+|\W+$")
_SHAPES = ((re.compile(r"[^\W\d_]+"), lambda m: "A" if m[0].isupper() and len(m[0]) > 1 else "a"), (re.compile(r"\d+"), lambda m: "0"))


def _bucket(x: float, steps: int) -> int:
    return int(min(steps - 1, max(0, x * steps)))


class TextView:
    """Hashed features of the words, their shapes and how often they repeat; each counts once."""

    def __init__(self, bits: int):
        self.mask, self.memo = (1 << bits) - 1, {}

    def _dim(self, kind: str, name: str) -> int:
        return xxhash.xxh3_64_intdigest(f"{kind}\0{name}".encode("utf-8", "surrogatepass")) & self.mask

    def _word(self, word: str) -> tuple[int, int]:
        shape = word
        for pattern, to in _SHAPES:
            shape = pattern.sub(to, shape)
        return self._dim("word", _STRIP.sub("", word).lower()), self._dim("shape", shape[:12])

    def __call__(self, text: str) -> np.ndarray:
        words = WORD.findall(text)
        own, memo = set(words), self.memo
        if len(memo) > MEMO_WORDS:
            memo.clear()
        dims = set()
        for w in own:
            got = memo.get(w)
            if got is None:
                got = memo[w] = self._word(w)
            dims.update(got)
        n = max(1, len(words))
        dims.add(self._dim("unique", f"{_bucket(len(own) / n, 10)}-{min(4, n.bit_length() // 3)}"))
        dims.add(self._dim("length", str(n.bit_length())))
        return np.fromiter(sorted(dims), np.int64, len(dims))


class MetaView:
    """Hashed features of language, source, size and layout; nothing of the words themselves."""

    def __init__(self, bits: int):
        self.mask = (1 << bits) - 1

    def __call__(self, text: str, lang: object, source: object, n_chars: object) -> np.ndarray:
        lines = text.split("\n")
        n, k = max(1, len(text)), len(lines)
        letters, digits, spaces = sum(map(len, re.findall(r"[^\W\d_]+", text))), sum(map(len, re.findall(r"\d+", text))), text.count(" ") + k - 1
        ends = sum(line.rstrip().endswith((".", "!", "?", ":", '"')) for line in lines)
        said = {
            "lang": lang, "source": source, "chars": int(n_chars or 0).bit_length() if n_chars is not None and n_chars == n_chars else None,
            "lines": k.bit_length(), "line": (n // k).bit_length(), "ends": _bucket(ends / k, 5), "letters": _bucket(letters / n, 20),
            "digits": _bucket(digits / n * 4, 12), "spaces": _bucket(spaces / n * 2, 20), "other": _bucket((n - letters - digits - spaces) / n * 3, 24),
            "first": _bucket(len(lines[0]) / n, 4), "blank": _bucket(sum(not x.strip() for x in lines) / k, 5),
        }
        return np.array(sorted({xxhash.xxh3_64_intdigest(f"{a}={b}".encode("utf-8", "surrogatepass")) & self.mask for a, b in said.items()}), np.int64)


@dataclass
class Model:
    weights: np.ndarray
    bias: float

    def odds(self, rows: list[np.ndarray]) -> np.ndarray:
        """Log odds of each row of features, whose weights are shared out by the root of their number."""
        if not rows:
            return np.empty(0)
        n = np.array([len(r) for r in rows])
        total = np.add.reduceat(self.weights[np.concatenate(rows)], np.concatenate([[0], np.cumsum(n)[:-1]]))
        return total / np.sqrt(n) + self.bias


def fit(rows: list[np.ndarray], y: np.ndarray, dims: int, opts: CoTraining) -> Model:
    """Logistic regression by full-batch steps of Adagrad, classes weighted alike.

    Each feature is scaled by its log ratio of frequencies in the two classes, so
    that a few telling words outweigh the many that say nothing.
    """
    w, bias = np.zeros(dims), 0.0
    if not len(rows) or len(np.unique(y)) < 2:
        p = float(np.clip(y.mean() if len(y) else 0.5, 0.01, 0.99))
        return Model(w, float(np.log(p / (1 - p))))
    n = np.array([len(r) for r in rows])
    at, start = np.concatenate(rows), np.concatenate([[0], np.cumsum(n)[:-1]])
    used, at = np.unique(at, return_inverse=True)
    scale, own = 1 / np.sqrt(n), np.repeat(np.arange(len(rows)), n)
    share = np.where(y > 0, 0.5 / max(1, y.sum()), 0.5 / max(1, (1 - y).sum()))
    ratio = np.log((np.bincount(at, y[own], len(used)) + 0.5) / (y.sum() + 1)) - np.log((np.bincount(at, 1 - y[own], len(used)) + 0.5) / ((1 - y).sum() + 1))
    v, seen, seen_bias = np.ones(len(used)), np.full(len(used), 1e-8), 1e-8
    for _ in range(opts.steps):
        z = np.add.reduceat((v * ratio)[at], start) * scale + bias
        e = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) * share
        g = np.bincount(at, (e * scale)[own], minlength=len(used)) * ratio + opts.l2 * v
        gb = e.sum()
        seen, seen_bias = seen + g * g, seen_bias + gb * gb
        v -= 0.5 * g / np.sqrt(seen)
        bias -= 0.5 * gb / np.sqrt(seen_bias)
    w[used] = v * ratio
    return Model(w, float(bias))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def scale_odds(x: np.ndarray, y: np.ndarray, steps: int = 25) -> np.ndarray:
    """Coefficients of a small logistic model by Newton's method, the last for the constant; x has a column for each input."""
    x = np.column_stack([x, np.ones(len(y))])
    c = np.zeros(x.shape[1])
    c[:-1] = 1 / (x.shape[1] - 1)
    if len(np.unique(y)) < 2:
        return c
    for _ in range(steps):
        p = _sigmoid(x @ c)
        h = (x * (p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(len(c))
        c -= np.linalg.solve(h, x.T @ (p - y) + 1e-2 * (c - np.array([*[0.0] * (len(c) - 1), 0.0])))
    return c


@dataclass
class Pair:
    """The views of one label: models, calibrations, and the weights of the calibrated log odds."""

    views: list[Model]
    calibrations: list[np.ndarray]
    combined: np.ndarray
    given: list[int] = field(default_factory=list)

    def view(self, i: int, rows: list[np.ndarray]) -> np.ndarray:
        a, b = self.calibrations[i]
        return self.views[i].odds(rows) * a + b

    def __call__(self, text: list[np.ndarray], meta: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Probabilities of both views together and of each alone."""
        t, m = self.view(0, text), self.view(1, meta)
        return _sigmoid(t * self.combined[0] + m * self.combined[1] + self.combined[2]), _sigmoid(t), _sigmoid(m)


def _training(text: list[np.ndarray], meta: list[np.ndarray], y: np.ndarray, opts: CoTraining) -> Generator:
    """Fit both views on rows whose order is random already; the last ones are held out for calibration.

    Yields models, calibrations and how sure a view must be of each label; is sent, for
    each view, the features (of the other view) and labels that it gives, or None to stop.
    """
    dims, cut = 1 << opts.bits, max(1, int(len(y) * (1 - opts.held_out)))
    own, held = [text[:cut], meta[:cut]], [text[cut:], meta[cut:]]
    extra: list[tuple[list, list]] = [([], []), ([], [])]  # pseudo-labels that each view has got from the other
    given = [0, 0]
    for step in range(opts.rounds + 1):
        models = [fit(own[v] + extra[v][0], np.concatenate([y[:cut], extra[v][1]]), dims, opts) for v in (0, 1)]
        calibrations = [scale_odds(models[v].odds(held[v])[:, None], y[cut:]) if len(held[v]) else np.array([1.0, 0.0]) for v in (0, 1)]
        if step == opts.rounds or not len(y):
            break
        base = y[:cut].mean()
        new = yield models, calibrations, {label: max(opts.sure, 1 - opts.gain * (1 - b)) for label, b in ((0.0, 1 - base), (1.0, base))}  # a common class is no news
        if new is None:
            break
        for v in (0, 1):
            extra[1 - v][0].extend(new[v][0])
            extra[1 - v][1].extend(new[v][1])
            given[v] += len(new[v][0])
    both = np.column_stack([models[v].odds(held[v]) * calibrations[v][0] + calibrations[v][1] for v in (0, 1)]) if held[0] else np.zeros((0, 2))
    return Pair(models, calibrations, scale_odds(both, y[cut:]) if len(both) else np.array([0.5, 0.5, 0.0]), given)


def _next(training: Generator, new: object = None) -> tuple[object, Pair | None]:
    """The next state of a training, or its result."""
    try:
        return training.send(new), None
    except StopIteration as end:
        return None, end.value


def co_train(text: list[np.ndarray], meta: list[np.ndarray], y: np.ndarray, pool_text: list[np.ndarray], pool_meta: list[np.ndarray], opts: CoTraining) -> Pair:
    """Co-training with unlabelled rows in memory."""
    pool, training, taken = [pool_text, pool_meta], _training(text, meta, y, opts), (set(), set())
    state, pair = _next(training)
    while pair is None:
        models, calibrations, least = state
        new = ([], []), ([], [])
        for v in (0, 1) if pool[0] else ():
            p = _sigmoid(models[v].odds(pool[v]) * calibrations[v][0] + calibrations[v][1])
            for label in (0.0, 1.0):
                sure = p if label else 1 - p
                got = [i for i in np.argsort(-sure, kind="stable").tolist() if sure[i] >= least[label] and i not in taken[v]][: opts.gives]
                taken[v].update(got)
                new[v][0].extend(pool[1 - v][i] for i in got)
                new[v][1].extend([label] * len(got))
        state, pair = _next(training, new if pool[0] else None)
    return pair


def _featured(docs: DataFrame, key: str, opts: CoTraining) -> DataFrame:
    """_id, its hash, and the features of both views as 32-bit integers, written once for all passes."""

    def features(columns: Iterator[tuple[pd.Series, ...]]) -> Iterator[pd.DataFrame]:
        text, meta = TextView(opts.bits), MetaView(opts.bits)
        for ts, langs, sources, sizes in columns:
            ts = texts(ts)
            yield pd.DataFrame({
                "t": [text(t).astype("<i4").tobytes() for t in ts],
                "m": [meta(*r).astype("<i4").tobytes() for r in zip(ts, langs, sources, sizes, strict=True)],
            })

    features.__annotations__ = {"columns": Iterator[tuple[pd.Series, ...]], "return": Iterator[pd.DataFrame]}
    made = docs.select(F.col(key).alias("_id"), F.xxhash64(key).alias("_hash"), F.pandas_udf(features, "t binary, m binary").asNondeterministic()("text", "lang", "source", "n_chars").alias("_f"))
    return settle(made.select("_id", "_hash", "_f.t", "_f.m"), "features")


def _rows(column: pd.Series) -> list[np.ndarray]:
    return [np.frombuffer(x, "<i4").astype(np.int64) for x in column]


def _surest(other: DataFrame, states: dict[str, tuple], taken: dict[tuple[str, int], set], opts: CoTraining) -> DataFrame:
    """target, view, label, _id: of all unlabelled documents those of which each view is surest, at most `gives` of each label."""
    sent = other.sparkSession.sparkContext.broadcast((states, taken))

    def best(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        states, taken = sent.value
        for frame in frames:
            rows = _rows(frame["t"]), _rows(frame["m"])
            for target, (models, calibrations, least) in states.items():
                for v in (0, 1):
                    p = _sigmoid(models[v].odds(rows[v]) * calibrations[v][0] + calibrations[v][1])
                    for label in (0.0, 1.0):
                        sure = p if label else 1 - p
                        out = frame[["_id", "_hash"]].assign(target=target, view=v, label=label, sure=sure)[sure >= least[label]]
                        out = out[~out["_id"].isin(taken[target, v])].sort_values(["sure", "_hash", "_id"], ascending=[False, True, True])
                        yield out.drop_duplicates("_id")[: opts.gives]

    kind = other.schema["_id"].dataType.simpleString()
    found = other.mapInPandas(best, f"_id {kind}, _hash long, target string, view int, label double, sure double")
    found = settle(found.groupBy("target", "view", "label", "_id", "_hash").agg(F.max("sure").alias("sure")), "surest")
    parts = [
        found.filter((F.col("target") == t) & (F.col("view") == v) & (F.col("label") == label)).orderBy(F.desc("sure"), "_hash", "_id").limit(opts.gives)
        for t in states for v in (0, 1) for label in (0.0, 1.0)
    ]
    return reduce(DataFrame.unionByName, parts).select("target", "view", "label", "_id", "sure")


def _unlabelled(featured: DataFrame, said: DataFrame) -> DataFrame:
    """Documents without a label. Both sides are dealt by id at any size: labels grow with the documents and are sent to no executor whole."""
    return featured.join(said.select("_id").hint("merge"), "_id", "left_anti")


def fit_views(docs: DataFrame, labels: DataFrame, targets: list[str], key: str = "doc_id", opts: CoTraining = CoTraining(), featured: DataFrame | None = None) -> dict[str, Pair]:
    """One pair of views for each label column. Null labels are left out; several of one document are averaged.

    In each round all unlabelled documents are scored where they lie.
    """
    said = labels.groupBy(key).agg(*(F.avg(t).alias(t) for t in targets)).filter(F.col(key).isNotNull()).withColumnRenamed(key, "_id")
    featured = (featured if featured is not None else _featured(docs, key, opts)).filter("_id IS NOT NULL")
    chosen = said.orderBy(F.xxhash64("_id"), "_id").limit(opts.labelled)
    known = featured.join(F.broadcast(chosen), "_id").toPandas().sort_values(["t", "m"]).drop_duplicates("_id")
    known = known.sort_values("_id", key=lambda c: c.map(lambda x: xxhash.xxh3_64_intdigest(str(x))))  # one order whatever the order of arrival
    text, meta = _rows(known["t"]), _rows(known["m"])
    other = settle(_unlabelled(featured, said), "unlabelled")
    trainings, states, out, taken = {}, {}, {}, {(t, v): set() for t in targets for v in (0, 1)}

    def move(t: str, new: object = None) -> None:
        state, pair = _next(trainings[t], new)
        if pair is None:
            states[t] = state
        else:
            states.pop(t, None)
            out[t] = pair

    for t in targets:
        at = np.flatnonzero(known[t].notna().to_numpy()) if len(known) else np.empty(0, int)
        y = (known[t].to_numpy(dtype=float)[at] >= 0.5).astype(float) if len(at) else np.empty(0)
        trainings[t] = _training([text[i] for i in at], [meta[i] for i in at], y, opts)
        move(t)
    while states:
        won = _surest(other, states, taken, opts).toPandas()
        ids = other.sparkSession.createDataFrame([(x,) for x in dict.fromkeys(won["_id"].tolist())], other.select("_id").schema)
        rows = other.join(F.broadcast(ids), "_id").groupBy("_id").agg(F.min(F.struct("t", "m")).alias("f")).select("_id", "f.t", "f.m").toPandas()
        won = won.merge(rows, on="_id").sort_values(["label", "sure", "_id"], ascending=[True, False, True])
        for t in list(states):
            new = []
            for v in (0, 1):
                own = won[(won["target"] == t) & (won["view"] == v)]
                taken[t, v].update(own["_id"].tolist())
                new.append((_rows(own["m" if v == 0 else "t"]), own["label"].tolist()))
            move(t, new)
    return {t: out[t] for t in targets}


def classify(docs: DataFrame, labels: DataFrame, targets: list[str], key: str = "doc_id", opts: CoTraining = CoTraining()) -> DataFrame:
    """Every document's probability of each label, by both views together and by each alone.

    Columns: key and for each target t: t, t_text, t_metadata. Null texts count as
    empty, null metadata as a value of its own; repeated rows are scored each. With
    no usable label all documents get one probability.
    """
    featured = _featured(docs, key, opts)
    sent = docs.sparkSession.sparkContext.broadcast(fit_views(docs, labels, targets, key, opts, featured))
    schema = ", ".join(f"`{t}` double, `{t}_text` double, `{t}_metadata` double" for t in targets)

    def score(columns: Iterator[tuple[pd.Series, ...]]) -> Iterator[pd.DataFrame]:
        for ts, ms in columns:
            a, b = _rows(ts), _rows(ms)
            out = {}
            for t, pair in sent.value.items():
                out[t], out[f"{t}_text"], out[f"{t}_metadata"] = pair(a, b)
            yield pd.DataFrame(out)

    score.__annotations__ = {"columns": Iterator[tuple[pd.Series, ...]], "return": Iterator[pd.DataFrame]}
    scored = featured.select(F.col("_id").alias(key), F.pandas_udf(score, schema).asNondeterministic()("t", "m").alias("_p"))
    return scored.select(key, "_p.*")


def op6_cotraining(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality and toxicity of every document; kept: good and not toxic, each at even odds."""
    scored = classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ["quality", "toxic"])
    return scored.withColumn("kept", (F.col("quality") >= 0.5) & (F.col("toxic") < 0.5))
