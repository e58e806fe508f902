"""Repeated passages from a sparse suffix array.

Only suffixes that start at minimiser positions are kept: the least hash of every
window of w runs of k words. A passage of `words` words has its minimiser among its
first w places wherever it stands, and from there on all of its copies agree for
core = words - w + 1 words. Suffixes are brought together by this core. Those that
share it with another are extended to the left and to the right: each carries the
hashes of the windows of `words` words whose minimiser it is, these are sorted, and
equal neighbours are passages that stand elsewhere as a whole. A span is a union of
such windows, so nothing shorter than `words` words ever makes one.

A first pass counts cores. What it sends to the second is a bitmap of fixed size
over the shared ones: it lets through every shared core and some others, which then
meet nobody. Texts are read twice where they lie and never shuffled.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WORD, WordHashes, bitmap, gram_hashes, in_bitmap, settle, table, texts

_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 2**64)


@dataclass(frozen=True)
class Suffixes:
    #: Every repeated passage of so many words is found whole; shorter ones are not reported.
    words: int = 50
    window: int = 25
    run: int = 4
    #: Bits of the map of shared cores, a power of two.
    map_bits: int = 1 << 27
    #: Suffixes of one core that a task compares, about 13 MB; larger groups are compared window by window.
    group: int = 100_000
    #: Most cores treated so; with more of them larger groups stay in one task.
    large_cores: int = 1_000_000

    @property
    def core(self) -> int:
        return self.words - self.window + 1


_POWERS: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    """The first n + 1 powers modulo 2^64, remembered up to a million."""
    if base not in _POWERS or len(_POWERS[base]) <= n:
        out = np.full(max(n, 1 << 14) + 1, base, np.uint64)
        out[0] = 1
        out = np.multiply.accumulate(out)
        if n > 1 << 20:
            return out[: n + 1]
        _POWERS[base] = out
    return _POWERS[base][: n + 1]


def minimisers(words: np.ndarray, opts: Suffixes) -> np.ndarray:
    """For each window of opts.words words the place of its minimiser; of equal hashes the first. Never falls."""
    n = len(words) - opts.words + 1
    if n <= 0:
        return np.empty(0, np.int64)
    views = np.lib.stride_tricks.sliding_window_view(gram_hashes(words, opts.run), opts.window)[:n]
    return views.argmin(axis=1) + np.arange(n)


def core_hashes(words: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """Hashes of n words from each place, by differences of one running polynomial."""
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(words * _powers(_INVERSE, len(words))[: len(words)], dtype=np.uint64)])
    return (total[at + n] - total[at]) * _powers(_BASE, len(words))[at]


def suffixes(text: str, hashes: WordHashes, opts: Suffixes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all words; the places of the suffixes that are kept, and the first window of each."""
    words = hashes(WORD.findall(text.lower()))
    owner = minimisers(words, opts)
    first = np.flatnonzero(np.diff(owner, prepend=-1))
    return words, owner[first], first


def _cores(opts: Suffixes):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            for low in range(0, batch.num_rows, 512):
                found = [np.empty(0, np.uint64)]
                for t in texts(batch.column(0).slice(low, 512).to_pylist()):
                    words, at, _ = suffixes(t, hashes, opts)
                    if len(at):
                        found.append(core_hashes(words, at, opts.core))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(found).view(np.int64))], ["core"])

    return run


def _contexts(opts: Suffixes, sent):
    """The suffixes whose core may be shared, each with the hashes of its windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, (seen, large) = WordHashes(), sent.value
        for batch in batches:
            for begin in range(0, batch.num_rows, 512):
                part = batch.slice(begin, 512)
                of, pos, core, low, windows, sizes = ([] for _ in range(6))
                for d, t in enumerate(texts(part.column(3).to_pylist())):
                    words, at, first = suffixes(t, hashes, opts)
                    if not len(at):
                        continue
                    own = core_hashes(words, at, opts.core).view(np.int64)
                    keep = np.flatnonzero(in_bitmap(seen, own))
                    if not len(keep):
                        continue
                    n = np.diff(first, append=len(words) - opts.words + 1)[keep]
                    starts = np.repeat(first[keep] - np.cumsum(n) + n, n) + np.arange(n.sum())
                    of.append(np.full(len(keep), d))
                    pos.append(at[keep])
                    core.append(own[keep])
                    low.append(first[keep])
                    sizes.append(n)
                    windows.append(core_hashes(words, starts, opts.words).view(np.int64))
                if not of:
                    continue
                rows, cores = pa.array(np.concatenate(of)), np.concatenate(core)
                ends = np.concatenate([[0], np.cumsum(np.concatenate(sizes))]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([
                    pa.array(cores), *(part.column(i).take(rows) for i in range(3)), pa.array(np.concatenate(pos).astype(np.int32)), pa.array(np.concatenate(low).astype(np.int32)),
                    pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(windows))), pa.array(np.isin(cores, large)),
                ], ["core", "last", "_id", "said", "pos", "low", "windows", "large"])

    return run


def _meet(opts: Suffixes, most: int = 1 << 15):
    """The windows of each core's suffixes sorted, and equal neighbours joined; rows come sorted by core, then by rank."""

    def joined(rows: pa.Table) -> pa.RecordBatch | None:
        rows = rows.combine_chunks()
        windows = rows.column("windows").combine_chunks()
        n = np.diff(windows.offsets.to_numpy())
        row = np.repeat(np.arange(rows.num_rows), n)
        start = np.repeat(rows.column("low").to_numpy() - np.cumsum(n) + n, n) + np.arange(n.sum())
        key = windows.flatten().to_numpy()
        # one core's windows are no other's; a row that repeats is no other place
        same = np.zeros(rows.num_rows, bool)
        for c in ("core", "said", "pos", "_id"):
            column = rows.column(c).combine_chunks()
            a, b = column[1:], column[:-1]
            equal = np.asarray(pc.fill_null(pc.equal(a, b), False)) | np.asarray(pc.and_(a.is_null(), b.is_null()))
            same[1:] = equal if c == "core" else same[1:] & equal
        alive = np.flatnonzero(~same[row])
        row, start, key = row[alive], start[alive], key[alive]
        _, first, back, count = np.unique(key, return_index=True, return_inverse=True, return_counts=True)
        at = np.flatnonzero(count[back] > 1)
        origin = first[back[at]]
        later = origin != at
        if not len(at):
            return None
        own, begin = np.unique(row[at], return_index=True)
        last = np.append(begin[1:], len(at)) - 1
        s = start[at]
        later_from = np.minimum.reduceat(np.where(later, s, np.iinfo(np.int64).max), begin)
        later_to = np.maximum.reduceat(np.where(later, s + opts.words, -1), begin)
        take = pa.array(own)
        ids = rows.column("_id").combine_chunks()
        none = later_to < 0
        return pa.RecordBatch.from_arrays([
            ids.take(take), rows.column("said").combine_chunks().take(take), pa.array(s[begin].astype(np.int32)), pa.array((s[last] + opts.words).astype(np.int32)),
            pa.array(np.where(none, 0, later_from).astype(np.int32), mask=none), pa.array(np.where(none, 0, later_to).astype(np.int32), mask=none),
            ids.take(pa.array(row[origin[begin]])), pa.array(start[origin[begin]].astype(np.int32)),
        ], ["_id", "said", "a", "b", "later_a", "later_b", "first_id", "first_word"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            core = batch.column("core").to_numpy()
            # the last core may go on in the next batch; what is before it is whole
            whole = int(np.flatnonzero(core != core[-1])[-1]) + 1 if core[0] != core[-1] else 0
            done: list[pa.RecordBatch] = []
            if held and not whole and held[-1].column("core")[-1].as_py() != core[0]:
                done, held = held, []
            elif whole and sum(b.num_rows for b in held) + whole >= most:
                done, held, batch = [*held, batch.slice(0, whole)], [], batch.slice(whole)
            held.append(batch)
            if done and (out := joined(pa.Table.from_batches(done))) is not None:
                yield out
        if held and (out := joined(pa.Table.from_batches(held))) is not None:
            yield out

    return run


_SPAN = "a int, b int, later_a int, later_b int, first_id {kind}, first_word int"


def _window_by_window(rows: DataFrame, opts: Suffixes) -> DataFrame:
    """The same for large groups: equal windows are aggregated where they lie, and the frequent ones sent out."""
    each = settle(rows.select("last", "_id", "said", F.col("low"), F.posexplode("windows").alias("k", "key")).select("last", "_id", "said", (F.col("low") + F.col("k")).alias("s"), "key"), "windows")
    place = F.struct("last", "_id", "said", "s")
    shared = settle(each.groupBy("key").agg(F.count("*").alias("n"), F.min(place).alias("first"), F.max(place).alias("final")).filter("first <> final").select("key", "n", "first"), "keys")
    often = F.col("n") * 1000 >= (shared.agg(F.sum("n")).first()[0] or 0)  # at most a thousand
    hot, cold = shared.filter(often), shared.filter(~often)
    met = each.join(F.broadcast(hot), "key").unionByName(each.join(F.broadcast(hot.select("key")), "key", "left_anti").join(cold, "key"))
    later = ~(F.col("first._id").eqNullSafe(F.col("_id")) & (F.col("first.said") == F.col("said")) & (F.col("first.s") == F.col("s")))
    met = met.select("_id", "said", "s", F.col("s").alias("a"), (F.col("s") + opts.words).alias("b"), F.when(later, F.col("s")).alias("later_a"), F.when(later, F.col("s") + opts.words).alias("later_b"), F.col("first._id").alias("first_id"), F.col("first.s").alias("first_word"))
    return met.drop("s")


def _merged(kind: pa.DataType):
    """Overlapping spans of a text joined: all of them, and those that stand earlier too."""

    def join(spans: list[tuple], later: bool) -> list[list]:
        out: list[list] = []
        for a, b, *first in sorted(spans, key=lambda s: s[:2]):
            if out and (a < out[-1][1] or later and a == out[-1][1]):
                out[-1][1] = max(out[-1][1], b)
            else:
                out.append([a, b, *first])
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            of, rows = [], []
            for d, spans in enumerate(batch.column(2).to_pylist()):
                for a, b, first_id, first_word in join([(s["a"], s["b"], s["first_id"], s["first_word"]) for s in spans], False):
                    of.append(d)
                    rows.append((False, a, b, first_id, first_word))
                for a, b in join([(s["later_a"], s["later_b"]) for s in spans if s["later_a"] is not None], True):
                    of.append(d)
                    rows.append((True, a, b, None, None))
            columns = list(zip(*rows, strict=True)) or [()] * 5
            kinds = (pa.bool_(), pa.int32(), pa.int32(), kind, pa.int32())
            take = pa.array(of, pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(take), batch.column(1).take(take), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], ["_id", "said", "later", "a", "b", "first_id", "first_word"])

    return run


def _spans(df: DataFrame, key: str, text: str, opts: Suffixes) -> DataFrame:
    """_id, said (the text's hash), later (whether an earlier place holds every part of it), a, b, first_id, first_word."""
    spark, kind = df.sparkSession, df.schema[key].dataType.simpleString()
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    docs = df.select(F.col(key).isNull().alias("last"), F.col(key).alias("_id"), F.col(text).cast("string").alias("_text"))
    cores = docs.select("_text").mapInArrow(_cores(opts), "core long").groupBy("core").agg(F.count("*").alias("n"))
    shared = settle(cores.filter("n > 1"), "cores")
    total = shared.agg(F.sum("n")).first()[0] or 0
    large = shared.filter(F.col("n") > max(opts.group, total // opts.large_cores)).select("core").toArrow().column("core").to_numpy()  # at most large_cores
    sent = spark.sparkContext.broadcast((bitmap(shared, "core", opts.map_bits), large))
    rows = docs.select("last", "_id", F.xxhash64("_text").alias("said"), "_text").mapInArrow(_contexts(opts, sent), f"core long, last boolean, _id {kind}, said long, pos int, low int, windows array<long>, large boolean")
    if len(large):  # read twice then
        rows = settle(rows, "contexts")
    near = rows.filter("NOT large").drop("large").repartition(parts, "core").sortWithinPartitions("core", "last", "_id", "said", "pos")
    found = near.mapInArrow(_meet(opts), f"_id {kind}, said long, {_SPAN.format(kind=kind)}")
    if len(large):
        found = found.unionByName(_window_by_window(rows.filter("large"), opts))
    each = found.groupBy("_id", "said").agg(F.collect_list(F.struct("a", "b", "later_a", "later_b", "first_id", "first_word")).alias("spans"))
    arrow = {"bigint": pa.int64(), "int": pa.int32()}.get(kind, pa.string())
    return settle(each.mapInArrow(_merged(arrow), f"_id {kind}, said long, later boolean, a int, b int, first_id {kind}, first_word int"), "spans")


def repeated_passages(df: DataFrame, key: str = "doc_id", text: str = "text", opts: Suffixes = Suffixes()) -> DataFrame:
    """Spans of words that stand elsewhere too: key, start_word, n_words, first_<key>, first_word.

    Every passage of at least opts.words words that occurs twice, in one text or
    in two, is covered at all its places, and every word of a span is in such a
    passage. Overlapping passages make one span. Words are compared in lower case.
    first_<key> and first_word name the earliest place of the span's first
    opts.words words, which for the earliest copy is the span itself. Null and
    short texts have none; null keys rank last; rows that repeat a key and its text
    count as one document, other texts under the key are documents of their own.
    Very long texts are covered whole; ties between equal passages go to the lower
    key, then the text's hash, then the place. Other columns are not looked at.
    """
    spans = _spans(df, key, text, opts).filter("NOT later")
    return spans.select(F.col("_id").alias(key), F.col("a").alias("start_word"), (F.col("b") - F.col("a")).alias("n_words"), F.col("first_id").alias(f"first_{key}"), "first_word")


def later_passages(df: DataFrame, key: str = "doc_id", text: str = "text", opts: Suffixes = Suffixes()) -> DataFrame:
    """The words that an earlier place holds as part of a repeated passage: _id, said (the text's hash), start, length in words."""
    return _spans(df, key, text, opts).filter("later").select("_id", "said", F.col("a").alias("start"), (F.col("b") - F.col("a")).alias("length"))


def op7_sparse_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_passages(table(spark, sf_dir, "documents").select("doc_id", "text"))
