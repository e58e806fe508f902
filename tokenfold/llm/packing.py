"""Packing by lexical retrieval.

Documents become token ids. The leading term of each document, the rarest of those
that it shares with another under document frequencies of the whole corpus, routes
it to a shard, so that documents about the same words meet; a term with more tokens than a shard
holds is dealt over several shards, and rare terms share one. Each shard builds an
inverted index over the rests of its documents that do not fill a window of their
own. A seed asks the index for its unused neighbours, which fill the seed's window
from the best one down; the last is cut at the window's end and its other part
stays in the pool. Only the last window of a shard can stay short; it is cut into
powers of two, so that nothing is padded.

Frequencies are a row for each id of the vocabulary, so what the driver gathers and
sends out is bounded by the vocabulary and the number of tasks, not by the corpus.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from .common import MEMO_WORDS, settle, table


@dataclass(frozen=True)
class Packing:
    window: int = 2048
    end_id: int = 1
    #: Tokens for which a shard is laid out; a task holds about this many.
    shard_tokens: int = 1 << 20
    #: Terms of a seed that its query keeps, by weight.
    query_terms: int = 24
    k1: float = 1.2
    b: float = 0.75


class WordIds:
    """Ids of texts as little-endian 16-bit (or 32-bit) integers; white-space runs are remembered.

    The tokenizer's patterns never reach over white space, so the ids of a text are
    those of its runs in turn. Control characters that Python splits at and the
    tokenizer does not send a text through the tokenizer whole.
    """

    def __init__(self, path: str, most: int = 3 * MEMO_WORDS):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        self.tokenizer = Tokenizer.from_file(path)
        self.size = self.tokenizer.get_vocab_size()
        self.dtype = np.dtype("<u2" if self.size <= 1 << 16 else "<u4")
        self.memo: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.most = most // 2
        ends = self.tokenizer.get_vocab().items()
        self.closes = np.zeros(self.size, bool)
        self.closes[[i for w, i in ends if w.endswith("</w>")]] = True
        self.tails = {t: self.tokenizer.encode(t, add_special_tokens=False).ids[0] for t in ".,"}

    def _pack(self, ids: list[int]) -> bytes:
        return np.array(ids, self.dtype).tobytes()

    def _whole(self, text: str) -> bytes:
        return self._pack(self.tokenizer.encode(text, add_special_tokens=False).ids)

    def _learn(self, runs: list[str], words: np.ndarray) -> None:
        """Remember the ids of new runs; words tells which are letters alone.

        Those are one word each, and are encoded many at a time: a word's last id, and no
        other, ends in the mark of a word's end.
        """
        memo, others = self.memo, [r for r, w in zip(runs, words.tolist(), strict=True) if not w]
        listed = [r for r, w in zip(runs, words.tolist(), strict=True) if w]
        for low in range(0, len(listed), 200):
            some = listed[low : low + 200]
            ids = np.array(self.tokenizer.encode(" ".join(some), add_special_tokens=False).ids, self.dtype)
            ends = np.flatnonzero(self.closes[ids]) + 1
            if len(ends) != len(some):
                others += some
                continue
            packed, at = ids.tobytes(), 0
            for w, end in zip(some, (ends * self.dtype.itemsize).tolist(), strict=True):
                memo[w] = packed[at:end]
                at = end
        for w, e in zip(others, self.tokenizer.encode_batch_fast(others, add_special_tokens=False), strict=True):
            memo[w] = self._pack(e.ids)

    def _known(self, column: pa.Array, plain: pa.Array) -> list[bytes]:
        """Ids of distinct runs; plain: whether lower case is all that normalising does to a run."""
        if len(self.memo) > self.most:
            self.old, self.memo = self.memo, {}
        runs = column.to_pylist()
        got = list(map(self.memo.get, runs))
        new = [i for i, g in enumerate(got) if g is None]
        if new and self.old:
            for i in new:
                if (known := self.old.get(runs[i])) is not None:
                    self.memo[runs[i]] = got[i] = known
            new = [i for i in new if got[i] is None]
        if new:
            at = pa.array(new)
            letters = pc.and_(plain.take(at), pc.match_substring_regex(column.take(at), r"^\p{L}+$"))
            self._learn([runs[i] for i in new], letters.to_numpy(zero_copy_only=False))
            for i in new:
                got[i] = self.memo[runs[i]]
        return got

    def _runs(self, runs: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Number of ids of each run, and all ids one run after another.

        A capital, or one full stop or comma after a letter, leaves the other ids as they
        are, so runs that differ only in these share one look-up. Only letters up to
        U+024F are treated so: these are composed, and but for U+0130 change one by one.
        """
        plain = pc.invert(pc.match_substring_regex(runs, "[^\\x{0}-\\x{24F}]|\\x{130}"))
        stopped = pc.and_(plain, pc.match_substring_regex(runs, r"\p{L}[.,]$"))
        low = pc.if_else(plain, pc.utf8_lower(runs), runs)
        bare = pc.if_else(stopped, pc.utf8_slice_codeunits(low, 0, -1), low).dictionary_encode()
        codes = bare.indices.to_numpy()
        some = np.empty(len(bare.dictionary), np.int64)
        some[codes] = np.arange(len(codes))  # any run of each
        known = self._known(bare.dictionary, plain.take(pa.array(some)))
        size = np.array([len(k) for k in known], np.int64) // self.dtype.itemsize
        start, ids = np.cumsum(size) - size, np.frombuffer(b"".join(known), self.dtype)
        stop = np.flatnonzero(stopped.to_numpy(zero_copy_only=False))
        n = size[codes]
        n[stop] += 1
        before = np.cumsum(n) - n
        at = np.repeat(start[codes] - before, n) + np.arange(n.sum())
        last = (before + n - 1)[stop]
        at[last] = 0
        out = ids[at] if len(ids) else np.zeros(len(at), self.dtype)
        point = pc.ends_with(runs.take(pa.array(stop)), ".").to_numpy(zero_copy_only=False)
        out[last] = np.where(point, self.tails["."], self.tails[","])
        return n, out

    def __call__(self, column: pa.Array, end: list[int] | None = None) -> tuple[np.ndarray, pa.Array]:
        """How many ids each text has, and the ids, with those of `end` after each text. Null counts as empty."""
        column = pc.fill_null(column, "")
        odd = pc.match_substring_regex(column, "[\x1c-\x1f]")
        spread = pc.utf8_split_whitespace(pc.if_else(odd, "", column))
        coded = spread.flatten().dictionary_encode()
        size, ids = self._runs(coded.dictionary)
        start = np.cumsum(size) - size
        codes = coded.indices.to_numpy()
        n = size[codes]
        before = np.concatenate([[0], np.cumsum(n)])
        flat = ids[np.repeat(start[codes] - before[:-1], n) + np.arange(before[-1])]
        edge = before[spread.offsets.to_numpy() - spread.offsets[0].as_py()]
        tail = np.array(end or [], self.dtype)
        rows = odd.to_numpy(zero_copy_only=False)
        if rows.any() or len(tail) > 1:
            parts = [np.frombuffer(self._whole(column[i].as_py()), self.dtype) if rows[i] else flat[edge[i] : edge[i + 1]] for i in range(len(column))]
            parts = [np.concatenate([p, tail]) for p in parts]
            lengths, flat = np.array([len(p) for p in parts], np.int64), np.concatenate(parts) if parts else flat
        else:
            lengths = np.diff(edge) + len(tail)
            flat = np.insert(flat, edge[1:], tail[0]) if len(tail) else flat
        ends = np.concatenate([[0], np.cumsum(lengths)]) * self.dtype.itemsize
        return lengths, pa.Array.from_buffers(pa.large_binary(), len(lengths), [None, pa.py_buffer(ends.astype(np.int64)), pa.py_buffer(np.ascontiguousarray(flat))]).cast(pa.binary())


def _tokenise(path: str, end_id: int, rows: int = 2048, most: int = 1 << 23):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = WordIds(path)
        for batch in batches:
            step = max(1, min(rows, most * batch.num_rows // max(1, batch.nbytes)))  # about as many bytes at once
            for at in range(0, batch.num_rows, step):
                part = batch.slice(at, step)
                lengths, ids = words(part.column(1), [end_id])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(lengths), ids], ["_id", "n", "ids"])

    return run


def _frequencies(dtype: str, size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df = np.zeros(size, np.int64)
        for batch in batches:
            for ids in batch.column(0):
                terms = np.sort(np.frombuffer(ids.as_buffer(), dtype), kind="stable")
                df[terms[np.flatnonzero(np.diff(terms, prepend=terms[:1] - terms.dtype.type(1)))]] += 1
        terms = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(terms, pa.int32()), pa.array(df[terms])], ["term", "df"])

    return run


class Weights:
    """BM25 weights of the terms of one piece of text."""

    def __init__(self, df: np.ndarray, docs: int, mean_length: float, opts: Packing):
        self.idf = np.log1p((docs - df + 0.5) / (df + 0.5)).astype(np.float32)
        self.mean, self.opts = max(mean_length, 1.0), opts

    def __call__(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        ordered = np.sort(ids, kind="stable")
        starts = np.flatnonzero(np.diff(ordered, prepend=ordered[:1] + ordered.dtype.type(1)))
        tf = np.diff(starts, append=len(ordered)).astype(np.float32)
        terms, o = ordered[starts], self.opts
        return terms, self.idf[terms] * tf * (o.k1 + 1) / (tf + o.k1 * (1 - o.b + o.b * len(ids) / self.mean))


def _leads(rarity: np.ndarray, dtype: str):
    """The rarest term of each document that another one has too; of equally rare ones the first in the text."""

    def lead(column: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for series in column:
            out = []
            for i in series:
                ids = np.frombuffer(i, dtype)
                out.append(ids[rarity[ids].argmax()])
            yield pd.Series(out, dtype="int32")

    lead.__annotations__ = {"column": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return F.pandas_udf(lead, "int").asNondeterministic()


def lay_out(tokens: dict[int, int], size: int, target: int) -> tuple[np.ndarray, np.ndarray]:
    """First shard and number of shards of each term: terms in order fill shards of the target size."""
    first, share = np.zeros(size, np.int64), np.ones(size, np.int64)
    shard, filled = 0, 0
    for term in sorted(tokens):
        n = tokens[term]
        if filled and filled + n > target:
            shard, filled = shard + 1, 0
        k = -(-n // target)
        first[term], share[term] = shard, k
        if k > 1:
            shard, filled = shard + k, 0
        else:
            filled += n
    return first, share


def fill_windows(pieces: list[np.ndarray], weights: Weights, window: int) -> list[list[tuple[int, int, int]]]:
    """Windows of (piece, start, length) that hold every id of every piece once; all but the last are full.

    The seed is the piece cut by the window before, or the first unused one.
    """
    n = len(pieces)
    start, left = np.zeros(n, np.int64), np.array([len(p) for p in pieces], np.int64)
    rows = [weights(p) for p in pieces]
    terms = np.concatenate([t for t, _ in rows]) if n else np.empty(0, np.int64)
    order = np.argsort(terms, kind="stable")
    owner = np.repeat(np.arange(n), [len(t) for t, _ in rows])[order]
    weight = (np.concatenate([w for _, w in rows]) if n else np.empty(0, np.float32))[order]
    bounds = np.zeros(len(weights.idf) + 1, np.int64)
    np.cumsum(np.bincount(terms, minlength=len(weights.idf)), out=bounds[1:])

    def neighbours(seed: int) -> np.ndarray:
        t, w = rows[seed]
        if len(t) > weights.opts.query_terms:
            t = t[np.argpartition(-w, weights.opts.query_terms)[: weights.opts.query_terms]]
        spans = [slice(bounds[i], bounds[i + 1]) for i in t]
        score = np.bincount(np.concatenate([owner[s] for s in spans]), np.concatenate([weight[s] for s in spans]), minlength=n)
        score[left == 0] = 0
        score[seed] = 0
        found = np.flatnonzero(score)
        return found[np.argsort(-score[found], kind="stable")]

    out, nxt, cut = [], 0, -1
    while True:
        while nxt < n and not left[nxt]:
            nxt += 1
        if nxt == n and (cut < 0 or not left[cut]):
            return out
        seed = cut if cut >= 0 and left[cut] else nxt
        room, row, cut = window, [], -1

        def take(i: int) -> None:
            nonlocal room, cut
            k = int(min(room, left[i]))
            row.append((i, int(start[i]), k))
            start[i] += k
            left[i] -= k
            room -= k
            if left[i]:
                cut = i

        take(seed)
        if room:
            for i in neighbours(seed):
                take(int(i))
                if not room:
                    break
        at = nxt
        while room and at < n:  # no unused neighbour is left: the next unused pieces
            if left[at]:
                take(at)
            at += 1
        out.append(row)


def _pack_shard(weights: Weights, dtype: str):
    opts = weights.opts

    def pack(group: pa.Table) -> pa.Table:
        group = group.combine_chunks()
        keys, shard = group.column("_id"), group.column("shard")[0].as_py()
        ids = [np.frombuffer(i.as_buffer(), dtype) for i in group.column("ids")]
        # an order that does not depend on how the rows arrived
        named = keys.to_pylist()
        twice = len(set(named)) < len(named)
        order = sorted(range(len(ids)), key=lambda i: (named[i] is None, named[i] or 0, ids[i].tobytes() if twice else b""))
        rows: list[tuple[int, int, int, int, int]] = []  # document, start, length, sequence, offset
        rests, sequence = [], 0
        for d in order:
            whole = len(ids[d]) // opts.window
            for i in range(whole):
                rows.append((d, i * opts.window, opts.window, sequence, 0))
                sequence += 1
            if len(ids[d]) % opts.window:
                rests.append((d, whole * opts.window))
        for row in fill_windows([ids[d][s:] for d, s in rests], weights, opts.window):
            # full windows stay whole; the last is cut at the bits of its length, so each part is a power of two
            total, sizes = sum(k for _, _, k in row), []
            for bit in range(total.bit_length() - 1, -1, -1):
                if total >> bit & 1:
                    sizes.append(1 << bit)
            if total == opts.window:
                sizes = [total]
            offset, size = 0, sizes.pop(0)
            for i, s, k in row:
                d, base = rests[i]
                while k:
                    part = min(k, size - offset)
                    rows.append((d, base + s, part, sequence, offset))
                    s, k, offset = s + part, k - part, offset + part
                    if offset == size:
                        sequence, offset = sequence + 1, 0
                        size = sizes.pop(0) if sizes else 0
        of = pa.array([r[0] for r in rows], pa.int64())
        return pa.table({
            "_id": keys.take(of), "start": pa.array([r[1] for r in rows], pa.int64()), "length": pa.array([r[2] for r in rows], pa.int64()),
            "doc_tokens": pa.array([len(ids[r[0]]) for r in rows], pa.int64()), "sequence_id": pa.array([(shard << 32) + r[3] for r in rows], pa.int64()),
            "offset": pa.array([r[4] for r in rows], pa.int64()), "ids": pa.array([ids[r[0]][r[1] : r[1] + r[2]].astype("<u4").tobytes() for r in rows], pa.binary()),
        })

    return pack


def pack(df: DataFrame, key: str = "doc_id", text: str = "text", tokenizer: str | None = None, opts: Packing = Packing()) -> DataFrame:
    """Pieces of documents and their places in sequences.

    Columns: key, start and length of the piece among its document's ids, doc_tokens,
    sequence_id, offset in the sequence, and ids (32-bit little-endian integers). A
    null or empty text is the end id alone. Every row of the input is a document,
    also where keys or whole rows repeat; equal keys are ordered by their ids. An
    empty table gives no pieces. Texts of any length are tokenised whole: a long
    one fills windows of its own and only its rest is packed with others.
    """
    spark = df.sparkSession
    path = tokenizer or public_tokenizers.path("word_bpe_49k.json")
    words = WordIds(path)
    size, dtype = words.size, words.dtype.str
    kind = df.schema[key].dataType.simpleString()
    ids = settle(df.select(F.col(key).alias("_id"), F.col(text).cast("string").alias("_text")).mapInArrow(_tokenise(path, opts.end_id), f"_id {kind}, n long, ids binary"), "ids")

    counts = ids.select("ids").mapInArrow(_frequencies(dtype, size), "term int, df long").groupBy("term").agg(F.sum("df").alias("df")).collect()  # at most one row for each id
    frequency = np.zeros(size, np.int64)
    for r in counts:
        frequency[r["term"]] = r["df"]
    docs, tokens = ids.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    weights = Weights(frequency, docs, tokens / max(docs, 1), opts)
    lead = _leads(np.where(frequency > 1, weights.idf, 0), dtype)

    per_lead = ids.select("n", lead("ids").alias("lead")).groupBy("lead").agg(F.sum("n").alias("n")).collect()  # as above
    first, share = lay_out({r["lead"]: r["n"] for r in per_lead}, size, opts.shard_tokens)
    salt = F.xxhash64("_id", "n", F.crc32("ids"))
    used = sorted({r["lead"] for r in per_lead})
    places = spark.createDataFrame([(t, int(first[t]), int(share[t])) for t in used], "lead int, first long, share long")
    routed = ids.select("*", lead("ids").alias("lead")).join(F.broadcast(places), "lead").select("_id", "ids", (F.col("first") + F.pmod(salt, F.col("share"))).alias("shard"))
    out = routed.groupBy("shard").applyInArrow(_pack_shard(weights, dtype), f"_id {kind}, start long, length long, doc_tokens long, sequence_id long, offset long, ids binary")
    return out.withColumnRenamed("_id", key)


def op1_bm25_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = pack(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return packed.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")
