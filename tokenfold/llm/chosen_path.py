"""Jaccard join of word n-gram sets by chosen paths.

A text is the set of its n-grams of words, embedded as a fixed number of MinHash
values. Texts with equal sets are one node, so copies never meet. Each run splits
all nodes by one value; a bucket that stays large is split again by values that its
own path samples, up to a depth. Small buckets, and those that no split reduces,
are compared by brute force on the embeddings, in blocks if they are large. What
survives is linked loosely into groups, which hold every pair that a run has put
together; inside a group all sets are compared exactly, again in blocks. Rows are
nodes, stars or counts at every step, never the pairs of a group.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WORD, WordHashes, bitmap, fresh, gram_hashes, in_bitmap, mix, settle, table, texts
from .components import components


@dataclass(frozen=True)
class Join:
    n: int = 5
    least: float = 0.8
    #: Chance that a pair of the least similarity shares a bucket of the last level in some run.
    recall: float = 0.999
    values: int = 64
    #: Buckets up to this size are compared whole.
    bucket: int = 256
    #: Splits after that of the run; with more a bucket is compared in blocks.
    depth: int = 4
    #: Standard deviations by which an estimate may fall short of the least similarity.
    margin: float = 4.0
    #: Nodes of a large bucket or group that are compared with each other in one task.
    block: int = 1024

    #: Bits of the map of texts that are compared exactly, a power of two.
    map_bits: int = 1 << 26

    def __post_init__(self):
        if 2 * self.runs > self.values:  # half of the values are for deeper splits
            raise ValueError(f"a recall of {self.recall} at a similarity of {self.least} takes {self.runs} runs, so at least {2 * self.runs} values, not {self.values}")

    @property
    def runs(self) -> int:
        """Each run's split keeps a pair together with its similarity; deeper splits follow a branching process."""
        alive = 1.0
        for _ in range(self.depth):
            alive = 1 - math.exp(-alive)  # a split keeps one shared child on average
        p = self.least * alive
        return math.ceil(math.log(1 - self.recall) / math.log(1 - p))

    @property
    def loose(self) -> int:
        """Equal values from which a pair counts as a candidate."""
        t = self.values
        return math.floor(t * self.least - self.margin * math.sqrt(t * self.least * (1 - self.least)))


def grams(text: str, hashes: WordHashes, n: int) -> np.ndarray:
    """Sorted hashes of the text's n-grams of lower-case words; a shorter text is one gram of all its words."""
    words = WORD.findall(text.lower())
    if not words:
        return np.empty(0, np.uint64)
    return np.unique(gram_hashes(hashes(words), min(n, len(words))))


def _digest(g: np.ndarray) -> bytes:
    return hashlib.md5(g.tobytes()).digest()


def _multipliers(t: int) -> tuple[np.ndarray, np.ndarray]:
    i = np.arange(1, t + 1, dtype=np.uint64)
    return mix(i) | np.uint64(1), mix(i + np.uint64(1 << 32))


def minhash(g: np.ndarray, t: int) -> np.ndarray:
    """t values of 32 bits."""
    a, b = _multipliers(t)
    out = np.empty(t, np.uint64)
    for low in range(0, t, 16):  # 16 rows at a time stay in the cache
        out[low : low + 16] = (g[None, :] * a[low : low + 16, None] + b[low : low + 16, None]).min(axis=1)
    return (out >> np.uint64(32)).astype(np.uint32)


def _embed(opts: Join):
    def embed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            digests, values = [], []
            for t in texts(batch.column(2).to_pylist()):
                g = grams(t, hashes, opts.n)
                digests.append(_digest(g) if len(g) else None)
                values.append(minhash(g, opts.values).tobytes() if len(g) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(digests, pa.binary()), pa.array(values, pa.binary())], ["_id", "said", "node", "emb"])

    return embed


def _matrix(column: pa.Array, dtype: str, width: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), dtype).reshape(len(column), width)


def _roots(opts: Join):
    """First buckets: one for each run."""

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            emb = _matrix(batch.column(1), "<u4", opts.values)[:, : opts.runs].astype(np.uint64)
            path = mix(emb + (np.arange(1, opts.runs + 1, dtype=np.uint64) << np.uint64(32)))
            of = pa.array(np.repeat(np.arange(batch.num_rows), opts.runs))
            yield pa.RecordBatch.from_arrays([pa.array(path.reshape(-1).view(np.int64)), batch.column(0).take(of)], ["path", "node"])

    return split


def _children(opts: Join, level: int):
    """The buckets below: each path samples values, one on average, of those that no run starts with."""
    pool = np.arange(opts.runs, opts.values, dtype=np.uint64)
    below = np.uint64(int(2**64 / len(pool) / opts.least) - 1)

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            path = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            emb = _matrix(batch.column(2), "<u4", opts.values)
            chosen = mix(path[:, None] + mix(pool + np.uint64(level << 16))[None, :]) < below
            row, i = np.nonzero(chosen)
            child = mix(path[row] ^ mix((pool[i] << np.uint64(32)) + emb[row, pool[i].astype(np.int64)]))
            yield pa.RecordBatch.from_arrays([pa.array(child.view(np.int64)), batch.column(0).take(pa.array(row)), batch.column(1).take(pa.array(row))], ["path", "parent", "node"])

    return split


def label(linked: np.ndarray, first: int, labels: np.ndarray) -> None:
    """Join the rows first, first + 1, ... with those that they are linked to; a label is the least row of its group."""
    for i, row in enumerate(linked, first):
        near = labels[row]
        if len(near) and ((near != labels[i]).any()):
            old = np.unique(np.append(near, labels[i]))
            labels[np.isin(labels, old)] = old[0]


def by_group(handle: Callable[[object, pa.Table], pa.RecordBatch | None]):
    """Call handle with the rows of each value of the first column, over batches sorted by it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def groups(t: pa.Table) -> Iterator[pa.RecordBatch]:
            key = t.column(0).to_numpy(zero_copy_only=False)
            cut = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1).tolist(), len(key)]
            for a, b in zip(cut, cut[1:], strict=False):
                if (out := handle(key[a], t.slice(a, b - a))) is not None and out.num_rows:
                    yield out

        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column(0)
            if held and held[-1].column(0)[-1] == key[len(key) - 1] and held[-1].column(0)[-1] == key[0]:
                held.append(batch)  # one group as yet
                continue
            values = key.to_numpy(zero_copy_only=False)
            last = int(np.flatnonzero(values != values[-1])[-1]) + 1 if (values != values[-1]).any() else 0
            if last or held:
                yield from groups(pa.Table.from_batches([*held, batch.slice(0, last)]))
            held = [batch.slice(last)]
        if held:
            yield from groups(pa.Table.from_batches(held))

    return run


def _compare(opts: Join):
    """Star edges between the nodes of a bucket (or of two of its blocks) that look similar enough."""

    def handle(_, t: pa.Table) -> pa.RecordBatch | None:
        n = t.num_rows
        if n < 2:
            return None
        emb = _matrix(t.column("emb").combine_chunks(), "<u4", opts.values)
        root, step = np.arange(n), max(1, (1 << 22) // (n * opts.values))
        for low in range(0, n, step):
            same = (emb[low : low + step, None, :] == emb[None, :, :]).sum(axis=2)
            label(same >= opts.loose, low, root)
        a = np.flatnonzero(root != np.arange(n))
        node = t.column("node").combine_chunks()
        return pa.RecordBatch.from_arrays([node.take(pa.array(a)), node.take(pa.array(root[a]))], ["a", "b"])

    return by_group(handle)


def intersections(sets: list[np.ndarray], heavy: float = 1 / 16) -> np.ndarray:
    """Sizes of all pairwise intersections: frequent members by matrix product, rare ones by their owners' pairs."""
    n = len(sets)
    member = np.concatenate(sets)
    owner = np.repeat(np.arange(n), [len(s) for s in sets])
    order = np.argsort(member, kind="stable")
    member, owner = member[order], owner[order]
    first = np.flatnonzero(np.diff(member, prepend=member[:1] - np.uint64(1)) != 0)
    size = np.diff(first, append=len(member))
    out = np.zeros((n, n), np.float32)
    dense = np.flatnonzero((size > max(2, heavy * n)))
    for low in range(0, len(dense), 4096):
        part = dense[low : low + 4096]
        m = np.zeros((n, len(part)), np.float32)
        for k, d in enumerate(part):
            m[owner[first[d] : first[d] + size[d]], k] = 1
        out += m @ m.T
    flat = out.reshape(-1)
    for d_size in np.unique(size[(size > 1) & (size <= max(2, heavy * n))]):
        which = first[size == d_size]
        step = max(1, (1 << 20) // int(d_size) ** 2)
        for low in range(0, len(which), step):
            own = owner[which[low : low + step, None] + np.arange(d_size)[None, :]]
            cell = (own[:, :, None] * n + own[:, None, :]).reshape(-1)
            flat += np.bincount(cell, minlength=n * n).astype(np.float32) if len(cell) * 4 > n * n else 0
            if len(cell) * 4 <= n * n:
                np.add.at(flat, cell, 1)
    return out


def _verify(opts: Join):
    """Exact links among the sets of a group, or between two of its blocks: for each node a star edge and its links."""
    schema = pa.schema([("a", pa.binary()), ("b", pa.binary()), ("links", pa.int64())])

    def handle(_, t: pa.Table) -> pa.RecordBatch | None:
        hashes = _WORDS
        seen: dict[bytes, tuple[np.ndarray, int, int]] = {}
        for node, text, copies, block, lone in zip(*(t.column(c).to_pylist() for c in ("node", "text", "copies", "block", "lone")), strict=True):
            if node not in seen:
                g = grams(text, hashes, opts.n)
                if _digest(g) == node:  # else another text under a repeated key
                    seen[node] = g, copies, block if not lone else 0
        nodes = sorted(seen)
        if len(nodes) < 2:
            return None
        size = np.array([len(seen[x][0]) for x in nodes])
        inter = intersections([seen[x][0] for x in nodes])
        linked = inter >= opts.least * (size[:, None] + size[None, :] - inter) - 1e-9 * size[:, None]
        np.fill_diagonal(linked, False)
        blocks = np.array([seen[x][2] for x in nodes])
        if len(np.unique(blocks)) > 1:  # pairs inside one block are another task's
            linked &= blocks[:, None] != blocks[None, :]
        links = linked @ np.array([seen[x][1] for x in nodes], np.int64)
        root = np.arange(len(nodes))
        label(linked, 0, root)
        keep = np.flatnonzero(links)
        return pa.RecordBatch.from_arrays([pa.array([nodes[i] for i in keep], pa.binary()), pa.array([nodes[i] for i in root[keep]], pa.binary()), pa.array(links[keep], pa.int64())], schema=schema)

    return by_group(handle)


_WORDS = WordHashes()


def _blocks(rows: DataFrame, size: str, most: int) -> DataFrame:
    """Rows once for each pair of blocks that theirs is in: key, block, lone (the pair is a block with itself)."""
    n = F.greatest(F.ceil(F.col(size) / most), F.lit(1)).cast("int")
    own = F.pmod(F.xxhash64("node"), n).cast("int")
    rows = rows.withColumn("_n", n).withColumn("block", own)
    rows = rows.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_n") - 1)))
    key = F.when(F.col("_n") == 1, F.col("group")).otherwise(F.xxhash64("group", F.least("block", "_other"), F.greatest("block", "_other")))
    return rows.withColumn("key", key).withColumn("lone", F.col("block") == F.col("_other")).drop("_n", "_other")


def _classes(df: DataFrame, key: str, text: str, opts: Join) -> tuple[DataFrame, DataFrame]:
    """Each row's _id, said (its text's hash) and node; and each node's class: head (last, id and said of its first row), copies, n_links."""
    spark = df.sparkSession
    kind = df.schema[key].dataType.simpleString()
    slim = df.select(F.col(key).alias("_id"), F.col(text).cast("string").alias("text")).select("_id", F.xxhash64("text").alias("said"), "text")
    base = settle(slim.mapInArrow(_embed(opts), f"_id {kind}, said long, node binary, emb binary"), "embedded")
    rank = F.struct(F.col("_id").isNull().alias("last"), F.col("_id").alias("id"), F.col("said").alias("said"))
    nodes = settle(base.filter("node IS NOT NULL").groupBy("node").agg(F.min(rank).alias("rep"), F.count("*").alias("copies"), F.min("emb").alias("emb")), "nodes")

    # Paths: small buckets are leaves, large ones split again unless their split has reduced nothing.
    paths = settle(nodes.select("node", "emb").mapInArrow(_roots(opts), "path long, node binary"), "paths")
    sizes = paths.groupBy("path").agg(F.count("*").alias("size")).filter("size > 1")
    met = settle(paths.join(sizes, "path"), "met")
    leaves = met.filter(F.col("size") <= opts.bucket).select(F.col("path").alias("group"), "node", "size")
    large = met.filter(F.col("size") > opts.bucket)
    for level in range(1, opts.depth + 1):
        if large.isEmpty():
            break
        if level == opts.depth:
            leaves = leaves.unionByName(large.select(F.col("path").alias("group"), "node", "size"))
            break
        split = settle(large.join(nodes.select("node", "emb"), "node").select("path", "node", "emb").mapInArrow(_children(opts, level), "path long, parent long, node binary"), "split")
        counted = split.groupBy("path", "parent").agg(F.count("*").alias("size")).filter("size > 1")
        above = large.groupBy("path").agg(F.first("size").alias("whole")).withColumnRenamed("path", "parent")
        counted = counted.join(above, "parent").select("path", "parent", "size", (F.col("size") * 4 > F.col("whole") * 3).alias("dense"))
        met = settle(split.join(counted, ["path", "parent"]), "met")
        done = (F.col("size") <= opts.bucket) | F.col("dense")
        leaves = leaves.unionByName(met.filter(done).select(F.col("path").alias("group"), "node", "size"))
        large = met.filter(~done).select("path", "node", "size")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    shown = _blocks(leaves.join(nodes.select("node", "emb"), "node"), "size", opts.block)
    loose = shown.select("key", "node", "emb").repartition(parts, "key").sortWithinPartitions("key").mapInArrow(_compare(opts), "a binary, b binary")
    groups = components(loose)

    # Exact comparison inside the groups.
    sized = groups.groupBy("root").agg(F.count("*").alias("size"))
    inside = groups.join(sized, "root").join(nodes.select("node", "rep", "copies"), "node").select("node", F.xxhash64("root").alias("group"), "size", "copies", F.col("rep.id").alias("_rep"), F.col("rep.said").alias("_said"))
    # texts of no group stay where they are: only those whose hash is on the map take part in the join
    inside = settle(inside, "inside")
    sent = spark.sparkContext.broadcast(bitmap(inside.filter("_said IS NOT NULL"), "_said", opts.map_bits))

    def wanted(said: pd.Series) -> pd.Series:
        return pd.Series(in_bitmap(sent.value, said.to_numpy()))

    wanted.__annotations__ = {"said": pd.Series, "return": pd.Series}
    slim = slim.filter(F.pandas_udf(wanted, "boolean")("said"))
    whole = slim.join(inside, F.col("_id").eqNullSafe(F.col("_rep")) & (F.col("said") == F.col("_said"))).select("node", "group", "size", "copies", "text")
    exact = settle(_blocks(whole, "size", opts.block).select("key", "node", "text", "copies", "block", "lone").repartition(parts, "key").sortWithinPartitions("key").mapInArrow(_verify(opts), "a binary, b binary, links long"), "links")
    linked = exact.groupBy(F.col("a").alias("node")).agg(F.sum("links").alias("links"))
    root = components(exact.select("a", "b"))
    named = nodes.select("node", "rep", "copies").join(root, "node", "left").join(linked, "node", "left").withColumn("root", F.coalesce("root", "node"))
    classes = named.groupBy("root").agg(F.min("rep").alias("head"))
    labels = named.join(classes, "root").select("node", "head", (F.col("copies") - 1).alias("copies"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    return base.select("_id", "said", "node"), labels


def similar_documents(df: DataFrame, key: str = "doc_id", text: str = "text", opts: Join = Join()) -> DataFrame:
    """One row for each document: key, class_id, copies, n_links.

    class_id is the least key among the documents that links connect, n_links the
    number of other documents with at least the least similarity, copies those of
    them with the same set of n-grams. Texts without a word (null, empty, white
    space) link to nothing and are a class each; a text with fewer than n words is
    one gram of all of them. Rows that repeat a key are documents of their own that
    share it. Null keys rank last. Whole texts are compared; ties need no rule.
    """
    base, labels = _classes(df, key, text, opts)
    out = base.select("_id", "node").join(labels.withColumn("class_id", F.col("head.id")), "node", "left")
    return out.select(F.col("_id").alias(key), F.when(F.col("node").isNull(), F.col("_id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("copies", F.lit(0)).alias("copies"), F.coalesce("n_links", F.lit(0)).alias("n_links"))


def drop_similar(df: DataFrame, key: str = "doc_id", text: str = "text", opts: Join = Join()) -> DataFrame:
    """One row of each class, that of the least key, with all columns as they were.

    Of rows of a class that share this key one text stays, that of the least hash, and
    of rows that repeat key and text one. Other texts under the key are in classes of
    their own and stay by those. Texts without a word stay.
    """
    base, labels = _classes(df, key, text, opts)
    k, said, many = fresh(df, "_key"), fresh(df, "_said"), fresh(df, "_many")
    first = labels.select("head.id", "head.said").distinct()
    rows = base.filter("node IS NOT NULL").groupBy("_id", "said").agg((F.count("*") > 1).alias(many))
    rows = rows.join(first, F.col("_id").eqNullSafe(F.col("id")) & (rows["said"] == first["said"])).select(F.col("_id").alias(k), rows["said"].alias(said), many)
    heads = settle(rows, "heads").withColumnRenamed(said, f"{said}_of")
    has_word = F.coalesce(F.col(text).cast("string").rlike(r"[^\x20\x09-\x0d]"), F.lit(False))
    worded = df.filter(has_word).withColumn(said, F.xxhash64(F.col(text).cast("string")))
    kept = worded.join(heads, worded[key].eqNullSafe(heads[k]) & (worded[said] == heads[f"{said}_of"]), "inner")
    once = kept.filter(~F.col(many)).select(df.columns)
    row = F.struct(*(F.col(c) for c in df.columns))
    twice = kept.filter(many).groupBy(k, said).agg(F.min_by(row, F.to_json(row)).alias(many)).select(f"{many}.*")
    return df.filter(~has_word).unionByName(once).unionByName(twice)


def op5_chosen_path_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_documents(table(spark, sf_dir, "documents").select("doc_id", "text"))
