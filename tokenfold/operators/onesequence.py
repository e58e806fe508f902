"""One sequence: a small one in one task, or a corpus spread over the cluster."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tokenfold.functions import kernels, rng
from tokenfold.functions.schedule import bits_for_target
from tokenfold.options import CompressOptions
from tokenfold.sources.tables import settle, table

#: Partial product matrices that one task adds up.
FAN_IN = 64
MOST_EXACT = kernels.MOST_EXACT


def on_table(spark: SparkSession, e: np.ndarray, check: Callable[[np.ndarray], list[tuple]], schema: str) -> DataFrame:
    """Rows of a check of one bounded sequence; a longer one is refused, not cut."""
    if len(e) > MOST_EXACT:
        raise ValueError(f"exact checks take at most {MOST_EXACT} vectors, not {len(e)}")
    sent = spark.sparkContext.broadcast(e)
    names = [c.strip().split(" ")[0] for c in schema.split(", ")]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            if len(batch):
                yield pd.DataFrame(check(sent.value), columns=names)

    return spark.range(1, numPartitions=1).mapInPandas(run, schema)


#: Rows of a tile of pairs: a task holds a few tiles of this many squared numbers.
TILE = 1024


def over_pairs(spark: SparkSession, e: np.ndarray, make: Callable[[np.ndarray, np.ndarray], list[tuple]], schema: str) -> DataFrame:
    """Rows made from tiles that hold every pair of vectors in one order or both: a task for each TILE rows, with half of the other blocks."""
    sent, names = spark.sparkContext.broadcast(e), [c.strip().split(" ")[0] for c in schema.split(", ")]
    blocks = -(-len(e) // TILE)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for b in batch["id"].tolist():
                own = sent.value[b * TILE : (b + 1) * TILE]
                for other in range(b, b + blocks // 2 + 1):
                    low = other % blocks * TILE
                    yield pd.DataFrame(make(own, sent.value[low : low + TILE]), columns=names)

    return spark.range(0, blocks, numPartitions=max(1, blocks)).mapInPandas(run, schema)


def kernel_product(spark: SparkSession, e: np.ndarray, q: np.ndarray) -> np.ndarray:
    """The exact kernel of all vectors times the columns q: a task for each TILE rows, and no more of the kernel at once than a tile."""
    sent, blocks = spark.sparkContext.broadcast((e, q)), -(-len(e) // TILE)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x, y = sent.value
        for batch in batches:
            for b in batch["id"].tolist():
                own = x[b * TILE : (b + 1) * TILE]
                total = sum(kernels.gaussian_kernel(own, x[low : low + TILE]) @ y[low : low + TILE] for low in range(0, len(x), TILE))
                yield pd.DataFrame({"b": [b], "part": [total.tobytes()]})

    made = spark.range(0, blocks, numPartitions=max(1, blocks)).mapInPandas(run, "b long, part binary").collect()  # as many numbers as q has
    sent.unpersist()
    return np.concatenate([np.frombuffer(r["part"], np.float64).reshape(-1, q.shape[1]) for r in sorted(made, key=lambda r: r["b"])])


def exact_coordinates(spark: SparkSession, e: np.ndarray, opts: CompressOptions, width: int = 128, most: int = 60) -> np.ndarray:
    """`kernels.dense_coordinates` of more vectors than one task takes: the same eigenvectors by block iteration on the exact kernel.

    It starts from the features' leading directions and ends when every residual is a
    millionth of the least gap between the eigenvalues that are used (or at rounding), and
    raises an error if it does not get there. A vector's sign is that of its sum.
    """
    if len(e) <= MOST_EXACT:
        return kernels.dense_coordinates(e, opts)
    k = opts.top_k or opts.rank
    q = np.linalg.qr(kernels.rff(e, max(width, opts.rff_dim), opts.seed)[:, : max(width, 2 * k)])[0]
    for _ in range(most):
        y = kernel_product(spark, e, q)
        t = q.T @ y
        values, vectors = np.linalg.eigh((t + t.T) / 2)
        lead, residual = values[-k:], np.linalg.norm(y @ vectors[:, -k:] - q @ (vectors[:, -k:] * values[-k:]), axis=0)
        if residual.max() <= max(1e-6 * np.diff(values[-k - 1 :]).min(), 1e-13 * len(e) ** 0.5 * values[-1]):
            z = q @ vectors[:, -k:]
            z, lead = z * np.where(z.sum(axis=0) < 0, -1.0, 1.0), np.maximum(lead, 0)
            if opts.weighting != "none":
                z = z * (np.sqrt(lead) if opts.weighting == "sqrt" else lead)
            return z[:, :-1] if opts.drop_top and k > 1 else z
        q = np.linalg.qr(y)[0]
    raise ValueError(f"the exact kernel's leading eigenvectors were not reached in {most} passes: a residual of {residual.max()}")


def _added(df: DataFrame) -> DataFrame:
    """Product matrices added within groups of FAN_IN neighbours."""

    def add(batch: pd.DataFrame) -> pd.DataFrame:
        total = sum(np.frombuffer(b, np.float64) for b in batch["gram"])
        return pd.DataFrame({"part": [int(batch["part"].iloc[0])], "n": [int(batch["n"].sum())], "gram": [total.tobytes()]})

    near = df.withColumn("part", F.floor(F.col("part") / FAN_IN))
    return near.groupBy("part").applyInPandas(add, "part long, n long, gram binary")


#: Words that a task counts or remembers at once, words whose features it makes at once, and tokens it places at once.
MOST_WORDS, MOST_FEATURED, MOST_PLACED = 100_000, 4096, 1 << 18


def _lots(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """All rows in smaller batches, so that a task holds few copies of few prompts."""
    for batch in batches:
        for low in range(0, batch.num_rows, rows):
            yield batch.slice(low, rows)


def _encoded(batch: pa.RecordBatch) -> tuple[np.ndarray, list[str], np.ndarray]:
    """Tokens of each prompt (a null prompt has none), the batch's different words, and the word of each token."""
    tokens = batch.column("tokens")
    flat = tokens.flatten().dictionary_encode()
    sizes = pc.fill_null(pc.list_value_length(tokens), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    return sizes, flat.dictionary.to_pylist(), flat.indices.to_numpy(zero_copy_only=False)


def _features(vocabulary: kernels.Vocabulary, words: list[str], opts: CompressOptions) -> Iterator[tuple[int, np.ndarray]]:
    """Features of words, MOST_FEATURED at once, each lot with its first place."""
    for low in range(0, len(words), MOST_FEATURED):
        yield low, kernels.rff(vocabulary.vectors(words[low : low + MOST_FEATURED]), opts.rff_dim, opts.seed, opts.kernel)


def gram(df: DataFrame, e: np.ndarray, opts: CompressOptions) -> tuple[int, np.ndarray]:
    """Tokens and the product matrix of all tokens' features; a word's features are made once for all its tokens in a task."""
    sent = df.sparkSession.sparkContext.broadcast(e)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        vocabulary = kernels.Vocabulary(sent.value, opts.anisotropy, opts.subword)
        total, n, counts = np.zeros((opts.rff_dim, opts.rff_dim)), 0, {}

        def add() -> None:
            times = np.fromiter(counts.values(), np.float64, len(counts))
            for low, phi in _features(vocabulary, list(counts), opts):
                total[:] += (phi * times[low : low + len(phi), None]).T @ phi
            counts.clear()

        for batch in _lots(batches):
            _, words, which = _encoded(batch)
            n += len(which)
            for word, k in zip(words, np.bincount(which, minlength=len(words)).tolist(), strict=True):
                counts[word] = counts.get(word, 0) + k
            if len(counts) > MOST_WORDS:
                add()
        add()
        yield pa.record_batch({"part": pa.array([TaskContext.get().partitionId()], pa.int64()), "n": pa.array([n], pa.int64()), "gram": pa.array([total.tobytes()], pa.binary())})

    return _total(df.select("tokens").mapInArrow(run, "part long, n long, gram binary"), opts.rff_dim)


def _total(parts: DataFrame, width: int) -> tuple[int, np.ndarray]:
    """Rows and the sum of partial product matrices, added in a tree."""
    parts = settle(parts, "gram")
    most = (parts.agg(F.max("part")).first()[0] or 0) + 1
    while most > FAN_IN:
        parts, most = _added(parts), -(-most // FAN_IN)
    last = _added(parts).collect()  # one row
    return (last[0]["n"], np.frombuffer(last[0]["gram"], np.float64).reshape(width, -1)) if last else (0, np.zeros((width, width)))


def numbered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All vectors of the frozen table (i, embedding), i counted from 0 in the order of their ids. They stay on the executors."""
    df = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    n, low, high, ids = df.agg(F.count("*"), F.min("vec_id"), F.max("vec_id"), F.count_distinct("vec_id")).first()
    if n == ids and (not n or (low == 0 and high == n - 1)):
        return df.select(F.col("vec_id").alias("i"), "embedding")
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ranged = settle(df.repartitionByRange(parts, "vec_id").withColumn("part", F.spark_partition_id()), "numbered")
    return _running(ranged, ["vec_id"], i=F.lit(1)).select("i", "embedding")


Columns = Callable[[np.ndarray, np.ndarray], np.ndarray]


def products(df: DataFrame, columns: Columns, width: int) -> tuple[int, np.ndarray]:
    """Rows, and products with each other of the columns made from all (i, vectors), whatever their number."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        total, n = np.zeros((width, width)), 0
        for batch in batches:
            for i, x in _stacks(batch):
                made = columns(i, x)
                total, n = total + made.T @ made, n + len(i)
        yield pd.DataFrame({"part": [TaskContext.get().partitionId()], "n": [n], "gram": [total.tobytes()]})

    return _total(df.mapInPandas(run, "part long, n long, gram binary"), width)


def _stacks(batch: pd.DataFrame, rows: int = 4096) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    for low in range(0, len(batch), rows):
        part = batch[low : low + rows]
        yield part["i"].to_numpy(), np.stack(part["embedding"].to_numpy()).astype(np.float64)


def by_row(df: DataFrame, make: Callable[[np.ndarray, np.ndarray], pd.DataFrame], schema: str) -> DataFrame:
    """Rows made from stacks of (i, vectors) where they lie."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for i, x in _stacks(batch):
                yield make(i, x)

    return df.mapInPandas(run, schema)


def with_start(dims: int, opts: CompressOptions) -> Columns:
    """Columns [features, random start] of vectors."""

    def columns(i: np.ndarray, x: np.ndarray) -> np.ndarray:
        phi = kernels.rff(x, dims, opts.seed, opts.kernel)
        return phi if opts.start == "range" else np.column_stack([phi, rng.normals_at(opts.seed, "token", i)])

    return columns


def _running(df: DataFrame, order: list[str], **sums) -> DataFrame:
    """Sums over all rows before each one, of rows in range partitions `part`: totals by partition first, then within."""
    names = list(sums)
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each partition
    within = Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    totals = df.groupBy("part").agg(*(F.sum(sums[c]).alias(c) for c in names))
    starts = totals.select("part", *(F.coalesce(F.sum(c).over(earlier), F.lit(0)).alias(f"_{c}") for c in names))
    own = df.select("*", *(F.coalesce(F.sum(sums[c]).over(within), F.lit(0)).alias(c) for c in names))
    return own.join(F.broadcast(starts), "part").withColumns({c: F.col(c) + F.col(f"_{c}") for c in names}).drop(*(f"_{c}" for c in names))


def _share(a: Column, b: Column | int, c: Column | int) -> Column:
    """floor(a * b / c) of whole numbers, exact where the product is beyond 64 bits."""
    a, b, c = (x.cast("decimal(19,0)") if isinstance(x, Column) else F.lit(x).cast("decimal(19,0)") for x in (a, b, c))
    return F.call_function("div", a * b, c)


def fit_corpus(coded: DataFrame, target: int) -> DataFrame:
    """Groups (seq_id, pos, place, grp) of tokens (seq_id, pos, place), where pos counts a prompt's tokens from 0."""
    wide = coded.groupBy("seq_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "place"))), lambda t: t["place"]).alias("places"))
    return fit_prompts(wide, target)


def _pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Tokens of each code in the prompts of each range, batch by batch."""
    for batch in _lots(batches):
        places, ranges = batch.column("places"), batch.column("part").to_numpy(zero_copy_only=False)
        sizes = pc.list_value_length(places).to_numpy(zero_copy_only=False)
        pairs = pa.table({"place": places.flatten().cast(pa.int64()), "part": np.repeat(ranges, sizes)}).group_by(["place", "part"]).aggregate([([], "count_all")])
        yield from pairs.rename_columns(["place", "part", "piece"]).combine_chunks().to_batches()


def _placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Groups of tokens, from rows in the order of ranges: of each range its codes' pieces first, then its prompts in order.

    A token's rank in its code is that of its code's next token here: pieces say how many earlier ranges hold.
    """
    part, kept, codes = None, [], None
    for batch in batches:
        of, kind = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("part", "kind"))
        cuts = [0, *(np.flatnonzero((np.diff(of) != 0) | (np.diff(kind) != 0)) + 1).tolist(), len(of)]
        for low, high in zip(cuts, cuts[1:], strict=False):
            if low == high:
                continue
            rows = batch.slice(low, high - low)
            if of[low] != part:
                part, kept, codes = of[low], [], None
            if kind[low] == 0:
                kept.append(np.stack([rows.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("place", "next", "first", "runs", "size")]))
                continue
            if codes is None:
                codes, kept = np.concatenate(kept, axis=1), []
                codes = codes[:, np.argsort(codes[0])]
            ends = np.cumsum(pc.list_value_length(rows.column("places")).to_numpy(zero_copy_only=False))
            at = 0
            while at < len(ends):
                done = int(ends[at - 1]) if at else 0
                to = max(at + 1, int(np.searchsorted(ends, done + MOST_PLACED, side="right")))
                yield _in_order(rows.slice(at, to - at), codes)
                at = to


def _in_order(rows: pa.RecordBatch, codes: np.ndarray) -> pa.RecordBatch:
    """Groups of the tokens of a few prompts; codes (place, rank of the next token, first group, groups, tokens) are moved on."""
    sizes = pc.list_value_length(rows.column("places")).to_numpy(zero_copy_only=False).astype(np.int64)
    place = rows.column("places").flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    seq = np.repeat(rows.column("seq_id").to_numpy(zero_copy_only=False), sizes)
    pos = np.arange(len(place)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    here = np.searchsorted(codes[0], place)
    order = np.argsort(here, kind="stable")
    used, start, times = np.unique(here[order], return_index=True, return_counts=True)
    own = np.empty(len(place), np.int64)
    own[order] = np.arange(len(place)) - np.repeat(start, times)
    rank = codes[1][here] + own
    codes[1][used] += times
    _, _, first, runs, size = codes[:, here]
    share = rank * runs // np.maximum(size, 1)
    for i in np.flatnonzero(size > (1 << 62) // np.maximum(runs, 1)).tolist():  # the product is beyond 64 bits
        share[i] = int(rank[i]) * int(runs[i]) // int(size[i])
    return pa.record_batch({"seq_id": pa.array(seq, pa.int64()), "pos": pa.array(pos, pa.int32()), "place": pa.array(place, pa.int64()), "grp": pa.array(first + share, pa.int64())})


def fit_prompts(wide: DataFrame, target: int) -> DataFrame:
    """Groups (seq_id, pos, place, grp) of all tokens of prompts (seq_id, places: the Gray ranks of its tokens' codes), by the rule of kernels.fit_groups_in_order.

    Prompts are dealt by ranges of seq_id, and no token is sorted: its rank in its code is the
    code's tokens in the ranges before, from counts, and those met in its range's prompts in order.
    """
    wide = settle(wide.select(F.col("seq_id").cast("long").alias("seq_id"), "places"), "coded")
    total = wide.agg(F.coalesce(F.sum(F.size("places")), F.lit(0))).first()[0]
    least = max(1, int(wide.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    parts = max(least, -(-total // (1 << 22)))
    bounds = sorted(set(wide.approxQuantile("seq_id", [i / parts for i in range(1, parts)], 0.1 / parts))) if parts > 1 and total else []
    ranged = wide.withColumn("part", F.size(F.filter(F.array(*map(F.lit, bounds)).cast("array<double>"), lambda b: b <= F.col("seq_id"))))
    pieces = settle(ranged.mapInArrow(_pieces, "place long, part int, piece long").groupBy("place", "part").agg(F.sum("piece").alias("piece")), "pieces")
    sizes = pieces.groupBy("place").agg(F.sum("piece").alias("size"))
    sizes = settle(sizes.repartitionByRange(least, "place").withColumn("part", F.spark_partition_id()), "sizes")
    codes = _running(sizes, ["place"], start=F.col("size"), i=F.lit(1))
    n = sizes.count()
    if n >= target:
        ends = (_share(F.col("start") + F.col("size"), target, max(1, total)) > _share(F.col("start"), target, max(1, total))).cast("long")
        codes = settle(codes.withColumn("ends", ends), "codes")
        used = codes.agg(F.coalesce(F.sum("ends"), F.lit(0))).first()[0]
        codes = _running(codes, ["place"], before=F.col("ends"))
        first = F.col("before") + _share(F.col("i") - F.col("before"), target - used, max(1, n - used))
        codes = codes.select("place", first.alias("first"), F.lit(1).cast("long").alias("runs"), "size")
    else:
        spare, room = target - n, max(1, total - n)
        after = F.col("i") + 1 + _share(F.col("start") + F.col("size") - F.col("i") - 1, spare, room)
        first = F.col("i") + _share(F.col("start") - F.col("i"), spare, room)
        codes = codes.select("place", first.alias("first"), (after - first).alias("runs"), "size")
    earlier = Window.partitionBy("place").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each range at most
    pieces = pieces.withColumn("next", F.coalesce(F.sum("piece").over(earlier), F.lit(0))).join(codes, "place")
    ahead = [F.col(c).cast("long").alias(c) for c in ("place", "next", "first", "runs", "size")]
    no = [F.lit(None).cast("long").alias(c) for c in ("place", "next", "first", "runs", "size")]
    pieces = pieces.select("part", F.lit(0).alias("kind"), F.lit(None).cast("long").alias("seq_id"), F.lit(None).cast(wide.schema["places"].dataType).alias("places"), *ahead)
    prompts = ranged.filter(F.size("places") > 0).select("part", F.lit(1).alias("kind"), "seq_id", "places", *no)
    dealt = pieces.unionByName(prompts).repartitionById(len(bounds) + 1, F.col("part")).sortWithinPartitions("part", "kind", "seq_id")
    return dealt.mapInArrow(_placed, "seq_id long, pos int, place long, grp long")


def compress_corpus(df: DataFrame, e: np.ndarray, opts: CompressOptions) -> DataFrame:
    """Groups (seq_id, pos, place, grp) of all tokens of wide prompts as one sequence: exactly the wanted number.

    place is the Gray rank of a token's spectral code. Codes merge whole with their
    neighbours or are split, never both (fit_prompts).
    """
    n, g = gram(df, e, opts)
    target = max(1, math.ceil(n / max(1.0, opts.rho)))
    values, vectors = kernels.gram_eigen(g, opts.rank)
    project = vectors if opts.weighting == "sqrt" else vectors / np.sqrt(np.maximum(values, 1e-300)) * (values if opts.weighting == "full" else 1.0)
    if opts.drop_top and project.shape[1] > 1:
        project = project[:, :-1]
    bits = min(62, opts.bits or bits_for_target(target))
    kind = np.int32 if bits < 32 else np.int64
    sent = df.sparkSession.sparkContext.broadcast((e, project))

    def codes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, to = sent.value
        vocabulary, known = kernels.Vocabulary(table, opts.anisotropy, opts.subword), {}
        for batch in _lots(batches):
            sizes, words, which = _encoded(batch)
            if len(known) > MOST_WORDS:
                known.clear()
            new = [w for w in words if w not in known]
            for low, phi in _features(vocabulary, new, opts):
                known.update(zip(new[low : low + len(phi)], kernels.gray_rank(kernels.simhash(phi @ to, bits, opts.seed)).tolist(), strict=True))
            place = np.fromiter((known[w] for w in words), kind, len(words))[which]
            offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
            yield pa.record_batch({"seq_id": batch.column("seq_id").cast(pa.int64()), "places": pa.ListArray.from_arrays(offsets, pa.array(place))})

    return fit_prompts(df.select("seq_id", "tokens").mapInArrow(codes, f"seq_id long, places array<{'int' if kind is np.int32 else 'long'}>"), target)
