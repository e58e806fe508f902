"""Benchmark passages in documents, found under edits.

The CGK random walk turns edit distance into Hamming distance: a walk writes the
character under its head at each step and moves on or stays by a random bit for
that step and character. Two strings that differ by a few edits soon walk in step
again, so their outputs agree in most places. Tables of a locality-sensitive hash
each sample some places of an output; strings with equal samples in any table are
candidates, and an exact edit distance decides.

Documents are walked from every STRIDE-th character. The window from there is as
long as the rest of the item that it is compared with: an item is walked from each
of its own characters, so a passage meets its item at every place of the stride
that lies in it, each of which is another chance for each table. Walks write only
the first STEPS places, which is where the tables sample: a walk over a whole item
with a fifth of edits falls out of step, one over a short part of it often does not.

How many walks an item needs for the target recall follows from its length and is
measured on random strings with random edits. Items that the most walks do not serve,
the short ones, are searched exactly: what their edits leave of their runs of four
characters is counted over all texts. Candidates of both kinds first meet a lower
bound of their edits, many at once; the edit distance of what is left decides. The pass over documents is narrow; only the items, a stated query set, are sent out, in blocks.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache, reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh, mix, table, texts


@dataclass(frozen=True)
class Walks:
    #: Edits that a passage may have, as a share of its item's characters.
    edits: float = 0.2
    #: Chance that a passage with that share of random edits is a candidate; sets the walks of each item.
    recall: float = 0.99
    stride: int = 4
    steps: int = 40
    #: Most walks of an item; items that need more are searched exactly.
    walks: int = 2
    tables: int = 6
    #: Places that a table samples.
    places: int = 16
    #: Passages of each length from which the recall is measured.
    trials: int = 300
    seed: int = 0
    #: Items sent out at once.
    block: int = 5000


def folded(text: str) -> str:
    """Lower case, character by character where the length would change."""
    low = text.lower()
    return low if len(low) == len(text) else "".join(c if len(c.lower()) != 1 else c.lower() for c in text)


def _symbols(text: str) -> np.ndarray:
    """Characters as 1..255, equal ones alike; 0 is left for what stands outside a text."""
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    return np.where(codes < 128, codes + 1, 129 + codes % 127).astype(np.uint8)


class Walker:
    """Keys of all tables for walks from given places."""

    def __init__(self, opts: Walks):
        self.opts = opts
        rng = np.random.Generator(np.random.PCG64(opts.seed))
        # a number for each walk, step and character, whose lowest bit moves the head
        self.numbers = rng.integers(0, 2**64, (opts.walks, opts.steps, 256), dtype=np.uint64)
        self.numbers[:, :, 0] &= ~np.uint64(1)
        samples = [[set(rng.choice(opts.steps, opts.places, replace=False).tolist()) for _ in range(opts.tables)] for _ in range(opts.walks)]
        self.tables_at = [[[t for t, s in enumerate(own) if j in s] for j in range(opts.steps)] for own in samples]

    def keys(self, symbols: np.ndarray, at: np.ndarray, walks: int | None = None) -> Iterator[np.ndarray]:
        """Keys of one table after another, of the first walks or of all. symbols must end in at least STEPS zeros."""
        o, move, wide = self.opts, np.uint64(1), symbols.astype(np.intp)
        for w in range(o.walks if walks is None else walks):
            head, keys = at.astype(np.int64), np.zeros((o.tables, len(at)), np.uint64)
            for numbers, tables in zip(self.numbers[w], self.tables_at[w], strict=True):
                written = numbers.take(wide.take(head))
                for t in tables:
                    keys[t] ^= written
                written &= move
                head += written.view(np.int64)
            yield from keys


class EditDistance:
    """Edit distance of a pattern to parts of a text, all rows of a column at once in one integer (Myers)."""

    def __init__(self, pattern: str):
        self.n = len(pattern)
        self.full = (1 << self.n) - 1
        self.masks: dict[str, int] = {}
        for i, c in enumerate(pattern):
            self.masks[c] = self.masks.get(c, 0) | 1 << i

    def nearest(self, text: str, from_start: bool = False) -> tuple[int, int]:
        """Least distance and the first end that has it; from_start: the part begins where the text does."""
        full, get, top, edge = self.full, self.masks.get, 1 << (self.n - 1), int(from_start)
        rise, fall, score = full, 0, self.n
        best, end = score, 0
        for j, c in enumerate(text, 1):
            same = get(c, 0)
            x = (((same & rise) + rise) ^ rise) | same
            up, down = fall | ~(x | rise) & full, rise & x
            score += bool(up & top) - bool(down & top)
            if score < best:
                best, end = score, j
            up, down, same = (up << 1 | edge) & full, down << 1 & full, same | fall
            rise, fall = down | ~(same | up) & full, up & same
        return best, end


def _passages(rng: np.random.Generator, n: int, length: int, edits: int, after: int) -> tuple[np.ndarray, np.ndarray]:
    """Random strings over 26 letters, and the same with substitutions, deletions and insertions at random places and other text behind."""
    plain = rng.integers(2, 28, (n, length)).astype(np.uint8)
    other = rng.integers(2, 28, (n, length + edits + after)).astype(np.uint8)
    for row, out in zip(plain, other, strict=True):
        t = row.tolist()
        for kind in rng.integers(0, 3, edits).tolist():
            i, c = int(rng.integers(len(t))), int(rng.integers(2, 28))
            t[i : i + (kind < 2)] = [c][: kind != 1]
        out[: len(t)] = t
    return plain, other


#: Characters by which the lengths grow for which recall is measured.
LENGTHS = 16


@lru_cache(8)
def walks_by_length(opts: Walks) -> tuple[int, ...]:
    """Walks that items of LENGTHS, 2 LENGTHS, ... characters need; walks + 1 where all are too few. The last holds for all longer ones."""
    out, walker = [], Walker(opts)
    for length in range(LENGTHS, 64 * LENGTHS, LENGTHS):
        if length <= opts.steps // 2:
            out.append(opts.walks + 1)
            continue
        rng = np.random.Generator(np.random.PCG64(opts.seed + length))
        plain, other = _passages(rng, opts.trials, length, int(opts.edits * length), 2 * opts.steps)
        item_at = np.arange(max(1, length - opts.steps // 2))
        symbols = np.pad(plain, ((0, 0), (0, opts.steps + 1)))
        shift = rng.integers(0, opts.stride, opts.trials)
        text_at = shift[:, None] + np.arange(0, length, opts.stride)[None, :]
        ours = walker.keys(symbols.reshape(-1), (np.arange(opts.trials)[:, None] * symbols.shape[1] + item_at[None, :]).reshape(-1))
        theirs = walker.keys(other.reshape(-1), (np.arange(opts.trials)[:, None] * other.shape[1] + text_at).reshape(-1))
        hit, need = np.zeros(opts.trials, bool), opts.walks + 1
        own = np.uint64(0x9E3779B97F4A7C15) * np.arange(opts.trials, dtype=np.uint64)[:, None]
        for t, (a, b) in enumerate(zip(ours, theirs, strict=True), 1):
            hit |= np.isin(mix(b.reshape(opts.trials, -1) ^ own), mix(a.reshape(opts.trials, -1) ^ own)).any(axis=1)
            if t % opts.tables == 0 and hit.mean() >= opts.recall:
                need = t // opts.tables
                break
        out.append(need)
        if need == 1:
            break
    return tuple(out)


class ShortItems:
    """Where items that are searched exactly may stand, by counts of their runs of four characters.

    A passage with e edits shares at least n - 3 - 4 e such runs with its item of n
    characters, and each of these is at most e places off. So the runs of either half of
    an item are counted where that half may lie if the passage starts in a block of the
    text, and a block with fewer runs in all starts no passage. Runs are hashed, which
    only raises counts; the counters of eight halves lie side by side in one integer.
    """

    RUN, BLOCK, PARTS, LANES, BITS, JOINED = 4, 16, 2, 8, 16, 8

    def __init__(self, items: list[tuple[int, str]], edits: float):
        self.columns = []
        ordered, each = sorted(items, key=lambda x: len(x[1])), self.LANES // self.PARTS
        for low in range(0, len(ordered), each):
            some = ordered[low : low + each]
            counts, places, lane = np.zeros(1 << self.BITS, np.uint64), [], 0
            for _, t in some:
                slack, runs = int(edits * len(t)), self.runs(_symbols(t))
                spans = []
                for k in range(self.PARTS):
                    a, b = k * len(runs) // self.PARTS, (k + 1) * len(runs) // self.PARTS
                    counts[np.unique(runs[a:b])] |= np.uint64(1 << 8 * lane)
                    # first block and end of those that a start anywhere in a block reaches
                    spans.append((lane, max(0, a - slack) // self.BLOCK, (self.BLOCK + b - 2 + slack) // self.BLOCK + 1))
                    lane += 1
                places.append((max(0, len(t) - self.RUN + 1 - self.RUN * slack), spans))
            self.columns.append((np.array([i for i, _ in some]), counts, places))

    def runs(self, symbols: np.ndarray) -> np.ndarray:
        wide, n = symbols.astype(np.uint32), max(0, len(symbols) - self.RUN + 1)
        mixed = np.zeros(n, np.uint32)
        for k in range(self.RUN):
            mixed = mixed * np.uint32(31) + wide[k : k + n]
        return (mixed * np.uint32(2654435761) >> np.uint32(32 - self.BITS)).astype(np.intp)

    def __call__(self, symbols: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Items, the middle of the blocks in which their passage may start, and half the width of these."""
        n = -(-len(symbols) // self.BLOCK)
        padded = np.zeros(n * self.BLOCK + self.RUN - 1, np.uint8)
        padded[: len(symbols)] = symbols
        runs, found = np.ascontiguousarray(self.runs(padded).reshape(n, self.BLOCK).T), [np.empty((3, 0), np.int64)]
        for items, counts, places in self.columns:
            each = counts.take(runs).sum(axis=0).view(np.uint8).reshape(n, self.LANES)
            ends = max(end for _, spans in places for *_, end in spans)
            before = np.zeros((self.LANES, n + ends), np.int32)
            np.cumsum(each.T, axis=1, out=before[:, 1 : n + 1])
            before[:, n + 1 :] = before[:, n : n + 1]
            enough = [sum(before[lane, end : end + n] - before[lane, low : low + n] for lane, low, end in spans) >= need for need, spans in places]
            lane, block = np.nonzero(np.stack(enough))
            # neighbouring blocks are one candidate, up to JOINED of them
            new = np.flatnonzero((np.diff(block, prepend=-2) != 1) | (np.diff(lane, prepend=-1) != 0))
            run = np.repeat(np.arange(len(new)), np.diff(new, append=len(block)))
            new = np.flatnonzero((np.arange(len(block)) - new[run]) % self.JOINED == 0) if len(new) else new
            half = np.diff(new, append=len(block)) * self.BLOCK // 2
            found.append(np.stack([items[lane[new]], block[new] * self.BLOCK + half, half]))
        return tuple(np.concatenate(found, axis=1))


_ONE = np.uint64(1)
#: All but the 22 bits of a key that a quick look-up uses.
_SEEN = np.uint64(64 - 22)


class PartBounds:
    """Lower bounds of edit distances for many candidates at once.

    An item's edits are at least the sum over its parts of up to 64 characters of each
    part's least distance to any stretch near its place (Myers, a part to a 64-bit
    word). Candidates whose sum is over the limit go; the others are to be checked.
    """

    def __init__(self, items: list[str], edits: float):
        k = np.array([-(-len(t) // 64) for t in items], np.int64)
        cuts = [(t, n * len(t) // m, (n + 1) * len(t) // m) for t, m in zip(items, k.tolist(), strict=True) for n in range(m)]
        self.first, self.count = np.cumsum(k) - k, k
        self.low, self.size = np.array([c[1] for c in cuts], np.int64), np.array([c[2] - c[1] for c in cuts], np.int64)
        self.limit = np.array([int(edits * len(t)) for t in items], np.int64)
        # a pattern ends in the highest bit; the free bits below match everything and cost nothing
        self.masks = np.zeros((len(cuts), 256), np.uint64)
        for p, (t, low, high) in enumerate(cuts):
            free = 64 - (high - low)
            self.masks[p] = np.uint64((1 << free) - 1)
            for bit, c in enumerate(_symbols(t[low:high]).tolist(), free):
                self.masks[p, c] |= np.uint64(1 << bit)

    def _least(self, part: np.ndarray, symbols: np.ndarray, low: np.ndarray, length: int) -> np.ndarray:
        """Least distance of each part to a stretch of the symbols from low on."""
        masks, row, n = self.masks.reshape(-1), part * 256, len(part)
        free = (64 - self.size[part]).astype(np.uint64)
        rise, fall = ~((np.uint64(1) << free) - np.uint64(1)), np.zeros(n, np.uint64)
        # no score is over 64; bytes keep the sums of signs free of conversions
        score = self.size[part].astype(np.int8)
        best = score.copy()
        same, x, up, down = (np.empty(n, np.uint64) for _ in range(4))
        at, c, sign = np.empty(n, np.int64), np.empty(n, np.int64), np.empty(n, bool)
        for k in range(length):
            symbols.take(np.add(low, k, out=at), out=c, mode="clip")
            np.add(row, c, out=at)
            masks.take(at, out=same, mode="clip")
            np.bitwise_and(same, rise, out=x)
            x += rise
            x ^= rise
            x |= same
            x |= fall
            np.bitwise_and(rise, x, out=down)
            np.bitwise_or(x, rise, out=up)
            np.invert(up, out=up)
            up |= fall
            score += np.less(up.view(np.int64), 0, out=sign).view(np.int8)
            score -= np.less(down.view(np.int64), 0, out=sign).view(np.int8)
            np.minimum(best, score, out=best)
            up <<= _ONE
            down <<= _ONE
            np.bitwise_and(up, x, out=fall)
            x |= up
            np.invert(x, out=x)
            np.bitwise_or(down, x, out=rise)
        return best

    def __call__(self, item: np.ndarray, symbols: np.ndarray, about: np.ndarray, wide: np.ndarray, step: int = 4096) -> np.ndarray:
        """Which candidates the bound leaves; about: where the item may start, give or take `wide` and its edits."""
        limit, symbols = self.limit[item], symbols.astype(np.int64)
        total = np.zeros(len(item), np.int64)

        def add(which: np.ndarray, part: np.ndarray) -> None:
            slack = limit[which] + wide[which]
            order = np.argsort(self.size[part] + 2 * slack, kind="stable")
            for low in range(0, len(order), step):
                own = order[low : low + step]
                start = np.maximum(about[which[own]] + self.low[part[own]] - slack[own], 0)
                np.add.at(total, which[own], self._least(part[own], symbols, start, int((self.size[part[own]] + 2 * slack[own]).max())))

        # the first part decides most; the others of what it leaves go together
        add(np.arange(len(item)), self.first[item])
        left = np.flatnonzero(total <= limit)
        n = self.count[item[left]] - 1
        nth = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        add(np.repeat(left, n), np.repeat(self.first[item[left]], n) + 1 + nth)
        return left[total[left] <= limit[left]]


class Items:
    """A block of items with the tables of their walks, and the counting filter of those that are searched exactly."""

    #: Characters by which a candidate's place is uncertain beside its edits.
    WIDE = 8

    def __init__(self, items: list[tuple[object, str]], opts: Walks, needs: tuple[int, ...] | None = None):
        self.opts, self.walker = opts, Walker(opts)
        self.items = [(key, folded(t)) for key, t in items if t]
        #: Characters to search at once: candidates grow with them and with the items.
        self.portion = max(1 << 18, (1 << 28) // max(1 << 8, len(self.items)))
        self.reverse: dict[int, tuple[EditDistance, EditDistance]] = {}
        needs = needs or walks_by_length(opts)
        exact, symbols, at, of, offset, need, total = [], [], [], [], [], [], 0
        for i, (_, t) in enumerate(self.items):
            walks = needs[min(len(t) // LENGTHS, len(needs)) - 1] if len(t) >= LENGTHS else opts.walks + 1
            if walks > opts.walks:
                exact.append((i, t))
                continue
            # the last starts leave the walk about as many characters as it reads
            starts = np.arange(max(1, len(t) - opts.steps // 2))
            symbols += [_symbols(t), np.zeros(opts.steps + 1, np.uint8)]
            at.append(total + starts)
            of.append(np.full(len(starts), i))
            offset.append(starts)
            need.append(np.full(len(starts), walks))
            total += len(t) + opts.steps + 1
        self.short = ShortItems(exact, opts.edits)
        self.bounds = PartBounds([t for _, t in self.items], opts.edits)
        self.tables, self.walks = [], 0
        if at:
            of_all, offset_all, need_all = np.concatenate(of), np.concatenate(offset), np.concatenate(need)
            self.walks = int(need_all.max())
            for t, keys in enumerate(self.walker.keys(np.concatenate(symbols), np.concatenate(at), self.walks)):
                own = np.flatnonzero(need_all > t // opts.tables)
                order = own[np.argsort(keys[own], kind="stable")]
                seen = np.zeros(1 << 22, bool)
                seen[keys[own] >> _SEEN] = True
                self.tables.append((seen, keys[order], of_all[order], offset_all[order]))

    def within(self, i: int, text: str, low: int, high: int) -> tuple[int, int, int] | None:
        """Edits, start and end of item i in a stretch of a folded text, if it is there."""
        item = self.items[i][1]
        if i not in self.reverse:
            self.reverse[i] = EditDistance(item), EditDistance(item[::-1])
        low = max(0, low)
        part = text[low : max(0, high)]
        edits, end = self.reverse[i][0].nearest(part)
        if edits > int(self.opts.edits * len(item)):
            return None
        _, back = self.reverse[i][1].nearest(part[:end][::-1], from_start=True)
        return edits, low + end - back, low + end

    def candidates(self, symbols: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Items, their estimated starts in the symbols of many texts, and how far off these may be; first: where the texts begin."""
        o = self.opts
        at = np.concatenate([np.arange(f, g - o.steps - 1, o.stride) for f, g in zip(first, first[1:], strict=False)])
        found = [np.stack(self.short(symbols))]
        for low in range(0, len(at), 1 << 13):
            part = at[low : low + (1 << 13)]
            start, end = int(part[0]), int(part[-1]) + o.steps + 1
            for (seen, keys, of, offset), own in zip(self.tables, self.walker.keys(symbols[start:end], part - start, self.walks), strict=True):
                hit = np.flatnonzero(seen.take((own >> _SEEN).view(np.int64)))
                left = np.searchsorted(keys, own[hit], "left")
                n = np.searchsorted(keys, own[hit], "right") - left
                hit, left, n = hit[n > 0], left[n > 0], n[n > 0]
                if len(hit):
                    j = np.repeat(left - np.cumsum(n) + n, n) + np.arange(n.sum())
                    about = (np.repeat(part[hit], n) - offset[j]) // self.WIDE * self.WIDE
                    found.append(np.stack([of[j], about, np.full(len(j), self.WIDE)]))
        item, about, wide = np.concatenate(found, axis=1)
        _, one = np.unique(item * (2 * len(symbols) + 1) + about + len(symbols), return_index=True)
        return item[one], about[one], wide[one]

    def __call__(self, batch: list[str]) -> list[tuple[int, int, int, int, int]]:
        """Text, item, edits, start and end of the best place of each item in each text."""
        batch = [folded(t) for t in batch]
        best: dict[tuple[int, int], tuple[int, int, int]] = {}
        if not self.items or not any(batch):
            return []
        pad = np.zeros(self.opts.steps + 1, np.uint8)
        symbols = np.concatenate([x for t in batch for x in (_symbols(t), pad)])
        first = np.cumsum([0, *(len(t) + len(pad) for t in batch)])
        item, about, wide = self.candidates(symbols, first)
        left = self.bounds(item, symbols, about, wide)
        stretches: dict[tuple[int, int], list[list[int]]] = {}
        for i, a, w in sorted(zip(item[left].tolist(), about[left].tolist(), wide[left].tolist(), strict=True)):
            n, slack = len(self.items[i][1]), int(self.bounds.limit[i])
            low, high = a - slack - w, a + n + 2 * slack + w
            d = max(0, int(np.searchsorted(first, low, "right")) - 1)
            while d < len(batch) and first[d] < high:
                x, y = max(0, low - int(first[d])), min(len(batch[d]), high - int(first[d]))
                if x < y:
                    own = stretches.setdefault((d, i), [])
                    if own and x <= own[-1][1]:
                        own[-1][1] = max(y, own[-1][1])
                    else:
                        own.append([x, y])
                d += 1
        for (d, i), places in stretches.items():
            for low, high in places:
                if (got := self.within(i, batch[d], low, high)) is not None and got < best.get((d, i), (1 << 30,)):
                    best[d, i] = got
        return [(d, i, *got) for (d, i), got in sorted(best.items())]


def _portions(column: list[str], most: int) -> Iterator[tuple[int, list[str]]]:
    """First row and texts of each portion of at most so many characters; a longer text is one of its own."""
    low, size = 0, 0
    for i, t in enumerate(column):
        if i > low and size + len(t) > most:
            yield low, column[low:i]
            low, size = i, 0
        size += len(t)
    if low < len(column):
        yield low, column[low:]


def _search(items: list[tuple[object, str]], opts: Walks, item_type: pa.DataType, names: list[str]):
    needs = walks_by_length(opts)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = Items(items, opts, needs)
        for batch in batches:
            for low, own in _portions(texts(batch.column(1).to_pylist()), block.portion):
                part, found = batch.slice(low, len(own)), block(own)
                yield pa.RecordBatch.from_arrays([
                    part.column(0).take(pa.array([f[0] for f in found], pa.int32())), pa.array([block.items[f[1]][0] for f in found], item_type),
                    *(pa.array([f[k] for f in found], pa.int32()) for k in (2, 3, 4)),
                ], names)

    return search


def _item_blocks(items: DataFrame, item_key: str, item_text: str, size: int) -> Iterator[list[tuple[object, str]]]:
    """The items in order, one block at a time; one empty block if there is none."""
    rows: list[tuple[object, str]] = []
    none = True
    for row in items.select(item_key, item_text).orderBy(item_key, item_text).toLocalIterator():
        rows.append((row[0], row[1]))
        if len(rows) == size:
            yield rows
            rows, none = [], False
    if rows or none:
        yield rows


def _holds(rows: list[tuple[object, str]], opts: Walks):
    needs = walks_by_length(opts)

    def holds(column: Iterator[pd.Series]) -> Iterator[pd.Series]:
        block = Items(rows, opts, needs)
        for series in column:
            out = np.zeros(len(series), bool)
            for low, own in _portions(texts(series), block.portion):
                out[[low + f[0] for f in block(own)]] = True
            yield pd.Series(out)

    holds.__annotations__ = {"column": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return F.pandas_udf(holds, "boolean").asNondeterministic()


def contaminated(df: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", opts: Walks = Walks()) -> DataFrame:
    """Each document and item of which it holds a passage: keys, edits, and start and end (code points) of the best place.

    Null and empty texts hold nothing, null items are in nothing; repeated rows are
    reported each. Of places with equal edits the first is named. Whole texts are
    searched. Items are read in blocks, and each block is searched in all documents.
    """
    kind, item_kind = df.schema[key].dataType.simpleString(), items.schema[item_key].dataType.simpleString()
    item_type = {"bigint": pa.int64(), "int": pa.int32()}.get(item_kind, pa.string())
    names = [key, item_key if item_key != key else f"item_{item_key}", "edits", "start", "end"]
    schema = f"`{key}` {kind}, `{names[1]}` {item_kind}, edits int, start int, end int"
    docs = df.select(F.col(key), F.col(text).cast("string"))
    found = [docs.mapInArrow(_search(rows, opts, item_type, names), schema) for rows in _item_blocks(items, item_key, item_text, opts.block)]
    return reduce(DataFrame.unionByName, found)


def drop_contaminated(df: DataFrame, items: DataFrame, text: str = "text", item_key: str = "item_id", item_text: str = "text", opts: Walks = Walks()) -> DataFrame:
    """The rows whose text holds no item, with all columns as they were; texts stay where they are."""
    flag = fresh(df, "_holds")
    for rows in _item_blocks(items, item_key, item_text, opts.block):
        df = df.withColumn(flag, _holds(rows, opts)(F.col(text).cast("string"))).filter(~F.col(flag)).drop(flag)
    return df


def op3_cgk_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return contaminated(docs, table(spark, sf_dir, "benchmark"))
