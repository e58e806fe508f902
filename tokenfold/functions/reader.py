"""A frozen surrogate reader: the same one for every backend, with no model behind it.

It predicts from the mean of the vectors before it and from what followed vectors
like the last one (an induction read-out). Its numbers compare backends with each
other; they say nothing about a language model.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Reader:
    beta: float = 8.0
    bag: float = 1.0
    induction: float = 1.0
    gain: float = 5.0
    rotary: bool = False
    sliding: int | None = None
    #: Dimensions of the table that the reader sees.
    width: int | None = None
    #: Whether the context first attends to itself, each vector to those at no later position.
    masked: bool = False


READERS = {"flat": Reader(), "rotary": Reader(rotary=True), "sliding": Reader(sliding=2048), "narrow16": Reader(width=16), "narrow8": Reader(width=8), "masked": Reader(rotary=True, masked=True)}


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=-1, keepdims=True), 1e-12)


def prefill(x: np.ndarray, pos: np.ndarray, beta: float = 8.0, block: int = 512) -> np.ndarray:
    """What each vector reads in one masked pass: a mean of those at no later position, by their cosines."""
    keys, out = _unit(x), np.empty_like(x)
    for low in range(0, len(x), block):
        rows = slice(low, low + block)
        score = np.where(pos[None, :] <= pos[rows, None], beta * (keys[rows] @ keys.T), -np.inf)
        w = np.exp(score - score.max(axis=1, keepdims=True))
        out[rows] = (w @ x) / w.sum(axis=1, keepdims=True)
    return out


_OUT: list = [None, None, None]


def _readout(table: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Directions of the table's rows without the shared one, kept for the last table and direction."""
    if _OUT[0] is not table or not np.array_equal(_OUT[1], u):
        _OUT[:] = table, u, _unit(table - np.outer(table @ u, u))
    return _OUT[2]


def attended(reader: Reader, context: np.ndarray, pos: np.ndarray) -> np.ndarray:
    """The context as the reader takes it: after its own masked pass, if it has one."""
    return (context + prefill(context, pos, reader.beta)) / 2 if reader.masked and len(context) else context


def logits(reader: Reader, table: np.ndarray, u: np.ndarray, context: np.ndarray, pos: np.ndarray, continuation: np.ndarray) -> np.ndarray:
    """Logits over the table's rows for each step of a teacher-forced continuation."""
    return _logits(reader, table, u, attended(reader, context, pos), pos, continuation, 0)


def _logits(reader: Reader, table: np.ndarray, u: np.ndarray, context: np.ndarray, pos: np.ndarray, continuation: np.ndarray, begin: int) -> np.ndarray:
    """Those of the steps from `begin` on, after a context that the reader has attended."""
    k = len(continuation)
    s = np.concatenate([context, continuation[:-1]])
    p = np.concatenate([pos, pos[-1] + 1 + np.arange(k - 1)]).astype(float)
    s = s - np.outer(s @ u, u)
    e = _readout(table, u)
    if reader.width:
        s, e = s[:, : reader.width], e[:, : reader.width]
    m = len(context)
    asked = np.empty((k - begin, e.shape[1]))
    total = np.cumsum(s, axis=0)
    keys = _unit(s)
    for t in range(begin, k):
        n = m + t  # vectors before this step
        q, now = keys[n - 1], p[n - 1]
        score = reader.beta * (keys[: n - 1] @ q)
        if reader.rotary:
            score = score * np.cos((now - p[: n - 1]) / 4096.0)
        if reader.sliding:
            score = np.where(now - p[: n - 1] < reader.sliding, score, -np.inf)
        w = np.exp(score - score.max()) if n > 1 and np.isfinite(score.max()) else np.zeros(n - 1)
        after = (w @ s[1:n]) / max(w.sum(), 1e-12)
        asked[t - begin] = reader.bag * _unit(total[n - 1]) + reader.induction * _unit(after)
    return (reader.gain * asked) @ e.T  # one pass over the table for all steps


#: Rows of the table in a tile of first choices, and places of padded contexts that are continued at once.
TILE, MOST_PLACES = 128, 1 << 15
#: How far a row may be, as a share of its length, from the one that it shares a pass over the table with.
NEAR = 1 / 128


def _leaders(h: np.ndarray) -> np.ndarray:
    """For each row an earlier one that is near it, or itself."""
    size = (h * h).sum(axis=1)
    near = size[:, None] + size[None] - 2 * h @ h.T <= NEAR**2 * size[:, None]
    out = np.full(len(h), -1)
    for row in range(len(h)):
        if out[row] < 0:
            out[near[row] & (out < 0)] = row
            out[row] = row
    return out


_NARROW: list = [None, None, None]


def _narrow(e: np.ndarray) -> tuple[np.ndarray, float]:
    """The rows in single precision and the length of the longest, kept for the last table."""
    if _NARROW[0] is not e:
        _NARROW[:] = e, e.astype(np.float32), float(np.sqrt((e * e).sum(axis=1).max(initial=0.0)))
    return _NARROW[1], _NARROW[2]


def first_choices(e: np.ndarray, h: np.ndarray) -> np.ndarray:
    """The row of e with the largest product with each h, the lowest of equal ones.

    One pass in single precision, for one of each group of near rows, gives the largest
    product in each tile. A tile is multiplied again in double precision where the bounds of
    the pass's error and of what the distance of two rows can change let it hold the choice.
    """
    leader = _leaders(h)
    some, place = np.unique(leader, return_inverse=True)
    tops, short, (rows, longest) = [], h[some].astype(np.float32), _narrow(e)
    for low in range(0, len(e), 32 * TILE):
        z = short @ rows[low : low + 32 * TILE].T
        tops.append(np.maximum.reduceat(z, np.arange(0, z.shape[1], TILE), axis=1))
    tops = np.concatenate(tops, axis=1).astype(np.float64)[place]
    apart = np.linalg.norm(h - h[leader], axis=1)
    slack = 2 * longest * ((e.shape[1] + 4) * 2.0**-23 * np.linalg.norm(h[leader], axis=1) + 1.000001 * apart)
    best, out = np.full(len(h), -np.inf), np.zeros(len(h), np.int64)
    for row, tile in zip(*(at.tolist() for at in np.nonzero(tops >= (tops.max(axis=1) - slack)[:, None])), strict=True):
        z = (e[tile * TILE : (tile + 1) * TILE] * h[row]).sum(axis=1)
        at = int(z.argmax())
        if z[at] > best[row]:
            best[row], out[row] = z[at], tile * TILE + at
    return out


def continued(reader: Reader, table: np.ndarray, vocabulary, contexts: list[tuple[np.ndarray, np.ndarray]], steps: int) -> list[tuple[np.ndarray, list[int]]]:
    """For each context (vectors and positions) what it asks the table for first, and the rows that a continuation by first choices takes.

    Contexts of like length take each step together: the table is gone over once for all of them.
    """
    out: list = [None] * len(contexts)
    by = sorted(range(len(contexts)), key=lambda i: -len(contexts[i][1]))
    while by:
        some = max(1, MOST_PLACES // (len(contexts[by[0]][1]) + steps))
        for i, got in zip(by[:some], _continued(reader, table, vocabulary, [contexts[i] for i in by[:some]], steps), strict=True):
            out[i] = got
        by = by[some:]
    return out


def _continued(reader: Reader, table: np.ndarray, vocabulary, contexts: list[tuple[np.ndarray, np.ndarray]], steps: int) -> list[tuple[np.ndarray, list[int]]]:
    u, e = vocabulary.u, _readout(table, vocabulary.u)
    e = e[:, : reader.width] if reader.width else e
    n = np.array([len(pos) for _, pos in contexts])
    rows, length, width = np.arange(len(n)), int(n.max()) + steps, e.shape[1]
    s, p = np.zeros((len(n), length, width)), np.zeros((len(n), length))
    for k, (x, pos) in enumerate(contexts):
        x = attended(reader, x, pos)
        s[k, : n[k]], p[k, : n[k]] = (x - np.outer(x @ u, u))[:, :width], pos
        p[k, n[k] :] = pos[-1] + 1 + np.arange(length - n[k])
    keys, total, first, said = _unit(s), s.sum(axis=1), None, []
    for _ in range(steps):
        now = p[rows, n - 1]
        score = reader.beta * np.matmul(keys, keys[rows, n - 1][:, :, None])[:, :, 0]
        if reader.rotary:
            score = score * np.cos((now[:, None] - p) / 4096.0)
        seen = np.arange(length) < (n - 1)[:, None]
        if reader.sliding:
            seen &= now[:, None] - p < reader.sliding
        score = np.where(seen, score, -np.inf)
        most = score.max(axis=1, keepdims=True)
        w = np.exp(score - np.where(np.isfinite(most), most, 0.0))
        after = np.matmul(w[:, None, :-1], s[:, 1:])[:, 0] / np.maximum(w.sum(axis=1, keepdims=True), 1e-12)
        h = reader.bag * _unit(total) + reader.induction * _unit(after)
        first = h if first is None else first
        said.append(first_choices(e, h))
        x = np.sqrt(1 - vocabulary.a) * table[said[-1]] + np.sqrt(vocabulary.a) * u
        x = (x - np.outer(x @ u, u))[:, :width]
        s[rows, n], keys[rows, n] = x, _unit(x)
        total, n = total + x, n + 1
    return [(h, [int(c[k]) for c in said]) for k, h in enumerate(first)]


def products(reader: Reader, table: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Products of the columns that logits are read from: what two vectors of logits have for one is a bilinear form of what they ask."""
    e = _readout(table, u)
    e = e[:, : reader.width] if reader.width else e
    return e.T @ e


def greedy(reader: Reader, table: np.ndarray, vocabulary, context: np.ndarray, pos: np.ndarray, steps: int) -> tuple[np.ndarray, list[int]]:
    """The logits after the context, and the rows of the table that a continuation by first choices takes."""
    ((h, said),) = continued(reader, table, vocabulary, [(context, pos)], steps)
    e = _readout(table, vocabulary.u)
    return reader.gain * ((e[:, : reader.width] if reader.width else e) @ h), said


def log_softmax(z: np.ndarray) -> np.ndarray:
    z = z - z.max(axis=-1, keepdims=True)
    return z - np.log(np.exp(z).sum(axis=-1, keepdims=True))


def _top(z: np.ndarray, k: int) -> np.ndarray:
    """Places of the k largest numbers of each row, the largest first and the lower place before equal ones, without sorting all."""
    k, out = min(k, z.shape[1]), []
    for row, least in zip(z, np.partition(z, -k, axis=1)[:, -k] if k else z[:, :0], strict=True):
        at = np.flatnonzero(row >= least)
        out.append(at[np.argsort(-row[at], kind="stable")][:k])
    return np.array(out, np.int64).reshape(len(z), k)


@dataclass(frozen=True)
class Reading:
    """What is compared of one context's logits: themselves, log of the sum of their exponentials, length and first choices."""

    z: np.ndarray
    total: np.ndarray
    norm: np.ndarray
    top: np.ndarray


def reading(z: np.ndarray, k: int = 10) -> Reading:
    most = z.max(axis=1, keepdims=True)
    part = z - most
    np.exp(part, out=part)
    return Reading(z, most[:, 0] + np.log(part.sum(axis=1)), np.linalg.norm(z, axis=1), _top(z, k))


def shares(a: Reading) -> np.ndarray:
    """Softmax of a reading's logits."""
    p = a.z - a.total[:, None]
    return np.exp(p, out=p)


def compare(a: np.ndarray | Reading, b: np.ndarray, target: np.ndarray, k: int = 10, p: np.ndarray | None = None) -> dict[str, float]:
    """Quality of logits b against the original's a on one continuation; a reading of a, and its shares p, serve many b."""
    a = a if isinstance(a, Reading) else reading(a, k)
    b, p = reading(b, k), shares(a) if p is None else p
    at = np.arange(len(target))
    nll_a, nll_b = (a.total - a.z[at, target]).mean(), (b.total - b.z[at, target]).mean()
    return {
        "cosine": float((np.einsum("tv,tv->t", a.z, b.z) / np.maximum(a.norm * b.norm, 1e-12)).mean()),
        "top1": float((a.top[:, 0] == b.top[:, 0]).mean()),
        "top10": float(np.mean([len(np.intersect1d(x, y)) / k for x, y in zip(a.top, b.top, strict=True)])),
        "label_accuracy": float((b.top[:, 0] == target).mean()),
        "kl": float((np.einsum("tv,tv->t", p, a.z) - np.einsum("tv,tv->t", p, b.z) - a.total + b.total).mean()),
        "delta_nll": float(nll_b - nll_a),
        "ppl_ratio": float(np.exp(nll_b - nll_a)),
    }
