"""Random numbers from counters: one formula in Spark SQL, DuckDB and numpy.

A uniform number is the first 52 bits of md5(seed|tag|i|j), taken at the middle of
its cell; a normal number combines two of them (Box-Muller). Any task can draw any
number without state, and an oracle can replay it.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np

_CELLS = float(1 << 52)


def uniform_sql(seed: int, tag: str, i: str, j: str, engine: str = "spark") -> str:
    """SQL text of a uniform number; i and j are SQL expressions of integers."""
    digest = f"substr(md5(concat('{seed}|{tag}|', cast({i} AS {'STRING' if engine == 'spark' else 'VARCHAR'}), '|', cast({j} AS {'STRING' if engine == 'spark' else 'VARCHAR'}))), 1, 13)"
    number = f"cast(conv({digest}, 16, 10) AS DOUBLE)" if engine == "spark" else f"cast(cast('0x' || {digest} AS BIGINT) AS DOUBLE)"
    return f"(({number} + 0.5D) / 4503599627370496D)" if engine == "spark" else f"(({number} + 0.5) / 4503599627370496.0)"


def normal_sql(seed: int, tag: str, i: str, j: str, engine: str = "spark") -> str:
    u, v = (uniform_sql(seed, f"{tag}{k}", i, j, engine) for k in "ab")
    return f"(sqrt(-2 * ln({u})) * cos(2 * pi() * {v}))"


def _uniform(seed: int, tag: str, i: int, j: int) -> float:
    return (int(hashlib.md5(f"{seed}|{tag}|{i}|{j}".encode()).hexdigest()[:13], 16) + 0.5) / _CELLS


_DRAWN: dict[tuple[int, str, int], np.ndarray] = {}
#: Numbers that are remembered for one seed and tag; longer arrays are drawn anew.
_MOST = 1 << 20


def uniforms(seed: int, tag: str, n: int, m: int) -> np.ndarray:
    """Numbers of the places up to n by m. Rows that were drawn before are not drawn again, whatever n was."""
    have = _DRAWN.get((seed, tag, m), np.empty((0, m)))
    if len(have) < n:
        more = np.array([[_uniform(seed, tag, i, j) for j in range(m)] for i in range(len(have), n)]).reshape(n - len(have), m)
        have = np.concatenate([have, more])
        if have.size <= _MOST:
            if len(_DRAWN) > 256:
                _DRAWN.clear()
            _DRAWN[seed, tag, m] = have
    out = have[:n]
    out.setflags(write=False)
    return out


@lru_cache(64)
def normals(seed: int, tag: str, n: int, m: int) -> np.ndarray:
    out = np.sqrt(-2 * np.log(uniforms(seed, f"{tag}a", n, m))) * np.cos(2 * np.pi * uniforms(seed, f"{tag}b", n, m))
    out.setflags(write=False)
    return out


def normals_at(seed: int, tag: str, rows: np.ndarray) -> np.ndarray:
    """The first column of `normals` at chosen rows alone."""
    u, v = (np.array([_uniform(seed, f"{tag}{k}", i, 0) for i in rows.tolist()], np.float64) for k in "ab")
    return np.sqrt(-2 * np.log(u)) * np.cos(2 * np.pi * v)
