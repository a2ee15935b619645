"""A seeded hash family in 64-bit integer arithmetic, the same in Spark, DuckDB and numpy.

Two affine rounds modulo a prime with a fold between them; plain affine hashes give false-positive counts with a far
wider spread. Offsets must be below 2**31: blocks keep them small, and the block number enters the first round.
"""

from __future__ import annotations

import random
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2**31 - 1
SHIFT = 15


@lru_cache(maxsize=1024)
def constants(j: int, seed: int, tag: str) -> tuple[int, int, int, int, int]:
    r = random.Random(f"{tag}/{seed}/{j}")
    return tuple(r.randrange(1, PRIME) for _ in range(5))


def hash_sql(offset: str, j: int = 0, seed: int = 0, tag: str = "bloom", block: str = "0", duckdb: bool = False) -> str:
    """An SQL expression in [0, PRIME) over an integer expression."""
    a, b, c, d, e = constants(j, seed, tag)
    first = f"((CAST({offset} AS BIGINT) * {a} + (CAST({block} AS BIGINT) % 65536) * {b} + {c}) % {PRIME})"
    fold = f"xor({first}, {first} >> {SHIFT})" if duckdb else f"({first} ^ shiftright({first}, {SHIFT}))"
    return f"(({fold} * {d} + {e}) % {PRIME})"


def hash_of(offset: str, j: int = 0, seed: int = 0, tag: str = "bloom", block: str = "0") -> Column:
    return F.expr(hash_sql(offset, j, seed, tag, block))


def hash_positions(offset: str, k: int, m: str, seed: int = 0, block: str = "0") -> Column:
    """Array of k filter positions; m is an SQL expression."""
    return F.array(*[F.expr(f"{hash_sql(offset, j, seed, 'bloom', block)} % {m}") for j in range(k)])


def hash_array(offset: np.ndarray, j: int = 0, seed: int = 0, tag: str = "bloom", block: int = 0) -> np.ndarray:
    a, b, c, d, e = constants(j, seed, tag)
    first = (offset.astype(np.int64) * a + (block % 65536) * b + c) % PRIME
    return ((first ^ (first >> SHIFT)) * d + e) % PRIME
