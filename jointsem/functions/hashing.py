"""A uniform draw from values, equal in Spark, DuckDB and Python.

Every random choice of the engine is such a draw of ids and a seed, so results
do not depend on partitions, row order or retries.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

_RANGE = 4294967296.0


def portable_uniform(*parts: Column | str | int) -> Column:
    """First 32 bits of the md5 of the parts joined by '|', as a number in [0, 1); strings name literals, not columns."""
    joined = F.concat_ws("|", *[(p if isinstance(p, Column) else F.lit(p)).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(joined.cast("binary")), 1, 8), 16, 10).cast("double") / _RANGE


def uniform(*parts: object) -> float:
    """portable_uniform in Python."""
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16) / _RANGE


def uniforms(prefix: tuple, ids) -> np.ndarray:
    """uniform(*prefix, id) for many ids."""
    head = "".join(f"{p}|" for p in prefix)
    return np.frombuffer(b"".join([hashlib.md5(f"{head}{i}".encode()).digest()[:4] for i in ids]), ">u4") / _RANGE


def uniform_table(heads: list[tuple], ids) -> np.ndarray:
    """uniform(*head, id), a row for each head and a column for each id."""
    starts, ends = ["".join(f"{p}|" for p in h).encode() for h in heads], [str(i).encode() for i in ids]
    drawn = b"".join([hashlib.md5(a + b).digest()[:4] for a in starts for b in ends])
    return np.frombuffer(drawn, ">u4").reshape(len(starts), len(ends)) / _RANGE


def uniform_sql(*parts: str) -> str:
    """portable_uniform as DuckDB SQL; parts are SQL expressions."""
    return f"(CAST('0x' || substr(md5(concat_ws('|', {', '.join(f'CAST({p} AS VARCHAR)' for p in parts)})), 1, 8) AS UBIGINT) / {_RANGE})"
