"""Counter-based random columns: the same key gives the same number in any partitioning, on any retry and in other engines."""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

TWO52 = float(1 << 52)


def unit_int(*key: Column | int, fast: bool = False) -> Column:
    """52-bit integer from the key: md5 (portable), or xxhash64 (fast, Spark only)."""
    cols = [k if isinstance(k, Column) else F.lit(k) for k in key]
    if fast:
        return F.shiftrightunsigned(F.xxhash64(*cols), 12)
    return F.conv(F.substring(F.md5(F.concat_ws("|", *cols)), 1, 13), 16, 10).cast("long")


def uniform(*key: Column | int, fast: bool = False) -> Column:
    """Uniform double in [0, 1)."""
    return unit_int(*key, fast=fast) / F.lit(TWO52)


def normal4(*key: Column | int, fast: bool = False) -> Column:
    """Near-normal, zero mean, unit variance: four uniforms, arithmetic only."""
    u = [uniform(*key, j, fast=fast) for j in range(1, 5)]
    return (u[0] + u[1] + u[2] + u[3] - F.lit(2.0)) * F.lit(math.sqrt(3.0))


def sql_unit(*key: str) -> str:
    """``uniform`` as DuckDB SQL."""
    return f"(CAST(('0x' || substr(md5(concat_ws('|', {', '.join(key)})), 1, 13)) AS BIGINT) / {TWO52!r})"


def sql_normal4(*key: str) -> str:
    u = [sql_unit(*key, str(j)) for j in range(1, 5)]
    return f"(({u[0]} + {u[1]} + {u[2]} + {u[3]} - 2.0) * {math.sqrt(3.0)!r})"


def py_int(*key: int) -> int:
    return int(hashlib.md5("|".join(map(str, key)).encode()).hexdigest()[:13], 16)


def py_uniform(*key: int) -> float:
    return py_int(*key) / TWO52


def py_uniforms(prefix: tuple[int, ...], rows: int, cols: int) -> np.ndarray:
    """Matrix of uniforms keyed (prefix, row, col); row and column counters start at 0."""
    head = "|".join(map(str, prefix))
    return np.array([[int(hashlib.md5(f"{head}|{r}|{c}".encode()).hexdigest()[:13], 16) for c in range(cols)] for r in range(rows)]) / TWO52


def py_normal4(*key: int) -> float:
    u = [py_uniform(*key, j) for j in range(1, 5)]
    return (u[0] + u[1] + u[2] + u[3] - 2.0) * math.sqrt(3.0)
