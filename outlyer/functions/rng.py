"""Counter-based randomness: a draw depends on a seed, a purpose and ids only, never on partitioning or retries."""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SEED = 42


def _text(seed: int, purpose: str, cols) -> Column:
    parts = [F.lit(f"{seed}:{purpose}")]
    for c in cols:
        parts.append((F.col(c) if isinstance(c, str) else c if isinstance(c, Column) else F.lit(c)).cast("string"))
    return F.concat_ws(":", *parts)


def u01(purpose: str, *cols, seed: int = SEED, mode: str = "portable") -> Column:
    """Uniform in [0, 1). ``portable`` equals :func:`u01_sql` in DuckDB; ``fast`` stays in one hash instruction."""
    text = _text(seed, purpose, cols)
    if mode == "fast":
        return F.shiftrightunsigned(F.xxhash64(text), 11) / F.lit(float(2**53))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def u01_sql(purpose: str, *cols: str, seed: int = SEED) -> str:
    """The same draw as a DuckDB expression."""
    text = f"concat_ws(':', '{seed}:{purpose}', {', '.join(cols)})"
    return f"(('0x' || substr(md5({text}), 1, 8))::UBIGINT / 4294967296.0)"


def u01_py(purpose: str, *ids, seed: int = SEED) -> float:
    return int(hashlib.md5(":".join([f"{seed}:{purpose}", *map(str, ids)]).encode()).hexdigest()[:8], 16) / 4294967296.0


def uint(purpose: str, b: int, *cols, seed: int = SEED) -> Column:
    """Uniform integer 1..b."""
    return (F.floor(u01(purpose, *cols, seed=seed) * b) + 1).cast("int")


def urange(purpose: str, lo, hi, *cols, seed: int = SEED) -> Column:
    return F.lit(lo) + u01(purpose, *cols, seed=seed) * (F.lit(hi) - F.lit(lo))


def normal01(purpose: str, *cols, seed: int = SEED) -> Column:
    """Standard normal by Box-Muller, rounded to 6 digits."""
    a, b = u01(purpose + "-r", *cols, seed=seed), u01(purpose + "-t", *cols, seed=seed)
    return F.round(F.sqrt(-2 * F.log(F.greatest(a, F.lit(1e-10)))) * F.cos(2 * math.pi * b), 6)


def normal01_sql(purpose: str, *cols: str, seed: int = SEED) -> str:
    return f"round(sqrt(-2 * ln(greatest({u01_sql(purpose + '-r', *cols, seed=seed)}, 1e-10))) * cos({2 * math.pi!r} * {u01_sql(purpose + '-t', *cols, seed=seed)}), 6)"


def bottom_k(df: DataFrame, k: int, purpose: str, id_col: str, by: list[str] | None = None, total: int | None = None, seed: int = SEED) -> DataFrame:
    """The k rows with the smallest draw, in each group of ``by``. With ``total`` a filter keeps about 4k rows before the sort."""
    by = by or []
    keyed = df.withColumn("_u", u01(purpose, *by, id_col, seed=seed))
    if total and total > 4 * k:
        keyed = keyed.where(F.col("_u") < F.lit(4.0 * k / total))
    w = Window.partitionBy(*(by or [F.lit(1)])).orderBy("_u", id_col)
    return keyed.withColumn("_k", F.row_number().over(w)).where(F.col("_k") <= k).drop("_u", "_k")
