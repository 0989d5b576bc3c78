"""Counter-based uniforms: a function of seed, purpose and keys only, so retried tasks and other engines get the same."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

_BITS52 = float(1 << 52)


def u01(seed: int, purpose: str, *keys: Column, fast: bool = False) -> Column:
    """Uniform in [0, 1). Portable: the first 13 hexadecimal digits of an md5; fast: xxhash64."""
    if fast:
        return F.pmod(F.xxhash64(F.lit(seed), F.lit(purpose), *keys), F.lit(1 << 52)) / F.lit(_BITS52)
    text = F.concat_ws(":", F.lit(str(seed)), F.lit(purpose), *[k.cast("string") for k in keys])
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long") / F.lit(_BITS52)


def u01_sql(seed: int, purpose: str, *keys: str) -> str:
    """The portable form in DuckDB's SQL."""
    text = " || ':' || ".join([f"'{seed}:{purpose}'", *[f"CAST({k} AS VARCHAR)" for k in keys]])
    return f"(CAST('0x' || substr(md5({text}), 1, 13) AS BIGINT) / {int(_BITS52)}.0)"


def id_keys(df: DataFrame, name: str = "walk_id") -> list[Column]:
    """The parts of an id column as keys of `u01`: its fields, or itself if it has none."""
    kind = df.schema[name].dataType
    return [F.col(f"{name}.{f}") for f in kind.names] if isinstance(kind, StructType) else [F.col(name)]


def hop_thresholds(alpha: float) -> list[float]:
    """Cumulative probabilities of the hop counts, as far as a uniform of 52 bits can tell them from 1."""
    longest = math.ceil(52 * math.log(2) / -math.log1p(-alpha))
    return [1 - (1 - alpha) ** k for k in range(1, longest)]


def geometric(u: Column, alpha: float, least: int = 1, fast: bool = False) -> Column:
    """Hop count: least, and one more for each threshold that u reaches. Portable: by comparison with the thresholds, which
    every engine does alike; fast: by logarithms."""
    if fast:
        return (F.floor(F.log1p(-u) / F.lit(math.log1p(-alpha))) + F.lit(least)).cast("int")
    steps = F.array(*[F.lit(t) for t in hop_thresholds(alpha)])
    # the uniform is bound once: inside the filter it would be drawn again for each threshold
    return F.element_at(F.transform(F.array(u), lambda v: (F.size(F.filter(steps, lambda t: v >= t)) + F.lit(least)).cast("int")), 1)


def pick_slot(u: Column, d: Column) -> Column:
    return F.floor(u * d).cast("long")
