"""Column functions: portable hashes, activation, ties, z log z."""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

DEC = "decimal(38,0)"


def portable(*parts: Column | str | int) -> Column:
    """First eight hex digits of the md5 of the parts joined by ":", as a number."""
    cols = [p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *cols)), 1, 8), 16, 10).cast("long")


def activation_sql(v: str, rnd: int, seed: int, k: int, kind: str = "fast") -> str:
    """`activation` as SQL text; moving phases are built of texts, which cost one call to the JVM each."""
    return f"{portable_sql(v, rnd, seed)} % {k}" if kind == "portable" else f"pmod(xxhash64({v}, {rnd}, {seed}), {k})"


def tie_sql(c: str, v: str, seed: int, kind: str = "fast") -> str:
    return portable_sql(c, seed, between=v) if kind == "portable" else f"xxhash64({c}, {v}, {seed})"


def portable_sql(v: str, *numbers: int, between: str | None = None) -> str:
    parts = [v, *([between] if between else []), *[f"'{x}'" for x in numbers]]
    return f"cast(conv(substring(md5(concat_ws(':', {', '.join(parts)})), 1, 8), 16, 10) as bigint)"


def plogp_sql(z: str) -> str:
    return f"CASE WHEN {z} > 0 THEN {z} * ln(greatest({z}, 1e-300D)) ELSE 0D END"


def activation(v: Column, rnd: int, seed: int, k: int, kind: str = "fast") -> Column:
    """The sub-round of round `rnd` in which node v may move."""
    return portable(v, rnd, seed) % k if kind == "portable" else F.pmod(F.xxhash64(v, F.lit(rnd), F.lit(seed)), F.lit(k))


def tie_key(c: Column, v: Column, seed: int, kind: str = "fast") -> Column:
    return portable(c, v, seed) if kind == "portable" else F.xxhash64(c, v, F.lit(seed))


def plogp(z: Column, base: float = math.e) -> Column:
    return F.when(z > 0, z * F.ln(F.greatest(z, F.lit(1e-300)))).otherwise(F.lit(0.0)) / (1.0 if base == math.e else math.log(base))


def power_law(u: Column, lo: float, hi: float, exponent: float) -> Column:
    """Inverse distribution function of a power law cut to [lo, hi]."""
    if exponent == 1:
        return lo * F.pow(F.lit(hi / lo), u)
    e = 1 - exponent
    return F.pow(lo**e + u * (hi**e - lo**e), F.lit(1 / e))


def register_sql(spark: SparkSession) -> None:
    """plogp as a function of Spark SQL."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION plogp(x DOUBLE) RETURNS DOUBLE RETURN CASE WHEN x > 0 THEN x * ln(x) ELSE 0D END")
