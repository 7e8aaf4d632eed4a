"""Closed-form code lengths, in bits, as built-in expressions, and the same as SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def bitlen(x: Column) -> Column:
    """Binary digits of x >= 1."""
    return F.length(F.bin(x)).cast("long")


def ceil_log2(x: Column) -> Column:
    """Of x >= 1, exactly."""
    return F.when(x <= 1, F.lit(0)).otherwise(bitlen(x - 1)).cast("long")


def truncated(x: Column, r: Column) -> Column:
    """Bits of the value x of r values, 0 <= x < r, the small ones short."""
    w = bitlen(r) - 1
    return w + F.when(x < F.call_function("shiftleft", F.lit(2).cast("long"), w.cast("int")) - r, 0).otherwise(1)


def unary(g: Column) -> Column:
    return g


def gamma(g: Column) -> Column:
    return 2 * bitlen(g) - 1


def delta(g: Column) -> Column:
    b = bitlen(g)
    return b - 1 + 2 * bitlen(b) - 1


def _pow2(n: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), n.cast("int"))


def zeta(g: Column, k: int) -> Column:
    h = F.floor((bitlen(g) - 1) / k).cast("long")
    low = _pow2(h * k)
    return h + 1 + truncated(g - low, _pow2(h * k + k) - low)


def rice(g: Column, r: Column) -> Column:
    return F.floor((g - 1) / _pow2(r)).cast("long") + 1 + r


def golomb(g: Column, m: Column) -> Column:
    q = F.floor((g - 1) / m).cast("long")
    return q + 1 + truncated(g - 1 - q * m, m)


def vbyte(g: Column) -> Column:
    return 8 * F.ceil(bitlen(g) / 7).cast("long")


def nibble(g: Column) -> Column:
    return 4 * F.ceil(bitlen(g) / 3).cast("long")


def golomb_parameter(n: Column, u: Column) -> Column:
    """About ln 2 times the mean gap, at least 1; in integers, so that engines agree: 69/100."""
    return F.greatest(F.lit(1).cast("long"), F.floor((69 * u + 50 * n) / (100 * n)).cast("long"))


def rice_parameter(n: Column, u: Column) -> Column:
    return bitlen(golomb_parameter(n, u)) - 1


def elias_fano(n: Column, u: Column) -> Column:
    """n ids in 1..u: low bits, and high parts in unary."""
    low = F.when(u > n, bitlen(F.floor(u / n).cast("long")) - 1).otherwise(F.lit(0).cast("long"))
    return n * low + n + F.call_function("shiftright", u, low.cast("int"))


def bernoulli(n: Column, u: Column) -> Column:
    """Ideal bits of u independent draws of which n are ones."""
    part = lambda k: F.when(k > 0, k * F.log2(u / k)).otherwise(F.lit(0.0))
    return part(n) + part(u - n)


def trit_string(g: Column) -> Column:
    return F.concat(F.substring(F.bin(g), 2, 64), F.lit("2"))


#: name -> (parameters, type, body) of the SQL functions; their bodies are inlined by the optimiser.
SQL = {
    "bitlen": ("g BIGINT", "BIGINT", "length(bin(g))"),
    "gamma_bits": ("g BIGINT", "BIGINT", "2 * length(bin(g)) - 1"),
    "delta_bits": ("g BIGINT", "BIGINT", "length(bin(g)) + 2 * length(bin(length(bin(g)))) - 2"),
    "vbyte_bits": ("g BIGINT", "BIGINT", "8 * ((length(bin(g)) + 6) div 7)"),
    "nibble_bits": ("g BIGINT", "BIGINT", "4 * ((length(bin(g)) + 2) div 3)"),
    "rice_bits": ("g BIGINT, r INT", "BIGINT", "shiftright(g - 1, r) + 1 + r"),
    "truncated_bits": ("x BIGINT, r BIGINT", "BIGINT", "length(bin(r)) - IF(x < shiftleft(2L, length(bin(r)) - 1) - r, 1, 0)"),
    "golomb_bits": ("g BIGINT, m BIGINT", "BIGINT", "(g - 1) div m + 1 + length(bin(m)) - IF((g - 1) % m < shiftleft(2L, length(bin(m)) - 1) - m, 1, 0)"),
    "zeta_bits": ("g BIGINT, k INT", "BIGINT", "(length(bin(g)) - 1) div k + 1 + length(bin(shiftleft(1L, CAST(((length(bin(g)) - 1) div k) * k + k AS INT)) - shiftleft(1L, CAST(((length(bin(g)) - 1) div k) * k AS INT)))) - IF(g - shiftleft(1L, CAST(((length(bin(g)) - 1) div k) * k AS INT)) < shiftleft(2L, length(bin(shiftleft(1L, CAST(((length(bin(g)) - 1) div k) * k + k AS INT)) - shiftleft(1L, CAST(((length(bin(g)) - 1) div k) * k AS INT)))) - 1) - (shiftleft(1L, CAST(((length(bin(g)) - 1) div k) * k + k AS INT)) - shiftleft(1L, CAST(((length(bin(g)) - 1) div k) * k AS INT))), 1, 0)"),
    "ef_bits": ("n BIGINT, u BIGINT", "BIGINT", "n * IF(u > n, length(bin(u div n)) - 1, 0) + n + shiftright(u, IF(u > n, length(bin(u div n)) - 1, 0))"),
    "trit_string": ("g BIGINT", "STRING", "concat(substr(bin(g), 2), '2')"),
    "trits_to_gaps": ("s STRING", "ARRAY<BIGINT>", "transform(filter(split(s, '2', -1), (x, i) -> i < length(s) - length(replace(s, '2', ''))), x -> CAST(conv(concat('1', x), 2, 10) AS BIGINT))"),
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions of the session, and the Arrow-backed ``stem`` and ``midpoint_bits``."""
    for name, (args, kind, body) in SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    from ..operators.codecs import midpoint_udf
    from .stem import stem_udf

    spark.udf.register("stem", stem_udf())
    spark.udf.register("midpoint_bits", midpoint_udf())
