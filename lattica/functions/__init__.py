"""Column functions: portable hashes and signed weights, as columns and as SQL functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

P = 2147483647
#: Coefficients of the squaring rounds.
ROUNDS = ((16807, 7), (39373, 1013), (62089, 50021))


def portable_hash(v, u, seed: int = 0) -> Column:
    """A hash below 2^31 - 1 in BIGINT arithmetic, the same in Spark, SQL and numpy; squaring rounds make it non-linear."""
    v, u = (x if isinstance(x, Column) else F.col(x) for x in (v, u))
    prime = F.lit(P).cast("long")
    x = F.pmod(F.pmod(F.pmod(v, prime) * 48271, prime) + F.pmod(F.pmod(u, prime) * 69621, prime) + F.lit((seed * 40692 + 11) % P), prime)
    for a, b in ROUNDS:
        x = F.pmod(x * x + x * a + b, prime)
    return x


def portable_hash_np(v, u, seed: int = 0) -> np.ndarray:
    v, u = np.asarray(v, np.int64), np.asarray(u, np.int64)
    x = (v % P * 48271 % P + u % P * 69621 % P + (seed * 40692 + 11) % P) % P
    for a, b in ROUNDS:
        x = (x * x + a * x + b) % P
    return x


def hash_sql(v: str, u: str, seed: int = 0) -> str:
    """The hash as SQL text for non-negative v and u."""
    x = f"((({v}) % {P} * 48271 % {P} + ({u}) % {P} * 69621 % {P} + {(seed * 40692 + 11) % P}) % {P})"
    for a, b in ROUNDS:
        x = f"(list_transform([{x}], lambda t: (t * t + {a} * t + {b}) % {P})[1])"
    return x


def signed_weight(w, vu, vv, num: int, den: int) -> Column:
    """den times w'(u,v) = w - (num/den) vu vv."""
    w, vu, vv = (x if isinstance(x, Column) else F.col(x) for x in (w, vu, vv))
    return F.lit(den) * w - F.lit(num) * vu * vv


def ranks_before(gain_u, id_u, gain_v, id_v, den, eps=(1, 10)) -> Column:
    """Whether move u is replayed before move v: a gain larger by eps, else the smaller (hash, id)."""
    lead = (gain_u - gain_v) * eps[1]
    wide = F.lit(den) * eps[0]
    hu, hv = portable_hash(id_u, F.lit(0).cast("long")), portable_hash(id_v, F.lit(0).cast("long"))
    tie = (hu < hv) | ((hu == hv) & (id_u < id_v))
    return (lead >= wide) | ((lead > -wide) & tie)


def register_functions(spark: SparkSession) -> None:
    """signed_weight and portable_hash as SQL functions, inlined by the analyzer."""
    x = f"pmod(pmod(pmod(v, {P}) * 48271, {P}) + pmod(pmod(u, {P}) * 69621, {P}) + pmod(seed * 40692 + 11, {P}), {P})"
    for a, b in ROUNDS:
        x = f"aggregate(array({x}), 0L, (z, t) -> pmod(t * t + {a} * t + {b}, {P}))"
    spark.sql(f"create or replace temporary function portable_hash(v bigint, u bigint, seed bigint) returns bigint return {x}")
    spark.sql("create or replace temporary function signed_weight(w bigint, vu bigint, vv bigint, num bigint, den bigint) returns bigint return den * w - num * vu * vv")


def degree_class(degree, classes: int):
    """Classes of fourfold degree from 0, the last open (a column)."""
    return F.least(F.floor((F.length(F.bin(degree)) - 1) / 2), F.lit(classes - 1)).cast("int")


def degree_class_np(degree, classes: int) -> np.ndarray:
    bits = np.frexp(np.maximum(np.asarray(degree), 1).astype(float))[1]
    return np.minimum((bits - 1) // 2, classes - 1)
