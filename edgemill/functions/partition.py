"""Exact range and chunk arithmetic, as expressions and as SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from edgemill.config import Layout
from edgemill.functions.prng import hash_constants


def int_div(a: Column, b: Column | int) -> Column:
    """Integer division of longs, exact at any size."""
    return F.call_function("div", a, F.lit(b).cast("long") if isinstance(b, int) else b)


def owner_of(v: Column, n: int, nb: int) -> Column:
    """The bucket whose range holds v: floor(v * nb / n); ranges differ by one vertex at most."""
    return int_div(v * F.lit(nb).cast("long"), n)


def bin_of(v: Column, layout: Layout) -> Column:
    return int_div(v * F.lit(layout.nb * layout.nc).cast("long"), layout.n)


def lane_of(v: Column, layout: Layout) -> Column:
    return F.pmod(bin_of(v, layout), F.lit(layout.nc))


def range_lo(bucket: Column | int, n: int, nb: int):
    """The first vertex of a bucket's range."""
    if isinstance(bucket, int):
        return (bucket * n + nb - 1) // nb
    return int_div(bucket * F.lit(n).cast("long") + (nb - 1), nb)


def chunk_of(position: Column, chunk: int) -> Column:
    return int_div(position, chunk)


def _hash_body(bits: int, key: int = 7, rounds: int = 4) -> str:
    """prng.bijective_hash as SQL."""
    mask, low, half, body = (1 << bits) - 1, (1 << min(bits, 24)) - 1, (bits + 1) // 2, "v"
    for a, c in hash_constants(key, rounds):
        moved = f"(({body} * {(a & low) | 1} + {c & mask}) & {mask})"
        body = f"({moved} ^ shiftright({moved}, {half}))"
    return body


def register_sql(spark: SparkSession, hash_bits: int = 24) -> None:
    """The same arithmetic, and the collision-free hash on [0, 2^hash_bits), for SQL users; the analyzer inlines the bodies, so they stay in generated code."""
    for name, args, body in (
        ("owner_of", "v BIGINT, n BIGINT, nb BIGINT", "(v * nb) div n"),
        ("lane_of", "v BIGINT, n BIGINT, nb BIGINT, nc BIGINT", "((v * nb * nc) div n) % nc"),
        ("range_lo", "b BIGINT, n BIGINT, nb BIGINT", "(b * n + nb - 1) div nb"),
        ("chunk_of", "p BIGINT, csz BIGINT", "p div csz"),
        ("bijective_hash", "v BIGINT", _hash_body(hash_bits)),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS BIGINT RETURN {body}")
