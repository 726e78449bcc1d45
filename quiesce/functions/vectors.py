"""Distances and nearest centres as unrolled JVM expressions."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def coordinates(d: int) -> list[str]:
    return [f"x{j}" for j in range(d)]


def sqdist(xs: list[str], centre: list[float]) -> Column:
    """Squared distance; it has the same order as the distance."""
    return reduce(lambda a, b: a + b, ((F.col(x) - F.lit(float(c))) * (F.col(x) - F.lit(float(c))) for x, c in zip(xs, centre)))


def nearest(distances: list[tuple[int, Column]]) -> Column:
    """Struct (d, m) of the smallest distance, ties to the smaller index."""
    structs = [F.struct(d.alias("d"), F.lit(m).alias("m")) for m, d in distances]
    return structs[0] if len(structs) == 1 else F.least(*structs)


def last_nearest(distances: list[tuple[int, Column]]) -> Column:
    """Struct (d, m) of the smallest distance, ties to the larger index."""
    structs = [F.struct(d.alias("d"), F.lit(-m).alias("m")) for m, d in distances]
    best = structs[0] if len(structs) == 1 else F.least(*structs)
    return F.struct(best["d"].alias("d"), (-best["m"]).alias("m"))


def array_sqdist(a: Column, b: Column) -> Column:
    """For vectors as arrays; readable, but outside code generation."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
