"""Integer hashes that Spark and other SQL engines compute alike, and placements built on them.

Each is written once as an SQL expression over BIGINT, so the same text serves ``expr`` and an oracle.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# fixed values: multipliers, increments and moduli of the four hashes
MIX = {1: (1103515245, 12345, 1 << 31), 2: (1664525, 1013904223, 1 << 32), 3: (69069, 1, 1 << 32), 4: (22695477, 1, 1 << 31)}


def mix_sql(k: int, x: str) -> str:
    a, c, m = MIX[k]
    return f"(({a} * ({x}) + {c}) % {m})"


def edge_mix_sql(src: str, dst: str, seed: int) -> str:
    return mix_sql(2, f"31 * {src} + 17 * {dst} + {7919 * seed}")


def part_sql(vid: str, parts: int, engine: str = "spark") -> str:
    """Hash placement from the high bits (ids are tagged in their low bits)."""
    div = "div" if engine == "spark" else "//"
    return f"(({mix_sql(1, vid)} {div} 65536) % {parts})"


def mix(k: int, x: Column) -> Column:
    a, c, m = MIX[k]
    return (F.lit(a).cast("long") * x + F.lit(c)) % F.lit(m).cast("long")


def hash_part(vid: Column, parts: int) -> Column:
    return (F.floor(mix(1, vid) / 65536) % parts).cast("int")
