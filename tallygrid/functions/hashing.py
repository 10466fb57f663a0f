"""Hash families that send an item to one of k cells, once per replicate.

`poly4`: a cubic polynomial over the integers modulo 2^31 - 1, for integer items below it; any SQL engine can compute it. `md5`: a prefix of the digest
of salt and item, for strings and large keys, portable too. `xx64`: Spark's 64-bit hash with the salt in front, the fast choice for production.
Affine hashing is not offered: on sequential keys its cells are far too even for any error model.
"""

from __future__ import annotations

import random
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1


@dataclass(frozen=True)
class GridSpec:
    """Depth r, width k and hash family of a grid; grids can be added only if their specs are equal."""

    r: int
    k: int
    family: str = "xx64"
    seed: int = 11

    def __post_init__(self):
        if self.r < 1 or self.k < 1 or self.family not in ("xx64", "poly4", "md5"):
            raise ValueError(f"no such grid: {self}")

    @property
    def cells(self) -> int:
        return self.r * self.k


def coefficients(spec: GridSpec, rep: int) -> list[int]:
    draw = random.Random(spec.seed * 1_000_003 + rep)
    return [draw.randrange(1, PRIME) for _ in range(4)]


def cell_sql(item: str, rep: int, spec: GridSpec) -> str:
    """The cell of `item`, an SQL expression, as SQL that DuckDB and Spark read alike (portable families only)."""
    if spec.family == "poly4":
        a, b, c, d = coefficients(spec, rep)
        return f"(((({a} * ({item}) + {b}) % {PRIME} * ({item}) + {c}) % {PRIME} * ({item}) + {d}) % {PRIME}) % {spec.k}"
    if spec.family == "md5":
        return f"CAST(concat('0x', substr(md5(concat('{spec.seed}.{rep}:', ({item}))), 1, 15)) AS BIGINT) % {spec.k}"
    raise ValueError(f"{spec.family} has no portable form")


def cell(item: Column, rep: int, spec: GridSpec) -> Column:
    if spec.family == "xx64":
        return F.pmod(F.xxhash64(F.lit(spec.seed * 1_000_003 + rep), item), F.lit(spec.k).cast("long"))
    if spec.family == "md5":
        digest = F.md5(F.concat(F.lit(f"{spec.seed}.{rep}:"), item.cast("string")).cast("binary"))
        return F.pmod(F.conv(F.substring(digest, 1, 15), 16, 10).cast("long"), F.lit(spec.k).cast("long"))
    x, out = item.cast("long"), F.lit(0).cast("long")
    for c in coefficients(spec, rep):
        out = (out * x + F.lit(c).cast("long")) % F.lit(PRIME).cast("long")
    return out % F.lit(spec.k).cast("long")


def sign_sql(item: str, rep: int, spec: GridSpec) -> str:
    """+1 or -1 from a hash of its own."""
    return f"(1 - 2 * ({cell_sql(item, rep, GridSpec(spec.r, 2, spec.family, spec.seed + 1000))}))"


def sign(item: Column, rep: int, spec: GridSpec) -> Column:
    return F.lit(1).cast("long") - 2 * cell(item, rep, GridSpec(spec.r, 2, spec.family, spec.seed + 1000))
