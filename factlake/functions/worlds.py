"""Corpora in several versions ("worlds") that share most units: a row says by ``worlds``, a bit for each, which it is in."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def worlds_of(n: int) -> list[str]:
    """What the names of columns that differ between n worlds end in; a corpus of one world (n is 0) has one column of each."""
    return [f"_{i}" for i in range(n)] or [""]


def inside(world: int | str) -> Column:
    """Whether a row is in a world, given by its number or by what its columns end in."""
    if world == "":
        return F.lit(True)
    return F.col("worlds").bitwiseAND(F.lit(1 << int(str(world).lstrip("_")))) != 0
