"""Cost models of a road edge. Integers throughout: tenths of seconds, metres, counts, energy units."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Speed by market segment of the tail, penalties of a crossing with and without a light.
SPEEDS = {"BUILDING": 30, "HOUSEHOLD": 50, "FURNITURE": 70, "MACHINERY": 100, "AUTOMOBILE": 130}
LIGHT, NO_LIGHT = 300, 150

#: One letter per criterion of the grid network.
LETTERS = {"t": "c_time", "d": "c_distance", "c": "c_crossings", "l": "c_penalised", "e": "c_energy"}
ALL = list(LETTERS.values())


@dataclass(frozen=True)
class Criterion:
    """A named non-negative cost; `scale` turns decimals into whole numbers."""

    name: str
    expr: Column
    scale: int = 1

    def column(self) -> Column:
        return (F.round(self.expr * self.scale) if self.scale != 1 else self.expr).cast("long").alias(self.name)


def criterion(name: str, expr: Column, scale: int = 1) -> Criterion:
    if scale < 1:
        raise ValueError("scale must be positive")
    return Criterion(name, expr, scale)


def duration(distance: Column, speed: Column) -> Column:
    return F.floor(distance * 36 / speed).cast("long")


def crossings(head_nation: Column) -> Column:
    return F.when(head_nation % 3 == 0, 1).otherwise(0).cast("long")


def penalised(time: Column, head_nation: Column) -> Column:
    return (time + F.when(head_nation % 6 == 0, LIGHT).when(head_nation % 3 == 0, NO_LIGHT).otherwise(0)).cast("long")


def energy(distance: Column, ascent: Column) -> Column:
    return F.greatest(F.lit(0), F.floor(distance / 4) + ascent).cast("long")


def columns(letters: str | list[str]) -> list[str]:
    """'tel' -> cost columns; a list of names passes through."""
    return [LETTERS[x] for x in letters] if isinstance(letters, str) else list(letters)
