"""Public regions of attributes and the cells they span.

A region number is a Column expression of built-in functions, so cells are counted in generated
code and only the bucketed columns are read.  Regions are declared, never taken from the data.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Attribute:
    """``size`` disjoint regions numbered by ``region``; values outside are null before the overflow policy."""

    name: str
    region: Column
    size: int
    overflow: str = "drop"  # drop, clamp or error

    @staticmethod
    def width(name: str, value: Column, low: float, step: float, size: int, overflow: str = "drop") -> Attribute:
        return Attribute(name, F.floor((value - F.lit(low)) / F.lit(step)).cast("long"), size, overflow)

    @staticmethod
    def edges(name: str, value: Column, edges: list[float], overflow: str = "drop") -> Attribute:
        """Regions [edges[i], edges[i+1])."""
        region = reduce(lambda a, e: a + (value >= F.lit(e)).cast("long"), edges[1:], F.when(value >= F.lit(edges[0]), 0).otherwise(-1).cast("long"))
        return Attribute(name, region, len(edges) - 1, overflow)

    @staticmethod
    def dates(name: str, value: Column, start: str, numerator: int, days: int, size: int, overflow: str = "drop") -> Attribute:
        """Region numerator * (days since start) div days."""
        since = F.datediff(value, F.lit(start).cast("date")).cast("long")
        return Attribute(name, F.floor(since * numerator / days).cast("long"), size, overflow)

    @staticmethod
    def categories(name: str, value: Column, values: list) -> Attribute:
        return Attribute.groups(name, value, [[v] for v in values])

    @staticmethod
    def groups(name: str, value: Column, groups: list[list]) -> Attribute:
        """Value sets, which need not be contiguous; other values are outside."""
        region = F.lit(None).cast("long")
        for k in range(len(groups) - 1, -1, -1):
            region = F.when(value.isin(groups[k]), F.lit(k).cast("long")).otherwise(region)
        return Attribute(name, region, len(groups))

    @staticmethod
    def flag(name: str, condition: Column) -> Attribute:
        return Attribute(name, condition.cast("long"), 2)

    def placed(self) -> Column:
        r, last = self.region, self.size - 1
        if self.overflow == "clamp":
            return F.least(F.greatest(r, F.lit(0)), F.lit(last))
        inside = r.between(0, last)
        if self.overflow == "error":
            return F.when(r.isNull() | inside, r).otherwise(F.raise_error(F.lit(f"value outside the regions of {self.name}")).cast("long"))
        return F.when(inside, r)


@dataclass(frozen=True)
class Domain:
    """The cross product of attributes; cells are numbered row by row, the first attribute slowest."""

    attributes: tuple[Attribute, ...]

    @property
    def dims(self) -> tuple[int, ...]:
        return tuple(a.size for a in self.attributes)

    @property
    def n(self) -> int:
        return reduce(lambda a, b: a * b, self.dims, 1)

    def cell_id(self) -> Column:
        """The cell of a row; null if some value has no region."""
        return reduce(lambda c, a: c * F.lit(a.size) + a.placed(), self.attributes, F.lit(0).cast("long"))

    def coords(self, cell: Column) -> list[Column]:
        out, rest = [], cell
        for a in reversed(self.attributes):
            out.append((rest % a.size).alias(a.name))
            rest = F.call_function("div", rest, F.lit(a.size))
        return out[::-1]
