"""Public domains of matrices: dimensions with declared bounds and widths, never taken from the data."""

from __future__ import annotations

import json
from dataclasses import dataclass
from math import prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class DimSpec:
    """An ordered axis: ``expr`` (Spark SQL) over [lo, hi) in ``cells`` equal cells, or the declared ``values`` in order."""

    name: str
    expr: str
    lo: float = 0.0
    hi: float = 1.0
    cells: int = 1
    values: tuple[str, ...] = ()

    @property
    def width(self) -> int:
        return len(self.values) or self.cells

    def index(self, outside: str = "drop") -> Column:
        """The cell of a value; null where the record is outside (drop), else the nearest cell (clamp) or a failure (error)."""
        x = F.expr(self.expr)
        if self.values:
            at = F.array_position(F.array(*map(F.lit, self.values)), x.cast("string")).cast("int") - 1
            missing = F.raise_error(F.concat(F.lit(f"{self.name}: undeclared value "), x.cast("string"))).cast("int") if outside == "error" else F.lit(None).cast("int")
            return F.when(x.isNull(), F.lit(None).cast("int")).when(at >= 0, at).otherwise(missing)
        x = x.cast("double")
        at = F.floor((x - self.lo) * self.cells / (self.hi - self.lo)).cast("int")
        usable = x.isNotNull() & ~F.isnan(x)
        inside = (x >= self.lo) & (x < self.hi)
        if outside == "clamp":
            at = F.when(x < self.lo, 0).when(x >= self.hi, self.cells - 1).otherwise(at)
            return F.when(usable, F.greatest(F.lit(0), F.least(at, F.lit(self.cells - 1))))
        beyond = F.raise_error(F.lit(f"{self.name}: value out of bounds")).cast("int") if outside == "error" else F.lit(None).cast("int")
        return F.when(usable & inside, F.least(at, F.lit(self.cells - 1))).when(usable, beyond)


@dataclass(frozen=True)
class MatrixSpec:
    name: str
    dims: tuple[DimSpec, ...]
    unit: str = "record"

    @property
    def d(self) -> int:
        return len(self.dims)

    @property
    def widths(self) -> tuple[int, ...]:
        return tuple(dim.width for dim in self.dims)

    @property
    def entries(self) -> int:
        return prod(self.widths)

    @property
    def axes(self) -> list[str]:
        return [f"x{i}" for i in range(1, self.d + 1)]

    @property
    def key(self) -> str:
        """Names the matrix in the keys of its noise; matrices of one name and shape must be the same."""
        return f"{self.name}:{'x'.join(map(str, self.widths))}"

    def prefix(self, d: int) -> MatrixSpec:
        return MatrixSpec(f"{self.name}{d}", self.dims[:d], self.unit)

    def index_columns(self, df: DataFrame, outside: str = "drop") -> DataFrame:
        """x1..xd of each record; a record with any null coordinate is dropped."""
        placed = df.select(*[dim.index(outside).alias(x) for dim, x in zip(self.dims, self.axes)])
        return placed.where(" AND ".join(f"{x} IS NOT NULL" for x in self.axes))

    def json(self) -> str:
        return json.dumps([[dim.name, dim.expr, dim.lo, dim.hi, dim.width] for dim in self.dims])


def plain(name: str, *widths: int) -> MatrixSpec:
    """A matrix whose records already hold cell positions x1..xd."""
    return MatrixSpec(name, tuple(DimSpec(f"x{i}", f"x{i}", 0, w, w) for i, w in enumerate(widths, 1)))
