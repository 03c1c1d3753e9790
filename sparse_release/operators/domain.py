"""Declared attribute domains: coordinates to cell numbers and back.

The owner states every domain; none is read off the data, since that would tell which values occur.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

OTHER = "__other__"


@dataclass(frozen=True)
class Dimension:
    """name; radix; code: SQL of a whole number (null or out of range: outside); label: SQL of the value that stands for a code, with {c} for it."""

    name: str
    radix: int
    code: str
    label: str = "{c}"


def categorical(name: str, values: list[str], column: str | None = None, other: bool = False) -> Dimension:
    """One code for each value in the order given; with `other`, a last one for all else and null."""
    column = column or name
    quoted = ["'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'" for v in [*values, *([OTHER] if other else [])]]
    code = f"map({', '.join(f'{v}, {k}L' for k, v in enumerate(quoted[: len(values)]))})[{column}]"
    return Dimension(name, len(quoted), f"coalesce({code}, {len(values)}L)" if other else code, f"array({', '.join(quoted)})[CAST({{c}} AS INT)]")


def int_range(name: str, lo: int, hi: int, column: str | None = None) -> Dimension:
    """Whole numbers lo up to hi - 1."""
    return Dimension(name, hi - lo, f"CAST({column or name} AS BIGINT) - {lo}", f"{{c}} + {lo}")


def bucket(name: str, width: float, n: int, column: str | None = None, lo: float = 0) -> Dimension:
    """Numeric buckets of one width; a label is the bucket's lower end. NaN is outside."""
    x = f"CAST({column or name} AS DOUBLE)"
    return Dimension(name, n, f"CASE WHEN NOT isnan({x}) THEN CAST(floor(({x} - {lo!r}D) / {float(width)!r}D) AS BIGINT) END", f"{{c}} * {width} + {lo}")


def day(name: str, origin: str, n: int, column: str | None = None) -> Dimension:
    return Dimension(name, n, f"date_diff(CAST({column or name} AS DATE), DATE'{origin}')", f"date_add(DATE'{origin}', CAST({{c}} AS INT))")


def hour(name: str, origin: str, n: int, column: str | None = None) -> Dimension:
    return Dimension(name, n, f"timestampdiff(HOUR, TIMESTAMP_NTZ'{origin}', CAST({column or name} AS TIMESTAMP_NTZ))", f"TIMESTAMP_NTZ'{origin}' + make_dt_interval(0, CAST({{c}} AS INT))")


@dataclass(frozen=True)
class Domain:
    """Dimensions in order; the last turns fastest. outside: drop (rows go), clamp (nearest code; null: the first)."""

    dims: tuple[Dimension, ...]
    outside: str = "drop"
    order: tuple[str, ...] = field(default=())

    @property
    def size(self) -> int:
        return math.prod(d.radix for d in self.dims)

    def _layout(self) -> list[Dimension]:
        by = {d.name: d for d in self.dims}
        return [by[x] for x in self.order] if self.order else list(self.dims)

    def encode(self, df: DataFrame, name: str = "cell_id") -> DataFrame:
        """df with the cell number of each row."""
        if self.size >= 1 << 63:
            raise ValueError("cells need more than 63 bits; split the domain by its first dimensions")
        if self.outside not in ("drop", "clamp"):
            raise ValueError("outside must be drop or clamp")
        # codes are columns of their own first: each is used several times, and one expression of them all would outgrow generated code
        codes = {f"_code_{k}": F.expr(f"CAST(({d.code}) AS BIGINT)") for k, d in enumerate(self._layout())}
        cell = "CAST(0 AS BIGINT)"
        for k, d in enumerate(self._layout()):
            fit = f"least(greatest(coalesce(_code_{k}, 0), 0), {d.radix - 1})" if self.outside == "clamp" else f"CASE WHEN _code_{k} BETWEEN 0 AND {d.radix - 1} THEN _code_{k} END"
            cell = f"({cell} * {d.radix} + {fit})"
        out = df.withColumns(codes).withColumn(name, F.expr(cell)).drop(*codes)
        return out.where(F.col(name).isNotNull()) if self.outside == "drop" else out

    def decode(self, df: DataFrame, name: str = "cell_id", labels: bool = True) -> DataFrame:
        """df with a column for each dimension: values, or codes."""
        cols, step = {}, 1
        for d in reversed(self._layout()):
            code = f"(({name} div {step}) % {d.radix})"
            cols[d.name] = F.expr(d.label.format(c=code) if labels else code)
            step *= d.radix
        return df.withColumns({d.name: cols[d.name] for d in self.dims})


def line(m: int) -> Domain:
    """A plain domain of cells 0 to m - 1."""
    return Domain((int_range("cell_id", 0, m),))
