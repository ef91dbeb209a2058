"""Kinds of attributes: symbols, and numbers with the precision at which their values count as equal."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

SYMBOL, NUMBER = "symbol", "number"


@dataclass(frozen=True)
class Attribute:
    """name: a column. delta: width of the grid on which a number's values are one."""

    name: str
    kind: str = NUMBER
    delta: float = 1.0


@dataclass(frozen=True)
class HybridSchema:
    """Attributes in their canonical order; an attribute's number is its place."""

    attributes: tuple[Attribute, ...] = field(default_factory=tuple)

    @property
    def names(self) -> list[str]:
        return [a.name for a in self.attributes]

    def numbers(self) -> list[tuple[int, Attribute]]:
        return [(i, a) for i, a in enumerate(self.attributes) if a.kind == NUMBER]

    def symbols(self) -> list[tuple[int, Attribute]]:
        return [(i, a) for i, a in enumerate(self.attributes) if a.kind == SYMBOL]

    def reordered(self, order: str) -> HybridSchema:
        """'given', or 'symbols_first' for searches that must add symbols before intervals."""
        if order == "given":
            return self
        if order != "symbols_first":
            raise ValueError(f"unknown order: {order}")
        return HybridSchema(tuple(sorted(self.attributes, key=lambda a: a.kind != SYMBOL)))

    def limited(self, max_numbers: int | None) -> HybridSchema:
        """No more than so many numbers, the first ones; all symbols."""
        left, out = len(self.attributes) if max_numbers is None else max_numbers, []
        for a in self.attributes:
            if a.kind == NUMBER:
                left -= 1
                if left < 0:
                    continue
            out.append(a)
        return HybridSchema(tuple(out))


def number(name: str, delta: float = 1.0) -> Attribute:
    return Attribute(name, NUMBER, delta)


def symbol(name: str) -> Attribute:
    return Attribute(name, SYMBOL)


def infer_schema(df: DataFrame, without: tuple[str, ...] = (), deltas: dict[str, float] | None = None, as_symbols: tuple[str, ...] = ()) -> HybridSchema:
    """Numbers, dates and times are numbers; strings, booleans and what `as_symbols` names are symbols; others are left out."""
    out = []
    for f in df.schema:
        if f.name in without:
            continue
        if f.name in as_symbols or isinstance(f.dataType, (T.StringType, T.BooleanType)):
            out.append(symbol(f.name))
        elif isinstance(f.dataType, (T.NumericType, T.DateType, T.TimestampType, T.TimestampNTZType, T.DayTimeIntervalType)):
            out.append(number(f.name, (deltas or {}).get(f.name, 1.0)))
    return HybridSchema(tuple(out))


def as_number(df: DataFrame, name: str) -> Column:
    """The column as a double: dates in days, times and intervals in seconds; NaN is null."""
    kind, c = df.schema[name].dataType, F.col(f"`{name}`")
    if isinstance(kind, T.DateType):
        c = F.unix_date(c)
    elif isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        c = F.unix_micros(c.cast("timestamp")) / 1e6
    elif isinstance(kind, T.DayTimeIntervalType):
        c = c.cast("interval second").cast("decimal(18,6)")
    value = c.cast("double")
    return F.when(~F.isnan(value), value)
