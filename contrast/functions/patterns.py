"""Items and patterns as columns.

An item is (attr, lo, hi): the attribute's code lies in [lo, hi). A symbol with code k is [k, k + 1), a
base interval too; wider ones are unions of neighbouring base intervals. A pattern is an array of items
with distinct attributes, sorted by attribute. A row's codes are an array by attribute, -1 for none.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

ITEM = "struct<attr:int,lo:int,hi:int>"
PATTERN = f"array<{ITEM}>"


def item(attr, lo, hi) -> Column:
    as_int = lambda x: (x if isinstance(x, Column) else F.lit(x)).cast("int")
    return F.struct(as_int(attr).alias("attr"), as_int(lo).alias("lo"), as_int(hi).alias("hi"))


def pattern(*items: Column) -> Column:
    return F.array_sort(F.array(*items)) if items else F.array().cast(PATTERN)


def subsumes_item(x: Column, y: Column, strict: bool = False) -> Column:
    """x says no more than y: the same attribute, and y's interval lies in x's."""
    held = (x["attr"] == y["attr"]) & (x["lo"] <= y["lo"]) & (y["hi"] <= x["hi"])
    return held & (x != y) if strict else held


def subsumes(p: Column, q: Column, strict: bool = False) -> Column:
    """Every item of p subsumes one of q."""
    held = F.forall(p, lambda x: F.exists(q, lambda y: subsumes_item(x, y)))
    return held & (p != q) if strict else held


def covers(p: Column, codes: Column) -> Column:
    """Every item of p holds the row's code; a row without a code isn't held. The empty pattern covers all."""
    return F.forall(p, lambda x: (F.get(codes, x["attr"]) >= x["lo"]) & (F.get(codes, x["attr"]) < x["hi"]))


def pattern_id(p: Column) -> Column:
    """Canonical text of a pattern: attr:lo:hi of each item."""
    return F.array_join(F.transform(p, lambda x: F.concat_ws(":", x["attr"].cast("string"), x["lo"].cast("string"), x["hi"].cast("string"))), ";")


def number_text(c: Column) -> Column:
    """A double in plain digits, without needless zeros."""
    return F.regexp_replace(F.regexp_replace(F.format_string("%.6f", c), "0+$", ""), r"\.$", "")


def render(p: Column, names: Column, kinds: Column, edges: Column, values: Column) -> Column:
    """Inequalities: names and kinds by attribute, cut-points of each number, values of each symbol."""

    def one(x: Column) -> Column:
        name, cuts = F.get(names, x["attr"]), F.get(edges, x["attr"])
        low, high = F.get(cuts, x["lo"] - 1), F.get(cuts, x["hi"] - 1)
        left = F.when(x["lo"] > 0, F.concat(number_text(low), F.lit(" <= "))).otherwise("")
        right = F.when(high.isNotNull(), F.concat(F.lit(" < "), number_text(high))).otherwise("")
        equal = F.concat(name, F.lit(" = "), F.get(F.get(values, x["attr"]), x["lo"]))
        return F.when(F.get(kinds, x["attr"]) == "symbol", equal).otherwise(F.concat(left, name, right))

    return F.array_join(F.transform(p, one), ", ")
