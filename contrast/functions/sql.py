"""The engine in SQL: functions over pattern and code columns, a table function, and mining by table name."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from contrast.functions.measures import FSCORE, MEASURES
from contrast.schema import SYMBOL

#: SQL functions in SQL: no Python runs when they are used.
DEFINITIONS = {
    "contrast_covers(items ARRAY<STRUCT<attr: INT, lo: INT, hi: INT>>, codes ARRAY<INT>) RETURNS BOOLEAN": "forall(items, x -> get(codes, x.attr) >= x.lo AND get(codes, x.attr) < x.hi)",
    "contrast_fscore(a BIGINT, b BIGINT, p BIGINT) RETURNS DOUBLE": "2.0D * a / (p + a + b)",
    "contrast_bound(a BIGINT, p BIGINT) RETURNS DOUBLE": "2.0D * a / (p + a)",
    "contrast_floor(score DOUBLE) RETURNS DOUBLE": "score / (2 - score)",
    "contrast_associated(a BIGINT, b BIGINT, p BIGINT, n BIGINT) RETURNS BOOLEAN": "a * n >= b * p",
}


@udtf(returnType="lo: int, hi: int, n_pos: bigint, n_neg: bigint")
class ExpandIntervals:
    """All unions of neighbouring codes, without the whole line, from arrays of class counts by code."""

    def eval(self, n_pos: list, n_neg: list):
        size = len(n_pos)
        for lo in range(size):
            p = q = 0
            for hi in range(lo + 1, size + 1):
                p, q = p + n_pos[hi - 1], q + n_neg[hi - 1]
                if (lo, hi) != (0, size):
                    yield lo, hi, p, q


def register_all(spark: SparkSession) -> None:
    for head, body in DEFINITIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("contrast_intervals", ExpandIntervals)


def contrast_mine(spark: SparkSession, table: str, cls: str, positive: str, measure: str = FSCORE.name, without: tuple[str, ...] = (), deltas: dict[str, float] | None = None) -> DataFrame:
    """The covering answer for one class of a table or view, with kinds of attributes read from its schema."""
    from contrast.plans.search import mine_covering, prepare
    from contrast.schema import infer_schema

    df = spark.table(table)
    schema = infer_schema(df, (*without, cls), deltas)
    return mine_covering(prepare(df, schema, F.col(f"`{cls}`").cast("string") == positive), MEASURES[measure]).patterns


def as_predicate(items, book) -> Column:
    """A pattern (its items, as a row holds them) as a condition on raw columns, which the scan can take.

    Made of the codebook's own cut-points and values, so it covers exactly the rows that the codes do.
    """
    out = F.lit(True)
    for x in items:
        attr, lo, hi = x["attr"], x["lo"], x["hi"]
        column = F.col(f"`{book.schema.attributes[attr].name}`")
        if book.schema.attributes[attr].kind == SYMBOL:
            out &= column.cast("string") == book.values[attr][lo]
            continue
        if lo > 0:
            out &= column >= book.edges[attr][lo - 1]
        if hi <= len(book.edges[attr]):
            out &= column < book.edges[attr][hi - 1]
        out &= column.isNotNull()
    return out
