"""Rows as arrays of codes, and equal rows as one with its class counts."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.ml.feature import Bucketizer
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from contrast.schema import SYMBOL, HybridSchema, as_number

#: Cut-points or symbols of one attribute that the driver takes; more are an error that asks for a coarser grid.
LIMIT = 1_000_000
#: Symbols of an attribute that stand in the plan as a constant map; more are a dictionary table.
MAPPED = 1_000


@dataclass(frozen=True)
class Codebook:
    """For each attribute: cut-points in order (numbers) or values in order (symbols)."""

    schema: HybridSchema
    edges: tuple[tuple[float, ...], ...]
    values: tuple[tuple[str, ...], ...]

    def size(self, attr: int) -> int:
        """Codes of an attribute."""
        return len(self.values[attr]) if self.schema.attributes[attr].kind == SYMBOL else len(self.edges[attr]) + 1

    def columns(self) -> tuple[Column, Column, Column, Column]:
        """names, kinds, edges and values as constant columns, for render()."""
        names = F.array(*(F.lit(a.name) for a in self.schema.attributes))
        kinds = F.array(*(F.lit(a.kind) for a in self.schema.attributes))
        edges = F.array(*((F.array(*map(F.lit, e)) if e else F.array()).cast("array<double>") for e in self.edges))
        values = F.array(*((F.array(*map(F.lit, v)) if v else F.array()).cast("array<string>") for v in self.values))
        return names, kinds, edges, values


def symbol_counts(df: DataFrame, schema: HybridSchema, positive: Column) -> DataFrame:
    """attr, value, code, n_pos, n_neg of each symbol; codes follow the values' order, null is left out."""
    values = F.array(*(F.struct(F.lit(i).alias("attr"), F.col(f"`{a.name}`").cast("string").alias("value")) for i, a in schema.symbols()))
    each = df.select(positive.cast("int").alias("pos"), F.explode(values).alias("x")).select("pos", "x.*").where("value is not null")
    counts = each.groupBy("attr", "value").agg(F.sum("pos").alias("n_pos"), F.sum(1 - F.col("pos")).alias("n_neg"))
    return counts.select("attr", "value", (F.row_number().over(Window.partitionBy("attr").orderBy("value")) - 1).cast("int").alias("code"), "n_pos", "n_neg")


def codebook(df: DataFrame, schema: HybridSchema, positive: Column, cuts: DataFrame) -> Codebook:
    """Brings cut-points and symbols to the driver, after a look at how many there are."""
    edges: list[tuple[float, ...]] = [()] * len(schema.attributes)
    values: list[tuple[str, ...]] = [()] * len(schema.attributes)
    found = cuts.where("lo is not null").groupBy("attr").agg(F.count(F.lit(1)).alias("n"), F.array_sort(F.collect_list("lo")).alias("points"))
    if cuts.where("lo is not null").count() > LIMIT:
        raise ValueError("too many cut-points: choose a coarser grid or fewer bins")
    for row in found.collect():
        edges[row["attr"]] = tuple(row["points"])
    if schema.symbols():
        symbols = symbol_counts(df, schema, positive).select("attr", "value")
        if symbols.count() > LIMIT:
            raise ValueError("too many symbols: leave the attribute out")
        for row in symbols.groupBy("attr").agg(F.array_sort(F.collect_list("value")).alias("found")).collect():
            values[row["attr"]] = tuple(row["found"])
    return Codebook(schema, tuple(edges), tuple(values))


def encode(df: DataFrame, book: Codebook, positive: Column, keep: tuple[str, ...] = ()) -> DataFrame:
    """codes (array by attribute, -1 for none), is_pos, and the columns to keep.

    Numbers find their base interval by binary search in the JVM, symbols theirs in a constant map or, when
    they are many, by a join with a dictionary; a symbol that the book lacks has no code.
    """
    schema = book.schema
    numbers = [(i, a) for i, a in schema.numbers() if book.edges[i]]
    plain = df.select(*keep, positive.cast("boolean").alias("is_pos"), *(as_number(df, a.name).alias(f"__v{i}") for i, a in schema.numbers()), *(F.col(f"`{a.name}`").cast("string").alias(f"__s{i}") for i, a in schema.symbols()))
    if numbers:
        inf = float("inf")
        cutter = Bucketizer(splitsArray=[[-inf, *book.edges[i], inf] for i, _ in numbers], inputCols=[f"__v{i}" for i, _ in numbers], outputCols=[f"__c{i}" for i, _ in numbers], handleInvalid="keep")
        plain = cutter.transform(plain)
    codes = []
    for i, a in enumerate(schema.attributes):
        if a.kind == SYMBOL and len(book.values[i]) > MAPPED:
            words = df.sparkSession.createDataFrame(list(zip(book.values[i], range(len(book.values[i])))), f"__s{i} string, __c{i} int")
            plain = plain.join(words, f"__s{i}", "left")
            code = F.coalesce(F.col(f"__c{i}"), F.lit(-1))
        elif a.kind == SYMBOL:
            known = F.create_map(*(F.lit(x) for k, v in enumerate(book.values[i]) for x in (v, k))) if book.values[i] else None
            code = F.lit(-1) if known is None else F.coalesce(F.try_element_at(known, F.col(f"__s{i}")), F.lit(-1))
        else:
            code = F.when(F.col(f"__v{i}").isNull(), -1).otherwise(F.col(f"__c{i}").cast("int") if book.edges[i] else F.lit(0))
        codes.append(code.cast("int"))
    return plain.select(*keep, F.array(*codes).alias("codes"), "is_pos")


def compress(encoded: DataFrame) -> DataFrame:
    """codes, n_pos, n_neg: equal rows have equal candidates, so counts stand for them."""
    pos = F.col("is_pos").cast("long")
    return encoded.groupBy("codes").agg(F.sum(pos).alias("n_pos"), F.sum(1 - pos).alias("n_neg"))


def class_totals(tx: DataFrame) -> tuple[int, int]:
    """Positive and negative rows."""
    row = tx.agg(F.coalesce(F.sum("n_pos"), F.lit(0)), F.coalesce(F.sum("n_neg"), F.lit(0))).first()
    return row[0], row[1]


def probabilities(tx: DataFrame) -> DataFrame:
    """n, n_pos, n_neg, p_class, p_other."""
    sums = tx.agg(F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg")).withColumn("n", F.col("n_pos") + F.col("n_neg"))
    return sums.select("n", "n_pos", "n_neg", (F.col("n_pos") / F.col("n")).alias("p_class"), (F.col("n_neg") / F.col("n")).alias("p_other"))
