"""Nodes as numbers within a run: they keep the order of the names, so ties break alike, and rows of pairs stay short."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweld.operators.facts import is_literal


def numbers(facts: DataFrame, more: DataFrame | None = None) -> DataFrame:
    """(name, id) of all nodes of a graph and of the entities (t) in ``more``; odd for literals. To be written before use."""
    names = facts.select(F.explode(F.array("h", "t")).alias("name"))
    if more is not None:
        names = names.unionByName(more.select(F.col("t").alias("name")))
    mark = is_literal(F.col("name")).cast("long")
    return names.distinct().orderBy("name").select("name", (F.monotonically_increasing_id() * 2 + mark).alias("id"))


def numbered(rows: DataFrame, *sides: tuple[str, DataFrame]) -> DataFrame:
    """The rows with numbers for the names in each column, by its table of numbers."""
    out = rows
    for c, names in sides:
        out = out.join(names.select(F.col("name").alias(c), F.col("id").alias("_id")), c).withColumn(c, F.col("_id")).drop("_id")
    return out.select(*rows.columns)


def named(rows: DataFrame, *sides: tuple[str, DataFrame]) -> DataFrame:
    """The rows with names for the numbers in each column."""
    out = rows
    for c, names in sides:
        out = out.join(names.select(F.col("id").alias(c), F.col("name").alias("_name")), c).withColumn(c, F.col("_name")).drop("_name")
    return out.select(*rows.columns)


def named_reasons(reasons: DataFrame, names_a: DataFrame, names_b: DataFrame) -> DataFrame:
    """(n, k, k2, why): reasons with names for the heads in both lists. Its keys are known to be distinct, so a join that asks for no reason is left out."""
    side = lambda c, s: F.transform(f"why.{c}", lambda x: F.struct(F.lit(s).alias("side"), x.r.alias("r"), x.h.alias("h")))
    items = reasons.select("n", "k", "k2", "why", F.explode(F.concat(side("a", 1), side("b", 2))).alias("i")).select("n", "k", "k2", "why", "i.side", "i.r", "i.h")
    names = names_a.withColumn("side", F.lit(1)).unionByName(names_b.withColumn("side", F.lit(2))).select("side", F.col("id").alias("h"), "name")
    fact = F.struct("r", F.col("name").alias("h"))
    both = items.join(names, ["side", "h"]).groupBy("n", "k", "k2").agg(F.first("why").alias("w"), *(F.array_sort(F.collect_list(F.when(F.col("side") == s, fact))).alias(c) for c, s in (("a", 1), ("b", 2))))
    return both.select("n", "k", "k2", F.struct("w.score", "w.shorter", "a", "b", *(f"w.{c}" for c in ("hm_h", "hm_r", "f1", "f2", "f3", "f4"))).alias("why"))
