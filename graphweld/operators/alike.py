"""Entities of one graph with the same facts: every rule scores them alike, so one of them is scored for all."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphweld.operators.facts import is_literal

#: Entities with more facts than this are not compared with others, so that no array of facts is large.
FACTS = 64


def alike(facts: DataFrame, apart: DataFrame | None = None) -> DataFrame:
    """(id, rep, n): the entities that share all their facts with others; facts closed under inverses.

    ``rep`` is the smallest id of a group; n is the group's size for it and 0
    for the others. apart: (t) of entities that stay alone whatever their facts.
    Facts are compared as they are, not by a digest.
    """
    tails = facts.filter(~is_literal(F.col("t"))).select("h", "r", "t")
    if apart is not None:
        tails = tails.join(apart.select("t").distinct(), "t", "left_anti")
    few = tails.groupBy("t").agg(F.count(F.lit(1)).alias("d")).filter(F.col("d") <= FACTS).select("t")
    sets = tails.join(few, "t", "left_semi").groupBy("t").agg(F.array_sort(F.collect_list(F.struct("r", "h"))).alias("facts"))
    group = Window.partitionBy("facts")
    rows = sets.select("t", F.min("t").over(group).alias("rep"), F.count(F.lit(1)).over(group).alias("n")).filter("n > 1")
    return rows.select(F.col("t").alias("id"), "rep", F.when(F.col("t") == F.col("rep"), F.col("n")).otherwise(0).alias("n"))


def folded(facts: DataFrame, many: DataFrame) -> DataFrame:
    """(h, r, t, hn, tn): the facts whose tail stands for itself or for a group of ``tn``; hn is 0 for a head that another one stands for."""
    size = lambda c: many.select(F.col("id").alias(c), F.col("n").alias(f"{c}n"))
    rows = facts.select("h", "r", "t").join(size("t"), "t", "left").withColumn("tn", F.coalesce("tn", F.lit(1))).filter("tn > 0")
    return rows.join(size("h"), "h", "left").select("h", "r", "t", F.coalesce("hn", F.lit(1)).alias("hn"), "tn")


def unfolded(pairs: DataFrame, many: DataFrame, many2: DataFrame) -> DataFrame:
    """Pairs (t, t2, ...) of representatives as pairs of all that they stand for."""
    out = pairs
    for c, m in (("t", many), ("t2", many2)):
        members = m.select(F.col("rep").alias(c), F.col("id").alias("_id"))
        out = out.join(members, c, "left").withColumn(c, F.coalesce("_id", c)).drop("_id")
    return out.select(*pairs.columns)


def counted(pairs: DataFrame, many: DataFrame, many2: DataFrame) -> DataFrame:
    """Pairs (t, t2, ...) with ``w``, the number of pairs that each stands for."""
    for c, m in (("t", many), ("t2", many2)):
        pairs = pairs.join(m.filter("n > 0").select(F.col("id").alias(c), F.col("n").alias(f"_{c}")), c, "left")
    return pairs.withColumn("w", F.coalesce("_t", F.lit(1)) * F.coalesce("_t2", F.lit(1))).drop("_t", "_t2")
