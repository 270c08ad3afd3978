"""Triples: built from tables by declared rules, closed under inverses, with the kinds of their nodes."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweld.plans.fact_rules import LITERALS, FactRule
from graphweld.plans.lineage import table

#: First character of a literal's id, by type.
MARKS = {"string": '"', "number": "#", "date": "@"}


def base(spark: SparkSession, sf_dir: str, rules: tuple[FactRule, ...]) -> DataFrame:
    """Distinct base facts (hk, hid, r, tk, tid, x, part); a null head or tail gives no fact."""

    def of(name: str) -> DataFrame:
        """All facts of one table in one scan."""
        structs = [
            f"named_struct('hk', '{q.head_kind}', 'hid', cast({q.head} as bigint), 'r', '{q.relation}', 'tk', '{q.tail_kind}', 'tid', {q.tail}, 'x', cast({q.number or 'NULL'} as double), 'part', {q.part})".replace("as varchar(32)", "as string")
            for q in rules
            if q.table == name
        ]
        return table(spark, sf_dir, name).selectExpr(f"inline(array({', '.join(structs)}))")

    rows = reduce(DataFrame.unionByName, map(of, dict.fromkeys(q.table for q in rules)))
    return rows.filter("hid IS NOT NULL AND tid IS NOT NULL").dropDuplicates(["hk", "hid", "r", "tk", "tid"])


def entity_id(kind, key):
    """Readable ids, ``part/17``; literals carry a mark of their type."""
    marks = F.when(kind == "string", F.lit(MARKS["string"])).when(kind == "number", F.lit(MARKS["number"])).when(kind == "date", F.lit(MARKS["date"]))
    return F.concat(F.coalesce(marks, F.concat(kind, F.lit("/"))), key)


def build(spark: SparkSession, sf_dir: str, rules: tuple[FactRule, ...]) -> DataFrame:
    """facts (h, r, t, kind, x): kind is the tail's."""
    rows = base(spark, sf_dir, rules)
    return rows.select(entity_id(F.col("hk"), F.col("hid").cast("string")).alias("h"), "r", entity_id(F.col("tk"), F.col("tid")).alias("t"), F.col("tk").alias("kind"), "x")


def inverse_name(r):
    """``r~`` for ``r`` and back."""
    return F.when(r.endswith("~"), F.expr("substring(r, 1, length(r) - 1)")).otherwise(F.concat(r, F.lit("~")))


def with_inverse(facts: DataFrame) -> DataFrame:
    """(h, r, t) closed under inverses; every fact is read once and gives two rows, without a shuffle."""
    there = F.struct("h", "r", "t")
    back = F.struct(F.col("t").alias("h"), inverse_name(F.col("r")).alias("r"), F.col("h").alias("t"))
    return facts.select(F.inline(F.array(there, back)))


def is_literal(column):
    """By the mark of a name, or by a number of ``numbered``: odd ones are literals. The type is known to the planner, which keeps one of the two."""
    return F.when(F.typeof(column) == "bigint", column.try_cast("bigint") % 2 == 1).otherwise(F.substring(column.cast("string"), 1, 1).isin(*MARKS.values()))


def nodes(facts: DataFrame) -> DataFrame:
    """(id, kind): kind is literal type, class or instance."""
    kind = F.when(F.col("kind").isin(*LITERALS, "class"), F.col("kind")).otherwise("instance")
    return facts.select(F.col("t").alias("id"), kind.alias("kind")).unionByName(facts.select(F.col("h").alias("id"), F.lit("instance").alias("kind"))).distinct()
