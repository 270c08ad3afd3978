"""Pairs of entities with the same counterparts: every list and score of theirs is the same, so one of them is looked at for all."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphweld.operators.facts import is_literal
from graphweld.plans.lineage import cut, cuts, keep, release

#: Links of a tail, and facts of its partner, up to which a pair's counterparts are found in arrays; other pairs are looked up fact by fact and stay alone.
MOST = 256


class Facts:
    """Facts of one graph by number: keys (r, h, f) and has (t, f), without literal tails; they never change."""

    def __init__(self, facts: DataFrame) -> None:
        inner = facts.filter(~is_literal(F.col("t"))).select("h", "r", "t")
        self.keys = cut(inner.select("r", "h").distinct().withColumn("f", F.monotonically_increasing_id()))
        self.has = cut(inner.join(self.keys, ["r", "h"]).select("t", "f"))


class SharedPairs:
    """Pairs (t, t2) with (k, k2), the smallest pair with the same counterparts; ``large`` are those that stay alone.

    Counterparts are compared as they are, by the numbers of the links between
    facts, and not by a digest. They stay the same while the similar heads and
    the relations that are similar at all do.
    """

    def __init__(self, a: Facts, b: Facts, heads: DataFrame, relations: DataFrame | None, pairs: DataFrame) -> None:
        mine, theirs = a.keys, b.keys.select(F.col("r").alias("r2"), F.col("h").alias("h2"), F.col("f").alias("f2"))
        links = heads.filter("s > 0").select("h", "h2", F.col("s").alias("s_h")).join(mine, "h").join(theirs, "h2")
        if relations is not None:
            links = links.join(relations.filter("s_r > 0").select("r", "r2"), ["r", "r2"], "left_semi")
        self.links = keep(cut(links.select("r", "h", "r2", "h2", "s_h", "f", "f2").withColumn("l", F.monotonically_increasing_id())))
        met = self.links.groupBy("f").agg(F.count(F.lit(1)).alias("m"))
        ours, partners = a.has, b.has.withColumnsRenamed({"t": "t2", "f": "f2"})
        big, big2 = cuts(ours.join(met, "f").groupBy("t").agg(F.sum("m").alias("m")).filter(F.col("m") > MOST).select("t"), partners.groupBy("t2").agg(F.count(F.lit(1)).alias("m")).filter(F.col("m") > MOST).select("t2"))
        x = ours.join(big, "t", "left_anti").join(self.links.select("f", "f2", "l"), "f").groupBy("t").agg(F.array_sort(F.collect_list(F.struct("l", "f2"))).alias("x"))
        y = partners.join(big2, "t2", "left_anti").groupBy("t2").agg(F.collect_list("f2").alias("y"))
        x, y = cuts(x, y)
        common = F.transform(F.filter("x", lambda e: F.array_contains("y", e.f2)), lambda e: e.l)
        rows = pairs.select("t", "t2").join(x, "t").join(y, "t2").select("t", "t2", common.alias("all"))
        one = F.min(F.struct("t", "t2")).over(Window.partitionBy("all"))
        rows = rows.withColumn("one", one).select("t", "t2", F.col("one.t").alias("k"), F.col("one.t2").alias("k2"), "all")
        self.rows = keep(cut(rows.withColumn("all", F.when((F.col("t") == F.col("k")) & (F.col("t2") == F.col("k2")), F.col("all")))))
        self.large = None
        if not (big.isEmpty() and big2.isEmpty()):
            self.large = keep(cut(pairs.select("t", "t2").join(big, "t", "left_semi").unionByName(pairs.select("t", "t2").join(big, "t", "left_anti").join(big2, "t2", "left_semi"))))

    def counterparts(self, relations: DataFrame | None, theta_r: float) -> DataFrame:
        """Those of the pairs that stand for others, as ``rules.counterparts`` has them."""
        rows = self.rows.filter("all IS NOT NULL").select("t", "t2", F.explode("all").alias("l")).join(self.links.select("l", "r", "h", "r2", "h2", "s_h"), "l")
        if relations is None:
            rows = rows.withColumn("s_r", F.lit(theta_r))
        else:
            rows = rows.join(F.broadcast(relations.filter("s_r > 0").select("r", "r2", "s_r")), ["r", "r2"])
        return rows.select("t", "t2", "r", "h", "r2", "h2", "s_h", "s_r")

    def spread(self, found: DataFrame, *columns: str) -> DataFrame:
        """(t, t2, k, k2, columns) of all pairs, from rows (t, t2, columns) of those that stand for others."""
        every = self.rows.select("t", "t2", "k", "k2")
        if self.large is not None:
            every = every.unionByName(self.large.select("t", "t2", F.col("t").alias("k"), F.col("t2").alias("k2")))
        return every.join(found.select(F.col("t").alias("k"), F.col("t2").alias("k2"), *columns), ["k", "k2"]).select("t", "t2", "k", "k2", *columns)

    def pairs(self) -> DataFrame:
        every = self.rows.select("t", "t2")
        return every if self.large is None else every.unionByName(self.large)

    def release(self) -> None:
        release(self.links, self.rows, self.large)
