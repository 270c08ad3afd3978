"""Accuracy measures against gold pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _ratio(x, y):
    return F.when(y > 0, x / y).otherwise(F.lit(0.0))


def prf(predicted: DataFrame, gold: DataFrame, by: str | None = None, universe: str = "all") -> DataFrame:
    """One row (or one a ``by`` value of gold, and 'overall'): right, predicted, gold, precision, recall, f1.

    predicted: e, e2; gold: e, e2 (and ``by``). universe 'gold_left' only judges
    predictions about entities that gold knows.
    """
    pairs = predicted.select("e", "e2").distinct()
    if universe == "gold_left":
        pairs = pairs.join(gold.select("e").distinct(), "e", "left_semi")
    if by is None:
        joined = pairs.withColumn("p", F.lit(1)).join(gold.select("e", "e2").distinct().withColumn("g", F.lit(1)), ["e", "e2"], "full_outer")
        grouped = joined.agg(F.count(F.when(F.col("p") + F.col("g") == 2, 1)).alias("right_n"), F.count("p").alias("predicted_n"), F.count("g").alias("gold_n"))
    else:
        kinds = gold.select("e", by).distinct()
        told = pairs.join(kinds, "e", "left").withColumn(by, F.coalesce(by, F.lit("instance"))).withColumn("p", F.lit(1))
        joined = told.join(gold.select("e", "e2", by).distinct().withColumn("g", F.lit(1)), ["e", "e2", by], "full_outer")
        grouped = joined.rollup(by).agg(F.count(F.when(F.col("p") + F.col("g") == 2, 1)).alias("right_n"), F.count("p").alias("predicted_n"), F.count("g").alias("gold_n"))
        grouped = grouped.withColumn(by, F.coalesce(by, F.lit("overall")))
    out = grouped.withColumns({"precision": _ratio(F.col("right_n"), F.col("predicted_n")), "recall": _ratio(F.col("right_n"), F.col("gold_n"))})
    p, r = F.col("precision"), F.col("recall")
    return out.withColumn("f1", F.when(p + r > 0, 2 * p * r / F.when(p + r > 0, p + r)).otherwise(F.lit(0.0)))


def ranking(scored: DataFrame, gold: DataFrame, ks: tuple[int, ...] = (1, 10), ties: str = "pessimistic") -> DataFrame:
    """One row: hit_at_k for each k, and mrr. scored: e, e2, score. Gold pairs without a score are misses.

    Ties: 'pessimistic' counts all pairs as good as the gold one before it, 'optimistic' none, 'average' half of them.
    """
    w = Window.partitionBy("e").orderBy(F.desc("score"))
    first = F.rank().over(w)
    same = F.count(F.lit(1)).over(Window.partitionBy("e", "score"))
    ranks = scored.select("e", "e2", "score").withColumns({"_f": first, "_n": same})
    rank = {"optimistic": F.col("_f").cast("double"), "pessimistic": (F.col("_f") + F.col("_n") - 1).cast("double"), "average": F.col("_f") + (F.col("_n") - 1) / 2.0}[ties]
    joined = gold.select("e", "e2").distinct().join(ranks.withColumn("rank", rank), ["e", "e2"], "left")
    hits = [F.avg(F.when(F.col("rank") <= k, 1.0).otherwise(0.0)).alias(f"hit_at_{k}") for k in ks]
    return joined.agg(*hits, F.avg(F.coalesce(1.0 / F.col("rank"), F.lit(0.0))).alias("mrr"))


def sweep(scores: DataFrame, gold: DataFrame, thresholds: list[float]) -> DataFrame:
    """(theta, right_n, predicted_n, recall, precision): one pass over the scores for all thresholds. scores: e, e2, score."""
    marked = scores.join(gold.select("e", "e2", F.lit(1).alias("g")), ["e", "e2"], "left")
    rows = marked.withColumn("theta", F.explode(F.array(*map(F.lit, thresholds)))).filter("score > theta")
    total = gold.select("e", "e2").distinct().agg(F.count(F.lit(1)).alias("gold_n"))
    out = rows.groupBy("theta").agg(F.count("g").alias("right_n"), F.count(F.lit(1)).alias("predicted_n")).join(F.broadcast(total))
    return out.select("theta", "right_n", "predicted_n", _ratio(F.col("right_n"), F.col("predicted_n")).alias("precision"), _ratio(F.col("right_n"), F.col("gold_n")).alias("recall"))
