"""Mixing sources to target weights, by DataFrame functions only.

Every source has a weight and a target, its share of all words, at most
``repeats`` times its own size; what a full source can't take goes to the
others by weight until nobody is above. Documents get a hash-random key, are
ordered by it within their source, and an exclusive prefix sum of their sizes
tells where the source's budget ends: whole epochs first, then the documents
up to the cut.

The prefix sums run in two levels (ranges of the hash key, then rows within a
range), so a source with a third of all rows is no hot task, and the order
doesn't depend on the number of ranges. One row a source is all that is ever
ranked globally, in one task: fine for thousands of sources.

Defined results: a null text has size 0; a null source is a source of its own,
last in order; repeated rows count one by one; an empty table gives no rows.
With no words at all, every target is 0.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphweld.llm.common import WORD, cut, prefix_sums, spread

SEED = 20
#: Bits of the hash key, the first of an MD5 digest.
BITS = 60


def _key():
    digest = F.md5(F.concat_ws("|", F.lit(SEED), F.col("doc_id"), F.col("text")))
    return F.conv(F.substring(digest, 1, BITS // 4), 16, 10).cast("long")


def sizes(documents: DataFrame) -> DataFrame:
    """doc_id, source, size and a hash-random key of every row."""
    size = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    return documents.select("doc_id", "source", size.alias("size"), _key().alias("mix_key"))


def targets(sized: DataFrame, weights=(1, 2, 3), repeats: float = 3.0) -> DataFrame:
    """source, source_size, target. Level filling: all sources whose cap lies below level x weight are full.

    The sources are ordered by the level at which they fill up; the water level
    is the first at which the words that remain fit the weights that remain.
    """
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("source_rows"))
    n = len(weights)
    order = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(n)) + 1).cast("int"))
    per = per.withColumn("weight", weight).withColumn("cap", F.col("source_size") * F.lit(float(repeats)))
    everything = Window.partitionBy()
    by_level = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    fills = by_level.rowsBetween(Window.unboundedPreceding, -1)
    per = per.withColumns(
        {
            "total": F.sum("source_size").over(everything),
            "full_caps": F.coalesce(F.sum("cap").over(fills), F.lit(0.0)),
            "open_weight": F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(fills), F.lit(0.0)),
        }
    )
    level = (F.col("total") - F.col("full_caps")) / F.col("open_weight")
    per = per.withColumn("level", F.when(F.col("cap") >= level * F.col("weight"), level))
    per = per.withColumn("level", F.first("level", ignorenulls=True).over(by_level.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    return per.select("source", "source_size", "source_rows", F.coalesce(F.least("cap", F.col("level") * F.col("weight")), "cap").alias("target"))


def mix(documents: DataFrame, weights=(1, 2, 3), repeats: float = 3.0, whole: bool = False) -> DataFrame:
    """doc_id, mix_key, size, source_size, target, taken of every row.

    ``taken`` counts words, repeats included. By default the document at the
    cut gives just the words that are missing; with ``whole`` it is taken if at
    least half of it fits.
    """
    sized = cut(sizes(documents))
    goal = targets(sized, weights, repeats)
    most = goal.agg(F.max("source_rows")).first()[0] or 0
    buckets = spread(most)
    keyed = sized.withColumn("bucket", F.shiftright("mix_key", BITS + 1 - buckets.bit_length()))
    run = prefix_sums(keyed, "source", ["mix_key", "doc_id", "size"], "bucket", "size", "before")
    goal = goal.withColumnRenamed("source", "_source").drop("source_rows")
    run = run.join(F.broadcast(goal) if _few(goal) else goal, F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
    budget = F.round("target").cast("long")
    epochs = F.when(F.col("source_size") > 0, F.floor(budget / F.col("source_size"))).otherwise(0).cast("long")
    left = budget - F.col("epochs") * F.col("source_size")
    part = F.greatest(F.lit(0), F.least("size", F.col("left") - F.col("before")))
    if whole:
        part = F.when(F.col("left") - F.col("before") >= F.col("size") / 2, F.col("size")).otherwise(0)
    run = run.withColumn("epochs", epochs).withColumn("left", left).withColumn("taken", (F.col("epochs") * F.col("size") + part).cast("long"))
    return run.select("doc_id", "mix_key", "size", "source_size", "target", "taken")


#: Sources beyond this number are joined by a shuffle instead of a broadcast.
BROADCAST_SOURCES = 10_000


def _few(goal: DataFrame) -> bool:
    return goal.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES


def mixed_documents(documents: DataFrame, weights=(1, 2, 3), repeats: float = 3.0) -> DataFrame:
    """The documents of the mixture with all their columns, as often as it takes each; whole documents only."""
    names = documents.columns
    taken = mix(documents, weights, repeats, whole=True).filter("taken > 0")
    times = taken.groupBy("doc_id", "mix_key").agg(F.sum(F.expr("taken div size")).cast("int").alias("_times")).withColumnsRenamed({"doc_id": "_doc", "mix_key": "_key"})
    rows = documents.withColumn("_mix_key", _key()).join(times, F.col("doc_id").eqNullSafe(F.col("_doc")) & (F.col("_mix_key") == F.col("_key")))
    rows = rows.dropDuplicates(["doc_id", "_mix_key"])  # repeated rows have their times together
    return rows.withColumn("_n", F.explode(F.sequence(F.lit(1), F.col("_times")))).select(*names)
