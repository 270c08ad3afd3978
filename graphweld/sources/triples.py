"""Readers and writers of triples."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_NT = r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"(?:\^\^<([^>]*)>|@([A-Za-z0-9-]+))?)\s*\.\s*$'


def ntriples(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(facts, malformed lines) of an N-Triples file; comments and empty lines are neither."""
    lines = spark.read.text(path).filter("NOT trim(value) LIKE '#%' AND trim(value) <> ''")
    part = lambda i: F.regexp_extract("value", _NT, i)
    kind = F.when(part(5).rlike("(integer|decimal|double|float)$"), "number").when(part(5).rlike("date$"), "date").otherwise("string")
    good = lines.filter(F.col("value").rlike(_NT))
    mark = F.when(kind == "number", "#").when(kind == "date", "@").otherwise('"')
    is_node = part(3) != ""
    facts = good.select(
        part(1).alias("h"), part(2).alias("r"), F.when(is_node, part(3)).otherwise(F.concat(mark, part(4))).alias("t"), F.when(is_node, "instance").otherwise(kind).alias("kind"), F.when(~is_node & (kind == "number"), F.expr(f"try_cast(regexp_extract(value, r'{_NT}', 4) as double)")).alias("x")
    )
    return facts.dropDuplicates(["h", "r", "t"]), lines.filter(~F.col("value").rlike(_NT))


def tsv(spark: SparkSession, path: str) -> DataFrame:
    """facts (h, r, t) from tab-separated lines."""
    return spark.read.schema("h string, r string, t string").option("sep", "\t").csv(path).na.drop().dropDuplicates()


def write_by_relation(facts: DataFrame, path: str) -> None:
    """Parquet partitioned by relation, so that reads of one relation prune the rest."""
    facts.repartition("r").write.mode("overwrite").partitionBy("r").parquet(path)


def write_bucketed(facts: DataFrame, name: str, key: str = "h", buckets: int = 16) -> None:
    """A bucketed, sorted table: joins on the key need no shuffle."""
    facts.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def write_explanations(explained: DataFrame, path: str) -> None:
    explained.write.mode("overwrite").json(path)


class Slice(InputPartition):
    def __init__(self, start: int, stop: int) -> None:
        self.start, self.stop = start, stop


class FactSource(DataSource):
    """``spark.read.format("facts")``: a generated chain of facts (h, r, t), for load tests; options n and parts."""

    @classmethod
    def name(cls) -> str:
        return "facts"

    def schema(self) -> str:
        return "h string, r string, t string"

    def reader(self, schema) -> DataSourceReader:
        return FactReader(int(self.options.get("n", "1000")), int(self.options.get("parts", "4")))


class FactReader(DataSourceReader):
    def __init__(self, n: int, parts: int) -> None:
        self.n, self.parts = n, parts

    def partitions(self) -> list[Slice]:
        step = -(-self.n // self.parts)
        return [Slice(k, min(self.n, k + step)) for k in range(0, self.n, step)]

    def read(self, partition: Slice):
        for k in range(partition.start, partition.stop):
            yield f"n/{k}", "next", f"n/{k + 1}"
