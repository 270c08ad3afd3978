"""Fuzzy inference systems as tables: rules (rule, conclusion, agg, alpha), premises (rule, pos, var), vars (var, floor, fixed).

Full systems fuzzify inputs, fire rules, cap and combine output sets and read
off the first of the maxima. In positive systems memberships are identities;
recursive ones, where conclusions are premises too, are solved by iterating to
the least fixed point from the floors. Tables of systems are joined by sorting
(the hints ``merge``): many rows come from each row of a compressed table, so
the planner would take them for small and collect them on the driver.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphweld.functions.aggregators import PLAIN, grouped
from graphweld.plans.lineage import cut

AGGREGATORS = ("min", "hmean", "alpha_mean", "identity", "product", "lukasiewicz", "mean", "max")


def ramp(x: Column, low: float, high: float) -> Column:
    """0 up to low, 1 from high on, linear between."""
    return F.least(F.lit(1.0), F.greatest(F.lit(0.0), (x - F.lit(float(low))) / F.lit(float(high - low))))


def fuzzify(rows: DataFrame, memberships: dict[str, Column]) -> DataFrame:
    return rows.withColumns(memberships)


def cap(grid: DataFrame, strength: Column) -> DataFrame:
    """grid with mu capped at the firing strength."""
    return grid.withColumn("mu", F.least("mu", strength))


def combine(grid: DataFrame, *by: str) -> DataFrame:
    """Point by point the greatest of all rules' output sets."""
    return grid.groupBy(*by, "x").agg(F.max("mu").alias("mu"))


def first_of_maxima(grid: DataFrame, *by: str) -> DataFrame:
    """The smallest x with the greatest mu."""
    return grid.groupBy(*by).agg(F.min_by("x", F.struct(-F.col("mu"), F.col("x"))).alias("x"))


def strengths(rules: DataFrame, premises: DataFrame, values: DataFrame) -> DataFrame:
    """(rule, conclusion, strength) for values (var, value)."""
    rows = premises.join(values.select("var", "value").hint("merge"), "var").join(rules.hint("merge"), "rule")
    each = reduce(lambda acc, name: acc.when(F.first("agg") == name, grouped(name, F.col("value"), F.first("alpha"))), AGGREGATORS[1:], F.when(F.first("agg") == AGGREGATORS[0], grouped(AGGREGATORS[0], F.col("value"))))
    return rows.groupBy("rule").agg(F.first("conclusion").alias("conclusion"), each.alias("strength"))


def step(rules: DataFrame, premises: DataFrame, values: DataFrame) -> DataFrame:
    """One simultaneous update of values (var, floor, fixed, value): the greatest strength, never below the old value."""
    best = strengths(rules, premises, values).groupBy("conclusion").agg(F.max("strength").alias("s"))
    joined = values.join(best, values["var"] == best["conclusion"], "left")
    return joined.select("var", "floor", "fixed", F.when(F.col("fixed"), F.col("value")).otherwise(F.greatest("value", F.coalesce("s", F.lit(0.0)))).alias("value"))


def solve(rules: DataFrame, premises: DataFrame, variables: DataFrame, epsilon: float = 1e-9, rounds: int = 100, delta: bool = True) -> DataFrame:
    """The least solution above the floors, to within ``epsilon``. variables: var, floor, fixed.

    With ``delta`` only the rules with a premise that has just grown fire again.
    """
    values = cut(variables.withColumn("value", F.col("floor").cast("double")))
    changed = None
    for _ in range(rounds):
        active, used = rules, premises
        if changed is not None and delta:
            hot = premises.join(changed, "var", "left_semi").select("rule").distinct()
            active, used = rules.join(hot, "rule", "left_semi"), premises.join(hot, "rule", "left_semi")
        new = cut(step(active, used, values))
        grown = values.select("var", F.col("value").alias("old")).join(new, "var").filter(F.col("value") - F.col("old") > epsilon)
        changed = cut(grown.select("var"))
        values = new
        if changed.isEmpty():
            break
    return values


def violations(rules: DataFrame, premises: DataFrame, values: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """Rules whose conclusion is below their strength."""
    s = strengths(rules, premises, values)
    return s.join(values.select(F.col("var").alias("conclusion"), "value").hint("merge"), "conclusion").filter(F.col("strength") > F.col("value") + tolerance).select("rule", "conclusion", "strength", "value")


def not_minimal(rules: DataFrame, premises: DataFrame, values: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """Variables above both their floor and all their rules' strengths."""
    best = strengths(rules, premises, values).groupBy("conclusion").agg(F.max("strength").alias("s"))
    rows = values.join(best.hint("merge"), values["var"] == best["conclusion"], "left")
    return rows.filter(~F.col("fixed") & (F.col("value") > F.greatest(F.col("floor"), F.coalesce("s", F.lit(0.0))) + tolerance)).select("var", "value")


def normalised(rules: DataFrame, variables: DataFrame) -> DataFrame:
    """Variables of the form in which every one has an initial value, as inputs (fixed) and outputs (with floors)."""
    out = rules.select(F.col("conclusion").alias("var")).distinct().withColumn("is_output", F.lit(True))
    return variables.join(out, "var", "left").select("var", "floor", F.coalesce(~F.col("is_output"), F.lit(True)).alias("fixed"))


def solve_plain(rules: list[tuple], values: dict[str, float], sequential: bool = True, rounds: int = 10_000, tolerance: float = 1e-12) -> dict[str, float]:
    """The same for small systems in Python: rules (aggregator, premises, conclusion); updates in place or simultaneously."""
    values = dict(values)
    for _ in range(rounds):
        old = dict(values)
        source = values if sequential else old
        for agg, premises, conclusion in rules:
            values[conclusion] = max(values[conclusion], PLAIN[agg]([source[p] for p in premises]))
        if max(abs(values[k] - old[k]) for k in values) <= tolerance:
            break
    return values


def ground(a: DataFrame, b: DataFrame, theta_r: float = 0.1) -> tuple[DataFrame, DataFrame]:
    """(rules, premises) of the single-fact entity rules of two small closed graphs, for checking the engine."""
    x = a.select("h", "r", "t")
    y = b.select(F.col("h").alias("h2"), F.col("r").alias("r2"), F.col("t").alias("t2"))
    rows = x.crossJoin(F.broadcast(y)).withColumn("rule", F.concat_ws("|", "h", "r", "t", "h2", "r2", "t2"))
    rules = rows.select("rule", F.concat_ws("=", "t", "t2").alias("conclusion"), F.lit("min").alias("agg"), F.lit(1.0).alias("alpha"))
    premises = rows.select("rule", F.lit(0).alias("pos"), F.concat_ws("=", "h", "h2").alias("var")).unionByName(rows.select("rule", F.lit(1).alias("pos"), F.concat_ws("~", "r", "r2").alias("var")))
    return rules, premises
