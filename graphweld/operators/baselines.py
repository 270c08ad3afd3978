"""Baselines: exact labels, name similarity, token overlap, the probabilistic aligner, and two propagation methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphweld.operators import functionality as fun
from graphweld.operators import literals as lit
from graphweld.operators import rules
from graphweld.operators.facts import is_literal
from graphweld.plans.lineage import cut


def names(facts: DataFrame, relations: tuple[str, ...]) -> DataFrame:
    """(e, s): entities with their label strings."""
    return facts.filter(F.col("r").isin(*relations) & (F.col("kind") == "string")).select(F.col("h").alias("e"), F.expr("substring(t, 2)").alias("s")).distinct()


def normal(s):
    return F.trim(F.regexp_replace(F.lower(s), "[^a-z0-9]+", " "))


def exact_label(a: DataFrame, b: DataFrame, relations_a: tuple[str, ...], relations_b: tuple[str, ...]) -> DataFrame:
    """(t, t2): entities with the same normalised label that no other entity of either side has."""

    def unique(f, rels):
        rows = names(f, rels).select("e", normal(F.col("s")).alias("s")).distinct()
        return rows.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("s"))).filter("n = 1").drop("n")

    return unique(a, relations_a).join(unique(b, relations_b).withColumnRenamed("e", "e2"), "s").select(F.col("e").alias("t"), F.col("e2").alias("t2"))


def name_similarity(a: DataFrame, b: DataFrame, relations_a, relations_b, theta: float = 0.7, encoder: str = "ngram") -> DataFrame:
    """(t, t2, score): most similar names, mutual best.

    A pair is the best of both sides if names with the best similarity of
    either entity are the best of each other, so names are judged first, and
    only pairs that stay are made. Two entities meet once, but for those with
    several names of the same similarity.
    """
    na, nb = cut(names(a, relations_a)), cut(names(b, relations_b).withColumnsRenamed({"e": "e2", "s": "s2"}))
    sims = cut(lit.strings_similar(na.select("s"), nb.select(F.col("s2").alias("s")), theta, 1, encoder))

    def best(named: DataFrame, e: str, s: str, one: str) -> DataFrame:
        """The names of each entity that are the most similar to any; ``one`` if it is a single one."""
        every = Window.partitionBy(e)
        rows = named.join(sims.groupBy(s).agg(F.max("sim").alias("top")), s).withColumn("most", F.max("top").over(every)).filter("top = most")
        return rows.select(e, s, (F.count(F.lit(1)).over(every) == 1).alias(one))

    x, y = cut(best(na, "e", "s", "one")), cut(best(nb, "e2", "s2", "one2"))
    alike = cut(rules.mutual_max(sims, "s", "s2", "sim"))
    meet = lambda x, y: x.join(alike, "s").join(y.hint("merge"), "s2").select(F.col("e").alias("t"), F.col("e2").alias("t2"), F.col("sim").alias("score"))
    single = x.filter("one")
    several = meet(x.filter("NOT one"), y).unionByName(meet(single, y.filter("NOT one2")))
    return meet(single, y.filter("one2")).unionByName(several.distinct())


def token_jaccard(a: DataFrame, b: DataFrame, relations_a, relations_b, least: float = 0.5) -> DataFrame:
    """(t, t2, score): token overlap of labels, found through shared tokens; mutual best."""

    def tokens(f, rels):
        rows = names(f, rels).select("e", F.explode(F.array_distinct(F.split(normal(F.col("s")), " "))).alias("w")).filter("w <> ''").distinct()
        return rows.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("e")))

    x, y = tokens(a, relations_a), tokens(b, relations_b).withColumnsRenamed({"e": "e2", "n": "n2"})
    rows = x.join(y, "w").groupBy("e", "e2", "n", "n2").agg(F.count(F.lit(1)).alias("k"))
    rows = rows.select(F.col("e").alias("t"), F.col("e2").alias("t2"), (F.col("k") / (F.col("n") + F.col("n2") - F.col("k"))).alias("score"))
    return rules.mutual_max(rows.filter(F.col("score") >= least))


def none_of(p):
    """1 - product of (1 - p) over a group; 1 as soon as a p is 1."""
    return F.when(F.max(p) >= 1.0, F.lit(1.0)).otherwise(1.0 - F.exp(F.sum(F.ln(F.when(p < 1.0, 1.0 - p)))))


def probable_entities(a: DataFrame, b: DataFrame, heads: DataFrame, sub: DataFrame | None, theta: float = 0.1) -> DataFrame:
    """(t, t2, score): noisy-or over single counterpart facts, with both directions of inclusion.

    The functionality that weighs a fact r(h, t) is that of r: closed graphs hold the inverses.
    """
    if sub is None:
        cp = rules.counterparts(a, b, heads, None, theta).withColumns({"s1": F.lit(theta), "s2": F.lit(theta)})
    else:
        both = sub.withColumn("s_r", F.greatest("sub", "sup")).select("r", "r2", "s_r", F.col("sub").alias("s1"), F.col("sup").alias("s2"))
        cp = rules.counterparts(a, b, heads, both.select("r", "r2", "s_r"), theta).join(both.drop("s_r"), ["r", "r2"])
    fa = cut(fun.of_relations(a).withColumnRenamed("f", "f1"))  # written, so that the planner knows its size
    fb = cut(fun.of_relations(b).withColumnsRenamed({"r": "r2", "f": "f2"}))
    rows = cp.join(fa, "r").join(fb, "r2")
    miss = (1.0 - F.col("s2") * F.col("f1") * F.col("s_h")) * (1.0 - F.col("s1") * F.col("f2") * F.col("s_h"))
    return rows.withColumn("p", 1.0 - miss).groupBy("t", "t2").agg(F.round(none_of(F.col("p")), 9).alias("score"))  # so that ties are ties


def probable_inclusion(a: DataFrame, b: DataFrame, nodes: DataFrame) -> DataFrame:
    """(r, r2, degree): expected facts of r that b knows under r2, over expected facts of r whose ends have any partner."""
    heads = nodes.select("h", "h2", F.col("s").alias("s1"))
    tails = nodes.select(F.col("h").alias("t"), F.col("h2").alias("t2"), F.col("s").alias("s2"))
    pairs = a.select("h", "r", "t").join(heads, "h").join(tails, "t").withColumn("p", F.col("s1") * F.col("s2"))
    base = pairs.groupBy("r", "h", "t").agg(none_of(F.col("p")).alias("p")).groupBy("r").agg(F.sum("p").alias("total"))
    seen = pairs.join(b.select(F.col("h").alias("h2"), F.col("r").alias("r2"), F.col("t").alias("t2")), ["h2", "t2"]).groupBy("r", "h", "t", "r2").agg(none_of(F.col("p")).alias("p"))
    return seen.groupBy("r", "r2").agg(F.sum("p").alias("s")).join(base, "r").select("r", "r2", (F.col("s") / F.col("total")).alias("degree"))


def probabilistic(a: DataFrame, b: DataFrame, literals: DataFrame, rounds: int = 5, theta: float = 0.1, seeds: DataFrame | None = None) -> DataFrame:
    """(t, t2, score) of the probabilistic aligner: literals by identity, single facts, a fixed number of rounds, best partners between rounds."""
    sub = entities = None
    for _ in range(rounds):
        heads = literals if entities is None else literals.unionByName(entities.select(F.col("t").alias("h"), F.col("t2").alias("h2"), F.col("score").alias("s")))
        new = probable_entities(a, b, heads, sub, theta)
        if seeds is not None:
            new = new.join(seeds.select("t"), "t", "left_anti").join(seeds.select("t2"), "t2", "left_anti").unionByName(seeds.select("t", "t2", F.lit(1.0).alias("score")))
        entities = cut(rules.one_to_one(cut(new)))
        nodes = literals.unionByName(entities.select(F.col("t").alias("h"), F.col("t2").alias("h2"), F.col("score").alias("s")))
        there = probable_inclusion(a, b, nodes).withColumnRenamed("degree", "sub")
        back = probable_inclusion(b, a, nodes.select(F.col("h2").alias("h"), F.col("h").alias("h2"), "s")).select(F.col("r2").alias("r"), F.col("r").alias("r2"), F.col("degree").alias("sup"))
        sub = cut(there.join(back, ["r", "r2"], "full_outer").na.fill(0.0, ["sub", "sup"]))
    return entities


def sinkhorn(scores: DataFrame, rounds: int = 5, sharpness: float = 20.0) -> DataFrame:
    """(t, t2, score): entropic transport between the candidates' rows and columns by alternating normalisation."""
    out = scores.select("t", "t2", F.exp(F.lit(sharpness) * (F.col("score") - 1.0)).alias("score"))
    row, column = Window.partitionBy("t"), Window.partitionBy("t2")
    for _ in range(rounds):
        out = out.withColumn("score", F.col("score") / F.sum("score").over(row))
        out = out.withColumn("score", F.col("score") / F.sum("score").over(column))
    return out


def propagate_features(facts: DataFrame, features: DataFrame, hops: int = 2) -> DataFrame:
    """(e, g, w): sparse features averaged over the neighbours of each entity, ``hops`` times, with the entity's own."""
    links = facts.filter(~is_literal(F.col("h")) & ~is_literal(F.col("t"))).select("h", "t").distinct()
    degree = links.groupBy("t").agg(F.count(F.lit(1)).alias("d"))
    for _ in range(hops):
        moved = links.join(features.withColumnRenamed("e", "h"), "h").join(degree, "t").groupBy(F.col("t").alias("e"), "g").agg(F.sum(F.col("w") / F.col("d")).alias("w"))
        features = features.unionByName(moved).groupBy("e", "g").agg(F.sum("w").alias("w"))
    return features


def feature_propagation(a: DataFrame, b: DataFrame, relations_a, relations_b, hops: int = 1, rounds: int = 5) -> DataFrame:
    """(t, t2, score): names' grams spread over the graph, cosine of all pairs that share a gram, then transport and mutual best.

    Exact: common grams propose pairs and count like any other, so the pairs can grow with the product of the sides.
    """

    def vectors(f, rels):
        w = names(f, rels).select("e", F.explode(lit.grams(F.col("s"))).alias("g")).groupBy("e", "g").agg(F.count(F.lit(1)).cast("double").alias("w"))
        rows = propagate_features(f, w, hops)
        return rows.withColumn("w", F.col("w") / F.sqrt(F.sum(F.col("w") * F.col("w")).over(Window.partitionBy("e"))))

    x, y = vectors(a, relations_a), vectors(b, relations_b).withColumnsRenamed({"e": "e2", "w": "w2"})
    pairs = x.join(y, "g").groupBy(F.col("e").alias("t"), F.col("e2").alias("t2")).agg(F.sum(F.col("w") * F.col("w2")).alias("score"))
    return rules.mutual_max(sinkhorn(pairs, rounds))
