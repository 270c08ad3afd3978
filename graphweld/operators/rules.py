"""The alignment rules: counterparts, relation lists, entity scores, subrelations, candidates, assignment."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from graphweld.operators import functionality as fun
from graphweld.operators.facts import is_literal
from graphweld.plans.lineage import at_once, cut, cuts, keep, release


def counterparts(a: DataFrame, b: DataFrame, heads: DataFrame, relations: DataFrame | None = None, theta_r: float = 0.1) -> DataFrame:
    """(t, t2, r, h, r2, h2, s_h, s_r): facts whose heads are matched (h, h2, s) and whose relations are similar (r, r2, s_r).

    Without ``relations`` every pair has ``theta_r``. Tails are no literals; that is filtered below the joins.
    """
    x = a.filter(~is_literal(F.col("t"))).select("h", "r", "t")
    y = b.filter(~is_literal(F.col("t"))).select(F.col("h").alias("h2"), F.col("r").alias("r2"), F.col("t").alias("t2"))
    rows = heads.filter("s > 0").select("h", "h2", F.col("s").alias("s_h")).join(x, "h").join(y, "h2")
    if relations is None:
        return rows.withColumn("s_r", F.lit(theta_r)).select("t", "t2", "r", "h", "r2", "h2", "s_h", "s_r")
    similar = relations.filter("s_r > 0").select("r", "r2", "s_r")
    return rows.join(similar, ["r", "r2"]).select("t", "t2", "r", "h", "r2", "h2", "s_h", "s_r")


def candidates(cp: DataFrame, direction: str = "left", top: int = 1) -> DataFrame:
    """(t, t2, n): for each t those t2 with the most counterpart facts, ties kept; a fact counts once however many partners it has."""
    n = cp.groupBy("t", "t2").agg(F.count_distinct("r", "h").alias("n"))
    left = F.rank().over(Window.partitionBy("t").orderBy(F.desc("n")))
    ranked = n.withColumn("k", left)
    if direction == "both":
        ranked = ranked.withColumn("k", F.least("k", F.rank().over(Window.partitionBy("t2").orderBy(F.desc("n")))))
    return ranked.filter(F.col("k") <= top).drop("k")


#: Counterparts of a pair that are looked at first; pairs that need more get all of theirs.
FIRST = 32


def ranked_lists(cp: DataFrame, longest: int = 4, first: int | None = FIRST) -> DataFrame:
    """(t, t2, items, seen): the best counterparts of a pair by the weaker of head and relation score, one to one, at most ``longest``.

    The first in rank wins on either side, so both lists hold distinct facts.
    Only the ``first`` ranks of a pair are gathered, which is cut off before the
    shuffle; ``seen`` tells how many there were. None: all are gathered.
    """
    h, h2 = (cp.schema[c].dataType.simpleString() for c in ("h", "h2"))  # names or numbers
    kind = f"array<struct<m:double,n:double,r:string,h:{h},r2:string,h2:{h2},s_h:double,s_r:double>>"
    item = F.struct((-F.least("s_h", "s_r")).alias("m"), (-F.col("s_h")).alias("n"), "r", "h", "r2", "h2", "s_h", "s_r")
    taken = lambda acc, x: F.exists(acc, lambda y: ((y.r == x.r) & (y.h == x.h)) | ((y.r2 == x.r2) & (y.h2 == x.h2)))
    greedy = F.aggregate("all", F.expr("array()").cast(kind), lambda acc, x: F.when((F.size(acc) >= longest) | taken(acc, x), acc).otherwise(F.concat(acc, F.array(x).cast(kind))))
    if first is not None:
        rank = F.row_number().over(Window.partitionBy("t", "t2").orderBy(F.desc(F.least("s_h", "s_r")), F.desc("s_h"), "r", "h", "r2", "h2"))
        cp = cp.withColumn("k", rank).filter(F.col("k") <= first)
    return cp.groupBy("t", "t2").agg(F.array_sort(F.collect_list(item)).alias("all")).select("t", "t2", greedy.alias("items"), F.size("all").alias("seen"))


def ranked_prefixes(cp: DataFrame, longest: int, minimum: bool = False, first: int = FIRST) -> DataFrame:
    """``prefixes`` of ``ranked_lists``, written. A pair whose list is short of ``longest`` after its ``first`` counterparts is done again with all of them."""
    short = (F.col("seen") >= first) & (F.size("items") < longest)
    watch = Observation()
    top = ranked_lists(cp, longest, first)
    lists = cut(prefixes(top.observe(watch, F.count(F.when(short, 1)).alias("short")), longest, minimum))
    if not watch.get["short"]:
        return lists
    again = cut(top.filter(short).select("t", "t2"))
    more = prefixes(ranked_lists(cp.join(again, ["t", "t2"], "left_semi"), longest, None), longest, minimum)
    return cut(lists.join(again, ["t", "t2"], "left_anti").unionByName(more))


def positional_lists(cp: DataFrame, longest: int = 4) -> DataFrame:
    """As ``ranked_lists``, paired by place: both sides' facts are ordered by name and the first meets the first. For comparison only, as names of two graphs don't sort alike."""
    left = Window.partitionBy("t", "t2").orderBy("r", "h")
    a = cp.select("t", "t2", "r", "h").distinct().withColumn("k", F.row_number().over(left)).filter(F.col("k") <= longest)
    right = Window.partitionBy("t", "t2").orderBy("r2", "h2")
    b = cp.select("t", "t2", "r2", "h2").distinct().withColumn("k", F.row_number().over(right)).filter(F.col("k") <= longest)
    rows = a.join(b, ["t", "t2", "k"]).join(cp, ["t", "t2", "r", "h", "r2", "h2"])
    item = F.struct("k", (-F.col("s_h")).alias("n"), "r", "h", "r2", "h2", "s_h", "s_r")
    # a list ends before the first place where no counterparts meet
    full = rows.groupBy("t", "t2").agg(F.array_sort(F.collect_list(item)).alias("all"))
    whole = F.filter("all", lambda x, i: x.k == i + 1)
    return full.select("t", "t2", whole.alias("items")).filter("size(items) > 0")


def prefixes(lists: DataFrame, longest: int, minimum: bool = False) -> DataFrame:
    """(t, t2, n, a, b, hm_h, hm_r): every prefix with both sides' facts in canonical order, and its aggregated scores."""
    rows = lists.withColumn("n", F.explode(F.sequence(F.lit(1), F.least(F.size("items"), F.lit(longest))))).withColumn("p", F.slice("items", 1, F.col("n")))
    mean = lambda c: F.array_min(F.transform("p", lambda x: x[c])) if minimum else F.col("n") / F.aggregate("p", F.lit(0.0), lambda s, x: s + 1.0 / x[c])
    side = lambda r, h: F.array_sort(F.transform("p", lambda x: F.struct(x[r].alias("r"), x[h].alias("h"))))
    return rows.select("t", "t2", "n", side("r", "h").alias("a"), side("r2", "h2").alias("b"), mean("s_h").alias("hm_h"), mean("s_r").alias("hm_r"))


def list_functionality(facts: DataFrame, needed: DataFrame, longest: int, relations: DataFrame | None = None, heads: DataFrame | None = None) -> DataFrame:
    """(items, f_all, f_here): global and local functionality of the distinct lists in ``needed``; facts closed under inverses.

    relations and heads: the values of single relations and heads, if they are known already.
    """
    items = needed.select("items").distinct()
    relations = fun.of_relations(facts) if relations is None else relations
    heads = fun.of_heads(facts) if heads is None else heads
    single = items.filter("size(items) = 1")
    here = single.select("items", F.col("items")[0]["r"].alias("r"), F.col("items")[0]["h"].alias("h")).join(heads.withColumnRenamed("f", "f_here"), ["r", "h"])
    out = here.join(relations.withColumnRenamed("f", "f_all"), "r").select("items", "f_all", "f_here")
    if longest > 1:
        more = items.filter("size(items) > 1").withColumn("rels", F.transform("items", lambda x: x.r))
        everywhere = fun.global_lists(facts, more, longest, relations).withColumnRenamed("f", "f_all")
        local = fun.local_lists(facts, more, heads).withColumnRenamed("f", "f_here")
        out = out.unionByName(more.join(local, "items").join(everywhere, "rels").select("items", "f_all", "f_here"))
    return out


def sided(facts: DataFrame, side: str) -> DataFrame:
    """Facts of one graph with a mark before their relations, for tables that hold both graphs."""
    return facts.select("h", F.concat(F.lit(side), "r").alias("r"), "t")


def listed(facts: DataFrame, side: str) -> DataFrame:
    """(h, r, t, tn) of one graph, marked, for the relations that have entities for tails: only their facts are in lists."""
    inner = facts.filter(~is_literal(F.col("t"))).select("r").distinct()
    mark = lambda c: F.concat(F.lit(side), c).alias(c)
    many = F.col("tn") if "tn" in facts.columns else F.lit(1)
    return facts.join(inner, "r", "left_semi").select("h", mark("r"), mark("t"), many.cast("long").alias("tn"))


def sided_items(items, side: str):
    return F.transform(items, lambda x: F.struct(F.concat(F.lit(side), x.r).alias("r"), x.h.alias("h")))


class ListFunctionality:
    """Functionality of the lists of both graphs; it never changes, so each list, and each relation list, is computed once in all rounds.

    Lists of the two graphs are kept in one table, told apart by a mark before
    the names of relations, so one pass serves both.
    """

    def __init__(self, a: DataFrame, b: DataFrame, longest: int, short: tuple[DataFrame, DataFrame] | None = None) -> None:
        """short: both graphs with ``tn``, the tails that each tail stands for."""
        self.facts, self.local = at_once(
            lambda: cut(sided(a, "1").unionByName(sided(b, "2"))),
            lambda: fun.LocalLists(listed(short[0] if short else a, "1").unionByName(listed(short[1] if short else b, "2")), longest) if longest > 1 else None,
        )
        self.longest = longest
        self.relations, self.heads = cuts(fun.of_relations(self.facts), fun.of_heads(self.facts))
        self.rels: DataFrame | None = None
        self.known: list[DataFrame] = []

    def of(self, lists: DataFrame) -> DataFrame:
        """(items, f_all, f_here) of the lists a and b of each row, and maybe more."""
        items = lists.select(sided_items("a", "1").alias("items")).unionByName(lists.select(sided_items("b", "2").alias("items"))).distinct()
        if self.known:
            items = items.join(reduce(DataFrame.unionByName, self.known).select("items"), "items", "left_anti")
        fresh = cut(items)
        if self.known and fresh.isEmpty():
            return reduce(DataFrame.unionByName, self.known)
        single = list_functionality(self.facts, fresh.filter("size(items) = 1"), 1, self.relations, self.heads)
        if self.longest > 1:
            more = fresh.filter("size(items) > 1").withColumn("rels", F.transform("items", lambda x: x.r))
            local, _ = at_once(lambda: cut(self.local.of(more).withColumnRenamed("f", "f_here")), lambda: self._add(more.select("rels").distinct()))
            both = local.withColumn("rels", F.transform("items", lambda x: x.r)).join(self.rels, "rels")
            single = single.unionByName(both.select("items", "f_all", "f_here"))
        self.known.append(keep(cut(single)))
        return reduce(DataFrame.unionByName, self.known)

    def _add(self, rels: DataFrame) -> None:
        """Computes the relation lists that are new; most rounds have none."""
        rels = cut(rels if self.rels is None else rels.join(self.rels, "rels", "left_anti"))
        if self.rels is not None and rels.isEmpty():
            return
        new, old = fun.global_lists(self.facts, rels, self.longest, self.relations).withColumnRenamed("f", "f_all"), self.rels
        self.rels = keep(cut(new if old is None else old.unionByName(new)))
        release(old)


def entity_scores(a: DataFrame, b: DataFrame, cp: DataFrame, chosen: DataFrame | None = None, longest: int = 2, minimum: bool = False, terms: tuple[str, ...] = ("global", "local"), lists: DataFrame | None = None, known: ListFunctionality | None = None) -> DataFrame:
    """(t, t2, score, why): the strongest list of each pair. a and b are closed under inverses.

    The strength of a list is the weakest of the head score, the relation score
    and the functionality terms of both sides.
    """
    if lists is None:
        if chosen is not None:
            cp = cp.join(chosen.select("t", "t2"), ["t", "t2"], "left_semi")
        lists = ranked_prefixes(cp, longest, minimum)
    if known is not None:
        both = known.of(lists)
        here = lambda x, f, g: both.select(F.col("items").alias(x), F.col("f_all").alias(f), F.col("f_here").alias(g))
        rows = lists.withColumns({"xa": sided_items("a", "1"), "xb": sided_items("b", "2")}).join(here("xa", "f1", "f2"), "xa").join(here("xb", "f3", "f4"), "xb").drop("xa", "xb")
    else:
        fa = list_functionality(a, lists.select(F.col("a").alias("items")), longest).select(F.col("items").alias("a"), F.col("f_all").alias("f1"), F.col("f_here").alias("f2"))
        fb = list_functionality(b, lists.select(F.col("b").alias("items")), longest).select(F.col("items").alias("b"), F.col("f_all").alias("f3"), F.col("f_here").alias("f4"))
        rows = lists.join(fa, "a").join(fb, "b")
    parts = ["hm_h", "hm_r"] + ["f1", "f3"] * ("global" in terms) + ["f2", "f4"] * ("local" in terms)
    rows = rows.withColumn("score", F.round(F.least(*parts), 9))  # so that ties are ties
    why = F.struct("score", (-F.col("n")).alias("shorter"), "a", "b", "hm_h", "hm_r", "f1", "f2", "f3", "f4")
    return rows.groupBy("t", "t2").agg(F.max(why).alias("why")).select("t", "t2", F.col("why.score").alias("score"), "why")


def subset_lists(cp: DataFrame, minimum: bool = False) -> DataFrame:
    """As ``prefixes`` for all lists of one or two counterparts of a pair: the rule read literally, up to length two."""
    one = F.struct("r", "h", "r2", "h2", "s_h", "s_r")
    x = cp.select("t", "t2", one.alias("x"))
    y = cp.select("t", "t2", one.alias("y"))
    two = x.join(y, ["t", "t2"]).filter("(x.r < y.r OR (x.r = y.r AND x.h < y.h)) AND NOT (x.r2 = y.r2 AND x.h2 = y.h2)")
    rows = x.select("t", "t2", F.array("x").alias("items")).unionByName(two.select("t", "t2", F.array("x", "y").alias("items")))
    mean = lambda c: F.array_min(F.transform("items", lambda x: x[c])) if minimum else F.size("items") / F.aggregate("items", F.lit(0.0), lambda s, x: s + 1.0 / x[c])
    side = lambda r, h: F.array_sort(F.transform("items", lambda x: F.struct(x[r].alias("r"), x[h].alias("h"))))
    return rows.select("t", "t2", F.size("items").alias("n"), side("r", "h").alias("a"), side("r2", "h2").alias("b"), mean("s_h").alias("hm_h"), mean("s_r").alias("hm_r"))


def witnesses(a: DataFrame, b: DataFrame, nodes: DataFrame) -> DataFrame:
    """(r, h, t, r2, m): for each fact of a and relation of b, the best match of both ends by a fact of b; with ``w`` if a has it."""
    heads = nodes.select("h", "h2", F.col("s").alias("s_h"))
    tails = nodes.select(F.col("h").alias("t"), F.col("h2").alias("t2"), F.col("s").alias("s_t"))
    y = b.select(F.col("h").alias("h2"), F.col("r").alias("r2"), F.col("t").alias("t2"))
    weight = [c for c in ("w",) if c in a.columns]
    rows = a.select("h", "r", "t", *weight).join(heads, "h").join(tails, "t").join(y, ["h2", "t2"])
    return rows.groupBy("r", "h", "t", "r2").agg(F.max(F.least("s_h", "s_t")).alias("m"), *(F.first(c).alias(c) for c in weight))


def subrelations(a: DataFrame, b: DataFrame, nodes: DataFrame, alpha: float = 3.0, minimum: bool = False) -> DataFrame:
    """(r, r2, coverage, degree): how far the facts of r are facts of r2; facts without witness count in the mean. A column ``w`` of a tells how many facts each row stands for."""
    found, w = witnesses(a, b, nodes), F.col("w") if "w" in a.columns else F.lit(1)
    total = a.groupBy("r").agg(F.sum(w).alias("total"))
    seen = found.groupBy("r", "r2").agg(F.sum(F.col("m") * w).alias("s"), F.sum(w).alias("k"), F.min("m").alias("low"))
    rows = seen.join(total, "r").withColumn("coverage", F.round(F.col("s") / F.col("total"), 9))
    degree = F.when(F.col("k") == F.col("total"), F.col("low")).otherwise(0.0) if minimum else F.round(F.least(F.lit(1.0), F.lit(float(alpha)) * F.col("coverage")), 9)
    return rows.select("r", "r2", "coverage", degree.alias("degree"))


def relation_pairs(a: DataFrame, b: DataFrame, nodes: DataFrame, alpha: float = 3.0, minimum: bool = False) -> DataFrame:
    """(r, r2, sub, sup, cov, cov2, s_r): both directions of inclusion; similarity is the stronger one."""
    there = subrelations(a, b, nodes, alpha, minimum).select("r", "r2", F.col("degree").alias("sub"), F.col("coverage").alias("cov"))
    flipped = nodes.select(F.col("h2").alias("h"), F.col("h").alias("h2"), "s")
    back = subrelations(b, a, flipped, alpha, minimum).select(F.col("r2").alias("r"), F.col("r").alias("r2"), F.col("degree").alias("sup"), F.col("coverage").alias("cov2"))
    rows = there.join(back, ["r", "r2"], "full_outer")
    zero = lambda c: F.coalesce(c, F.lit(0.0)).alias(c)
    return rows.select("r", "r2", zero("sub"), zero("sup"), zero("cov"), zero("cov2"), F.greatest(F.coalesce("sub", F.lit(0.0)), F.coalesce("sup", F.lit(0.0))).alias("s_r"))


def verdicts(pairs: DataFrame, above: float = 0.0) -> DataFrame:
    """(r, r2, op, sub, sup): every pair with a positive degree."""
    op = F.when((F.col("sub") > above) & (F.col("sup") > above), "equivalent").when(F.col("sub") > above, "sub").otherwise("super")
    return pairs.filter((F.col("sub") > above) | (F.col("sup") > above)).select("r", "r2", op.alias("op"), "sub", "sup", "cov", "cov2")


def best_verdicts(pairs: DataFrame, near: float = 0.8) -> DataFrame:
    """One verdict for each relation pair that is the best of either side by uncapped coverage; equivalent if both coverages are alike."""
    score = F.greatest("cov", "cov2")
    rows = pairs.withColumn("c", score).filter("c > 0")
    left = F.row_number().over(Window.partitionBy("r").orderBy(F.desc("c"), F.desc(F.least("cov", "cov2")), "r2"))
    right = F.row_number().over(Window.partitionBy("r2").orderBy(F.desc("c"), F.desc(F.least("cov", "cov2")), "r"))
    rows = rows.withColumns({"k": left, "k2": right}).filter("k = 1 OR k2 = 1")
    op = F.when(F.least("cov", "cov2") >= F.lit(near) * F.greatest("cov", "cov2"), "equivalent").when(F.col("cov") > F.col("cov2"), "sub").otherwise("super")
    return rows.select("r", "r2", op.alias("op"), "cov", "cov2")


# ---------------------------------------------------------------- assignment


def mutual_max(scores: DataFrame, e: str = "t", e2: str = "t2", s: str = "score") -> DataFrame:
    """Pairs whose score is the greatest of both their row and their column; ties stay."""
    row, column = F.max(s).over(Window.partitionBy(e)), F.max(s).over(Window.partitionBy(e2))
    return scores.withColumns({"_r": row, "_c": column}).filter((F.col(s) >= F.col("_r")) & (F.col(s) >= F.col("_c"))).drop("_r", "_c")


def one_to_one(scores: DataFrame, e: str = "t", e2: str = "t2", s: str = "score") -> DataFrame:
    """As mutual_max with ties broken by id on both sides."""
    row = F.row_number().over(Window.partitionBy(e).orderBy(F.desc(s), e2))
    column = F.row_number().over(Window.partitionBy(e2).orderBy(F.desc(s), e))
    return scores.withColumns({"_r": row, "_c": column}).filter("_r = 1 AND _c = 1").drop("_r", "_c")


def greedy(scores: DataFrame, rounds: int = 3, e: str = "t", e2: str = "t2", s: str = "score") -> DataFrame:
    """One to one in rounds: the mutual best are taken and leave with all their pairs."""
    out, rest = None, scores
    for _ in range(rounds):
        best = one_to_one(rest, e, e2, s)
        out = best if out is None else out.unionByName(best)
        rest = rest.join(best.select(e), e, "left_anti").join(best.select(e2), e2, "left_anti")
    return out


def dangling(nodes: DataFrame, matched: DataFrame) -> DataFrame:
    """Entities (id) without a match (id)."""
    return nodes.join(matched, "id", "left_anti")
