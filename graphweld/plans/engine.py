"""The whole aligner: literal similarities once, then entity and subrelation steps in turn until the total score settles."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphweld.operators import literals as lit
from graphweld.operators import rules
from graphweld.operators.alike import alike, counted, folded, unfolded
from graphweld.operators.facts import inverse_name, is_literal, with_inverse
from graphweld.operators.numbered import named, named_reasons, numbered, numbers
from graphweld.operators.overlap import most_shared
from graphweld.operators.shared import Facts, SharedPairs
from graphweld.plans.lineage import at_once, cut, cuts, keep, release, scratch, written


@dataclass(frozen=True)
class Params:
    theta_r: float = 0.1
    alpha: float = 3.0
    theta_s: float = 0.7
    theta_e: float = 0.1
    epsilon: float = 0.01
    relative: bool = False
    longest: int = 3
    lists: str = "ranked"  # "subsets": all lists up to length two; "positional": paired by place
    minimum: bool = False  # the weakest premise in every rule
    terms: tuple[str, ...] = ("global", "local")
    direction: str | None = "left"  # of the candidate search; None: no search
    refresh: bool = True  # search candidates anew in every step
    assign_each_round: bool = True
    assign: str = "ties"  # pairs that are the best of row and column; "one": ties broken, so that nobody has two partners
    accumulate: bool = True
    encoder: str | Callable = "ngram"
    identity: bool = False  # literals by identity only
    rounds: int = 12
    #: Heads with more tails than this propose no pairs where that can't change the candidates. None: all propose.
    hub: int | None = 50


@dataclass
class Alignment:
    entities: DataFrame  # t, t2, score, why above theta_e, assigned; ties stay
    scores: DataFrame  # all scored pairs before assignment
    relations: DataFrame  # r, r2, sub, sup, cov, cov2, s_r
    history: list[dict] = field(default_factory=list)
    seconds: dict[str, float] = field(default_factory=dict)
    settled: bool = False  # did the total settle before the limit of rounds?

    @property
    def one_to_one(self) -> DataFrame:
        """The entities with ties broken, so that nobody has two partners."""
        return rules.one_to_one(self.entities)


def of_pairs(a: DataFrame, b: DataFrame, heads: DataFrame, relations: DataFrame | None, pairs: DataFrame, theta_r: float) -> DataFrame:
    """All counterparts of given pairs (t, t2), as ``rules.counterparts`` has them."""
    x = a.select("h", "r", "t").join(pairs.select("t", "t2"), "t")
    y = b.select(F.col("h").alias("h2"), F.col("r").alias("r2"), F.col("t").alias("t2"))
    rows = x.join(heads.filter("s > 0").select("h", "h2", F.col("s").alias("s_h")), "h").join(y, ["h2", "t2"])
    if relations is None:
        return rows.withColumn("s_r", F.lit(theta_r)).select("t", "t2", "r", "h", "r2", "h2", "s_h", "s_r")
    return rows.join(relations.filter("s_r > 0").select("r", "r2", "s_r"), ["r", "r2"]).select("t", "t2", "r", "h", "r2", "h2", "s_h", "s_r")


class Busy:
    """The heads of both graphs with more than ``hub`` tails that are no literals; they never change."""

    def __init__(self, a: DataFrame, b: DataFrame, hub: int) -> None:
        busy = lambda f: f.filter(~is_literal(F.col("t"))).groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > hub).select("h")
        self.a, self.b = cuts(busy(a), busy(b))
        self.none = self.a.isEmpty() and self.b.isEmpty()


def search(a: DataFrame, b: DataFrame, heads: DataFrame, relations: DataFrame | None, p: Params, busy: Busy | None = None, work: dict | None = None) -> DataFrame:
    """(t, t2): for each t the partners with the most counterpart facts, the same with and without ``hub``.

    A head with d tails that meets one with d2 makes d x d2 pairs, so popular
    heads are held back, and the others propose pairs with a count. The popular
    facts of t can add at most their own number to it; only pairs that may still
    win get these counted, by looking up both tails. A pair that popular heads
    alone would propose has at most that number too. So a tail whose best pair
    has more facts is done; only the other tails meet everyone under their
    popular heads, in blocks (``most_shared``). All of it is counted before any
    pair is written.
    """
    if p.hub is not None and p.direction == "left" and busy is None:
        busy = Busy(a, b, p.hub)
    if busy is None or busy.none or p.direction != "left":
        return rules.candidates(rules.counterparts(a, b, heads, relations, p.theta_r), p.direction)
    inner = lambda f: f.filter(~is_literal(F.col("t")))
    a, b = inner(a), inner(b)
    meets = heads.join(busy.b.withColumnRenamed("h", "h2"), "h2", "left_semi").select("h")
    popular = busy.a.unionByName(meets).distinct()
    count = lambda cp: cp.groupBy("t", "t2").agg(F.count_distinct("r", "h").alias("n"))
    held = a.join(popular, "h", "left_semi").join(heads.select("h").distinct(), "h", "left_semi").groupBy("t").agg(F.count(F.lit(1)).alias("most"))
    found = count(rules.counterparts(a.join(popular, "h", "left_anti"), b, heads, relations, p.theta_r)).join(held, "t", "left")
    top = F.max("n").over(Window.partitionBy("t"))
    found = cut(found.withColumn("most", F.coalesce("most", F.lit(0))).withColumn("top", top).filter(F.col("n") >= F.col("top") - F.col("most")))
    more = count(of_pairs(a.join(popular, "h", "left_semi"), b, heads, relations, found.filter("most > 0"), p.theta_r)).withColumnRenamed("n", "more")
    found = cut(found.join(more, ["t", "t2"], "left").select("t", "t2", (F.col("n") + F.coalesce("more", F.lit(0))).alias("n")))
    best = found.groupBy("t").agg(F.max("n").alias("n"))
    open_tails = cut(held.join(best, "t", "left").filter(F.coalesce("n", F.lit(0)) <= F.col("most")).select("t"))
    rest = most_shared(a.join(open_tails, "t", "left_semi"), b, heads, relations)
    if work is not None:
        work |= {"proposed": found.count(), "open_tails": open_tails.count()}
    done = found.join(open_tails, "t", "left_anti")
    rank = F.rank().over(Window.partitionBy("t").orderBy(F.desc("n")))
    return done.withColumn("k", rank).filter("k = 1").select("t", "t2").unionByName(rest)


def entity_step(a: DataFrame, b: DataFrame, heads: DataFrame, relations: DataFrame | None, p: Params, shared: SharedPairs | None = None, known=None, work: dict | None = None, groups: tuple[DataFrame, DataFrame] | None = None) -> tuple[DataFrame, DataFrame]:
    """(scores, reasons): one pass of the entity rule; scores have the key of their reason (k, k2) instead of it.

    shared: the candidates; None: all pairs with a counterpart. work: gets the
    numbers of rows that the pass has made. groups: of both graphs, if a and b
    are folded.
    """
    if shared is None:
        cp = rules.counterparts(a, b, heads, relations, p.theta_r)
    else:
        cp = shared.counterparts(relations, p.theta_r)
        if shared.large is not None:
            cp = cp.unionByName(of_pairs(a.filter(~is_literal(F.col("t"))), b, heads, relations, shared.large, p.theta_r))
    if p.lists == "subsets":
        lists = cut(rules.subset_lists(cp, p.minimum))
    elif p.lists == "positional":
        lists = cut(rules.prefixes(rules.positional_lists(cut(cp), p.longest), p.longest, p.minimum))
    else:
        lists = rules.ranked_prefixes(cp, p.longest, p.minimum)
    every = (lambda rows, *c: rows.select("t", "t2", F.col("t").alias("k"), F.col("t2").alias("k2"), *c)) if shared is None else shared.spread
    if work is not None:
        made = every(lists.groupBy("t", "t2").agg(F.count(F.lit(1)).alias("made")), "made")
        made = made.withColumn("w", F.lit(1)) if groups is None else counted(made, *groups)
        work |= {"lists": made.agg(F.sum(F.col("w") * F.col("made"))).first()[0] or 0}
    longest = 2 if p.lists == "subsets" else p.longest
    reasons = cut(rules.entity_scores(a, b, cp, longest=longest, minimum=p.minimum, terms=p.terms, lists=lists, known=known))
    return every(reasons, "score"), reasons


def merged(old: DataFrame | None, new: DataFrame, seeds: DataFrame | None, fresh: bool = False) -> DataFrame:
    """The greater of old and new scores with its reason; seed pairs keep 1. fresh: also new scores as they are, null where there are none."""
    more = ["fresh"] * fresh
    if fresh:
        new = new.withColumn("fresh", F.struct("score", "why"))
    if old is not None:
        both = old.select("t", "t2", F.col("score").alias("o"), F.col("why").alias("ow")).join(new, ["t", "t2"], "full_outer")
        keep = F.coalesce("o", F.lit(-1.0)) >= F.coalesce("score", F.lit(-1.0))
        new = both.select("t", "t2", F.when(keep, F.col("o")).otherwise(F.col("score")).alias("score"), F.when(keep, F.col("ow")).otherwise(F.col("why")).alias("why"), *more)
    if seeds is not None:
        free = new.join(seeds.select("t"), "t", "left_anti").join(seeds.select("t2"), "t2", "left_anti")
        fixed = seeds.join(new.select("t", "t2", "why", *more), ["t", "t2"], "left").select("t", "t2", F.lit(1.0).alias("score"), "why", *more)
        new = free.select("t", "t2", "score", "why", *more).unionByName(fixed)
    return new


def relation_step(a: DataFrame, b: DataFrame, entities: DataFrame, literals: DataFrame, p: Params) -> DataFrame:
    """Both directions of inclusion for forward relations of the first graph, mirrored to their inverses.

    A relation without any fact whose ends are both matched can't be judged
    yet. Pairs of two such relations keep the starting value; classes, say, are
    only reached through instances, one round later.
    """
    nodes = entities.select(F.col("t").alias("h"), F.col("t2").alias("h2"), F.col("score").alias("s")).filter("s > 0").unionByName(literals)
    forward = a.filter("NOT r LIKE '%~'")
    found = rules.relation_pairs(forward, b, nodes, p.alpha, p.minimum)
    dark_a, dark_b = unjudged(forward, nodes.select("h")), unjudged(b, nodes.select(F.col("h2").alias("h"))).withColumnRenamed("r", "r2")
    zero = [F.lit(0.0).alias(c) for c in ("sub", "sup", "cov", "cov2")]
    found = found.unionByName(dark_a.crossJoin(dark_b).select("r", "r2", *zero, F.lit(p.theta_r).alias("s_r")))
    both = F.array(F.struct("r", "r2"), F.struct(inverse_name(F.col("r")).alias("r"), inverse_name(F.col("r2")).alias("r2")))
    return found.withColumn("x", F.explode(both)).select("x.r", "x.r2", "sub", "sup", "cov", "cov2", "s_r")


def meeting(a: DataFrame, b: DataFrame, heads: DataFrame) -> DataFrame:
    """(r, r2): relations of facts with similar heads."""
    side = lambda f, r, h: f.filter(~is_literal(F.col("t"))).select(F.col("r").alias(r), F.col("h").alias(h)).distinct()
    return heads.filter("s > 0").select("h", "h2").join(side(a, "r", "h"), "h").join(side(b, "r2", "h2"), "h2").select("r", "r2").distinct()


def same_support(old: DataFrame | None, new: DataFrame, among: DataFrame) -> bool:
    """Are the same pairs of relations similar at all, of those that matter? None: all are."""
    pairs = lambda df, c: among.withColumn(c, F.lit(1)) if df is None else among.join(df.filter("s_r > 0").select("r", "r2"), ["r", "r2"], "left_semi").withColumn(c, F.lit(1))
    return pairs(old, "x").join(pairs(new, "y"), ["r", "r2"], "full_outer").filter("x IS NULL OR y IS NULL").isEmpty()


def meets_entities(facts: DataFrame) -> bool:
    """Is there a fact between two entities?"""
    return not facts.filter(~is_literal(F.col("h")) & ~is_literal(F.col("t"))).isEmpty()


def unjudged(facts: DataFrame, matched: DataFrame) -> DataFrame:
    """(r): relations without a fact whose ends are both matched. One row a relation, the dictionary of a graph."""
    ends = matched.distinct()
    seen = facts.join(ends, "h", "left_semi").join(ends.withColumnRenamed("h", "t"), "t", "left_semi").select("r").distinct()
    return facts.select("r").distinct().join(seen, "r", "left_anti")


def align(facts_a: DataFrame, facts_b: DataFrame, params: Params | None = None, seeds: DataFrame | None = None, counters: bool = False, **changes) -> Alignment:
    """Aligns two fact tables (h, r, t, kind, x). seeds: (t, t2), matched with score 1 for good.

    Every round is written to tables in the shared folder, and what only that
    round needs is deleted at its end; a sum and a count a round come back to
    the driver, to tell when the total score has settled. The first two
    rounds never stop the loop, as they only set the starting values of
    relations. counters: also count the rows that a round
    has made, for ``history``.
    """
    p = replace(params or Params(), **changes)
    spark = facts_a.sparkSession
    started = time.time()
    facts_a, facts_b = at_once(lambda: written(facts_a), lambda: written(facts_b))  # read several times
    pool = ThreadPoolExecutor(1)  # literals are many small jobs, and nothing before the first round needs them
    similar = pool.submit(lambda: cut(lit.matches(facts_a, facts_b, p.theta_s, 1, p.encoder, identity=p.identity)))
    names_a, names_b = cuts(numbers(facts_a, seeds), numbers(facts_b, None if seeds is None else seeds.select(F.col("t2").alias("t"))))
    if seeds is not None:
        seeds = cut(numbered(seeds.select("t", "t2"), ("t", names_a), ("t2", names_b)))
    a, b = cuts(*(with_inverse(numbered(f.select("h", "r", "t"), ("h", n), ("t", n))) for f, n in ((facts_a, names_a), (facts_b, names_b))))
    longest = 2 if p.lists == "subsets" else p.longest
    groups: tuple[DataFrame, DataFrame] | None = tuple(cuts(alike(a, seeds), alike(b, None if seeds is None else seeds.select(F.col("t2").alias("t")))))
    if groups[0].isEmpty() and groups[1].isEmpty():
        groups = None
    xa, xb = (a, b) if groups is None else cuts(folded(a, groups[0]), folded(b, groups[1]))
    deep = meets_entities(a) and meets_entities(b)
    # do pairs of entities stand for all members of their groups? If ties are broken by id, only the representatives have partners
    whole = p.assign != "one" or not p.assign_each_round
    apart = groups is not None and not whole
    spread = lambda df: df if groups is None or not whole else unfolded(df, *groups)
    ends_a, ends_b = (a, b) if groups is None or not whole else (f.filter("hn > 0").withColumn("w", F.col("hn") * F.col("tn")) for f in (xa, xb))
    known, busy, fa, fb = at_once(
        lambda: rules.ListFunctionality(a, b, longest, None if groups is None else (xa, xb)),
        lambda: Busy(xa, xb, p.hub) if p.hub is not None and p.direction == "left" else None,
        lambda: Facts(xa) if p.direction is not None else None,
        lambda: Facts(xb) if p.direction is not None else None,
    )
    literals = cut(numbered(similar.result(), ("h", names_a), ("h2", names_b)))
    pool.shutdown()
    among = None if deep or p.direction is None else cut(meeting(xa, xb, literals))
    seconds = {"literals": time.time() - started}
    entities = merged(None, _no_scores(a), seeds) if seeds is not None else None
    relations = scores = None
    shared: SharedPairs | None = None
    reasons: list[DataFrame] = []
    history: list[dict] = []
    total, settled, again = 0.0, False, False
    for number in range(p.rounds):
        began = time.time()
        work: dict | None = {} if counters else None
        before = (entities, relations, scores)
        with scratch(spark):
            heads = literals if entities is None or not deep else literals.unionByName(spread(entities.select("t", "t2", "score")).select(F.col("t").alias("h"), F.col("t2").alias("h2"), F.col("score").alias("s")))
            if p.direction is not None and (shared is None or deep or p.refresh and not again):
                if p.refresh or shared is None:
                    chosen = cut(search(xa, xb, heads, relations, p, busy, work))
                else:  # the first candidates, whose counterparts may be others now
                    chosen = shared.pairs()
                old, shared = shared, SharedPairs(fa, fb, heads, relations, chosen)
                if old is not None:
                    old.release()
            new, why = entity_step(xa, xb, heads, relations, p, shared, known, work, groups)
            reasons.append(keep(why).select(F.lit(number).alias("n"), F.col("t").alias("k"), F.col("t2").alias("k2"), "why"))
            new = new.select("t", "t2", "score", F.struct(F.lit(number).alias("n"), "k", "k2").alias("why"))
            scores = keep(cut(merged(entities if p.accumulate else None, new, seeds, apart)))
            entities = keep(cut(assigned(scores, p.assign))) if p.assign_each_round else scores
            each = entities.withColumn("w", F.lit(1)) if groups is None or not whole else counted(entities.select("t", "t2", "score"), *groups)
            now = each.agg(F.coalesce(F.sum(F.col("score") * F.col("w")), F.lit(0.0)), F.coalesce(F.sum("w"), F.lit(0))).first()
            gain, total = now[0] - total, now[0]
            relations = keep(cut(relation_step(ends_a, ends_b, entities, literals, p)))
            # without facts between entities, candidates only change with the relations that are similar at all
            again = among is not None and same_support(before[1], relations, among)
        release(*{id(x): x for x in before if x is not None}.values())
        history.append({"round": number, "total": total, "gain": gain, "pairs": now[1], "seconds": time.time() - began} | (work or {}))
        if number > 1 and abs(gain) < (p.epsilon * max(1.0, total) if p.relative else p.epsilon):
            settled = True
            break
    seconds["rounds"] = time.time() - started - seconds["literals"]
    columns = ["t", "t2", "score", "why"]
    final = assigned(scores, p.assign).select(*columns).filter(F.col("score") > p.theta_e)
    if groups is not None and p.assign != "one":
        final = unfolded(final, *groups)
    if groups is not None:
        every = unfolded(scores.withColumns({"_t": F.col("t"), "_t2": F.col("t2")}), *groups)
        if apart:  # what representatives have from earlier rounds is theirs alone
            own = (F.col("t") == F.col("_t")) & (F.col("t2") == F.col("_t2"))
            every = every.filter(own | F.col("fresh").isNotNull()).withColumns({c: F.when(own, F.col(c)).otherwise(F.col(f"fresh.{c}")) for c in ("score", "why")})
        scores = every.select(*columns)
    told = named_reasons(reduce(DataFrame.unionByName, reasons), names_a, names_b)

    def explained(rows: DataFrame) -> DataFrame:
        keyed = named(rows, ("t", names_a), ("t2", names_b)).select("t", "t2", "score", "why.n", "why.k", "why.k2")
        return keyed.join(told, ["n", "k", "k2"], "left").select(*columns)

    return Alignment(explained(final), explained(scores), relations, history, seconds, settled)


def assigned(scores: DataFrame, how: str) -> DataFrame:
    return rules.one_to_one(scores) if how == "one" else rules.mutual_max(scores)


def _no_scores(facts: DataFrame) -> DataFrame:
    return facts.limit(0).select(F.col("t"), F.col("t").alias("t2"), F.lit(0.0).alias("score"), F.lit(None).cast("struct<n:int,k:bigint,k2:bigint>").alias("why"))


def explain(alignment: DataFrame, t: str | None = None) -> DataFrame:
    """(t, t2, score, facts, reason): the strongest rule of matches in words."""
    rows = alignment.filter("why IS NOT NULL") if t is None else alignment.filter((F.col("t") == t) & F.col("why").isNotNull())
    fact = lambda c: F.array_join(F.transform(c, lambda x: F.concat(x.r, F.lit("("), x.h, F.lit(")"))), " and ")
    shown = lambda c: F.format_number(F.col(f"why.{c}"), 3)
    reason = F.concat(fact("why.a"), F.lit(" like "), fact("why.b"), F.lit("; heads "), shown("hm_h"), F.lit(", relations "), shown("hm_r"), F.lit(", functionality "), shown("f1"), F.lit("/"), shown("f2"), F.lit(" and "), shown("f3"), F.lit("/"), shown("f4"))
    return rows.select("t", "t2", "score", F.size("why.a").alias("facts"), reason.alias("reason"))
