"""How far heads fix their tails: of relations, relations at a head, relation lists, and lists at head lists.

Facts are joined by sorting (the hints ``merge``): several facts come from each
row of a compressed table, so the planner would take them for small and collect
them on the driver to broadcast them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphweld.plans.lineage import cut


def of_relations(facts: DataFrame) -> DataFrame:
    """(r, f): heads over facts. Two-step: heads are counted once each, before the final sum."""
    heads = facts.groupBy("r", "h").agg(F.count(F.lit(1)).alias("n"))
    return heads.groupBy("r").agg((F.count(F.lit(1)) / F.sum("n")).alias("f"))


def of_heads(facts: DataFrame) -> DataFrame:
    """(r, h, f): one over the number of tails."""
    return facts.groupBy("r", "h").agg((F.lit(1.0) / F.count(F.lit(1))).alias("f"))


def pairs(facts: DataFrame, distinct: bool = True) -> DataFrame:
    """Lists of two facts with a tail in common: (r1, h1, r2, h2, t), in order of (r, h)."""
    a = facts.select("t", F.col("r").alias("r1"), F.col("h").alias("h1"))
    b = facts.select("t", F.col("r").alias("r2"), F.col("h").alias("h2"))
    less = (F.col("r1") < F.col("r2")) | ((F.col("r1") == F.col("r2")) & ((F.col("h1") < F.col("h2")) if distinct else (F.col("h1") <= F.col("h2"))))
    return a.join(b.hint("merge"), "t").filter(less).select("r1", "h1", "r2", "h2", "t")


def enumerate_lists(facts: DataFrame, n: int, distinct: bool = True) -> DataFrame:
    """(t, items): all lists of n facts of each tail, items sorted by (r, h); by n - 1 joins on the tail."""
    item = F.struct("r", "h")
    one = facts.select("t", item.alias("i"))
    out = facts.select("t", F.array(item).alias("items"))
    for _ in range(n - 1):
        last = F.element_at("items", -1)
        later = F.col("i") > last if distinct else F.col("i") >= last
        out = out.join(one.hint("merge"), "t").filter(later).select("t", F.concat("items", F.array("i")).alias("items"))
    return out


def of_pairs(facts: DataFrame) -> DataFrame:
    """(r1, r2, f) of all relation lists of length two: distinct head lists over (head list, tail) pairs."""
    rows = pairs(facts).groupBy("r1", "r2", "h1", "h2").agg(F.count(F.lit(1)).alias("n"))
    return rows.groupBy("r1", "r2").agg((F.count(F.lit(1)) / F.sum("n")).alias("f"))


def of_head_pairs(facts: DataFrame) -> DataFrame:
    """(r1, h1, r2, h2, f) of lists of two."""
    return pairs(facts).groupBy("r1", "h1", "r2", "h2").agg((F.lit(1.0) / F.count(F.lit(1))).alias("f"))


def pair_counts(facts: DataFrame) -> DataFrame:
    """(r1, r2, n): the (head list, tail) pairs of length two without enumerating them.

    A tail with d facts of r has d choose 2 lists (r, r), and d times e lists (r, s).
    """
    d = facts.groupBy("t", "r").agg(F.count(F.lit(1)).alias("d"))
    same = d.filter("d > 1").groupBy("r").agg(F.sum(F.expr("d * (d - 1) div 2")).alias("n")).select(F.col("r").alias("r1"), F.col("r").alias("r2"), "n")
    x, y = d.select("t", F.col("r").alias("r1"), F.col("d").alias("d1")), d.select("t", F.col("r").alias("r2"), F.col("d").alias("d2"))
    mixed = x.join(y.hint("merge"), "t").filter("r1 < r2").groupBy("r1", "r2").agg(F.sum(F.col("d1") * F.col("d2")).alias("n"))
    return same.unionByName(mixed)


def pair_mean_local(facts: DataFrame) -> DataFrame:
    """(r1, r2, f): the mean of the local functionality over (head list, tail) pairs, which equals the global one."""
    local = of_head_pairs(facts)
    return pairs(facts).join(local.hint("merge"), ["r1", "h1", "r2", "h2"]).groupBy("r1", "r2").agg(F.avg("f").alias("f"))


def pair_sampled(facts: DataFrame, size: int, seed: int = 7) -> DataFrame:
    """(r1, r2, f, n): estimate of ``of_pairs`` from about ``size`` lists per relation list.

    Tails are chosen by hash first, with a share for each relation list that
    follows from the counted number of its lists, and only their lists are
    enumerated. The estimate is the mean of the local functionalities of these
    lists, which are exact. For lists drawn one by one the error is below
    sqrt(ln(2/d) / (2 n)) with probability 1 - d; lists of one tail are drawn
    together, so tails with many lists widen it.
    """
    facts = cut(facts.select("h", "r", "t"))  # read several times
    share = cut(pair_counts(facts).select("r1", "r2", F.least(F.lit(1.0), F.lit(float(size)) / F.col("n")).alias("q")))
    draw = lambda t: F.pmod(F.xxhash64(F.lit(seed), t), F.lit(1 << 30)) / F.lit(float(1 << 30))
    a = facts.select("t", F.col("r").alias("r1"), F.col("h").alias("h1"), draw(F.col("t")).alias("u"))
    a = a.join(share.groupBy("r1").agg(F.max("q").alias("most")), "r1").filter("u < most").drop("most")
    b = facts.select("t", F.col("r").alias("r2"), F.col("h").alias("h2"))
    sample = a.join(b.hint("merge"), "t").filter("r1 < r2 OR (r1 = r2 AND h1 < h2)").join(share, ["r1", "r2"]).filter("u < q")
    sample = sample.select("r1", "h1", "r2", "h2", "t")
    sample = cut(sample.groupBy("r1", "h1", "r2", "h2").agg(F.count(F.lit(1)).alias("k")))  # written, so that the planner knows it
    local = head_pairs_among(facts, sample.select("r1", "h1", "r2", "h2"))
    return sample.join(local, ["r1", "h1", "r2", "h2"]).groupBy("r1", "r2").agg((F.sum(F.col("f") * F.col("k")) / F.sum("k")).alias("f"), F.sum("k").alias("n"))


def head_pairs_among(facts: DataFrame, needed: DataFrame) -> DataFrame:
    """(r1, h1, r2, h2, f): ``of_head_pairs`` for the distinct lists in ``needed``, lists that some tail has.

    Either each list looks at the tails of its rarer fact, or each tail pairs
    its facts that are in any list, whichever makes fewer rows; both are exact.
    """
    first, second = (needed.select(F.col(f"r{i}").alias("r"), F.col(f"h{i}").alias("h")) for i in (1, 2))
    used = cut(facts.select("r", "h", "t").join(first.unionByName(second).distinct(), ["r", "h"], "left_semi"))
    degree = cut(used.groupBy("r", "h").agg(F.count(F.lit(1)).alias("d")))
    each = needed.join(degree.select(F.col("r").alias("r1"), F.col("h").alias("h1"), F.col("d").alias("d1")), ["r1", "h1"])
    each = each.join(degree.select(F.col("r").alias("r2"), F.col("h").alias("h2"), F.col("d").alias("d2")), ["r2", "h2"])
    by_list = each.agg(F.sum(F.least("d1", "d2").cast("double"))).first()[0] or 0.0
    by_tail = used.groupBy("t").agg(F.count(F.lit(1)).cast("double").alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2)).first()[0] or 0.0
    if by_tail <= by_list:
        met = pairs(used).join(needed, ["r1", "h1", "r2", "h2"], "left_semi")
        return met.groupBy("r1", "h1", "r2", "h2").agg((F.lit(1.0) / F.count(F.lit(1))).alias("f"))
    item = lambda i: F.struct(F.col(f"r{i}").alias("r"), F.col(f"h{i}").alias("h"))
    local = local_lists(used, needed.select(F.array(item(1), item(2)).alias("items")))
    return local.select(*(F.col("items")[i][c].alias(f"{c}{i + 1}") for i in range(2) for c in ("r", "h")), "f")


def pair_approximate(facts: DataFrame, error: float = 0.02) -> DataFrame:
    """(r1, r2, f): distinct head lists by a sketch, pairs by counting."""
    heads = pairs(facts).groupBy("r1", "r2").agg(F.approx_count_distinct(F.struct("h1", "h2"), error).alias("k"))
    return heads.join(pair_counts(facts), ["r1", "r2"]).select("r1", "r2", F.least(F.lit(1.0), F.col("k") / F.col("n")).alias("f"))


# ---------------------------------------------------------------- on demand, any length


def local_lists(facts: DataFrame, needed: DataFrame, heads: DataFrame | None = None, held: bool = True) -> DataFrame:
    """(items, f) for the distinct arrays of (r, h) in ``needed``, lists that some tail has: one over the tails that have all facts.

    Only the tails of the fact with the fewest are looked at; the others are
    looked up. A list with a fact of a single tail has that one, so it is 1.
    heads: what ``of_heads`` gives, if it is known already. held: False if no
    tail may have a list, which then gives no row.
    """
    degree = (of_heads(facts) if heads is None else heads).select("r", "h", F.round(1.0 / F.col("f")).cast("long").alias("d"))
    keys = needed.select("items").distinct().withColumn("k", F.xxhash64("items"))
    each = keys.select("k", "items", F.explode("items").alias("i")).select("k", "items", "i.r", "i.h").join(degree.hint("merge"), ["r", "h"])
    least = each.groupBy("k", "items").agg(F.min(F.struct("d", "r", "h")).alias("m"))
    sure = least.filter(F.lit(held) & (F.col("m.d") == 1)).select("items", F.lit(1.0).alias("f"))
    open_ = least.filter(~F.lit(held) | (F.col("m.d") > 1)).select("items", F.col("m.r").alias("r"), F.col("m.h").alias("h"))
    tails = open_.join(facts.select("r", "h", "t").hint("merge"), ["r", "h"]).select("items", "t", "r", "h", F.explode("items").alias("o")).filter("NOT (o.r = r AND o.h = h)")
    rest = tails.select("items", "t", F.col("o.r").alias("r"), F.col("o.h").alias("h")).join(facts.select("r", "h", "t").hint("merge"), ["r", "h", "t"], "left_semi")
    whole = rest.groupBy("items", "t").agg(F.count(F.lit(1)).alias("n")).filter("n = size(items) - 1")
    single = open_.filter("size(items) = 1").join(facts.select("r", "h", "t").hint("merge"), ["r", "h"]).select("items", "t")
    counted = whole.select("items", "t").unionByName(single).groupBy("items").agg((F.lit(1.0) / F.count(F.lit(1))).alias("f"))
    return sure.unionByName(counted)


#: Facts of a tail whose lists are enumerated.
FEW = 8


class LocalLists:
    """``local_lists`` from the tails' side for tails of few facts, whose lists are enumerated once for each; only other tails are looked up from the lists.

    The tails of a list are those of either kind, so their numbers add up.
    facts: (h, r, t), or with ``tn``, the tails that a row's tail stands for.
    """

    def __init__(self, facts: DataFrame, longest: int) -> None:
        self.longest = longest
        weight = F.col("tn") if "tn" in facts.columns else F.lit(1)
        facts = facts.select("h", "r", "t", weight.cast("long").alias("tn"))
        sizes = facts.groupBy("t").agg(F.count(F.lit(1)).alias("n"))
        few = facts.join(sizes.filter(F.col("n") <= FEW).select("t"), "t", "left_semi")
        self.few = cut(few.groupBy("t").agg(F.array_sort(F.collect_set(F.struct("r", "h"))).alias("all"), F.first("tn").alias("tn")).groupBy("all").agg(F.sum("tn").alias("tn")))
        many = facts.join(sizes.filter(F.col("n") > FEW).select("t"), "t", "left_semi")
        many = cut(many.withColumn("i", F.explode(F.sequence(F.lit(1).cast("long"), "tn"))).select("h", "r", F.concat("t", F.lit("|"), "i").alias("t")))
        self.many = None if many.isEmpty() else many
        self.heads = None if self.many is None else cut(of_heads(self.many))

    def of(self, needed: DataFrame) -> DataFrame:
        """(items, f), as ``local_lists``; items in order and without repeats."""
        wanted = needed.select("items").distinct()
        grown = self.few.select("tn", "all", F.expr("transform(sequence(1, size(all)), i -> named_struct('at', i, 'items', array(all[i - 1])))").alias("x"))
        counts = None
        for n in range(1, self.longest + 1):
            rows = grown.select("tn", F.explode("x.items").alias("items")).join(wanted.filter(F.size("items") == n), "items", "left_semi").groupBy("items").agg(F.sum("tn").alias("k"))
            counts = rows if counts is None else counts.unionByName(rows)
            if n < self.longest:
                step = "flatten(transform(x, p -> transform(filter(sequence(1, size(all)), i -> i > p.at), i -> named_struct('at', i, 'items', concat(p.items, array(all[i - 1]))))))"
                grown = grown.select("tn", "all", F.expr(step).alias("x"))
        if self.many is not None:
            other = local_lists(self.many, wanted, self.heads, held=False).select("items", F.round(1.0 / F.col("f")).cast("long").alias("k"))
            counts = counts.unionByName(other).groupBy("items").agg(F.sum("k").alias("k"))
        return counts.select("items", (F.lit(1.0) / F.col("k")).alias("f"))


#: Facts of one relation that a list may hold.
LONGEST = 8
#: Lists that an estimate is made from; its error is about 0.02.
SAMPLE_LISTS = 5_000


def global_lists(facts: DataFrame, needed: DataFrame, longest: int, relations: DataFrame | None = None, budget: int | None = None, seed: int = 7) -> DataFrame:
    """(rels, f) for the distinct relation lists (arrays of r) in ``needed``: head lists over (head list, tail) pairs.

    A list with a relation whose heads all have one tail is 1, as the head
    fixes the tail. The others grow head lists position by position, but for
    lists of two whose pairs are far more than their facts, which are counted
    in blocks (``pairs_in_blocks``); both are exact. budget, for callers that
    want an estimate: relation lists of more (head list, tail) pairs, counted
    by degrees, are estimated: facts are chosen by hash with the share that
    leaves about ``SAMPLE_LISTS`` lists, each of all with the same chance, and
    the mean of their local functionality, which equals the global one over
    all lists, is the estimate. No tail's lists are enumerated as a whole for
    it. The aligner never asks for one.
    """
    keys = cut(needed.select("rels").distinct().withColumn("size", F.size("rels")))  # few; written, so that the planner knows it
    known = of_relations(facts) if relations is None else relations
    fixed = keys.select("rels", F.explode("rels").alias("r")).join(known.filter("f = 1.0").select("r"), "r", "left_semi").select("rels").distinct()
    keys = keys.join(fixed, "rels", "left_anti")
    one = facts.select("r", "h", "t")
    dense = None
    if budget is None:
        keys = keys.withColumn("q", F.lit(1.0))
        if longest > 1:
            dense = cut(dense_pairs(one, keys.filter("size = 2").select("rels")))
            dense = None if dense.isEmpty() else dense
        if dense is not None:
            keys = keys.join(dense.select("rels"), "rels", "left_anti")
    else:
        share = F.when(F.col("n") <= budget, 1.0).otherwise(F.pow(F.lit(float(SAMPLE_LISTS)) / F.col("n"), 1.0 / F.col("size")))
        keys = cut(keys.join(list_counts(one, keys.select("rels")), "rels").select("rels", "size", share.alias("q")))
    drawn = (F.col("q") >= 1) | (F.pmod(F.xxhash64(F.lit(seed), "rels", "r", "h", "t"), F.lit(1 << 30)) < F.col("q") * F.lit(float(1 << 30)))
    done = fixed.select("rels", F.lit(1.0).alias("f"))
    if dense is not None:
        done = done.unionByName(pairs_in_blocks(one, dense))
    grown = keys.select("rels", "size", "q", F.col("rels")[0].alias("r")).join(one, "r").filter(drawn).select("rels", "size", "q", "t", F.array("h").alias("hs"))
    for n in range(1, longest + 1):
        full = grown.filter(F.col("size") == n)
        exact = full.filter("q >= 1").groupBy("rels", "hs").agg(F.count(F.lit(1)).alias("k")).groupBy("rels").agg((F.count(F.lit(1)) / F.sum("k")).alias("f"))
        done = done.unionByName(exact)
        if budget is not None:
            part = full.filter("q < 1").withColumn("items", F.zip_with("rels", "hs", lambda r, h: F.struct(r.alias("r"), h.alias("h"))))
            part = cut(part.select("rels", "items"))
            done = done.unionByName(part.join(local_lists(facts, part.select("items")), "items").groupBy("rels").agg(F.avg("f").alias("f")))
        if n < longest:
            step = grown.filter(F.col("size") > n).withColumn("r", F.col("rels")[n]).join(one.hint("merge"), ["r", "t"])
            later = (F.col("rels")[n] != F.col("rels")[n - 1]) | (F.col("h") > F.element_at("hs", -1))
            grown = step.filter(later).filter(drawn).select("rels", "size", "q", "t", F.concat("hs", F.array("h")).alias("hs"))
    return done


#: Facts of either side that meet in a block, about.
BLOCK = 200_000
#: Pairs of a relation list for each fact that blocks would shuffle, from which on blocks are less work than rows of pairs.
PAIRS_A_ROW = 4
#: Pairs that a block holds at a time, about.
_PAIRS = 4_000_000


def dense_pairs(facts: DataFrame, needed: DataFrame) -> DataFrame:
    """(k, rels, left, right), to be written: the lists of two relations in ``needed`` that are less work in blocks, with a number and their numbers of blocks."""
    size = facts.groupBy("r").agg(F.count(F.lit(1)).alias("n"))
    of = lambda i: size.select(F.col("r").alias(f"r{i}"), F.col("n").alias(f"n{i}"))
    rows = list_counts(facts, needed).select("rels", "n", F.col("rels")[0].alias("r1"), F.col("rels")[1].alias("r2")).join(of(1), "r1").join(of(2), "r2")
    blocks = lambda c: F.ceil(F.col(c) / F.lit(BLOCK)).cast("int")
    rows = rows.withColumns({"left": blocks("n1"), "right": blocks("n2")})
    return rows.filter(F.col("n") > F.lit(PAIRS_A_ROW) * (F.col("n1") * F.col("right") + F.col("n2") * F.col("left"))).select(F.monotonically_increasing_id().alias("k"), "rels", "left", "right")


def pairs_in_blocks(facts: DataFrame, lists: DataFrame) -> DataFrame:
    """(rels, f) of the lists of two in ``dense_pairs``: every pair of heads meets in one block, which counts it once for its tails.

    Only facts are shuffled, once for each block of the other side. A block
    holds its facts and a bounded number of pairs, however many heads a tail
    has. Heads of one relation meet in either order, which leaves the share as
    it is.
    """
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    block = lambda n: F.pmod(F.xxhash64("h"), F.col(n)).cast("int")
    lists = F.broadcast(lists.withColumn("same", F.col("rels")[0] == F.col("rels")[1]))
    meet = lambda n: facts.join(lists.withColumn("r", F.col("rels")[n]), "r")
    x = meet(0).withColumns({"i": block("left"), "side": F.lit(1)}).withColumn("j", every("right"))
    y = meet(1).withColumns({"j": block("right"), "side": F.lit(0)}).withColumn("i", every("left"))
    columns = ["k", "same", "i", "j", "side", "h", "t"]
    dealt = x.select(*columns).unionByName(y.select(*columns)).repartition("k", "i", "j").sortWithinPartitions("k", "i", "j")
    found = dealt.mapInArrow(_pair_blocks, "k long, lists long, pairs long").groupBy("k").agg((F.sum("lists") / F.sum("pairs")).alias("f"))
    return found.join(lists.select("k", "rels"), "k").select("rels", "f")


def _pair_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow over (k, same, i, j, side, h, t) sorted by k, i and j."""
    held: list[pa.RecordBatch] = []
    name = None
    for batch in batches:
        if not batch.num_rows:
            continue
        k, i, j = (batch.column(c).to_numpy() for c in ("k", "i", "j"))
        edges = [0, *(np.flatnonzero((k[1:] != k[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])) + 1).tolist(), len(k)]
        for start, end in zip(edges[:-1], edges[1:], strict=True):
            here = (k[start], i[start], j[start])
            if held and here != name:
                yield _pair_block(held)
                held = []
            held.append(batch.slice(start, end - start))
            name = here
    if held:
        yield _pair_block(held)


def _pair_block(rows: list[pa.RecordBatch]) -> pa.RecordBatch:
    """(k, lists, pairs): the distinct pairs of heads with a tail in common, and the same counted for each tail."""
    table = pa.Table.from_batches(rows)
    code = lambda c: table.column(c).combine_chunks().dictionary_encode().indices.to_numpy().astype(np.int64)
    side, h, t, same = table.column("side").to_numpy(), code("h"), code("t"), table.column("same")[0].as_py()
    mine, theirs = np.flatnonzero(side == 1), np.flatnonzero(side == 0)
    mine, theirs = mine[np.argsort(h[mine], kind="stable")], theirs[np.argsort(t[theirs], kind="stable")]
    who, under, heads = h[theirs], t[theirs], h[mine]
    start = np.searchsorted(under, t[mine], "left")
    times = np.searchsorted(under, t[mine], "right") - start
    last = np.flatnonzero(np.append(heads[1:] != heads[:-1], True)) + 1 if len(heads) else np.zeros(0, np.int64)  # ends of heads: a head is never dealt apart
    upto = np.append(0, np.cumsum(times))
    lists = pairs = begin = 0
    while begin < len(heads):
        fit = np.searchsorted(upto[last], upto[begin] + _PAIRS, "right")
        end = int(last[max(fit - 1, 0)])
        if end <= begin:  # one head with more pairs than that
            end = int(last[np.searchsorted(last, begin, "right")])
        n = times[begin:end]
        at = np.repeat(start[begin:end] - (upto[begin:end] - upto[begin]), n) + np.arange(upto[end] - upto[begin])
        one, two = np.repeat(heads[begin:end], n), who[at]
        if same:
            one, two = one[one != two], two[one != two]
        pairs += len(one)
        met = np.sort((one << 32) | two)
        lists += int((met[1:] != met[:-1]).sum()) + 1 if len(met) else 0
        begin = end
    return pa.RecordBatch.from_arrays([pa.array([table.column("k")[0].as_py()]), pa.array([lists], pa.int64()), pa.array([pairs], pa.int64())], names=["k", "lists", "pairs"])


def list_counts(facts: DataFrame, needed: DataFrame) -> DataFrame:
    """(rels, n): the (head list, tail) pairs of relation lists, from the degrees of tails: over all tails the product of binomials."""
    degree = facts.groupBy("t", "r").agg(F.count(F.lit(1)).cast("double").alias("d"))
    wanted = needed.select("rels").distinct().select("rels", F.size(F.array_distinct("rels")).alias("kinds"), F.explode("rels").alias("r"))
    wanted = wanted.groupBy("rels", "kinds", "r").agg(F.count(F.lit(1)).alias("m"))
    ways = F.lit(1.0)
    for i in range(LONGEST):
        ways = ways * F.when(F.col("m") > i, F.greatest(F.lit(0.0), F.col("d") - i) / (i + 1)).otherwise(F.lit(1.0))
    rows = wanted.join(degree, "r").withColumn("w", ways).filter("w > 0")
    each = rows.groupBy("rels", "t").agg(F.count(F.lit(1)).alias("k"), F.exp(F.sum(F.ln("w"))).alias("w"), F.first("kinds").alias("kinds"))
    return each.filter("k = kinds").groupBy("rels").agg(F.sum("w").alias("n"))
