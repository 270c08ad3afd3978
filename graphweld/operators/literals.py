"""Similarities between literals of two graphs; computed once and fixed.

Strings: cosine of character 3-gram counts, found through shared grams, kept
from a threshold on and only for the most similar counterparts (ties stay).
Numbers: within a relative error, by a join on logarithmic buckets. Dates: equal.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphweld.plans.lineage import cut, cuts


def grams(text: Column, size: int = 3) -> Column:
    """All substrings of ``size`` characters of the text between two marks."""
    padded = F.concat(F.lit("^"), text, F.lit("$"))
    return F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(padded) - (size - 1))), lambda i: F.substring(padded, i, F.lit(size)))


def skeleton(text: Column) -> Column:
    """Without vowels: the stand-in for an encoder that sees through a change of vowels."""
    return F.regexp_replace(F.lower(text), "[aeiou]", "")


ENCODERS: dict[str, Callable[[Column], Column]] = {"ngram": F.lower, "skeleton": skeleton}


def vectors(strings: DataFrame, encoder: str = "ngram") -> DataFrame:
    """(s, g, w): normalised gram counts of each distinct string ``s``."""
    rows = strings.select("s").distinct().withColumn("g", F.explode(grams(ENCODERS[encoder](F.col("s")))))
    counts = rows.groupBy("s", "g").agg(F.count(F.lit(1)).cast("double").alias("c"))
    return counts.withColumn("w", F.col("c") / F.sqrt(F.sum(F.col("c") * F.col("c")).over(Window.partitionBy("s")))).select("s", "g", "w")


def strings_similar(a: DataFrame, b: DataFrame, theta: float = 0.7, top: int | None = 1, encoder: str = "ngram") -> DataFrame:
    """(s, s2, sim) of distinct strings from ``theta`` on; each string keeps its ``top`` ranks, from either side.

    Exact by a prefix filter: grams are in order of how many strings hold them,
    rarest first. The grams after a string's prefix have a norm below theta, so
    two strings without a common prefix gram are less alike than theta. Only
    prefix grams propose pairs; common grams just count for the cosine. Where
    they would propose a good part of all pairs, as names that differ in a
    number only do, strings meet in blocks instead (``best_in_blocks``), which
    gives the same best ones; so it does if there are few pairs in all.
    """
    a, b = cuts(a.select("s").distinct(), b.select("s").distinct())
    n, n2 = a.count(), b.count()
    if top == 1 and n * n2 <= FEW_PAIRS:
        return best(best_in_blocks(a, b, n, n2, theta, encoder), "s", "s2")
    x, y = vectors(a, encoder), vectors(b, encoder)
    held = x.select("g").unionByName(y.select("g")).groupBy("g").agg(F.count(F.lit(1)).alias("n"))

    def side(v: DataFrame) -> DataFrame:
        order = Window.partitionBy("s").orderBy("n", "g").rowsBetween(0, Window.unboundedFollowing)
        marked = v.join(held, "g").withColumn("rest", F.sqrt(F.sum(F.col("w") * F.col("w")).over(order)))
        return marked.select("s", "g", "w", (F.col("rest") >= F.lit(theta) - 1e-9).alias("first"))

    left, right = cuts(side(x), side(y))
    if top == 1:
        under = lambda v, c: v.filter("first").groupBy("g").agg(F.count(F.lit(1)).cast("double").alias(c))
        many = under(left, "n").join(under(right, "n2"), "g").agg(F.sum(F.col("n") * F.col("n2"))).first()[0] or 0.0
        if many * DEAR > n * n2:
            return best(best_in_blocks(a, b, n, n2, theta, encoder), "s", "s2")
    proposed = left.filter("first").select("s", "g").join(right.filter("first").select(F.col("s").alias("s2"), "g"), "g").select("s", "s2").distinct()
    whole = lambda v: v.groupBy("s").agg(F.map_from_entries(F.collect_list(F.struct("g", "w"))).alias("v"))
    dot = F.aggregate(F.map_entries("v"), F.lit(0.0), lambda acc, e: acc + e.value * F.coalesce(F.try_element_at("v2", e.key), F.lit(0.0)))
    sims = proposed.join(whole(left), "s").join(whole(right).withColumnsRenamed({"s": "s2", "v": "v2"}), "s2").select("s", "s2", dot.alias("sim"))
    sims = sims.withColumn("sim", F.least(F.lit(1.0), F.round("sim", 9))).filter(F.col("sim") >= theta)
    return sims if top is None else best(sims, "s", "s2", top)


#: Pairs of strings up to which all meet in blocks, as that takes seconds.
FEW_PAIRS = 100_000_000
#: Pairs that a block compares in the time of one proposed pair, about.
DEAR = 300
#: Strings of either side in a block, and blocks of the left side at least, if it has so many strings.
STRINGS, SPREAD = 20_000, 16
#: Similarities that a block holds at a time, and pairs that it keeps before it looks for better ones, about.
_SIMS, _KEPT = 4_000_000, 1_000_000
#: Grams that are multiplied as a matrix, at most.
_DENSE = 256


def best_in_blocks(a: DataFrame, b: DataFrame, n: int, n2: int, theta: float, encoder: str) -> DataFrame:
    """(s, s2, sim): the pairs from ``theta`` on that are the best of either string within a block, so all that are the best of all.

    a and b: distinct strings, n and n2 of them. Only strings are shuffled, once
    for each block of the other side.
    """
    rows, columns = max(-(-n // STRINGS), min(SPREAD, -(-n // 256)), 1), max(-(-n2 // STRINGS), 1)
    block = lambda m: F.pmod(F.xxhash64("s"), F.lit(m)).cast("int")
    every = lambda m: F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    text = ENCODERS[encoder](F.col("s")).alias("text")
    x = a.select("s", text, F.lit(1).alias("side"), block(rows).alias("i")).withColumn("j", every(columns))
    y = b.select("s", text, F.lit(0).alias("side"), block(columns).alias("j")).withColumn("i", every(rows))
    both = x.unionByName(y).repartition(rows * columns, "i", "j")
    return both.groupBy("i", "j").applyInArrow(lambda t: _best_strings(t, theta), "s string, s2 string, sim double")


def _weights(texts: list[str], codes: dict[str, int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, gram, weight) of normalised gram counts, as ``vectors`` has them."""
    row, gram, weight = [], [], []
    for i, text in enumerate(texts):
        padded = f"^{text}$"
        counts = Counter(padded[k : k + 3] for k in range(max(1, len(padded) - 2)))
        norm = sum(c * c for c in counts.values()) ** 0.5
        for g, c in counts.items():
            row.append(i)
            gram.append(codes.setdefault(g, len(codes)))
            weight.append(c / norm)
    return np.array(row, np.int64), np.array(gram, np.int64), np.array(weight, np.float64)


def _best_strings(table: pa.Table, theta: float) -> pa.Table:
    """The best pairs of a block: common grams as a product of matrices, the others by the strings that hold them."""
    side = table.column("side").to_numpy()
    s, text = table.column("s").combine_chunks(), table.column("text").to_pylist()
    mine, theirs = np.flatnonzero(side == 1), np.flatnonzero(side == 0)
    codes: dict[str, int] = {}
    row, gram, weight = _weights([text[i] for i in mine], codes)
    row2, gram2, weight2 = _weights([text[i] for i in theirs], codes)
    n, n2 = len(mine), len(theirs)
    held = np.bincount(gram2, minlength=len(codes))
    common = np.argsort(-held, kind="stable")[:_DENSE]
    common = common[held[common] > n2 / 16]
    at = np.full(len(codes), -1)
    at[common] = np.arange(len(common))
    thick = np.zeros((n2, len(common)))
    dense = at[gram2] >= 0
    thick[row2[dense], at[gram2[dense]]] = weight2[dense]
    order = np.argsort(gram2, kind="stable")
    row2, weight2, starts = row2[order], weight2[order], np.append(0, np.cumsum(held))
    first = np.searchsorted(row, np.arange(n + 1))
    top = np.full(n2, theta)
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    size, step = 0, max(1, _SIMS // max(1, n2))

    def better() -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """What is still the best of its right string, or was the best of its left one."""
        return [tuple(c[x[3] | (x[2] >= top[x[1]])] for c in x) for x in out]

    for begin in range(0, n if n2 else 0, step):
        end = min(n, begin + step)
        r, g, w = (c[first[begin] : first[end]] for c in (row, gram, weight))
        left = np.zeros((end - begin, len(common)))
        dense = at[g] >= 0
        left[r[dense] - begin, at[g[dense]]] = w[dense]
        sims = left @ thick.T
        for i, k, x in zip((r[~dense] - begin).tolist(), g[~dense].tolist(), w[~dense].tolist(), strict=True):
            if held[k]:
                p = slice(starts[k], starts[k + 1])
                sims[i, row2[p]] += x * weight2[p]
        sims = np.minimum(1.0, np.round(sims, 9))
        np.maximum(top, sims.max(axis=0), out=top)
        mine_best = sims >= np.maximum(theta, sims.max(axis=1))[:, None]
        i, j = np.nonzero(mine_best | (sims >= top))
        out.append((i + begin, j, sims[i, j], mine_best[i, j]))
        size += len(i)
        if size > _KEPT:
            out = better()
            size = sum(len(x[0]) for x in out) // 2  # at least so many more until the next look
    out = better()
    i, j, sim = (np.concatenate([x[c] for x in out]) if out else np.zeros(0, kind) for c, kind in enumerate((np.int64, np.int64, np.float64)))
    return pa.table({"s": s.take(pa.array(mine[i])), "s2": s.take(pa.array(theirs[j])), "sim": sim})


def best(sims: DataFrame, left: str, right: str, top: int = 1) -> DataFrame:
    """The ``top`` ranks for each left or each right value, ties kept."""
    of_left = F.rank().over(Window.partitionBy(left).orderBy(F.desc("sim")))
    of_right = F.rank().over(Window.partitionBy(right).orderBy(F.desc("sim")))
    return sims.withColumns({"_l": of_left, "_r": of_right}).filter((F.col("_l") <= top) | (F.col("_r") <= top)).drop("_l", "_r")


def identical(a: DataFrame, b: DataFrame) -> DataFrame:
    """Strings that are equal after nothing at all: the ablation."""
    return a.select("s").distinct().join(b.select(F.col("s").alias("s2")).distinct(), F.col("s") == F.col("s2")).withColumn("sim", F.lit(1.0))


def close(x: Column, y: Column, rel: float) -> Column:
    return F.abs(x - y) <= F.lit(rel) * F.greatest(F.abs(x), F.abs(y))


def numbers_close(a: DataFrame, b: DataFrame, rel: float = 1e-9) -> DataFrame:
    """(n, n2) with ids of (n, x) and (n2, x2) within a relative error; zero only meets zero, signs must agree.

    Numbers whose logarithms differ by less than ``rel`` are in the same or in
    neighbouring buckets. Two values meet once, so only ids with several values
    can give a pair twice; the pairs of all others are shuffled no further.
    """
    width = 2 * rel
    bucket = lambda c: F.when(c == 0, F.lit(0)).otherwise(F.floor(F.ln(F.abs(c)) / F.lit(width)))
    one = lambda n: F.count(F.lit(1)).over(Window.partitionBy(n)) == 1
    x = a.select("n", "x").distinct().withColumn("one", one("n")).withColumns({"g": F.signum("x"), "k": bucket(F.col("x"))})
    y = b.select("n2", "x2").distinct().withColumn("one2", one("n2")).withColumns({"g": F.signum("x2"), "k": F.explode(F.array(*[bucket(F.col("x2")) + d for d in (-1, 0, 1)]))})
    meet = lambda x, y: x.join(y.hint("merge"), ["g", "k"]).filter(close(F.col("x"), F.col("x2"), rel)).select("n", "n2")
    single = x.filter("one")
    several = meet(x.filter("NOT one"), y).unionByName(meet(single, y.filter("NOT one2")))
    return meet(single, y.filter("one2")).unionByName(several.distinct())


def matches(a: DataFrame, b: DataFrame, theta: float = 0.7, top: int = 1, encoder: str = "ngram", rel: float = 1e-9, identity: bool = False) -> DataFrame:
    """(h, h2, s): similarity of all literal nodes of two fact tables (h, r, t, kind, x)."""
    text = lambda f, c: f.filter("kind = 'string'").select(F.expr("substring(t, 2)").alias("s")).distinct()
    sims = identical(text(a, 0), text(b, 0)) if identity else strings_similar(text(a, 0), text(b, 0), theta, top, encoder)
    out = sims.select(F.concat(F.lit('"'), "s").alias("h"), F.concat(F.lit('"'), "s2").alias("h2"), F.col("sim").alias("s"))
    num = lambda f, n, x: f.filter("kind = 'number'").select(F.col("t").alias(n), F.col("x").alias(x))
    close_numbers = numbers_close(num(a, "n", "x"), num(b, "n2", "x2"), rel)
    out = out.unionByName(close_numbers.select(F.col("n").alias("h"), F.col("n2").alias("h2"), F.lit(1.0).alias("s")))
    days = a.filter("kind = 'date'").select(F.col("t").alias("h")).distinct().join(b.filter("kind = 'date'").select(F.col("t").alias("h2")).distinct(), F.col("h") == F.col("h2"))
    return out.unionByName(days.withColumn("s", F.lit(1.0)))


# ---------------------------------------------------------------- given vectors


def cosine(v: Column, w: Column) -> Column:
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return dot(v, w) / F.sqrt(dot(v, v) * dot(w, w))


def vector_top1(a: DataFrame, b: DataFrame, theta: float = 0.7) -> DataFrame:
    """(id, id2, sim) by exact search over blocks: the right side in hash blocks against all of the left.

    Work is the product of the sizes, so this is for bounded sides and for
    checking ``vector_lsh``.
    """
    blocks = 8
    left = a.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    right = b.withColumn("k", F.pmod(F.xxhash64("id2"), F.lit(blocks)).cast("int"))
    sims = left.join(right, "k").withColumn("sim", cosine(F.col("v"), F.col("v2"))).filter(F.col("sim") >= theta)
    one = F.row_number().over(Window.partitionBy("id").orderBy(F.desc("sim"), "id2"))
    return sims.withColumn("n", one).filter("n = 1").select("id", "id2", "sim")


#: Vectors of either side in a block of one key; keys with more are dealt over several blocks.
VECTORS = 32_768


def vector_lsh(a: DataFrame, b: DataFrame, theta: float = 0.7, dimension: int = 64, tables: int = 12, bits: int = 8, seed: int = 11) -> DataFrame:
    """(id, id2, sim): candidates share the signs of ``bits`` random projections in one of the tables.

    Vectors under a key meet in blocks, which compare all of their pairs as a
    product of matrices and give on the best partner of each id; common keys
    are dealt over several blocks. Pairs of vectors are never rows.
    """
    import random

    draw = random.Random(seed)
    planes = np.array([[[draw.gauss(0, 1) for _ in range(dimension)] for _ in range(bits)] for _ in range(tables)]).reshape(tables, bits, dimension)

    def keyed(f: DataFrame, v: str) -> DataFrame:
        f = f.filter(F.size(v) > 0)
        names = ", ".join(f"{c} {f.schema[c].dataType.simpleString()}" for c in f.columns)
        return f.mapInArrow(lambda batches: (_keys(batch, v, planes) for batch in batches), f"{names}, ks array<long>")

    # written with their keys, which are needed to count and to deal
    x, y = cuts(keyed(a.select("id", "v"), "v"), keyed(b.select("id2", "v2"), "v2"))
    held = lambda f, c: f.select(F.explode("ks").alias("k")).groupBy("k").agg(F.ceil(F.count(F.lit(1)) / F.lit(VECTORS)).cast("int").alias(c))
    parts = F.broadcast(cut(held(x, "rows").join(held(y, "columns"), "k")))  # one row a key, at most tables x 2 ** bits
    block = lambda c, n: F.pmod(F.xxhash64(c), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = x.select("id", "v", F.explode("ks").alias("k")).join(parts, "k").withColumn("i", block("id", "rows")).withColumn("j", every("columns"))
    right = y.select("id2", "v2", F.explode("ks").alias("k")).join(parts, "k").withColumn("j", block("id2", "columns")).withColumn("i", every("rows"))
    kind = {c: f.schema[c].dataType.simpleString() for c, f in (("id", a), ("id2", b))}
    met = left.select("k", "i", "j", "id", "v").groupBy("k", "i", "j").cogroup(right.select("k", "i", "j", "id2", "v2").groupBy("k", "i", "j"))
    found = met.applyInArrow(lambda l, r: _best_vectors(l, r, theta), f"id {kind['id']}, id2 {kind['id2']}, sim double")
    # pairs that meet in several tables don't change the best
    top = found.groupBy("id").agg(F.min(F.struct((-F.col("sim")).alias("less"), "id2")).alias("m"))
    return top.select("id", F.col("m.id2").alias("id2"), (-F.col("m.less")).alias("sim"))


def _keys(batch: pa.RecordBatch, v: str, planes: np.ndarray) -> pa.RecordBatch:
    """With ``ks``: a number for each table, the signs of its projections and the vector's length, as only vectors of one length compare. A sign that rounding may decide is that of the sum in order."""
    tables, bits, dimension = planes.shape
    size = pc.list_value_length(batch.column(v)).to_numpy(zero_copy_only=False).astype(np.int64)
    here = np.flatnonzero(size == dimension)
    flat = planes.reshape(-1, dimension)
    on = np.zeros((len(size), tables * bits), np.int64)
    if len(here) and bits:
        x = _rows_of(batch.column(v).take(pa.array(here)))
        sums = x @ flat.T
        i, j = np.nonzero(np.abs(sums) <= 1e-11 * (np.abs(x) @ np.abs(flat).T))
        sums[i, j] = np.add.accumulate(x[i] * flat[j], axis=1)[:, -1]
        on[here] = sums >= 0
    code = (on.reshape(len(size), tables, bits) << np.arange(bits)[::-1]).sum(axis=2)
    ks = (size[:, None] * tables + np.arange(tables) << bits) | code
    return batch.append_column("ks", pa.ListArray.from_arrays(pa.array(np.arange(len(size) + 1) * tables, pa.int32()), pa.array(ks.ravel())))


def _rows_of(vectors: pa.Array | pa.ChunkedArray) -> np.ndarray:
    flat = vectors.combine_chunks() if isinstance(vectors, pa.ChunkedArray) else vectors
    return flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1)


def _best_vectors(left: pa.Table, right: pa.Table, theta: float) -> pa.Table:
    """The best partner of each left vector in a block; the product of matrices finds those near the best, whose cosine is then summed in one order, so that ties are ties."""
    kinds = [left.schema.field("id").type, right.schema.field("id2").type, pa.float64()]
    if not left.num_rows or not right.num_rows:
        return pa.table([pa.array([], k) for k in kinds], names=["id", "id2", "sim"])
    x, y = _rows_of(left.column("v")), _rows_of(right.column("v2"))
    dot = lambda p, q: np.add.accumulate(p * q, axis=1)[:, -1]
    xx, yy = dot(x, x), dot(y, y)
    with np.errstate(divide="ignore", invalid="ignore"):
        ux, uy = x / np.sqrt(xx)[:, None], y / np.sqrt(yy)[:, None]
    ux, uy = (np.nan_to_num(u, nan=0.0, posinf=0.0, neginf=0.0).astype(np.float32) for u in (ux, uy))
    names = right.column("id2").combine_chunks()
    rank = np.empty(len(names), np.int64)
    rank[pc.sort_indices(names).to_numpy()] = np.arange(len(names))
    who, partner, sim = [], [], []
    step = max(1, _SIMS // len(y))
    for begin in range(0, len(x), step):
        sims = ux[begin : begin + step] @ uy.T
        near = np.maximum(sims.max(axis=1), np.float32(theta)) - np.float32(2e-5)  # more than these sums can be off
        i, j = np.nonzero(sims >= near[:, None])
        i += begin
        exact = np.concatenate([dot(x[i[k : k + 50_000]], y[j[k : k + 50_000]]) for k in range(0, max(1, len(i)), 50_000)])
        with np.errstate(divide="ignore", invalid="ignore"):
            exact = exact / np.sqrt(xx[i] * yy[j])
        fit = exact >= theta
        i, j, exact = i[fit], j[fit], exact[fit]
        order = np.lexsort((rank[j], -exact, i))
        first = order[np.append(True, i[order][1:] != i[order][:-1])] if len(order) else order
        who.append(i[first])
        partner.append(j[first])
        sim.append(exact[first])
    return pa.table([left.column("id").combine_chunks().take(pa.array(np.concatenate(who))), names.take(pa.array(np.concatenate(partner))), pa.array(np.concatenate(sim))], names=["id", "id2", "sim"])


def encoder_udf(encode: Callable[[pd.Series], pd.Series]):
    """A vectorised encoder (strings to vectors) as a column function; the hook for a real language model."""
    return F.pandas_udf("array<double>")(encode)
