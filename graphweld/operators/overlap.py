"""Partners with the most facts in common, counted in blocks instead of by rows of pairs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphweld.plans.lineage import cut

#: Facts of the first and of the second graph that meet in a block, about.
LEFT, RIGHT = 50_000, 300_000
#: Pairs that a task gives on at a time, about.
_ROWS = 100_000


def most_shared(a: DataFrame, b: DataFrame, heads: DataFrame, relations: DataFrame | None, left: int = LEFT, right: int = RIGHT) -> DataFrame:
    """(t, t2): as ``rules.candidates`` of ``rules.counterparts`` from the left; a and b without literal tails.

    Popular heads make far more pairs than stay in the end. Here only facts are
    shuffled: those of the first graph get numbers, every fact of the second one
    the numbers that it meets, and blocks of tails of either side meet once
    each. A task adds up the tails under each number for one t at a time, so it
    holds a block and one array of counts, however popular a head is.
    """
    numbers = cut(a.select("h", "r").distinct().withColumn("f", F.monotonically_increasing_id()))
    links = numbers.join(heads.filter("s > 0").select("h", "h2").distinct(), "h")
    keys = ["h2"]
    if relations is not None:
        links, keys = links.join(relations.filter("s_r > 0").select("r", "r2").distinct(), "r"), ["h2", "r2"]
    mine = cut(a.join(numbers, ["h", "r"]).select("f", F.col("t").alias("key")).distinct())
    theirs = b.select(F.col("h").alias("h2"), F.col("r").alias("r2"), F.col("t").alias("key"))
    theirs = cut(theirs.join(links.select("f", *keys).hint("merge"), keys).select("f", "key").distinct())
    rows = max(a.sparkSession.sparkContext.defaultParallelism * 2, -(-mine.count() // left))
    columns = max(1, -(-theirs.count() // right))
    block = lambda n: F.pmod(F.xxhash64("key"), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    x = mine.withColumns({"i": block(rows), "side": F.lit(1)}).withColumn("j", every(columns))
    y = theirs.withColumns({"j": block(columns), "side": F.lit(0)}).withColumn("i", every(rows))
    both = x.select("i", "j", "side", "key", "f").unionByName(y.select("i", "j", "side", "key", "f"))
    dealt = both.repartition("i", "j").select((F.col("i").cast("long") * columns + F.col("j")).alias("g"), "side", "key", "f").sortWithinPartitions("g")
    kind = {c: f.schema["t"].dataType.simpleString() for c, f in (("t", a), ("t2", b))}
    found = dealt.mapInArrow(_blocks, f"t {kind['t']}, t2 {kind['t2']}, n long")
    if columns > 1:
        found = found.withColumn("top", F.max("n").over(Window.partitionBy("t"))).filter("n = top")
    return found.select("t", "t2")


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow over (g, side, key, f) sorted by g."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        g = batch.column("g").to_numpy()
        if held and len(g) and held[0].column("g")[0].as_py() != g[0]:
            yield from _block(held)
            held = []
        edges = [0, *(np.flatnonzero(g[1:] != g[:-1]) + 1).tolist(), len(g)]
        for k, (start, end) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
            if k:
                yield from _block(held)
                held = []
            if end > start:
                held.append(batch.slice(start, end - start))
    if held:
        yield from _block(held)


def _block(rows: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The best partners of each left key within a block."""
    table = pa.Table.from_batches(rows).select(["side", "key", "f"])
    side, f = table.column("side").to_numpy(), table.column("f").to_numpy()
    names = table.column("key").combine_chunks()
    mine, theirs = np.flatnonzero(side == 1), np.flatnonzero(side == 0)
    if not len(mine) or not len(theirs):
        return
    t, t2 = names.take(pa.array(mine)).dictionary_encode(), names.take(pa.array(theirs)).dictionary_encode()
    order = np.argsort(f[theirs], kind="stable")
    number, who = f[theirs][order], t2.indices.to_numpy()[order]
    by = np.argsort(t.indices.to_numpy(), kind="stable")
    code, wanted = t.indices.to_numpy()[by], f[mine][by]
    start, end = np.searchsorted(number, wanted, "left"), np.searchsorted(number, wanted, "right")
    edges = [0, *(np.flatnonzero(code[1:] != code[:-1]) + 1).tolist(), len(code)]
    n2 = len(t2.dictionary)
    out: list[tuple[int, np.ndarray, int]] = []
    size = 0

    def packed() -> pa.RecordBatch:
        times = [len(x[1]) for x in out]
        left = t.dictionary.take(pa.array(np.repeat([x[0] for x in out], times)))
        return pa.RecordBatch.from_arrays([left, t2.dictionary.take(pa.array(np.concatenate([x[1] for x in out]))), pa.array(np.repeat([x[2] for x in out], times))], names=["t", "t2", "n"])

    for p, q in zip(edges[:-1], edges[1:], strict=True):
        met = np.concatenate([who[s:e] for s, e in zip(start[p:q].tolist(), end[p:q].tolist(), strict=True)])
        if not len(met):
            continue
        if len(met) * 16 < n2:
            ids, n = np.unique(met, return_counts=True)
            most = int(n.max())
            best = ids[n == most]
        else:
            n = np.bincount(met, minlength=n2)
            most = int(n.max())
            best = np.flatnonzero(n == most)
        out.append((int(code[p]), best, most))
        size += len(best)
        if size >= _ROWS:
            yield packed()
            out, size = [], 0
    if out:
        yield packed()
