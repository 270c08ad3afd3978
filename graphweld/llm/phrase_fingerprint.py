"""Document fingerprints by locally consistent parsing.

A level cuts a row of symbols into phrases by deterministic coin tossing: the
label of a symbol becomes the place of the lowest bit in which it differs from
its left neighbour, with that bit; a few rounds bring any alphabet down to six
labels, and the phrases start at the local maxima. Cuts depend on a few symbols
around them only, so equal substrings are cut alike in their interior wherever
they stand. The name of a phrase is a hash of its symbols; names are the
symbols of the next level. Level 1 reads UTF-8 bytes; phrases of level 2 and 3
are about 6 and 15 bytes long.

The fingerprint is one permutation min-hash over the set of phrase names:
32 bins for level 2 and 64 bins for level 3, a byte each, 0 for an empty bin.
The likeness of two fingerprints is the share of phrases in common (twice the
common ones over all), estimated over the used bins of both levels together;
short texts have few phrases of level 3 and so few bins of it.

Texts and edited texts need a document's successor by descending doc_id. The
rows are dealt once, into ranges of doc_id; the first row of each range is sent
to the range that needs it as well. Equal ids are ordered by a hash of the text
and are one range, so ids should be names of documents, not of groups.

Defined results: every row is returned; null ids come last in descending order,
as the least id of all; a null text is an empty one; an empty text has all bins
empty and is unlike any other, but wholly like another empty one; the successor
of a single row is the row itself.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweld.llm.common import map_slices, slices

BINS = {2: 32, 3: 64}
#: The place of null ids in the order.
NO_ID = -(1 << 63)

_LOWEST = np.zeros(1 << 16, np.uint8)
for _bit in range(15, -1, -1):
    _LOWEST[1 << _bit :: 2 << _bit] = _bit
_random = np.random.Generator(np.random.PCG64(20240229))
_BYTE = _random.integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_PLACE = _random.integers(1, 1 << 63, 64, dtype=np.uint64) | np.uint64(1)


def _mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads their bits."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def phrase_starts(symbols: np.ndarray, starts: np.ndarray, rounds: int) -> np.ndarray:
    """Where phrases begin. symbols: 16 bits each; starts: where the texts begin, in order, none empty."""
    label = symbols
    for _ in range(rounds):
        before = np.empty_like(label)
        before[1:] = label[:-1]
        before[starts] = label[starts] ^ 1  # a text has no left neighbour
        low = _LOWEST[label ^ before]
        label = (low.astype(np.uint16) << 1) | ((label >> low) & 1)
    after = np.empty_like(label)
    after[:-1] = label[1:]
    after[starts[1:] - 1] = after[-1] = 0xFFFF  # nor a right one at its end
    cut = np.zeros(len(label), bool)
    cut[1:] = (label[1:] > label[:-1]) & (label[1:] >= after[1:])
    cut[starts] = True
    return np.flatnonzero(cut)


def phrases(texts: list[bytes]) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """For levels 2 and 3: the names of all phrases, and the text that each belongs to."""
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    owners = np.flatnonzero(lengths)
    none = (np.empty(0, np.uint64), np.empty(0, np.int64))
    if not len(owners):
        return {2: none, 3: none}
    data = np.frombuffer(b"".join(texts), np.uint8)
    starts = np.concatenate(([0], np.cumsum(lengths[owners])[:-1]))
    names, symbols = _BYTE[data], data.astype(np.uint16)
    found = {}
    for level in (1, 2, 3):
        at = phrase_starts(symbols, starts, 3 if level == 1 else 4)
        size = np.diff(np.append(at, len(symbols)))
        place = (np.arange(len(symbols)) - np.repeat(at, size)) & 63
        names = _mixed(np.add.reduceat(names * _PLACE[place], at) + size.astype(np.uint64))
        symbols = (names >> np.uint64(48)).astype(np.uint16)
        starts = np.searchsorted(at, starts)
        if level in BINS:
            found[level] = (names, owners[np.searchsorted(starts, np.arange(len(names)), side="right") - 1])
    return found


def fingerprints(texts: list[bytes]) -> np.ndarray:
    """One row of bin bytes a text."""
    found = phrases(texts)
    parts = []
    for level, bins in BINS.items():
        names, owner = found[level]
        out = np.zeros(len(texts) * bins, np.uint8)
        if len(names):
            draw = _mixed(names ^ np.uint64(level))
            cell = owner * bins + (draw % np.uint64(bins)).astype(np.int64)
            rank = draw >> np.uint64(16)
            order = np.lexsort((rank, cell))
            cell, rank = cell[order], rank[order]
            first = np.flatnonzero(np.concatenate(([True], cell[1:] != cell[:-1])))
            out[cell[first]] = (rank[first] % np.uint64(255)).astype(np.uint8) + 1
        parts.append(out.reshape(len(texts), bins))
    return np.hstack(parts)


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row: estimated share of common phrases, 0 to 1."""
    used = ((a > 0) | (b > 0)).sum(1)
    same = ((a == b) & (a > 0)).sum(1)
    jaccard = np.divide(same, used, out=np.zeros(len(a)), where=used > 0)
    jaccard = np.where(same == used, jaccard, np.maximum(0.0, (jaccard - 1 / 255) / (1 - 1 / 255)))  # bytes agree by chance
    jaccard[used == 0] = 1.0
    return 2 * jaccard / (1 + jaccard)


def fingerprint(documents: DataFrame) -> DataFrame:
    """doc_id and fingerprint of every row, without a shuffle."""

    def make():
        def work(part):
            fp = fingerprints([x or b"" for x in part.column("body").to_pylist()])
            return {"doc_id": part.column("doc_id"), "fingerprint": [x.tobytes().hex() for x in fp]}

        return work

    kind = dict(documents.dtypes)["doc_id"]
    return map_slices(documents.select("doc_id", F.col("text").cast("binary").alias("body")), "body", make, f"doc_id {kind}, fingerprint string")


OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _describe(ids: list[int], texts: list[str]) -> pa.RecordBatch:
    """Rows for all but the last text, each with its successor."""
    edited = []
    for text, after in zip(texts, texts[1:], strict=False):
        n = len(text) // 3
        edited.append((text[: len(text) - n] + after[:n]).encode())
    own = fingerprints([x.encode() for x in texts])
    other = fingerprints(edited)
    rows = {
        "doc_id": pa.array([None if x == NO_ID else x for x in ids[:-1]], pa.int64()),
        "n_chars": [len(x) for x in texts[:-1]],
        "edited_sha256": [hashlib.sha256(x).hexdigest() for x in edited],
        "fingerprint": [x.tobytes().hex() for x in own[:-1]],
        "edited_fingerprint": [x.tobytes().hex() for x in other],
        "near_edited": likeness(own[:-1], other),
        "near_next": likeness(own[:-1], own[1:]),
    }
    return pa.RecordBatch.from_pydict(rows)


def compare_edited(documents: DataFrame, ranges: int | None = None) -> DataFrame:
    """Fingerprints of every text and of its edited text, and how alike they are."""
    spark = documents.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranges = ranges or 4 * parts
    known = F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id")
    ids = documents.select(known)
    points = ids.agg(F.percentile_approx("doc_id", [k / ranges for k in range(1, ranges)] or [0.5], max(10_000, 20 * ranges))).first()[0]
    bounds = np.array(sorted(set(points or [])), np.int64)

    @F.pandas_udf("int")
    def range_of(doc_id: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(bounds, doc_id.to_numpy(np.int64), side="left").astype(np.int32))

    heads = ids.select("doc_id", range_of("doc_id").alias("p")).groupBy("p").agg(F.max("doc_id").alias("head")).collect()
    heads = sorted((r.p, r.head) for r in heads)
    # the successor of a range's last row is the head of the range below; below the lowest comes the highest
    needs = {head: heads[(i + 1) % len(heads)][0] for i, (_, head) in enumerate(heads)}

    @F.pandas_udf("array<int>")
    def places(doc_id: pd.Series) -> pd.Series:
        own = np.searchsorted(bounds, doc_id.to_numpy(np.int64), side="left").tolist()
        return pd.Series([[p, -1 - needs[d]] if d in needs else [p] for p, d in zip(own, doc_id.tolist(), strict=True)])

    rows = documents.select(known, F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("place", F.explode(places("doc_id")))
    rows = rows.select(F.when(F.col("place") < 0, -1 - F.col("place")).otherwise(F.col("place")).alias("p"), (F.col("place") < 0).alias("extra"), "doc_id", "text")
    dealt = rows.repartition(parts, "p").sortWithinPartitions("p", "extra", F.col("doc_id").desc(), F.xxhash64("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids: list[int] = []
        texts: list[str] = []
        range_now, ended, weight = None, False, 0
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                for p, extra, doc_id, text in zip(*(part.column(k).to_pylist() for k in range(4)), strict=True):
                    if p != range_now:
                        range_now, ended, ids, texts, weight = p, False, [], [], 0
                    if ended:
                        continue
                    ids.append(doc_id)
                    texts.append(text)
                    weight += len(text)
                    if len(ids) > 1 and (extra or weight > 2 << 20):
                        yield _describe(ids, texts)
                        ids, texts, weight = ids[-1:], texts[-1:], len(text)
                    ended = extra

    return dealt.mapInArrow(run, OUT)
