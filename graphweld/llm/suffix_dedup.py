"""Exact removal of repeated byte strings by induced suffix sorting over shards.

A byte goes if a string of ``LENGTH`` bytes that covers it also starts anywhere
else. Sorting all suffixes of a corpus is out of reach; sorting a sparse set of
them and inducing the rest is not:

1. *Seeds.* Every window of ``LENGTH`` bytes has one seed, the leftmost
   ``GRAM``-gram with the smallest hash. Equal windows have equal seeds at equal
   offsets, so only suffixes that start left of a seed shared with another
   place can matter. Seed tuples (hash, digest of all bytes that the windows of
   this seed span, place) are sorted externally by Spark, which spills sorted
   runs and merges them through a priority queue.
2. *Whole spans.* Seeds whose spans have equal digests are repeated as a whole.
   Seeds of a hash with one span only are unique and drop out.
3. *Induction.* For the hashes with several different spans, one span each is
   fetched and sharded by hash. In a shard the suffixes that start at the seeds
   are sorted, with the common-prefix lengths of neighbours. The order of the
   suffixes one byte further left is induced from it by a stable sort on that
   byte alone, and their common-prefix lengths are the carried minima plus one;
   so the recursion walks left through all windows. A suffix whose
   neighbour in order shares ``LENGTH`` bytes is a repeated window.
4. Spans of a hash with over ``SHARD`` different ones are cut into their windows,
   which are counted by 128-bit digests; nothing is dropped and no task holds
   such a hash.

Deviation from sorting every suffix, as unique seeds are left out: the result
is the same, the work is a few percent of the suffixes.

Defined results: a null text is an empty one; texts shorter than ``LENGTH``
lose nothing; repeated rows count as two places and so remove each other.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphweld.llm.common import cut, give_back, map_slices

LENGTH, GRAM = 200, 64
#: Spans of one hash that a task sorts together.
SHARD = 100_000
#: Spans that are sorted at a time otherwise.
BATCH = 32_000
#: Bytes that are hashed at a time; the arrays for it take some 60 bytes each.
_SEGMENT = 1 << 18
_STEP = np.array([0x9E3779B97F4A7C15, 0xD1342543DE82EF95, 0xAF251AF3B0F025B5, 0xB564EF22EC7AECE5, 0xF7C2EBC08F67F2B5, 0x8CB92BA72F3D8DD7], np.uint64)


def gram_hashes(data: np.ndarray) -> np.ndarray:
    """Hash of the 64 bytes from each place on, by doubling."""
    h = (data.astype(np.uint64) + np.uint64(1)) * np.uint64(0x2545F4914F6CDD1D)
    h ^= h >> np.uint64(29)
    size = 1
    for step in _STEP:
        h = h[:-size] * step + h[size:]
        size *= 2
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    return h


def sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    """Least of each ``width`` entries, from blocks' running minima from both sides."""
    n = len(x)
    full = -(-n // width) * width
    blocks = np.full(full, np.iinfo(x.dtype).max, x.dtype)
    blocks[:n] = x
    blocks = blocks.reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[: n - width + 1], ahead[width - 1 : n])


def seeds(bodies: list[bytes]) -> tuple[np.ndarray, ...]:
    """(text, first window, last window, seed place, hash) of all seeds, places within their text."""
    out: list[tuple[np.ndarray, ...]] = []

    def add(part: list[tuple[int, int, bytes]]) -> None:
        data = np.frombuffer(b"".join(x[2] for x in part), np.uint8)
        h = gram_hashes(data)
        place = np.arange(len(h), dtype=np.uint64)
        least = sliding_least((h & ~np.uint64(0xFFFFFF)) | place, LENGTH - GRAM + 1)
        ends = np.cumsum([len(x[2]) for x in part])
        begins = ends - [len(x[2]) for x in part]
        valid = np.zeros(len(least), bool)
        for a, b in zip(begins.tolist(), ends.tolist(), strict=True):
            valid[a : b - LENGTH + 1] = True
        at = np.flatnonzero(valid)
        seed = (least[at] & np.uint64(0xFFFFFF)).astype(np.int64)
        new = np.flatnonzero(np.concatenate(([True], (seed[1:] != seed[:-1]) | (at[1:] != at[:-1] + 1))))
        first, last, p = at[new], at[np.append(new[1:], len(at)) - 1], seed[new]
        k = np.searchsorted(ends, first, side="right")
        shift = np.array([x[1] for x in part])[k] - begins[k]
        out.append((np.array([x[0] for x in part])[k], first + shift, last + shift, p + shift, h[p]))

    part: list[tuple[int, int, bytes]] = []
    size = 0
    for i, body in enumerate(bodies):
        for a in range(0, max(0, len(body) - LENGTH + 1), _SEGMENT):
            piece = body[a : a + _SEGMENT + LENGTH - 1]
            if part and size + len(piece) > 2 * _SEGMENT:
                add(part)
                part, size = [], 0
            part.append((i, a, piece))
            size += len(piece)
    if part:
        add(part)
    if not out:
        none = np.zeros(0, np.int64)
        return none, none, none, none, none.astype(np.uint64)
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def _keyed(documents: DataFrame, *keep: str) -> DataFrame:
    body = F.coalesce("text", F.lit("")).cast("binary")
    return documents.select("doc_id", *keep, F.xxhash64("doc_id", "text").alias("key"), body.alias("body"))


def seed_table(keyed: DataFrame) -> DataFrame:
    """(h, c, key, place): hash, digest of the span, text, and first window, windows and seed packed into a number.

    A span that a slice of rows holds more than once is known to be repeated:
    one row of it goes on to be compared, and all its places are told directly,
    as rows with a hash of their own and -1 - place. So a passage that is
    everywhere is a row a slice and not a row a place.
    """

    def make():
        from xxhash import xxh64_intdigest

        def work(part):
            bodies = part.column("body").to_pylist()
            text, first, last, p, h = seeds(bodies)
            c = np.fromiter((xxh64_intdigest(bodies[i][a:b]) for i, a, b in zip(text.tolist(), first.tolist(), (last + LENGTH).tolist(), strict=True)), np.uint64, len(text))
            key = part.column("key").to_numpy()[text]
            place = first << 16 | (last - first) << 8 | (p - first)
            _, one, which, times = np.unique(h * np.uint64(0x9E3779B97F4A7C15) ^ c, return_index=True, return_inverse=True, return_counts=True)
            told = np.flatnonzero(times[which] > 1)
            own = (key[told].view(np.uint64) ^ (place[told].view(np.uint64) * np.uint64(0xD1342543DE82EF95))) * np.uint64(0x9E3779B97F4A7C15)
            return {
                "h": np.concatenate((h[one], own)).view(np.int64),
                "c": np.concatenate((c[one], np.zeros(len(told), np.uint64))).view(np.int64),
                "key": np.concatenate((key[one], key[told])),
                "place": np.concatenate((place[one], -1 - place[told])),
            }

        return work

    return map_slices(keyed.select("key", "body").filter(F.length("body") >= LENGTH), "body", make, "h long, c long, key long, place long")


def classed(table: DataFrame) -> DataFrame:
    """Seeds that matter: ``whole`` if their span is repeated, ``ask`` if their hash has other spans too, ``hot`` if too many."""
    by = Window.partitionBy("h")
    run = by.orderBy("c")
    rows = table.withColumns(
        {
            "before": F.lag("c").over(run),
            "after": F.lead("c").over(run),
            "low": F.min("c").over(by),
            "high": F.max("c").over(by),
            "n": F.count(F.lit(1)).over(by),
        }
    )
    rows = rows.filter("n > 1 OR place < 0")
    told = F.col("place") < 0
    whole = told | F.coalesce(F.col("before") == F.col("c"), F.lit(False)) | F.coalesce(F.col("after") == F.col("c"), F.lit(False))
    ask = ~told & (F.col("low") != F.col("high")) & F.coalesce(F.col("before") != F.col("c"), F.lit(True))
    return rows.select("h", "key", F.when(told, -1 - F.col("place")).otherwise(F.col("place")).alias("place"), whole.alias("whole"), ask.alias("ask"), (F.col("n") > SHARD).alias("hot")).filter("whole OR ask")


def spans(keyed: DataFrame, asked: DataFrame) -> DataFrame:
    """(h, hot, key, place, span): the bytes of the spans of all ``asked`` seeds."""
    lists = asked.groupBy("key").agg(F.collect_list(F.struct("h", "place", "hot")).alias("seeds"))
    packed = packed_bodies(keyed.select("key", "body"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        inflate = zstandard.ZstdDecompressor()
        for batch in batches:
            for k in range(0, len(batch), 256):
                part = batch.slice(k, 256)
                rows: list[tuple] = []
                for key, z, asks in zip(*(part.column(i).to_pylist() for i in range(3)), strict=True):
                    body = inflate.decompress(z)
                    for x in asks:
                        a, n = x["place"] >> 16, x["place"] >> 8 & 255
                        rows.append((x["h"], x["hot"], key, x["place"], body[a : a + n + LENGTH]))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], names=["h", "hot", "key", "place", "span"])

    joined = packed.select("key", "z").join(lists, "key").select("key", "z", "seeds")
    return joined.mapInArrow(run, "h long, hot boolean, key long, place long, span binary")


def packed_bodies(keyed: DataFrame) -> DataFrame:
    """The rows with the compressed text ``z`` for ``body``: what the shuffles by text carry."""
    kinds = {c: k for c, k in keyed.dtypes if c != "body"}

    def make():
        import zstandard

        deflate = zstandard.ZstdCompressor(level=3)
        return lambda part: {c: part.column(c) for c in kinds} | {"z": [deflate.compress(x) for x in part.column("body").to_pylist()]}

    return map_slices(keyed, "body", make, "".join(f"`{c}` {k}, " for c, k in kinds.items()) + "z binary")


def induced(group: np.ndarray, place: np.ndarray, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(entry, window start within its text) of every window that another entry of its group has too.

    group: equal for the spans of one hash, which are together.
    """
    first, left = place >> 16, place & 255
    most = left  # offsets left of the seed at which this entry has windows: from least to most
    least = left - (place >> 8 & 255)
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    base = np.concatenate(([0], np.cumsum(size)[:-1]))
    data = np.frombuffer(b"".join(texts) + b"\0" * LENGTH, np.uint8)
    seed = base + left
    ahead = size - left
    # sort the suffixes that start at the seeds, within their groups
    rights = [int(g).to_bytes(8, "big") + t[a : a + LENGTH] for g, t, a in zip((group - group.min()).tolist(), texts, left.tolist(), strict=True)]
    order = np.array(sorted(range(len(texts)), key=rights.__getitem__), np.int64)
    group, seed, most, least, ahead = group[order], seed[order], most[order], least[order], np.minimum(ahead[order], LENGTH)
    n = len(order)
    common = np.zeros(n, np.uint8)  # with the entry before
    view = np.lib.stride_tricks.sliding_window_view(data, LENGTH)
    for a in range(1, n, 8192):
        b = min(n, a + 8192)
        differs = view[seed[a:b]] != view[seed[a - 1 : b - 1]]
        lcp = np.where(differs.any(1), differs.argmax(1), LENGTH)
        common[a:b] = np.minimum(lcp, np.minimum(ahead[a:b], ahead[a - 1 : b - 1]))
    common[np.flatnonzero(group[1:] != group[:-1]) + 1] = 0
    levels = [common]
    while 2 << (len(levels) - 1) <= n:
        x, step = levels[-1], 1 << (len(levels) - 1)
        levels.append(np.minimum(x[:-step], x[step:]))
    best = np.maximum(common, np.append(common[1:], 0)).astype(np.int64)
    rank = np.flatnonzero(best + most >= LENGTH)  # the others share too little with anyone
    kind = group[rank] if len(rank) else group[:0]
    entries, offsets = [], []
    offset = 0
    while len(rank) > 1:
        same = kind[1:] == kind[:-1]
        a, b = rank[:-1][same] + 1, rank[1:][same]
        if len(a):
            width = b - a + 1
            level = np.frexp(width)[1] - 1
            shared = np.empty(len(a), np.int64)
            for k in np.unique(level).tolist():
                m = level == k
                shared[m] = np.minimum(levels[k][a[m]], levels[k][b[m] - (1 << k) + 1])
            hit = shared + offset >= LENGTH
            found = np.unique(np.concatenate((a[hit] - 1, b[hit])))
            found = found[(least[found] <= offset) & (offset <= most[found])]
            entries.append(order[found])
            offsets.append(np.full(len(found), offset))
        offset += 1
        keep = most[rank] >= offset
        if len(rank) > 1:
            alone = np.ones(len(rank), bool)
            alone[1:] &= ~same
            alone[:-1] &= ~same
            keep &= ~alone
        rank, kind = rank[keep], kind[keep]
        if not len(rank):
            break
        # one byte further left: a stable sort on it within each class
        _, kind = np.unique(kind, return_inverse=True)
        deeper = kind.astype(np.int64) * 256 + data[seed[rank] - offset]
        by = np.argsort(deeper, kind="stable")
        rank, kind = rank[by], deeper[by]
    if not entries:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    entry = np.concatenate(entries)
    return entry, (first + left)[entry] - np.concatenate(offsets)


def intervals(key: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of consecutive starts of a text as (key, first, last)."""
    order = np.lexsort((start, key))
    key, start = key[order], start[order]
    new = np.flatnonzero(np.concatenate(([True], (key[1:] != key[:-1]) | (start[1:] > start[:-1] + 1)))) if len(key) else np.zeros(0, np.int64)
    last = np.append(new[1:], len(key))[: len(new)] - 1
    return key[new], start[new], start[last]


def sort_shards(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow over spans sorted by h: the repeated windows of each text as intervals of starts."""
    held: list[pa.RecordBatch] = []
    size = 0

    def solve(rows: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(rows)
        h, key, place = (table.column(c).to_numpy() for c in ("h", "key", "place"))
        group = np.cumsum(np.concatenate(([0], (h[1:] != h[:-1]).astype(np.int64))))
        entry, start = induced(group, place, table.column("span").to_pylist())
        columns = intervals(key[entry], start)
        return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["key", "a", "b"])

    for batch in batches:
        if not len(batch):
            continue
        held.append(batch)
        size += len(batch)
        if size < BATCH:
            continue
        h = batch.column("h").to_numpy()
        change = np.flatnonzero(h[1:] != h[:-1]) + 1
        if len(change):
            at = int(change[-1])
            held[-1] = batch.slice(0, at)
            yield solve(held)
            held, size = [batch.slice(at)], len(batch) - at
    if held:
        yield solve(held)
    held = batch = None
    give_back()


def hot_windows(hot: DataFrame) -> DataFrame:
    """Repeated windows of spans whose hash has too many of them, by counting digests of all their windows."""

    def make():
        from xxhash import xxh3_128_digest

        def work(part):
            rows: dict[str, list] = {"d": [], "key": [], "a": []}
            for key, place, span in zip(part.column("key").to_pylist(), part.column("place").to_pylist(), part.column("span").to_pylist(), strict=True):
                for i in range(len(span) - LENGTH + 1):
                    rows["d"].append(xxh3_128_digest(span[i : i + LENGTH]))
                    rows["key"].append(key)
                    rows["a"].append((place >> 16) + i)
            return rows

        return work

    rows = map_slices(hot.select("key", "place", "span"), "span", make, "d binary, key long, a long", 1 << 18)
    many = rows.groupBy("d").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("d")
    return rows.join(many, "d").select("key", "a", F.col("a").alias("b"))


def repeated(keyed: DataFrame) -> DataFrame:
    """(key, a, b): starts a to b of a text are repeated windows."""
    marked = cut(classed(seed_table(keyed)))
    whole = marked.filter("whole").select("key", F.shiftright("place", 16).alias("a"), (F.shiftright("place", 16) + F.shiftright("place", 8).bitwiseAND(255)).alias("b"))
    asked = marked.filter("ask").select("key", "h", "place", "hot")
    fetched = spans(keyed, asked)
    hot = asked.filter("hot")
    if hot.isEmpty():
        return whole.unionByName(fetched.drop("hot").repartition("h").sortWithinPartitions("h").mapInArrow(sort_shards, "key long, a long, b long"))
    fetched = cut(fetched)
    some = fetched.filter("NOT hot").drop("hot").repartition("h").sortWithinPartitions("h").mapInArrow(sort_shards, "key long, a long, b long")
    return whole.unionByName(some).unionByName(hot_windows(fetched.filter("hot")))


def removed_runs(parts: list[dict] | None) -> list[tuple[int, int]]:
    """Maximal runs of removed bytes from intervals of window starts."""
    out: list[tuple[int, int]] = []
    for a, b in sorted((x["a"], x["b"] + LENGTH) for x in parts or ()):
        if out and a <= out[-1][1]:
            if b > out[-1][1]:
                out[-1] = (out[-1][0], b)
        else:
            out.append((a, b))
    return out


def kept(body: bytes, runs: list[tuple[int, int]]) -> bytes:
    ends = [0, *(b for _, b in runs)]
    starts = [*(a for a, _ in runs), len(body)]
    return b"".join(body[a:b] for a, b in zip(ends, starts, strict=True))


def characters(body: bytes, runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The runs without characters that they cover in part."""
    out = []
    for a, b in runs:
        while a < b and body[a] & 0xC0 == 0x80:
            a += 1
        while b > a and b < len(body) and body[b] & 0xC0 == 0x80:
            b -= 1
        if a < b:
            out.append((a, b))
    return out


def strip(documents: DataFrame, with_text: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and the digest of what is left, and the columns named in ``keep``.

    with_text: also that text; characters that a run covers in part stay whole.
    """
    keyed = _keyed(documents, *keep)
    lists = repeated(keyed).groupBy("key").agg(F.collect_list(F.struct("a", "b")).alias("parts"))
    joined = packed_bodies(keyed).join(lists, "key", "left").select("doc_id", *keep, "z", "parts")
    kinds = dict(documents.dtypes)
    schema = "".join(f"{c} {kinds[c]}, " for c in ("doc_id", *keep)) + "n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", text string" * with_text

    def make():
        import zstandard

        inflate = zstandard.ZstdDecompressor()

        def work(part):
            out: dict[str, list] = {k: [] for k in ("n_bytes", "n_removed", "n_spans", "kept_sha256", "text")}
            for z, parts in zip(part.column("z").to_pylist(), part.column("parts").to_pylist(), strict=True):
                body = inflate.decompress(z)
                runs = removed_runs(parts)
                rest = kept(body, runs)
                text = kept(body, characters(body, runs)).decode() if with_text else None
                for k, v in zip(out, (len(body), len(body) - len(rest), len(runs), hashlib.sha256(rest).hexdigest(), text), strict=True):
                    out[k].append(v)
            return out | {c: part.column(c) for c in ("doc_id", *keep)}

        return work

    return map_slices(joined, "z", make, schema, 1 << 20)
