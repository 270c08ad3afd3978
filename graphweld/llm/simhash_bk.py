"""SimHash near-duplicates with BK-trees over shards of fingerprints.

Fingerprints are 64 majority bits over the XXH64 of word shingles. Two of them
that differ in at most ``radius`` bits agree on at least ``blocks - radius`` of
``blocks`` bit blocks, so every choice of that many blocks is a table whose key
is the bits of those blocks, and each pair of near fingerprints shares a key in
some table. The distinct fingerprints under one key are a shard. Each shard gets a
BK-tree (children keyed by their Hamming distance to the parent); a search
follows only the edges within the radius. Shards stay where the shuffle put
them instead of being broadcast, as their number grows with the data.

A shard emits a spanning forest of its links, never all pairs. A shard of over
``SHARD`` fingerprints is cut into chunks, and each pair of chunks is a task of
its own. Components follow from the links by star contraction.

``cluster`` finds exactly the pairs within 4 bits. ``near_groups`` links exactly
the texts whose sets of word shingles have a Jaccard similarity of 0.8 or more
(shingles are compared by 64-bit hashes). Candidates come from two searches:
fingerprints of 128 bits within a radius of 28, under keys of 16 bits or more in which
the least sure bit is tried both ways, find most links cheaply, also in large
groups; a prefix join finds what they miss. In any one order of all shingles,
two sets that similar share one of their first ``n - ceil(0.8 n) + 1``; the
order puts shingles that are frequent in a sample last, which only changes
cost. Its postings first propose stars, then all pairs that are not connected
yet. A candidate whose counts of shingles by hash class rule the similarity out
is dropped (the sum of the smaller counts bounds the overlap); every other one
is verified on the full sets, so nothing is linked below the threshold and no
link that components need is missed. Keys grow with the number of texts, so
that a key holds a few texts at any size.

Defined results: a null or empty text has fingerprint zero and is linked like
any other; equal texts, repeated rows included, share fingerprint and
component; a single row is its own component; no rows give no rows. In
``near_groups`` a component's id is its smallest doc_id that is not null, and
null only if all are null; ``one_of_each`` keeps one row of such a component too.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweld.llm.common import cut, map_slices, stored
from graphweld.llm.components import components

BITS, RADIUS, SHINGLE, SEED = 64, 4, 4, 42
#: Fingerprints that one task holds of one shard.
SHARD = 4096
#: Tasks among which the fingerprints of one component are dealt to learn its smallest doc_id.
CELLS = 16
#: Up to this many in a tree are searched one by one, more of them together.
SMALL = 24


def fingerprint(text: bytes, shingle: int = SHINGLE) -> int:
    from xxhash import xxh64_intdigest

    words = text.lower().split()
    if not words:
        return 0
    flat = b" ".join(words)
    if len(words) <= shingle:
        return xxh64_intdigest(flat, SEED)
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = np.concatenate(([0], ends[:-shingle])).tolist()
    hashes = np.fromiter((xxh64_intdigest(flat[a:b], SEED) for a, b in zip(starts, (ends[shingle - 1 :] - 1).tolist(), strict=True)), np.uint64, len(starts))
    ones = np.zeros(BITS, np.int64)
    for k in range(0, len(hashes), 1 << 14):
        part = hashes[k : k + (1 << 14)]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(documents: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id and fp, the fingerprint as a signed 64-bit number."""

    def make():
        def work(part):
            fp = np.fromiter((fingerprint(x or b"", shingle) for x in part.column("body").to_pylist()), np.uint64, len(part))
            return {"doc_id": part.column("doc_id"), "fp": fp.view(np.int64)}

        return work

    kind = dict(documents.dtypes)["doc_id"]
    return map_slices(documents.select("doc_id", F.col("text").cast("binary").alias("body")), "body", make, f"doc_id {kind}, fp long")


class Tree:
    """BK-tree of distinct integers under the Hamming distance."""

    def __init__(self) -> None:
        self.values: list[int] = []
        self.children: list[dict[int, int]] = []

    def add(self, value: int) -> None:
        self.values.append(value)
        self.children.append({})
        at, new = 0, len(self.values) - 1
        while at != new:
            at = self.children[at].setdefault((value ^ self.values[at]).bit_count(), new)

    def near(self, value: int, radius: int) -> list[int]:
        """Places of all values within the radius."""
        found, stack = [], [0] if self.values else []
        while stack:
            at = stack.pop()
            d = (value ^ self.values[at]).bit_count()
            if d <= radius:
                found.append(at)
            for k, child in self.children[at].items():
                if d - radius <= k <= d + radius:
                    stack.append(child)
        return found


class Forest:
    """Groups of places; keeps one link for each union."""

    def __init__(self, n: int) -> None:
        self.group = np.arange(n)
        self.links: list[tuple[int, int]] = []

    def join(self, at: int, others: np.ndarray) -> None:
        mine = self.group[at]
        groups, first = np.unique(self.group[others], return_index=True)
        fresh = groups != mine
        if fresh.any():
            self.links += [(at, int(others[k])) for k in first[fresh]]
            self.group[np.isin(self.group, groups)] = mine


def links_small(values: list[int], radius: int) -> list[tuple[int, int]]:
    """Places linked, as a spanning forest; one search a value."""
    tree, parent, found = Tree(), list(range(len(values))), []

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = x = parent[parent[x]]
        return x

    for i, v in enumerate(values):
        for k in tree.near(v, radius):
            if root(k) != root(i):
                parent[root(k)] = root(i)
                found.append((i, k))
        tree.add(v)
    return found


def _bits(words: list[np.ndarray], places: np.ndarray, pivot: int) -> np.ndarray:
    """Hamming distances of ``places`` to ``pivot`` over all words."""
    return sum(np.bitwise_count(w[places] ^ w[pivot]).astype(np.int64) for w in words)


def links_large(words: list[np.ndarray], tree: np.ndarray, asking: np.ndarray, radius: int, forest: Forest | None = None) -> list[tuple[int, int]]:
    """As links_small for places ``asking`` against a tree of places ``tree``; all questions go down the tree together.

    Where a whole subtree is in one group, its members have nothing to ask any
    more, so a dense group is linear work. forest: links that are known.
    """
    forest = Forest(len(words[0])) if forest is None else forest
    stack = [(tree, asking)]
    while stack:
        own, asked = stack.pop()
        group = forest.group[own]
        if (group == group[0]).all():
            asked = asked[forest.group[asked] != group[0]]
            if not len(asked):
                continue
        pivot, rest = own[0], own[1:]
        d = _bits(words, asked, pivot)
        near = asked[d <= radius]
        if len(near):
            forest.join(int(pivot), near)
        if len(rest):
            edge = _bits(words, rest, pivot)
            order = np.argsort(edge, kind="stable")
            keys, at = np.unique(edge[order], return_index=True)
            for k, child in zip(keys.tolist(), np.split(rest[order], at[1:]), strict=True):
                follow = asked[np.abs(d - k) <= radius]
                if len(follow):
                    stack.append((child, follow))
    return forest.links


def links_of(words: list[np.ndarray], radius: int) -> list[tuple[int, int]]:
    n = len(words[0])
    if n <= SMALL:
        values = words[0].tolist()
        for w in words[1:]:
            values = [v << BITS | x for v, x in zip(values, w.tolist(), strict=True)]
        return links_small(values, radius)
    every = np.arange(n)
    return links_large(words, every, every, radius)


LINK = pa.schema([("t", pa.int32()), ("key", pa.int64()), ("a", pa.int64()), ("b", pa.int64())])


def search_shards(radius: int, shard: int, words: int = 0):
    """mapInArrow over rows (t, key, id, words ...) sorted by t and key: links (a, b) of each shard, or (id, null) for the members of a too large one.

    words: how many columns hold the fingerprint; 0 if the id itself is it.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        held: list[np.ndarray] | None = None  # the open shard, unless it is known to be too large
        mark = None  # of the open shard
        large = False

        def close() -> None:
            if held is not None and len(held[2]) > 1:
                solve([held])

        def whole(columns: list[np.ndarray]) -> None:
            n = len(columns[2])
            out.append((columns[0], columns[1], columns[2], np.zeros(n, np.int64), np.ones(n, bool)))

        def solve(shards: list[list[np.ndarray]]) -> None:
            for columns in shards:
                if len(columns[2]) > shard:
                    whole(columns)
                    continue
                fingerprint = [c.view(np.uint64) for c in columns[3:]] if words else [columns[2].view(np.uint64)]
                pairs = links_of(fingerprint, radius)
                if pairs:
                    p = np.array(pairs)
                    n = len(p)
                    out.append((np.full(n, columns[0][0], np.int32), np.full(n, columns[1][0]), columns[2][p[:, 0]], columns[2][p[:, 1]], np.zeros(n, bool)))

        def flush() -> Iterator[pa.RecordBatch]:
            if out:
                t, key, a, b, null = (np.concatenate(c) for c in zip(*out, strict=True))
                out.clear()
                yield pa.RecordBatch.from_arrays([pa.array(t, pa.int32()), pa.array(key, pa.int64()), pa.array(a, pa.int64()), pa.array(b, pa.int64(), mask=null)], schema=LINK)

        for batch in batches:
            if not len(batch):
                continue
            columns = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(3 + words)]
            t, key = columns[:2]
            bounds = [0, *(np.flatnonzero((t[1:] != t[:-1]) | (key[1:] != key[:-1])) + 1).tolist(), len(t)]
            for a, b in zip(bounds[:-1], bounds[1:], strict=True):
                last = b == len(t)
                now = (int(t[a]), int(key[a]))
                if now != mark:
                    close()
                    held, mark, large = None, now, False
                    if b - a == 1 and not last:
                        continue
                elif large:
                    whole([c[a:b] for c in columns])
                    continue
                part = [c[a:b] for c in columns]
                held = part if held is None else [np.concatenate(x) for x in zip(held, part, strict=True)]
                if not last:
                    close()
                    held = None
                elif len(held[2]) > shard:
                    whole(held)
                    held, large = None, True
            yield from flush()
        close()
        yield from flush()

    return run


def masks(blocks: int, radius: int) -> list[int]:
    edges = [round(BITS * k / blocks) for k in range(blocks + 1)]
    bits = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(edges, edges[1:], strict=False)]
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    return [signed(sum(c)) for c in combinations(bits, blocks - radius)]


def blocks_for(n: int) -> int:
    """Bit blocks that keep a shard of unrelated fingerprints at a few entries; 6 up to 32 million fingerprints."""
    return 6 if n < 1 << 25 else 7 if n < 1 << 31 else 8


def near_links(distinct: DataFrame, radius: int = RADIUS, shard: int = SHARD, blocks: int | None = None) -> DataFrame:
    """(a, b): links between distinct fingerprints ``fp`` that connect all that are within the radius."""
    blocks = blocks or max(radius + 1, blocks_for(distinct.count()))
    keys = F.array(*[F.struct(F.lit(i).alias("t"), F.col("fp").bitwiseAND(F.lit(m).cast("long")).alias("key")) for i, m in enumerate(masks(blocks, radius))])
    rows = distinct.select("fp", F.explode(keys).alias("k")).select("k.t", "k.key", F.col("fp").alias("id"))
    return shard_links(rows, radius, shard)


def shard_links(rows: DataFrame, radius: int, shard: int, words: DataFrame | None = None) -> DataFrame:
    """(a, b): links from all shards. rows: t, key, id and the words of the fingerprint, if these aren't the id; words: these by id."""
    names = [] if words is None else [c for c in words.columns if c != "id"]
    dealt = rows.repartition("t", "key").sortWithinPartitions("t", "key", "id")
    found = cut(dealt.mapInArrow(search_shards(radius, shard, len(names)), "t int, key long, a long, b long"))
    links = found.filter("b IS NOT NULL").select("a", "b").distinct()
    hot = found.filter("b IS NULL").select("t", "key", F.col("a").alias("id"))
    if hot.isEmpty():
        return links
    return links.unionByName(hot_links(hot if words is None else hot.join(words, "id"), radius, shard, names or ["id"]))


def hot_links(hot: DataFrame, radius: int, shard: int, names: list[str]) -> DataFrame:
    """Links within shards larger than a task may hold: one task for each pair of their chunks."""
    chunks = hot.groupBy("t", "key").agg(F.ceil(2 * F.count(F.lit(1)) / shard).cast("int").alias("n"))
    cells = hot.join(chunks, ["t", "key"]).withColumn("c", F.pmod(F.xxhash64("id"), F.col("n")).cast("int"))
    cells = cells.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    cells = cells.select("t", "key", F.least("c", "o").alias("i"), F.greatest("c", "o").alias("j"), "c", *dict.fromkeys(["id", *names]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def solve(rows: list[pa.RecordBatch]) -> pa.RecordBatch:
            table = pa.Table.from_batches(rows)
            i, c = table.column("i").to_numpy(), table.column("c").to_numpy()
            ids = table.column("id").to_numpy()
            values = [table.column(c).to_numpy().view(np.uint64) for c in names]
            tree = np.flatnonzero(c == i[0])
            other = np.flatnonzero(c == table.column("j").to_numpy())
            forest = Forest(len(ids))
            for chunk in (tree, other) if i[0] != table.column("j").to_numpy()[0] else ():
                if len(chunk):
                    links_large(values, chunk, chunk, radius, forest)
            forest.links.clear()  # the tasks of the single chunks give these
            pairs = links_large(values, tree, other, radius, forest) if len(tree) and len(other) else []
            p = np.array(pairs, np.int64).reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array(ids[p[:, 0]]), pa.array(ids[p[:, 1]])], names=["a", "b"])

        held: list[pa.RecordBatch] = []
        mark = None
        for batch in batches:
            cols = [batch.column(k).to_numpy() for k in range(4)]
            change = np.flatnonzero(np.any([x[1:] != x[:-1] for x in cols], axis=0)) + 1
            for a, b in zip([0, *change.tolist()], [*change.tolist(), len(batch)], strict=True):
                now = tuple(int(x[a]) for x in cols) if b > a else mark
                if held and now != mark:
                    yield solve(held)
                    held = []
                mark = now
                held.append(batch.slice(a, b - a))
        if held:
            yield solve(held)

    dealt = cells.repartition("t", "key", "i", "j").sortWithinPartitions("t", "key", "i", "j")
    return dealt.mapInArrow(run, "a long, b long").distinct()


def cluster(documents: DataFrame, radius: int = RADIUS, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fingerprint (hexadecimal), component_id and the number of rows with the same fingerprint."""
    marked = cut(fingerprints(documents, shingle))
    distinct = marked.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("copies"))
    labels = components(near_links(distinct.select("fp"), radius))
    named = distinct.join(labels.withColumnRenamed("node", "fp"), "fp", "left")
    named = named.select("fp", "first", "copies", F.coalesce("label", "fp").alias("label"), F.col("label").isNotNull().alias("linked"), F.pmod(F.xxhash64("fp"), F.lit(CELLS)).alias("cell"))
    least = named.filter("linked").groupBy("label", "cell").agg(F.min("first").alias("m")).groupBy("label").agg(F.min("m").alias("m"))
    least = least.withColumn("cell", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(CELLS - 1).cast("long"))))
    named = named.join(least, ["label", "cell"], "left").select("fp", F.coalesce("m", "first").alias("component_id"), "copies")
    return marked.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "copies")


# ---------------------------------------------------------------- exact similarity join of shingle sets

#: Shingle words, bits that may differ of 128 (a similarity of 0.8 differs in 18 on average), least key bits, and how many of the least sure bits of a key are tried both ways.
WIDE_SHINGLE, WIDE_RADIUS, KEY_BITS, UNSURE = 5, 28, 16, 1
#: Hash classes in which a set's shingles are counted, a power of two. Two sets of 300 shingles at a similarity of 0.75 share about 4 places by chance in 512.
CLASSES = 512
#: The least similarity, as a fraction.
NUM, DEN = 4, 5
#: Texts sampled for the order of shingles, and how many shingles it ranks.
SAMPLE, RANKED = 2_000, 1 << 17
#: Candidates' ids up to this number are broadcast to find their texts.
BROADCAST_IDS = 2_000_000


def shingle_hashes(text: bytes, shingle: int = WIDE_SHINGLE) -> np.ndarray:
    """128-bit hashes of all word shingles, a row of 16 bytes each; a text of up to ``shingle`` words is one shingle."""
    from xxhash import xxh3_128_digest

    words = text.lower().split()
    flat = b" ".join(words)
    if len(words) <= shingle:
        parts = [flat]
    else:
        ends = np.cumsum([len(w) + 1 for w in words])
        parts = [flat[a:b] for a, b in zip(np.concatenate(([0], ends[:-shingle])).tolist(), (ends[shingle - 1 :] - 1).tolist(), strict=True)]
    return np.frombuffer(b"".join(map(xxh3_128_digest, parts)), np.uint8).reshape(-1, 16)


def shingle_set(raw: np.ndarray) -> np.ndarray:
    """Distinct 64-bit hashes in order."""
    return np.unique(raw.view(np.int64)[:, 0])


def set_key(own: np.ndarray) -> tuple[int, int]:
    """128 bits that name a set."""
    from xxhash import xxh3_128_digest

    return tuple(np.frombuffer(xxh3_128_digest(own.tobytes()), np.int64).tolist())


def key_bits(texts: int) -> int:
    """Bits of a key that leave some 32 unrelated texts under one; a search under longer keys finds fewer of the links, the prefix join finds the rest."""
    return min(42, max(KEY_BITS, texts.bit_length() + UNSURE - 5))


def class_counts(own: np.ndarray) -> bytes:
    """How many shingles of a set are in each hash class, a byte each, 255 for that many and more."""
    return np.minimum(np.bincount((own.view(np.uint64) >> np.uint64(65 - CLASSES.bit_length())).astype(np.int64), minlength=CLASSES), 255).astype(np.uint8).tobytes()


def wide_fingerprint(raw: np.ndarray, width: int = KEY_BITS) -> tuple[int, int, list[int]]:
    """(high word, low word, keys): 128 majority bits over shingle hashes, ties by the exclusive or of all hashes.

    keys: of each ``width`` bits, these with all choices for the ``UNSURE``
    bits whose majority was the closest. Near texts differ in such bits, so
    they meet under one of the keys.
    """
    ones, n, odd = np.zeros(128, np.int64), len(raw), np.bitwise_xor.reduce(raw, axis=0)
    for k in range(0, n, 1 << 13):
        ones += np.unpackbits(raw[k : k + (1 << 13)], axis=1).sum(0, dtype=np.int64)
    lead = 2 * ones - n
    bits = (lead > 0) | ((lead == 0) & np.unpackbits(odd).astype(bool))
    high, low = np.packbits(bits).view(">u8").tolist()
    used = len(bits) // width * width
    base = bits[:used].reshape(-1, width) @ (1 << np.arange(width))
    close = np.argsort(np.abs(lead[:used]).reshape(-1, width), axis=1, kind="stable")[:, :UNSURE]
    keys = base[:, None]
    for i in range(UNSURE):
        keys = np.hstack([keys, keys ^ (1 << close[:, i : i + 1])])
    return high, low, keys.ravel().tolist()


def prefix(own: np.ndarray, ranked: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The first shingles of a set, one of which a similar set shares: unranked ones by hash, then ranked ones by count."""
    n = len(own)
    if len(ranked):
        at = np.minimum(np.searchsorted(ranked, own), len(ranked) - 1)
        known = ranked[at] == own
        last, c = own[known], counts[at[known]]
        own = np.concatenate([own[~known], last[np.lexsort((last, c))]])
    return own[: n + (-NUM * n) // DEN + 1]


def ranks(documents: DataFrame, shingle: int, total: int) -> tuple[np.ndarray, np.ndarray]:
    """(shingles by hash, how many sampled texts hold each): the most frequent of a sample of bounded size."""
    step = max(1, total // SAMPLE)

    def make():
        def work(part):
            return {"s": np.concatenate([shingle_set(shingle_hashes(x or b"", shingle)) for x in part.column("body").to_pylist()])}

        return work

    some = documents.filter(F.pmod(F.xxhash64("text"), F.lit(step)) == 0).select(F.col("text").cast("binary").alias("body"))
    rows = map_slices(some, "body", make, "s long").groupBy("s").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    found = sorted((r.s, r.n) for r in rows.orderBy(F.desc("n"), "s").limit(RANKED).collect())
    return np.array([x[0] for x in found], np.int64), np.array([x[1] for x in found], np.int64)


def marks(documents: DataFrame, shingle: int) -> DataFrame:
    """doc_id, x (hash of the text), the key k1, k2 of the shingle set, its size n, prefix and class counts, and the wide fingerprint of every row."""
    total = documents.count()
    ranked, counts = ranks(documents, shingle, total)
    width = key_bits(total)

    def make():
        def work(part):
            out: dict[str, list] = {c: [] for c in ("k1", "k2", "n", "prefix", "classes", "hi", "lo", "keys")}
            for text in part.column("body").to_pylist():
                raw = shingle_hashes(text or b"", shingle)
                own = shingle_set(raw)
                high, low, keys = wide_fingerprint(raw, width)
                for c, v in zip(out, (*set_key(own), len(own), prefix(own, ranked, counts), class_counts(own), high, low, keys), strict=True):
                    out[c].append(v)
            for c in ("hi", "lo"):
                out[c] = np.array(out[c], np.uint64).view(np.int64)
            return out | {"doc_id": part.column("doc_id"), "x": part.column("x")}

        return work

    kind = dict(documents.dtypes)["doc_id"]
    source = documents.select("doc_id", F.xxhash64("text").alias("x"), F.col("text").cast("binary").alias("body"))
    return map_slices(source, "body", make, f"doc_id {kind}, x long, k1 long, k2 long, n int, prefix array<long>, classes binary, hi long, lo long, keys array<long>")


def may_reach(n: np.ndarray, p: np.ndarray, n2: np.ndarray, p2: np.ndarray) -> np.ndarray:
    """Can sets of n and n2 shingles that share the one at p and p2 be similar enough? By sizes and places."""
    most = np.minimum(p, p2) + 1 + np.minimum(n - p - 1, n2 - p2 - 1)
    return (DEN * np.minimum(n, n2) >= NUM * np.maximum(n, n2)) & ((NUM + DEN) * most >= NUM * (n + n2))


POSTING = pa.schema([("s", pa.int64()), ("a", pa.int64()), ("b", pa.int64()), ("n", pa.int32()), ("p", pa.int32())])


def search_postings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (s, n, p, id) sorted by s, n, id: stars of each posting as (null, a, b), and the members of postings of three and more as (s, id, null, n, p)."""
    out: list[tuple] = []
    mark, seen, held, pivot = None, 0, [], None  # of the open posting: shingle, rows so far, rows not given out, last pivot

    def rows(s: int, part: list[np.ndarray]) -> None:
        k = len(part[0])
        out.append((np.full(k, s), part[2], np.zeros(k, np.int64), part[0], part[1], np.zeros(k, bool)))

    for batch in batches:
        if not len(batch):
            continue
        s, n, p, ids = (batch.column(k).to_numpy() for k in range(4))
        bounds = [0, *(np.flatnonzero(s[1:] != s[:-1]) + 1).tolist(), len(s)]
        for a, b in zip(bounds[:-1], bounds[1:], strict=True):
            now = int(s[a])
            if now != mark:
                mark, seen, held, pivot = now, 0, [], None
                if b - a == 1 and b < len(s):
                    continue
            part = [n[a:b].astype(np.int64), p[a:b].astype(np.int64), ids[a:b]]
            seen += b - a
            if seen < 3:
                held.append(part)
            else:
                for x in (*held, part):
                    rows(now, x)
                held = []
            at = 0
            while at < b - a:
                first = at
                if pivot is None or DEN * pivot[0] < NUM * part[0][at]:
                    pivot, first = tuple(int(c[at]) for c in part), at + 1
                end = int(np.searchsorted(part[0], pivot[0] * DEN // NUM, "right"))
                pn, pp, pid = (c[first:end] for c in part)
                ok = may_reach(np.int64(pivot[0]), np.int64(pivot[1]), pn, pp) if end > first else np.zeros(0, bool)
                if ok.any():
                    k = int(ok.sum())
                    out.append((np.zeros(k, np.int64), np.full(k, pivot[2]), pid[ok], np.zeros(k, np.int64), np.zeros(k, np.int64), np.ones(k, bool)))
                at = max(end, first)
        if out:
            shingle, left, right, size, place, pair = (np.concatenate(c) for c in zip(*out, strict=True))
            out.clear()
            yield pa.RecordBatch.from_arrays([pa.array(shingle, pa.int64(), mask=pair), pa.array(left, pa.int64()), pa.array(right, pa.int64(), mask=~pair), pa.array(size.astype(np.int32)), pa.array(place.astype(np.int32))], schema=POSTING)


def overlap_bound(n: np.ndarray, x: np.ndarray, m: np.ndarray, y: np.ndarray) -> np.ndarray:
    """May sets of n and m shingles with class counts x and y be similar enough? The smaller counts add up to the overlap at most."""
    size = np.minimum(n, m)
    least = np.minimum(x, y)
    most = least.sum(1, dtype=np.int64)
    most[(least == 255).any(1)] = np.iinfo(np.int32).max  # counts that were cut off bound nothing
    return (NUM + DEN) * np.minimum(most, size) >= NUM * (n + m)


def open_pairs(members: DataFrame, labels: DataFrame, classes: DataFrame, shard: int) -> DataFrame:
    """(a, b): all pairs under a shingle that have different labels and may be similar, by sizes, places and class counts; one task for each pair of chunks of a large posting. classes: id, classes."""
    named = members.join(labels.withColumnRenamed("node", "id"), "id", "left").withColumn("label", F.coalesce("label", "id"))
    sizes = named.groupBy("s").agg(F.ceil(F.count(F.lit(1)) / shard).cast("int").alias("m"), F.min("label").alias("l1"), F.max("label").alias("l2")).filter("l1 < l2")
    cells = named.join(sizes.select("s", "m"), "s").join(classes, "id").withColumn("c", F.pmod(F.xxhash64("id"), F.col("m")).cast("int"))
    cells = cells.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("m") - 1)))
    cells = cells.select("s", F.least("c", "o").alias("i"), F.greatest("c", "o").alias("j"), "c", "id", "label", "n", "p", "classes")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def solve(parts: list[list[np.ndarray]]) -> Iterator[pa.RecordBatch]:
            _, i, j, c, ids, label, n, p, counts = (np.concatenate(x) for x in zip(*parts, strict=True))
            if (label == label[0]).all():
                return
            n, p = n.astype(np.int64), p.astype(np.int64)
            left, right = np.flatnonzero(c == i), np.flatnonzero(c == j)
            for k in left.tolist():
                other = right[(label[right] != label[k]) & may_reach(n[k], p[k], n[right], p[right])]
                if i[0] == j[0]:
                    other = other[other > k]
                if len(other):
                    other = other[overlap_bound(np.full(len(other), n[k]), counts[k], n[other], counts[other])]
                if len(other):
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(ids[k], ids[other])), pa.array(np.maximum(ids[k], ids[other]))], names=["a", "b"])

        held: list[list[np.ndarray]] = []
        mark = None
        for batch in batches:
            cols = [batch.column(k).to_numpy() for k in range(8)]
            cols.append(np.frombuffer(b"".join(batch.column(8).to_pylist()), np.uint8).reshape(-1, CLASSES))
            change = np.flatnonzero(np.any([x[1:] != x[:-1] for x in cols[:3]], axis=0)) + 1
            for a, b in zip([0, *change.tolist()], [*change.tolist(), len(batch)], strict=True):
                if a == b:
                    continue
                now = tuple(int(x[a]) for x in cols[:3])
                if held and now != mark:
                    yield from solve(held)
                    held = []
                mark = now
                held.append([x[a:b] for x in cols])
        if held:
            yield from solve(held)

    return cells.repartition("s", "i", "j").sortWithinPartitions("s", "i", "j").mapInArrow(run, "a long, b long").distinct()


def within_reach(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """The pairs (a, b) whose class counts leave room for the similarity; none that has it is lost."""
    side = lambda c: nodes.select(F.col("id").alias(c), F.col("n").alias(f"n_{c}"), F.col("classes").alias(f"classes_{c}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, m = (batch.column(c).to_numpy().astype(np.int64) for c in ("n_a", "n_b"))
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, CLASSES) for c in ("classes_a", "classes_b"))
            yield batch.select(["a", "b"]).filter(pa.array(overlap_bound(n, x, m, y)))

    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "n_a", "n_b", "classes_a", "classes_b").mapInArrow(run, "a long, b long")


def verified(documents: DataFrame, nodes: DataFrame, pairs: DataFrame, shingle: int) -> DataFrame:
    """The pairs (a, b) of nodes (id, first, x, n, classes) whose shingle sets are similar enough.

    Compressed texts travel, as they are smaller than their sets, and only
    those of candidates; all texts are shuffled only if the candidates are more
    than ``BROADCAST_IDS``.
    """

    def deflated():
        import zstandard

        deflate = zstandard.ZstdCompressor(level=3)
        return lambda part: {"id": part.column("id"), "z": [deflate.compress(x or b"") for x in part.column("body").to_pylist()]}

    def make():
        import zstandard

        inflate = zstandard.ZstdDecompressor()
        last: list = [None, None]

        def own(z):
            return shingle_set(shingle_hashes(inflate.decompress(z), shingle))

        def work(part):
            good = []
            for x, y in zip(part.column("z_a").to_pylist(), part.column("z_b").to_pylist(), strict=True):
                if last[0] != y:
                    last[:] = y, own(y)
                mine, other = own(x), last[1]
                shared = len(np.intersect1d(mine, other, assume_unique=True))
                good.append((NUM + DEN) * shared >= NUM * (len(mine) + len(other)))
            kept = part.filter(pa.array(good, pa.bool_()))
            return {"a": kept.column("a"), "b": kept.column("b")}

        return work

    pairs = stored(within_reach(nodes, pairs))
    asked = stored(nodes.join(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "id", "left_semi").select("id", "first", F.col("x").alias("_x")))
    few = F.broadcast(asked) if asked.count() <= BROADCAST_IDS else asked
    rows = documents.select("doc_id", F.xxhash64("text").alias("x"), F.col("text").cast("binary").alias("body"))
    rows = rows.join(few, F.col("doc_id").eqNullSafe(F.col("first")) & (F.col("x") == F.col("_x"))).select("id", "body")
    texts = map_slices(rows, "body", deflated, "id long, z binary").dropDuplicates(["id"])  # repeated rows have one text
    both = pairs.join(texts.select(F.col("id").alias("a"), F.col("z").alias("z_a")), "a").join(texts.select(F.col("id").alias("b"), F.col("z").alias("z_b")), "b")
    return cut(map_slices(both.select("a", "b", "z_a", "z_b"), "z_a", make, "a long, b long", 1 << 20))


def _grouped(documents: DataFrame, shingle: int, radius: int, shard: int) -> DataFrame:
    """doc_id, x and component (a node's number) of every row."""
    documents = documents.select("doc_id", "text")
    marked = stored(marks(documents, shingle))
    same = [F.first(c).alias(c) for c in ("n", "prefix", "classes", "hi", "lo", "keys")]
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "x")).alias("m")
    nodes = marked.groupBy("k1", "k2").agg(first, *same).withColumn("id", F.monotonically_increasing_id())
    nodes = stored(nodes.select("id", "k1", "k2", F.col("m.doc_id").alias("first"), F.col("m.x").alias("x"), "n", "prefix", "classes", "hi", "lo", "keys"))
    few = nodes.select("id", "first", "x", "n", "classes")

    rows = nodes.select("id", "hi", "lo", F.posexplode("keys").alias("t", "key"))
    rows = rows.select(F.expr(f"t div {1 << UNSURE}").cast("int").alias("t"), "key", "id", "hi", "lo")
    near = shard_links(rows, radius, shard, nodes.select("id", "hi", "lo"))

    postings = nodes.select("n", F.posexplode("prefix").alias("p", "s"), "id").select("s", "n", "p", "id")
    found = stored(postings.repartition("s").sortWithinPartitions("s", "n", "id").mapInArrow(search_postings, "s long, a long, b long, n int, p int"))
    pairs = near.unionByName(found.filter("s IS NULL").select("a", "b")).filter("a <> b")
    pairs = stored(pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    links = verified(documents, few, pairs, shingle)
    labels = components(links)

    members = found.filter("s IS NOT NULL").select("s", F.col("a").alias("id"), "n", "p")
    rest = stored(open_pairs(members, labels, nodes.select("id", "classes"), shard).join(pairs, ["a", "b"], "left_anti"))
    if not rest.isEmpty():
        labels = components(links.unionByName(verified(documents, few, rest, shingle)))
    named = nodes.select("k1", "k2", "id").join(labels.withColumnRenamed("node", "id"), "id", "left")
    named = named.select("k1", "k2", F.coalesce("label", "id").alias("component"))
    return marked.select("doc_id", "x", "k1", "k2").join(named, ["k1", "k2"]).select("doc_id", "x", "component")


def near_groups(documents: DataFrame, shingle: int = WIDE_SHINGLE, radius: int = WIDE_RADIUS, shard: int = SHARD) -> DataFrame:
    """doc_id and component_id (smallest doc_id reachable) over all links of texts with a similarity of 0.8 and more."""
    rows = cut(_grouped(documents, shingle, radius, shard))
    least = rows.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    return rows.join(least, "component").select("doc_id", "component_id")


def one_of_each(documents: DataFrame, shingle: int = WIDE_SHINGLE, radius: int = WIDE_RADIUS) -> DataFrame:
    """The document with the smallest id of each group of near texts, with all its columns; null ids come last, repeated rows stay once."""
    rows = _grouped(documents, shingle, radius, SHARD)
    first = rows.groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "x")).alias("m"))
    first = first.select(F.col("m.doc_id").alias("_doc"), F.col("m.x").alias("_x")).distinct()
    names = documents.columns
    kept = documents.withColumn("_text", F.xxhash64("text")).join(first, F.col("doc_id").eqNullSafe(F.col("_doc")) & (F.col("_text") == F.col("_x")), "left_semi")
    return kept.dropDuplicates(["doc_id", "_text"]).select(*names)
