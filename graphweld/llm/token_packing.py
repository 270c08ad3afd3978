"""Best-fit packing of tokenized documents by linear grouping.

Documents are tokenized, closed by id 0, cut into pieces of ``CAPACITY`` tokens
at most, and the pieces are packed into as few sequences as possible.

The plan is made on the histogram of piece lengths, which has at most
``CAPACITY`` entries however many documents there are:

1. lengths of at least ``capacity / 16`` are large; sorted downwards they are
   cut into groups of about equal cardinality, and every length counts as the
   largest of its group (linear grouping);
2. configurations over these few sizes are searched for the best fill (bounded
   knapsack by dynamic programming, starting from the largest size that is
   left) and used as often as the groups allow;
3. actual lengths are substituted group by group, downwards, which leaves a
   true gap in each sequence;
4. the gaps are filled best-fit with the small lengths, downwards; what is
   left opens new sequences.

Sequences of equal composition are one row with a count throughout. Documents
then find their place by their rank within their length: the ranks come from
two-level prefix sums, so a length shared by a third of all pieces is no hot
task, and the plan is a small table of rank intervals. No text is shuffled.

Defined results: a null text is an empty one and gives one piece of length 1;
an empty table gives no rows; equal rows get places of their own.
"""

from __future__ import annotations

import bisect
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweld.llm.common import cut, map_slices, prefix_sums, spread

CAPACITY, CLOSE = 2048, 0
#: Words that a task keeps with their ids.
MEMORY = 400_000


class Memory(dict):
    """Words with their ids. A class made for each encoder would be a cycle that holds it after its task, until the garbage is collected."""

    def __init__(self, plain) -> None:
        super().__init__()
        self.plain = plain

    def __missing__(self, word: str) -> bytes:
        if len(self) >= MEMORY:
            self.clear()
        self[word] = ids = np.array(self.plain(word), "<u4").tobytes()
        return ids


class Encoder:
    """Ids as little-endian bytes of the byte-level vocabulary, word by word with a memory.

    A text is cut before each single space and around each line feed that
    stands between other characters; the vocabulary's pattern never joins
    across such a cut, so the ids of the parts are the ids of the text. Texts
    where white space meets white space, or with a special token, are encoded
    as a whole.
    """

    def __init__(self, name: str = "byte_bpe_50k") -> None:
        import base64
        import os

        import public_tokenizers
        import tiktoken

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.plain = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.file = public_tokenizers.path(f"{name}.json")
        self.whole = None
        self.special = "<|endoftext|>"
        self.first, self.spaced, self.feed = Memory(self.plain), Memory(self.plain), np.array(self.plain("\n"), "<u4").tobytes()

    def __call__(self, text: str) -> bytes:
        if self.special in text:
            if self.whole is None:
                from tokenizers import Tokenizer

                self.whole = Tokenizer.from_file(self.file)
            return np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        lines = []
        for line in text.split("\n"):
            words = line.split(" ")
            if len(words) != len(line.split()) or not line:  # empty words or other white space
                return np.array(self.plain(text), "<u4").tobytes()
            lines.append(self.first[words[0]] + b"".join(map(self._spaced, words[1:])))
        return self.feed.join(lines)

    def _spaced(self, word: str) -> bytes:
        return self.spaced[" " + word]


def pieces(documents: DataFrame, capacity: int = CAPACITY, vocabulary: str = "byte_bpe_50k") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: the documents' tokens in pieces."""

    def make():
        encode = Encoder(vocabulary)
        end = np.array([CLOSE], "<u4").tobytes()

        def work(part):
            owner, piece, start, length, crc = [], [], [], [], []
            for k, text in enumerate(part.column("text").to_pylist()):
                ids = encode(text or "") + end
                n = len(ids) // 4
                at, size, number = 0, n % capacity or capacity, 0
                while at < n:
                    owner.append(k)
                    piece.append(number)
                    start.append(at)
                    length.append(size)
                    crc.append(zlib.crc32(ids[4 * at : 4 * (at + size)]))
                    at, size, number = at + size, capacity, number + 1
            return {"doc_id": part.column("doc_id").take(pa.array(owner, pa.int64())), "piece": piece, "start": start, "length": length, "ids_crc32": crc}

        return work

    kind = dict(documents.dtypes)["doc_id"]
    return map_slices(documents.select("doc_id", "text"), "text", make, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long")


# ---------------------------------------------------------------- the plan


def group_lengths(counts: dict[int, int], groups: int) -> list[list[tuple[int, int]]]:
    """Lengths downwards in groups of about equal cardinality, as (length, count)."""
    total = sum(counts.values())
    out: list[list[tuple[int, int]]] = [[]]
    room = per = max(1, -(-total // groups))
    for length in sorted(counts, reverse=True):
        n = counts[length]
        while n:
            take = min(n, room)
            out[-1].append((length, take))
            n -= take
            room -= take
            if not room:
                out.append([])
                room = per
    return [g for g in out if g]


def best_configuration(sizes: list[int], left: list[int], capacity: int) -> list[int]:
    """How many of each size: the largest that is left, filled up as far as possible.

    Sums that can be reached are bits of an integer, one integer per stage of
    the bounded knapsack; the choice is read backwards, larger sizes first.
    """
    top = next(i for i, n in enumerate(left) if n)
    room = capacity - sizes[top]
    stock = [n - (i == top) for i, n in enumerate(left)]
    usable = [i for i in range(len(sizes) - 1, top - 1, -1) if stock[i] and sizes[i] <= room]
    mask = (1 << (room + 1)) - 1
    stages = [1]
    for i in usable:
        bits, n, step = stages[-1], min(stock[i], room // sizes[i]), 1
        while n:
            step = min(step, n)
            bits |= (bits << (step * sizes[i])) & mask
            n -= step
            step *= 2
        stages.append(bits)
    total = stages[-1].bit_length() - 1
    use = [0] * len(sizes)
    use[top] = 1
    for k in range(len(usable) - 1, -1, -1):
        i = usable[k]
        n = min(stock[i], total // sizes[i])
        while n and not stages[k] >> (total - n * sizes[i]) & 1:
            n -= 1
        use[i] += n
        total -= n * sizes[i]
    return use


class Plan:
    """Sequences as runs (number of sequences, gap, lengths in them)."""

    def __init__(self, counts: dict[int, int], capacity: int = CAPACITY, groups: int = 1024, small: int | None = None) -> None:
        small = capacity // 16 if small is None else small
        self.capacity = capacity
        self.runs: list[tuple[int, int, tuple[int, ...]]] = []
        full = counts.get(capacity, 0)
        if full:
            self.runs.append((full, 0, (capacity,)))
        self._large({k: n for k, n in counts.items() if small <= k < capacity and n}, groups)
        self._small({k: n for k, n in counts.items() if k < small and n})

    def _large(self, counts: dict[int, int], groups: int) -> None:
        if not counts:
            return
        members = group_lengths(counts, groups)
        sizes = [g[0][0] for g in members]
        left = [sum(n for _, n in g) for g in members]
        queues = [list(reversed(g)) for g in members]
        while any(left):
            use = best_configuration(sizes, left, self.capacity)
            times = min(left[i] // n for i, n in enumerate(use) if n)
            if times > 1 and any(left[i] - times * n for i, n in enumerate(use)):
                times = max(1, times * 3 // 4)  # leave some of each for better mixtures later
            self._substitute(use, times, queues)
            for i, n in enumerate(use):
                left[i] -= n * times

    def _substitute(self, use: list[int], times: int, queues: list) -> None:
        """Replaces rounded sizes by actual lengths, in runs of sequences with the same lengths."""
        slots = [i for i, n in enumerate(use) for _ in range(n)]
        while times:
            # as many sequences as every group can serve from the lengths at its head
            need = Counter(slots)
            run = times
            for i, n in need.items():
                run = min(run, max(1, queues[i][-1][1] // n))
            lengths = []
            for i in slots:
                take = run
                if queues[i][-1][1] < run:  # only when run is 1 or a head ends between the slots
                    run = take = max(1, queues[i][-1][1])
                lengths.append(i)
            actual = []
            for i in lengths:
                length, n = queues[i][-1]
                actual.append(length)
                if n == run:
                    queues[i].pop()
                else:
                    queues[i][-1] = (length, n - run)
            self.runs.append((run, self.capacity - sum(actual), tuple(actual)))
            times -= run

    def _small(self, counts: dict[int, int]) -> None:
        """Best fit, downwards, of a whole count at a time."""
        gaps: dict[int, list] = defaultdict(list)
        for run in self.runs:
            gaps[run[1]].append(run)
        known = sorted(gaps)
        for length in sorted(counts, reverse=True):
            n = counts[length]
            while n:
                k = bisect.bisect_left(known, length)
                while k < len(known) and not gaps[known[k]]:
                    del known[k]
                if k < len(known):
                    m, gap, lengths = gaps[known[k]].pop()
                else:
                    m, gap, lengths = max(1, n // (self.capacity // length)), self.capacity, ()
                each = min(gap // length, max(1, n // m))
                used = min(m, n // each)
                if used < m and lengths:
                    gaps[gap].append((m - used, gap, lengths))
                rest = gap - each * length
                if rest not in gaps or not gaps[rest]:
                    at = bisect.bisect_left(known, rest)
                    if at == len(known) or known[at] != rest:
                        known.insert(at, rest)
                gaps[rest].append((used, rest, lengths + (length,) * each))
                n -= used * each
        self.runs = [run for gap in sorted(gaps) for run in gaps[gap]]

    def places(self) -> dict[int, list[tuple[int, int, int]]]:
        """length -> (first rank, first sequence, offset), by rank; a run of ranks takes consecutive sequences."""
        out: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
        ranks: Counter = Counter()
        sequence = 0
        for n, _, lengths in self.runs:
            offset = 0
            for length in lengths:
                out[length].append((ranks[length], sequence, offset))
                ranks[length] += n
                offset += length
            sequence += n
        return out

    @property
    def sequences(self) -> int:
        return sum(run[0] for run in self.runs)


def pack(documents: DataFrame, capacity: int = CAPACITY, vocabulary: str = "byte_bpe_50k") -> DataFrame:
    """The pieces of all documents with their sequence and their offset in it."""
    cutup = cut(pieces(documents, capacity, vocabulary))
    counts = {int(r.length): int(r.n) for r in cutup.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    plan = Plan(counts, capacity).places()
    first = {k: tuple(np.array(c, np.int64) for c in zip(*v, strict=True)) for k, v in plan.items()}
    buckets = spread(max(counts.values(), default=0))
    keyed = cutup.withColumn("draw", F.xxhash64("doc_id", "piece", "ids_crc32"))
    keyed = keyed.withColumn("bucket", F.pmod(F.shiftrightunsigned("draw", 40), F.lit(buckets))).withColumn("one", F.lit(1))
    ranked = prefix_sums(keyed, "length", ["draw", "doc_id", "piece"], "bucket", "one", "rank")
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", F.col("rank").cast("long").alias("rank"))

    def place(batches):
        for batch in batches:
            length, rank = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
            sequence, offset = np.zeros(len(batch), np.int64), np.zeros(len(batch), np.int64)
            order = np.argsort(length, kind="stable")
            kinds, at = np.unique(length[order], return_index=True)
            for k, rows in zip(kinds.tolist(), np.split(order, at[1:]), strict=True):
                ranks, sequences, offsets = first[k]
                run = np.searchsorted(ranks, rank[rows], side="right") - 1
                sequence[rows] = sequences[run] + rank[rows] - ranks[run]
                offset[rows] = offsets[run]
            columns = [batch.column(n) for n in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(sequence), pa.array(offset)], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    kind = dict(documents.dtypes)["doc_id"]
    return ranked.mapInArrow(place, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
