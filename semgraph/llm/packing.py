"""Packing of documents into sequences: dominance reduction, then best fit, over a histogram of lengths.

Lengths are whole numbers up to the capacity, so the whole instance is a histogram of that many counts,
whatever the number of documents. On it the reduction of Martello and Toth fixes sets of one to three lengths
that dominate every alternative; sets that recur are fixed with their multiplicity. Best fit packs the
rest in descending order. The result, a list of (lengths of a sequence, how often), is broadcast; each
piece then finds its place by its length and its rank among pieces of that length, all in parallel.
"""

from __future__ import annotations

import bisect
import functools
import re
import zlib
from array import array
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, spread, text_of

CAPACITY = 2048
#: Texts are encoded in blocks of about this many bytes.
BLOCK_BYTES = 8 << 20
#: Distinct words that the library takes in one call.
WORDS_A_CALL = 1000
#: Stands between words in such a call: a control character with an id of its own; texts that hold it go to the library whole.
SEPARATOR = "\x01"

Pattern = tuple[int, ...]


def _dominating(length: int, rest: int, sizes: list[int], count: dict[int, int]) -> Pattern | None:
    """Lengths that, with `length`, dominate every other set with it; () if it stays alone, None if none is known.

    `sizes` ascends and holds what is left beside this piece; `rest` is the room beside it.
    """
    if not sizes or sizes[0] > rest:
        return ()
    if count.get(rest, 0) > 0:
        return (rest,)
    low = [s for x in sizes[:3] for s in [x] * min(3, count[x])][:3]
    first = sizes[bisect.bisect_right(sizes, rest) - 1]
    if len(low) < 2 or low[0] + low[1] > rest:
        return (first,)  # one more piece at most fits: the longest such
    if len(low) < 3 or sum(low) > rest:
        # two more at most: (first, second) dominates if no pair that fits has a greater lesser part
        i = bisect.bisect_right(sizes, rest - first) - 1
        second = sizes[i] if i >= 0 and (sizes[i] != first or count[first] > 1) else None
        if second is not None:
            half = bisect.bisect_right(sizes, rest // 2) - 1
            lesser = 0
            if half >= 0:
                x = sizes[half]
                partner = rest - x
                j = bisect.bisect_right(sizes, partner) - 1
                if sizes[j] > x or (sizes[j] == x and count[x] > 1):
                    lesser = x
                elif half > 0:
                    lesser = sizes[half - 1]
            if lesser <= second:
                return (first, second)
    return None


def reduce_by_dominance(counts: dict[int, int], capacity: int = CAPACITY) -> tuple[list[tuple[Pattern, int]], dict[int, int]]:
    """(fixed sequences with multiplicity, what is left of the histogram)."""
    left = {s: n for s, n in counts.items() if n > 0}
    fixed: list[tuple[Pattern, int]] = []

    def take(pattern: Pattern, n: int) -> None:
        fixed.append((pattern, n))
        for s in pattern:
            left[s] -= n
            if not left[s]:
                del left[s]

    for s in sorted(left, reverse=True):
        if s == capacity:
            take((s,), left[s])
        elif s in left and left.get(capacity - s, 0) and s >= capacity - s:
            n = left[s] // 2 if 2 * s == capacity else min(left[s], left[capacity - s])
            if n:
                take((s, capacity - s), n)
    changed = True
    while changed and left:
        changed = False
        for s in sorted(left, reverse=True):
            while left.get(s, 0):
                others = dict(left)
                others[s] -= 1
                if not others[s]:
                    del others[s]
                found = _dominating(s, capacity - s, sorted(others), others)
                if found is None:
                    break
                need = Counter((s, *found))
                n = min(left[x] // k for x, k in need.items())
                # the ground for a set is the lengths beside it, which change only when one runs out or is down to three
                n = max(1, min(n, min((left[x] - 4) // k for x, k in need.items())))
                take((s, *found), n)
                changed = True
    return fixed, left


def best_fit(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[Pattern, int]]:
    """Best fit in descending order over a histogram: sequences of the same content are handled together."""
    room: dict[int, list[list]] = defaultdict(list)  # free room -> [pattern, how many]
    rooms: list[int] = []

    def put(free: int, pattern: Pattern, n: int) -> None:
        if free not in room or not room[free]:
            bisect.insort(rooms, free)
            room[free] = []
        for group in room[free]:
            if group[0] == pattern:
                group[1] += n
                return
        room[free].append([pattern, n])

    for s in sorted(counts, reverse=True):
        n = counts[s]
        while n:
            i = bisect.bisect_left(rooms, s)
            if i == len(rooms):
                free, pattern, have = capacity, (), n
            else:
                free = rooms[i]
                pattern, have = room[free][-1]
            each = free // s  # the fullest place that fits is the one just used, until it is full
            full, part = min(have, n // each), 0
            if not full:
                each, full, part = n, 1, 1
            if i < len(rooms):
                group = room[free][-1]
                group[1] -= full
                if not group[1]:
                    room[free].pop()
                    if not room[free]:
                        rooms.pop(i)
                        del room[free]
            put(free - each * s, pattern + (s,) * each, full)
            n -= each * full
    return [(p, n) for groups in room.values() for p, n in groups]


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[Pattern, int]]:
    """Sequences as (lengths, multiplicity) for a histogram of lengths up to `capacity`."""
    fixed, left = reduce_by_dominance(counts, capacity)
    return fixed + best_fit(left, capacity)


def slots(planned: list[tuple[Pattern, int]]) -> tuple[np.ndarray, ...]:
    """Where the k-th piece of a length goes, as ranges sorted by (length, rank).

    (length, first rank, first sequence, copies in a sequence, offset of the first copy)
    """
    rows, used, sequence = [], Counter(), 0
    for pattern, n in planned:
        offset = 0
        for s, c in sorted(Counter(pattern).items(), reverse=True):
            rows.append((s, used[s], sequence, c, offset))
            used[s] += c * n
            offset += c * s
        sequence += n
    rows.sort()
    table = np.array(rows, np.int64).reshape(-1, 5)
    return tuple(table.T)


class WordIds:
    """Ids of whole texts by the word-based vocabulary, as little-endian bytes.

    White space parts words, and no id depends on more than its word. The texts of a block are split and their words
    numbered in Arrow; the library sees each distinct word once a block, many in one call with a separator between,
    and the ids of the texts are gathered from those of the words. The words of the last block stay known, so memory
    is bounded by the size of a block (or of a text, if that is longer).
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        specials = [re.escape(x.content) for x in self.tok.get_added_tokens_decoder().values()]
        # separators on which Arrow and the library's white space differ, the separator of words, special strings
        self.odd = "|".join(["[\x1c-\x1f]", SEPARATOR, *specials])
        (self.cut,) = self._library(SEPARATOR)
        self._remember(pa.array([], pa.string()), np.zeros(0, np.uint32), np.zeros(0, np.int64))

    def _library(self, text: str) -> list[int]:
        return self.tok.encode_batch_fast([text], add_special_tokens=False)[0].ids  # offsets are not worked out

    def _remember(self, words: pa.Array, ids: np.ndarray, counts: np.ndarray) -> None:
        self.words, self.ids, self.counts, self.starts = words, ids, counts, np.cumsum(counts) - counts

    def _learn(self, words: pa.Array) -> None:
        """Make the distinct `words`, in this order, the known ones."""
        at = pc.index_in(words, value_set=self.words)
        new = words.filter(pc.is_null(at)).to_pylist()
        ids, counts = [self.ids], [self.counts]
        for i in range(0, len(new), WORDS_A_CALL):
            some = new[i : i + WORDS_A_CALL]
            found = np.array(self._library(f" {SEPARATOR} ".join(some)), np.uint32)
            cuts = np.flatnonzero(found == self.cut)
            counts.append(np.diff(cuts, prepend=-1, append=len(found)) - 1)
            ids.append(np.delete(found, cuts))
        counts = np.concatenate(counts)
        rows = at.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
        rows[rows < 0] = np.arange(len(self.counts), len(counts))
        self._remember(words, _gather(np.concatenate(ids), np.cumsum(counts) - counts, counts, rows), counts[rows])

    def _block(self, texts: pa.Array) -> Iterator[bytes]:
        split = pc.utf8_split_whitespace(texts)
        coded = split.flatten().dictionary_encode()
        self._learn(coded.dictionary)
        rows = coded.indices.to_numpy()
        ids = _gather(self.ids, self.starts, self.counts, rows)
        ends = np.concatenate([[0], np.cumsum(self.counts[rows])])
        words = np.concatenate([[0], np.cumsum(pc.list_value_length(split).to_numpy())])
        raw, bounds = memoryview(ids.tobytes()), (4 * ends[words]).tolist()
        for i, j in zip(bounds, bounds[1:]):
            yield bytes(raw[i:j])

    def encode(self, texts: pa.Array) -> Iterator[bytes]:
        """Ids of each of `texts`, in order."""
        odd = pc.match_substring_regex(texts, self.odd)
        plain = pc.if_else(odd, "", texts)
        block = np.cumsum(pc.binary_length(plain).to_numpy()) // BLOCK_BYTES
        cuts = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), len(texts)]
        for i, j in zip(cuts, cuts[1:]):
            for k, ids in enumerate(self._block(plain.slice(i, j - i)), i):
                yield array("I", self._library(texts[k].as_py())).tobytes() if odd[k].as_py() else ids


def _gather(ids: np.ndarray, starts: np.ndarray, counts: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """The runs of `ids` that `rows` name, one after the other."""
    own = counts[rows]
    ends = np.cumsum(own)
    total = int(ends[-1]) if len(ends) else 0
    return ids[np.arange(total) + np.repeat(starts[rows] - (ends - own), own)]


@functools.lru_cache(1)
def _coder(path: str) -> WordIds:
    """One coder for all tasks of a worker, so that its words stay known."""
    return WordIds(path)


def pieces(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, pid, k): pieces of documents with their end id.

    pid is the task that made the piece and k its number among that task's pieces of the same length.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, end, pid = _coder(path), np.uint32(end_id).tobytes(), TaskContext.get().partitionId()
        seen: Counter[int] = Counter()
        for b in batches:
            out = [[] for _ in range(6)]
            for doc, ids in zip(b.column(0).to_pylist(), coder.encode(b.column(1))):
                ids += end
                for j, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    n = len(part) // 4
                    for c, v in zip(out, (doc, j, at // 4, n, zlib.crc32(part), seen[n])):
                        c.append(v)
                    seen[n] += 1
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
            cols = [pa.array(c, t) for c, t in zip(out, kinds)]
            yield pa.RecordBatch.from_arrays([*cols, pa.array([pid] * len(out[0]), pa.int32())], ["doc_id", "piece", "start", "length", "ids_crc32", "k", "pid"])

    rows = spread(docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text")))
    return rows.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, k long, pid int")


def pack_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset): a row for each piece.

    Null text counts as empty: a piece of the end id alone. Null ids and repeated rows are documents like any
    other. Documents longer than `capacity` are cut, others never. An empty table gives an empty result.
    Other columns play no part. Only the histogram, at most `capacity` rows, comes to the driver.
    """
    cut = materialize(pieces(docs, path, id_col, text_col, capacity, end_id), "pieces")
    by_task = cut.groupBy("length", "pid").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)
    first = by_task.withColumn("first", F.coalesce(F.sum("n").over(before), F.lit(0)))
    counts = {r.length: r.n for r in by_task.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    table = docs.sparkSession.sparkContext.broadcast(slots(plan(counts, capacity)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        length, rank0, sequence0, copies, offset0 = table.value
        wide = np.int64(1) << np.int64(40)
        start_keys = length * wide + rank0
        for b in batches:
            n, rank = b.column("length").to_numpy(zero_copy_only=False), b.column("rank").to_numpy(zero_copy_only=False)
            i = np.searchsorted(start_keys, n * wide + rank, "right") - 1
            own = rank - rank0[i]
            sequence, offset = sequence0[i] + own // copies[i], offset0[i] + own % copies[i] * n
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    ranked = cut.join(first.select("length", "pid", "first"), ["length", "pid"]).withColumn("rank", (F.col("first") + F.col("k")).cast("long"))
    return ranked.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
