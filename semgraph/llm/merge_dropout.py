"""SentencePiece encoding and decoding with seeded merge dropout.

Merges of a segment are taken from an agenda by score (ties: leftmost). Each candidate, when it is its
turn, is skipped for good if a 64-bit hash keyed by seed, document, position of the segment and the characters it would
cover is under the dropout rate. Every occurrence of a segment so draws its own segmentation; all decode to the same text.

No piece of the vocabulary has a space mark after another character, so no merge crosses the start of a word:
a text falls into segments (space marks, then other characters) that are encoded apart. Nothing is cached: the agendas of
many segments advance together, one candidate of each segment a step, as columns of arrays of integers.
"""

from __future__ import annotations

import functools
import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import spread, text_of

MARK = "▁"
#: Characters whose segments are encoded together; a longer text is a batch of its own.
GROUP = 1_000_000
#: Places of segments in one array of agendas.
CELLS = 1 << 17
#: Lengths up to which segments share an array. Longer segments use a heap; both ways give the same pieces.
WIDTHS = (2, 4, 6, 8, 11, 16, 24, 40, 64)
SHORT = WIDTHS[-1]
#: An agenda's place holds an offer's rank and, in its lowest bits, the place itself, so the least is the best and leftmost.
PLACE_BITS = 6
NONE = np.iinfo(np.int32).max
_M = (1 << 64) - 1
_STEP, _B, _C = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB


@functools.lru_cache(2)
def vocabulary(path: str) -> tuple[dict[str, float], dict[str, int], list[bytes]]:
    """(score of each mergeable piece, id of each piece, bytes of each id)."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    score, ids, raw = {}, {}, []
    for i in range(sp.get_piece_size()):
        p = sp.id_to_piece(i)
        if sp.is_byte(i):
            raw.append(bytes([int(p[3:-1], 16)]))
        elif sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i):
            raw.append(b"")
            continue
        else:
            raw.append(p.replace(MARK, " ").encode())
            score[p] = sp.get_score(i)
        ids[p] = i
    if any(MARK in p.lstrip(MARK) for p in score):
        raise ValueError("this vocabulary has pieces across word starts")
    return score, ids, raw


def _skip_table(dropout: float) -> int:
    """Candidates are skipped whose hash has its upper 53 bits under this."""
    return int(dropout * 2**53)


def _mix(x: int) -> int:
    x &= _M
    x = (x ^ x >> 30) * _B & _M
    x = (x ^ x >> 27) * _C & _M
    return x ^ x >> 31


def _mix_all(x: np.ndarray) -> np.ndarray:
    """`_mix` of each element, in place."""
    x ^= x >> np.uint64(30)
    x *= np.uint64(_B)
    x ^= x >> np.uint64(27)
    x *= np.uint64(_C)
    x ^= x >> np.uint64(31)
    return x


def _mark(left: int, right: int) -> int:
    return (left << 32 | right) * _STEP & _M


def _place(key: int, left: int, right: int) -> int:
    """Upper 53 bits of the hash of a candidate that covers the characters left to right, under a key."""
    return _mix(key + _mark(left, right)) >> 11


def merge_segment(segment: str, score: dict[str, float], key: int, dropout: float) -> list[str]:
    """Pieces of one segment: candidates by (score, leftmost), each skipped by its keyed hash."""
    skip = _skip_table(dropout) if dropout > 0 else None
    return (_short if len(segment) <= SHORT else _long)(segment, score, key, skip)


def _short(segment: str, score: dict[str, float], key: int, skip: int | None) -> list[str]:
    none = float("-inf")
    parts = list(segment)
    at = list(range(len(parts) + 1))  # where each part begins
    get = score.get
    offers = [get(a + b, none) for a, b in zip(parts, parts[1:])]
    while offers:
        best = max(offers)
        if best == none:
            break
        i = offers.index(best)
        if skip is not None and _place(key, at[i], at[i + 2]) < skip:
            offers[i] = none
            continue
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
        del at[i + 1], offers[i]
        if i < len(offers):
            offers[i] = get(parts[i] + parts[i + 1], none)
        if i:
            offers[i - 1] = get(parts[i - 1] + parts[i], none)
    return parts


def _long(segment: str, score: dict[str, float], key: int, skip: int | None) -> list[str]:
    n = len(segment)
    end = list(range(1, n + 1))  # of the part that begins here, 0 if none does
    before = list(range(-1, n - 1))
    heap: list[tuple[float, int, int, int]] = []

    def offer(i: int) -> None:
        j = end[i]
        if j < n and (s := score.get(segment[i : end[j]])) is not None:
            heapq.heappush(heap, (-s, i, j, end[j]))

    for i in range(n):
        offer(i)
    while heap:
        _, i, j, k = heapq.heappop(heap)
        if end[i] != j or j >= n or end[j] != k or (skip is not None and _place(key, i, k) < skip):
            continue
        end[i], end[j] = k, 0
        if k < n:
            before[k] = i
            offer(i)
        if before[i] >= 0:
            offer(before[i])
    out, i = [], 0
    while i < n:
        out.append(segment[i : end[i]])
        i = end[i]
    return out


class _Offers:
    """Characters and pieces as part numbers, and the merge of each pair of parts that has one.

    Pieces have their ids as part numbers, characters that only occur inside longer pieces the numbers after, and any other
    character `other` plus its code point. Pairs are found in an open hash table, at most a quarter full.
    """

    def __init__(self, score: dict[str, float], ids: dict[str, int]) -> None:
        number = {p: ids[p] for p in score}
        top = max(ids.values()) + 1
        for c in sorted({c for p in score for c in p} - number.keys()):
            number[c] = top = top + 1
        self.pieces, self.other = max(ids.values()) + 1, top + 1
        self.of_char = np.arange(0x110000, dtype=np.int32) + np.int32(self.other)
        for p, n in number.items():
            if len(p) == 1:
                self.of_char[ord(p)] = n
        self.bytes_of = {n: [ids[f"<0x{b:02X}>"] for b in p.encode()] for p, n in number.items() if n >= self.pieces}
        self.byte_ids = ids
        rank = {v: i for i, v in enumerate(sorted({-v for v in score.values()}))}
        if len(rank) << PLACE_BITS >= NONE:
            raise ValueError("too many scores for the ranks of offers")
        pairs = [(number[p[:i]], number[p[i:]], rank[-v], number[p]) for p, v in score.items() for i in range(1, len(p)) if p[:i] in number and p[i:] in number]
        left, right, ranks, into = (np.array(x, np.int64) for x in zip(*pairs)) if pairs else [np.zeros(0, np.int64)] * 4
        bits = max(4, (4 * len(pairs)).bit_length())
        self.shift, self.last = np.uint64(64 - bits), (1 << bits) - 1
        self.pair = np.full(1 << bits, _M, np.uint64)
        self.rank, self.into = np.full(1 << bits, NONE, np.int32), np.zeros(1 << bits, np.int32)
        pair = left.astype(np.uint64) << np.uint64(32) | right.astype(np.uint64)
        for k, slot, r, m in zip(pair.tolist(), self._slot(pair).tolist(), ranks.tolist(), into.tolist()):
            while self.pair[slot] != _M:
                slot = slot + 1 & self.last
            self.pair[slot], self.rank[slot], self.into[slot] = k, r << PLACE_BITS, m

    def _slot(self, pair: np.ndarray) -> np.ndarray:
        return (pair * np.uint64(_STEP) >> self.shift).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(rank of each pair above the bits of a place, NONE if the pair does not merge; part that it becomes)."""
        pair = left.astype(np.uint64) << np.uint64(32) | right.astype(np.uint64)
        slot = self._slot(pair)
        held = self.pair[slot]
        on = np.flatnonzero((held != pair) & (held != _M))
        while len(on):
            slot[on] = slot[on] + 1 & self.last
            held = self.pair[slot[on]]
            on = on[(held != pair[on]) & (held != _M)]
        return self.rank[slot], self.into[slot]

    def ids_of(self, parts: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of the parts: those without an id become their bytes; how many for each of the segments that have `counts` parts)."""
        raw = np.flatnonzero(parts >= self.pieces)
        if not len(raw):
            return parts, counts
        kinds, which = np.unique(parts[raw], return_inverse=True)
        spelled = [self.bytes_of.get(k) or [self.byte_ids[f"<0x{b:02X}>"] for b in chr(k - self.other).encode()] for k in kinds.tolist()]
        size = np.ones(len(parts), np.int64)
        size[raw] = np.array([len(x) for x in spelled])[which]
        ends = np.cumsum(size)
        out = np.repeat(parts, size)
        table = np.array([x + [0] * (4 - len(x)) for x in spelled], np.int32)
        for b in range(4):
            has = size[raw] > b
            out[(ends - size)[raw[has]] + b] = table[which[has], b]
        return out, np.diff(np.concatenate([[0], ends])[np.cumsum(np.concatenate([[0], counts]))])


def _agendas(offers: _Offers, part: np.ndarray, size: np.ndarray, keys: np.ndarray, skip: int | None) -> None:
    """Merges the columns of `part` (one part number a character, -1 beyond a segment's end) in place.

    A merged part stands where it begins; -1 stands at its other places. Each step takes the best offer of each column.
    """
    height, width = part.shape
    part = part.reshape(-1)
    place = np.arange(height, dtype=np.int32)[:, None]
    end = np.repeat(place + 1, width, 1).reshape(-1)  # of the part that begins here
    before = end - 2  # where the part before this one begins
    into = np.empty_like(part)
    agenda = np.full((height, width), NONE, np.int32)
    flat = agenda.reshape(-1)
    some = np.flatnonzero((place < size - 1).reshape(-1))
    rank, into[some] = offers.find(part[some], part[some + width])
    flat[some] = rank | (some // width).astype(np.int32)
    column = np.arange(width)
    while len(column):
        best = agenda.min(0)
        live = np.flatnonzero(best != NONE)
        if 2 * len(live) < len(column):  # most are done: go on with the others
            agenda = np.ascontiguousarray(agenda[:, live])
            flat, column, best, live = agenda.reshape(-1), column[live], best[live], np.arange(len(live))
        if not len(live):
            break
        wide = len(column)
        own = column[live]
        at = best[live].astype(np.int64) & (1 << PLACE_BITS) - 1
        i = at * width + own
        middle = end[i].astype(np.int64)
        j = middle * width + own
        stop = end[j].astype(np.int64)
        if skip is not None:
            drawn = _mix_all(keys[own] + (at << 32 | stop).astype(np.uint64) * np.uint64(_STEP)) >> np.uint64(11)
            kept = drawn >= np.uint64(skip)
            flat[(at * wide + live)[~kept]] = NONE
            live, own, at, i, middle, j, stop = (x[kept] for x in (live, own, at, i, middle, j, stop))
        part[i] = into[i]
        part[j] = -1
        end[i] = stop
        flat[at * wide + live] = NONE
        flat[middle * wide + live] = NONE
        right = np.flatnonzero(stop < size[own])
        left = np.flatnonzero(at > 0)
        after = stop[right] * width + own[right]
        before[after] = at[right]
        start = before[i[left]].astype(np.int64)
        first = np.concatenate([i[right], start * width + own[left]])
        rank, into[first] = offers.find(part[first], part[np.concatenate([after, i[left]])])
        at = np.concatenate([at[right], start])
        flat[at * wide + live[np.concatenate([right, left])]] = rank | at.astype(np.int32)


def _ranges(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """All elements of the ranges, one after another."""
    ends = np.cumsum(size)
    return np.repeat(first - (ends - size), size) + np.arange(ends[-1] if len(ends) else 0)


@functools.lru_cache(2)
def _offers(path: str) -> _Offers:
    score, ids, _ = vocabulary(path)
    return _Offers(score, ids)


class DropoutEncoder:
    def __init__(self, path: str, seed: int = 0, dropout: float = 0.1) -> None:
        self.score, self.ids, self.raw = vocabulary(path)
        self.seed, self.dropout = seed, dropout
        self.offers = _offers(path)

    def ids_of(self, pieces: list[str]) -> list[int]:
        out: list[int] = []
        for p in pieces:
            i = self.ids.get(p)
            if i is None:  # a character outside the vocabulary: its bytes
                out += [self.ids[f"<0x{b:02X}>"] for b in p.encode()]
            else:
                out.append(i)
        return out

    def keys(self, doc: int, n: int) -> np.ndarray:
        """The keys of the first n positions of a document."""
        own = _mix(_mix(self.seed * _STEP + 1) + doc * _C)
        return _mix_all(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(_STEP) + np.uint64(own))

    def encode(self, text: str, doc: int = 0) -> bytes:
        """Ids, little-endian unsigned 32-bit."""
        return self.encode_all([text], [doc])[0]

    def encode_all(self, texts: list[str], docs: list[int]) -> list[bytes]:
        out: list[bytes] = []
        first = held = 0
        for i, t in enumerate(texts):
            held += len(t) + 1
            if held >= GROUP or i == len(texts) - 1:
                out += self._group(texts[first : i + 1], docs[first : i + 1])
                first, held = i + 1, 0
        return out

    def _group(self, texts: list[str], docs: list[int]) -> list[bytes]:
        marked = [MARK + t.replace(" ", MARK) if t else "" for t in texts]
        points = np.frombuffer("".join(marked).encode("utf-32-le"), "<u4")
        if not len(points):
            return [b""] * len(texts)
        is_mark = points == ord(MARK)
        begins = is_mark.copy()
        begins[1:] &= ~is_mark[:-1]
        lengths = np.array([len(m) for m in marked])
        text_first = np.cumsum(lengths) - lengths
        begins[text_first[lengths > 0]] = True
        first = np.flatnonzero(begins)
        size = np.diff(first, append=len(points))
        bounds = np.searchsorted(first, np.append(text_first, len(points)))  # segments of each text
        keys = np.concatenate([self.keys(d, n) for d, n in zip(docs, np.diff(bounds).tolist())])
        ids, counts = self._segments(points, first, size, keys)
        ends = 4 * np.concatenate([[0], np.cumsum(counts)])[bounds]
        data = memoryview(ids.astype("<u4")).cast("B")
        return [bytes(data[a:b]) for a, b in zip(ends.tolist(), ends[1:].tolist())]

    def _segments(self, points: np.ndarray, first: np.ndarray, size: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all segments, how many of each)."""
        skip = _skip_table(self.dropout) if self.dropout > 0 else None
        done: list[tuple[np.ndarray, np.ndarray]] = []  # segments, ids
        counts = np.zeros(len(first), np.int64)
        under = 0
        for height in WIDTHS:
            rows = np.flatnonzero((size > under) & (size <= height))
            under = height
            for some in np.split(rows, range(CELLS // height + 1, len(rows), CELLS // height + 1)):
                place = np.arange(height)[:, None]
                at = np.minimum(first[some] + place, len(points) - 1)
                part = np.where(place < size[some], self.offers.of_char[points[at]], np.int32(-1))
                _agendas(self.offers, part, size[some], keys[some], skip)
                across = part.T
                held = across >= 0
                ids, counts[some] = self.offers.ids_of(across[held], held.sum(1))
                done.append((some, ids))
        for i in np.flatnonzero(size > SHORT).tolist():
            segment = points[first[i] : first[i] + size[i]].tobytes().decode("utf-32-le")
            ids = self.ids_of(merge_segment(segment, self.score, int(keys[i]), self.dropout))
            counts[i] = len(ids)
            done.append((np.array([i]), np.array(ids)))
        begin = np.cumsum(counts) - counts
        out = np.empty(int(counts.sum()), np.uint32)
        for some, ids in done:
            out[_ranges(begin[some], counts[some])] = ids
        return out, counts

    def decode(self, ids: bytes) -> str:
        raw = self.raw
        data = b"".join([raw[i] for i in np.frombuffer(ids, "<u4").tolist()])
        return (data[1:] if data[:1] == b" " else data).decode("utf-8", "replace")


@functools.lru_cache(1)
def _coder(path: str, seed: int, dropout: float) -> DropoutEncoder:
    """One coder for all tasks of a worker, so that its tables are built once."""
    return DropoutEncoder(path, seed, dropout)


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", seed: int = 0, dropout: float = 0.1) -> DataFrame:
    """(doc_id, ids binary): pieces of every whole text, little-endian unsigned 32-bit; see `decode_documents`.

    Null text counts as empty and has no ids. Null ids count as document 0. Repeated rows get the same
    pieces. An empty table gives an empty result; other columns play no part. Dropout 0 gives the library's pieces.
    The space mark inside a text decodes to a space, as with the library; all else is lossless.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _coder(path, seed, dropout)
        for b in batches:
            out = coder.encode_all(b.column(1).to_pylist(), [d or 0 for d in b.column(0).to_pylist()])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], ["doc_id", "ids"])

    return spread(docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text"))).mapInArrow(run, "doc_id long, ids binary")


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) of (doc_id, ids)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = DropoutEncoder(path)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([coder.decode(x or b"") for x in b.column(1).to_pylist()])], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def segmentation_digest(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", seed: int = 0, dropout: float = 0.1) -> DataFrame:
    """(doc_id, n_pieces, ids_crc32, decodes): encoded and decoded again; `decodes` tells whether the whole text came back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _coder(path, seed, dropout)
        for b in batches:
            out = [[], [], []]
            texts = b.column(1).to_pylist()
            for t, ids in zip(texts, coder.encode_all(texts, [d or 0 for d in b.column(0).to_pylist()])):
                for c, v in zip(out, (len(ids) // 4, zlib.crc32(ids), coder.decode(ids) == t.replace(MARK, " "))):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.bool_())], ["doc_id", "n_pieces", "ids_crc32", "decodes"])

    rows = spread(docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text")))
    return rows.mapInArrow(run, "doc_id long, n_pieces long, ids_crc32 long, decodes boolean")
