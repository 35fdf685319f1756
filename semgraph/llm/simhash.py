"""Near-duplicates by SimHash: fuzzy keys from Golay decoding find the pairs, popcounts verify them.

A fingerprint is cut into three segments (23, 23 and 18 bits, the last padded to 23). The perfect
[23,12,7] Golay code gives each 23-bit word one nearest codeword at 0 to 3 errors. A word with three
errors also lies at distance 4 from five more codewords. The nearest codeword alone, or with those
five, gives one or six indices of 12 bits with two properties that the tests check exhaustively:

* words at distance <= 2 share at least one index ("wide" against "wide");
* of words at distance <= 1, the nearest index of either is among the indices of the other.

Four differing bits over three segments leave these cases, and each has its join keys:

* a segment without error, and another with two or fewer: its 23 bits with a wide index of the other;
* no segment without error, so two segments have exactly one: wide and nearest index, left against right.

Rows of a key are compared in Python in batches cut at key ends; a task emits an edge only if it joins
two sets of its own union-find, so a group of n copies gives at most n - 1 edges a task, never n^2 pairs.
Keys that a sample shows as hot are split into blocks that meet pairwise, without loss.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, spread, text_of
from .components import connected_components

#: Generator polynomial of the binary Golay code [23,12,7].
GOLAY_GENERATOR = 0b110001110101

SEGMENTS = ((0, 23), (23, 23), (46, 18))
SHINGLE = 4
MAX_BITS = 4
SEED = 42
#: Pairs compared at once in a task, and rows of a block of a hot key.
PAIRS_AT_ONCE = 2_000_000
HOT_ROWS = 50_000
#: A fingerprint with this share of all rows is joined by broadcast; there are no more than this many of them.
HOT_SHARE = 1000
#: Shingles hashed at once, so that a very long text needs bounded memory.
SHINGLES_AT_ONCE = 100_000

_ASCII_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@functools.cache
def _words():
    import re

    return re.compile(r"[^\x20\x09-\x0D]+")


def fingerprint(text: str, k: int = SHINGLE, seed: int = SEED) -> int:
    """SimHash of all k-word shingles of a text; 0 if it has no word."""
    import xxhash

    words = _words().findall(text.translate(_ASCII_LOWER))
    if not words:
        return 0
    n = max(1, len(words) - k + 1)
    ones = np.zeros(64, np.int64)
    digest = xxhash.xxh64_intdigest
    for at in range(0, n, SHINGLES_AT_ONCE):
        part = words[at : at + SHINGLES_AT_ONCE + k - 1]
        shingles = map(" ".join, zip(*(part[i:] for i in range(k)))) if len(words) >= k else [" ".join(words)]
        hashes = np.fromiter((digest(s, seed) for s in shingles), np.uint64)
        ones += np.unpackbits(hashes.view(np.uint8)).reshape(-1, 64).sum(0, dtype=np.int64)
    return int(np.packbits(ones * 2 > n).view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """(doc_id, fp long, text_key long): a row for each row of `docs`; null text counts as empty, null ids stay. text_key is a hash of the whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = [fingerprint(t, k, seed) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.array(fps, np.uint64).view(np.int64)), b.column(2)], ["doc_id", "fp", "text_key"])

    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text"), F.xxhash64(text_of(text_col)).alias("text_key"))
    return spread(own).mapInArrow(run, "doc_id long, fp long, text_key long")


@functools.cache
def golay_tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """By syndrome: the error pattern, whether it has three errors, and the masks to the five indices at distance 4."""
    from itertools import combinations

    syndromes = np.zeros(23, np.int64)
    for bit in range(23):
        x = 1 << bit
        for at in range(22, 10, -1):
            if x >> at & 1:
                x ^= GOLAY_GENERATOR << (at - 11)
        syndromes[bit] = x
    pattern = np.zeros(2048, np.int64)
    three = np.zeros(2048, bool)
    for weight in (1, 2, 3):
        for bits in combinations(range(23), weight):
            s = int(np.bitwise_xor.reduce(syndromes[list(bits)]))
            pattern[s] = sum(1 << b for b in bits)
            three[s] = weight == 3
    words = np.arange(4096, dtype=np.int64) << 11
    codewords = words ^ _remainder(words, syndromes)
    heavy = codewords[np.bitwise_count(codewords) == 7]
    masks = np.zeros((2048, 5), np.int64)
    for s in np.flatnonzero(three):
        masks[s] = heavy[(heavy & pattern[s]) == pattern[s]] >> 11
    return pattern, three, masks


def _remainder(words: np.ndarray, syndromes: np.ndarray) -> np.ndarray:
    out = np.zeros_like(words)
    for bit, s in enumerate(syndromes):
        out ^= np.where(words >> bit & 1, s, 0)
    return out


@functools.cache
def _syndromes() -> np.ndarray:
    """Syndromes of all values of the lower 12 and of the upper 11 bits of a word."""
    single = np.zeros(23, np.int64)
    for bit in range(23):
        x = 1 << bit
        for at in range(22, 10, -1):
            if x >> at & 1:
                x ^= GOLAY_GENERATOR << (at - 11)
        single[bit] = x
    low, high = np.arange(4096, dtype=np.int64), np.arange(2048, dtype=np.int64) << 12
    return np.concatenate([_remainder(low, single), _remainder(high, single)])


def golay_indices(words: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(nearest index, all indices (n, 6), valid (n, 6)) of 23-bit words."""
    pattern, three, masks = golay_tables()
    table = _syndromes()
    s = table[words & 4095] ^ table[4096 + (words >> 12)]
    nearest = (words ^ pattern[s]) >> 11
    wide = np.concatenate([nearest[:, None], nearest[:, None] ^ masks[s]], 1)
    valid = np.ones(wide.shape, bool)
    valid[:, 1:] = three[s][:, None]
    return nearest, wide, valid


def fuzzy_keys(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of fps, key, side) for uint64 fingerprints; keys of side 0 meet those of side 1 and of their own side 2.

    Side 2 stands for both sides: exact segment with wide index.
    """
    parts = [((fps >> np.uint64(at)) & np.uint64((1 << n) - 1)).astype(np.int64) for at, n in SEGMENTS]
    codes = [golay_indices(p) for p in parts]
    rows, keys, sides = [], [], []
    kind = 0

    def put(first: np.ndarray, wide: np.ndarray, valid: np.ndarray, side: int) -> None:
        at, j = np.nonzero(valid)
        rows.append(at)
        keys.append((kind << 36) | (first[at] << 12) | wide[at, j])
        sides.append(np.full(len(at), side, np.int8))

    for a in range(3):
        for b in range(3):
            if a != b:
                kind += 1
                put(parts[a], codes[b][1], codes[b][2], 2)
    for a, b in ((0, 1), (0, 2), (1, 2)):
        kind += 1
        put(codes[b][0], codes[a][1], codes[a][2], 0)
        # the right side has the nearest index of a and the wide ones of b: the same number, put together the other way round
        at, j = np.nonzero(codes[b][2])
        rows.append(at)
        keys.append((kind << 36) | (codes[b][1][at, j] << 12) | codes[a][0][at])
        sides.append(np.ones(len(at), np.int8))
    return np.concatenate(rows), np.concatenate(keys), np.concatenate(sides)


class _Sets:
    """Union-find over the fingerprints that a task has linked so far."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        up = self.up
        while (y := up.setdefault(x, x)) != x:
            up[x] = up[y]
            x = y
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.root(x), self.root(y)
        if x == y:
            return False
        self.up[max(x, y)] = min(x, y)
        return True


def _links(key: np.ndarray, fp: np.ndarray, side: np.ndarray, max_bits: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (lesser, greater) within max_bits among rows of the same key that meet."""
    left = np.flatnonzero(side != 1)
    right = np.flatnonzero(side != 0)
    left = left[np.argsort(key[left], kind="stable")]
    lk = key[left]
    begin, end = np.searchsorted(lk, key[right]), np.searchsorted(lk, key[right], "right")
    many = end - begin
    right, begin, many = right[many > 0], begin[many > 0], many[many > 0]
    lf, rf, ufp = fp[left], fp[right], fp.view(np.uint64)
    lu, ru = ufp[left], ufp[right]
    total = np.concatenate([[0], np.cumsum(many)])
    for start in range(0, int(total[-1]), PAIRS_AT_ONCE):
        stop = min(start + PAIRS_AT_ONCE, int(total[-1]))
        i0, i1 = np.searchsorted(total, start, "right") - 1, np.searchsorted(total, stop, "left")
        own = np.arange(i0, i1)
        lo = np.maximum(total[own], start)
        n = np.minimum(total[own + 1], stop) - lo
        r = np.repeat(own, n)
        l = np.arange(start, stop) - np.repeat(total[own], n) + np.repeat(begin[own], n)
        ok = np.bitwise_count(lu[l] ^ ru[r]) <= max_bits
        x, y = lf[l[ok]], rf[r[ok]]
        differ = x != y
        x, y = x[differ], y[differ]
        yield np.minimum(x, y), np.maximum(x, y)


def _hot_keys(fps: DataFrame, sample: int = 256) -> tuple[np.ndarray, np.ndarray]:
    """Keys that hold many fingerprints, and blocks to split each into, from the fingerprints whose hash is 0 mod `sample`.

    It only decides how work is dealt out; no pair depends on it. At most 10,000 keys come back.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(fuzzy_keys(b.column(0).to_numpy(zero_copy_only=False).view(np.uint64))[1])], ["key"])

    few = max(8, HOT_ROWS // sample)
    found = (
        fps.filter(F.pmod(F.xxhash64("fp", F.lit(7)), F.lit(sample)) == 0)
        .select("fp").mapInArrow(run, "key long").groupBy("key").count()
        .filter(F.col("count") >= few).orderBy(F.desc("count"), "key").limit(10_000).collect()
    )
    found.sort(key=lambda r: r.key)
    return np.array([r.key for r in found], np.int64), np.array([-(-r["count"] * sample // HOT_ROWS) + 1 for r in found], np.int64)


def fingerprint_links(fps: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """(a, b): edges between distinct values of column fp that connect all pairs within `max_bits` (0 to 4) bits."""
    if not 0 <= max_bits <= MAX_BITS:
        raise ValueError("the keys find pairs of 4 or fewer differing bits")
    hot, blocks = _hot_keys(fps)

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            whole = b.column(0).to_numpy(zero_copy_only=False)
            for at in range(0, len(whole), 4096):
                fp = whole[at : at + 4096]
                row, key, side = fuzzy_keys(fp.view(np.uint64))
                cell = np.zeros(len(row), np.int64)
                f = fp[row]
                if len(hot):
                    i = np.minimum(np.searchsorted(hot, key), len(hot) - 1)
                    n = np.where(hot[i] == key, blocks[i], 1)
                    mine = ((f.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)).astype(np.int64) % n
                    plain = n == 1
                    # a row of a hot key goes, as left, to the cells (own, *) and, as right, to (*, own)
                    pieces = [(np.flatnonzero(plain), cell[plain], side[plain])]
                    for s, own_first in ((0, True), (1, False)):
                        at_ = np.flatnonzero(~plain & (side != 1 - s))
                        many = n[at_]
                        r = np.repeat(at_, many)
                        other = np.arange(len(r)) - np.repeat(np.cumsum(many) - many, many)
                        own, m = mine[r], n[r]
                        pieces.append((r, 1 + (own * m + other if own_first else other * m + own), np.full(len(r), s, np.int8)))
                    pick, cell, side = (np.concatenate([p[j] for p in pieces]) for j in range(3))
                    key, f = key[pick], f[pick]
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(cell.astype(np.int32)), pa.array(f), pa.array(side)], ["key", "cell", "fp", "side"])

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets = _Sets()
        held: list[list[np.ndarray]] = []
        count = 0

        def flush(parts: list[np.ndarray]) -> pa.RecordBatch:
            out: list[tuple[int, int]] = []
            key = parts[0] * 1_000_003 + parts[1]  # cells of a key are apart; a rare clash only adds verified pairs
            for x, y in _links(key, parts[2], parts[3], max_bits):
                out += [(a, b) for a, b in zip(x.tolist(), y.tolist()) if sets.join(a, b)]
            return pa.RecordBatch.from_arrays([pa.array([a for a, _ in out], pa.int64()), pa.array([b for _, b in out], pa.int64())], ["a", "b"])

        for b in batches:
            held.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
            count += b.num_rows
            if count >= 500_000:
                parts = [np.concatenate(p) for p in zip(*held)]
                last = (parts[0] == parts[0][-1]) & (parts[1] == parts[1][-1])
                keep = int(np.argmax(last))
                if keep:
                    yield flush([p[:keep] for p in parts])
                held = [[p[keep:] for p in parts]]
                count = len(held[0][0])
        if count:
            yield flush([np.concatenate(p) for p in zip(*held)])

    keys = spread(fps.select("fp")).mapInArrow(emit, "key long, cell int, fp long, side byte")
    dealt = keys.repartition("key", "cell").sortWithinPartitions("key", "cell")
    return dealt.mapInArrow(match, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_bits: int = MAX_BITS, k: int = SHINGLE) -> DataFrame:
    """(doc_id, fp long, text_key long, component_id, root): one row for each row of `docs`; component_id is the least doc_id linked to it, and
    root a fingerprint that names the component (two components that share a repeated id have the same component_id).

    Null text counts as empty (fingerprint 0). Null ids stay and are never a component_id unless all ids of
    the component are null. Repeated rows each give a row. An empty table gives an empty result. Other
    columns of `docs` play no part.
    """
    fps = materialize(fingerprints(docs, id_col, text_col, k), "fingerprints")
    own = fps.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count("*").alias("rows"))
    links = fingerprint_links(own.select("fp"), max_bits)
    roots = connected_components(links, "a", "b")
    linked = own.join(roots, own.fp == roots.node).select("fp", "first", "root")
    least = linked.groupBy("root").agg(F.min("first").alias("least"))
    named = linked.join(least, "root").select("fp", "least", "root")
    label = own.join(named, "fp", "left").select("fp", F.coalesce("least", "first").alias("component_id"), F.coalesce("root", "fp").alias("root"), "rows")
    label = materialize(label, "labels")
    # a fingerprint of a thousandth of all rows or more is hot; there are a thousand of these at most, so they are broadcast and their rows stay where they are
    hot = F.broadcast(label.filter(F.col("rows") * HOT_SHARE >= max(HOT_SHARE, fps.count())).select("fp", "component_id", "root"))
    columns = ["doc_id", "fp", "text_key", "component_id", "root"]
    rare = fps.join(hot, "fp", "left_anti").join(label.join(hot, "fp", "left_anti"), "fp").select(*columns)
    return fps.join(hot, "fp").select(*columns).unionByName(rare)


def keep_one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of `docs` less near-duplicates: of each component one row stays, that with the least id.

    Where that id is repeated inside the component, one of its texts stays (the least by hash), once. A repeated id whose texts
    belong to different components stays in each. Rows without an id cannot be named as a copy of another and stay. An empty
    table gives an empty one; other columns are kept as they are.
    """
    found = near_duplicates(docs, id_col, text_col).filter("doc_id IS NOT NULL")
    first = found.groupBy("root").agg(F.min(F.struct("doc_id", "text_key")).alias("one")).select(F.col("one.doc_id").alias("__one_id"), F.col("one.text_key").alias("__one_key"))
    named = docs.filter(F.col(id_col).isNotNull())
    own = [F.col(id_col).cast("long") == F.col("__one_id"), F.xxhash64(text_of(text_col)) == F.col("__one_key")]
    kept = named.join(first, own[0] & own[1]).dropDuplicates(["__one_id", "__one_key"]).select(*[named[c] for c in named.columns])
    return kept.unionByName(docs.filter(F.col(id_col).isNull()))
