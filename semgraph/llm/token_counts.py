"""Token counts by a map-side two-tier lookup of pre-tokens.

Tier one is a compact table of the most frequent pre-tokens with their token counts, made from a bounded
sample and broadcast. Tier two is a cache in each worker; only pre-tokens in neither are encoded, in batches.
Nothing is shuffled. The sample decides speed alone: every count is the library's.
"""

from __future__ import annotations

import functools
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import spread, text_of

#: Rows of the sample and entries of the broadcast table (about 1 MB), entries of a worker's cache.
SAMPLE_ROWS = 1_000
TABLE_ENTRIES = 50_000
CACHE_ENTRIES = 500_000
#: Characters whose class is the same in all Unicode versions of the two regex engines; other texts go to the library whole.
PLAIN_TEXT = r"[\x00-՗֐-ࢎऀ-౛ഀ-₎₠-ꟍ가-힣豈-龎＀-￮\U0001F300-\U0001FAF8]*"


@functools.lru_cache(4)
def _library(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@functools.cache
def _patterns():
    import public_tokenizers
    import regex

    return regex.compile(public_tokenizers.PATTERN), regex.compile(PLAIN_TEXT)


class PretokenCounter:
    """Counts tokens of whole texts; counts of pre-tokens come from the table, then from the cache."""

    def __init__(self, path: str, table: dict[str, int] | None = None) -> None:
        self.tok = _library(path)
        self.specials = [t.content for t in self.tok.get_added_tokens_decoder().values()]
        self.split, self.plain = _patterns()
        self.table = table or {}
        self.cache: dict[str, int] = dict(self.table)

    def _learn(self, missing: list[str]) -> None:
        if len(self.cache) + len(missing) > CACHE_ENTRIES + len(self.table):
            self.cache = dict(self.table)
        for at in range(0, len(missing), 10_000):
            part = missing[at : at + 10_000]
            self.cache.update(zip(part, map(len, self.tok.encode_batch(part, add_special_tokens=False))))

    def counts(self, texts: list[str]) -> list[int]:
        out, pending = [], []
        for i, t in enumerate(texts):
            if self.plain.fullmatch(t) is None or any(s in t for s in self.specials):
                out.append(len(self.tok.encode(t, add_special_tokens=False)))
                continue
            words = self.split.findall(t)
            lengths = list(map(self.cache.get, words))
            if None in lengths:
                pending.append((i, words))
                out.append(0)
            else:
                out.append(sum(lengths))
        # misses of some texts are encoded together; a batch of the cache's size at most is held
        group, missing = [], {}
        for i, words in pending:
            group.append((i, words))
            missing.update((w, None) for w in words if w not in self.cache)
            if len(missing) > 50_000:
                self._finish(group, missing, out)
                group, missing = [], {}
        self._finish(group, missing, out)
        return out

    def _finish(self, group: list, missing: dict, out: list[int]) -> None:
        self._learn(list(missing))
        for i, words in group:
            lengths = list(map(self.cache.get, words))
            if None in lengths:  # the cache was emptied on the way
                late = [w for w, n in zip(words, lengths) if n is None]
                known = dict(zip(late, map(len, self.tok.encode_batch(late, add_special_tokens=False))))
                lengths = [known[w] if n is None else n for w, n in zip(words, lengths)]
            out[i] = sum(lengths)


def frequent_pretokens(docs: DataFrame, path: str, text_col: str = "text", rows: int = SAMPLE_ROWS, entries: int = TABLE_ENTRIES) -> dict[str, int]:
    """Token counts of the most frequent pre-tokens of up to `rows` rows: the broadcast tier."""
    split, _ = _patterns()
    seen: Counter[str] = Counter()
    for r in docs.select(F.substring(text_of(text_col), 1, 20_000).alias("t")).limit(rows).toLocalIterator():
        seen.update(split.findall(r.t))
    words = [w for w, _ in seen.most_common(entries) if len(w) <= 40]
    return dict(zip(words, map(len, _library(path).encode_batch(words, add_special_tokens=False))))


def count_tokens(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 1024) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit): a row for each row of `docs`, over its whole text.

    Null text counts as empty: 0 bytes, 0 tokens. Null ids and repeated rows stay as they are; an empty
    table gives an empty result; other columns play no part. Special strings inside a text count as the
    library's default has them: one token.
    """
    table = docs.sparkSession.sparkContext.broadcast(frequent_pretokens(docs, path, text_col))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = PretokenCounter(path, table.value)
        for b in batches:
            n = pa.array(counter.counts(b.column(2).to_pylist()), pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), n], ["doc_id", "n_bytes", "n_tokens"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.octet_length(text_of(text_col)).cast("long").alias("n_bytes"), text_of(text_col).alias("text"))
    return spread(rows).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
