"""Quality classifier: attention-based multiple-instance learning over the passages of a document.

A document is a bag of passages of at most PASSAGE bytes; every passage of the whole text is encoded. Features of a
passage are shares of character-class pairs (language plays little part in them) and how much its words
repeat. A hidden layer encodes the passage, a gated attention (tanh times sigmoid) weighs it, and the weighted sum of
all encodings is scored by a logistic layer. Only document labels train it, by gradient descent on the
driver, from a bounded sample of labelled rows, each with all its passages. Documents score map-side.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import spread, text_of

PASSAGE = 512
#: Labelled rows that train, at most, and passages that they have together, at most (0.8 KB each on the driver).
TRAIN_ROWS = 4000
TRAIN_PASSAGES = 100_000
#: Passages of a step of training, unless one document has more.
STEP_PASSAGES = 8192
N_CLASSES = 20
HIDDEN = 24
EPOCHS = 60
_CLASS = np.full(256, 1, np.uint8)  # letters of other scripts and accents
for _chars, _kind in ((b"abcdefghijklmnopqrstuvwxyz", 0), (b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", 2), (b"0123456789", 3), (b" \t", 4), (b"\n\r", 5), (b".", 6), (b",", 7), (b"!", 8), (b"?", 9), (b"|", 10), (b"*", 11), (b"#", 12), (b"$%&", 13), (b"<>{}[]()", 14), (b"=_+-", 15), (b"\"'`", 16), (b":;", 17), (b"/\\@", 18)):
    _CLASS[list(_chars)] = _kind
_CLASS[:9] = 19
_CLASS[127] = 19
_WORD = re.compile(rb"[^\x20\x09-\x0D]+")
EXTRAS = 6
WIDTH = N_CLASSES * N_CLASSES + EXTRAS


def passages(text: str) -> np.ndarray:
    """Features of every passage of a whole text, one row each; an empty text is one passage of zeros."""
    raw = text.encode("utf-8", "replace")
    n = len(raw)
    if not n:
        return np.zeros((1, WIDTH), np.float32)
    kinds = _CLASS[np.frombuffer(raw, np.uint8)].astype(np.int64)
    bags = -(-n // PASSAGE)
    own = np.arange(n) // PASSAGE
    pair = kinds.copy() * N_CLASSES
    pair[:-1] += kinds[1:]
    pair[-1] += 5  # the end counts as a line's end
    out = np.bincount(own * (N_CLASSES * N_CLASSES) + pair, minlength=bags * N_CLASSES * N_CLASSES).reshape(bags, -1).astype(np.float32)
    lengths = np.bincount(own, minlength=bags).astype(np.float32)
    spans = [(m.start(), m[0]) for m in _WORD.finditer(raw)]
    extra = np.zeros((bags, EXTRAS), np.float32)
    if spans:
        at = np.array([a for a, _ in spans]) // PASSAGE
        seen: dict[bytes, int] = {}
        code = np.array([seen.setdefault(w, len(seen)) for _, w in spans])
        count = np.bincount(at, minlength=bags)
        some = np.maximum(count, 1)
        same = np.zeros(len(code), bool)
        same[1:] = code[1:] == code[:-1]
        extra[:, 0] = np.bincount(at, same, bags) / some
        extra[:, 1] = np.bincount(np.unique(at * len(seen) + code) // len(seen), minlength=bags) / some
        extra[:, 2] = np.bincount(at, [len(w) for _, w in spans], bags) / some / 20
        length = np.array([len(w) for _, w in spans])
        extra[:, 3] = np.bincount(at, length > 25, bags) / some
        line_seen: set[bytes] = set()
        again = np.zeros(bags, np.float32)
        begin = 0
        for line in raw.split(b"\n"):
            if line in line_seen:
                again[begin // PASSAGE] += len(line) + 1
            elif line:
                line_seen.add(line)
            begin += len(line) + 1
            if begin >= n:
                break
        extra[:, 4] = np.minimum(again / lengths, 1)
    extra[:, 5] = min(1.0, np.log1p(n) / 12)
    return np.concatenate([np.sqrt(out / lengths[:, None]), extra], 1)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


class Model:
    """Parameters: encoder (w, b), gated attention (v, u, a), output (c, d), and the mean and scale of features."""

    NAMES = ("w", "b", "v", "u", "a", "c", "d")

    def __init__(self, seed: int = 0) -> None:
        rng = np.random.default_rng(seed)
        h = HIDDEN
        self.w, self.b = rng.normal(0, WIDTH**-0.5, (WIDTH, h)), np.zeros(h)
        self.v, self.u, self.a = rng.normal(0, h**-0.5, (h, h)), rng.normal(0, h**-0.5, (h, h)), np.zeros(h)
        self.c, self.d = rng.normal(0, h**-0.5, h), np.zeros(1)
        self.mean, self.scale = np.zeros(WIDTH), np.ones(WIDTH)

    def forward(self, x: np.ndarray, starts: np.ndarray) -> tuple:
        """x: passages of all bags; starts: first passage of each bag."""
        z = np.tanh((x - self.mean) / self.scale @ self.w + self.b)
        t, s = np.tanh(z @ self.v), _sigmoid(z @ self.u)
        e = (t * s) @ self.a
        bag = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(x))))
        e = np.exp(e - np.maximum.reduceat(e, starts)[bag])
        weight = e / np.add.reduceat(e, starts)[bag]
        m = np.add.reduceat(z * weight[:, None], starts)
        return z, t, s, weight, bag, m, _sigmoid(m @ self.c + self.d)

    def score(self, x: np.ndarray, starts: np.ndarray) -> np.ndarray:
        return self.forward(x, starts)[-1]

    def gradient(self, x: np.ndarray, starts: np.ndarray, y: np.ndarray, importance: np.ndarray, decay: float) -> dict[str, np.ndarray]:
        z, t, s, weight, bag, m, p = self.forward(x, starts)
        g = (p - y) * importance / importance.sum()
        gm = g[:, None] * self.c
        per = (z * gm[bag]).sum(1)
        ge = weight * (per - np.add.reduceat(weight * per, starts)[bag])
        gt, gs = ge[:, None] * self.a * s * (1 - t * t), ge[:, None] * self.a * t * s * (1 - s)
        gz = (weight[:, None] * gm[bag] + gt @ self.v.T + gs @ self.u.T) * (1 - z * z)
        scaled = (x - self.mean) / self.scale
        return {"w": scaled.T @ gz + decay * self.w, "b": gz.sum(0), "v": z.T @ gt, "u": z.T @ gs, "a": (t * s).T @ ge, "c": m.T @ g + decay * self.c, "d": g.sum(keepdims=True)}


def _steps(order: np.ndarray, bags: list[np.ndarray], batch: int) -> Iterator[list[int]]:
    """`order` in runs of at most `batch` bags and STEP_PASSAGES passages; a larger bag is a run of its own."""
    rows, count = [], 0
    for i in order.tolist():
        if rows and (len(rows) == batch or count + len(bags[i]) > STEP_PASSAGES):
            yield rows
            rows, count = [], 0
        rows.append(i)
        count += len(bags[i])
    if rows:
        yield rows


def fit(bags: list[np.ndarray], labels: list[int], epochs: int = EPOCHS, batch: int = 128, rate: float = 0.004, decay: float = 1e-4, seed: int = 0) -> Model:
    """Adam on the log loss of document labels; both classes weigh the same."""
    model = Model(seed)
    if not bags:
        return model
    n = sum(map(len, bags))
    model.mean = sum(b.sum(0, dtype=float) for b in bags) / n
    model.scale = np.maximum(np.sqrt(sum(((b - model.mean) ** 2).sum(0) for b in bags) / n), 0.02)
    y = np.asarray(labels, float)
    share = np.bincount(y.astype(int), minlength=2) / len(y)
    importance = np.where(y == 1, 0.5 / max(share[1], 1e-9), 0.5 / max(share[0], 1e-9))
    rng = np.random.default_rng(seed)
    first, second, step = {}, {}, 0
    for epoch in range(epochs):
        order = rng.permutation(len(bags))
        for rows in _steps(order, bags, batch):
            sizes = [len(bags[i]) for i in rows]
            g = model.gradient(np.concatenate([bags[i] for i in rows]), np.cumsum([0, *sizes[:-1]]), y[rows], importance[rows], decay)
            step += 1
            speed = rate * 0.5 * (1 + np.cos(np.pi * epoch / epochs))
            for k, v in g.items():
                first[k] = 0.9 * first.get(k, 0) + 0.1 * v
                second[k] = 0.999 * second.get(k, 0) + 0.001 * v * v
                setattr(model, k, getattr(model, k) - speed * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8))
    return model


def score_texts(model: Model, texts: list[str]) -> list[float]:
    """Scores of whole texts; texts are scored in groups of bounded size."""
    out: list[float] = []
    held: list[np.ndarray] = []
    count = 0
    for t in texts:
        held.append(passages(t))
        count += len(held[-1])
        if count > 4000:
            out += model.score(np.concatenate(held), np.cumsum([0, *map(len, held[:-1])])).tolist()
            held, count = [], 0
    if held:
        out += model.score(np.concatenate(held), np.cumsum([0, *map(len, held[:-1])])).tolist()
    return out


def fold(column: str = "doc_id"):
    """crc32 of the id's decimal digits, mod 4."""
    return F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(4))


def _chosen(sizes: list[tuple[int, int]], room: int) -> set[int]:
    """Ids of (id, passages), in their order, whose passages fit into `room` together; ids that alone exceed it are left out."""
    out, used = set(), 0
    for i, n in sizes:
        if n > room:
            continue
        used += n
        if used > room:
            break
        out.add(i)
    return out


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", rows: int = TRAIN_ROWS, room: int = TRAIN_PASSAGES, condition=None) -> Model:
    """A model from labelled documents, each with its whole text: the least by hash of the id, at most `rows` and `room` passages.

    A text with more than `room` passages does not train. Rows with a null id or label, or outside `condition`, are left out.
    Without rows every score is one half or so.
    """
    known = labels.filter(F.col(id_col).isNotNull() & F.col(label_col).isin(0, 1))
    if condition is not None:
        known = known.filter(condition)
    order = F.xxhash64(F.col("doc_id").cast("long"))
    picked = known.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("label")).orderBy(order, "doc_id", "label").limit(rows)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text"))
    # `picked` has `rows` rows at most, so it may be broadcast and brought to the driver
    labelled = [(r.doc_id, r.label) for r in picked.collect()]
    picked = docs.sparkSession.createDataFrame(labelled, "doc_id long, label int")
    found = texts.join(F.broadcast(picked), "doc_id")
    passage_count = F.greatest(F.ceil(F.octet_length("text") / PASSAGE), F.lit(1)).cast("long")
    counts = found.groupBy("doc_id").agg(F.sum(passage_count).alias("n"))
    size = {r.doc_id: r.n for r in counts.collect()}
    chosen = _chosen([(i, size[i]) for i in dict.fromkeys(i for i, _ in labelled) if i in size], room)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):  # one row at a time: a bag may be large
                bag = passages(b.column(2)[i].as_py()).astype(np.float16).tobytes()
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, 1), b.column(1).slice(i, 1), pa.array([bag], pa.binary())], ["doc_id", "label", "bag"])

    some = docs.sparkSession.createDataFrame([x for x in labelled if x[0] in chosen], "doc_id long, label int")
    bags = texts.join(F.broadcast(some), "doc_id").select("doc_id", "label", "text").mapInArrow(run, "doc_id long, label int, bag binary")
    got = sorted(((r.doc_id, r.label, bytes(r.bag)) for r in bags.toLocalIterator()))
    return fit([np.frombuffer(b, np.float16).reshape(-1, WIDTH) for *_, b in got], [lab for _, lab, _ in got])


def score_documents(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.7) -> DataFrame:
    """(doc_id, score, predicted): a row for each row of `docs`, from its whole text alone.

    Null text counts as empty and is scored too. Null ids and repeated rows stay. An empty table gives an empty result;
    other columns play no part.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score_texts(shared.value, b.column(1).to_pylist()), pa.float64())], ["doc_id", "score"])

    rows = spread(docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text")))
    return rows.mapInArrow(run, "doc_id long, score double").withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def keep_good(docs: DataFrame, model: Model, text_col: str = "text", threshold: float = 0.7) -> DataFrame:
    """Rows of `docs` that the model does not reject, with all their columns as they are.

    A null text is judged as the empty one. Repeated rows are judged alike, so all stay or go. An empty table gives an empty one.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            good = np.array(score_texts(shared.value, [t or "" for t in b.column(at).to_pylist()])) >= threshold
            yield b.filter(pa.array(good, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
