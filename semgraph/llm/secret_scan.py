"""Secret scans: candidate strings by pattern, false positives removed by a random forest.

Candidates are long unbroken runs that are no plain word, values assigned to or beside a word such as `password` (of any
length and alphabet), passwords in URLs, and key blocks. The forest judges each by its length,
character transitions, dictionary coverage, the path of its document and the words beside it. It is trained on
labelled findings (`labelled_findings` makes a set from stated kinds of secrets and of look-alikes;
users pass their own), on the driver, from a bounded number of them.
"""

from __future__ import annotations

import bisect
import functools
import hashlib
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import spread, text_of

#: Words of identifiers and prose that make a run less random.
DICTIONARY = (
    "account action address admin alpha amount api app archive array asset auth backup base batch beta block body build button cache call case chain change check class "
    "client cloud code color column common config connect content control copy count create data database date debug default delete demo deploy device dev direct document domain "
    "down driver dummy edit email enable engine entry error event example export fake field file filter final find first folder font form format frame function group handler "
    "hash header hello help home host http https icon image import index info input insert internal item java job json key label language last layer layout level library line "
    "link list load local lock log login long main manager map master memory menu message meta method mode model module month name net network new node note null number "
    "object offer option order package page panel parent parse password path pattern placeholder plain player plugin point policy port post print private process product profile project "
    "property public query queue quick random read record redirect region release remote render report request resource response rest result return root row sample save scale scan schema script search "
    "section select self send sequence server service session setting shared show sign simple single site size skip sort source space spec split stack start state static status "
    "step stop storage store stream string style submit success suite support switch sync system table target task template test text theme thread time title tool total trace track "
    "transform tree trigger true type undefined unit unknown update upload user util value variable vector vendor version video view visible wait warning weight widget window word work "
    "world wrapper write year your zero zone"
).split()
#: Words beside a candidate that speak for a secret, and against.
FOR = ("token", "secret", "password", "passwd", "pwd", "api", "apikey", "key", "auth", "authorization", "bearer", "credential", "credentials", "access", "private", "client")
AGAINST = ("commit", "sha", "sha1", "sha256", "md5", "checksum", "digest", "hash", "etag", "uuid", "guid", "id", "revision", "rev", "integrity", "card", "order", "phone", "example", "image", "version", "build", "trace", "session", "file", "path")
PATH_HINTS = ("test", "example", "sample", "doc", "mock", "fixture", "lock", "vendor", "min.js", "config", "env", "secret", "prod", "src")
#: Longest part of a candidate and of its surroundings that features look at: transitions use the whole run.
CONTEXT = 48
RUN = re.compile(r"[A-Za-z0-9+/_=\-]{16,}(?:\.[A-Za-z0-9_\-]{16,}){0,2}")
BLOCK = re.compile(r"-----BEGIN [A-Z0-9 ]{0,30}PRIVATE KEY(?: BLOCK)?-----[^-]*(?:-(?!----)[^-]*)*-----END [A-Z0-9 ]{0,30}PRIVATE KEY(?: BLOCK)?-----")
MASK = "[SECRET]"
#: A word that speaks for a secret (whole, or a part of a name), the rest of the name, what assigns, and the value.
ASSIGNED = re.compile(
    r"(?:(?<![A-Za-z])|(?<=[a-z])(?=[A-Z]))(?i:" + "|".join(sorted(FOR, key=len, reverse=True)) + r")s?(?![a-z])(?:[_.\-]?[A-Za-z0-9]{1,40}(?=[\w.\-]*[\"'\]]{0,2}[ \t]{0,3}[:=])){0,4}"
    r"[\"'\]]{0,2}[ \t]{0,3}(?P<sign>:=|=>|->|[:=]|is(?=[ \t])|)[ \t]{0,3}"
    r"(?:\"(?P<a>[^\"\n]+)\"|'(?P<b>[^'\n]+)'|`(?P<c>[^`\n]+)`|[\"'`]?(?P<d>[^\s\"'`:=]\S*))"
)
IN_URL = re.compile(r"://[^\s/:@]*:([^\s/?#\"'<>]+)@")
URL_START = re.compile(r"[A-Za-z][A-Za-z0-9+.\-]*://")
_NAMES = re.compile("(?:" + "|".join(FOR) + r")s?[:=]*", re.IGNORECASE)
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")
_WORDS = re.compile(r"[A-Za-z]+\d*")
_CLASS = np.full(256, 5, np.int64)
for _chars, _kind in ((b"abcdef", 0), (b"ghijklmnopqrstuvwxyz", 1), (b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", 2), (b"0123456789", 3), (b"-_", 4)):
    _CLASS[list(_chars)] = _kind

FEATURES = (
    ["length", "log_length", "entropy", "distinct", "longest_same", "coverage", "vowels", "hex_only", "digits_only", "upper_only", "parts", "dotted", "padded", "length_is_key_size", "block", "in_url", "placeholder", "spaces"]
    + [f"share_{i}" for i in range(6)]
    + [f"move_{i}_{j}" for i in range(6) for j in range(6)]
    + ["assigned", "quoted", "for", "against", "nearest"]
    + [f"for_{w}" for w in FOR] + [f"against_{w}" for w in AGAINST] + [f"path_{w}" for w in PATH_HINTS]
)


def _mixed(w: str) -> bool:
    digits = sum(map(w.count, "0123456789"))
    return 0 < digits < len(w) or re.search(r"[a-z][A-Z]+[a-z]", w) is not None


def _assigned(text: str) -> Iterator[tuple[int, int, int]]:
    """(start of the name, start, end) of values assigned to or beside words that speak for a secret."""
    at = 0
    while m := ASSIGNED.search(text, at):
        group = next(g for g in "abcd" if m[g])
        a, z = m.span(group)
        at = z
        if group == "d":
            value = m[group]
            if value.startswith(MASK):
                continue
            inner = ASSIGNED.search(text, a, z) if not m["sign"] else None
            if _NAMES.fullmatch(value) or (inner and inner["sign"]):
                at = a  # a name, whose value follows
                continue
            z = a + len(value.rstrip(",;.)]}>\"'`"))
            if URL_START.match(value):
                at = a  # its password is a candidate of its own
                continue
        elif m[group] == MASK:
            continue
        if a < z:
            yield m.start(), a, z


def find_candidates(text: str) -> list[tuple[int, int]]:
    """(start, end) of key blocks, passwords in URLs, values beside words that speak for a secret, and runs that hold digits and
    letters or change case inside; in order, not overlapping."""
    blocks = [m.span() for m in BLOCK.finditer(text)]
    taken = [(a, z, a) for a, z in blocks]
    for m in IN_URL.finditer(text):
        if m[1] != MASK:
            taken.append((*m.span(1), m.start(1)))
    for lead, a, z in _assigned(text):
        i = bisect.bisect_left(blocks, (z,)) - 1
        if i < 0 or blocks[i][1] <= a:
            taken.append((a, z, lead))
    out: list[tuple[int, int]] = []
    leads: list[int] = []
    for a, z, lead in sorted(taken, key=lambda x: (x[0], -x[1])):
        if out and a < out[-1][1]:
            if z > out[-1][1]:
                out[-1] = (out[-1][0], z)  # overlapping values are one
        else:
            out.append((a, z))
            leads.append(lead)
    runs, i = [], 0
    for m in RUN.finditer(text):
        a, end = m.span()
        while i < len(out) and out[i][1] <= a:
            i += 1
        j = i
        while a < end:  # what of the run is before, between and after values and their names
            z = min(end, max(a, min(leads[j], out[j][0]))) if j < len(out) and out[j][0] < end else end
            if z - a >= 16 and _mixed(text[a:z]):
                runs.append((a, z))
            if z == end:
                break
            a, j = max(a, out[j][1]), j + 1
    return sorted(out + runs)


def features(text: str, start: int, end: int, path: str) -> list[float]:
    w = text[start:end]
    raw = np.frombuffer(w.encode("ascii", "replace"), np.uint8)
    n = len(raw)
    counts = np.bincount(raw, minlength=256)
    p = counts[counts > 0] / n
    kinds = _CLASS[raw]
    moves = np.bincount(kinds[:-1] * 6 + kinds[1:], minlength=36) / max(1, n - 1)
    changes = np.flatnonzero(np.diff(raw))
    same = int(np.diff(np.concatenate([[-1], changes, [n - 1]])).max()) if n > 1 else 1
    low = w.lower()
    covered = sum(len(m) for m in _dictionary().findall(low)) / n
    before, after = _CAMEL.sub("_", text[max(0, start - CONTEXT) : start]).lower(), text[end : end + CONTEXT // 2].lower()
    near = [x for m in _WORDS.findall(before)[-4:] for x in m.split("_")]
    near_after = _WORDS.findall(after)[:2]
    last = before.rstrip("\"'` ")
    said = [x in near for x in FOR], [x in near or x in near_after for x in AGAINST]
    nearest = next((1.0 if x in FOR else -1.0 for x in reversed(near) if x in FOR or x in AGAINST), 0.0)
    parts = re.split(r"[-_/.+]", w)
    place = path.lower()
    return [
        n, math.log(n), float(-(p * np.log2(p)).sum()), len(p) / n, same / n, covered, sum(map(low.count, "aeiou")) / n,
        float(re.fullmatch("[0-9a-f]+|[0-9A-F]+", w) is not None), float(w.isdigit()), float(w == w.upper()), len(parts), float("." in w), float(w.endswith("=")), float(n in (20, 32, 36, 40, 64)), float(w.startswith("-----BEGIN")),
        float(re.search(r"://[^\s/:@]*:$", before) is not None), float(re.search(r"[(\[{<]|\*{3}|\.{3}", w) is not None), w.count(" ") / n,
        *(np.bincount(kinds, minlength=6) / n).tolist(), *moves.tolist(),
        float(last[-1:] in ("=", ":")), float(before[-1:] in "\"'`" and before != ""), float(any(said[0])), float(any(said[1])), nearest,
        *map(float, said[0]), *map(float, said[1]), *(float(h in place) for h in PATH_HINTS),
    ]


@functools.cache
def _dictionary() -> re.Pattern:
    return re.compile("|".join(sorted((w for w in DICTIONARY if len(w) >= 4), key=len, reverse=True)))


def labelled_findings(n: int = 3000, seed: int = 0) -> list[tuple[str, int, int, str, int]]:
    """(text, start, end, path, label): findings of stated kinds, with the surroundings that mark them as secrets or not."""
    rng = np.random.default_rng(seed)
    pick = lambda options: options[int(rng.integers(len(options)))]
    chars = lambda alphabet, k: "".join(alphabet[i] for i in rng.integers(0, len(alphabet), k))
    hexes, digits = "0123456789abcdef", "0123456789"
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    alnum = upper + lower + digits
    word = lambda: chars("aeiounrstldm", int(rng.integers(2, 9)))
    secret_kinds = (
        lambda: chars(hexes, pick((32, 40, 48, 64))), lambda: chars(hexes, 40), lambda: "AKIA" + chars(upper + digits, 16), lambda: "ghp_" + chars(alnum, 36),
        lambda: "sk_live_" + chars(alnum, 24), lambda: chars(alnum + "+/", 40), lambda: chars(alnum, int(rng.integers(20, 64))), lambda: chars(alnum + "-_", 43) + "=",
        lambda: f"eyJ{chars(alnum, 30)}.eyJ{chars(alnum, 60)}.{chars(alnum + '-_', 43)}", lambda: f"xoxb-{chars(digits, 12)}-{chars(alnum, 24)}",
    )
    other_kinds = (
        lambda: chars(hexes, 40), lambda: chars(hexes, 64), lambda: chars(hexes, 32), lambda: "-".join(chars(hexes, k) for k in (8, 4, 4, 4, 12)),
        lambda: "_".join(pick(DICTIONARY) for _ in range(4)) + chars(digits, 2), lambda: "".join(pick(DICTIONARY).title() for _ in range(4)), lambda: "/".join(pick(DICTIONARY) for _ in range(5)) + chars(digits, 1),
        lambda: "x" * int(rng.integers(8, 20)) + chars(digits, 1) + "x" * 8, lambda: "your-" + "-".join(pick(DICTIONARY) for _ in range(3)) + "-here1", lambda: "-".join(pick(DICTIONARY) for _ in range(3)) + "-20" + chars(digits, 2) + "-" + chars(digits, 2),
        lambda: chars(alnum + "+/", int(rng.integers(80, 240))),
    )
    symbols = "!@#$%&*"
    passwords = ("password", "passwd", "pwd", "secret", "credential")
    plain = lambda: pick(DICTIONARY) if rng.random() < 0.5 else word()
    body = lambda: "\n".join(chars(alnum + "+/", 64) for _ in range(int(rng.integers(2, 12))))
    near_secrets = (
        lambda: chars(alnum + symbols, int(rng.integers(7, 16))), lambda: word().title() + chars(digits, int(rng.integers(2, 5))) + pick(symbols), lambda: chars(alnum, int(rng.integers(8, 16))),
        lambda: word() + pick(symbols) + word() + chars(digits, 3), lambda: chars(lower, int(rng.integers(12, 40))), lambda: chars(upper, int(rng.integers(12, 40))), lambda: chars(digits, int(rng.integers(6, 24))),
    )
    near_others = (
        plain, plain, plain, lambda: pick(("none", "null", "true", "false", "required", "undefined", "nil", "string", "optional")), lambda: chars(digits, int(rng.integers(1, 4))),
        lambda: pick(("get", "load", "read")) + "_" + pick(FOR) + "(" + pick(("", word())) + ")", lambda: "${" + pick(FOR).upper() + "}", lambda: "<" + pick(("your-", "")) + pick(FOR) + ">", lambda: "*" * int(rng.integers(3, 12)),
        lambda: "{{ " + pick(FOR) + " }}", lambda: f"{plain()} {plain()} {plain()}",
    )
    out = []
    for i in range(n):
        label = int(rng.random() < 0.5)
        special = rng.random()
        if special < 0.4:
            close, path = "", pick(("src", "src/app", "config/prod", "docs/example", "tests/fixture", "lib", "web")) + str(int(rng.integers(100)))
            if special < 0.04:
                kind = pick(("", "RSA ", "EC ", "OPENSSH ", "ENCRYPTED ", "PGP "))
                end = " BLOCK" if kind == "PGP " else ""
                head = pick(("", "", "Proc-Type: 4,ENCRYPTED\nDEK-Info: AES-128-CBC," + chars(hexes, 32).upper() + "\n\n", "Version: 2\nComment: " + word() + "\n\n"))
                inside = head + body() if label else pick(("...", "<key>", " ".join(plain() for _ in range(12)), "*" * 20))
                lead, value = pick(("", "key: ", "private ", f"{word()} ")), f"-----BEGIN {kind}PRIVATE KEY{end}-----\n{inside}\n-----END {kind}PRIVATE KEY{end}-----"
            elif special < 0.08:
                lead, close = f"{pick(('postgres', 'https', 'mysql', 'ftp', 'amqp'))}://{word()}:", f"@{word()}.{word()}/{word()}"
                value = pick(near_secrets)() if label else pick((lambda: pick(FOR), lambda: "${" + pick(FOR).upper() + "}", lambda: "<" + pick(FOR) + ">", lambda: "***", lambda: chars(digits, 2)))()
                value = value.replace("#", "!")
            elif label:
                value, named = pick(near_secrets)(), pick(passwords) if rng.random() < 0.7 else pick(FOR)
                lead = pick((f'{named} = "', f"{named}: '", f"{named}=", f"{named}: ", f"{named} is ", f"db_{named} = '", f"{named.upper()}=", f"{named} "))
                if lead.endswith(f"{named} ") and re.fullmatch("[a-z]+|[A-Z]+", value):
                    lead = f"{named}: "
            else:
                value, named = pick(near_others)(), pick(FOR)
                lead = pick((f"{named} ", f"{named} ", f"{named} ", f"{named} is ", f"{named}: ", f"{named} = ", f"{named}=", f'{named} = "', f"{named.title()} "))
            close = close or {'"': '"', "'": "'"}.get(lead[-1:], "")
            if rng.random() < 0.15 and "-----" not in value:
                lead, value = lead.upper(), value.upper()
            before = " ".join(word() for _ in range(int(rng.integers(0, 8)))) + " "
            start = len(before) + len(lead)
            out.append((before + lead + value + close + pick(("", " ", "\n", " ### ", " !! ", ",", ";")) + " ".join(word() for _ in range(3)), start, start + len(value), path, label))
            continue
        value = pick(secret_kinds if label else other_kinds)()
        named = pick(FOR)
        other = pick(AGAINST)
        if label:
            lead = pick((f'{named} = "', f'{named} = "', f"{named}: '", f"{named}=", f'"{named}": "', f"{other}_{named} = \"", f"{named.upper()}_{pick(FOR).upper()}=", f"{named} bearer "))
        elif value.startswith(("x", "your")) or rng.random() < 0.15 and not re.fullmatch(r"[0-9a-f]+|[A-Za-z0-9+/]{80,}", value):
            lead = pick((f'{named} = "', f"{named}: ", f"{named}="))  # a placeholder or plain words where a secret might be
        else:
            lead = pick((f"{other} ", f"{other}: ", f'{other} = "', f"{other}=", f"{word()} ", f"{word()} {word()} ", "data:image/png;base64," if len(value) >= 80 else f"{word()}: ", f"{other}/{word()}/"))
        close = {'"': '"', "'": "'"}.get(lead[-1], "")
        if rng.random() < 0.15:
            lead, value = lead.upper(), value.upper()
        before = " ".join(word() for _ in range(int(rng.integers(0, 8)))) + " "
        after = close + pick(("", " ", "\n", "### ", "!! ", ",", ";")) + " ".join(word() for _ in range(3))
        text = before + lead + value + after
        start = len(before) + len(lead)
        path = pick(("src", "src/app", "config/prod", "docs/example", "tests/fixture", "lib", "web")) + str(int(rng.integers(100)))
        out.append((text, start, start + len(value), path, label))
    return out


class Forest:
    """A random forest of binary decision trees on bootstrap samples and random features; nodes in arrays."""

    def __init__(self, trees: int = 40, depth: int = 9, leaf: int = 3, seed: int = 0) -> None:
        self.n_trees, self.depth, self.leaf, self.seed = trees, depth, leaf, seed
        self.trees: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []

    def fit(self, x: np.ndarray, y: np.ndarray) -> Forest:
        rng = np.random.default_rng(self.seed)
        for _ in range(self.n_trees):
            rows = rng.integers(0, len(x), len(x))
            self.trees.append(self._grow(x[rows], y[rows], rng))
        return self

    def _grow(self, x: np.ndarray, y: np.ndarray, rng: np.random.Generator) -> tuple:
        feature, cut, kids, value = [], [], [], []

        def node(rows: np.ndarray, depth: int) -> int:
            me = len(feature)
            feature.append(-1)
            cut.append(0.0)
            kids.append((me, me))
            value.append(float(y[rows].mean()))
            if depth == self.depth or len(rows) < 2 * self.leaf or value[me] in (0.0, 1.0):
                return me
            best = (0.0, -1, 0.0)
            for f in rng.choice(x.shape[1], max(1, int(2 * math.sqrt(x.shape[1]))), replace=False):
                v = x[rows, f]
                order = np.argsort(v, kind="stable")
                s, t = v[order], np.cumsum(y[rows][order])
                n = np.arange(1, len(s))
                ok = (s[1:] > s[:-1]) & (n >= self.leaf) & (len(s) - n >= self.leaf)
                if not ok.any():
                    continue
                left, right = t[:-1], t[-1] - t[:-1]
                gain = left**2 / n + right**2 / (len(s) - n) - t[-1] ** 2 / len(s)
                gain[~ok] = -1
                i = int(gain.argmax())
                if gain[i] > best[0] + 1e-12:
                    best = (float(gain[i]), int(f), float((s[i] + s[i + 1]) / 2))
            if best[1] >= 0:
                feature[me], cut[me] = best[1], best[2]
                low = x[rows, best[1]] <= best[2]
                kids[me] = (node(rows[low], depth + 1), node(rows[~low], depth + 1))
            return me

        node(np.arange(len(x)), 0)
        return np.array(feature), np.array(cut), np.array(kids), np.array(value)

    def predict(self, x: np.ndarray) -> np.ndarray:
        """Mean share of secrets in the leaves that each row reaches."""
        total = np.zeros(len(x))
        every = np.arange(len(x))
        for feature, cut, kids, value in self.trees:
            at = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                f = feature[at]
                at = np.where(f < 0, at, kids[at, (x[every, np.maximum(f, 0)] > cut[at]).astype(np.int64)])
            total += value[at]
        return total / max(1, len(self.trees))


def train(findings: list[tuple[str, int, int, str, int]] | None = None, **params) -> Forest:
    found = findings if findings is not None else labelled_findings()
    x = np.array([features(t, a, b, p) for t, a, b, p, _ in found])
    return Forest(**params).fit(x, np.array([f[4] for f in found], float))


def _judged(forest: Forest, texts: list[str], paths: list[str]) -> Iterator[tuple[int, list[tuple[int, int]], np.ndarray]]:
    spans = [find_candidates(t) for t in texts]
    x = [features(texts[i], a, b, paths[i]) for i, s in enumerate(spans) for a, b in s]
    scores = forest.predict(np.array(x)) if x else np.zeros(0)
    at = 0
    for i, s in enumerate(spans):
        yield i, s, scores[at : at + len(s)]
        at += len(s)


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path_col: str | None = "source", threshold: float = 0.5, forest: Forest | None = None) -> DataFrame:
    """(doc_id, start, length, sha256, score, is_secret): a row for each candidate of each row of `docs`.

    start and length count code points. Null text and null paths count as empty; null ids and repeated rows stay.
    An empty table gives an empty result; other columns play no part.
    """
    model = docs.sparkSession.sparkContext.broadcast(forest or train())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, texts = b.column(0).to_pylist(), b.column(1).to_pylist()
            out = [[] for _ in range(5)]
            for i, spans, scores in _judged(model.value, texts, b.column(2).to_pylist()):
                for (a, z), s in zip(spans, scores.tolist()):
                    for c, v in zip(out, (ids[i], a, z - a, hashlib.sha256(texts[i][a:z].encode()).hexdigest(), s)):
                        c.append(v)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds)], ["doc_id", "start", "length", "sha256", "score"])

    path = text_of(path_col) if path_col and path_col in docs.columns else F.lit("")
    rows = spread(docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text"), path.alias("path")))
    return rows.mapInArrow(run, "doc_id long, start long, length long, sha256 string, score double").withColumn("is_secret", F.col("score") >= threshold)


def mask_secrets(docs: DataFrame, text_col: str = "text", path_col: str = "source", threshold: float = 0.5, mask: str = MASK, forest: Forest | None = None) -> DataFrame:
    """`docs` with each secret in the text replaced by `mask`; all rows and columns stay, null texts too, n_chars follows the text."""
    model = docs.sparkSession.sparkContext.broadcast(forest or train())
    names = docs.columns
    at, path_at = names.index(text_col), names.index(path_col) if path_col in names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(at).to_pylist()
            paths = [p or "" for p in b.column(path_at).to_pylist()] if path_at is not None else [""] * len(texts)
            for i, spans, scores in _judged(model.value, [t or "" for t in texts], paths):
                for (a, z), s in sorted(zip(spans, scores.tolist()), reverse=True):
                    if s >= threshold:
                        texts[i] = texts[i][:a] + mask + texts[i][z:]
            columns = list(b.columns)
            columns[at] = pa.array(texts, pa.string())
            if "n_chars" in names and names.index("n_chars") != at:
                j = names.index("n_chars")
                columns[j] = pa.array([n if t is None else len(t) for t, n in zip(texts, b.column(j).to_pylist())], b.column(j).type)
            yield pa.RecordBatch.from_arrays(columns, names)

    return docs.mapInArrow(run, docs.schema)
