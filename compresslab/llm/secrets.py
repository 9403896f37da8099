"""Secret scan: candidates from whole texts, judged by a random forest trained from labelled findings.

Candidates are (a) runs of 16 and more letters, digits and + / _ - = with a digit and a letter, (b) values assigned to
a word such as token, password or api_key, (c) private-key blocks. Features: length, transitions between classes of
characters, entropy, shares of digits, capitals and hex, coverage by dictionary words, looks of a path, and the
neighbouring words. The forest removes false positives: checksums, commit ids, placeholders, paths, long words.

The dictionary is a public tokenizer's word list, whose path is a parameter; labelled findings may be given as rows
(value, before, after, label), else the forest learns from generated ones, which are the same in every run.

Candidates never overlap: a block goes before an assigned value, and a run loses what these cover. What is found in a text
depends on this text alone, and no value has an upper bound of length. Offsets are characters. Null and empty texts have
no candidates. Repeated rows are scanned each. Empty tables give no
rows. Extra columns are not read by scan and left as they are by redact.
"""

from __future__ import annotations

import bisect
import json
import math
import random
import re
import uuid
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C
from . import words as W

WORD_LIST = "word_bpe_49k.json"
LONGEST = 16
CONTEXT = 48
_RUN = W._lookup(lambda b: b < 0x80 and (chr(b).isalnum() or chr(b) in "+/_-="))
_ALPHA = W._lookup(lambda b: b < 0x80 and chr(b).isalpha())
_SET = W._lookup(lambda b: b in b"=:")
# fixed values: words that name a secret, words that name something else, words of placeholders
SECRET_WORDS = "secret token password passwd pwd apikey api_key api-key access_key private_key client_secret auth credential credentials bearer passphrase"
OTHER_WORDS = "commit sha sha1 sha256 md5 checksum digest hash etag revision blob uuid guid integrity session build version image file path url http https href src id isbn"
PLACEHOLDERS = "your example sample test dummy placeholder changeme change_me xxxx insert replace redacted todo fake foo none null my_ here"
_KEYWORD = re.compile(rb"(?i)(?:secret|token|passw(?:or)?d|passwd|pwd|api[_-]?key|access[_-]?key|private[_-]?key|auth|credentials?|passphrase|bearer)[\w-]{0,16}[\"']?\s*$")
_STOP = W._lookup(lambda b: b in b" \t\n\r\f\v\"'`,;<>(){}[]")  # a value ends before these
_KNOWN = re.compile(r"^(?:AKIA[0-9A-Z]{16}$|gh[pousr]_[A-Za-z0-9]{20,}|xox[abprs]-|sk_live_|AIza[\w-]{30,}|eyJ[\w-]{10,}|glpat-)")
_PEM = re.compile(rb"-----(BEGIN|END) [A-Z ]*PRIVATE KEY-----")


def dictionary(path: str | None = None) -> frozenset[str]:
    """Whole words of four letters and more of a public tokenizer's vocabulary."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path(WORD_LIST)
    with open(path, encoding="utf-8") as f:
        vocabulary = json.load(f)["model"]["vocab"]
    return frozenset(w[:-4] for w in vocabulary if w.endswith("</w>") and len(w) >= 8 and w[:-4].isascii() and w[:-4].isalpha())


def coverage(value: str, known: frozenset[str]) -> float:
    """Share of the letters that dictionary words cover, longest first from the left."""
    letters = covered = 0
    for run in re.findall(r"[a-z]+", re.sub(r"(?<=[a-z])(?=[A-Z])", " ", value).lower()):
        letters += len(run)
        i = 0
        while i < len(run):
            for n in range(min(LONGEST, len(run) - i), 3, -1):
                if run[i : i + n] in known:
                    covered += n
                    i += n
                    break
            else:
                i += 1
    return covered / letters if letters else 0.0


def _kind(c: str) -> int:
    return 0 if c.islower() else 1 if c.isupper() else 2 if c.isdigit() else 3


_SECRET, _OTHER, _PLACE = (tuple(x.split()) for x in (SECRET_WORDS, OTHER_WORDS, PLACEHOLDERS))


def features(value: str, before: str, after: str, known: frozenset[str]) -> list[float]:
    n = len(value)
    kinds = [_kind(c) for c in value]
    m = len(kinds)
    counts = Counter(value)
    entropy = -sum(c / n * math.log2(c / n) for c in counts.values())
    low, left, right = value.lower(), before.lower()[-CONTEXT:], after.lower()[:CONTEXT]
    near = re.findall(r"[a-z0-9_-]+", left)
    close = near[-3:]
    pairs = sum(abs(ord(a) - ord(b)) == 1 for a, b in zip(value, value[1:])) / max(1, n - 1)
    return [
        float(n), entropy, entropy / math.log2(max(2, n)),
        sum(a != b for a, b in zip(kinds, kinds[1:])) / max(1, m - 1),
        kinds.count(2) / m, kinds.count(1) / m, kinds.count(0) / m, kinds.count(3) / m,
        float(all(c in "0123456789abcdef" for c in low)), coverage(value, known),
        float(value.count("/") + value.count("\\")), float(value.count(".")), float("://" in value or left.endswith(("/", "\\", "."))),
        float(any(w in s for s in close for w in _SECRET)), float(any(s in _OTHER for s in close)),
        float(any(w in low for w in _PLACE)), float(any(w in left or w in right for w in ("example", "placeholder", "dummy", "checksum"))),
        float(bool(re.search(r"[=:]\s*[\"'`]?$", before))), float(before[-1:] in "\"'`" and before != ""), float(bool(_KNOWN.match(value))),
        max(counts.values()) / n, pairs, float(value.count("-") + value.count("_")), float(bool(re.fullmatch(r"[0-9a-f]{8}(-[0-9a-f]{4}){3}-[0-9a-f]{12}", low))),
    ]


def labelled_findings(n: int = 3000, seed: int = 11) -> list[tuple[str, str, str, int]]:
    """Generated findings (value, before, after, label), half of them secrets; the same for equal arguments."""
    rng = random.Random(seed)
    low, up, dig = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    pick = lambda alphabet, k: "".join(rng.choice(alphabet) for _ in range(k))
    syllable = lambda: rng.choice(("th", "er", "on", "an", "re", "in", "ver", "keit", "tion", "ou", "ment", "ción", "ent", "ha", "st", "ai"))
    word = lambda: rng.choice(("config", "server", "user", "data", "index", "page", "value", "report", "image", "module", "service", "handler", "session"))
    prose = lambda: " ".join("".join(syllable() for _ in range(rng.randint(1, 4))) for _ in range(rng.randint(2, 7)))
    names = [w for w in _SECRET if w not in ("bearer",)]
    out = []
    for i in range(n):
        op, quote = rng.choice((" = ", "=", ": ", ":", " => ")), rng.choice(('"', "'", ""))
        if i % 2:
            name = rng.choice(("", "aws_", "db_", "my_", "app.", "")) + rng.choice(names)
            name = rng.choice((name, name.upper(), name.title()))
            value = rng.choice((
                lambda: pick("0123456789abcdef", rng.choice((32, 40, 40, 48, 64))), lambda: pick("0123456789ABCDEF", rng.choice((32, 40, 64))),
                lambda: pick(low + up + dig + "+/", rng.choice((24, 32, 40, 44, 64))), lambda: pick(low + up + dig, rng.randint(20, 48)),
                lambda: "AKIA" + pick(up + dig, 16), lambda: rng.choice(("ghp_", "gho_", "ghs_")) + pick(low + up + dig, 36), lambda: "sk_live_" + pick(low + up + dig, 24),
                lambda: pick(low + up + dig + "!@#$%^&*", rng.randint(9, 20)), lambda: "xoxb-" + pick(dig, 11) + "-" + pick(low + up + dig, 24),
                lambda: "eyJ" + pick(low + up + dig + "-_", 60), lambda: str(uuid.UUID(int=rng.getrandbits(128))),
            ))()
            bare = _KNOWN.match(value) and rng.random() < 0.4
            out.append((value, prose() + (" " if bare else f" {name}{op}{quote}"), ("" if bare else quote) + " " + prose(), 1))
        else:
            choice = rng.randrange(11)
            hexes = pick("0123456789abcdef", rng.choice((32, 40, 64)))
            other = rng.choice(("commit ", "sha256:", "md5: ", "checksum = ", "etag=\"", "revision ", "sha1 ", "digest: ", "build ", "integrity="))
            value, left = [
                lambda: (hexes, other), lambda: (rng.choice(("your_token_here_1", "xxxxxxxxxxxxxxxx1", "changeme12345", "example-token-123", "<password1>", "insert_api_key_0", "test_password_1")), f"{rng.choice(names)}{op}{quote}"),
                lambda: ("/".join(word() for _ in range(rng.randint(3, 6))) + pick(dig, 2), "path "), lambda: ("/usr/lib/x86_64-linux-gnu/" + word() + pick(dig, 1), "in "),
                lambda: ("".join(w().title() for w in (word,) * 3) + pick(dig, rng.randint(1, 3)), " "), lambda: ("_".join(word() for _ in range(3)) + "_" + pick(dig, 4), " "),
                lambda: (str(uuid.UUID(int=rng.getrandbits(128))), rng.choice(("id=", "uuid: ", "request "))), lambda: ("".join(syllable() for _ in range(8)) + pick(dig, 2), " "),
                lambda: (f"{word()}-{word()}-{rng.randint(1, 9)}-{rng.randint(0, 20)}-{rng.randint(0, 99)}", "version "), lambda: (f"{rng.choice(names)}_{word()}_{word()}1", f"{rng.choice(names)}{op}"), lambda: ("-" * rng.randint(3, 20) + "=" * 10 + "a1", " "),
            ][choice]()
            out.append((value, prose() + " " + left, quote + " " + prose(), 0))
    return out


class Forest:
    """Random forest of binary trees on numpy; grown once from a bounded list, shipped as arrays."""

    def __init__(self, x: np.ndarray, y: np.ndarray, trees: int = 40, depth: int = 9, least: int = 4, seed: int = 5):
        rng = np.random.default_rng(seed)
        self.trees = []
        for _ in range(trees):
            at = rng.integers(0, len(y), len(y))
            self.trees.append(self._grow(x[at], y[at].astype(float), rng, depth, least))

    def _grow(self, x, y, rng, depth, least):
        nodes: list[tuple] = []

        def grow(rows, left) -> int:
            me = len(nodes)
            nodes.append((-1, 0.0, 0, 0, float(y[rows].mean()) if len(rows) else 0.5))
            if left == 0 or len(rows) < 2 * least or nodes[me][4] in (0.0, 1.0):
                return me
            best = (1e-9, -1, 0.0)
            share = nodes[me][4]
            for f in rng.choice(x.shape[1], max(1, int(math.sqrt(x.shape[1])) + 1), replace=False):
                order = rows[np.argsort(x[rows, f], kind="stable")]
                v, s = x[order, f], np.cumsum(y[order])
                n = np.arange(1, len(order))
                cut = (v[1:] > v[:-1]) & (n >= least) & (len(order) - n >= least)
                if not cut.any():
                    continue
                p, q = s[:-1] / n, (s[-1] - s[:-1]) / (len(order) - n)
                gain = share * (1 - share) - (n * p * (1 - p) + (len(order) - n) * q * (1 - q)) / len(order)
                i = int(np.argmax(np.where(cut, gain, -1)))
                if gain[i] > best[0]:
                    best = (gain[i], int(f), float((v[i] + v[i + 1]) / 2))
            if best[1] < 0:
                return me
            _, f, t = best
            under = x[rows, f] <= t
            a, b = grow(rows[under], left - 1), grow(rows[~under], left - 1)
            nodes[me] = (f, t, a, b, nodes[me][4])
            return me

        grow(np.arange(len(y)), depth)
        return tuple(np.array(c) for c in zip(*nodes))

    def predict(self, x: np.ndarray) -> np.ndarray:
        total = np.zeros(len(x))
        for f, t, a, b, value in self.trees:
            node = np.zeros(len(x), dtype=np.int64)
            while True:
                inner = f[node] >= 0
                if not inner.any():
                    break
                go = x[np.arange(len(x)), np.maximum(f[node], 0)] <= t[node]
                node = np.where(inner, np.where(go, a[node], b[node]), node)
            total += value[node]
        return total / len(self.trees)


def train(findings=None, words: frozenset[str] | None = None) -> tuple[Forest, frozenset[str]]:
    """A forest and its dictionary. findings: rows (value, before, after, label); generated ones if None."""
    words = dictionary() if words is None else words
    findings = labelled_findings() if findings is None else findings
    x = np.array([features(v, b, a, words) for v, b, a, _ in findings])
    return Forest(x, np.array([f[3] for f in findings])), words


def candidates(raw: np.ndarray, offsets: np.ndarray) -> list[tuple[int, int, int, str]]:
    """(row, begin, end, kind) in bytes of all candidates, ordered, without overlaps."""
    if not len(raw):
        return []
    edge = np.zeros(len(raw) + 2, dtype=np.int8)
    edge[1:-1] = _RUN[raw]
    change = np.diff(edge)
    # a run that goes on in the next text is cut between them
    ends = np.unique(offsets[(offsets > 0) & (offsets < len(raw))])
    ends = ends[(edge[ends] == 1) & (edge[ends + 1] == 1)]
    begin, end = (np.sort(np.concatenate([np.flatnonzero(change == step), ends])) for step in (1, -1))
    long = end - begin >= 16
    begin, end = begin[long], end[long]
    digits, letters = (np.concatenate([[0], np.cumsum(t[raw])]) for t in (W._DIGIT, _ALPHA))
    mixed = (digits[end] > digits[begin]) & (letters[end] > letters[begin])
    begin, end = begin[mixed], end[mixed]
    data = raw.tobytes()
    found: dict[int, list[tuple[int, int, int, str]]] = {}

    def row_of(b):
        return int(np.searchsorted(offsets, b, side="right") - 1)

    def add(b, e, kind):
        found.setdefault(row_of(b), []).append((b, e, {"block": 0, "assigned": 1, "token": 2}[kind], kind))

    # every match is bound to its own text: nothing depends on the texts beside it
    for row in sorted({row_of(m.start()) for m in re.finditer(b"PRIVATE KEY-----", data)}):
        opened = None
        for m in _PEM.finditer(data, int(offsets[row]), int(offsets[row + 1])):
            if m[1] == b"BEGIN":
                opened = m
            elif opened and m.start() - opened.end() >= 16:
                add(opened.start(), m.end(), "block")
                opened = None
    stops = np.flatnonzero(_STOP[raw])
    for at in np.flatnonzero(_SET[raw]).tolist():
        row = row_of(at)
        low, high = int(offsets[row]), int(offsets[row + 1])
        head = data[max(low, at - 40) : at]
        if _KEYWORD.search(head):
            skip = at + 1
            while skip < high and data[skip : skip + 1] in (b">", b" ", b"="):
                skip += 1
            if skip < high and data[skip : skip + 1] in (b'"', b"'", b"`"):
                skip += 1
            stop = np.searchsorted(stops, skip)
            stop = min(high, int(stops[stop])) if stop < len(stops) else high
            if stop - skip >= 6:
                add(skip, stop, "assigned")
    for b, e in zip(begin.tolist(), end.tolist()):
        while b < e and data[b : b + 1] in (b"=", b"-", b"_", b"/"):  # marks before a value
            b += 1
        while e > b and data[e - 1 : e] in (b"-", b"_", b"/"):
            e -= 1
        if e - b >= 16:
            add(b, e, "token")
    out = []
    for row in sorted(found):
        cover: list[tuple[int, int, str]] = []  # sorted, apart from each other

        def over(b, e, cover=cover):
            i = bisect.bisect_left(cover, (b,))
            i -= i > 0 and cover[i - 1][1] > b
            while i < len(cover) and cover[i][0] < e:
                yield cover[i]
                i += 1

        # whole blocks first, then assigned values; a run loses what these cover and stays if it is long enough then
        runs = []
        for b, e, rank, kind in sorted(found[row], key=lambda s: (s[2], s[0], -s[1])):
            if rank < 2:
                if next(over(b, e), None) is None:
                    bisect.insort(cover, (b, e, kind))
            else:
                edges = [b, *(x for k in over(b, e) for x in k[:2]), e]
                runs += [(lo, hi, kind) for lo, hi in zip(edges[::2], edges[1::2]) if hi - lo >= 16 and (len(edges) == 2 or _mixed(data[lo:hi]))]
        out += [(row, *k) for k in sorted(cover + runs)]
    return out


def _mixed(run: bytes) -> bool:
    return any(_ALPHA[c] for c in run) and any(W._DIGIT[c] for c in run)


def judge(column: pa.Array, model: tuple[Forest, frozenset[str]]):
    """(row, begin, end in characters, kind, value, score) of every candidate of a column of texts."""
    forest, known = model
    raw, offsets = C.text_bytes(column)
    found = candidates(raw, offsets)
    if not found:
        return []
    data = raw.tobytes()
    rows, x = [], []
    place = (-1, 0, 0)
    for row, b, e, kind in found:
        low = int(offsets[row])
        if place[0] != row:
            place = (row, low, 0)
        chars = place[2] + len(data[place[1] : b].decode("utf-8", "replace"))
        value = data[b:e].decode("utf-8", "replace")
        place = (row, b, chars)
        before = data[max(low, b - 2 * CONTEXT) : b].decode("utf-8", "ignore")
        after = data[e : min(int(offsets[row + 1]), e + 2 * CONTEXT)].decode("utf-8", "ignore")
        rows.append((row, chars, chars + len(value), kind, value))
        x.append(features(value, before, after, known))
    score = forest.predict(np.array(x))
    return [(*r, 1.0 if r[3] == "block" else float(s)) for r, s in zip(rows, score)]


def scan(docs: DataFrame, model=None, threshold: float = 0.5) -> DataFrame:
    """doc_id, begin_char, end_char, kind, value_sha256, score, secret of every candidate; values themselves stay out."""
    import hashlib

    shared = docs.sparkSession.sparkContext.broadcast(train() if model is None else model)
    names = ["doc_id", "begin_char", "end_char", "kind", "value_sha256", "score", "secret"]

    def run(batches):
        for b in batches:
            for piece in C.small_batches(b, "text"):
                found = judge(piece.column("text"), shared.value)
                if found:
                    row, begin, end, kind, value, score = zip(*found)
                    ids = piece.column("doc_id").cast(pa.int64()).take(pa.array(row))
                    yield pa.RecordBatch.from_arrays([ids, pa.array(begin, pa.int32()), pa.array(end, pa.int32()), pa.array(kind), pa.array([hashlib.sha256(v.encode()).hexdigest() for v in value]), pa.array(score), pa.array([s >= threshold for s in score])], names=names)

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, begin_char int, end_char int, kind string, value_sha256 string, score double, secret boolean")


def redact(docs: DataFrame, model=None, threshold: float = 0.5, mark: str = "[SECRET]") -> DataFrame:
    """docs with every secret in `text` replaced by a mark, and n_chars, if there, counted anew for these rows."""
    shared = docs.sparkSession.sparkContext.broadcast(train() if model is None else model)
    columns = docs.columns

    def run(batches):
        for b in batches:
            for piece in C.small_batches(b, "text"):
                cuts: dict[int, list] = {}
                for row, begin, end, _, _, score in judge(piece.column("text"), shared.value):
                    if score >= threshold:
                        cuts.setdefault(row, []).append((begin, end))
                if not cuts:
                    yield piece
                    continue
                texts = piece.column("text").to_pylist()
                for row, spans in cuts.items():
                    for begin, end in reversed(spans):
                        texts[row] = texts[row][:begin] + mark + texts[row][end:]
                at = columns.index("text")
                piece = piece.set_column(at, piece.schema.field(at), pa.array(texts, piece.schema.field(at).type))
                if "n_chars" in columns:
                    at = columns.index("n_chars")
                    sizes = piece.column(at).to_pylist()
                    for row in cuts:
                        sizes[row] = len(texts[row])
                    piece = piece.set_column(at, piece.schema.field(at), pa.array(sizes, piece.schema.field(at).type))
                yield piece

    return docs.mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(C.table(spark, sf_dir, "documents"))
