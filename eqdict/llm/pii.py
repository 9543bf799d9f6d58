"""Personal data: fixed patterns, and a linear-chain conditional random field over word shapes.

The field tags words as outside, or as first or further word of a secret, an identity number or a bank account. It is trained on
a small labelled table (`labelled_words`) by gradient ascent on the penalised log-likelihood, and decoded by Viterbi in numpy
batches over whole texts. A word's scores depend on its own shape and on those of its neighbours, so they are looked up by shape.
Decoding is exact though most words never enter it: where `outside` leads by more than any transitions could make up for, the best
path must pass through it, and the text falls into short runs that are decoded many at a time.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_right
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqdict.llm.common import word_bounds

BASE_KINDS = ("email", "ip", "card", "phone")
FIELD_KINDS = ("secret", "identity", "account")
TAGS = ("O", *(f"{p}-{k}" for k in FIELD_KINDS for p in "BI"))
SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_field long"

# --- fixed patterns -------------------------------------------------------------------------------------------------------------
# Each is found in time linear in the text, with the results of a leftmost search without overlaps.

_LOCAL_END = re.compile(r"[A-Za-z0-9._%+-]*\Z")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_DOTTED = re.compile(r"[0-9]+(?:\.[0-9]+)+")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def emails(text: str) -> Iterator[tuple[int, int]]:
    """An address starts where the run of characters before its @ starts, or where the last address ended."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            yield start, m.end()
            done = m.end()
            at = text.find("@", done)
        else:
            done = at + 1  # nothing left of this @ can be in a later address
            at = text.find("@", at + 1)


def ips(text: str) -> Iterator[tuple[int, int]]:
    """Four parts after four parts of each dotted run."""
    for m in _DOTTED.finditer(text):
        parts = m.group().split(".")
        at = m.start()
        for i in range(0, len(parts) - 3, 4):
            four = parts[i : i + 4]
            size = sum(map(len, four)) + 3
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in four):
                yield at, at + size
            at += size + 1


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def cards(text: str) -> Iterator[tuple[int, int]]:
    for m in _CARD.finditer(text):
        digits = m.group().replace(" ", "").replace("-", "")
        if 16 <= len(digits) <= 19 and luhn(digits):
            yield m.span()


def phones(text: str) -> Iterator[tuple[int, int]]:
    for m in _PHONE.finditer(text):
        if 8 <= sum(c.isdigit() for c in m.group()) <= 15:
            yield m.span()


_ANY = re.compile(r"[0-9@]")


def base_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    if not _ANY.search(text):
        return {k: [] for k in BASE_KINDS}
    return {"email": list(emails(text)), "ip": list(ips(text)), "card": list(cards(text)), "phone": list(phones(text)) if "+" in text else []}


# --- the labelled table ---------------------------------------------------------------------------------------------------------


def labelled_words(seed: int = 7, sentences: int = 360, length: int = 9) -> list[tuple[int, int, str, str]]:
    """(sentence, position, word, tag): lines made by rule, each with one entity or none among invented words."""
    r = np.random.Generator(np.random.PCG64(seed))
    pick = lambda s, n: "".join(r.choice(list(s), n))
    num = lambda n: pick("0123456789", n)
    alpha, hexa = "abcdefghijklmnopqrstuvwxyz", "0123456789abcdef"

    def word() -> str:
        w = pick(alpha + "éèñü", int(r.integers(1, 13)))
        w = {0: w.capitalize(), 1: w.upper(), 2: w + ".", 3: w + ",", 4: w[:4] + "-" + w[4:], 5: "(" + w + ")", 6: w + "!!", 7: w + "***"}.get(int(r.integers(0, 24)), w)
        return w or "a"

    def neutral() -> str:
        return (
            lambda: num(int(r.integers(1, 6))), lambda: f"{num(4)}-{num(2)}-{num(2)}", lambda: f"{num(2)}:{num(2)}", lambda: f"{num(1)}.{num(2)}", lambda: f"${num(3)}.{num(2)}",
            lambda: f"{word()}.{num(2)}@mail{num(1)}.example.com", lambda: f"{num(2)}.{num(3)}.{num(1)}.{num(2)}", lambda: num(16), lambda: f"+{num(1)}", lambda: f"({num(3)})", lambda: f"{num(3)}-{num(4)}",
            lambda: "|", lambda: "=", lambda: ":", lambda: "#" + num(3), lambda: f"https://{pick(alpha, 6)}.example.com/{pick(alpha, 5)}/{num(3)}", lambda: f"v{num(1)}.{num(1)}", lambda: f"{pick(alpha, 5)}_{pick(alpha, 4)}", lambda: f'"{word()}"', lambda: f"{word()}/{word()}",
            lambda: f"{num(3)}%", lambda: f"{num(2)}th", lambda: f"{num(1)}x{num(2)}", lambda: f"{num(3)},{num(3)}",
        )[int(r.integers(0, 24))]()

    def entity() -> tuple[list[str], str]:
        kind = FIELD_KINDS[int(r.choice(3, p=[0.5, 0.25, 0.25]))]
        if kind == "secret":
            body = [lambda: pick(hexa, 40), lambda: pick(hexa, 32), lambda: pick(hexa, 64), lambda: pick(alpha + alpha.upper() + "0123456789", int(r.integers(20, 45))), lambda: "sk_live_" + pick(alpha + "0123456789", 24), lambda: "AKIA" + pick(alpha.upper() + "0123456789", 16), lambda: pick(hexa, 40).upper()][int(r.integers(0, 7))]()
            return [{0: f'"{body}"', 1: f"'{body}'", 2: body, 3: f'"{body}"###', 4: f'"{body}"!!'}[int(r.choice(5, p=[0.4, 0.15, 0.25, 0.1, 0.1]))]], kind
        if kind == "identity":
            return [[lambda: f"{num(3)}-{num(2)}-{num(4)}", lambda: f"{num(3)}-{num(2)}-{num(4)}.", lambda: f"{pick(alpha.upper(), 2)}{num(6)}{pick(alpha.upper(), 1)}"][int(r.integers(0, 3))]()], kind
        head = pick(alpha.upper(), 2) + num(2)
        return [[head, *(num(4) for _ in range(4)), num(2)], [head + num(18)]][int(r.integers(0, 2))], kind

    rows = []
    for s in range(sentences):
        line = [(neutral() if r.random() < 0.18 else word(), "O") for _ in range(length)]
        if s % 2 == 0:
            words, kind = entity()
            cue = [("=", "O")] if kind == "secret" and r.random() < 0.6 else []
            at = int(r.integers(0, length - len(words) - len(cue) + 1))
            new = cue + [(w, f"{'BI'[i > 0]}-{kind}") for i, w in enumerate(words)]
            line[at : at + len(new)] = new
        rows += [(s, i, w, t) for i, (w, t) in enumerate(line[:length])]
    return rows


def labelled_table(spark: SparkSession, **how) -> DataFrame:
    return spark.createDataFrame(labelled_words(**how), "sentence int, position int, word string, tag string")


# --- shapes and features --------------------------------------------------------------------------------------------------------

_SHAPE = bytes(ord("d") if 48 <= c <= 57 else ord("X") if 65 <= c <= 90 else ord("x") if 97 <= c <= 122 or c >= 0x80 else c for c in range(256))
_ALNUM = re.compile(rb"[xXd]+")
_TURN = re.compile(rb"(?<=d)(?=[xX])|(?<=[xX])(?=d)")
_FOLD = re.compile(rb"(.)\1+", re.S)


def shapes(data: bytes) -> list[bytes]:
    """Words as classes: x small or other letter, X capital, d digit, and the rest as it is."""
    return data.translate(_SHAPE).split()


def features(shape: bytes) -> list[str]:
    core = max(_ALNUM.findall(shape), key=len, default=b"")
    fold = _FOLD.sub(rb"\1", shape)
    turns = len(_TURN.findall(core))
    n = len(core)
    size = next(i for i, x in enumerate((0, 1, 2, 4, 8, 12, 15, 19, 27, 39, 50, 1 << 62)) if n <= x)
    kinds = "".join(k for k, c in zip("xXd", b"xXd", strict=True) if c in core)
    out = [f"size={size}", f"kinds={kinds}", f"size,kinds={size},{kinds}", f"turns={min(turns, 9)}", f"turns,size={min(turns, 6)},{size}", f"first={chr(shape[0])}", f"last={chr(shape[-1])}", f"marks={min(4, len(shape) - n)}"]
    if len(fold) <= 6:
        out.append(f"fold={fold.decode()}")
    if len(shape) <= 12 and b"d" in shape:
        out.append(f"shape={shape.decode()}")
    return out


def beside(shape: bytes) -> list[str]:
    fold = _FOLD.sub(rb"\1", shape)
    return [f"fold={fold.decode()}" if len(fold) <= 3 else "fold=*", f"last={chr(shape[-1])}", f"digits={b'd' in shape}"] + ([f"shape={shape.decode()}"] if len(shape) <= 6 and b"d" in shape else [])


def word_features(shape: bytes) -> tuple[list[str], list[str], list[str]]:
    """For the word itself, for the word after it, and for the word before it."""
    near = beside(shape)
    return features(shape), [f"<{f}" for f in near], [f">{f}" for f in near]


class Field:
    """Weights of features and transitions; a text's ends count as outside."""

    #: Beyond so many shapes the table of scores is made anew before the next group of texts.
    most_shapes = 200_000

    def __init__(self, names: dict[str, int], weights: np.ndarray, moves: np.ndarray):
        self.names, self.weights, self.moves = names, weights, moves
        # what a path can gain at most on the way into and out of a tag against `outside`
        self.slack = float((moves[:, 1:] - moves[:, :1]).max() + (moves[1:, :] - moves[:1, :]).max())
        self.clear()

    def __getstate__(self):
        return self.names, self.weights, self.moves

    def __setstate__(self, state):
        self.__init__(*state)

    def clear(self) -> None:
        """Rows of scores by shape: 0 stands for the end of a text. Numbers that `ids` gave before no longer hold."""
        self.at: dict[bytes, int] = {}
        self.rows = np.zeros((3, 1024, len(TAGS)))
        self.lead = np.zeros((3, 1024))

    def lookup(self, shape: bytes) -> int:
        i = self.at[shape] = len(self.at) + 1
        if i >= self.rows.shape[1]:
            self.rows = np.concatenate([self.rows, np.zeros_like(self.rows)], axis=1)
            self.lead = np.concatenate([self.lead, np.zeros_like(self.lead)], axis=1)
        for k, names in enumerate(word_features(shape)):
            self.rows[k, i] = self.weights[[self.names[f] for f in names if f in self.names]].sum(axis=0)
        self.lead[:, i] = (self.rows[:, i, 1:] - self.rows[:, i, :1]).max(axis=1)
        return i

    def ids(self, words: list[bytes]) -> np.ndarray:
        known = list(map(self.at.get, words))
        if None in known:
            known = [self.at.get(w) or self.lookup(w) for w in words]
        return np.array(known, np.int64)

    def scores(self, ids: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Of the words at the given places of a padded row of shapes (an end before and after each text)."""
        return self.rows[0, ids[at]] + self.rows[1, ids[at - 1]] + self.rows[2, ids[at + 1]]

    def doubtful(self, ids: np.ndarray) -> np.ndarray:
        """Places where a tag other than `outside` is not ruled out."""
        lead = self.lead[0, ids[1:-1]] + self.lead[1, ids[:-2]] + self.lead[2, ids[2:]]
        return np.flatnonzero((ids[1:-1] > 0) & (lead + self.slack >= 0)) + 1

    def decode(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(places, tags) of the words that are not outside."""
        at = self.doubtful(ids)
        if not len(at):
            return at, at
        first = np.flatnonzero(np.diff(at, prepend=at[0] - 2) != 1)
        size = np.diff(np.append(first, len(at)))
        tags, scores = np.zeros(len(at), np.int64), self.scores(ids, at)
        for n in np.unique(size):  # runs of one length together
            where = first[size == n][:, None] + np.arange(n)
            tags[where] = viterbi(scores[where], self.moves)
        hit = tags > 0
        return at[hit], tags[hit]


def viterbi(scores: np.ndarray, moves: np.ndarray) -> np.ndarray:
    """Best tags of many runs of one length: scores[run, place, tag], with `outside` (0) before and after each run."""
    runs, n, _ = scores.shape
    best, back = scores[:, 0] + moves[0], []
    for i in range(1, n):
        step = best[:, :, None] + moves
        back.append(step.argmax(axis=1))
        best = step.max(axis=1) + scores[:, i]
    out = np.zeros((runs, n), np.int64)
    out[:, -1] = (best + moves[:, 0]).argmax(axis=1)
    for i in range(n - 1, 0, -1):
        out[:, i - 1] = back[i - 1][np.arange(runs), out[:, i]]
    return out


def _lse(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return (top + np.log(np.exp(x - top).sum(axis=axis, keepdims=True))).squeeze(axis)


def objective(x: np.ndarray, want: np.ndarray, want_moves: np.ndarray, w: np.ndarray, moves: np.ndarray, penalty: float) -> tuple[float, np.ndarray, np.ndarray]:
    """(penalised log-likelihood, its gradients in w and moves) by forward-backward: x[sentence, place, feature], want[sentence, place,
    tag] and want_moves the true tags and their transitions."""
    n, size = x.shape[1], len(moves)
    e = x @ w
    fwd, bwd = np.empty_like(e), np.empty_like(e)
    fwd[:, 0] = e[:, 0] + moves[0]
    for i in range(1, n):
        fwd[:, i] = _lse(fwd[:, i - 1][:, :, None] + moves, 1) + e[:, i]
    bwd[:, -1] = moves[:, 0]
    for i in range(n - 2, -1, -1):
        bwd[:, i] = _lse(moves + (e[:, i + 1] + bwd[:, i + 1])[:, None, :], 2)
    z = _lse(fwd[:, -1] + moves[:, 0], 1)
    p = np.exp(fwd + bwd - z[:, None, None])
    have = np.zeros((size, size))
    have[0] += p[:, 0].sum(axis=0)
    have[:, 0] += p[:, -1].sum(axis=0)
    for i in range(n - 1):
        have += np.exp(fwd[:, i][:, :, None] + moves + (e[:, i + 1] + bwd[:, i + 1])[:, None, :] - z[:, None, None]).sum(axis=0)
    value = float((want * e).sum() + (want_moves * moves).sum() - z.sum() - penalty / 2 * ((w**2).sum() + (moves**2).sum()))
    return value, np.tensordot(x, want - p, ([0, 1], [0, 1])) - penalty * w, want_moves - have - penalty * moves


def train(rows: list[tuple[int, int, str, str]], steps: int = 150, penalty: float = 0.02, rate: float = 0.15) -> Field:
    """Maximum penalised likelihood on (sentence, position, word, tag), by forward-backward and Adam."""
    lines: dict[int, list[tuple[int, str, str]]] = {}
    for s, i, w, t in rows:
        lines.setdefault(s, []).append((i, w, t))
    sentences = [sorted(v) for v in lines.values()]
    n, names = max(map(len, sentences)), {}
    feats = []
    for s in sentences:
        own = [word_features(shapes(w.encode())[0]) for _, w, _ in s]
        for i in range(len(s)):
            feats.append([names.setdefault(f, len(names)) for f in own[i][0] + (own[i - 1][1] if i else []) + (own[i + 1][2] if i + 1 < len(s) else [])])
    x = np.zeros((len(sentences), n, len(names)), np.float32)
    gold, mask = np.zeros((len(sentences), n), np.int64), np.zeros((len(sentences), n), bool)
    k = 0
    for a, s in enumerate(sentences):
        for i, (_, _, t) in enumerate(s):
            x[a, i, feats[k]] = 1
            gold[a, i], mask[a, i], k = TAGS.index(t), True, k + 1
    size = len(TAGS)
    want = np.eye(size)[gold] * mask[..., None]
    padded = np.concatenate([np.zeros((len(sentences), 1), np.int64), gold, np.zeros((len(sentences), 1), np.int64)], axis=1)
    want_moves = np.zeros((size, size))
    for a, s in enumerate(sentences):
        for i in range(len(s) + 1):
            want_moves[padded[a, i], padded[a, i + 1]] += 1
    theta = [np.zeros((len(names), size)), np.zeros((size, size))]
    m, v = [np.zeros_like(t) for t in theta], [np.zeros_like(t) for t in theta]
    if not mask.all():
        raise ValueError("sentences of the labelled table must have one length")
    for step in range(1, steps + 1):
        _, *grads = objective(x, want, want_moves, *theta, penalty)
        for j, g in enumerate(grads):
            m[j] = 0.9 * m[j] + 0.1 * g
            v[j] = 0.99 * v[j] + 0.01 * g * g
            theta[j] = theta[j] + rate * (m[j] / (1 - 0.9**step)) / (np.sqrt(v[j] / (1 - 0.99**step)) + 1e-8)
    return Field(names, *theta)


@lru_cache(maxsize=1)
def default_field() -> Field:
    return train(labelled_words())


# --- texts ----------------------------------------------------------------------------------------------------------------------

_TRIM_LEFT, _TRIM_RIGHT = "\"'([{<=:", "\"'.,;:!?)]}>#*&%$"


def field_spans(text: str, data: bytes, hits: list[tuple[int, int]]) -> list[tuple[str, int, int]]:
    """(kind, start, end) in code points from (word number, tag) of a text. Words that go on an entity join it."""
    raw = np.frombuffer(data, np.uint8)
    starts, ends = word_bounds(raw)
    before = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])  # code points before each byte
    out, last = [], None
    for w, t in hits:
        kind = TAGS[t][2:]
        if last and last[0] == kind and last[2] == w - 1 and TAGS[t][0] == "I":
            last[2] = w
        else:
            out.append(last := [kind, w, w])
    spans = []
    for kind, a, b in out:
        start, end = int(before[starts[a]]), int(before[ends[b]])
        body = text[start:end]
        end -= len(body) - len(body.rstrip(_TRIM_RIGHT))
        start += len(body) - len(body.lstrip(_TRIM_LEFT))
        if start < end:
            spans.append((kind, start, end))
    return spans


def apart(added: list[tuple[str, int, int]], taken: list[tuple[int, int]]) -> list[tuple[str, int, int]]:
    """Those of added that overlap none of taken, by binary search in the taken spans' union."""
    starts, ends = [], []
    for a, b in sorted(taken):
        if ends and a <= ends[-1]:
            ends[-1] = max(ends[-1], b)
        else:
            starts.append(a), ends.append(b)
    first = [bisect_right(ends, x[1]) for x in added]  # the first that ends after the span starts
    return [x for x, i in zip(added, first, strict=True) if i == len(starts) or starts[i] >= x[2]]


def found_in(texts: list[str], field: Field) -> list[tuple[dict[str, list[tuple[int, int]]], list[tuple[str, int, int]]]]:
    """(base spans, spans that the field adds) of each text. What overlaps a base span is not added."""
    if len(field.at) > field.most_shapes:  # bounded memory; never between the texts of a group, whose numbers are decoded together
        field.clear()
    data = [t.encode("utf-8", "surrogatepass") for t in texts]
    words = [shapes(d) for d in data]
    first, rows = [], [np.zeros(1, np.int64)]
    at = 1
    for w in words:
        first.append(at)
        rows += [field.ids(w), np.zeros(1, np.int64)]
        at += len(w) + 1
    hits: list[list[tuple[int, int]]] = [[] for _ in texts]
    places, tags = field.decode(np.concatenate(rows))
    owner = np.searchsorted(np.array(first), places, "right") - 1
    for p, t, o in zip(places.tolist(), tags.tolist(), owner.tolist(), strict=True):
        hits[o].append((p - first[o], t))
    out = []
    for text, d, h in zip(texts, data, hits, strict=True):
        base = base_spans(text)
        added = field_spans(text, d, h) if h else []
        out.append((base, apart(added, [s for v in base.values() for s in v]) if added else []))
    return out


def joined(spans: Iterator[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def personal_data(docs: DataFrame, field: Field | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For every row: doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_field.

    The counts and the checksum are those of the fixed patterns; `spans` holds these and then what the field adds, by kind and
    start, in code points. Null counts as empty. Repeated rows and null identifiers give a row each. Other columns are ignored,
    whatever their names. An empty table gives no rows.
    """
    field = field or default_field()

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(),) * 5 + (pa.string(), pa.string(), pa.int64())
        for b in batches:
            ids, texts = b.column(0).to_pylist(), [t or "" for t in b.column(1).to_pylist()]
            out, at = [], 0
            while at < len(texts):  # a bounded number of words at a time
                to, size = at, 0
                while to < len(texts) and (to == at or size + len(texts[to]) <= 4 << 20):
                    size, to = size + len(texts[to]), to + 1
                for d, (base, added) in zip(ids[at:to], found_in(texts[at:to], field), strict=True):
                    plain = joined((k, a, z) for k in BASE_KINDS for a, z in base[k])
                    more = joined(sorted(added, key=lambda x: (FIELD_KINDS.index(x[0]), x[1])))
                    out.append((d, *(len(base[k]) for k in BASE_KINDS), hashlib.sha256(plain.encode()).hexdigest(), ",".join(x for x in (plain, more) if x), len(added)))
                at = to
            cols = list(zip(*out, strict=True)) or [()] * len(kinds)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [c.split()[0] for c in SCHEMA.split(", ")])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text")).mapInArrow(find, SCHEMA)
