"""Toxicity by a support vector machine over a gap-weighted subsequence kernel.

The kernel of two strings sums over their common subsequences of three characters, each
weighted by a decay for every place it spans; subsequences span at most five places, so one
inserted character between any two is tolerated. It is normalised by length and squared. A text
is mapped by its words' kernel values with landmark strings (Nystroem: the values are made
orthogonal by the landmarks' own kernel matrix): of each landmark the three largest values over
the text's distinct words count, since one word like a landmark says less than several.
Letters spelt out with gaps count as one word, digits and signs are read as letters too.

Landmarks are starts of words of labelled texts: those that the labels tell apart best, in order
of their likelihood ratio, a fixed number for either class, with no threshold and no list of
words. Starts pool the evidence of inflected forms, in any language. Every text gets its value
from all landmarks, so scores are graded.
"""

from __future__ import annotations

import re
import sys
import zlib
from collections import Counter
from dataclasses import dataclass, field
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.llm.arrow import map_rows, texts
from cubelens.llm.labelled import held_out, training_rows

SUBSEQUENCE, DECAY, SPAN, POWER = 3, 0.7, 5, 2
#: Labelled texts of each class that training reads at most.
PER_CLASS = 3000
#: Landmarks from toxic and from clean texts; starts of words of this many characters at most.
TOXIC_LANDMARKS, CLEAN_LANDMARKS, LONGEST_START = 48, 24, 8
#: Buckets of starts by which those of a single text are told from others, to spare the driver's memory.
START_BUCKETS = 1 << 22
#: How many of a text's largest values of a landmark count.
LARGEST = 3
#: Words whose values are all below this add nothing that their text's other words do not.
LEAST = 0.04
#: Words as written that a task remembers; the memory is emptied when full.
REMEMBERED = 600_000
#: Cost of a margin's violation, folds of the calibration; a missed toxic text costs it so many false alarms.
COST, FOLDS, MISS_COST = 0.3, 4, 3
#: Size of the best landmark's values, and the power of the others' share of its likelihood ratio that sizes theirs.
SCALE, SCALE_POWER = 2.0, 0.5
#: Longer words are cut into windows of this length that overlap by half.
LONGEST_WORD = 32
#: Words whose subsequences are held at once.
BATCH = 2048
_STRIP = re.compile(r"^[\W_]+|[\W_]+$")
_ENDS = ".,;:!?\"'()[]#*$%&|<>-"
#: Digits and signs that stand for letters.
_LOOKALIKE = str.maketrans("013457@$!|", "oieastasii")


def _spelt(text: str) -> list[str]:
    """Words spelt out letter by letter with one to three signs between."""
    return [re.sub(r"[\W_]+", "", m[0]) for m in re.finditer(r"(?<![^\W_])[^\W_](?:[^\w\n]{1,3}[^\W_](?![^\W_])){3,}", text)]


def variants(word: str) -> list[str]:
    """A word as written, and with look-alike signs read as letters and other signs dropped."""
    core = word.strip(_ENDS)
    if not core.isalpha():
        core = _STRIP.sub("", word)
    out = [core] if core else []
    if not core.isalpha():
        plain = re.sub(r"[\W\d_]+", "", word.strip(".,;:!?\"'()[]").translate(_LOOKALIKE))
        out += [plain] if plain and plain != core else []
    return [x for w in out for x in ([w] if len(w) <= LONGEST_WORD else [w[i : i + LONGEST_WORD] for i in range(0, len(w) - LONGEST_WORD // 2, LONGEST_WORD // 2)])]


def _codes(words: list[str], width: int | None = None) -> np.ndarray:
    width = width or max(map(len, words), default=1)
    out = np.zeros((len(words), max(width, 1)), np.int32)
    for i, w in enumerate(words):
        out[i, : len(w)] = np.frombuffer(w.encode("utf-32-le", "surrogatepass"), np.int32)
    return out


def tokens_of(text: str) -> set[str]:
    """The distinct words of a text as written, in lower case, and those spelt out."""
    low = text.lower()
    return {*low.split(), *_spelt(low)}


def readings(token: str) -> list[str]:
    """What a word as written can be read as, three letters or more."""
    if not token.isalpha():
        token = token.strip(_ENDS)
    found = [token] if token.isalpha() and len(token) <= LONGEST_WORD else variants(token) if token else []
    return [w for w in found if len(w) >= SUBSEQUENCE]


def subsequences(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(word, subsequence, weight, place of its last character) of all subsequences that span at most SPAN places, ordered by word and subsequence."""
    c = _codes(words).astype(np.int64)
    width = c.shape[1]
    rows, keys, weights, ends = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)], [np.zeros(0, np.int64)]
    for b in range(2, SPAN):
        if b >= width:
            break
        r, at = np.nonzero(c[:, b:])
        first, last = c[r, at] << 42, c[r, at + b]
        for a in range(1, b):
            rows.append(r)
            keys.append(first | c[r, at + a] << 21 | last)  # three code points are one number
            weights.append(np.full(len(r), DECAY ** (b + 1)))
            ends.append(at + b)
    r, k, w, e = (np.concatenate(x) for x in (rows, keys, weights, ends))
    order = np.lexsort((k, r))
    return r[order], k[order], w[order], e[order]


def _groups(*columns: np.ndarray) -> np.ndarray:
    """Number of the run of equal values that each place belongs to."""
    new = np.zeros(len(columns[0]), bool)
    for c in columns:
        new[1:] |= np.diff(c) != 0
    return np.cumsum(new)


@dataclass
class Landmarks:
    """Landmark strings by their subsequences: of each one, which landmarks have it and its normalised weights in them."""

    words: list[str]
    keys: np.ndarray = field(init=False)
    start: np.ndarray = field(init=False)
    owner: np.ndarray = field(init=False)
    weight: np.ndarray = field(init=False)
    length: np.ndarray = field(init=False)

    def __post_init__(self):
        r, k, w, _ = subsequences(self.words)
        g = _groups(r, k) if len(r) else r
        first = np.flatnonzero(np.diff(g, prepend=-1))
        r, k, w = r[first], k[first], np.bincount(g, w)
        size = np.sqrt(np.bincount(r, w * w, minlength=len(self.words)))
        order = np.lexsort((r, k))
        self.keys, start = np.unique(k[order], return_index=True)
        self.start = np.append(start, len(k))
        self.owner, self.weight = r[order], (w / np.maximum(size[r], 1e-12))[order]
        self.length = np.array([len(t) for t in self.words], int)

    def kernel(self, words: list[str]) -> np.ndarray:
        """Kernel of words (rows) with landmarks; strings of fewer than three characters have none."""
        return self._kernels(words)[0]

    def likeness(self, words: list[str]) -> np.ndarray:
        """Of a word and a landmark the larger of two kernels: that of the word, and that of its start as long as the landmark."""
        return np.maximum(*self._kernels(words))

    def _kernels(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        m = len(self.words)
        out = np.zeros((2, len(words), m), np.float32)
        if not len(self.keys):
            return out[0], out[1]
        for at in range(0, len(words), BATCH):
            n = len(words[at : at + BATCH])
            r, k, w, e = subsequences(words[at : at + n])
            if not len(r):
                continue
            group = _groups(r, k)
            holder = r[np.flatnonzero(np.diff(group, prepend=-1))]
            norm = lambda w: np.maximum(np.sqrt(np.bincount(holder, np.bincount(group, w) ** 2, minlength=n)), 1e-12)
            place = np.searchsorted(self.keys, k)
            place[place == len(self.keys)] = 0
            hit = np.flatnonzero(self.keys[place] == k)
            times = self.start[place[hit] + 1] - self.start[place[hit]]
            i = np.repeat(hit, times)  # once for each landmark that has the subsequence
            j = np.arange(len(i)) - np.repeat(np.cumsum(times) - times, times) + self.start[place[i]]
            cell, part = r[i] * m + self.owner[j], w[i] * self.weight[j]
            out[0, at : at + n] = np.bincount(cell, part, minlength=n * m).reshape(n, m) / norm(w)[:, None]
            own = e[i] < self.length[self.owner[j]]  # inside the word's start as long as the landmark
            raw = np.bincount(cell[own], part[own], minlength=n * m).reshape(n, m)
            for size in set(self.length.tolist()):
                here = self.length == size
                some = np.flatnonzero(raw[:, here].any(axis=1))
                if len(some):
                    out[1, at + some[:, None], np.flatnonzero(here)] = raw[some][:, here] / norm(np.where(e < size, w, 0))[some, None]
        return out[0] ** POWER, out[1] ** POWER


@dataclass
class Model:
    landmarks: Landmarks
    whiten: np.ndarray
    w: np.ndarray
    b: float
    platt: np.ndarray

    def __post_init__(self):
        self.known: dict[str, tuple[int, ...]] = {}
        self.place: dict[str, int] = {}
        self.rows, self.used = np.zeros((0, len(self.landmarks.words)), np.float32), 0

    def _learn(self, tokens: set[str]) -> None:
        """Remember for words as written the rows of kernel values of what they can be read as; none if like no landmark."""
        read = {w: readings(w) for w in tokens}
        new = sorted(set(chain.from_iterable(read.values())) - self.place.keys())
        if new:
            value = self.landmarks.likeness(new)
            like = (value >= LEAST).any(axis=1)
            self.place |= dict(zip(new, np.where(like, self.used + np.cumsum(like) - 1, -1).tolist()))
            end = self.used + int(like.sum())
            if end > len(self.rows):  # room for twice as many
                self.rows = np.concatenate([self.rows[: self.used], np.zeros((2 * end - self.used, self.rows.shape[1]), np.float32)])
            self.rows[self.used : end] = value[like]
            self.used = end
        place = self.place
        self.known |= {w: tuple(p for v in r if (p := place[v]) >= 0) for w, r in read.items()}

    def features(self, rows: list[str]) -> np.ndarray:
        """A row for each text: the largest kernel values of each landmark, made orthogonal, and the logarithm of the number of words."""
        m = len(self.landmarks.words)
        tokens = [tokens_of(t) for t in rows]
        every = set().union(*tokens)
        new = every - self.known.keys()
        if len(self.known) + len(new) > REMEMBERED:
            self.__post_init__()
            new = every
        if new:
            self._learn(new)
        out, known = np.zeros((len(rows), LARGEST * m + 1)), self.known.__getitem__
        for i, x in enumerate(tokens):
            if x:
                out[i, -1] = np.log1p(len(x)) / 6
                at = set(chain.from_iterable(map(known, x)))
                if at:
                    k = self.rows[list(at)]
                    if len(k) > LARGEST:
                        k = np.partition(k, len(k) - LARGEST, axis=0)[len(k) - LARGEST :]
                    top = np.sort(k, axis=0)[::-1]
                    out[i, : top.size] = (top @ self.whiten).reshape(-1)
        return out

    def scores(self, rows: list[str]) -> np.ndarray:
        z = np.column_stack([self.features(rows) @ self.w + self.b, np.ones(len(rows))])
        return 1 / (1 + np.exp(-np.clip(z @ self.platt, -30, 30)))


def _svm(x: np.ndarray, y: np.ndarray, weight: np.ndarray, c: float = COST, rounds: int = 30) -> tuple[np.ndarray, float]:
    """Linear soft-margin machine by dual coordinate ascent; the bias is a constant feature."""
    z = np.column_stack([x, np.ones(len(x))])
    alpha, w, norm = np.zeros(len(z)), np.zeros(z.shape[1]), (z * z).sum(1)
    order = np.random.default_rng(5)
    for _ in range(rounds):
        moved = 0.0
        for i in order.permutation(len(z)):
            g = y[i] * (z[i] @ w) - 1
            new = min(max(alpha[i] - g / norm[i], 0), c * weight[i])
            if new != alpha[i]:
                w += (new - alpha[i]) * y[i] * z[i]
                moved = max(moved, abs(new - alpha[i]))
                alpha[i] = new
        if moved < 1e-3:
            break
    return w[:-1], float(w[-1])


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 50) -> np.ndarray:
    """Logistic regression by Newton steps; the last column of x is the constant."""
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        step = np.linalg.solve(h, x.T @ (y - p) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def _unlike(rows: list[tuple[str, int]]) -> list[tuple[str, int]]:
    """The rows without near-copies of earlier ones: two of the five smallest hashes of word triples in common."""
    seen: set[int] = set()
    out = []
    for t, y in rows:
        w = t.lower().split()
        sketch = sorted({zlib.crc32(" ".join(g).encode("utf-8", "surrogatepass")) for g in zip(w, w[1:], w[2:])})[:5]
        if sum(h in seen for h in sketch) < 2:
            out.append((t, y))
        seen.update(sketch)
    return out


def _evidence(k: int, n: int, share: float) -> float:
    """Signed likelihood ratio of k toxic texts among n against the share among all."""
    g = sum(x * np.log(x / (n * q)) for x, q in ((k, share), (n - k, 1 - share)) if x)
    return 2 * g if k > n * share else -2 * g


def choose_landmarks(rows: list[tuple[list[str], int]], toxic: int = TOXIC_LANDMARKS, clean: int = CLEAN_LANDMARKS) -> dict[str, float]:
    """Starts of words that tell the classes apart best, those of toxic texts first, and how well each does.

    rows: distinct words and label of each text. A start is counted with one, two and three
    words on it and ranked by the best of the three; of starts of one another the best is taken.
    """
    share = (sum(y for _, y in rows) + 0.5) / (len(rows) + 1)
    starts = lambda words: [w[:k] for w in words for k in range(SUBSEQUENCE, min(len(w), LONGEST_START) + 1)]
    texts_with = np.zeros(START_BUCKETS, np.int32)
    bucket = lambda x: zlib.crc32(x.encode("utf-8", "surrogatepass")) % START_BUCKETS
    for words, _ in rows:
        texts_with[list({bucket(x) for x in starts(words)})] += 1
    # a start of a single text has the same ratio with any number of words on it: a text's longest is as good as its others
    seen, single = (Counter(), Counter()), ({}, {})
    for words, y in rows:
        on = Counter(starts(words))
        several = {x: m for x, m in on.items() if texts_with[bucket(x)] > 1}
        seen[y].update((x, n) for x, m in several.items() for n in range(1, min(m, LARGEST) + 1))
        single[y].update(dict.fromkeys(sorted(on.keys() - several.keys(), key=lambda x: (-len(x), x))[:1]))
    rate: dict[str, list[float]] = {}
    for x in seen[0].keys() | seen[1].keys():
        rate.setdefault(x[0], []).append(_evidence(seen[1][x], seen[0][x] + seen[1][x], share))
    for y in (0, 1):
        rate |= dict.fromkeys(single[y], [_evidence(y, 1, share)])
    out: dict[str, float] = {}
    for most, best, order in ((toxic, max, sorted(rate, key=lambda x: (-max(rate[x]), -len(x), x))), (clean, min, sorted(rate, key=lambda x: (min(rate[x]), -len(x), x)))):
        end, known = len(out) + most, {x[:k] for x in out for k in range(SUBSEQUENCE, len(x) + 1)}
        for x in order:
            if len(out) == end:
                break
            if x not in known and not any(x[:k] in out for k in range(SUBSEQUENCE, len(x))):
                out[x] = abs(best(rate[x]))
                known |= {x[:k] for k in range(SUBSEQUENCE, len(x) + 1)}
    return out


def train(rows: list[tuple[str, int]]) -> Model:
    """A model from (text, label) pairs; without both classes it scores the share of toxic texts."""
    y = np.array([y for _, y in rows], float)
    n1 = int(y.sum())
    model = Model(Landmarks([]), np.zeros((0, 0)), np.zeros(1), 0.0, np.array([0.0, np.log((n1 + 1) / (len(y) - n1 + 1)) if len(y) else -2.0]))
    if n1 in (0, len(y)):
        return model
    chosen = choose_landmarks([(sorted({sys.intern(v) for w in tokens_of(t) for v in readings(w)}), k) for t, k in _unlike(rows)])
    landmarks = Landmarks(list(chosen))
    value, vector = np.linalg.eigh(landmarks.kernel(landmarks.words).astype(float))
    whiten = vector @ np.diag(1 / np.sqrt(np.maximum(value, 1e-2))) @ vector.T
    # the machine's penalty weighs on landmarks the less, the better they tell the classes apart
    scale = np.array(list(chosen.values()))
    whiten = whiten * (SCALE * (scale / max(scale.max(), 1e-9)) ** SCALE_POWER)
    model = Model(landmarks, whiten.astype(np.float32), np.zeros(0), 0.0, model.platt)
    x = np.concatenate([model.features([t for t, _ in rows[at : at + 512]]) for at in range(0, len(rows), 512)])

    def machine(own: np.ndarray) -> tuple[np.ndarray, float]:
        k = y[own]
        balance = np.where(k > 0, len(k) / (2 * max(k.sum(), 1)), len(k) / (2 * max(len(k) - k.sum(), 1)))
        return _svm(x[own], 2 * k - 1, balance)

    # calibrated on decisions about texts that a machine did not learn from
    decided, fold = np.zeros(len(y)), np.array([zlib.crc32(t.encode("utf-8", "surrogatepass")) % FOLDS for t, _ in rows])
    for f in range(FOLDS):
        if len(set(y[fold != f].tolist())) == 2:
            w, b = machine(fold != f)
            decided[fold == f] = x[fold == f] @ w + b
    twice = np.repeat(np.arange(len(y)), np.where(y > 0, MISS_COST, 1))
    platt = logistic(np.column_stack([decided, np.ones(len(y))])[twice], y[twice])
    return Model(landmarks, model.whiten, *machine(np.ones(len(y), bool)), platt)  # without the memory of training


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> Model:
    """Train on a bounded sample of the labelled texts that are not held out."""
    rows = training_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), labels, "toxic", per_class).select("doc_id", "text", "y").collect()
    return train([(r.text or "", r.y) for r in sorted(rows, key=lambda r: r.doc_id)])


def score(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    """(doc_id, held_out, score, predicted), one row per row of ``docs``.

    Null and empty texts score as texts without words. Repeated rows and
    null doc_ids (never held out) are kept; of ``docs`` only doc_id and text are read.
    """
    model = fit(docs, labels, per_class)

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        s = model.scores(texts(part.column(1)))
        return pa.record_batch([part.column(0).cast(pa.int64()), part.column(2), pa.array(s, pa.float64()), pa.array((s >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    rows = docs.select("doc_id", "text", held_out(F.col("doc_id")).alias("held_out"))
    return map_rows(rows, run, "doc_id long, held_out boolean, score double, predicted int")
