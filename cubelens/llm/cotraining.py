"""Quality by co-training: a classifier of the text and one of the page's metadata teach each other.

Both are logistic regressions on their own view. In each round either one labels, among all
unlabelled rows, those it is surest of, and these join the other's training rows. Unlabelled
rows stay where they are: their views are written once, and every pass over them sends sums
(counts of scores, gradients) to the driver. Which rows were labelled before, a pass finds out
by the models and cuts of the rounds before, so nothing is written in between. At the end
both views are calibrated on labelled rows that neither has seen, and a logistic regression
of the two calibrated scores, fitted on further ones, decides about every document.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.llm.arrow import map_rows, slices, texts
from cubelens.llm.labelled import held_out, training_rows
from cubelens.llm.quality_rules import gram_buckets
from cubelens.llm.toxicity import logistic
from cubelens.storage import materialize, release

TEXT_DIMS, NAME_DIMS = 1024, 32
#: Labelled rows of each class that training reads at most; unlabelled ones are all used.
PER_CLASS = 1500
ROUNDS, SHARE, STEPS = 4, 0.05, 5
#: Log-odds are counted in hundredths up to this bound; surer than SURE is sure enough to teach.
BOUND, SURE = 1300, 100
RIDGE = 1.0


def text_view(text: str | None) -> np.ndarray:
    """Logarithmic frequencies of hashed byte n-grams, of length one, with a constant."""
    x = np.zeros(TEXT_DIMS + 1)
    x[:-1] = np.log1p(np.bincount(gram_buckets(text, TEXT_DIMS), minlength=TEXT_DIMS))
    x[:-1] *= 8 / max(np.sqrt((x * x).sum()), 1e-9)
    x[-1] = 1
    return x


def page_view(text: str | None, lang: str | None, source: str | None) -> np.ndarray:
    """What is known about a page apart from its words: language, source, length and layout."""
    text = text or ""
    lines = text.split("\n")
    size = np.array([len(x) for x in lines], float)
    x = np.zeros(2 * NAME_DIMS + 6)
    for k, name in enumerate((lang, source)):
        x[k * NAME_DIMS + zlib.crc32((name or "").encode("utf-8", "surrogatepass")) % NAME_DIMS] = 1
    x[-6:] = np.log1p(len(text)), np.log1p(len(lines)), np.log1p(size.mean()), np.log1p(size.max()), len(set(lines)) / len(lines), 1
    return x


@dataclass
class Model:
    text_w: np.ndarray
    page_w: np.ndarray
    text_cal: np.ndarray
    page_cal: np.ndarray
    blend: np.ndarray

    def logits(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Calibrated log-odds of both views, and a constant."""
        cal = lambda x, w, c: np.clip(c[0] * (x @ w) + c[1], -12, 12)
        return np.column_stack([cal(a, self.text_w, self.text_cal), cal(b, self.page_w, self.page_cal), np.ones(len(a))])

    def scores(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.logits(a, b) @ self.blend))


def _views(rows: list[tuple]) -> tuple[np.ndarray, np.ndarray]:
    a = np.array([text_view(t) for t, _, _ in rows]).reshape(len(rows), TEXT_DIMS + 1)
    b = np.array([page_view(*r) for r in rows]).reshape(len(rows), 2 * NAME_DIMS + 6)
    return a, b


def _fit(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return logistic(x, y, ridge=RIDGE, rounds=12)


#: Weights of both views, and for each view the bins of log-odds up to which rows are bad and from which they are good.
Round = tuple[np.ndarray, np.ndarray, list[tuple[int, int]]]


def pool_views(rows: DataFrame) -> DataFrame:
    """Both views of (doc_id, text, lang, source) rows in few bytes: the text's in 255 steps of its largest value."""

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        a, b = _views(list(zip(texts(part.column(1)), part.column(2).to_pylist(), part.column(3).to_pylist())))
        a = np.round(a[:, :-1] * (255 / np.maximum(a[:, :-1].max(1, keepdims=True), 1e-9))).astype(np.uint8)
        return pa.record_batch([part.column(0), *(pa.array([x.tobytes() for x in m], pa.binary()) for m in (a, b.astype("<f4")))], ["doc_id", "a", "b"])

    return map_rows(rows.select("doc_id", "text", "lang", "source"), run, "doc_id long, a binary, b binary")


def _read(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    n = part.num_rows
    q, b = (np.frombuffer(b"".join(part.column(k).to_pylist()), kind).reshape(n, -1) for k, kind in ((0, np.uint8), (1, "<f4")))
    a = np.ones((n, TEXT_DIMS + 1), np.float32)
    a[:, :-1] = q
    a[:, :-1] *= 8 / np.maximum(np.sqrt((a[:, :-1] ** 2).sum(1, keepdims=True)), 1e-9)
    return a, b


def _total(pool: DataFrame, size: int, fn: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> np.ndarray:
    """The sum of ``fn`` of both views over all rows; a task sends one vector of ``size``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros(size)
        for part in slices(batches, 512):
            if part.num_rows:
                out += fn(*_read(part))
        k = np.flatnonzero(out)
        yield pa.record_batch([pa.array(k, pa.int32()), pa.array(out[k], pa.float64())], ["k", "v"])

    out = np.zeros(size)
    for r in pool.select("a", "b").mapInArrow(run, "k int, v double").groupBy("k").agg(F.sum("v").alias("v")).collect():
        out[r.k] = r.v
    return out


def _bins(p: np.ndarray) -> np.ndarray:
    return np.clip(np.floor(p * 100), -BOUND, BOUND).astype(int)


def picked(a: np.ndarray, b: np.ndarray, rounds: list[Round]) -> tuple[np.ndarray, np.ndarray]:
    """The view that labelled each row first (-1: none), and its label."""
    by, y = np.full(len(a), -1), np.zeros(len(a))
    for wa, wb, cuts in rounds:
        for view, (low, high) in enumerate(cuts):
            bins = _bins(a @ wa.astype(a.dtype) if view == 0 else b @ wb.astype(b.dtype))
            for hit, label in ((bins >= high, 1.0), (bins <= low, 0.0)):
                hit &= by < 0
                by[hit], y[hit] = view, label
    return by, y


def _cut(counts: np.ndarray, n: int) -> int:
    """How many bins, the surest first, hold at most ``n`` rows; the first that holds any counts in any case."""
    some = np.flatnonzero(counts)
    return max(int(np.searchsorted(np.cumsum(counts), n, side="right")), int(some[0]) + 1) if len(some) else 0


def _sums(rounds: list[Round], wa: np.ndarray, wb: np.ndarray) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """For each view, over the rows that the other one labelled: gradient, number of rows, loss."""

    def fn(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        by, y = picked(a, b, rounds)
        out = []
        for x, w, teacher in ((a, wa, 1), (b, wb, 0)):
            at = by == teacher
            p = 1 / (1 + np.exp(-np.clip(x[at] @ w, -30, 30)))
            out += [(p - y[at]) @ x[at], [at.sum(), _loss(x[at], y[at], w)]]
        return np.concatenate(out)

    return fn


def _loss(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> float:
    z = x @ w
    return float((np.logaddexp(0, z) - y * z).sum())


class Descent:
    """Logistic regression over labelled rows here and sums from elsewhere: quasi-Newton steps that start from the curvature of the labelled rows.

    A step that does not lower the loss is halved. Rows from elsewhere together weigh as much
    as the given share of the labelled ones at most: however many they are, they do not drown them.
    """

    def __init__(self, x: np.ndarray, y: np.ndarray, w: np.ndarray, share: float):
        self.x, self.y, self.at, self.next, self.most = x, y, None, w, share * len(y)
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        self.inverse = np.linalg.inv((x * (p * (1 - p))[:, None]).T @ x + RIDGE * np.eye(len(w)))

    def see(self, sums: np.ndarray) -> None:
        """Take the sums at ``next`` (gradient, number, loss); afterwards ``next`` is the point to look at next."""
        w, weight = self.next, min(1.0, self.most / max(sums[-2], 1.0))
        p = 1 / (1 + np.exp(-np.clip(self.x @ w, -30, 30)))
        grad = (p - self.y) @ self.x + weight * sums[:-2] + RIDGE * w
        loss = _loss(self.x, self.y, w) + weight * sums[-1] + RIDGE / 2 * w @ w
        if self.at is None or loss <= self.loss + 1e-4 * self.step @ self.grad:
            if self.at is not None:
                change = grad - self.grad
                if (along := self.step @ change) > 1e-12:
                    side = self.inverse @ change
                    self.inverse += np.outer(self.step, self.step) * ((along + change @ side) / along**2) - (np.outer(side, self.step) + np.outer(self.step, side)) / along
            self.at, self.loss, self.grad = w, loss, grad
            self.step = -self.inverse @ grad
        else:
            self.step = self.step / 2
        self.next = self.at + self.step


def train(labelled: list[tuple], y: np.ndarray, pool: DataFrame | None, rounds: int = ROUNDS, share: float = SHARE) -> Model:
    """labelled: (text, lang, source); y: 0 or 1; pool: ``pool_views``. Every fourth labelled row is kept for calibration."""
    y = np.asarray(y, float)
    if len(set(y.tolist())) < 2:
        flat = np.zeros(3)
        flat[2] = np.log((y.sum() + 1) / (len(y) - y.sum() + 1))
        return Model(np.zeros(TEXT_DIMS + 1), np.zeros(2 * NAME_DIMS + 6), np.zeros(2), np.zeros(2), flat)
    a, b = _views(labelled)
    cal = np.arange(len(y)) % 4 == 3
    if len(set(y[cal].tolist())) < 2 or len(set(y[~cal].tolist())) < 2:
        cal = np.ones(len(y), bool)
    own = ~cal if (~cal).any() else cal
    xa, xb, yo = a[own], b[own], y[own]
    wa, wb = _fit(xa, yo), _fit(xb, yo)
    done: list[Round] = []
    n = None
    width = 2 * BOUND + 1
    for _ in range(rounds if pool is not None else 0):

        def count(a: np.ndarray, b: np.ndarray, done=done, wa=wa, wb=wb) -> np.ndarray:
            free = picked(a, b, done)[0] < 0
            return np.concatenate([np.bincount(_bins(x @ w.astype(x.dtype))[free] + BOUND, minlength=width) for x, w in ((a, wa), (b, wb))])

        seen = _total(pool, 2 * width, count).reshape(2, width)
        n = int(seen[0].sum()) if n is None else n  # all rows are free in the first round
        good, bad = (max(1, int(int(n * share) * part)) for part in (yo.mean(), 1 - yo.mean()))
        cuts = [(-BOUND - 1 + _cut(h[: BOUND - SURE], bad), BOUND + 1 - _cut(h[BOUND + SURE :][::-1], good)) for h in seen]
        if all(low < -BOUND and high > BOUND for low, high in cuts):
            break  # no view is sure of a free row
        done = [*done, (wa, wb, cuts)]
        one, two = (Descent(x, yo, w, share * len(done)) for x, w in ((xa, wa), (xb, wb)))
        for _ in range(STEPS):
            sums = _total(pool, len(wa) + len(wb) + 4, _sums(done, one.next, two.next))
            one.see(sums[: len(wa) + 2])
            two.see(sums[len(wa) + 2 :])
        wa, wb = one.at, two.at
    # one half of the rows kept back calibrates the views, the other one blends them
    first, second = (cal & (np.arange(len(y)) % 8 == k) for k in (3, 7))
    if any(len(set(y[half].tolist())) < 2 for half in (first, second)):
        first = second = cal
    one = np.ones(first.sum())
    model = Model(wa, wb, logistic(np.column_stack([a[first] @ wa, one]), y[first]), logistic(np.column_stack([b[first] @ wb, one]), y[first]), np.zeros(3))
    model.blend = logistic(model.logits(a[second], b[second]), y[second], ridge=0.1)
    return model


def unlabelled(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """All rows with an id that has no label and is not held out."""
    ids = labels.select(F.col("doc_id").cast("long").alias("doc_id")).filter("doc_id is not null").distinct()
    return docs.filter(F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).join(ids.hint("shuffle_hash"), "doc_id", "left_anti")


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> Model:
    """Train on a bounded sample, by hash order, of labelled rows that are not held out, and on all rows without a label."""
    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"))
    rows = sorted(training_rows(named, labels, "quality", per_class).collect(), key=lambda r: r.doc_id)
    free = F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))
    pool = materialize(unlabelled(pool_views(named.filter(free)), labels), "pool") if len({r.y for r in rows}) == 2 else None  # views shuffle, not texts
    model = train([(r.text, r.lang, r.source) for r in rows], np.array([r.y for r in rows]), pool)
    release(pool)
    return model


def score(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    """(doc_id, held_out, text_score, page_score, score, predicted, kept), one row per row of ``docs``.

    Scores are probabilities of good quality; ``kept`` is score >= 0.5. Null texts count as
    empty, null languages and sources as empty names. Without labels of both classes every
    row gets the share of good labels. Repeated rows and null doc_ids (never held out) stay.
    """
    model = fit(docs, labels, per_class)

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        a, b = _views(list(zip(texts(part.column(1)), part.column(2).to_pylist(), part.column(3).to_pylist())))
        z, s = model.logits(a, b), model.scores(a, b)
        view = lambda k: pa.array(1 / (1 + np.exp(-z[:, k])), pa.float64())
        return pa.record_batch([part.column(0).cast(pa.int64()), part.column(4), view(0), view(1), pa.array(s, pa.float64()), pa.array((s >= 0.5).astype(np.int32)), pa.array(s >= 0.5)], names)

    schema = "doc_id long, held_out boolean, text_score double, page_score double, score double, predicted int, kept boolean"
    names = [x.split()[0] for x in schema.split(", ")]
    rows = docs.select("doc_id", "text", F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), held_out(F.col("doc_id")).alias("held_out"))
    return map_rows(rows, run, schema)
