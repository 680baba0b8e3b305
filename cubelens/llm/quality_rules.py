"""Quality rules: counts on each text, and a log-likelihood ratio of hashed n-grams.

Two multinomials over hashed byte n-grams are counted: one over trusted texts, one over the
whole corpus. A text's score is the mean over its n-grams of log p_trusted - log p_corpus,
and one threshold decides about every text alike.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.llm.arrow import map_rows, slices, texts

BUCKETS = 1 << 16
GRAM_BYTES = 3
#: Texts that score below are rejected: on average an n-gram is exp(-0.3) times as likely in trusted texts.
THRESHOLD = -0.3
#: Counts added to what a bucket holds and to what it should hold, so that rare n-grams say little.
PRIOR_COUNTS = 20.0
#: Up to so many trusted ids are broadcast (8 bytes each); more are joined by a shuffle.
BROADCAST_IDS = 2_000_000
_SYMBOLS = re.compile(r"[#*$%&|<>]")
_SPACE = re.compile(r"[\x20\x09-\x0D]+")


def rule_counts(text: str | None) -> tuple[int, int, int, int, int]:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words) of a whole text."""
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()
    n = len(words)
    seen: set[str] = set()
    dup = 0
    for line in text.split("\n"):
        if line in seen:
            dup += 1
        elif line.encode("utf-8", "surrogatepass").split():
            seen.add(line)
    repeat = 0
    if n > 3:
        windows = list(zip(words, words[1:], words[2:]))
        often = {w for w, k in Counter(windows).items() if k > 1}
        if often:
            done = 0
            for i, w in enumerate(windows):
                if w in often:
                    repeat += i + 3 - max(i, done)
                    done = i + 3
    return n, sum(map(len, _SPACE.split(text))), len(_SYMBOLS.findall(text)), dup, repeat


def base_failed(n_words: int, n_repeat_words: int) -> bool:
    return n_words < 50 or 100 * n_repeat_words > 50 * n_words


def gram_buckets(text: str | None, buckets: int = BUCKETS) -> np.ndarray:
    """Buckets of the byte n-grams of a whole text, lower-cased; a power of two buckets."""
    raw = np.frombuffer((text or "").lower().encode("utf-8", "surrogatepass"), np.uint8).astype(np.uint64)
    n = len(raw) - GRAM_BYTES + 1
    if n < 1:
        return np.zeros(0, np.int64)
    h = np.zeros(n, np.uint64)
    for k in range(GRAM_BYTES):
        h = h << np.uint64(8) | raw[k : k + n]
    return (h * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(65 - buckets.bit_length())).astype(np.int64)


def gram_counts(docs: DataFrame, buckets: int = BUCKETS) -> tuple[np.ndarray, int]:
    """N-grams in each bucket over all rows of ``docs`` (column text).

    Each task adds its rows up in one array and sends its nonzero buckets; Spark adds those.
    What reaches the driver is one number a bucket.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(buckets, np.int64)
        for part in slices(batches):
            for t in texts(part.column(0)):
                total += np.bincount(gram_buckets(t, buckets), minlength=buckets)
        at = np.flatnonzero(total)
        yield pa.record_batch([pa.array(at.astype(np.int32)), pa.array(total[at])], ["bucket", "n"])

    rows = docs.select("text").mapInArrow(run, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(buckets, np.int64)
    out[rows["bucket"].to_numpy()] = rows["n"].to_numpy()
    return out, int(out.sum())


def log_ratio(trusted: np.ndarray, corpus: np.ndarray, prior: float = PRIOR_COUNTS) -> np.ndarray:
    """log p_trusted - log p_corpus of every bucket; all zero where either saw nothing.

    Both multinomials are smoothed by the same counts at the size of the trusted texts, so
    the ratio of a bucket with little evidence is close to zero whatever the corpus' size.
    """
    if not trusted.sum() or not corpus.sum():
        return np.zeros(len(trusted))
    expected = corpus * (trusted.sum() / corpus.sum())
    return np.log(trusted + prior) - np.log(expected + prior)


def with_ids(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose doc_id is in ``ids``: by broadcast if those are few, else by a shuffle."""
    ids = ids.select(F.col("doc_id").cast("long").alias("doc_id")).filter("doc_id is not null").distinct()
    few = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    return docs.join(F.broadcast(ids) if few else ids.hint("merge"), "doc_id", "left_semi")


def fit(docs: DataFrame, labels: DataFrame, buckets: int = BUCKETS) -> np.ndarray:
    """Weights of the buckets; trusted texts are those that ``labels`` gives quality 1."""
    corpus, _ = gram_counts(docs, buckets)
    trusted, _ = gram_counts(with_ids(docs.select("doc_id", "text"), labels.filter("quality = 1")), buckets)
    return log_ratio(trusted, corpus)


def _score(text: str | None, weights: np.ndarray) -> float:
    b = gram_buckets(text, len(weights))
    return float(weights[b].mean()) if len(b) else 0.0


def assess(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, llr, kept).

    One row per row of ``docs``. Null texts have no words and fail. Without any trusted text
    every llr is 0 and the base rules decide alone. Columns other than doc_id and text are
    not read.
    """
    weights = fit(docs, labels)

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        for t in texts(part.column(1)):
            c = rule_counts(t)
            bad, llr = base_failed(c[0], c[4]), _score(t, weights)
            rows.append((*c, bad, llr, not bad and llr >= threshold))
        kinds = [pa.int64()] * 5 + [pa.bool_(), pa.float64(), pa.bool_()]
        columns = [pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds)]
        return pa.record_batch([part.column(0).cast(pa.int64()), *columns], names)

    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, llr double, kept boolean"
    names = [x.split()[0] for x in schema.split(", ")]
    return map_rows(docs.select("doc_id", "text"), run, schema)


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that ``assess`` keeps, with all their columns; nothing is shuffled."""
    weights, at = fit(docs, labels), docs.columns.index("text")

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        keep = []
        for t in texts(part.column(at)):
            c = rule_counts(t)
            keep.append(not base_failed(c[0], c[4]) and _score(t, weights) >= threshold)
        return part.filter(pa.array(keep, pa.bool_()))

    return map_rows(docs, run, docs.schema)
