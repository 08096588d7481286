"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics come from the bytes and words of a whole text. Trees are grown in
numpy on binned statistics of a bounded, hash-chosen sample of labelled rows;
the forest is then flattened into arrays (feature, cut, value of complete
binary trees) that score a batch of documents by vectorised traversal.

Defined cases: a null text counts as empty and gets the score of its (zero)
statistics; labels that are null, and labelled documents that are missing, are
not learned from; of labels of one id that disagree the smallest counts;
without any usable label the score is 0.5; repeated rows are scored alike and
learned from once; an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spreadmax.llm.common import append_columns, text_bytes

#: Labelled rows that a classifier is fitted on, at most.
SAMPLE_ROWS = 8000
#: Words of more bytes are long ones.
LONG_WORD = 24
STATISTICS = (
    "log_bytes", "log_words", "word_length", "upper", "digit", "space", "newline", "beyond_ascii", "stop", "symbol",
    "bracket", "quote", "byte_entropy", "distinct_words", "top_word", "distinct_lines", "line_words", "long_words",
    "loud_words", "marked_words", "word_run",
)


def _classes() -> np.ndarray:
    kinds = np.zeros((256, 9))
    for b in range(256):
        c = chr(b)
        for k, yes in enumerate(
            (c.isupper() and b < 128, c.isdigit() and b < 128, c in " \t", c in "\r\n", b >= 128, c in ".,;:!?", c in "#$%&*@^~+=_|\\/<>", c in "()[]{}", c in "\"'`")
        ):
            kinds[b, k] = yes
    return kinds


_KINDS = _classes()
_HIGH = bytes(range(128, 256))


def statistics(text: bytes) -> list[float]:
    n = len(text)
    if not n:
        return [0.0] * len(STATISTICS)
    counts = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    shares = (counts @ _KINDS) / n
    p = counts[counts > 0] / n
    words = text.split()
    lines = text.split(b"\n")
    k = max(1, len(words))
    seen = set(words)
    runs = sum(map(bytes.__eq__, words, words[1:]))
    loud = sum(map(bytes.isupper, words)) / k
    top = max(Counter(words).values(), default=0) / k
    long = sum(map(LONG_WORD.__lt__, map(len, words))) / k
    marked = sum(not w[-1:].isalnum() and w[-1] < 128 for w in words) / k
    return [
        np.log1p(n), np.log1p(len(words)), n / k, *shares, float(-(p * np.log2(p)).sum()),
        len(seen) / k, top, len(set(lines)) / len(lines), k / len(lines), long,
        loud, marked, runs / k,
    ]


def with_statistics(docs: DataFrame, name: str = "stats") -> DataFrame:
    def maker():
        return lambda texts: [[statistics(t) for t in text_bytes(texts)]]

    return append_columns(docs, ["text"], [(name, T.ArrayType(T.DoubleType()))], maker)


@dataclass
class Forest:
    """Complete binary trees as arrays: inner nodes by level, then leaf values."""

    start: float
    feature: np.ndarray  # trees x (2**depth - 1)
    cut: np.ndarray  # trees x (2**depth - 1); a statistic above it goes right
    value: np.ndarray  # trees x 2**depth
    depth: int

    def margin(self, x: np.ndarray) -> np.ndarray:
        trees = np.arange(len(self.feature))
        node = np.zeros((len(x), len(trees)), np.int64)
        for _ in range(self.depth):
            right = np.take_along_axis(x, self.feature[trees, node], axis=1) > self.cut[trees, node]
            node = 2 * node + 1 + right
        return self.start + self.value[trees, node - (2**self.depth - 1)].sum(axis=1)

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.margin(x))) if len(x) else np.zeros(0)


def grow(
    x: np.ndarray, y: np.ndarray, trees: int = 60, depth: int = 4, rate: float = 0.15, bins: int = 64, l2: float = 1.0, least: float = 2.0
) -> Forest:
    """Second-order boosting of the logistic loss with histogram splits, level by level."""
    inner = 2**depth - 1
    prior = (y.sum() + 1) / (len(y) + 2) if len(y) else 0.5
    start = float(np.log(prior / (1 - prior)))
    feature = np.zeros((trees, inner), np.int64)
    cut = np.full((trees, inner), np.inf)
    value = np.zeros((trees, inner + 1))
    if len(y) < 2 or y.min() == y.max():
        return Forest(start if len(y) else 0.0, feature, cut, value, depth)
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
    coded = np.stack([np.searchsorted(e, c, "left") for e, c in zip(edges, x.T, strict=True)], axis=1)
    features = x.shape[1]
    margin = np.full(len(y), start)
    offsets = np.arange(features) * bins
    for t in range(trees):
        p = 1 / (1 + np.exp(-margin))
        grad, hess = y - p, p * (1 - p) + 1e-9
        node = np.zeros(len(y), np.int64)
        for level in range(depth):
            width, first = 2**level, 2**level - 1
            key = ((node - first)[:, None] * (features * bins) + offsets + coded).ravel()
            shape = (width, features, bins)
            size = width * features * bins
            g = np.bincount(key, np.repeat(grad, features), size).reshape(shape).cumsum(axis=2)
            h = np.bincount(key, np.repeat(hess, features), size).reshape(shape).cumsum(axis=2)
            gt, ht = g[:, :, -1:], h[:, :, -1:]
            gain = g**2 / (h + l2) + (gt - g) ** 2 / (ht - h + l2) - gt**2 / (ht + l2)
            gain[(h < least) | (ht - h < least)] = 0
            best = gain.reshape(width, -1).argmax(axis=1)
            for k in range(width):
                f, b = divmod(int(best[k]), bins)
                if gain[k, f, b] > 1e-6 and b < len(edges[f]):
                    feature[t, first + k], cut[t, first + k] = f, edges[f][b]
            node = 2 * node + 1 + (x[np.arange(len(y)), feature[t, node]] > cut[t, node])
        leaf = node - inner
        value[t] = rate * np.bincount(leaf, grad, inner + 1) / (np.bincount(leaf, hess, inner + 1) + l2)
        margin += value[t, leaf]
    return Forest(start, feature, cut, value, depth)


def labelled_ids(labels: DataFrame, label: str, usable: Column) -> DataFrame:
    """(doc_id, y): one row per usable labelled id; of labels that disagree the smallest counts."""
    return (
        labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull())
        .select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("double").alias("y"))
        .filter(usable)
        .groupBy("doc_id")
        .agg(F.min("y").alias("y"))
    )


def sampled_ids(ids: DataFrame, rows: int) -> DataFrame:
    """At most `rows` of the ids, chosen by a hash."""
    return ids.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)


def held_out(parts: int, part: int) -> Column:
    """Whether crc32 of the id, as text, leaves the remainder `part`."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % parts == part, F.lit(False))


def fit_quality(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> Forest:
    ids = sampled_ids(labelled_ids(labels, "quality", ~held_out(3, 1)), rows)
    sample = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(ids), "doc_id")
    # rows that repeat an id are one, so the bound on ids bounds what the driver gets
    once = with_statistics(sample).groupBy("doc_id", "y").agg(F.min("stats").alias("stats"))
    got = sorted(once.collect(), key=lambda r: r["doc_id"])
    x = np.array([r["stats"] for r in got], float).reshape(len(got), len(STATISTICS))
    return grow(x, np.array([r["y"] for r in got]))


def score_quality(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted."""
    forest = fit_quality(docs, labels, rows)

    def maker():
        def step(texts):
            x = np.array([statistics(t) for t in text_bytes(texts)], float).reshape(len(texts), len(STATISTICS))
            return [forest.score(x)]

        return step

    work = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    scored = append_columns(work, ["text"], [("score", T.DoubleType())], maker)
    return scored.select(
        "doc_id", held_out(3, 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted")
    )
