"""Toxicity: a convolutional text classifier in numpy.

A word is the sum of hashed embeddings of itself and of its beginnings.
Filters of several widths slide over the words of the whole text, each keeps
its largest different responses (so that one chance word and many bad ones are
told apart), and a logistic layer reads these maxima. The model is trained by
Adam on a bounded, hash-chosen sample of labelled rows; gradients reach only
the words at the maxima. Scores never see the language; decision thresholds of
`toxic_by_language` are calibrated per language on all labelled rows that are
not held out, counted by bins of the log odds of their scores. Rows that the
net was trained on get scores of nets trained without them, in inner folds of
the sample; all others get the scores of the net itself.

Defined cases: a null text counts as empty; texts without words get the score
of empty maxima; of labels of one id that disagree the smallest counts, and
repeated rows are learned from once; without usable labels of both kinds the score is the share of
the label (0.5 without any); an empty table gives an empty result; columns of
the input keep their names and values in `drop_toxic`.
"""

from __future__ import annotations

from array import array
from zlib import crc32

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spreadmax.llm.common import append_columns, columns, fresh, text_bytes, words_of
from spreadmax.llm.quality import held_out, labelled_ids, sampled_ids
from spreadmax.session import written

#: Labelled rows that the net is trained on, and bytes of their texts that the driver gets, at most.
SAMPLE_ROWS = 3_000
SAMPLE_BYTES = 64 << 20
#: Inner folds of the sample.
FOLDS = 3
BUCKETS = 1 << 15
WIDTHS = (1, 2, 3)
FILTERS = 6
#: Largest different responses that the pooling of a filter keeps: of 1, 2 and 3 the one with the least log loss in inner folds of training rows.
KEEP = 3
SIZE = 8
#: Bytes of a word's beginnings that have an embedding of their own.
BEGINNINGS = (4, 5, 6, 7)
#: Words of one step of the filters, so that long texts need no more memory.
BLOCK = 1 << 16
CACHE = 400_000
PARTS = 1 + len(BEGINNINGS)
#: Bins of log odds that thresholds are chosen from: their bound, their number a unit, and the rows of each kind that a language needs.
ODDS = 32
BINS = 64
LEAST = 20
_NONE = BUCKETS  # the row of an absent beginning: always zero


def pieces(word: bytes) -> tuple[int, ...]:
    """Buckets of the word and of its beginnings (those it has)."""
    n = len(word)
    return (crc32(word) % BUCKETS, *[crc32(word[:k], k) % BUCKETS if n >= k else _NONE for k in BEGINNINGS])


class WordIndex(dict):
    """Numbers of words; `codes` has the buckets of each number, one word after the other."""

    def __init__(self):
        super().__init__()
        self.codes = array("i")

    def __missing__(self, word: bytes) -> int:
        self[word] = n = len(self)
        self.codes.extend(pieces(word))
        return n


class ConvNet:
    def __init__(self, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.emb = (rng.standard_normal((BUCKETS + 1, SIZE)) * 0.1).astype(np.float32)
        self.emb[_NONE] = 0
        #: One matrix per width and place in the window.
        self.filters = [(rng.standard_normal((w, SIZE, FILTERS)) * 0.4).astype(np.float32) for w in WIDTHS]
        self.bias = np.zeros(len(WIDTHS) * FILTERS, np.float32)
        self.out = (rng.standard_normal(KEEP * len(WIDTHS) * FILTERS) * 0.3).astype(np.float32)
        self.last = np.zeros(1, np.float32)

    def responses(self, vectors: np.ndarray) -> list[np.ndarray]:
        """Per width: (words, place * filters) responses of single words."""
        return [vectors @ f.transpose(1, 0, 2).reshape(SIZE, -1) for f in self.filters]

    def maxima(self, numbers: np.ndarray, starts: np.ndarray, resp: list[np.ndarray], where: bool = False):
        """Maxima over the windows of each text; texts begin at `starts` in `numbers`.

        Windows that do not fit into the text are left out; a text shorter than the
        width has zero maxima. Shape (texts, KEEP, filters). With `where`, also the window of each maximum.
        """
        n, docs = len(numbers), len(starts)
        ends = np.append(starts[1:], n)
        top = np.zeros((docs, KEEP, len(WIDTHS) * FILTERS), np.float32)
        place = np.full((docs, KEEP, len(WIDTHS) * FILTERS), -1, np.int64)
        for i, w in enumerate(WIDTHS):
            cols = slice(i * FILTERS, (i + 1) * FILTERS)
            if n < w:
                continue
            conv = resp[i][numbers[: n - w + 1], :FILTERS].copy()
            for j in range(1, w):
                conv += resp[i][numbers[j : n - w + 1 + j], j * FILTERS : (j + 1) * FILTERS]
            for lo in range(1, w):  # windows that reach over the end of a text
                cross = ends[:-1] - lo
                conv[cross[(cross >= 0) & (cross < len(conv))]] = -np.inf
            have = np.flatnonzero(ends - starts >= w)
            if not len(have):
                continue
            at = starts[have]
            body = conv[at[0] :]
            sizes = np.diff(np.append(at, len(conv)))
            for k in range(KEEP):
                best = np.maximum.reduceat(conv, at, axis=0)  # the rest until the next start is cut off or infinite
                top[have, k, cols] = np.maximum(best + self.bias[cols], 0)
                if where:
                    for d in have:
                        place[d, k, cols] = conv[starts[d] : ends[d] - w + 1].argmax(axis=0) + starts[d]
                if k + 1 < KEEP:
                    body[body == np.repeat(best, sizes, axis=0)] = -np.inf
        return (top, place) if where else top

    def score(self, top: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(top.reshape(len(top), len(self.out)) @ self.out + self.last[0]).astype(np.float64)))


class Scorer:
    """Scores batches; remembers the responses of words it has met, within a bound."""

    def __init__(self, net: ConvNet):
        self.net = net
        self.reset()

    def reset(self) -> None:
        self.index = WordIndex()
        self.resp = [np.zeros((0, w * FILTERS), np.float32) for w in WIDTHS]

    def _grow(self) -> None:
        old, new = len(self.resp[0]), len(self.index)
        if new > old:
            codes = np.array(self.index.codes, np.int64).reshape(-1, PARTS)
            self.index.codes = array("i")
            vectors = np.zeros((len(codes), SIZE), np.float32)
            for k in range(PARTS):
                vectors += self.net.emb[codes[:, k]]
            self.resp = [np.concatenate((a, b)) for a, b in zip(self.resp, self.net.responses(vectors), strict=True)]

    def score(self, texts: list[bytes]) -> np.ndarray:
        top = np.zeros((len(texts), KEEP, len(WIDTHS) * FILTERS), np.float32)
        reach = max(WIDTHS) - 1
        held: list[tuple[int, np.ndarray]] = []
        size = 0
        for d, text in enumerate(texts):
            words = words_of(text)
            numbers = np.fromiter(map(self.index.__getitem__, words), np.int64, len(words))
            for a in range(0, max(1, len(numbers) - reach), BLOCK):
                part = numbers[a : a + BLOCK + reach]
                if len(part):
                    held.append((d, part))
                    size += len(part)
            if size >= BLOCK:
                self._pool(held, top)
                held, size = [], 0
        self._pool(held, top)
        return self.net.score(top)

    def _pool(self, held: list[tuple[int, np.ndarray]], top: np.ndarray) -> None:
        if held:
            self._grow()
            lengths = np.array([len(p) for _, p in held])
            numbers = np.concatenate([p for _, p in held])
            starts = np.concatenate(([0], np.cumsum(lengths)[:-1]))
            for (d, _), own in zip(held, self.net.maxima(numbers, starts, self.resp), strict=True):
                top[d] = _largest(top[d], own) if top[d].any() else own
        if len(self.index) > CACHE:
            self.reset()


def _largest(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The KEEP largest different values of each column of both."""
    both = -np.sort(-np.concatenate((a, b)), axis=0)
    both[1:][both[1:] == both[:-1].copy()] = 0
    return -np.sort(-both, axis=0)[:KEEP]


class _Adam:
    def __init__(self, rate: float):
        self.rate, self.t, self.state = rate, 0, {}

    def step(self, name: str, value: np.ndarray, grad: np.ndarray, rows: np.ndarray | None = None) -> None:
        m, v = self.state.setdefault(name, (np.zeros_like(value), np.zeros_like(value)))
        at = slice(None) if rows is None else rows
        m[at] = 0.9 * m[at] + 0.1 * grad
        v[at] = 0.98 * v[at] + 0.02 * grad * grad
        fix = np.sqrt(1 - 0.98**self.t) / (1 - 0.9**self.t)
        value[at] -= self.rate * fix * m[at] / (np.sqrt(v[at]) + 1e-6)


def train(texts: list[bytes], y: np.ndarray, epochs: int = 6, batch: int = 64, rate: float = 0.03, seed: int = 7) -> ConvNet:
    """Adam on the logistic loss, classes weighted alike. Embeddings begin with the
    smoothed log odds of their bucket in one coordinate, so that the first maxima
    already point at words that tell the classes apart."""
    net = ConvNet(seed)
    if not len(y) or y.min() == y.max():
        net.out[:] = 0
        share = (y.sum() + 1) / (len(y) + 2)
        net.last[:] = np.log(share / (1 - share))
        return net
    index = WordIndex()
    docs = [np.fromiter(map(index.__getitem__, words_of(t)), np.int64) for t in texts]
    codes = np.array(index.codes, np.int64).reshape(-1, PARTS)
    count = np.zeros((2, BUCKETS + 1))
    for d, label in zip(docs, y, strict=True):
        count[int(label)][np.unique(codes[np.unique(d)])] += 1
    n0, n1 = (y == 0).sum(), (y == 1).sum()
    odds = np.log((count[1] + 1) / n1) - np.log((count[0] + n0 / n1) / n0)  # one more document of each kind, at the base rate
    net.emb[:, 0] = np.clip(odds, -3, 4) / 2
    net.emb[_NONE] = 0
    for f in net.filters:
        f[:, 0, : FILTERS // 2] = np.abs(f[:, 0, : FILTERS // 2]) + 0.3
    net.out[:] = np.abs(net.out)
    net.last[:] = -2
    weight = np.where(y == 1, len(y) / (2 * n1), len(y) / (2 * n0)).astype(np.float32) ** 0.5
    adam, rng = _Adam(rate), np.random.default_rng(seed)
    for epoch in range(epochs):
        order = rng.permutation(len(docs))
        adam.rate = rate * (1 - epoch / epochs)
        for a in range(0, len(order), batch):
            part = order[a : a + batch]
            own = [docs[i] for i in part]
            lengths = np.array([len(d) for d in own])
            if not lengths.sum():
                continue
            words, numbers = np.unique(np.concatenate(own), return_inverse=True)
            starts = np.concatenate(([0], np.cumsum(lengths)[:-1]))
            used = np.flatnonzero(lengths)
            vectors = net.emb[codes[words]].sum(axis=1)
            top, place = net.maxima(numbers, starts[used], net.responses(vectors), where=True)
            error = ((net.score(top) - y[part][used]) * weight[part][used]).astype(np.float32) / len(used)
            adam.t += 1
            top, place = (x.reshape(len(x), len(net.out)) for x in (top, place))
            back = error[:, None] * net.out * (top > 0)
            g_vec = np.zeros_like(vectors)
            g_filters = [np.zeros_like(f) for f in net.filters]
            for i, w in enumerate(WIDTHS):
                for k, c in ((k, (m * len(WIDTHS) + i) * FILTERS + k) for m in range(KEEP) for k in range(FILTERS)):
                    d = np.flatnonzero((place[:, c] >= 0) & (back[:, c] != 0))
                    for j in range(w):
                        at = numbers[place[d, c] + j]
                        g_filters[i][j, :, k] += (back[d, c][:, None] * vectors[at]).sum(axis=0)
                        np.add.at(g_vec, at, back[d, c][:, None] * net.filters[i][j, :, k])
            adam.step("out", net.out, top.T @ error + 1e-3 * net.out)
            adam.step("last", net.last, np.array([error.sum()], np.float32))
            adam.step("bias", net.bias, back.sum(axis=0).reshape(KEEP, -1).sum(axis=0))
            for i, g in enumerate(g_filters):
                adam.step(f"f{i}", net.filters[i], g + 1e-4 * net.filters[i])
            hot = np.flatnonzero(np.abs(g_vec).sum(axis=1))
            rows, inverse = np.unique(codes[words[hot]], return_inverse=True)
            grad = np.zeros((len(rows), SIZE), np.float32)
            np.add.at(grad, inverse.reshape(-1), np.repeat(g_vec[hot], PARTS, axis=0))
            keep = rows != _NONE
            adam.step("emb", net.emb, grad[keep], rows[keep])
    return net


def crossfit(texts: list[bytes], y: np.ndarray, folds: int = FOLDS) -> np.ndarray:
    """The score of each text by a net that was trained without its fold; folds take turns within each class."""
    fold = np.zeros(len(y), np.int64)
    for label in (0, 1):
        own = np.flatnonzero(y == label)
        fold[own] = np.arange(len(own)) % folds
    out = np.zeros(len(y))
    for f in range(folds):
        rest, own = np.flatnonzero(fold != f), np.flatnonzero(fold == f)
        out[own] = Scorer(train([texts[i] for i in rest], y[rest])).score([texts[i] for i in own])
    return out


def fit_toxicity(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS, most: int = SAMPLE_BYTES) -> tuple[ConvNet, dict[int, float]]:
    """The net, trained on at most `rows` labelled rows of at most `most` bytes, and the scores of these rows by inner folds."""
    known = _training_ids(labels)
    # toxic rows are rare: half of the bound is theirs
    ids = sampled_ids(known.filter("y = 1"), rows // 2).unionByName(sampled_ids(known.filter("y = 0"), rows // 2))
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    # rows that repeat an id are one, so the bound on ids bounds what the driver gets
    once = own.join(F.broadcast(ids), "doc_id").groupBy("doc_id", "y").agg(F.min(F.struct("text")).alias("row"))
    once = written(once.select("doc_id", "y", F.coalesce("row.text", F.lit(b"")).alias("text")), "sample")
    sizes = once.select("doc_id", "y", F.octet_length("text").alias("n"), F.xxhash64("doc_id").alias("h")).collect()  # at most `rows`
    kept, left = [], {0.0: most // 2, 1.0: most // 2}
    for r in sorted(sizes, key=lambda r: (r["h"], r["doc_id"])):
        left[r["y"]] = left.get(r["y"], 0) - r["n"]
        if left[r["y"]] >= 0:
            kept.append(r["doc_id"])
    if len(kept) < len(sizes):
        once = once.join(F.broadcast(docs.sparkSession.createDataFrame([(i,) for i in kept], "doc_id long")), "doc_id")
    got = sorted(once.collect(), key=lambda r: r["doc_id"])
    texts, y = [bytes(r["text"]) for r in got], np.array([r["y"] for r in got])
    inner = dict(zip([r["doc_id"] for r in got], crossfit(texts, y).tolist(), strict=True)) if len(got) else {}
    return train(texts, y), inner


def _training_ids(labels: DataFrame) -> DataFrame:
    return labelled_ids(labels, "toxic", ~held_out(5, 0))


def score_counts(scored: DataFrame, labels: DataFrame, inner: dict[int, float] | None = None, least: int = LEAST) -> DataFrame:
    """lang, bin, clean, toxic, low, high: all labelled training rows of `scored` (doc_id, lang, score) by log odds
    of their score, for the languages with `least` rows of both kinds; low and high are the scores that a bin holds.
    `inner`: scores that stand for those of the rows that the net was trained on."""
    own = scored.select(F.col("doc_id").cast("long").alias("doc_id"), F.struct(F.col("lang").cast("string").alias("lang"), "score").alias("row"))
    once = own.join(_training_ids(labels), "doc_id").groupBy("doc_id", "y").agg(F.min("row").alias("row"))
    other = scored.sparkSession.createDataFrame(sorted((inner or {}).items()), "doc_id long, inner double")  # at most SAMPLE_ROWS
    once = once.join(F.broadcast(other), "doc_id", "left").select("y", "row.lang", F.coalesce("inner", "row.score").alias("score"))
    odds = F.ln(F.col("score") / (1 - F.col("score")))
    place = F.when(F.col("score") >= 1, ODDS).when(F.col("score") <= 0, -ODDS).otherwise(F.greatest(F.lit(-ODDS), F.least(F.lit(ODDS), odds)))
    number = lambda y: F.sum((F.col("y") == y).cast("long"))
    bins = once.filter("lang is not null").groupBy("lang", F.floor(place * BINS).cast("int").alias("bin")).agg(
        number(0).alias("clean"), number(1).alias("toxic"), F.min("score").alias("low"), F.max("score").alias("high")
    )
    bins = written(bins, "scores")
    enough = bins.groupBy("lang").agg(F.sum("clean").alias("c"), F.sum("toxic").alias("t")).filter((F.col("c") >= least) & (F.col("t") >= least))
    return bins.join(enough.select("lang"), "lang")


def calibrate(counts: list) -> dict[str, float]:
    """Per language the threshold with the fewest errors (clean rows weigh double), the middle of the gap below it;
    `counts`: rows of `score_counts`. Where any threshold takes more clean rows than it is worth, none is taken."""
    out: dict[str, float] = {}
    for lang in {r["lang"] for r in counts}:
        own = sorted((r for r in counts if r["lang"] == lang), key=lambda r: -r["bin"])
        cost = np.cumsum([2 * r["clean"] - r["toxic"] for r in own])
        k = int(cost.argmin())
        below = own[k + 1]["high"] if k + 1 < len(own) else 0
        out[lang] = float((own[k]["low"] + below) / 2) if cost[k] <= 0 else float(np.nextafter(own[0]["high"], 2))
    return out


def _scored(docs: DataFrame, labels: DataFrame, rows: int, score: str, toxic: str) -> DataFrame:
    """`docs` with the columns `score` and `toxic`: whether the score reaches the threshold of its language."""
    net, inner = fit_toxicity(docs, labels, rows)
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(net)  # of fixed size

    def maker():
        scorer = Scorer(shared.value)
        return lambda texts: [scorer.score(text_bytes(texts))]

    scored = append_columns(docs, ["text"], [(score, T.DoubleType())], maker)
    limit = F.lit(0.5)
    if "lang" in docs.columns:
        # a table of its own: thresholds come from the scores of all labelled rows, and no text is scored twice
        scored = written(scored, "scored")
        # at most 2 * ODDS * BINS + 1 rows a language
        counts = score_counts(scored.select("doc_id", "lang", F.col(f"`{score}`").alias("score")), labels, inner).collect()
        for lang, cut in sorted(calibrate(counts).items()):
            limit = F.when(F.col("lang") == lang, cut).otherwise(limit)
    return scored.withColumn(toxic, F.col(f"`{score}`") >= limit)


def score_toxicity(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted, toxic_by_language."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *[c for c in ("lang",) if c in docs.columns])
    return _scored(own, labels, rows, "score", "toxic_by_language").select(
        "doc_id",
        held_out(5, 0).alias("held_out"),
        "score",
        (F.col("score") >= 0.5).cast("int").alias("predicted"),
        "toxic_by_language",
    )


def drop_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """`docs` without those above the threshold of their language, same columns and values."""
    score, toxic = fresh(docs.columns, "score", "toxic")
    return _scored(docs, labels, SAMPLE_ROWS, score, toxic).filter(~F.col(toxic)).select(*columns(docs))
