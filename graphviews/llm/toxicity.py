"""Toxicity by a chain of linear classifiers.

The categories stand in a fixed order; the model of each sees the words of a text, their beginnings
and the probabilities that the earlier models give it.  In training those are
out-of-fold: each fold's probabilities come from models that never saw it, so a
later model learns how far an earlier one can be trusted on new texts.

Training takes at most ``max_rows`` labelled rows (the smallest id hashes) of at
most ``max_chars`` characters, which bounds the driver's part; features found in
fewer than ``min_docs`` of them have no weight.  Every whole text is scored, map
only, with a broadcast of the weights.  The bar from which a text counts as positive is
the best one on the out-of-fold probabilities of the training rows.

Defined results: null or empty text has the probabilities of a text without known
words; without labelled rows, or with one class only, a model says the class's
share (0.5 without rows) for every text; a null label teaches its own category nothing;
repeated rows are scored each.
"""

from __future__ import annotations

import uuid
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.llm.common import alnum_words, bounded_batches, table, worker_memory

MAX_ROWS, MAX_CHARS, MIN_DOCS = 6000, 20_000, 8
FOLDS, STEPS, RIDGE = 4, 150, 2e-4
#: A feature gets a weight if its positives are off the share by this chi-square (one in a thousand by chance).
TELLING = 10.83
#: Bytes of the word beginnings that are features beside the word.
HEADS = (5, 6, 7, 8)
REMEMBERED = 400_000


def sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -50, 50)))


def features(word: bytes) -> list[bytes]:
    """A word and its beginnings, marked by their length."""
    return [word, *(b"%d %b" % (k, word[:k]) for k in HEADS if len(word) > k)]


class Sparse:
    """Rows of distinct word numbers; one more dense block holds earlier probabilities."""

    def __init__(self, rows: list[list[int]], width: int):
        self.sizes = np.fromiter(map(len, rows), np.int64, len(rows))
        self.columns = np.fromiter((c for r in rows for c in r), np.int64, int(self.sizes.sum()))
        self.owner = np.repeat(np.arange(len(rows)), self.sizes)
        self.width, self.n = width, len(rows)


class Linear:
    """Logistic regression on word presence and dense inputs."""

    def __init__(self, words: np.ndarray, dense: np.ndarray, bias: float):
        self.words, self.dense, self.bias = words, dense, bias

    @classmethod
    def fitted(cls, x: Sparse, dense: np.ndarray, y: np.ndarray, use: np.ndarray) -> Linear:
        known = use & ~np.isnan(y)
        share = float(y[known].mean()) if known.any() else 0.5
        words, extra, bias = np.zeros(x.width), np.zeros(dense.shape[1]), float(np.log(max(share, 1e-4) / max(1 - share, 1e-4)))
        if not 0 < share < 1 or not known.any():
            return cls(words, extra, bias)
        weight = known / known.sum()
        rows = np.bincount(x.columns, known[x.owner].astype(float), x.width)
        positives = np.bincount(x.columns, np.where(known, np.nan_to_num(y), 0)[x.owner], x.width)
        telling = (positives - rows * share) ** 2 > TELLING * np.maximum(rows, 1) * share * (1 - share)
        used = telling[x.columns]
        columns, owner = x.columns[used], x.owner[used]
        target = np.where(known, y, 0)
        state = [np.zeros(x.width), np.zeros(dense.shape[1]), 0.0]
        speed = [np.zeros(x.width), np.zeros(dense.shape[1]), 0.0]
        for step in range(1, STEPS + 1):
            out = np.bincount(owner, words[columns], x.n) + dense @ extra + bias
            error = (sigmoid(out) - target) * weight
            grads = [np.bincount(columns, error[owner], x.width) + RIDGE * words, dense.T @ error, error.sum()]
            moved = []
            for k, g in enumerate(grads):
                state[k] = 0.9 * state[k] + 0.1 * g
                speed[k] = 0.99 * speed[k] + 0.01 * g * g
                moved.append(0.1 * (state[k] / (1 - 0.9**step)) / (np.sqrt(speed[k] / (1 - 0.99**step)) + 1e-6))
            words, extra, bias = words - moved[0], extra - moved[1], bias - moved[2]
        return cls(words, extra, float(bias))

    def of(self, x: Sparse, dense: np.ndarray) -> np.ndarray:
        return sigmoid(np.bincount(x.owner, self.words[x.columns], x.n) + dense @ self.dense + self.bias)


class ChainModel:
    def __init__(self, vocabulary: dict[bytes, int], models: list[tuple[str, Linear]]):
        self.vocabulary, self.models, self.token = vocabulary, models, uuid.uuid4().hex
        self.bars: dict[str, float] = {}

    def rows(self, texts: list[bytes | None], known: dict[bytes, tuple[int, ...]] | None = None) -> Sparse:
        """Feature numbers of each text; known remembers those of words from call to call."""
        known = {} if known is None else known
        number, rows = self.vocabulary.get, []
        for text in texts:
            found: set[int] = set()
            for w in set(alnum_words(text)):
                if (slots := known.get(w)) is None:
                    if len(known) >= REMEMBERED:
                        known.clear()
                    slots = known[w] = tuple(i for f in features(w) if (i := number(f)) is not None)
                found.update(slots)
            rows.append(sorted(found))
        return Sparse(rows, len(self.vocabulary))

    def probabilities(self, texts: list[bytes | None], known: dict | None = None) -> np.ndarray:
        x = self.rows(texts, known)
        out = np.zeros((x.n, 0))
        for _, model in self.models:
            out = np.column_stack([out, model.of(x, out)])
        return out


def best_bar(probability: np.ndarray, y: np.ndarray) -> float:
    """The probability from which calling a text positive gives the best F1 on out-of-fold training rows; 0.5 without positives."""
    known = ~np.isnan(y)
    p, y = probability[known], y[known]
    if not y.any():
        return 0.5
    order = np.argsort(-p, kind="stable")
    hits = np.cumsum(y[order])
    f1 = 2 * hits / (np.arange(1, len(p) + 1) + y.sum())
    f1[np.append(p[order][1:] == p[order][:-1], False)] = 0  # equal probabilities go together
    at = int(f1.argmax())
    below = p[order][at + 1] if at + 1 < len(p) else 0.0
    return float((p[order][at] + below) / 2)


def train(texts: list[bytes], labels: dict[str, list[float | None]], folds: np.ndarray, min_docs: int = MIN_DOCS) -> ChainModel:
    """Fit the categories in the order of labels."""
    seen = Counter(f for t in texts for f in {f for w in set(alnum_words(t)) for f in features(w)})
    vocabulary = {w: i for i, w in enumerate(sorted(w for w, n in seen.items() if n >= min_docs))}
    chain = ChainModel(vocabulary, [])
    x = chain.rows(texts)
    fed = np.zeros((len(texts), 0))
    for category, values in labels.items():
        y = np.array([np.nan if v is None else float(v) for v in values])
        chain.models.append((category, Linear.fitted(x, fed, y, np.ones(len(texts), bool))))
        out_of_fold = np.zeros(len(texts))
        for fold in range(FOLDS):
            part = folds == fold
            if part.any():
                out_of_fold[part] = Linear.fitted(x, fed, y, ~part).of(x, fed)[part]
        fed = np.column_stack([fed, out_of_fold])
        chain.bars[category] = best_bar(out_of_fold, y)
    return chain


def fit(docs: DataFrame, labels: DataFrame, categories: dict[str, object], *, doc_id: str = "doc_id", text: str = "text", max_rows: int = MAX_ROWS, max_chars: int = MAX_CHARS) -> ChainModel:
    """Train on a bounded sample of labelled documents; categories: name to a column of labels that is 0 or 1."""
    spark = docs.sparkSession
    picked = labels.where(F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("tox_id"), *[F.expr(e).cast("double").alias(c) for c, e in categories.items()])
    picked = picked.orderBy(F.xxhash64("tox_id"), "tox_id").limit(max_rows)
    rows = docs.select(F.col(doc_id).alias("id"), F.col(text).cast("binary").alias("body")).where(F.length(F.col("body")) <= max_chars)
    sample = rows.join(F.broadcast(picked), F.col("id") == F.col("tox_id")).withColumn("fold", F.pmod(F.xxhash64("id", F.lit(1)), F.lit(FOLDS)))
    got = sample.orderBy("id", *categories).limit(max_rows).collect()  # max_rows at most
    return train([bytes(r["body"]) for r in got], {c: [r[c] for r in got] for c in categories}, np.array([r["fold"] for r in got], np.int64))


def score(docs: DataFrame, chain: ChainModel, *, text: str = "text") -> DataFrame:
    """docs with a probability p_<category> for each category; columns of these names in docs are replaced."""
    shared = docs.sparkSession.sparkContext.broadcast(chain)
    added = [f"p_{c}" for c, _ in chain.models]
    docs = docs.drop(*added)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        known = worker_memory(model.token, dict)
        for batch in batches:
            for lo in range(0, len(batch), 512):
                part = batch.slice(lo, 512)
                p = model.probabilities(part.column(text).cast(pa.binary()).to_pylist(), known)
                yield pa.RecordBatch.from_arrays([*part.columns, *(pa.array(p[:, k]) for k in range(len(added)))], [*part.schema.names, *added])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return bounded_batches(docs).mapInArrow(run, f"{fields}, " + ", ".join(f"{a} double" for a in added))


#: The chain's order and the labels behind it.
CATEGORIES = {"low_quality": "1 - quality", "toxic": "toxic"}


def op10_toxicity_chain(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    chain = fit(docs, table(spark, sf_dir, "labels"), CATEGORIES)
    out = score(docs, chain)
    return out.select("doc_id", "p_low_quality", "p_toxic", (F.col("p_toxic") >= chain.bars["toxic"]).alias("toxic"))
