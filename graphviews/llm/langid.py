"""Language of texts from a linear-chain conditional random field over their words.

A word's features are its prefixes and suffixes, character n-grams and whether it
stands in a language's lexicon; transitions between the languages of neighbouring
words are learned with the weights.  Training sequences join stretches of
documents of different languages, so the transitions know code switching.
Forward-backward gives each word's language probabilities; a text has the language
of the largest sum over all its words, and the mean probability as its score.

Training uses at most ``per_lang`` labelled rows of each language of at most
``max_chars`` characters (those of the smallest id hashes; where there are too few, inner
pieces of longer rows), which bounds what the
driver holds; prediction covers every whole text and sees nothing but the text.
The chains of a batch advance together, word by word, the longest first, so the
work is vectorised over documents and a very long text costs its own length only.

Defined results: null text or text without a letter is ``und`` with score 0; ties
go to the alphabetically first language; repeated rows are predicted each; rows
without a language, or an empty training table, teach nothing (everything is then
``und``).
"""

from __future__ import annotations

import re
import uuid
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphviews.llm.common import bounded_batches, held_out, returned_memory, table, worker_memory

UNKNOWN = "und"
SLOTS = 1 << 16
PER_LANG, MAX_CHARS = 300, 4000
STRETCH, BATCH, EPOCHS = 32, 128, 3
#: Words in one pass of the chains, and words whose scores a worker remembers.
CHAIN_WORDS, REMEMBERED = 350_000, 200_000
WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text and any(map(str.isalpha, text)) else []


class Slots(dict):
    """Hashed slots of features, remembered; slot 0 stays empty."""

    def __missing__(self, feature: str) -> int:
        if len(self) > REMEMBERED:
            self.clear()
        value = self[feature] = 1 + zlib.crc32(feature.encode("utf-8", "surrogatepass")) % (SLOTS - 1)
        return value


_SLOT = Slots()


def features(word: str, lexicon: dict[str, int]) -> list[int]:
    """Slots of a word's features; the last slots are the lexicons'."""
    marked = f"^{word}$"
    found = {"p" + word[:1], "p" + word[:2], "p" + word[:3], "s" + word[-1:], "s" + word[-2:], "s" + word[-3:]}
    found.update([marked[i : i + 2] for i in range(len(marked) - 1)])
    found.update([marked[i : i + 3] for i in range(len(marked) - 2)])
    slots = sorted(map(_SLOT.__getitem__, found))
    if (lang := lexicon.get(word)) is not None:
        slots.append(SLOTS + lang)
    return slots


class Chain:
    """The trained field: languages, lexicon, feature weights, start and transition scores."""

    def __init__(self, langs: list[str], lexicon: dict[str, int], weights, start, move):
        self.langs, self.lexicon = langs, lexicon
        self.weights, self.start, self.move = weights, start, move
        self.token = uuid.uuid4().hex

    def scores(self, words: list[str]) -> np.ndarray:
        """Positive scores of each word for each language, the best about 1."""
        slots = [features(w, self.lexicon) for w in words]
        sizes = np.fromiter(map(len, slots), np.int64, len(slots))
        flat = np.fromiter((x for s in slots for x in s), np.int64, int(sizes.sum()))
        value = np.add.reduceat(self.weights[flat], np.cumsum(sizes) - sizes, 0)
        return np.exp(np.maximum(value - value.max(1, keepdims=True), -60))


def chain_posteriors(emit: np.ndarray, lengths: np.ndarray, start: np.ndarray, move: np.ndarray) -> np.ndarray:
    """Posterior of each word's label; emit holds positive scores of all words, chain after chain."""
    order = np.argsort(-lengths, kind="stable")
    begin = (np.cumsum(lengths) - lengths)[order]
    sorted_lengths = lengths[order]
    steps = int(sorted_lengths[0]) if len(lengths) else 0
    active = np.searchsorted(-sorted_lengths, -np.arange(1, steps + 1), "right")
    alpha = np.empty_like(emit)
    now = np.broadcast_to(start, (len(order), len(start)))
    for t in range(steps):
        n = active[t]
        at = begin[:n] + t
        now = (now[:n] @ move if t else now[:n]) * emit[at]
        now = now / now.sum(1, keepdims=True)
        alpha[at] = now
    back = np.ones((len(order), emit.shape[1]), emit.dtype)
    for t in range(steps - 1, -1, -1):
        n = active[t]
        at = begin[:n] + t
        both = alpha[at] * back[:n]
        alpha[at] = both / both.sum(1, keepdims=True)
        if t:
            ahead = (back[:n] * emit[at]) @ move.T
            back[:n] = ahead / ahead.sum(1, keepdims=True)
    return alpha


def stretches_of(words: list[str]) -> list[list[str]]:
    """Stretches of one length that cover all words: the last one reaches back, a short text is repeated."""
    half = STRETCH // 2
    if len(words) < half:
        return [(words * half)[:half]] if words else []
    return [words[min(i, len(words) - half) :][:half] for i in range(0, len(words), half)]


def train(rows: list[tuple[str, str]], seed: int = 7) -> Chain:
    """Fit the field to (language, text) rows by stochastic gradients of the conditional likelihood."""
    langs = sorted({lang for lang, _ in rows})
    if not langs:
        return Chain([], {}, np.zeros((SLOTS, 0), np.float32), np.zeros(0), np.zeros((0, 0)))
    number = {lang: i for i, lang in enumerate(langs)}
    docs = [(number[lang], words_of(text)) for lang, text in rows]
    counts = [Counter() for _ in langs]
    for lang, words in docs:
        counts[lang].update(words)
    total: Counter = sum(counts, Counter())
    lexicon = {w: i for i, c in enumerate(counts) for w, n in c.items() if n >= 3 and n > 0.9 * total[w]}
    rng = np.random.default_rng(seed)
    stretches = [(lang, s) for lang, words in docs for s in stretches_of(words)]
    known = {w: i for i, w in enumerate(sorted({w for _, ws in stretches for w in ws}))}
    slots = [features(w, lexicon) for w in known]
    wide = max(map(len, slots), default=1)
    table_ = np.zeros((len(known), wide), np.int64)
    for i, s in enumerate(slots):
        table_[i, : len(s)] = s
    word_ids = np.array([[known[w] for w in ws] for _, ws in stretches])
    labels = np.array([lang for lang, _ in stretches])
    size = len(langs)
    weights = np.zeros((SLOTS + size, size))
    move, start = np.zeros((size, size)), np.zeros(size)
    grown = [np.full_like(x, 1e-2) for x in (weights, move, start)]
    half = STRETCH // 2
    for _ in range(EPOCHS):
        order = rng.permutation(len(stretches))
        # nine in ten sequences go on in their language, the others switch
        partner = np.where(rng.random(len(order)) < 0.9, order, rng.permutation(order))
        for at in range(0, len(order), BATCH):
            a, b = order[at : at + BATCH], partner[at : at + BATCH]
            ids = np.concatenate([word_ids[a], word_ids[b]], 1)
            gold = np.repeat(np.stack([labels[a], labels[b]], 1), half, 1)
            used = table_[ids]
            score = weights[used].sum(2)
            emit = np.exp(score - score.max(2, keepdims=True))
            step, begin = np.exp(move - move.max()), np.exp(start - start.max())
            n, length = ids.shape
            alpha, beta = np.empty_like(emit), np.ones_like(emit)
            for t in range(length):
                x = (alpha[:, t - 1] @ step if t else begin) * emit[:, t]
                alpha[:, t] = x / x.sum(1, keepdims=True)
            for t in range(length - 1, 0, -1):
                x = (beta[:, t] * emit[:, t]) @ step.T
                beta[:, t - 1] = x / x.sum(1, keepdims=True)
            gamma = alpha * beta
            gamma /= gamma.sum(2, keepdims=True)
            pair = alpha[:, :-1, :, None] * step * (beta[:, 1:] * emit[:, 1:])[:, :, None, :]
            pair /= pair.sum((2, 3), keepdims=True)
            truth = np.eye(size)[gold]
            grad_move = pair.sum((0, 1)) - np.einsum("nti,ntj->ij", truth[:, :-1], truth[:, 1:])
            grad_start = (gamma[:, 0] - truth[:, 0]).sum(0)
            flat, error = used.reshape(-1), np.repeat((gamma - truth).reshape(-1, size), wide, 0)
            grad = np.stack([np.bincount(flat, error[:, k], len(weights)) for k in range(size)], 1)
            grad[0] = 0
            for value, g, acc in ((weights, grad / n, grown[0]), (move, grad_move / n, grown[1]), (start, grad_start / n, grown[2])):
                acc += g * g
                value -= 0.3 * (g + 1e-5 * value) / np.sqrt(acc)
    weights[0] = 0
    return Chain(langs, lexicon, weights.astype(np.float32), np.exp(start - start.max()), np.exp(move - move.max()))


def _predict(shared, text: str, with_words: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chain: Chain = shared.value
        size = max(1, len(chain.langs))
        memory = worker_memory(chain.token, lambda: {"number": {}, "scores": np.zeros((1024, size), np.float32)})
        number, scores = memory["number"], memory["scores"]
        for batch in batches:
            texts = batch.column(text).to_pylist()
            lo = 0
            while lo < len(texts):
                docs, total, hi = [], 0, lo
                while hi < len(texts) and (hi == lo or total < CHAIN_WORDS):
                    docs.append(words_of(texts[hi]) if chain.langs else [])
                    total += len(docs[-1])
                    hi += 1
                if len(number) > REMEMBERED:
                    number = {}
                fresh = list({w for words in docs for w in words}.difference(number))
                while len(scores) < len(number) + len(fresh):
                    scores = np.concatenate([scores, np.zeros_like(scores)])
                for at in range(0, len(fresh), 20_000):
                    part = fresh[at : at + 20_000]
                    scores[len(number) : len(number) + len(part)] = chain.scores(part)
                    number.update(zip(part, range(len(number), len(number) + len(part))))
                memory.update(number=number, scores=scores)
                lengths = np.fromiter(map(len, docs), np.int64, len(docs))
                get = number.__getitem__
                ids = np.fromiter((i for words in docs for i in map(get, words)), np.int64, int(lengths.sum()))
                posterior = chain_posteriors(scores[ids], lengths, chain.start.astype(np.float32), chain.move.astype(np.float32))
                ends = np.cumsum(lengths)
                summed = np.zeros((len(docs), size))
                some = lengths > 0
                if some.any():
                    summed[some] = np.add.reduceat(posterior.astype(np.float64), (ends - lengths)[some], 0) / lengths[some, None]
                best = summed.argmax(1)
                pred = [chain.langs[b] if n else UNKNOWN for b, n in zip(best.tolist(), lengths.tolist())]
                out = [*(batch.column(c).slice(lo, hi - lo) for c in batch.schema.names), pa.array(pred, pa.string()),
                       pa.array(np.clip(summed[np.arange(len(docs)), best], 0, 1), pa.float64())]
                names = [*batch.schema.names, "lang_pred", "lang_score"]
                if with_words:
                    tags = posterior.argmax(1).tolist()
                    out.append(pa.array([[{"word": w, "lang": chain.langs[t]} for w, t in zip(ws, tags[e - n : e])] for ws, n, e in zip(docs, lengths.tolist(), ends.tolist())],
                                        pa.list_(pa.struct([("word", pa.string()), ("lang", pa.string())]))))
                    names.append("lang_words")
                yield pa.RecordBatch.from_arrays(out, names)
                lo = hi
        _SLOT.clear()
        returned_memory()

    return run


def fit(labelled: DataFrame, *, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", per_lang: int = PER_LANG, max_chars: int = MAX_CHARS) -> Chain:
    """Train on at most per_lang rows of each language."""
    rows = labelled.select(F.col(doc_id).alias("id"), F.col(text).alias("text"), F.col(lang).alias("lang"))
    # an inner piece of a longer row stands behind all rows that are short enough
    long = F.length("text") > max_chars
    piece = F.when(long, F.col("text").substr(((F.length("text") - max_chars) / 2).cast("int") + 1, F.lit(max_chars))).otherwise(F.col("text"))
    rows = rows.where(F.col("lang").isNotNull()).select("id", "lang", long.alias("long"), piece.alias("text")).where(F.col("text").rlike(r"\p{L}"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy("long", F.xxhash64("id"), "id", "text"))
    sample = rows.withColumn("r", rank).where(F.col("r") <= per_lang).select("lang", "text").orderBy("lang", "text")
    return train([(r["lang"], r["text"]) for r in sample.toLocalIterator()])


def identify(docs: DataFrame, chain: Chain, *, text: str = "text", with_words: bool = False) -> DataFrame:
    """docs with lang_pred and lang_score, and with_words the label of every word in lang_words.

    Columns of these names in docs are replaced.
    """
    docs = docs.drop("lang_pred", "lang_score", "lang_words")
    shared = docs.sparkSession.sparkContext.broadcast(chain)
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    extra = ", lang_words array<struct<word: string, lang: string>>" if with_words else ""
    return bounded_batches(docs).mapInArrow(_predict(shared, text, with_words), f"{fields}, lang_pred string, lang_score double{extra}")


def keep_known(docs: DataFrame, chain: Chain, *, text: str = "text", least: float = 0.35) -> DataFrame:
    """The documents, all columns, with a known language of at least the score."""
    shared = docs.sparkSession.sparkContext.broadcast(chain)

    @F.arrow_udf("struct<lang_pred:string,lang_score:double>")
    def language(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        # only texts go to Python and only verdicts come back; the rows wait in Spark
        predict = _predict(shared, "text", False)
        for batch in texts:
            parts = list(predict(iter([pa.RecordBatch.from_arrays([batch], ["text"])])))
            found = pa.Table.from_batches(parts).combine_chunks() if parts else None
            columns = [found.column(c).combine_chunks() if found else pa.array([], t) for c, t in (("lang_pred", pa.string()), ("lang_score", pa.float64()))]
            yield pa.StructArray.from_arrays(columns, ["lang_pred", "lang_score"])

    said = language(F.col(text))
    return bounded_batches(docs).where((said["lang_pred"] != UNKNOWN) & (said["lang_score"] >= least))


def op4_language_id(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    chain = fit(docs.where(~held_out("doc_id", 4, 2)))
    out = identify(docs.select("doc_id", "text"), chain)
    return out.select("doc_id", held_out("doc_id", 4, 2).alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))
