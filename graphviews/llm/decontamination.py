"""Benchmark decontamination with suffix arrays over the training words.

Every Arrow batch of documents is a shard: its words become integers, the
suffixes that can start a benchmark window are sorted into a suffix array, and
every benchmark suffix is binary-searched in it for its first ``window`` words.
Where one occurs, the document's suffix is searched in turn among all suffixes of
the benchmark, in their full order; the words it shares with its neighbours there
are the longest verbatim match that starts at that word, with one item at
consecutive words of it.  A hit's place is a span of words (start, length).

Only words of the benchmark get a number, and only positions whose first two
words follow each other somewhere in the benchmark enter the array.  Both steps
drop suffixes that no search could return.

Nothing is shuffled: a document is searched where it is read.  The benchmark is
broadcast in blocks of at most ``block_bytes``; with more text than that, the
documents stream through one search after another.

Defined results: null text or text without words has no words and no hits; an
item without words, or null, matches nothing; an item of fewer words than a
window is one window; items with a null id count as the id ``""``; repeated
items count once; repeated documents are searched each on its own.  Columns of
the input are passed through, those added start with ``decon_``.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphviews.llm.common import alnum_words, bounded_batches, table

WINDOW = 10
BLOCK_BYTES = 32 << 20
#: Words of one suffix array; a longer document is a shard of its own.
SHARD_WORDS = 2_000_000

ADDED = T.StructType(
    [
        T.StructField("decon_words", T.LongType()),
        T.StructField("decon_spans", T.ArrayType(T.LongType())),
        T.StructField("decon_items", T.ArrayType(T.StringType())),
        T.StructField("decon_longest", T.LongType()),
    ]
)


class BenchmarkWindows:
    """The benchmark's words as numbers, and its distinct windows as packed sort keys."""

    def __init__(self, items: Iterable[tuple[str, bytes]], window: int = WINDOW):
        self.window = window
        self.vocab: dict[bytes, int] = {}
        found: dict[tuple[int, ...], set[str]] = {}
        follows: set[tuple[int, int]] = set()
        different: dict[tuple[int, ...], None] = {}
        for item, text in items:
            ids = [self.vocab.setdefault(w, len(self.vocab) + 1) for w in alnum_words(text)]
            if len(ids) > window:
                different[tuple(ids)] = None
            for at in range(max(1, len(ids) - window + 1) if ids else 0):
                found.setdefault(tuple(ids[at : at + window]), set()).add(item)
            follows.update(zip(ids, ids[1:]))
        self.bits = 16 if len(self.vocab) < (1 << 16) - 1 else 32
        self.windows = list(found)
        self.items = [sorted(found[w]) for w in self.windows]
        self.length = np.array([len(w) for w in self.windows], np.int64)
        full = (1 << self.bits) - 1
        padded = np.zeros((len(self.windows), window), np.uint64)
        ceiling = np.full((len(self.windows), window), full, np.uint64)
        for row, w in enumerate(self.windows):
            padded[row, : len(w)] = ceiling[row, : len(w)] = w
        self.low, self.high = self.packed(padded), self.packed(ceiling)
        self.singles = np.zeros(len(self.vocab) + 1, bool)
        self.singles[[w[0] for w in self.windows if len(w) == 1]] = True
        self.pairs = np.array(sorted((a << 32) | b for a, b in follows), np.int64)
        self.words = np.array([w for ids in different for w in (*ids, -1)], np.int64)  # -1 ends an item and equals no word
        self.suffixes = suffix_order(self.words)

    def longest(self, ids: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Words that the suffixes of a shard at starts share with the benchmark suffix nearest to them."""
        if not len(self.suffixes):
            return np.zeros(len(starts), np.int64)
        padded = np.concatenate([ids, [0]])  # 0 is no word of the benchmark

        def shared(of: np.ndarray, place: np.ndarray, begun: np.ndarray) -> np.ndarray:
            out, open_ = begun.copy(), np.arange(len(of))
            while len(open_):
                at = of[open_] + out[open_]
                open_ = open_[padded[np.minimum(at, len(ids))] == self.words[place[open_] + out[open_]]]
                out[open_] += 1
            return out

        lo, hi = np.full(len(starts), -1), np.full(len(starts), len(self.suffixes))
        below, above = np.zeros(len(starts), np.int64), np.zeros(len(starts), np.int64)
        while len(which := np.flatnonzero(hi - lo > 1)):
            mid = (lo[which] + hi[which]) >> 1
            place = self.suffixes[mid]
            same = shared(starts[which], place, np.minimum(below[which], above[which]))
            beyond = padded[np.minimum(starts[which] + same, len(ids))] > self.words[place + same]
            lo[which[beyond]], below[which[beyond]] = mid[beyond], same[beyond]
            hi[which[~beyond]], above[which[~beyond]] = mid[~beyond], same[~beyond]
        return np.maximum(below, above)

    def packed(self, words: np.ndarray) -> list[np.ndarray]:
        """Columns of words as few unsigned integers that sort in the same order."""
        per = 64 // self.bits
        keys = []
        for at in range(0, self.window, per):
            key = np.zeros(len(words), np.uint64)
            for column in range(at, at + per):
                key <<= np.uint64(self.bits)
                if column < self.window:
                    key |= words[:, column].astype(np.uint64)
            keys.append(key)
        return keys


def suffix_order(words: np.ndarray) -> np.ndarray:
    """Starts of all suffixes in sorted order, by ranks of prefixes that double in length."""
    if not len(words):
        return np.zeros(0, np.int64)
    rank, width = np.unique(words, return_inverse=True)[1], 1
    while True:
        following = np.concatenate([rank[width:] + 1, np.zeros(min(width, len(words)), np.int64)])
        key = rank * (len(words) + 1) + following
        names, rank = np.unique(key, return_inverse=True)
        if len(names) == len(words):
            return np.argsort(rank)
        width *= 2


class SuffixArray:
    """Suffixes of a shard's words in sorted order, compared on their first ``window`` words."""

    def __init__(self, ids: np.ndarray, index: BenchmarkWindows):
        padded = np.concatenate([ids, np.zeros(index.window, ids.dtype)])
        code = (padded[: len(ids)] << 32) | padded[1 : len(ids) + 1]
        can = np.zeros(len(ids), bool)
        known = np.flatnonzero(ids)
        if len(index.pairs) and len(known):
            at = np.minimum(np.searchsorted(index.pairs, code[known]), len(index.pairs) - 1)
            can[known] = index.pairs[at] == code[known]
        can |= index.singles[ids]
        start = np.flatnonzero(can)
        keys = index.packed(padded[start[:, None] + np.arange(index.window)])
        order = np.lexsort(keys[::-1])
        self.start = start[order]
        self.keys = [k[order] for k in keys]

    def bound(self, wanted: list[np.ndarray], after: bool) -> np.ndarray:
        """Binary search of all wanted suffixes at once: the first place not before (or, with after, beyond) each."""
        lo = np.zeros(len(wanted[0]), np.int64)
        hi = np.full(len(wanted[0]), len(self.start), np.int64)
        while (open_ := lo < hi).any():
            mid = (lo + hi) >> 1
            at = np.minimum(mid, len(self.start) - 1)
            less = np.zeros(len(lo), bool)
            same = np.ones(len(lo), bool)
            for have, want in zip(self.keys, wanted):
                value = have[at]
                less |= same & (value < want)
                same &= value == want
            if after:
                less |= same
            lo = np.where(open_ & less, mid + 1, lo)
            hi = np.where(open_ & ~less, mid, hi)
        return lo


def search_shard(docs: list[list[bytes]], index: BenchmarkWindows) -> tuple[list, list, list]:
    """For each document: hit spans (start, length, ...), items that occur, longest verbatim match in words."""
    lengths = np.fromiter(map(len, docs), np.int64, len(docs))
    begins = np.concatenate([[0], np.cumsum(lengths + 1)])
    number = index.vocab.get
    ids = np.zeros(begins[-1], np.int64)
    for at, words in zip(begins, docs):
        ids[at : at + len(words)] = [number(w, 0) for w in words]
    spans: list[list[int]] = [[] for _ in docs]
    items: list[list[str]] = [[] for _ in docs]
    longest = [0] * len(docs)
    if not index.windows or not ids.any():
        return spans, items, longest
    suffixes = SuffixArray(ids, index)
    if not len(suffixes.start):
        return spans, items, longest
    first, last = suffixes.bound(index.low, False), suffixes.bound(index.high, True)
    counts = last - first
    which = np.repeat(np.arange(len(counts)), counts)
    if not len(which):
        return spans, items, longest
    ranks = np.arange(len(which)) - np.repeat(np.cumsum(counts) - counts, counts) + first[which]
    at = suffixes.start[ranks]
    reach = index.length[which]
    order = np.argsort(at, kind="stable")
    at, reach, which = at[order], reach[order], which[order]
    doc = np.searchsorted(begins, at, "right") - 1
    ends = np.maximum.accumulate(at + reach)
    new = np.concatenate([[True], at[1:] > ends[:-1]])  # touching spans merge, documents never touch
    open_at = np.flatnonzero(new)
    close = np.concatenate([open_at[1:] - 1, [len(at) - 1]])
    for d, s, e in zip(doc[open_at].tolist(), at[open_at].tolist(), ends[close].tolist()):
        spans[d] += [s - int(begins[d]), e - s]
    seen: list[set[str]] = [set() for _ in docs]
    met = np.unique(doc * len(index.windows) + which)
    for d, w in zip((met // len(index.windows)).tolist(), (met % len(index.windows)).tolist()):
        seen[d].update(index.items[w])
    items = [sorted(x) for x in seen]
    # at each place the longest match: with a suffix of one item, or, below a window, the short item that occurs there
    head = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
    match = index.longest(ids, at[head])
    match = np.where(match >= index.window, match, np.maximum.reduceat(reach, head))
    for d, n in zip(doc[head].tolist(), match.tolist()):
        longest[d] = max(longest[d], n)
    return spans, items, longest


def _searcher(index_of, doc_text: str, carried: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = index_of()
        for batch in batches:
            texts = batch.column(doc_text).cast(pa.binary()).to_pylist()
            kept = [n for n in batch.schema.names if not (carried and n in ADDED.names)]
            lo = 0
            while lo < len(texts):
                docs, words, hi = [], 0, lo
                while hi < len(texts) and (hi == lo or words < SHARD_WORDS):
                    docs.append(alnum_words(texts[hi]))
                    words += len(docs[-1])
                    hi += 1
                spans, items, longest = search_shard(docs, index)
                if carried:
                    for i in range(lo, hi):
                        old = batch.column("decon_spans")[i].as_py()
                        spans[i - lo] = merged_spans(old, spans[i - lo])
                        items[i - lo] = sorted({*items[i - lo], *batch.column("decon_items")[i].as_py()})
                        longest[i - lo] = max(longest[i - lo], batch.column("decon_longest")[i].as_py())
                part = batch.slice(lo, hi - lo)
                yield pa.RecordBatch.from_arrays(
                    [part.column(n) for n in kept]
                    + [
                        pa.array([len(d) for d in docs], pa.int64()),
                        pa.array(spans, pa.list_(pa.int64())),
                        pa.array(items, pa.list_(pa.string())),
                        pa.array(longest, pa.int64()),
                    ],
                    [*kept, *ADDED.names],
                )
                lo = hi

    return run


def merged_spans(a: list[int], b: list[int]) -> list[int]:
    """Union of two lists of (start, length, start, length, ...)."""
    out: list[int] = []
    for start, length in sorted([*zip(a[::2], a[1::2]), *zip(b[::2], b[1::2])]):
        if out and start <= out[-2] + out[-1]:
            out[-1] = max(out[-1], start + length - out[-2])
        else:
            out += [start, length]
    return out


def match_benchmark(
    docs: DataFrame, items: DataFrame, *, text: str = "text", item_id: str = "item_id",
    item_text: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES,
) -> DataFrame:
    """docs with decon_words, decon_spans (hit words as start, length pairs), decon_items and decon_longest.

    Columns of these names in docs are replaced.
    """
    docs = docs.drop(*ADDED.names)
    out = bounded_batches(docs)
    schema = T.StructType([*docs.schema.fields, *ADDED.fields])
    for block, shared in enumerate(_indexes(docs.sparkSession, items, item_id=item_id, item_text=item_text, window=window, block_bytes=block_bytes)):
        out = out.mapInArrow(_searcher(lambda shared=shared: shared.value, text, block > 0), schema)
    return out


def _indexes(spark, items: DataFrame, *, item_id: str = "item_id", item_text: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> list:
    """Broadcasts of the benchmark's windows, in as many blocks as its size asks for."""
    items = items.select(
        F.coalesce(F.col(item_id).cast("string"), F.lit("")).alias("item"), F.col(item_text).cast("string").alias("text")
    ).where("text is not null").distinct()
    total = items.agg(F.sum(F.octet_length("text") + F.octet_length("item"))).first()[0] or 0
    blocks = max(1, -(-2 * total // block_bytes)) if total > block_bytes else 1
    out = []
    for block in range(blocks):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == block)
        index = BenchmarkWindows([(r["item"], r["text"].encode()) for r in part.toLocalIterator()], window)
        out.append(spark.sparkContext.broadcast(index))
    return out


def hit_words():
    """Column: words inside any hit span."""
    spans = F.col("decon_spans")
    return F.aggregate(
        F.transform(spans, lambda x, i: F.when(i % 2 == 1, x).otherwise(F.lit(0).cast("long"))),
        F.lit(0).cast("long"), lambda a, x: a + x,
    )


def contamination(docs: DataFrame, items: DataFrame, *, doc_id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """One row per document: words, words hit, items that occur and their digest, the longest match, and where (``start+length`` in words, each with a blank behind it)."""
    found = match_benchmark(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")), items, **options)
    n_hit = hit_words()
    return found.select(
        "doc_id",
        F.col("decon_words").alias("n_words"),
        n_hit.alias("n_hit"),
        F.size("decon_items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("decon_items"), ","), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"),
        F.col("decon_longest").alias("longest_match"),
        F.array_join(F.transform("decon_spans", lambda x, i: F.concat(x.cast("string"), F.when(i % 2 == 0, "+").otherwise(" "))), "").alias("hit_spans"),
    )


def remove_contaminated(docs: DataFrame, items: DataFrame, **options) -> DataFrame:
    """The documents, all columns, in which no benchmark window occurs."""
    text = options.get("text", "text")
    out = bounded_batches(docs)
    for shared in _indexes(docs.sparkSession, items, **{k: v for k, v in options.items() if k != "text"}):
        out = out.where(~_hit(shared)(F.col(text)))
    return out


def _hit(shared):
    @F.arrow_udf("boolean")
    def hit(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        # only texts go to Python and only verdicts come back; the rows wait in Spark
        search = _searcher(lambda: shared.value, "text", False)
        for batch in texts:
            flags = [bool(s) for part in search(iter([pa.RecordBatch.from_arrays([batch], ["text"])])) for s in part.column("decon_spans").to_pylist()]
            yield pa.array(flags, pa.bool_())

    return hit


def op7_decontaminate(spark, sf_dir):
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


#: The SQL computes longest_match as the longest run of hits along one diagonal.
OP7_SQL = r"""
WITH RECURSIVE lowered AS (
  SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
d AS (SELECT doc_id, coalesce(w, []::VARCHAR[]) AS w FROM lowered),
b AS (SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark WHERE text IS NOT NULL),
win AS (SELECT item_id, p, least(len(w), 10) AS k, array_to_string(list_slice(w, p, p + least(len(w), 10) - 1), ' ') AS s
        FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 10, 0) + 2)) AS p FROM b WHERE len(w) > 0)),
ks AS (SELECT DISTINCT k FROM win),
dw AS (SELECT doc_id, k, p, array_to_string(list_slice(w, p, p + k - 1), ' ') AS s
       FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS p FROM d, ks WHERE len(w) >= k)),
m AS (SELECT doc_id, dw.p AS p, dw.k AS k, win.p AS q, item_id FROM dw JOIN win USING (k, s)),
hx AS (SELECT DISTINCT doc_id, x FROM (SELECT doc_id, unnest(range(p, p + k)) AS x FROM m)),
isl AS (SELECT doc_id, min(x) - 1 AS a, count(*) AS n FROM (SELECT doc_id, x, x - row_number() OVER (PARTITION BY doc_id ORDER BY x) AS g FROM hx) GROUP BY doc_id, g),
hit AS (SELECT doc_id, sum(n) AS n_hit, string_agg(a || '+' || n || ' ', '' ORDER BY a) AS spans FROM isl GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS s
        FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS i FROM m) GROUP BY doc_id),
diag AS (SELECT DISTINCT doc_id, item_id, k, p, p - q AS g FROM m),
runs AS (SELECT doc_id, k, p - row_number() OVER (PARTITION BY doc_id, item_id, k, g ORDER BY p) AS r, item_id, g FROM diag),
lng AS (SELECT doc_id, max(n) AS n FROM (SELECT doc_id, k + count(*) - 1 AS n FROM runs GROUP BY doc_id, item_id, k, g, r) GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(its.s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated, coalesce(lng.n, 0)::BIGINT AS longest_match, coalesce(hit.spans, '') AS hit_spans
FROM d LEFT JOIN hit USING (doc_id) LEFT JOIN its USING (doc_id) LEFT JOIN lng USING (doc_id)
"""
