"""Lexical retrieval packing: windows filled with BM25 neighbours of a seed.

1. Texts become token ids once; the table is kept in the shared folder.  What a
   document has in whole windows needs no partner and is a sequence by itself.
   Its tail, shorter than a window, is a unit to be packed.
2. Document frequencies, the number of documents and their mean length are counted
   over all documents; they are arrays of the tokenizer's vocabulary, so what is
   broadcast does not grow with the data.
3. Units are dealt to index shards by content.  A router holds at most ``leaders``
   different units (those of the smallest hashes) as random projections of their BM25 weights
   and gives each unit the two of the largest cosine; units of equal leaders stand together, and shards are runs of them of about
   ``shard_terms`` postings.  A pair of leaders with more than that has shards of its own,
   among which its units are dealt by hash.
4. A shard is packed by one task.  The longest unused unit is the seed: a query of its whole
   document's terms to the shard's index.  Its window takes the best unused units in turn, the last one is cut at the window's end, its rest stays unused.
   Equal scores go by the next unit after the seed.  A document is indexed by all its terms,
   whatever its tail holds.
5. What is left at the end is cut into sequences of a power of two.

Work grows with the units, as shards have one size; nothing but counts of pairs of leaders
and the router comes to the driver.  A seed sees the neighbours of its own shard only: how
many of its best ones over the whole corpus those are is measured by ``shard_recall``.

So no sequence is padded.  Word by word tokenization with a memory of known words
gives the ids of the whole text: the tokenizer's rules never reach across a blank,
nor across the last full stop or comma behind a letter.

Defined results: null text is empty and has the end id alone; every row, repeated
or not, is a document; a document of n ids lies in pieces that cover 0 to n.
"""

from __future__ import annotations

import copy
import heapq
import re
import unicodedata
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.llm.common import bounded_batches, stored, table, worker_memory

WINDOW = 2048
END_ID = 1
#: Postings (a unit and one of its terms) of an index shard, and leaders of the router.
SHARD_TERMS, LEADERS = 1 << 18, 256
#: Random projections by which the router compares.
ROUTED = 32
MOST_TASKS = 20_000
K1, B = 1.2, 0.75
#: Queries of one matrix product, neighbours taken at first, and the inverse share of documents from which a term is common.
BLOCK, WANTED, COMMON = 256, 64, 16
FAR = (1 << 32) - 1
REMEMBERED = 1_200_000
#: Letters from here on have exceptions of case or composition.
EXCEPTIONAL = re.compile("[^\x00-\u012f]").search

SCHEMA = "kind int, doc_id long, start long, length long, doc_tokens long, ids_crc32 long, sequence_id long, ids binary, terms binary, counts binary"
PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
FULL, TAIL, TERM, TOTAL = 0, 1, 2, 3


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary: itself if it prints, else the next from U+0100."""
    prints = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b if b in prints else next(spare)) for b in range(256)]


class WordIds(dict):
    """Ids of words as bytes, remembered.

    A lower-case word of Latin letters is one unit of the merges: spelled in byte
    letters, it goes to the model at once.  A mark behind a letter is a unit of its
    own.  Any other word takes the tokenizer's whole way.
    """

    def __init__(self, tokenizer, code: str):
        super().__init__({"": b""})
        self.tokenizer, self.code, self.letters, self.model = tokenizer, code, byte_letters(), tokenizer.model

    def __missing__(self, word: str) -> bytes:
        if len(self) >= REMEMBERED:
            self.clear()
            self[""] = b""
        plain = not EXCEPTIONAL(word)
        if plain and word[-1] in ".," and word[:-1].isalpha():
            value = self[word[:-1]] + self[word[-1]]
            if len(word) > 6:
                return value  # most long words are rare, with the mark all the more
        elif plain and word.isalpha() and word.islower():
            spelled = word if word.isascii() else "".join(map(self.letters.__getitem__, unicodedata.normalize("NFC", word).encode()))
            value = array(self.code, [t.id for t in self.model.tokenize(spelled)]).tobytes()
        else:
            value = array(self.code, self.tokenizer.encode(word, add_special_tokens=False).ids).tobytes()
        self[word] = value
        return value


class TextIds:
    """Ids of whole texts as bytes."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.vocabulary = self.tokenizer.get_vocab_size()
        self.kind = np.dtype("<u2") if self.vocabulary <= 1 << 16 else np.dtype("<u4")
        self.end = np.array([END_ID], self.kind).tobytes()
        self.known = WordIds(self.tokenizer, "H" if self.kind.itemsize == 2 else "I")  # little-endian machines

    def of(self, texts: list[str | None]) -> list[bytes]:
        get, out = self.known.__getitem__, []
        for text in texts:
            text = text or ""
            folded = text.lower() if text.isascii() or not EXCEPTIONAL(text) else text
            out.append(b"".join(map(get, folded.replace("\n", " ").split(" "))) + self.end)
        return out


def text_ids(path: str) -> TextIds:
    """One for each worker process, so that tasks share what it remembers."""
    return worker_memory(f"ids {path}", lambda: TextIds(path))


def _crc(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


def _encode(path: str, window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        encoder = text_ids(path)
        frequency = np.zeros(encoder.vocabulary, np.int64)
        documents = tokens = made = 0
        base = TaskContext.get().partitionId() << 34
        names = [f.split()[0] for f in SCHEMA.split(", ")]
        types = [pa.int32(), *[pa.int64()] * 6, *[pa.binary()] * 3]

        def batch_of(rows):
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names)

        for batch in batches:
            ids_of, texts = batch.column("doc_id"), batch.column("text")
            for lo in range(0, len(batch), 256):
                rows = []
                for doc, raw in zip(ids_of.slice(lo, 256).to_pylist(), encoder.of(texts.slice(lo, 256).to_pylist())):
                    ids = np.frombuffer(raw, encoder.kind)
                    n = len(ids)
                    terms, counts = np.unique(ids, return_counts=True)
                    frequency[terms] += 1
                    documents += 1
                    tokens += n
                    whole = n - n % window
                    for start in range(0, whole, window):
                        rows.append((FULL, doc, start, window, n, _crc(ids[start : start + window]), (base + made) * 2, None, None, None))
                        made += 1
                    if whole < n:
                        rows.append((TAIL, doc, whole, n - whole, n, None, None, ids[whole:].tobytes(), terms.tobytes(), counts.astype("<u4").tobytes()))
                yield batch_of(rows)
        if documents:
            rows = [(TERM, None, t, int(frequency[t]), *[None] * 6) for t in np.flatnonzero(frequency).tolist()]
            yield batch_of([*rows, (TOTAL, None, documents, tokens, *[None] * 6)])

    return run


class ShardIndex:
    """Inverted index of a shard's units with BM25 weights from counts over the whole corpus.

    A unit is indexed by its whole document: parts has the terms and counts of each,
    sizes the documents' lengths; without them the units are the documents.  Weights are
    whole 1/256, so sums are exact and a score is the same in any shard.
    """

    def __init__(self, units: list[np.ndarray], frequency: np.ndarray, documents: int, mean: float, parts=None, sizes=None):
        parts = [np.unique(u, return_counts=True) for u in units] if parts is None else parts
        sizes = np.fromiter(map(len, units), np.float64, len(units)) if sizes is None else np.asarray(sizes, np.float64)
        self.terms = [t for t, _ in parts]
        many = np.fromiter((len(t) for t in self.terms), np.int64, len(parts))
        term = np.concatenate(self.terms).astype(np.int64) if parts else np.zeros(0, np.int64)
        count = np.concatenate([c for _, c in parts]).astype(np.float64) if parts else np.zeros(0)
        unit = np.repeat(np.arange(len(parts)), many)
        df = np.maximum(frequency[term], 1)
        idf = np.maximum(np.log((documents - df + 0.5) / (df + 0.5)), 0)
        norm = K1 * (1 - B + B * sizes / mean)
        weight = np.rint(256 * idf * count * (K1 + 1) / (count + norm[unit]))
        telling = weight > 0
        term, unit, weight = term[telling], unit[telling], weight[telling].astype(np.float32)
        # what many documents have goes through a matrix product, the rest through postings
        self.n, self.size = len(parts), len(frequency)
        common = np.flatnonzero(frequency * COMMON > documents)
        self.column = np.full(self.size, -1, np.int64)
        self.column[common] = np.arange(len(common))
        column = self.column[term]
        self.matrix = np.zeros((len(common), self.n), np.float32)
        self.matrix[column[column >= 0], unit[column >= 0]] = weight[column >= 0]
        term, unit, weight = term[column < 0], unit[column < 0], weight[column < 0]
        order = np.argsort(term, kind="stable")
        self.unit, self.weight = unit[order].astype(np.int32), weight[order]
        self.begin = np.searchsorted(term[order], np.arange(self.size + 1))

    def without(self, gone: np.ndarray) -> ShardIndex:
        """The index of the other units alone, numbered in their order."""
        out = copy.copy(self)
        out.n, number = int((~gone).sum()), np.cumsum(~gone, dtype=np.int32) - 1
        keep = ~gone[self.unit]
        out.unit, out.weight, out.matrix = number[self.unit[keep]], self.weight[keep], self.matrix[:, ~gone]
        out.begin = np.concatenate([[0], np.cumsum(keep)])[self.begin]
        return out

    def one(self, query: np.ndarray) -> np.ndarray:
        """BM25 in 1/256 of every unit for one query's terms."""
        term = query.astype(np.int64)
        column = self.column[term]
        common = column >= 0
        out = self.matrix[column[common]].sum(0)
        term = term[~common]
        if len(term):
            rows = [slice(a, b) for a, b in zip(self.begin[term].tolist(), self.begin[term + 1].tolist()) if b > a]
            if rows:
                out = out + np.bincount(np.concatenate([self.unit[r] for r in rows]), np.concatenate([self.weight[r] for r in rows]), self.n)
        return out

    def block(self, queries: list[np.ndarray]) -> np.ndarray:
        """BM25 in 1/256 of every unit for each query's terms."""
        query = np.repeat(np.arange(len(queries)), [len(q) for q in queries])
        term = np.concatenate(queries).astype(np.int64)
        column = self.column[term]
        asked = np.zeros((len(queries), len(self.matrix)), np.float32)
        asked[query[column >= 0], column[column >= 0]] = 1
        out = asked @ self.matrix
        query, term = query[column < 0], term[column < 0]
        lo = self.begin[term]
        size = self.begin[term + 1] - lo
        at = np.arange(size.sum()) + np.repeat(lo - (np.cumsum(size) - size), size)
        out += np.bincount(np.repeat(query * self.n, size) + self.unit[at], self.weight[at], out.size).reshape(out.shape)
        return out

    def keys(self, queries: list[np.ndarray], seeds: np.ndarray, names: np.ndarray, total: int) -> np.ndarray:
        """A number for each query and unit: the score, then how soon the unit's name follows the seed's, round the end; -1 for the seed itself."""
        after = names[None, :] - seeds[:, None]
        after += np.where(after < 0, total, 0)
        score = self.one(queries[0])[None, :] if len(queries) == 1 else self.block(queries)
        return np.where(after > 0, (score.astype(np.int64) << 32) + (FAR - after), -1)


def largest(keys: np.ndarray, k: int) -> np.ndarray:
    return keys if keys.shape[1] <= k else np.partition(keys, keys.shape[1] - k, 1)[:, -k:]


def pack_shard(units: list[np.ndarray], index: ShardIndex, window: int) -> list[list[tuple[int, int, int]]]:
    """Sequences of (unit, start in it, length) of the units that an index holds; each but the last ones full, those of a power of two."""
    left, start = np.fromiter(map(len, units), np.int64, len(units)), np.zeros(len(units), np.int64)
    total, names, out, whole = int(left.sum()), np.arange(len(units)), [], index
    longest = [(-n, unit) for unit, n in enumerate(left.tolist())]
    heapq.heapify(longest)
    while total:
        length, seed = heapq.heappop(longest)
        if left[seed] != -length:
            continue  # used or cut since
        chosen, room, k = [seed], window + length, WANTED
        if room > 0 and total > -length:
            if 2 * np.count_nonzero(left) < len(names):
                index, names = whole.without(left == 0), np.flatnonzero(left)
            keys = np.where(left[names] > 0, index.keys([whole.terms[seed]], np.array([seed]), names, len(units))[0], -1)
            while True:
                best = units_of(-np.sort(-largest(keys[None, :], k), 1), [seed], len(units))[0]
                ends = np.cumsum(left[best])
                if k >= len(names) or len(ends) and ends[-1] >= room:
                    break
                k *= 4
            chosen += best[: int(np.searchsorted(ends, room)) + 1].tolist()
        filled, room = [], window
        for unit in chosen:
            take = min(room, int(left[unit]))
            filled.append((unit, int(start[unit]), take))
            start[unit] += take
            left[unit] -= take
            room -= take
            if left[unit]:
                heapq.heappush(longest, (-int(left[unit]), unit))
        total -= window - room
        out += [filled] if not room else powers_of_two(filled)
    return out


def units_of(keys: np.ndarray, seeds: np.ndarray, total: int) -> list[np.ndarray]:
    """Names of units from sorted keys."""
    return [(FAR - (row[row >= 0] & FAR) + seed) % total for row, seed in zip(keys, seeds)]


def powers_of_two(pieces: list[tuple[int, int, int]]) -> list[list[tuple[int, int, int]]]:
    """The pieces, cut where the binary digits of their total say."""
    total = sum(n for _, _, n in pieces)
    out, rest = [], list(reversed(pieces))
    for bit in reversed(range(total.bit_length())):
        room = total & (1 << bit)
        part = []
        while room:
            unit, start, n = rest.pop()
            take = min(room, n)
            part.append((unit, start, take))
            room -= take
            if take < n:
                rest.append((unit, start + take, n - take))
        if part:
            out.append(part)
    return out


class Router:
    """Leaders as random projections of their BM25 weights; a unit goes to those of the largest cosine."""

    def __init__(self, counted: Counts, terms: list[bytes], counts: list[bytes], sizes: list[int]):
        self.counted = counted
        self.random = np.random.default_rng(ROUTED).standard_normal((len(counted.frequency), ROUTED), np.float32)
        self.n, self.leaders = len(terms), self.vectors(terms, counts, sizes)

    def vectors(self, terms: list[bytes], counts: list[bytes], sizes: list[int]) -> np.ndarray:
        c = self.counted
        many = np.array([len(x) // c.kind.itemsize for x in terms], np.int64)
        term, count = np.frombuffer(b"".join(terms), c.kind).astype(np.int64), np.frombuffer(b"".join(counts), "<u4").astype(np.float64)
        norm = np.repeat(K1 * (1 - B + B * np.array(sizes, np.float64) / max(c.mean, 1)), many)
        rows = self.random[term] * (c.idf[term] * count / (count + norm)).astype(np.float32)[:, None]
        out = np.add.reduceat(rows, np.cumsum(many) - many) if len(many) else np.zeros((0, ROUTED), np.float32)
        length = np.sqrt((out * out).sum(1))
        return out / np.where(length > 0, length, 1)[:, None]

    def best(self, terms: list[bytes], counts: list[bytes], sizes: list[int]) -> np.ndarray:
        """The two best leaders of each unit; without any telling term, the number of leaders."""
        own = self.vectors(terms, counts, sizes)
        score = np.rint(own @ self.leaders.T * 4096)  # equal texts have equal leaders, whatever the block they come in
        out = np.full((2, len(own)), self.n, np.int32)
        told, at = own.any(1), np.arange(len(own))
        for k in range(min(2, self.n)):
            top = score.argmax(1)
            out[k, told] = top[told]
            score[at, top] = -np.inf
        return out


class Counts:
    """What indexes need of the whole corpus: document frequencies, the number of documents and their mean length."""

    def __init__(self, kind: np.dtype, frequency: np.ndarray, documents: int, mean: float):
        self.kind, self.frequency, self.documents, self.mean = kind, frequency, documents, mean
        df = np.maximum(frequency, 1)
        self.idf = np.maximum(np.log((documents - df + 0.5) / (df + 0.5)), 0)

    def index(self, terms: list[bytes], counts: list[bytes], sizes: list[int]) -> ShardIndex:
        parts = [(np.frombuffer(t, self.kind), np.frombuffer(c, "<u4")) for t, c in zip(terms, counts)]
        return ShardIndex([], self.frequency, self.documents, self.mean, parts, sizes)


def _routed(shared):
    """Rows of units with their two best leaders."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, router = shared.value
        for batch in batches:
            for lo in range(0, len(batch), BLOCK):
                part = batch.slice(lo, BLOCK)
                best = router.best(*(part.column(c).to_pylist() for c in ("terms", "counts", "doc_tokens")))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(best[0]), pa.array(best[1])], [*part.schema.names, "leader", "second"])

    return run


def dealt(sizes: list[tuple[int, int, int]], shard_terms: int) -> list[tuple[int, int, int, int]]:
    """(leader, second, first shard, shards) of pairs of leaders with so many postings: runs of small pairs share a shard."""
    out, shard, held = [], 0, 0
    for leader, second, size in sorted(sizes):
        if size > shard_terms:
            shard += held > 0
            many = -(-size // shard_terms)
            out.append((leader, second, shard, many))
            shard, held = shard + many, 0
            continue
        if held and held + size > shard_terms:
            shard, held = shard + 1, 0
        out.append((leader, second, shard, 1))
        held += size
    return out


def _packed(shared, window: int):
    """Pieces of the sequences of each shard of a partition, whose rows stand together in any order."""
    def shards(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            shard = batch.column("shard").to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(shard)) + 1).tolist(), len(batch)]
            for lo, hi in zip(cuts, cuts[1:]):
                if held and held[0].column("shard")[0].as_py() != shard[lo]:
                    yield pa.Table.from_batches(held)
                    held = []
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield pa.Table.from_batches(held)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in shards(b for b in batches if len(b)):
            yield from pieces_of(group, group.column("shard")[0].as_py()).to_batches(max_chunksize=10_000)

    def pieces_of(group: pa.Table, shard: int) -> pa.Table:
        counted, _ = shared.value
        group = group.sort_by([(c, "ascending") for c in ("doc_id", "start", "length", "ids")])
        ids = [np.frombuffer(x, counted.kind) for x in group.column("ids").to_pylist()]
        doc, start, size = (group.column(c).to_pylist() for c in ("doc_id", "start", "doc_tokens"))
        index = counted.index(group.column("terms").to_pylist(), group.column("counts").to_pylist(), size)
        rows = []
        for number, pieces in enumerate(pack_shard(ids, index, window)):
            offset, name = 0, ((shard << 32) + number) * 2 + 1
            for unit, at, n in pieces:
                rows.append((doc[unit], start[unit] + at, n, _crc(ids[unit][at : at + n]), size[unit], name, offset))
                offset += n
        names = [f.split()[0] for f in PIECE.split(", ")]
        return pa.table([pa.array(c, pa.int64()) for c in zip(*rows)], names=names)

    return run


def _units(docs: DataFrame, doc_id: str, text: str, path: str, window: int, leaders: int, shard_terms: int):
    """Encoded rows, units with their shards, the number of these, and a broadcast of the corpus counts and the router."""
    spark = docs.sparkSession
    plain = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    encoded = stored(bounded_batches(plain).mapInArrow(_encode(path, window), SCHEMA), "encoded")
    terms = encoded.where(F.col("kind") == TERM).groupBy("start").agg(F.sum("length").alias("n")).toPandas()  # at most the vocabulary
    totals = encoded.where(F.col("kind") == TOTAL).agg(F.sum("start").alias("documents"), F.sum("length").alias("tokens")).first()
    encoder = TextIds(path)
    frequency = np.zeros(encoder.vocabulary, np.int64)
    frequency[terms["start"].to_numpy(np.int64)] = terms["n"].to_numpy(np.int64)
    documents = totals["documents"] or 0
    counted = Counts(encoder.kind, frequency, documents, (totals["tokens"] or 0) / max(1, documents))
    tails = encoded.where(F.col("kind") == TAIL)
    hashed = tails.withColumn("h", F.xxhash64("terms", "counts"))
    smallest = hashed.select("h").distinct().orderBy("h").limit(leaders)
    led = hashed.join(F.broadcast(smallest), "h", "left_semi").groupBy("h").agg(F.first(F.struct("terms", "counts", "doc_tokens")).alias("x")).orderBy("h").select("x.*").collect()  # at most the leaders
    router = Router(counted, *([bytes(r[c]) for r in led] for c in ("terms", "counts")), [r["doc_tokens"] for r in led])
    shared = spark.sparkContext.broadcast((counted, router))
    own = ("doc_id", "start", "length", "doc_tokens", "ids", "terms", "counts")
    fields = {f.split()[0]: f for f in SCHEMA.split(", ")}
    routed = tails.select(*own).mapInArrow(_routed(shared), ", ".join(fields[c] for c in own) + ", leader int, second int")
    routed = stored(routed.withColumn("size", F.octet_length("terms") / encoder.kind.itemsize), "routed")
    sizes = routed.groupBy("leader", "second").agg(F.sum("size").cast("long").alias("n")).collect()  # at most pairs of leaders
    pairs = dealt([tuple(r) for r in sizes], shard_terms)
    deal = spark.createDataFrame(pairs, "leader int, second int, first long, many long")
    part = F.pmod(F.xxhash64("doc_id", "start", "ids"), F.col("many"))
    units = routed.join(F.broadcast(deal), ["leader", "second"]).select(*own, (F.col("first") + part).alias("shard"))
    return encoded, units, max((first + many for _, _, first, many in pairs), default=0), shared


def pack(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", tokenizer: str | None = None, window: int = WINDOW, leaders: int = LEADERS, shard_terms: int = SHARD_TERMS) -> DataFrame:
    """Pieces of sequences: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    encoded, units, shards, shared = _units(docs, doc_id, text, tokenizer or default_tokenizer(), window, leaders, shard_terms)
    whole = encoded.where(F.col("kind") == FULL).select(
        "doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", F.lit(0).cast("long").alias("offset")
    )
    # a task a shard while there are few: their work is more than their bytes let adaptive execution see
    together = units.repartitionById(max(1, min(shards, MOST_TASKS)), F.pmod("shard", F.lit(MOST_TASKS)).cast("int")).sortWithinPartitions("shard", "doc_id", "start")
    return whole.unionByName(together.mapInArrow(_packed(shared, window), PIECE))


def shard_recall(docs: DataFrame, queries: int, k: int = 10, **options) -> tuple[float, float]:
    """The share of the k best units of the whole corpus that lie in a query's own shard, and the same by chance; for tests and reports, on one machine."""
    tokenizer = options.pop("tokenizer", None) or default_tokenizer()
    settings = {"window": WINDOW, "leaders": LEADERS, "shard_terms": SHARD_TERMS} | options
    _, units, _, shared = _units(docs, "doc_id", "text", tokenizer, **settings)
    rows = units.select("shard", "terms", "counts", "doc_tokens").orderBy("doc_id", "start").toArrow()
    index = shared.value[0].index(*(rows.column(c).to_pylist() for c in ("terms", "counts", "doc_tokens")))
    shard, names = rows.column("shard").to_numpy(), np.arange(index.n)
    asked = names[:: max(1, index.n // queries)]
    found = 0
    for lo in range(0, len(asked), 64):
        part = asked[lo : lo + 64]
        keys = -np.sort(-largest(index.keys([index.terms[i] for i in part], part, names, index.n), k), 1)
        found += sum(int((shard[u] == shard[q]).sum()) for q, u in zip(part.tolist(), units_of(keys, part, index.n)))
    _, sizes = np.unique(shard, return_counts=True)
    return found / (min(k, index.n - 1) * len(asked)), float((sizes / index.n) @ (sizes / index.n))


def op2_retrieval_packing(spark, sf_dir):
    return pack(table(spark, sf_dir, "documents"))
