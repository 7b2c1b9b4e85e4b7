"""Near-duplicate documents: b-bit MinHash, bands, and a check on full shingle sets.

1. One pass over the texts gives each document a digest of its words, the size
   of its shingle set, the low byte of 128 minima and 32 band keys of four
   minima each.  Equal word sequences are one class from here on.
2. Classes that share a band key meet in a bucket.  There the collision-corrected
   similarity is estimated from counts of equal bytes for all pairs, in
   blocks, and each group of classes held together by estimates gives a star of
   links, never its pairs.  The bar is five standard errors below the threshold.
3. Components of the stars are clusters.  The texts of a cluster are brought
   together once and all its pairs are compared on full sets, in blocks, by a
   product of incidence matrices; again only stars of true links come out.
4. Components of the true links, and the smallest doc_id of each.

Buckets and clusters of more than a block's rows are dealt out as pairs of
blocks, so a group of any size spreads over tasks and no link is lost.  A link at
the threshold misses all bands with probability below 1e-7.

Defined results: a text without words, or null, has 0 shingles, is linked with
nothing and is a component of its own; fewer than five words are one shingle.
Rows of equal id are each a row of the result.  A null id counts as larger than
any other, a component of null ids only has a null component_id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphviews.llm.common import blank_words, bounded_batches, returned_memory, shielded, stored, table, worker_memory
from graphviews.llm.components import components

SHINGLE = 5
MINIMA = 128
BANDS, ROWS = 32, 4
BUCKET_BLOCK = 2048
CLUSTER_BLOCK = 512
COLUMNS = 4096
#: Words whose hashes a worker remembers before it starts anew.
REMEMBERED = 250_000

_rng = np.random.Generator(np.random.PCG64(20240901))
_MUL = _rng.integers(0, 1 << 32, MINIMA, dtype=np.uint64).astype(np.uint32) | np.uint32(1)
_ADD = _rng.integers(0, 1 << 32, MINIMA, dtype=np.uint64).astype(np.uint32)
_POSITION = _rng.integers(0, 1 << 63, SHINGLE, dtype=np.uint64) | np.uint64(1)
_BAND = _rng.integers(0, 1 << 63, (BANDS, ROWS + 1), dtype=np.uint64) | np.uint64(1)


class WordHashes(dict):
    """64-bit hashes of words, remembered."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= REMEMBERED:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def shingles(words: list[bytes], hashes: WordHashes) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the five-word shingles."""
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    n = len(h) - SHINGLE + 1
    if n < 1:
        return mixed((h * _POSITION[: len(h)]).sum(keepdims=True, dtype=np.uint64) + np.uint64(len(h)))
    total = h[:n] * _POSITION[0]
    for k in range(1, SHINGLE):
        total += h[k : k + n] * _POSITION[k]
    return np.unique(mixed(total))


def minima(sets: np.ndarray) -> np.ndarray:
    low = np.full(MINIMA, 0xFFFFFFFF, np.uint32)
    short = (sets >> np.uint64(32)).astype(np.uint32)
    for at in range(0, len(short), 256):
        part = short[at : at + 256, None] * _MUL
        part += _ADD
        np.minimum(low, part.min(0), out=low)
    return low


def signature(sets: np.ndarray) -> tuple[bytes, np.ndarray]:
    """The minima's mixed low bytes, packed, and the band keys."""
    low = minima(sets)
    wide = low.astype(np.uint64)
    packed = (mixed(wide) & np.uint64(0xFF)).astype(np.uint8).tobytes()
    rows = wide[: BANDS * ROWS].reshape(BANDS, ROWS)
    keys = mixed((rows * _BAND[:, :ROWS]).sum(1, dtype=np.uint64) + _BAND[:, ROWS])
    return packed, keys.view(np.int64)


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hashes = worker_memory("word hashes", WordHashes)
    for batch in batches:
        texts = batch.column("text").cast(pa.binary())
        for lo in range(0, len(texts), 512):
            digests, sizes, packed, bands = [], [], [], []
            for text in texts.slice(lo, 512).to_pylist():
                words = blank_words(text)
                found = shingles(words, hashes)
                sizes.append(len(found))
                digests.append(xxhash.xxh3_128_digest(b" ".join(words)) if words else None)
                sig, keys = signature(found) if words else (None, None)
                packed.append(sig)
                bands.append(keys)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").slice(lo, 512), batch.column("text_hash").slice(lo, 512), pa.array(digests, pa.binary()), pa.array(sizes, pa.int64()), pa.array(packed, pa.binary()), pa.array(bands, pa.list_(pa.int64()))],
                ["doc_id", "text_hash", "digest", "n_shingles", "sig", "bands"],
            )
    returned_memory()


def groups_of(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.RecordBatch]:
    """Batches that end where a key ends, from batches sorted by keys; holds one group beyond a batch at most."""
    rest: list[pa.RecordBatch] = []
    for batch in batches:
        if not len(batch):
            continue
        rest.append(batch)
        last = [batch.column(k)[-1].as_py() for k in keys]
        cut = len(batch)
        while cut and [batch.column(k)[cut - 1].as_py() for k in keys] == last:
            cut -= 1
        first = [rest[0].column(k)[0].as_py() for k in keys]
        if cut == 0 and first == last:
            continue
        whole = rest[:-1] + ([batch.slice(0, cut)] if cut else [])
        yield pa.Table.from_batches(whole).combine_chunks().to_batches()[0]
        rest = [batch.slice(cut)]
    if rest:
        yield pa.Table.from_batches(rest).combine_chunks().to_batches()[0]


def bounds(*columns: np.ndarray) -> np.ndarray:
    """Where groups of equal keys begin, and the end."""
    new = np.zeros(len(columns[0]), bool)
    new[:1] = True
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    return np.append(np.flatnonzero(new), len(new))


def stars(linked: np.ndarray) -> list[tuple[int, int]]:
    """(member, first member) of the connected groups of a symmetric boolean matrix."""
    left = np.ones(len(linked), bool)
    out = []
    for root in range(len(linked)):
        if not left[root]:
            continue
        left[root] = False
        front = linked[root] & left
        while front.any():
            members = np.flatnonzero(front)
            left[members] = False
            out += [(m, root) for m in members.tolist()]
            front = linked[members].any(0) & left
    return out


def estimated(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Similarity from counts of equal low bytes, corrected for bytes equal by chance."""
    chance = 1 / 256
    return ((a == b).mean(-1) - chance) / (1 - chance)


def _bucket_links(bar: float):
    def run(batches):
        for batch in groups_of(batches, ["bucket", "bi", "bj"]):
            keys = [batch.column(k).to_numpy() for k in ("bucket", "bi", "bj")]
            own = batch.column("own").to_numpy()
            digest = batch.column("digest").to_pylist()
            sig = np.frombuffer(b"".join(batch.column("sig").to_pylist()), np.uint8).reshape(-1, MINIMA)
            edge = bounds(*keys)
            size = np.diff(edge)
            found: list[tuple[int, int]] = []
            for m in np.unique(size[(size > 1) & (size <= 12)]).tolist():
                i, j = np.triu_indices(m, 1)
                starts = edge[:-1][size == m]
                for at in range(0, len(starts), 2048):
                    left = (starts[at : at + 2048, None] + i).ravel()
                    right = (starts[at : at + 2048, None] + j).ravel()
                    near = (estimated(sig[left], sig[right]) >= bar).reshape(-1, len(i))
                    tree = near.sum(1) < m
                    keep = (near & tree[:, None]).ravel()
                    found += zip(left[keep].tolist(), right[keep].tolist())
                    for g in np.flatnonzero(~tree).tolist():  # more pairs than a star needs
                        square = np.zeros((m, m), bool)
                        square[i, j] = square[j, i] = near[g]
                        lo = int(starts[at + g])
                        found += [(lo + x, lo + y) for x, y in stars(square)]
            for g in np.flatnonzero(size > 12).tolist():
                lo, hi = int(edge[g]), int(edge[g + 1])
                part, bi, bj = sig[lo:hi], keys[1][lo], keys[2][lo]
                near = np.zeros((hi - lo, hi - lo), bool)
                for at in range(0, hi - lo, 64):
                    near[at : at + 64] = estimated(part[at : at + 64, None, :], part[None, :, :]) >= bar
                if bi != bj:
                    side = own[lo:hi] == bi
                    near &= side[:, None] != side[None, :]
                found += [(lo + x, lo + y) for x, y in stars(near)]
            yield pa.RecordBatch.from_arrays(
                [pa.array([digest[x] for x, _ in found], pa.binary()), pa.array([digest[y] for _, y in found], pa.binary())], ["a", "b"]
            )

    return run


def blocked(df: DataFrame, group: str, count: str, block: int) -> DataFrame:
    """df once for each pair of blocks (bi, bj) of its group that its own block belongs to."""
    blocks = F.ceil(F.col(count) / block).cast("int")
    own = F.pmod(F.xxhash64("digest", F.lit(11)), blocks).cast("int")
    pair = F.transform(
        F.sequence(F.lit(0), blocks - 1), lambda x: F.struct(F.least(x, F.col("own")).alias("bi"), F.greatest(x, F.col("own")).alias("bj"))
    )
    return df.withColumn("own", own).withColumn("p", F.explode(pair)).withColumns({"bi": F.col("p.bi"), "bj": F.col("p.bj")}).drop("p")


def full_set_links(sets: list[np.ndarray], num: int, den: int) -> np.ndarray:
    """Matrix of pairs with den * intersection >= num * union, from intersections of all pairs."""
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    values = np.concatenate(sets)
    owner = np.repeat(np.arange(len(sets)), sizes)
    _, column, times = np.unique(values, return_inverse=True, return_counts=True)
    shared = times[column] > 1
    owner, column = owner[shared], column[shared]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    names, column = np.unique(column, return_inverse=True)
    common = np.zeros((len(sets), len(sets)), np.float32)
    for at in range(0, len(names), COLUMNS):
        lo, hi = np.searchsorted(column, [at, at + COLUMNS])
        incidence = np.zeros((len(sets), min(COLUMNS, len(names) - at)), np.float32)
        incidence[owner[lo:hi], column[lo:hi] - at] = 1
        common += incidence @ incidence.T
    both = common.astype(np.int64)
    union = sizes[:, None] + sizes[None, :] - both
    linked = den * both >= num * union
    np.fill_diagonal(linked, False)
    return linked & (both > 0)


def _cluster_links(num: int, den: int):
    def run(batches):
        hashes = WordHashes()
        for batch in groups_of(batches, ["cluster", "bi", "bj"]):
            cluster, digest = batch.column("cluster").to_pylist(), batch.column("digest").to_pylist()
            bi, bj, own = (batch.column(k).to_numpy() for k in ("bi", "bj", "own"))
            texts = batch.column("text").cast(pa.binary())
            lo, out = 0, []
            while lo < len(batch):
                hi = lo
                while hi < len(batch) and cluster[hi] == cluster[lo] and bi[hi] == bi[lo] and bj[hi] == bj[lo]:
                    hi += 1
                rows, sets, seen = [], [], set()
                for at, text in zip(range(lo, hi), texts.slice(lo, hi - lo).to_pylist()):
                    words = blank_words(text)
                    if digest[at] not in seen and xxhash.xxh3_128_digest(b" ".join(words)) == digest[at]:
                        seen.add(digest[at])
                        rows.append(at)
                        sets.append(shingles(words, hashes))
                if len(rows) > 1:
                    linked = full_set_links(sets, num, den)
                    if bi[lo] != bj[lo]:
                        side = own[rows] == bi[lo]
                        linked &= side[:, None] != side[None, :]
                    out += [(digest[rows[x]], digest[rows[y]]) for x, y in stars(linked)]
                lo = hi
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in out], pa.binary()), pa.array([y for _, y in out], pa.binary())], ["a", "b"])

    return run


def _dealt(df: DataFrame, *keys: str) -> DataFrame:
    """Groups together; inside a group the smallest digest first, so that stars of different bands share their roots."""
    return df.repartition(*keys).sortWithinPartitions(*keys, "digest")


def near_duplicates(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", num: int = 85, den: int = 100) -> DataFrame:
    """One row per document: n_shingles, component_id, kept; linked where den * intersection >= num * union.

    Further columns: text_hash, and label, which only rows of one component share (null without words).
    """
    plain = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    hashed = plain.withColumn("text_hash", F.xxhash64("text"))
    signed = stored(bounded_batches(hashed).mapInArrow(_sign, "doc_id long, text_hash long, digest binary, n_shingles long, sig binary, bands array<long>"), "signed")
    named = F.struct("doc_id", "text_hash")
    classes = stored(
        signed.where("digest is not null").groupBy("digest").agg(
            F.coalesce(F.min(F.when(F.col("doc_id").isNotNull(), named)), F.min(named)).alias("rep"), F.first("sig").alias("sig"), F.first("bands").alias("bands")
        ).select("digest", "rep.doc_id", "rep.text_hash", "sig", "bands"),
        "classes",
    )
    similarity = num / den
    bar = similarity - 5 * (similarity * (1 - similarity) / MINIMA) ** 0.5
    keyed = classes.select("digest", F.explode("bands").alias("bucket"))
    shared = keyed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    members = keyed.join(shared, "bucket").join(classes.select("digest", "sig"), "digest")
    members = blocked(members, "bucket", "n", BUCKET_BLOCK).select("bucket", "bi", "bj", "own", "digest", "sig")
    hinted = _dealt(members, "bucket", "bi", "bj").mapInArrow(_bucket_links(bar), "a binary, b binary").distinct()
    clusters = components(hinted)
    sized = clusters.join(clusters.groupBy("label").agg(F.count(F.lit(1)).alias("n")), "label")
    wanted = sized.select(F.col("node").alias("digest"), F.col("label").alias("cluster"), "n").join(classes.select("digest", F.col("doc_id").alias("rep"), F.col("text_hash").alias("rep_hash")), "digest")
    # one text a class, by id and text, so that rows of one id (or none) do not all meet
    found = hashed.join(wanted.hint("shuffle_hash"), F.col("doc_id").eqNullSafe(F.col("rep")) & (F.col("text_hash") == F.col("rep_hash")))
    found = found.groupBy("digest").agg(F.first("cluster").alias("cluster"), F.first("n").alias("n"), F.first("text").alias("text"))
    texts = blocked(found, "cluster", "n", CLUSTER_BLOCK).select("cluster", "bi", "bj", "own", "digest", "text")
    links = _dealt(texts, "cluster", "bi", "bj").mapInArrow(_cluster_links(num, den), "a binary, b binary")
    labels = components(links).withColumnRenamed("node", "digest")
    members_ = classes.select("digest", "doc_id").join(labels, "digest", "left").select("digest", "doc_id", F.coalesce("label", "digest").alias("label"))
    smallest = members_.groupBy("label").agg(F.min("doc_id").alias("component_id"))
    of_class = members_.join(smallest, "label").select("digest", "label", "component_id")
    out = signed.select("doc_id", "text_hash", "digest", "n_shingles").join(of_class, "digest", "left")
    component = F.when(F.col("digest").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"), "text_hash", "label")


def keep_one(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", num: int = 80, den: int = 100) -> DataFrame:
    """The documents, all columns, less all but one of each component; texts without words all stay."""
    marks = near_duplicates(docs, doc_id=doc_id, text=text, num=num, den=den)
    best = marks.where("kept and label is not null").groupBy("label").agg(F.min(F.struct("doc_id", "text_hash")).alias("k"))
    alone = marks.where("label is null").select("doc_id", "text_hash", F.lit(False).alias("mh_once")).distinct()
    keep = best.select("k.doc_id", "k.text_hash", F.lit(True).alias("mh_once")).unionByName(alone).withColumnsRenamed({"doc_id": "mh_id", "text_hash": "mh_hash"})
    rows, back = shielded(docs, ["mh_id", "mh_hash", "mh_once", "mh_key", "mh_row"])
    rows = rows.withColumns({"mh_key": F.col(doc_id).cast("long"), "mh_row": F.xxhash64(F.col(text))})
    joined = rows.join(keep, F.col("mh_key").eqNullSafe(F.col("mh_id")) & (F.col("mh_row") == F.col("mh_hash")))
    again = F.row_number().over(Window.partitionBy("mh_key", "mh_row").orderBy(F.lit(0)))
    one = joined.withColumn("mh_number", again).where("mh_number = 1 or not mh_once")
    return one.drop("mh_number", "mh_id", "mh_hash", "mh_once", "mh_key", "mh_row").withColumnsRenamed(back)


def op9_minhash_dedup(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id", "kept")


OP9_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS a FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(list_slice(a, p, p + 4), ' ') AS g FROM (SELECT doc_id, a, unnest(range(1, greatest(len(a) - 4, 1) + 1)) AS p FROM w WHERE len(a) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS k FROM s x JOIN s y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM c JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * k >= 85 * (na.n + nb.n - k)),
u AS (SELECT a AS x, b AS y FROM l UNION SELECT b, a FROM l),
r(doc_id, z) AS (SELECT x, y FROM u UNION SELECT r.doc_id, u.y FROM r JOIN u ON r.z = u.x),
m AS (SELECT doc_id, min(z) AS z FROM r GROUP BY doc_id)
SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(w.doc_id, coalesce(m.z, w.doc_id)) AS component_id,
       w.doc_id <= coalesce(m.z, w.doc_id) AS kept
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN m USING (doc_id)
"""
