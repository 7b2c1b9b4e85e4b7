"""Line dedup by overlapping three-line windows, in DataFrame functions only.

The lines of a text are hashed, every three consecutive lines make a window, and
a window that occurs more than once in the corpus keeps its first occurrence (in
order of doc_id, then position).  A line goes when any later occurrence covers it;
what stays is joined again.

Plan: windows are 128-bit hashes; their first occurrences are a partial
aggregate, so a window that half the corpus shares costs one row a task; the
occurrences meet them in a sort-merge join whose hot keys the adaptive planner
splits.  Texts are shuffled once, against the positions to remove, hashed on
their own side so that no text is sorted.  Covered positions are merged by hash
sets, in time linear in a text's lines.

Defined results: null text stays null with 0 lines; the empty text is one empty
line; fewer lines than a window lose nothing.  Rows with equal id and text are
one document and share its result; rows with equal id and different text count
as different documents in the order of a hash.  A null id sorts first.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.llm.common import shielded, table

WINDOW = 3


def _lines(text: str):
    return F.split(F.col(text), "\n")


def _windows(text: str, window: int):
    """Column: array of (position, two hashes) of every window of a text."""
    hashes = F.transform(_lines(text), lambda x: F.struct(F.xxhash64(x).alias("a"), F.xxhash64(F.lit(7), x, F.lit(1)).alias("b")))
    count = F.size(_lines(text)) - (window - 1)

    def of(at, field, salt):
        return F.xxhash64(F.lit(salt), *[F.element_at("ld_hashes", at + 1 + k)[field] for k in range(window)])

    each = F.transform(
        F.sequence(F.lit(0), F.col("ld_count") - 1),
        lambda i: F.struct(i.alias("ld_at"), of(i, "a", 1).alias("ld_w1"), of(i, "b", 2).alias("ld_w2")),
    )
    return hashes, count, each


def _keyed(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    ids, body = F.col(doc_id), F.col(text)
    return docs.withColumns(
        {"ld_k1": F.xxhash64(F.lit(3), ids, body), "ld_k2": F.xxhash64(body, F.lit(5), ids)}
    )


def removed_lines(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", window: int = WINDOW) -> DataFrame:
    """For each document that loses lines: its key (ld_k1, ld_k2) and the covered positions, from 0."""
    hashes, count, each = _windows("ld_text", window)
    occurrences = (
        _keyed(docs.select(F.col(doc_id).alias("ld_id"), F.col(text).alias("ld_text")), "ld_id", "ld_text")
        .where(F.col("ld_text").isNotNull())
        .select("ld_id", "ld_k1", "ld_k2", hashes.alias("ld_hashes"), count.alias("ld_count"))
        .where("ld_count > 0")
        .select("ld_id", "ld_k1", "ld_k2", F.explode(each).alias("x"))
        .select("ld_id", "ld_k1", "ld_k2", "x.*")
    )
    place = F.struct("ld_id", "ld_k1", "ld_k2", "ld_at")
    firsts = (
        occurrences.groupBy("ld_w1", "ld_w2")
        .agg(F.min(place).alias("ld_first"), F.max(place).alias("ld_last"))
        .where(~F.col("ld_first").eqNullSafe(F.col("ld_last")))
        .select("ld_w1", "ld_w2", "ld_first")
    )
    later = occurrences.join(firsts, ["ld_w1", "ld_w2"]).where(~place.eqNullSafe(F.col("ld_first")))
    return later.groupBy("ld_k1", "ld_k2").agg(F.collect_set("ld_at").alias("ld_starts"))


def dedup_lines(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", window: int = WINDOW) -> DataFrame:
    """docs with the text that stays, and ld_lines and ld_removed (counts of lines).

    Columns of docs that begin with ld_ and are named like one of this operator's are replaced.
    """
    docs = docs.drop("ld_k1", "ld_k2", "ld_starts", "ld_kept", "ld_lines", "ld_removed")
    gone = removed_lines(docs, doc_id=doc_id, text=text, window=window)
    lines = _lines(text)
    covered = F.flatten(F.transform("ld_starts", lambda p: F.sequence(p, p + (window - 1))))
    kept = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), covered)
    return (
        _keyed(docs, doc_id, text)
        .join(gone.hint("shuffle_hash"), ["ld_k1", "ld_k2"], "left")
        .withColumns({
            "ld_lines": F.when(F.col(text).isNull(), 0).otherwise(F.size(lines)).cast("long"),
            "ld_kept": F.when(F.col("ld_starts").isNotNull(), kept),
        })
        .withColumns({
            "ld_removed": F.when(F.col("ld_kept").isNull(), 0).otherwise(F.col("ld_lines") - F.size("ld_kept")).cast("long"),
            text: F.when(F.col("ld_kept").isNull(), F.col(text)).otherwise(
                F.array_join(F.transform("ld_kept", lambda i: F.get(lines, i)), "\n")
            ),
        })
        .drop("ld_k1", "ld_k2", "ld_starts", "ld_kept")
    )


def without_repeats(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", n_chars: str = "n_chars", window: int = WINDOW) -> DataFrame:
    """The documents, all columns, with deduplicated texts; those left without any text are dropped.

    A column n_chars, where there is one, follows the text.
    """
    rows, back = shielded(docs, ["ld_k1", "ld_k2", "ld_starts", "ld_kept", "ld_lines", "ld_removed"])
    out = dedup_lines(rows, doc_id=doc_id, text=text, window=window).where((F.col("ld_removed") == 0) | (F.trim(F.col(text)) != ""))
    if n_chars in docs.columns:
        kind = dict(docs.dtypes)[n_chars]
        out = out.withColumn(n_chars, F.when(F.col("ld_removed") > 0, F.length(text).cast(kind)).otherwise(F.col(n_chars)))
    return out.drop("ld_lines", "ld_removed").withColumnsRenamed(back).select(*docs.columns)


def op1_line_dedup(spark, sf_dir):
    out = dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "text", F.col("ld_lines").alias("n_lines"), F.col("ld_removed").alias("n_removed"))


OP1_SQL = """
WITH l AS (SELECT doc_id, string_split(text, chr(10)) AS a FROM documents),
win AS (SELECT doc_id, p, a[p] || chr(10) || a[p + 1] || chr(10) || a[p + 2] AS s
        FROM (SELECT doc_id, a, unnest(range(1, len(a) - 1)) AS p FROM l WHERE len(a) >= 3)),
cov AS (SELECT DISTINCT doc_id, unnest([p, p + 1, p + 2]) AS i FROM
        (SELECT *, row_number() OVER (PARTITION BY s ORDER BY doc_id, p) AS r FROM win) WHERE r > 1),
rest AS (SELECT doc_id, string_agg(a[i], chr(10) ORDER BY i) AS text, count(*) AS n
         FROM (SELECT doc_id, a, unnest(range(1, len(a) + 1)) AS i FROM l) x ANTI JOIN cov USING (doc_id, i) GROUP BY doc_id)
SELECT l.doc_id, CASE WHEN a IS NULL THEN NULL ELSE coalesce(rest.text, '') END AS text,
       coalesce(len(a), 0)::BIGINT AS n_lines, (coalesce(len(a), 0) - coalesce(rest.n, 0))::BIGINT AS n_removed
FROM l LEFT JOIN rest USING (doc_id)
"""
