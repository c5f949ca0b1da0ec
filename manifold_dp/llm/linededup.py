"""Line dedup by winnowing over line hashes (native DataFrame operations).

A document is its sequence of lines (split at ``\\n``; lines of white space only are
layout and take no part, and stay). A run is ``min_lines`` or more consecutive lines.
A line goes if a run that covers it also starts earlier: in a document with a smaller
``doc_id``, or further up in the same document. First copies stay.

How: every ``min_lines`` consecutive lines elect the line of least hash (the leftmost on
ties) as fingerprint, so equal runs always elect the same line at the same place. A
fingerprint carries the ``min_lines - 1`` lines on both sides; positions that share one
are joined, and a match is extended left and right over that context against the earliest
position that has the same lines there. The extended windows of one run overlap, so their
union is the whole repeated run, however long.

A match rests on the 64-bit hashes of all its lines, ``64 * min_lines`` bits at the least.

Nothing is gathered by line: the earliest position is a partial aggregate, and the join
back is a plain equi join whose hot keys AQE can split, against one row per window.

Defined results: null or empty text has no lines and stays as it is; rows with a null
``doc_id`` come first in order and are never matched to a document (their text stays);
rows of one id are versions of one document, each cleaned by its own text, and a line
counts as further up if it stands at a smaller index in any of them. Extra columns pass
through ``clean`` untouched; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import others, table

MIN_LINES = 3


def _key() -> Column:
    """Tells rows of one ``doc_id`` apart."""
    return F.xxhash64("text")


def _lines() -> Column:
    return F.filter(F.transform(F.split("text", "\n"), lambda x, i: F.struct(i.alias("i"), x.alias("x"))), lambda s: F.length(F.trim(s["x"], F.lit(" \t\r"))) > 0)


def fingerprints(docs: DataFrame, min_lines: int = MIN_LINES) -> DataFrame:
    """Winnowing: rows ``(doc_id, key, fp, q, from, h, i)``, one for each elected line.

    ``key``: hash of the text; ``q``: its place among the document's lines; ``h``, ``i``: hashes and indexes of it and
    of the ``min_lines - 1`` lines on both sides, the first of which has place ``from``.
    """
    k = min_lines
    d = docs.where(F.col("doc_id").isNotNull() & (F.length("text") > 0)).select("doc_id", _key().alias("key"), F.transform(_lines(), lambda s: F.struct(s["i"].alias("i"), F.xxhash64(s["x"]).alias("h"))).alias("l"))
    d = d.where(F.size("l") >= k).select("doc_id", "key", F.col("l.h").alias("h"), F.col("l.i").alias("i"))
    elected = F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("h") - (k - 1)), lambda p: (p + F.array_position(F.slice("h", p, k), F.array_min(F.slice("h", p, k))) - 1).cast("int")))
    begin = lambda q: F.greatest(F.lit(1), q - (k - 1))
    return d.select(
        "doc_id",
        "key",
        F.inline(F.transform(elected, lambda q: F.struct(F.element_at("h", q).alias("fp"), q.alias("q"), begin(q).alias("from"), F.slice("h", begin(q), q + k - begin(q)).alias("h"), F.slice("i", begin(q), q + k - begin(q)).alias("i")))),
    )


def windows(docs: DataFrame, min_lines: int = MIN_LINES) -> DataFrame:
    """Extension to both sides: the runs of ``min_lines`` lines that elected a fingerprint.

    Rows ``(fp, w, doc_id, key, at)``; ``w``: line hashes, ``at``: indexes of its lines.
    """
    k = min_lines
    place = F.col("q") - F.col("from") + 1
    run = F.transform(F.sequence(F.lit(1), F.size("h") - (k - 1)), lambda p: F.struct(F.slice("h", p, k).alias("w"), F.slice("i", p, k).alias("at"), (p + F.array_position(F.slice("h", p, k), F.array_min(F.slice("h", p, k))) - 1 == place).alias("own")))
    return fingerprints(docs, k).select("fp", "doc_id", "key", F.inline(F.filter(run, lambda r: r["own"]))).select("fp", "w", "doc_id", "key", "at")


def repeated_lines(docs: DataFrame, min_lines: int = MIN_LINES) -> DataFrame:
    """``(doc_id, key, gone)``: indexes of the lines to delete, for documents that have any."""
    w = windows(docs, min_lines)
    start = F.struct("doc_id", F.col("at")[0].alias("i"))
    first = w.groupBy("fp", "w").agg(F.min(start).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    hits = w.join(first, ["fp", "w"]).where((F.col("doc_id") > F.col("first.doc_id")) | (F.col("at")[0] > F.col("first.i")))
    return hits.groupBy("doc_id", "key").agg(F.array_distinct(F.flatten(F.collect_set("at"))).alias("gone"))


def clean(docs: DataFrame, min_lines: int = MIN_LINES) -> DataFrame:
    """``docs`` with repeated runs deleted from ``text``, and ``n_lines``, ``n_removed`` (replaced if there)."""
    names = others(docs.columns, "n_lines", "n_removed")
    hits = repeated_lines(docs, min_lines).select(F.col("doc_id").alias("_line_dedup_id"), F.col("key").alias("_line_dedup_key"), F.col("gone").alias("_line_dedup_gone"))
    j = docs.select(*names).join(hits, (F.col("doc_id") == F.col("_line_dedup_id")) & (_key() == F.col("_line_dedup_key")), "left")
    gone = F.array_sort(F.coalesce("_line_dedup_gone", F.array().cast("array<int>")))
    j = j.withColumn("_line_dedup_gone", gone).withColumn("_line_dedup_rows", F.split("text", "\n"))
    gone, rows = F.col("_line_dedup_gone"), F.col("_line_dedup_rows")
    # the stretches between deleted lines, each cut out once
    kept = F.flatten(F.zip_with(F.concat(F.array(F.lit(-1)), gone), F.concat(gone, F.array(F.size(rows))), lambda a, b: F.slice(rows, a + 2, b - a - 1)))
    return j.select(
        *[F.when(F.size(gone) > 0, F.array_join(kept, "\n")).otherwise(F.col("text")).alias("text") if c == "text" else F.col(f"`{c}`") for c in names],
        F.coalesce(F.when(F.length("text") > 0, F.size(rows)), F.lit(0)).cast("long").alias("n_lines"),
        F.size(gone).cast("long").alias("n_removed"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return clean(docs).select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


ORACLE = r"""
WITH raw AS (
  SELECT doc_id, generate_subscripts(ls, 1) - 1 AS i, unnest(ls) AS x
  FROM (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents WHERE length(text) > 0)
), seq AS (
  SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS p FROM raw WHERE length(trim(x, chr(32) || chr(9) || chr(13))) > 0
), win AS (
  SELECT doc_id, p, i AS i1, x AS a,
    lead(x, 1) OVER d AS b, lead(i, 1) OVER d AS i2, lead(x, 2) OVER d AS c, lead(i, 2) OVER d AS i3
  FROM seq WINDOW d AS (PARTITION BY doc_id ORDER BY p)
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY a, b, c ORDER BY doc_id, p) AS r FROM win WHERE c IS NOT NULL
), gone AS (
  SELECT DISTINCT doc_id, unnest([i1, i2, i3]) AS i FROM ranked WHERE r > 1
), kept AS (
  SELECT doc_id, count(*) AS n_lines, count(g.i) AS n_removed,
    coalesce(string_agg(x, chr(10) ORDER BY raw.i) FILTER (g.i IS NULL), '') AS t
  FROM raw LEFT JOIN gone g USING (doc_id, i) GROUP BY doc_id
)
SELECT d.doc_id, coalesce(n_lines, 0) AS n_lines, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM documents d LEFT JOIN kept USING (doc_id)
"""
