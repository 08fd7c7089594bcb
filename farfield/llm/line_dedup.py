"""Line dedup by overlapping three-line windows.

Every three consecutive non-blank lines of a document form a window. A window that occurs more than once in the
corpus keeps its first occurrence, by (doc_id, hash of the text, line); each later occurrence covers its three lines,
and all covered lines go. Covered positions are merged as bits, so windows that overlap cost nothing twice.

No text is lost: a covered line has an equal line at an earlier place, which is kept or has one in turn.

Defined results: a null text stays null; an empty text, or one with fewer than three non-blank lines, stays as it is;
blank lines (nothing but ASCII white space) are in no window and always stay; rows that repeat both doc_id and text are
one document and are cut alike; a null doc_id comes before all others; an empty table gives an empty table; other columns are
carried along untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farfield.llm.common import bitmaps, has_bit

WINDOW_LINES = 3
NOT_BLANK = r"[^\x20\x09-\x0D]"


def _windows(text: Column, lines: int) -> Column:
    """array<struct<key binary, at array<int>>>: the windows of a text."""
    numbered = F.transform(F.split(text, "\n", -1), lambda x, i: F.struct(i.alias("i"), x.alias("x")))
    solid = F.filter(numbered, lambda s: s["x"].rlike(NOT_BLANK))
    shifted = [solid if k == 0 else F.slice(solid, k + 1, F.greatest(F.size(solid) - k, F.lit(0))) for k in range(lines)]
    together = F.filter(F.arrays_zip(*(c.alias(f"l{k}") for k, c in enumerate(shifted))), lambda z: z[f"l{lines - 1}"].isNotNull())
    return F.transform(
        together,
        lambda z: F.struct(
            F.unhex(F.md5(F.concat_ws("\n", *(z[f"l{k}"]["x"] for k in range(lines))))).alias("key"),
            F.array(*(z[f"l{k}"]["i"] for k in range(lines))).alias("at"),
        ),
    )


def covered_lines(docs: DataFrame, lines: int = WINDOW_LINES) -> DataFrame:
    """(d_id, d_hash, bits): one row per document that loses lines, and the lines that go."""
    found = docs.select(
        F.col("doc_id").alias("d_id"), F.xxhash64("text").alias("d_hash"), F.explode(_windows(F.col("text"), lines)).alias("w")
    ).select("d_id", "d_hash", F.col("w.key").alias("key"), F.col("w.at").alias("at"))
    place = F.struct("d_id", "d_hash", F.col("at")[0].alias("line"))
    # Sums before the shuffle: a window that all documents share is one row of each task. The second form of the key
    # makes both sides of the join exchanges of their own, so that Spark can split a hot key's occurrences.
    first = (
        found.groupBy("key")
        .agg(F.min(place).alias("first"), F.max(place).alias("last"))
        .filter(F.col("first") != F.col("last"))
        .select(F.hex("key").alias("k"), "first")
    )
    later = (
        found.select(F.hex("key").alias("k"), "d_id", "d_hash", "at", place.alias("place"))
        .join(first, "k")
        .filter(~F.col("place").eqNullSafe(F.col("first")))
        .select("d_id", "d_hash", F.explode("at").alias("i"))
    )
    return bitmaps(later, ["d_id", "d_hash"], "i")


def dedup_lines(docs: DataFrame, lines: int = WINDOW_LINES) -> DataFrame:
    """docs with its text cut, and __n_lines, __n_removed."""
    cut = covered_lines(docs, lines)
    kept = F.filter(F.split("text", "\n", -1), lambda _, i: ~has_bit(F.col("bits"), i))
    joined = docs.withColumn("__hash", F.xxhash64("text")).join(
        cut, F.col("doc_id").eqNullSafe(F.col("d_id")) & (F.col("__hash") == F.col("d_hash")), "left"
    )
    n_removed = F.coalesce(F.aggregate("bits", F.lit(0).cast("long"), lambda a, w: a + F.bit_count(w)), F.lit(0).cast("long"))
    return joined.select(
        *(F.when(F.col("bits").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n")).alias("text") if c == "text" else docs[c] for c in docs.columns),
        F.coalesce(F.regexp_count("text", F.lit("\n")) + 1, F.lit(0)).cast("long").alias("__n_lines"),
        n_removed.alias("__n_removed"),
    )


def op2_line_dedup(docs: DataFrame) -> DataFrame:
    """doc_id, text (what is left of it), n_lines (before), n_removed."""
    return dedup_lines(docs.select("doc_id", "text")).select(
        "doc_id", "text", F.col("__n_lines").alias("n_lines"), F.col("__n_removed").alias("n_removed")
    )


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline: lines that repeat go, every document stays."""
    cut = dedup_lines(docs.select("doc_id", "text", "lang", "source"))
    return cut.select("doc_id", "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))


#: The same by ordinary joins and string functions.
ORACLE_SQL = r"""
WITH lines AS (
  SELECT doc_id, text, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS i
  FROM documents WHERE text IS NOT NULL
), solid AS (
  SELECT doc_id, i, line, lead(i, 1) OVER w AS i1, lead(i, 2) OVER w AS i2, lead(line, 1) OVER w AS l1, lead(line, 2) OVER w AS l2
  FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]')
  WINDOW w AS (PARTITION BY doc_id ORDER BY i)
), windows AS (
  SELECT doc_id, i, i1, i2, row_number() OVER (PARTITION BY line || chr(10) || l1 || chr(10) || l2 ORDER BY doc_id, i) AS nth
  FROM solid WHERE i2 IS NOT NULL
), covered AS (
  SELECT DISTINCT doc_id, unnest([i, i1, i2]) AS i FROM windows WHERE nth > 1
), kept AS (
  SELECT l.doc_id, string_agg(CASE WHEN c.i IS NULL THEN l.line END, chr(10) ORDER BY l.i) AS text,
         count(*) AS n_lines, count(c.i) AS n_removed
  FROM lines l LEFT JOIN covered c USING (doc_id, i) GROUP BY l.doc_id
)
SELECT d.doc_id, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(k.text, '') END AS text,
       coalesce(n_lines, 0) AS n_lines, coalesce(n_removed, 0) AS n_removed
FROM documents d LEFT JOIN kept k USING (doc_id)
"""
