"""Removal of repeated multi-line chunks, in DataFrame and SQL functions only.

Each line has a hash of its own; a rolling polynomial over the hashes of a line and
the one before it marks a line where it is divisible by ``divisor``, and a marked line
whose predecessor is not marked closes a chunk. So a chunk has two lines at least (but
perhaps the last of a text), and the boundaries depend on nearby lines alone and survive
insertions elsewhere. Of chunks of two lines or more with equal digests in the whole table, the first (smallest id,
then place) stays and the others go, once their bytes have been found equal: the
smallest and the largest text of the group must be the same. A group whose bytes
differ is left alone.

Texts meet their removals in sort-merge joins at every size, so that a run on a small
table moves what a run on a large one would.

Edge cases: null texts stay null and have no lines; an empty text has one empty
line; chunks without a visible character are never removed; rows without an id
neither lose nor claim anything; rows of one id with equal texts are one document
and keep what it keeps; an empty table gives no rows; other columns pass through
``remove`` untouched, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.llm.common import Scratch

DIVISOR, MULTIPLIER, MODULUS = 2, 131, 2147483647


def let(name: str, value: str, body: str) -> str:
    """``body`` with ``name`` bound to ``value``, computed once a row; a plain column would be inlined into the lambdas."""
    return f"transform(array({value}), {name} -> {body})[0]"


def chunks_of(text: str, divisor: int = DIVISOR) -> str:
    """SQL for the array of (a, b, digest): first and last line of each chunk of several lines, and the MD5 of its text."""
    hashes = f"transform(lines, x -> cast(conv(substring(md5(cast(x as binary)), 1, 15), 16, 10) as bigint) % {MODULUS})"
    marks = f"transform(sequence(0, size(lines) - 1), i -> ({MULTIPLIER} * (case when i > 0 then hashes[i - 1] else 0 end) + hashes[i]) % {MODULUS} % {divisor} = 0)"
    ends = "filter(sequence(0, size(lines) - 1), i -> i = size(lines) - 1 or (i > 0 and marks[i] and not marks[i - 1]))"
    spans = "filter(transform(ends, (e, k) -> struct(case when k > 0 then ends[k - 1] + 1 else 0 end as a, e as b)), c -> c.b > c.a)"
    texts = f"filter(transform({spans}, c -> struct(c.a as a, c.b as b, {lines_text('c')} as chunk)), c -> c.chunk rlike '[^ \\\\t\\\\r\\\\n]')"
    found = f"transform({texts}, c -> struct(c.a as a, c.b as b, md5(cast(c.chunk as binary)) as digest))"
    return let("lines", f"split({text}, '\n')", let("hashes", hashes, let("marks", marks, let("ends", ends, found))))


def lines_text(span: str) -> str:
    return f"array_join(slice(lines, {span}.a + 1, {span}.b - {span}.a + 1), '\n')"


def removals(docs: DataFrame, divisor: int = DIVISOR) -> DataFrame:
    """(id, key, gone: array of (a, b)) for the rows of (id, key, text) that lose chunks."""
    scratch = Scratch(docs.sparkSession)
    known = docs.where(F.col("id").isNotNull() & F.col("text").contains("\n"))
    chunks = scratch.keep(known.select("id", "key", F.explode(F.expr(chunks_of("text", divisor))).alias("c")).select("id", "key", "c.a", "c.b", "c.digest").distinct(), "chunks")
    place = F.struct("id", "key", "a")
    first = chunks.groupBy("digest").agg(F.min(place).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    first = scratch.keep(first, "first")  # apart from the join, so that a digest of very many rows can be split there
    repeated = scratch.keep(chunks.join(first.hint("merge"), "digest").select("id", "key", "a", "b", "digest", (place != F.col("first")).alias("later")), "repeated")
    wanted = repeated.groupBy("id", "key").agg(F.collect_list(F.struct("a", "b", "digest")).alias("wanted"))
    parts = let("lines", "split(text, '\n')", f"transform(wanted, c -> struct(c.digest as digest, {lines_text('c')} as chunk))")
    texts = known.join(wanted.hint("merge"), ["id", "key"]).select(F.explode(F.expr(parts)).alias("c"))
    equal = texts.groupBy("c.digest").agg((F.min("c.chunk") == F.max("c.chunk")).alias("equal")).where("equal").select("digest")
    gone = repeated.where("later").join(equal, "digest").groupBy("id", "key").agg(F.collect_list(F.struct("a", "b")).alias("gone"))
    out = scratch.keep(gone, "gone")
    scratch.drop(chunks, repeated, first)
    return out


def keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).alias("id"), F.md5(text.cast("binary")).alias("key"), text.alias("text"))


def kept_text(lines: str = "lines", gone: str = "gone") -> str:
    return f"array_join(filter({lines}, (x, i) -> not exists({gone}, g -> i between g.a and g.b)), '\n')"


def remove(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", divisor: int = DIVISOR) -> DataFrame:
    """``docs`` with the text cut; the column ``lines_removed`` counts the lines that went (0 if none)."""
    gone = removals(keyed(docs, id_col, text_col), divisor).select(F.col("id").alias("_gone_id"), F.col("key").alias("_gone_key"), F.col("gone").alias("_gone"))
    kept = docs.drop("lines_removed")
    joined = kept.join(gone.hint("merge"), (kept[id_col] == F.col("_gone_id")) & (F.md5(kept[text_col].cast("string").cast("binary")) == F.col("_gone_key")), "left")
    cut = F.when(F.col("_gone").isNull(), kept[text_col]).otherwise(F.expr(kept_text(f"split(`{text_col}`, '\n')", "_gone")))
    return joined.withColumns({text_col: cut, "lines_removed": F.coalesce(F.expr("aggregate(_gone, 0, (n, g) -> n + g.b - g.a + 1)"), F.lit(0))}).drop("_gone_id", "_gone_key", "_gone")


def op9_lines(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", F.coalesce(F.size(F.split("text", "\n")), F.lit(0)).alias("n_lines"))
    kept = F.coalesce("text", F.lit(""))
    return remove(docs).select("doc_id", F.greatest("n_lines", F.lit(0)).alias("n_lines"), "lines_removed", F.char_length(kept).alias("kept_chars"), F.md5(kept.cast("binary")).alias("kept_md5"))


OP9_SQL = f"""
WITH lines AS (
  SELECT d.doc_id, md5(d.text) AS key, u.i - 1 AS i, u.line,
         ('0x' || substr(md5(u.line), 1, 15))::BIGINT % {MODULUS} AS h
  FROM documents d, unnest(string_split(d.text, chr(10))) WITH ORDINALITY AS u(line, i)
), marked AS (
  SELECT *, CASE WHEN ({MULTIPLIER} * coalesce(lag(h) OVER w, 0) + h) % {MODULUS} % {DIVISOR} = 0 THEN 1 ELSE 0 END AS mark
  FROM lines WINDOW w AS (PARTITION BY doc_id, key ORDER BY i)
), closed AS (
  SELECT *, CASE WHEN mark = 1 AND lag(mark) OVER w = 0 THEN 1 ELSE 0 END AS closes
  FROM marked WINDOW w AS (PARTITION BY doc_id, key ORDER BY i)
), numbered AS (
  SELECT *, coalesce(sum(closes) OVER (PARTITION BY doc_id, key ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS c FROM closed
), chunks AS (
  SELECT doc_id, key, c, min(i) AS a, count(*) AS n, string_agg(line, chr(10) ORDER BY i) AS chunk FROM numbered GROUP BY doc_id, key, c
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY chunk ORDER BY doc_id, key, a) AS place
  FROM chunks WHERE n > 1 AND regexp_matches(chunk, '[^ \\t\\r\\n]')
), gone AS (SELECT doc_id, key, c, n FROM ranked WHERE place > 1),
kept AS (
  SELECT l.doc_id, count(*) AS n_lines, count(g.c) AS lines_removed,
         coalesce(string_agg(CASE WHEN g.c IS NULL THEN l.line END, chr(10) ORDER BY l.i), '') AS text
  FROM numbered l LEFT JOIN gone g ON l.doc_id = g.doc_id AND l.key = g.key AND l.c = g.c GROUP BY l.doc_id, l.key
)
SELECT doc_id, n_lines::INTEGER AS n_lines, lines_removed::INTEGER AS lines_removed, length(text)::INTEGER AS kept_chars, md5(text) AS kept_md5 FROM kept
"""
