"""Quality rules with cross-document line frequency, in DataFrame functions only.

Base figures of each text come from array functions over its words and lines. The method then hashes
the normalised lines (lower case, runs of digits as 0, trimmed), counts on how many distinct
documents of a host (``source``) each occurs (exact copies of a text are one document), removes
lines that occur on more than ``line_limit`` of them, but for the first document that has the line,
and rejects documents that are depleted: fewer than ``least_left`` words or less than half of their
words are left.

Counting pre-aggregates per (host, line, text) before it counts per (host, line); the lines above
the limit meet the documents' lines on a salted key, so a line that a third of all documents have
is spread over ``salts`` tasks.

Defined results: a null or empty text has no words, fails the base rule and is not kept; a null
source is a host of its own; repeated rows get a row each; an empty table gives no rows; extra
columns are ignored by ``judge`` and pass through ``apply``; very long texts are measured whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from edgesketch.llm.common import materialize, table

SPACE = " \t\n\x0b\x0c\r"
MIN_WORDS = 20
REPEAT_PERCENT = 30
LINE_LIMIT = 20
LEFT_PERCENT = 50
LEAST_LEFT = 10
SALTS = 16


def words_of(text: Column) -> Column:
    """``[^\\x20\\x09-\\x0D]+`` of a text."""
    bare = F.btrim(text, F.lit(SPACE))
    return F.when(F.length(bare) == 0, F.array().cast("array<string>")).otherwise(F.split(bare, "[ \t-\r]+"))


def _lines(text: Column) -> Column:
    return F.split(text, "\n")


def _has_word(line: Column) -> Column:
    return F.length(F.btrim(line, F.lit(SPACE))) > 0


def _normal_lines(text: Column) -> Column:
    """The normalised lines, one for each raw line and in their order; one without a word is empty."""
    return F.transform(_lines(F.lower(F.regexp_replace(text, "[0-9]+", "0"))), lambda x: F.btrim(x, F.lit(SPACE)))


def _steps(array: str) -> Column:
    """Falling powers of two below the size of an array: the strides of a binary search in it."""
    powers = F.array(*[F.lit(1 << k) for k in range(30, -1, -1)])
    return F.filter(powers, lambda s: s < F.size(array))


def _among(h: Column, array: str, steps: str) -> Column:
    """Whether a rising array holds ``h``, in as many steps as the array's size has bits."""
    spot = F.aggregate(steps, F.lit(0), lambda at, s: F.when(F.get(array, at + s) <= h, at + s).otherwise(at))
    return F.coalesce(F.get(array, spot) == h, F.lit(False))


def _repeat_words(df: DataFrame, width: int = 8) -> DataFrame:
    """Adds n_repeat_words: words in windows of ``width`` words found twice or more in the text.

    Window hashes are compared as a set first; only a text with a repeated one sorts its windows.
    """
    windows = F.when(
        F.size("words") > width,
        F.transform(F.sequence(F.lit(1), F.size("words") - (width - 1)), lambda i: F.xxhash64(F.slice("words", i, width))),
    )
    df = df.withColumn("_w", windows)
    df = df.withColumn("_s", F.when(F.size(F.array_distinct("_w")) < F.size("_w"), F.array_sort(F.transform("_w", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    same = lambda a, b: F.coalesce(a["h"] == b["h"], F.lit(False))
    twice = F.filter("_s", lambda s, j: same(s, F.get("_s", j - 1)) | same(s, F.get("_s", j + 1)))
    df = df.withColumn("_p", F.array_sort(F.transform(twice, lambda s: s["i"])))
    covered = F.transform("_p", lambda p, j: F.least(F.lit(width), F.coalesce(F.get("_p", j + 1), p + width) - p))
    return df.withColumn("n_repeat_words", F.coalesce(F.aggregate(covered, F.lit(0), lambda a, x: a + x), F.lit(0)).cast("long")).drop("_w", "_s", "_p")


def base(docs: DataFrame) -> DataFrame:
    """doc_id, host, sig (hash of the text), the base figures, and the lines as hashes with their words."""
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("host"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    df = df.withColumn("words", words_of(F.col("text"))).withColumn("full", F.filter(_lines(F.col("text")), _has_word))
    df = df.select(
        "doc_id", "host", F.xxhash64("text").alias("sig"), "words",
        F.size("words").cast("long").alias("n_words"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        F.regexp_count("text", F.lit("[#*$%&|<>]")).cast("long").alias("n_symbols"),
        (F.size("full") - F.size(F.array_distinct("full"))).cast("long").alias("n_dup_lines"),
        F.transform(F.filter(_normal_lines(F.col("text")), lambda x: F.length(x) > 0), lambda x: F.struct(F.xxhash64(x).alias("h"), F.regexp_count(x, F.lit("[^ \t-\r]+")).alias("n"))).alias("lines"),
    )
    df = _repeat_words(df).drop("words")
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"))
    return df.withColumn("base_failed", failed)


def common_lines(docs: DataFrame, line_limit: int = LINE_LIMIT) -> DataFrame:
    """(host, h, first_doc) of the lines that occur on more than ``line_limit`` distinct documents of a host."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(
        F.col("source").cast("string").alias("host"), F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("sig"),
        F.explode(F.array_distinct(F.transform(F.filter(_normal_lines(text), lambda x: F.length(x) > 0), lambda x: F.xxhash64(x)))).alias("h"),
    )
    per_text = rows.groupBy("host", "h", "sig").agg(F.min("doc_id").alias("doc_id"))
    return per_text.groupBy("host", "h").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("first_doc")).where(F.col("n") > line_limit).drop("n")


def lines_to_cut(measured: DataFrame, common: DataFrame, salts: int = SALTS) -> DataFrame:
    """(doc_id, host, sig, cut, steps): rising hashes of the lines that each document loses, and the strides to search them."""
    own = measured.select("doc_id", "host", "sig", F.explode(F.array_distinct(F.col("lines.h"))).alias("h"), F.pmod(F.xxhash64("doc_id"), F.lit(salts)).alias("salt"))
    spread = common.select("host", "h", "first_doc", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))).alias("salt"))
    met = own.alias("a").join(spread.alias("b"), (F.col("a.h") == F.col("b.h")) & F.col("a.host").eqNullSafe(F.col("b.host")) & (F.col("a.salt") == F.col("b.salt")))
    lost = met.where(~F.col("a.doc_id").eqNullSafe(F.col("b.first_doc"))).select("a.doc_id", "a.host", "a.sig", "a.h")
    return lost.groupBy("doc_id", "host", "sig").agg(F.array_sort(F.collect_set("h")).alias("cut")).withColumn("steps", _steps("cut"))


def judge(docs: DataFrame, line_limit: int = LINE_LIMIT, least_left: int = LEAST_LEFT, left_percent: int = LEFT_PERCENT) -> DataFrame:
    """One row per document with its figures, the words that lines above the limit leave it, and kept."""
    measured = base(docs)
    cut = lines_to_cut(measured.select("doc_id", "host", "sig", "lines"), common_lines(docs, line_limit))
    both = measured.alias("m").join(
        cut.alias("c"), F.col("m.doc_id").eqNullSafe(F.col("c.doc_id")) & F.col("m.host").eqNullSafe(F.col("c.host")) & (F.col("m.sig") == F.col("c.sig")), "left"
    )
    lost = F.aggregate(F.filter("lines", lambda x: _among(x["h"], "cut", "steps")), F.lit(0).cast("long"), lambda a, x: a + x["n"])
    both = both.select("m.*", F.col("c.cut").alias("cut"), F.col("c.steps").alias("steps")).withColumn("words_left", F.col("n_words") - F.when(F.col("cut").isNull(), F.lit(0)).otherwise(lost))
    depleted = (F.col("words_left") < least_left) | (100 * F.col("words_left") < left_percent * F.col("n_words"))
    return both.withColumn("kept", ~F.col("base_failed") & ~depleted)


FIGURES = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]


def apply(docs: DataFrame, line_limit: int = LINE_LIMIT, least_left: int = LEAST_LEFT, left_percent: int = LEFT_PERCENT) -> DataFrame:
    """The documents that stay, with all their columns, their text without the lines above the limit."""
    verdicts = judge(docs, line_limit, least_left, left_percent).select(F.col("doc_id").alias("__es_id"), F.col("host").alias("__es_host"), F.col("sig").alias("__es_sig"), F.col("cut").alias("__es_cut"), F.col("steps").alias("__es_steps"), F.col("kept").alias("__es_kept"))
    # written before it is filtered: a filter pushed below the figures would make a text's words for each window
    told = materialize(verdicts, "verdicts").where("__es_kept").drop("__es_kept").distinct()
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    own = docs.withColumn("__es_s", F.xxhash64(text))
    met = own.join(told, F.col("doc_id").cast("long").eqNullSafe(F.col("__es_id")) & F.col("source").cast("string").eqNullSafe(F.col("__es_host")) & (F.col("__es_s") == F.col("__es_sig")))
    # one zipped array, made once for a text: a column that only a lambda names would be made for each line
    pairs = F.zip_with(_lines(F.col("text")), F.transform(_normal_lines(F.col("text")), lambda x: F.xxhash64(x)), lambda x, h: F.struct(x.alias("x"), h.alias("h")))
    left = F.filter(pairs, lambda s: ~_among(s["h"], "__es_cut", "__es_steps"))
    met = met.withColumn("text", F.when(F.col("__es_cut").isNull(), F.col("text")).otherwise(F.array_join(F.transform(left, lambda s: s["x"]), "\n")))
    if "n_chars" in docs.columns:
        met = met.withColumn("n_chars", F.when(F.col("__es_cut").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(docs.schema["n_chars"].dataType)))
    return met.select(*docs.columns)


def query(spark, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents")).select(*FIGURES)


ORACLE = r"""
WITH d AS (SELECT doc_id, source AS host, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
win AS (SELECT doc_id, unnest(range(1, len(w) - 6)) AS i, w FROM d WHERE len(w) >= 8),
wh AS (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS g FROM win),
tw AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS c FROM wh) WHERE c > 1),
rp AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM tw) GROUP BY doc_id),
b AS (SELECT d.doc_id, host, text, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars, length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS n_symbols,
             len(list_filter(ls, lambda x: regexp_matches(x, '[^\x20\x09-\x0D]'))) - len(list_distinct(list_filter(ls, lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))) AS n_dup_lines,
             coalesce(rp.n, 0) AS n_repeat_words FROM d LEFT JOIN rp USING (doc_id)),
f AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM b),
ln AS (SELECT doc_id, host, text, unnest(list_transform(string_split(lower(regexp_replace(text, '[0-9]+', '0', 'g')), chr(10)), lambda x: trim(x, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)))) AS l FROM d),
lx AS (SELECT * FROM ln WHERE l <> ''),
cm AS (SELECT host, l, min(doc_id) AS first_doc FROM lx GROUP BY host, l HAVING count(DISTINCT text) > 20),
cut AS (SELECT lx.doc_id, sum(len(regexp_extract_all(lx.l, '[^\x20\x09-\x0D]+'))) AS n FROM lx JOIN cm ON lx.l = cm.l AND lx.host IS NOT DISTINCT FROM cm.host WHERE lx.doc_id <> cm.first_doc GROUP BY lx.doc_id)
SELECT f.doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words, base_failed,
       NOT base_failed AND n_words - coalesce(cut.n, 0) >= 10 AND 100 * (n_words - coalesce(cut.n, 0)) >= 50 * n_words AS kept
FROM f LEFT JOIN cut USING (doc_id)
"""
