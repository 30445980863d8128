"""Operator 8: a threshold table compiled into one projection of length, symbol, stop-word and line ratios.

Every measure is a built-in expression of the text, so the whole verdict is one Spark projection with neither
shuffle nor user function. Defined results: a null or empty text has no words and fails; extra columns are ignored;
repeated rows are judged alike, each in its own row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from packsum.llm.textexpr import let, spaced, word_array

# The commonest function words of the languages covered, and what counts as a symbol.
STOP_WORDS = (
    "the of and to in is that for with was on as are by this be at from or an it not have a "
    "de la le et les des en un du une que dans pour par est qui il sur au ne pas plus avec "
    "der die und das von den mit ist des im dem nicht ein eine zu auf fur sich auch als an "
    "el los las del se por con para su al lo como y una mas o e es si no"
).split()
STOP_WORDS = tuple(dict.fromkeys(STOP_WORDS))
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Threshold:
    """``low <= 100 * measure <= high * per``, in whole numbers so that every engine agrees; None: no bound."""

    measure: str
    per: str | None
    low: int | None
    high: int | None


#: Clean documents pass with a wide margin; spam, tables and chants do not.
THRESHOLDS = (
    Threshold("n_words", None, 5_000, 100 * 200_000),
    Threshold("word_chars", "n_words", 200, 2_000),
    Threshold("n_symbols", "n_words", None, 10),
    Threshold("n_stop_words", "n_words", 2, None),
    Threshold("n_dup_lines", "n_lines", None, 50),
    Threshold("n_bullet_lines", "n_lines", None, 90),
)


def repeated_window_words(words: Column, width: int = 3) -> Column:
    """Words in ``width``-word windows that the array holds at least twice, the first of them included.

    Each window becomes one integer: the high bits of its fingerprint over its position. Sorting these primitive
    integers puts equal windows side by side; the words themselves are compared where the high bits agree.
    """

    def covered(ws: Column, bits: Column) -> Column:
        mask = F.call_function("shiftleft", F.lit(1).cast("long"), bits) - 1
        coded = F.transform(ws, lambda w, i: F.xxhash64(w, *(F.get(ws, i + k) for k in range(1, width))).bitwiseAND(F.bitwise_not(mask)).bitwiseOR(i.cast("long")))
        ordered = F.sort_array(F.slice(coded, F.lit(1), F.greatest(F.size(ws) - (width - 1), F.lit(0))))

        def places(s: Column) -> Column:
            def same(x: Column, y: Column) -> Column:
                i, j = (v.bitwiseAND(mask).cast("int") for v in (x, y))
                out = x.bitwiseXOR(y).bitwiseAND(F.bitwise_not(mask)) == 0
                for k in range(width):
                    out &= F.get(ws, i + k) == F.get(ws, j + k)
                return F.coalesce(out, F.lit(False))

            again = F.filter(s, lambda x, k: same(x, F.get(s, k + 1)) | same(x, F.get(s, k - 1)))
            return F.sort_array(F.transform(again, lambda x: x.bitwiseAND(mask)))

        start = F.struct(F.lit(-width).cast("long").alias("last"), F.lit(0).cast("long").alias("n"))
        step = lambda a, p: F.struct(p.alias("last"), (a["n"] + F.least(F.lit(width).cast("long"), p - a["last"])).alias("n"))
        return F.aggregate(let(ordered, places), start, step, lambda a: a["n"])

    return let(words, lambda ws: let(F.ceil(F.log2(F.size(ws) + F.lit(2))).cast("int"), lambda bits: covered(ws, bits)))


def with_measures(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Measures of each row: one narrow projection."""
    own = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("_text"))
    own = own.withColumn("_plain", spaced(F.col("_text"))).withColumn("_words", word_array(F.col("_text")))
    lines = F.filter(F.split(F.col("_text"), "\n"), lambda x: F.trim(spaced(x)) != "")
    long = lambda c: c.cast("long")

    def without(c: Column, characters: str) -> Column:
        for x in characters:
            c = F.replace(c, F.lit(x), F.lit(""))
        return F.length(c)

    def of_lines(x: Column) -> Column:
        bullets = F.filter(x, lambda y: F.ltrim(y).substr(1, 1).isin("-", "*", "|"))
        return F.struct(long(F.size(x)).alias("n"), long(F.size(x) - F.size(F.array_distinct(x))).alias("dup"), long(F.size(bullets)).alias("bullets"))

    return own.select(
        "doc_id",
        long(F.size("_words")).alias("n_words"),
        long(without(F.col("_plain"), " ")).alias("word_chars"),
        long(F.length("_text") - without(F.col("_text"), SYMBOLS)).alias("n_symbols"),
        let(lines, of_lines).alias("_lines"),
        repeated_window_words(F.col("_words")).alias("n_repeat_words"),
        long(F.size(F.filter("_words", lambda w: w.isin(*STOP_WORDS)))).alias("n_stop_words"),
    ).select(
        "doc_id", "n_words", "word_chars", "n_symbols", F.col("_lines.dup").alias("n_dup_lines"), "n_repeat_words", "n_stop_words", F.col("_lines.n").alias("n_lines"), F.col("_lines.bullets").alias("n_bullet_lines")
    )


def verdict(thresholds: tuple[Threshold, ...] = THRESHOLDS) -> Column:
    """The table as one boolean expression."""
    out = F.lit(True)
    for t in thresholds:
        per = F.col(t.per) if t.per else F.lit(1)
        if t.low is not None:
            out &= 100 * F.col(t.measure) >= t.low * per
        if t.high is not None:
            out &= 100 * F.col(t.measure) <= t.high * per
    return out


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def quality_rules(docs: DataFrame, thresholds: tuple[Threshold, ...] = THRESHOLDS, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each input row: its measures, whether the base rules fail it, and whether it is kept."""
    out = with_measures(docs, doc_id, text).withColumn("base_failed", base_failed())
    return out.withColumn("kept", ~F.col("base_failed") & verdict(thresholds)).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_lines", "n_stop_words", "n_bullet_lines"
    )


def oracle() -> str:
    """The same over DuckDB's view ``documents``."""
    bounds = [f"100 * {t.measure} >= {t.low} * {t.per or 1}" for t in THRESHOLDS if t.low is not None]
    bounds += [f"100 * {t.measure} <= {t.high} * {t.per or 1}" for t in THRESHOLDS if t.high is not None]
    stops = ", ".join(f"'{w}'" for w in STOP_WORDS)
    return rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
pos AS (SELECT doc_id, unnest(ws) AS a, generate_subscripts(ws, 1) AS i FROM d),
tri AS (SELECT doc_id, i, a, lead(a) OVER p AS b, lead(a, 2) OVER p AS c FROM pos WINDOW p AS (PARTITION BY doc_id ORDER BY i)),
win AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, a, b, c) AS n FROM tri WHERE c IS NOT NULL),
rep AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM win WHERE n > 1) GROUP BY doc_id),
m AS (SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(list_sum(list_transform(ws, lambda w: length(w))), 0)::BIGINT AS word_chars,
  (length(text) - length(regexp_replace(text, '[{SYMBOLS}]', '', 'g')))::BIGINT AS n_symbols,
  list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls,
  len(list_filter(ws, lambda w: w IN ({stops})))::BIGINT AS n_stop_words, coalesce(rep.n, 0)::BIGINT AS n_repeat_words
  FROM d LEFT JOIN rep ON rep.doc_id = d.doc_id),
f AS (SELECT *, len(ls)::BIGINT AS n_lines, (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines,
  len(list_filter(ls, lambda x: left(ltrim(x, ' '), 1) IN ('-', '*', '|')))::BIGINT AS n_bullet_lines,
  (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND {' AND '.join(bounds)}) AS kept,
  n_lines, n_stop_words, n_bullet_lines FROM f"""
