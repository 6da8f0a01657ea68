"""Quality rules as a bitmask ledger, in DataFrame functions only.

Every rule is evaluated once per document; the ledger keeps the measurements and one bit per
failed rule. A policy is a mask of rules that count, named by version; applying one, or
measuring what a rule alone removes, is bit arithmetic on the ledger and never reads a text.

Nulls and empty texts measure 0 everywhere (so the word minimum fails). Repeated rows are
judged each for itself, an empty table gives no rows, other columns are not looked at. A
text's windows are sorted inside its row, so a long text costs n log n and no shuffle."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SPACES, SYMBOLS = " \t\n\x0b\x0c\r", "#*$%&|<>"
MIN_WORDS, REPEAT_PERCENT, SYMBOL_PERCENT, DUP_LINE_PERCENT = 50, 50, 100, 50
MEAN_LETTERS = (2, 20)
RULES = ("few_words", "repeated_words", "word_length", "symbols", "duplicate_lines")
BASE = 0b00011
POLICIES = {"base": BASE, "v1": 0b11111}


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def text_words(text: Column) -> Column:
    return F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != "")


def repeated_words(words: Column) -> Column:
    """Words inside a three-word window that stands at two or more places of the text."""
    n = F.size(words)
    marks = F.sort_array(F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.struct(F.xxhash64(words[i], words[i + 1], words[i + 2]).alias("h"), i.alias("i"))))

    def covered(m: Column) -> Column:
        last = F.size(m) - 1
        again = F.filter(m, lambda x, k: F.coalesce((k > 0) & (m[F.greatest(k - 1, F.lit(0))]["h"] == x["h"]), F.lit(False)) | F.coalesce((k < last) & (m[F.least(k + 1, last)]["h"] == x["h"]), F.lit(False)))
        places = F.array_sort(F.transform(again, lambda x: x["i"]))
        return let(places, lambda p: F.when(F.size(p) == 0, 0).otherwise(F.aggregate(p, F.struct(F.lit(0).alias("n"), F.lit(-3).alias("last")), lambda a, i: F.struct((a["n"] + F.least(F.lit(3), i - a["last"])).alias("n"), i.alias("last")))["n"]))

    return F.when(n < 3, 0).otherwise(let(marks, covered))


def ledger(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, the measurements and ``fail_bits`` (bit k: RULES[k])."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: F.translate(x, SPACES, "") != "")
    solid = F.translate(text, SPACES, "")
    measured = docs.select(
        F.col(id_col).alias("doc_id"),
        let(text_words(text), lambda w: F.struct(F.size(w).alias("n_words"), repeated_words(w).alias("n_repeat_words"))).alias("__w"),
        F.length(solid).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long").alias("n_symbols"),
        let(lines, lambda x: F.struct(F.size(x).alias("all"), (F.size(x) - F.size(F.array_distinct(x))).alias("dup"))).alias("__l"),
    ).select(
        "doc_id", F.col("__w.n_words").cast("long").alias("n_words"), "word_chars", "n_symbols", F.col("__l.dup").cast("long").alias("n_dup_lines"),
        F.col("__w.n_repeat_words").cast("long").alias("n_repeat_words"), F.col("__l.all").cast("long").alias("n_lines"),
    )
    fails = (
        F.col("n_words") < MIN_WORDS,
        100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"),
        (F.col("word_chars") < MEAN_LETTERS[0] * F.col("n_words")) | (F.col("word_chars") > MEAN_LETTERS[1] * F.col("n_words")),
        100 * F.col("n_symbols") > SYMBOL_PERCENT * F.col("n_words"),
        100 * F.col("n_dup_lines") > DUP_LINE_PERCENT * F.col("n_lines"),
    )
    bits = sum((F.when(f, F.lit(1 << k)).otherwise(F.lit(0)) for k, f in enumerate(fails)), F.lit(0))
    return measured.withColumn("fail_bits", bits.cast("long"))


def judged(entries: DataFrame, policy: str = "v1") -> DataFrame:
    """Adds ``kept`` by a policy."""
    return entries.withColumn("kept", F.col("fail_bits").bitwiseAND(F.lit(POLICIES[policy])) == 0)


def ablations(entries: DataFrame) -> DataFrame:
    """For each policy and rule of it: documents that fail, and those that only this rule removes."""
    rows = F.explode(F.array(*[F.struct(F.lit(p).alias("policy"), F.lit(r).alias("rule"), F.lit(m).alias("mask"), F.lit(1 << k).alias("bit")) for p, m in POLICIES.items() for k, r in enumerate(RULES) if m >> k & 1]))
    failed = F.col("fail_bits").bitwiseAND(F.col("r.mask"))
    by_bits = entries.groupBy("fail_bits").agg(F.count("*").alias("n"))  # one row per set of failed rules
    return by_bits.select("fail_bits", "n", rows.alias("r")).groupBy("r.policy", "r.rule").agg(
        F.sum(F.when(failed.bitwiseAND(F.col("r.bit")) != 0, F.col("n")).otherwise(0)).alias("failed"),
        F.sum(F.when(failed == F.col("r.bit"), F.col("n")).otherwise(0)).alias("only_this"),
    )


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    entries = judged(ledger(spark.read.parquet(f"{sf_dir}/documents.parquet")))
    base_failed = F.col("fail_bits").bitwiseAND(F.lit(BASE)) != 0
    return entries.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base_failed.alias("base_failed"), "kept", "fail_bits")


OP5_SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws,
             list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
win AS (SELECT doc_id, i, ws[i] || chr(10) || ws[i + 1] || chr(10) || ws[i + 2] AS g
        FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 1, 1))) AS i FROM w)),
rep AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) WHERE c > 1),
cov AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, i + unnest([0, 1, 2]) AS j FROM rep) GROUP BY doc_id),
m AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
             CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
             CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines, CAST(coalesce(cov.n, 0) AS BIGINT) AS n_repeat_words, len(ls) AS n_lines
      FROM w LEFT JOIN cov USING (doc_id)),
b AS (SELECT *, CAST((n_words < 50)::INT + 2 * (100 * n_repeat_words > 50 * n_words)::INT + 4 * (word_chars < 2 * n_words OR word_chars > 20 * n_words)::INT
             + 8 * (100 * n_symbols > 100 * n_words)::INT + 16 * (100 * n_dup_lines > 50 * n_lines)::INT AS BIGINT) AS fail_bits FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (fail_bits & 3) <> 0 AS base_failed, fail_bits = 0 AS kept, fail_bits FROM b
"""
