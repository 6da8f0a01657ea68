"""Records as strings and their shingles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from recblock.operators.scan import running_sums


def let(value: Column, body) -> Column:
    """``body`` of a value that is computed once, however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def record_text(fields: list[str], sep: str = " ") -> Column:
    return F.concat_ws(sep, *[F.col(f).cast("string") for f in fields])


def with_text(records: DataFrame, fields: list[str]) -> DataFrame:
    return records.select("rec_id", record_text(fields).alias("rec_text"))


def char_shingles(text: Column, k: int) -> Column:
    """All strings of k letters, with repeats; a shorter text is its own only shingle, an empty one has none.
    The look-ahead finds overlapping ones in one pass over the text."""
    full = F.regexp_extract_all(text, F.lit(f"(?s)(?=(.{{{k}}}))"), F.lit(1))
    return F.when(F.length(text) == 0, F.array().cast("array<string>")).when(F.length(text) < k, F.array(text)).otherwise(full)


def shingle_set(text: Column, k: int) -> Column:
    return F.array_distinct(char_shingles(text, k))


def word_bag(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"\s+"), lambda w: w != "")


def word_shingles(text: Column, w: int) -> Column:
    return let(word_bag(text), lambda t: F.when(F.size(t) == 0, F.array().cast("array<string>")).when(F.size(t) < w, F.array(F.array_join(t, " "))).otherwise(F.transform(F.sequence(F.lit(1), F.size(t) - w + 1), lambda i: F.array_join(F.slice(t, i, F.lit(w)), " "))))


def shingle_counts(texts: DataFrame, k: int) -> DataFrame:
    """(rec_id, term, tf)."""
    return texts.select("rec_id", F.explode(char_shingles(F.col("rec_text"), k)).alias("term")).groupBy("rec_id", "term").agg(F.count("*").alias("tf"))


def vocabulary_growth(texts: DataFrame, k: int, sizes: list[int] | None = None, shares: tuple[int, ...] = (16, 8, 4, 2, 1)) -> DataFrame:
    """Distinct shingles among the first n records in order of id, whatever the ids are; (n, w_n).
    Without ``sizes``, n is an nth of the records for each of ``shares``, 1 being all of them. A size
    is given if it holds a shingle; an empty table gives no rows."""
    placed = running_sums(texts, [F.col("rec_id")], {"place": F.lit(1)})
    terms = placed.select("place", F.explode(shingle_set(F.col("rec_text"), k)).alias("term")).groupBy("term").agg(F.min("place").alias("first"))
    if sizes is None:
        total = texts.count()
        sizes = sorted({-(-total // d) for d in shares if total})
    if not sizes:
        return terms.select(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("w_n")).limit(0)
    rows = terms.select(F.explode(F.array(*[F.lit(n).cast("long") for n in sizes])).alias("n"), "first").where("first <= n")
    return rows.groupBy("n").agg(F.count("*").alias("w_n"))


def growth_exponent(growth: DataFrame) -> DataFrame:
    return growth.agg(F.round(F.regr_slope(F.ln("w_n"), F.ln("n")), 6).alias("beta"))


def shingle_density(texts: DataFrame, k: int) -> DataFrame:
    """How much of the records by shingles matrix is filled."""
    terms = texts.select("rec_id", F.explode(shingle_set(F.col("rec_text"), k)).alias("term"))
    one = terms.agg(F.count("*").alias("filled"), F.countDistinct("term").alias("vocabulary")).crossJoin(F.broadcast(texts.agg(F.count("*").alias("n"))))
    return one.select(F.lit(k).alias("k"), "vocabulary", "filled", F.round(F.col("filled") / (F.col("n") * F.col("vocabulary")), 9).alias("density"))
