"""Language identification by words first, then shorter and shorter character n-grams.

A known word scores by its log frequency in each language. An unseen one falls back to its
character 5-grams (with marks for its ends); if none of them is known, to 4-grams, and so on;
the mean log frequency of the n-grams of the first size that has known ones is its score.
The sums over the whole text give the posterior of each language.

Words are maximal runs of letters (and numerals that are no decimal digits) of the text in
lower case. All texts of a chunk are cut, hashed and looked up together: the tables are sorted
64-bit hashes with a row of log frequencies each.

Training takes about ``per_language`` documents of each language, chosen by a hash of the id;
that is the only bound. Of this sample every word and every n-gram that stands twice in it is
kept. The tables grow with the number of languages times the sample.

A null text, or one without a letter, is ``und`` with score 0, as is every text if nothing
could be learned. Ties go to the first language by code point. Repeated rows are judged each
for itself; an empty table gives no rows; other columns are not looked at."""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from recblock.llm import textkernel as K

SIZES = (5, 4, 3, 2, 1)
PER_LANGUAGE, UNSEEN, LEAST = 3000, "und", 2
_STEP, _FIRST, _LAST = np.uint64(0x9E3779B97F4A7C15), np.uint64(2), np.uint64(3)


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


@cache
def _letters() -> np.ndarray:
    """Of each code point: bit 0 if it belongs to words, bit 1 if it is a letter."""
    return np.array([(c.isalnum() and not c.isdecimal()) | c.isalpha() << 1 for c in map(chr, range(0x110000))], np.uint8)


def cut_words(texts: pa.Array, size: int = K.SLICE) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Chunk by chunk of about ``size`` bytes: first text, last text + 1, code points, start and end of each word, its
    text's number, and whether each text has a letter."""
    for a, b in K.bounds(texts, size):
        data, offs = K.buffers(pc.utf8_lower(texts.slice(a, b - a)))
        head = np.flatnonzero((data & 0xC0) != 0x80)
        codes = np.frombuffer(data.tobytes().decode().encode("utf-32-le"), np.uint32)
        edges = np.searchsorted(head, offs)
        kind = _letters()[codes]
        start, end, doc = K.words(np.where(kind & 1, 1, 0).astype(np.uint8), edges, _OUTSIDE)
        letter = np.zeros(b - a, bool)
        letter[np.searchsorted(edges, np.flatnonzero(kind & 2), "right") - 1] = True
        yield a, b, codes, start, end, doc, letter


_OUTSIDE = np.array([True] + [False] * 255)


def word_hashes(codes: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each codes[start:end], the same wherever the letters stand."""
    prefix = np.zeros(len(codes) + 1, np.uint64)
    np.cumsum(K.mixed(codes.astype(np.uint64) + np.uint64(1)) * K.powers(K.BASE, len(codes)), out=prefix[1:])
    return K.span_hash(prefix, start, end)


def gram_hashes(codes: np.ndarray, start: np.ndarray, end: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the n-grams of each word between marks, and the word's number of each."""
    length = end - start + 2
    owner = np.repeat(np.arange(len(start)), length)
    inside = np.arange(len(owner)) - np.repeat(np.cumsum(length) - length, length)
    marked = np.full(len(owner), _FIRST)
    letters = (inside > 0) & (inside < length[owner] - 1)
    marked[letters] = codes[(start[owner] + inside - 1)[letters]]
    marked[inside == length[owner] - 1] = _LAST
    if len(marked) < n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    whole = inside[: len(marked) - n + 1] + n <= length[owner[: len(marked) - n + 1]]
    h = np.zeros(len(marked) - n + 1, np.uint64)
    for j in range(n):
        h = h * _STEP + marked[j : len(marked) - n + 1 + j]
    return K.mixed(h[whole] + np.uint64(n)), owner[: len(whole)][whole]


class Table:
    """Sorted hashes and the log frequency of each in every language."""

    def __init__(self, hashes: np.ndarray, counts: np.ndarray):
        order = np.argsort(hashes)
        self.hashes, c = hashes[order], counts[order].astype(float)
        self.logs = np.log((c + 0.5) / (c.sum(0) + 0.5 * len(c)))

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """The row of each hash, -1 if it is unknown."""
        if not len(self.hashes):
            return np.full(len(hashes), -1)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return np.where(self.hashes[at] == hashes, at, -1)


class Model:
    """Log frequencies of words and n-grams by language. ``tables``: 0 for words, n for n-grams."""

    def __init__(self, languages: list[str], documents: list[int], tables: dict[int, Table]):
        self.languages, self.tables = languages, tables
        self.prior = np.log(np.array(documents, float) + 1)

    def unseen(self, codes: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Scores of words that no table of words has, 0 where no n-gram is known either."""
        out, todo = np.zeros((len(start), len(self.languages))), np.arange(len(start))
        for n in SIZES:
            if not len(todo):
                break
            h, owner = gram_hashes(codes, start[todo], end[todo], n)
            at = self.tables[n].find(h)
            owner, at = owner[at >= 0], at[at >= 0]
            count = np.bincount(owner, minlength=len(todo))
            known = count > 0
            for k in range(len(self.languages)):
                total = np.bincount(owner, self.tables[n].logs[at, k], minlength=len(todo))
                out[todo[known], k] = total[known] / count[known]
            todo = todo[~known]
        return out

    def judge(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        """Language and score of each text."""
        names, scores = [UNSEEN] * len(texts), np.zeros(len(texts))
        if not self.languages:
            return names, scores
        for a, b, codes, start, end, doc, letter in cut_words(texts):
            h = word_hashes(codes, start, end)
            distinct, where, back = np.unique(h, return_index=True, return_inverse=True)
            at = self.tables[0].find(distinct)
            logs = np.zeros((len(distinct), len(self.languages)))
            logs[at >= 0] = self.tables[0].logs[at[at >= 0]]
            new = np.flatnonzero(at < 0)
            logs[new] = self.unseen(codes, start[where[new]], end[where[new]])
            total = np.stack([np.bincount(doc, logs[back, k], minlength=b - a) for k in range(len(self.languages))], axis=1) + (self.prior - self.prior.max())
            p = np.exp(total - total.max(1, keepdims=True))
            best = p.argmax(1)
            for i in np.flatnonzero(letter).tolist():
                names[a + i] = self.languages[best[i]]
            scores[a:b] = np.where(letter, p[np.arange(b - a), best] / p.sum(1), 0.0)
        return names, scores


def _sums(h: np.ndarray, k: np.ndarray, counts: np.ndarray, languages: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashes and their counts by language."""
    distinct, group = np.unique(h, return_inverse=True)
    table = np.zeros((len(distinct), languages), np.int64)
    np.add.at(table, (group, k), counts)
    return distinct, table


def train(docs: DataFrame, per_language: int = PER_LANGUAGE) -> Model:
    """The model of ``docs(doc_id, text, lang)``: rows that aren't held out and have a language."""
    known = docs.where(~held_out(F.col("doc_id")) & F.col("lang").isNotNull())
    sizes = dict(sorted((r[0], r[1]) for r in known.groupBy(F.col("lang").cast("string")).agg(F.count("*")).collect()))  # one row per language
    languages = list(sizes)
    if not languages:
        return Model([], [], {})
    rate = F.element_at(F.create_map(*[F.lit(x) for k, v in sizes.items() for x in (k, min(1.0, per_language / v))]), F.col("lang").cast("string"))
    number = F.element_at(F.create_map(*[F.lit(x) for k, v in enumerate(languages) for x in (v, k)]), F.col("lang").cast("string"))
    chance = F.pmod(F.xxhash64(F.col("doc_id").cast("string")), F.lit(1 << 30)) / F.lit(float(1 << 30))
    sample = known.where(chance < rate).select(number.alias("k"), F.col("text").cast("string").alias("text"))
    width = len(languages)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Counts of words and n-grams of a chunk, one size after the other; each distinct word is cut into n-grams once."""
        for batch in batches:
            language = batch.column(0).to_numpy()
            for a, _, codes, start, end, doc, _ in cut_words(batch.column(1), K.CHUNK):
                h = word_hashes(codes, start, end)
                of = language[a + doc].astype(np.uint64)
                _, where, times = np.unique(K.mixed(h ^ (of * _STEP)), return_index=True, return_counts=True)
                h, of, start, end = h[where], of[where].astype(np.int64), start[where], end[where]
                for n in (0, *SIZES):
                    g, owner = gram_hashes(codes, start, end, n) if n else (h, np.arange(len(h)))
                    x, table = _sums(g, of[owner], times[owner], width)
                    lists = pa.FixedSizeListArray.from_arrays(pa.array(table.ravel()), width).cast(pa.list_(pa.int64()))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), n, np.int32)), pa.array(x.view(np.int64)), lists], ["size", "h", "c"])

    counted = sample.mapInArrow(count, "size int, h long, c array<long>")
    sums = counted.groupBy("size", "h").agg(*[F.sum(F.col("c")[i]).alias(f"c{i}") for i in range(width)])
    kept = sums.where(sum((F.col(f"c{i}") for i in range(width)), F.lit(0)) >= LEAST).toArrow()  # bounded by the sample
    size, h = kept.column("size").to_numpy(), kept.column("h").to_numpy().view(np.uint64)
    c = np.stack([kept.column(f"c{i}").to_numpy() for i in range(width)], axis=1)
    return Model(languages, list(sizes.values()), {n: Table(h[size == n], c[size == n]) for n in (0, *SIZES)})


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """``docs(doc_id, text)`` to doc_id, lang_pred and score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the sample it was learned from

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, scores = shared.value.judge(batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(scores)], ["doc_id", "lang_pred", "score"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, lang_pred string, score double")


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    return identify(docs, train(docs)).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
