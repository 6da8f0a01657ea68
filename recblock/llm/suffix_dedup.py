"""Removal of repeated byte strings by a column-wise construction over many documents.

Every string of ``length`` bytes holds an anchor: the 64-byte gram of least hash. Equal strings
have their anchors at the same place, so only contexts of equal anchors (what lies within reach
before and after) can hold equal strings, and contexts stand aligned at the anchor. All contexts
of an anchor are one collection, whose Burrows-Wheeler order is built column by column from
the right: each round inserts one symbol of every context, sorts stably by it, and carries the
common prefix of neighbours on (one more than the least of those between them). A context's
string at a column is repeated if a neighbour shares ``length`` symbols with it. Of the order
and the prefixes only the last column's are held; the symbols lie column after column and are
read once, front to back. A collection of very many contexts is parted by what stands beside
the anchor, so that its columns fit a task.

Anchors that stand once are dropped; contexts that are all equal need no construction; equal
contexts of one anchor go through it once.

Every row gets a number of its own before the first stage, so ids are only carried along: they
may be null, repeat, or be of any type, and each row is a document of its own. A null text is
empty. Strings are judged on the input; matches never cross documents; places in one document
count as well. An empty table gives no rows."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from recblock.llm import textkernel as K
from recblock.session import stored

LENGTH, GRAM = 200, 64
GROUP, LARGE = 20_000, 100_000  # contexts that are built together, and of a collection that is parted first
FREQUENT = 1024  # a context at more than this part of all places is known to every task
_PLACE = np.uint64((1 << 28) - 1)


def anchors(data: np.ndarray, offs: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Text number, place, hash of the gram, hash of the context of every anchor."""
    n = len(data)
    none = np.zeros(0, np.int64)
    if n < length:
        return none, none, none, none
    reach = length - gram
    prefix = K.prefix_hash(data)
    places = np.arange(n - gram + 1)
    value = (K.span_hash(prefix, places, places + gram) & ~_PLACE) | places.astype(np.uint64)
    width = reach + 1
    m = -(-len(value) // width)
    block = np.full((m, width), np.iinfo(np.uint64).max, np.uint64)
    block.ravel()[: len(value)] = value
    before = np.minimum.accumulate(block, axis=1).ravel()
    after = np.minimum.accumulate(block[:, ::-1], axis=1)[:, ::-1].ravel()
    starts = n - length + 1
    least = np.minimum(after[:starts], before[width - 1 : width - 1 + starts]) & _PLACE
    ends = np.repeat(offs[1:], np.diff(offs))[:starts]
    least = least[np.arange(starts) + length <= ends].astype(np.int64)
    if not len(least):
        return none, none, none, none
    at = least[np.append(True, least[1:] != least[:-1])]
    doc = np.searchsorted(offs, at, "right") - 1
    lo, hi = np.maximum(at - reach, offs[doc]), np.minimum(at + length, offs[doc + 1])
    h = K.span_hash(prefix, at, at + gram).view(np.int64)
    c = K.mixed(K.span_hash(prefix, lo, hi) + (at - lo).astype(np.uint64) * np.uint64(0xDA942042E4DD58B5)).view(np.int64)
    return doc, at - offs[doc], h, c


def _text_anchors(data: np.ndarray, offs: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """As anchors(), a very long text in overlapping pieces."""
    if len(offs) > 2 or len(data) <= 4 * K.CHUNK:
        return anchors(data, offs, length)
    at = np.unique(np.concatenate([s + anchors(data[s : s + K.CHUNK + length - 1], np.array([0, min(len(data) - s, K.CHUNK + length - 1)]), length)[1] for s in range(0, len(data), K.CHUNK)]))
    h, c = [], []
    for s in range(0, len(data), K.CHUNK):
        own = at[(at >= s) & (at < s + K.CHUNK)]
        base = max(0, s - length)
        prefix = K.prefix_hash(data[base : s + K.CHUNK + length])
        lo, hi = np.maximum(own - (length - GRAM), 0), np.minimum(own + length, len(data))
        h.append(K.span_hash(prefix, own - base, own - base + GRAM).view(np.int64))
        c.append(K.mixed(K.span_hash(prefix, lo - base, hi - base) + (own - lo).astype(np.uint64) * np.uint64(0xDA942042E4DD58B5)).view(np.int64))
    return np.zeros(len(at), np.int64), at, np.concatenate(h), np.concatenate(c)


def numbered_texts(docs: DataFrame) -> DataFrame:
    """(row, doc_id, z): the compressed texts under numbers that are fixed by being written once."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tight = zstandard.ZstdCompressor(level=1)
        for batch in batches:
            data, offs = K.buffers(batch.column(2))
            raw = memoryview(data)
            z = [tight.compress(raw[x:y]) for x, y in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(z, pa.binary())], ["row", "doc_id", "z"])

    rows = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", F.col("text").cast("string").alias("text"))
    return stored(rows.mapInArrow(run, f"row long, doc_id {kind}, z binary"))


def anchor_rows(texts: DataFrame, length: int = LENGTH) -> DataFrame:
    """h, c, row and place of all anchors of ``texts(row, z)``. place: where the anchor stands, times
    256, and by how much the text's end shortens the context."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        un = zstandard.ZstdDecompressor()
        for batch in batches:
            rows, z = batch.column(0).to_numpy(), batch.column(1)
            at = 0
            while at < len(rows):  # about a megabyte of texts at a time
                own, size = [], 0
                while at + len(own) < len(rows) and (not own or size < K.CHUNK):
                    own.append(un.decompress(z[at + len(own)].as_py()))
                    size += len(own[-1])
                data, offs = np.frombuffer(b"".join(own), np.uint8), np.append(0, np.cumsum([len(x) for x in own])).astype(np.int64)
                doc, place, h, c = _text_anchors(data, offs, length)
                short = np.maximum(place + length - np.diff(offs)[doc], 0)
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(c), pa.array(rows[at + doc]), pa.array(place * 256 + short)], ["h", "c", "row", "place"])
                at += len(own)

    return texts.select("row", "z").mapInArrow(run, "h long, c long, row long, place long")


def repeated_columns(columns: np.ndarray, left: np.ndarray, right: np.ndarray, group: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """First and last column at which each context begins a string that another of its group has
    there (-1: none). columns: (reach + length, contexts) symbols; left, right: how far a
    context goes before and after the anchor; group: ascending numbers."""
    reach, m = length - gram, len(group)
    order = np.arange(m)
    common = np.zeros(m + 1, np.int16)
    low, high = np.full(m, -1), np.full(m, -1)
    edge = np.append(True, group[1:] != group[:-1])
    small = (np.cumsum(edge) - 1).astype(np.uint16)  # callers keep groups under 65,536
    for t in range(reach + length - 1, -1, -1):
        symbol = columns[t][order].astype(np.uint16)
        outside = (t < reach - left) | (t >= reach + right)
        symbol[outside[order]] = 256
        same = np.append(False, symbol[1:] == symbol[:-1])
        if (same | edge).all():  # the order stands
            grown = common[:m] + 1
            now = symbol
        else:
            by_symbol = np.argsort(symbol, kind="stable")
            move = by_symbol[np.argsort(small[by_symbol], kind="stable")]
            now = symbol[move]
            gap = np.append(1, np.diff(move))
            grown = common[:m][move] + 1
            wide = np.flatnonzero((gap != 1) & ~edge & np.append(False, now[1:] == now[:-1]))
            if len(wide):
                ranges = np.empty(2 * len(wide), np.int64)
                ranges[0::2], ranges[1::2] = move[wide - 1] + 1, move[wide] + 1
                grown[wide] = np.minimum.reduceat(common, ranges)[0::2] + 1
            order = order[move]
        grown[edge | (now == 256) | np.append(True, now[1:] != now[:-1])] = 0
        common[:m] = np.minimum(grown, length)
        if t <= reach:
            hit = order[(common[:m] >= length) | (common[1:] >= length)]
            low[hit] = t
            high[hit] = np.maximum(high[hit], t)
    return low, high


def _columns(contexts: list[bytes], left: np.ndarray, length: int, gram: int) -> np.ndarray:
    """The contexts' symbols, column after column, aligned at the anchor."""
    reach = length - gram
    out = np.zeros((reach + length, len(contexts)), np.uint8)
    for k in range(0, len(contexts), 4096):
        rows = np.zeros((min(4096, len(contexts) - k), len(out)), np.uint8)
        for i, x in enumerate(contexts[k : k + 4096]):
            s = reach - left[k + i]
            rows[i, s : s + len(x)] = np.frombuffer(x, np.uint8)
        out[:, k : k + len(rows)] = rows.T
    return out


def repeated_contexts(contexts: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """``contexts(g, h, c, x, left)``, sorted by the collection g in each partition, to (h, c, lo, hi):
    the bytes, counted from the anchor, that repeated strings of the context cover."""
    reach = length - gram

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []

        def done() -> pa.RecordBatch:
            gs, hs, cs, xs, lefts = zip(*rows, strict=True)
            left = np.array(lefts)
            right = np.array([len(x) for x in xs]) - left
            h, c = np.array(hs, np.int64), np.array(cs, np.int64)
            low, high = repeated_columns(_columns(xs, left, length, gram), left, right, np.array(gs, np.int64), length, gram)
            hit = np.flatnonzero(low >= 0)
            return pa.RecordBatch.from_arrays([pa.array(h[hit]), pa.array(c[hit]), pa.array((low[hit] - reach).astype(np.int32)), pa.array((high[hit] - reach + length).astype(np.int32))], ["h", "c", "lo", "hi"])

        for batch in batches:
            for row in zip(*(batch.column(k).to_pylist() for k in ("g", "h", "c", "x", "left")), strict=True):
                if len(rows) >= GROUP and row[0] != rows[-1][0]:
                    yield done()
                    rows = []
                rows.append(row)
        if rows:
            yield done()

    return contexts.select("g", "h", "c", "x", "left").mapInArrow(run, "h long, c long, lo int, hi int")


def _cut_contexts(texts: DataFrame, length: int, gram: int) -> DataFrame:
    """``texts(z, wanted array<struct<h, c, place, large>>)`` to contexts. Those of a large collection
    go into smaller ones: a repeated string holds half of its bytes beside the gram on one side at
    least, so it is found among contexts that are alike on that side."""
    reach = length - gram
    side = -(-reach // 2)
    names = ["g", "h", "c", "x", "left"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        un = zstandard.ZstdDecompressor()
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int32()]
        for batch in batches:
            out: list[list] = [[], [], [], [], []]
            for z, wanted in zip(batch.column("z"), batch.column("wanted"), strict=True):
                text = un.decompress(z.as_py())
                for w in wanted.as_py():
                    at, short = divmod(w["place"], 256)
                    left = min(reach, at)
                    x = text[at - left : at + length - short]
                    collections = [w["h"]]
                    if w["large"]:
                        parts = [x[left - side : left] if left >= side else None, x[left + gram : left + gram + side] if len(x) >= left + gram + side else None]
                        collections = [int.from_bytes(hashlib.blake2b(b"%d|%d|" % (w["h"], k) + p, digest_size=8).digest(), "little", signed=True) for k, p in enumerate(parts) if p is not None]
                    for g in collections:
                        for column, value in zip(out, (g, w["h"], w["c"], x, left), strict=True):
                            column.append(value)
                if len(out[0]) >= 20_000:
                    yield pa.RecordBatch.from_arrays([pa.array(o, k) for o, k in zip(out, kinds, strict=True)], names)
                    out = [[], [], [], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(o, k) for o, k in zip(out, kinds, strict=True)], names)

    return texts.select("z", "wanted").mapInArrow(run, "g long, h long, c long, x binary, left int")


def repeated_spans(texts: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """``texts(row, doc_id, z)`` with stretches (s, e), maybe overlapping, that cover exactly the
    bytes of each row's repeated strings. A context that stands at a thousandth of all shared places
    or more is one of at most a thousand, which every task knows; the others are joined."""
    reach = length - gram
    every = anchor_rows(texts, length)
    known = stored(every.groupBy("h").agg(F.count("*").alias("n"), F.min("c").alias("c1"), F.max("c").alias("c2")).where("n > 1").select("h", (F.col("c1") == F.col("c2")).alias("alike")))
    shared = stored(every.join(known, "h"))
    pos = F.shiftright("place", 8)
    start, end = F.greatest(F.lit(0), pos - reach), pos + length - F.col("place").bitwiseAND(F.lit(255))
    alike = shared.where("alike").select("row", start.alias("s"), end.alias("e"))
    mixed = shared.where("not alike")
    classes = stored(mixed.groupBy("h", "c").agg(F.count("*").alias("n"), F.min(F.struct("row", "place")).alias("at")))
    frequent = classes.where(F.col("n") > F.greatest(F.lit(1), F.lit(mixed.count() // FREQUENT))).select("h", "c")  # fewer than FREQUENT rows
    marked = mixed.join(F.broadcast(frequent.withColumn("__all", F.lit(True))), ["h", "c"], "left")
    whole = marked.where("__all").select("row", start.alias("s"), end.alias("e"))
    rest = marked.where("__all is null").select(*mixed.columns)
    large = stored(classes.groupBy("h").agg(F.count("*").alias("__n")).where(F.col("__n") > LARGE).select("h", F.lit(True).alias("large")))
    several_large = large.count()  # few, and sent to every task if they are; most often there is none
    sized = classes.join(F.broadcast(large) if several_large <= LARGE else large, "h", "left") if several_large else classes.withColumn("large", F.lit(None).cast("boolean"))
    sized = sized.withColumn("large", F.coalesce("large", F.lit(False)))
    wanted = sized.groupBy(F.col("at.row").alias("row")).agg(F.collect_list(F.struct("h", "c", F.col("at.place").alias("place"), "large")).alias("wanted"))
    contexts = _cut_contexts(texts.select("row", "z").join(wanted, "row"), length, gram).repartition("g").sortWithinPartitions("g", "c")
    found = repeated_contexts(contexts, length, gram)
    # a context that stands at several places is repeated whole; the others where the construction says so
    several = classes.where("n > 1").select("h", "c", F.lit(-reach).alias("lo"), F.lit(length).alias("hi"))
    covered = found.unionByName(several).groupBy("h", "c").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    unlike = rest.join(covered, ["h", "c"]).select("row", F.greatest(F.lit(0), pos + F.col("lo")).alias("s"), F.least(end, pos + F.col("hi")).alias("e"))
    by_doc = alike.unionByName(whole).unionByName(unlike).groupBy("row").agg(F.collect_list(F.struct("s", "e")).alias("spans"))
    return texts.join(by_doc, "row", "left")


def remove_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """``docs(doc_id, text)`` to the digest of each document's remaining bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        un = zstandard.ZstdDecompressor()
        for batch in batches:
            n_bytes, n_removed, n_spans, sha = [], [], [], []
            for z, spans in zip(batch.column("z"), batch.column("spans"), strict=True):
                text = un.decompress(z.as_py())
                runs: list[list[int]] = []
                for x in sorted((x["s"], x["e"]) for x in spans.as_py() or ()):
                    if runs and x[0] <= runs[-1][1]:
                        runs[-1][1] = max(runs[-1][1], x[1])
                    else:
                        runs.append([*x])
                digest, at = hashlib.sha256(), 0
                for s, e in runs:
                    digest.update(text[at:s])
                    at = e
                digest.update(text[at:])
                n_bytes.append(len(text))
                n_removed.append(sum(e - s for s, e in runs))
                n_spans.append(len(runs))
                sha.append(digest.hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n_bytes, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(sha, pa.string())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return repeated_spans(numbered_texts(docs), length).select("doc_id", "z", "spans").mapInArrow(run, f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
