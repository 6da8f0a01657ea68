"""Best-fit packing of token sequences by a configuration program.

The histogram of piece lengths (at most ``size`` counts) is all that reaches the driver.
A covering program over configurations (multisets of lengths that fit a sequence) starts from
a fractional solution that covers every length exactly: the largest length left, with what
fills its sequence best, as often as all of these last. However near that is to a lower bound
(volume, pieces above half a sequence, or prices), multiplicative weights go on from it: scarce
lengths get high prices, a knapsack over the capacity finds the dearest configuration, and its
lengths get cheaper, until nothing has got better for ROUNDS rounds. What the weights found is
also taken first and the rest covered as at the start. The best solution is rounded down, the
rest is packed by a knapsack with lengths as prices and no piece more than there is. Each piece
finds its place by its rank among the pieces of its length, counted in buckets, so no length is
a group that one task must hold.

Token ids: the text is cut into the tokenizer's pre-tokens on its bytes, each distinct
pre-token is encoded once by the tokenizer and kept for the task.

A null or empty text is the single id 0. Repeated rows are packed each for itself; an empty
table gives no rows; other columns are not looked at."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import cache
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from recblock.llm import textkernel as K
from recblock.session import cut

#: ROUNDS: so many rounds without a better solution or bound, and the weights stop.
SIZE, VOCABULARY, ROUNDS = 2048, "byte_bpe_50k.json", 300
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
BUCKET_ROWS = 50_000
KEPT = 1_000_000  # distinct pre-tokens that a worker remembers


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


@cache
def _classes() -> np.ndarray:
    """Of each code point: 0 other, 1 letter, 2 number, 3 white space, by the pattern's classes."""
    import regex

    points = np.arange(0x110000, dtype="<u4")
    every = np.delete(points, slice(0xD800, 0xE000)).tobytes().decode("utf-32-le")
    out = np.zeros(0x110000, np.uint8)
    for k, pattern in ((1, r"\p{L}+"), (2, r"\p{N}+"), (3, r"\s+")):
        for m in regex.finditer(pattern, every):
            a, b = m.span()
            for x in ((a, min(b, 0xD800)), (max(a, 0xD800), b)) if a < 0xD800 < b else ((a, b),):
                shift = 0x800 if x[0] >= 0xD800 else 0
                out[x[0] + shift : x[1] + shift] = k
    return out


@cache
def _alphabet() -> dict[int, str]:
    """The character that a byte-level model has for each byte: printable ones stand for
    themselves, the others for the code points from 256 on, in turn."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    others = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(others)}


def _pretoken_starts(codes: np.ndarray, edge: np.ndarray) -> np.ndarray:
    """Where pre-tokens begin. codes: code points of all texts; edge: bool, n + 1, where a text begins."""
    n = len(codes)
    kind = _classes()[codes]
    change = np.ones(n, bool)
    change[1:] = (kind[1:] != kind[:-1]) | edge[1:n]
    starts = change.copy()
    run = np.cumsum(change) - 1
    first = np.flatnonzero(change)
    last = np.append(first[1:], n)
    white = kind == 3
    # the last white-space character of a run that something follows stands apart; a blank goes on into what follows
    tails = last[white[first] & ~edge[last]] - 1
    starts[tails] = True
    blank = tails[codes[tails] == 32]
    starts[blank + 1] = False
    # contractions: an apostrophe where a pre-token begins, or an apostrophe alone, with its letters
    quotes = np.flatnonzero(codes == 39)
    for q in quotes[starts[quotes]]:
        if q + 1 < n and kind[q + 1] == 1 and not edge[q + 1]:
            for tail in ("re", "ve", "ll", "s", "t", "m", "d"):
                e = q + 1 + len(tail)
                if e <= last[run[q + 1]] and all(codes[q + 1 + i] == ord(c) for i, c in enumerate(tail)):
                    starts[q + 1] = False
                    if e < n:
                        starts[e] = True
                        if e == last[run[q + 1]] and codes[e] == 32 and kind[e] == 3:
                            starts[e] = True
                    break
    return starts


class Encoder:
    """Ids of many texts at once; distinct pre-tokens are encoded once by the tokenizer."""

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.reset()

    def reset(self) -> None:
        self.hashes = np.zeros(0, np.uint64)  # of pre-tokens, sorted, and the slot of each
        self.slots = np.zeros(0, np.int32)
        self.ids = np.zeros(1 << 16, np.uint32)
        self.at = np.zeros(1 << 16, np.int64)
        self.used = 0

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """The slot of each hash, -1 if it is unknown."""
        if not len(self.hashes):
            return np.full(len(hashes), -1)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return np.where(self.hashes[at] == hashes, self.slots[at], -1)

    def learn(self, hashes: np.ndarray, tokens: list[str]) -> None:
        """hashes: sorted, none of them known. tokens: their pre-tokens in the alphabet of the
        tokenizer's model, which cuts them."""
        got = [[t.id for t in self.model.tokenize(x)] for x in tokens]
        flat, counts = np.fromiter(chain.from_iterable(got), np.uint32), [len(x) for x in got]
        n = len(self.hashes)
        while n + len(tokens) + 1 > len(self.at):
            self.at = np.append(self.at, np.zeros_like(self.at))
        while self.used + len(flat) > len(self.ids):
            self.ids = np.append(self.ids, np.zeros_like(self.ids))
        self.ids[self.used : self.used + len(flat)] = flat
        self.at[n + 1 : n + 1 + len(tokens)] = self.used + np.cumsum(counts)
        self.used += len(flat)
        to = np.searchsorted(self.hashes, hashes)
        self.hashes = np.insert(self.hashes, to, hashes)
        self.slots = np.insert(self.slots, to, np.arange(n, n + len(tokens), dtype=np.int32))

    def encode(self, data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """ids of the texts one after the other, and where each begins (n + 1)."""
        if not len(data):
            return np.zeros(0, np.uint32), np.zeros(len(offs), np.int64)
        raw = data.tobytes()
        if any(s.encode() in raw for s in self.special):  # such a text goes whole to the tokenizer
            got = [self.tokenizer.encode(raw[a:b].decode(), add_special_tokens=False).ids for a, b in zip(offs[:-1], offs[1:], strict=True)]
            return np.fromiter(chain.from_iterable(got), np.uint32), np.append(0, np.cumsum([len(x) for x in got]))
        if len(self.hashes) > KEPT:
            self.reset()
        head = np.flatnonzero((data & 0xC0) != 0x80)  # first bytes of code points
        codes = np.frombuffer(raw.decode().encode("utf-32-le"), np.uint32)
        edge = np.zeros(len(codes) + 1, bool)
        edge[np.searchsorted(head, offs)] = True
        begin = head[_pretoken_starts(codes, edge)]
        end = np.append(begin[1:], len(data))
        hashes, where, back = np.unique(K.span_hash(K.prefix_hash(data), begin, end), return_index=True, return_inverse=True)
        known = self.find(hashes)
        new = np.flatnonzero(known < 0)
        if len(new):
            letters = raw.decode("latin-1").translate(_alphabet())
            self.learn(hashes[new], [letters[x:y] for x, y in zip(begin[where[new]].tolist(), end[where[new]].tolist(), strict=True)])
            known = self.find(hashes)
        slots = known[back]
        start, length = self.at[slots], self.at[slots + 1] - self.at[slots]
        to = np.cumsum(length)
        pick = np.arange(to[-1]) + np.repeat(start - (to - length), length)
        return self.ids[pick], np.append(0, to)[np.searchsorted(begin, offs)]


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def token_pieces(docs: DataFrame, size: int = SIZE, vocabulary: str = VOCABULARY, with_ids: bool = False) -> DataFrame:
    """Each document's ids, 0 at their end, in pieces of ``size``, the first with what is over;
    one row per piece, with the ids themselves if ``with_ids``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(vocabulary_path(vocabulary))
        for batch in batches:
            for a, b, data, offs in K.chunks(batch.column(1), K.SLICE):
                ids, at = enc.encode(data, offs)
                out: list[list] = [[], [], [], [], [], []]
                for i, doc in enumerate(batch.column(0).slice(a, b - a).to_pylist()):
                    own = np.append(ids[at[i] : at[i + 1]], 0).astype("<u4")
                    cuts = [0, *range(len(own) % size or min(size, len(own)), len(own) + 1, size)]
                    for k, (s, e) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                        for column, value in zip(out, (doc, k, s, e - s, zlib.crc32(own[s:e].tobytes()), own[s:e] if with_ids else None), strict=True):
                            column.append(value)
                kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64())]
                n = 6 if with_ids else 5
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out[:n], kinds, strict=False)], ["doc_id", "piece", "start", "length", "ids_crc32", "ids"][:n])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, PIECES + (", ids array<long>" if with_ids else ""))


def dearest(price: np.ndarray, size: int) -> tuple[np.ndarray, float]:
    """The configuration of lengths 1..size of greatest total price; lengths at price 0 are left out.
    Only lengths up to half a sequence can stand in it beside each other; one above that, once."""
    best, take = np.zeros(size + 1), np.zeros(size + 1, np.int64)
    items = np.flatnonzero(price[: size // 2 + 1] > 0)
    value, upto = price[items], np.searchsorted(items, np.arange(size + 1), "right")
    for c in range(1, size + 1):
        best[c] = best[c - 1]
        if k := upto[c]:
            gain = best[c - items[:k]] + value[:k]
            i = int(np.argmax(gain))
            if gain[i] > best[c]:
                best[c], take[c] = gain[i], items[i]
    out, c, most = np.zeros(size + 1, np.int64), size, float(best[size])
    large = np.flatnonzero(price > 0)
    large = large[large > size // 2]
    if len(large) and (gain := best[size - large] + price[large]).max() > most:
        top = int(large[gain.argmax()])
        out[top], c, most = 1, size - top, float(gain.max())
    while c > 0:
        if take[c]:
            out[take[c]] += 1
            c -= take[c]
        else:
            c -= 1
    return out, most


def lower_bound(histogram: dict[int, int], size: int = SIZE) -> int:
    """Sequences that any packing needs: by volume, and by pieces that share none."""
    return max(-(-sum(k * n for k, n in histogram.items()) // size), sum(n for k, n in histogram.items() if 2 * k > size))


def _covering(left: np.ndarray, size: int, used: dict[bytes, tuple[np.ndarray, float]] | None = None) -> dict[bytes, tuple[np.ndarray, float]]:
    """Configurations with how often each is taken, beside those ``used``, so that all that is left is
    covered: the largest length with what fills its sequence best, as often as all of these last."""
    used = dict(used or {})
    while (left > 0).any():
        config = _fullest(left, size)
        on = config > 0
        much = float((left[on] / config[on]).min())
        left[on] -= config[on] * much
        left[left < 1e-9] = 0.0
        used[config.tobytes()] = (config, used.get(config.tobytes(), (config, 0.0))[1] + much)
    return used


def fractional(need: np.ndarray, size: int, rounds: int = ROUNDS) -> tuple[list[tuple[np.ndarray, float]], float, float]:
    """Configurations with how often each is taken, so that every length is covered; their
    total, and a lower bound of any such total."""
    live = need > 0
    low = float(lower_bound({int(k): int(need[k]) for k in np.flatnonzero(live)}, size))
    used = _covering(need.astype(float), size)
    start = dict(used)
    total = sum(x for _, x in used.values())
    best, least = list(used.values()), total
    covered = np.ones(size + 1)  # how often each length is covered by what is used
    weight, step, idle = live.astype(float), 0.5, 0
    while idle < rounds:  # a start near the bound is no reason to stop
        config, value = dearest(np.where(live, weight / np.maximum(need, 1), 0.0), size)
        bound = float(weight.sum() / value)
        cover = config / np.maximum(need, 1)
        much = 1 / cover.max()  # the length that it covers fastest is covered once
        used[config.tobytes()] = (config, used.get(config.tobytes(), (config, 0.0))[1] + much)
        covered, total = covered + much * cover, total + much
        idle += 1
        scale = float(covered[live].min())
        if total / scale < least * 0.999 or bound > low * 1.001:
            idle = 0
        if total / scale < least:
            best, least = [(c, x / scale) for c, x in used.values()], total / scale
        low = max(low, bound)
        weight = weight * np.exp(-step * much * cover)
        weight /= weight.max()
    found = {key: (c, x - start.get(key, (c, 0.0))[1]) for key, (c, x) in used.items()}
    first, left = {}, need.astype(float)
    for key, (config, x) in sorted(found.items(), key=lambda v: (-v[1][1], v[0])):
        on = config > 0
        much = min(x, float((left[on] / config[on]).min()))
        if much > 0:
            left[on] -= config[on] * much
            left[left < 1e-9] = 0.0
            first[key] = (config, much)
    mixed = _covering(left, size, first)
    if (total := sum(x for _, x in mixed.values())) < least:
        best, least = list(mixed.values()), total
    return best, least, low


def configurations(histogram: dict[int, int], size: int = SIZE, rounds: int = ROUNDS) -> list[tuple[dict[int, int], int]]:
    """(configuration, times) that together hold every piece of the histogram exactly once."""
    need = np.zeros(size + 1, np.int64)
    for length, count in histogram.items():
        need[length] = count
    if not need.any():
        return []
    solution = fractional(need, size, rounds)[0]
    plans = []
    for start in (solution, []):  # rounded, or whole sequences from the beginning, whichever are fewer
        left, plan = need.copy(), []
        for config, x in sorted(start, key=lambda v: (-v[1], v[0].tobytes())):
            on = config > 0
            times = min(int(x + 1e-9), int((left[on] // config[on]).min()))
            if times > 0:
                plan.append((config, times))
                left = left - config * times
        while (left > 0).any():
            config = _fullest(left, size)
            on = config > 0
            times = int((left[on] // config[on]).min())
            plan.append((config, times))
            left = left - config * times
        plans.append(plan)
    plan = min(plans, key=lambda p: sum(t for _, t in p))
    return [({int(k): int(c[k]) for k in np.flatnonzero(c)}, t) for c, t in plan]


def _fullest(left: np.ndarray, size: int) -> np.ndarray:
    """The largest length that is left, with what fills the rest of the sequence best: a knapsack
    with lengths as prices, each taken no more often than it is left (a part of a piece counts
    as one). Bits of an integer are the sums that can be reached."""
    out = np.zeros(size + 1, np.int64)
    top = int(np.flatnonzero(left > 0)[-1])
    out[top] += 1
    room = size - top
    items, reach, every = [], [1], (1 << room + 1) - 1
    fits = np.flatnonzero(left[: room + 1] > 0)[::-1]
    counts = np.ceil(left[fits]).astype(np.int64) - (fits == top)
    for length, n in zip(fits.tolist(), np.minimum(counts, room // fits).tolist(), strict=True):
        part = 1
        while n > 0 and not reach[-1] >> room & 1:  # 1, 2, 4 ... times, and what is over
            k = min(part, n)
            items.append((length, k))
            reach.append((reach[-1] | reach[-1] << length * k) & every)
            n, part = n - k, part * 2
        if reach[-1] >> room & 1:
            break
    at = reach[-1].bit_length() - 1
    for i in range(len(items) - 1, -1, -1):
        if not reach[i] >> at & 1:
            length, k = items[i]
            out[length] += k
            at -= length * k
    return out


def pack(pieces: DataFrame, size: int = SIZE, rounds: int = ROUNDS, buckets: int = 64) -> DataFrame:
    """Adds ``sequence_id`` and ``offset`` to rows with doc_id, piece and length; at least ``buckets``
    buckets of a length, and more for a larger table, so that a window holds a bounded number of rows."""
    buckets = max(buckets, -(-pieces.count() // BUCKET_ROWS))
    counted = pieces.withColumn("__bucket", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(buckets)).cast("int"))
    tally = cut(counted.groupBy("length", "__bucket").agg(F.count("*").alias("__n")))
    histogram = {r[0]: r[1] for r in tally.groupBy("length").agg(F.sum("__n")).collect()}  # one row per length, at most ``size``
    spots: dict[int, list[tuple[int, int, int, int]]] = {}
    base = 0
    filled: dict[int, int] = {}
    for config, times in configurations(histogram, size, rounds):
        offset = 0
        for length, each in sorted(config.items(), reverse=True):
            spots.setdefault(length, []).append((filled.get(length, 0), each, base, offset))
            filled[length] = filled.get(length, 0) + each * times
            offset += length * each
        base += times
    table = {k: np.array(v, np.int64) for k, v in spots.items()}  # bounded by lengths and configurations
    before = Window.partitionBy("length").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = tally.select("length", "__bucket", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__before"))
    inside = Window.partitionBy("length", "__bucket").orderBy("doc_id", "piece", "ids_crc32")
    ranked = counted.join(offsets, ["length", "__bucket"]).withColumn("__rank", F.col("__before") + F.row_number().over(inside) - 1)
    columns = pieces.columns
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema.fields)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = batch.column("length").to_numpy(), batch.column("__rank").to_numpy()
            seq, off = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for k in np.unique(length):
                own, spot = np.flatnonzero(length == k), table[int(k)]
                row = spot[np.searchsorted(spot[:, 0], rank[own], "right") - 1]
                inside = rank[own] - row[:, 0]
                seq[own], off[own] = row[:, 2] + inside // row[:, 1], row[:, 3] + inside % row[:, 1] * k
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in columns], pa.array(seq), pa.array(off)], [*columns, "sequence_id", "offset"])

    return ranked.select(*columns, "__rank").mapInArrow(place, f"{kinds}, sequence_id long, offset long")


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def pack_documents(docs: DataFrame, size: int = SIZE, vocabulary: str = VOCABULARY) -> DataFrame:
    """``docs(doc_id, text)`` to one row per piece with its sequence and place."""
    return pack(cut(token_pieces(docs.select("doc_id", "text"), size, vocabulary)), size)
