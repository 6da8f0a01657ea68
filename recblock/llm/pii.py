"""Personal data by bootstrapped contextual extraction.

Seeds are what the strict patterns find (addresses, ips, cards, phones) and secrets that their
form alone gives away. The words before a seed are a lexical pattern; every identifier-like run
of the corpus, seed or not, hangs on the pattern it stands after, once for each kind that its
shape admits: loose addresses, groups of numbers, long words with digits. The graph of patterns
and instances is scored in turns: a pattern is as good as its instances, smoothed so that rare
patterns stay low; an instance as good as the best of its patterns and its own seed value. A
seed of one kind of number speaks against the other kinds of number after its pattern.
Every seed is a span. Runs after patterns of high confidence become spans of the pattern's
kind, of the most confident one if there are several.

Offsets count code points of whole texts, ends exclusive. A null text is empty. Repeated rows
are searched each for itself, an empty table gives no rows, other columns are not looked at."""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from recblock.llm import textkernel as K
from recblock.session import cut

#: The base patterns, in the order in which kinds are listed.
EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
#: The same places: a match takes its digits to their end, so the next one begins a run of digits.
IP_AT_RUN = re.compile(r"(?<![0-9])" + IP.pattern)
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
KINDS = ("email", "ip", "card", "phone", "secret")
RUN = re.compile(r"[A-Za-z0-9_]{12,}")
HEX = re.compile(r"(?=[0-9a-f]*[a-f])(?=[0-9a-f]*[0-9])[0-9a-f]{32,64}")
#: Looser runs, spans only after a good pattern: numbers with any usual separators, four groups
#: or hexadecimal groups for ips, and what stands around an @ however it is written.
NUMBER = re.compile(r"(?<!\w)\+?\(?[0-9](?:[\x20().\-/]{0,3}[0-9]){6,}(?!\w)")
DIGITS = re.compile(r"[0-9]+")
GROUPS = re.compile(r"(?<![\w.])[0-9]{1,3}(?:(?:\x20?[.,:_-]\x20?|[\[(]\.[\])])[0-9]{1,3}){3}(?!\w)|(?<![\w:])(?:[0-9A-Fa-f]{0,4}:){3,7}[0-9A-Fa-f]{1,4}(?!\w)")
AT = re.compile(r"\x20?(?:@|[(\[{]\x20?[Aa][Tt]\x20?[)\]}])\x20?")
PART = re.compile(r"""[^\s@<>()\[\]{}"',;:|]+""")
NUMBERS = KINDS[1:4]
CONTEXT = re.compile(r"\w+|[^\w\s]")
SMOOTH, CONFIDENT, TURNS, SUPPORT = 2.0, 0.8, 3, 5
LOCAL = re.compile(r"[A-Za-z0-9._%+-]")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if k % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def _emails(text: str) -> list[tuple[int, int]]:
    """As finditer would, but it looks at the surroundings of each @ only: a match has its first
    @ right after a run of local characters, which begins after the last match."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and LOCAL.match(text[start - 1]):
            start -= 1
        m = EMAIL.match(text, start) if start < at else None
        if m:
            out.append(m.span())
            free = m.end()
        at = text.find("@", max(at + 1, free))
    return out


def base_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    """Spans of the four base kinds; matches that fail their check are dropped."""
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS[:4]}
    if "@" in text:
        out["email"] = _emails(text)
    for m in CARD.finditer(text):
        digits = m.group().replace(" ", "").replace("-", "")
        if 13 <= len(digits) <= 19 and luhn(digits):
            out["card"].append(m.span())
    if "." in text:
        out["ip"] = [m.span() for m in IP_AT_RUN.finditer(text) if all(int(p) <= 255 for p in m.group().split(".") if len(p.lstrip("0")) <= 3) and all(len(p.lstrip("0")) <= 3 for p in m.group().split("."))]
    if "+" in text:
        out["phone"] = [m.span() for m in PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m.group()) <= 15]
    return out


def covered(spans: list[tuple[int, int]]) -> tuple[list[int], list[int]]:
    """Starts and ends of the spans' union, in order."""
    starts: list[int] = []
    ends: list[int] = []
    for s, e in sorted(spans):
        if ends and s <= ends[-1]:
            ends[-1] = max(ends[-1], e)
        else:
            starts.append(s)
            ends.append(e)
    return starts, ends


def overlaps(union: tuple[list[int], list[int]], s: int, e: int) -> bool:
    k = bisect_left(union[0], e)
    return k > 0 and union[1][k - 1] > s


def pattern_before(text: str, start: int) -> str:
    """The last three words or signs before a place, in lower case; each of them whole."""
    width = 64
    while True:
        begin = max(0, start - width)
        found = CONTEXT.findall(text[begin:start])
        if begin == 0 or len(found) > 3:
            return " ".join(found[-3:]).lower()
        width *= 4


def _addresses(text: str) -> list[tuple[int, int]]:
    """What stands around each @, or at in brackets, without a full stop at its end."""
    out, free = [], 0
    for m in AT.finditer(text):
        start = m.start()
        while start > free and PART.match(text[start - 1]):
            start -= 1
        tail = PART.match(text, m.end())
        end = m.end() + len(tail.group().rstrip(".!?")) if tail else m.end()
        if start < m.start() and end > m.end():
            out.append((start, end))
        free = max(m.end(), end)
    return out


def loose_runs(text: str) -> list[tuple[int, int, tuple[str, ...]]]:
    """Spans that may be personal data and the kinds that their shape admits. Numbers that
    stand too close together to be one are taken each for itself."""
    out = [(s, e, KINDS[:1]) for s, e in _addresses(text)]
    out += [(*m.span(), KINDS[1:2]) for m in GROUPS.finditer(text)]
    for m in NUMBER.finditer(text):
        n = sum(c.isdigit() for c in m.group())
        for s, e in [m.span()] if n <= 19 else [x.span() for x in DIGITS.finditer(text, *m.span())]:
            n = sum(c.isdigit() for c in text[s:e])
            kinds = tuple(k for k, least, most in ((KINDS[2], 12, 19), (KINDS[3], 7, 15)) if least <= n <= most)
            if kinds:
                out.append((s, e, kinds))
    return out


def _instance(kind: str, run: str) -> int:
    """Numbers are the same however their digits are separated."""
    return _digest(("." if kind == KINDS[1] else "").join(DIGITS.findall(run)) if kind in NUMBERS and ":" not in run else run)


def _digest(text: str) -> int:
    return int.from_bytes(hashlib.blake2b(text.encode(), digest_size=8).digest(), "little", signed=True)


def occurrences(docs: DataFrame) -> DataFrame:
    """doc_id, a digest of the text, the base spans, and all runs with their kinds, pattern and
    seed value: 1 for a seed of the kind, -1 for a seed of another, 0 for what is open."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    mention = pa.struct([("s", pa.int32()), ("e", pa.int32()), ("kind", pa.string()), ("pattern", pa.string()), ("instance", pa.int64()), ("seed", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in K.parts(whole, 1)):
            counts: dict[str, list[int]] = {k: [] for k in KINDS[:4]}
            shas, spans, mentions = [], [], []
            for scalar in batch.column(1):
                text = scalar.as_py() or ""
                base = base_spans(text)
                listed = ",".join(f"{k}:{s}:{e}" for k in KINDS[:4] for s, e in base[k])
                own = []
                for k in KINDS[:4]:
                    counts[k].append(len(base[k]))
                    for s, e in base[k]:
                        pattern = pattern_before(text, s)
                        own += [{"s": s, "e": e, "kind": x, "pattern": pattern, "instance": _instance(x, text[s:e]), "seed": 1 if x == k else -1} for x in (NUMBERS if k in NUMBERS else (k,))]
                taken = covered([x for k in KINDS[:4] for x in base[k]])
                for m in RUN.finditer(text):
                    s, e = m.span()
                    seed = bool(HEX.fullmatch(m.group()))  # a number inside a secret does not take its place
                    if seed or (sum(c.isdigit() for c in m.group()) >= 4 and not overlaps(taken, s, e)):
                        own.append({"s": s, "e": e, "kind": "secret", "pattern": pattern_before(text, s), "instance": _digest(m.group()), "seed": int(seed)})
                for s, e, kinds in loose_runs(text):
                    if not overlaps(taken, s, e):
                        pattern = pattern_before(text, s)
                        own += [{"s": s, "e": e, "kind": k, "pattern": pattern, "instance": _instance(k, text[s:e]), "seed": 0} for k in kinds]
                shas.append(hashlib.sha256(listed.encode()).hexdigest())
                spans.append(listed)
                mentions.append(own)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(2), *[pa.array(counts[k], pa.int64()) for k in KINDS[:4]], pa.array(shas), pa.array(spans), pa.array(mentions, pa.list_(mention))],
                ["doc_id", "text_hash", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "base_spans", "mentions"],
            )

    text = F.col("text").cast("string")
    return docs.select("doc_id", text.alias("text"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("text_hash")).mapInArrow(
        run, f"doc_id {kind}, text_hash long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, base_spans string, mentions array<struct<s:int,e:int,kind:string,pattern:string,instance:long,seed:int>>"
    )


def pattern_scores(mentions: DataFrame, turns: int = TURNS) -> DataFrame:
    """``mentions(kind, pattern, instance, seed)`` to (kind, pattern, confidence, support)."""
    edges = cut(mentions.where("pattern <> ''").groupBy("kind", "pattern", "instance").agg(F.max(F.col("seed").cast("double")).alias("seed")))
    scored = edges.withColumn("value", F.greatest("seed", F.lit(0.0)))
    for turn in range(turns):
        patterns = scored.groupBy("kind", "pattern").agg((F.sum("value") / (F.count("*") + SMOOTH)).alias("confidence"), F.sum((F.col("seed") > 0).cast("long")).alias("support"))
        if turn < turns - 1:
            best = edges.join(patterns, ["kind", "pattern"]).groupBy("kind", "instance").agg(F.max("confidence").alias("by_pattern"))
            value = F.when(F.col("seed") < 0, 0.0).otherwise(F.greatest("seed", F.col("by_pattern")))
            scored = edges.join(best, ["kind", "instance"]).select("kind", "pattern", "instance", "seed", value.alias("value"))
    return patterns


def extract(docs: DataFrame, confident: float = CONFIDENT, support: int = SUPPORT) -> DataFrame:
    """``docs(doc_id, text)`` to the base columns and ``spans`` with what the patterns add."""
    found = cut(occurrences(docs))
    mentions = found.select("doc_id", "text_hash", F.explode("mentions").alias("m")).select("doc_id", "text_hash", "m.*")
    good = pattern_scores(mentions).where((F.col("confidence") >= confident) & (F.col("support") >= support)).select("kind", "pattern", "confidence")
    seeds = mentions.where((F.col("kind") == KINDS[4]) & (F.col("seed") > 0)).withColumn("confidence", F.lit(1.0))
    runs = mentions.where("seed = 0").join(good, ["kind", "pattern"]).select(*seeds.columns)
    added = seeds.unionByName(runs).groupBy("doc_id", "text_hash", "s", "e").agg(F.max(F.struct("confidence", "kind"))["kind"].alias("kind"))
    spans: Column = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("s", "e", "kind"))), lambda x: F.concat_ws(":", x["kind"], x["s"], x["e"])), ",")
    by_doc = added.groupBy(F.col("doc_id").alias("__id"), F.col("text_hash").alias("__hash")).agg(spans.alias("__more"))
    both = found.join(by_doc, found["doc_id"].eqNullSafe(F.col("__id")) & (found["text_hash"] == F.col("__hash")), "left")
    everything = F.concat_ws(",", F.when(F.col("base_spans") != "", F.col("base_spans")), F.col("__more"))
    return both.select("doc_id", "text_hash", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", everything.alias("spans"))


def masked(docs: DataFrame) -> DataFrame:
    """``docs`` with every span of a text replaced by its kind in brackets; n_chars follows."""
    spans = extract(docs.select("doc_id", "text")).where("spans <> ''").select(F.col("doc_id").alias("__id"), F.col("text_hash").alias("__hash"), F.col("spans").alias("__spans")).dropDuplicates(["__id", "__hash"])
    names, schema = docs.columns, docs.schema
    rows = docs.select(F.struct(*names).alias("__row"), F.xxhash64(F.coalesce(F.col("text"), F.lit(""))).alias("__h"))
    both = rows.join(spans, rows["__row"]["doc_id"].eqNullSafe(spans["__id"]) & (F.col("__h") == F.col("__hash")), "left").select("__row.*", "__spans")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in K.parts(whole, "text")):
            texts = batch.column("text").to_pylist()
            for i, listed in enumerate(batch.column(batch.num_columns - 1).to_pylist()):
                if listed:
                    out, at = [], 0
                    for s, e, k in sorted((int(x[1]), int(x[2]), x[0]) for x in (y.split(":") for y in listed.split(","))):
                        if s >= at:
                            out += [texts[i][at:s], f"[{k.upper()}]"]
                        at = max(at, e)
                    texts[i] = "".join([*out, texts[i][at:]])
            columns = dict(zip(names, batch.columns, strict=False)) | {"text": pa.array(texts, pa.string())}
            if "n_chars" in columns:
                columns["n_chars"] = pa.array([None if t is None else len(t) for t in texts], pa.int64()).cast(batch.column("n_chars").type)
            yield pa.RecordBatch.from_arrays([columns[c] for c in names], names)

    return both.mapInArrow(run, schema)


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")).drop("text_hash")
