"""Near duplicates by a chosen-path similarity join on word shingles.

Documents with equal shingle sets are one class first. Every tree then branches the classes
by the shingle that is least under the tree's hash of that level: classes that chose the same
one share a node. Nodes of one class end; small nodes are compared exhaustively on full sets;
large ones branch again by the next level's choice. A node that is still large after the last
level is cut into blocks, and each pair of blocks is a node, so nothing is left out. Trees are
repeated until a link at the threshold is missed with a chance of at most MISS even where all
levels must choose alike (``trees_for``); where the first level ends, as for most, the chance is
many times smaller. Equal nodes of several trees are compared once.

Inside a node, similarity is the share of common shingles, whose complement is a metric: after
each class is compared with the node's leaders, only pairs that the triangle inequality allows
are compared further, which finds the components of all links without all pairs.

Texts without words, and nulls, have no shingles, link with nothing and stay. Ids may repeat or
be null: a class is a set of shingles, whoever bears it. A component's id is its least id, null if
all of its rows are without one. An empty table gives no rows."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from recblock.llm import textkernel as K
from recblock.operators.graph import connected_components
from recblock.session import cut

WORDS, PERCENT, LEVELS, MISS = 5, 85, 3, 1e-4
SMALL, LARGEST = 512, 1024
_ODD = K.mixed(np.arange(1, 1001, dtype=np.uint64) * np.uint64(0xD1B54A32D192ED03)) | np.uint64(1)


def shingles(data: np.ndarray, offs: np.ndarray, width: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each text, one after the other, and where each text's begin."""
    n = len(offs) - 1
    data = K.LOWER[data]
    start, end, doc = K.words(data, offs)
    if not len(start):
        return np.zeros(0, np.uint64), np.zeros(n + 1, np.int64)
    word = K.span_hash(K.prefix_hash(data), start, end)
    count = np.bincount(doc, minlength=n)
    first = np.append(0, np.cumsum(count))
    full = np.zeros(0, np.uint64)
    owner = np.zeros(0, np.int64)
    if len(word) >= width:
        whole = sum((word[i : len(word) - width + 1 + i] * _ODD[900 + i] for i in range(1, width)), word[: len(word) - width + 1] * _ODD[900])
        same = doc[: len(whole)] == doc[width - 1 :]
        full, owner = K.mixed(whole[same]), doc[: len(whole)][same]
    short = np.flatnonzero((count > 0) & (count < width))
    if len(short):
        own = [K.mixed((word[first[d] : first[d + 1]] * _ODD[920 : 920 + count[d]]).sum(keepdims=True) + np.uint64(count[d])) for d in short]
        full, owner = np.append(full, np.concatenate(own)), np.append(owner, short)
    order = np.lexsort((full, owner))
    full, owner = full[order], owner[order]
    keep = np.ones(len(full), bool)
    keep[1:] = (full[1:] != full[:-1]) | (owner[1:] != owner[:-1])
    full, owner = full[keep], owner[keep]
    return full, np.append(0, np.cumsum(np.bincount(owner, minlength=n)))


def trees_for(percent: int, levels: int = LEVELS, miss: float = MISS) -> int:
    """So many trees that a pair of this similarity is missed by all with at most the chance ``miss``."""
    found = (percent / 100) ** levels
    return 1 if found >= 1 else math.ceil(math.log(miss) / math.log(1 - found))


def signatures(docs: DataFrame, width: int, trees: int, levels: int) -> DataFrame:
    """row (a number), doc_id, text_hash, n_shingles, two digests of the set, and the least shingle of
    each tree and level."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, data, offs in K.chunks(batch.column(3), K.SLICE):
                full, at = shingles(data, offs, width)
                size = np.diff(at)
                some = np.flatnonzero(size)
                sums = np.zeros((2, b - a), np.int64)
                least = np.zeros((b - a, trees * levels), np.int64)
                if len(some):
                    heads = at[:-1][some]
                    sums[0, some] = np.add.reduceat(full, heads).view(np.int64)
                    sums[1, some] = np.add.reduceat(K.mixed(full ^ np.uint64(0x5851F42D4C957F2D)), heads).view(np.int64)
                    for k in range(trees * levels):
                        least[some, k] = np.minimum.reduceat(full * _ODD[k], heads).view(np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(b - a + 1, dtype=np.int32) * (trees * levels)), pa.array(least.ravel()))
                yield pa.RecordBatch.from_arrays([*(batch.column(k).slice(a, b - a) for k in range(3)), pa.array(size.astype(np.int64)), pa.array(sums[0]), pa.array(sums[1]), lists], ["row", "doc_id", "text_hash", "n_shingles", "s1", "s2", "least"])

    text = F.col("text").cast("string")
    return docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", F.xxhash64(text).alias("text_hash"), text.alias("text")).mapInArrow(run, f"row long, doc_id {kind}, text_hash long, n_shingles long, s1 long, s2 long, least array<long>")


def node_links(sets: list[np.ndarray], percent: int = PERCENT) -> list[tuple[int, int]]:
    """Links that join exactly the components of {100 * common >= percent * union}."""
    n = len(sets)
    size = np.array([len(s) for s in sets])
    if n == 2:
        common = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        return [(0, 1)] if 100 * common >= percent * (size.sum() - common) else []
    _, flat = np.unique(np.concatenate(sets), return_inverse=True)
    at = np.append(0, np.cumsum(size))
    mark = np.zeros(int(flat.max()) + 1, bool)

    def against(i: int) -> tuple[np.ndarray, np.ndarray]:
        own = flat[at[i] : at[i + 1]]
        mark[own] = True
        common = np.add.reduceat(mark[flat], at[:-1], dtype=np.int64)
        mark[own] = False
        union = size + size[i] - common
        return 100 * common >= percent * union, 1 - common / union

    root = list(range(n))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out: list[tuple[int, int]] = []

    def tie(i: int, j: int) -> None:
        a, b = find(i), find(j)
        if a != b:
            root[max(a, b)] = min(a, b)
            out.append((i, j))

    leader = np.full(n, -1)
    far: dict[int, np.ndarray] = {}
    for i in range(n):
        if leader[i] < 0:
            near, far[i] = against(i)
            for j in np.flatnonzero(near):
                tie(i, int(j))
            leader[near & (leader < 0)] = i
            leader[i] = i
    if len(far) == 1:
        return out
    slack = 1 - percent / 100 + 1e-9
    comp = np.array([find(i) for i in range(n)])
    for z in range(n):  # members that aren't leaders may link across
        if leader[z] == z:
            continue
        other = comp != find(z)
        for a, d in far.items():
            if not other.any():
                break
            other &= np.abs(d - d[z]) <= slack
        if other[z + 1 :].any():
            near, _ = against(z)
            for j in np.flatnonzero(near & other):
                tie(z, int(j))
            comp = np.array([find(i) for i in range(n)])
    return out


def _compared(members: DataFrame, width: int, percent: int) -> DataFrame:
    """``members(node, cls, z)`` to links (src, dst) of classes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        un = zstandard.ZstdDecompressor()
        rows: list[tuple[int, int, bytes]] = []
        held = 0

        def done(part: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
            sets: list[np.ndarray] = []
            texts: list[bytes] = []
            waiting = 0
            for k, (_, _, z) in enumerate(part):
                texts.append(un.decompress(z))
                waiting += len(texts[-1])
                if waiting > K.SLICE or k == len(part) - 1:
                    full, at = shingles(*K.buffers(pa.array(texts, pa.large_binary())), width)
                    sets += [full[x:y].copy() for x, y in zip(at[:-1], at[1:], strict=True)]
                    texts, waiting = [], 0
            src, dst, i = [], [], 0
            while i < len(part):
                j = i
                own: dict[int, np.ndarray] = {}
                while j < len(part) and part[j][0] == part[i][0]:
                    if len(sets[j]):
                        own.setdefault(part[j][1], sets[j])
                    j += 1
                if len(own) > 1:
                    ids = list(own)
                    for a, b in node_links(list(own.values()), percent):
                        src.append(ids[a])
                        dst.append(ids[b])
                i = j
            return pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], ["src", "dst"])

        for batch in batches:
            for node, doc, z in zip(*(batch.column(c).to_pylist() for c in ("node", "cls", "z")), strict=True):
                if held > 1_000_000 and node != rows[-1][0]:
                    yield done(rows)
                    rows, held = [], 0
                rows.append((node, doc, z))
                held += len(z)
        if rows:
            yield done(rows)

    return members.select("node", "cls", "z").mapInArrow(run, "src long, dst long")


def packed_texts(docs: DataFrame) -> DataFrame:
    """doc_id, the text's hash and the compressed text, which moves in the text's place."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tight = zstandard.ZstdCompressor(level=1)
        for batch in batches:
            for a, b, data, offs in K.chunks(batch.column(2)):
                raw = memoryview(data)
                z = [tight.compress(raw[x:y]) for x, y in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), pa.array(z, pa.binary())], ["doc_id", "text_hash", "z"])

    text = F.col("text").cast("string")
    return docs.select("doc_id", F.xxhash64(text).alias("text_hash"), text.alias("text")).mapInArrow(run, f"doc_id {kind}, text_hash long, z binary")


def _nodes(classes: DataFrame, trees: int, levels: int) -> DataFrame:
    """(node, cls) of all nodes with two classes or more, equal ones once."""
    path = F.slice("least", F.col("tree") * levels + 1, levels)
    live = classes.select("cls", "least", F.explode(F.sequence(F.lit(0), F.lit(trees - 1))).alias("tree")).select("cls", F.col("tree").cast("long").alias("node"), path.alias("path"))
    found = None
    for level in range(levels):
        keyed = live.select("cls", F.xxhash64("node", F.col("path")[level]).alias("node"), "path")
        shared = keyed.groupBy("node").agg(F.count("*").alias("n")).where("n > 1")
        now = cut(keyed.join(shared, "node"))
        small = now.where(F.col("n") <= SMALL).select("node", "cls")
        found = small if found is None else found.unionByName(small)
        live = now.where(F.col("n") > SMALL)
        if live.isEmpty():
            break
    else:
        blocks = F.when(F.col("n") <= LARGEST, 1).otherwise(F.ceil(F.col("n") / (LARGEST // 2))).cast("int")
        own = F.pmod(F.xxhash64("cls"), F.col("__blocks")).cast("int")
        cells = live.withColumn("__blocks", blocks).withColumn("__own", own).withColumn("__other", F.explode(F.sequence(F.lit(0), F.col("__blocks") - 1)))
        found = found.unionByName(cells.select(F.xxhash64("node", F.least("__own", "__other"), F.greatest("__own", "__other")).alias("node"), "cls"))
    members = cut(found.distinct())
    mark = members.groupBy("node").agg(F.count("*").alias("n"), F.sum(F.xxhash64("cls").cast("decimal(20,0)")).alias("a"), F.bit_xor(F.xxhash64("cls", F.lit(7))).alias("b"))
    once = mark.groupBy("n", "a", "b").agg(F.min("node").alias("node")).select("node")
    return members.join(once, "node", "left_semi")


def judged(docs: DataFrame, width: int = WORDS, percent: int = PERCENT, trees: int | None = None, levels: int = LEVELS) -> DataFrame:
    """``docs(doc_id, text)`` to doc_id, text_hash, n_shingles, group (a number; null without
    shingles) and component_id."""
    trees = trees or trees_for(percent, levels)
    signed = cut(signatures(docs, width, trees, levels))
    key = ["n_shingles", "s1", "s2"]
    first = F.min(F.struct("row", "doc_id", "text_hash", "least"))
    classes = cut(signed.where("n_shingles > 0").groupBy(*key).agg(first.alias("f"), F.min("doc_id").alias("least_id")).select(*key, "f.*", "least_id").withColumnRenamed("row", "cls"))
    members = cut(_nodes(classes, trees, levels))
    wanted = members.select("cls").distinct().join(classes.select("cls", F.col("doc_id").alias("__id"), F.col("text_hash").alias("__hash")), "cls")
    texts = packed_texts(docs)
    held = texts.join(wanted, texts["doc_id"].eqNullSafe(F.col("__id")) & (texts["text_hash"] == F.col("__hash"))).select("cls", "z")
    nodes = members.join(held, "cls").repartition("node").sortWithinPartitions("node", "cls")
    roots = cut(connected_components(_compared(nodes, width, percent)).select(F.col("node").alias("cls"), F.col("component_id").alias("root")))
    grouped = classes.select("cls", "least_id").join(roots, "cls")
    ids = grouped.groupBy("root").agg(F.min("least_id").alias("linked_id"))
    linked = roots.join(ids, "root")
    named = classes.join(linked, "cls", "left").select(*[F.col(k).alias(f"__{k}") for k in key], F.coalesce("root", "cls").alias("group"), F.when(F.col("root").isNotNull(), F.col("linked_id")).otherwise(F.col("least_id")).alias("component_id"))
    both = signed.join(named, [signed[k] == F.col(f"__{k}") for k in key], "left")
    return both.select("doc_id", "text_hash", "n_shingles", "group", F.when(F.col("group").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def near_duplicates(docs: DataFrame, width: int = WORDS, percent: int = PERCENT, trees: int | None = None, levels: int = LEVELS) -> DataFrame:
    """``docs(doc_id, text)`` to doc_id, n_shingles, component_id and kept: true for rows of the
    component's id, and for rows without an id in a component that has none."""
    out = judged(docs, width, percent, trees, levels)
    return out.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def without_near_duplicates(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The rows of ``docs`` without near duplicates: of each component exactly one row stays, one of
    least id (rows without an id last), however often ids or rows repeat; rows without words stay."""
    names, text = docs.columns, F.col("text").cast("string")
    found = judged(docs.select("doc_id", "text"), percent=percent).where("n_shingles > 0")
    id_hash = F.xxhash64(F.col("doc_id").isNull(), F.col("doc_id"))
    first = found.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).groupBy("group").agg(F.min(F.struct(id_hash.alias("__id"), F.col("text_hash").alias("__hash"))).alias("f")).select("f.*")
    wordless = F.coalesce(~text.rlike(r"[^\x20\x09-\x0D]"), F.lit(True))
    rows = docs.where(~wordless).select(F.struct(*names).alias("__row"), id_hash.alias("__id"), F.xxhash64(text).alias("__hash"))
    once = Window.partitionBy("__id", "__hash").orderBy("__hash")
    kept = rows.join(first, ["__id", "__hash"]).withColumn("__n", F.row_number().over(once)).where("__n = 1")
    return kept.select("__row.*").unionByName(docs.where(wordless))


def op4_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
