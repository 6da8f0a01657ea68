"""Graph blocking: components of the band graph, cut into communities of bounded size."""

from __future__ import annotations

import heapq
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from recblock.operators.graph import connected_components
from recblock.operators.minhash import band_keys, bucket_stars, fast_signatures, shared_keys
from recblock.operators.shingle import with_text
from recblock.session import cut, freed, stored

EDGE_LIMIT = 100_000  # a part with more possible edges goes through label_moves first
LABEL_LIMIT = 1_000  # so many records of one label have at most half a million edges
DENSE = 2_048  # so many nodes have a matrix of at most 32 MB
MOVED = 1 << 21  # so many rows of a part are a few hundred megabytes for the task that moves its labels
PULLING = 8  # labels of a bucket that pull its members: the most frequent ones


def modularity(edges: list[tuple[int, int, float]], community: dict[int, int]) -> float:
    m = sum(w for _, _, w in edges)
    if not m:
        return 0.0
    inner: dict[int, float] = defaultdict(float)
    degree: dict[int, float] = defaultdict(float)
    for a, b, w in edges:
        degree[community[a]] += w
        degree[community[b]] += w
        if community[a] == community[b]:
            inner[community[a]] += w
    return sum(inner[c] / m - (degree[c] / (2 * m)) ** 2 for c in degree)


def _dense_communities(nodes: list[int], edges: list[tuple[int, int, float]], cap: int | None = None) -> dict[int, int]:
    """greedy_communities by rows of a matrix: each row knows its best partner, and a merge looks at
    those rows again that it can change."""
    ids, n = np.array(sorted(nodes)), len(nodes)
    src, dst, weight = (np.array(x) for x in zip(*edges, strict=True))
    a, b = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    link = np.bincount(a * n + b, weight, n * n).reshape(n, n)
    link += link.T
    m = float(weight.sum())
    degree, size, root = link.sum(1), np.ones(n, np.int64), np.arange(n)

    def gains(rows: np.ndarray) -> np.ndarray:
        own = link[rows]
        out = 2 * m * own - degree[rows, None] * degree
        out[own == 0] = -np.inf
        if cap:
            out[size[rows, None] + size > cap] = -np.inf
        return out

    own = gains(root)
    partner, best = own.argmax(1), own.max(1)
    while True:
        a = int(best.argmax())
        if not best[a] > 0:
            break
        b = int(partner[a])  # above a, as row b has the same gain
        link[a] += link[b]
        link[a, a] = 0.0
        link[:, a] = link[a]
        link[b], link[:, b] = 0.0, 0.0
        degree[a] += degree[b]
        size[a] += size[b]
        root[root == b] = a
        best[b] = -np.inf
        rows = np.append(np.flatnonzero(((partner == a) | (partner == b)) & (best > -np.inf)), a)
        own = gains(rows)
        partner[rows], best[rows] = own.argmax(1), own.max(1)
        to = own[-1]  # gains with the merged one
        better = (to > best) | ((to == best) & (to > -np.inf) & (a < partner))
        better[a] = False
        partner[better], best[better] = a, to[better]
    return dict(zip(ids.tolist(), ids[root].tolist(), strict=True))


def greedy_communities(nodes: list[int], edges: list[tuple[int, int, float]], cap: int | None = None, dense: bool | None = None) -> dict[int, int]:
    """Merges the pair of communities of greatest gain while there is one; ties go to the smaller
    ids; with ``cap`` no merge goes beyond it. Returns node -> least id of its community.
    ``dense``: by a matrix, which is faster where few nodes have many edges; the result is the same."""
    if dense is None:
        dense = len(nodes) <= DENSE and len(edges) > 4 * len(nodes)
    if dense and edges:
        return _dense_communities(nodes, edges, cap)
    m = sum(w for _, _, w in edges)
    link: dict[int, dict[int, float]] = {v: {} for v in nodes}
    for a, b, w in edges:
        link[a][b] = link[a].get(b, 0.0) + w
        link[b][a] = link[b].get(a, 0.0) + w
    degree = {v: sum(link[v].values()) for v in nodes}
    size = {v: 1 for v in nodes}
    members = {v: [v] for v in nodes}
    gain = lambda a, b: 2 * m * link[a][b] - degree[a] * degree[b]  # noqa: E731  # times 2 m^2: exact for whole weights, so ties are ties
    heap = [(-gain(a, b), a, b) for a in nodes for b in link[a] if a < b]
    heapq.heapify(heap)
    while heap:
        g, a, b = heapq.heappop(heap)
        if a not in members or b not in members or b not in link[a] or gain(a, b) != -g:
            continue  # stale
        if g >= 0:
            break
        if cap and size[a] + size[b] > cap:
            continue
        for c, w in link.pop(b).items():
            link[c].pop(b)
            if c != a:
                link[a][c] = link[a].get(c, 0.0) + w
                link[c][a] = link[a][c]
        degree[a] += degree.pop(b)
        size[a] += size.pop(b)
        members[a] += members.pop(b)
        for c in link[a]:
            x, y = min(a, c), max(a, c)
            heapq.heappush(heap, (-gain(x, y), x, y))
    return {v: min(own) for own in members.values() for v in own}


def _bucket_edges(rec: np.ndarray, bucket: np.ndarray, n: int, step: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Codes src * n + dst of the pairs src < dst below ``n`` that share a bucket, and in how many rows they do."""
    order = np.argsort(bucket, kind="stable")
    rec, bucket = rec[order], bucket[order]
    after = np.searchsorted(bucket, bucket, "right") - 1 - np.arange(len(bucket))  # members that follow in the bucket
    total = np.append(0, np.cumsum(after))
    dense = np.zeros(n * n, np.int64) if n <= DENSE else None
    codes, at = [np.zeros(0, np.int64)], 0
    while at < len(rec):
        to = max(at + 1, int(np.searchsorted(total, total[at] + step, "right")) - 1)
        count = after[at:to]
        x = np.repeat(np.arange(at, to), count)
        y = x + 1 + np.arange(len(x)) - np.repeat(total[at:to] - total[at], count)
        x, y = rec[x], rec[y]
        code = (np.minimum(x, y) * n + np.maximum(x, y))[x != y]
        if dense is None:
            codes.append(code)
        else:
            dense += np.bincount(code, minlength=n * n)
        at = to
    if dense is None:
        return np.unique(np.concatenate(codes), return_counts=True)
    found = np.flatnonzero(dense)
    return found, dense[found]


def capped_communities(nodes: list[int], edges: list[tuple[int, int, float]], cap: int, scope: str = "oversized", mode: str = "recursive") -> tuple[dict[int, int], set[int]]:
    """Communities of at most ``cap`` nodes, and the communities that had to be cut as even runs
    of a part that modularity left whole."""
    if scope == "oversized" and len(nodes) <= cap:
        return {v: min(nodes) for v in nodes}, set()
    if mode == "constrained":
        return greedy_communities(nodes, edges, cap), set()
    out: dict[int, int] = {}
    forced: set[int] = set()
    work = [(nodes, edges)]
    while work:
        own, inner = work.pop()
        found = greedy_communities(own, inner)
        parts: dict[int, list[int]] = defaultdict(list)
        for v, c in found.items():
            parts[c].append(v)
        for part in parts.values():
            if len(part) <= cap:
                out.update((v, min(part)) for v in part)
            elif len(parts) == 1:
                part.sort()
                pieces = -(-len(part) // cap)
                for i in range(pieces):
                    run = part[i * len(part) // pieces : (i + 1) * len(part) // pieces]
                    out.update((v, run[0]) for v in run)
                    forced.add(run[0])
            else:
                held = set(part)
                work.append((part, [e for e in inner if e[0] in held and e[1] in held]))
    return out, forced


def label_moves(keys: DataFrame, rounds: int = 4, cap: int = LABEL_LIMIT, one_task: int = MOVED) -> DataFrame:
    """``keys(rec_id, part, band, key)`` to (rec_id, label, forced), for parts whose edges no worker
    should hold. Records move to the label of greatest modularity gain, by turns for odd and even
    digests; a round looks at the rows of those whose turn it is. No edge is made: a bucket, told by a
    64-bit digest, pulls its members towards its most frequent labels, by how many members bear them.
    Parts of at most ``one_task`` rows are moved by a task each, others by joins, with the same result.
    A label still above ``cap`` is cut by digest, which ``forced`` tells."""
    keys = stored(keys.select("part", "rec_id", F.xxhash64("part", "band", "key").alias("bucket")))
    wide = keys.groupBy("part").agg(F.count("*").alias("n")).where(F.col("n") > one_task).select("part")
    odd = F.pmod(F.xxhash64("rec_id"), F.lit(2)).cast("int")
    few = keys.join(wide, "part", "left_anti").withColumn("odd", odd)
    labels = few.groupBy("part").applyInArrow(lambda table: _moves_in_task(table, rounds), "part long, rec_id long, label long")
    if not wide.isEmpty():
        labels = labels.unionByName(_moves_by_joins(keys.join(wide, "part", "left_semi"), rounds, odd))
    labels = stored(labels)
    freed(keys)
    many = labels.groupBy("part", "label").agg(F.count("*").alias("n"))
    piece = F.pmod(F.xxhash64("rec_id"), F.ceil(F.col("n") / cap))
    return labels.join(many, ["part", "label"]).select("rec_id", F.xxhash64("part", "label", piece).alias("label"), (F.col("n") > cap).alias("forced"))


def _moves_by_joins(keys: DataFrame, rounds: int, odd: Column) -> DataFrame:
    """(part, rec_id, label) of ``keys(part, rec_id, bucket)`` after all rounds."""
    sizes = keys.groupBy("bucket").agg(F.count("*").alias("v"), F.min("rec_id").alias("least"))
    state = stored(keys.join(sizes, "bucket").groupBy("part", "rec_id").agg(F.sum(F.col("v") - 1).cast("double").alias("d"), F.count("*").alias("own"), F.min("least").alias("label")))
    m2 = cut(state.groupBy("part").agg(F.sum("d").alias("m2")))
    first = Window.partitionBy("bucket").orderBy(F.desc("c"), "label")
    for r in range(rounds):
        turn = odd == r % 2
        mass = state.groupBy("part", "label").agg(F.sum("d").alias("mass"))
        pulling = keys.join(state.select("part", "rec_id", "label"), ["part", "rec_id"]).groupBy("bucket", "label").agg(F.count("*").alias("c")).withColumn("__n", F.row_number().over(first)).where(F.col("__n") <= PULLING)
        pull = keys.where(turn).join(pulling.drop("__n"), "bucket").groupBy("part", "rec_id", "label").agg(F.sum("c").alias("pull"))
        at_home = F.col("label") == F.col("mine")
        scored = pull.join(mass, ["part", "label"]).join(state.where(turn).withColumnRenamed("label", "mine"), ["part", "rec_id"]).join(m2, "part")
        gain = F.col("pull") - F.when(at_home, F.col("own")).otherwise(0) - F.col("d") * (F.col("mass") - F.when(at_home, F.col("d")).otherwise(0.0)) / F.col("m2")
        best = scored.groupBy("part", "rec_id").agg(F.max(F.struct(gain.alias("gain"), (-F.col("label")).alias("minus"))).alias("b")).select("part", "rec_id", (-F.col("b.minus")).alias("to"), F.col("b.gain").alias("gain"))
        state = stored(state.join(best, ["part", "rec_id"], "left").select("part", "rec_id", "d", "own", F.when(F.col("gain") > 0, F.col("to")).otherwise(F.col("label")).alias("label")))
    return state.select("part", "rec_id", "label")


def _moves_in_task(table: pa.Table, rounds: int, step: int = 1 << 18) -> pa.Table:
    """The same of one part's ``table(part, rec_id, bucket, odd)``, so many rows of it at a time."""
    ids, head, r = np.unique(table.column("rec_id").to_numpy(), return_index=True, return_inverse=True)
    odd, n = table.column("odd").to_numpy()[head], len(ids)
    b = np.unique(table.column("bucket").to_numpy(), return_inverse=True)[1]
    v, order = np.bincount(b), np.argsort(b, kind="stable")
    least = np.minimum.reduceat(r[order], np.cumsum(v) - v)
    d, own, label = np.bincount(r, v[b] - 1, n), np.bincount(r, minlength=n), np.full(n, n)
    np.minimum.at(label, r, least[b])
    m2 = d.sum()
    order = np.argsort(r, kind="stable")
    for t in range(rounds):
        mass = np.bincount(label, d, n)
        code, c = np.unique(b * n + label[r], return_counts=True)
        of, to = code // n, code % n
        at = np.lexsort((to, -c, of))  # a bucket's most frequent labels first
        of, to, c = of[at], to[at], c[at]
        keep = np.arange(len(of)) - np.searchsorted(of, of) < PULLING
        of, to, c = of[keep], to[keep], c[keep]
        count = np.bincount(of, minlength=len(v))
        first = np.cumsum(count) - count
        rows, now, a = order[odd[r[order]] == t % 2], label.copy(), 0
        while a < len(rows):  # whole records
            z = int(np.searchsorted(r[rows], r[rows[min(a + step, len(rows)) - 1]], "right"))
            x, y = r[rows[a:z]], b[rows[a:z]]
            each = count[y]
            place = np.repeat(first[y] - (np.cumsum(each) - each), each) + np.arange(each.sum())
            code, back = np.unique(np.repeat(x, each) * n + to[place], return_inverse=True)
            pull, rec, new = np.bincount(back, c[place]), code // n, code % n
            home = new == label[rec]
            gain = pull - np.where(home, own[rec], 0) - d[rec] * (mass[new] - np.where(home, d[rec], 0.0)) / m2
            at = np.lexsort((new, -gain, rec))
            at = at[np.flatnonzero(np.diff(rec[at], prepend=-1))]
            at = at[gain[at] > 0]
            now[rec[at]] = new[at]
            a = z
        label = now
    return pa.table({"part": np.full(n, table.column("part")[0].as_py() if n else 0), "rec_id": ids, "label": ids[label]})


def tlsh_blocks(records: DataFrame, fields: list[str], k: int = 5, p: int = 100, b: int = 22, cap: int = 500, seed: int = 42, community: str = "greedy", scope: str = "oversized", mode: str = "recursive", weight: str = "one") -> DataFrame:
    """(rec_id, block_id): a partition whose blocks have at most ``cap`` records. Components are
    found on star edges; all edges are made inside oversized components only. Records without
    text, and nulls, are blocks of their own; an empty table has no blocks."""
    texts = with_text(records, fields)
    return blocks_of_keys(text_keys(texts, k, p, b, seed), texts.select("rec_id"), cap, community, scope, mode, weight).select("rec_id", "block_id")


def text_keys(texts: DataFrame, k: int = 5, p: int = 100, b: int = 22, seed: int = 42) -> DataFrame:
    """Shared band keys, written once before they are counted: signatures are worked out once."""
    every = stored(band_keys(fast_signatures(texts, k, p, seed), p, b, fast=True))
    shared = stored(shared_keys(every))
    freed(every)
    return shared


def blocks_of_keys(keys: DataFrame, ids: DataFrame, cap: int = 500, community: str = "greedy", scope: str = "oversized", mode: str = "recursive", weight: str = "one", edge_limit: int = EDGE_LIMIT) -> DataFrame:
    """(rec_id, block_id, forced): ``forced`` where a block is an even run of a part that no
    community cut. Possible edges are counted from bucket sizes first; where a part has more than
    ``edge_limit``, label moves without edges cut it, so a worker's edges are bounded."""
    components = stored(connected_components(bucket_stars(keys), ids.select(F.col("rec_id").alias("node"))))
    if community == "none":
        return components.select(F.col("node").alias("rec_id"), F.col("component_id").alias("block_id"), F.lit(False).alias("forced"))
    sizes = components.groupBy("component_id").agg(F.count("*").alias("n"))
    large = sizes.where(F.col("n") > (cap if scope == "oversized" else 1))
    small = components.join(large, "component_id", "left_anti").select(F.col("node").alias("rec_id"), F.col("component_id").alias("block_id"), F.lit(False).alias("forced"))
    members = components.join(large, "component_id").select(F.col("node").alias("rec_id"), F.col("component_id").alias("part"))
    inside = stored(keys.join(members, "rec_id").select("rec_id", "part", "band", "key"))
    bucket = ["part", "band", "key"]
    possible = inside.groupBy(*bucket).agg(F.count("*").alias("v")).groupBy("part").agg(F.sum(F.col("v") * (F.col("v") - 1) / 2).alias("e"))
    heavy = possible.where(F.col("e") > edge_limit).select("part")
    parts = members.select("rec_id", "part", F.lit(False).alias("forced"))
    if not heavy.isEmpty():
        moved = label_moves(inside.join(heavy, "part", "left_semi"))
        parts = stored(parts.join(heavy, "part", "left_anti").unionByName(moved.withColumnRenamed("label", "part"), allowMissingColumns=False).select("rec_id", "part", "forced"))
        whole, inside = inside, stored(inside.drop("part").join(parts.select("rec_id", "part"), "rec_id"))
        freed(whole)
    done = None
    if scope == "oversized":  # parts within the cap need no edges
        counted = parts.join(parts.groupBy("part").agg(F.count("*").alias("n"), F.min("rec_id").alias("block_id")), "part")
        done = counted.where(F.col("n") <= cap).select("rec_id", "block_id", "forced")
        parts = stored(counted.where(F.col("n") > cap).select("rec_id", "part", "forced"))
        inside = inside.join(parts.select("rec_id", "part").distinct(), ["rec_id", "part"], "left_semi")
    rows = parts.select("part", "rec_id", F.lit(None).cast("long").alias("bucket"), "forced").unionByName(inside.select("part", "rec_id", F.xxhash64("band", "key").alias("bucket"), F.lit(False).alias("forced")))

    def split(table: pa.Table) -> pa.Table:
        rec, forced = table.column("rec_id").to_numpy(), table.column("forced").to_numpy(zero_copy_only=False)
        single = table.column("bucket").is_null().to_numpy()
        nodes = np.unique(rec[single])
        links, hits = _bucket_edges(np.searchsorted(nodes, rec[~single]), table.column("bucket").drop_null().to_numpy(), len(nodes))
        worth = hits.astype(float) if weight == "bands_hit" else np.ones(len(links))
        src, dst = nodes[links // len(nodes)], nodes[links % len(nodes)]
        found, cuts = capped_communities(nodes.tolist(), list(zip(src.tolist(), dst.tolist(), worth.tolist(), strict=True)), cap, scope, mode)
        every = bool(forced.any())
        return pa.table({"rec_id": list(found), "block_id": list(found.values()), "forced": [every or c in cuts for c in found.values()]}, pa.schema({"rec_id": pa.int64(), "block_id": pa.int64(), "forced": pa.bool_()}))

    # communities are dear for their bytes: parts are dealt to all partitions
    dealt = rows.repartition(int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions")), "part")
    small = small.unionByName(done) if done is not None else small
    return small.unionByName(dealt.groupBy("part").applyInArrow(split, "rec_id long, block_id long, forced boolean"))
