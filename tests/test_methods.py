"""Projection blocking, clusters, measures and linking on small inputs with nulls, ties and empty tables."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from recblock.operators import cluster, klsh, linkage, metrics, shingle

PERSONS = "rec_id long, name string"


def words(rng, n):
    return [(i, " ".join("".join(rng.choice("abcd") for _ in range(4)) for _ in range(3))) for i in range(n)]


def test_projection_blocks_are_a_partition_with_empty_texts(spark):
    rows = words(random.Random(1), 40) + [(100, ""), (101, None), (-5, None)]
    r = spark.createDataFrame(rows, PERSONS)
    got = klsh.klsh_blocks(r, ["name"], 2, 10, 4, 3).collect()
    assert sorted(x.rec_id for x in got) == sorted(i for i, _ in rows)
    own = [x.block_id for x in got if x.rec_id in (100, 101, -5)]
    assert len(set(own)) == 3 and all(b < 0 for b in own) and {x.block_id for x in got if 0 <= x.rec_id < 40} <= set(range(4))
    least = klsh.klsh_blocks(r, ["name"], 2, 10, 4, 3, min_block_size=5)
    assert least.count() == len(rows) and least.groupBy("block_id").count().agg(F.min("count")).first()[0] >= 5
    assert klsh.klsh_blocks(r.limit(0), ["name"]).count() == 0


def test_vectors_from_texts_equal_those_from_written_counts(spark):
    rng = random.Random(4)
    rows = words(rng, 40) + [(50, ""), (51, None), (52, "a"), (53, "é\nßé\nßé"), (54, "ab" * 300)]
    r = spark.createDataFrame(rows, PERSONS)
    assert {x.term: x.df for x in klsh.shingle_df(shingle.with_text(r, ["name"]), 2).collect()} == {x.term: x.df for x in klsh.idf(shingle.shingle_counts(shingle.with_text(r, ["name"]), 2), 1).collect()}
    for k, unit in ((2, False), (3, True)):
        got = {x.rec_id: x.vec for x in klsh.klsh_vectors(r, ["name"], k, 10, unit=unit).collect()}
        assert got == {x.rec_id: x.vec for x in klsh.klsh_vectors(r, ["name"], k, 10, unit=unit, vocabulary=0).collect()} and set(got) == {i for i, t in rows if t}
    plan = klsh.klsh_vectors(r, ["name"], 2, 10)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Generate" not in plan
    assert klsh._bag("a😀a😀", 2) == {"a😀": 2, "😀a": 1} and klsh._bag("", 2) == klsh._bag(None, 2) == {}  # whole letters
    twice = r.unionByName(r.limit(3))
    assert klsh.klsh_vectors(twice, ["name"], 2, 10).count() == len(rows) - 2


def test_projection_blocks_of_short_texts_write_no_vectors(spark, monkeypatch):
    rows = [(i, f"{'anna bert carl dora emil'.split()[i % 5]} {'smith jones'.split()[i % 2]}{i % 7}") for i in range(60)] + [(100, ""), (101, None)]
    r = spark.createDataFrame(rows, "rec_id long, name string")
    vectors = klsh.klsh_vectors(r, ["name"], 2, 40)
    want = {x.rec_id: x.block_id for x in klsh.kmeans_blocks(vectors, 6, 4).collect()}
    written = []
    for name in ("stored", "cut"):
        monkeypatch.setattr(klsh, name, lambda df, real=getattr(klsh, name): written.append(df.columns) or real(df))
    got = {x.rec_id: x.block_id for x in klsh.klsh_blocks(r, ["name"], 2, 40, 6, 4).collect()}
    assert got == want | {100: -201, 101: -203}
    assert written and not [c for c in written if "vec" in c]


def test_too_many_centroids_are_refused():
    with pytest.raises(ValueError):
        klsh._held(1 << 20, 150)


def test_epsilon_pairs_equal_brute_force(spark):
    rng = random.Random(2)
    rows = words(rng, 60) + [(200 + i, t[:-1] + "x") for i, t in words(random.Random(2), 20)] + [(300, ""), (301, None)]
    t = spark.createDataFrame(rows, "rec_id long, rec_text string")
    bags = {r.rec_id: dict(zip(r.terms, r.ws, strict=True)) for r in cluster.unit_bags(t).collect()}
    for metric, at, block in (("tfidf", 0.5, 1024), ("tfidf", 1.1, 7), ("cosine", 0.4, 16)):
        want = {}
        for a in bags:
            for b in bags:
                if a < b:
                    sim = sum(w * bags[b].get(k, 0.0) for k, w in bags[a].items())
                    d = 1 - sim if metric == "cosine" else max(0.0, round(2 - 2 * sim, 9)) ** 0.5
                    if d <= at:
                        want[a, b] = round(d, 6)
        for way in ("auto", "prefix", "blocks"):
            got = cluster.epsilon_pairs(t, at, 2, metric, block, way).collect()
            assert len(got) == len({(r.id_a, r.id_b) for r in got}) and {(r.id_a, r.id_b): round(r.distance, 6) for r in got} == want
    assert cluster.epsilon_pairs(t.limit(0), 0.5).count() == 0
    with pytest.raises(ValueError):
        cluster.epsilon_pairs(t, 1.5)


def test_vectors_are_not_written_for_each_prefix_term(spark, monkeypatch):
    written, own = [], cluster.stored
    monkeypatch.setattr(cluster, "stored", lambda df: written.append(df.columns) or own(df))
    t = spark.createDataFrame(words(random.Random(3), 20), "rec_id long, rec_text string")
    for way in ("auto", "prefix", "blocks"):
        cluster.epsilon_pairs(t, 0.5, way=way).count()
    assert written and not any({"at", "terms"} <= set(c) for c in written)


def test_growth_from_the_base_and_by_chains(spark):
    ids = spark.createDataFrame([(i,) for i in range(6)], "rec_id long")
    pairs = spark.createDataFrame([(0, 1), (1, 2), (2, 3)], "id_a long, id_b long")
    assert {tuple(r) for r in cluster.tnn_blocks(ids, pairs).collect()} == {(0, 0), (1, 0), (2, 0), (3, 0), (4, 4), (5, 5)}
    order = {r.rec_id: r.ord for r in klsh.rank_by_digest(ids).collect()}
    near = {i: {i} | {b for a, b in ((0, 1), (1, 0), (1, 2), (2, 1), (2, 3), (3, 2)) if a == i} for i in range(6)}
    block, left = {}, set(range(6))
    for i in sorted(order, key=order.get):
        if i in left:
            left -= near[i]
            block[i] = i
    want = {i: min((b for b in block if i in near[b]), key=order.get) for i in range(6)}
    assert dict(map(tuple, cluster.tnn_blocks(ids, pairs, "base").collect())) == want


def test_sorted_neighbours_over_ranges(spark):
    rng = random.Random(3)
    rows = [(i, "".join(rng.choice("ab") for _ in range(rng.randint(0, 6)))) for i in range(80)] + [(90, None)]
    got = dict(map(tuple, cluster.sorted_tnn_blocks(spark.createDataFrame(rows, "rec_id long, rec_text string"), 1).collect()))

    def distance(a, b):
        d = list(range(len(b) + 1))
        for i, x in enumerate(a):
            d, last = [i + 1], d
            for j, y in enumerate(b):
                d.append(min(d[-1] + 1, last[j + 1] + 1, last[j] + (x != y)))
        return d[-1]

    number, before, want = 0, None, {}
    for t, i in sorted((t or "", i) for i, t in rows):
        number += before is None or distance(before, t) > 1
        before, want[i] = t, number
    assert got == want


def test_nearest_neighbour_clusters(spark):
    rng = np.random.default_rng(4)
    rows = [(i, v.tolist()) for i, v in enumerate(rng.standard_normal((43, 3)))] + [(100, None), (101, [1.0, None, 2.0])]
    v = spark.createDataFrame(rows, "rec_id long, vec array<double>")
    for cells in (1, 3):
        got = cluster.knn_blocks(v, 5, cells).collect()
        assert sorted(r.rec_id for r in got) == sorted(i for i, _ in rows)
        sizes = {}
        for r in got:
            sizes[r.block_id] = sizes.get(r.block_id, 0) + 1
        assert all(n >= 5 for b, n in sizes.items() if b != 100) and sizes[100] == 2
    with pytest.raises(ValueError):
        cluster.knn_blocks(v, 5, 1, limit=10)


def test_reference_values_and_new_records(spark):
    r = spark.createDataFrame([(i, n) for i, n in enumerate(["adam", "bert", "bea", "carl", "dora", "zoe", None, "aa"])], PERSONS)
    refs = spark.createDataFrame([("b",), ("c",), ("d",), (None,), ("b",)], "name string")
    got = {x.rec_id: (x.ref, x.block_id) for x in cluster.reference_blocks(r, refs, "name", 3).collect()}
    assert {i: x[0] for i, x in got.items()} == {0: "", 1: "b", 2: "b", 3: "c", 4: "d", 5: "d", 6: "", 7: ""}
    sizes = {}
    for _, b in got.values():
        sizes[b] = sizes.get(b, 0) + 1
    assert min(sizes.values()) >= 3
    old = spark.createDataFrame([(1, [0.0]), (2, [10.0]), (3, [10.0])], "rec_id long, vec array<double>")
    new = spark.createDataFrame([(50, [1.0]), (51, [9.0])], "rec_id long, vec array<double>")
    blocks = spark.createDataFrame([(1, 7), (2, 8), (3, 9)], "rec_id long, block_id long")
    assert {tuple(x) for x in cluster.assign_new(new, old, blocks).collect()} == {(50, 7), (51, 8)}


def test_settings_can_not_take_names_of_results(spark):
    r = spark.createDataFrame([(1, 1, 1), (2, 1, 1)], "rec_id long, entity_id long, block_id long")
    assert metrics.block_scores(r.select("rec_id", "block_id", F.lit(3).alias("c")), r, ["c"]).first().recall == 1.0
    with pytest.raises(ValueError):
        metrics.block_scores(r, r, ["recall"])


def test_entities_and_deduplication(spark):
    r = spark.createDataFrame([(i, f"n{i}") for i in range(5)], PERSONS)
    linked = linkage.entities(spark.createDataFrame([(0, 3), (3, 4)], "id_a long, id_b long"), r)
    assert sorted(x.rec_id for x in linkage.deduplicate(r, linked).collect()) == [0, 1, 2]


def test_pair_counts_come_from_block_sizes(spark, monkeypatch):
    rows = [(i % 37, "ab"[i % 2] if i % 5 else None) for i in range(90)] + [(None, "a")]
    b = spark.createDataFrame(rows, "rec_id long, block_id string")
    want = sum(x[0] is not None and y[0] is not None and x[0] < y[0] and x[1] == y[1] is not None for x in rows for y in rows)
    monkeypatch.setattr(linkage, "block_pairs", None)  # no pair is made
    got = linkage.pair_count(b)
    assert got.first().pairs == want and dict(got.dtypes)["pairs"] == "bigint"
    assert linkage.pair_count(b.limit(0)).first().pairs == 0


def test_pairs_of_two_keyings_equal_sets_of_pairs(spark):
    rng = random.Random(3)
    rows = [(i, rng.choice(["x", "y", None]), rng.choice(["p", "q", "r", None])) for i in range(60)]
    for own in (rows, rows + [(5, "x", "q"), (5, "y", "p"), (7, "x", "r"), (None, "x", "p")]):  # ids may repeat
        t = spark.createDataFrame(own, "rec_id long, first string, second string")
        pairs = lambda k, own=own: {(a[0], b[0]) for a in own for b in own if a[0] is not None and b[0] is not None and a[0] < b[0] and a[k] == b[k] is not None}
        for how, want in (("union", pairs(1) | pairs(2)), ("except", pairs(1) - pairs(2))):
            df = linkage.paired_by_two(t, how)
            got = [tuple(r) for r in df.collect()]
            assert len(got) == len(set(got)) and set(got) == want
            if own is rows:  # nothing is made distinct or set against other pairs
                plan = df._jdf.queryExecution().optimizedPlan().toString()
                assert "Aggregate" not in plan and "LeftAnti" not in plan


def test_cost_and_curve_read_tables(spark, tmp_path):
    from recblock.plans import methods

    spark.sql("select o_orderkey, if(o_orderkey < 9, timestamp_ntz'1995-03-01', if(o_orderkey < 12, timestamp_ntz'1996-01-01', null)) as o_orderdate from range(13) as t(o_orderkey)").write.parquet(f"{tmp_path}/orders.parquet")
    assert {r.n for r in methods.predicted_costs(spark, str(tmp_path)).collect()} == {9, 12}
    turns = [(1, 0, "a b c"), (1, 1, "A b d "), (1, 2, None), (2, 0, "a"), (2, 2, "a"), (3, 0, ""), (3, 1, "")]
    spark.createDataFrame(turns, "conv_id long, turn long, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    got = methods.band_curve_values(spark, str(tmp_path)).collect()
    assert sorted((r.b, r.s, r.pairs) for r in got) == [(b, 0.5, 1) for b in (21, 22, 26)]


def test_forests_of_near_vectors_join_what_all_pairs_join(spark):
    rng = np.random.default_rng(5)
    rows = [(i, [float(v) for v in rng.normal(size=6)]) for i in range(150)]
    rows += [(500, [rows[0][1][0] + 1.1, *rows[0][1][1:]]), (501, None), (502, []), (503, [None] * 6), (504, [float("nan")] * 6), (505, [None, *rows[3][1][1:]]), (506, rows[4][1][:2]), (500, rows[9][1])]
    v = spark.createDataFrame(rows, "rec_id long, vec array<double>")

    def close(a, b):
        own = [(x - y) ** 2 for x, y in zip(a or [], b or []) if x is not None and y is not None]
        return bool(own) and sum(own) ** 0.5 <= 1.1

    near = {(min(i, j), max(i, j)) for i, a in rows for j, b in rows if i != j and close(a, b)}
    ids = v.select("rec_id")
    want = {tuple(r) for r in cluster.tnn_blocks(ids, spark.createDataFrame(sorted(near), "id_a long, id_b long")).collect()}
    for block in (16, 4096):
        pairs = cluster.near_forest(v, 1.1, block)
        got = [tuple(r) for r in pairs.collect()]
        assert set(got) <= near and {tuple(r) for r in cluster.tnn_blocks(ids, pairs).collect()} == want
    assert len(got) < len({i for i, _ in rows})  # a forest, not all pairs
    assert cluster.near_forest(v.limit(0), 1.1).count() == 0
