"""Sweeps and comparisons of the methods over the person files and the documents, the growth
of their cost, and records that arrive on a stream."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from recblock.operators import cluster as X
from recblock.operators import criteria as D
from recblock.operators import graph, klsh, linkage, metrics, minhash, shingle, tlsh
from recblock.plans import methods as M
from recblock.session import checkpoint_root, cut, stored
from recblock.sources.persons import fields_of, file_sql, noisy_sql, persons
from recblock.streaming import blocks as S

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _named(blocks: DataFrame, **setting) -> DataFrame:
    return blocks.select("rec_id", F.col("block_id").cast("string").alias("block_id"), *[F.lit(v).alias(k) for k, v in setting.items()])


def _scored(blocks: list[DataFrame], truth: DataFrame, by: list[str]) -> DataFrame:
    return metrics.block_scores(_union(blocks), truth, by).select(*by, "recall", "rr", "blocks", "max_block")


# nearest neighbours and canopies


def _tnn_sweep(file: str):
    def run(spark, sf_dir):
        """Recall and reduction of threshold neighbours over t, grown by chains and from the base."""
        r, t = M._texts(spark, sf_dir, file)
        near = stored(X.epsilon_pairs(t, 0.95))
        parts = []
        for at in (0.4, 0.6, 0.75, 0.85, 0.95):
            own = near.where(F.col("distance") <= at)
            parts += [_named(stored(X.tnn_blocks(r, own, growth)), t=at, growth=growth) for growth in ("chain", "base")]
        return _scored(parts, r, ["t", "growth"])

    return run


def _canopy_sweep(file: str):
    def run(spark, sf_dir):
        """Recall and reduction of canopies over (t1, t2), by pairs that share one."""
        r, t = M._texts(spark, sf_dir, file)
        near = stored(X.epsilon_pairs(t, 0.95))
        parts = [X.canopy_pairs(stored(X.canopies(r.select("rec_id"), near, t1, t2))).select("id_a", "id_b", F.lit(t1).alias("t1"), F.lit(t2).alias("t2")) for t1, t2 in ((0.6, 0.6), (0.75, 0.6), (0.85, 0.75), (0.95, 0.75), (0.95, 0.95))]
        return metrics.pair_scores(stored(_union(parts)), r, ["t1", "t2"]).select("t1", "t2", "recall", "rr")

    return run


for _file in ("clean10k", "noisy10"):
    query(f"tnn_sweep_{_file}")(_tnn_sweep(_file))
    query(f"canopy_sweep_{_file}")(_canopy_sweep(_file))


@query("sorted_tnn_sweep_noisy10", " UNION ALL ".join(M._block_rates_sql("noisy10", M._sorted_sql("noisy10", t), f"{t} AS t") for t in (10, 20, 30)))
def sorted_tnn_sweep_noisy(spark, sf_dir):
    r, t = M._texts(spark, sf_dir, "noisy10")
    return metrics.block_scores(_union([X.sorted_tnn_blocks(t, d).withColumn("t", F.lit(d)) for d in (10, 20, 30)]), r, ["t"]).select("t", "recall", "rr", "blocks", "max_block")


@query("epsilon_pairs_persons", f"WITH {M._near_cte(0.9)} SELECT id_a, id_b, round(distance, 6) AS distance FROM near")
def epsilon_pairs_persons(spark, sf_dir):
    return X.epsilon_pairs(M._texts(spark, sf_dir, "clean500")[1], 0.9).select("id_a", "id_b", F.round("distance", 6).alias("distance"))


@query("canopy_pairs_persons", f"WITH RECURSIVE {M._bases_cte} SELECT DISTINCT a.rec_id AS id_a, b.rec_id AS id_b FROM cover a JOIN cover b USING (canopy_id) WHERE a.rec_id < b.rec_id")
def canopy_pairs_persons(spark, sf_dir):
    return X.canopy_pairs(M._cover(spark, sf_dir)[1])


@query("canopy_count", f"WITH RECURSIVE {M._bases_cte} SELECT count(*) AS canopies, (SELECT count(*) FROM cover) AS memberships FROM bases")
def canopy_count(spark, sf_dir):
    return M._cover(spark, sf_dir)[1].agg(F.countDistinct("canopy_id").alias("canopies"), F.count("*").alias("memberships"))


@query("canopy_first_blocks", f"WITH RECURSIVE {M._bases_cte} SELECT rec_id, arg_min(canopy_id, md5('42|' || canopy_id)) AS block_id FROM cover GROUP BY rec_id")
def canopy_first_blocks(spark, sf_dir):
    return X.canopy_blocks(M._cover(spark, sf_dir)[1], "equal")


@query("canopy_merged_blocks", f"""WITH RECURSIVE {M._bases_cte}, e AS (SELECT rec_id AS s, canopy_id AS d FROM cover UNION SELECT canopy_id, rec_id FROM cover),
reach AS (SELECT DISTINCT s AS rec_id, s AS c FROM e UNION SELECT e.d, reach.c FROM reach JOIN e ON e.s = reach.rec_id WHERE reach.c <= e.d) SELECT rec_id, min(c) AS block_id FROM reach GROUP BY rec_id""")
def canopy_merged_blocks(spark, sf_dir):
    return X.canopy_blocks(M._cover(spark, sf_dir)[1], "merge")


_score_sql = "round(((a.birth_year = b.birth_year)::INT + (a.birth_month = b.birth_month)::INT + (a.birth_day = b.birth_day)::INT + 2 * (1 - levenshtein(a.first_name, b.first_name) / greatest(length(a.first_name), length(b.first_name), 1)) + 2 * (1 - levenshtein(a.last_name, b.last_name) / greatest(length(a.last_name), length(b.last_name), 1))) / 7, 6)"


@query("link_in_canopies", f"WITH RECURSIVE {M._bases_cte}, r AS ({file_sql('duckdb', 'clean500')}), p AS (SELECT DISTINCT x.rec_id AS i, y.rec_id AS j FROM cover x JOIN cover y USING (canopy_id) WHERE x.rec_id < y.rec_id) SELECT i AS id_a, j AS id_b, {_score_sql} AS score FROM p JOIN r a ON a.rec_id = i JOIN r b ON b.rec_id = j WHERE {_score_sql} >= 0.7")
def link_in_canopies(spark, sf_dir):
    """The dear comparison, inside canopies of the cheap one."""
    r, cover = M._cover(spark, sf_dir)
    return linkage.link_pairs(X.canopy_pairs(cover), r, M._weights, ("first_name", "last_name"), 0.7)


# graph blocking: bands, letters, permutations, cap


def _graph_grid(file: str, settings: list[tuple[int, int, int, int]]):
    def run(spark, sf_dir):
        """Recall and reduction over letters k, bands b, permutations p and the cap."""
        r, t = M._texts(spark, sf_dir, file)
        parts, signed = [], {}
        for k, b, p, cap in settings:
            if (k, p) not in signed:
                signed[k, p] = stored(minhash.fast_signatures(t, k, p))
            keys = stored(minhash.shared_keys(stored(minhash.band_keys(signed[k, p], p, b, fast=True))))
            parts.append(_named(stored(tlsh.blocks_of_keys(keys, r.select("rec_id"), cap)), k=k, b=b, p=p, cap=cap))
        return _scored(parts, r, ["k", "b", "p", "cap"])

    return run


query("tlsh_bands_clean500")(_graph_grid("clean500", [(5, b, 100, 500) for b in (5, 10, 15, 22, 26, 33, 50)]))
query("tlsh_bands_clean10k")(_graph_grid("clean10k", [(5, b, 100, 500) for b in (15, 22, 26, 33)]))
query("tlsh_letters_clean10k")(_graph_grid("clean10k", [(k, 26, 100, 500) for k in (3, 4, 5)]))
query("tlsh_permutations_clean10k")(_graph_grid("clean10k", [(5, p * 22 // 100, p, 500) for p in (50, 100, 150, 200)]))
query("tlsh_grid_noisy10")(_graph_grid("noisy10", [(k, b, 100, 500) for k in (4, 5) for b in (22, 26)]))


@query("tlsh_cap_report")
def tlsh_cap_report(spark, sf_dir):
    """Recall, reduction, largest block and records in forced cuts over the cap, at k = 5, b = 26; 10,000 cuts nothing."""
    r, t = M._texts(spark, sf_dir, "clean10k")
    keys = tlsh.text_keys(t, 5, 100, 26)
    found = {cap: stored(tlsh.blocks_of_keys(keys, r.select("rec_id"), cap)) for cap in (50, 100, 500, 10_000)}
    forced = _union([b.agg(F.lit(cap).alias("cap"), F.sum(F.col("forced").cast("long")).alias("forced")) for cap, b in found.items()])
    return _scored([_named(b, cap=cap) for cap, b in found.items()], r, ["cap"]).join(forced, "cap")


def _true_pairs_sql(file: str, k: int) -> str:
    return f"""t AS MATERIALIZED (SELECT DISTINCT rec_id, entity_id, term FROM ({M._terms_sql(file, k)})), n AS (SELECT rec_id, entity_id, count(*) AS n FROM t GROUP BY ALL),
p AS (SELECT a.rec_id AS id_a, b.rec_id AS id_b, a.n + b.n AS n FROM n a JOIN n b ON a.entity_id = b.entity_id AND a.rec_id < b.rec_id),
j AS (SELECT id_a, id_b, count(y.term) / (any_value(p.n) - count(y.term)) AS s FROM p JOIN t x ON x.rec_id = id_a LEFT JOIN t y ON y.rec_id = id_b AND y.term = x.term GROUP BY id_a, id_b)"""


def _curve_sql(b: int) -> str:
    sizes = minhash.band_sizes(100, b)
    return "1 - " + " * ".join(f"power(1 - power(s, {r}), {sizes.count(r)})" for r in sorted(set(sizes)))


@query("expected_band_recall", f"WITH {_true_pairs_sql('clean10k', 5)} " + " UNION ALL ".join(f"SELECT {b} AS b, round(avg(s), 6) AS mean_similarity, round(avg({_curve_sql(b)}), 6) AS expected_recall FROM j" for b in (15, 21, 22, 26, 33, 50)))
def expected_band_recall(spark, sf_dir):
    """What the band curve gives for the similarity that the true pairs of our file have: the recall
    that no choice of permutations can better before components add to it."""
    r, t = M._texts(spark, sf_dir, "clean10k")
    sets = cut(t.select("rec_id", shingle.shingle_set(F.col("rec_text"), 5).alias("s")).join(r.select("rec_id", "entity_id"), "rec_id"))
    a, b = (sets.select(F.col("rec_id").alias(f"id_{x}"), "entity_id", F.col("s").alias(f"s_{x}")) for x in "ab")
    j = cut(a.join(b, "entity_id").where("id_a < id_b").select(minhash.jaccard(F.col("s_a"), F.col("s_b")).alias("s")))
    parts = []
    for bands in (15, 21, 22, 26, 33, 50):
        sizes, miss = minhash.band_sizes(100, bands), F.lit(1.0)
        for rows in sorted(set(sizes)):
            miss = miss * F.pow(1 - F.pow("s", F.lit(rows)), F.lit(sizes.count(rows)))
        parts.append(j.agg(F.lit(bands).alias("b"), F.round(F.avg("s"), 6).alias("mean_similarity"), F.round(F.avg(1 - miss), 6).alias("expected_recall")))
    return _union(parts)


# projection blocking: letters, blocks, projections


def _projection_grid(file: str, settings: list[tuple[int, int, int]]):
    def run(spark, sf_dir):
        """Recall and reduction over letters k, length p of the projection and number of blocks."""
        r, _ = M._texts(spark, sf_dir, file)
        parts, vectors = [], {}
        for k, p, cells in settings:
            if (k, p) not in vectors:
                vectors[k, p] = stored(klsh.klsh_vectors(r, fields_of(file), k, p))
            parts.append(_named(stored(klsh.kmeans_blocks(vectors[k, p], cells, 5)), k=k, p=p, cells=cells))
        return _scored(parts, r, ["k", "p", "cells"])

    return run


query("klsh_permutations_clean10k")(_projection_grid("clean10k", [(2, p, 25) for p in (25, 50, 100, 150, 200)]))
for _file in ("noisy10", "noisy30", "noisy50"):
    query(f"klsh_grid_{_file}")(_projection_grid(_file, [(k, p, 25) for k in (2, 3) for p in (100, 150)]))


# comparisons


def _comparison(file: str):
    def run(spark, sf_dir):
        """Every method at a tuned setting, with the criteria."""
        r, t = M._texts(spark, sf_dir, file)
        fields, clean = fields_of(file), file.startswith("clean")
        near = stored(X.epsilon_pairs(t, 0.85))
        vectors = stored(klsh.klsh_vectors(r, fields, 2, 20))
        k, b = (5, 26) if clean else (4, 26)
        blocks = {
            f"graph blocking k={k} b={b}": tlsh.tlsh_blocks(r, fields, k, 100, b), "projection blocking k=2 25 blocks": klsh.klsh_blocks(r, fields, c=25), "projection blocking k=2 100 blocks": klsh.klsh_blocks(r, fields, c=100),
            "threshold neighbours t=0.75": X.tnn_blocks(r, near.where("distance <= 0.75")), "sorted neighbours": X.sorted_tnn_blocks(t, 14 if clean else 20),
            "nearest neighbours of five": X.knn_blocks(vectors, 5), "canopies 0.85": X.canopy_blocks(X.canopies(r.select("rec_id"), near, 0.85, 0.85)),
            "key " + ("birth year" if clean else "postal code"): D.key_blocks(r, ["birth_year" if clean else "postal_code"]),
        }
        found = _scored([_named(stored(x), method=name) for name, x in blocks.items()], r, ["method"]).select("method", "recall", "rr")
        derived = cut(D.derive(r))
        rules = {n: c for n, c in (D.CLEAN if clean else D.NOISY).items() if not c.edit}
        counted = metrics.rates(D.criterion_counts(derived, rules).withColumnRenamed("rule", "method"), r).select("method", "recall", "rr")
        return found.unionByName(counted)

    return run


query("method_comparison_clean10k")(_comparison("clean10k"))
query("method_comparison_noisy10")(_comparison("noisy10"))


@query("t1_all_clean500", " UNION ALL ".join(f"SELECT '{k}' AS rule, kept, kept_true, recall, rr FROM ({M._rates_sql(c.keep_sql(), 'clean500')})" for k, c in D.CLEAN.items()))
def criteria_clean500(spark, sf_dir):
    r = cut(D.derive(persons(spark, sf_dir, "clean500")))
    plain = metrics.rates(D.criterion_counts(r, {k: c for k, c in D.CLEAN.items() if not c.edit}), r).select("rule", "kept", "kept_true", "recall", "rr")
    edited = [metrics.pair_scores(D.criterion_pairs(r, c), r).select(F.lit(k).alias("rule"), "kept", "kept_true", "recall", "rr") for k, c in D.CLEAN.items() if c.edit]
    return _union([plain, *edited])


# files that grow with the table


@query("criteria_all_orders", " UNION ALL ".join(f"SELECT '{k}' AS rule, kept, kept_true, recall, rr FROM ({M._rates_sql(c.keep_sql(), 'clean_all')})" for k, c in M._counted.items()))
def criteria_all_orders(spark, sf_dir):
    """Criteria without an edit distance over the file made of all orders, counted without pairs."""
    r = cut(D.derive(persons(spark, sf_dir, "clean_all")))
    return metrics.rates(D.criterion_counts(r, M._counted), r).select("rule", "kept", "kept_true", "recall", "rr")


@query("sorted_tnn_all_orders", M._block_rates_sql("clean_all", M._sorted_sql("clean_all", 6), "6 AS t"))
def sorted_tnn_all_orders(spark, sf_dir):
    r, t = M._texts(spark, sf_dir, "clean_all")
    return metrics.block_scores(X.sorted_tnn_blocks(t, 6).withColumn("t", F.lit(6)), r, ["t"]).select("t", "recall", "rr", "blocks", "max_block")


@query("blocking_all_orders")
def blocking_all_orders(spark, sf_dir):
    """Graph and projection blocking over the file made of all orders."""
    # short rows that cost much each: spread by rows, not by bytes
    r = stored(persons(spark, sf_dir, "clean_all").repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "rec_id"))
    fields = fields_of("clean_all")
    blocks = {"graph blocking k=5 b=26": tlsh.tlsh_blocks(r, fields, 5, 100, 26), "projection blocking k=2 100 blocks": klsh.klsh_blocks(r, fields, 2, 150, 100, 5)}
    return _scored([_named(stored(b), method=name) for name, b in blocks.items()], r, ["method"])


@query("errors_and_richer_text")
def errors_and_richer_text(spark, sf_dir):
    """Graph and projection blocking over 1, 3 and 5 errors a copy, with and without the whole text of a document that the copies share."""
    parts = []
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    docs.createOrReplaceTempView("documents")
    spark.read.parquet(f"{sf_dir}/orders.parquet").createOrReplaceTempView("orders")
    n_docs = max(1, docs.count())
    texts = docs.groupBy((F.col("doc_id") % n_docs).alias("d")).agg(F.min_by(F.coalesce("text", F.lit("")), "doc_id").alias("extra"))
    for errors in (1, 3, 5):
        r = spark.sql(noisy_sql("spark", 10, 2000, errors=errors))
        # few rows of long texts: shingling them is the work, so they are spread by rows, not by bytes
        r = stored(r.join(texts, F.col("entity_id") % n_docs == F.col("d"), "left").drop("d").repartition(8, "rec_id"))
        fields = fields_of("noisy10")
        for rich, own in ((False, fields), (True, [*fields, "extra"])):
            for name, blocks in (("graph", tlsh.tlsh_blocks(r, own, 4, 100, 26)), ("projection", klsh.klsh_blocks(r, own, 2, 100, 25, 5))):
                scored = metrics.block_scores(_named(blocks, errors=errors, rich=rich, method=name), r, ["errors", "rich", "method"])
                parts.append(cut(scored.select("errors", "rich", "method", "recall", "rr")))
    return _union(parts)


_sizes = (500, 2000, 10_000)


@query("complexity_measured", " UNION ALL ".join(f"SELECT {n} AS n, (SELECT count(DISTINCT term) FROM ({M._terms_sql('clean10k', 2).replace(file_sql('duckdb', 'clean10k'), file_sql('duckdb', 'clean10k', n))})) AS vocabulary, CAST(sum(v * v) AS BIGINT) AS sum_v2, CAST(sum(v) AS BIGINT) AS keys, max(v) AS max_v FROM (SELECT band, key, count(*) AS v FROM ({M._keys_sql('clean10k', 5, 100, 22).replace(file_sql('duckdb', 'clean10k'), file_sql('duckdb', 'clean10k', n))}) GROUP BY ALL)" for n in _sizes))
def complexity_measured(spark, sf_dir):
    """What the growth formulas speak of, counted over n records: the vocabulary w(n), band keys (n times b)
    and the sum of squared bucket sizes, which leads the cost of graph blocking."""
    parts = []
    for n in _sizes:
        t = cut(shingle.with_text(persons(spark, sf_dir, "clean10k", n), fields_of("clean10k")))
        stats = metrics.bucket_stats(minhash.band_keys(minhash.minhash(t, 5, 100), 100, 22))
        sums = stats.agg(F.sum("sum_v2").alias("sum_v2"), F.max("max_v").alias("max_v"))
        words = t.select(F.explode(shingle.shingle_set(F.col("rec_text"), 2)).alias("x")).agg(F.countDistinct("x").alias("vocabulary"))
        keyed = t.where(F.length("rec_text") > 0).agg((F.count("*") * 22).alias("keys"))
        parts.append(sums.join(words).join(keyed).select(F.lit(n).alias("n"), "vocabulary", "sum_v2", "keys", "max_v"))  # one row each
    return _union(parts)


_timed_sizes = (1250, 2500, 5000, 10_000)


def _times(spark, runs: list[tuple]) -> DataFrame:
    """Seconds from the first step of each run, those that write intermediate tables included, to its last row."""
    rows = []
    for name, n, make in runs:
        began = time.time()
        metrics.timed(make())
        rows.append((name, n, time.time() - began))
    return spark.createDataFrame(rows, "method string, n long, seconds double")


@query("times_against_n")
def times_against_n(spark, sf_dir):
    """Seconds of graph (k=5, b=26) and projection blocking (k=5) over the number of records."""
    files = {n: stored(persons(spark, sf_dir, "clean10k", n)) for n in _timed_sizes}
    fields = fields_of("clean10k")
    metrics.timed(tlsh.tlsh_blocks(files[1250], fields, 5, 100, 26))  # the first run pays for starting workers
    runs = [("graph", n, lambda r=r: tlsh.tlsh_blocks(r, fields, 5, 100, 26)) for n, r in files.items()]
    return _times(spark, runs + [("projection", n, lambda r=r: klsh.klsh_blocks(r, fields, 5, 100, 25, 5)) for n, r in files.items()])


@query("sqrt_time_fit")
def sqrt_time_fit(spark, sf_dir):
    """How straight the root of the time is over n, by method."""
    times = cut(times_against_n(spark, sf_dir))
    return _union([metrics.sqrt_time_fit(times.where(F.col("method") == m)).select(F.lit(m).alias("method"), "slope", "r2") for m in ("graph", "projection")])


@query("times_noisy")
def times_noisy(spark, sf_dir):
    """Seconds of graph blocking (k=4, b=22) at 10, 30 and 50 percent of copies."""
    files = {p: stored(persons(spark, sf_dir, f"noisy{p}")) for p in (10, 30, 50)}
    metrics.timed(tlsh.tlsh_blocks(files[10].limit(100), fields_of("noisy10"), 4))
    return _times(spark, [(f"graph noisy{p}", 10_000, lambda r=r: tlsh.tlsh_blocks(r, fields_of("noisy10"), 4)) for p, r in files.items()])


# documents, pages, turns


@query("document_methods")
def document_methods(spark, sf_dir):
    """Methods on the whole documents against the truth of similar pairs (half of the shingles or more)."""
    t = M._document_texts(spark, sf_dir)
    pairs = cut(M.jaccard_truth_documents(spark, sf_dir).select("id_a", "id_b"))
    r = t.select("rec_id", F.col("rec_text").alias("text"))
    truth = cut(linkage.entities(pairs, r).withColumnRenamed("linked_id", "entity_id"))
    blocks = {
        "graph blocking k=5 b=22": tlsh.tlsh_blocks(r, ["text"]), "projection blocking k=2 25 blocks": klsh.klsh_blocks(r, ["text"], 2, 100, 25, 5, unit=True),
        "threshold neighbours, words": X.tnn_blocks(r, X.epsilon_pairs(t, 0.7, 4)),
    }
    return _scored([_named(stored(b), method=name) for name, b in blocks.items()], truth, ["method"])


def _page_texts(spark, sf_dir) -> DataFrame:
    text = F.regexp_replace(F.regexp_replace("html", r"(?s)<script.*?</script>|<style.*?</style>", " "), "<[^>]*>", " ")
    return spark.read.parquet(f"{sf_dir}/pages.parquet").select(F.col("page_id").alias("rec_id"), F.trim(F.regexp_replace(text, r"\s+", " ")).alias("text"))


@query("tlsh_blocks_pages")
def tlsh_blocks_pages(spark, sf_dir):
    return tlsh.tlsh_blocks(_page_texts(spark, sf_dir), ["text"])


@query("tlsh_blocks_turns")
def tlsh_blocks_turns(spark, sf_dir):
    c = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    return tlsh.tlsh_blocks(c.select((F.col("conv_id") * 10_000 + F.col("turn")).alias("rec_id"), "text"), ["text"], 5, 100, 26)


@query("klsh_blocks_embeddings")
def klsh_blocks_embeddings(spark, sf_dir):
    """K-means blocks of ready vectors, MLlib's engine."""
    v = spark.read.parquet(f"{sf_dir}/embeddings.parquet").where("vec_id is not null and embedding is not null").select(F.col("vec_id").alias("rec_id"), F.col("embedding").cast("array<double>").alias("vec"))
    return klsh.kmeans_blocks(v, 10, 10, engine="mllib")


# arriving records


def _replayed(spark, rows: DataFrame, parts: int = 4) -> DataFrame:
    """Rows written as several files and read back as a stream."""
    folder = f"{checkpoint_root(spark)}/replay-{uuid.uuid4().hex}"
    rows.repartition(parts).write.parquet(folder)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 2).parquet(folder)


@query("stream_band_components", M.SQL["tlsh_components_persons"])
def stream_band_components(spark, sf_dir):
    """Components of the edges that a stateful band index gives as records arrive: the batch's."""
    _, t = M._texts(spark, sf_dir, "clean500")
    keys = minhash.band_keys(minhash.minhash(t, 5, 100), 100, 22)
    edges = S.drained(S.band_index(_replayed(spark, keys)))
    return graph.connected_components(edges, t.select(F.col("rec_id").alias("node"))).select(F.col("node").alias("rec_id"), "component_id")


@query("stream_key_assignment", f"SELECT a.rec_id, min(b.rec_id) AS block_id FROM ({file_sql('duckdb', 'clean500')}) a JOIN ({file_sql('duckdb', 'clean500')}) b ON b.rec_id < 450 AND a.birth_year = b.birth_year WHERE a.rec_id >= 450 GROUP BY a.rec_id")
def stream_key_assignment(spark, sf_dir):
    """Arriving copies to the blocks of birth years that were made of the originals."""
    r = cut(persons(spark, sf_dir, "clean500"))
    blocks = r.where("rec_id < 450").groupBy("birth_year").agg(F.min("rec_id").alias("block_id"))
    arrived = S.assign_arrivals(_replayed(spark, r.where("rec_id >= 450").select("rec_id", "birth_year")), blocks, ["birth_year"])
    return S.drained(arrived).where("block_id is not null").select("rec_id", "block_id")


@query("stream_centroid_assignment", M.SQL["klsh_first_assignment"])
def stream_centroid_assignment(spark, sf_dir):
    """Arriving vectors to the nearest of fitted centroids."""
    r, t = M._texts(spark, sf_dir, "clean500")
    v = cut(klsh.project(klsh.weighted_terms(shingle.shingle_counts(t, 2), r.count()), 20))
    return S.drained(klsh.assign_nearest(_replayed(spark, v), klsh.first_centroids(v, 10)).select("rec_id", "cluster"))


@query("stream_sliding_events", "SELECT w AS window_start, event_type, count(*) AS n FROM (SELECT event_type, unnest([date_trunc('hour', ts) - to_hours(CAST(i AS INT)) FOR i IN range(0, 2)]) AS w FROM events) GROUP BY ALL")
def stream_sliding_events(spark, sf_dir):
    rows = S.drained(S.windowed_blocks(S.replay(spark, sf_dir, "events"), "2 hours", "1 hour"), "complete")
    return rows.groupBy("window_start", "event_type").agg(F.max("n").alias("n"))


@query("stream_session_events", "WITH l AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 1 HOUR THEN 0 ELSE 1 END AS f FROM events), s AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM l) SELECT user_id, min(ts) AS session_start, count(*) AS n FROM s GROUP BY user_id, k")
def stream_session_events(spark, sf_dir):
    rows = S.drained(S.session_blocks(S.replay(spark, sf_dir, "events")), "complete")
    return rows.groupBy("user_id", F.col("session_start").cast("timestamp_ntz").alias("session_start")).agg(F.max("n").alias("n"))


# small operators


@query("sampled_recall", f"""WITH s AS (SELECT * FROM ({file_sql('duckdb', 'clean10k')}) WHERE CAST('0x' || substr(md5('sample|' || entity_id), 1, 8) AS BIGINT) % 4 = 0),
p AS (SELECT (a.birth_year = b.birth_year)::INT AS kept FROM s a JOIN s b ON a.entity_id = b.entity_id AND a.rec_id < b.rec_id) SELECT count(*) AS pairs, round(avg(kept), 6) AS recall, round(1.96 * sqrt(avg(kept) * (1 - avg(kept)) / count(*)), 6) AS margin FROM p""")
def sampled_recall(spark, sf_dir):
    """Recall of birth-year blocks estimated on a quarter of the entities, each with all its records, and the margin of error."""
    r = persons(spark, sf_dir, "clean10k")
    s = cut(r.where(F.conv(F.substring(F.md5(F.concat(F.lit("sample|"), F.col("entity_id").cast("string"))), 1, 8), 16, 10).cast("long") % 4 == 0))
    a, b = (s.select("entity_id", F.col("rec_id").alias(f"id_{x}"), F.col("birth_year").alias(f"y_{x}")) for x in "ab")
    kept = F.avg((F.col("y_a") == F.col("y_b")).cast("int"))
    return a.join(b, "entity_id").where("id_a < id_b").agg(F.count("*").alias("pairs"), F.round(kept, 6).alias("recall"), F.round(1.96 * F.sqrt(kept * (1 - kept) / F.count("*")), 6).alias("margin"))


@query("agreement_subset_counts", f"SELECT g, sum(c * (c - 1) / 2)::DOUBLE AS pairs FROM (SELECT CAST(grouping(first_name, last_name, birth_year) AS BIGINT) AS g, count(*)::DOUBLE AS c FROM ({file_sql('duckdb', 'clean10k')}) GROUP BY GROUPING SETS ((first_name), (last_name), (birth_year), (first_name, last_name), (first_name, birth_year), (last_name, birth_year), (first_name, last_name, birth_year))) GROUP BY g")
def agreement_subset_counts(spark, sf_dir):
    """Pairs that agree on each subset of three fields, from group sizes."""
    persons(spark, sf_dir, "clean10k").createOrReplaceTempView("clean_persons")
    c = spark.sql("SELECT grouping_id(first_name, last_name, birth_year) AS g, count(*) AS c FROM clean_persons GROUP BY GROUPING SETS ((first_name), (last_name), (birth_year), (first_name, last_name), (first_name, birth_year), (last_name, birth_year), (first_name, last_name, birth_year)) ")
    return c.groupBy(F.col("g").cast("long").alias("g")).agg(F.sum(metrics.choose2(F.col("c"))).cast("double").alias("pairs"))


@query("criteria_cube", f"SELECT birth_month, birth_day, count(*) AS n FROM ({file_sql('duckdb', 'clean10k')}) GROUP BY CUBE (birth_month, birth_day)")
def criteria_cube(spark, sf_dir):
    return persons(spark, sf_dir, "clean10k").cube("birth_month", "birth_day").agg(F.count("*").alias("n"))


@query("criteria_keep_filter", f"SELECT rec_id FROM ({file_sql('duckdb', 'clean10k')}) WHERE birth_year = 1950 AND NOT (birth_month = 1 OR birth_day = 1)")
def criteria_keep_filter(spark, sf_dir):
    return persons(spark, sf_dir, "clean10k").where("birth_year = 1950 and not (birth_month = 1 or birth_day = 1)").select("rec_id")


@query("idf_join_back", f"SELECT rec_id, term, round(w, 6) AS w FROM ({M._w_sql('clean500', 2)})")
def idf_join_back(spark, sf_dir):
    r, t = M._texts(spark, sf_dir, "clean500")
    return klsh.weighted_terms(stored(shingle.shingle_counts(t, 2)), r.count()).select("rec_id", "term", F.round("w", 6).alias("w"))


@query("bucket_edges_documents", M.SQL["lsh_pairs_documents"])
def bucket_edges_documents(spark, sf_dir):
    return M.lsh_pairs_documents(spark, sf_dir)


@query("vocab_size_k", " UNION ALL ".join(f"SELECT {k} AS k, count(DISTINCT term) AS n_distinct FROM ({M._terms_sql('clean10k', k)})" for k in (1, 2, 3, 4, 5)))
def vocab_size_k(spark, sf_dir):
    t = M._texts(spark, sf_dir, "clean10k")[1]
    return _union([t.select(F.explode(shingle.shingle_set(F.col("rec_text"), k)).alias("x")).agg(F.lit(k).alias("k"), F.countDistinct("x").alias("n_distinct")) for k in (1, 2, 3, 4, 5)])


@query("age_bucket", f"SELECT CAST(floor(age / 10) * 10 AS BIGINT) AS bucket, count(*) AS n FROM ({file_sql('duckdb', 'noisy10')}) GROUP BY 1")
def age_bucket(spark, sf_dir):
    return persons(spark, sf_dir, "noisy10").groupBy((F.floor(F.col("age") / 10) * 10).alias("bucket")).agg(F.count("*").alias("n"))


@query("signature_similarity_persons", f"WITH s AS MATERIALIZED ({M._signature_sql('clean500', 5, 100)}) SELECT a.rec_id AS id_a, b.rec_id AS id_b, round(list_sum([(x[1] = x[2])::INT FOR x IN list_zip(a.sig, b.sig)]) / 100, 6) AS s FROM s a JOIN s b ON a.entity_id = b.entity_id AND a.rec_id < b.rec_id")
def signature_similarity_persons(spark, sf_dir):
    """Shares of equal signature places of the true pairs."""
    r, t = M._texts(spark, sf_dir, "clean500")
    sig = cut(minhash.minhash(t, 5, 100).join(r.select("rec_id", "entity_id"), "rec_id"))
    a, b = (sig.select(F.col("rec_id").alias(f"id_{x}"), "entity_id", F.col("sig").alias(f"s_{x}")) for x in "ab")
    return a.join(b, "entity_id").where("id_a < id_b").select("id_a", "id_b", F.round(minhash.signature_jaccard(F.col("s_a"), F.col("s_b")), 6).alias("s"))
