"""Queries of the blocking methods, their measures and the experiments, over the person files
and the given tables. SQL states each result anew, mostly over all pairs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from recblock.operators import cluster as X
from recblock.operators import criteria as D
from recblock.operators import graph, klsh, linkage, metrics, minhash, shingle, tlsh
from recblock.session import cut, stored
from recblock.sources.persons import CLEAN_FIELDS, fields_of, file_sql, persons

QUERIES: dict = {}
SQL: dict[str, str] = {}
P31 = minhash.PRIME


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _texts(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    r = cut(persons(spark, sf_dir, name))
    return r, shingle.with_text(r, fields_of(name))


def _document_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").alias("rec_id"), F.col("text").alias("rec_text"))


def _rates_sql(keep: str, file: str) -> str:
    return f"""WITH r AS (SELECT *, substr(first_name, 1, 1) AS initial_f, substr(last_name, 1, 1) AS initial_l{', floor(birth_year / 10) AS decade' if file.startswith('clean') else ''} FROM ({file_sql('duckdb', file)})),
k AS (SELECT count(*) AS kept, coalesce(sum((a.entity_id = b.entity_id)::INT), 0) AS kept_true FROM r a JOIN r b ON a.rec_id < b.rec_id AND {keep}),
t AS (SELECT sum(c * (c - 1) / 2) AS all_true, sum(c) AS n FROM (SELECT count(*)::DOUBLE AS c FROM r GROUP BY entity_id))
SELECT kept::DOUBLE AS kept, kept_true::DOUBLE AS kept_true, round(kept_true / all_true, 6) AS recall, round(1 - kept / (n * (n - 1) / 2), 6) AS rr FROM k, t"""


def _criterion_query(criterion: D.Criterion, file: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = cut(D.derive(persons(spark, sf_dir, file)))
        if criterion.edit:
            return metrics.pair_scores(D.criterion_pairs(r, criterion), r).select("kept", "kept_true", "recall", "rr")
        return metrics.rates(D.criterion_counts(r, {"rule": criterion}).drop("rule"), r).select("kept", "kept_true", "recall", "rr")

    return run


for _rule, _c in D.CLEAN.items():
    query(_rule, _rates_sql(_c.keep_sql(), "clean10k"))(_criterion_query(_c, "clean10k"))
for _file in ("noisy10", "noisy30", "noisy50"):
    for _rule, _c in D.NOISY.items():
        query(f"{_rule}_{_file}", _rates_sql(_c.keep_sql(), _file))(_criterion_query(_c, _file))

_counted = {k: c for k, c in D.CLEAN.items() if not c.edit}


@query("criteria_counts_incl_excl", " UNION ALL ".join(f"SELECT '{k}' AS rule, kept, kept_true FROM ({_rates_sql(c.keep_sql(), 'clean10k')})" for k, c in _counted.items()))
def criteria_counts(spark, sf_dir):
    return D.criterion_counts(cut(D.derive(persons(spark, sf_dir, "clean10k"))), _counted)


_steps = [("t1_10", D.CLEAN["t1_10"]), ("t1_11", D.CLEAN["t1_11"]), ("t1_12", D.CLEAN["t1_12"])]


@query("cascade_persons", f"WITH r AS (SELECT *, substr(first_name, 1, 1) AS initial_f, substr(last_name, 1, 1) AS initial_l FROM ({file_sql('duckdb', 'clean10k')})) " + " UNION ALL ".join(f"SELECT {i} AS stage, count(*) AS pairs_left, sum((a.entity_id = b.entity_id)::INT) AS true_left FROM r a JOIN r b ON a.rec_id < b.rec_id AND " + " AND ".join(c.keep_sql() for _, c in _steps[: i + 1]) for i in range(3)))
def cascade_persons(spark, sf_dir):
    return D.cascade(cut(D.derive(persons(spark, sf_dir, "clean10k"))), _steps)


# shingles, signatures, bands

_text_sql = lambda file: "SELECT doc_id AS rec_id, doc_id AS entity_id, text AS rec_text FROM documents WHERE text <> ''" if file == "documents" else f"SELECT rec_id, entity_id, concat_ws(' ', {', '.join(fields_of(file))}) AS rec_text FROM ({file_sql('duckdb', file)})"
_terms_sql = lambda file, k: f"SELECT rec_id, entity_id, unnest(CASE WHEN length(rec_text) < {k} THEN [rec_text] ELSE list_transform(range(1, length(rec_text) - {k - 2}), lambda i: substr(rec_text, i, {k})) END) AS term FROM ({_text_sql(file)})"


@query("shingle_counts_persons", f"SELECT rec_id, term, count(*) AS tf FROM ({_terms_sql('clean500', 2)}) GROUP BY ALL")
def shingle_counts_persons(spark, sf_dir):
    return shingle.shingle_counts(_texts(spark, sf_dir, "clean500")[1], 2)


@query("shingle_counts_documents", f"SELECT 5 AS k, count(DISTINCT term) AS n_distinct, count(*) AS n_shingles FROM ({_terms_sql('documents', 5)})")
def shingle_counts_documents(spark, sf_dir):
    t = _document_texts(spark, sf_dir)
    return t.select(F.explode(shingle.char_shingles(F.col("rec_text"), 5)).alias("t")).agg(F.lit(5).alias("k"), F.countDistinct("t").alias("n_distinct"), F.count("*").alias("n_shingles"))


@query("word_shingle_counts", r"""WITH t AS (SELECT doc_id, unnest(list_filter(string_split_regex(lower(text), '\s+'), lambda x: x <> '')) AS x, generate_subscripts(list_filter(string_split_regex(lower(text), '\s+'), lambda x: x <> ''), 1) AS i FROM documents),
s AS (SELECT doc_id, i, x AS s1, x || ' ' || lead(x) OVER w AS s2, x || ' ' || lead(x) OVER w || ' ' || lead(x, 2) OVER w AS s3, count(*) OVER (PARTITION BY doc_id) AS n FROM t WINDOW w AS (PARTITION BY doc_id ORDER BY i)),
e AS (SELECT 1 AS w, s1 AS s FROM s UNION ALL SELECT 2, coalesce(s2, CASE WHEN n < 2 THEN s1 END) FROM s UNION ALL SELECT 3, coalesce(s3, CASE WHEN n < 3 AND i = 1 THEN coalesce(s2, s1) END) FROM s)
SELECT w, count(DISTINCT s) AS n_distinct, count(s) AS n_shingles FROM e WHERE s IS NOT NULL GROUP BY w""")
def word_shingle_counts(spark, sf_dir):
    t = _document_texts(spark, sf_dir)
    parts = [t.select(F.lit(w).alias("w"), F.explode(shingle.word_shingles(F.col("rec_text"), w)).alias("s")) for w in (1, 2, 3)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).groupBy("w").agg(F.countDistinct("s").alias("n_distinct"), F.count("*").alias("n_shingles"))


@query("shingle_density", f"SELECT 2 AS k, count(DISTINCT term) AS vocabulary, count(*) AS filled, round(count(*) / (count(DISTINCT rec_id) * count(DISTINCT term)), 9) AS density FROM (SELECT DISTINCT rec_id, term FROM ({_terms_sql('clean10k', 2)}))")
def shingle_density(spark, sf_dir):
    return shingle.shingle_density(_texts(spark, sf_dir, "clean10k")[1], 2)


def _signature_sql(file: str, k: int, p: int) -> str:
    family = "[" + ", ".join(f"{{'a': {a}::BIGINT, 'c': {c}::BIGINT}}" for a, c in minhash.hash_family(p)) + "]"
    return f"""SELECT rec_id, any_value(entity_id) AS entity_id, list_transform({family}, lambda f: list_min(list_transform(list(h), lambda x: (x * f.a + f.c) % {P31}))) AS sig
FROM (SELECT DISTINCT rec_id, entity_id, CAST('0x' || substr(md5(term), 1, 8) AS BIGINT) % {P31} AS h FROM ({_terms_sql(file, k)})) GROUP BY rec_id"""


def _keys_sql(file: str, k: int, p: int, b: int) -> str:
    parts, at = [], 1
    for i, r in enumerate(minhash.band_sizes(p, b)):
        parts.append(f"{{'band': {i}, 'key': md5(array_to_string(sig[{at}:{at + r - 1}], ','))}}")
        at += r
    return f"SELECT rec_id, entity_id, unnest([{', '.join(parts)}], recursive := true) FROM ({_signature_sql(file, k, p)})"


@query("minhash_signatures_persons", f"SELECT rec_id, unnest(range(0, 100)) AS i, unnest(sig) AS value FROM ({_signature_sql('clean500', 5, 100)})")
def minhash_signatures_persons(spark, sf_dir):
    return minhash.minhash(_texts(spark, sf_dir, "clean500")[1], 5, 100).select("rec_id", F.posexplode("sig").alias("i", "value"))


@query("band_keys_persons", f"SELECT rec_id, band, key FROM ({_keys_sql('clean500', 5, 100, 22)})")
def band_keys_persons(spark, sf_dir):
    return minhash.band_keys(minhash.minhash(_texts(spark, sf_dir, "clean500")[1], 5, 100, arrow=False), 100, 22)


@query("bucket_stats_persons", f"SELECT band, count(*) AS buckets, max(v) AS max_v, CAST(sum(v * v) AS BIGINT) AS sum_v2 FROM (SELECT band, key, count(*) AS v FROM ({_keys_sql('clean10k', 5, 100, 22)}) GROUP BY ALL) GROUP BY band")
def bucket_stats_persons(spark, sf_dir):
    return metrics.bucket_stats(minhash.band_keys(minhash.minhash(_texts(spark, sf_dir, "clean10k")[1], 5, 100), 100, 22))


_edges_sql = lambda file, k, b: f"SELECT a.rec_id AS id_a, b.rec_id AS id_b, count(*) AS bands_hit, any_value(a.entity_id = b.entity_id) AS same FROM ({_keys_sql(file, k, 100, b)}) a JOIN ({_keys_sql(file, k, 100, b)}) b USING (band, key) WHERE a.rec_id < b.rec_id GROUP BY ALL"


@query("lsh_pairs_persons", f"SELECT id_a, id_b, bands_hit FROM ({_edges_sql('clean10k', 5, 22)})")
def lsh_pairs_persons(spark, sf_dir):
    return minhash.lsh_pairs(_texts(spark, sf_dir, "clean10k")[1])


_grid = [(4, 22), (4, 26), (5, 22), (5, 26)]


@query("tlsh_raw_recall_rr", " UNION ALL ".join(f"SELECT {k} AS k, {b} AS b, round(sum(same::INT) / 50, 6) AS recall, round(1 - count(*) / 124750, 6) AS rr FROM ({_edges_sql('clean500', k, b)})" for k, b in _grid))
def tlsh_raw_recall_rr(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    out = None
    for k, b in _grid:
        part = minhash.lsh_pairs(t, k, 100, b).select("id_a", "id_b", F.lit(k).alias("k"), F.lit(b).alias("b"))
        out = part if out is None else out.unionByName(part)
    return metrics.pair_scores(out, r, ["k", "b"]).select("k", "b", "recall", "rr")


@query("lsh_neighbors_persons", f"""WITH e AS MATERIALIZED ({_edges_sql('clean500', 5, 22)}), b AS (SELECT id_a, id_b FROM e UNION ALL SELECT id_b, id_a FROM e), t AS MATERIALIZED (SELECT DISTINCT rec_id, term FROM ({_terms_sql('clean500', 5)})),
n AS (SELECT rec_id, count(*) AS n FROM t GROUP BY rec_id), j AS (SELECT id_a, id_b, count(y.term) AS k FROM b JOIN t x ON x.rec_id = id_a LEFT JOIN t y ON y.rec_id = id_b AND y.term = x.term GROUP BY ALL),
r AS (SELECT id_a, id_b, round(k / (p.n + q.n - k), 6) AS jaccard FROM j JOIN n p ON p.rec_id = id_a JOIN n q ON q.rec_id = id_b)
SELECT id_a, id_b, jaccard, CAST(rank AS INT) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY id_a ORDER BY jaccard DESC, id_b) AS rank FROM r) WHERE rank <= 3""")
def lsh_neighbors_persons(spark, sf_dir):
    return minhash.lsh_neighbors(_texts(spark, sf_dir, "clean500")[1], 3)


@query("tlsh_components_persons", f"""WITH RECURSIVE k AS MATERIALIZED ({_keys_sql('clean500', 5, 100, 22)}),
e AS MATERIALIZED (SELECT DISTINCT a.rec_id AS s, b.rec_id AS d FROM k a JOIN k b USING (band, key)), reach AS (SELECT DISTINCT s AS rec_id, s AS c FROM e UNION SELECT e.d, reach.c FROM reach JOIN e ON e.s = reach.rec_id WHERE reach.c <= e.d)
SELECT rec_id, min(c) AS component_id FROM reach GROUP BY rec_id""")
def tlsh_components_persons(spark, sf_dir):
    _, t = _texts(spark, sf_dir, "clean500")
    keys = minhash.band_keys(minhash.minhash(t, 5, 100), 100, 22)
    return graph.connected_components(minhash.bucket_stars(keys), t.select(F.col("rec_id").alias("node"))).select(F.col("node").alias("rec_id"), "component_id")


@query("tlsh_blocks_persons")
def tlsh_blocks_persons(spark, sf_dir):
    return tlsh.tlsh_blocks(cut(persons(spark, sf_dir, "clean10k")), CLEAN_FIELDS)


@query("tlsh_blocks_documents")
def tlsh_blocks_documents(spark, sf_dir):
    """Flagship: graph blocks of the whole documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").alias("rec_id"), "text")
    return tlsh.tlsh_blocks(docs, ["text"])


@query("lsh_pairs_documents", f"SELECT id_a, id_b, bands_hit FROM ({_edges_sql('documents', 5, 22)})")
def lsh_pairs_documents(spark, sf_dir):
    return minhash.lsh_pairs(_document_texts(spark, sf_dir))


@query("minhash_signatures_documents", f"SELECT rec_id, unnest(range(0, 100)) AS i, unnest(sig) AS value FROM ({_signature_sql('documents', 5, 100)})")
def minhash_signatures_documents(spark, sf_dir):
    return minhash.minhash(_document_texts(spark, sf_dir), 5, 100).select("rec_id", F.posexplode("sig").alias("i", "value"))


@query("hottest_buckets_topk", f"SELECT band, key, count(*) AS n FROM ({_keys_sql('clean10k', 5, 100, 22)}) GROUP BY ALL ORDER BY n DESC, band, key LIMIT 10")
def hottest_buckets(spark, sf_dir):
    keys = minhash.band_keys(minhash.minhash(_texts(spark, sf_dir, "clean10k")[1], 5, 100), 100, 22)
    return keys.groupBy("band", "key").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "band", "key").limit(10)


_jaccard_cte = f"""t AS MATERIALIZED (SELECT DISTINCT rec_id, term FROM ({_terms_sql('documents', 5)})), n AS (SELECT rec_id, count(*) AS n FROM t GROUP BY rec_id),
c AS (SELECT a.rec_id AS id_a, b.rec_id AS id_b, count(*) AS k FROM t a JOIN t b ON a.term = b.term AND a.rec_id < b.rec_id GROUP BY ALL)"""


@query("jaccard_truth_documents", f"""WITH {_jaccard_cte}
SELECT id_a, id_b, round(k / (x.n + y.n - k), 6) AS jaccard FROM c JOIN n x ON x.rec_id = id_a JOIN n y ON y.rec_id = id_b WHERE k / (x.n + y.n - k) >= 0.5""")
def jaccard_truth_documents(spark, sf_dir):
    """Exact similarity of at least one half among the documents."""
    return minhash.similar_pairs(_document_texts(spark, sf_dir), 50, 5)


# projection blocking

_tf_sql = lambda file, k: f"SELECT rec_id, term, count(*) AS tf FROM ({_terms_sql(file, k)}) GROUP BY ALL"
_w_sql = lambda file, k: f"SELECT rec_id, term, tf * ln((SELECT count(*) FROM ({file_sql('duckdb', file)})) / df) AS w FROM ({_tf_sql(file, k)}) JOIN (SELECT term, count(*) AS df FROM ({_tf_sql(file, k)}) GROUP BY term) USING (term)"
_vec_sql = lambda file, k, p: f"SELECT rec_id, j, round(sum(w * CASE WHEN CAST('0x' || substr(md5('42|' || term || '|' || j), 1, 1) AS BIGINT) % 2 = 0 THEN 1 ELSE -1 END / sqrt({p})), 9) AS value FROM ({_w_sql(file, k)}), range({p}) AS js(j) GROUP BY rec_id, j"


@query("idf_persons", f"SELECT term, df, round(ln(500 / df), 6) AS idf FROM (SELECT term, count(*) AS df FROM ({_tf_sql('clean500', 2)}) GROUP BY term)")
def idf_persons(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    return klsh.idf(shingle.shingle_counts(t, 2), r.count()).select("term", "df", F.round("idf", 6).alias("idf"))


@query("bag_inner_products", f"SELECT a.rec_id AS id_a, b.rec_id AS id_b, round(sum(a.w * b.w), 6) AS sim FROM ({_w_sql('clean500', 2)}) a JOIN ({_w_sql('clean500', 2)}) b ON a.term = b.term AND a.rec_id < b.rec_id GROUP BY ALL")
def bag_inner_products(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    return klsh.bag_similarity(klsh.weighted_terms(shingle.shingle_counts(t, 2), r.count())).select("id_a", "id_b", F.round("sim", 6).alias("sim"))


@query("projected_vectors_persons", f"SELECT rec_id, CAST(j AS INT) AS j, round(value, 6) AS value FROM ({_vec_sql('clean500', 2, 20)})")
def projected_vectors_persons(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    v = klsh.project(klsh.weighted_terms(shingle.shingle_counts(t, 2), r.count()), 20)
    return v.select("rec_id", F.posexplode("vec").alias("j", "value")).select("rec_id", "j", F.round("value", 6).alias("value"))


_assign_sql = f"""v AS MATERIALIZED ({_vec_sql('clean500', 2, 20)}), o AS (SELECT rec_id, row_number() OVER (ORDER BY md5('42|' || rec_id), rec_id) - 1 AS cluster FROM (SELECT DISTINCT rec_id FROM v)),
c AS MATERIALIZED (SELECT cluster, j, value FROM o JOIN v USING (rec_id) WHERE cluster < 10),
n AS (SELECT cluster, sum(value * value) AS q FROM c GROUP BY cluster), d AS (SELECT v.rec_id, c.cluster, round(any_value(n.q) - 2 * sum(v.value * c.value), 9) AS d FROM v JOIN c USING (j) JOIN n USING (cluster) GROUP BY v.rec_id, c.cluster),
a AS (SELECT rec_id, CAST(cluster AS INT) AS cluster FROM (SELECT *, row_number() OVER (PARTITION BY rec_id ORDER BY d, cluster) AS r FROM d) WHERE r = 1)"""


@query("klsh_first_assignment", f"WITH {_assign_sql} SELECT rec_id, cluster FROM a")
def klsh_first_assignment(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    v = cut(klsh.project(klsh.weighted_terms(shingle.shingle_counts(t, 2), r.count()), 20))
    return klsh.assign_nearest(v, klsh.first_centroids(v, 10)).select("rec_id", "cluster")


@query("klsh_lloyd_step", f"WITH {_assign_sql} SELECT cluster, CAST(j AS INT) AS j, round(avg(value), 5) AS mean FROM a JOIN v USING (rec_id) GROUP BY cluster, j")
def klsh_lloyd_step(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    v = cut(klsh.project(klsh.weighted_terms(shingle.shingle_counts(t, 2), r.count()), 20))
    m = klsh.lloyd_step(v, klsh.first_centroids(v, 10))
    return spark.createDataFrame([(i, j, float(m[i, j])) for i in range(m.shape[0]) for j in range(m.shape[1])], "cluster int, j int, mean double").withColumn("mean", F.round("mean", 5))


@query("klsh_blocks_persons")
def klsh_blocks_persons(spark, sf_dir):
    return klsh.klsh_blocks(cut(persons(spark, sf_dir, "clean10k")), CLEAN_FIELDS)


@query("klsh_dispersion")
def klsh_dispersion(spark, sf_dir):
    return metrics.block_dispersion(klsh_blocks_persons(spark, sf_dir))


# cluster-based baselines

_near_cte = lambda t: f"""w AS MATERIALIZED (SELECT rec_id, term, w FROM ({_w_sql('clean500', 2)}) WHERE w > 0), q AS (SELECT rec_id, sqrt(sum(w * w)) AS norm FROM w GROUP BY rec_id),
u AS MATERIALIZED (SELECT w.rec_id, term, w / norm AS w FROM w JOIN q ON q.rec_id = w.rec_id), near AS MATERIALIZED (SELECT * FROM (SELECT a.rec_id AS id_a, b.rec_id AS id_b, sqrt(greatest(0, round(2 - 2 * sum(a.w * b.w), 9))) AS distance FROM u a JOIN u b ON a.term = b.term AND a.rec_id < b.rec_id GROUP BY ALL) WHERE distance <= {t})"""  # noqa: E731


@query("tnn_blocks_persons", f"""WITH RECURSIVE {_near_cte(0.9)}, e AS (SELECT id_a AS s, id_b AS d FROM near UNION ALL SELECT id_b, id_a FROM near),
reach AS (SELECT rec_id, rec_id AS c FROM ({file_sql('duckdb', 'clean500')}) UNION SELECT e.d, reach.c FROM reach JOIN e ON e.s = reach.rec_id)
SELECT rec_id, min(c) AS block_id FROM reach GROUP BY rec_id""")
def tnn_blocks_persons(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    return X.tnn_blocks(r, X.epsilon_pairs(t, 0.9))


_near_sql = "list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: power(CAST(z[1] AS DOUBLE) - CAST(z[2] AS DOUBLE), 2))) <= 1.21"


@query("tnn_blocks_embeddings", f"""WITH RECURSIVE e AS MATERIALIZED (SELECT a.vec_id AS s, b.vec_id AS d FROM embeddings a JOIN embeddings b ON {_near_sql}),
reach AS (SELECT vec_id, vec_id AS c FROM embeddings UNION SELECT e.d, reach.c FROM reach JOIN e ON e.s = reach.vec_id WHERE reach.c <= e.d)
SELECT vec_id AS rec_id, min(c) AS block_id FROM reach GROUP BY vec_id""")
def tnn_blocks_embeddings(spark, sf_dir):
    """Nearest-neighbour clusters of ready vectors within 1.1: all blocks against each other, a forest of each."""
    v = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("rec_id"), F.col("embedding").cast("array<double>").alias("vec"))
    return X.tnn_blocks(v, X.near_forest(v, 1.1))


@query("sorted_tnn_blocks", f"SELECT rec_id, CAST(sum(n) OVER (ORDER BY rec_text, rec_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS block_id FROM (SELECT rec_id, rec_text, CASE WHEN lag(rec_text) OVER w IS NULL OR levenshtein(rec_text, lag(rec_text) OVER w) > 8 THEN 1 ELSE 0 END AS n FROM ({_text_sql('clean10k')}) WINDOW w AS (ORDER BY rec_text, rec_id))")
def sorted_tnn(spark, sf_dir):
    return X.sorted_tnn_blocks(_texts(spark, sf_dir, "clean10k")[1], 8)


_block_rates_sql = lambda file, blocks, label: f"""SELECT {label}, round(sum(tr) / (SELECT sum(c * (c - 1) / 2) FROM (SELECT count(*)::DOUBLE AS c FROM ({file_sql('duckdb', file)}) GROUP BY entity_id)), 6) AS recall,
round(1 - sum(s * (s - 1) / 2) / (SELECT count(*)::DOUBLE * (count(*) - 1) / 2 FROM ({file_sql('duckdb', file)})), 6) AS rr, count(*) AS blocks, CAST(max(s) AS BIGINT) AS max_block
FROM (SELECT block_id, sum(c)::DOUBLE AS s, sum(c * (c - 1) / 2)::DOUBLE AS tr FROM (SELECT block_id, entity_id, count(*) AS c FROM ({blocks}) GROUP BY ALL) GROUP BY block_id)"""  # noqa: E731
_sorted_sql = lambda file, t: f"SELECT rec_id, entity_id, sum(n) OVER (ORDER BY rec_text, rec_id ROWS UNBOUNDED PRECEDING) AS block_id FROM (SELECT rec_id, entity_id, rec_text, CASE WHEN lag(rec_text) OVER w IS NULL OR levenshtein(rec_text, lag(rec_text) OVER w) > {t} THEN 1 ELSE 0 END AS n FROM ({_text_sql(file)}) WINDOW w AS (ORDER BY rec_text, rec_id))"


@query("sorted_tnn_sweep", " UNION ALL ".join(_block_rates_sql("clean10k", _sorted_sql("clean10k", t), f"{t} AS t") for t in (2, 6, 10, 14, 18)))
def sorted_tnn_sweep(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean10k")
    out = None
    for d in (2, 6, 10, 14, 18):
        part = X.sorted_tnn_blocks(t, d).withColumn("t", F.lit(d))
        out = part if out is None else out.unionByName(part)
    return metrics.block_scores(out, r, ["t"]).select("t", "recall", "rr", "blocks", "max_block")


@query("knn_blocks_persons")
def knn_blocks_persons(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    v = klsh.project(klsh.weighted_terms(shingle.shingle_counts(t, 2), r.count()), 20)
    return X.knn_blocks(cut(v), 5)


def _cover(spark, sf_dir, t1=1.1, t2=0.9):
    r, t = _texts(spark, sf_dir, "clean500")
    return r, X.canopies(r.select("rec_id"), cut(X.epsilon_pairs(t, t1)), t1, t2)


# Bases in SQL: one record after the other in the order of digests, with the list of bases so far.
_bases_cte = f"""{_near_cte(1.1)}, o AS MATERIALIZED (SELECT rec_id, row_number() OVER (ORDER BY md5('42|' || rec_id)) AS i FROM ({file_sql('duckdb', 'clean500')})),
nb AS MATERIALIZED (SELECT o.i, o.rec_id, list(x.d) FILTER (WHERE x.d IS NOT NULL) AS near_ones FROM o LEFT JOIN (SELECT id_a AS s, id_b AS d FROM near WHERE distance <= 0.9 UNION ALL SELECT id_b, id_a FROM near WHERE distance <= 0.9) x ON x.s = o.rec_id GROUP BY ALL),
step AS (SELECT CAST(0 AS BIGINT) AS i, CAST([] AS BIGINT[]) AS chosen UNION ALL SELECT nb.i, CASE WHEN list_has_any(chosen, coalesce(near_ones, [])) THEN chosen ELSE list_append(chosen, nb.rec_id) END FROM step JOIN nb ON nb.i = step.i + 1),
bases AS (SELECT unnest(chosen) AS base FROM step WHERE i = (SELECT max(i) FROM o)),
cover AS (SELECT base AS rec_id, base AS canopy_id FROM bases UNION SELECT id_b, id_a FROM near JOIN bases ON base = id_a UNION SELECT id_a, id_b FROM near JOIN bases ON base = id_b)"""


@query("canopy_cover", f"WITH RECURSIVE {_bases_cte} SELECT rec_id, canopy_id FROM cover")
def canopy_cover(spark, sf_dir):
    return _cover(spark, sf_dir)[1]


@query("canopy_bases", f"WITH RECURSIVE {_bases_cte} SELECT base FROM bases")
def canopy_bases(spark, sf_dir):
    return _cover(spark, sf_dir)[1].select(F.col("canopy_id").alias("base")).distinct()


@query("canopy_atoms", f"WITH RECURSIVE {_bases_cte} SELECT rec_id, array_to_string(list_sort(list(canopy_id)), ',') AS block_id FROM cover GROUP BY rec_id")
def canopy_atoms(spark, sf_dir):
    return X.canopy_blocks(_cover(spark, sf_dir)[1], "atoms")


@query("canopy_sweep")
def canopy_sweep(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    near = cut(X.epsilon_pairs(t, 1.25))
    out = None
    for t1, t2 in ((0.6, 0.6), (0.9, 0.6), (0.9, 0.9), (1.1, 0.9), (1.25, 1.1)):
        part = X.canopy_pairs(cut(X.canopies(r.select("rec_id"), near, t1, t2))).select("id_a", "id_b", F.lit(t1).alias("t1"), F.lit(t2).alias("t2"))
        out = part if out is None else out.unionByName(part)
    return metrics.pair_scores(out, r, ["t1", "t2"]).select("t1", "t2", "recall", "rr")


_letters = "aceghikmnoprstuvwz"


@query("reference_blocks_persons", f"""WITH RECURSIVE refs AS (SELECT unnest(string_split('{','.join(_letters)}', ',')) AS ref), n AS MATERIALIZED (SELECT rec_id, coalesce((SELECT max(ref) FROM refs WHERE ref <= last_name), '') AS ref FROM ({file_sql('duckdb', 'clean10k')})),
s AS MATERIALIZED (SELECT ref, c, row_number() OVER (ORDER BY ref) AS i FROM (SELECT ref, count(*) AS c FROM n GROUP BY ref)),
g AS (SELECT CAST(0 AS BIGINT) AS i, CAST('' AS VARCHAR) AS ref, CAST(-1 AS BIGINT) AS own, CAST(0 AS BIGINT) AS grp, CAST(0 AS BIGINT) AS held UNION ALL SELECT s.i, s.ref, g.grp, CASE WHEN g.held + s.c >= 500 THEN g.grp + 1 ELSE g.grp END, CASE WHEN g.held + s.c >= 500 THEN 0 ELSE g.held + s.c END FROM g JOIN s ON s.i = g.i + 1),
z AS (SELECT arg_max(grp, i) AS last_grp, arg_max(held, i) AS last_held FROM g)
SELECT n.rec_id, n.ref, CASE WHEN last_held > 0 AND last_grp > 0 THEN least(own, last_grp - 1) ELSE own END AS block_id FROM n JOIN g ON g.ref = n.ref AND g.i > 0, z""")
def reference_blocks_persons(spark, sf_dir):
    r = persons(spark, sf_dir, "clean10k")
    refs = spark.createDataFrame([(c,) for c in _letters], "last_name string")
    return X.reference_blocks(cut(r), refs, "last_name", 500)


# measures, comparisons, linkage

@query("comparison_cost_birth_year", f"SELECT count(*) AS blocks, max(s) AS n_max, CAST(count(*) * max(s) * max(s) AS DOUBLE) AS bound_cost, CAST(sum(s * s) AS DOUBLE) AS sum_cost FROM (SELECT birth_year, count(*) AS s FROM ({file_sql('duckdb', 'clean10k')}) GROUP BY 1)")
def comparison_cost_birth_year(spark, sf_dir):
    return metrics.comparison_cost(D.key_blocks(persons(spark, sf_dir, "clean10k"), ["birth_year"]), 2)


@query("anonymity_level_birth_year", f"SELECT min(s) AS level, CAST(sum((s < 100)::INT) AS BIGINT) AS below_k FROM (SELECT birth_year, count(*) AS s FROM ({file_sql('duckdb', 'clean10k')}) GROUP BY 1)")
def anonymity_level_birth_year(spark, sf_dir):
    return metrics.anonymity_level(D.key_blocks(persons(spark, sf_dir, "clean10k"), ["birth_year"]), 100)


_growth_sql = f"WITH r AS (SELECT doc_id AS rec_id, row_number() OVER (ORDER BY doc_id) AS p FROM documents), t AS (SELECT term, min(p) AS f FROM ({_terms_sql('documents', 3)}) JOIN r USING (rec_id) GROUP BY term), v AS (SELECT DISTINCT n FROM (SELECT CAST(ceil(count(*) / d) AS BIGINT) AS n FROM r, (VALUES (16), (8), (4), (2), (1)) AS s(d) GROUP BY d)) SELECT n, count(*) AS w_n FROM t JOIN v ON f <= n GROUP BY n"


@query("vocab_growth_documents", _growth_sql)
def vocab_growth_documents(spark, sf_dir):
    """Growth to the whole table, in order of id."""
    return shingle.vocabulary_growth(_document_texts(spark, sf_dir), 3)


@query("vocab_growth_fit", f"SELECT round(regr_slope(ln(w_n), ln(n)), 6) AS beta FROM ({_growth_sql})")
def vocab_growth_fit(spark, sf_dir):
    return shingle.growth_exponent(vocab_growth_documents(spark, sf_dir))


_rated_sql = " UNION ALL ".join(f"SELECT '{k}' AS method, recall, rr FROM ({_rates_sql(c.keep_sql(), 'clean10k')})" for k, c in _counted.items())


@query("dominated_settings", f"WITH s AS MATERIALIZED ({_rated_sql}) SELECT a.method AS better, b.method AS worse FROM s a JOIN s b ON a.recall >= b.recall AND a.rr >= b.rr AND (a.recall > b.recall OR a.rr > b.rr)")
def dominated_settings(spark, sf_dir):
    """Which criteria on the clean file are no better than another in recall and in reduction."""
    r = cut(D.derive(persons(spark, sf_dir, "clean10k")))
    return metrics.dominated(cut(metrics.rates(D.criterion_counts(r, _counted), r).withColumnRenamed("rule", "method")))


@query("best_setting", f"SELECT method, recall, rr FROM ({_rated_sql}) WHERE rr >= 0.98 ORDER BY recall DESC, rr DESC, method LIMIT 1")
def best_setting(spark, sf_dir):
    """The criterion of highest recall among those that leave out 98 percent of the pairs."""
    r = cut(D.derive(persons(spark, sf_dir, "clean10k")))
    return metrics.best_setting(metrics.rates(D.criterion_counts(r, _counted), r).withColumnRenamed("rule", "method").select("method", "recall", "rr"), 0.98)


@query("klsh_grid_persons")
def klsh_grid_persons(spark, sf_dir):
    """Recall and reduction over letters per shingle, blocks, and length of the projection."""
    r = cut(persons(spark, sf_dir, "clean10k"))
    out = None
    for k, p in ((1, 100), (2, 100), (2, 150), (3, 100), (4, 100)):
        v = cut(klsh.klsh_vectors(r, CLEAN_FIELDS, k, p))
        for c in (10, 25, 100):
            part = klsh.kmeans_blocks(v, c, 5).select("rec_id", "block_id", F.lit(k).alias("k"), F.lit(p).alias("p"), F.lit(c).alias("cells"))
            out = part if out is None else out.unionByName(part)
    return metrics.block_scores(out, r, ["k", "p", "cells"]).select("k", "p", "cells", "recall", "rr", "max_block")


@query("cross_file_pairs_persons", f"SELECT a.rec_id AS id_a, b.rec_id AS id_b FROM ({file_sql('duckdb', 'clean10k')}) a JOIN ({file_sql('duckdb', 'clean10k')}) b ON a.birth_year = b.birth_year AND a.birth_month = b.birth_month AND a.birth_day = b.birth_day AND a.rec_id < 9000 AND b.rec_id >= 9000")
def cross_file_pairs_persons(spark, sf_dir):
    r = persons(spark, sf_dir, "clean10k").withColumn("source", F.when(F.col("rec_id") < 9000, "A").otherwise("B"))
    b = D.key_blocks(r, ["birth_year", "birth_month", "birth_day"]).join(r.select("rec_id", "source"), "rec_id")
    return linkage.block_pairs(b, "source")


@query("tuple_count_persons", f"SELECT CAST(sum(x * y) AS DOUBLE) AS tuples FROM (SELECT birth_year, sum((rec_id < 9000)::INT) AS x, sum((rec_id >= 9000)::INT) AS y FROM ({file_sql('duckdb', 'clean10k')}) GROUP BY 1)")
def tuple_count_persons(spark, sf_dir):
    r = persons(spark, sf_dir, "clean10k").withColumn("source", F.when(F.col("rec_id") < 9000, "A").otherwise("B"))
    return linkage.tuple_count(D.key_blocks(r, ["birth_year"]).join(r.select("rec_id", "source"), "rec_id"))


_weights = {"first_name": 2.0, "last_name": 2.0, "birth_year": 1.0, "birth_month": 1.0, "birth_day": 1.0}
_links_sql = f"""WITH r AS ({file_sql('duckdb', 'clean10k')}),
p AS (SELECT a.rec_id AS id_a, b.rec_id AS id_b, round(((a.birth_year = b.birth_year)::INT + (a.birth_month = b.birth_month)::INT + (a.birth_day = b.birth_day)::INT + 2 * (1 - levenshtein(a.first_name, b.first_name) / greatest(length(a.first_name), length(b.first_name), 1)) + 2 * (1 - levenshtein(a.last_name, b.last_name) / greatest(length(a.last_name), length(b.last_name), 1))) / 7, 6) AS score
FROM r a JOIN r b ON a.rec_id < b.rec_id AND {D.CLEAN['t1_10'].keep_sql()}) SELECT id_a, id_b, score FROM p WHERE score >= 0.8"""


@query("link_persons", _links_sql)
def link_persons(spark, sf_dir):
    r = cut(D.derive(persons(spark, sf_dir, "clean10k")))
    return linkage.link_pairs(D.criterion_pairs(r, D.CLEAN["t1_10"]), r, _weights, ("first_name", "last_name"), 0.8)


@query("deduplicate_persons", f"""WITH RECURSIVE l AS MATERIALIZED ({_links_sql}), e AS (SELECT id_a AS s, id_b AS d FROM l UNION ALL SELECT id_b, id_a FROM l),
reach AS (SELECT DISTINCT s AS rec_id, s AS c FROM e UNION SELECT e.d, reach.c FROM reach JOIN e ON e.s = reach.rec_id), m AS (SELECT rec_id, min(c) AS first FROM reach GROUP BY rec_id)
SELECT rec_id, entity_id FROM ({file_sql('duckdb', 'clean10k')}) LEFT JOIN m USING (rec_id) WHERE first IS NULL OR first = rec_id""")
def deduplicate_persons(spark, sf_dir):
    r = cut(persons(spark, sf_dir, "clean10k"))
    return linkage.deduplicate(r, linkage.entities(link_persons(spark, sf_dir), r)).select("rec_id", "entity_id")


@query("private_link_persons", f"""WITH r AS ({file_sql('duckdb', 'clean500')}), t AS MATERIALIZED (SELECT DISTINCT rec_id, term FROM ({_terms_sql('clean500', 2)})), n AS (SELECT rec_id, count(*) AS n FROM t GROUP BY rec_id),
p AS (SELECT a.rec_id AS id_a, b.rec_id AS id_b FROM r a JOIN r b ON a.birth_month = b.birth_month AND a.rec_id < b.rec_id), k AS (SELECT id_a, id_b, count(*) AS k FROM p JOIN t x ON x.rec_id = id_a JOIN t y ON y.rec_id = id_b AND y.term = x.term GROUP BY ALL)
SELECT id_a, id_b, round(2 * k / (x.n + y.n), 6) AS dice FROM k JOIN n x ON x.rec_id = id_a JOIN n y ON y.rec_id = id_b WHERE round(2 * k / (x.n + y.n), 6) >= 0.7""")
def private_link_persons(spark, sf_dir):
    r, t = _texts(spark, sf_dir, "clean500")
    hashed = t.select("rec_id", linkage.salted_shingles(F.col("rec_text"), 2, "a secret").alias("s"))
    return linkage.private_link(linkage.block_pairs(D.key_blocks(r, ["birth_month"])), hashed, 0.7)


@query("benchmark_containment", "SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def benchmark_containment(spark, sf_dir):
    b = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", F.col("text").alias("passage"))
    return contained(b, spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


def contained(b: DataFrame, d: DataFrame, chunk: int = 10_000) -> DataFrame:
    """Passages that stand in a document, found by their first inner words, eight or as many as
    they have, then checked. Passages of one or two words have no inner word and are checked
    everywhere, ``chunk`` of them at a time. Nulls are nowhere."""
    bag = shingle.word_bag(F.col("passage"))
    inner = F.greatest(F.coalesce(F.size(bag), F.lit(0)) - 2, F.lit(0))
    probe = stored(b.where("passage is not null").withColumn("n", F.least(inner, F.lit(8))).withColumn("s", F.array_join(F.slice(bag, F.lit(2), F.col("n")), " ")))
    out = None
    sizes = sorted(map(tuple, probe.groupBy("n").count().collect())) or [(8, 0)]  # nine at most
    for n, count in sizes:
        own = probe.where(F.col("n") == n)
        if n:
            found = d.select("doc_id", F.explode(F.array_distinct(shingle.word_shingles(F.col("text"), n))).alias("s")).join(own.select("item_id", "s"), "s").select("item_id", "doc_id")
            parts = [found.join(d, "doc_id").join(own.select("item_id", "passage"), "item_id").where(F.expr("contains(text, passage)"))]
        else:
            turns = -(-count // chunk)
            turn = F.pmod(F.xxhash64("item_id", "passage"), F.lit(turns))
            parts = [d.join(F.broadcast(own.where(turn == i).select("item_id", "passage")), F.expr("contains(text, passage)")) for i in range(turns)]
        for part in parts:
            part = part.select("item_id", "doc_id").distinct()
            out = part if out is None else out.unionByName(part)
    return out.distinct()


@query("label_strata_recall", f"""WITH {_jaccard_cte}, j AS (SELECT id_a, id_b FROM c JOIN n x ON x.rec_id = id_a JOIN n y ON y.rec_id = id_b WHERE k / (x.n + y.n - k) >= 0.5), e AS ({_edges_sql('documents', 5, 22)}),
p AS (SELECT DISTINCT quality, j.id_a, j.id_b, e.id_a IS NOT NULL AS hit FROM j JOIN labels ON doc_id IN (j.id_a, j.id_b) LEFT JOIN e ON e.id_a = j.id_a AND e.id_b = j.id_b)
SELECT quality, count(*) AS pairs, round(avg(hit::INT), 6) AS recall FROM p GROUP BY quality""")
def label_strata_recall(spark, sf_dir):
    """Share of near-equal document pairs that blocking keeps, by quality label: a pair counts once
    for each label that one of its documents bears."""
    truth = cut(jaccard_truth_documents(spark, sf_dir).select("id_a", "id_b"))
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality")
    sides = truth.withColumn("doc_id", F.explode(F.array("id_a", "id_b")))
    pairs = cut(sides.join(labels, "doc_id").select("quality", "id_a", "id_b").distinct())
    asked = pairs.select(F.explode(F.array("id_a", "id_b")).alias("rec_id")).distinct()  # no other document's buckets are looked at
    kept = cut(minhash.lsh_pairs(_document_texts(spark, sf_dir).join(asked, "rec_id", "left_semi")).select("id_a", "id_b", F.lit(1).alias("hit")))
    return pairs.join(kept, ["id_a", "id_b"], "left").groupBy("quality").agg(F.count("*").alias("pairs"), F.round(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("recall"))


_costs = {"tlsh": "n + n * 100 + n * 22 + n * n / 1e9 + n * power(ln(n), 2)", "klsh": "n * 100 * sqrt(n) + sqrt(n) * n * 100 * 10", "traditional": "n", "traditional_pairs": "n * n", "tnn": "n * n", "canopies": "n * sqrt(n)", "blocked": "sqrt(n) * power(n / sqrt(n), 2)", "none": "power(n, 2)"}


_years_sql = "SELECT CAST(sum(c) OVER (ORDER BY y) AS BIGINT) AS m FROM (SELECT year(o_orderdate) AS y, count(*) AS c FROM orders WHERE o_orderdate IS NOT NULL GROUP BY 1)"


@query("predicted_costs", " UNION ALL ".join(f"SELECT '{m}' AS method, m AS n, round(log10({f}), 6) AS log10_cost FROM (SELECT m, CAST(m AS DOUBLE) AS n FROM ({_years_sql}))" for m, f in _costs.items()))
def predicted_costs(spark, sf_dir):
    """Steps of the growth formulas, as logarithms, for a file of the orders up to the end of each year;
    ``none`` takes every pair of two files."""
    years = spark.read.parquet(f"{sf_dir}/orders.parquet").where("o_orderdate is not null").groupBy(F.year("o_orderdate").alias("y")).agg(F.count("*").alias("c"))
    grown = years.select(F.sum("c").over(Window.orderBy("y")).alias("n"))  # one row for each year
    steps = F.udf(lambda m, n: math.log10(metrics.predicted_cost(m, n)), "double")
    return grown.withColumn("method", F.explode(F.array(*map(F.lit, _costs)))).select("method", "n", F.round(steps("method", "n"), 6).alias("log10_cost"))


# Turns that follow each other, by hundredths of the share of their words that both have.
_turns_sql = """t AS (SELECT conv_id, turn, list_distinct(list_filter(string_split(lower(text), ' '), lambda x: x <> '')) AS w FROM conversations),
k AS (SELECT len(list_intersect(a.w, b.w)) AS k, len(a.w) + len(b.w) AS n FROM t a JOIN t b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1),
p AS (SELECT (100 * k // (n - k)) / 100 AS s, count(*) AS pairs FROM k WHERE n > 0 GROUP BY 1)"""


@query("band_curve_values", f"WITH {_turns_sql} " + " UNION ALL ".join(f"SELECT {b} AS b, s, pairs, round(1 - " + " * ".join(f"power(1 - power(s, {r}), {minhash.band_sizes(100, b).count(r)})" for r in sorted(set(minhash.band_sizes(100, b)))) + ", 6) AS chance FROM p" for b in (21, 22, 26)))
def band_curve_values(spark, sf_dir):
    """The chance to share a band for turns of a conversation that follow each other, by how alike their words are."""
    words = F.array_distinct(F.filter(F.split(F.lower("text"), " "), lambda x: x != ""))
    t = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", words.alias("w"))
    after = t.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("w").alias("v"))
    both = t.join(after, ["conv_id", "turn"]).select(F.size(F.array_intersect("w", "v")).alias("k"), (F.size("w") + F.size("v")).alias("n"))
    alike = both.where("n > 0 and k is not null").select((F.floor(100 * F.col("k") / (F.col("n") - F.col("k"))) / 100).alias("s")).groupBy("s").agg(F.count("*").alias("pairs"))
    curve = F.udf(lambda s, b: minhash.band_curve(s, 100, b), "double")
    return alike.withColumn("b", F.explode(F.array(*map(F.lit, (21, 22, 26))))).select("b", "s", "pairs", F.round(curve("s", "b"), 6).alias("chance"))
