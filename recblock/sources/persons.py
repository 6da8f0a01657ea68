"""Person files with known truth, drawn from ``orders`` and ``documents`` by digests.

The statements are built for either engine (``spark`` or ``duckdb``), which differ in a few
function names only, so an oracle can recompute every file."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from recblock.session import cut

CLEAN_FIELDS = ["first_name", "last_name", "birth_year", "birth_month", "birth_day"]
NOISY_FIELDS = ["first_name", "last_name", "gender", "city", "postal_code", "phone", "card_no", "age"]
SEED = 42
MOST = {"clean": 200, "noisy": 400}  # names of a list


def chance(dialect: str, *parts: str) -> str:
    """A number in [0, 1): the first 8 digits of the md5 of the parts joined by bars."""
    text = " || '|' || ".join([f"'{SEED}'", *[p if p.startswith("'") else f"CAST({p} AS {'STRING' if dialect == 'spark' else 'VARCHAR'})" for p in parts]])
    digits = f"substr(md5({text}), 1, 8)"
    whole = f"CAST(conv({digits}, 16, 10) AS DOUBLE)" if dialect == "spark" else f"CAST(CAST('0x' || {digits} AS BIGINT) AS DOUBLE)"
    return f"({whole} / CAST(4294967296 AS DOUBLE))"


def pick(dialect: str, n: int | str, *parts: str) -> str:
    return f"CAST(floor(({n}) * {chance(dialect, *parts)}) AS BIGINT)"


def names_cte(dialect: str, most: int) -> str:
    """first(i, w) and last(i, w): words of the German texts, frequent ones first."""
    split = r"explode(split(lower(text), '[^\\p{L}]+'))" if dialect == "spark" else r"unnest(string_split_regex(lower(text), '[^\p{L}]+'))"
    full = "w RLIKE '^[a-z]{4,10}$'" if dialect == "spark" else "regexp_full_match(w, '[a-z]{4,10}')"
    return f"""
words AS (SELECT DISTINCT doc_id, w FROM (SELECT doc_id, {split} AS w FROM documents WHERE lang = 'de') AS x WHERE {full}),
freq AS (SELECT w, count(*) AS df FROM words GROUP BY w),
ranked AS (SELECT w, row_number() OVER (PARTITION BY substr(w, 1, 1) ORDER BY df DESC, w) AS rk FROM freq),
placed AS (SELECT w, row_number() OVER (ORDER BY rk, substr(w, 1, 1)) - 1 AS pos FROM ranked),
firsts AS (SELECT CAST(floor(pos / 2) AS BIGINT) AS i, w FROM placed WHERE pos % 2 = 0 AND pos < {2 * most}),
lasts AS (SELECT CAST(floor(pos / 2) AS BIGINT) AS i, w FROM placed WHERE pos % 2 = 1 AND pos < {2 * most})"""


def _name_index(dialect: str, table: str, ident: str, purpose: str) -> str:
    u = chance(dialect, ident, purpose)
    return f"CAST(floor((SELECT count(*) FROM {table}) * {u} * {u}) AS BIGINT)"


def _typo(dialect: str, column: str, ident: str, tag: str) -> str:
    """One letter after the first replaced by another."""
    at = f"(2 + {pick(dialect, f'length({column}) - 1', ident, f"'{tag}at'")})"
    old = f"(ascii(substr({column}, CAST({at} AS INT), 1)) - 97)"
    new = f"chr(CAST(97 + ({old} + 1 + {pick(dialect, 25, ident, f"'{tag}by'")}) % 26 AS INT))"
    return f"substr({column}, 1, CAST({at} - 1 AS INT)) || {new} || substr({column}, CAST({at} + 1 AS INT))"


def clean_sql(dialect: str, n: int | None = 10_000, most: int = MOST["clean"], names: str | None = None) -> str:
    """n records, a tenth of them copies with one error each. Without n, every order is an
    original and every ninth has a copy; ids are then even and odd, so no count is needed.
    ``names``: where the names come from, in place of names_cte."""
    if n is None:
        inside, original_id, copy_id, copied = "", "2 * e", "2 * e + 1", "e % 9 = 0"
    else:
        originals, copies = n - n // 10, n // 10
        inside, original_id, copy_id, copied = f"WHERE o_orderkey < {originals}", "e", f"e + {originals}", f"e < {copies}"
    u = lambda *p: chance(dialect, *p)
    year = f"CASE WHEN {u('e', "'yk'")} < 0.55 THEN y - y % 10 + (y % 10 + 1 + {pick(dialect, 9, 'e', "'yd'")}) % 10 ELSE 1920 + (y - 1920 + 10 * (1 + {pick(dialect, 7, 'e', "'ye'")})) % 80 END"
    return f"""WITH {names or names_cte(dialect, most)},
base AS (SELECT o_orderkey AS e, {_name_index(dialect, 'firsts', 'o_orderkey', "'first'")} AS fi, {_name_index(dialect, 'lasts', 'o_orderkey', "'last'")} AS li,
  1920 + {pick(dialect, 80, 'o_orderkey', "'year'")} AS y, 1 + {pick(dialect, 12, 'o_orderkey', "'month'")} AS m, 1 + {pick(dialect, 28, 'o_orderkey', "'day'")} AS d
  FROM orders {inside}),
named AS (SELECT e, firsts.w AS f, lasts.w AS l, y, m, d, {u('e', "'field'")} AS hit FROM base JOIN firsts ON firsts.i = fi JOIN lasts ON lasts.i = li),
every AS (SELECT {original_id} AS rec_id, e AS entity_id, f, l, y, m, d FROM named UNION ALL
SELECT {copy_id}, e, CASE WHEN hit < 0.30 THEN {_typo(dialect, 'f', 'e', 'f')} ELSE f END, CASE WHEN hit >= 0.30 AND hit < 0.60 THEN {_typo(dialect, 'l', 'e', 'l')} ELSE l END,
  CASE WHEN hit >= 0.60 AND hit < 0.76 THEN {year} ELSE y END, CASE WHEN hit >= 0.76 AND hit < 0.89 THEN 1 + (m + {pick(dialect, 11, 'e', "'mm'")}) % 12 ELSE m END,
  CASE WHEN hit >= 0.89 THEN 1 + (d + {pick(dialect, 27, 'e', "'dd'")}) % 28 ELSE d END
FROM named WHERE {copied})
SELECT rec_id, entity_id, f AS first_name, l AS last_name, CAST(y AS INT) AS birth_year, CAST(m AS INT) AS birth_month, CAST(d AS INT) AS birth_day FROM every"""


def noisy_sql(dialect: str, percent: int = 10, n: int = 10_000, most: int = MOST["noisy"], errors: int = 5, names: str | None = None) -> str:
    """n records, ``percent`` of them copies with ``errors`` errors in distinct fields, up to five copies of one original."""
    copies = n * percent // 100
    originals = n - copies
    u = lambda *p: chance(dialect, *p)
    string = "STRING" if dialect == "spark" else "VARCHAR"
    digits = lambda ident, tag, k: "lpad(CAST(" + pick(dialect, 10**k, ident, f"'{tag}'") + f" AS {string}), {k}, '0')"
    card = f"{digits('o_orderkey', 'card1', 8)} || {digits('o_orderkey', 'card2', 8)}"
    draws = ", ".join(f"{u('rec_id', f"'hit{k}'")} * {0.5 if k < 2 else 1.0} AS h{k}" for k in range(8))
    hit = lambda k: " + ".join(f"CASE WHEN h{j} < h{k} OR (h{j} = h{k} AND {j} < {k}) THEN 1 ELSE 0 END" for j in range(8) if j != k) + f" < {errors}"

    def name(c: str) -> str:
        kind, at = u("rec_id", f"'{c}kind'"), f"CAST(1 + {pick(dialect, f'length({c})', 'rec_id', f"'{c}pos'")} AS INT)"
        letter = f"chr(CAST(97 + {pick(dialect, 26, 'rec_id', f"'{c}new'")} AS INT))"
        return f"CASE WHEN {kind} < 0.4 THEN {_typo(dialect, c, 'rec_id', c)} WHEN {kind} < 0.7 THEN substr({c}, 1, {at} - 1) || substr({c}, {at} + 1) ELSE substr({c}, 1, {at}) || {letter} || substr({c}, {at} + 1) END"

    def digit(c: str, k: int) -> str:
        at = f"CAST(1 + {pick(dialect, k, 'rec_id', f"'{c}pos'")} AS INT)"
        new = f"CAST((CAST(substr({c}, {at}, 1) AS INT) + 1 + {pick(dialect, 9, 'rec_id', f"'{c}new'")}) % 10 AS {string})"
        return f"substr({c}, 1, {at} - 1) || {new} || substr({c}, {at} + 1)"

    corrupt = {
        "first_name": name("first_name"), "last_name": name("last_name"), "gender": f"CASE gender WHEN 'f' THEN 'm' ELSE 'f' END",
        "city": f"'city' || CAST((CAST(substr(city, 5) AS INT) + 1 + {pick(dialect, 11, 'rec_id', "'citynew'")}) % 12 AS {string})",
        "postal_code": digit("postal_code", 5), "phone": digit("phone", 10), "card_no": digit("card_no", 16), "age": f"18 + (age - 18 + 1 + {pick(dialect, 72, 'rec_id', "'agenew'")}) % 73",
    }
    changed = ", ".join(f"CASE WHEN {hit(k)} THEN {corrupt[f]} ELSE {f} END AS {f}" for k, f in enumerate(NOISY_FIELDS))
    fields = ", ".join(NOISY_FIELDS)
    share = u("o_orderkey", "'copies'")
    return f"""WITH {names or names_cte(dialect, most)},
base AS (SELECT o_orderkey, {_name_index(dialect, 'firsts', 'o_orderkey', "'nfirst'")} AS fi, {_name_index(dialect, 'lasts', 'o_orderkey', "'nlast'")} AS li,
  CASE WHEN {u('o_orderkey', "'gender'")} < 0.48 THEN 'f' WHEN {u('o_orderkey', "'gender'")} < 0.96 THEN 'm' ELSE 'u' END AS gender,
  CAST(floor(12 * {u('o_orderkey', "'city'")} * {u('o_orderkey', "'city'")} * {u('o_orderkey', "'city'")}) AS BIGINT) AS c,
  {pick(dialect, 4, 'o_orderkey', "'post'")} AS p, {digits('o_orderkey', 'phone', 9)} AS ph, {card} AS card_no, 18 + {pick(dialect, 73, 'o_orderkey', "'age'")} AS age,
  CASE WHEN {share} < 0.62 THEN 1 WHEN {share} < 0.85 THEN 2 WHEN {share} < 0.94 THEN 3 WHEN {share} < 0.98 THEN 4 ELSE 5 END AS k
  FROM orders WHERE o_orderkey < {originals}),
named AS (SELECT o_orderkey AS e, k, firsts.w AS first_name, lasts.w AS last_name, gender, 'city' || CAST(c AS {string}) AS city,
  CAST(10000 + 4 * c + p AS {string}) AS postal_code, '0' || ph AS phone, card_no, age FROM base JOIN firsts ON firsts.i = fi JOIN lasts ON lasts.i = li),
counted AS (SELECT *, sum(k) OVER (ORDER BY e ROWS UNBOUNDED PRECEDING) - k AS before FROM named WHERE e < {copies}),
copied AS (SELECT CAST({originals} + before + j AS BIGINT) AS rec_id, e, {fields} FROM counted CROSS JOIN (SELECT 0 AS j UNION ALL SELECT 1 UNION ALL SELECT 2 UNION ALL SELECT 3 UNION ALL SELECT 4) AS js
  WHERE j < k AND before + j < {copies}),
drawn AS (SELECT *, {draws} FROM copied)
SELECT e AS rec_id, e AS entity_id, {fields} FROM named UNION ALL SELECT rec_id, e AS entity_id, {changed} FROM drawn"""


FILES = {"clean10k": ("clean", {}), "clean500": ("clean", {"n": 500}), "clean_all": ("clean", {"n": None}), "noisy10": ("noisy", {"percent": 10}), "noisy30": ("noisy", {"percent": 30}), "noisy50": ("noisy", {"percent": 50})}


def file_sql(dialect: str, name: str, n: int | None = None, names: str | None = None) -> str:
    kind, options = FILES[name]
    options = options | ({"n": n} if n else {}) | ({"names": names} if names else {})
    return (clean_sql if kind == "clean" else noisy_sql)(dialect, **options)


def persons(spark: SparkSession, sf_dir: str, name: str, n: int | None = None) -> DataFrame:
    """A person file, ``clean_all`` of all orders; the others are smaller when ``orders`` is too small for it (as at the smoke scale)."""
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    if n is None and (FILES[name][1].get("n", 10_000) or 0) > 1000 and orders.count() < 10_000:
        n = 1000
    orders.createOrReplaceTempView("orders")
    spark.read.parquet(f"{sf_dir}/documents.parquet").createOrReplaceTempView("documents")
    # the statement names both lists several times, and would read the texts each time
    most = MOST[FILES[name][0]]
    cut(spark.sql(f"WITH {names_cte('spark', most)} SELECT w, pos FROM placed WHERE pos < {2 * most}")).createOrReplaceTempView("person_names")
    names = ", ".join(f"{k} AS (SELECT CAST(floor(pos / 2) AS BIGINT) AS i, w FROM person_names WHERE pos % 2 = {i})" for i, k in enumerate(("firsts", "lasts")))
    return spark.sql(file_sql("spark", name, n, names))


def fields_of(name: str) -> list[str]:
    return CLEAN_FIELDS if name.startswith("clean") else NOISY_FIELDS
