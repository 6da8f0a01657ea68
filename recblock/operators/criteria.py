"""Criteria over field disagreements, rewritten to equi-joins.

A criterion says when a pair is no match. What it keeps is put in disjunctive form over field
agreements; each conjunct is one equi-join, and a pair is taken by its first conjunct only, so
no distinct over pairs is needed. Counts come from group sizes alone."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from recblock.operators.metrics import choose2


@dataclass(frozen=True)
class Criterion:
    """keeps: sets of fields; a pair is kept if it agrees on all of one set. edit: fields whose
    edit distance must stay below ``edit_at``."""

    keeps: tuple[frozenset, ...]
    edit: tuple[str, ...] = ()
    edit_at: int = 4

    def keep_sql(self, a: str = "a", b: str = "b") -> str:
        agree = " OR ".join("(" + " AND ".join(f"{a}.{f} = {b}.{f}" for f in sorted(s)) + ")" for s in self.keeps)
        near = "".join(f" AND levenshtein({a}.{f}, {b}.{f}) < {self.edit_at}" for f in self.edit)
        return f"({agree}){near}"


def _minimal(sets) -> tuple[frozenset, ...]:
    sets = set(sets)
    return tuple(sorted((s for s in sets if not any(t < s for t in sets)), key=lambda s: (len(s), sorted(s))))


def disagree(field: str) -> Criterion:
    return Criterion((frozenset([field]),))


def any_of(*cs: Criterion) -> Criterion:
    """Discards if one of them does: kept by all."""
    keeps = {frozenset()}
    for c in cs:
        keeps = {a | b for a in keeps for b in c.keeps}
    return Criterion(_minimal(keeps), tuple(f for c in cs for f in c.edit))


def all_of(*cs: Criterion) -> Criterion:
    """Discards only if all of them do: kept by one."""
    if any(c.edit for c in cs):
        raise ValueError("an edit distance refines a criterion; it can't be one of several ways to keep a pair")
    return Criterion(_minimal(s for c in cs for s in c.keeps))


def more_than(m: int, fields: list[str]) -> Criterion:
    """Discards if more than m of the fields disagree."""
    return Criterion(_minimal(frozenset(s) for s in combinations(fields, len(fields) - m)))


def edit_at_least(criterion: Criterion, d: int, *fields: str) -> Criterion:
    return Criterion(criterion.keeps, fields, d)


_name, _birth = ("first_name", "last_name"), ("birth_day", "birth_month", "birth_year")
_five = [*_name, "birth_year", "birth_month", "birth_day"]
_eight = [*_name, "gender", "city", "postal_code", "phone", "card_no", "age"]
_initials = any_of(disagree("initial_f"), disagree("initial_l"))
CLEAN = {
    "t1_01": any_of(*map(disagree, _name)), "t1_02": any_of(*map(disagree, _birth)), "t1_03": disagree("birth_year"), "t1_04": disagree("birth_day"),
    "t1_05": disagree("birth_month"), "t1_06": disagree("decade"), "t1_07": all_of(*map(disagree, _name)),
    "t1_08": any_of(all_of(*map(disagree, _name)), all_of(*map(disagree, _birth))), "t1_09": all_of(*map(disagree, _birth)),
    "t1_10": more_than(3, _five), "t1_11": _initials, "t1_12": edit_at_least(more_than(3, _five), 4, *_name),
}
NOISY = {
    "t2_01": disagree("gender"), "t2_02": disagree("city"), "t2_03": disagree("postal_code"), "t2_04": any_of(*map(disagree, _name)), "t2_05": _initials,
    "t2_06": all_of(*map(disagree, _name)), "t2_07": all_of(*map(disagree, _eight)), "t2_08": edit_at_least(all_of(*map(disagree, _eight)), 4, *_name),
}


def derive(records: DataFrame) -> DataFrame:
    out = records.withColumn("initial_f", F.substring("first_name", 1, 1)).withColumn("initial_l", F.substring("last_name", 1, 1))
    return out.withColumn("decade", F.floor(F.col("birth_year") / 10)) if "birth_year" in records.columns else out


def with_null_policy(records: DataFrame, fields: list[str], policy: str = "disagree") -> DataFrame:
    """``disagree``: a null agrees with nothing (as joins have it); ``agree``: nulls agree with each other."""
    if policy == "disagree":
        return records
    return records.select(*[F.coalesce(F.col(c).cast("string"), F.lit("\x00null")).alias(c) if c in fields else F.col(c) for c in records.columns])


def block_key(columns: list[str]) -> Column:
    """The key of a record's exact-key block; a null key makes a block of its own record."""
    some_null = F.greatest(*[F.col(c).isNull() for c in columns], F.lit(False))
    return F.when(some_null, F.concat(F.lit("null-"), F.col("rec_id").cast("string"))).otherwise(F.md5(F.to_json(F.struct(*columns))))


def key_blocks(records: DataFrame, columns: list[str]) -> DataFrame:
    """Exact-key blocks."""
    return records.select("rec_id", block_key(columns).alias("block_id"))


def edit_below(a: Column, b: Column, d: int) -> Column:
    return F.levenshtein(a, b, d - 1) >= 0


def near_values(records: DataFrame, field: str, d: int) -> DataFrame:
    """Distinct values of a field whose edit distance is below d, both ways. Values, not records,
    are compared; a text's length bounds its distance, so lengths are joined within d - 1."""
    v = records.select(F.col(field).alias("va")).where("va is not null").distinct()
    lengths = F.explode(F.sequence(F.length("vb") - (d - 1), F.length("vb") + (d - 1)))
    other = v.select(F.col("va").alias("vb")).select("vb", lengths.alias("n"))
    return v.withColumn("n", F.length("va")).join(other, "n").where(edit_below(F.col("va"), F.col("vb"), d)).select(F.col("va").alias(f"{field}_a"), F.col("vb").alias(f"{field}_b"))


def criterion_pairs(records: DataFrame, criterion: Criterion) -> DataFrame:
    """(id_a, id_b) that the criterion keeps. With an edit distance, candidates come from the near
    values of its fields, which are few; else from one equi-join per conjunct."""
    fields = sorted({f for s in criterion.keeps for f in s} | set(criterion.edit))
    side = lambda x: records.select(F.col("rec_id").alias(f"id_{x}"), *[F.col(f).alias(f"{f}_{x}") for f in fields])
    agree = lambda s: F.coalesce(_and(F.col(f"{f}_a") == F.col(f"{f}_b") for f in sorted(s)), F.lit(False))
    if criterion.edit:
        near = side("a")
        for f in criterion.edit:
            near = near.join(near_values(records, f, criterion.edit_at), f"{f}_a")
        both = near.join(side("b"), [f"{f}_b" for f in criterion.edit]).where("id_a < id_b")
        kept = F.lit(False)
        for s in criterion.keeps:
            kept = kept | agree(s)
        return both.where(kept).select("id_a", "id_b")
    out = None
    for k, s in enumerate(criterion.keeps):
        part = side("a").join(side("b"), [F.col(f"{f}_a") == F.col(f"{f}_b") for f in sorted(s)]).where("id_a < id_b")
        for earlier in criterion.keeps[:k]:
            part = part.where(~agree(earlier))
        part = part.select("id_a", "id_b")
        out = part if out is None else out.unionByName(part)
    return out


def _and(columns) -> Column:
    out = None
    for c in columns:
        out = c if out is None else out & c
    return out


def criterion_counts(records: DataFrame, criteria: dict[str, Criterion]) -> DataFrame:
    """(rule, kept, kept_true) of criteria without edit distance, from group sizes: agreements on
    a union of conjuncts are counted by inclusion and exclusion. One pass makes all groups."""
    if any(c.edit for c in criteria.values()):
        raise ValueError("edit distances need pairs; see criterion_pairs")
    signed: dict[str, dict[frozenset, int]] = {}
    for name, c in criteria.items():
        own: dict[frozenset, int] = {}
        for s in c.keeps:  # of a union, one conjunct at a time
            for t, n in list(own.items()):
                own[t | s] = own.get(t | s, 0) - n
            own[s] = own.get(s, 0) + 1
        signed[name] = {s: n for s, n in own.items() if n}
    sets = sorted({s for own in signed.values() for s in own}, key=sorted)
    fields = sorted({f for s in sets for f in s})
    order = [*fields, "entity_id"]
    masks = {(i, flag): sum(1 << k for k, f in enumerate(order) if f in s or (flag and f == "entity_id")) for i, s in enumerate(sets) for flag in (False, True)}
    has = [F.col("g").bitwiseAND(F.lit(1 << k)) != 0 for k in range(len(order))]
    # One row per record and set, made by explode: as grouping sets, hundreds of sets outgrow generated code.
    spread = records.select(*order, F.explode(F.array(*[F.lit(m) for m in masks.values()])).alias("g"))
    whole = _and(~has[k] | F.col(f).isNotNull() for k, f in enumerate(fields))  # a null agrees with nothing
    keys = [F.when(has[k], F.col(f)).alias(f"k{k}") for k, f in enumerate(order)]
    grouped = spread.where(whole).select("g", *keys).groupBy("g", *[f"k{k}" for k in range(len(order))]).agg(F.count("*").alias("c"))
    pairs = grouped.where("c > 1").groupBy("g").agg(F.sum(choose2(F.col("c"))).alias("pairs"))
    numbers = records.sparkSession.createDataFrame([(m, f, [(r, own[sets[i]]) for r, own in signed.items() if sets[i] in own]) for (i, f), m in masks.items()], "g int, true_pairs boolean, w array<struct<rule:string,n:int>>")
    joined = numbers.join(pairs, "g", "left").select("true_pairs", F.coalesce("pairs", F.lit(0)).alias("pairs"), F.explode("w").alias("w"))
    part = lambda flag: F.sum(F.when(F.col("true_pairs") == flag, F.col("pairs") * F.col("w.n")).otherwise(0)).cast("double")
    return joined.groupBy(F.col("w.rule").alias("rule")).agg(part(False).alias("kept"), part(True).alias("kept_true"))


def cascade(records: DataFrame, criteria: list[tuple[str, Criterion]]) -> DataFrame:
    """(stage, pairs_left, true_left) after each criterion in turn; every pair is made once."""
    named = records.select("rec_id", "entity_id")
    pairs, out = None, None
    for stage, (_, c) in enumerate(criteria):
        now = criterion_pairs(records, c)
        pairs = now if pairs is None else pairs.join(now, ["id_a", "id_b"], "left_semi")
        counted = pairs.join(named.withColumnRenamed("rec_id", "id_a"), "id_a").join(named.select(F.col("rec_id").alias("id_b"), F.col("entity_id").alias("other")), "id_b")
        row = counted.agg(F.lit(stage).alias("stage"), F.count("*").alias("pairs_left"), F.sum(F.when(F.col("entity_id") == F.col("other"), 1).otherwise(0)).alias("true_left"))
        out = row if out is None else out.unionByName(row)
    return out
