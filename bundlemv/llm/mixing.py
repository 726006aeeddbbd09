"""Mixing sources to target weights by capped water-filling, with DataFrame functions only.

Each source has a weight and may be repeated ``max_epochs`` times at most. The water
level is found in closed form: with sources ordered by cap per unit of weight, the
level is the first at which the words that are left, shared over the weights that are
left, stay below the next cap. That equals clamping and resharing until nothing is
above its cap.

Documents are drawn in a seeded order. A source takes ``target div size`` whole
repetitions of every document, and the remainder from the front of the seeded order;
the document at the boundary gives a fractional repetition (its first words), so a
source's taken words equal its rounded target.

Skew: a source may hold most rows. Running sums go over about sqrt(n) buckets of about
sqrt(n) documents each, so no task sees a whole source.

Defined cases: null text has size 0; a null source is a source of its own, last in
order; null ids are ordered as the empty string; repeated rows count each; an empty
table gives an empty result; a corpus without words gives targets of 0.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bundlemv.session import materialise

WORD = r"[^\x20\x09-\x0D]+"
#: Source plans of up to so many rows are broadcast (a row has a few dozen bytes); beyond, they are joined by shuffle.
BROADCAST_SOURCES = 20_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def cycling_weight(position: Column, weights: tuple[int, ...]) -> Column:
    """The weight at 0-based ``position``, the tuple repeating."""
    return F.element_at(F.array(*[F.lit(w) for w in weights]), (position % len(weights) + 1).cast("int"))


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), max_epochs: int = 3) -> DataFrame:
    """(key, size) rows -> one row per source: key, source_size, n, target, whole, remainder.

    The windows here run over one row per source, in one task.
    """
    per = sizes.groupBy("__key").agg(F.sum("__size").alias("source_size"), F.count("*").alias("n"))
    by_name, by_cap = Window.orderBy("__key"), Window.orderBy("ratio", "__key")
    everything = Window.partitionBy()
    cap = F.col("source_size") * max_epochs
    per = (
        per.withColumn("w", cycling_weight(F.row_number().over(by_name) - 1, weights))
        .withColumn("total", F.sum("source_size").over(everything))
        .withColumn("ratio", cap.cast("double") / F.col("w"))
        .withColumn("spent", F.coalesce(F.sum(cap).over(by_cap.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("w_left", F.sum("w").over(by_cap.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("level", (F.col("total") - F.col("spent")).cast("double") / F.col("w_left"))
        .withColumn("fits", F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", "__key", "level")))
        .withColumn("level", F.min("fits").over(everything)["level"])
        .withColumn("target", F.least(cap.cast("double"), F.coalesce("level", F.lit(0.0)) * F.col("w")))
    )
    goal = F.least(cap, F.floor(F.col("target") + 0.5).cast("long"))
    positive = F.greatest("source_size", F.lit(1).cast("long"))
    return per.select(
        "__key", "source_size", "n", "target",
        goal.alias("goal"), positive.alias("unit"),
    ).selectExpr(
        "__key", "source_size", "n", "target", "goal div unit as whole", "goal % unit as remainder",
        "cast(ceil(sqrt(n)) as long) as n_buckets",
    )


def mix_sources(
    docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), max_epochs: int = 3, seed: int = 7,
    id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", keep: tuple[str, ...] = (),
) -> DataFrame:
    """One row per input row: id, the ``keep`` columns, size, source_size, target, taken."""
    ident = F.coalesce(F.col(id_col).cast("string"), F.lit(""))
    rows = docs.select(
        F.col(id_col).alias("__id"), F.struct(*[F.col(c) for c in (id_col, *keep)]).alias("__row"),
        # code point order with null last: UTF-8 bytes sort by code point, and the prefix puts null behind
        F.coalesce(F.concat(F.lit("0"), source_col), F.lit("1")).alias("__key"),
        word_count(F.col(text_col)).alias("__size"),
        F.md5(F.concat(F.lit(f"{seed}:"), ident)).alias("__h"),
    )
    slim = materialise(rows.select("__id", "__key", "__size", "__h"), "mix-sizes")  # words are counted here, once
    if not keep:
        rows = slim.withColumn("__row", F.struct(F.col("__id").alias(id_col)))
    plan = materialise(source_targets(slim, weights, max_epochs), "mix-plan")
    if plan.count() <= BROADCAST_SOURCES:
        plan = F.broadcast(plan)
    share = F.conv(F.substring("__h", 1, 8), 16, 10).cast("long") / F.lit(2.0**32)
    placed = lambda x: x.join(plan, "__key").withColumn("__bucket", F.floor(share * F.col("n_buckets")).cast("long"))
    rows = placed(rows)
    before = Window.partitionBy("__key").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    buckets = (
        placed(slim).groupBy("__key", "__bucket").agg(F.sum("__size").alias("__sum"))
        .select("__key", "__bucket", F.coalesce(F.sum("__sum").over(before), F.lit(0)).alias("__base"))
    )
    inside = Window.partitionBy("__key", "__bucket").orderBy("__h", "__id", "__size").rowsBetween(Window.unboundedPreceding, -1)
    ahead = F.col("__base") + F.col("__inside")
    part = F.greatest(F.lit(0), F.least(F.col("__size"), F.col("remainder") - ahead))
    return (
        rows.withColumn("__inside", F.coalesce(F.sum("__size").over(inside), F.lit(0)))
        .join(buckets, ["__key", "__bucket"])
        .select("__row.*", F.col("__size").alias("size"), "source_size", "target", (F.col("whole") * F.col("__size") + part).cast("long").alias("taken"))
    )


def repeat_rows(mixed: DataFrame, text_col: str = "text", taken: str = "__taken", size: str = "__words") -> DataFrame:
    """The mix itself: a row per repetition; a fractional repetition holds the first words of its text.

    Reads the columns ``taken`` and ``size`` and drops them.
    """
    some = F.col(size) > 0
    whole = F.when(some, F.expr(f"`{taken}` div `{size}`")).otherwise(F.lit(0)).cast("int")
    left = F.when(some, F.expr(f"`{taken}` % `{size}`")).otherwise(F.lit(0)).cast("int")
    copies = F.concat(F.array_repeat(F.lit(-1), whole), F.when(left > 0, F.array(left)).otherwise(F.array().cast("array<int>")))
    words = F.split(F.ltrim(F.regexp_replace(text_col, r"[\x20\x09-\x0D]+", " ")), " ")
    head = F.array_join(F.slice(words, 1, F.greatest("__n", F.lit(0))), " ")
    out = mixed.withColumn("__n", F.explode(copies))
    return out.withColumn(text_col, F.when(F.col("__n") < 0, F.col(text_col)).otherwise(head)).drop("__n", taken, size)


def mixed_documents(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), max_epochs: int = 3, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The columns of ``docs``; each row as often as the mix takes it, the last repetition maybe in part.

    Documents without words are no part of a mix.
    """
    held = docs.select(F.struct(*docs.columns).alias("__doc"), F.col(id_col), F.col(text_col), F.col(source_col))
    mixed = mix_sources(held, weights, max_epochs, seed, id_col, text_col, source_col, keep=("__doc",))
    taken = mixed.where("taken > 0").select("__doc.*", F.col("taken").alias("__taken"), F.col("size").alias("__words"))
    return repeat_rows(taken, text_col)


def op7(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    return mix_sources(load_table(spark, sf_dir, "documents"))


OP7_SQL = r"""
with d as (
  select doc_id, source, cast(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as bigint) as size,
         md5('7:' || cast(doc_id as varchar)) as h
  from documents),
s as (select source, cast(sum(size) as bigint) as source_size from d group by source),
w as (select *, (row_number() over (order by source nulls last) - 1) % 3 + 1 as w from s),
r as (select *, 3 * source_size / cast(w as double) as ratio, sum(source_size) over () as total from w),
l as (select *, (total - coalesce(sum(3 * source_size) over (order by ratio, source nulls last rows between unbounded preceding and 1 preceding), 0))
         / cast(sum(w) over (order by ratio, source nulls last rows between current row and unbounded following) as double) as lev from r),
v as (select arg_min(lev, ratio) as lev from l where lev <= ratio),
t as (select l.source, l.source_size, least(3.0 * l.source_size, v.lev * l.w) as target from l, v),
g as (select *, least(3 * source_size, cast(floor(target + 0.5) as bigint)) as goal from t),
o as (select d.doc_id, d.size, g.source_size, g.target, g.goal // greatest(g.source_size, 1) as whole, g.goal % greatest(g.source_size, 1) as rem,
         coalesce(sum(d.size) over (partition by d.source order by d.h, d.doc_id rows between unbounded preceding and 1 preceding), 0) as ahead
      from d join g on d.source is not distinct from g.source)
select doc_id, size, cast(source_size as bigint) as source_size, cast(target as double) as target,
       cast(whole * size + greatest(0, least(size, rem - ahead)) as bigint) as taken
from o
"""
