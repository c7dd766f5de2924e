"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

Each source gets a token budget: its target weight's share of the total.  A budget of
``e`` times the source's tokens and a rest means ``e`` complete epochs first; the rest
is a weighted sample without replacement: documents in order of ``-ln(u) / quality``
(``u`` uniform from a hash of seed and doc_id) as long as the running sum of tokens
stays within it.

The order is total within a source, so a sample is fixed by the last key that it takes.
That cut is found from a histogram of tokens over key ranges and an exact running sum
inside the one range where the budget ends: no source is sorted whole, no task holds
one, and the second pass over the texts has no shuffle on account of the sampling.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from evenkeel.llm import _store


#: Sources up to which their budgets and cuts are broadcast; more are joined by source.
MOST_BROADCAST = 50_000
#: Labelled documents up to which their weights are broadcast; with more, documents are
#: shuffled once on their way to ``mix``.
MOST_LABELS = 200_000


@dataclass(frozen=True)
class Settings:
    #: Target weight by source; sources without one get (their share of tokens) ** temperature.
    weights: tuple[tuple[str, float], ...] = ()
    temperature: float = 0.7
    #: All sources' budgets together, as a multiple of the tokens there are.
    budget: float = 1.0
    seed: str = "mix-1"
    #: Sampling weight of documents labelled good, labelled bad and not labelled.
    good: float = 1.0
    bad: float = 0.25
    unknown: float = 0.75
    #: Key ranges of the histogram; bounds the rows that are put in order, not the result.
    ranges: int = 1 << 16


def tokens(text: Column) -> Column:
    """Blank-separated words, at least 1: what budgets count. A null text has 1."""
    return F.coalesce(F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit(""))) + 1, F.lit(1)).cast("bigint")


def _identity() -> Column:
    return F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("text "), F.md5(F.coalesce("text", F.lit("")))))


def _key(identity: Column, quality: Column, s: Settings) -> Column:
    digits = F.substring(F.md5(F.concat(F.lit(f"{s.seed}-"), identity)), 1, 13)
    u = (F.conv(digits, 16, 10).cast("double") + 0.5) / float(1 << 52)
    return -F.log(u) / quality


def _quality(labels: DataFrame, s: Settings) -> DataFrame:
    """doc_id and sampling weight; a doc_id labelled both ways counts as bad."""
    by_id = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("q"))
    return _store.small(by_id.select("doc_id", F.when(F.col("q") > 0, s.good).otherwise(s.bad).alias("weight")), MOST_LABELS)


def _units(docs: DataFrame, labels: DataFrame, s: Settings) -> DataFrame:
    """source, id, key, tokens, doc_id: one row for each document of a source, repeated rows summed."""
    narrow = docs.select("doc_id", "source", _identity().alias("id"), tokens(F.col("text")).alias("tokens"))
    weighted = narrow.join(_quality(labels, s), "doc_id", "left")
    key = _key(F.col("id"), F.coalesce("weight", F.lit(s.unknown)), s)
    return weighted.groupBy("source", "id").agg(F.min(key).alias("key"), F.sum("tokens").alias("tokens"), F.min("doc_id").alias("doc_id"))


def plan(units: DataFrame, s: Settings = Settings()) -> DataFrame:
    """One row a source: source, total, budget, epochs, cut_key, cut_id (null: no rest).

    ``units`` is read twice; materialise it.  Sources are few enough to be counted on one
    task; documents are not.
    """
    by_source = units.groupBy("source").agg(F.sum("tokens").alias("total"))
    everything = W.partitionBy()
    given = F.lit(None).cast("double")
    for name, weight in s.weights:
        given = F.when(F.col("source") == name, float(weight)).otherwise(given)
    share = F.col("total") / F.sum("total").over(everything)
    weight = by_source.withColumn("weight", F.coalesce(given, F.round(F.pow(share, F.lit(s.temperature)), 9)))
    budget = F.floor(F.round(F.col("weight") / F.sum("weight").over(everything), 9) * (F.sum("total").over(everything) * s.budget)).cast("bigint")
    budgets = weight.withColumn("budget", budget).withColumn("epochs", F.floor(F.col("budget") / F.col("total")).cast("bigint"))
    budgets = budgets.withColumn("rest", F.col("budget") - F.col("epochs") * F.col("total")).select("source", "total", "budget", "epochs", "rest")
    held = _store.small(_store.materialise(budgets), MOST_BROADCAST)

    spot = F.floor((1 - F.exp(-F.col("key") / 2)) * s.ranges).cast("bigint")  # grows with the key
    histogram = units.groupBy("source", spot.alias("spot")).agg(F.sum("tokens").alias("tokens"))
    running = W.partitionBy("source").orderBy("spot")
    before = F.sum("tokens").over(running) - F.col("tokens")
    # the range in which the running sum passes the rest, or the last one
    h = histogram.withColumn("before", before).alias("h").join(held.alias("b"), F.expr("h.source <=> b.source"))
    crossing = h.where("h.before <= b.rest").groupBy(F.col("h.source").alias("source")).agg(F.max(F.struct("h.spot", "h.before")).alias("x"), F.first("b.rest").alias("rest"))
    crossing = crossing.select(F.col("source").alias("c_source"), F.col("x.spot").alias("c_spot"), F.col("x.before").alias("c_before"), F.col("rest").alias("c_rest"))
    crossing = _store.small(_store.materialise(crossing), MOST_BROADCAST)
    inside = units.withColumn("spot", spot).join(crossing, F.expr("source <=> c_source and spot = c_spot"))
    in_order = W.partitionBy("source").orderBy("key", "id")
    upto = F.col("c_before") + F.sum("tokens").over(in_order)
    taken = inside.withColumn("upto", upto).where("upto <= c_rest").groupBy("source").agg(F.max(F.struct("key", "id")).alias("last"))
    # A range of which nothing fits still has all ranges before it: cut just under it.
    t = held.alias("b").join(crossing, F.expr("b.source <=> c_source"), "left").join(taken.alias("t"), F.expr("b.source <=> t.source"), "left")
    cuts = t.select("b.source", "b.total", "b.budget", "b.epochs", F.col("c_spot").alias("cut_spot"), F.col("t.last.key").alias("cut_key"), F.col("t.last.id").alias("cut_id"))
    return _store.small(_store.materialise(cuts), MOST_BROADCAST)


def _copies(frame: DataFrame, cuts: DataFrame, key: Column, identity: Column, s: Settings, name: str) -> DataFrame:
    """``frame`` with how often each row is taken."""
    spot = F.floor((1 - F.exp(-key / 2)) * s.ranges).cast("bigint")
    cut = _store.fresh([*frame.columns, name], f"{name}_cut")
    c = cuts.select(F.struct("source", "epochs", "cut_spot", "cut_key", "cut_id").alias(cut))
    joined = frame.join(c, F.col("source").eqNullSafe(F.col(f"{cut}.source")))
    inside = (spot == F.col(f"{cut}.cut_spot")) & ((key < F.col(f"{cut}.cut_key")) | ((key == F.col(f"{cut}.cut_key")) & (identity <= F.col(f"{cut}.cut_id"))))
    extra = F.coalesce((spot < F.col(f"{cut}.cut_spot")) | inside, F.lit(False))
    return joined.withColumn(name, F.col(f"{cut}.epochs") + extra.cast("bigint")).drop(cut)


def select(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> DataFrame:
    """doc_id, source, n_tokens, copies of every document that is taken at least once.

    Null sources are one source; null doc_ids are told apart by text; repeated rows of a
    doc_id are one document of the sum of their tokens, with copies of the sum.  Null
    texts count one token.  Missing labels: all documents weigh the same.  doc_id may be of
    any type that casts to a string.
    """
    units = _store.materialise(_units(docs, labels, s))
    taken = _copies(units, plan(units, s), F.col("key"), F.col("id"), s, "copies")
    taken = taken.where("copies > 0")
    return taken.select("doc_id", "source", F.col("tokens").alias("n_tokens"), "copies")


def mix(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> DataFrame:
    """``docs`` with each row as often as its document is taken, all columns kept."""
    names = docs.columns
    units = _store.materialise(_units(docs, labels, s))
    cuts = plan(units, s)
    weight, key, identity, copies = (_store.fresh(names, f"mix_{x}") for x in ("weight", "key", "id", "copies"))
    quality = _quality(labels, s).withColumnRenamed("weight", weight)
    marked = docs.join(quality, "doc_id", "left").withColumn(identity, _identity())
    marked = marked.withColumn(key, _key(F.col(identity), F.coalesce(weight, F.lit(s.unknown)), s))
    taken = _copies(marked, cuts, F.col(key), F.col(identity), s, copies).where(F.col(copies) > 0)
    again = _store.fresh(names, "mix_epoch")
    repeated = taken.withColumn(again, F.explode(F.sequence(F.lit(1).cast("bigint"), F.col(copies))))
    return repeated.select(*[F.col(f"`{c}`") for c in names])


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return select(_store.table(spark, sf_dir, "documents"), _store.table(spark, sf_dir, "labels"))


def _sql(s: Settings = Settings()) -> str:
    return f"""
with quality as (
  select doc_id, case when min(quality) > 0 then {s.good}::double else {s.bad}::double end as weight
  from labels where doc_id is not null and quality is not null group by doc_id),
units as (
  select source, d.doc_id::varchar as id,
         min(-ln((('0x' || substr(md5('{s.seed}-' || d.doc_id::varchar), 1, 13))::bigint::double + 0.5) / 4503599627370496::double)
             / coalesce(weight, {s.unknown}::double)) as key,
         sum(length(text) - length(replace(text, ' ', '')) + 1)::bigint as tokens
  from documents d left join quality q on q.doc_id = d.doc_id group by source, d.doc_id),
totals as (select source, sum(tokens)::bigint as total from units group by source),
weights as (select *, round(pow(total::double / sum(total) over ()::double, {s.temperature}::double), 9) as weight from totals),
budgets as (
  select *, floor(round(weight / sum(weight) over (), 9) * (sum(total) over ()::double * {s.budget}::double))::bigint as budget from weights),
parts as (select *, budget // total as epochs, budget % total as rest from budgets),
ordered as (
  select u.source, id, u.tokens, epochs, rest,
         sum(u.tokens) over (partition by u.source order by key, id rows unbounded preceding) as upto
  from units u join parts p on u.source is not distinct from p.source)
select id::bigint as doc_id, source, tokens as n_tokens, (epochs + case when upto <= rest then 1 else 0 end)::bigint as copies
from ordered where epochs > 0 or upto <= rest"""


OP8_SQL = _sql()
