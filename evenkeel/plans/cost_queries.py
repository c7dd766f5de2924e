"""Virtual round times and what they add up to."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from evenkeel import hashing
from evenkeel.functions import metrics
from evenkeel.operators.stragglers import late_table, trace_from_events
from evenkeel.plans import planner
from evenkeel.sources import datasets

QUERIES, ORACLES = {}, {}
N, ROUNDS, D, POINTS = 12, 20, 554_400, 100
#: scheme, s, share of the data on a worker, vectors it sends, answers waited for.
GRID = [(x, s, round(metrics.load(x, N, s, a)["load"], 12), metrics.load(x, N, s, a)["vectors"], N if x == "uncoded" else 1 if x == "full_copy" else N - s, a, round((s + 1) / (N * (s + a)), 12) if x == "two_stage" else 0.0) for s in (1, 2) for x, a in (("uncoded", 1.0), ("drop_s", 1.0), ("block", 1.0), ("ring", 1.0), ("full_copy", 1.0), ("two_stage", 1.2), ("two_stage", 2.0))]
DELAYS = (0.0, 25.0, 50.0, 100.0, 200.0, 400.0)
ROW_MS, FLOAT_MS, LATENCY_MS = 0.001, 0.0001, 1.0
#: Added before means are rounded, so that none is a tie that engines round differently.
NUDGE = 1.23e-7


def _grid(spark):
    return F.broadcast(spark.createDataFrame(GRID, "scheme string, s int, share double, vectors int, wait int, alpha double, plain double"))


def arrivals(spark):
    """scheme, s, alpha, delay_ms, round, worker, arrival_ms, wait, first_ms (of the plain part)."""
    late = late_table(spark, ROUNDS, N, 1).withColumn("s", F.lit(1)).unionByName(late_table(spark, ROUNDS, N, 2).withColumn("s", F.lit(2)))
    delays = F.broadcast(spark.createDataFrame([(d,) for d in DELAYS], "delay_ms double"))
    cells = late.join(_grid(spark), "s").crossJoin(delays)
    extra = F.col("late").cast("double") * F.col("delay_ms")
    ms = F.col("share") * D * ROW_MS + F.col("vectors") * POINTS * FLOAT_MS + LATENCY_MS + extra
    first = F.when(F.col("plain") > 0, F.col("plain") * D * ROW_MS + POINTS * FLOAT_MS + LATENCY_MS + extra).otherwise(0.0)
    return cells.select("scheme", "s", "alpha", "delay_ms", "round", "worker", "wait", ms.alias("arrival_ms"), first.alias("first_ms"))


KEYS = ("scheme", "s", "alpha", "delay_ms", "round")


def round_times(spark, sf_dir):
    """When a round ends: the answer that is waited for, and for two-stage also the last
    plain answer."""
    place = F.row_number().over(W.partitionBy(*KEYS).orderBy("arrival_ms", "worker"))
    ranked = arrivals(spark).withColumn("place", place)
    last = ranked.groupBy(*KEYS).agg(F.max(F.when(F.col("place") == F.col("wait"), F.col("arrival_ms"))).alias("waited"), F.max("first_ms").alias("first"))
    return last.select(*KEYS, F.round(F.greatest("waited", "first"), 6).alias("round_ms"))


_ROUND_SQL = f"""
with grid(scheme, s, share, vectors, wait, alpha, plain) as (values {", ".join(f"('{x}', {s}, {sh}::double, {v}, {w}, {a}::double, {pl}::double)" for x, s, sh, v, w, a, pl in GRID)}),
delays(delay_ms) as (values {", ".join(f"({d}::double)" for d in DELAYS)}),
late as (select r, w, ss, row_number() over (partition by r, ss order by {hashing.sql_number("'delay-' || r || '-' || w")}, w) <= ss as late
  from generate_series(0, {ROUNDS - 1}) a(r), generate_series(0, {N - 1}) b(w), (values (1), (2)) c(ss)),
cells as (select scheme, s, alpha, delay_ms, r as round, w, wait,
    share * {D} * {ROW_MS}::double + vectors * {POINTS} * {FLOAT_MS}::double + {LATENCY_MS} + late::int * delay_ms as arrival,
    case when plain > 0 then plain * {D} * {ROW_MS}::double + {POINTS} * {FLOAT_MS}::double + {LATENCY_MS} + late::int * delay_ms else 0 end as first
  from late join grid on ss = s, delays),
ranked as (select *, row_number() over (partition by scheme, s, alpha, delay_ms, round order by arrival, w) as place from cells)
select scheme, s::int as s, alpha, delay_ms, round::int as round, round(greatest(max(case when place = wait then arrival end), max(first)), 6) as round_ms
from ranked group by scheme, s, alpha, delay_ms, round"""
QUERIES["round_times"] = round_times
ORACLES["round_times"] = _ROUND_SQL


def time_summary(spark, sf_dir):
    t = round_times(spark, sf_dir)
    return t.groupBy("scheme", "s", "alpha", "delay_ms").agg(F.round(F.avg("round_ms") + NUDGE, 4).alias("mean_ms"), F.round(F.stddev_samp("round_ms"), 4).alias("std_ms"))


QUERIES["time_summary"] = time_summary
ORACLES["time_summary"] = f"select scheme, s, alpha, delay_ms, round(avg(round_ms) + {NUDGE}, 4) as mean_ms, round(stddev_samp(round_ms), 4) as std_ms from ({_ROUND_SQL}) group by all"


def _sets(kind):
    def run(spark, sf_dir):
        t = round_times(spark, sf_dir)
        if kind == "gsets":
            t.createOrReplaceTempView("evenkeel_round_times")
            g = spark.sql(f"select scheme, s, delay_ms, cast(grouping_id() as bigint) as level, round(avg(round_ms) + {NUDGE}, 4) as mean_ms from evenkeel_round_times group by grouping sets ((scheme, s, delay_ms), (scheme, delay_ms), (s), ())")
        else:
            g = getattr(t, kind)("scheme", "s", "delay_ms").agg(F.grouping_id().cast("bigint").alias("level"), F.round(F.avg("round_ms") + NUDGE, 4).alias("mean_ms"))
        return g.select(F.coalesce("scheme", F.lit("all")).alias("scheme"), F.coalesce("s", F.lit(-1)).alias("s"), F.coalesce("delay_ms", F.lit(-1.0)).alias("delay_ms"), "level", "mean_ms")

    return run


for kind, clause in (("cube", "cube (scheme, s, delay_ms)"), ("rollup", "rollup (scheme, s, delay_ms)"), ("gsets", "grouping sets ((scheme, s, delay_ms), (scheme, delay_ms), (s), ())")):
    QUERIES[f"cost_{kind}"] = _sets(kind)
    ORACLES[f"cost_{kind}"] = f"""select coalesce(scheme, 'all') as scheme, coalesce(s, -1)::int as s, coalesce(delay_ms, -1)::double as delay_ms, level, mean_ms
from (select scheme, s, delay_ms, grouping(scheme, s, delay_ms)::bigint as level, round(avg(round_ms) + {NUDGE}, 4) as mean_ms from ({_ROUND_SQL}) group by {clause})"""


def pivot_times(spark, sf_dir):
    """Mean times with a column a scheme, as in a plot against the delay."""
    t = round_times(spark, sf_dir).where("alpha <> 2.0")
    return t.groupBy("s", "delay_ms").pivot("scheme", ["uncoded", "drop_s", "block", "ring", "two_stage"]).agg(F.round(F.avg("round_ms") + NUDGE, 4))


QUERIES["pivot_times"] = pivot_times
ORACLES["pivot_times"] = f"select s, delay_ms, {', '.join(f'round(avg(case when scheme = {chr(39)}{x}{chr(39)} then round_ms end) + {NUDGE}, 4) as {x}' for x in ('uncoded', 'drop_s', 'block', 'ring', 'two_stage'))} from ({_ROUND_SQL}) where alpha <> 2.0 group by s, delay_ms"


def cum_time(spark, sf_dir):
    t = round_times(spark, sf_dir).where("delay_ms = 100.0 and s = 1")
    run = W.partitionBy("scheme", "alpha").orderBy("round").rowsBetween(W.unboundedPreceding, 0)
    return t.select("scheme", "alpha", "round", F.round(F.sum("round_ms").over(run), 4).alias("cum_ms"))


QUERIES["cum_time"] = cum_time
ORACLES["cum_time"] = f"select scheme, alpha, round, round(sum(round_ms) over (partition by scheme, alpha order by round rows unbounded preceding), 4) as cum_ms from ({_ROUND_SQL}) where delay_ms = 100.0 and s = 1"


def crossover(spark, sf_dir):
    """The scheme with the shortest expected round by price of computing and sending."""
    rows = [(r, f, x) for r in (0.0001, 0.001, 0.01) for f in (0.00001, 0.0001, 0.001, 0.01) for x in [planner.advise(12, 2, 60_000, 10_000, r, f, 2.0).scheme]]
    return spark.createDataFrame(rows, "row_ms double, float_ms double, best string")


QUERIES["crossover"] = crossover
ORACLES["crossover"] = """
with g as (select r, f from (values (0.0001::double), (0.001::double), (0.01::double)) a(r), (values (0.00001::double), (0.0001::double), (0.001::double), (0.01::double)) b(f)),
t as (select r, f, 1 as o, 'uncoded' as x, 60000.0::double / 12 * r * 2 + 10000 * f as ms from g
  union all select r, f, 2, 'block', 60000.0::double * 3 / 12 * r + 10000 * f from g
  union all select r, f, 3, 'two_stage_block', greatest(60000.0::double * 3 / 48 * r * 2 + 10000 * f, 60000.0::double * 3 / 12 * 2 / 4 * r + 20000 * f) from g),
k as (select *, row_number() over (partition by r, f order by round(ms, 6), o) as n from t)
select r as row_ms, f as float_ms, x as best from k where n = 1"""


# --- natural delays, from events -------------------------------------------------------

_TRACE_SQL = """select (user_id % {n})::int as worker, row_number() over (partition by user_id % {n} order by ts, event_id)::int as round, value as delay_ms from events"""


def _trace(spark, sf_dir, n=50, most_rounds=None):
    return trace_from_events(datasets.read(spark, sf_dir, "events"), n, most_rounds)


def comm_profile(spark, sf_dir):
    """Mean and deviation of each worker's delays over 100 rounds, and against the typical."""
    c = metrics.communication(_trace(spark, sf_dir, most_rounds=100))
    return c.select("worker", F.round("mean_ms", 6).alias("mean_ms"), F.round("std_ms", 6).alias("std_ms"), "rounds", F.round("ratio", 6).alias("ratio"))


QUERIES["comm_profile"] = comm_profile
ORACLES["comm_profile"] = f"""
with m as (select worker, avg(delay_ms) as a, stddev_samp(delay_ms) as sd, count(*) as rounds from ({_TRACE_SQL.format(n=50)}) where round <= 100 group by worker)
select worker, round(a, 6) as mean_ms, round(sd, 6) as std_ms, rounds, round(a / median(a) over (), 6) as ratio from m"""


def arrival_rank(spark, sf_dir):
    w = W.partitionBy("round").orderBy("delay_ms")
    fixed = W.partitionBy("round").orderBy("delay_ms", "worker")
    return _trace(spark, sf_dir).select("round", "worker", F.row_number().over(fixed).alias("place"), F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.round(F.percent_rank().over(w), 9).alias("percent"), F.ntile(4).over(fixed).alias("quarter"), F.round(F.cume_dist().over(w), 9).alias("share"))


QUERIES["arrival_rank"] = arrival_rank
ORACLES["arrival_rank"] = f"""
select round, worker, (row_number() over f)::int as place, (rank() over w)::int as rank, (dense_rank() over w)::int as dense, round(percent_rank() over w, 9) as percent,
  (ntile(4) over f)::int as quarter, round(cume_dist() over w, 9) as share
from ({_TRACE_SQL.format(n=50)}) window w as (partition by round order by delay_ms), f as (partition by round order by delay_ms, worker)"""


def nth_arrival(spark, sf_dir):
    """First, (n - s)-th and last answer of each round on ten workers."""
    w = W.partitionBy("round").orderBy("delay_ms", "worker").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    t = _trace(spark, sf_dir, 10)
    return t.select("round", F.first("delay_ms").over(w).alias("first_ms"), F.nth_value("delay_ms", 8).over(w).alias("eighth_ms"), F.last("delay_ms").over(w).alias("last_ms")).distinct()


QUERIES["nth_arrival"] = nth_arrival
ORACLES["nth_arrival"] = f"""
select distinct round, first_value(delay_ms) over w as first_ms, nth_value(delay_ms, 8) over w as eighth_ms, last_value(delay_ms) over w as last_ms
from ({_TRACE_SQL.format(n=10)}) window w as (partition by round order by delay_ms, worker rows between unbounded preceding and unbounded following)"""


def lat_quantiles(spark, sf_dir):
    e = datasets.read(spark, sf_dir, "events")
    return e.groupBy("event_type").agg(*[F.round(F.expr(f"percentile(value, {q})"), 6).alias(f"p{int(q * 100)}") for q in (0.5, 0.9, 0.99)], F.round(F.stddev_samp("value"), 6).alias("std"))


QUERIES["lat_quantiles"] = lat_quantiles
ORACLES["lat_quantiles"] = "select event_type, " + ", ".join(f"round(quantile_cont(value, {q}), 6) as p{int(q * 100)}" for q in (0.5, 0.9, 0.99)) + ", round(stddev_samp(value), 6) as std from events group by event_type"


def lat_moving(spark, sf_dir):
    """Mean of a worker's last hour."""
    t = datasets.read(spark, sf_dir, "events").select(F.pmod("user_id", F.lit(50)).cast("int").alias("worker"), "event_id", "value", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    w = W.partitionBy("worker").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return t.select("worker", "event_id", F.round(F.avg("value").over(w), 6).alias("moving_ms"))


QUERIES["lat_moving"] = lat_moving
ORACLES["lat_moving"] = """
select (user_id % 50)::int as worker, event_id, round(avg(value) over (partition by user_id % 50 order by epoch_us(ts) range between 3600000000 preceding and current row), 6) as moving_ms from events"""


def slowest_workers(spark, sf_dir):
    t = _trace(spark, sf_dir).groupBy("worker").agg(F.round(F.avg("delay_ms"), 6).alias("mean_ms"))
    return t.orderBy(F.desc("mean_ms"), "worker").limit(5)


QUERIES["slowest_workers"] = slowest_workers
ORACLES["slowest_workers"] = f"select worker, round(avg(delay_ms), 6) as mean_ms from ({_TRACE_SQL.format(n=50)}) group by worker order by 2 desc, 1 limit 5"


def representation(spark, sf_dir):
    """Share of each source's labelled documents in the gradient when worker 3 of 12 is
    always late: dropped, and through a code."""
    d, lab = datasets.read(spark, sf_dir, "documents"), datasets.read(spark, sf_dir, "labels")
    both = d.select("doc_id", "source").join(lab.select("doc_id", "toxic"), "doc_id").withColumn("used", hashing.block_of(F.col("doc_id").cast("string"), 12) != 3)
    r = metrics.representation(both, F.col("used"), "source")
    toxic = both.groupBy("source").agg(F.sum("toxic").alias("toxic"), F.sum(F.when(F.col("used"), F.col("toxic")).otherwise(0)).alias("toxic_used"))
    return r.join(toxic, "source").select("source", "rows", F.round("share", 9).alias("dropped_share"), F.lit(1.0).alias("coded_share"), "toxic", "toxic_used")


QUERIES["representation"] = representation
ORACLES["representation"] = f"""
with b as (select source, toxic, {hashing.sql_number("doc_id::varchar")} % 12 <> 3 as used from documents join labels using (doc_id))
select source, count(*) as rows, round(avg(used::int), 9) as dropped_share, 1.0::double as coded_share, sum(toxic)::bigint as toxic, sum(case when used then toxic else 0 end)::bigint as toxic_used from b group by source"""


def length_bias(spark, sf_dir):
    """Cost grows with length: the block with most characters in a round is late and lost.
    Share kept by length, documents and conversations."""
    docs = datasets.read(spark, sf_dir, "documents").select(F.lit("documents").alias("kind"), F.col("doc_id").cast("string").alias("key"), F.col("n_chars").alias("n"))
    turns = datasets.read(spark, sf_dir, "conversations").select(F.lit("conversations").alias("kind"), F.concat_ws("-", "conv_id", "turn").alias("key"), F.length("text").cast("bigint").alias("n"))
    d = docs.unionByName(turns).withColumn("block", hashing.block_of(F.col("key"), 40)).withColumn("bucket", F.floor(F.log2(F.col("n") + 1)).cast("int"))
    cost = d.groupBy("kind", "block").agg(F.sum("n").alias("cost"))
    place = F.row_number().over(W.partitionBy("kind").orderBy(F.desc("cost"), "block"))
    late = F.broadcast(cost.withColumn("place", place).select("kind", "block", (F.col("place") > 8).alias("used")))
    return d.join(late, ["kind", "block"]).groupBy("kind", "bucket").agg(F.count("*").alias("rows"), F.sum(F.col("used").cast("bigint")).alias("kept"))


QUERIES["length_bias"] = length_bias
ORACLES["length_bias"] = f"""
with u as (select 'documents' as kind, doc_id::varchar as key, n_chars as n from documents union all select 'conversations', conv_id || '-' || turn, length(text) from conversations),
d as (select *, {hashing.sql_number("key")} % 40 as block, floor(log2(n + 1))::int as bucket from u),
c as (select kind, block, row_number() over (partition by kind order by sum(n) desc, block) > 8 as used from d group by kind, block)
select kind, bucket, count(*) as rows, sum(used::int)::bigint as kept from d join c using (kind, block) group by kind, bucket"""


def event_variability(spark, sf_dir):
    """Two delay traces from kinds of events: variability between kinds of machines."""
    e = datasets.read(spark, sf_dir, "events").where(F.col("event_type").isin("view", "error", "click"))
    t = e.select("event_type", F.pmod("user_id", F.lit(10)).cast("int").alias("worker"), F.col("value").alias("delay_ms"))
    m = t.groupBy("event_type", "worker").agg(F.avg("delay_ms").alias("m"))
    return m.groupBy("event_type").agg(F.round(F.avg("m"), 6).alias("mean_ms"), F.round(F.stddev_samp("m"), 6).alias("between_ms"))


QUERIES["event_variability"] = event_variability
ORACLES["event_variability"] = """
with m as (select event_type, user_id % 10 as w, avg(value) as m from events where event_type in ('view', 'error', 'click') group by all)
select event_type, round(avg(m), 6) as mean_ms, round(stddev_samp(m), 6) as between_ms from m group by event_type"""
