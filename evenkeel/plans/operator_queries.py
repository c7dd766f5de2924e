"""The operators around the methods: joins, sets, functions, sampling, sources and sinks."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from evenkeel import hashing
from evenkeel.operators.stragglers import late_table
from evenkeel.plans.code_queries import LATE_SQL
from evenkeel.sources import datasets

QUERIES, ORACLES = {}, {}


def _q(sql):
    def add(f):
        QUERIES[f.__name__] = f
        ORACLES[f.__name__] = sql
        return f

    return add


read = datasets.read


@_q("select o_orderpriority, count(*) as rows, sum(l_quantity)::double as quantity from lineitem join orders on l_orderkey = o_orderkey where o_orderstatus = 'F' group by 1")
def join_sort_merge(spark, sf_dir):
    li, o = read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "orders")
    both = li.select("l_orderkey", "l_quantity").hint("merge").join(o.where("o_orderstatus = 'F'").select("o_orderkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
    return both.groupBy("o_orderpriority").agg(F.count("*").alias("rows"), F.sum("l_quantity").alias("quantity"))


@_q("select o_orderpriority, count(*) as rows, sum(l_quantity)::double as quantity from lineitem join orders on l_orderkey = o_orderkey group by 1")
def join_shuffle_hash(spark, sf_dir):
    li, o = read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "orders")
    both = li.select("l_orderkey", "l_quantity").join(o.select("o_orderkey", "o_orderpriority").hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey"))
    return both.groupBy("o_orderpriority").agg(F.count("*").alias("rows"), F.sum("l_quantity").alias("quantity"))


@_q("select n_name, count(*) as suppliers from supplier join nation on s_nationkey = n_nationkey group by 1")
def join_broadcast(spark, sf_dir):
    both = read(spark, sf_dir, "supplier").join(F.broadcast(read(spark, sf_dir, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))
    return both.groupBy("n_name").agg(F.count("*").alias("suppliers"))


@_q("select c_mktsegment, count(o_orderkey) as orders, count(*) as rows from customer left join orders on c_custkey = o_custkey group by 1")
def join_outer(spark, sf_dir):
    both = read(spark, sf_dir, "customer").join(read(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left")
    return both.groupBy("c_mktsegment").agg(F.count("o_orderkey").alias("orders"), F.count("*").alias("rows"))


@_q(f"select round, count(*) as alive from ({LATE_SQL}) where not late group by round")
def alive_semi(spark, sf_dir):
    t = late_table(spark, 20, 12, 2)
    return t.join(t.where("not late").select("round", "worker"), ["round", "worker"], "left_semi").groupBy("round").agg(F.count("*").alias("alive"))


@_q(f"select round, worker from ({LATE_SQL}) where late")
def straggler_anti(spark, sf_dir):
    t = late_table(spark, 20, 12, 2)
    return t.select("round", "worker").join(t.where("not late").select("round", "worker"), ["round", "worker"], "left_anti")


@_q("""
with m as (select event_id, ts, user_id, (event_id % 100 = 0) as model from events)
select user_id, count(*) as messages, count(v.event_id) as known, coalesce(sum(m.event_id - v.event_id), 0)::bigint as staleness
from (select * from m where not model) m asof left join (select event_id, ts from m where model) v on m.ts >= v.ts group by user_id""")
def join_asof_model(spark, sf_dir):
    """The latest model version at each message.  Versions and messages are put in order
    within hourly buckets; each bucket takes over the last version before it, so no task
    holds the whole stream."""
    e = read(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), (F.col("event_id") % 100 == 0).alias("model"))
    e = e.withColumn("hour", F.expr("us div 3600000000"))
    mark = F.when(F.col("model"), F.struct("us", "event_id"))
    ends = e.groupBy("hour").agg(F.max(mark).alias("newest"))
    before = F.max("newest").over(W.orderBy("hour").rowsBetween(W.unboundedPreceding, -1))  # one row an hour
    carried = F.broadcast(ends.select("hour", before.alias("carried")))
    upto = W.partitionBy("hour").orderBy("us").rangeBetween(W.unboundedPreceding, 0)
    v = e.withColumn("own", F.max(mark).over(upto)).join(carried, "hour").where("not model")
    latest = F.coalesce("own", "carried")
    known = v.select("user_id", "event_id", latest["event_id"].alias("version"))
    return known.groupBy("user_id").agg(F.count("*").alias("messages"), F.count("version").alias("known"), F.coalesce(F.sum(F.col("event_id") - F.col("version")), F.lit(0)).alias("staleness"))


@_q("""
with d as (select event_id, ts as start, ts + interval 10 minute as stop from events where event_type = 'purchase')
select d.event_id, count(e.event_id) as messages from d join events e on e.ts >= d.start and e.ts < d.stop and e.event_type = 'click' group by d.event_id""")
def join_range_deadline(spark, sf_dir):
    """Messages between a round's opening and its deadline: a range join as an equi-join
    on ten-minute cells."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    e = read(spark, sf_dir, "events").select("event_id", "event_type", us.alias("us"))
    cell = 600_000_000
    d = e.where("event_type = 'purchase'").select(F.col("event_id").alias("round"), F.col("us").alias("start"), F.explode(F.array(F.expr(f"us div {cell}"), F.expr(f"us div {cell} + 1"))).alias("cell"))
    m = e.where("event_type = 'click'").select("us", F.expr(f"us div {cell}").alias("cell"))
    hit = d.join(m, "cell").where(f"us >= start and us < start + {cell}")
    return hit.groupBy(F.col("round").alias("event_id")).agg(F.count("*").alias("messages"))


@_q("select p::bigint as pattern, w::int as worker from generate_series(0, 14) a(p), generate_series(0, 5) b(w)")
def cross_patterns(spark, sf_dir):
    return spark.range(15).select(F.col("id").alias("pattern")).crossJoin(F.broadcast(spark.range(6).select(F.col("id").cast("int").alias("worker"))))


def _workers(spark):
    a = spark.range(8).select(F.col("id").cast("int").alias("worker"))
    return a, spark.range(4, 12).select(F.col("id").cast("int").alias("worker"))


@_q("select i::int as worker from generate_series(0, 11) t(i)")
def set_union(spark, sf_dir):
    a, b = _workers(spark)
    return a.union(b).distinct()


@_q("select i::int as worker from generate_series(4, 7) t(i)")
def set_intersect(spark, sf_dir):
    a, b = _workers(spark)
    return a.intersect(b)


@_q("select i::int as worker from generate_series(0, 3) t(i)")
def set_except(spark, sf_dir):
    a, b = _workers(spark)
    return a.subtract(b)


@_q("select i::int as worker from generate_series(0, 7) t(i) union all select i::int from generate_series(0, 3) t(i)")
def set_except_all(spark, sf_dir):
    a, b = _workers(spark)
    return a.union(a).exceptAll(a.intersect(b))


@_q("select i::int as worker, (case when i < 8 then 'a' end) as left_tag, (case when i >= 8 then 'b' end) as right_tag from generate_series(0, 11) t(i)")
def set_union_by_name(spark, sf_dir):
    a, b = _workers(spark)
    return a.withColumn("left_tag", F.lit("a")).unionByName(b.where("worker >= 8").withColumn("right_tag", F.lit("b")), allowMissingColumns=True)


@_q("""
with w as (select unnest(string_split_regex(lower(text), '[^a-z]+')) as w, source from documents)
select source, count(distinct w) as words from w where w <> '' group by source""")
def dim_exact(spark, sf_dir):
    d = read(spark, sf_dir, "documents").select("source", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("w")).where("w <> ''")
    return d.groupBy("source").agg(F.countDistinct("w").alias("words"))


def dim_approx(spark, sf_dir):
    """Within 5 % of dim_exact; a sketch, so there is no oracle."""
    d = read(spark, sf_dir, "documents").select("source", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("w")).where("w <> ''")
    return d.groupBy("source").agg(F.approx_count_distinct("w", 0.02).alias("words"))


QUERIES["dim_approx"] = dim_approx


@_q("""
select event_type, hour(ts)::int as hour, count(*) as rows, sum((props::json ->> 'k')::int)::bigint as k, count(*) filter ((props::json ->> 'k')::int >= 50) as high
from events group by all""")
def event_features(spark, sf_dir):
    e = read(spark, sf_dir, "events").withColumn("k", F.from_json("props", "k int")["k"])
    return e.groupBy("event_type", F.hour("ts").alias("hour")).agg(F.count("*").alias("rows"), F.sum("k").alias("k"), F.count(F.when(F.col("k") >= 50, 1)).alias("high"))


@_q("""
select strftime(o_orderdate, '%Y-%m') as month, dayofweek(o_orderdate)::int + 1 as weekday, count(*) as rows from orders
where o_orderpriority like '%URGENT%' or regexp_matches(o_orderpriority, '^[12]-') group by all""")
def date_features(spark, sf_dir):
    o = read(spark, sf_dir, "orders").where(F.col("o_orderpriority").like("%URGENT%") | F.col("o_orderpriority").rlike("^[12]-"))
    return o.groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month"), F.dayofweek("o_orderdate").alias("weekday")).agg(F.count("*").alias("rows"))


@_q(f"""
select (toxic = 1) as toxic, count(*) as rows, sum(case when h % 10 < case when toxic = 1 then 10 else 2 end then 1 else 0 end)::bigint as kept
from (select toxic, {hashing.sql_number("'balance-' || doc_id")} as h from labels) group by all""")
def sample_balanced(spark, sf_dir):
    """All of the rare label and a fifth of the other, by hash."""
    lab = read(spark, sf_dir, "labels").withColumn("h", hashing.md5_number(F.concat(F.lit("balance-"), F.col("doc_id").cast("string"))))
    keep = F.pmod("h", F.lit(10)) < F.when(F.col("toxic") == 1, 10).otherwise(2)
    return lab.groupBy((F.col("toxic") == 1).alias("toxic")).agg(F.count("*").alias("rows"), F.sum(keep.cast("bigint")).alias("kept"))


@_q("""
with o as (select unnest(['uncoded', 'ring']) as scheme, unnest([1.0, 2.0]::double[]) as load)
select scheme, 'load' as measure, load as value from o""")
def unpivot_loads(spark, sf_dir):
    t = spark.createDataFrame([("uncoded", 1.0), ("ring", 2.0)], "scheme string, load double")
    return t.unpivot("scheme", ["load"], "measure", "value")


@_q("""
select p_type, string_agg(p_brand, ',' order by p_brand) as brands, count(*) as n
from (select distinct p_type, p_brand from part) group by p_type""")
def brand_lists(spark, sf_dir):
    p = read(spark, sf_dir, "part").select("p_type", "p_brand").distinct()
    return p.groupBy("p_type").agg(F.array_join(F.array_sort(F.collect_list("p_brand")), ",").alias("brands"), F.count("*").alias("n"))


@_q("select block, idx, g from (select block, 1::int as idx, sum(x1)::double as g from ({s}) group by block) order by abs(g) desc, block limit 5")
def topk_coord(spark, sf_dir):
    from evenkeel.plans.gradient_queries import _blocks

    g = _blocks(spark, sf_dir, 12).groupBy("block").agg(F.sum("x1").alias("g")).withColumn("idx", F.lit(1))
    return g.orderBy(F.abs("g").desc(), "block").limit(5).select("block", "idx", "g")


def _fill():
    from evenkeel.plans.gradient_queries import samples_sql

    ORACLES["topk_coord"] = ORACLES["topk_coord"].replace("{s}", samples_sql(12))


_fill()


@_q("select count(*) as rows, sum(l_quantity)::double as quantity from lineitem where l_quantity between 10 and 20 and l_returnflag in ('A', 'R') and l_shipdate >= timestamp '1995-01-01'")
def filter_pushdown(spark, sf_dir):
    li = read(spark, sf_dir, "lineitem").where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp_ntz")))
    return li.agg(F.count("*").alias("rows"), F.sum("l_quantity").alias("quantity"))


@_q("""
with p as (select p_partkey, p_brand from part)
select a.p_brand, count(*) as parts, count(*) filter (exists (select 1 from lineitem where l_partkey = a.p_partkey and l_quantity > 49)) as bulk from p a group by a.p_brand""")
def exists_bulk(spark, sf_dir):
    p, li = read(spark, sf_dir, "part").select("p_partkey", "p_brand"), read(spark, sf_dir, "lineitem").where("l_quantity > 49").select(F.col("l_partkey").alias("p_partkey")).distinct()
    both = p.join(li.withColumn("hit", F.lit(1)), "p_partkey", "left")
    return both.groupBy("p_brand").agg(F.count("*").alias("parts"), F.count("hit").alias("bulk"))


@_q("""
select m::bigint as mask, bit_count(m)::int as alive from generate_series(0, 63) t(m) where bit_count(m) = 4""")
def alive_masks(spark, sf_dir):
    return spark.range(64).select(F.col("id").alias("mask"), F.bit_count("id").alias("alive")).where("alive = 4")


@_q("select w::int as worker, ((w + j) % 6)::int as block from generate_series(0, 5) a(w), generate_series(0, 2) b(j)")
def lateral_support(spark, sf_dir):
    """Blocks of each worker by a lateral join."""
    spark.range(6).createOrReplaceTempView("evenkeel_workers")
    return spark.sql("select cast(id as int) as worker, cast((id + j) % 6 as int) as block from evenkeel_workers, lateral (select explode(sequence(0, 2)) as j)")


@_q("""
select event_type, sum((case when event_type = 'purchase' then -0.5 else 0.5 end) * (props::json ->> 'k')::int)::double as g_k,
  sum((case when event_type = 'purchase' then -0.5 else 0.5 end) * hour(ts))::double as g_hour from events group by event_type""")
def event_grad0(spark, sf_dir):
    """First logistic gradient of purchases on event features, by kind of event."""
    e = read(spark, sf_dir, "events").withColumn("k", F.from_json("props", "k int")["k"])
    slope = 0.5 - (F.col("event_type") == "purchase").cast("double")
    return e.groupBy("event_type").agg(F.sum(slope * F.col("k")).alias("g_k"), F.sum(slope * F.hour("ts")).alias("g_hour"))


@_q("select 4::int as n, 6::int as k, true as ok, 3::int as most")
def given_code(spark, sf_dir):
    """A code of four workers and six blocks given as CSV rows: two copies of each half."""
    from evenkeel.operators import codes, decode

    lines = [f"{w},{b},1.0" for w in range(4) for b in range(6) if b // 3 == w % 2]
    table = spark.createDataFrame([(x,) for x in lines], "line string").select(F.from_csv("line", codes.TRIPLETS).alias("t")).select("t.*")
    code = codes.from_triplets(table, 4, 6, 1)
    return spark.createDataFrame([(code.n, code.k, decode.span_check(code)[0], int(code.density().max()))], "n int, k int, ok boolean, most int")
