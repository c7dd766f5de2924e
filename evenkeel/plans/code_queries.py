"""Codes, patterns, loads: tables that depend on no data."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from evenkeel import hashing
from evenkeel.functions import metrics
from evenkeel.operators import codes, decode, placement
from evenkeel.operators.stragglers import late_table
from evenkeel.sources import datasets

QUERIES, ORACLES = {}, {}


def worked_example(spark, sf_dir):
    code = codes.example3()
    rows = []
    for late in range(3):
        a = decode.decode_row(code, [w for w in range(3) if w != late])
        rows += [(late, int(w), float(round(a[w], 6)) + 0.0, float(round((a @ code.matrix)[w], 6))) for w in range(3)]
    return spark.createDataFrame(rows, "late int, worker int, weight double, product double")


QUERIES["worked_example"] = worked_example
ORACLES["worked_example"] = """
with b(worker, j0, j1, j2) as (values (0, 0.5, 1.0, 0.0), (1, 0.0, 1.0, -1.0), (2, 0.5, 0.0, 1.0)),
a(late, w0, w1, w2) as (values (0, 0.0, 1.0, 2.0), (1, 1.0, 0.0, 1.0), (2, 2.0, -1.0, 0.0)),
cells as (select a.late, b.worker, case b.worker when 0 then w0 when 1 then w1 else w2 end as weight, j0, j1, j2 from a, b),
p as (select late, sum(weight * j0) as p0, sum(weight * j1) as p1, sum(weight * j2) as p2 from cells group by late)
select c.late::int as late, c.worker::int as worker, c.weight::double as weight,
       (case c.worker when 0 then p0 when 1 then p1 else p2 end)::double as product
from cells c join p on c.late = p.late"""


def _block(n, s):
    def table(spark, sf_dir):
        return codes.block_code(n, s).triplets(spark)

    return table


def _support(n, s):
    def table(spark, sf_dir):
        w = spark.range(n).select(F.col("id").cast("int").alias("worker"))
        return w.select("worker", F.explode(F.transform(F.sequence(F.lit(0), F.lit(s)), lambda j: F.pmod(F.col("worker") + j, F.lit(n)))).alias("block"))

    return table


for n, s in ((6, 2), (12, 1), (12, 2)):
    QUERIES[f"code_block_{n}_{s}"] = _block(n, s)
    ORACLES[f"code_block_{n}_{s}"] = f"""
select w::int as worker, j::int as block, 1.0::double as coef
from generate_series(0, {n - 1}) a(w), generate_series(0, {n - 1}) b(j) where j // {s + 1} = w % {n // (s + 1)}"""
    QUERIES[f"code_ring_support_{n}_{s}"] = _support(n, s)
    ORACLES[f"code_ring_support_{n}_{s}"] = f"select w::int as worker, ((w + j) % {n})::int as block from generate_series(0, {n - 1}) a(w), generate_series(0, {s}) b(j)"


def _closed(n, s):
    def table(spark, sf_dir):
        t = codes.ring_code_closed(n, s).triplets(spark)
        return t.select("worker", "block", (F.round("coef", 6) + 0.0).alias("coef"))

    return table


QUERIES["code_ring_closed_12_1"] = _closed(12, 1)
ORACLES["code_ring_closed_12_1"] = """
with h as (select j, case when j < 11 then j + 1 else -66 end::double as h from generate_series(0, 11) t(j))
select a.j::int as worker, a.j::int as block, 1.0::double as coef from h a
union all select a.j::int, b.j::int, round(-a.h / b.h, 6) + 0.0 from h a join h b on b.j = (a.j + 1) % 12"""
QUERIES["code_ring_closed_12_2"] = _closed(12, 2)
ORACLES["code_ring_closed_12_2"] = """
with h as (select j, case when j < 11 then j + 1 else -66 end::double as h1, case when j < 11 then (j + 1) * (j + 1) else -506 end::double as h2
           from generate_series(0, 11) t(j)),
r as (select a.j, b.j as b, c.j as c, -(a.h1 * c.h2 - c.h1 * a.h2) / (b.h1 * c.h2 - c.h1 * b.h2) as x,
             -(b.h1 * a.h2 - a.h1 * b.h2) / (b.h1 * c.h2 - c.h1 * b.h2) as y
      from h a join h b on b.j = (a.j + 1) % 12 join h c on c.j = (a.j + 2) % 12)
select j::int as worker, j::int as block, 1.0::double as coef from r
union all select j::int, b::int, round(x, 6) + 0.0 from r union all select j::int, c::int, round(y, 6) + 0.0 from r"""


def decode_block_6_2(spark, sf_dir):
    """All 15 patterns: the workers whose answers are used."""
    return decode.decode_table(spark, codes.block_code(6, 2)).groupBy("pattern").agg(F.concat_ws(",", F.sort_array(F.collect_list("worker"))).alias("used"), F.sum("coef").alias("total"))


QUERIES["decode_block_6_2"] = decode_block_6_2
ORACLES["decode_block_6_2"] = """
with w as (select i from generate_series(0, 5) t(i)),
sets as (select row_number() over (order by a.i, b.i, c.i, d.i) - 1 as pattern, [a.i, b.i, c.i, d.i] as alive
         from w a join w b on a.i < b.i join w c on b.i < c.i join w d on c.i < d.i),
picks as (select pattern, min(u) as pick from (select pattern, unnest(alive) as u from sets) group by pattern, u % 2)
select pattern::bigint as pattern, string_agg(pick::varchar, ',' order by pick) as used, count(*)::double as total from picks group by pattern"""


def decode_chain_ring_12_1(spark, sf_dir):
    """Ring code s = 1 with integer weights: closed-form decoding rows as running sums."""
    h = codes.integer_null_matrix(12, 1)[0]
    rows = [(late, w, float(round(a[w], 6)) + 0.0) for late in range(12) for a in [decode.chain_row_s1(h, late)] for w in range(12) if w != late]
    return spark.createDataFrame(rows, "late int, worker int, coef double")


QUERIES["decode_chain_ring_12_1"] = decode_chain_ring_12_1
ORACLES["decode_chain_ring_12_1"] = """
with h as (select j, case when j < 11 then j + 1 else -66 end::double as h from generate_series(0, 11) t(j)),
walk as (select m, step, (m + step) % 12 as worker from generate_series(0, 11) a(m), generate_series(1, 11) b(step)),
sums as (select m, worker, h, sum(h) over (partition by m order by step) as total from walk join h on h.j = worker)
select m::int as late, worker::int as worker, round(total / h, 6) + 0.0 as coef from sums"""

_CODES = (("block", 6, 2), ("block", 12, 1), ("block", 12, 2), ("ring", 6, 2), ("ring", 12, 1), ("ring", 12, 2), ("ring", 12, 3), ("full_copy", 5, 4), ("uncoded", 4, 0), ("example3", 3, 1))


def _make(name, n, s):
    return {"block": lambda: codes.block_code(n, s), "ring": lambda: codes.ring_code(n, s), "full_copy": lambda: codes.full_copy_code(n), "uncoded": lambda: codes.identity_code(n), "example3": codes.example3}[name]()


def span_check_all(spark, sf_dir):
    rows = []
    for name, n, s in _CODES:
        code = _make(name, n, s)
        rows.append((name, n, s, len(codes.patterns(n, s)), decode.span_check(code)[0], n > s + 1 and decode.span_check(code, s + 1)[0]))
    return spark.createDataFrame(rows, "code string, n int, s int, patterns bigint, ok boolean, survives_more boolean")


QUERIES["span_check_all"] = span_check_all
ORACLES["span_check_all"] = f"""
with recursive f(i, v) as (select 0, 1::hugeint union all select i + 1, v * (i + 1) from f where i < 12),
c(code, n, s) as (values {", ".join(f"('{c}', {n}, {s})" for c, n, s in _CODES)})
select code, n::int as n, s::int as s, (a.v // (b.v * d.v))::bigint as patterns, true as ok, false as survives_more
from c join f a on a.i = n join f b on b.i = s join f d on d.i = n - s"""


def density_report(spark, sf_dir):
    rows = []
    for name, n, s in _CODES:
        code = _make(name, n, s)
        rows += [(name, n, s, int(w), int(d), codes.density_bound(n, code.k, s)) for w, d in enumerate(code.density())]
    t = spark.createDataFrame(rows, "code string, n int, s int, worker int, blocks int, bound double")
    return t.groupBy("code", "n", "s").agg(F.min("blocks").alias("least"), F.max("blocks").alias("most"), F.first("bound").alias("bound"), (F.sum("blocks") / F.col("n")).alias("replication"))


QUERIES["density_report"] = density_report
ORACLES["density_report"] = f"""
with c(code, n, s) as (values {", ".join(f"('{c}', {n}, {s})" for c, n, s in _CODES)})
select code, n::int as n, s::int as s, (s + 1)::int as least, (s + 1)::int as most, (s + 1)::double as bound, (s + 1)::double as replication from c"""

_LOADS = [(x, n, s, a) for n in (6, 12, 30) for s in (1, 2) for x, a in (("uncoded", 1.0), ("drop_s", 1.0), ("full_copy", 1.0), ("block", 1.0), ("ring", 1.0), ("two_stage", 1.2), ("two_stage", 1.5), ("two_stage", 2.0), ("two_stage", 3.0))]


def load_table(spark, sf_dir):
    rows = []
    for x, n, s, a in _LOADS:
        m = metrics.load(x, n, s, a)
        rows.append((x, n, s, a, round(m["load"], 9), m["vectors"], round(m["coded_share"], 9)))
    return spark.createDataFrame(rows, "scheme string, n int, s int, alpha double, load double, vectors int, coded_share double")


QUERIES["load_table"] = load_table
ORACLES["load_table"] = f"""
with c(scheme, n, s, alpha) as (values {", ".join(f"('{x}', {n}, {s}, {a}::double)" for x, n, s, a in _LOADS)})
select scheme, n::int as n, s::int as s, alpha,
  round(case when scheme in ('uncoded', 'drop_s') then 1.0::double / n when scheme = 'full_copy' then 1.0::double
             when scheme = 'two_stage' then (s + 1)::double / n * alpha / (s + alpha) else (s + 1)::double / n end, 9) as load,
  case when scheme = 'two_stage' then 2 else 1 end::int as vectors,
  round(case when scheme in ('uncoded', 'drop_s') then 0.0::double when scheme = 'two_stage' then (alpha - 1) / (s + alpha) else 1.0::double end, 9) as coded_share
from c"""


def two_stage_rows(spark, sf_dir):
    """Three workers, one straggler, alpha 2, on orders: rows of each part."""
    placed = placement.assign_two_stage(datasets.read(spark, sf_dir, "orders").select("o_orderkey"), F.col("o_orderkey"), codes.two_stage(3, 1, 2.0, "ring"))
    return placed.groupBy("stage", "block").agg(F.count("*").alias("rows"))


QUERIES["two_stage_rows"] = two_stage_rows
ORACLES["two_stage_rows"] = f"""
with o as (select {hashing.sql_number("o_orderkey::varchar")} as h, {hashing.sql_number("'block-' || o_orderkey::varchar")} as b from orders)
select case when h < {int(2 / 3 * (1 << 32))} then 'plain' else 'coded' end as stage, (b % 3)::int as block, count(*) as rows from o group by all"""


def block_sizes(spark, sf_dir):
    li = datasets.lineitem_integer(spark, sf_dir)
    return placement.assign_blocks(li.select("key"), F.col("key"), 12).groupBy("block").agg(F.count("*").alias("rows"))


QUERIES["block_sizes"] = block_sizes
ORACLES["block_sizes"] = f"select ({hashing.sql_number('l_orderkey || chr(45) || l_linenumber')} % 12)::int as block, count(*) as rows from lineitem group by 1"


def delays_round(spark, sf_dir):
    return late_table(spark, 20, 12, 2)


LATE_SQL = f"""
select r::int as round, w::int as worker,
       row_number() over (partition by r order by {hashing.sql_number("'delay-' || r || '-' || w")}, w) <= 2 as late
from generate_series(0, 19) a(r), generate_series(0, 11) b(w)"""
QUERIES["delays_round"] = delays_round
ORACLES["delays_round"] = LATE_SQL


def mds_checks(spark, sf_dir):
    rng = np.random.default_rng(3)
    rows = [("normal", n, s, codes.mds_check(codes.zero_sum_matrix(n, s, rng), s)[0]) for n, s in ((6, 2), (12, 2), (12, 3))]
    rows += [("integer", n, 2, codes.mds_check(codes.integer_null_matrix(n, 2), 2)[0]) for n in (6, 9, 12, 5, 8)]
    return spark.createDataFrame(rows, "matrix string, n int, s int, independent boolean")


QUERIES["mds_checks"] = mds_checks
ORACLES["mds_checks"] = """
select * from (values ('normal', 6, 2, true), ('normal', 12, 2, true), ('normal', 12, 3, true)) t(matrix, n, s, independent)
union all select 'integer', n, 2, n % 3 <> 2 from (values (6), (9), (12), (5), (8)) u(n)"""


def replica_pairs(spark, sf_dir):
    """Workers that share blocks in the ring code 12, 2: a self join."""
    t = codes.ring_code_closed(12, 2).triplets(spark)
    a, b = t.select(F.col("worker").alias("a"), "block"), t.select(F.col("worker").alias("b"), "block")
    return a.join(b, "block").where("a < b").groupBy("a", "b").agg(F.count("*").alias("shared"))


QUERIES["replica_pairs"] = replica_pairs
ORACLES["replica_pairs"] = """
with t as (select w, (w + j) % 12 as block from generate_series(0, 11) a(w), generate_series(0, 2) b(j))
select x.w::int as a, y.w::int as b, count(*) as shared from t x join t y using (block) where x.w < y.w group by all"""
