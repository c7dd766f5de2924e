"""Gradients, messages and decoded sums."""

from __future__ import annotations

from math import comb

import numpy as np
from pyspark.sql import functions as F

from evenkeel import hashing
from evenkeel.functions import metrics
from evenkeel.functions.losses import Logistic, Squared
from evenkeel.operators import codes, decode, gradient, messages, placement
from evenkeel.operators.stragglers import Stragglers
from evenkeel.sources import datasets

QUERIES, ORACLES = {}, {}
X = datasets.INTEGER
KEY = "l_orderkey || chr(45) || l_linenumber"
BETA = [0.02, -0.05, 0.03, 0.1]


def samples_sql(k: int) -> str:
    return f"""select ({hashing.sql_number(KEY)} % {k})::int as block, case when l_returnflag = 'R' then 1.0 else 0.0 end::double as y,
  l_quantity::double as x1, round(l_discount * 100)::double as x2, round(l_tax * 100)::double as x3, 1.0::double as x4 from lineitem"""


def _blocks(spark, sf_dir, k):
    return placement.assign_blocks(datasets.lineitem_integer(spark, sf_dir), F.col("key"), k)


def _rounded(df, names, digits=6):
    return df.select(*[(F.round(c, digits) + 0.0).alias(c) if c in names else F.col(c) for c in df.columns])


G = [f"g{j}" for j in range(1, 5)]


def grad0_logit_block(spark, sf_dir):
    return gradient.partial_wide(_blocks(spark, sf_dir, 12), Logistic(), [0.0] * 4, X)


def grad0_sq_block(spark, sf_dir):
    return gradient.partial_wide(_blocks(spark, sf_dir, 12), Squared(), [0.0] * 4, X)


def grad_logit_at_beta(spark, sf_dir):
    return _rounded(gradient.partial_wide(_blocks(spark, sf_dir, 12), Logistic(), BETA, X), G, 5)


_MARGIN = " + ".join(f"x{j} * ({b}::double)" for j, b in enumerate(BETA, 1))
QUERIES |= {"grad0_logit_block": grad0_logit_block, "grad0_sq_block": grad0_sq_block, "grad_logit_at_beta": grad_logit_at_beta}
ORACLES["grad0_logit_block"] = f"select block, {', '.join(f'sum((0.5 - y) * x{j})::double as g{j}' for j in range(1, 5))}, count(*) as rows from ({samples_sql(12)}) group by block"
ORACLES["grad0_sq_block"] = f"select block, {', '.join(f'sum(-y * x{j})::double + 0.0 as g{j}' for j in range(1, 5))}, count(*) as rows from ({samples_sql(12)}) group by block"
ORACLES["grad_logit_at_beta"] = f"select block, {', '.join(f'round(sum((1 / (1 + exp(-({_MARGIN}))) - y) * x{j}), 5) + 0.0 as g{j}' for j in range(1, 5))}, count(*) as rows from ({samples_sql(12)}) group by block"


def _kernel(name):
    def run(spark, sf_dir):
        s = _blocks(spark, sf_dir, 12)
        if name == "sparse":
            xs = F.array(*[F.struct(F.lit(j).alias("idx"), F.col(c).alias("val")) for j, c in enumerate(X)])
            long = gradient.partial_sparse(s.select("block", "y", F.col("key").alias("row_id"), xs.alias("xs")), Logistic(), np.array(BETA))
            long = long.withColumn("idx", F.col("idx") + 1)
        elif name == "sparse_joined":
            xs = F.array(*[F.struct(F.lit(j).alias("idx"), F.col(c).alias("val")) for j, c in enumerate(X)])
            once = s.withColumn("row_id", F.monotonically_increasing_id())
            long = gradient.partial_sparse(once.select("block", "y", "row_id", xs.alias("xs")), Logistic(), np.array(BETA), limit=0)
            long = long.withColumn("idx", F.col("idx") + 1)
        else:
            long = gradient.partial_gradients(s.withColumn("x", F.array(*X)), Logistic(), np.array(BETA), name, X)
        return long.select("block", F.col("idx").cast("int").alias("idx"), (F.round("g", 4) + 0.0).alias("g"))

    return run


for k in ("wide", "array", "arrow", "sparse", "sparse_joined"):
    QUERIES[f"grad_kernel_{k}"] = _kernel(k)
    ORACLES[f"grad_kernel_{k}"] = " union all ".join(f"select block, {j}::int as idx, round(sum((1 / (1 + exp(-({_MARGIN}))) - y) * x{j}), 4) + 0.0 as g from ({samples_sql(12)}) group by block" for j in range(1, 5))


def _messages(make, digits):
    def run(spark, sf_dir):
        code = make()
        g = gradient.partial_wide(_blocks(spark, sf_dir, code.k), Logistic(), [0.0] * 4, X)
        return _rounded(messages.encode_wide(g, code.triplets(spark), 4), [f"v{j}" for j in range(1, 5)], digits)

    return run


QUERIES["messages_block_12_2"] = _messages(lambda: codes.block_code(12, 2), 6)
QUERIES["messages_ring_12_1"] = _messages(lambda: codes.ring_code_closed(12, 1), 4)
_G0 = ORACLES["grad0_logit_block"]
ORACLES["messages_block_12_2"] = f"""
with g as ({_G0}), b as (select w, j from generate_series(0, 11) p(w), generate_series(0, 11) q(j) where j // 3 = w % 4)
select w::int as worker, {", ".join(f"round(sum(g{j}), 6) + 0.0 as v{j}" for j in range(1, 5))} from b join g on g.block = b.j group by w"""
ORACLES["messages_ring_12_1"] = f"""
with g as ({_G0}), h as (select j, case when j < 11 then j + 1 else -66 end::double as h from generate_series(0, 11) t(j)),
b as (select j as w, j, 1.0::double as coef from h union all select a.j, c.j, -a.h / c.h from h a join h c on c.j = (a.j + 1) % 12)
select w::int as worker, {", ".join(f"round(sum(coef * g{j}), 4) + 0.0 as v{j}" for j in range(1, 5))} from b join g on g.block = b.j group by w"""


def _full(make):
    """The decoded gradient of every pattern; each equals the plain sum."""

    def run(spark, sf_dir):
        code = make()
        g = gradient.partial_wide(_blocks(spark, sf_dir, code.k), Logistic(), [0.0] * 4, X)
        sent = messages.encode_wide(g, code.triplets(spark), 4)
        return _rounded(messages.combine_wide(sent, decode.decode_table(spark, code), 4), G, 3)

    return run


_FULL = {
    "coded_full_block": (lambda: codes.block_code(6, 2), comb(6, 2)),
    "coded_full_block_12_2": (lambda: codes.block_code(12, 2), comb(12, 2)),
    "coded_full_ring": (lambda: codes.ring_code(12, 2), comb(12, 2)),
    "coded_full_ring_12_1": (lambda: codes.ring_code(12, 1), comb(12, 1)),
    "coded_full_example3": (codes.example3, 3),
    "coded_full_full_copy": (lambda: codes.full_copy_code(4), 4),
    "coded_full_uncoded": (lambda: codes.identity_code(6), 1),
}
for name, (make, f) in _FULL.items():
    QUERIES[name] = _full(make)
    ORACLES[name] = f"with g as (select {', '.join(f'round(sum((0.5 - y) * x{j}), 3) + 0.0 as g{j}' for j in range(1, 5))} from ({samples_sql(1)})) select p::bigint as pattern, g.* from generate_series(0, {f - 1}) t(p), g"


def coded_full_two_stage(spark, sf_dir):
    """Two-stage with an inner ring code: plain sums of all and coded sums of any two of three."""
    code = codes.two_stage(3, 1, 2.0, "ring", seed=1)
    placed = placement.assign_two_stage(datasets.lineitem_integer(spark, sf_dir), F.col("key"), code)
    g = gradient.partial_wide(placed, Logistic(), [0.0] * 4, X, by=("stage", "block"))
    plain = g.where("stage = 'plain'").agg(*[F.sum(c).alias(f"p_{c}") for c in G])
    sent = messages.encode_wide(g.where("stage = 'coded'").drop("stage"), code.inner.triplets(spark), 4)
    coded = messages.combine_wide(sent, decode.decode_table(spark, code.inner), 4)
    both = coded.crossJoin(F.broadcast(plain))
    return both.select("pattern", *[(F.round(F.col(c) + F.col(f"p_{c}"), 3) + 0.0).alias(c) for c in G])


QUERIES["coded_full_two_stage"] = coded_full_two_stage
ORACLES["coded_full_two_stage"] = ORACLES["coded_full_example3"]


def coded_full_feedback(spark, sf_dir):
    """Replicas and requests: for each late pair of the ring placement, blocks summed by
    their first holder that answers."""
    code = codes.ring_code(6, 2)
    rows = {}
    for i, alive in enumerate(codes.patterns(6, 2)):
        holder = {}
        for w in alive:
            for b in code.support(w):
                holder.setdefault(int(b), int(w))
        rows[i] = holder
    asked = spark.createDataFrame([(p, b) for p, h in rows.items() for b in h], "pattern bigint, block int")
    g = gradient.partial_wide(_blocks(spark, sf_dir, 6), Logistic(), [0.0] * 4, X)
    return _rounded(asked.join(g, "block").groupBy("pattern").agg(*[F.sum(c).alias(c) for c in G]), G, 3)


QUERIES["coded_full_feedback"] = coded_full_feedback
ORACLES["coded_full_feedback"] = ORACLES["coded_full_block"]


def drop_s_grad(spark, sf_dir):
    """What is left with two of twelve workers dropped, by round, and its error."""
    rows = [(t, w) for t in range(6) for w in set(range(12)) - set(Stragglers("additive", s=2).late(t, 12))]
    alive = F.broadcast(spark.createDataFrame(rows, "round int, block int"))
    g = gradient.partial_wide(_blocks(spark, sf_dir, 12), Logistic(), [0.0] * 4, X)
    long = gradient.long_form(g, 4)
    exact = long.groupBy("idx").agg(F.sum("g").alias("exact"))
    left = long.join(alive, "block").groupBy("round", "idx").agg(F.sum("g").alias("g")).join(F.broadcast(exact), "idx")
    return metrics.gradient_error(left, "g", "exact", ("round",)).select("round", F.round("error", 6).alias("error"))


QUERIES["drop_s_grad"] = drop_s_grad
ORACLES["drop_s_grad"] = f"""
with g as ({_G0}), late as (select r, w, row_number() over (partition by r order by {hashing.sql_number("'delay-' || r || '-' || w")}, w) <= 2 as late
  from generate_series(0, 5) a(r), generate_series(0, 11) b(w)),
e as (select {", ".join(f"sum(g{j}) as e{j}" for j in range(1, 5))} from g),
s as (select r, {", ".join(f"sum(g{j}) as g{j}" for j in range(1, 5))} from late join g on g.block = w where not late group by r)
select r::int as round, round(sqrt({" + ".join(f"(g{j} - e{j}) * (g{j} - e{j})" for j in range(1, 5))}) / sqrt({" + ".join(f"e{j} * e{j}" for j in range(1, 5))}), 6) as error from s, e"""


def sparse_grad0(spark, sf_dir):
    """First gradient on hashed words of labelled documents: the 50 largest coordinates."""
    d = datasets.document_tokens(spark, sf_dir, "quality").withColumn("block", F.lit(0))
    g = gradient.partial_sparse(d, Logistic(), np.zeros(4096))
    return g.select(F.col("idx").cast("int").alias("idx"), "g").orderBy(F.abs("g").desc(), "idx").limit(50)


QUERIES["sparse_grad0"] = sparse_grad0
ORACLES["sparse_grad0"] = f"""
with d as (select doc_id, quality::double as y, unnest(string_split_regex(lower(text), '[^a-z]+')) as w from documents join labels using (doc_id)),
t as (select distinct doc_id, y, ({hashing.sql_number("w")} % 4096)::int as idx from d where w <> '')
select idx, sum(0.5 - y) as g from t group by idx order by abs(sum(0.5 - y)) desc, idx limit 50"""


def star_onehot_grad(spark, sf_dir):
    """First gradient of brand by type indicators after a six-way join."""
    d = datasets.star(spark, sf_dir)
    y = (F.col("l_returnflag") == "R").cast("double")
    return d.groupBy("p_brand", "p_type").agg(F.count("*").alias("rows"), F.sum(0.5 - y).alias("g"), F.sum((0.5 - y) * F.col("l_quantity")).alias("g_quantity"))


QUERIES["star_onehot_grad"] = star_onehot_grad
ORACLES["star_onehot_grad"] = """
select p_brand, p_type, count(*) as rows, sum(0.5 - case when l_returnflag = 'R' then 1 else 0 end)::double as g,
  sum((0.5 - case when l_returnflag = 'R' then 1 else 0 end) * l_quantity)::double as g_quantity
from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join part on l_partkey = p_partkey
join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey group by all"""


def embed_grad0(spark, sf_dir):
    e = datasets.embeddings_dense(spark, sf_dir).withColumn("block", F.lit(0))
    return gradient.partial_arrow(e, Logistic(), np.zeros(64)).select(F.col("idx").cast("int").alias("idx"), (F.round("g", 5) + 0.0).alias("g"))


QUERIES["embed_grad0"] = embed_grad0
ORACLES["embed_grad0"] = """
select i::int as idx, round(sum((0.5 - case when label = 0 then 1 else 0 end) * embedding[i]::double), 5) + 0.0 as g
from embeddings, generate_series(1, 64) t(i) group by i"""


_ONE_HOT_JOIN = """lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join part on l_partkey = p_partkey
join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey"""
_PLACES = ", ".join(f"({hashing.sql_number(' || chr(124) || '.join(f'{chr(39)}{c}={chr(39)} || {c}' for c in t))} % {datasets.ONE_HOT})::int" for t in datasets.INTERACTIONS)


def one_hot_sql() -> str:
    """id, y, idx of ``datasets.star_one_hot``; rows with the same categories and label come in
    as one with their number ``rows``."""
    kept = ", ".join(datasets.CATEGORIES)
    return f"""select row_number() over () as id, y, rows, unnest(list_distinct([{_PLACES}])) as idx
  from (select {kept}, case when l_returnflag = 'R' then 1.0 else 0.0 end::double as y, count(*) as rows from {_ONE_HOT_JOIN} group by all)"""


def onehot_grad0(spark, sf_dir):
    """First gradient on one-hot categories with pairs and threes of them, p = 241,915."""
    d = datasets.star_one_hot(spark, sf_dir).withColumn("block", F.lit(0))
    return gradient.partial_sparse(d, Logistic(), np.zeros(datasets.ONE_HOT)).select(F.col("idx").cast("int").alias("idx"), "g")


QUERIES["onehot_grad0"] = onehot_grad0
ORACLES["onehot_grad0"] = f"select idx, sum((0.5 - y) * rows)::double as g from ({one_hot_sql()}) group by idx"


def onehot_gd2(spark, sf_dir):
    """Two steps on them through a ring code of ten workers, one late."""
    from evenkeel.operators import optim, schemes, train

    scheme, model, late = schemes.build("ring", 10, 1), optim.GD(datasets.ONE_HOT, 2.0), Stragglers("additive", s=1, delay_ms=100.0)
    if counted := datasets.star_counted(spark, sf_dir, 10):
        done = train.fit(counted[0], "", scheme, Logistic(), model, 2, late, kernel="counted", places=counted[1])
    else:
        done = train.fit(datasets.star_one_hot(spark, sf_dir), "key", scheme, Logistic(), model, 2, late, kernel="sparse")
    there = np.flatnonzero(done.beta)
    return spark.createDataFrame([(int(i), float(round(done.beta[i], 6)) + 0.0) for i in there], "idx int, beta double").where("abs(beta) >= 0.001")


QUERIES["onehot_gd2"] = onehot_gd2
ORACLES["onehot_gd2"] = f"""
with total as (select count(*) as n from {_ONE_HOT_JOIN}),
s as materialized ({one_hot_sql()}),
b1 as materialized (select idx, -2.0 * sum((0.5 - y) * rows) / any_value(n) as b from s, total group by idx),
m as materialized (select id, any_value(y) as y, any_value(rows) as rows, 1 / (1 + exp(-sum(b))) as p from s join b1 using (idx) group by id),
g as (select idx, sum((m.p - m.y) * m.rows) as g from s join m using (id) group by idx)
select idx, round(b - 2.0 * g / n, 6) + 0.0 as beta from b1 join g using (idx), total where abs(round(b - 2.0 * g / n, 6)) >= 0.001"""
