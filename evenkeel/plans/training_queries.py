"""Models after a few rounds; oracles are unrolled by Python, one SQL step a round."""

from __future__ import annotations

from pyspark.sql import functions as F

from evenkeel import hashing
from evenkeel.functions import metrics
from evenkeel.functions.losses import Logistic
from evenkeel.operators import gradient, optim, schemes, train
from evenkeel.operators.stragglers import Stragglers
from evenkeel.plans.gradient_queries import KEY
from evenkeel.sources import datasets

QUERIES, ORACLES = {}, {}
X, P = datasets.SCALED, 5
ROUNDS = 5
LATE = Stragglers("additive", s=2, delay_ms=1000.0)


def planted_sql() -> str:
    m = " + ".join(f"x{j} * ({b}::double)" for j, b in enumerate(datasets.PLANTED, 1))
    return f"""with raw as (select {KEY} as key, l_quantity::double / 50 as x1, l_discount::double * 10 as x2, l_tax::double * 10 as x3,
    l_extendedprice::double / 100000 as x4, case when l_returnflag = 'R' then 1.0 else 0.0 end::double as x5 from lineitem)
  select *, case when ({hashing.sql_number("'label-' || key")} + 0.5)::double / 4294967296::double < 1 / (1 + exp(2 * ({m}))) then 1.0 else 0.0 end::double as y,
    {hashing.sql_number("'holdout-' || key")} % 5 = 0 as holdout, ({hashing.sql_number("key")} % 12)::int as block from raw"""


def _model(scheme, make, stragglers=LATE, rounds=ROUNDS):
    def run(spark, sf_dir):
        samples = datasets.lineitem_planted(spark, sf_dir).where("not holdout")
        done = train.fit(samples, "key", scheme(), Logistic(), make(), rounds, stragglers, columns=X)
        return spark.createDataFrame([(j, float(round(b, 6)) + 0.0) for j, b in enumerate(done.beta, 1)], "idx int, beta double")

    return run


def _vector(prefix: str) -> str:
    return ", ".join(f"{prefix}{j}" for j in range(1, P + 1))


def _unrolled(kind: str, drop: bool = False) -> str:
    """``kind`` gd, decay, nag, prox, aprox or fw."""
    parts = [f"s as materialized (select * from ({planted_sql()}) where not holdout)", "d as (select count(*)::double as d from s)"]
    parts.append("b0 as (select " + ", ".join(f"0.0::double as b{j}, 0.0::double as a{j}" for j in range(1, P + 1)) + ")")
    for t in range(ROUNDS):
        point = "a" if kind in ("nag", "aprox") else "b"
        m = " + ".join(f"x{j} * {point}{j}" for j in range(1, P + 1))
        alive = f"where block not in (select w from (select w, row_number() over (order by {hashing.sql_number(f'chr(100) || {chr(39)}elay-{t}-{chr(39)} || w')}, w) as n from generate_series(0, 11) q(w)) where n <= 2)" if drop else ""
        sums = ", ".join(f"sum((1 / (1 + exp(-({m}))) - y) * x{j}) / {'count(*)' if drop else 'any_value(d)'} as g{j}" for j in range(1, P + 1))
        parts.append(f"g{t + 1} as materialized (select {sums} from s, d, b{t} {alive})")
        if kind in ("gd", "decay", "prox"):
            rate = "2.0" if kind != "decay" else f"(20.0::double / ({t} + 10))"
            move = [f"b{j} - {rate} * g{j}" for j in range(1, P + 1)]
            if kind == "prox":
                move = [f"sign({x}) * greatest(abs({x}) - {2.0 * 0.02}, 0)" for x in move]
            new = ", ".join(f"({x})::double as b{j}, 0.0::double as a{j}" for j, x in enumerate(move, 1))
        elif kind == "aprox":
            c = f"({t}::double / ({t} + 3))"
            prox = [f"(sign(a{j} - 2.0 * g{j}) * greatest(abs(a{j} - 2.0 * g{j}) - {2.0 * 0.02}, 0))" for j in range(1, P + 1)]
            new = ", ".join(f"({x})::double as b{j}, ({x} + {c} * ({x} - b{j}))::double as a{j}" for j, x in enumerate(prox, 1))
        elif kind == "nag":
            c = f"({t}::double / ({t} + 3))"
            new = ", ".join(f"a{j} - 2.0 * g{j} as b{j}, (a{j} - 2.0 * g{j}) + {c} * ((a{j} - 2.0 * g{j}) - b{j}) as a{j}" for j in range(1, P + 1))
        else:
            most = "greatest(" + ", ".join(f"abs(g{j})" for j in range(1, P + 1)) + ")"
            first = [" and ".join([f"abs(g{j}) = {most}", *[f"abs(g{i}) < {most}" for i in range(1, j)]]) for j in range(1, P + 1)]
            new = ", ".join(f"b{j} + (2.0::double / ({t} + 2)) * ((case when {first[j - 1]} then -1.5 * sign(g{j}) else 0 end) - b{j}) as b{j}, 0.0::double as a{j}" for j in range(1, P + 1))
        parts.append(f"b{t + 1} as materialized (select {new} from b{t}, g{t + 1})")
    out = " union all ".join(f"select {j}::int as idx, round(b{j}, 6) + 0.0 as beta from b{ROUNDS}" for j in range(1, P + 1))
    return "with " + ",\n".join(parts) + "\n" + out


_plain = lambda: schemes.build("block", 12, 2)
_RUNS = {
    "gd5": (_plain, lambda: optim.GD(P, 2.0), "gd"),
    "decay5": (_plain, lambda: optim.DecayGD(P, 20.0, 10.0), "decay"),
    "nag5": (lambda: schemes.build("uncoded", 12, 0), lambda: optim.NAG(P, 2.0), "nag"),
    "prox5": (_plain, lambda: optim.Prox(P, 2.0, 0.02), "prox"),
    "fw5": (_plain, lambda: optim.FrankWolfe(P, 1.5), "fw"),
    "gd5_ring": (lambda: schemes.build("ring", 12, 2), lambda: optim.GD(P, 2.0), "gd"),
    "nag5_block": (_plain, lambda: optim.NAG(P, 2.0), "nag"),
    "nag5_ring": (lambda: schemes.build("ring", 12, 2), lambda: optim.NAG(P, 2.0), "nag"),
    "nag5_two_stage": (lambda: schemes.build("two_stage_ring", 12, 2, 2.0), lambda: optim.NAG(P, 2.0), "nag"),
    "nag5_full_copy": (lambda: schemes.build("full_copy", 12, 11), lambda: optim.NAG(P, 2.0), "nag"),
    "nag5_feedback": (lambda: schemes.build("feedback_replica", 12, 2), lambda: optim.NAG(P, 2.0), "nag"),
}
for name, (scheme, make, kind) in _RUNS.items():
    QUERIES[name] = _model(scheme, make)
    ORACLES[name] = _unrolled(kind)
QUERIES["drop_s5"] = _model(lambda: schemes.build("drop_s", 12, 2), lambda: optim.DecayGD(P, 20.0, 10.0))
ORACLES["drop_s5"] = _unrolled("decay", drop=True).replace("chr(100) || 'elay-", "'delay-")
QUERIES["lbfgs10_block"] = _model(_plain, lambda: optim.LBFGS(P, first=2.0), rounds=10)
QUERIES["accelerated_prox5"] = _model(_plain, lambda: optim.AcceleratedProx(P, 2.0, 0.02))
ORACLES["accelerated_prox5"] = _unrolled("aprox")


def loss_trace(spark, sf_dir):
    """Loss and accuracy on the holdout after each round of gd5, all models in one scan."""
    d = datasets.lineitem_planted(spark, sf_dir)
    done = train.fit(d.where("not holdout"), "key", _plain(), Logistic(), optim.GD(P, 2.0), ROUNDS, LATE, columns=X, keep_betas=True)
    held, loss = d.where("holdout"), Logistic()
    sums = []
    for t, b in enumerate(done.betas, 1):
        m = gradient.margin_wide(b, X)
        sums.append(F.struct(F.lit(t).alias("round"), F.round(F.avg(loss.value(m, F.col("y"))), 6).alias("loss"), F.round(F.avg(((m > 0) == (F.col("y") > 0.5)).cast("double")), 6).alias("accuracy")))
    return held.agg(F.array(*sums).alias("r")).select(F.explode("r").alias("r")).select("r.*")


def _loss_sql() -> str:
    head = _unrolled("gd").rsplit("\n", 1)[0]
    parts = []
    for t in range(1, ROUNDS + 1):
        m = " + ".join(f"x{j} * b{j}" for j in range(1, P + 1))
        parts.append(f"select {t}::int as round, round(avg(greatest({m}, 0) + ln(1 + exp(-abs({m}))) - y * ({m})), 6) as loss, round(avg(case when ({m} > 0) = (y > 0.5) then 1.0 else 0.0 end), 6) as accuracy from h, b{t}")
    return head + f", h as (select * from ({planted_sql()}) where holdout)\n" + " union all ".join(parts)


QUERIES["loss_trace"] = loss_trace
ORACLES["loss_trace"] = _loss_sql()


def loss_delta(spark, sf_dir):
    from pyspark.sql import Window as W

    t = loss_trace(spark, sf_dir)
    return t.select("round", F.round(F.col("loss") - F.lag("loss").over(W.orderBy("round")), 6).alias("delta"))


QUERIES["loss_delta"] = loss_delta
ORACLES["loss_delta"] = f"select round, round(loss - lag(loss) over (order by round), 6) as delta from ({_loss_sql()})"

_FIXED = "x1 * (-1.5::double) + x2 * (1.0::double) + x5 * (-0.3::double)"


def auc_exact(spark, sf_dir):
    """Area under the curve of a fixed model on the holdout, by line of returned or not."""
    d = datasets.lineitem_planted(spark, sf_dir).where("holdout")
    score = F.round(F.col("x1") * -1.5 + F.col("x2") * 1.0 + F.col("x5") * -0.3, 9)
    a = metrics.auc(d.withColumn("score", score), by=("x5",))
    return a.select("x5", F.round("auc", 9).alias("auc"), "positives", "negatives")


QUERIES["auc_exact"] = auc_exact
ORACLES["auc_exact"] = f"""
with h as (select x5, y, round({_FIXED}, 9) as score from ({planted_sql()}) where holdout),
r as (select x5, y, rank() over (partition by x5 order by score) as low, count(*) over (partition by x5, score) as ties from h)
select x5, round((sum(case when y = 1 then low + (ties - 1) / 2.0 else 0 end)::double - sum(y) * (sum(y) + 1) / 2) / (sum(y) * sum(1 - y)), 9) as auc,
  sum(y) as positives, sum(1 - y) as negatives from r group by x5"""


def auc_by_round(spark, sf_dir):
    """Area under the curve on the holdout after each round of gd5, all models in one scan."""
    d = datasets.lineitem_planted(spark, sf_dir)
    done = train.fit(d.where("not holdout"), "key", _plain(), Logistic(), optim.GD(P, 2.0), ROUNDS, LATE, columns=X, keep_betas=True)
    scores = F.array(*[F.round(gradient.margin_wide(b, X), 9) for b in done.betas])
    each = d.where("holdout").select("y", F.posexplode(scores).alias("t", "score"))
    return metrics.auc(each, by=("t",)).select((F.col("t") + 1).alias("round"), F.round("auc", 6).alias("auc"))


QUERIES["auc_by_round"] = auc_by_round
ORACLES["auc_by_round"] = _unrolled("gd").rsplit("\n", 1)[0] + f""", h as (select * from ({planted_sql()}) where holdout),
scored as ({" union all ".join(f"select {t}::int as round, y, round({' + '.join(f'x{j} * b{j}' for j in range(1, P + 1))}, 9) as score from h, b{t}" for t in range(1, ROUNDS + 1))}),
ranked as (select round, y, rank() over (partition by round order by score) as low, count(*) over (partition by round, score) as ties from scored)
select round, round((sum(case when y = 1 then low + (ties - 1) / 2.0 else 0 end)::double - sum(y) * (sum(y) + 1) / 2) / (sum(y) * sum(1 - y)), 6) as auc from ranked group by round"""


def nag_drop_s(spark, sf_dir):
    """Why inexact gradients are not accelerated: loss on the holdout after each of 12 rounds of
    accelerated descent with all blocks and with two of twelve dropped."""
    d, rows = datasets.lineitem_planted(spark, sf_dir), []
    for name, s in (("ring", 2), ("drop_s", 2)):
        done = train.fit(d.where("not holdout"), "key", schemes.build(name, 12, s), Logistic(), optim.NAG(P, 4.0), 12, LATE, columns=X, allow_unstable=True, keep_betas=True)
        losses = d.where("holdout").agg(*[F.avg(Logistic().value(gradient.margin_wide(b, X), F.col("y"))) for b in done.betas]).first()
        rows += [(name, r["round"], r["gradient_error"], float(v)) for r, v in zip(done.trace, losses, strict=True)]
    return spark.createDataFrame(rows, "scheme string, round int, gradient_error double, loss double")


QUERIES["nag_drop_s"] = nag_drop_s
DOC_P, DOC_RATE = 512, 1.0


def train_docs_quality(spark, sf_dir):
    """Quality of documents from hashed words: the model after two steps through a ring code."""
    d = datasets.document_tokens(spark, sf_dir, "quality", DOC_P).select("row_id", "key", "y", "xs")
    done = train.fit(d, "key", schemes.build("ring", 6, 1), Logistic(), optim.GD(DOC_P, DOC_RATE), 2, Stragglers("additive", s=1, delay_ms=100.0), kernel="sparse")
    return spark.createDataFrame([(i, float(round(b, 6)) + 0.0) for i, b in enumerate(done.beta) if b], "idx int, beta double")


QUERIES["train_docs_quality"] = train_docs_quality


def two_steps_sql(samples: str, rate: float) -> str:
    """The model after two steps, of ``samples`` (id, y, idx) without repeats, with all rows'
    number in the table ``total``."""
    return f"""
s as materialized ({samples}),
b1 as materialized (select idx, -{rate} * sum(0.5 - y) / any_value(n) as b from s, total group by idx),
m as materialized (select id, any_value(y) as y, 1 / (1 + exp(-sum(b))) as p from s join b1 using (idx) group by id),
g as (select idx, sum(m.p - m.y) as g from s join m using (id) group by idx)
select idx, round(b - {rate} * g / n, 6) + 0.0 as beta from b1 join g using (idx), total"""


ORACLES["train_docs_quality"] = f"""
with total as (select count(*) as n from documents join labels using (doc_id)),
w as (select doc_id, quality::double as y, unnest(string_split_regex(lower(text), '[^a-z]+')) as w from documents join labels using (doc_id)),
{two_steps_sql(f"select distinct doc_id as id, y, ({hashing.sql_number('w')} % {DOC_P})::int as idx from w where w <> ''", DOC_RATE)}"""


def rate_grid(spark, sf_dir):
    """Mean training loss after three rounds for a grid of rates, tuned in shared scans."""
    d = datasets.lineitem_planted(spark, sf_dir).where("not holdout").withColumn("block", F.lit(0))
    tuned = train.tune_rate(d, Logistic(), (0.5, 1.0, 2.0, 4.0), 3, X, lambda p, r: optim.GD(p, r))
    return spark.createDataFrame([(r, float(round(v, 6))) for r, v in tuned.items()], "rate double, loss double")


QUERIES["rate_grid"] = rate_grid
