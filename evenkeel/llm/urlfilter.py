"""URLs filtered by the ratio of two character language models.

One variable-order Markov model is counted over all accepted URLs and one over all
rejected ones, on bytes, with Witten-Bell interpolation from order 5 down to a uniform
one; a context seen less than ``least_context`` times gives way to the shorter one.
A URL's score is the difference of its log-likelihoods divided by its length; a logistic
curve turns it into a probability, and URLs under a half go.  The curve is fitted on a
held-out fifth with models of the other URLs; then the fifth is counted too.

All grams count, however many they are.  While they fit, both models are broadcast; beyond
that they stay tables, and only the grams that are not among the most frequent are joined.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from evenkeel.llm import _bytes, _store

ORDER = 5


@dataclass(frozen=True)
class Settings:
    #: URLs whose host matches are the rejected examples, all others accepted ones.
    rejected_hosts: str = r"(?i)://[^/]*(adult|porn|xxx|(?<![a-z])bets?(?![a-z])|casino|poker|viagra|escort)"
    least_context: int = 2
    #: Most grams of both classes to broadcast; it changes the plan and no result.
    broadcast_grams: int = 2_000_000


def grams(urls: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """For every byte of every URL and for its end, the byte with the four before it in
    one number, and the URL that it belongs to.  1 stands before a URL, 2 for its end."""
    data, offsets = _bytes.buffers(urls)
    n = len(urls)
    length = np.diff(offsets)
    padded = np.full(len(data) + ORDER * n, 1, dtype=np.uint64)
    owner = np.repeat(np.arange(n), length)
    at = np.arange(len(data)) + (owner + 1) * (ORDER - 1) + owner
    padded[at] = data
    ends = np.cumsum(length + ORDER) - 1
    padded[ends] = 2
    where = np.sort(np.concatenate([at, ends]))
    packed = np.zeros(len(where), dtype=np.uint64)
    for k in range(ORDER):
        packed |= padded[where - k] << np.uint64(8 * k)
    return packed, np.repeat(np.arange(n), length + 1)


def _shorter(packed: np.ndarray, order: int) -> np.ndarray:
    return packed & np.uint64((1 << 8 * order) - 1)


class Model:
    """Counts of one class: for each order, sorted grams and sorted contexts."""

    def __init__(self, packed: np.ndarray, counts: np.ndarray, least_context: int):
        self.orders = []
        for k in range(1, ORDER + 1):
            g, inverse = np.unique(_shorter(packed, k), return_inverse=True)
            n = np.bincount(inverse, weights=counts, minlength=len(g))
            c, inverse = np.unique(g >> np.uint64(8), return_inverse=True)
            total, kinds = np.bincount(inverse, weights=n, minlength=len(c)), np.bincount(inverse, minlength=len(c))
            kept = total >= least_context
            self.orders.append((g, n, c[kept], total[kept], kinds[kept].astype(float)))

    def log_probability(self, packed: np.ndarray) -> np.ndarray:
        p = np.full(len(packed), 1 / 256)
        for k, (g, n, c, total, kinds) in enumerate(self.orders, 1):
            if not len(c):
                break
            gram = _shorter(packed, k)
            context = gram >> np.uint64(8)
            at = np.minimum(np.searchsorted(c, context), len(c) - 1)
            known = c[at] == context
            of = np.minimum(np.searchsorted(g, gram), len(g) - 1)
            times = np.where(g[of] == gram, n[of], 0.0)
            p = np.where(known, (times + kinds[at] * p) / (total[at] + kinds[at]), p)
        return np.log(p)


@dataclass
class Ratio:
    accepted: Model
    rejected: Model
    slope: float = 1.0
    offset: float = 0.0

    def scores(self, urls: pa.Array) -> np.ndarray:
        packed, owner = grams(urls)
        difference = self.accepted.log_probability(packed) - self.rejected.log_probability(packed)
        return np.bincount(owner, weights=difference, minlength=len(urls)) / np.bincount(owner, minlength=len(urls))


def _labelled(pages: DataFrame, s: Settings) -> DataFrame:
    held = F.pmod(F.xxhash64("url"), F.lit(5)) == 0
    return pages.where("url is not null and url <> ''").select("url", F.col("url").rlike(s.rejected_hosts).alias("rejected"), held.alias("held"))


def _count(labelled: DataFrame) -> DataFrame:
    """rejected, gram, fitted (times in URLs that are not held out), n (times in all)."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rejected, held = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("rejected", "held"))
            for flag in (False, True):
                packed, owner = grams(batch.column("url").filter(pa.array(rejected == flag)))
                g, inverse, n = np.unique(packed, return_inverse=True, return_counts=True)
                fitted = np.bincount(inverse, weights=~held[rejected == flag][owner], minlength=len(g)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(g), flag)), pa.array(g.astype(np.int64)), pa.array(fitted), pa.array(n, pa.int64())], ["rejected", "gram", "fitted", "n"])

    counted = labelled.mapInArrow(partial, "rejected boolean, gram bigint, fitted bigint, n bigint")
    return counted.groupBy("rejected", "gram").agg(F.sum("fitted").alias("fitted"), F.sum("n").alias("n"))


def _sizes(counts: DataFrame) -> dict[bool, tuple[int, int]]:
    """Of each class, how many grams there are and how many in URLs that are not held out."""
    rows = counts.groupBy("rejected").agg(F.count("*").alias("n"), F.count_if(F.col("fitted") > 0).alias("fitted")).collect()
    return {r["rejected"]: (r["n"], r["fitted"]) for r in rows}


def _fit(labelled: DataFrame, counts: DataFrame, calibrate: bool, s: Settings) -> Ratio:
    early, late = {}, {}
    for flag in (False, True):
        frame = counts.where(F.col("rejected") == flag).select("gram", "fitted", "n").toPandas()
        g, fitted, n = frame["gram"].to_numpy().astype(np.uint64), frame["fitted"].to_numpy().astype(float), frame["n"].to_numpy().astype(float)
        early[flag], late[flag] = Model(g[fitted > 0], fitted[fitted > 0], s.least_context), Model(g, n, s.least_context)
    curve = (4.0, 0.0)
    if calibrate:
        curve = _curve(_scored(labelled.where("held"), Ratio(early[False], early[True]), "score"))
    return Ratio(late[False], late[True], *curve)


def fit(pages: DataFrame, s: Settings = Settings()) -> Ratio | None:
    """Both models in memory.  None if either class has no URL to learn from."""
    labelled = _labelled(pages, s)
    counts = _store.materialise(_count(labelled))
    sizes = _sizes(counts)
    return _fit(labelled, counts, all(f for _, f in sizes.values()), s) if len(sizes) == 2 else None


def _curve(scored: DataFrame) -> tuple[float, float]:
    histogram = scored.groupBy("rejected", F.round("score", 3).alias("score")).count().toPandas()
    return _platt(histogram["score"].to_numpy(), (~histogram["rejected"].to_numpy(dtype=bool)).astype(float), histogram["count"].to_numpy(dtype=float))


def _differences(counts: DataFrame, s: Settings) -> DataFrame:
    """gram, n, early, late: the difference of the models' logarithms at every gram that any
    URL has, without and with the held-out URLs.  ``Model`` as tables, an order a step."""
    kinds = [("fitted", False), ("fitted", True), ("n", False), ("n", True)]
    names = [f"n{i}" for i in range(len(kinds))]
    wide = _store.materialise(counts.groupBy("gram").agg(*[F.sum(F.when(F.col("rejected") == flag, F.col(c)).otherwise(0)).alias(x) for x, (c, flag) in zip(names, kinds, strict=True)]))
    below = None
    for k in range(1, ORDER + 1):
        own = wide.groupBy(F.col("gram").bitwiseAND(F.lit((1 << 8 * k) - 1)).alias("gram")).agg(*[F.sum(x).alias(x) for x in names])
        context = W.partitionBy(F.shiftright("gram", 8))
        own = own.select("gram", *names, *[F.sum(x).over(context).alias(f"total_{x}") for x in names], *[F.count_if(F.col(x) > 0).over(context).alias(f"kinds_{x}") for x in names])
        if below is None:
            own = own.select("*", *[F.lit(1 / 256).alias(f"p_{x}") for x in names])
        else:
            own = own.withColumn("short", F.col("gram").bitwiseAND(F.lit((1 << 8 * (k - 1)) - 1))).join(below, "short")
        p = [F.when(F.col(f"total_{x}") >= s.least_context, (F.col(x) + F.col(f"kinds_{x}") * F.col(f"p_{x}")) / (F.col(f"total_{x}") + F.col(f"kinds_{x}"))).otherwise(F.col(f"p_{x}")).alias(f"p_{x}") for x in names]
        below = own.select(F.col("gram").alias("short"), *p, *(names if k == ORDER else []))
    return below.select(F.col("short").alias("gram"), (F.col("n2") + F.col("n3")).alias("n"), (F.log("p_n0") - F.log("p_n1")).alias("early"), (F.log("p_n2") - F.log("p_n3")).alias("late"))


def _joined(labelled: DataFrame, counts: DataFrame, s: Settings) -> DataFrame:
    """url, rejected, held, score (without the held-out URLs), raw (with them), a row a URL.
    The most frequent grams are looked up, the others joined."""
    differences = _store.materialise(_differences(counts, s))
    least, some = None, 0
    for n, many in sorted(((r["n"], r["count"]) for r in differences.groupBy("n").count().toLocalIterator()), reverse=True):
        some += many
        if some > s.broadcast_grams:
            break
        least = n
    frequent = differences.where(F.col("n") >= least).orderBy("gram").toPandas() if least is not None else differences.limit(0).toPandas()
    known = labelled.sparkSession.sparkContext.broadcast((frequent["gram"].to_numpy().astype(np.uint64), frequent["early"].to_numpy(), frequent["late"].to_numpy()))

    @F.arrow_udf("n int, early double, late double, rest array<bigint>")
    def look_up(urls: pa.Array) -> pa.Array:
        g, early, late = known.value
        parts = []
        for piece in _bytes.pieces(urls):
            packed, owner = grams(piece)
            at = np.minimum(np.searchsorted(g, packed), max(len(g) - 1, 0))
            found = g[at] == packed if len(g) else np.zeros(len(packed), dtype=bool)
            sums = [np.bincount(owner[found], weights=w[at[found]], minlength=len(piece)) for w in (early, late)]
            ends = np.concatenate([[0], np.bincount(owner[~found], minlength=len(piece)).cumsum()]).astype(np.int32)
            rest = pa.ListArray.from_arrays(pa.array(ends), pa.array(packed[~found].astype(np.int64)))
            parts.append(pa.StructArray.from_arrays([pa.array(np.bincount(owner, minlength=len(piece)).astype(np.int32)), *map(pa.array, sums), rest], ["n", "early", "late", "rest"]))
        return pa.concat_arrays(parts) if parts else pa.array([], pa.struct([("n", pa.int32()), ("early", pa.float64()), ("late", pa.float64()), ("rest", pa.list_(pa.int64()))]))

    urls = labelled.distinct().withColumn("u", look_up("url")).select("url", "rejected", "held", "u.*", F.monotonically_increasing_id().alias("id"))
    urls = _store.materialise(urls)
    rest = urls.select("id", F.explode("rest").alias("gram")).join(differences.select("gram", F.col("early").alias("e"), F.col("late").alias("l")), "gram")
    rest = rest.groupBy("id").agg(F.sum("e").alias("e"), F.sum("l").alias("l"))
    whole = lambda own, more: (F.col(own) + F.coalesce(more, F.lit(0.0))) / F.col("n")
    return _store.materialise(urls.drop("rest").join(rest, "id", "left").select("url", "rejected", "held", whole("early", "e").alias("score"), whole("late", "l").alias("raw")))


def _platt(score: np.ndarray, accepted: np.ndarray, weight: np.ndarray) -> tuple[float, float]:
    """Slope and offset of the logistic curve; classes weigh the same, with a small ridge."""
    total = [weight[accepted == k].sum() for k in (0, 1)]
    if not min(total):
        return 4.0, 0.0
    w = weight / np.where(accepted > 0, total[1], total[0])
    x, b = np.stack([score, np.ones_like(score)], 1), np.array([4.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        gradient = x.T @ (w * (p - accepted)) + 1e-3 * np.array([b[0], 0])
        hessian = (x * (w * p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
        b = b - np.linalg.solve(hessian, gradient)
    return float(b[0]), float(b[1])


def _scored(frame: DataFrame, ratio: Ratio, name: str) -> DataFrame:
    held = frame.sparkSession.sparkContext.broadcast(ratio)

    @F.arrow_udf("double")
    def score(urls: pa.Array) -> pa.Array:
        parts = [held.value.scores(p) for p in _bytes.pieces(urls)]
        return pa.array(np.concatenate(parts) if parts else np.empty(0))

    return frame.withColumn(name, score("url"))


def judge(pages: DataFrame, s: Settings = Settings()) -> DataFrame:
    """page_id, score, p_accept, accepted of every row.

    Null and empty URLs: score null, p_accept null, rejected.  Without examples of both
    classes every other URL has score 0 and is accepted.  Repeated rows are judged each;
    other columns are ignored.
    """
    labelled = _labelled(pages, s)
    counts = _store.materialise(_count(labelled))
    sizes = _sizes(counts)
    calibrate = all(fitted for _, fitted in sizes.values())
    frame = pages.select("page_id", "url")
    there = F.coalesce(F.col("url") != "", F.lit(False))
    if len(sizes) < 2:
        scored = frame.withColumn("score", F.when(there, 0.0)).withColumn("p_accept", F.when(there, 1.0))
    else:
        if sum(n for n, _ in sizes.values()) <= s.broadcast_grams:
            ratio = _fit(labelled, counts, calibrate, s)
            raw, slope, offset = _scored(frame, ratio, "raw"), ratio.slope, ratio.offset
        else:
            by_url = _joined(labelled, counts, s)
            held = labelled.where("held").select("url").join(by_url, "url")
            slope, offset = _curve(held) if calibrate else (4.0, 0.0)
            raw = frame.join(by_url.select("url", "raw"), "url", "left")
        scored = raw.withColumn("score", F.when(there, F.round("raw", 6)))
        scored = scored.withColumn("p_accept", F.when(there, F.round(1 / (1 + F.exp(-(F.col("raw") * slope + offset))), 6)))
    return scored.select("page_id", "score", "p_accept", F.coalesce(F.col("p_accept") >= 0.5, F.lit(False)).alias("accepted"))


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(_store.table(spark, sf_dir, "pages"))
