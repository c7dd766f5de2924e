"""Near-duplicate groups by SimHash with pigeonring filtering.

A fingerprint has 128 bits (two longs): every distinct word votes for its hash's bits
with a weight that grows with its length, so that rare long words count more than
particles.  Two texts are near copies if their fingerprints differ in at most ``tau``
bits.  The fingerprint is a ring of 16 boxes of 8 bits.  If the boxes of a pair differ
in ``tau`` < 16 bits in all, some start exists from which EVERY chain of ``l`` boxes
differs in at most ``floor(l * tau / 16)`` bits: the first box agrees, two boxes differ
in at most 1 bit, and so on.  The chain's first ``depth`` boxes are the join key, tried
with every error pattern that the budgets allow; the longer chains are checked on the
joined rows, and what is left gets the full Hamming check.  Nothing is lost by this.

All Spark work is on (doc_id, text hash, fingerprint); texts move once, at the end.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from evenkeel.llm import _bytes, _store

BOXES, WIDTH = 16, 8


@dataclass(frozen=True)
class Settings:
    #: Most differing bits of 128; under 16, so that a chain can begin with an equal box.
    tau: int = 15
    #: Lengths of the chains that are checked on joined rows, besides 8 and all 16.
    chains: tuple[int, ...] = (4,)
    #: Boxes in the join key; None: by cost from the number of fingerprints.
    depth: int | None = None


_WEIGHT = np.sqrt(np.maximum(np.arange(64) - 3, 0.05)).astype(np.float32)
_SIGNS = (np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.float32) * 2 - 1)


def fingerprints(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(n, 2) signed longs, and whether the text has a fingerprint: null and empty texts
    have none.  A text without words is taken as one word."""
    out, there = np.zeros((len(texts), 2), dtype=np.int64), np.zeros(len(texts), dtype=bool)
    at = 0
    for piece in _bytes.pieces(texts):
        w = _bytes.word_hashes(*_bytes.buffers(piece))
        key = (w.hash & np.uint64(2**64 - 64)) | np.minimum(w.end - w.start, 63).astype(np.uint64)
        for i in range(len(piece)):
            k = np.sort(key[w.first[i] : w.first[i + 1]])
            if not len(k):
                raw = w.data[w.offsets[i] : w.offsets[i + 1]]
                if not len(raw):
                    continue
                k = _bytes.scramble(np.array([hash_bytes(raw)], dtype=np.uint64))
            elif len(k) > 1:
                k = k[np.concatenate(([True], k[1:] != k[:-1]))]
            bits = np.stack([_bytes.scramble(k, 1), _bytes.scramble(k, 2)], 1).view(np.uint8)  # (words, 16)
            weight, votes = _WEIGHT[(k & np.uint64(63)).astype(np.int64)], np.zeros(128, dtype=np.float32)
            for b in range(0, len(k), 4096):
                votes += weight[b : b + 4096] @ _SIGNS[bits[b : b + 4096]].reshape(-1, 128)
            out[at + i] = np.packbits(votes > 0, bitorder="little").view(np.int64)
            there[at + i] = True
        at += len(piece)
    return out, there


def hash_bytes(raw: np.ndarray) -> int:
    h = np.uint64(len(raw))
    with np.errstate(over="ignore"):
        for b in range(0, len(raw), _bytes.BLOCK):
            part = raw[b : b + _bytes.BLOCK]
            h = _bytes.scramble(np.array([h]), 3)[0] + (_bytes._CODE[part] * _bytes._power_tables(len(part))[0][: len(part)]).sum(dtype=np.uint64)
    return int(h)


@F.arrow_udf(T.StructType([T.StructField("hi", T.LongType()), T.StructField("lo", T.LongType())]))
def _fingerprint(texts: pa.Array) -> pa.Array:
    fp, there = fingerprints(texts)
    _bytes.give_back()
    return pa.StructArray.from_arrays([pa.array(fp[:, 0]), pa.array(fp[:, 1])], ["hi", "lo"], mask=pa.array(~there))


def budget(length: int, tau: int) -> int:
    return length * tau // BOXES


def error_patterns(depth: int, tau: int) -> list[int]:
    """Masks over ``depth`` boxes, the first in the low bits, whose every prefix stays in
    its budget."""
    fields = [m for m in range(1 << WIDTH) if m.bit_count() <= budget(depth, tau)]
    found: list[tuple[int, ...]] = [()]
    for at in range(depth):
        found = [p + (m,) for p, m in product(found, fields) if sum(x.bit_count() for x in p) + m.bit_count() <= budget(at + 1, tau)]
    return [reduce(lambda a, m: a << WIDTH | m, reversed(p), 0) for p in found]


def key_depth(n: int, tau: int) -> int:
    """The depth with the least work: probe rows to shuffle plus chance matches, of which
    one costs a tenth of a row.  Any depth finds the same pairs."""

    def cost(depth: int) -> float:
        patterns = BOXES * len(error_patterns(depth, tau))
        return patterns * (n / 2 + 0.1 * n * n / 2 ** (WIDTH * depth + 1))

    return min((1, 2, 3), key=cost)


def _turned(points: DataFrame, depth: int) -> DataFrame:
    """16 rows a fingerprint: the ring turned so that each box in turn is the low byte of
    ``x`` (the first 8 boxes; ``y`` has the other 8), with start and the first ``depth``
    boxes in ``key``."""
    p = points.withColumn("start", F.explode(F.sequence(F.lit(0), F.lit(BOXES - 1))))
    front = F.when(F.col("start") < 8, F.col("hi")).otherwise(F.col("lo"))
    back = F.when(F.col("start") < 8, F.col("lo")).otherwise(F.col("hi"))
    p = p.select("start", front.alias("f"), back.alias("b"), F.expr(f"(start % 8) * {WIDTH}").alias("r"))
    x = F.expr("shiftrightunsigned(f, r) | shiftleft(shiftleft(b, 1), 63 - r)")
    y = F.expr("shiftrightunsigned(b, r) | shiftleft(shiftleft(f, 1), 63 - r)")
    p = p.select("start", x.alias("x"), y.alias("y"))
    key = F.expr(f"shiftleft(cast(start as bigint), {WIDTH * depth}) | (x & {(1 << WIDTH * depth) - 1}L)")
    return p.select(key.alias("key"), "x", "y")


def near_pairs(points: DataFrame, n: int, settings: Settings = Settings()) -> DataFrame:
    """All pairs of distinct fingerprints (hi, lo) at most ``tau`` bits apart, each once:
    a_hi, a_lo, b_hi, b_lo with a < b.  ``n``: how many there are, about."""
    tau = settings.tau
    if not 0 <= tau < BOXES:
        raise ValueError("tau must be under the number of boxes")
    depth = settings.depth or key_depth(n, tau)
    low = (1 << WIDTH * depth) - 1
    left = _turned(points, depth).select("key", F.col("x").alias("ax"), F.col("y").alias("ay"))
    masks = F.array(*[F.lit(m).cast("bigint") for m in error_patterns(depth, tau)])
    right = _turned(points, depth).withColumn("mask", F.explode(masks))
    # Two keys that differ meet once: the one with a 0 in the lowest differing bit probes.
    right = right.where("mask = 0 or (x & (mask & -mask)) = 0")
    right = right.select(F.expr("key ^ mask").alias("key"), F.col("x").alias("bx"), F.col("y").alias("by"))
    once = F.expr(f"((ax ^ bx) & {low}L) <> 0 or ax < bx or (ax = bx and ay < by)")
    chains = [F.expr(f"bit_count((ax ^ bx) & {(1 << WIDTH * k) - 1}L) <= {budget(k, tau)}") for k in settings.chains if k > depth]
    chains.append(F.expr(f"bit_count(ax ^ bx) <= {budget(8, tau)}"))
    full = F.expr(f"bit_count(ax ^ bx) + bit_count(ay ^ by) <= {tau}")
    # By Spark's estimate an explode adds no rows, so it would broadcast a table 16 or more times over.
    found = left.join(right.hint("merge"), "key").where(reduce(lambda p, q: p & q, [*chains, full, once]))
    start = F.expr(f"cast(shiftright(key, {WIDTH * depth}) as int)")
    back = found.withColumn("start", start).withColumn("r", F.expr(f"(start % 8) * {WIDTH}"))
    for side in "ab":
        f = F.expr(f"shiftleft({side}x, r) | shiftrightunsigned(shiftrightunsigned({side}y, 1), 63 - r)")
        b = F.expr(f"shiftleft({side}y, r) | shiftrightunsigned(shiftrightunsigned({side}x, 1), 63 - r)")
        back = back.withColumn(f"{side}f", f).withColumn(f"{side}b", b)
        back = back.withColumn(side, F.when(F.col("start") < 8, F.struct(F.col(f"{side}f").alias("hi"), F.col(f"{side}b").alias("lo"))).otherwise(F.struct(F.col(f"{side}b").alias("hi"), F.col(f"{side}f").alias("lo"))))
    pair = back.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    return pair.select(F.col("a.hi").alias("a_hi"), F.col("a.lo").alias("a_lo"), F.col("b.hi").alias("b_hi"), F.col("b.lo").alias("b_lo")).distinct()


def stars(edges: DataFrame) -> DataFrame:
    """(v, u) of every node v of a graph but the least of its component, which is u.
    ``edges``: v, u with u < v, of any type that has an order.  Alternates joining all larger
    neighbours and all smaller ones to the least one until stars are left."""
    found = _store.materialise(edges.select("v", "u"))
    if not found.take(1):
        return found
    while True:
        both = found.unionByName(found.select(F.col("u").alias("v"), F.col("v").alias("u")))
        near = both.groupBy("v").agg(F.min("u").alias("least"))
        near = near.select("v", F.least("v", "least").alias("root"))
        large = both.join(near.hint("merge"), "v").where("u > v").select(F.col("u").alias("v"), F.col("root").alias("u")).distinct()
        low = large.groupBy("v").agg(F.min("u").alias("root"))
        small = large.join(low.hint("merge"), "v").select(F.col("u").alias("v"), F.col("root").alias("u")).where("v <> u").unionByName(low.select("v", F.col("root").alias("u"))).distinct()
        new = _store.materialise(small)
        inner = new.select(F.col("u").alias("v")).join(new.select("v").hint("merge"), "v", "left_semi").take(1)
        several = new.groupBy("v").count().where("count > 1").take(1)
        found = new
        if not inner and not several:
            return found


def components(edges: DataFrame) -> DataFrame:
    """(hi, lo, root_hi, root_lo) of every node of a graph of fingerprint pairs but the roots;
    the root is a group's least node."""
    a, b = F.struct(F.col("a_hi").alias("hi"), F.col("a_lo").alias("lo")), F.struct(F.col("b_hi").alias("hi"), F.col("b_lo").alias("lo"))
    return stars(edges.select(b.alias("v"), a.alias("u"))).select("v.hi", "v.lo", F.col("u.hi").alias("root_hi"), F.col("u.lo").alias("root_lo"))


def groups(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """One row for each (doc_id, text hash): doc_id, text_hash, group_id, keep.

    group_id is the least doc_id of the near copies, keep marks that document.  Rows
    without doc_id are left out; null and empty texts are groups of their own.  Other
    columns are ignored.
    """
    return _grouped(docs, settings)[0]


def _grouped(docs: DataFrame, settings: Settings) -> tuple[DataFrame, DataFrame]:
    """``groups``, and (doc_id, text_hash) of the rows that are there more than once."""
    wanted = docs.select("doc_id", F.xxhash64("text").alias("text_hash"), "text").where("doc_id is not null")
    points = _store.materialise(wanted.select("doc_id", "text_hash", _fingerprint("text").alias("f")).select("doc_id", "text_hash", "f.hi", "f.lo"))
    found = points.where("hi is not null").groupBy("hi", "lo").agg(F.min(F.struct("doc_id", "text_hash")).alias("first"))
    distinct = _store.materialise(found)
    pairs = near_pairs(distinct.select("hi", "lo"), distinct.count(), settings)
    roots = components(pairs)
    # What follows grows with the documents.  Its files and exchanges are a third of its hashed
    # rows and less, so Spark would broadcast more than its threshold: merge joins.
    named = distinct.join(roots.hint("merge"), ["hi", "lo"], "left")
    root = [F.coalesce("root_hi", "hi").alias("root_hi"), F.coalesce("root_lo", "lo").alias("root_lo")]
    # roots have no row of their own in the stars: the left join leaves them to be their own root
    named = _store.materialise(named.select("hi", "lo", "first", *root))
    first = named.groupBy("root_hi", "root_lo").agg(F.min("first").alias("first_of_group"))
    of_fingerprint = named.join(first.hint("merge"), ["root_hi", "root_lo"]).select("hi", "lo", "first_of_group")
    rows = points.dropDuplicates(["doc_id", "text_hash"]).join(of_fingerprint.hint("merge"), ["hi", "lo"], "left")
    own = F.struct("doc_id", "text_hash")
    repeated = points.groupBy("doc_id", "text_hash").count().where("count > 1").drop("count")
    return rows.select("doc_id", "text_hash", F.coalesce("first_of_group.doc_id", "doc_id").alias("group_id"), F.coalesce(F.col("first_of_group") == own, F.lit(True)).alias("keep")), repeated


#: Documents to drop, and documents in several rows, up to which they are broadcast (some 100
#: bytes each on the driver); with more, documents are shuffled once.
MOST_BROADCAST = 100_000


def deduplicate(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """``docs`` with one document of each group of near copies, all columns kept.

    Of rows with equal doc_id and text one stays, the least by its columns as JSON.  Rows
    without doc_id stay.
    """
    names = docs.columns
    th = _store.fresh(names, "text_hash")
    found, repeated = _grouped(docs, settings)
    gone, repeated = (_store.small(_store.materialise(x.select("doc_id", F.col("text_hash").alias(th))), MOST_BROADCAST) for x in (found.where(~F.col("keep")), repeated))
    left = docs.withColumn(th, F.xxhash64("text")).join(gone, ["doc_id", th], "left_anti")
    single = left.join(repeated, ["doc_id", th], "left_anti").select(*[F.col(f"`{c}`") for c in names])
    row = F.struct(*[F.col(f"`{c}`") for c in names])
    one = left.join(repeated, ["doc_id", th], "left_semi").groupBy("doc_id", th).agg(F.min_by(row, F.to_json(row)).alias("row"))
    return single.unionByName(one.select(*[F.col("row").getField(c).alias(c) for c in names]))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = groups(_store.table(spark, sf_dir, "documents"))
    return found.select("doc_id", "group_id", "keep")
