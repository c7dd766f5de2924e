"""Embedding near-duplicates by iterative quantisation and multi-index Hamming tables.

Vectors are centred, turned to principal axes and by a rotation under which their signs
are balanced bits with little loss; the rotation is learned from all vectors, each step
needing only one matrix sum over them.  Codes are cut into substrings, each with a table of
its own; an equi-join on (table, substring) with every error pattern of up to
``substring_radius`` bits finds the pairs of a table.  What is within the Hamming radius of
that code is reranked by the cosine of the original vectors.

A search for all codes within a radius of a fourth of the bits would look at most pairs
there are.  So the tables are made for the pairs that are asked for: substrings have about
log2(n) bits, so that candidates grow with the number n of vectors and not with its square,
and there are as many tables as find a pair at the least cosine with probability ``recall``
(from more than one code, each with a rotation of its own, where one has not enough bits).
The share of bits in which such a pair differs follows from its angle after centring.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel.llm import _store, simhash


@dataclass(frozen=True)
class Settings:
    cosine: float = 0.95
    #: Bits of a code (at most 63 and the vectors' dimension), and the least Hamming radius;
    #: it grows with the bits in which pairs at ``cosine`` differ.
    bits: int = 60
    radius: int = 15
    #: Most differing bits that a substring may have to be a candidate.
    substring_radius: int = 1
    #: Least bits of a substring; more for more than 2 ** substring_bits vectors.
    substring_bits: int = 15
    #: Probability with which a pair at ``cosine`` is to be found.
    recall: float = 0.98
    iterations: int = 8
    seed: int = 7


@dataclass(frozen=True)
class Tables:
    """How codes are searched: bits of a substring, substrings of a code, codes, radius."""

    width: int
    each: int
    codes: int
    radius: int


def plan(n: int, bits: int, centred: float, s: Settings) -> Tables:
    """``centred``: the mean square length of the centred vectors of length 1."""
    angle = np.arccos(np.clip(1 - (1 - s.cosine) / max(centred, 1e-9), -1, 1))
    p = min(float(angle / np.pi), 0.4)  # beyond it a code says next to nothing
    width = min(bits, max(s.substring_bits, int(np.ceil(np.log2(max(n, 2))))))
    hit = sum(comb(width, k) * p**k * (1 - p) ** (width - k) for k in range(s.substring_radius + 1))
    tables = max(1, int(np.ceil(np.log(1 - s.recall) / np.log1p(-hit))) if hit < 1 else 1)
    each = max(1, bits // width)
    return Tables(width, each, -(-tables // each), max(s.radius, int(np.ceil(bits * p + 3 * np.sqrt(bits * p * (1 - p))))))


@dataclass
class Quantiser:
    mean: np.ndarray
    #: For each code (dimension, bits), the principal axes times its rotation.
    axes: list[np.ndarray]
    #: Number of vectors, and mean square length of the centred ones.
    n: int
    centred: float

    def codes(self, x: np.ndarray, which: int = 0) -> np.ndarray:
        bits = ((x - self.mean) @ self.axes[which]) > 0
        return bits @ (np.int64(1) << np.arange(bits.shape[1], dtype=np.int64))


def unit_rows(vectors: pa.Array, dimension: int) -> tuple[np.ndarray, np.ndarray]:
    """(n, dimension) of length 1, and which rows are proper vectors: not null, of that
    dimension, finite and not zero."""
    if isinstance(vectors, pa.ChunkedArray):
        vectors = vectors.combine_chunks()
    flat, sizes = vectors.flatten().to_numpy(zero_copy_only=False).astype(np.float64), vectors.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    out = np.zeros((len(vectors), dimension))
    proper = sizes == dimension
    starts = np.cumsum(sizes) - sizes
    if proper.any():
        out[proper] = flat[(starts[proper][:, None] + np.arange(dimension)).astype(np.int64)]
    norm = np.sqrt((out * out).sum(1))
    proper &= np.isfinite(norm) & (norm > 0)
    out[~proper] = 0
    return out / np.where(proper, norm, 1)[:, None], proper


def _sums(frame: DataFrame, dimension: int, rows: int, columns: int, part) -> np.ndarray:
    """The sum over all vectors of ``part(x)``, a matrix, added up on executors."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((rows, columns))
        for b in batches:
            x, proper = unit_rows(b.column(0), dimension)
            total += part(x[proper])
        n = rows * columns
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(n), pa.int32()), pa.array(total.ravel())], ["i", "v"])

    summed = frame.select("embedding").mapInArrow(partial, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).toPandas()
    out = np.zeros(rows * columns)
    out[summed["i"].to_numpy()] = summed["v"].to_numpy()
    return out.reshape(rows, columns)


def learn(vectors: DataFrame, dimension: int, s: Settings = Settings()) -> tuple[Quantiser, Tables]:
    """The codes and how to search them; all rotations are learned in the same passes."""
    bits = min(s.bits, 63, dimension)

    def moments(x: np.ndarray) -> np.ndarray:
        y = np.concatenate([x, np.ones((len(x), 1))], 1)
        return y.T @ y

    m = _sums(vectors, dimension, dimension + 1, dimension + 1, moments)
    n = max(m[-1, -1], 1.0)
    mean = m[-1, :-1] / n
    centred = float(np.trace(m[:-1, :-1]) / n - mean @ mean)
    tables = plan(int(n), bits, centred, s)
    _, axes = np.linalg.eigh(m[:-1, :-1] / n - np.outer(mean, mean))
    axes = axes[:, ::-1][:, :bits]
    rng = np.random.default_rng(s.seed)
    rotations = [np.linalg.qr(rng.standard_normal((bits, bits)))[0] for _ in range(tables.codes)]
    for _ in range(s.iterations if n > 1 else 0):
        turned = [axes @ r for r in rotations]

        def agreement(x: np.ndarray, turned=turned) -> np.ndarray:
            y = x - mean
            return np.concatenate([np.where(y @ t > 0, 1.0, -1.0).T for t in turned]) @ (y @ axes)

        both = _sums(vectors, dimension, bits * tables.codes, bits, agreement).reshape(tables.codes, bits, bits)
        u, _, vt = np.linalg.svd(both)
        rotations = [(a @ b).T for a, b in zip(u, vt, strict=True)]
    return Quantiser(mean, [axes @ r for r in rotations], int(n), centred), tables


def _vectors(embeddings: DataFrame) -> tuple[DataFrame | None, int]:
    """(vec_id, embedding) of the vectors of the commonest dimension (of equally common ones the
    larger), and that dimension.  An id is there once, with the least of its vectors."""
    there = embeddings.select("vec_id", "embedding").where("vec_id is not null and size(embedding) > 0")
    common = there.groupBy(F.size("embedding").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    if not common:
        return None, 0
    return _store.materialise(there.where(F.size("embedding") == common["d"]).groupBy("vec_id").agg(F.min("embedding").alias("embedding"))), common["d"]


def _search(vectors: DataFrame, head: int, s: Settings) -> tuple[DataFrame, DataFrame]:
    """(vec_id, codes) of the proper vectors, and vec_a, vec_b, cosine of the pairs found."""
    spark = vectors.sparkSession
    quantiser, t = learn(vectors, head, s)
    held, bits = spark.sparkContext.broadcast(quantiser), min(s.bits, 63, head)

    @F.arrow_udf("array<bigint>")
    def code(x: pa.Array) -> pa.Array:
        unit, ok = unit_rows(x, head)
        codes = np.stack([held.value.codes(unit, k) for k in range(t.codes)], 1)
        ends = np.append(0, np.cumsum(ok) * t.codes).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(ends), pa.array(codes[ok].ravel()))

    codes = _store.materialise(vectors.select("vec_id", code("embedding").alias("codes")).where("size(codes) > 0"))
    keyed = codes.select("vec_id", F.posexplode("codes").alias("of", "code"))
    keyed = keyed.withColumn("cut", F.explode(F.sequence(F.lit(0), F.lit(t.each - 1))))
    piece = F.expr(f"shiftrightunsigned(code, cut * {t.width}) & {(1 << t.width) - 1}L")
    keyed = keyed.select("vec_id", "code", (F.col("of") * t.each + F.col("cut")).alias("table"), piece.alias("key"))
    masks = [sum(1 << i for i in c) for k in range(s.substring_radius + 1) for c in combinations(range(min(t.width, bits)), k)]
    probes = keyed.withColumn("mask", F.explode(F.array(*[F.lit(m).cast("bigint") for m in masks])))
    probes = probes.where("mask = 0 or (key & (mask & -mask)) = 0")  # keys that differ meet once
    probes = probes.select("table", F.expr("key ^ mask").alias("key"), F.col("vec_id").alias("vec_b"), F.col("code").alias("code_b"))
    left = keyed.select("table", "key", F.col("vec_id").alias("vec_a"), F.col("code").alias("code_a"))
    near = left.join(probes, ["table", "key"]).where(F.expr(f"bit_count(code_a ^ code_b) <= {t.radius} and vec_a <> vec_b"))
    pairs = near.select(F.least("vec_a", "vec_b").alias("vec_a"), F.greatest("vec_a", "vec_b").alias("vec_b")).distinct()
    a = vectors.select(F.col("vec_id").alias("vec_a"), F.col("embedding").alias("ea"))
    b = vectors.select(F.col("vec_id").alias("vec_b"), F.col("embedding").alias("eb"))

    @F.arrow_udf("double")
    def cosine(x: pa.Array, y: pa.Array) -> pa.Array:
        return pa.array((unit_rows(x, head)[0] * unit_rows(y, head)[0]).sum(1))

    exact = pairs.join(a, "vec_a").join(b, "vec_b").select("vec_a", "vec_b", cosine("ea", "eb").alias("c"))
    return codes, exact.where(F.col("c") >= s.cosine).select("vec_a", "vec_b", F.round("c", 6).alias("cosine"))


def near_pairs(embeddings: DataFrame, s: Settings = Settings()) -> DataFrame:
    """vec_a, vec_b, cosine of all pairs found with at least that cosine, each once, ids in
    order.  Every vector is a query.

    Rows with null ids or with null, empty, zero or not finite vectors, or of another
    dimension than the commonest (of equally common ones the larger), take no part.  An id
    counts once, with the least of its vectors.  Other columns are ignored.
    """
    vectors, head = _vectors(embeddings)
    if vectors is None:
        return embeddings.sparkSession.createDataFrame([], "vec_a bigint, vec_b bigint, cosine double")
    return _search(vectors, head, s)[1]


def classes(embeddings: DataFrame, s: Settings = Settings()) -> DataFrame:
    """One row for each vec_id: vec_id, class_id, links.

    links is the number of other ids found with at least that cosine, class_id the least id that
    is reached over such links.  Equal vectors are searched as one and count with all their ids.
    Ids whose vectors take no part in ``near_pairs`` are classes of their own without links.
    """
    ids = embeddings.select("vec_id").where("vec_id is not null").distinct()
    alone = ids.select("vec_id", F.col("vec_id").alias("class_id"), F.lit(0).cast("bigint").alias("links"))
    vectors, head = _vectors(embeddings)
    if vectors is None:
        return alone
    equal = [F.xxhash64("embedding").alias("h"), F.xxhash64(F.lit(1), "embedding").alias("g")]
    held = vectors.select("vec_id", *equal)
    copies = _store.materialise(held.groupBy("h", "g").agg(F.min("vec_id").alias("first"), F.count("*").alias("members")))
    different = _store.materialise(vectors.join(copies.select(F.col("first").alias("vec_id")), "vec_id", "left_semi"))
    codes, pairs = _search(different, head, s)
    edges = _store.materialise(pairs.select(F.col("vec_a").alias("u"), F.col("vec_b").alias("v")))
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    links = both.join(copies.select(F.col("first").alias("v"), "members"), "v").groupBy(F.col("u").alias("first")).agg(F.sum("members").alias("others"))
    roots = simhash.stars(edges).select(F.col("v").alias("first"), F.col("u").alias("root"))
    proper = copies.join(codes.select(F.col("vec_id").alias("first")), "first", "left_semi")
    proper = proper.join(links, "first", "left").join(roots, "first", "left")
    number = F.col("members") - 1 + F.coalesce("others", F.lit(0))
    found = held.join(proper, ["h", "g"]).select("vec_id", F.coalesce("root", "first").alias("class_id"), number.cast("bigint").alias("links"))
    return found.unionByName(alone.join(found.select("vec_id"), "vec_id", "left_anti"))


def op5_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(_store.table(spark, sf_dir, "embeddings"))
