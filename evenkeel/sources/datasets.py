"""Training samples from the given tables, and generated ones."""

from __future__ import annotations

from functools import reduce
from itertools import combinations, product

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel import hashing

INTEGER = ["x1", "x2", "x3", "x4"]
SCALED = ["x1", "x2", "x3", "x4", "x5"]
#: Planted weights of the labels of ``lineitem_planted``.
PLANTED = [0.8, -0.6, 0.4, -0.3, 0.2]


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _row_key() -> Column:
    return F.concat_ws("-", "l_orderkey", "l_linenumber")


def lineitem_integer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """key, y (returned), x1..x4 whole numbers, so that sums are exact in any order."""
    li = read(spark, sf_dir, "lineitem")
    return li.select(
        _row_key().alias("key"),
        (F.col("l_returnflag") == "R").cast("double").alias("y"),
        F.col("l_quantity").alias("x1"),
        F.round(F.col("l_discount") * 100).alias("x2"),
        F.round(F.col("l_tax") * 100).alias("x3"),
        F.lit(1.0).alias("x4"),
    )


def lineitem_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """key, x1..x5 of order 1, u, y = 1 where u is under the logistic of -2 x beta, and
    holdout (a fifth)."""
    li = read(spark, sf_dir, "lineitem")
    x = li.select(
        _row_key().alias("key"),
        (F.col("l_quantity") / 50).alias("x1"),
        (F.col("l_discount") * 10).alias("x2"),
        (F.col("l_tax") * 10).alias("x3"),
        (F.col("l_extendedprice") / 100000).alias("x4"),
        (F.col("l_returnflag") == "R").cast("double").alias("x5"),
    )
    margin = sum((F.col(c) * b for c, b in zip(SCALED, PLANTED, strict=True)), F.lit(0.0))
    u = hashing.md5_uniform(F.concat(F.lit("label-"), "key"))
    y = (u < 1 / (1 + F.exp(2 * margin))).cast("double")
    return x.withColumn("y", y).withColumn("holdout", F.pmod(hashing.md5_number(F.concat(F.lit("holdout-"), "key")), F.lit(5)) == 0)


def mixture_logistic(spark: SparkSession, d: int, p: int, seed: int = 1, partitions: int | None = None, centres: str = "random") -> DataFrame:
    """key, x (array), y from two Gaussians of equal weight and labels by the logistic of
    -2 x beta.  Their centres are drawn from normals, or with ``centres="opposite"`` are
    +-1.5/p beta.  Normals come from hashes of (seed, row, column), not from a generator
    that depends on the partitioning."""
    beta = true_beta(p, seed)
    drawn = np.random.default_rng([seed, 2]).standard_normal((2, p)) if centres == "random" else np.stack([1.5 / p * beta, -1.5 / p * beta])
    one, other = (F.lit([float(v) for v in c]) for c in drawn)

    def uniform(tag: str) -> Column:
        return F.transform(F.sequence(F.lit(1), F.lit(p)), lambda j: (F.pmod(F.xxhash64(F.lit(f"{seed}{tag}"), "id", j), F.lit(1 << 40)) + 0.5) / float(1 << 40))

    normal = F.zip_with(uniform("a"), uniform("b"), lambda a, b: F.sqrt(-2 * F.log(a)) * F.cos(b * float(2 * np.pi)))
    centre = F.when(F.pmod(F.xxhash64(F.lit(f"{seed}side"), "id"), F.lit(2)) == 0, one).otherwise(other)
    rows = spark.range(0, d, 1, partitions) if partitions else spark.range(d)
    x = rows.select(F.col("id").alias("key"), "id", F.zip_with(normal, centre, lambda z, m: z + m).alias("x"))
    margin = F.aggregate(F.zip_with("x", F.lit([float(b) for b in beta]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    u = (F.pmod(F.xxhash64(F.lit(f"{seed}label"), "id"), F.lit(1 << 40)) + 0.5) / float(1 << 40)
    return x.select("key", "x", (u < 1 / (1 + F.exp(2 * margin))).cast("double").alias("y"))


_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turn(x: np.ndarray, bits: int) -> np.ndarray:
    return x << np.uint64(bits) | x >> np.uint64(64 - bits)


def _final(h: np.ndarray) -> np.ndarray:
    h = (h ^ h >> np.uint64(33)) * _P2
    h = (h ^ h >> np.uint64(29)) * _P3
    return h ^ h >> np.uint64(32)


def _with_long(seed: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Spark's xxhash64 carried on by a long."""
    h = seed + _P5 + np.uint64(8) ^ _turn(x.astype(np.uint64) * _P2, 31) * _P1
    return _final(_turn(h, 27) * _P1 + _P4)


def _with_int(seed: np.ndarray, x: np.ndarray) -> np.ndarray:
    h = seed + _P5 + np.uint64(4) ^ x.astype(np.uint64) * _P1
    return _final(_turn(h, 23) * _P2 + _P3)


def mixture_heads(spark: SparkSession, seed: int = 1) -> np.ndarray:
    """Where the hashes of ``mixture_samples`` begin."""
    row = spark.range(1).select(*[F.xxhash64(F.lit(f"{seed}{tag}")) for tag in ("a", "b", "side", "label")]).first()
    return np.array(row, dtype=np.int64).view(np.uint64)


def mixture_samples(ids: np.ndarray, p: int, heads: np.ndarray, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """x and y of ``mixture_logistic`` for some ids, made where they are needed: at p = 100 they take
    eight hundred bytes a sample and so are not kept."""
    beta, low = true_beta(p, seed), np.uint64((1 << 40) - 1)
    drawn = np.random.default_rng([seed, 2]).standard_normal((2, p))
    with np.errstate(over="ignore"):
        a, b, side, label = (_with_long(np.full(len(ids), h), ids) for h in heads)
        u, v = (((_with_int(h[:, None], np.arange(1, p + 1)[None]) & low).astype(float) + 0.5) / float(1 << 40) for h in (a, b))
    x = np.sqrt(-2 * np.log(u)) * np.cos(v * float(2 * np.pi)) + drawn[(side & np.uint64(1)).astype(int)]
    return x, (((label & low).astype(float) + 0.5) / float(1 << 40) < 1 / (1 + np.exp(2 * (x @ beta)))).astype(float)


def true_beta(p: int, seed: int = 1) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal(p) / np.sqrt(p)


def document_tokens(spark: SparkSession, sf_dir: str, label: str, p: int = 4096, pairs: bool = False) -> DataFrame:
    """row_id, y, xs (distinct hashed tokens, with ``pairs`` also neighbours), holdout,
    source, n_chars of the labelled documents."""
    docs, labels = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")
    both = docs.join(labels.select("doc_id", F.col(label).cast("double").alias("y")), "doc_id")
    words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: w != "")
    d = both.select(F.col("doc_id").alias("row_id"), "y", "source", "n_chars", words.alias("w"))
    tokens = F.col("w")
    if pairs:
        tokens = F.concat("w", F.zip_with(F.slice("w", 1, F.greatest(F.size("w") - 1, F.lit(0))), F.slice("w", 2, F.size("w")), lambda a, b: F.concat_ws(" ", a, b)))
    hashed = F.array_distinct(F.transform(tokens, lambda w: F.pmod(hashing.md5_number(w), F.lit(p)).cast("int")))
    xs = F.transform(hashed, lambda i: F.struct(i.alias("idx"), F.lit(1.0).alias("val")))
    return d.select("row_id", F.col("row_id").alias("key"), "y", "source", "n_chars", xs.alias("xs"), (F.pmod("row_id", F.lit(5)) == 0).alias("holdout"))


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with the categories of its part, supplier, order and customer; small sides
    are left to the optimizer to broadcast."""
    t = {x: read(spark, sf_dir, x) for x in ("lineitem", "orders", "customer", "part", "supplier", "nation")}
    li = t["lineitem"].select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag", "l_quantity")
    d = li.join(t["orders"].select("o_orderkey", "o_custkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
    d = d.join(t["customer"].select("c_custkey", "c_mktsegment", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    d = d.join(t["part"].select("p_partkey", "p_brand", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    d = d.join(t["supplier"].select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return d.join(t["nation"].select("n_nationkey", "n_name"), F.col("s_nationkey") == F.col("n_nationkey"))


#: Columns of the star that become indicators, alone and in pairs and threes.
CATEGORIES = ("p_brand", "p_type", "n_name", "c_nationkey", "c_mktsegment", "o_orderpriority")
INTERACTIONS = tuple(c for k in (1, 2, 3) for c in combinations(CATEGORIES, k))
#: Features after one-hot encoding with interactions.
ONE_HOT = 241_915


def star_one_hot(spark: SparkSession, sf_dir: str, p: int = ONE_HOT) -> DataFrame:
    """key, y (returned), xs: one indicator for each category and each pair and three of them,
    at a place by hash among ``p``."""
    d = star(spark, sf_dir)
    named = [F.concat_ws("|", *[F.concat_ws("=", F.lit(c), F.col(c).cast("string")) for c in t]) for t in INTERACTIONS]
    places = F.array_distinct(F.array(*[F.pmod(hashing.md5_number(x), F.lit(p)).cast("int") for x in named]))
    xs = F.transform(places, lambda i: F.struct(i.alias("idx"), F.lit(1.0).alias("val")))
    return d.select(_row_key().alias("key"), (F.col("l_returnflag") == "R").cast("double").alias("y"), xs.alias("xs"))


#: Tables that the categories come from.
_HOLDERS = {"p_brand": "part", "p_type": "part", "n_name": "nation", "c_nationkey": "customer", "c_mktsegment": "customer", "o_orderpriority": "orders"}
#: Values of a category, and combinations of values in all interactions, up to which places are
#: tabulated; with more, each sample has a row of its own, with the same result.
MOST_VALUES, MOST_PLACES = 50_000, 4_000_000


def star_counted(spark: SparkSession, sf_dir: str, blocks: int, p: int = ONE_HOT) -> tuple[DataFrame, list[tuple[np.ndarray, np.ndarray]]] | None:
    """``star_one_hot`` with samples of the same categories and label as one row: y, code, counts
    (samples by block); and for each interaction, what to divide a code by and take the rest of
    for each of its categories, and the places by their digits.  None if there are too many."""
    values = []
    for c in CATEGORIES:
        found = read(spark, sf_dir, _HOLDERS[c]).select(F.col(c).cast("string").alias("v")).where("v is not null").distinct().limit(MOST_VALUES + 1).collect()
        if len(found) > MOST_VALUES:
            return None
        values.append(sorted(r["v"] for r in found))
    sizes = [len(v) + 1 for v in values]  # the first is for null
    if sum(int(np.prod([float(sizes[CATEGORIES.index(c)]) for c in t])) for t in INTERACTIONS) > MOST_PLACES or np.prod([float(n) for n in sizes]) >= 2**62:
        return None
    steps = [int(np.prod(sizes[:i], dtype=object)) if i else 1 for i in range(len(sizes))]
    places = []
    for t in INTERACTIONS:
        at = [CATEGORIES.index(c) for c in t]
        names = [[c, *(f"{c}={v}" for v in values[i])] for c, i in zip(t, at, strict=True)]
        table = np.fromiter((hashing.md5_number_py("|".join(x)) % p for x in product(*names)), dtype=np.int32)
        places.append((np.array([(steps[i], sizes[i]) for i in at], dtype=np.int64), table))
    digits = [F.coalesce(F.array_position(F.lit(v) if v else F.array().cast("array<string>"), F.col(c).cast("string")), F.lit(0).cast("bigint")) * n for c, v, n in zip(CATEGORIES, values, steps, strict=True)]
    d = star(spark, sf_dir).where("l_returnflag is not null")
    d = d.select(reduce(lambda a, b: a + b, digits).alias("code"), (F.col("l_returnflag") == "R").cast("double").alias("y"), hashing.block_of(_row_key(), blocks).alias("block"))
    one = d.groupBy("code", "y").agg(*[F.count_if(F.col("block") == b).alias(f"n{b}") for b in range(blocks)])
    return one.select("y", "code", F.array(*[f"n{b}" for b in range(blocks)]).alias("counts")), places


def embeddings_dense(spark: SparkSession, sf_dir: str, label: int = 0) -> DataFrame:
    e = read(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("key"), (F.col("label") == label).cast("double").alias("y"), F.col("embedding").cast("array<double>").alias("x"))
