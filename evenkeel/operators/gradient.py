"""Gradients summed over samples, whole or by block, in four ways.

wide     features are columns; one sum a feature in whole-stage codegen (p up to ~16)
array    features are an array column; SQL only (p up to ~64)
arrow    features are an array column; one matrix product a batch (p from ~32)
sparse   features are (index, value) pairs; the model is an array that is broadcast up
         to ``broadcast_limit`` bytes and a table joined by index beyond it
counted  features are indicators; samples that are alike are one row with their number by block

Samples have ``block`` and ``y``.  A sample with a null label or feature, or null features, is
left out by each of them (``complete`` does so beforehand, for counts).  Only one partial vector a task and block leaves the
scan; data are never copied by worker.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A model's bytes up to which it is sent to every executor.
broadcast_limit = 1 << 30
#: Pieces in which long vectors travel, so that no row is megabytes long.
CHUNK = 4096


def kernel_for(p: int, sparse: bool = False) -> str:
    return "sparse" if sparse else "wide" if p <= 16 else "arrow"


def complete(samples: DataFrame, kernel: str, columns: Sequence[str] = ()) -> DataFrame:
    """The samples that take part in gradients."""
    there = F.col("y").isNotNull()
    if kernel == "counted":
        return samples.where(there)
    if kernel == "wide":
        for c in columns:
            there &= F.col(c).isNotNull()
    elif kernel == "sparse":
        there &= F.col("xs").isNotNull() & ~F.exists("xs", lambda e: e["val"].isNull() | e["idx"].isNull())
    else:
        there &= F.col("x").isNotNull()
        if samples.schema["x"].dataType.containsNull:
            there &= F.array_size(F.array_compact("x")) == F.array_size("x")
    return samples.where(there)


def margin_wide(beta: Sequence[float], columns: Sequence[str]) -> Column:
    return sum((F.col(c) * float(b) for c, b in zip(columns, beta, strict=True)), F.lit(0.0))


def partial_wide(samples: DataFrame, loss, beta: Sequence[float], columns: Sequence[str], by: Sequence[str] = ("block",)) -> DataFrame:
    """``by``, g1..gp, rows."""
    resid = samples.select(*by, *columns, loss.slope(margin_wide(beta, columns), F.col("y")).alias("resid"))
    sums = [F.sum(F.col("resid") * F.col(c)).alias(f"g{j}") for j, c in enumerate(columns, 1)]
    return resid.groupBy(*by).agg(*sums, F.count("resid").alias("rows"))


def long_form(wide: DataFrame, p: int, by: Sequence[str] = ("block",)) -> DataFrame:
    """``by``, idx (from 1), g."""
    pairs = F.array(*[F.struct(F.lit(j).alias("idx"), F.col(f"g{j}").alias("g")) for j in range(1, p + 1)])
    return wide.select(*by, F.explode(pairs).alias("e")).select(*by, "e.idx", "e.g")


def partial_array(samples: DataFrame, loss, beta: np.ndarray) -> DataFrame:
    """block, idx (from 1), g from an array column ``x``, in SQL only."""
    model = F.lit([float(b) for b in beta])
    margin = F.aggregate(F.zip_with("x", model, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    resid = samples.select("block", "x", loss.slope(margin, F.col("y")).alias("resid"))
    each = resid.select("block", "resid", F.posexplode("x").alias("i", "v"))
    return each.groupBy("block", (F.col("i") + 1).alias("idx")).agg(F.sum(F.col("resid") * F.col("v")).alias("g"))


def _matrix(column: pa.Array, p: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), p).astype(np.float64, copy=False)


def partial_arrow(samples: DataFrame, loss, beta: np.ndarray) -> DataFrame:
    """block, idx (from 1), g from an array column ``x``; one product a batch and block,
    one vector a task and block."""
    model = samples.sparkSession.sparkContext.broadcast(np.asarray(beta, dtype=float))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        b, total = model.value, {}
        for batch in batches:
            batch = batch.filter(pa.compute.and_(batch.column("x").is_valid(), batch.column("y").is_valid()))
            x, y, block = _matrix(batch.column("x"), len(b)), batch.column("y").to_numpy(), batch.column("block").to_numpy()
            if batch.column("x").flatten().null_count:
                ok = ~np.isnan(x).any(axis=1)
                x, y, block = x[ok], y[ok], block[ok]
            resid = loss.slope_np(x @ b, y)
            for k in np.unique(block):
                own = block == k
                total[k] = total.get(k, 0) + resid[own] @ x[own]
        for k, g in total.items():
            for at in range(0, len(g), CHUNK):
                part = g[at : at + CHUNK]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), k, dtype=np.int32)), pa.array(np.arange(at + 1, at + 1 + len(part), dtype=np.int32)), pa.array(part)], ["block", "idx", "g"])

    parts = samples.select("block", "y", "x").mapInArrow(scan, "block int, idx int, g double")
    return parts.groupBy("block", "idx").agg(F.sum("g").alias("g"))


def partial_sparse(samples: DataFrame, loss, beta: np.ndarray, limit: int | None = None) -> DataFrame:
    """block, idx (as in ``xs``, from 0), g of the coordinates that occur, from ``xs``
    array<struct<idx, val>> and ``row_id``."""
    spark = samples.sparkSession
    entries = F.explode("xs").alias("e")
    if 8 * len(beta) <= (broadcast_limit if limit is None else limit):
        model = spark.sparkContext.broadcast(np.asarray(beta, dtype=float))

        @F.arrow_udf("double")
        def margin(xs: pa.Array) -> pa.Array:
            flat = xs.flatten()
            v = model.value[flat.field("idx").to_numpy()] * flat.field("val").to_numpy(zero_copy_only=False)
            owner = np.repeat(np.arange(len(xs)), xs.value_lengths().fill_null(0).to_numpy())
            m = np.bincount(owner, weights=v, minlength=len(xs)) if len(v) else np.zeros(len(xs))
            return pa.array(m, mask=np.isnan(m))  # a null among the values: no part of the sum

        resid = samples.select("block", "xs", loss.slope(margin("xs"), F.col("y")).alias("resid"))
        each = resid.select("block", "resid", entries)
    else:  # the model is a table: join entries with their weights, sum up the margins
        there = np.flatnonzero(beta)
        table = spark.createDataFrame(pa.table({"idx": there.astype(np.int32), "beta": np.asarray(beta, dtype=float)[there]}))
        flat = complete(samples, "sparse").select("row_id", "block", "y", entries)
        m = flat.join(table, flat["e.idx"] == table["idx"], "left").groupBy("row_id").agg(F.sum(F.coalesce("beta", F.lit(0.0)) * F.col("e.val")).alias("margin"))
        each = flat.join(m, "row_id").select("block", loss.slope(F.col("margin"), F.col("y")).alias("resid"), "e")
    return each.groupBy("block", F.col("e.idx").alias("idx")).agg(F.sum(F.col("resid") * F.col("e.val")).alias("g"))


def combined_counted(samples: DataFrame, loss, beta: np.ndarray, weights: np.ndarray, places: Sequence[tuple[np.ndarray, np.ndarray]]) -> DataFrame:
    """idx (from 0), g (weighted by block) and exact of indicators, from samples that are alike in
    one row: ``y``, ``code`` and ``counts`` by block.  ``places`` tells a code's indicators."""
    p, held = len(beta), samples.sparkSession.sparkContext.broadcast((np.asarray(beta, dtype=float), np.asarray(weights, dtype=float), places))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (b, w, tables), total, seen = held.value, np.zeros((2, p)), np.zeros(p, dtype=bool)
        for batch in batches:
            code = batch.column("code").to_numpy()
            at = np.empty((len(code), len(tables)), dtype=np.int32)
            for j, (digits, table) in enumerate(tables):
                spot = np.zeros(len(code), dtype=np.int64)
                for step, size in digits:
                    spot = spot * size + code // step % size
                at[:, j] = table[spot]
            at.sort(axis=1)
            new = np.ones(at.shape, dtype=bool)  # places that two interactions share count once
            new[:, 1:] = at[:, 1:] != at[:, :-1]
            resid = loss.slope_np((b[at] * new).sum(axis=1), batch.column("y").to_numpy())
            counts = batch.column("counts").flatten().to_numpy().reshape(len(code), len(w))
            owner, flat = np.nonzero(new)[0], at[new]
            seen[flat] = True
            for k, many in enumerate((counts @ w, counts.sum(axis=1))):
                total[k] += np.bincount(flat, weights=(resid * many)[owner], minlength=p)
        idx = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(idx.astype(np.int32)), pa.array(total[0, idx]), pa.array(total[1, idx])], ["idx", "g", "exact"])

    return samples.select("y", "code", "counts").mapInArrow(scan, "idx int, g double, exact double").groupBy("idx").agg(F.sum("g").alias("g"), F.sum("exact").alias("exact"))


def partial_gradients(samples: DataFrame, loss, beta: np.ndarray, kernel: str, columns: Sequence[str] = ()) -> DataFrame:
    """block, idx, g by any kernel."""
    if kernel == "wide":
        return long_form(partial_wide(samples, loss, beta, columns), len(columns))
    return {"array": partial_array, "arrow": partial_arrow, "sparse": partial_sparse}[kernel](samples, loss, beta)


def to_vector(long: DataFrame, p: int, first: int = 1) -> np.ndarray:
    """A long vector (idx, g) on the driver; p floats."""
    out = np.zeros(p)
    frame = long.select("idx", "g").toPandas()
    out[frame["idx"].to_numpy(dtype=int) - first] = frame["g"].to_numpy()
    return out


def full_gradient(samples: DataFrame, loss, beta: np.ndarray, kernel: str, columns: Sequence[str] = ()) -> np.ndarray:
    """Without any code: the exact sum to compare with."""
    long = partial_gradients(samples, loss, beta, kernel, columns).groupBy("idx").agg(F.sum("g").alias("g"))
    return to_vector(long, len(beta), 0 if kernel == "sparse" else 1)


def batched_gradients(samples: DataFrame, loss, betas: Sequence[Sequence[float]], columns: Sequence[str]) -> DataFrame:
    """block, g<m>_<j> of several models in one scan, for tuning rates."""
    resids = [loss.slope(margin_wide(b, columns), F.col("y")).alias(f"r{m}") for m, b in enumerate(betas)]
    r = samples.select("block", *columns, *resids)
    return r.groupBy("block").agg(*[F.sum(F.col(f"r{m}") * F.col(c)).alias(f"g{m}_{j}") for m in range(len(betas)) for j, c in enumerate(columns, 1)])
