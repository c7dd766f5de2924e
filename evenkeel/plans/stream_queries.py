"""Streams over files, run until they have taken in what is there."""

from __future__ import annotations

import glob
import os
import shutil
import tempfile
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel.functions.losses import Logistic
from evenkeel.operators import codes, gradient, messages
from evenkeel.operators.stragglers import Stragglers
from evenkeel.plans.gradient_queries import X, _blocks, samples_sql
from evenkeel.sources import datasets
from evenkeel.streaming import mailbox

QUERIES, ORACLES = {}, {}


def shared_folder(spark: SparkSession) -> str:
    """A new folder under ``spark.checkpoint.dir``; without that setting, as in tests, a
    temporary one."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    return f"{base.rstrip('/')}/stream-{uuid.uuid4().hex}" if base else tempfile.mkdtemp(prefix="evenkeel-stream-")


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    # a file source wants a folder or a pattern
    source = path if os.path.isdir(path) else f"{sf_dir}/events[.]parquet"
    assert glob.glob(source), source
    return spark.readStream.schema(schema).parquet(source).withColumn("ts", F.col("ts").cast("timestamp"))


#: State beyond a bounded cache is on disk, not on the heap: on one machine that is the driver's.
STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "200",
}


def finish(stream: DataFrame, mode: str, state: dict[str, str] = {}) -> DataFrame:
    """Run on what is there, and the result as a table.  Executors write it as Parquet, a folder
    for each batch; no rows come to the driver.  In complete mode the last batch has it all.
    ``state``: settings of the session while the stream starts."""
    spark, schema = stream.sparkSession, stream.schema
    folder, out, written = shared_folder(spark), shared_folder(spark), []

    def keep(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{epoch}")
        if mode == "complete":
            written.clear()
        written.append(f"{out}/{epoch}")

    before = {k: spark.conf.get(k, None) for k in state}
    for k, v in state.items():
        spark.conf.set(k, v)
    try:  # a stream keeps the settings that it starts with
        query = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", folder).trigger(availableNow=True).start()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    query.awaitTermination()
    shutil.rmtree(folder.removeprefix("file://"), ignore_errors=True)
    return spark.read.schema(schema).parquet(*dict.fromkeys(written)) if written else spark.createDataFrame([], schema)


def stream_window(spark, sf_dir):
    """Mean delay by hour and kind."""
    e = event_stream(spark, sf_dir).withWatermark("ts", "1 hour")
    t = finish(e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("rows"), F.avg("value").alias("mean")), "complete")
    return t.select(F.unix_micros("window.start").alias("start_us"), "event_type", "rows", F.round("mean", 6).alias("mean_ms"))


QUERIES["stream_window"] = stream_window
ORACLES["stream_window"] = "select epoch_us(date_trunc('hour', ts)) as start_us, event_type, count(*) as rows, round(avg(value), 6) as mean_ms from events group by 1, 2"


def stream_sliding(spark, sf_dir):
    e = event_stream(spark, sf_dir).withWatermark("ts", "1 hour")
    t = finish(e.groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count("*").alias("rows")), "complete")
    return t.select(F.unix_micros("window.start").alias("start_us"), "rows")


QUERIES["stream_sliding"] = stream_sliding
ORACLES["stream_sliding"] = "select epoch_us(date_trunc('hour', ts) - i * interval 1 hour) as start_us, count(*) as rows from events, generate_series(0, 1) t(i) group by 1"


def stream_session(spark, sf_dir):
    """Bursts of a worker's messages with gaps under 30 minutes."""
    e = event_stream(spark, sf_dir).withWatermark("ts", "1 hour")
    t = finish(e.groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("rows")), "complete")
    return t.select("user_id", F.unix_micros("session_window.start").alias("start_us"), "rows")


QUERIES["stream_session"] = stream_session
ORACLES["stream_session"] = """
with a as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) >= interval 30 minute or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events),
b as (select *, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from a)
select user_id, epoch_us(min(ts)) as start_us, count(*) as rows from b group by user_id, k"""


def stream_dedup(spark, sf_dir):
    """Messages sent twice are taken once."""
    e = event_stream(spark, sf_dir)
    twice = e.select("event_id", "ts", "user_id", F.explode(F.array(F.lit(1), F.lit(2))).alias("try"))
    once = twice.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return finish(once.select("event_id", "user_id"), "append", STATE).groupBy("user_id").agg(F.count("*").alias("messages"))


QUERIES["stream_dedup"] = stream_dedup
ORACLES["stream_dedup"] = "select user_id, count(*) as messages from events group by user_id"


def stream_interval_join(spark, sf_dir):
    """Clicks within five minutes after a purchase of the same worker."""
    a = event_stream(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("opened"), F.col("ts").alias("t0"), F.col("user_id").alias("u")).withWatermark("t0", "1 hour")
    b = event_stream(spark, sf_dir).where("event_type = 'click'").select("event_id", F.col("ts").alias("t1"), "user_id").withWatermark("t1", "1 hour")
    hit = a.join(b, F.expr("u = user_id and t1 >= t0 and t1 < t0 + interval 5 minutes"))
    return finish(hit.select("opened", "event_id"), "append").select("opened", "event_id")


QUERIES["stream_interval_join"] = stream_interval_join
ORACLES["stream_interval_join"] = """
select a.event_id as opened, b.event_id from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts < a.ts + interval 5 minute
where a.event_type = 'purchase' and b.event_type = 'click'"""


def stream_rounds(spark, sf_dir):
    """Six rounds of a ring code 6, 2 as a stream of messages with repeats and latecomers:
    each decoded gradient equals the plain sum."""
    code = codes.ring_code(6, 2)
    g = gradient.partial_wide(_blocks(spark, sf_dir, 6), Logistic(), [0.0] * 4, X)
    vec = F.array(*[F.col(f"v{j}") for j in range(1, 5)])
    sent = messages.encode_wide(g, code.triplets(spark), 4).select("worker", vec.alias("vec"))
    late = Stragglers("additive", s=2)
    rows = [(t, w, 60.0 * t + (30 if w in late.late(t, 6) else 1) + w / 10) for t in range(6) for w in [*range(6), 0]]
    clock = spark.createDataFrame(rows, "round int, worker int, second double")
    folder = shared_folder(spark)
    full = clock.join(F.broadcast(sent), "worker").select("round", "worker", "vec", F.timestamp_seconds("second").alias("sent_at"))
    full.repartition(3, "worker").write.mode("overwrite").parquet(folder)
    stream = spark.readStream.schema(mailbox.MESSAGE).option("maxFilesPerTrigger", 1).parquet(folder)
    out = finish(mailbox.aggregate_rounds(stream, code), "append")
    return out.select("round", *[(F.round(F.col("g")[j - 1], 3) + 0.0).alias(f"g{j}") for j in range(1, 5)])


QUERIES["stream_rounds"] = stream_rounds
ORACLES["stream_rounds"] = f"with g as (select {', '.join(f'round(sum((0.5 - y) * x{j}), 3) + 0.0 as g{j}' for j in range(1, 5))} from ({samples_sql(1)})) select r::int as round, g.* from generate_series(0, 5) t(r), g"


def stream_model(spark, sf_dir):
    """Online descent: each micro-batch of planted lineitem samples makes one step through
    a block code in ``foreachBatch``; the models after each."""
    from evenkeel.operators import optim, placement

    folder = shared_folder(spark)
    d = datasets.lineitem_planted(spark, sf_dir).where("not holdout")
    d.repartition(3, "key").write.mode("overwrite").parquet(folder)
    code, model, rows = codes.block_code(6, 2), optim.NAG(5, 2.0), []

    def step(batch: DataFrame, epoch: int) -> None:
        placed = placement.assign_blocks(batch, F.col("key"), 6)
        g = gradient.partial_wide(placed, Logistic(), model.point(), datasets.SCALED)
        long = messages.encode(gradient.long_form(g, 5), code.triplets(batch.sparkSession)).where("worker < 4")
        weights = messages.weights_table(batch.sparkSession, {0: np.array([1, 1, 0, 0, 0, 0.0])})
        model.step(gradient.to_vector(messages.combine(long, weights), 5) / max(1, batch.count()))
        rows.extend((epoch, j, float(b)) for j, b in enumerate(model.beta, 1))

    q = spark.readStream.schema(d.schema).option("maxFilesPerTrigger", 1).parquet(folder).writeStream.foreachBatch(step).option("checkpointLocation", folder + "-state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.createDataFrame(rows, "epoch bigint, idx int, beta double")


QUERIES["stream_model"] = stream_model
