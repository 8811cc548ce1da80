"""Queries of the streaming operators: each runs its stream to the end of the given files, then returns what it put out."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallgram.operators.gram import exact_gram
from tallgram.operators.norms import column_norms
from tallgram.queries import query, sql
from tallgram.sources import workloads
from tallgram.streaming import events as E
from tallgram.streaming import incremental


def _folder(spark: SparkSession) -> str:
    """A new folder for checkpoints and results: in the shared folder, or a temporary one for a local session."""
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if shared:
        return f"{shared.rstrip('/')}/streams/{uuid.uuid4().hex}"
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    folder = tempfile.mkdtemp(prefix="tallgram-stream-")
    atexit.register(shutil.rmtree, folder, True)
    return folder


def _source(spark: SparkSession, d: str) -> DataFrame:
    # a file source takes a folder or a pattern: this pattern is the one table
    return E.watermarked(E.stream_events(spark, f"{d}/events.parquet*"))


def _finished(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Rows of the stream after all input: micro-batches are written to the shared folder, each in a folder of its own.

    A batch that runs again replaces what it left; in complete mode the last batch is the result.
    """
    spark, folder = stream.sparkSession, _folder(stream.sparkSession)
    spark.createDataFrame([], stream.schema).write.parquet(f"{folder}/out/batch=-1")
    last = [-1]

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={batch_id}")
        last[0] = batch_id

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    path = f"{folder}/out/batch={last[0]}" if mode == "complete" else f"{folder}/out/*"
    return spark.read.schema(stream.schema).parquet(path)


@query("stream_tumbling", "select date_trunc('day', ts)::timestamp as day, count(*) as n from events group by 1")
def stream_tumbling(s, d):
    return _finished(E.emissions_per_day(_source(s, d))).select(F.col("day").cast("timestamp_ntz").alias("day"), "n")


@query("stream_sliding", "select start, event_type, count(*) as n, round(sum(value), 4) as total from (select event_type, value, unnest(generate_series(time_bucket(interval 6 hours, ts) - interval 18 hours, time_bucket(interval 6 hours, ts), interval 6 hours)) as start from events) group by all")
def stream_sliding(s, d):
    return _finished(E.activity_sliding(_source(s, d))).select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("stream_session", "select user_id, min(ts) as start, count(*) as n from (select *, sum(new) over (partition by user_id order by ts, event_id) as k from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 30 minutes then 0 else 1 end as new from events)) group by user_id, k")
def stream_session(s, d):
    return _finished(E.user_sessions(_source(s, d))).select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_dedup", "select event_type, count(distinct event_id) as n from events group by event_type")
def stream_dedup(s, d):
    e = _source(s, d)
    twice = e.unionByName(e)
    return _finished(E.dedup_events(twice).select("event_id", "event_type"), "append").groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_interval_join", "select a.event_id as click, b.event_id as purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")
def stream_interval_join(s, d):
    return _finished(E.click_to_purchase(_source(s, d)), "append")


@query("stream_static_norms", f"with {sql.matrix('w3')} select event_type, count(*) as n, round(sum(norm), 4) as total from events join d on d.label = cast(json_extract_string(props, '$.k') as integer) join c using (col) group by event_type")
def stream_static_norms(s, d):
    names = workloads.dictionary(s, d, "w3")
    norms = column_norms(workloads.matrix(s, d, "w3")).join(F.broadcast(names), "col").select("label", "norm")
    found = E.with_norms(_source(s, d), norms).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("norm").alias("total"))
    return _finished(found).select("event_type", "n", F.round("total", 4).alias("total"))


@query("stream_assembled_rows")
def stream_assembled_rows(s, d):
    """Rows of the days that are over when the input ends."""
    return _finished(E.assemble_rows(_source(s, d)), "append").select("row_id", F.size("labels").cast("long").alias("n"))


@query("stream_incremental_gram", sql.with_pairs("w4", "select i, j, sum(x * y) as dot, count(*) as n from q group by i, j"))
def stream_incremental_gram(s, d):
    """Batch after batch of rows with a budget that keeps everything: the exact Gram matrix."""
    m = workloads.matrix(s, d, "w4")
    return _incremental(s, m, 1e9)


@query("stream_incremental_sampled", "select true as close")
def stream_incremental_sampled(s, d):
    """The sampled stream's total of all dot products is within a twentieth of the exact one."""
    m = workloads.matrix(s, d, "w4")
    got = _incremental(s, m, 100.0).agg(F.sum("dot").alias("a"))
    want = exact_gram(m).agg(F.sum("dot").alias("b"))
    return got.crossJoin(want).select((F.abs(F.col("a") - F.col("b")) <= F.col("b") / 20).alias("close"))


def _incremental(s: SparkSession, m: DataFrame, gamma: float) -> DataFrame:
    from tallgram.operators.matrix import ROW_FORM
    from tallgram.sources.files import save_rows

    folder = _folder(s)
    save_rows(m.repartition(4), f"{folder}/rows")
    rows = s.readStream.schema(ROW_FORM).option("maxFilesPerTrigger", 2).parquet(f"{folder}/rows")
    incremental.start_incremental_gram(rows, column_norms(m), gamma, 7, f"{folder}/gram", f"{folder}/checkpoint").awaitTermination()
    return incremental.current_gram(s, f"{folder}/gram")


@query("stream_update_counts", "select event_type, count(*) as n from events group by event_type")
def stream_update_counts(s, d):
    """Update mode: each batch puts out the counts that changed; the largest of each type is the last."""
    counts = _source(s, d).groupBy("event_type").agg(F.count("*").alias("n"))
    return _finished(counts, "update").groupBy("event_type").agg(F.max("n").alias("n"))


@query("stream_restarted_gram", sql.with_pairs("w4", "select i, j, sum(x * y) as dot, count(*) as n from q group by i, j"))
def stream_restarted_gram(s, d):
    """Half of the rows, a stop, the other half: the second run goes on from the first one's checkpoint."""
    from tallgram.operators.matrix import ROW_FORM

    m, folder = workloads.matrix(s, d, "w4"), _folder(s)
    norms = column_norms(m)
    for half in (0, 1):
        m.where(F.pmod("row_id", F.lit(2)) == half).write.mode("append").parquet(f"{folder}/rows")
        rows = s.readStream.schema(ROW_FORM).parquet(f"{folder}/rows")
        incremental.start_incremental_gram(rows, norms, 1e9, 7, f"{folder}/gram", f"{folder}/checkpoint").awaitTermination()
    return incremental.current_gram(s, f"{folder}/gram")
