"""Streaming queries, run over what the files hold."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.plans.base import query
from blockflow.operators import alias as A
from blockflow.operators import reuse
from blockflow.plans import graph_sql as G
from blockflow.sources import carriers
from blockflow.sources.tables import table
from blockflow.session import materialize
from blockflow.streaming.jobs import drained, drained_batches, events, file_stream


@query("stream_tumbling", "select event_type, cast(date_trunc('hour', ts) as timestamp) as start_ts, count(*) as n from events where ts is not null group by 1, 2")
def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    s = events(spark, d).where("ts is not null").groupBy("event_type", F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return drained(s.select("event_type", F.col("window.start").alias("start_ts"), "n"), "complete").withColumn("start_ts", F.col("start_ts").cast("timestamp_ntz"))


@query("stream_sliding", "select cast(time_bucket(interval 15 minute, ts) - k * interval 15 minute as timestamp) as start_ts, count(*) as n from events, (select unnest(range(4)) as k) where ts is not null group by 1")
def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    s = events(spark, d).where("ts is not null").groupBy(F.window("ts", "1 hour", "15 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return drained(s.select(F.col("window.start").alias("start_ts"), "n"), "complete").withColumn("start_ts", F.col("start_ts").cast("timestamp_ntz"))


@query("stream_exact_dedup", "select distinct event_id from events where ts is not null")
def stream_exact_dedup(spark: SparkSession, d: str) -> DataFrame:
    s = events(spark, d).where("ts is not null").withWatermark("ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"])
    return drained(s.select("event_id"))


@query("stream_session", "with s as (select *, sum(n) over (partition by user_id order by ts, event_id) as s from (select user_id, event_id, ts, case when ts > lag(ts) over (partition by user_id order by ts, event_id) + interval 12 hour then 1 else 0 end as n from events where ts is not null and user_id is not null)) select user_id, min(ts) as start_ts, max(ts) + interval 12 hour as end_ts, count(*) as n from s group by user_id, s")
def stream_session(spark: SparkSession, d: str) -> DataFrame:
    """Sessions of a user, with those that are still open where the events end."""
    s = events(spark, d).where("ts is not null and user_id is not null").groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.count(F.lit(1)).alias("n"))
    out = drained(s.select("user_id", F.col("session_window.start").alias("start_ts"), F.col("session_window.end").alias("end_ts"), "n"), "complete")
    return out.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start_ts", "end_ts")})


@query("stream_interval_join", "select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and p.ts between c.ts and c.ts + interval 1 hour where c.event_type = 'click' and p.event_type = 'purchase'")
def stream_interval_join(spark: SparkSession, d: str) -> DataFrame:
    """Purchases within an hour after a click of the same user; watermarks bound the state of both sides."""
    # the files hold 30 days in any order, so both sides wait that long
    side = lambda kind, x: events(spark, d).where((F.col("event_type") == kind) & F.col("user_id").isNotNull() & F.col("ts").isNotNull()).select(F.col("user_id").alias(f"user_{x}"), F.col("event_id").alias(f"id_{x}"), F.col("ts").alias(f"ts_{x}")).withWatermark(f"ts_{x}", "31 days")
    joined = side("click", "c").join(side("purchase", "p"), F.expr("user_c = user_p and ts_p >= ts_c and ts_p <= ts_c + interval 1 hour"))
    return drained(joined.select(F.col("id_c").alias("click_id"), F.col("id_p").alias("purchase_id")))


@query("stream_alias", "select n_nationkey, c_custkey from (select c_custkey, c_nationkey from customer) join (select n_nationkey, lower(n_name) as k from nation) on c_nationkey = n_nationkey")
def stream_alias(spark: SparkSession, d: str) -> DataFrame:
    """Records of a stream that name their nation in another spelling, resolved against the static names."""
    names = table(spark, d, "nation", "n_nationkey", "n_name").withColumn("k", A.clean(F.col("n_name")))
    spelled = names.select(F.col("n_nationkey").alias("c_nationkey"), F.concat(F.lit("The "), F.upper("n_name")).alias("spelling"))
    stream = file_stream(spark, d, "customer").join(spelled, "c_nationkey").withColumn("k", A.clean(F.col("spelling")))
    return drained(stream.join(names, "k").select("n_nationkey", "c_custkey"))


_HEADS = f"with {G.DOC_BLOCKS}, {G.FLOW}, {G.function_pairs()}"


@query("stream_near_dup", f"{_HEADS} select n.id, min(o.id) as lib_id from hd n join hd o on o.head = n.head where n.sample_id % 2 = 1 and o.sample_id % 2 = 0 group by 1")
def stream_near_dup(spark: SparkSession, d: str) -> DataFrame:
    """Functions of odd documents, as a stream, that have a twin in the static index of the even ones; batch by batch."""
    even = materialize(reuse.function_frame(carriers.documents(spark, d).where("sample_id % 2 = 0")), "index")
    index = materialize(even.groupBy("vec_digest").agg(F.min("id").alias("lib_id")), "index")

    def found(batch: DataFrame) -> DataFrame:
        vectors = materialize(reuse.function_frame(carriers.lines_of(batch.select("doc_id", "source", "text"))), "batch")
        return vectors.join(index, "vec_digest").select("id", "lib_id")

    return drained_batches(file_stream(spark, d, "documents").where("doc_id % 2 = 1"), found, "id long, lib_id long")


@query("stream_representatives", f"with {G.LINES} select md5(line) as func_digest, min(sample_id * 10000000 + func_id) as id, count(*) as n from lines group by 1")
def stream_representatives(spark: SparkSession, d: str) -> DataFrame:
    """The stateful form: for each line the one with the smallest id so far, and how many there were."""
    lines = carriers.document_lines(file_stream(spark, d, "documents").select("doc_id", "source", "text")).select(F.md5("line").alias("func_digest"), reuse.function_id().alias("id"))
    return drained(lines.groupBy("func_digest").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("n")), "complete")
