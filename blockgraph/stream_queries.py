"""Streaming queries, each against its SQL over the whole table, and the SQL
surface of vector search (table and scalar functions)."""

from __future__ import annotations

from pyspark.sql import functions as F

from .functions import features
from .operators import exact, index, search
from .streaming import changes
from .vector_queries import BIG, DEFAULT, EMB, R_SMALL, one_segment, sql_knn

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        Q[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


SNAPSHOT = """n as (select count(*) as n from embeddings),
c as (select event_id % n.n as vec_id, event_type, row_number() over (partition by event_id % n.n order by ts desc, event_id desc) as r from events, n where event_type in ('error', 'purchase'))"""


@query(f"with {SNAPSHOT} select vec_id, case when event_type = 'error' then 'delete' else 'upsert' end as op from c where r = 1")
def changes_batch_twin(spark, sf_dir):
    """Newest change of each vector, from a drained stream."""
    got = changes.result(changes.from_events(changes.event_stream(spark, sf_dir), features.emb_f32(spark, sf_dir)), "append")
    return changes.newest(got).select("vec_id", "op")


@query("select time_bucket(interval 1 hour, ts) as start, event_type, count(*) as n from events group by 1, 2")
def tumbling(spark, sf_dir):
    s = changes.event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return changes.result(s).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("select start, count(*) as n from (select ts, unnest([time_bucket(interval 1 hour, ts), time_bucket(interval 1 hour, ts) - interval 1 hour]) as start from events) group by 1")
def sliding(spark, sf_dir):
    s = changes.event_stream(spark, sf_dir).groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return changes.result(s).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("""with m as (select user_id, ts, case when ts - lag(ts) over w < interval 6 hour then 0 else 1 end as new from events window w as (partition by user_id order by ts)),
s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from m)
select user_id, min(ts) as start, count(*) as n from s group by user_id, k""")
def session_windows(spark, sf_dir):
    s = changes.event_stream(spark, sf_dir).groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return changes.result(s).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


@query("select distinct user_id, event_type from events")
def dedupe_watermark(spark, sf_dir):
    """First event of each user and type, by state kept within the watermark."""
    s = changes.event_stream(spark, sf_dir).select("ts", "user_id", "event_type").withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return changes.result(s, "append").select("user_id", "event_type")


def _snapshot_sql(events: str) -> str:
    return f"""with {SNAPSHOT.replace("('error', 'purchase')", events)}, v as ({EMB}),
b as (select vec_id, vec from v where vec_id not in (select vec_id from c) union all select vec_id, list_transform(vec, lambda x: x * 0.5) from v where vec_id in (select vec_id from c where r = 1 and event_type = 'purchase')),
d as (select q.vec_id as query_id, b.vec_id, round(list_distance(b.vec, q.vec), 6) + 0.0 as dist from b, v q where q.vec_id % 100 = 0)
select query_id, rank, vec_id, dist from (select *, row_number() over (partition by query_id order by dist, vec_id) as rank from d) where rank <= 10"""


def _snapshot(spark, sf_dir, keep):
    v = features.emb_f32(spark, sf_dir)
    dyn = changes.DynamicIndex(spark, v, DEFAULT)
    changes.drain(changes.from_events(changes.event_stream(spark, sf_dir).where(keep), v), dyn.commit)
    got = dyn.search(exact.sample_queries(v), index.Ask(10, options=search.Options(cand_size=BIG)))
    return got.withColumn("rank", F.col("rank").cast("long"))


@query(_snapshot_sql("('error', 'purchase')"))
def snapshot_search(spark, sf_dir):
    """The ten nearest in the static index and the streamed changes together."""
    return _snapshot(spark, sf_dir, F.lit(True))


@query(_snapshot_sql("('error')"))
def snapshot_search_deletes(spark, sf_dir):
    """Deletes only: what goes is made up for by what comes next."""
    return _snapshot(spark, sf_dir, F.col("event_type") == "error")


@query(sql_knn(EMB))
def streamed_queries_sat(spark, sf_dir):
    """Queries that arrive as a stream, on a static index."""
    schema = spark.read.parquet(f"{sf_dir}/embeddings.parquet").schema
    s = spark.readStream.schema(schema).option("pathGlobFilter", "embeddings.parquet").parquet(sf_dir)
    q = s.where("vec_id % 100 = 0").select(F.col("vec_id").alias("query_id"), F.col("embedding").cast("array<double>").alias("qvec"))
    got = changes.answer_stream(q, one_segment(spark, sf_dir, DEFAULT), 1, index.Ask(10, options=search.Options(cand_size=BIG)))
    return got.withColumn("rank", F.col("rank").cast("long"))


KNN_SQL = f"with v as ({EMB}), d as (select q.vec_id as query_id, b.vec_id, round(list_distance(b.vec, q.vec), 6) + 0.0 as dist from v q, v b where q.vec_id % 100 = 0)"


def _sql(spark, sf_dir, text: str):
    """The answer to a statement over the vectors; the view goes once it is analysed."""
    from .functions import sql_functions

    sql_functions.register(spark, one_segment(spark, sf_dir, DEFAULT))
    features.emb_f32(spark, sf_dir).createOrReplaceTempView("vectors_for_sql")
    out = spark.sql(text)
    spark.catalog.dropTempView("vectors_for_sql")
    return out


@query(f"{KNN_SQL} select query_id, vec_id, dist from (select *, row_number() over (partition by query_id order by dist, vec_id) as r from d) where r <= 5")
def sql_vector_search(spark, sf_dir):
    return _sql(spark, sf_dir, f"select q.vec_id as query_id, h.vec_id, h.dist from vectors_for_sql q, lateral vector_search(q.vec, 5, {BIG}) h where q.vec_id % 100 = 0")


@query(f"{KNN_SQL} select query_id, vec_id, dist from d where dist <= {R_SMALL}")
def sql_vector_range(spark, sf_dir):
    return _sql(spark, sf_dir, f"select q.vec_id as query_id, h.vec_id, h.dist from vectors_for_sql q, lateral vector_range(q.vec, double({R_SMALL}), 20, double(0)) h where q.vec_id % 100 = 0")


@query(f"with v as ({EMB}) select a.vec_id, round(list_distance(a.vec, b.vec), 6) + 0.0 as dist, round(-list_inner_product(a.vec, b.vec), 6) + 0.0 as ip from v a, v b where b.vec_id = 0")
def sql_l2(spark, sf_dir):
    return _sql(spark, sf_dir, "select a.vec_id, round(l2(a.vec, b.vec), 6) + 0.0d as dist, round(neg_ip(a.vec, b.vec), 6) + 0.0d as ip from vectors_for_sql a join (select vec from vectors_for_sql where vec_id = 0) b")
