"""Relational operators, functions and features around the vector methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import features
from .vector_queries import DOC_U8, R_SMALL  # noqa: F401

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        Q[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def money(c: str):
    return F.round(c, 4) + F.lit(0.0)


@query("select l_orderkey, l_linenumber::bigint as line, round(l_extendedprice * (1 - l_discount), 4) + 0.0 as revenue, l_quantity::bigint as quantity from lineitem where l_quantity > 45")
def op_project(spark, sf_dir):
    x = t(spark, sf_dir, "lineitem").where("l_quantity > 45")
    return x.select("l_orderkey", F.col("l_linenumber").cast("long").alias("line"), (F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4) + F.lit(0.0)).alias("revenue"), F.col("l_quantity").cast("long").alias("quantity"))


@query("select event_id, event_type from events where event_type in ('view', 'click') and user_id between 5 and 40 and props like '%1%' and not regexp_matches(props, '9') and event_type is distinct from 'view'")
def op_filter(spark, sf_dir):
    return t(spark, sf_dir, "events").where("event_type in ('view', 'click') and user_id between 5 and 40 and props like '%1%' and not props rlike '9' and not (event_type <=> 'view')").select("event_id", "event_type")


JOIN = "select n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey group by n_name"


def _join(spark, sf_dir, hint: str) -> DataFrame:
    c, n = t(spark, sf_dir, "customer"), t(spark, sf_dir, "nation")
    return c.join(n.hint(hint), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


@query(JOIN)
def op_join_broadcast(spark, sf_dir):
    """25 nations: a fixed size, safe to broadcast."""
    return _join(spark, sf_dir, "broadcast")


@query(JOIN)
def op_join_merge(spark, sf_dir):
    return _join(spark, sf_dir, "merge")


@query(JOIN)
def op_join_hash(spark, sf_dir):
    return _join(spark, sf_dir, "shuffle_hash")


@query("select s_suppkey, count(*) as n from supplier, region where s_acctbal > r_regionkey * 2000 group by 1")
def op_join_theta(spark, sf_dir):
    s, r = t(spark, sf_dir, "supplier"), t(spark, sf_dir, "region")
    return s.join(F.broadcast(r), s.s_acctbal > r.r_regionkey * 2000).groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("n"))


@query("select doc_id from documents where doc_id in (select doc_id from labels where toxic = 1)")
def op_semi(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id").join(t(spark, sf_dir, "labels").where("toxic = 1"), "doc_id", "left_semi")


@query("select doc_id from documents where doc_id not in (select doc_id from labels)")
def op_anti(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id").join(t(spark, sf_dir, "labels"), "doc_id", "left_anti")


@query("select d.doc_id, coalesce(l.quality, -1)::bigint as quality from documents d left join labels l using (doc_id)")
def op_left(spark, sf_dir):
    x = t(spark, sf_dir, "documents").join(t(spark, sf_dir, "labels"), "doc_id", "left")
    return x.select("doc_id", F.coalesce("quality", F.lit(-1)).cast("long").alias("quality"))


@query("select coalesce(a.k, b.k) as k, coalesce(a.n, 0) as events, coalesce(b.n, 0) as orders from (select user_id % 97 as k, count(*) as n from events group by 1) a full join (select o_custkey % 101 as k, count(*) as n from orders group by 1) b on a.k = b.k")
def op_full(spark, sf_dir):
    a = t(spark, sf_dir, "events").groupBy((F.col("user_id") % 97).alias("k")).agg(F.count(F.lit(1)).alias("events"))
    b = t(spark, sf_dir, "orders").groupBy((F.col("o_custkey") % 101).alias("k")).agg(F.count(F.lit(1)).alias("orders"))
    return a.join(b, "k", "full").select("k", F.coalesce("events", F.lit(0)).alias("events"), F.coalesce("orders", F.lit(0)).alias("orders"))


@query("select a.event_id, count(*) as n from events a join events b on b.user_id = a.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'click' group by 1")
def op_range_join(spark, sf_dir):
    """Events of a user in the hour behind each click: the hour is cut into
    buckets, so the range becomes an equality on two of them."""
    e = t(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    bucket = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / 3600)
    a = e.where("event_type = 'click'").select("event_id", "user_id", F.col("ts").alias("from"), F.explode(F.array(bucket("ts"), bucket("ts") + 1)).alias("b"))
    b = e.select("user_id", F.col("ts").alias("at"), bucket("ts").alias("b"))
    return a.join(b, ["user_id", "b"]).where("at > from and at <= from + interval 1 hour").groupBy("event_id").agg(F.count(F.lit(1)).alias("n"))


@query("select a.event_id, (select max(b.event_id) from events b where b.user_id = a.user_id and b.event_type = 'view' and b.ts = (select max(c.ts) from events c where c.user_id = a.user_id and c.event_type = 'view' and c.ts <= a.ts)) as last_view from events a where a.event_type = 'purchase'")
def op_asof(spark, sf_dir):
    """Last view of the user at each purchase: one sort, no pairing."""
    e = t(spark, sf_dir, "events").where("event_type in ('view', 'purchase')")
    view = F.when(F.col("event_type") == "view", F.col("event_id"))
    # at equal times views come first, and of several the largest id last
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("last_view", F.last(view, True).over(w)).where("event_type = 'purchase'").select("event_id", "last_view")


@query("select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 2) + 0.0 as quantity, round(avg(l_extendedprice), 4) + 0.0 as price, min(l_shipdate) as first, max(l_shipdate) as last, round(stddev(l_quantity), 6) + 0.0 as spread from lineitem group by 1, 2")
def op_agg(spark, sf_dir):
    x = t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus")
    return x.agg(F.count(F.lit(1)).alias("n"), (F.round(F.sum("l_quantity"), 2) + F.lit(0.0)).alias("quantity"), (F.round(F.avg("l_extendedprice"), 4) + F.lit(0.0)).alias("price"), F.min("l_shipdate").alias("first"), F.max("l_shipdate").alias("last"), (F.round(F.stddev("l_quantity"), 6) + F.lit(0.0)).alias("spread"))


@query("select event_type, count(distinct user_id) as users from events group by 1")
def op_distinct(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query()
def op_approx_distinct(spark, sf_dir):
    return t(spark, sf_dir, "events").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median"))


@query("select lang, source, count(*) as n from documents group by grouping sets ((lang), (source), ())")
def op_grouping_sets(spark, sf_dir):
    docs = t(spark, sf_dir, "documents").select("lang", "source")
    return docs.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count(F.lit(1)).alias("n"))


@query("select c_mktsegment, c_nationkey::bigint as nation, count(*) as n from customer group by cube (c_mktsegment, c_nationkey)")
def op_cube(spark, sf_dir):
    return t(spark, sf_dir, "customer").withColumn("nation", F.col("c_nationkey").cast("long")).cube("c_mktsegment", "nation").agg(F.count(F.lit(1)).alias("n"))


@query("select p_brand, p_type, count(*) as n from part group by rollup (p_brand, p_type)")
def op_rollup(spark, sf_dir):
    return t(spark, sf_dir, "part").rollup("p_brand", "p_type").agg(F.count(F.lit(1)).alias("n"))


@query("select user_id, count(*) filter (where event_type = 'view') as views, count(*) filter (where event_type = 'click') as clicks from events where event_type in ('view', 'click') group by 1")
def op_pivot(spark, sf_dir):
    x = t(spark, sf_dir, "events").where("event_type in ('view', 'click')").groupBy("user_id").pivot("event_type", ["view", "click"]).count()
    return x.select("user_id", F.coalesce("view", F.lit(0)).alias("views"), F.coalesce("click", F.lit(0)).alias("clicks"))


@query("select event_type, max_by(event_id, (value, event_id)) as top, min_by(event_id, (value, event_id)) as low, count(distinct user_id) as users from events group by 1")
def op_max_by(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("top"), F.min_by("event_id", F.struct("value", "event_id")).alias("low"), F.size(F.collect_set("user_id")).cast("long").alias("users"))


@query("select o_orderkey, row_number() over w as rn, rank() over w2 as rk, dense_rank() over w2 as dr, ntile(4) over w as nt from orders window w as (partition by o_custkey order by o_totalprice, o_orderkey), w2 as (partition by o_custkey order by o_orderpriority)")
def op_rank(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    w2 = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    long = lambda c: c.cast("long")
    return t(spark, sf_dir, "orders").select("o_orderkey", long(F.row_number().over(w)).alias("rn"), long(F.rank().over(w2)).alias("rk"), long(F.dense_rank().over(w2)).alias("dr"), long(F.ntile(4).over(w)).alias("nt"))


@query("select event_id, lag(event_id) over w as before, lead(event_id, 2) over w as behind, first_value(event_id) over w as first from events window w as (partition by user_id order by ts, event_id)")
def op_lag_lead(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("behind"), F.first("event_id").over(w).alias("first"))


@query("select o_orderkey, count(*) over (partition by o_custkey order by o_orderkey rows between 2 preceding and current row) as n, round(sum(o_totalprice) over (partition by o_custkey order by o_orderkey rows unbounded preceding), 4) + 0.0 as running, count(*) over (partition by o_custkey order by o_orderkey range between 1000 preceding and current row) as near from orders")
def op_frames(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    total = F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0))
    return t(spark, sf_dir, "orders").select("o_orderkey", F.count(F.lit(1)).over(w.rowsBetween(-2, 0)).alias("n"), (F.round(total, 4) + F.lit(0.0)).alias("running"), F.count(F.lit(1)).over(w.rangeBetween(-1000, 0)).alias("near"))


@query("select p_partkey, p_retailprice from part order by p_retailprice desc, p_partkey limit 20")
def op_topk(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").limit(20)


@query("select event_type, event_id, r from (select event_type, event_id, row_number() over (partition by event_type order by value desc, event_id) as r from events) where r <= 5")
def op_topk_per_group(spark, sf_dir):
    w = Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id")
    return t(spark, sf_dir, "events").select("event_type", "event_id", F.row_number().over(w).alias("r")).where("r <= 5").withColumn("r", F.col("r").cast("long"))


@query("select c_nationkey::bigint as k from customer union select s_nationkey::bigint from supplier")
def op_union(spark, sf_dir):
    k = lambda n, c: t(spark, sf_dir, n).select(F.col(c).cast("long").alias("k"))
    return k("customer", "c_nationkey").unionByName(k("supplier", "s_nationkey")).distinct()


@query("select doc_id from labels where quality = 1 intersect select doc_id from labels where toxic = 0")
def op_intersect(spark, sf_dir):
    x = t(spark, sf_dir, "labels")
    return x.where("quality = 1").select("doc_id").intersect(x.where("toxic = 0").select("doc_id"))


@query("select doc_id from documents except select doc_id from labels")
def op_except(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id").subtract(t(spark, sf_dir, "labels").select("doc_id"))


@query("select vec_id, label::bigint as label from embeddings where (vec_id * 2654435761) % 4294967296 < 858993459")
def op_sample(spark, sf_dir):
    from .functions.hashing import in_sample

    return t(spark, sf_dir, "embeddings").where(in_sample(F.col("vec_id"), 0.2)).select("vec_id", F.col("label").cast("long").alias("label"))


# --- functions ---------------------------------------------------------------


@query("""with v as (select vec_id, list_transform(embedding[1:8], lambda x: floor(x::double * 10)::bigint) as a from embeddings)
select vec_id, len(a)::bigint as n, list_sum(a)::bigint as total, list_max(a) as most, list_contains(a, 1) as has_one, coalesce(list_position(a, 0), 0)::bigint as at_zero, len(list_distinct(a))::bigint as kinds, array_to_string(list_sort(a), ',') as sorted, len(list_filter(a, lambda x: x > 0))::bigint as above from v""")
def fn_array(spark, sf_dir):
    a = F.transform(F.slice("embedding", 1, 8), lambda x: F.floor(x.cast("double") * 10))
    v = t(spark, sf_dir, "embeddings").select("vec_id", a.alias("a"))
    long = lambda c: c.cast("long")
    return v.select("vec_id", long(F.size("a")).alias("n"), F.aggregate("a", F.lit(0).cast("long"), lambda s, x: s + x).alias("total"), F.array_max("a").alias("most"), F.array_contains("a", 1).alias("has_one"), long(F.array_position("a", 0)).alias("at_zero"), long(F.size(F.array_distinct("a"))).alias("kinds"), F.array_join(F.transform(F.sort_array("a"), lambda x: x.cast("string")), ",").alias("sorted"), long(F.size(F.filter("a", lambda x: x > 0))).alias("above"))


@query("select user_id, list_sort(list(distinct event_type))[1] as first_type, count(*) filter (where event_type = 'view') as views from events group by 1")
def fn_map(spark, sf_dir):
    n = t(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.sort_array(F.map_keys("m"))[0].alias("first_type"), F.coalesce(F.try_element_at(F.transform_values("m", lambda k, x: x), F.lit("view")), F.lit(0)).alias("views"))


@query("select event_id, round(sqrt(abs(value)), 6) + 0.0 as root, floor(value)::bigint as low, ceil(value)::bigint as high, round(ln(abs(value) + 1), 6) + 0.0 as log, (event_id & 7) as bits, (event_id << 2) as shifted, greatest(user_id, 50) as big, least(user_id, 50) as small from events")
def fn_math(spark, sf_dir):
    v = F.col("value")
    return t(spark, sf_dir, "events").select("event_id", (F.round(F.sqrt(F.abs(v)), 6) + F.lit(0.0)).alias("root"), F.floor(v).alias("low"), F.ceil(v).alias("high"), (F.round(F.log(F.abs(v) + 1), 6) + F.lit(0.0)).alias("log"), F.col("event_id").bitwiseAND(F.lit(7)).alias("bits"), F.shiftleft("event_id", 2).alias("shifted"), F.greatest("user_id", F.lit(50)).alias("big"), F.least("user_id", F.lit(50)).alias("small"))


@query("select c_custkey, lower(c_name) as name, length(c_name) as n, substring(c_name, 3, 5) as part, replace(c_mktsegment, 'A', '*') as masked, upper(left(c_name, 2)) as head, split_part(c_name, '#', 2) as tail, regexp_extract(c_name, '([0-9]+)', 1) as digits, strpos(c_name, '#')::bigint as hash_at from customer")
def fn_string(spark, sf_dir):
    n = F.col("c_name")
    return t(spark, sf_dir, "customer").select("c_custkey", F.lower(n).alias("name"), F.length(n).cast("long").alias("n"), F.substring(n, 3, 5).alias("part"), F.replace("c_mktsegment", F.lit("A"), F.lit("*")).alias("masked"), F.upper(F.left(n, F.lit(2))).alias("head"), F.split_part(n, F.lit("#"), F.lit(2)).alias("tail"), F.regexp_extract(n, "([0-9]+)", 1).alias("digits"), F.instr(n, "#").cast("long").alias("hash_at"))


@query("select event_id, (props::json ->> 'k')::bigint as k from events")
def fn_json(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("select l_orderkey, l_linenumber::bigint as line, l_partkey, extract(year from l_shipdate)::bigint as y, extract(month from l_shipdate)::bigint as m, date_diff('day', timestamp '1995-01-01', l_shipdate)::bigint as days, date_trunc('month', l_shipdate)::date as month from lineitem")
def fn_date(spark, sf_dir):
    s = F.col("l_shipdate")
    return t(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_linenumber").cast("long").alias("line"), "l_partkey", F.year(s).cast("long").alias("y"), F.month(s).cast("long").alias("m"), F.datediff(s, F.lit("1995-01-01")).cast("long").alias("days"), F.trunc(s, "month").alias("month"))


@query("select event_id, case when value > 50 then 'high' when value > 10 then 'mid' else 'low' end as band, nullif(event_type, 'view') as other, coalesce(nullif(user_id, 3), -1) as who from events")
def fn_cond(spark, sf_dir):
    v = F.col("value")
    return t(spark, sf_dir, "events").select("event_id", F.when(v > 50, "high").when(v > 10, "mid").otherwise("low").alias("band"), F.nullif("event_type", F.lit("view")).alias("other"), F.coalesce(F.nullif("user_id", F.lit(3).cast("long")), F.lit(-1)).alias("who"))


@query("select user_id, type, count(*) as n from (select user_id, event_type as type from events) group by 1, 2")
def user_vectors(spark, sf_dir):
    """Vectors of event counts, unfolded to the counts they hold."""
    v = features.user_vec(spark, sf_dir)
    names = F.array(*map(F.lit, features.EVENT_TYPES))
    return v.select(F.col("vec_id").alias("user_id"), F.explode(F.arrays_zip(names.alias("type"), F.col("vec").alias("n"))).alias("x")).select("user_id", F.col("x.type").alias("type"), F.col("x.n").cast("long").alias("n")).where("n > 0")


@query(f"with v as ({DOC_U8}) select vec_id, list_sum(vec)::bigint as total, vec[5]::bigint as e, list_max(vec)::bigint as most from v")
def letter_histogram(spark, sf_dir):
    v = features.doc_u8(spark, sf_dir)
    return v.select("vec_id", F.aggregate("vec", F.lit(0.0), lambda s, x: s + x).cast("long").alias("total"), F.col("vec")[4].cast("long").alias("e"), F.array_max("vec").cast("long").alias("most"))


@query("select page_id, length(html) as n, length(regexp_replace(html, '<[^>]*>', '', 'g')) as bare from pages")
def page_lengths(spark, sf_dir):
    return t(spark, sf_dir, "pages").select("page_id", F.length("html").cast("long").alias("n"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("bare"))


@query("select conv_id, count(*) as turns, max(turn) as last_turn, sum(length(text))::bigint as chars, count(*) filter (where role = 'user') as by_user from conversations group by 1")
def conversation_stats(spark, sf_dir):
    return t(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.count(F.lit(1)).alias("turns"), F.max("turn").alias("last_turn"), F.sum(F.length("text")).alias("chars"), F.sum(F.when(F.col("role") == "user", 1).otherwise(0)).alias("by_user"))
