"""The operators, sources and functions around the methods, one query each."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockflow.plans.base import query
from blockflow.functions import sql as functions
from blockflow.functions.taxonomy import class_sql
from blockflow.session import removed_at_exit, shared_dir
from blockflow.sources.tables import table


@query("filter_analysable", "select doc_id, lang from documents where lang in ('en', 'de') and n_chars between 100 and 5000 and text is not null")
def filter_analysable(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents", "doc_id", "lang", "n_chars", "text").where(F.col("lang").isin("en", "de") & F.col("n_chars").between(100, 5000) & F.col("text").isNotNull()).select("doc_id", "lang")


@query("scan_parquet", "select l_returnflag, count(*) as n, cast(sum(cast(l_quantity as bigint)) as bigint) as quantity from lineitem where l_shipdate >= timestamp '1998-01-01' group by 1")
def scan_parquet(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem", "l_returnflag", "l_quantity", "l_shipdate").where(F.col("l_shipdate") >= F.lit("1998-01-01").cast("timestamp_ntz"))
    return li.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


def _round_trip(df: DataFrame, kind: str, **options) -> DataFrame:
    path = removed_at_exit(df.sparkSession, f"{shared_dir(df.sparkSession)}/scan-{kind}-{uuid.uuid4().hex}")
    df.write.format(kind).options(**options).save(path)
    return df.sparkSession.read.schema(df.schema).format(kind).options(**options).load(path)


@query("scan_json", "select n_nationkey, n_name from nation")
def scan_json(spark: SparkSession, d: str) -> DataFrame:
    return _round_trip(table(spark, d, "nation", "n_nationkey", "n_name"), "json")


@query("scan_csv", "select s_suppkey, s_name from supplier")
def scan_csv(spark: SparkSession, d: str) -> DataFrame:
    return _round_trip(table(spark, d, "supplier", "s_suppkey", "s_name"), "csv", header="true")


@query("join_labels", "select lang, count(*) as n, cast(sum(toxic) as bigint) as toxic from documents join labels using (doc_id) group by 1")
def join_labels(spark: SparkSession, d: str) -> DataFrame:
    j = table(spark, d, "documents", "doc_id", "lang").join(table(spark, d, "labels", "doc_id", "toxic"), "doc_id")
    return j.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum("toxic").alias("toxic"))


@query("join_full_truth", "select count(a) as predicted, count(b) as true_pairs, count(case when a is not null and b is not null then 1 end) as tp from (select doc_id as a from labels where quality = 1) full join (select doc_id as b from labels where toxic = 0) on a = b")
def join_full_truth(spark: SparkSession, d: str) -> DataFrame:
    labels = table(spark, d, "labels")
    a, b = labels.where("quality = 1").select(F.col("doc_id").alias("a")), labels.where("toxic = 0").select(F.col("doc_id").alias("b"))
    return a.join(b, F.col("a") == F.col("b"), "full").agg(F.count("a").alias("predicted"), F.count("b").alias("true_pairs"), F.count(F.when(F.col("a").isNotNull() & F.col("b").isNotNull(), 1)).alias("tp"))


@query("semi_major_groups", "select count(*) as n from orders where o_custkey in (select o_custkey from orders group by 1 having count(*) >= 12)")
def semi_major_groups(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders", "o_custkey")
    return o.join(o.groupBy("o_custkey").count().where("count >= 12"), "o_custkey", "left_semi").agg(F.count(F.lit(1)).alias("n"))


@query("anti_removed", "select doc_id from documents where doc_id not in (select doc_id from labels where doc_id is not null)")
def anti_removed(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents", "doc_id").join(table(spark, d, "labels", "doc_id"), "doc_id", "left_anti")


@query("range_join_grid", "select a.p_partkey as a, b.p_partkey as b from part a join part b on a.p_partkey < b.p_partkey and a.p_brand = b.p_brand and abs(a.p_retailprice - b.p_retailprice) <= 1.0")
def range_join_grid(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "part", "p_partkey", "p_brand", "p_retailprice").withColumn("cell", F.floor("p_retailprice"))
    r = p.select(F.col("p_partkey").alias("b"), "p_brand", F.col("p_retailprice").alias("pb"), F.explode(F.array(F.col("cell") - 1, "cell", F.col("cell") + 1)).alias("cell"))
    return p.join(r, ["p_brand", "cell"]).where((F.col("p_partkey") < F.col("b")) & (F.abs(F.col("p_retailprice") - F.col("pb")) <= 1.0)).select(F.col("p_partkey").alias("a"), "b")


@query("interval_sessions", "with s as (select *, sum(n) over (partition by user_id order by ts, event_id) as s from (select user_id, event_id, ts, case when ts > lag(ts) over (partition by user_id order by ts, event_id) + interval 12 hour then 1 else 0 end as n from events where user_id is not null)) select user_id, cast(s as int) as session, count(*) as n, min(ts) as start_ts, max(ts) as end_ts from s group by 1, 2")
def interval_sessions(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events", "user_id", "event_id", "ts").where("user_id is not null")
    e = e.withColumn("new", F.expr("case when ts > lag(ts) over (partition by user_id order by ts, event_id) + interval 12 hours then 1 else 0 end")).withColumn("session", F.expr("cast(sum(new) over (partition by user_id order by ts, event_id) as int)"))
    return e.groupBy("user_id", "session").agg(F.count(F.lit(1)).alias("n"), F.min("ts").alias("start_ts"), F.max("ts").alias("end_ts"))


@query("asof_kb_version", "select o_orderkey, v.version from orders asof left join (select unnest([timestamp '1996-01-01', timestamp '1998-01-01', timestamp '2000-01-01']) as since, unnest([1, 2, 3]) as version) v on o_orderdate >= v.since")
def asof_kb_version(spark: SparkSession, d: str) -> DataFrame:
    """The knowledge base version in force at each order's date: union, then the last version in time order by customer."""
    o = table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    versions = spark.sql("select * from values (timestamp_ntz '1996-01-01', 1), (timestamp_ntz '1998-01-01', 2), (timestamp_ntz '2000-01-01', 3) as t(since, version)")
    marks = o.select("o_custkey").distinct().crossJoin(F.broadcast(versions)).select("o_custkey", F.col("since").alias("at"), "version", F.lit(None).cast("long").alias("o_orderkey"))
    both = marks.union(o.select("o_custkey", F.col("o_orderdate").alias("at"), F.lit(None).cast("int").alias("version"), "o_orderkey"))
    w = Window.partitionBy("o_custkey").orderBy("at", F.col("o_orderkey").asc_nulls_first())
    return both.withColumn("version", F.last("version", True).over(w)).where("o_orderkey is not null").select("o_orderkey", "version")


@query("rollup_source_lang", "select source, lang, count(*) as n from documents group by rollup (source, lang)")
def rollup_source_lang(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents", "source", "lang").rollup("source", "lang").agg(F.count(F.lit(1)).alias("n"))


@query("cube_nation_year", "select c_nationkey, year(o_orderdate) as year, count(*) as n from orders join customer on o_custkey = c_custkey group by cube (c_nationkey, year(o_orderdate))")
def cube_nation_year(spark: SparkSession, d: str) -> DataFrame:
    j = table(spark, d, "orders", "o_custkey", "o_orderdate").join(table(spark, d, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).select("c_nationkey", F.year("o_orderdate").cast("long").alias("year"))
    return j.cube("c_nationkey", "year").agg(F.count(F.lit(1)).alias("n"))


@query("approx_groups")
def approx_groups(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem", "l_suppkey", "l_partkey").agg(F.approx_count_distinct("l_suppkey").alias("suppliers"), F.approx_count_distinct("l_partkey").alias("parts"))


@query("window_moving_month", "with m as (select date_trunc('month', o_orderdate) as month, count(*) as n from orders group by 1) select cast(month as date) as month, n, cast(sum(n) over (order by month rows between 2 preceding and current row) as bigint) as moving from m")
def window_moving_month(spark: SparkSession, d: str) -> DataFrame:
    m = table(spark, d, "orders", "o_orderdate").groupBy(F.date_trunc("month", "o_orderdate").cast("date").alias("month")).agg(F.count(F.lit(1)).alias("n"))
    return m.withColumn("moving", F.sum("n").over(Window.orderBy("month").rowsBetween(-2, 0)))


@query("topk_neighbours", "select a.o_custkey, a.o_orderkey from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as r from orders) a where r <= 3")
def topk_neighbours(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders", "o_custkey", "o_orderkey", "o_totalprice").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@query("top_clusters", "select md5(text) as digest, count(*) as n from documents group by 1 order by n desc, digest limit 10")
def top_clusters(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents", "text").groupBy(F.md5("text").alias("digest")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "digest").limit(10)


@query("set_union", "select c_nationkey as k from customer union select s_nationkey from supplier")
def set_union(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).union(table(spark, d, "supplier").select("s_nationkey")).distinct()


@query("set_intersect", "select c_nationkey as k from customer intersect select s_nationkey from supplier")
def set_intersect(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(spark, d, "supplier").select("s_nationkey"))


@query("set_except", "select c_custkey as k from customer except select o_custkey from orders")
def set_except(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select(F.col("c_custkey").alias("k")).subtract(table(spark, d, "orders").select("o_custkey"))


@query("json_props", "select event_type, cast(json_extract_string(props, '$.k') as bigint) as k, count(*) as n from events group by 1, 2")
def json_props(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events", "event_type", "props").groupBy("event_type", F.from_json("props", "k long")["k"].alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("unpivot_labels", "select doc_id, 'quality' as name, quality as value from labels union all select doc_id, 'toxic', toxic from labels")
def unpivot_labels(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "labels", "doc_id", "quality", "toxic").unpivot("doc_id", ["quality", "toxic"], "name", "value")


@query("scan_text", "select n_name as value from nation")
def scan_text(spark: SparkSession, d: str) -> DataFrame:
    return _round_trip(table(spark, d, "nation", "n_name").withColumnRenamed("n_name", "value"), "text")


@query("sink_partitioned", "select n_regionkey, count(*) as n from nation where n_regionkey in (1, 2) group by 1")
def sink_partitioned(spark: SparkSession, d: str) -> DataFrame:
    """Written by group, read with the other groups' folders pruned."""
    path = removed_at_exit(spark, f"{shared_dir(spark)}/sink-{uuid.uuid4().hex}")
    table(spark, d, "nation").write.partitionBy("n_regionkey").parquet(path)
    return spark.read.parquet(path).where("n_regionkey in (1, 2)").groupBy("n_regionkey").agg(F.count(F.lit(1)).alias("n"))


@query("window_running_f1", "with j as (select lang, doc_id, n_chars, quality from documents join labels using (doc_id)), p as (select lang, count(*) filter (where quality = 1) as p from j group by 1), r as (select lang, doc_id, row_number() over w as k, sum(quality) over (partition by lang order by n_chars desc, doc_id rows unbounded preceding) as tp from j window w as (partition by lang order by n_chars desc, doc_id)) select lang, doc_id, cast(k as int) as place, cast(tp as bigint) as tp, round(2 * tp / nullif(k + p, 0), 6) as f1 from r join p using (lang)")
def window_running_f1(spark: SparkSession, d: str) -> DataFrame:
    """Documents by length as a score for quality: F1 at every cut, language by language."""
    j = table(spark, d, "documents", "doc_id", "lang", "n_chars").join(table(spark, d, "labels", "doc_id", "quality"), "doc_id")
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    made = j.withColumn("place", F.row_number().over(w)).withColumn("tp", F.sum("quality").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    p = j.groupBy("lang").agg(F.sum("quality").alias("p"))
    return made.join(p, "lang").select("lang", "doc_id", "place", "tp", F.round(F.try_divide(2 * F.col("tp"), F.col("place") + F.col("p")), 6).alias("f1"))


@query("window_lineage_lag", "select o_orderkey, cast(cast(o_orderdate as date) - lag(cast(o_orderdate as date)) over (partition by o_custkey order by o_orderdate, o_orderkey) as int) as days from orders")
def window_lineage_lag(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    o = table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    return o.select("o_orderkey", F.datediff("o_orderdate", F.lag("o_orderdate").over(w)).alias("days"))


@query("sql_functions", f"""select p_partkey, round(case when p_size = 0 then 0 else least(1.0, (p_size * 1.0 + 2.0) / (sqrt(p_size * p_size + 4) * sqrt(2))) end, 6) as cosine, round(exp(-5 * power(p_size / 10.0 - 1, 2)), 6) as gauss,
    round(case when p_size = 0 then 0 else least(1.0, (p_size * 1.0 + 2.0) / (sqrt(p_size * p_size + 4) * sqrt(2))) end * exp(-5 * power(p_size / 10.0 - 1, 2)), 6) as hybrid,
    round(100 * (1 - levenshtein(p_name, p_brand) / greatest(length(p_name), length(p_brand))), 6) as edit,
    round(100 * (1 - levenshtein(array_to_string(list_sort(string_split(p_name, ' ')), ' '), array_to_string(list_sort(string_split(p_type, ' ')), ' ')) / greatest(length(p_name), length(p_type))), 6) as token_sort,
    cast({class_sql('p_brand', duck=True)} as int) as class, array_to_string(list_filter(string_split(trim(regexp_replace(lower(p_brand), '[^a-z0-9]+', ' ', 'g')), ' '), lambda w: w not in ('the', 'group', 'team', '')), ' ') as cleaned,
    (select round(-sum(n / t * log2(n / t)), 6) from (select ch, count(*) as n, sum(count(*)) over () as t from (select unnest(string_split(p_name, '')) as ch) group by 1)) as entropy from part""")
def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    """All bf_ functions in one statement."""
    functions.register(spark)
    table(spark, d, "part").createOrReplaceTempView("bf_part")
    return spark.sql("""select p_partkey, round(bf_cosine(array(double(p_size), 2d), array(1d, 1d)), 6) as cosine, round(bf_gauss(array(p_size / 10d), array(1d), 5d), 6) as gauss,
        round(bf_hybrid(array(double(p_size), 2d), array(1d, 1d), array(p_size / 10d), array(1d), 5d), 6) as hybrid, bf_edit_ratio(p_name, p_brand) as edit, bf_token_sort_ratio(p_name, p_type) as token_sort,
        bf_class_of(p_brand) as class, bf_clean_alias(p_brand) as cleaned, round(bf_entropy(p_name), 6) as entropy from bf_part""")


@query("udtf_blocks", "with b as (select item_id, list_filter(list_transform(string_split(text, chr(10)), lambda x: trim(x)), lambda x: x <> '') as l from benchmark), c as (select item_id, i - 1 as func_id, list_filter(list_transform(string_split_regex(l[i], '[.!?,;]+'), lambda x: trim(x)), lambda x: x <> '') as p from (select *, unnest(range(1, len(l) + 1)) as i from b)) select item_id, cast(func_id as int) as func_id, cast(j - 1 as int) as block_id, cast(len(list_filter(string_split_regex(p[j], '\\s+'), lambda x: x <> '')) as int) as n from (select *, unnest(range(1, len(p) + 1)) as j from c)")
def udtf_blocks(spark: SparkSession, d: str) -> DataFrame:
    functions.register(spark)
    table(spark, d, "benchmark").createOrReplaceTempView("bf_benchmark")
    return spark.sql("select item_id, b.func_id, b.block_id, b.n from bf_benchmark, lateral blocks_of(text) b")


@query("udf_normal_form", "select s_suppkey, s_name as name from supplier")
def udf_normal_form(spark: SparkSession, d: str) -> DataFrame:
    """Names in compatibility form; a wide letter, put in front, becomes the plain one and is cut off again."""
    made = table(spark, d, "supplier", "s_suppkey", "s_name").withColumn("name", functions.normal_form(F.concat(F.lit("\uff21"), "s_name")))
    return made.where(F.substring("name", 1, 1) == "A").select("s_suppkey", F.expr("substring(name, 2)").alias("name"))


@query("intervals_by_lang")
def intervals_by_lang(spark: SparkSession, d: str) -> DataFrame:
    j = table(spark, d, "documents", "doc_id", "lang").join(table(spark, d, "labels"), "doc_id")
    return functions.exact_intervals(j, "lang", "quality = 1 and toxic = 0")
