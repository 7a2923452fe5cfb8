"""Cleaning, labels, diversity, profiles, audits and sampling on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.operators import cleaning as C
from blockflow.operators import statistics as S
from blockflow.plans.base import query
from blockflow.sources.tables import table

#: (corpus name, table SQL, column) of the comparison.
CORPORA = [
    ("documents_source", "documents", "source"), ("documents_lang", "documents", "lang"), ("conversations_role", "conversations", "role"),
    ("customer_nation", "customer", "c_nationkey"), ("customer_segment", "customer", "c_mktsegment"), ("part_brand", "part", "p_brand"),
    ("part_type", "part", "p_type"), ("events_type", "events", "event_type"), ("embeddings_label", "embeddings", "label"),
]


def indices_sql(source: str, column: str, name: str) -> str:
    return (
        f"select '{name}' as corpus, k, total, round(h, 6) as h, case when k > 1 then round(h / ln(k), 6) end as h_norm, round(sq / (total * total), 6) as hhi from ("
        f"select count(*) as k, cast(sum(n) as bigint) as total, ln(sum(n)) - sum(n * ln(n)) / sum(n) as h, cast(sum(n * n) as double) as sq from (select {column}, count(*) as n from {source} where {column} is not null group by 1))"
    )


HOST = "regexp_extract(url, '^[a-z]+://([^/]+)', 1)"


@query("diversity_corpora", " union all ".join([indices_sql(t, c, n) for n, t, c in CORPORA] + [indices_sql(f"(select {HOST} as host from pages)", "host", "pages_host")]))
def diversity_corpora(spark: SparkSession, d: str) -> DataFrame:
    named = {n: (table(spark, d, t, c), c) for n, t, c in CORPORA}
    named["pages_host"] = (table(spark, d, "pages", "url").select(F.expr(HOST).alias("host")), "host")
    return S.compare(named)


@query("external_validation", """select count(*) as claimed, cast(sum(case when n_chars = length(text) and text <> '' then 1 else 0 end) as bigint) as usable,
    (select count(*) from (select md5(text) from documents group by 1 having count(distinct source) > 1)) as conflicting from documents""")
def external_validation(spark: SparkSession, d: str) -> DataFrame:
    docs = C.integrity(table(spark, d, "documents")).withColumnRenamed("source", "grp")
    n = docs.agg(F.count(F.lit(1)).alias("claimed"), F.sum(F.col("reason").isNull().cast("int")).cast("long").alias("usable"))
    return n.crossJoin(F.broadcast(C.label_conflicts(docs).agg(F.count(F.lit(1)).alias("conflicting"))))


_DIGESTS = "(select md5(text) as digest, source as grp, count(*) as n from documents where text is not null group by 1, 2)"
_IMPURE = f"""(select digest, sum(n) as total, count(*) as n_labels, round(1 - sum(n * n) / (sum(n) * sum(n)), 6) as impurity, max(n) as most,
    case when sum(case when n = m then 1 else 0 end) = 1 then max(case when n = m then grp end) end as majority from (select *, max(n) over (partition by digest) as m from {_DIGESTS}) group by digest)"""


def _resolved_sql(cut: float) -> str:
    return f"""select digest, impurity, case when impurity <= {cut} and majority is not null then majority else 'unknown' end as resolved,
        case when n_labels = 1 then 'none' when impurity <= {cut} and majority is not null then 'majority' else 'unknown' end as action from {_IMPURE}"""


def _labelled(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents", "text", "source").where("text is not null").select(F.md5("text").alias("digest"), F.col("source").alias("grp"))


@query("label_conflicts", f"select digest, n_labels, cast(total as bigint) as n from {_IMPURE} where n_labels > 1")
def label_conflicts(spark: SparkSession, d: str) -> DataFrame:
    return C.label_conflicts(_labelled(spark, d))


@query("label_impurity", f"select digest, cast(total as bigint) as total, n_labels, impurity, majority, round(cast(most as double) / total, 6) as p_max from {_IMPURE}")
def label_impurity(spark: SparkSession, d: str) -> DataFrame:
    return C.label_impurity(_labelled(spark, d))


@query("label_resolution", _resolved_sql(0.2))
def label_resolution(spark: SparkSession, d: str) -> DataFrame:
    return C.resolve_labels(_labelled(spark, d))


@query("dispute_rate", f"select count(*) as n, cast(sum(case when action = 'majority' then 1 else 0 end) as bigint) as kept, cast(sum(case when action = 'unknown' then 1 else 0 end) as bigint) as unknown, round(avg(case when action <> 'none' then 1.0 else 0.0 end), 6) as rate from ({_resolved_sql(0.2)})")
def dispute_rate(spark: SparkSession, d: str) -> DataFrame:
    return C.dispute_rate(C.resolve_labels(_labelled(spark, d)))


CUTS = [0.0, 0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9]


@query("dispute_sweep", f"select cut, cast(sum(case when n_labels > 1 and impurity <= cut and majority is not null then 1 else 0 end) as bigint) as kept, cast(sum(case when n_labels > 1 and not (impurity <= cut and majority is not null) then 1 else 0 end) as bigint) as unknown from {_IMPURE}, (select unnest([{', '.join(f'cast({c} as double)' for c in CUTS)}]) as cut) group by cut")
def dispute_sweep(spark: SparkSession, d: str) -> DataFrame:
    i = C.label_impurity(_labelled(spark, d)).withColumn("cut", F.explode(F.array(*[F.lit(c) for c in CUTS])))
    keep = (F.col("impurity") <= F.col("cut")) & F.col("majority").isNotNull()
    disputed = F.col("n_labels") > 1
    return i.groupBy("cut").agg(F.sum((disputed & keep).cast("int")).cast("long").alias("kept"), F.sum((disputed & ~keep).cast("int")).cast("long").alias("unknown"))


_LETTERS = r"length(regexp_replace(text, '[^\p{L}]', '', 'g')) < 0.5 * length(text)"
_FUNNEL = f"""with i as (select *, md5(text) as digest from documents where text is not null and text <> '' and n_chars = length(text)),
    u as (select digest, min(doc_id) as doc_id from i group by digest), r as ({_resolved_sql(0.2)}),
    k as (select u.digest, u.doc_id from u join r using (digest) where r.action <> 'unknown'),
    a as (select k.digest from k join documents using (doc_id) where lang in ('en', 'de', 'fr') and not ({_LETTERS}))"""


@query("cleaning_funnel", _FUNNEL + """ select 1 as step, 'collected' as name, count(*) as n from documents union all select 2, 'intact', count(*) from i union all select 3, 'distinct', count(*) from u
    union all select 4, 'resolved', count(*) from k union all select 5, 'analysable', count(*) from a union all select 6, 'pages', count(*) from pages union all select 7, 'whole pages', count(*) from pages where html like '%</html>%'""")
def cleaning_funnel(spark: SparkSession, d: str) -> DataFrame:
    docs = C.integrity(table(spark, d, "documents")).withColumnRenamed("source", "grp")
    intact = docs.where("reason is null")
    unique = C.collapse_exact(intact.select("digest", "doc_id", "lang", "text"), "digest", "doc_id")
    labels = C.resolve_labels(docs.where("text is not null").select("digest", "grp"))
    resolved = unique.join(labels.where("action <> 'unknown'"), "digest", "left_semi")
    usable = C.analysable(resolved, ["en", "de", "fr"], "lang", C.packed_proxy(F.col("text")))
    pages = C.page_integrity(table(spark, d, "pages", "html"))
    steps = [("collected", docs), ("intact", intact), ("distinct", unique), ("resolved", resolved), ("analysable", usable), ("pages", pages), ("whole pages", pages.where("reason is null"))]
    out = None
    for k, (name, df) in enumerate(steps, 1):
        row = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(k).alias("step"), F.lit(name).alias("name"), "n")
        out = row if out is None else out.union(row)
    return out


@query("merged_sources", "select md5(text) as digest, array_to_string(list_sort(list(distinct source)), ',') as labels, count(*) as n_records from documents where text is not null group by 1")
def merged_sources(spark: SparkSession, d: str) -> DataFrame:
    docs = _labelled(spark, d)
    return C.merge_sources([docs.where("grp < 'src2'"), docs.where("grp >= 'src2'")], "digest", "grp").withColumn("labels", F.array_join("labels", ","))


@query("enriched_documents", "select d.doc_id, d.source, l.quality, l.toxic from documents d left join labels l using (doc_id)")
def enriched_documents(spark: SparkSession, d: str) -> DataFrame:
    return C.enrich(table(spark, d, "documents", "doc_id", "source"), table(spark, d, "labels", "doc_id", "quality", "toxic"), "doc_id")


@query("verification", """with t as (select doc_id, source, md5(text) as digest from documents where text is not null), g as (select digest, count(distinct source) as n from t group by 1),
    b as (select distinct d.doc_id from documents d join (select doc_id, unnest(string_split(text, chr(10))) as line from documents) x using (doc_id) join (select line from (select source, unnest(string_split(text, chr(10))) as line from documents) where line <> '' group by line having count(distinct source) > 1) s using (line))
    select t.doc_id, case when g.n > 1 then 'primary' when b.doc_id is not null then 'secondary' else 'none' end as tier from t join g using (digest) left join b on b.doc_id = t.doc_id""")
def verification(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents", "doc_id", "source", "text").where("text is not null")
    primary = docs.select(F.md5("text").alias("digest"), "source").groupBy("digest").agg(F.count_distinct("source").alias("n")).where("n > 1").select("digest", F.lit(1).alias("p"))
    lines = docs.select("doc_id", "source", F.explode(F.split("text", "\n")).alias("line")).where("line <> ''").select("doc_id", "source", F.xxhash64("line").alias("h"), F.md5("line").alias("line"))
    shared = lines.groupBy("line").agg(F.count_distinct("source").alias("n")).where("n > 1").select("line")
    second = lines.join(shared, "line", "left_semi").select("doc_id").distinct().withColumn("s", F.lit(1))
    tier = F.when(F.col("p") == 1, "primary").when(F.col("s") == 1, "secondary").otherwise("none")
    return docs.select("doc_id", F.md5("text").alias("digest")).join(primary, "digest", "left").join(second, "doc_id", "left").select("doc_id", tier.alias("tier"))


@query("content_profile", r"select lang, count(*) as n, round(avg(n_chars), 6) as mean_chars, median(n_chars) as median_chars, round(avg(case when length(regexp_replace(text, '[^\p{L}]', '', 'g')) < 0.5 * length(text) then 1.0 else 0.0 end), 6) as packed from documents group by lang")
def content_profile(spark: SparkSession, d: str) -> DataFrame:
    packed = F.avg(F.when(C.packed_proxy(F.col("text")), 1.0).otherwise(0.0))
    return table(spark, d, "documents", "lang", "text", "n_chars").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("n_chars"), 6).alias("mean_chars"), F.median("n_chars").alias("median_chars"), F.round(packed, 6).alias("packed"))


@query("page_profile", f"select {HOST} as host, count(*) as n, round(avg(length(html)), 6) as mean_chars, max(length(html)) as most_chars from pages group by 1")
def page_profile(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "pages", "url", "html").groupBy(F.expr(HOST).alias("host")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(F.length("html")), 6).alias("mean_chars"), F.max(F.length("html")).cast("long").alias("most_chars"))


@query("char_entropy", "select doc_id, round(entropy, 6) as entropy from (select doc_id, list_aggregate(string_split(text, ''), 'entropy') as entropy from documents where text <> '')")
def char_entropy(spark: SparkSession, d: str) -> DataFrame:
    chars = F.filter(F.split("text", ""), lambda c: c != "")
    sorted_ = table(spark, d, "documents", "doc_id", "text").where("text <> ''").withColumn("cf_c", F.array_sort(chars))
    ends = "filter(transform(cf_c, (c, i) -> if(i + 1 = size(cf_c) or cf_c[i + 1] <> c, i + 1, 0)), x -> x > 0)"
    runs = sorted_.withColumn("cf_e", F.expr(ends)).withColumn("cf_n", F.expr("transform(cf_e, (e, i) -> (e - if(i = 0, 0, cf_e[i - 1])) / cast(size(cf_c) as double))"))
    return runs.select("doc_id", F.expr("round(aggregate(cf_n, cast(0 as double), (a, p) -> a - p * log2(p)), 6)").alias("entropy"))


@query("temporal_groups", "with o as (select n_name as grp, year(o_orderdate) as year from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey), b as (select grp from o group by grp having count(*) >= 150) select grp, cast(year as int) as year, count(*) as n from o where grp in (select grp from b) group by 1, 2")
def temporal_groups(spark: SparkSession, d: str) -> DataFrame:
    o = _nation_years(spark, d)
    big = o.groupBy("grp").count().where("count >= 150")
    return o.join(big, "grp", "left_semi").groupBy("grp", "year").agg(F.count(F.lit(1)).alias("n"))


def _nation_years(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders", "o_custkey", "o_orderdate").join(table(spark, d, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return o.join(F.broadcast(table(spark, d, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("n_name").alias("grp"), F.year("o_orderdate").alias("year"), "o_orderdate")


YEARS = list(range(1995, 2002))


@query("temporal_pivot", "select n_name as grp, " + ", ".join(f"cast(sum(case when year(o_orderdate) = {y} then 1 else 0 end) as bigint) as y{y}" for y in YEARS) + " from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by 1")
def temporal_pivot(spark: SparkSession, d: str) -> DataFrame:
    p = _nation_years(spark, d).groupBy("grp").pivot("year", YEARS).count()
    return p.select("grp", *[F.coalesce(F.col(str(y)), F.lit(0)).alias(f"y{y}") for y in YEARS])


@query("peak_period", "with c as (select event_type as grp, cast(ts as date) as day, count(*) as n from events where ts is not null group by 1, 2) select grp, cast(min(day) as varchar) as first_day, cast(max(day) as varchar) as last_day, cast((select c2.day from c c2 where c2.grp = c.grp order by n desc, day limit 1) as varchar) as peak_day, max(n) as peak_n from c group by grp")
def peak_period(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "events", "event_type", "ts").where("ts is not null").groupBy(F.col("event_type").alias("grp"), F.to_date("ts").alias("day")).agg(F.count(F.lit(1)).alias("n"))
    best = F.max_by(F.struct("day", "n"), F.struct("n", -F.unix_date("day")))
    return c.groupBy("grp").agg(F.min("day").cast("string").alias("first_day"), F.max("day").cast("string").alias("last_day"), best.alias("b")).select("grp", "first_day", "last_day", F.col("b.day").cast("string").alias("peak_day"), F.col("b.n").alias("peak_n"))


FIELDS = ["doc_id", "text", "lang", "source", "n_chars"]


@query("fill_rate", " union all ".join(f"select '{f}' as field, round(avg(case when {f} is not null then 1.0 else 0.0 end), 6) as rate from documents" for f in FIELDS))
def fill_rate(spark: SparkSession, d: str) -> DataFrame:
    return S.fill_rate(table(spark, d, "documents"), FIELDS)


@query("coverage", "select count(o) as covered, count(*) as total, round(count(o) / count(*), 6) as rate from (select distinct c_custkey as k from customer) left join (select distinct o_custkey as o from orders) on k = o")
def coverage(spark: SparkSession, d: str) -> DataFrame:
    return S.coverage(table(spark, d, "orders", "o_custkey").withColumnRenamed("o_custkey", "k"), table(spark, d, "customer", "c_custkey").withColumnRenamed("c_custkey", "k"), "k")


@query("representativeness", " union all ".join([indices_sql("documents", "lang", "type"), indices_sql("documents", "source", "group"), indices_sql("(select year(o_orderdate) as y from orders)", "y", "time")]))
def representativeness(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents", "lang", "source")
    years = table(spark, d, "orders", "o_orderdate").select(F.year("o_orderdate").alias("y"))
    return S.compare({"type": (docs, "lang"), "group": (docs, "source"), "time": (years, "y")})


@query("temporal_consistency", "select count(*) as n, cast(sum(case when o_orderdate > l_shipdate then 1 else 0 end) as bigint) as violations, cast(min(l_shipdate) as date) as first_ship, cast(max(l_shipdate) as date) as last_ship from orders join lineitem on o_orderkey = l_orderkey")
def temporal_consistency(spark: SparkSession, d: str) -> DataFrame:
    j = table(spark, d, "orders", "o_orderkey", "o_orderdate").join(table(spark, d, "lineitem", "l_orderkey", "l_shipdate"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("o_orderdate") > F.col("l_shipdate")).cast("int")).cast("long").alias("violations"), F.to_date(F.min("l_shipdate")).alias("first_ship"), F.to_date(F.max("l_shipdate")).alias("last_ship"))


@query("source_agreement", f"select count(*) as n, cast(sum(case when impurity = 0 then 1 else 0 end) as bigint) as agreeing, round(avg(case when impurity = 0 then 1.0 else 0.0 end), 6) as rate from {_IMPURE}")
def source_agreement(spark: SparkSession, d: str) -> DataFrame:
    i = C.label_impurity(_labelled(spark, d))
    ok = F.when(F.col("impurity") == 0, 1).otherwise(0)
    return i.agg(F.count(F.lit(1)).alias("n"), F.sum(ok).cast("long").alias("agreeing"), F.round(F.avg(ok.cast("double")), 6).alias("rate"))


_VERDICT = "case when quality = 1 and toxic = 0 then 'correct' when quality = 1 and toxic = 1 then 'suspicious' when quality = 0 and toxic = 1 then 'incorrect' else 'unknown' end"


@query("audit_verdicts", f"select verdict, count(*) as n, round(count(*) / sum(count(*)) over (), 6) as share from (select {_VERDICT} as verdict from labels) group by verdict")
def audit_verdicts(spark: SparkSession, d: str) -> DataFrame:
    v = table(spark, d, "labels", "quality", "toxic").groupBy(F.expr(_VERDICT).alias("verdict")).agg(F.count(F.lit(1)).alias("n"))
    total = v.agg(F.sum("n").alias("t"))
    return v.crossJoin(F.broadcast(total)).select("verdict", "n", F.round(F.col("n") / F.col("t"), 6).alias("share"))


@query("exact_interval")
def exact_interval(spark: SparkSession, d: str) -> DataFrame:
    r = table(spark, d, "labels", "quality", "toxic").agg(F.count(F.lit(1)).alias("n"), F.sum(F.expr("case when quality = 1 and toxic = 0 then 1 else 0 end")).alias("strict"), F.sum(F.expr("case when quality = 1 then 1 else 0 end")).alias("usable")).first()
    rows = [("published strict", 1838, 1906), ("published usable", 1878, 1906), ("labels strict", r["strict"] or 0, r["n"]), ("labels usable", r["usable"] or 0, r["n"])]
    return spark.createDataFrame([(name, k, n, k / max(n, 1), *[round(x, 6) for x in S.exact_interval(k, n)]) for name, k, n in rows], "name string, k long, n long, share double, low double, high double")


_RATERS = f"""(select doc_id as item, 1 as rater, {_VERDICT} as verdict from labels union all
    select doc_id, r, case when substr(md5(concat(doc_id, ':', r)), 1, 2) < '10' then case {_VERDICT} when 'correct' then 'suspicious' when 'suspicious' then 'incorrect' when 'incorrect' then 'unknown' else 'correct' end else {_VERDICT} end from labels, (select unnest([2, 3]) as r))"""


def _raters(spark: SparkSession, d: str) -> DataFrame:
    labels = table(spark, d, "labels")
    first = labels.select(F.col("doc_id").alias("item"), F.lit(1).alias("rater"), F.expr(_VERDICT).alias("verdict"))
    other = labels.withColumn("rater", F.explode(F.array(F.lit(2), F.lit(3)))).withColumn("v", F.expr(_VERDICT))
    moved = F.when(F.col("v") == "correct", "suspicious").when(F.col("v") == "suspicious", "incorrect").when(F.col("v") == "incorrect", "unknown").otherwise("correct")
    shift = F.substring(F.md5(F.concat_ws(":", "doc_id", "rater")), 1, 2) < "10"
    return first.union(other.select(F.col("doc_id").alias("item"), "rater", F.when(shift, moved).otherwise(F.col("v")).alias("verdict")))


@query("kappa_fleiss", f"""with r as {_RATERS}, per as (select item, verdict, count(*) as n from r group by 1, 2), i as (select item, sum(n) as m, sum(n * n) as sq from per group by 1),
    a as (select count(*) as items, avg((sq - m) / (m * (m - 1))) as po, sum(m) as t from i), c as (select sum(n * n) as sq from (select verdict, sum(n) as n from per group by 1))
    select items, round(po, 6) as agreement, round(sq / (t * t), 6) as chance, round((po - sq / (t * t)) / (1 - sq / (t * t)), 6) as kappa from a, c""")
def kappa_fleiss(spark: SparkSession, d: str) -> DataFrame:
    return S.fleiss_kappa(_raters(spark, d))


@query("kappa_cohen", f"""with r as {_RATERS}, b as (select a.rater as ra, c.rater as rb, a.verdict as va, c.verdict as vb from r a join r c on a.item = c.item and a.rater < c.rater),
    n as (select ra, rb, count(*) as n, sum(case when va = vb then 1 else 0 end) as same from b group by 1, 2), x as (select ra, rb, va as v, count(*) as na from b group by 1, 2, 3), y as (select ra, rb, vb as v, count(*) as nb from b group by 1, 2, 3),
    e as (select ra, rb, sum(na * nb) as cr from x join y using (ra, rb, v) group by 1, 2)
    select ra, rb, n, round(same / n, 6) as agreement, round((same / n - cr / (n * n)) / (1 - cr / (n * n)), 6) as kappa from n join e using (ra, rb)""")
def kappa_cohen(spark: SparkSession, d: str) -> DataFrame:
    return S.cohen_kappa(_raters(spark, d))


@query("agreement", f"with r as {_RATERS} select count(*) as items, round(avg(case when k = 1 then 1.0 else 0.0 end), 6) as rate from (select item, count(distinct verdict) as k from r group by 1)")
def agreement(spark: SparkSession, d: str) -> DataFrame:
    k = _raters(spark, d).groupBy("item").agg(F.count_distinct("verdict").alias("k"))
    return k.agg(F.count(F.lit(1)).alias("items"), F.round(F.avg(F.when(F.col("k") == 1, 1.0).otherwise(0.0)), 6).alias("rate"))


_STRATA = {"customer_orders": ("orders", "o_custkey", "o_orderkey"), "documents_source": ("documents", "source", "doc_id"), "documents_lang": ("documents", "lang", "doc_id"), "part_type": ("part", "p_type", "p_partkey")}


@query("sampling_tiers", " union all ".join(f"select '{k}' as design, cast({g} as varchar) as grp, n, {S.TIER_SQL} as take from (select {g}, count(*) as n from {t} group by 1)" for k, (t, g, _) in _STRATA.items()))
def sampling_tiers(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name, (t, g, _) in _STRATA.items():
        row = S.tiers(table(spark, d, t, g), g).select(F.lit(name).alias("design"), F.col(g).cast("string").alias("grp"), "n", "take")
        out = row if out is None else out.union(row)
    return out


@query("sampling_draw", f"select source, doc_id from (select source, doc_id, row_number() over (partition by source order by md5(concat(cast(doc_id as varchar), '0')), doc_id) as r, count(*) over (partition by source) as n from documents) where r <= {S.TIER_SQL}")
def sampling_draw(spark: SparkSession, d: str) -> DataFrame:
    return S.tiered_sample(table(spark, d, "documents", "source", "doc_id"), "source", "doc_id")


_PERIOD = "case when year(o_orderdate) < 1997 then 1 when year(o_orderdate) < 2000 then 2 else 3 end"


@query("sampling_periods", f"select n_name as grp, {_PERIOD} as period, count(*) as n, cast(ceil(count(*) * 0.08) as bigint) as take from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by 1, 2")
def sampling_periods(spark: SparkSession, d: str) -> DataFrame:
    return _nation_years(spark, d).groupBy("grp", F.expr(_PERIOD).alias("period")).agg(F.count(F.lit(1)).alias("n")).withColumn("take", F.ceil(F.col("n") * F.lit(0.08)))


@query("sampling_neyman", """with s as (select source as grp, count(*) as size, round(stddev_pop(n_chars), 6) as sd from documents group by 1), q as (select *, round(size * sd / sum(size * sd) over () * 100, 9) as quota from s),
    b as (select *, floor(quota) as base from q), p as (select *, 100 - sum(base) over () as rest, row_number() over (order by round(quota - base, 9) desc, grp) as place from b) select grp, size, cast(base + case when place <= rest then 1 else 0 end as bigint) as take from p""")
def sampling_neyman(spark: SparkSession, d: str) -> DataFrame:
    s = table(spark, d, "documents", "source", "n_chars").groupBy(F.col("source").alias("grp")).agg(F.count(F.lit(1)).alias("size"), F.round(F.stddev_pop("n_chars"), 6).alias("sd"))
    return S.neyman(s, 100)


@query("stratified_estimate", """with s as (select lang, count(*) as taken, sum(quality) as ok from documents join labels using (doc_id) group by 1), z as (select lang, count(*) as size from documents group by 1),
    w as (select size, taken, ok, cast(size as double) / sum(size) over () as w, ok / taken as p from s join z using (lang)) select round(sum(w * p), 6) as estimate, round(sum(w * w * (1 - taken / size) * p * (1 - p) / greatest(taken - 1, 1)), 9) as variance from w""")
def stratified_estimate(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents", "doc_id", "lang")
    taken = docs.join(table(spark, d, "labels", "doc_id", "quality"), "doc_id").groupBy("lang").agg(F.count(F.lit(1)).alias("taken"), F.sum("quality").alias("right"))
    return S.stratified_estimate(docs.groupBy("lang").agg(F.count(F.lit(1)).alias("size")).join(taken, "lang"))
