"""Flow vectors, propagation, deduplication, function clusters and reuse on the carriers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.config import FUNCTION_TAU, SAMPLE_TAU, FeatureConfig
from blockflow.operators import dedup, features, flowvec, reuse, similarity
from blockflow.operators import statistics as S
from blockflow.plans import graph_sql as G
from blockflow.plans.base import query
from blockflow.plans.corpus import indices_sql
from blockflow.session import materialize
from blockflow.sources import carriers
from blockflow.sources.tables import table

CFG = FeatureConfig()

def _flow(func: DataFrame) -> DataFrame:
    flat = [F.get("cls", F.lit(k)).alias(f"w{k + 1}") for k in range(9)]
    return flowvec.build(func).select("sample_id", "func_id", "grp", "n_blocks", "n_edges", "omega", "xn", "yn", "zn", *flat)


@query("flow_vectors_docs", f"with {G.DOC_BLOCKS}, {G.FLOW} {G.FLOW_SELECT}")
def flow_vectors_docs(spark: SparkSession, d: str) -> DataFrame:
    return _flow(carriers.documents(spark, d))


@query("flow_vectors_orders", f"with {G.ORDER_BLOCKS}, {G.FLOW} {G.FLOW_SELECT}")
def flow_vectors_orders(spark: SparkSession, d: str) -> DataFrame:
    return _flow(carriers.orders(spark, d))


@query("flow_vectors_turns", f"with {G.TURN_BLOCKS}, {G.FLOW} {G.FLOW_SELECT}")
def flow_vectors_turns(spark: SparkSession, d: str) -> DataFrame:
    return _flow(carriers.turns(spark, d))


@query("flow_vectors_pages", f"with {G.PAGE_BLOCKS}, {G.FLOW} {G.FLOW_SELECT}")
def flow_vectors_pages(spark: SparkSession, d: str) -> DataFrame:
    return _flow(carriers.page_sections(spark, d))


@query("flow_vectors_sessions", f"with {G.SESSION_BLOCKS}, {G.FLOW} {G.FLOW_SELECT}")
def flow_vectors_sessions(spark: SparkSession, d: str) -> DataFrame:
    return _flow(carriers.sessions(spark, d))


@query("extraction_report", f"with {G.LINES} select count(x) as n_ok, count(*) - count(x) as n_failed from (select doc_id from documents) left join (select distinct sample_id as x from lines where len(list_filter(string_split_regex(line, '[.!?,;]+'), lambda x: trim(x) <> '')) > 0) on doc_id = x")
def extraction_report(spark: SparkSession, d: str) -> DataFrame:
    vectors = flowvec.build(carriers.documents(spark, d))
    return flowvec.extraction_report(table(spark, d, "documents", "doc_id").withColumnRenamed("doc_id", "sample_id"), vectors)


@query("extraction_rate", f"with {G.LINES} select lang, round(avg(case when x is not null then 1.0 else 0.0 end), 6) as rate from documents left join (select distinct sample_id as x from lines where len(list_filter(string_split_regex(line, '[.!?,;]+'), lambda x: trim(x) <> '')) > 0) on doc_id = x group by lang")
def extraction_rate(spark: SparkSession, d: str) -> DataFrame:
    got = flowvec.build(carriers.documents(spark, d)).select(F.col("sample_id").alias("doc_id")).distinct().withColumn("ok", F.lit(1.0))
    return table(spark, d, "documents", "doc_id", "lang").join(got, "doc_id", "left").groupBy("lang").agg(F.round(F.avg(F.coalesce("ok", F.lit(0.0))), 6).alias("rate"))


_HOPS = " union all ".join(f"select sample_id, func_id, {k} as hop, " + ", ".join(f"round({c}, 9) as {c}" for c in G.NUM) + f" from h{k}" for k in range(3))


def _hops(func: DataFrame, calls: DataFrame) -> DataFrame:
    cfg = FeatureConfig(rounds=2)
    nodes = features.propagate(features.initial(flowvec.build(func), cfg), calls, cfg)
    flat = [F.round(F.get("shape", F.lit(k)), 9).alias(c) for k, c in enumerate(("x", "y"))] + [F.round(F.get("cls", F.lit(k)), 9).alias(w) for k, w in enumerate(G.WS)]
    return nodes.select("sample_id", "func_id", "hop", *flat)


@query("propagated_docs", f"with {G.DOC_BLOCKS}, {G.FLOW}, {G.DOC_CALLS}, {G.HOP0}, {G.hop(1)}, {G.hop(2)} {_HOPS}")
def propagated_docs(spark: SparkSession, d: str) -> DataFrame:
    return _hops(carriers.documents(spark, d), carriers.document_calls(table(spark, d, "documents", "doc_id", "text")))


@query("propagated_orders", f"with {G.ORDER_BLOCKS}, {G.FLOW}, {G.ORDER_CALLS}, {G.HOP0}, {G.hop(1)}, {G.hop(2)} {_HOPS}")
def propagated_orders(spark: SparkSession, d: str) -> DataFrame:
    return _hops(carriers.orders(spark, d), carriers.order_calls(spark, d))


def doc_flows(spark: SparkSession, d: str) -> DataFrame:
    """The flow vectors of all lines, written once for all that needs them."""
    return materialize(flowvec.build(carriers.documents(spark, d)), "flows")


def doc_vectors(spark: SparkSession, d: str, cfg: FeatureConfig = CFG, flows: DataFrame | None = None) -> DataFrame:
    flows = doc_flows(spark, d) if flows is None else flows
    frame = dedup.sample_frame_of(flows, carriers.document_calls(table(spark, d, "documents", "doc_id", "text")), cfg)
    return materialize(frame, "sample-vectors")


_SAMPLES = f"with recursive {G.DOC_BLOCKS}, {G.FLOW}"


@query("dedup_pairs", f"{_SAMPLES}, {G.sample_pairs(G.DOC_CALLS)} select a as id_a, b as id_b, round(s_cls, 6) as s_cls, round(s_shape, 6) as s_shape, round(s, 6) as s from sp")
def dedup_pairs(spark: SparkSession, d: str) -> DataFrame:
    return dedup.pairs_of(doc_vectors(spark, d))[0].select("id_a", "id_b", *[F.round(c, 6).alias(c) for c in ("s_cls", "s_shape", "s")])


def _doc_roots(spark: SparkSession, d: str, flows: DataFrame | None = None) -> DataFrame:
    return dedup.roots_of(*dedup.pairs_of(doc_vectors(spark, d, flows=flows)))


@query("dedup_clusters", f"{_SAMPLES}, {G.sample_roots(G.DOC_CALLS)} select id, root from rt")
def dedup_clusters(spark: SparkSession, d: str) -> DataFrame:
    return _doc_roots(spark, d)


@query("dedup_clusters_within_source", f"{_SAMPLES}, {G.scoped_roots(G.DOC_CALLS, 'select doc_id as id, source as grp from documents')} select id, root from rg")
def dedup_clusters_within_source(spark: SparkSession, d: str) -> DataFrame:
    return dedup.within_groups(*dedup.pairs_of(doc_vectors(spark, d)), table(spark, d, "documents", "doc_id", "source").toDF("id", "grp"))


def _doc_kept(spark: SparkSession, d: str, flows: DataFrame | None = None) -> DataFrame:
    order = table(spark, d, "documents", "doc_id", "text").select(F.col("doc_id").alias("id"), F.col("doc_id").alias("first_seen"), F.md5("text").alias("digest"))
    return dedup.keep_representatives(_doc_roots(spark, d, flows), order)


_KEPT_SQL = f"{_SAMPLES}, {G.sample_roots(G.DOC_CALLS)}, {G.KEPT}"


@query("dedup_kept", f"{_KEPT_SQL} select id, root, kept from od")
def dedup_kept(spark: SparkSession, d: str) -> DataFrame:
    return _doc_kept(spark, d)


@query("dedup_report", f"""{_KEPT_SQL}, j as (select doc_id, source, kept is null or kept as stays, kept from documents left join od on id = doc_id) select count(*) as n, count(*) filter (where stays) as n_kept, count(*) filter (where not stays) as n_removed,
    round(count(*) filter (where not stays) / count(kept), 6) as share_analysable, round(count(*) filter (where not stays) / count(*), 6) as share_corpus, count(distinct source) as groups_before, count(distinct case when stays then source end) as groups_after from j""")
def dedup_report(spark: SparkSession, d: str) -> DataFrame:
    return dedup.report(_doc_kept(spark, d), table(spark, d, "documents", "doc_id", "source").toDF("id", "grp"))


@query("dedup_customers", f"with recursive {G.ORDER_BLOCKS}, {G.FLOW}, {G.sample_roots(G.ORDER_CALLS)} select id, root from rt")
def dedup_customers(spark: SparkSession, d: str) -> DataFrame:
    v = materialize(dedup.sample_frame(carriers.orders(spark, d), carriers.order_calls(spark, d)), "sample-vectors")
    return dedup.roots_of(*dedup.pairs_of(v))


@query("diversity_after_dedup", f"{_KEPT_SQL}, gone as (select doc_id, source, lang from documents where doc_id not in (select id from od where not kept)) " + " union all ".join([indices_sql("documents", "source", "source_before"), indices_sql("gone", "source", "source_after"), indices_sql("documents", "lang", "lang_before"), indices_sql("gone", "lang", "lang_after")]))
def diversity_after_dedup(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents", "doc_id", "source", "lang")
    left = materialize(docs.join(_doc_kept(spark, d).where("not kept"), docs["doc_id"] == F.col("id"), "left_anti"), "left")
    return S.compare({"source_before": (docs, "source"), "source_after": (left, "source"), "lang_before": (docs, "lang"), "lang_after": (left, "lang")})


@query("incremental_dedup", f"{_SAMPLES}, {G.sample_roots(G.DOC_CALLS)} select id, root from rt")
def incremental_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Documents arrive in ten batches by doc_id; the roots in the end are those of one run."""
    v = doc_vectors(spark, d)
    index, roots = v.where("false").select("id", "shape", "cls", "vec_digest"), v.where("false").select("id", F.col("id").alias("root"))
    axes = similarity.axes_of(v, SAMPLE_TAU, CFG.gamma)
    for k in range(10):
        index, roots = dedup.increment(v.where(F.pmod("id", F.lit(10)) == k), index, roots, CFG, axes=axes)
    return roots


def line_vectors(spark: SparkSession, d: str, min_blocks: int = 3) -> DataFrame:
    return materialize(reuse.function_frame(carriers.documents(spark, d), min_blocks=min_blocks), "function-vectors")


@query("function_pairs", f"with {G.DOC_BLOCKS}, {G.FLOW}, {G.function_pairs()} select a as id_a, b as id_b, round(s, 6) as s from pp")
def function_pairs(spark: SparkSession, d: str) -> DataFrame:
    heads, _ = similarity.collapse(line_vectors(spark, d))
    return similarity.grid_pairs(materialize(heads, "heads"), FUNCTION_TAU).select("id_a", "id_b", F.round("s", 6).alias("s"))


def line_members(spark: SparkSession, d: str, min_blocks: int = 3, flows: DataFrame | None = None) -> DataFrame:
    """Members of the clusters of non-trivial lines; flows: the flow vectors of all lines, where they are known."""
    if flows is None:
        v = line_vectors(spark, d, min_blocks)
    else:
        v = materialize(reuse.as_functions(flows.where(F.col("n_blocks") >= min_blocks)), "function-vectors")
    return materialize(reuse.placed(v, reuse.cluster_functions(v)), "members")


def order_members(spark: SparkSession, d: str) -> DataFrame:
    v = materialize(reuse.function_frame(carriers.orders(spark, d), unique_ids=True), "function-vectors")
    return materialize(reuse.placed(v, reuse.cluster_functions(v)), "members")


_FUNCTIONS = f"with recursive {G.DOC_BLOCKS}, {G.FLOW}, {G.members()}"
_ORDERS = f"with recursive {G.ORDER_BLOCKS}, {G.FLOW}, {G.members(unique_ids=True)}"


@query("function_clusters", f"{_FUNCTIONS} select id, root from members")
def function_clusters(spark: SparkSession, d: str) -> DataFrame:
    return line_members(spark, d).select("id", "root")


@query("function_clusters_orders", f"{_ORDERS} select id, root from members")
def function_clusters_orders(spark: SparkSession, d: str) -> DataFrame:
    return order_members(spark, d).select("id", "root")


_CLUSTERS = "select root as cluster_id, count(*) as size, count(distinct sample_id) as n_samples, count(distinct grp) as n_groups from members group by 1"


@query("reuse_clusters", f"{_FUNCTIONS} {_CLUSTERS} having count(distinct grp) >= 2")
def reuse_clusters(spark: SparkSession, d: str) -> DataFrame:
    return reuse.clusters(line_members(spark, d))


@query("reuse_exact", f"with {G.LINES} select md5(line) as func_digest, count(*) as size, count(distinct sample_id) as n_samples, count(distinct grp) as n_groups from lines where len(list_filter(string_split_regex(line, '[.!?,;]+'), lambda x: trim(x) <> '')) >= 3 group by 1 having count(distinct grp) >= 2")
def reuse_exact(spark: SparkSession, d: str) -> DataFrame:
    lines = flowvec.drop_trivial(carriers.documents(spark, d))
    return reuse.clusters(lines.withColumn("root", F.col("func_digest"))).withColumnRenamed("cluster_id", "func_digest")


_SHARES = """n as (select root as cluster_id, grp, count(*) as n from members group by 1, 2), d as (select cluster_id, cast(sum(n) as bigint) as size, count(*) as n_groups, string_agg(concat(grp, '=', n), ',' order by grp) as by_group, arg_max(grp, (n, grp)) as top_group,
    round(1 - sum(n * n) / (sum(n) * sum(n)), 6) as impurity, round(ln(sum(n)) - sum(n * ln(n)) / sum(n), 6) as entropy from n group by 1 having count(*) >= 2)"""


@query("reuse_distribution", f"{_FUNCTIONS}, {_SHARES} select * from d")
def reuse_distribution(spark: SparkSession, d: str) -> DataFrame:
    dist = reuse.distribution(line_members(spark, d)).where("n_groups >= 2")
    return dist.withColumn("by_group", F.expr("array_join(transform(map_entries(by_group), e -> concat(e.key, '=', e.value)), ',')"))


@query("reuse_distribution_orders", f"{_ORDERS}, {_SHARES} select * exclude (by_group) from d")
def reuse_distribution_orders(spark: SparkSession, d: str) -> DataFrame:
    return reuse.distribution(order_members(spark, d)).where("n_groups >= 2").drop("by_group")


@query("reuse_representatives", f"""{_FUNCTIONS}, rp as (select root as cluster_id, min(id) as id from members group by 1), el as (select sample_id, func_id, string_agg(concat(src, '-', dst), ',' order by src, dst) as flow from edges group by 1, 2)
    select cluster_id, m.id, m.sample_id, m.grp, concat(m.sample_id, ':', m.func_id) as address, md5(line) as func_digest, cast(n_blocks as int) as n_blocks, cast(n_edges as int) as n_edges, coalesce(flow, '') as flow, concat(n_blocks, ' blocks, ', n_edges, ' edges, ', omega, ' edge mass') as summary
    from rp join members m on m.id = rp.id join lines l on l.sample_id = m.sample_id and l.func_id = m.func_id join v on v.sample_id = m.sample_id and v.func_id = m.func_id left join el on el.sample_id = m.sample_id and el.func_id = m.func_id""")
def reuse_representatives(spark: SparkSession, d: str) -> DataFrame:
    func = carriers.documents(spark, d).withColumn("id", reuse.function_id())
    return reuse.representative(line_members(spark, d), func)


@query("reuse_sizes", f"{_FUNCTIONS} select size, count(*) as n_clusters from ({_CLUSTERS}) where size >= 2 group by 1")
def reuse_sizes(spark: SparkSession, d: str) -> DataFrame:
    return reuse.size_histogram(line_members(spark, d))


@query("reuse_inter_intra", f"{_FUNCTIONS} select case when n_groups >= 2 then 'inter' else 'intra' end as kind, count(*) as n_clusters, cast(sum(size) as bigint) as n_functions from ({_CLUSTERS}) where size >= 2 group by 1")
def reuse_inter_intra(spark: SparkSession, d: str) -> DataFrame:
    return reuse.inter_intra(line_members(spark, d))


@query("group_network", f"{_FUNCTIONS}, g as (select distinct root, grp from members), z as (select grp, count(*) as n from g group by 1), sh as (select a.grp as grp_a, b.grp as grp_b, count(*) as shared from g a join g b using (root) where a.grp < b.grp group by 1, 2) select grp_a, grp_b, shared, round(shared / (x.n + y.n - shared), 6) as jaccard from sh join z x on x.grp = grp_a join z y on y.grp = grp_b")
def group_network(spark: SparkSession, d: str) -> DataFrame:
    return reuse.group_network(line_members(spark, d))


@query("reuse_lineage", f"""{_ORDERS}, sn as (select root, grp, min(cast(o_orderdate as date)) as seen from members join orders on o_orderkey = id group by 1, 2),
    w as (select *, first_value(grp) over o as first_grp, first_value(seen) over o as first_seen, row_number() over o as place, lag(seen) over o as prev from sn window o as (partition by root order by seen, grp))
    select root as cluster_id, grp, first_grp, cast(seen - first_seen as int) as lag_days, cast(seen - prev as int) as after_previous, cast(place as int) as place from w""")
def reuse_lineage(spark: SparkSession, d: str) -> DataFrame:
    times = table(spark, d, "orders", "o_orderkey", "o_orderdate").select(F.col("o_orderkey").alias("id"), F.to_date("o_orderdate").alias("first_seen"))
    return reuse.lineage(order_members(spark, d), times)


@query("fingerprint_lookup", f"""with {G.DOC_BLOCKS}, {G.FLOW}, {G.function_pairs(2)}, lib as (select u.* from u), {G.renamed(G.PASSAGE_BLOCKS, '2')},
    {G.renamed(G.FLOW, '2')}, {G.renamed(G.function_pairs(2), '2')},
    hit as (select n.id, b.id as lib_id, least(1, {' + '.join(f'n.{w} * b.{w}' for w in G.WS)}) as c, exp(-5 * ((n.x - b.x) * (n.x - b.x) + (n.y - b.y) * (n.y - b.y))) as g from un2 n join lib b on b.x between n.x - 0.0142 and n.x + 0.0142 and b.y between n.y - 0.0142 and n.y + 0.0142)
    select id, lib_id, round(c * g, 6) as s from hit where round(round(c, 10) * round(g, 10), 10) >= 0.999""")
def fingerprint_lookup(spark: SparkSession, d: str) -> DataFrame:
    """Functions of the benchmark's passages against the library of distinct line vectors."""
    passages = carriers.lines_of(table(spark, d, "benchmark", "item_id", "text").select(F.col("item_id").alias("doc_id"), F.lit("benchmark").alias("source"), "text"))
    new = reuse.function_frame(passages, min_blocks=2)
    library, _ = similarity.collapse(line_vectors(spark, d, 2))
    return reuse.lookup(new, library).select("id", "lib_id", F.round("s", 6).alias("s"))


def _other_members(func: DataFrame, min_blocks: int = 3) -> DataFrame:
    v = materialize(reuse.function_frame(func, min_blocks=min_blocks), "function-vectors")
    return reuse.placed(v, reuse.cluster_functions(v))


@query("reuse_pages", f"with recursive {G.PAGE_BLOCKS}, {G.FLOW}, {G.members()} {_CLUSTERS} having count(distinct grp) >= 2")
def reuse_pages(spark: SparkSession, d: str) -> DataFrame:
    return reuse.clusters(_other_members(carriers.page_sections(spark, d)))


@query("reuse_turns", f"with recursive {G.TURN_BLOCKS}, {G.FLOW}, {G.members(1)} {_CLUSTERS} having count(distinct sample_id) >= 2")
def reuse_turns(spark: SparkSession, d: str) -> DataFrame:
    """Turns that several conversations share; these are short, so single blocks count."""
    return reuse.clusters(_other_members(carriers.turns(spark, d), 1), "samples")


_LOSS = ", ".join(f"{G.members(k, tag=f'_{k}')}, q{k} as (select {k} as min_blocks, count(*) as n_clusters, cast(coalesce(sum(size), 0) as bigint) as n_functions from (select count(*) as size from members_{k} group by root having count(distinct grp) >= 2))" for k in (1, 2, 3, 4))


@query("trivial_filter_loss", f"with recursive {G.DOC_BLOCKS}, {G.FLOW}, {_LOSS} select q.*, round(1 - q.n_clusters / nullif(q1.n_clusters, 0), 6) as lost from (select * from q1 union all select * from q2 union all select * from q3 union all select * from q4) q, q1")
def trivial_filter_loss(spark: SparkSession, d: str) -> DataFrame:
    """Reuse clusters by the least number of blocks, and the share lost against keeping every function."""
    flows = materialize(flowvec.build(carriers.documents(spark, d)), "flows")
    out = None
    for k in (1, 2, 3, 4):
        v = materialize(reuse.as_functions(flows.where(F.col("n_blocks") >= k), CFG), "function-vectors")
        row = reuse.clusters(reuse.placed(v, reuse.cluster_functions(v))).agg(F.count(F.lit(1)).alias("n_clusters"), F.coalesce(F.sum("size"), F.lit(0)).alias("n_functions")).select(F.lit(k).alias("min_blocks"), "*")
        out = row if out is None else out.union(row)
    out = materialize(out, "loss")
    base = out.where("min_blocks = 1").select(F.col("n_clusters").alias("b"))
    return out.crossJoin(F.broadcast(base)).select("min_blocks", "n_clusters", "n_functions", F.round(1 - F.try_divide("n_clusters", "b"), 6).alias("lost"))


def _embedded(spark: SparkSession, d: str) -> DataFrame:
    """Embeddings with planted near copies of every tenth."""
    e = table(spark, d, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("cls"))
    near = e.where("id % 10 = 0").select((F.col("id") + 1_000_000).alias("id"), F.transform("cls", lambda x, i: F.when(i == 0, x + F.lit(0.001)).otherwise(x)).alias("cls"))
    return e.union(near).select("id", F.expr("cast(array() as array<double>)").alias("shape"), "cls", F.md5(F.to_json("cls")).alias("vec_digest"))


_EMBEDDED = """ev as (select vec_id as id, list_transform(embedding, lambda x: cast(x as double)) as c from embeddings), ee as (select * from ev union all select id + 1000000, list_concat([c[1] + 0.001], c[2:]) from ev where id % 10 = 0),
    pr as (select a.id as a, b.id as b, round(least(1, list_dot_product(a.c, b.c) / (sqrt(list_dot_product(a.c, a.c)) * sqrt(list_dot_product(b.c, b.c)))), 10) as s from ee a join ee b on a.id < b.id), pp as (select * from pr where s >= 0.999)"""


@query("ann_neighbours", f"with {_EMBEDDED} select a as id_a, b as id_b, round(s, 6) as s from pp")
def ann_neighbours(spark: SparkSession, d: str) -> DataFrame:
    v = materialize(_embedded(spark, d), "vectors")
    return similarity.ann_pairs(v, 0.999).select("id_a", "id_b", F.round("s", 6).alias("s"))


@query("search_and_prune", f"with recursive {_EMBEDDED}, {G.reach('pp')} select ee.id, coalesce(root, ee.id) as root from ee left join roots on node = ee.id")
def search_and_prune(spark: SparkSession, d: str) -> DataFrame:
    return similarity.search_and_prune(_embedded(spark, d), 0.999, metric="cls", backend="ann")


@query("candidate_cost")
def candidate_cost(spark: SparkSession, d: str) -> DataFrame:
    """Pairs that exist, that the grid proposes and that pass, over distinct line vectors."""
    heads = materialize(similarity.collapse(line_vectors(spark, d))[0], "heads")
    n = heads.agg(F.count(F.lit(1)).alias("n_vectors"))
    c = similarity.grid(heads, FUNCTION_TAU).agg(F.count(F.lit(1)).alias("candidates"))
    p = similarity.grid_pairs(heads, FUNCTION_TAU).agg(F.count(F.lit(1)).alias("accepted"))
    every = F.expr("n_vectors * (n_vectors - 1) div 2")
    return n.crossJoin(c).crossJoin(p).select("n_vectors", every.alias("possible"), "candidates", "accepted", F.round(1 - F.try_divide(F.col("candidates"), every), 9).alias("reduction"))


@query("exact_hash_pairs", "select md5(text) as digest, min(doc_id) as doc_id, count(*) as copies, cast(count(*) * (count(*) - 1) // 2 as bigint) as pairs from documents where text is not null group by 1 having count(*) > 1")
def exact_hash_pairs(spark: SparkSession, d: str) -> DataFrame:
    g = table(spark, d, "documents", "doc_id", "text").where("text is not null").groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies"))
    return g.where("copies > 1").withColumn("pairs", F.expr("copies * (copies - 1) div 2"))
