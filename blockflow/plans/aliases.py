"""Alias queries on variants of the names in `part`, `nation` and `region`, and on the hosts of `pages`.

Supplier names are left out: they differ in digits only, so nearly every pair of them would have to be scored.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.operators import alias as A
from blockflow.operators import statistics as S
from blockflow.plans.base import query
from blockflow.session import materialize, removed_at_exit, shared_dir
from blockflow.sources.tables import table

#: Variants of a two-word name, as SQL over `canonical`.
KINDS = {
    "upper": "upper(canonical)", "prefix": "concat('the ', canonical)", "suffix": "concat(canonical, ' group')", "hyphen": "replace(canonical, ' ', '-')",
    "swap": "case when instr(canonical, ' ') > 0 then concat(substr(canonical, instr(canonical, ' ') + 1), ' ', substr(canonical, 1, instr(canonical, ' ') - 1)) else canonical end", "doubled": "concat(substr(canonical, 1, 3), substr(canonical, 3))",
    "dropped": "concat(substr(canonical, 1, 2), substr(canonical, 4))", "accent": "replace(canonical, 'e', 'é')", "other": "concat('zq', reverse(canonical))",
}
_NAMES = "select p_name as canonical from part where instr(p_name, ' ') > 0 union select n_name from nation union select r_name from region"
_VARIANTS = " union ".join(f"select canonical as truth, '{k}' as kind, {e} as query from names" for k, e in KINDS.items())
_CLEAN = "array_to_string(list_filter(string_split(trim(regexp_replace(translate(lower({0}), 'áàâäéèêëíìîïóòôöúùûüñç', 'aaaaeeeeiiiioooouuuunc'), '[^a-z0-9]+', ' ', 'g')), ' '), lambda w: w not in ('the', 'group', 'team', '')), ' ')"


def _names(spark: SparkSession, d: str) -> DataFrame:
    parts = table(spark, d, "part", "p_name").where("instr(p_name, ' ') > 0")
    return parts.union(table(spark, d, "nation", "n_name")).union(table(spark, d, "region", "r_name")).select(F.col("p_name").alias("canonical")).distinct()


def _variants(spark: SparkSession, d: str) -> DataFrame:
    n = _names(spark, d)
    made = n.select(F.col("canonical").alias("truth"), F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), F.expr(e).alias("query")) for k, e in KINDS.items()])).alias("v"))
    return made.select("truth", "v.*").distinct()


@query("alias_cleaned", f"with names as ({_NAMES}), v as ({_VARIANTS}) select truth, kind, query, {_CLEAN.format('query')} as cleaned from v")
def alias_cleaned(spark: SparkSession, d: str) -> DataFrame:
    return _variants(spark, d).withColumn("cleaned", A.clean(F.col("query")))


_RATIO = "case when greatest(length({0}), length({1})) = 0 then 100.0 else round(100 * (1 - levenshtein({0}, {1}) / greatest(length({0}), length({1}))), 6) end"
_SORTED = "array_to_string(list_sort(string_split({0}, ' ')), ' ')"
_RESOLVED = f"""with names as ({_NAMES}), v as ({_VARIANTS}), q as (select distinct query, {_CLEAN.format('query')} as cq from v), k as (select canonical, {_CLEAN.format('canonical')} as ck from names),
    s as (select query, canonical, greatest({_RATIO.format('cq', 'ck')}, {_RATIO.format(_SORTED.format('cq'), _SORTED.format('ck'))}) as score from q join k on least(length(cq), length(ck)) * 100 >= 80 * greatest(length(cq), length(ck))),
    b as (select *, row_number() over (partition by query order by score desc, canonical) as r from s), f as (select q.query, b.canonical, coalesce(b.score, 0) as score from q left join b on q.query = b.query and b.r = 1),
    o as (select query, case when score >= 80 then canonical end as canonical, case when score >= 80 then score else 0.0 end as score, case when score >= 95 then 'accept' when score >= 80 then 'review' else 'reject' end as decision from f)"""


def _resolved(spark: SparkSession, d: str) -> DataFrame:
    return A.resolve(_variants(spark, d).select("query").distinct(), _names(spark, d))


@query("alias_resolve", _RESOLVED + " select * from o")
def alias_resolve(spark: SparkSession, d: str) -> DataFrame:
    return _resolved(spark, d)


@query("alias_bands", _RESOLVED + " select kind, decision, count(*) as n, cast(sum(case when canonical = truth then 1 else 0 end) as bigint) as right_name from v join o using (query) group by 1, 2")
def alias_bands(spark: SparkSession, d: str) -> DataFrame:
    j = _variants(spark, d).join(_resolved(spark, d), "query")
    return j.groupBy("kind", "decision").agg(F.count(F.lit(1)).alias("n"), F.sum(F.coalesce((F.col("canonical") == F.col("truth")).cast("int"), F.lit(0))).cast("long").alias("right_name"))


#: Host labels weigh 1, path words 0.6; the first page that uses an alias says when, and the host's own label is recommended.
_HOSTS = """(select entity, alias, max(weight) as weight, min(page_id) as first_use, bool_or(alias = string_split(entity, '.')[1]) as recommended from (
    select entity, unnest(string_split(host, '.')) as alias, 1.0 as weight, page_id from hp union all select entity, unnest(list_filter(string_split(path, '/'), lambda x: x <> '')), 0.6, page_id from hp) group by 1, 2)"""
_HP = "hp as (select page_id, host, path, array_to_string(list_slice(string_split(host, '.'), -3, -2), '.') as entity from (select page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host, regexp_extract(url, '^[a-z]+://[^/]+([^?#]*)', 1) as path from pages))"


def _hosts(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host"), F.regexp_extract("url", r"^[a-z]+://[^/]+([^?#]*)", 1).alias("path"))
    parts = F.split("host", r"\.")
    entity = F.array_join(F.slice(parts, F.greatest(F.size(parts) - 2, F.lit(1)), 2), ".")
    weigh = lambda words, w: F.transform(words, lambda x: F.struct(x.alias("alias"), F.lit(w).alias("weight")))
    words = F.concat(weigh(parts, 1.0), weigh(F.filter(F.split("path", "/"), lambda x: x != ""), 0.6))
    used = p.select(entity.alias("entity"), "page_id", F.inline(words))
    kb = used.groupBy("entity", "alias").agg(F.max("weight").alias("weight"), F.min("page_id").alias("first_use"))
    return kb.withColumn("recommended", F.col("alias") == F.split("entity", r"\.")[0])


def _jaccard_sql(kb: str, tag: str = "") -> str:
    """js{tag}: (a, b, jaccard, weighted) of entities of a relation that share an alias."""
    return f"""k{tag} as (select entity, alias, max(weight) as weight from {kb} group by 1, 2), n{tag} as (select entity, count(*) as n, sum(weight) as w from k{tag} group by 1), s{tag} as (select a.entity as a, b.entity as b, count(*) as c, sum(least(a.weight, b.weight)) as cw from k{tag} a join k{tag} b using (alias) where a.entity < b.entity group by 1, 2),
    js{tag} as (select a, b, round(c / (x.n + y.n - c), 6) as jaccard, round(cw / (x.w + y.w - cw), 6) as weighted from s{tag} join n{tag} x on x.entity = a join n{tag} y on y.entity = b)"""


def _merged_sql(rounds: int = 4, cut: float = 0.3) -> str:
    """ro: (entity, root) after so many rounds; the query fails where ten don't do, and more than enough rounds change nothing."""
    out = f"{_HP}, kb as materialized {_HOSTS}, ro0 as materialized (select distinct entity, entity as root from kb)"
    for r in range(1, rounds + 1):
        out += f", kb{r} as materialized (select root as entity, alias, weight from kb join ro{r - 1} using (entity)), {_jaccard_sql(f'kb{r}', str(r))}, l{r} as materialized (select a, b from js{r} where jaccard >= {cut}), e{r} as (select a, b from l{r} union select b, a from l{r}), rc{r}(node, root) as (select a, a from e{r} union select e.b, c.root from rc{r} c join e{r} e on e.a = c.node), st{r} as materialized (select node, min(root) as next from rc{r} group by 1), ro{r} as materialized (select entity, coalesce(next, root) as root from ro{r - 1} left join st{r} on node = root)"
    return out


_MERGED = f"with recursive {_merged_sql()}"


@query("alias_jaccard", f"with {_HP}, kb as {_HOSTS}, {_jaccard_sql('kb')} select * from js")
def alias_jaccard(spark: SparkSession, d: str) -> DataFrame:
    return A.set_jaccard(_hosts(spark, d))


@query("alias_merged", f"{_MERGED} select entity, root from ro4")
def alias_merged(spark: SparkSession, d: str) -> DataFrame:
    return A.merge(_hosts(spark, d), 0.3)


@query("alias_canonical", f"{_MERGED}, g as (select root, alias, round(sum(weight), 6) as w, count(*) as n, bool_or(recommended) as rec, min(first_use) as use from kb join ro4 using (entity) group by 1, 2) select root, alias as canonical from (select *, row_number() over (partition by root order by rec desc, w desc, n desc, use, alias) as p from g) where p = 1")
def alias_canonical(spark: SparkSession, d: str) -> DataFrame:
    kb = _hosts(spark, d)
    return A.pick_canonical(kb, A.merge(kb, 0.3))


@query("alias_collected", f"with {_HP}, kb as {_HOSTS}, c as (select {_CLEAN.format('entity')} as entity, {_CLEAN.format('alias')} as alias from kb) select entity, alias, count(*) as n from c where length(regexp_replace(alias, '[^a-z]', '', 'g')) >= 2 and alias <> entity group by 1, 2")
def alias_collected(spark: SparkSession, d: str) -> DataFrame:
    return A.collect(_hosts(spark, d).withColumn("source", F.lit("pages"))).select("entity", "alias", "n")


_SOURCED = _RESOLVED + ", acc as (select canonical, list_sort(list(distinct o.query)) as aliases, list_sort(list(distinct kind)) as sources from o join v using (query) where decision = 'accept' group by 1)"


def _kb(spark: SparkSession, d: str) -> DataFrame:
    return A.knowledge_base(_resolved(spark, d), _variants(spark, d).select("query", F.col("kind").alias("source")))


@query("kb_json", _SOURCED + " select canonical, array_to_string(aliases, '|') as aliases, array_to_string(sources, '|') as sources from acc")
def kb_json(spark: SparkSession, d: str) -> DataFrame:
    """Two versions of the knowledge base as JSON lines; the latest is read."""
    path = removed_at_exit(spark, f"{shared_dir(spark)}/kb-{uuid.uuid4().hex}")
    kb = _kb(spark, d)
    A.write_kb(kb.where("false"), path, 1)
    A.write_kb(kb, path, 2)
    return A.read_kb(spark, path).select("canonical", F.array_join("aliases", "|").alias("aliases"), F.array_join("sources", "|").alias("sources"))


@query("alias_lookup", _SOURCED + " select query, canonical, score, decision, len(aliases) as n_aliases from o left join acc using (canonical) where decision <> 'reject'")
def alias_lookup(spark: SparkSession, d: str) -> DataFrame:
    kb = materialize(_kb(spark, d), "kb")
    found = A.lookup(_variants(spark, d).select("query").distinct(), kb).where("decision <> 'reject'")
    return found.select("query", "canonical", "score", "decision", F.size("aliases").cast("long").alias("n_aliases"))


_TRUTH = "(select query, min(truth) as truth from v group by 1)"
_REVIEWED = f"{_RESOLVED}, dc as (select query, case when canonical = truth then 'accept' else 'reject' end as verdict from o join {_TRUTH} using (query) where decision = 'review'), ap as (select query, case when decision = 'review' then verdict else decision end as decision, case when decision = 'review' and verdict = 'reject' then null else canonical end as canonical from o left join dc using (query))"


def _decided(spark: SparkSession, d: str, resolved: DataFrame) -> DataFrame:
    """What an analyst who knows the truth decides on the queue."""
    truth = _variants(spark, d).groupBy("query").agg(F.min("truth").alias("truth"))
    return A.review_queue(resolved).join(truth, "query").select("query", F.when(F.col("canonical") == F.col("truth"), "accept").otherwise("reject").alias("verdict"))


@query("alias_review", f"{_REVIEWED} select decision, count(*) as n from ap group by 1")
def alias_review(spark: SparkSession, d: str) -> DataFrame:
    resolved = materialize(_resolved(spark, d), "resolved")
    return A.apply_decisions(resolved, _decided(spark, d, resolved)).groupBy("decision").agg(F.count(F.lit(1)).alias("n"))


@query("alias_change_rate", f"{_REVIEWED} select count(*) as n, count(*) filter (where o.canonical is distinct from ap.canonical) as changed, round(count(*) filter (where o.canonical is distinct from ap.canonical) / count(*), 6) as rate from o join ap using (query)")
def alias_change_rate(spark: SparkSession, d: str) -> DataFrame:
    resolved = materialize(_resolved(spark, d), "resolved")
    return A.change_rate(resolved, A.apply_decisions(resolved, _decided(spark, d, resolved)))


@query("alias_review_subset", f"{_RESOLVED}, rs as (select *, row_number() over (order by score, query) as p, count(*) over () as t from o where decision <> 'reject') select query, canonical, score from rs where p <= ceil(t * 0.15)")
def alias_review_subset(spark: SparkSession, d: str) -> DataFrame:
    return A.review_subset(_resolved(spark, d))


_RATED = f"{_RESOLVED}, it as (select query as item, case when canonical = truth then 'right' else 'wrong' end as verdict from o join {_TRUTH} using (query) where decision = 'review'), r as (select item, rater, case when substr(md5(concat(item, ':', rater)), 1, 1) = '0' then case verdict when 'right' then 'wrong' else 'right' end else verdict end as verdict from it, (select unnest([1, 2, 3]) as rater))"


@query("alias_reviewers", f"""{_RATED}, rb2 as (select a.rater as ra, c.rater as rb, a.verdict as va, c.verdict as vb from r a join r c on a.item = c.item and a.rater < c.rater), nn as (select ra, rb, count(*) as n, sum(case when va = vb then 1 else 0 end) as same from rb2 group by 1, 2),
    xa as (select ra, rb, va as v, count(*) as na from rb2 group by 1, 2, 3), yb as (select ra, rb, vb as v, count(*) as nb from rb2 group by 1, 2, 3), ec as (select ra, rb, sum(na * nb) as cr from xa join yb using (ra, rb, v) group by 1, 2)
    select ra, rb, n, round(same / n, 6) as agreement, round((same / n - cr / (n * n)) / nullif(1 - cr / (n * n), 0), 6) as kappa from nn join ec using (ra, rb)""")
def alias_reviewers(spark: SparkSession, d: str) -> DataFrame:
    """Kappa of three reviewers over the review band, who err where a hash says so."""
    resolved = materialize(_resolved(spark, d), "resolved")
    items = resolved.where("decision = 'review'").join(_variants(spark, d).groupBy("query").agg(F.min("truth").alias("truth")), "query")
    rated = items.select(F.col("query").alias("item"), F.when(F.col("canonical") == F.col("truth"), "right").otherwise("wrong").alias("v"), F.explode(F.array(*[F.lit(k) for k in (1, 2, 3)])).alias("rater"))
    flips = F.substring(F.md5(F.concat_ws(":", "item", "rater")), 1, 1) == "0"
    return S.cohen_kappa(rated.select("item", "rater", F.when(flips, F.when(F.col("v") == "right", "wrong").otherwise("right")).otherwise(F.col("v")).alias("verdict")))


_KINDS = sorted(KINDS)
_ROWS = f"ln as (select l_orderkey, ([{', '.join(repr(k) for k in _KINDS)}])[1 + l_orderkey % {len(_KINDS)}] as kind, n_name as truth from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey), nm as (select v.query as label from ln join v on v.kind = ln.kind and v.truth = ln.truth)"


@query("alias_consolidated", f"{_RESOLVED}, {_ROWS}, af as (select label, coalesce(canonical, label) as name from nm left join o on o.query = label) select count(*) as n, count(distinct label) as names_before, count(distinct name) as names_after, count(*) filter (where name <> label) as consolidated, round(count(*) filter (where name <> label) / count(*), 6) as share from af")
def alias_consolidated(spark: SparkSession, d: str) -> DataFrame:
    """Line items named by variants of their supplier's nation, before and after the labels are normalised."""
    rows = table(spark, d, "lineitem", "l_orderkey", "l_suppkey").join(table(spark, d, "supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    rows = rows.join(table(spark, d, "nation", "n_nationkey", "n_name"), F.col("s_nationkey") == F.col("n_nationkey"))
    rows = rows.select(F.get(F.array(*[F.lit(k) for k in _KINDS]), (F.col("l_orderkey") % len(_KINDS)).cast("int")).alias("kind"), F.col("n_name").alias("truth"))
    named = rows.join(_variants(spark, d), ["kind", "truth"]).select(F.col("query").alias("label"))
    done = A.normalize_labels(named, _resolved(spark, d), "label")
    moved = F.sum((F.col("label") != F.col("raw_label")).cast("int")).cast("long")
    return done.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("raw_label").alias("names_before"), F.count_distinct("label").alias("names_after"), moved.alias("consolidated"), F.round(moved / F.count(F.lit(1)), 6).alias("share"))


@query("alias_impact", _RESOLVED + " select count(distinct query) as names_before, count(distinct coalesce(canonical, query)) as names_after, cast(sum(case when canonical is not null and canonical <> query then 1 else 0 end) as bigint) as unified from o")
def alias_impact(spark: SparkSession, d: str) -> DataFrame:
    o = _resolved(spark, d)
    moved = F.coalesce((F.col("canonical") != F.col("query")).cast("int"), F.lit(0))
    return o.agg(F.count_distinct("query").alias("names_before"), F.count_distinct(F.coalesce("canonical", "query")).alias("names_after"), F.sum(moved).cast("long").alias("unified"))
