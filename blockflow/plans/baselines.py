"""Fuzzy-hash baselines, brute force, and approximate search against it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.operators import baselines as B
from blockflow.operators import similarity
from blockflow.plans.base import query
from blockflow.plans.graph import _embedded
from blockflow.session import materialize
from blockflow.sources.tables import table

_DIGIT = "(instr('0123456789abcdef', substr({h}, {k}, 1)) - 1) * {w}"


def _code(x: str, n: int) -> str:
    return "(" + " + ".join(_DIGIT.format(h=f"md5({x})", k=k, w=16 ** (8 - k)) for k in range(1, 9)) + f") % {n}"


def _signatures(source: str, key: str) -> str:
    return f"""tk as (select {key} as id, list_filter(string_split_regex(text, '\\s+'), lambda t: t <> '') as t from {source} where text is not null),
    wd as (select id, i, t[i] as w, {_code('t[i]', 16)} = 0 as stop from (select *, unnest(range(1, len(t) + 1)) as i from tk)),
    ck as (select id, i, w, coalesce(sum(case when stop then 1 else 0 end) over (partition by id order by i rows between unbounded preceding and 1 preceding), 0) as c from wd),
    jn as (select id, c, (case when c > 0 then ' ' else '' end) || string_agg(w, ' ' order by i) as s from ck group by 1, 2),
    sg as (select tk.id, coalesce(string_agg(substr('{B.ALPHABET}', cast({_code('s', 64)} + 1 as int), 1), '' order by c), '') as signature from tk left join jn using (id) group by 1),
    hs as (select signature, min(id) as id from sg group by 1)"""


_SCORE = "round(100 * (1 - levenshtein(a.signature, b.signature) / greatest(length(a.signature), length(b.signature))), 6)"
_PAIRS = f"select a.id as id_a, b.id as id_b, {_SCORE} as score from hs a join hs b on a.id < b.id and {{extra}} least(length(a.signature), length(b.signature)) * 100 >= 80 * greatest(length(a.signature), length(b.signature)) where {_SCORE} >= 80"
_GRAMS = "gr as (select distinct id, substr(signature, i, 7) as g from (select *, unnest(range(1, length(signature) - 5)) as i from hs where length(signature) >= 7)), sm as (select distinct x.id as p, y.id as q from gr x join gr y using (g) where x.id < y.id)"


@query("fuzzy_hash_signatures", f"with {_signatures('documents', 'doc_id')} select id, signature from sg")
def fuzzy_hash_signatures(spark: SparkSession, d: str) -> DataFrame:
    return B.fuzzy_hash(table(spark, d, "documents", "doc_id", "text").withColumnRenamed("doc_id", "id"))


@query("fuzzy_hash_pairs", f"with {_signatures('documents', 'doc_id')}, {_GRAMS} {_PAIRS.format(extra='(a.id, b.id) in (select (p, q) from sm) and')}")
def fuzzy_hash_pairs(spark: SparkSession, d: str) -> DataFrame:
    return B.fuzzy_pairs(materialize(fuzzy_hash_signatures(spark, d), "signatures"))


@query("fuzzy_hash_all", f"with {_signatures('benchmark', 'item_id')} {_PAIRS.format(extra='')}")
def fuzzy_hash_all(spark: SparkSession, d: str) -> DataFrame:
    """Every pair of the benchmark's passages, as the baseline has it."""
    hashed = B.fuzzy_hash(table(spark, d, "benchmark", "item_id", "text").withColumnRenamed("item_id", "id"))
    return B.fuzzy_pairs(materialize(hashed, "signatures"), every="all")


_VECTORS = "ev as (select vec_id as id, list_transform(embedding, lambda x: cast(x as double)) as c from embeddings), ee as (select * from ev union all select id + 1000000, list_concat([c[1] + 0.001], c[2:]) from ev where id % 10 = 0)"


@query("brute_pairs", f"with {_VECTORS} select a.id as id_a, b.id as id_b, round(list_dot_product(a.c, b.c) / (sqrt(list_dot_product(a.c, a.c)) * sqrt(list_dot_product(b.c, b.c))), 6) as s from ee a join ee b on a.id < b.id where round(least(1, list_dot_product(a.c, b.c) / (sqrt(list_dot_product(a.c, a.c)) * sqrt(list_dot_product(b.c, b.c)))), 10) >= 0.3")
def brute_pairs(spark: SparkSession, d: str) -> DataFrame:
    return similarity.brute(_embedded(spark, d), "cls", least=0.3).select("id_a", "id_b", F.round("s", 6).alias("s"))


@query("ann_recall")
def ann_recall(spark: SparkSession, d: str) -> DataFrame:
    """Recall of the ten nearest by inverted lists, against all vectors, over every query vector with an id divisible by 50."""
    v = materialize(_embedded(spark, d), "vectors")
    queries = v.where("id % 50 = 0")
    near = similarity.nearest(v, queries, 10).select("query", "id")
    true = materialize(similarity.nearest(v, queries, 10, probes=None).select("query", "id"), "true")
    hit = true.join(near, ["query", "id"], "left_semi").agg(F.count(F.lit(1)).alias("hits"))
    return true.agg(F.count(F.lit(1)).alias("wanted")).crossJoin(F.broadcast(hit)).withColumn("recall", F.round(F.col("hits") / F.col("wanted"), 6))


@query("exact_neighbours", f"with {_VECTORS}, sc as (select a.id as query, b.id, round(least(1, list_dot_product(a.c, b.c) / (sqrt(list_dot_product(a.c, a.c)) * sqrt(list_dot_product(b.c, b.c)))), 10) as s from ee a join ee b on a.id <> b.id where a.id % 50 = 0), r as (select *, row_number() over (partition by query order by s desc, id) as place from sc) select query, id, cast(place as int) as place from r where place <= 10")
def exact_neighbours(spark: SparkSession, d: str) -> DataFrame:
    v = materialize(_embedded(spark, d), "vectors")
    return similarity.nearest(v, v.where("id % 50 = 0"), 10, probes=None).select("query", "id", "place")
