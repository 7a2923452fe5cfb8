"""The thin registered queries of the training-data operators, and their DuckDB oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.session import materialize
from blockflow.llm import htmltext, mixing, toxicity
from blockflow.llm.fingerprints import fingerprint_pairs
from blockflow.llm.huffman import read_shards, write_shards
from blockflow.llm.licenses import license_report
from blockflow.llm.neardup import near_duplicates
from blockflow.llm.packing import pack_documents
from blockflow.llm.quality import quality_verdicts
from blockflow.llm.substrings import remove_repeats
from blockflow.llm.tables import table

QUERIES: dict = {}
ORACLES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


@query
def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return quality_verdicts(docs, lambda df: materialize(df, "quality"))


@query
def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return license_report(docs).drop("spans")


@query
def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))


@query
def op2_repeated_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents", "doc_id", "text"))


def _tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@query
def op5_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return read_shards(*write_shards(docs, _tokenizer("word_bpe_49k.json"), end_id=2))


@query
def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return pack_documents(docs, _tokenizer("byte_bpe_50k.json"), end_id=1)


@query
def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    labels = table(spark, sf_dir, "labels", "doc_id", "toxic").where(~toxicity.held_out(F.col("doc_id")))
    scored = toxicity.score(docs, toxicity.fit(docs, labels))
    return scored.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= 0.5).cast("int").alias("predicted"))


@query
def op4_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint_pairs(table(spark, sf_dir, "documents", "doc_id", "text"))


@query
def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    labels = table(spark, sf_dir, "labels", "doc_id", "quality", "toxic")
    rated, model, targets = mixing.mix(docs, labels)
    shares = [F.round(F.get("p", F.lit(d)), 9).alias(f"p_{name}") for d, name in enumerate(model.domains)]
    return rated.select("doc_id", "n_tokens", *shares, F.round("rate", 9).alias("rate"), mixing.copies(F.col("rate"), F.col("doc_id")).alias("copies"))


@query
def op8_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "page_id", "url", "html")
    return htmltext.extract(pages).withColumnsRenamed({"main_text": "text", "main_chars": "n_chars"})


@query
def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


#: Sets of five-word shingles, all pairs that share one, and the components of the links.
ORACLES["op1_near_duplicates"] = r"""with recursive w as (select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents),
    s as (select doc_id, list_distinct(case when len(w) = 0 then cast([] as varchar[]) when len(w) < 5 then [array_to_string(w, ' ')] else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end) as s from w),
    z as materialized (select doc_id, hash(unnest(s)) as g from s), n as (select doc_id, len(s) as n from s),
    c as (select a.doc_id as a, b.doc_id as b, count(*) as k from z a join z b using (g) where a.doc_id < b.doc_id group by 1, 2),
    l as materialized (select a, b from c join n x on x.doc_id = a join n y on y.doc_id = b where 100 * k >= 85 * (x.n + y.n - k)), e as (select a, b from l union select b, a from l),
    reach(node, root) as (select a, a from e union select e.b, r.root from reach r join e on e.a = r.node), roots as (select node, min(root) as root from reach group by 1)
    select doc_id, n as n_shingles, coalesce(root, doc_id) as component_id, doc_id = coalesce(root, doc_id) as kept from n left join roots on node = doc_id"""

#: Every 100-byte window of every text, which of them starts earlier elsewhere, and what the others leave.
ORACLES["op2_repeated_substrings"] = """with h as (select doc_id, hex(encode(coalesce(text, ''))) as h, octet_length(encode(coalesce(text, ''))) as n from documents),
    w as (select doc_id, i, hash(substr(h, 2 * i + 1, 200)) as g, row_number() over () as r from (select *, unnest(range(0, n - 99)) as i from h)),
    f as (select doc_id, i, min((doc_id, i)) over (partition by g) as f from w), a as (select doc_id, i from f where f <> (doc_id, i)),
    b as (select *, case when i <= lag(i) over (partition by doc_id order by i) + 100 then 0 else 1 end as nw from a), c as (select *, sum(nw) over (partition by doc_id order by i) as run from b),
    runs as (select doc_id, run, min(i) as lo, max(i) + 100 as hi from c group by 1, 2),
    cut as (select doc_id, coalesce(lag(hi) over (partition by doc_id order by lo), 0) as lo, lo as hi from runs union all select h.doc_id, coalesce(max(hi), 0), max(n) from h left join runs using (doc_id) group by 1),
    kept as (select doc_id, string_agg(substr(h, 2 * lo + 1, 2 * (hi - lo)), '' order by lo) as k from cut join h using (doc_id) group by 1),
    t as (select doc_id, cast(sum(hi - lo) as bigint) as removed, count(*) as spans from runs group by 1)
    select doc_id, n as n_bytes, coalesce(removed, 0) as n_removed, coalesce(spans, 0) as n_spans, sha256(unhex(k)) as kept_sha256 from h join kept using (doc_id) left join t using (doc_id)"""


def _pipeline_oracle() -> None:
    import corpus_pipeline

    if corpus_pipeline.ORACLE_SQL is not None:
        ORACLES["pipeline"] = corpus_pipeline.ORACLE_SQL


_pipeline_oracle()
