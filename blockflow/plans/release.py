"""The data set family: full, deduplicated and reuse files with a manifest, and the whole pipeline."""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from blockflow.operators import cleaning as C
from blockflow.operators import dedup, reuse
from blockflow.plans import graph
from blockflow.plans import graph_sql as G
from blockflow.plans.base import query
from blockflow.session import materialize, removed_at_exit, shared_dir
from blockflow.sources.tables import table


#: How files of a format are written and read; values may hold quotes, line ends and outer blanks, which CSV keeps by these.
_LINES = {"compression": "gzip"}
FORMATS = {
    "parquet": {"compression": "zstd"},
    "json": _LINES | {"ignoreNullFields": "false"},
    "csv": _LINES | {"header": "true", "escape": '"', "multiLine": "true", "lineSep": "\n", "ignoreLeadingWhiteSpace": "false", "ignoreTrailingWhiteSpace": "false"},
}


def read_file(spark: SparkSession, path: str, kind: str, like: DataFrame) -> DataFrame:
    """A release file with the columns of its frame. CSV tells an empty value, in quotes, from null, without, if no value equals the null mark."""
    known = {"nullValue": uuid.uuid4().hex} if kind == "csv" else {}
    return spark.read.schema(like.schema).format(kind).options(**FORMATS[kind], **known).load(path).select(like.columns)


def _nested(df: DataFrame) -> set[str]:
    return {c for c, kind in df.dtypes if kind.startswith(("array", "map", "struct"))}


def _content(df: DataFrame, key: str | None = None) -> Row:
    """n_rows, and the sum of the rows' hashes over all values; a folder's name, the key, can't tell empty from null."""
    values = [F.to_json(c) if c in _nested(df) else F.nullif(F.col(c).cast("string"), F.lit("")) if c == key else F.col(c) for c in df.columns]
    hashed = F.xxhash64(*[x for v in values for x in (v, v.isNull())])
    return df.agg(F.count(F.lit(1)).alias("n_rows"), F.sum(hashed.cast("decimal(20,0)")).alias("hashes")).first()


def write_release(spark: SparkSession, path: str, frames: dict[str, DataFrame], partition_by: dict[str, str] | None = None) -> DataFrame:
    """Write each frame as Parquet (partitioned where asked), JSON Lines and CSV; the manifest is read back from the files.

    All values of a file are read back and must be those of its frame. CSV has no arrays, so frames with any are left out there.
    """
    rows = []
    for name, df in frames.items():
        place = (partition_by or {}).get(name)
        want = {key: _content(df, key) for key in {place, None}}
        for kind in ("parquet", "json", *([] if _nested(df) else ["csv"])):
            key = place if kind == "parquet" else None
            writer = df.write.mode("errorifexists").format(kind).options(**FORMATS[kind])
            (writer.partitionBy(key) if key else writer).save(f"{path}/{name}.{kind}")
            back = read_file(spark, f"{path}/{name}.{kind}", kind, df)
            found = _content(back, key)
            if found != want[key]:
                raise RuntimeError(f"{name}.{kind} holds {found}, its frame {want[key]}")
            rows.append((name, kind, len(back.columns), found.n_rows))
    manifest = materialize(spark.createDataFrame(rows, "name string, format string, n_columns int, n_rows bigint"), "manifest")
    manifest.coalesce(1).write.json(f"{path}/manifest.json")
    return manifest


def build_corpus(spark: SparkSession, d: str) -> dict[str, DataFrame]:
    """The six stages in order, each a written table: collected, labelled, cleaned, deduplicated, checked, clustered."""
    docs = C.integrity(table(spark, d, "documents", "doc_id", "text", "lang", "source", "n_chars")).withColumnRenamed("source", "grp")
    collected = materialize(docs, "collected")
    labels = C.resolve_labels(collected.where("text is not null").select("digest", "grp"))
    labelled = materialize(collected.join(labels.select("digest", "resolved", "action"), "digest", "left"), "labelled")
    cleaned = materialize(C.collapse_exact(labelled.where("reason is null and action <> 'unknown'").select("digest", "doc_id", "text", "lang", "grp", "resolved"), "digest", "doc_id"), "cleaned")
    flows = graph.doc_flows(spark, d)
    roots = graph._doc_roots(spark, d, flows)
    order = cleaned.select(F.col("doc_id").alias("id"), F.col("doc_id").alias("first_seen"), "digest")
    kept = dedup.keep_representatives(roots.join(order.select("id"), "id", "left_semi"), order)
    deduplicated = materialize(cleaned.join(kept.where("not kept").select(F.col("id").alias("doc_id")), "doc_id", "left_anti"), "deduplicated")
    checked = materialize(deduplicated.join(table(spark, d, "labels"), "doc_id", "left"), "checked")
    members = graph.line_members(spark, d, flows=flows).join(checked.select(F.col("doc_id").alias("sample_id")), "sample_id", "left_semi")
    clustered = materialize(reuse.clusters(members), "clustered")
    return {"collected": collected, "labelled": labelled, "cleaned": cleaned, "deduplicated": deduplicated, "checked": checked, "clustered": clustered}


_CLEANED = "i as (select *, md5(text) as digest from documents where text is not null and text <> '' and n_chars = length(text)), r as (select digest, count(*) as k, max(n) as most, sum(n) as t, 1 - sum(n * n) / (sum(n) * sum(n)) as impurity, count(*) filter (where n = m) as ties from (select *, max(n) over (partition by digest) as m from (select md5(text) as digest, source, count(*) as n from documents where text is not null group by 1, 2)) group by 1), cl as (select digest, min(doc_id) as doc_id from i join r using (digest) where k = 1 or (round(impurity, 6) <= 0.2 and ties = 1) group by 1)"
_CORPUS = f"with recursive {G.DOC_BLOCKS}, {G.FLOW}, {G.sample_roots(G.DOC_CALLS)}, {_CLEANED}, dd as (select doc_id from cl where doc_id not in (select id from (select rt.id, row_number() over (partition by root order by id) as p from rt join cl on cl.doc_id = rt.id) where p > 1)), {G.members(tag='_f')}"


@query("build_corpus", f"{_CORPUS} select 'collected' as stage, count(*) as n from documents union all select 'labelled', count(*) from documents union all select 'cleaned', count(*) from cl union all select 'deduplicated', count(*) from dd union all select 'checked', count(*) from dd left join labels using (doc_id) union all select 'clustered', count(*) from (select root from members_f where sample_id in (select doc_id from dd) group by 1 having count(distinct grp) >= 2)")
def corpus_stages(spark: SparkSession, d: str) -> DataFrame:
    return reduce(DataFrame.union, [df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(k).alias("stage"), "n") for k, df in build_corpus(spark, d).items()])


_FULL = "select 'full' as name, count(*) as n, 5 as c from documents"
_MANIFEST = f"{graph._KEPT_SQL}, fam as ({_FULL} union all select 'deduplicated', count(*), 5 from documents where doc_id not in (select id from od where not kept)), {G.members(tag='_f')}, ru as (select 'reuse' as name, count(*) as n, 4 as c from (select root from members_f group by 1 having count(distinct grp) >= 2))"


@query("release_manifest", f"{_MANIFEST} select name, format, cast(c as int) as n_columns, n as n_rows from (select * from fam union all select * from ru), (select unnest(['parquet', 'json', 'csv']) as format)")
def release_manifest(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents", "doc_id", "text", "lang", "source", "n_chars")
    flows = graph.doc_flows(spark, d)
    kept = materialize(docs.join(graph._doc_kept(spark, d, flows).where("not kept").select(F.col("id").alias("doc_id")), "doc_id", "left_anti"), "deduplicated")
    frames = {"full": docs, "deduplicated": kept, "reuse": materialize(reuse.clusters(graph.line_members(spark, d, flows=flows)), "reuse")}
    path = removed_at_exit(spark, f"{shared_dir(spark)}/release-{uuid.uuid4().hex}")
    return write_release(spark, path, frames, {"full": "source", "deduplicated": "source"})
