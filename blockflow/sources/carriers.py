"""Carriers: how a table's rows become samples, functions, blocks and call edges.

A function frame has sample_id, func_id, grp and blocks, an array of (n, a, b, cls): instruction count, forward key, back
key, counts of the nine classes. Block ids are array places from 0.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.functions.taxonomy import TokenClasses
from blockflow.sources.tables import spread, table


_PARTS, _TOKENS = re.compile("[.!?,;]+"), re.compile("[^ \t\n\x0b\f\r]+")
_BLOCKS = "array<struct<n: bigint, a: string, b: string, cls: array<bigint>>>"


def _block_kernel(line: str, names: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        classes = TokenClasses()
        for batch in batches:
            n, first, last, kinds, at = [], [], [], [], [0]
            known = batch.column(line)
            for text in known.cast(pa.binary()).to_pylist():
                for part in _PARTS.split((text or b"").decode("utf-8", "replace")):
                    part = part.strip(" ")
                    if part:
                        tokens = _TOKENS.findall(part)
                        kinds.extend(map(classes.__getitem__, tokens))
                        n.append(len(tokens))
                        first.append(part[0].lower())
                        last.append(part[-1].lower())
                at.append(len(n))
            place = np.repeat(np.arange(len(n)), n) * 9 + np.array(kinds, np.int64) - 1
            counts = pa.array(np.bincount(place, minlength=len(n) * 9).astype(np.int64))
            cls = pa.ListArray.from_arrays(pa.array(np.arange(0, len(n) * 9 + 1, 9, dtype=np.int32)), counts)
            made = pa.StructArray.from_arrays([pa.array(n, pa.int64()), pa.array(first, pa.string()), pa.array(last, pa.string()), cls], ["n", "a", "b", "cls"])
            blocks = pa.ListArray.from_arrays(pa.array(at, pa.int32()), made, mask=known.is_null() if known.null_count else None)
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in names], blocks], names=[*names, "blocks"])

    return run


def _sentence_blocks(df: DataFrame, line: str) -> DataFrame:
    """Add `blocks` for a text column: clauses as blocks, tokens as instructions.

    An Arrow kernel does this, as it classes a token once where expressions test each of its occurrences.
    """
    kinds = ", ".join([*[f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema], f"blocks {_BLOCKS}"])
    return df.mapInArrow(_block_kernel(line, df.columns), kinds)


def document_lines(docs: DataFrame) -> DataFrame:
    """sample_id, grp, func_id, line: the non-empty trimmed lines, numbered from 0."""
    lines = F.expr("filter(transform(split(text, '\\n'), x -> trim(x)), x -> x <> '')")
    return docs.select(F.col("doc_id").alias("sample_id"), F.col("source").alias("grp"), F.posexplode(lines).alias("func_id", "line"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C1: lines of documents; one row stays one map-side row, so no shuffle."""
    return lines_of(spread(table(spark, sf_dir, "documents", "doc_id", "source", "text")))


def lines_of(docs: DataFrame) -> DataFrame:
    """The function frame of any texts: doc_id, source, text."""
    return _sentence_blocks(document_lines(docs), "line").select("sample_id", "func_id", "grp", "blocks", F.md5("line").alias("func_digest"))


def document_calls(docs: DataFrame) -> DataFrame:
    """C1 call edges: to the next line, and to the next line with the same first letter."""
    lines = F.expr("filter(transform(split(text, '\\n'), x -> trim(x)), x -> x <> '')")
    lead = docs.select(F.col("doc_id").alias("sample_id"), F.transform(lines, lambda x: F.lower(F.substring(x, 1, 1))).alias("cf_l"))
    # equal letters stand next to each other once sorted by (letter, place)
    lead = lead.withColumn("cf_s", F.expr("sort_array(transform(cf_l, (l, i) -> named_struct('key', l, 'i', i)))"))
    step = "transform(cf_l, (l, i) -> if(i + 1 < size(cf_l), named_struct('caller', i, 'callee', i + 1), null))"
    again = "transform(cf_s, (x, k) -> if(get(cf_s, k + 1).key <=> x.key and get(cf_s, k + 1).i > x.i + 1, named_struct('caller', x.i, 'callee', get(cf_s, k + 1).i), null))"
    return lead.select("sample_id", F.inline(F.expr(f"filter(concat({step}, {again}), e -> e is not null)")))


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C2: orders of customers; line items are blocks."""
    item = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_returnflag", "l_linestatus", "l_shipdate")
    part = table(spark, sf_dir, "part", "p_partkey", "p_type")
    order = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    customer = table(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    nation = table(spark, sf_dir, "nation", "n_nationkey", "n_name")
    # part types are few whatever the scale; their ranks are the classes 1 to 6
    types = part.select("p_type").distinct().withColumn("k", F.expr("row_number() over (order by p_type)"))
    typed = part.join(F.broadcast(types), "p_type").select(F.col("p_partkey").alias("l_partkey"), "k")
    flag = F.when(F.col("l_returnflag") == "A", 7).when(F.col("l_returnflag") == "N", 8).otherwise(9)
    n = F.col("l_quantity").cast("long")
    cls = F.transform(F.sequence(F.lit(1), F.lit(9)), lambda k: F.when(k == F.col("k"), n).when(k == flag, F.lit(1).cast("long")).otherwise(F.lit(0).cast("long")))
    block = F.struct("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate", n.alias("n"), F.col("l_returnflag").alias("a"), F.col("l_linestatus").alias("b"), cls.alias("cls"))
    blocks = item.join(typed, "l_partkey").groupBy("l_orderkey").agg(F.array_sort(F.collect_list(block)).alias("blocks"))
    owner = order.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    picked = F.transform("blocks", lambda x: F.struct(x["n"].alias("n"), x["a"].alias("a"), x["b"].alias("b"), x["cls"].alias("cls")))
    return blocks.join(owner, F.col("l_orderkey") == F.col("o_orderkey")).select(
        F.col("o_custkey").alias("sample_id"), F.col("o_orderkey").alias("func_id"), F.col("n_name").alias("grp"), picked.alias("blocks"), F.md5(F.to_json(picked)).alias("func_digest")
    )


def order_calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C2 call edges: to the customer's next order, and to the next one of the same priority."""
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    both = o.selectExpr(
        "o_custkey as sample_id", "o_orderkey as caller",
        "array(lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey), lead(o_orderkey) over (partition by o_custkey, o_orderpriority order by o_orderdate, o_orderkey)) as next",
    )
    return both.select("sample_id", "caller", F.explode(F.array_distinct(F.array_compact("next"))).alias("callee"))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C4: turns of conversations; the group is the role of the turn."""
    t = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text").where("text is not null")
    return _sentence_blocks(t.select(F.col("conv_id").alias("sample_id"), F.col("turn").cast("int").alias("func_id"), F.col("role").alias("grp"), "text"), "text").select("sample_id", "func_id", "grp", "blocks", F.md5("text").alias("func_digest"))


def page_sections(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C3: sections of pages that begin at nav, article, p, ul, table or h1; each opening tag in one is a block."""
    p = table(spark, sf_dir, "pages", "page_id", "url", "html").where("html is not null")
    host = F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)
    cut = F.expr("split(html, '(?=<(?:nav|article|p|ul|table|h1)[ >])')")
    sections = p.select(F.col("page_id").alias("sample_id"), host.alias("grp"), F.posexplode(cut).alias("func_id", "body")).where("func_id > 0")
    tags = F.expr("regexp_extract_all(body, '<([a-z][a-z0-9]*)([^>]*)>([^<]*)', 0)")
    made = sections.withColumn("cf_t", tags).where("size(cf_t) > 0")
    name, attrs, words = "regexp_extract(x, '^<([a-z0-9]+)', 1)", "size(regexp_extract_all(x, '[a-z-]+=', 0))", "size(filter(split(regexp_replace(x, '^<[^>]*>', ''), '\\\\s+'), t -> t <> ''))"
    kinds = "case when {n} in ('p','article','h1') then 1 when {n} in ('ul','li') then 2 when {n} in ('nav','footer') then 3 when {n} in ('b','i','em','strong') then 4 when {n} = 'a' then 5 when {n} in ('div','span') then 6 when {n} in ('table','tr','td','th') then 7 when {n} in ('meta','link','script','style','head') then 8 else 9 end".format(n=name)
    block = f"named_struct('n', cast({attrs} + 1 + {words} as bigint), 'a', {name}, 'b', {name}, 'cls', transform(sequence(1, 9), k -> cast(if({kinds} = k, 1, 0) as bigint)))"
    return made.select("sample_id", "func_id", "grp", F.expr(f"transform(cf_t, x -> {block})").alias("blocks"), F.md5("body").alias("func_digest"))


def sessions(spark: SparkSession, sf_dir: str, gap_hours: int = 12) -> DataFrame:
    """C5: sessions of users; each event is a block."""
    e = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "props").where("user_id is not null")
    new = f"case when ts > lag(ts) over (partition by user_id order by ts, event_id) + interval {gap_hours} hours then 1 else 0 end"
    e = e.withColumn("cf_new", F.expr(new)).withColumn("func_id", F.expr("cast(sum(cf_new) over (partition by user_id order by ts, event_id) as int)"))
    # event types are few whatever the scale
    types = e.select("event_type").distinct().withColumn("k", F.expr("row_number() over (order by event_type)"))
    e = e.join(F.broadcast(types), "event_type")
    n = F.expr("1 + cast(get_json_object(props, '$.k') as bigint) % 8")
    cls = F.transform(F.sequence(F.lit(1), F.lit(9)), lambda k: F.when(k == F.col("k"), n).otherwise(F.lit(0).cast("long")))
    block = F.struct("ts", "event_id", F.coalesce(n, F.lit(1)).alias("n"), F.col("event_type").alias("a"), (F.hour("ts") % 2).cast("string").alias("b"), cls.alias("cls"))
    made = e.groupBy("user_id", "func_id").agg(F.array_sort(F.collect_list(block)).alias("blocks"), F.mode("event_type", True).alias("grp"))
    picked = F.transform("blocks", lambda x: F.struct(x["n"].alias("n"), x["a"].alias("a"), x["b"].alias("b"), x["cls"].alias("cls")))
    return made.select(F.col("user_id").alias("sample_id"), "func_id", "grp", picked.alias("blocks"), F.md5(F.to_json(picked)).alias("func_digest"))
